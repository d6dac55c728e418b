"""Near-duplicate groups from SetSketch registers, bands, a joint likelihood and exact verification.

Every document's distinct word shingles are sketched: register i is the exponentially spaced, truncated level of the
smallest of the shingles' exponential values under hash i. Such registers merge by taking the larger level and agree in a
share that follows the Jaccard similarity. `bands` groups of `rows` registers are keys; two documents at similarity 0.85 share
at least one of 30 keys of 7 registers with probability 1 - 1e-5. Then:

1. Documents with equal shingle sets form classes; one representative of each goes on, so copies cost nothing more.
2. In every bucket (band, key) of up to 32 members each one is paired with the bucket's smallest member only, not with all others;
   larger buckets go to step 4 at once.
3. The joint maximum likelihood of both sketches, given both set sizes, estimates the similarity; pairs far below the threshold
   go no further. The others are confirmed on their full shingle sets.
4. Confirmed links join representatives into components. Buckets that hold several components still (a passage that many documents
   share, or many copies of one text, each edited in places of its own) are refined: their members form clusters, each with a core
   of shingles that most members hold, and a member is told by its residual, what it has beyond the core and what of the core it
   lacks. Differences of residuals are differences of sets, so the members near the core link with the one nearest to it, and for the
   others the shared part of the residuals, which is small, decides: those without enough of it have no partner at all, the rest
   meet in bands of minima over it (missed with probability 1e-5 again), or under an exact prefix of its rarest elements where
   little need be shared. Pairs across components are enumerated in these finer buckets only.

On n copies of a 400-word text with six edits each, none of them linked, that makes about 10 n pairs, not n^2 / 2.

Edge cases: null or empty texts and texts without words have an empty set, are linked with nothing and stay; a text with fewer
words than a shingle has its whole sequence as one shingle; rows without an id are reported under null, with the component of a
document of the same set; rows that repeat an id are one document, which has the links of all its texts; extra columns are
ignored, whatever their names; an empty table gives no rows; texts are read whole, whatever their length.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh_names, shared_table, without

BASE, LEVELS = 1.001, 65534
#: Buckets of more members are refined at once: a pivot that is one copy among many settles little, their common core settles most.
STAR_MEMBERS = 32
SKETCH = "doc_id long, n_shingles long, set_a long, set_b long, registers binary, keys array<long>"
SETS = "n_shingles long, set_a long, set_b long, shingles array<long>"


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer: every bit of the result depends on every bit of x."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= 400_000:
            self.clear()
        found = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 64:
            self[word] = found
        return found


WORDS = WordHashes()


def shingle_set(data: bytes | None, width: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word shingles; A-Z lower-cased, words parted by ASCII white space."""
    words = (data or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    hashes = np.fromiter(map(WORDS.__getitem__, words), np.uint64, len(words))
    factors = mixed(np.arange(1, max(width, len(words) if len(words) < width else 0) + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
    n = max(1, len(words) - width + 1)
    total = np.full(n, min(len(words), width), np.uint64)
    for k in range(min(width, len(words))):
        total = total + mixed(hashes[k : k + n]) * factors[k]
    return np.unique(mixed(total))


def set_sums(shingles: np.ndarray) -> tuple[int, int]:
    """Two checksums of a set."""
    return tuple(int(x) for x in np.array([shingles.sum(), mixed(shingles + np.uint64(0x9E3779B97F4A7C15)).sum()], np.uint64).view(np.int64))


class Sketcher:
    """registers(set) -> uint16 levels, keys(levels) -> one 64-bit key per band."""

    def __init__(self, bands: int, rows: int, seed: int = 7):
        draw = np.random.default_rng(seed)
        self.bands, self.rows, m = bands, rows, bands * rows
        self.factors = draw.integers(0, 1 << 32, m, dtype=np.uint64).astype(np.uint32)[:, None] | np.uint32(1)
        self.offsets = draw.integers(0, 1 << 32, m, dtype=np.uint64).astype(np.uint32)[:, None]
        self.mixers = draw.integers(1, 1 << 63, m, dtype=np.uint64).reshape(bands, rows) | np.uint64(1)
        self.salts = draw.integers(1, 1 << 63, bands, dtype=np.uint64)

    def registers(self, shingles: np.ndarray) -> np.ndarray:
        short = (shingles >> np.uint64(32)).astype(np.uint32)
        least = np.full(len(self.factors), 0xFFFFFFFF, np.uint32)
        for at in range(0, len(short), 512):
            part = short[None, at : at + 512] * self.factors
            part += self.offsets
            np.minimum(least, part.min(axis=1), out=least)
        value = -np.log1p(-(least.astype(np.float64) + 0.5) / 2.0**32)
        # Levels fall as the minimum grows; 2^20 as the rate keeps sets of any size within the levels.
        return np.clip(np.floor(1 - np.log(value * 2.0**20) / np.log(BASE)) + LEVELS // 2, 0, LEVELS + 1).astype(np.uint16)

    def keys(self, levels: np.ndarray) -> np.ndarray:
        return mixed((levels.reshape(self.bands, self.rows).astype(np.uint64) * self.mixers).sum(axis=1) + self.salts).view(np.int64)


def sketches(docs: DataFrame, bands: int, rows: int, width: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: set size, two checksums of the set, registers and band keys (none for an empty set)."""

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Sketcher(bands, rows)
        for batch in batches:
            out: list[tuple] = []
            for text in batch.column(1):
                found = shingle_set(text.as_py(), width)
                if len(found):
                    levels = own.registers(found)
                    out.append((len(found), *set_sums(found), levels.tobytes(), own.keys(levels)))
                else:
                    out.append((0, 0, 0, None, np.empty(0, np.int64)))
            keys = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *(len(r[4]) for r in out)]), pa.int32()), pa.array(np.concatenate([np.empty(0, np.int64), *(r[4] for r in out)])))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array([r[j] for r in out], pa.int64()) for j in range(3)), pa.array([r[3] for r in out], pa.binary()), keys], [x.split()[0] for x in SKETCH.split(", ")])

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))
    return narrow.mapInArrow(sketch, SKETCH)


def joint_similarity(a: np.ndarray, b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray, grid: int = 101) -> np.ndarray:
    """Maximum likelihood of the Jaccard similarity from registers (rows of levels) and set sizes."""
    above, below = (a > b).sum(axis=1)[:, None], (a < b).sum(axis=1)[:, None]
    equal = a.shape[1] - above - below
    u, v = (n_a / (n_a + n_b))[:, None], (n_b / (n_a + n_b))[:, None]
    most = np.minimum(u / v, v / u)
    j = most * np.linspace(0, 1, grid)[None, :] * (1 - 1e-9)
    p = lambda x: -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE)
    up, down = p(u - v * j), p(v - u * j)
    with np.errstate(divide="ignore", invalid="ignore"):
        part = lambda n, q: np.where(n > 0, n * np.log(np.maximum(q, 1e-300)), 0.0)
        fit = part(above, up) + part(below, down) + part(equal, 1 - up - down)
    return np.take_along_axis(j, fit.argmax(axis=1)[:, None], axis=1)[:, 0]


def estimate_pairs(pairs: DataFrame) -> DataFrame:
    """a, b, n_a, n_b, reg_a, reg_b -> a, b, n_a, n_b, estimate."""

    def estimate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            regs = [np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint16).reshape(batch.num_rows, -1) for i in (4, 5)]
            sizes = [batch.column(i).to_numpy().astype(float) for i in (2, 3)]
            found = np.concatenate([joint_similarity(*(x[i : i + 2048] for x in (*regs, *sizes))) for i in range(0, batch.num_rows, 2048)])
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(found, pa.float64())], ["a", "b", "n_a", "n_b", "estimate"])

    return pairs.select("a", "b", "n_a", "n_b", "reg_a", "reg_b").mapInArrow(estimate, "a long, b long, n_a long, n_b long, estimate double")


def estimated(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """Pairs whose sizes allow the similarity, with the estimate from their registers."""
    side = lambda c: reps.select(F.col("node").alias(c), F.col("n_shingles").alias(f"n_{c}"), F.col("registers").alias(f"reg_{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b")
    return estimate_pairs(both.filter(F.least("n_a", "n_b") * 100 >= F.greatest("n_a", "n_b") * percent))


def shingle_sets(docs: DataFrame, wanted: DataFrame, width: int, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 1_000_000) -> DataFrame:
    """node and full shingle set of the wanted classes (node, doc_id of a member). Texts are shuffled only if the ids are too many to broadcast."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                sets = [shingle_set(text.as_py(), width) for text in batch.column(0).slice(at, 256)]
                sums = np.array([set_sums(own) for own in sets], np.int64).reshape(-1, 2)
                flat = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, sets)]), pa.int32()), pa.array(np.concatenate([np.empty(0, np.uint64), *sets]).view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(list(map(len, sets)), pa.int64()), pa.array(sums[:, 0]), pa.array(sums[:, 1]), flat], [x.split()[0] for x in SETS.split(", ")])

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))
    ids, nodes = wanted.select("doc_id").distinct(), wanted.select("node")
    few = ids.limit(broadcast_rows + 1).count() <= broadcast_rows
    made = narrow.join(F.broadcast(ids) if few else ids, "doc_id", "left_semi").select("text").mapInArrow(build, SETS)
    made = made.select(F.xxhash64("n_shingles", "set_a", "set_b").alias("node"), "shingles").dropDuplicates(["node"])
    return made.join(F.broadcast(nodes) if few else nodes, "node", "left_semi")


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """a, b, n_a, n_b, common: the exact size of the intersection."""
    side = lambda c: sets.select(F.col("node").alias(c), F.col("shingles").alias(f"set_{c}"))
    both = pairs.select("a", "b", "n_a", "n_b").join(side("b"), "b").join(side("a"), "a")
    return both.select("a", "b", "n_a", "n_b", F.size(F.array_intersect("set_a", "set_b")).cast("long").alias("common"))


def core_of(rows: DataFrame, voters: int) -> DataFrame:
    """cluster, core: the shingles that more than half of at most about `voters` members hold. Any core is right; one that most members share is fast."""
    sizes = rows.groupBy("cluster").agg(F.count(F.lit(1)).alias("members"))
    votes = rows.join(sizes, "cluster").filter(F.pmod(F.xxhash64("node"), F.col("members")) < voters).select("cluster", "shingles")
    cast = votes.groupBy("cluster").agg(F.count(F.lit(1)).alias("votes"))
    counted = votes.select("cluster", F.explode("shingles").alias("s")).groupBy("cluster", "s").agg(F.count(F.lit(1)).alias("n"))
    return counted.join(cast, "cluster").filter(F.col("n") * 2 > F.col("votes")).groupBy("cluster").agg(F.collect_list("s").alias("core"))


def residuals(rows: DataFrame, percent: int, voters: int = 16) -> DataFrame:
    """node, component, cluster, n, residual, slack of every member of a cluster.

    residual: the symmetric difference of the member's shingles and its cluster's core (missing ones negated). The difference of two
    members is the difference of their residuals, so x and y link if and only if the shingles in both residuals number at least
    -(slack x + slack y) / 2 / (100 + percent); if the slacks add up to 0 or more they link whatever the residuals hold.
    """
    core = F.coalesce("core", F.array().cast("array<bigint>"))
    own = rows.join(core_of(rows, voters), "cluster", "left")
    residual = F.concat(F.array_except("shingles", core), F.transform(F.array_except(core, "shingles"), lambda s: -1 - s))
    own = own.select("node", "component", "cluster", F.size("shingles").cast("long").alias("n"), residual.alias("residual"))
    return own.withColumn("slack", (100 - percent) * F.col("n") - (100 + percent) * F.size("residual"))


def common_features(rows: DataFrame) -> DataFrame:
    """rows with `shared`: the residual's features that other rows of the cluster have too, rarest first."""
    each = rows.select("cluster", "node", F.explode("residual").alias("f"))
    met = each.groupBy("cluster", "f").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    shared = each.join(met, ["cluster", "f"]).groupBy("node").agg(F.transform(F.sort_array(F.collect_list(F.struct("n", "f"))), lambda x: x["f"]).alias("shared"))
    return rows.drop("shared").join(shared, "node", "left").withColumn("shared", F.coalesce("shared", F.array().cast("array<bigint>")))


def possible(rows: DataFrame, percent: int) -> DataFrame:
    """Of rows with `shared`, those whose common features could make a link: no partner's needs may exceed what both sides have."""
    reach = 2 * (100 + percent) * F.size("shared") + F.col("slack")
    rows = rows.withColumn("reach", reach)
    bounds = rows.groupBy("cluster").agg(F.max("reach").alias("farthest"), F.min(F.when(F.col("outside"), -F.col("slack"))).alias("nearest"), F.min(-F.col("slack")).alias("least"))
    far = F.col("outside") & (-F.col("slack") <= F.col("farthest")) & (F.col("least") <= F.col("reach"))
    near = ~F.col("outside") & (F.col("nearest") <= F.col("reach"))
    return rows.join(bounds, "cluster").filter(far | near).drop("reach", "farthest", "nearest", "least")


class ResidualKeys:
    """Bucket keys of residuals for each pair of slack classes: bands of minima where the pair's similarity is high enough, else a prefix."""

    MOST_BANDS, MOST_HASHES = 32, 512

    def __init__(self, percent: int, miss: float = 1e-5, seed: int = 11):
        self.percent, self.miss = percent, miss
        self.salts = np.random.default_rng(seed).integers(1, 1 << 63, self.MOST_HASHES, dtype=np.uint64)

    def bands(self, similarity: float) -> tuple[int, int]:
        """(bands, rows) of most rows that find this similarity with probability 1 - miss; (0, 0) if there are none of two rows or more."""
        found = (0, 0)
        for rows in range(2, 33):
            n = 1 if similarity >= 1 else int(np.ceil(np.log(self.miss) / np.log1p(-(similarity**rows))))
            if n <= self.MOST_BANDS and n * rows <= self.MOST_HASHES:
                found = (n, rows)
        return found

    def of(self, cluster: int, slack: int, shared: np.ndarray, unit: int, own: tuple, others: list[tuple]) -> np.ndarray:
        """own, others: (class, most shared features of a member, whether it has members outside the centre)."""
        double, minima, made = 2 * (100 + self.percent), None, [np.empty(0, np.uint64)]
        mark = lambda *parts: mixed(np.array([sum((int(x) & 0xFFFFFFFF) * f for x, f in zip(parts, (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5), strict=False)) & 0xFFFFFFFFFFFFFFFF], np.uint64))
        for other in others:
            low = max(1, -(-(own[0] + other[0]) * unit // double))
            need = max(1, -(-(other[0] * unit - slack) // double))
            if not (own[2] or other[2]) or need > min(len(shared), other[1]) or low > min(own[1], other[1]):
                continue
            bands, rows = self.bands(low / (own[1] + other[1] - low))
            pair = mark(cluster, cluster >> 32, min(own[0], other[0]), max(own[0], other[0]))
            if bands:
                if minima is None:
                    minima = np.array([mixed(shared ^ salt).min() for salt in self.salts])
                cut = minima[: bands * rows].reshape(bands, rows)
                factors = self.salts[:rows] | np.uint64(1)
                made.append(mixed((mixed(cut) * factors).sum(axis=1) + pair + self.salts[:bands]))
            else:
                made.append(mixed(mixed(shared[: len(shared) - need + 1]) + pair))
        return np.unique(np.concatenate(made))


def residual_members(rows: DataFrame, percent: int) -> DataFrame:
    """bucket, node: members of a cluster that can link, but are not known to by their slacks, meet in a bucket."""
    unit = (100 + percent) * F.greatest(F.lit(1), F.floor(F.col("top.n") * (100 - percent) / (100 + percent) / 24)).cast("long")
    units = rows.groupBy("cluster").agg(F.max(F.struct("slack", "n")).alias("top")).select("cluster", unit.alias("unit"))
    classed = rows.join(units, "cluster").withColumn("class", F.floor(-F.col("slack") / F.col("unit")).cast("long"))
    classes = classed.groupBy("cluster", "class").agg(F.max(F.size("shared")).cast("long").alias("most"), F.max(F.col("outside").cast("long")).alias("out"))
    listed = classes.groupBy("cluster").agg(F.sort_array(F.collect_list(F.struct("class", "most", "out"))).alias("classes"))
    whole = classed.join(listed, "cluster").select("node", "cluster", "slack", "unit", "class", "shared", "classes")

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = ResidualKeys(percent)
        for batch in batches:
            plain = [batch.column(i).to_pylist() for i in range(5)]
            for node, cluster, slack, size, own, shared, known in zip(*plain, batch.column(5), batch.column(6).to_pylist(), strict=True):
                others = [(c["class"], c["most"], c["out"]) for c in known]
                found = keys.of(cluster, slack, shared.values.to_numpy().view(np.uint64), size, next(c for c in others if c[0] == own), others)
                yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(np.full(len(found), node, np.int64))], ["bucket", "node"])

    return whole.mapInArrow(meet, "bucket long, node long")


def linked(percent: int):
    return F.col("common") * 100 >= (F.col("n_a") + F.col("n_b") - F.col("common")) * percent


def lowest(links: DataFrame, times: int) -> DataFrame:
    """node, component: every node points to its smallest neighbour, if that is smaller, and goes 4^times pointers down."""
    ends = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    up = shared_table(ends.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("component")))
    for _ in range(times):
        far = up.withColumnRenamed("component", "up_1")
        for k in (1, 2, 3):
            far = far.join(up.select(F.col("node").alias(f"up_{k}"), F.col("component").alias(f"up_{k + 1}")), f"up_{k}")
        up = shared_table(far.select("node", F.col("up_4").alias("component")))
    return up


def components(links: DataFrame) -> DataFrame:
    """node, component (the smallest node reachable) of every node that has a link. Links: a, b.

    Each round contracts: nodes become the node that their pointers lead to, and only links between different ones go on, so that most
    links are read by one round. Pointers are followed farther from the third round on, which settles long chains too.
    """
    links = shared_table(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    found, rounds = None, 0
    while True:
        rounds += 1
        ends = lowest(links, max(1, rounds - 1))
        if found is None:
            found = ends
        else:
            over = ends.select(F.col("node").alias("component"), F.col("component").alias("top"))
            found = shared_table(found.join(over, "component", "left").select("node", F.coalesce("top", "component").alias("component")))
        end = lambda c: ends.select(F.col("node").alias(c), F.col("component").alias(f"of_{c}"))  # noqa: B023, E731
        between = links.join(end("a"), "a").join(end("b"), "b").filter("of_a != of_b")
        links = shared_table(between.select(F.least("of_a", "of_b").alias("a"), F.greatest("of_a", "of_b").alias("b")).distinct())
        if not some(links):
            return found


def merged(groups: DataFrame, links: DataFrame) -> DataFrame:
    """The components `groups` (node, component) after more links (a, b): only the links between components go through the rounds."""
    end = lambda c: groups.select(F.col("node").alias(c), F.col("component").alias(f"of_{c}"))
    placed_ends = links.select("a", "b").join(end("a"), "a", "left").join(end("b"), "b", "left")
    between = shared_table(placed_ends.select("a", "b", F.coalesce("of_a", "a").alias("of_a"), F.coalesce("of_b", "b").alias("of_b")).filter("of_a != of_b"))
    if not some(between):
        return groups
    over = components(between.select(F.col("of_a").alias("a"), F.col("of_b").alias("b"))).select(F.col("node").alias("component"), F.col("component").alias("top"))
    # A node that had no link before is a component of its own.
    own = between.select(F.explode(F.array(F.struct(F.col("a").alias("node"), F.col("of_a").alias("component")), F.struct(F.col("b").alias("node"), F.col("of_b").alias("component")))).alias("r"))
    new = own.select("r.*").filter("node = component").distinct().join(groups.select("node"), "node", "left_anti")
    return shared_table(groups.unionByName(new).join(over, "component", "left").select("node", F.coalesce("top", "component").alias("component")))


def stars(members: DataFrame) -> DataFrame:
    """a, b: every member of a bucket with the bucket's smallest member."""
    pivots = members.groupBy("bucket").agg(F.min("node").alias("a"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    return members.join(pivots, "bucket").filter("node != a").select("a", F.col("node").alias("b")).distinct()


def placed(members: DataFrame, groups: DataFrame) -> DataFrame:
    """bucket, node, component: members with the component they are in so far."""
    return members.join(groups, "node", "left").select("bucket", "node", F.coalesce("component", "node").alias("component"))


def mixed_buckets(here: DataFrame) -> DataFrame:
    return here.groupBy("bucket").agg(F.min("component").alias("c"), F.max("component").alias("d")).filter("c != d").select("bucket")


def unsettled(members: DataFrame, groups: DataFrame) -> DataFrame:
    """bucket, node, component: members, without the smallest, of buckets in which they belong to several components still."""
    here = placed(members, groups)
    pivots = here.groupBy("bucket").agg(F.min("node").alias("pivot"), F.count(F.lit(1)).alias("n")).filter("n > 2").drop("n")
    rest = here.join(pivots, "bucket").filter("node != pivot").drop("pivot")
    return rest.join(mixed_buckets(rest), "bucket")


def some(df: DataFrame) -> bool:
    return df.limit(1).count() > 0


class Linker:
    """What the rounds of one run share: sketches of the classes, sets fetched so far, pairs looked at, links that are not in components yet."""

    def __init__(self, docs: DataFrame, reps: DataFrame, percent: int, width: int, margin: float, id_col: str, text_col: str):
        self.docs, self.reps, self.percent, self.width, self.margin, self.id_col, self.text_col = docs, reps, percent, width, margin, id_col, text_col
        self.sets: DataFrame | None = None
        self.looked_at: DataFrame | None = None
        self.links: DataFrame | None = None

    def fetch(self, nodes: DataFrame) -> DataFrame:
        """node, shingles; builds the sets that are not known yet."""
        new = nodes.select("node").distinct()
        if self.sets is not None:
            new = new.join(self.sets.select("node"), "node", "left_anti")
        wanted = shared_table(new.join(self.reps.select("node", "doc_id"), "node"))
        more = shared_table(shingle_sets(self.docs, wanted, self.width, self.id_col, self.text_col))
        self.sets = more if self.sets is None else self.sets.unionByName(more)
        return self.sets

    def confirm(self, pairs: DataFrame) -> None:
        """Estimates pairs (a, b) by their registers, confirms those near the threshold on their full sets, and adds links."""
        pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        if self.looked_at is not None:
            pairs = pairs.join(self.looked_at, ["a", "b"], "left_anti")
        known = shared_table(estimated(pairs, self.reps, self.percent))
        close = known.filter(F.col("estimate") >= self.percent / 100 - self.margin)
        sets = self.fetch(close.select(F.col("a").alias("node")).union(close.select(F.col("b").alias("node"))))
        links = shared_table(verified(close, sets).filter(linked(self.percent)).select("a", "b"))
        seen = known.select("a", "b")
        self.looked_at = seen if self.looked_at is None else self.looked_at.union(seen)
        self.links = links if self.links is None else self.links.union(links)

    def new_links(self) -> DataFrame:
        """The links (a, b) found since the last call."""
        links, self.links = self.links, None
        return links

    def refine(self, loose: DataFrame) -> DataFrame | None:
        """bucket, node: finer buckets for the members (bucket, node, component) of buckets that hold several components.

        Members of buckets that touch form a cluster, and a core of shingles that most of them hold stands for the text that they were copied
        from. Members near the core link with the nearest one. Those farther off are told apart by what parts them from the core alone.
        """
        edges = loose.groupBy("bucket").agg(F.min("node").alias("a")).join(loose.select("bucket", F.col("node").alias("b")), "bucket").filter("a != b").select("a", "b").distinct()
        clusters = components(edges).withColumnRenamed("component", "cluster")
        nodes = loose.select("node", "component").distinct().join(clusters, "node")
        rows = shared_table(nodes.join(self.fetch(nodes), "node"))
        own = shared_table(residuals(rows, self.percent))
        hubs = own.groupBy("cluster").agg(F.max(F.struct("slack", "node", "component")).alias("h"))
        own = own.join(hubs, "cluster").withColumn("outside", F.col("slack") + F.col("h.slack") < 0)
        near = own.filter(~F.col("outside") & (F.col("component") != F.col("h.component")))
        self.confirm(shared_table(near.select(F.col("h.node").alias("a"), F.col("node").alias("b"))))
        left = own.drop("h")
        for _ in range(2):
            left = shared_table(possible(common_features(left), self.percent))
        return shared_table(residual_members(left, self.percent)) if some(left) else None


def near_duplicate_groups(docs: DataFrame, percent: int = 85, width: int = 5, bands: int = 30, rows: int = 7, margin: float = 0.25,
                          id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each document; documents link at a Jaccard similarity of percent / 100.

    margin: how far an estimate may lie below the threshold for its pair to be verified still (about ten standard errors).
    """
    node = F.when(F.col("n_shingles") > 0, F.xxhash64("n_shingles", "set_a", "set_b")).alias("node")
    found = shared_table(sketches(docs, bands, rows, width, id_col, text_col).select("doc_id", "n_shingles", node, "registers", "keys"))
    # 1. One representative of each distinct set.
    classes = found.filter("node is not null and doc_id is not null").groupBy("node").agg(F.min(F.struct("doc_id", "n_shingles", "registers", "keys")).alias("r"))
    reps = shared_table(classes.select("node", "r.*"))
    linker = Linker(docs, reps, percent, width, margin, id_col, text_col)
    # 2. Members of buckets that hold more than one, each with the bucket's smallest member; 3. estimate, then confirm.
    entries = reps.select("node", F.posexplode("keys").alias("band", "key")).select("node", F.xxhash64("band", "key").alias("bucket"))
    shared = entries.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    members = shared_table(entries.join(shared, "bucket"))
    small, large = members.filter(F.col("n") <= STAR_MEMBERS).drop("n"), members.filter(F.col("n") > STAR_MEMBERS).drop("n")
    linker.confirm(stars(small))
    # Rows of one id are one document: its texts belong together.
    ids = found.filter("node is not null and doc_id is not null").select("doc_id", "node")
    several = ids.groupBy("doc_id").agg(F.min("node").alias("a"), F.max("node").alias("z")).filter("a != z").drop("z")
    same_id = shared_table(ids.join(several, "doc_id").filter("a != node").select("a", F.col("node").alias("b")).distinct())
    groups = components(linker.new_links().union(same_id))
    # 4. Pairs across components among the members of buckets that hold several components still.
    crowd = placed(large, groups)
    loose = shared_table(unsettled(small, groups).unionByName(crowd.join(mixed_buckets(crowd), "bucket")))
    if some(loose):
        finer = linker.refine(loose)
        if finer is not None:
            linker.confirm(stars(finer))
        groups = merged(groups, linker.new_links())
        if finer is not None and some(here := shared_table(unsettled(finer, groups))):
            x, y = (here.select("bucket", F.col("node").alias(n), F.col("component").alias(f"{n}_component")) for n in "ab")
            linker.confirm(x.join(y, "bucket").filter("a < b and a_component != b_component").select("a", "b"))
            groups = merged(groups, linker.new_links())
    # Back to all documents: through their class to their component, which is named by its smallest id.
    named = reps.select("node", "doc_id").join(groups, "node", "left").withColumn("component", F.coalesce("component", "node"))
    smallest = named.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    of_class = named.join(smallest, "component").select("node", "component_id")
    component = F.coalesce("component_id", "doc_id")
    out = found.select("doc_id", "n_shingles", "node").join(of_class, "node", "left")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))


def merge_registers(registers: list[np.ndarray]) -> np.ndarray:
    """The sketch of the union of the sets."""
    return reduce(np.maximum, registers)


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """One document of each group stays: the one with the smallest id. Rows without an id stay where no document with an id has their set."""
    id_col, (own,) = options.get("id_col", "doc_id"), fresh_names(docs, 1)
    gone = shared_table(near_duplicate_groups(docs, **options).filter(~F.col("kept")).select(F.col("doc_id").alias(own)))
    return without(docs.withColumn(own, F.col(id_col).cast("long")), gone, [own]).select(*(f"`{c}`" for c in docs.columns))
