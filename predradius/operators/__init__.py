"""Embedding, ball counting, radius rules, samples, probes, radius methods and baselines.

Everything that is computed per item is narrow or aggregates to a few rows per predicate: ball counts multiply blocks of item
vectors with the matrix of all predicates and emit counts only, so nothing of the size items x predicates is ever shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import DIMS, cosine_distance, dot, holds, sign_vector
from ..sources import kept

#: Most (predicate, radius) pairs that one ball count takes; they are collected and sent to the workers.
RADII_BOUND = 1_000_000
ALL = 2.000001
PROBE_CONFIGS = ((128, 0.9), (64, 0.8), (32, 0.6))


def embed_items(items: DataFrame) -> DataFrame:
    """item_id, toks, vec, norm2."""
    return items.withColumn("embedded", sign_vector("toks")).select(*(c for c in items.columns if c not in ("vec", "norm2")), "embedded.vec", "embedded.norm2")


def embed_concepts(concepts: DataFrame) -> DataFrame:
    named = concepts.withColumn("toks_c", F.concat("all_of", "any_of")).withColumn("embedded", sign_vector("toks_c"))
    return named.select(*concepts.columns, F.col("embedded.vec").alias("cvec"), F.col("embedded.norm2").alias("cnorm2"))


def distances(syn: DataFrame, concepts: DataFrame) -> DataFrame:
    """concept_id, item_id, dist (and yes): for samples and small collections."""
    both = syn.crossJoin(F.broadcast(concepts))
    return both.select("concept_id", "item_id", cosine_distance("vec", "norm2", "cvec", "cnorm2").alias("dist"), holds().alias("yes"))


def answers(items: DataFrame, concepts: DataFrame) -> DataFrame:
    """concept_id, item_id, yes by the attributes: the exact answer model."""
    return items.crossJoin(F.broadcast(concepts)).select("concept_id", "item_id", holds().alias("yes"))


def true_selectivity(items: DataFrame, concepts: DataFrame) -> DataFrame:
    """concept_id, hits, total, selectivity: a narrow scan and one small aggregation."""
    got = answers(items, concepts).groupBy("concept_id").agg(F.sum(F.col("yes").cast("long")).alias("hits"), F.count(F.lit(1)).alias("total"))
    return got.withColumn("selectivity", F.col("hits") / F.col("total"))


def ball_selectivity(syn: DataFrame, radii: DataFrame, keys: list[str], vec: str = "vec", norm2: str = "norm2") -> DataFrame:
    """hits, total, selectivity for every row of radii (keys, cvec, cnorm2, radius): one scan whatever their number."""
    rows = radii.select(*keys, "cvec", "cnorm2", "radius").collect()
    if len(rows) > RADII_BOUND:
        raise ValueError(f"{len(rows)} radii; at most {RADII_BOUND} in one ball count")
    shapes: dict[tuple, int] = {}
    at = np.array([shapes.setdefault(tuple(r["cvec"]), len(shapes)) for r in rows], dtype=np.int64)
    matrix = np.array(list(shapes), dtype=np.float64).reshape(len(shapes), -1).T
    norms = np.zeros(len(shapes))
    for i, r in zip(at, rows, strict=True):
        norms[i] = r["cnorm2"]
    limit = np.array([r["radius"] for r in rows], dtype=np.float64)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits, total = np.zeros(len(limit), np.int64), 0
        for batch in batches:
            if not batch.num_rows or not len(limit):
                total += batch.num_rows
                continue
            block = batch.column(0).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)
            own = batch.column(1).to_numpy(zero_copy_only=False).astype(np.float64)
            for a in range(0, len(block), 4096):
                scale = np.sqrt(own[a : a + 4096, None] * norms[None, :])
                with np.errstate(divide="ignore", invalid="ignore"):
                    dist = np.where(scale > 0, 1 - (block[a : a + 4096] @ matrix) / scale, 1.0)
                dist.sort(axis=0)
                for j in range(len(shapes)):
                    mine = np.flatnonzero(at == j)
                    hits[mine] += np.searchsorted(dist[:, j], limit[mine], side="left")
            total += len(block)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(limit))), pa.array(hits), pa.array(np.full(len(limit), total))], ["r", "hits", "total"])

    sums = syn.select(vec, norm2).mapInArrow(count, "r long, hits long, total long").groupBy("r").agg(F.sum("hits").alias("hits"), F.sum("total").alias("total"))
    spark = syn.sparkSession
    names = spark.createDataFrame([(i, *(r[k] for k in keys), r["radius"]) for i, r in enumerate(rows)], "r long, " + ", ".join(f"`{k}` {radii.schema[k].dataType.simpleString()}" for k in keys) + ", radius double")
    return names.join(sums, "r").drop("r").withColumn("selectivity", F.col("hits") / F.nullif("total", F.lit(0)))


def hash_sample(items: DataFrame, n: int, seeds: list[int], id_col: str = "item_id") -> DataFrame:
    """The n items with the smallest md5(seed:id) for each seed: uniform, without replacement, the same however rows are dealt.

    Of many items only hashes below a bound, about 2n + 100 a seed, are written to the shared folder and ranked. A seed that has fewer than n
    of them ranks all items instead, so the bound never changes a sample.
    """
    order = Window.partitionBy("seed").orderBy("h", id_col)

    def hashed(of: list[int]) -> DataFrame:
        return items.withColumn("seed", F.explode(F.array(*map(F.lit, of)))).withColumn("h", F.md5(F.concat_ws(":", "seed", id_col)))

    def ranked(drawn: DataFrame) -> DataFrame:
        return drawn.withColumn("slot", F.row_number().over(order)).filter(F.col("slot") <= n).drop("h")

    share = (2 * n + 100) / max(items.count(), 1)
    if share >= 0.5:
        return ranked(hashed(seeds))
    near = kept(hashed(seeds).filter(F.col("h") < f"{int(share * 16**12):012x}"))
    enough = {r["seed"] for r in near.groupBy("seed").count().filter(F.col("count") >= n).collect()}
    short = [s for s in seeds if s not in enough]
    return ranked(near.filter(~F.col("seed").isin(short)).union(hashed(short).select(near.columns)) if short else near)


def radius_for_count(dist: DataFrame, keys: list[str], k: Column, rule: str = "next") -> DataFrame:
    """keys, k, n, radius, inside: the radius that leaves k points strictly inside; ALL if every point is to be inside.

    rule: 'next' is the (k+1)-th distance, 'mid' the mean of the k-th and the (k+1)-th, 'tight' just above the k-th.
    """
    order = Window.partitionBy(*keys).orderBy("dist", "item_id")
    whole = Window.partitionBy(*keys)
    ranked = dist.withColumns({"rank": F.row_number().over(order), "k": k.over(whole) if keys else k, "n": F.count(F.lit(1)).over(whole)})
    upper = F.max(F.when(F.col("rank") == F.col("k") + 1, F.col("dist")))
    lower = F.max(F.when(F.col("rank") == F.col("k"), F.col("dist")))
    first = F.min("dist")
    radius = {"next": F.coalesce(upper, F.lit(ALL)), "mid": F.coalesce((upper + F.coalesce(lower, upper)) / 2, F.lit(ALL)), "tight": F.coalesce(lower + 1e-9, first)}[rule]
    return ranked.groupBy(*keys, "k", "n").agg(radius.alias("radius"))


def probed_radius(dist: DataFrame, keys: list[str], rule: str = "next") -> DataFrame:
    """Radius that holds as many probe vectors as the probe has yes answers; no yes: the smallest probe distance."""
    return radius_for_count(dist, keys, F.sum(F.col("yes").cast("long")), rule)


def linear_radius(training: DataFrame, concepts: DataFrame) -> DataFrame:
    """concept_id, radius by least squares on one feature: the mean fourth power of the unit predicate vector."""
    def peak(vec: str, norm: str) -> Column:
        return F.expr(f"aggregate({vec}, cast(0 as bigint), (s, x) -> s + cast(x as bigint) * x * x * x)").cast("double") / (F.col(norm).cast("double") * F.col(norm).cast("double"))

    line = training.select(peak("cvec", "cnorm2").alias("x"), F.col("radius").alias("y")).agg(F.regr_slope("y", "x").alias("a"), F.regr_intercept("y", "x").alias("b"))
    return concepts.withColumn("x", peak("cvec", "cnorm2")).crossJoin(F.broadcast(line)).select("concept_id", "cvec", "cnorm2", (F.col("a") * F.col("x") + F.col("b")).alias("radius"))


def training_concepts(items: DataFrame, draws: int, subset: int, per_draw: int) -> tuple[DataFrame, DataFrame]:
    """(draw, item) subsets by hash and (draw, concept) picks among the concepts that the subset's items hold."""
    picked = hash_sample(items, subset, list(range(draws))).withColumnRenamed("seed", "draw").drop("slot")
    narrow = F.transform(F.col("toks"), lambda t: F.array(t))
    wide = F.transform(F.sequence(F.lit(2), F.size("toks")), lambda i: F.slice("toks", F.lit(1), i))
    held = picked.select("draw", F.explode(F.concat(narrow, wide)).alias("all_of")).distinct().withColumn("concept_id", F.array_join("all_of", "&"))
    order = Window.partitionBy("draw").orderBy(F.md5(F.concat_ws(":", "draw", "concept_id")), "concept_id")
    chosen = held.withColumn("n", F.row_number().over(order)).filter(F.col("n") <= per_draw).drop("n").withColumn("any_of", F.array().cast("array<string>"))
    return picked, chosen


def draw_distances(syn: DataFrame, concepts: DataFrame) -> DataFrame:
    """draw, concept_id, item_id, dist, yes for all pairs of a draw, by one matrix product a draw: the values of `cosine_distance` and `holds`."""
    def pairs(left: pa.Table, right: pa.Table) -> pa.Table:
        own, asked = left.to_pylist(), right.to_pylist()
        known = np.array([r["norm2"] is not None for r in own], bool)
        a = np.array([r["vec"] if ok else [0] * DIMS for r, ok in zip(own, known, strict=True)], np.float64).reshape(-1, DIMS)
        b = np.array([r["cvec"] for r in asked], np.float64).reshape(-1, DIMS)
        scale = np.sqrt(np.array([r["norm2"] or 0 for r in own], np.float64)[:, None] * np.array([r["cnorm2"] for r in asked], np.float64)[None, :])
        dist = np.where(scale > 0, 1 - (a @ b.T) / np.where(scale > 0, scale, 1), 1.0)
        held = [None if r["toks"] is None else set(r["toks"]) for r in own]
        wanted = [(set(r["all_of"]), set(r["any_of"])) for r in asked]
        yes = [None if h is None else every <= h and (not some or bool(some & h)) for h in held for every, some in wanted]
        n, m = len(own), len(asked)
        return pa.table({
            "draw": pa.array([r["of"] for r in asked] * n, pa.int32()), "concept_id": pa.array([r["concept_id"] for r in asked] * n, pa.string()), "item_id": pa.array([r["item_id"] for r in own for _ in range(m)], pa.int64()),
            "dist": pa.array(dist.ravel(), mask=np.repeat(~known, m)), "yes": pa.array(yes, pa.bool_())})

    dealt = syn.select("draw", F.col("item_id").cast("long").alias("item_id"), "toks", "vec", "norm2").groupBy("draw")
    return dealt.cogroup(concepts.select(F.col("draw").alias("of"), "concept_id", "all_of", "any_of", "cvec", "cnorm2").groupBy("of")).applyInArrow(pairs, "draw int, concept_id string, item_id long, dist double, yes boolean")


def radius_training_set(items: DataFrame, draws: int = 100, subset: int = 200, per_draw: int = 55) -> DataFrame:
    """draw, concept_id, cvec, cnorm2, k, radius: the radius that holds a concept's members within a random subset."""
    picked, chosen = training_concepts(items, draws, subset, per_draw)
    dist = draw_distances(embed_items(picked), embed_concepts(chosen))
    return probed_radius(dist, ["draw", "concept_id"]).join(embed_concepts(chosen).select("draw", "concept_id", "cvec", "cnorm2"), ["draw", "concept_id"]).filter("k < n")


class LearnedRadius:
    """A small neural net from unit predicate vector to radius, fitted by Adam on the driver: a few thousand pairs, whatever the data."""

    def __init__(self, weights: list[np.ndarray]):
        self.weights = weights

    @staticmethod
    def unit(rows) -> np.ndarray:
        x = np.array([r["cvec"] for r in rows], dtype=np.float64)
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    @classmethod
    def fit(cls, training: DataFrame, seed: int = 0, hidden: tuple[int, ...] = (64, 32), epochs: int = 60, rate: float = 3e-3, batch: int = 256, most: int = 20_000) -> LearnedRadius:
        rows = training.select("cvec", "radius", F.md5(F.concat_ws(":", "draw", "concept_id")).alias("h")).orderBy("h").limit(most).collect()
        x, y = cls.unit(rows), np.array([r["radius"] for r in rows])[:, None]
        draw = np.random.default_rng(seed)
        sizes = [x.shape[1], *hidden, 1]
        w = [p for a, b in zip(sizes, sizes[1:], strict=False) for p in (draw.normal(0, np.sqrt(2 / a), (a, b)), np.zeros(b))]
        w[-1] += y.mean()
        m, v, t = [np.zeros_like(p) for p in w], [np.zeros_like(p) for p in w], 0
        for _ in range(epochs):
            for part in np.array_split(draw.permutation(len(x)), max(1, len(x) // batch)):
                layers = [x[part]]
                for i in range(0, len(w) - 2, 2):
                    layers.append(np.maximum(layers[-1] @ w[i] + w[i + 1], 0))
                slope = 2 * (layers[-1] @ w[-2] + w[-1] - y[part]) / len(part)
                grads: list[np.ndarray] = []
                for i in range(len(w) - 2, -1, -2):
                    grads = [layers[i // 2].T @ slope, slope.sum(axis=0), *grads]
                    slope = (slope @ w[i].T) * (layers[i // 2] > 0)
                t += 1
                for i, g in enumerate(grads):
                    m[i], v[i] = 0.9 * m[i] + 0.1 * g, 0.999 * v[i] + 0.001 * g * g
                    w[i] -= rate * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
        return cls(w)

    def predict(self, x: np.ndarray) -> np.ndarray:
        for i in range(0, len(self.weights) - 2, 2):
            x = np.maximum(x @ self.weights[i] + self.weights[i + 1], 0)
        return np.clip((x @ self.weights[-2] + self.weights[-1])[:, 0], 0.0, ALL)

    def transform(self, concepts: DataFrame) -> DataFrame:
        """concept_id, cvec, cnorm2, radius."""
        def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = batch.to_pylist()
                found = self.predict(self.unit(rows)) if rows else np.empty(0)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.float64())], [*batch.schema.names, "radius"])

        own = concepts.select("concept_id", "cvec", F.col("cnorm2").cast("long"))
        return own.mapInArrow(apply, "concept_id string, cvec array<int>, cnorm2 long, radius double")


def blended_radius(a: DataFrame, b: DataFrame, keys: list[str], weight: float = 0.5) -> DataFrame:
    """The weighted mean of two radii per predicate."""
    return a.join(b.withColumnRenamed("radius", "other").select(*keys, "other"), keys).withColumn("radius", weight * F.col("radius") + (1 - weight) * F.col("other")).drop("other")


def diverse_sample(syn: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """item_id of the item nearest to each of n k-means centroids; refilled by hash order if centroids share an item."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector, vector_to_array

    unit = F.expr("transform(vec, x -> x / sqrt(cast(norm2 as double)))")
    points = syn.filter("norm2 > 0").select("item_id", array_to_vector(unit).alias("features"))
    model = KMeans(k=n, seed=seed, maxIter=10).fit(points)
    centers = points.sparkSession.createDataFrame([(i, c.tolist()) for i, c in enumerate(model.clusterCenters())], "cell int, center array<double>")
    cells = model.transform(points).select("item_id", F.col("prediction").alias("cell"), vector_to_array("features").alias("f")).join(F.broadcast(centers), "cell")
    near = cells.withColumn("d", F.expr("aggregate(zip_with(f, center, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"))
    picked = near.groupBy("cell").agg(F.min(F.struct("d", "item_id")).alias("m")).select(F.col("m.item_id").alias("item_id")).distinct()
    ids = [r["item_id"] for r in picked.collect()]  # at most n
    short = n - len(ids)
    if short <= 0:
        return picked
    rest = syn.filter(~F.col("item_id").isin(ids)) if ids else syn
    more = rest.select("item_id").orderBy(F.md5(F.concat_ws(":", F.lit(seed), "item_id")), "item_id").limit(short)
    return picked.sparkSession.createDataFrame([(i,) for i in ids], "item_id long").union(more.select(F.col("item_id").cast("long")))


def compress_state(items: DataFrame, importance: DataFrame, ratio: float) -> DataFrame:
    """item_id, kept: the share 1 - ratio of an item's tokens that matter most to predicates (ties by md5)."""
    rank = Window.partitionBy("item_id").orderBy(F.desc("weight"), F.md5("t"), "t")
    each = items.select("item_id", F.size("toks").alias("m"), F.explode("toks").alias("t")).join(F.broadcast(importance), "t", "left").na.fill(0, ["weight"])
    ranked = each.withColumn("r", F.row_number().over(rank)).filter(F.col("r") <= F.ceil((1 - F.lit(ratio).cast("decimal(4,2)")) * F.col("m")))
    return ranked.groupBy("item_id").agg(F.array_sort(F.collect_list("t")).alias("kept"))


def token_importance(items: DataFrame) -> DataFrame:
    """t, weight: how often predicates drawn from the collection would ask for a token, by its frequency. Vocabulary-sized."""
    return items.select(F.explode("toks").alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("weight"))


def truth_masks(items: DataFrame, concepts: DataFrame) -> DataFrame:
    """mask, n: how many items fulfil exactly the concepts whose bits are set. One scan prices every query and order."""
    rows = [(r["pos"], r["all_of"], r["any_of"]) for r in concepts.collect()]
    bit = lambda pos, a, o: F.when(
        (F.size(F.array_except(F.array(*map(F.lit, a)).cast("array<string>"), "toks")) == 0) & (F.arrays_overlap(F.array(*map(F.lit, o)), "toks") if o else F.lit(True)), F.lit(1 << pos)).otherwise(F.lit(0)).cast("long")
    total = sum((bit(*r) for r in rows[1:]), bit(*rows[0]))
    return items.select(total.alias("mask")).groupBy("mask").agg(F.count(F.lit(1)).alias("n"))
