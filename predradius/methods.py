"""Queries of the methods, baselines, measures and experiments, for the suites w1 (part) and w2 (geography)."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import operators as op
from . import plans
from .functions import q_error
from .oracles import SEEDS, SIZES
from .sources import SUITES, concepts, held_concepts, items, table

COST = plans.CostModel()


class Suite:
    """The frames of one suite, made when first needed."""

    def __init__(self, spark: SparkSession, sf_dir: str, suite: str, seeds: list[int] | None = None):
        self.spark, self.seeds = spark, seeds or SEEDS
        self.items, self.plain = items(spark, sf_dir, suite), concepts(spark, suite)
        self.syn, self.concepts = op.embed_items(self.items), op.embed_concepts(self.plain)
        self.suite = suite

    def truth(self) -> DataFrame:
        return op.true_selectivity(self.items, self.plain)

    def sized_sample(self, sizes: list[int]) -> DataFrame:
        drawn = op.hash_sample(self.items, max(sizes), self.seeds)
        return drawn.withColumn("m", F.explode(F.array(*map(F.lit, sizes)))).filter("slot <= m")

    def probed(self) -> DataFrame:
        """seed, m, concept_id, k, n, radius."""
        drawn = op.embed_items(op.hash_sample(self.items, 128, self.seeds))
        both = drawn.crossJoin(F.broadcast(self.concepts))
        dist = both.select("seed", "slot", "concept_id", "item_id", op.cosine_distance("vec", "norm2", "cvec", "cnorm2").alias("dist"), op.holds().alias("yes"))
        dist = dist.withColumn("m", F.explode(F.array(F.lit(32), F.lit(64), F.lit(128)))).filter("slot <= m")
        return op.probed_radius(dist, ["seed", "m", "concept_id"])

    def ball(self, radii: DataFrame, keys: list[str]) -> DataFrame:
        return op.ball_selectivity(self.syn, radii.join(self.concepts.select("concept_id", "cvec", "cnorm2"), "concept_id"), keys)

    def estimates(self) -> DataFrame:
        return self.ball(self.probed(), ["seed", "m", "concept_id"])

    def profile(self) -> DataFrame:
        share = F.avg(F.col("yes").cast("double"))
        drawn = self.sized_sample(SIZES).crossJoin(F.broadcast(self.plain))
        return drawn.select("seed", "m", "concept_id", op.holds().alias("yes")).groupBy("seed", "m", "concept_id").agg(share.alias("estimate"))

    def runs(self) -> DataFrame:
        """method, m, seed, concept_id, estimate, latency."""
        probed = self.estimates().select(F.lit("probed").alias("method"), "m", "seed", "concept_id", F.col("selectivity").alias("estimate"), F.lit(COST.batch_s).alias("latency"))
        profile = self.profile().select(F.lit("profile").alias("method"), "m", "seed", "concept_id", "estimate", (F.col("m") * COST.call_s).alias("latency"))
        return probed.union(profile)

    def errors(self) -> DataFrame:
        truth = self.truth().select("concept_id", "total", F.col("selectivity").alias("truth"))
        return self.runs().join(F.broadcast(truth), "concept_id").withColumn("q", q_error(F.col("estimate"), F.col("truth"), F.col("total")))

    def queries(self) -> DataFrame:
        return plans.random_queries(self.spark, self.plain)

    def token_queries(self) -> DataFrame:
        """Queries whose filters are drawn from all tokens of the collection."""
        return plans.random_queries(self.spark, held_concepts(self.items, wide=False).withColumn("pos", F.lit(0)))

    def orders(self) -> DataFrame:
        keys = ["method", "m", "seed"]
        perfect = self.truth().select(F.lit("perfect").alias("method"), F.lit(0).alias("m"), F.lit(0).alias("seed"), "concept_id", F.col("selectivity").alias("estimate"))
        known = self.runs().select(*keys, "concept_id", "estimate").union(perfect)
        written = self.queries().select(F.lit("written").alias("method"), F.lit(0).alias("m"), F.lit(0).alias("seed"), "query_id", "n_filters", "concept_id", "pos", F.col("written").alias("step"))
        return plans.order_filters(self.queries(), known, keys).select(*keys, "query_id", "n_filters", "concept_id", "pos", "step").union(written)

    def calls(self) -> DataFrame:
        return plans.chain_calls(self.orders(), op.truth_masks(self.items, self.plain), ["method", "m", "seed"])

    def groups(self) -> DataFrame:
        """method, m, n_filters, seed, est_s, plan_s, overhead: summed over the queries of a group, against the perfect estimator."""
        calls = self.calls()
        perfect = calls.filter("method = 'perfect'").select("query_id", F.col("calls").alias("least"))
        cost = calls.join(F.broadcast(perfect), "query_id").select("method", "m", "n_filters", "seed", (F.col("n_filters") * COST.estimation()).alias("est_s"), ((F.col("calls") - F.col("least")) * COST.call_s).alias("plan_s"))
        return cost.groupBy("method", "m", "n_filters", "seed").agg(F.sum("est_s").alias("est_s"), F.sum("plan_s").alias("plan_s"), F.sum(F.col("est_s") + F.col("plan_s")).alias("overhead"))

    def means(self) -> DataFrame:
        return self.groups().groupBy("method", "m", "n_filters").agg(F.avg("overhead").alias("mean"), F.stddev_samp("overhead").alias("sd"), F.count(F.lit(1)).alias("runs"))


r6 = lambda c: F.round(c, 6)


def embedded(s: Suite) -> DataFrame:
    return s.syn.select("item_id", F.array_join(F.col("vec").cast("array<string>"), ",").alias("vec"), F.col("norm2").cast("long").alias("norm2"))


def embedded_concepts(s: Suite) -> DataFrame:
    """Vectors of all predicates that the items hold."""
    made = op.embed_concepts(held_concepts(s.items))
    return made.select("concept_id", F.array_join(F.col("cvec").cast("array<string>"), ",").alias("vec"), F.col("cnorm2").cast("long").alias("norm2"))


def precision_recall(s: Suite) -> DataFrame:
    inside = F.col("dist") < 0.5
    n = lambda c: F.sum(c.cast("long"))
    return op.distances(s.syn, s.concepts).groupBy("concept_id").agg(n(inside & F.col("yes")).alias("found"), n(inside & ~F.col("yes")).alias("false_hits"), n(~inside & F.col("yes")).alias("missed"))


def ideal(s: Suite) -> DataFrame:
    return op.probed_radius(op.distances(s.syn, s.concepts), ["concept_id"])


def precomputed(s: Suite) -> DataFrame:
    known = s.truth().join(F.broadcast(s.plain.filter("pos % 2 = 0").select("concept_id")), "concept_id").select("concept_id", "selectivity")
    return s.plain.select("concept_id").join(F.broadcast(known), "concept_id", "left")


def noisy(s: Suite) -> DataFrame:
    flip = F.substring(F.md5(F.concat_ws(":", "concept_id", "item_id")), 1, 4) < "0ccc"
    both = op.answers(s.items, s.plain).withColumn("flip", flip)
    return both.groupBy("concept_id").agg(F.sum((F.col("yes") != F.col("flip")).cast("long")).alias("hits"), F.sum(F.col("flip").cast("long")).alias("flipped"))


def summary(s: Suite) -> DataFrame:
    p = lambda x: r6(F.percentile("q", F.lit(x)))
    return s.errors().groupBy("method", "m").agg(p(0.05).alias("p5"), p(0.5).alias("p50"), p(0.95).alias("p95"), r6(F.avg("latency")).alias("latency_s"))


def parity(s: Suite) -> DataFrame:
    mid = s.errors().groupBy("method", "m").agg(F.percentile("q", F.lit(0.5)).alias("p50"), F.percentile("q", F.lit(0.95)).alias("p95"))
    a = mid.filter("method = 'profile'").select(F.col("m").alias("sample"), F.col("p50").alias("own50"), F.col("p95").alias("own95"))
    b = mid.filter("method = 'probed'").select(F.col("m").alias("probe"), "p50", "p95")
    return b.join(F.broadcast(a), (F.col("own50") <= F.col("p50")) & (F.col("own95") <= F.col("p95")), "left").groupBy("probe").agg(F.min("sample").alias("sample"))


def fixed_count(s: Suite) -> DataFrame:
    """The radius that leaves ten items inside, for every predicate."""
    return op.radius_for_count(op.distances(s.syn, s.concepts), ["concept_id"], F.max(F.lit(10)))


def zero_truth(s: Suite) -> DataFrame:
    """Errors apart for predicates that no item fulfils; both sides of the ratio count as one item there."""
    return s.errors().groupBy("method", "m", (F.col("truth") == 0).alias("truth_zero")).agg(F.count(F.lit(1)).alias("n"), r6(F.percentile("q", F.lit(0.5))).alias("p50"))


def order_ties(s: Suite) -> DataFrame:
    """Pairs of predicates with equal estimates, whose order their names decide."""
    keys = ["method", "m", "seed"]
    a, b = (s.runs().select(*keys, F.col("concept_id").alias(f"c{i}"), F.col("estimate").alias(f"e{i}")) for i in "ab")
    return a.join(b, keys).filter("ca < cb and ea = eb").groupBy("method", "m").agg(F.count(F.lit(1)).alias("ties"))


def endtoend(s: Suite) -> DataFrame:
    """Seconds of estimation and execution, summed over the queries of a group."""
    return s.calls().groupBy("method", "m", "n_filters", "seed").agg(r6(F.sum(F.col("n_filters") * COST.estimation() + F.col("calls") * COST.call_s)).alias("seconds"))


def profile_reuse(s: Suite) -> DataFrame:
    """Overhead of profiling if the answers on the sample count as those of the first filter's run (m calls less in each of a group's 100 queries)."""
    mean = s.means().filter("method = 'profile'")
    return mean.select("m", "n_filters", r6(F.col("mean")).alias("mean"), r6(F.col("mean") - 100 * F.col("m") * COST.call_s).alias("mean_reused"))


def interval(s: Suite) -> DataFrame:
    half = 2.093 * F.col("sd") / F.sqrt("runs")  # t quantile of twenty seeds
    return s.means().filter("runs > 1").select("method", "m", "n_filters", r6(F.col("mean")).alias("mean"), r6(F.col("mean") - half).alias("low"), r6(F.col("mean") + half).alias("high"))


def best_config(s: Suite) -> DataFrame:
    return s.means().groupBy("method", "n_filters").agg(F.min(F.struct("mean", "m")).alias("b")).select("method", "n_filters", "b.m", r6(F.col("b.mean")).alias("mean"))


def reduction(s: Suite) -> DataFrame:
    least = lambda name: F.min(F.when(F.col("method") == name, F.col("mean")))
    return s.means().groupBy("n_filters").agg(r6(1 - least("probed") / least("profile")).alias("reduction"))


def inversions(s: Suite) -> DataFrame:
    truth = s.truth().select("concept_id", F.col("selectivity").alias("t"))
    own = s.orders().filter("method <> 'written'").join(F.broadcast(truth), "concept_id").select("method", "m", "seed", "query_id", "step", "t")
    other = own.select("method", "m", "seed", "query_id", F.col("step").alias("later"), F.col("t").alias("t2"))
    return own.join(other, ["method", "m", "seed", "query_id"]).filter("step < later").groupBy("method", "m").agg(F.count(F.lit(1)).alias("pairs"), F.sum((F.col("t") > F.col("t2")).cast("long")).alias("inverted"))


BY_SUITE: dict[str, Callable[[Suite], DataFrame]] = {
    "embed": embedded, "embed_concepts": embedded_concepts,
    "distance_matrix": lambda s: op.distances(s.syn, s.concepts).withColumn("dist", F.round("dist", 9)),
    "true_selectivity": lambda s: s.truth(),
    "fixed_radius": lambda s: s.ball(s.plain.select("concept_id", F.lit(0.5).alias("radius")), ["concept_id"]).drop("selectivity"),
    "ball_precision_recall": precision_recall,
    "hash_sample": lambda s: op.hash_sample(s.items, 64, SEEDS).select("seed", "slot", "item_id"),
    "probed_radius": lambda s: s.probed(),
    "probed_radius_zero": lambda s: s.probed().filter("k = 0").select("seed", "m", "concept_id", "radius"),
    "estimate_probed": lambda s: s.estimates().drop("radius"),
    "ideal_radius": ideal,
    "sample_profile": lambda s: s.profile(),
    "probe_share": lambda s: s.probed().select("seed", "m", "concept_id", (F.col("k") / F.col("n")).alias("estimate")),
    "precomputed_outcomes": precomputed, "noisy_answers": noisy,
    "qerror": lambda s: s.errors().select("method", "m", "seed", "concept_id", F.round("q", 9).alias("q_error")),
    "qerror_summary": summary, "parity_sample": parity, "radius_for_count": fixed_count, "qerror_zero_truth": zero_truth, "order_ties": order_ties, "endtoend_cost": endtoend, "profile_reuse": profile_reuse,
    "truth": lambda s: op.answers(s.items, s.plain),
    "random_queries": lambda s: s.token_queries().select("query_id", "n_filters", "concept_id", "written"),
    "order_filters": lambda s: s.orders().filter("method <> 'written'").select("method", "m", "seed", "query_id", "concept_id", "step"),
    "chain_calls": lambda s: s.calls(),
    "overhead": lambda s: s.groups().select("method", "m", "n_filters", "seed", r6(F.col("overhead")).alias("overhead")),
    "overhead_split": lambda s: s.groups().groupBy("method", "m", "n_filters").agg(r6(F.avg("est_s")).alias("est_part"), r6(F.avg("plan_s")).alias("plan_part")),
    "overhead_ci": interval, "best_config": best_config, "overhead_reduction": reduction, "order_inversions": inversions,
}


def learned(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Suite(spark, sf_dir, "w1")
    model = op.LearnedRadius.fit(op.radius_training_set(s.items))
    found = s.ball(model.transform(s.concepts).select("concept_id", "radius"), ["concept_id"])
    truth = s.truth().select("concept_id", F.col("selectivity").alias("truth"))
    return found.join(truth, "concept_id").withColumn("q_error", q_error(F.col("selectivity"), F.col("truth"), F.col("total")))


def blended(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Suite(spark, sf_dir, "w1", [0])
    model = op.LearnedRadius.fit(op.radius_training_set(s.items))
    radii = op.blended_radius(s.probed().filter("m = 128").select("concept_id", "radius"), model.transform(s.concepts), ["concept_id"])
    return s.ball(radii, ["concept_id"])


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    syn = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"))
    syn = syn.withColumn("norm2", op.dot("vec", "vec", "0D"))
    anchors = syn.filter(F.col("vec_id") % 20 == 0).select(F.col("vec_id").alias("anchor"), F.col("vec").alias("cvec"), F.col("norm2").alias("cnorm2"))
    radii = anchors.withColumn("radius", F.explode(F.array(*map(F.lit, (0.6, 0.7, 0.8, 0.9)))))
    return op.ball_selectivity(syn, radii, ["anchor"]).select("anchor", "radius", "hits", "total")


def memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Memory of each probe configuration by the tokens that the collection's items keep at its ratio, in full states and bytes."""
    configs = spark.createDataFrame(op.PROBE_CONFIGS, "n int, ratio double")
    size = F.size("toks")
    kept = F.ceil((1 - F.col("ratio").cast("decimal(4,2)")) * size).cast("long")
    sums = items(spark, sf_dir, "w1").filter("toks IS NOT NULL").crossJoin(F.broadcast(configs)).groupBy("n", "ratio").agg(F.sum(kept).alias("kept"), F.sum(size).alias("tokens"))
    states = F.col("n") * F.col("kept") / F.col("tokens")
    return sums.select("n", "ratio", r6(states).alias("full_states"), F.round(states * COST.state_bytes, 0).alias("bytes"))


def equiwidth(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_retailprice")
    ends = part.agg(F.min("p_retailprice").alias("lo"), F.max("p_retailprice").alias("hi"))
    at = F.least(F.lit(19), F.floor((F.col("p_retailprice") - F.col("lo")) / (F.col("hi") - F.col("lo")) * 20)).cast("int")
    return part.crossJoin(F.broadcast(ends)).groupBy(at.alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def compression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Yes answers of the probe on compressed state against exact ones, for each equal-memory configuration and for full state."""
    s = Suite(spark, sf_dir, "w1", [0])
    weights = op.token_importance(s.items)
    made = []
    for n, ratio in (*op.PROBE_CONFIGS, (128, 0.0)):
        probe = op.hash_sample(s.items, n, [0]).select("item_id", "toks")
        kept = op.compress_state(probe, weights, ratio).withColumnRenamed("kept", "toks")
        said = op.answers(kept, s.plain).withColumnRenamed("yes", "said").join(op.answers(probe, s.plain), ["concept_id", "item_id"])
        made.append(said.groupBy("concept_id").agg(F.sum(F.col("said").cast("long")).alias("said"), F.sum(F.col("yes").cast("long")).alias("true")).select(F.lit(n).alias("n"), F.lit(ratio).alias("ratio"), "concept_id", "said", "true"))
    return made[0].union(made[1]).union(made[2]).union(made[3])


def diverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op.diverse_sample(Suite(spark, sf_dir, "w1").syn, 64)


def best_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Suite(spark, sf_dir, "w1")
    return plans.best_orders(s.queries(), op.truth_masks(s.items, s.plain))


def semantic_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ring, red and PROMO parts: calls per filter count after ordering by the probed estimates."""
    s = Suite(spark, sf_dir, "w1", [0])
    by_name = {c[0]: c for c in SUITES["w1"]}
    estimates = s.estimates().filter("m = 128").select("concept_id", F.col("selectivity").alias("estimate"))
    query = plans.SemanticQuery(s.items).where(by_name["PROMO"]).where(by_name["red"]).where(by_name["ring"]).optimize(estimates)
    return query.execute().agg(F.sum("calls").alias("calls"), F.sum(F.col("passed").cast("long")).alias("survivors"))


OTHERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "learned_radius": learned, "blended_radius": blended, "ball_count_vectors": vectors, "probe_configs_memory": memory,
    "synopsis_bytes": lambda spark, d: table(spark, d, "part").agg(F.count(F.lit(1)).alias("items"), (F.count(F.lit(1)) * COST.vector_bytes).alias("bytes")),
    "hist_equiwidth": equiwidth,
    "compression_ablation": compression, "diverse_sample": diverse, "best_order": best_order, "semantic_query": semantic_query,
    "radius_training_set": lambda spark, d: op.radius_training_set(items(spark, d, "w1")).select("draw", "concept_id", "k", "n", "radius"),
}


def method_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {}
    for suite, tag in (("w1", "part"), ("w2", "geo")):
        for name, make in BY_SUITE.items():
            found[f"{name}_{tag}"] = partial(lambda make, suite, spark, d: make(Suite(spark, d, suite)), make, suite)
    return found | OTHERS
