"""Both experiments with every method: probed, compressed, learned and blended radius against sample profiling; training on another collection.

The probed radius has exact answers on the probe, the compressed one answers from compressed state (128 items at a ratio of 0.9, 64 at 0.8,
32 at 0.6: about equal memory); each is blended with the learned radius too.
The learned radius is the linear one, fitted on a small training set, so that SQL gives the same results; keys that end in `net` take
the neural net and the full training set instead.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import operators as op
from .functions import q_error
from .methods import COST, Suite, interval, r6, summary
from .oracles import EST_ALL, GROUPS, IT, MASKS, ORDERS, PROBED, PROFILE, QUERIES, SAMPLE, SIGN, TRUTH, VEC, sql
from .sources import items, kept

#: Draws, items of a draw and concepts of a draw in the training set of the linear radius.
TRAINING = (10, 100, 20)
OTHER = {"w1": "w2", "w2": "w1"}
RADIUS_METHODS = ("probed", "learned", "blended", "compressed", "blended_compressed")


class AllMethods(Suite):
    """A suite whose runs hold all methods. trained_on: the suite whose collection trains the radius; net: by the neural net."""

    def __init__(self, spark: SparkSession, sf_dir: str, suite: str, trained_on: str | None = None, net: bool = False):
        super().__init__(spark, sf_dir, suite)
        self.source, self.net = (self.items if trained_on in (None, suite) else items(spark, sf_dir, trained_on)), net

    def learned(self) -> DataFrame:
        """concept_id, radius."""
        if self.net:
            return op.LearnedRadius.fit(op.radius_training_set(self.source)).transform(self.concepts).select("concept_id", "radius")
        return op.linear_radius(op.radius_training_set(self.source, *TRAINING), self.concepts).select("concept_id", "radius")

    def radii(self) -> DataFrame:
        """method, m, seed, concept_id, radius; one ball count serves them all."""
        probed, compressed, learned = self.probed(), self.compressed(), self.learned()
        fixed = learned.withColumns({"seed": F.lit(0), "m": F.lit(0)})
        blends = [op.blended_radius(own, learned, ["concept_id"]) for own in (probed, compressed)]
        made = (probed, fixed, blends[0], compressed, blends[1])
        return reduce(DataFrame.union, (r.select(F.lit(name).alias("method"), "m", "seed", "concept_id", "radius") for name, r in zip(RADIUS_METHODS, made, strict=True)))

    def compressed(self) -> DataFrame:
        """seed, m, concept_id, k, n, radius of the probe whose answers come from compressed state."""
        drawn = op.hash_sample(self.items, 128, self.seeds)
        picked, weights = drawn.select("item_id", "toks").dropDuplicates(["item_id"]), op.token_importance(self.items)
        kept = reduce(DataFrame.union, (op.compress_state(picked, weights, ratio).select("item_id", F.lit(n).alias("m"), "kept") for n, ratio in op.PROBE_CONFIGS))
        sized = op.embed_items(drawn).withColumn("m", F.explode(F.array(*(F.lit(n) for n, _ in op.PROBE_CONFIGS)))).filter("slot <= m")
        known = sized.join(kept, ["item_id", "m"], "left").withColumn("toks", F.coalesce("kept", F.array().cast("array<string>")))
        both = known.crossJoin(F.broadcast(self.concepts))
        dist = both.select("seed", "m", "concept_id", "item_id", op.cosine_distance("vec", "norm2", "cvec", "cnorm2").alias("dist"), op.holds().alias("yes"))
        return op.probed_radius(dist, ["seed", "m", "concept_id"])

    def runs(self) -> DataFrame:
        keys = ["method", "m", "seed", "concept_id"]
        counted = self.ball(self.radii(), keys).select(*keys, F.col("selectivity").alias("estimate"))
        profile = self.profile().select(F.lit("profile").alias("method"), "m", "seed", "concept_id", "estimate")
        return counted.union(profile).withColumn("latency", COST.estimation())

    def calls(self) -> DataFrame:
        return kept(super().calls())  # the overheads and their bests read it several times


def reductions(s: Suite) -> DataFrame:
    """How much less overhead than the best sample profiling the best setting of each method has."""
    best = s.means().groupBy("n_filters", "method").agg(F.min("mean").alias("least"))
    profile = best.filter("method = 'profile'").select("n_filters", F.col("least").alias("own"))
    return best.filter(F.col("method").isin(*RADIUS_METHODS)).join(F.broadcast(profile), "n_filters").select("n_filters", "method", r6(1 - F.col("least") / F.col("own")).alias("reduction"))


def best_settings(s: Suite) -> DataFrame:
    return s.means().groupBy("method", "n_filters").agg(F.min(F.struct("mean", "m")).alias("b")).select("method", "n_filters", "b.m", r6(F.col("b.mean")).alias("mean"))


def shift(spark: SparkSession, sf_dir: str, suite: str) -> DataFrame:
    """Q-errors of the learned radius, trained on its own collection and on the other one."""
    made = []
    for source in (suite, OTHER[suite]):
        s = AllMethods(spark, sf_dir, suite, source)
        truth = s.truth().select("concept_id", "total", F.col("selectivity").alias("truth"))
        found = s.ball(s.learned(), ["concept_id"]).select("concept_id", "selectivity").join(F.broadcast(truth), "concept_id")
        made.append(found.select("concept_id", F.lit(source).alias("trained_on"), F.round(q_error(F.col("selectivity"), F.col("truth"), F.col("total")), 9).alias("q_error")))
    return made[0].union(made[1])


ALL: dict[str, Callable[[AllMethods], DataFrame]] = {
    "linear_radius": lambda s: s.learned().select("concept_id", F.round("radius", 9).alias("radius")),
    "estimate_all": lambda s: s.runs().filter("method <> 'profile'").select("method", "m", "seed", "concept_id", "estimate"),
    "qerror_summary_all": summary, "overhead_ci_all": interval, "best_config_all": best_settings, "overhead_reduction_all": reductions,
}
NET: dict[str, Callable[[AllMethods], DataFrame]] = {"qerror_summary_net": summary, "overhead_reduction_net": reductions}


def experiment_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
    for suite, tag in (("w1", "part"), ("w2", "geo")):
        for net, keys in ((False, ALL), (True, NET)):
            for name, make in keys.items():
                found[f"{name}_{tag}"] = partial(lambda make, suite, net, spark, d: make(AllMethods(spark, d, suite, net=net)), make, suite, net)
        found[f"domain_shift_{tag}"] = partial(lambda suite, spark, d: shift(spark, d, suite), suite)
    return found


def training(source: str, found: str) -> str:
    """Tables of the training set on the collection `source`, and concept_id, radius under the name `found`."""
    draws, subset, per_draw = TRAINING
    return f"""{found}_p AS (SELECT draw, item_id, toks FROM (SELECT draw, item_id, toks, row_number() OVER (PARTITION BY draw ORDER BY md5(draw || ':' || item_id), item_id) AS r FROM {source} CROSS JOIN range({draws}) d(draw)) WHERE r <= {subset}),
{found}_h AS (SELECT DISTINCT draw, unnest(list_concat(list_transform(toks, lambda t: [t]), list_transform(range(2, len(toks) + 1), lambda i: toks[1:i]))) AS all_of FROM {found}_p),
{found}_c AS (SELECT draw, concept_id, all_of FROM (SELECT draw, all_of, array_to_string(all_of, '&') AS concept_id, row_number() OVER (PARTITION BY draw ORDER BY md5(draw || ':' || array_to_string(all_of, '&')), array_to_string(all_of, '&')) AS r FROM {found}_h) WHERE r <= {per_draw}),
{found}_s AS (SELECT t, i, {SIGN} AS s FROM (SELECT DISTINCT unnest(toks) AS t FROM {found}_p) CROSS JOIN range(128) r(i)),
{found}_i AS (SELECT item_id, i, sum(s)::BIGINT AS v FROM (SELECT item_id, unnest(toks) AS t FROM (SELECT DISTINCT item_id, toks FROM {found}_p)) JOIN {found}_s USING (t) GROUP BY ALL),
{found}_v AS (SELECT concept_id, i, sum(s)::BIGINT AS v FROM (SELECT concept_id, unnest(all_of) AS t FROM (SELECT DISTINCT concept_id, all_of FROM {found}_c)) JOIN {found}_s USING (t) GROUP BY ALL),
{found}_n AS (SELECT item_id, sum(v * v)::BIGINT AS n1 FROM {found}_i GROUP BY ALL), {found}_m AS (SELECT concept_id, sum(v * v)::BIGINT AS n2, sum(v * v * v * v)::BIGINT AS n4 FROM {found}_v GROUP BY ALL),
{found}_d AS (SELECT draw, concept_id, item_id, list_has_all(toks, all_of) AS yes, CASE WHEN n1 * n2 > 0 THEN 1 - d / sqrt(n1::DOUBLE * n2::DOUBLE) ELSE 1.0 END AS dist
  FROM (SELECT draw, concept_id, item_id, any_value(toks) AS toks, any_value(all_of) AS all_of, sum(a.v * b.v)::BIGINT AS d FROM {found}_p JOIN {found}_c USING (draw) JOIN {found}_i a USING (item_id) JOIN {found}_v b USING (concept_id, i) GROUP BY ALL)
  JOIN {found}_n USING (item_id) JOIN {found}_m USING (concept_id)),
{found}_r AS (SELECT draw, concept_id, coalesce(max(dist) FILTER (WHERE r = k + 1), 2.000001) AS radius FROM (SELECT *, row_number() OVER (PARTITION BY draw, concept_id ORDER BY dist, item_id) AS r, sum(yes::INT) OVER (PARTITION BY draw, concept_id) AS k, count(*) OVER (PARTITION BY draw, concept_id) AS n FROM {found}_d) WHERE k < n GROUP BY ALL),
{found}_l AS (SELECT regr_slope(radius, n4::DOUBLE / (n2::DOUBLE * n2::DOUBLE)) AS a, regr_intercept(radius, n4::DOUBLE / (n2::DOUBLE * n2::DOUBLE)) AS b FROM {found}_r JOIN {found}_m USING (concept_id)),
{found} AS (SELECT concept_id, a * x + b AS radius FROM (SELECT concept_id, sum(v * v * v * v)::BIGINT::DOUBLE / (sum(v * v)::BIGINT::DOUBLE * sum(v * v)::BIGINT::DOUBLE) AS x FROM cv GROUP BY concept_id) CROSS JOIN {found}_l)"""


SECONDS = "CASE method WHEN 'profile' THEN m * 1.0 WHEN 'probed' THEN 0.9 WHEN 'compressed' THEN 0.9 WHEN 'learned' THEN 0.017 WHEN 'blended' THEN 0.917 WHEN 'blended_compressed' THEN 0.917 ELSE 0 END"
COMPRESSED = """wt AS (SELECT t, count(*) AS w FROM (SELECT unnest(toks) AS t FROM it) GROUP BY t),
kt AS (SELECT m, item_id, list(t) AS kept FROM (SELECT m, ratio, item_id, t, size, row_number() OVER (PARTITION BY m, item_id ORDER BY w DESC, md5(t), t) AS r
  FROM (SELECT item_id, len(toks) AS size, unnest(toks) AS t FROM it) JOIN wt USING (t) CROSS JOIN (VALUES (128, 0.9), (64, 0.8), (32, 0.6)) c(m, ratio)) WHERE r <= ceil((1 - ratio) * size) GROUP BY ALL),
ca AS (SELECT seed, m, concept_id, item_id, dist, list_has_all(kept, all_of) AND (len(any_of) = 0 OR list_has_any(kept, any_of)) AS said FROM hs JOIN kt USING (item_id) JOIN di USING (item_id) JOIN co USING (concept_id) WHERE slot <= m),
pc AS (SELECT seed, m, concept_id, coalesce(max(dist) FILTER (WHERE r = k + 1), 2.000001) AS radius FROM (
  SELECT *, row_number() OVER (PARTITION BY seed, m, concept_id ORDER BY dist, item_id) AS r, sum(said::INT) OVER (PARTITION BY seed, m, concept_id)::BIGINT AS k FROM ca) GROUP BY ALL)"""
ESTIMATES = """ra AS (SELECT 'probed' AS method, m, seed, concept_id, radius FROM pr UNION ALL SELECT 'compressed', m, seed, concept_id, radius FROM pc UNION ALL SELECT 'learned', 0, 0, concept_id, radius FROM lr
  UNION ALL SELECT 'blended', m, seed, concept_id, 0.5::DOUBLE * pr.radius + 0.5::DOUBLE * lr.radius FROM pr JOIN lr USING (concept_id)
  UNION ALL SELECT 'blended_compressed', m, seed, concept_id, 0.5::DOUBLE * pc.radius + 0.5::DOUBLE * lr.radius FROM pc JOIN lr USING (concept_id)),
ee AS (SELECT method, m, seed, concept_id, count(*) FILTER (WHERE dist < radius) / count(*) AS estimate FROM ra JOIN di USING (concept_id) GROUP BY ALL)"""
Q = "greatest(greatest(estimate, 1 / total) / greatest(truth, 1 / total), greatest(truth, 1 / total) / greatest(estimate, 1 / total))"
ALL_RUNS = f"""runs AS (SELECT method, m, seed, concept_id, estimate, {SECONDS} AS latency FROM (SELECT * FROM ee UNION ALL SELECT 'profile', m, seed, concept_id, estimate FROM sp)),
qe AS (SELECT method, m, seed, concept_id, latency, {Q} AS q FROM runs JOIN tr USING (concept_id))"""
ALL_COST = f"""ov AS (SELECT c.method, c.m, c.seed, c.query_id, c.n_filters, c.n_filters * c.each AS est_s, c.calls - p.calls AS plan_s
  FROM (SELECT *, {SECONDS} AS each FROM cc) c JOIN cc p ON c.query_id = p.query_id AND p.method = 'perfect')"""


def experiment_oracles() -> dict[str, str]:
    found = {}
    for s, tag in (("w1", "part"), ("w2", "geo")):
        known = (VEC, TRUTH, SAMPLE, PROBED, COMPRESSED, training("it", "lr"), ESTIMATES, PROFILE, ALL_RUNS)
        chain = (*known, QUERIES, MASKS, EST_ALL, ORDERS, ALL_COST, GROUPS)
        other = IT[OTHER[s]].replace("it AS", "ot AS", 1)
        trained = "SELECT concept_id, '{}' AS trained_on, count(*) FILTER (WHERE dist < radius) / count(*) AS estimate FROM {} JOIN di USING (concept_id) GROUP BY ALL"
        found |= {
            f"linear_radius_{tag}": sql(s, VEC, training("it", "lr"), "SELECT concept_id, round(radius, 9) AS radius FROM lr"),
            f"estimate_all_{tag}": sql(s, VEC, SAMPLE, PROBED, COMPRESSED, training("it", "lr"), ESTIMATES, "SELECT method, m, seed, concept_id, estimate FROM ee"),
            f"qerror_summary_all_{tag}": sql(s, *known, "SELECT method, m, round(quantile_cont(q, 0.05), 6) AS p5, round(quantile_cont(q, 0.5), 6) AS p50, round(quantile_cont(q, 0.95), 6) AS p95, round(avg(latency), 6) AS latency_s FROM qe GROUP BY ALL"),
            f"overhead_ci_all_{tag}": sql(s, *chain, "SELECT method, m, n_filters, round(mean, 6) AS mean, round(mean - 2.093 * sd / sqrt(runs), 6) AS low, round(mean + 2.093 * sd / sqrt(runs), 6) AS high FROM me WHERE runs > 1"),
            f"best_config_all_{tag}": sql(s, *chain, "SELECT method, n_filters, m, round(mean, 6) AS mean FROM (SELECT *, row_number() OVER (PARTITION BY method, n_filters ORDER BY mean, m) AS r FROM me) WHERE r = 1"),
            f"overhead_reduction_all_{tag}": sql(s, *chain, "SELECT a.n_filters, a.method, round(1 - min(a.mean) / min(b.mean), 6) AS reduction FROM me a JOIN me b ON a.n_filters = b.n_filters AND b.method = 'profile' WHERE a.method IN ('probed', 'learned', 'blended', 'compressed', 'blended_compressed') GROUP BY ALL"),
            f"domain_shift_{tag}": sql(s, VEC, TRUTH, other, training("it", "lr"), training("ot", "lo"), f"SELECT concept_id, trained_on, round({Q}, 9) AS q_error FROM ({trained.format(s, 'lr')} UNION ALL {trained.format(OTHER[s], 'lo')}) JOIN tr USING (concept_id)"),
        }
    return found
