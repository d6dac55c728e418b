"""Queries of variants: radius rules, given cells as a synopsis, filters of unlike latency, residency of the probe, prompts, latency of whole queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import operators as op
from . import plans
from .functions import DIMS, cosine_distance, prompt
from .methods import COST, Suite
from .oracles import HELD, HELD_QUERIES, PROBED, QUERIES, SAMPLE, TOKENS, TRUTH, VEC, sql
from .sources import held_concepts, items

RULES = ("next", "mid", "tight")
MEMORY_BUDGET, LOAD_S = 4_000_000_000, 0.1


def radius_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where between the k-th and the (k+1)-th probe distance the radius lies."""
    s = Suite(spark, sf_dir, "w1", [0])
    dist = op.distances(op.embed_items(op.hash_sample(s.items, 64, [0])), s.concepts)
    made = [op.probed_radius(dist, ["concept_id"], rule).select(F.lit(rule).alias("rule"), "concept_id", "k", F.round("radius", 9).alias("radius")) for rule in RULES]
    return made[0].union(made[1]).union(made[2])


def cell_centroids(syn: DataFrame, cell: str) -> DataFrame:
    """cell, n, vec, norm2: the sum of the member vectors stands for a cell; partial sums leave the tasks, no vectors."""
    sums = F.array(*(F.sum(F.col("vec")[i].cast("long")) for i in range(DIMS)))
    found = syn.groupBy(cell).agg(F.count(F.lit(1)).alias("n"), sums.alias("vec"))
    return found.withColumn("norm2", F.expr("aggregate(vec, 0L, (s, x) -> s + x * x)"))


def cell_synopsis_hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells count as a whole if their centroid is inside the ball (brands are the cells)."""
    s = Suite(spark, sf_dir, "w1")
    cells = cell_centroids(s.syn.withColumn("cell", F.element_at("toks", -1)), "cell")
    dist = cosine_distance("vec", "norm2", "cvec", "cnorm2", "0L")
    inside = F.when(dist < 0.8, F.col("n")).otherwise(F.lit(0))
    return cells.crossJoin(F.broadcast(s.concepts)).groupBy("concept_id").agg(F.sum(inside).alias("hits"), F.sum("n").alias("total"))


def order_by_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Filters of unlike latency go by (selectivity - 1) / latency; at equal latency that is ascending selectivity."""
    s = Suite(spark, sf_dir, "w1")
    latency = F.col("pos") % 3 + 1
    known = s.truth().join(F.broadcast(s.plain.select("concept_id", "pos")), "concept_id").select(F.lit("perfect").alias("method"), "concept_id", ((F.col("selectivity") - 1) / latency).alias("rank"))
    return plans.order_filters(s.queries(), known, ["method"], "rank").select("query_id", "concept_id", "step")


def probe_residency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """States beyond the fast memory are loaded for each predicate; a state's size goes by the tokens that the collection's items keep."""
    kept = F.floor((F.col("kept_percent") * F.size("toks") + 99) / 100).cast("long")
    shares = spark.createDataFrame([(k,) for k in (10, 20, 40, 100)], "kept_percent int")
    sums = items(spark, sf_dir, "w1").filter("toks IS NOT NULL").crossJoin(F.broadcast(shares)).groupBy("kept_percent").agg((F.sum(kept) / F.sum(F.size("toks"))).alias("share"))
    rows = sums.withColumn("n", F.explode(F.array(*map(F.lit, (32, 64, 128, 256, 512)))))
    fits = F.floor(F.lit(float(MEMORY_BUDGET)) / (F.lit(float(COST.state_bytes)) * F.col("share"))).cast("int")
    resident = F.least("n", fits)
    return rows.select("n", "kept_percent", resident.alias("resident"), F.round(COST.batch_s + LOAD_S * (F.col("n") - resident), 6).alias("latency_s"))


def prompt_render(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The prompts of all predicates that the items hold."""
    return held_concepts(items(spark, sf_dir, "w1")).select("concept_id", prompt(F.col("concept_id")).alias("prompt"))


def latency_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimation seconds of a query by its filters, drawn from the collection's tokens: one after the other, and all in one batch."""
    q = Suite(spark, sf_dir, "w1").token_queries().groupBy("query_id", "n_filters").agg(F.count(F.lit(1)).alias("filters"))
    each = F.explode(F.create_map(*(F.lit(x) for m in (("learned", COST.learned_s), ("probed", COST.batch_s), ("blended", COST.learned_s + COST.batch_s)) for x in m))).alias("method", "each")
    return q.select("query_id", "filters", each).select("query_id", "method", F.round(F.col("filters") * F.col("each"), 6).alias("serial_s"), F.round("each", 6).alias("batched_s"))


def variant_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (radius_rules, cell_synopsis_hard, order_by_rank, probe_residency, prompt_render, latency_model)}


def variant_oracles() -> dict[str, str]:
    ranked = """x AS (SELECT concept_id, dist, row_number() OVER (PARTITION BY concept_id ORDER BY dist, item_id) AS r, sum(yes::INT) OVER (PARTITION BY concept_id)::BIGINT AS k
      FROM hs JOIN di USING (item_id) WHERE seed = 0 AND slot <= 64),
    y AS (SELECT concept_id, k, max(dist) FILTER (WHERE r = k + 1) AS up, max(dist) FILTER (WHERE r = k) AS lo, min(dist) AS first FROM x GROUP BY ALL)"""
    cells = """ce AS (SELECT toks[-1] AS cell, i, sum(v)::BIGINT AS v FROM iv JOIN it USING (item_id) GROUP BY ALL), cn AS (SELECT cell, sum(v * v)::BIGINT AS n1 FROM ce GROUP BY ALL),
    sz AS (SELECT toks[-1] AS cell, count(*) AS n FROM it GROUP BY ALL), dc AS (SELECT cell, concept_id, sum(ce.v * cv.v)::BIGINT AS d FROM ce JOIN cv USING (i) GROUP BY ALL)"""
    return {
        "radius_rules": sql("w1", VEC, SAMPLE, ranked, """SELECT rule, concept_id, k, round(CASE rule WHEN 'next' THEN coalesce(up, 2.000001) WHEN 'mid' THEN coalesce((up + coalesce(lo, up)) / 2, 2.000001) ELSE coalesce(lo + 1e-9, first) END, 9) AS radius
          FROM y CROSS JOIN (SELECT unnest(['next', 'mid', 'tight']) AS rule)"""),
        "cell_synopsis_hard": sql("w1", VEC, cells, """SELECT concept_id, sum(CASE WHEN (CASE WHEN n1 * n2 > 0 THEN 1 - d / sqrt(n1::DOUBLE * n2::DOUBLE) ELSE 1 END) < 0.8 THEN n ELSE 0 END)::BIGINT AS hits, sum(n)::BIGINT AS total
          FROM dc JOIN cn USING (cell) JOIN sz USING (cell) JOIN cnn USING (concept_id) GROUP BY ALL"""),
        "order_by_rank": sql("w1", TRUTH, QUERIES, "SELECT query_id, concept_id, row_number() OVER (PARTITION BY query_id ORDER BY (truth - 1) / (pos % 3 + 1), concept_id)::INT AS step FROM qu JOIN tr USING (concept_id)"),
        "probe_residency": sql("w1", """SELECT n, kept AS kept_percent, least(n, fits) AS resident, round(0.9::DOUBLE + 0.1::DOUBLE * (n - least(n, fits)), 6) AS latency_s FROM (SELECT n, kept, floor(4000000000 / (300000000.0::DOUBLE * share))::INT AS fits
          FROM (SELECT unnest([32, 64, 128, 256, 512])::INT AS n) CROSS JOIN (SELECT kept, sum((kept * len(toks) + 99) // 100)::BIGINT / sum(len(toks))::BIGINT AS share FROM it CROSS JOIN (SELECT unnest([10, 20, 40, 100])::INT AS kept) GROUP BY kept))"""),
        "prompt_render": sql("w1", HELD, "SELECT concept_id, 'Look at the item. Does it show the following: ' || concept_id || '? Answer with yes or no only.' AS prompt FROM hc"),
        "latency_model": sql("w1", TOKENS, HELD_QUERIES, """SELECT query_id, method, round(f * each, 6) AS serial_s, round(each, 6) AS batched_s FROM (SELECT query_id, count(*) AS f FROM qu GROUP BY ALL)
          CROSS JOIN (SELECT unnest(['learned', 'probed', 'blended']) AS method, unnest([0.017, 0.9, 0.917])::DOUBLE AS each)"""),
    }
