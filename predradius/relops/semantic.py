"""Relational, UDF and streaming operators around a semantic filter, with SQL for the same results."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from .. import operators as op
from ..functions import cosine_distance, dot
from ..oracles import PROBED, SAMPLE, VEC, sql
from ..sources import concepts, items, shared_folder, table

#: Anchors that one nested-loop join broadcasts; more anchors are taken block by block.
ANCHOR_BLOCK = 4096


def ring(spark: SparkSession, name: str = "ring") -> DataFrame:
    return op.embed_concepts(concepts(spark, "w1").filter(F.col("concept_id") == name))


def part_distances(spark: SparkSession, sf_dir: str, name: str = "ring") -> DataFrame:
    return op.distances(op.embed_items(items(spark, sf_dir, "w1")), ring(spark, name))


def synopsis_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The synopsis written with a folder per cell (brand); one cell is read back."""
    path = f"{shared_folder(spark)}/synopsis-{uuid.uuid4().hex}"
    syn = op.embed_items(items(spark, sf_dir, "w1")).select("item_id", "vec", F.col("norm2").cast("long").alias("norm2"), F.element_at("toks", -1).alias("cell"))
    syn.repartition("cell").write.partitionBy("cell").parquet(path)
    return spark.read.parquet(path).filter("cell = 'Brand#13'").select("item_id", F.col("norm2").cast("long").alias("norm2"))


def hybrid_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relational filter first, at the scan; then membership of the part in a ball."""
    inside = part_distances(spark, sf_dir).filter("dist < 0.7").select("item_id")
    line = table(spark, sf_dir, "lineitem").filter("l_quantity < 5").select("l_orderkey", "l_linenumber", "l_partkey")
    return line.join(inside, F.col("l_partkey") == F.col("item_id"), "left_semi").select("l_orderkey", "l_linenumber")


def join_theta_ball(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors inside the ball of radius 0.75 around every anchor (ids divisible by 20), in blocks of anchors."""
    syn = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"))
    syn = syn.withColumn("norm2", dot("vec", "vec", "0D"))
    anchors = syn.filter("vec_id % 20 = 0").select(F.col("vec_id").alias("anchor"), F.col("vec").alias("cvec"), F.col("norm2").alias("cnorm2"))
    blocks = max(1, -(-anchors.count() // ANCHOR_BLOCK))
    found = None
    for b in range(blocks):
        own = anchors.filter(F.pmod(F.xxhash64("anchor"), F.lit(blocks)) == b) if blocks > 1 else anchors
        near = syn.crossJoin(F.broadcast(own)).select("anchor", "vec_id", F.round(cosine_distance("vec", "norm2", "cvec", "cnorm2", "0D"), 6).alias("dist")).filter("dist < 0.75")
        found = near if found is None else found.union(near)
    return found


def topk_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return part_distances(spark, sf_dir).select("item_id", F.round("dist", 9).alias("dist")).orderBy("dist", "item_id").limit(25)


def udf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance of every stored vector to the first one by a vectorised pandas function."""
    syn = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    own = syn.filter("vec_id = 0").first()
    at = np.array(own["embedding"] if own else [], dtype=np.float64)

    @pandas_udf("double")
    def distance(vec: pd.Series) -> pd.Series:
        block = np.stack(vec.to_numpy()).astype(np.float64) if len(vec) else np.empty((0, len(at)))
        return pd.Series(np.round(1 - (block @ at) / np.sqrt((block * block).sum(axis=1) * (at @ at)), 6))

    return syn.select("vec_id", distance("embedding").alias("dist"))


def udf_map_in_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same distances from blocks of vectors."""
    own = ring(spark).first()
    at, norm = np.array(own["cvec"], dtype=np.float64), float(own["cnorm2"])

    def distances(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                block = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)
                dist = 1 - (block @ at) / np.sqrt((block * block).sum(axis=1) * norm)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.round(dist, 9))], ["item_id", "dist"])

    return op.embed_items(items(spark, sf_dir, "w1")).select("item_id", "vec").mapInArrow(distances, "item_id long, dist double")


def probe_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = op.hash_sample(items(spark, sf_dir, "w1"), 64, [0])
    return op.distances(op.embed_items(drawn), op.embed_concepts(concepts(spark, "w1")))


def radius_of(dist: np.ndarray, yes: np.ndarray) -> float:
    k, inner = int(yes.sum()), np.sort(dist)
    return float(inner[k]) if k < len(inner) else op.ALL


def udaf_radius(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The probed radius of each predicate by a grouped aggregate over its probe of 64 rows."""

    @pandas_udf("double")
    def radius(dist: pd.Series, yes: pd.Series) -> float:
        return radius_of(dist.to_numpy(), yes.to_numpy())

    return probe_distances(spark, sf_dir).groupBy("concept_id").agg(radius("dist", "yes").alias("radius"))


def apply_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    def summary(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"concept_id": [rows["concept_id"].iloc[0]], "k": [int(rows["yes"].sum())], "n": [len(rows)], "radius": [radius_of(rows["dist"].to_numpy(), rows["yes"].to_numpy())]})

    return probe_distances(spark, sf_dir).groupBy("concept_id").applyInPandas(summary, "concept_id string, k long, n long, radius double")


def udtf_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The words of every part's name as rows, by a Python table function."""

    @udtf(returnType="pos int, token string")
    class Tokens:
        def eval(self, text: str):
            for i, token in enumerate((text or "").split(" ")):
                yield i, token

    spark.udtf.register("name_tokens", Tokens)
    table(spark, sf_dir, "part").createOrReplaceTempView("part")
    return spark.sql("SELECT p_partkey, t.pos, t.token FROM part, LATERAL name_tokens(p_name) t")


def sample_by(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sample by hash with a share for each type: the same however the rows are dealt."""
    share = F.when(F.col("p_type") == "PROMO", "4000").when(F.col("p_type").isin("SMALL", "LARGE"), "2000").otherwise("0800")
    return table(spark, sf_dir, "part").filter(F.substring(F.md5(F.concat(F.lit("s:"), F.col("p_partkey").cast("string"))), 1, 4) < share).select("p_partkey", "p_type")


def approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the distinct-count sketch is within four standard errors of the exact count, by group."""
    line = table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("exact"))
    return line.select("l_returnflag", "exact", (F.abs(F.col("a") / F.col("exact") - 1) < 0.08).alias("within"))


def approx_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the rank of the approximate median is within its error bound, by group."""
    line = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_extendedprice")
    mid = line.groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", 0.5, 1000).alias("m"), F.count(F.lit(1)).alias("n"))
    below = line.join(F.broadcast(mid), "l_returnflag").groupBy("l_returnflag", "n").agg(F.sum((F.col("l_extendedprice") <= F.col("m")).cast("long")).alias("below"))
    return below.select("l_returnflag", "n", (F.abs(F.col("below") / F.col("n") - 0.5) < 0.01).alias("within"))


def hist_equidepth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty buckets of equal depth by distinct value: bounds from exact percentiles, then one aggregation; no global sort."""
    part = table(spark, sf_dir, "part").select("p_retailprice")
    cuts = part.agg(F.percentile("p_retailprice", F.array(*(F.lit(i / 20) for i in range(1, 20)))).alias("cuts"))
    at = F.size(F.filter("cuts", lambda c: c < F.col("p_retailprice")))
    return part.crossJoin(F.broadcast(cuts)).groupBy(at.alias("bucket")).agg(F.count(F.lit(1)).alias("n"), F.min("p_retailprice").alias("lo"), F.max("p_retailprice").alias("hi"))


def chain_survivors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items that pass all filters of each query, from the histogram of truth masks."""
    from ..plans import random_queries

    plain = concepts(spark, "w1")
    need = random_queries(spark, plain).groupBy("query_id").agg(F.sum(F.expr("shiftleft(1L, pos)")).alias("need"))
    masks = op.truth_masks(items(spark, sf_dir, "w1"), plain)
    return need.join(F.broadcast(masks), F.col("mask").bitwiseAND(F.col("need")) == F.col("need"), "left").groupBy("query_id").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("survivors"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (synopsis_roundtrip, hybrid_filter, join_theta_ball, topk_nearest, udf_pandas, udf_map_in_arrow, udaf_radius, apply_in_pandas, udtf_tokens, sample_by, hist_equidepth, chain_survivors)
} | {"agg_approx_distinct": approx_distinct, "agg_approx_percentile": approx_percentile}

UNIT = "list_sum(list_transform(list_zip({0}, {1}), lambda z: z[1]::DOUBLE * z[2]::DOUBLE))"
MASK = "(SELECT item_id, sum(CASE WHEN (list_has_all(toks, all_of) AND (len(any_of) = 0 OR list_has_any(toks, any_of))) THEN 1::BIGINT << pos ELSE 0 END)::BIGINT AS mask FROM it CROSS JOIN co GROUP BY ALL)"


def oracles() -> dict[str, str]:
    from ..oracles import QUERIES as DRAWN

    dist = "SELECT item_id, round(dist, 9) AS dist FROM di WHERE concept_id = 'ring'"
    return {
        "synopsis_roundtrip": sql("w1", VEC, "SELECT item_id, n1 AS norm2 FROM inn JOIN it USING (item_id) WHERE toks[-1] = 'Brand#13'"),
        "hybrid_filter": sql("w1", VEC, "SELECT l_orderkey, l_linenumber FROM lineitem JOIN di ON item_id = l_partkey WHERE concept_id = 'ring' AND dist < 0.7 AND l_quantity < 5"),
        "join_theta_ball": f"SELECT * FROM (SELECT a.vec_id AS anchor, e.vec_id, round(1 - {UNIT.format('e.embedding', 'a.embedding')} / sqrt({UNIT.format('e.embedding', 'e.embedding')} * {UNIT.format('a.embedding', 'a.embedding')}), 6) AS dist FROM embeddings e CROSS JOIN (SELECT * FROM embeddings WHERE vec_id % 20 = 0) a) WHERE dist < 0.75",
        "topk_nearest": sql("w1", VEC, f"SELECT * FROM ({dist}) ORDER BY dist, item_id LIMIT 25"),
        "udf_pandas": f"SELECT e.vec_id, round(1 - {UNIT.format('e.embedding', 'a.embedding')} / sqrt({UNIT.format('e.embedding', 'e.embedding')} * {UNIT.format('a.embedding', 'a.embedding')}), 6) AS dist FROM embeddings e CROSS JOIN (SELECT * FROM embeddings WHERE vec_id = 0) a",
        "udf_map_in_arrow": sql("w1", VEC, dist),
        "udaf_radius": sql("w1", VEC, SAMPLE, PROBED, "SELECT concept_id, radius FROM pr WHERE seed = 0 AND m = 64"),
        "apply_in_pandas": sql("w1", VEC, SAMPLE, PROBED, "SELECT concept_id, k, n, radius FROM pr WHERE seed = 0 AND m = 64"),
        "udtf_tokens": "SELECT p_partkey, (generate_subscripts(t, 1) - 1)::INT AS pos, unnest(t) AS token FROM (SELECT p_partkey, string_split(p_name, ' ') AS t FROM part)",
        "sample_by": "SELECT p_partkey, p_type FROM part WHERE substr(md5('s:' || p_partkey), 1, 4) < CASE WHEN p_type = 'PROMO' THEN '4000' WHEN p_type IN ('SMALL', 'LARGE') THEN '2000' ELSE '0800' END",
        "agg_approx_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS exact, true AS within FROM lineitem GROUP BY ALL",
        "agg_approx_percentile": "SELECT l_returnflag, count(*) AS n, true AS within FROM lineitem GROUP BY ALL",
        "hist_equidepth": "SELECT len(list_filter(cuts, lambda c: c < p_retailprice))::INT AS bucket, count(*) AS n, min(p_retailprice) AS lo, max(p_retailprice) AS hi FROM part CROSS JOIN (SELECT quantile_cont(p_retailprice, [" + ", ".join(str(i / 20) for i in range(1, 20)) + "]) AS cuts FROM part) GROUP BY 1",
        "chain_survivors": sql("w1", DRAWN, f"SELECT query_id, count(mask) AS survivors FROM (SELECT query_id, sum(1::BIGINT << pos)::BIGINT AS need FROM qu GROUP BY ALL) LEFT JOIN {MASK} ON (mask & need) = need GROUP BY ALL"),
    }
