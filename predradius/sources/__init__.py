"""Tables, collections (items with tokens) and concept suites."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's checkpoint folder, or a temporary one of a local session without any."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not (spark.sparkContext.master or "").startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return named or tempfile.mkdtemp(prefix="shared-")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def kept(df: DataFrame) -> DataFrame:
    """The rows, computed once and read back from the shared folder: for small results that a query uses several times."""
    path = f"{shared_folder(df.sparkSession)}/kept-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """The rows of a scan over at least as many tasks as run at once; a small file of many short rows comes in one or two."""
    tasks = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(tasks) if df.rdd.getNumPartitions() < tasks else df


# Concept suites, (concept_id, tokens that all must hold, tokens of which one must hold).
SUITES = {
    "w1": [
        ("ring|rod|bolt|plate", [], ["ring", "rod", "bolt", "plate"]), ("large|small", [], ["large", "small"]), ("hot|cold", [], ["hot", "cold"]), ("PROMO", ["type:PROMO"], []), ("red", ["red"], []),
        ("Brand#1|2|3", [], ["Brand#1", "Brand#2", "Brand#3"]), ("ring", ["ring"], []), ("Brand#13", ["Brand#13"], []), ("ring&PROMO", ["ring", "type:PROMO"], []), ("small&widget", ["small", "widget"], []),
        ("red&ring", ["red", "ring"], []), ("hot&gear", ["hot", "gear"], []), ("blue&Brand#19", ["blue", "Brand#19"], []), ("STANDARD&Brand#8", ["type:STANDARD", "Brand#8"], []),
        ("red&ring&PROMO", ["red", "ring", "type:PROMO"], []), ("cold&anvil&LARGE", ["cold", "anvil", "type:LARGE"], []), ("new&bolt&MEDIUM", ["new", "bolt", "type:MEDIUM"], []), ("hot&gear&Brand#4", ["hot", "gear", "Brand#4"], []),
    ],
    "w2": [
        ("AFRICA|AMERICA|MIDDLE EAST", [], ["AFRICA", "AMERICA", "MIDDLE EAST"]), ("ASIA|EUROPE", [], ["ASIA", "EUROPE"]), ("AUTOMOBILE|FURNITURE", [], ["AUTOMOBILE", "FURNITURE"]), ("MACHINERY", ["MACHINERY"], []),
        ("EUROPE", ["EUROPE"], []), ("BUILDING", ["BUILDING"], []), ("AFRICA", ["AFRICA"], []), ("NATION_7", ["NATION_7"], []), ("NATION_12", ["NATION_12"], []), ("AFRICA&BUILDING", ["AFRICA", "BUILDING"], []),
        ("ASIA&FURNITURE", ["ASIA", "FURNITURE"], []), ("EUROPE&HOUSEHOLD", ["EUROPE", "HOUSEHOLD"], []), ("NATION_12&MACHINERY", ["NATION_12", "MACHINERY"], []), ("NATION_7&BUILDING", ["NATION_7", "BUILDING"], []),
        ("NATION_3&AUTOMOBILE", ["NATION_3", "AUTOMOBILE"], []), ("NATION_20&FURNITURE", ["NATION_20", "FURNITURE"], []),
    ],
}


def items(spark: SparkSession, sf_dir: str, suite: str) -> DataFrame:
    """item_id, toks of the suite's collection."""
    if suite == "w1":
        part = spread(table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_type", "p_brand"))
        return part.select(F.col("p_partkey").alias("item_id"), F.concat(F.split("p_name", " "), F.array(F.concat(F.lit("type:"), "p_type"), "p_brand")).alias("toks"))
    customer = spread(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment"))
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    where = F.broadcast(nation.join(region, nation["n_regionkey"] == region["r_regionkey"]).select("n_nationkey", "n_name", "r_name"))
    return customer.join(where, F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("item_id"), F.array("r_name", "n_name", "c_mktsegment").alias("toks"))


def concepts(spark: SparkSession, suite: str) -> DataFrame:
    """concept_id, all_of, any_of, pos (its number in the suite)."""
    rows = [(c, a, o, i) for i, (c, a, o) in enumerate(SUITES[suite])]
    return spark.createDataFrame(rows, "concept_id string, all_of array<string>, any_of array<string>, pos int")


def held_concepts(found: DataFrame, wide: bool = True) -> DataFrame:
    """concept_id, all_of, any_of of the predicates that a collection's items hold: every token and, if wide, every beginning of a token list."""
    lists = F.transform("toks", lambda t: F.array(t))
    if wide:
        beginnings = F.when(F.size("toks") > 1, F.transform(F.sequence(F.lit(2), F.size("toks")), lambda i: F.slice("toks", F.lit(1), i))).otherwise(F.array().cast("array<array<string>>"))
        lists = F.concat(lists, beginnings)
    held = found.select(F.explode(lists).alias("all_of")).distinct()
    return held.select(F.array_join("all_of", "&").alias("concept_id"), "all_of", F.array().cast("array<string>").alias("any_of"))
