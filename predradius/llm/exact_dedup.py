"""Exact deduplication by merging sorted runs of digests in binomial rounds.

Documents fall into `runs` runs, a power of the fan-in that is at least the number of shuffle partitions. A run holds one entry per
distinct text: digest, length and a second hash (an entry is verified by all three at every level), the identifier that stays,
and the number of copies. The number of a run has one digit for each round. In round k the `fan_in` runs that differ in digit k
alone exchange their entries: each takes over those whose hash has its digit k, and merges them in the order of their keys. After the
last round a run's number is made of the hash alone, so all entries of one text have met. A text that a third of all rows
share enters each merge as at most `fan_in` entries, whatever the number of rows, and the verdicts travel down the same rounds: in the
end each run's own rows are joined with one verdict per text, so no task ever sees all rows of one text.

Edge cases: null text counts as empty; rows equal in id and text are one document whose copies count in group_size;
rows without an id form groups among themselves and with others but only a non-null id can stay, if there is one; an id with
several texts is one document in each of their groups; an empty table gives an empty result; very long texts are hashed whole;
extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, fresh_names, shared_table, without

KEY = ["digest", "n_bytes", "check_hash"]


def run_count(df: DataFrame, fan_in: int) -> int:
    """The smallest power of the fan-in that gives every shuffle partition a run."""
    runs, wanted = fan_in, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    while runs < wanted:
        runs *= fan_in
    return runs


def digests(docs: DataFrame, runs: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One narrow row per row: id, verified text key and leaf run."""
    norm = docs.select(F.col(id_col).alias("doc_id"), ascii_lower(F.col(text_col)).alias("norm"))
    keyed = norm.select("doc_id", F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("digest"), F.octet_length("norm").alias("n_bytes"), F.xxhash64("norm").alias("check_hash"))
    return keyed.withColumn("run", F.pmod(F.xxhash64("doc_id"), F.lit(runs)).cast("int"))


def moved(run: Column, level: int, fan_in: int) -> Column:
    """The run that takes an entry over in a round: the entry's run with the digit of that level taken from the entry's hash."""
    step = fan_in**level
    own = F.floor(run / step) % fan_in
    wanted = F.pmod(F.floor(F.pmod("check_hash", F.lit(1 << 40)) / step), F.lit(fan_in))
    return (run + (wanted - own) * step).cast("int")


def merged(entries: DataFrame, keep: str) -> DataFrame:
    """The entries of each run, dealt by run and merged in the order of their keys; of equal keys one identifier stays."""
    known = F.col("keep_id").isNotNull() if keep == "max" else F.col("keep_id").isNull()
    pick = (F.max if keep == "max" else F.min)(F.struct(known.alias("known"), "keep_id"))
    whole = entries.repartition("run").groupBy("run", *KEY).agg(pick.alias("b"), F.sum("copies").alias("copies"))
    return whole.select("run", *KEY, F.col("b.keep_id").alias("keep_id"), "copies")


def verdicts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int | None = None, fan_in: int = 8, keep: str = "max") -> DataFrame:
    """doc_id, key, rows (that are equal in both), keep_id, group_size of each document."""
    runs = runs or run_count(docs, fan_in)
    leaves = digests(docs, runs, id_col, text_col).groupBy("run", *KEY, "doc_id").agg(F.count(F.lit(1)).alias("rows"))
    leaves = shared_table(leaves.sortWithinPartitions("run", *KEY))
    local = leaves.groupBy("run", *KEY).agg((F.max if keep == "max" else F.min)("doc_id").alias("keep_id"), F.sum("rows").alias("copies"))
    levels = [shared_table(local)]
    while fan_in ** (len(levels) - 1) < runs:
        level = len(levels) - 1
        levels.append(shared_table(merged(levels[-1].withColumn("run", moved(F.col("run"), level, fan_in)), keep)))
    verdict = levels.pop().filter("copies > 1").withColumnRenamed("copies", "group_size")
    # Down again, to the runs that hold the texts and then to their rows.
    while levels:
        below = levels.pop().select("run", *KEY)
        above = below.withColumn("up", moved(F.col("run"), len(levels), fan_in))
        verdict = above.join(verdict.withColumnRenamed("run", "up"), ["up", *KEY]).select("run", *KEY, "keep_id", "group_size")
    found = leaves.join(verdict, ["run", *KEY], "left")
    return found.select("doc_id", *KEY, "rows", F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"))


def exact_duplicates(docs: DataFrame, **options) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 and check_hash for each document.

    Options: id_col, text_col, runs, fan_in, and keep, 'max' or 'min': which identifier of equal texts stays.
    """
    kept = F.col("keep_id").eqNullSafe(F.col("doc_id")).alias("kept")
    return verdicts(docs, **options).select("doc_id", "keep_id", "group_size", kept, F.lower(F.hex("digest")).alias("text_sha256"), "check_hash")


def drop_exact_duplicates(docs: DataFrame, **options) -> DataFrame:
    """The documents that stay, with their columns. Rows equal in id and text stay once, and rows without an id once for each text."""
    text_col, id_col = options.get("text_col", "text"), options.get("id_col", "doc_id")
    kept = F.col("keep_id").eqNullSafe(F.col("doc_id"))
    marked = shared_table(verdicts(docs, **options).filter(~kept | (F.col("rows") > 1)).select("doc_id", "check_hash", kept.alias("kept")))
    own, key = fresh_names(docs, 2)
    keyed = docs.withColumns({own: F.col(id_col), key: F.xxhash64(ascii_lower(F.col(text_col)))})
    names = [f"`{c}`" for c in docs.columns]
    gone = marked.filter("not kept").select(F.col("doc_id").alias(own), F.col("check_hash").alias(key))
    left = without(keyed, gone, [own, key])
    repeated = marked.filter("kept").select(F.col("doc_id").alias(own), F.col("check_hash").alias(key))
    if repeated.limit(1).count():
        once = without(left, repeated, [own, key], keep=True).dropDuplicates([own, key])
        left = without(left, repeated, [own, key]).unionByName(once)
    return left.select(*names)
