"""What the training-data operators share: table access, text keys, tables in the shared folder, leaving out listed rows."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: Lists of up to so many narrow rows are broadcast (some tens of MB); longer ones are shuffled.
BROADCAST_ROWS = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only; null counts as empty. Pure ASCII texts take the fast built-in path."""
    text = F.coalesce(text, F.lit(""))
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def fold(number: Column) -> Column:
    """crc32(id as text) mod 4, the fold that holds out a quarter of the documents."""
    return F.crc32(number.cast("string").cast("binary")) % 4


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share. A local session without one gets a temporary folder; a cluster must name one."""
    sc = spark.sparkContext
    folder = sc._jsc.sc().getCheckpointDir()
    if folder.isDefined():
        return folder.get()
    named = sc.getConf().get("spark.checkpoint.dir")
    if not named and not (sc.master or "").startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def shared_table(df: DataFrame, partitions: int | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it back: cuts the lineage, survives lost executors, is computed once.

    The files go when the application ends.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    (df if partitions is None else df.coalesce(partitions)).write.option("compression", "zstd").parquet(path)
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path)


def fresh_names(df: DataFrame, n: int) -> list[str]:
    """n column names that df does not have, in any case."""
    taken, found, i = {c.lower() for c in df.columns}, [], 0
    while len(found) < n:
        if f"own_{i}" not in taken:
            found.append(f"own_{i}")
        i += 1
    return found


def without(df: DataFrame, listed: DataFrame, keys: list[str], keep: bool = False) -> DataFrame:
    """The rows of df whose keys (null equals null) are not listed; with keep, those that are. A list of counted, bounded size is broadcast, so that texts stay where they are."""
    listed = listed.select(*(F.col(k).alias(f"{k}_listed") for k in keys)).distinct()
    few = listed.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    same = [F.col(k).eqNullSafe(F.col(f"{k}_listed")) for k in keys]
    return df.join(F.broadcast(listed) if few else listed, same, "left_semi" if keep else "left_anti")
