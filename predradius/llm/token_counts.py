"""Token counts of documents in flat token files that have no index.

A file is one run of little-endian uint16 ids in which an end-of-document id follows each document. Files are read in
blocks that cut documents anywhere. A vectorised search finds the separators of each block; a prefix scan over block
summaries (first within runs of blocks, then over the runs, so that no task holds all blocks of a large file) gives each
block the tokens that earlier blocks left open and the ordinal of its first document.

Edge cases: empty documents count 0; tokens after a file's last separator are reported as an open tail, not as a
document; a block without separators adds to the next; null text counts as empty; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shared_table
from .tokens import encoder

END_OF_DOCUMENT = 50256
BLOCKS = "file_id long, block long, tokens binary, doc_ids array<long>"
FOUND = "file_id long, block long, n_tokens long, gaps array<long>, tail long"


def token_blocks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_tokens: int = 1 << 16,
                 separator: int = END_OF_DOCUMENT, ranks_file: str | None = None, pattern: str | None = None) -> DataFrame:
    """The flat files, one for each partition of docs, in blocks; doc_ids is the writer's own list, which no scan uses."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, file_id, block = encoder(ranks_file, pattern).encode, TaskContext.get().partitionId(), 0
        ends = np.array([separator], dtype="<u2")
        open_parts: list[np.ndarray] = []
        size, ids = 0, []

        def cut(parts: list[np.ndarray]) -> tuple[list[bytes], np.ndarray]:
            flat = np.concatenate(parts)
            whole = len(flat) // block_tokens * block_tokens
            return [flat[i : i + block_tokens].tobytes() for i in range(0, whole, block_tokens)], flat[whole:]

        def row(data: bytes, doc_ids: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays(
                [pa.array([file_id], pa.int64()), pa.array([block], pa.int64()), pa.array([data], pa.binary()), pa.array([doc_ids], pa.list_(pa.int64()))],
                ["file_id", "block", "tokens", "doc_ids"])

        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                flat = np.append(encode(text.as_py()).astype("<u2"), ends)
                open_parts.append(flat)
                size += len(flat)
                if size >= block_tokens:
                    blocks, left = cut(open_parts)
                    # The separator of this document lies in the block that its last token fell into.
                    for i, data in enumerate(blocks):
                        last = i == len(blocks) - 1
                        closes = ids + ([doc_id] if last and not len(left) else [])
                        yield row(data, closes)
                        ids, block = [], block + 1
                    open_parts, size = [left], len(left)
                    if len(left):
                        ids = [doc_id]
                else:
                    ids.append(doc_id)
        if size:
            yield row(np.concatenate(open_parts).tobytes(), ids)

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(write, BLOCKS)


def read_token_files(spark: SparkSession, path: str, block_tokens: int = 1 << 20) -> DataFrame:
    """file_id, block, tokens of existing flat files. file_id is the hash of the path."""
    files = spark.read.format("binaryFile").load(path).select(F.xxhash64("path").alias("file_id"), "content", "length")
    at = F.sequence(F.lit(0), F.floor((F.greatest("length", F.lit(1)) - 1) / (2 * block_tokens)))
    blocks = files.select("file_id", "content", F.explode(at).alias("block"))
    return blocks.select("file_id", "block", F.expr(f"substring(content, cast(block * {2 * block_tokens} + 1 as int), {2 * block_tokens})").alias("tokens"))


def find_separators(blocks: DataFrame, separator: int = END_OF_DOCUMENT) -> DataFrame:
    """Per block: its tokens, the tokens before each separator since the one before (or the block's start), its tail."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, gaps, tails = [], [], []
            for data in batch.column(2):
                tokens = np.frombuffer(data.as_py() or b"", dtype="<u2")
                at = np.flatnonzero(tokens == separator)
                gaps.append(np.diff(at, prepend=-1) - 1)
                sizes.append(len(tokens))
                tails.append(len(tokens) - 1 - (int(at[-1]) if len(at) else -1))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(sizes, pa.int64()), pa.array([g.tolist() for g in gaps], pa.list_(pa.int64())), pa.array(tails, pa.int64())],
                [x.split()[0] for x in FOUND.split(", ")])

    return blocks.select("file_id", "block", "tokens").mapInArrow(scan, FOUND)


def stitch(found: DataFrame, run_blocks: int = 1024) -> DataFrame:
    """file_id, block, first_ordinal, lengths (token count of each document that ends in the block), open_tokens after it."""
    before = (Window.unboundedPreceding, -1)
    inner = Window.partitionBy("file_id", "run").orderBy("block").rowsBetween(*before)
    outer = Window.partitionBy("file_id").orderBy("run").rowsBetween(*before)
    closes = F.size("gaps")
    last = F.when(closes > 0, F.col("at") + F.col("n_tokens") - F.col("tail"))  # position after the last separator
    blocks = found.withColumn("run", F.floor(F.col("block") / run_blocks))
    blocks = blocks.withColumns({"at": F.coalesce(F.sum("n_tokens").over(inner), F.lit(0)), "ordinal": F.coalesce(F.sum(closes).over(inner), F.lit(0))})
    blocks = blocks.withColumn("open_at", F.max(last).over(inner))
    runs = blocks.groupBy("file_id", "run").agg(F.sum("n_tokens").alias("run_tokens"), F.sum(closes).alias("run_closes"), F.max(last).alias("run_last"))
    runs = runs.withColumns({"run_at": F.coalesce(F.sum("run_tokens").over(outer), F.lit(0)), "run_ordinal": F.coalesce(F.sum("run_closes").over(outer), F.lit(0))})
    runs = runs.withColumn("run_open", F.coalesce(F.max(F.col("run_at") + F.col("run_last")).over(outer), F.lit(0)))
    joined = blocks.join(runs.select("file_id", "run", "run_at", "run_ordinal", "run_open"), ["file_id", "run"])
    opened = F.coalesce(F.col("run_at") + F.col("open_at"), F.col("run_open"))
    carry = F.col("run_at") + F.col("at") - opened
    lengths = F.transform("gaps", lambda g, i: F.when(i == 0, g + carry).otherwise(g))
    return joined.select(
        "file_id", "block", (F.col("run_ordinal") + F.col("ordinal")).alias("first_ordinal"), lengths.alias("lengths"),
        F.when(closes > 0, F.col("tail")).otherwise(F.col("tail") + carry).alias("open_tokens"))


def document_token_counts(docs: DataFrame, **options) -> DataFrame:
    """doc_id, file_id, ordinal, n_tokens: docs written as flat files, scanned, and told apart again."""
    blocks = shared_table(token_blocks(docs, **options))
    counts = stitch(find_separators(blocks, options.get("separator", END_OF_DOCUMENT)))
    both = counts.join(blocks.select("file_id", "block", "doc_ids"), ["file_id", "block"])
    rows = both.select("file_id", "first_ordinal", F.posexplode(F.arrays_zip("doc_ids", "lengths")).alias("i", "d"))
    return rows.select(F.col("d.doc_ids").alias("doc_id"), "file_id", (F.col("first_ordinal") + F.col("i")).cast("long").alias("ordinal"), F.col("d.lengths").alias("n_tokens"))
