"""Packing token sequences into windows by multiway differencing.

Each document's ids, with an end id, are cut into full windows and a rest of pieces of at most `piece` ids. The pieces of
a shard (about `shard_windows` windows, within one partition: no shuffle) are then dealt to k windows: every piece
starts as a partial partition of k bins, and the two partial partitions with the largest spread merge with opposing
imbalances, the heaviest bin of one with the lightest of the other, until one partition is left. k starts at the
smallest count that could hold the shard and rises whenever a window would exceed the capacity. A worker holds the
piece descriptors of one shard only.

Edge cases: null text counts as empty and still yields its end id; rows without an id are packed too, under a null id;
repeated rows are packed as often as they come, and ties of equal sizes go by their order in the partition; an empty table gives no
pieces; extra columns are ignored, whatever their names. Texts of any length are encoded whole. The string of the vocabulary's special
token inside a text becomes that token, as the tokenizer's own default has it.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import SPECIAL, encoder

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_tokens long"


def differencing(sizes: list[int], k: int) -> list[list[int]]:
    """Deals item indices to k bins of near-equal sums. A partial partition is its sorted non-empty bins."""
    if k == 1:
        return [list(range(len(sizes)))]
    # An entry: (-(spread), tie, sums descending, bins in that order); bins past the stored ones are empty.
    heap = [(-s, i, [s], [[i]]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    tie = len(sizes)
    while len(heap) > 1:
        _, _, sums_a, bins_a = heapq.heappop(heap)
        _, _, sums_b, bins_b = heapq.heappop(heap)
        free = k - len(sums_a)
        # b's heaviest bins go to a's empty bins first, then to its lightest.
        sums, bins = list(sums_a), list(bins_a)
        for j, (s, members) in enumerate(zip(sums_b, bins_b, strict=True)):
            if j < free:
                sums.append(s)
                bins.append(members)
            else:
                at = len(sums_a) - 1 - (j - free)
                sums[at] += s
                bins[at] = bins[at] + members
        order = sorted(range(len(sums)), key=sums.__getitem__, reverse=True)
        sums, bins = [sums[i] for i in order], [bins[i] for i in order]
        spread = sums[0] - (sums[-1] if len(sums) == k else 0)
        heapq.heappush(heap, (-spread, tie, sums, bins))
        tie += 1
    return heap[0][3] if heap else []


def windows(sizes: list[int], capacity: int) -> list[list[int]]:
    """Near-equal windows of at most `capacity`; their count rises until all fit."""
    k = -(-sum(sizes) // capacity)
    while True:
        dealt = differencing(sizes, k)
        if all(sum(sizes[i] for i in w) <= capacity for w in dealt):
            return dealt
        k += 1


def pack_partition(capacity: int, piece: int, shard_windows: int, end_id: int, ranks_file, pattern, special):
    end = np.array([end_id], dtype="<u4")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        ids_of = encoder(ranks_file, pattern, special).encode
        sequence = TaskContext.get().partitionId() << 40
        rest: list[tuple] = []  # doc_id, start, length, crc, doc_tokens
        rest_tokens = 0

        def flush(out: list[tuple], shard: list[tuple]) -> None:
            nonlocal sequence
            for window in windows([p[2] for p in shard], capacity):
                total, offset = sum(shard[i][2] for i in window), 0
                for i in window:
                    out.append((*shard[i], sequence, offset, total))
                    offset += shard[i][2]
                sequence += 1

        def rows(out: list[tuple]) -> pa.RecordBatch:
            names = [x.split()[0] for x in SCHEMA.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], pa.int64()) for j in range(len(names))], names)

        for batch in batches:
            out: list[tuple] = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                n = len(ids := np.append(ids_of(text.as_py()), end))
                full = n - n % capacity
                for start in range(0, full, capacity):
                    out.append((doc_id, start, capacity, zlib.crc32(ids[start : start + capacity].tobytes()), n, sequence, 0, capacity))
                    sequence += 1
                left = n - full
                if left:
                    parts = -(-left // piece)
                    cuts = [full + left * i // parts for i in range(parts + 1)]
                    for a, b in zip(cuts, cuts[1:], strict=False):
                        rest.append((doc_id, a, b - a, zlib.crc32(ids[a:b].tobytes()), n))
                    rest_tokens += left
                if rest_tokens >= shard_windows * capacity:
                    flush(out, rest)
                    rest, rest_tokens = [], 0
                if len(out) >= 20_000:
                    yield rows(out)
                    out = []
            if out:
                yield rows(out)
        if rest:
            out = []
            flush(out, rest)
            yield rows(out)

    return pack


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = 2048, piece: int = 256,
                   shard_windows: int = 128, end_id: int = 1, ranks_file: str | None = None, pattern: str | None = None,
                   special: dict[str, int] | None = SPECIAL) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, sequence_tokens.

    A sequence is padded to `capacity` unless its sequence_tokens is a power of two. special: strings in the texts that become ids of their own.
    """
    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(pack_partition(capacity, piece, shard_windows, end_id, ranks_file, pattern, special), SCHEMA)
