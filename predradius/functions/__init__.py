"""Column functions: the hashed joint embedding, distances, answers, error measures."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

DIMS = 128


def signs(token: str) -> np.ndarray:
    return np.unpackbits(np.frombuffer(hashlib.md5(token.encode()).digest(), np.uint8)).astype(np.int32) * 2 - 1


def sign_sums(toks: pa.Array) -> pa.Array:
    """vec, norm2 of each token list; no list: no vector; a null among the tokens: a vector of nulls."""
    count = len(toks)
    sizes = toks.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    coded = toks.flatten().dictionary_encode()
    unknown = np.zeros((1, DIMS), np.int32)  # stands for null tokens
    matrix = np.concatenate([*(signs(t)[None, :] for t in coded.dictionary.to_pylist()), unknown])
    at = coded.indices.fill_null(len(matrix) - 1).to_numpy(zero_copy_only=False)
    first, vec = np.cumsum(sizes) - sizes, np.zeros((count, DIMS), np.int32)
    broken = np.zeros(count, bool)
    for j in range(int(sizes.max(initial=0))):
        rows = np.flatnonzero(sizes > j)
        own = at[first[rows] + j]
        vec[rows] += matrix[own]
        broken[rows] |= own == len(matrix) - 1
    norm2 = (vec.astype(np.int64) ** 2).sum(axis=1).astype(np.int32)
    none = toks.is_null().to_numpy(zero_copy_only=False)
    values = pa.array(vec.ravel(), mask=np.repeat(broken, DIMS)) if broken.any() else pa.array(vec.ravel())
    ends = np.arange(count + 1, dtype=np.int32) * DIMS
    vectors = pa.ListArray.from_arrays(pa.array(ends), values, mask=pa.array(none)) if none.any() else pa.ListArray.from_arrays(pa.array(ends), values)
    return pa.StructArray.from_arrays([vectors, pa.array(norm2, mask=none | broken)], ["vec", "norm2"])


def sign_vector(toks: str) -> Column:
    """vec, norm2: sum of the tokens' sign vectors; a token's signs are the bits of its md5. Integers, so every engine agrees exactly.

    Each distinct token of an Arrow batch is hashed once, and rows add whole vectors.
    """
    return F.arrow_udf(sign_sums, "vec array<int>, norm2 int")(F.col(toks))


def dot(a: str, b: str, zero: str = "0") -> Column:
    return F.expr(f"aggregate(zip_with({a}, {b}, (x, y) -> x * y), {zero}, (s, x) -> s + x)")


def cosine_distance(a: str, norm_a: str, b: str, norm_b: str, zero: str = "0") -> Column:
    """1 - cosine; 1 where a vector is zero."""
    norms = F.sqrt(F.col(norm_a).cast("double") * F.col(norm_b).cast("double"))
    return F.when(norms > 0, 1 - dot(a, b, zero) / F.nullif(norms, F.lit(0.0))).otherwise(1.0)


def holds(toks: str = "toks") -> Column:
    """Whether an item's tokens fulfil a concept (all_of and any_of)."""
    return (F.size(F.array_except("all_of", toks)) == 0) & ((F.size("any_of") == 0) | F.arrays_overlap("any_of", toks))


def q_error(estimate: Column, truth: Column, total: Column) -> Column:
    """Ratio of estimate and truth, at least 1; zero on either side counts as one item."""
    least = 1 / total
    e, t = F.greatest(estimate, least), F.greatest(truth, least)
    return F.greatest(e / t, t / e)


def prompt(phrase: Column) -> Column:
    return F.concat(F.lit("Look at the item. Does it show the following: "), phrase, F.lit("? Answer with yes or no only."))
