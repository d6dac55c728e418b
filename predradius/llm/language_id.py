"""Language identification: multinomial naive Bayes over hashed character n-grams.

Texts are lower-cased, characters other than letters become one blank each, and n-grams of 1 to `longest` characters fall into
2^bits buckets. Bucket counts per language are summed by the cluster from at most `training_rows` rows (chosen by a hash,
a documented bound of the classifier); the matrix of log probabilities goes to the workers as one array of a few MB, whatever the
input. Texts are scored whole, batch by batch: the n-grams of many texts form one sparse document-by-bucket matrix (row starts and
bucket columns, one entry for each occurrence), which is multiplied by the log-probability matrix.

Edge cases: text that is null or has no letter is `und` with score 0; rows without a language are not learned from;
without any training row every text is `und`; rows that repeat an id are scored each by itself; of languages with equal scores
the first by name is taken; a long text is spread over several matrices, whose scores add up; extra columns are ignored, whatever
their names; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MULTIPLIERS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F, 0x165667B1], dtype=np.uint32)
#: Code points in a slice of a text, and entries in a sparse matrix, beyond which it is closed; texts read into memory at once.
SLICE, TEXTS = 1 << 18, 256
_LETTERS: list[np.ndarray] = []


def letters() -> np.ndarray:
    if not _LETTERS:
        _LETTERS.append(np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000))
    return _LETTERS[0]


def folded(text: str | None) -> np.ndarray | None:
    """Code points with all but letters blanked; None if there is no letter."""
    if not text:
        return None
    points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype="<u4")
    known = letters()[points]
    return np.where(known, points, 32).astype(np.uint32) if known.any() else None


def gram_buckets(points: np.ndarray, longest: int, bits: int) -> Iterator[np.ndarray]:
    """The bucket of every n-gram, slice by slice."""
    for start in range(0, len(points), SLICE):
        part = points[start : start + SLICE + longest - 1]
        rolled = np.zeros(len(part), np.uint32)
        for n in range(1, longest + 1):
            ends = len(part) - n + 1
            if ends <= 0:
                break
            rolled = (rolled[:ends] + part[n - 1 :]) * MULTIPLIERS[n % 5]
            rolled ^= rolled >> np.uint32(15)
            own = rolled[:SLICE]
            yield ((own * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - bits)).astype(np.int64)


def training_counts(rows: DataFrame, longest: int, bits: int) -> DataFrame:
    """lang, bucket, n over (text, lang) rows; bucket -1 counts documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                if (points := folded(text.as_py())) is not None:
                    own = sums.setdefault(lang, np.zeros((1 << bits) + 1, np.int64))
                    own[-1] += 1
                    for buckets in gram_buckets(points, longest, bits):
                        own[:-1] += np.bincount(buckets, minlength=1 << bits)
        for lang, own in sums.items():
            at = np.flatnonzero(own)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(np.where(at == 1 << bits, -1, at)), pa.array(own[at])], ["lang", "bucket", "n"])

    return rows.mapInArrow(count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))


class LanguageModel:
    def __init__(self, langs: list[str], weights: np.ndarray, priors: np.ndarray, longest: int, bits: int):
        self.langs, self.weights, self.priors, self.longest, self.bits = langs, weights, priors, longest, bits

    @classmethod
    def fit(cls, rows: DataFrame, training_rows: int = 20_000, longest: int = 4, bits: int = 16, smoothing: float = 0.5) -> LanguageModel:
        """rows: id, text, lang. Learns from all rows or from `training_rows` of them, by a hash of the id."""
        rows = rows.toDF("id", "text", "lang").filter("lang is not null and text is not null")
        n = rows.count()
        if n > training_rows:
            rows = rows.filter(F.pmod(F.xxhash64("id"), F.lit(1 << 20)) < int((1 << 20) * training_rows / n))
        counts = training_counts(rows.select("text", "lang"), longest, bits).toPandas()
        langs = sorted(counts["lang"].unique())
        table = np.zeros((1 << bits, len(langs)))
        priors = np.zeros(len(langs))
        for j, lang in enumerate(langs):
            own = counts[counts["lang"] == lang]
            grams = own[own["bucket"] >= 0]
            table[grams["bucket"].to_numpy(), j] = grams["n"].to_numpy()
            priors[j] = own.loc[own["bucket"] < 0, "n"].sum()
        weights = np.log(table + smoothing) - np.log(table.sum(axis=0, keepdims=True) + smoothing * (1 << bits))
        return cls(langs, weights.astype(np.float32), np.log(priors) - np.log(priors.sum()) if len(langs) else priors, longest, bits)

    def totals(self, texts: list[np.ndarray]) -> np.ndarray:
        """Log probability of each language (columns) for each text (rows of code points): sparse matrices of bounded size times the weights."""
        total = np.tile(self.priors.astype(np.float64), (len(texts), 1))
        rows: list[int] = []
        columns: list[np.ndarray] = []
        held = 0

        def multiply() -> None:
            starts = np.cumsum([0, *map(len, columns)][:-1])
            np.add.at(total, rows, np.add.reduceat(self.weights[np.concatenate(columns)], starts, axis=0, dtype=np.float64))

        for row, points in enumerate(texts):
            for buckets in gram_buckets(points, self.longest, self.bits):
                rows.append(row)
                columns.append(buckets)
                held += len(buckets)
                if held >= SLICE:
                    multiply()
                    rows, columns, held = [], [], 0
        if held:
            multiply()
        return total

    def predict_batch(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """The likeliest language of each text and its probability."""
        points = [folded(text) for text in texts]
        known = [i for i, own in enumerate(points) if own is not None] if self.langs else []
        langs, scores = ["und"] * len(texts), np.zeros(len(texts))
        if known:
            total = self.totals([points[i] for i in known])
            best = total.argmax(axis=1)
            scores[known] = 1 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1)
            for i, j in zip(known, best.tolist(), strict=True):
                langs[i] = self.langs[j]
        return langs, scores

    def predict(self, text: str | None) -> tuple[str, float]:
        langs, scores = self.predict_batch([text])
        return langs[0], float(scores[0])

    def transform(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """doc_id, lang_pred, score."""
        model = docs.sparkSession.sparkContext.broadcast(self)

        def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for at in range(0, batch.num_rows, TEXTS):
                    part = batch.slice(at, TEXTS)
                    langs, scores = model.value.predict_batch(part.column(1).to_pylist())
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(langs, pa.string()), pa.array(scores)], ["doc_id", "lang_pred", "score"])

        return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(score, "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame, held_out: Column, **options) -> DataFrame:
    """doc_id, held_out, lang_pred, score; learned from the rows that are not held out."""
    model = LanguageModel.fit(docs.filter(~held_out).select("doc_id", "text", "lang"), **options)
    return model.transform(docs).withColumn("held_out", held_out)
