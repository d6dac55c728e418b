"""Toxicity scores from a weighted lexicon matched by an Aho-Corasick automaton.

Texts are lower-cased and folded: look-alike letters of other scripts and digits or signs that stand for letters become
plain letters. The lexicon holds folded words and word beginnings with the log odds of toxic against clean documents that hold
them. It is learned from at most `training_rows` labelled rows (chosen by a hash, a documented bound of the
classifier), counted by the cluster, and at most `lexicon_size` entries of it are kept, so what goes to the workers has
a fixed bound. A text's matches (the heaviest entry at each word, none inside an exception phrase) give three measures:
the heaviest weight, the sum of weights, and that sum normalised by length; a logistic function of them, fitted on
labelled rows that the lexicon has not seen, is the score.

Digits and signs that end a word are read both as they are and as letters; an exception phrase must end where a word does.

Edge cases: null and empty texts have no match and get the score of a text without matches; without labels of both kinds
a fixed small lexicon and fixed coefficients are used; repeated texts are learned from once; texts are scored whole, in one pass; equal
weights at one word count once; an empty table gives no rows; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Characters that are read as the Latin letter in whose list they stand.
LOOKALIKES = {
    "a": "аɑα@4", "b": "ЬƄ8", "c": "сϲ", "d": "ԁ", "e": "еєε3", "g": "ɡ9", "h": "һ", "i": "іιı1!|", "j": "ј", "k": "κк", "l": "ӏ", "m": "м",
    "n": "ո", "o": "оο0", "p": "рρ", "q": "ԛ", "r": "г", "s": "ѕ5$", "t": "τт7", "u": "υս", "v": "ν", "w": "ԝ", "x": "хχ", "y": "уγ", "z": "ᴢ2",
}
FOLD = {ord(c): letter for letter, others in LOOKALIKES.items() for c in others if ord(c) > 127}
SIGNS = {ord(c): letter for letter, others in LOOKALIKES.items() for c in others if ord(c) < 128}
#: Digits and signs stand for letters before a letter.
IN_WORD = re.compile(r"[0-9@$!|]+(?=[^\W\d_])")
#: Digits and signs that end a word; they may be letters as well as numbers.
ENDING = re.compile(r"(?<=[^\W\d_])[0-9@$!|]+(?![^\W_])")
#: Used where no labels can be learned from, and the phrases in which a word is meant otherwise.
SEED = {w: 6.0 for w in ("idiot", "moron", "scum", "stupid", "loser", "pathetic", "worthless", "disgusting")}
EXCEPTIONS = ("trash can", "trash bin", "clown fish", "idiot proof", "the loser of the match", "worthless stock")
WORD = re.compile(r"[^\W\d_]+")
PREFIXES = range(4, 10)


def fold_text(text: str | None) -> str:
    if not text:
        return ""
    if not text.isascii():  # full-width and accented letters become plain ones
        text = "".join(c for c in unicodedata.normalize("NFKD", text) if not unicodedata.combining(c))
    return IN_WORD.sub(lambda m: m[0].translate(SIGNS), text.lower().translate(FOLD))


def word_features(folded: str) -> set[str]:
    """Every word of the text, and its beginnings (marked by a final *)."""
    words = set(WORD.findall(folded))
    return words | {w[:n] + "*" for w in words for n in PREFIXES if len(w) > n}


def feature_counts(rows: DataFrame) -> DataFrame:
    """feature, pos, neg over (text, toxic) rows: in how many toxic and clean documents it occurs."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pos, neg = Counter(), Counter()

        def flush() -> pa.RecordBatch:
            names = list(pos.keys() | neg.keys())
            batch = pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([pos[x] for x in names], pa.int64()), pa.array([neg[x] for x in names], pa.int64())], ["feature", "pos", "neg"])
            pos.clear()
            neg.clear()
            return batch

        for batch in batches:
            for text, toxic in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                (pos if toxic else neg).update(word_features(fold_text(text.as_py())))
            if len(pos) + len(neg) > 500_000:
                yield flush()
        yield flush()

    return rows.mapInArrow(count, "feature string, pos long, neg long").groupBy("feature").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))


def outside(best: dict[int, float], holes: list[tuple[int, int]]) -> dict[int, float]:
    """The matches that start outside all holes (from, to), in one sweep over both."""
    if not holes:
        return best
    kept, covered, i, holes = {}, -1, 0, sorted(holes)
    for at in sorted(best):
        while i < len(holes) and holes[i][0] <= at:
            covered, i = max(covered, holes[i][1]), i + 1
        if at > covered:
            kept[at] = best[at]
    return kept


class Lexicon:
    """weights: folded word, or word beginning with a final *, -> weight."""

    def __init__(self, weights: dict[str, float], exceptions=EXCEPTIONS):
        self.weights, self.exceptions, self.automaton = weights, [fold_text(x) for x in exceptions], None

    def __getstate__(self):
        return self.__dict__ | {"automaton": None}

    def matches(self, text: str | None) -> tuple[list[float], int]:
        """The heaviest weight at each matching word outside exception phrases, and the text's length in characters."""
        import ahocorasick

        if self.automaton is None:
            self.automaton = ahocorasick.Automaton()
            for entry, weight in self.weights.items():
                self.automaton.add_word(entry.rstrip("*"), (len(entry.rstrip("*")), max(weight, self.weights.get(entry.rstrip("*") + "*", 0)), weight if entry.endswith("*") else self.weights.get(entry + "*", 0.0)))
            for phrase in self.exceptions:
                self.automaton.add_word(" " + phrase, (len(phrase), None, None))
            self.automaton.make_automaton()
        folded, best, holes = fold_text(text), {}, []
        self.scan(" " + folded, best, holes)
        if ENDING.search(folded):  # digits that end a word are read as letters too
            self.scan(" " + ENDING.sub(lambda m: m[0].translate(SIGNS), folded), best, holes)
        return list(outside(best, holes).values()), len(folded)

    def scan(self, folded: str, best: dict[int, float], holes: list[tuple[int, int]]) -> None:
        """Adds the heaviest weight at the place of each matching word, and the places of exception phrases."""
        for end, (n, whole, part) in self.automaton.iter(folded):
            start, inside = end - n + 1, end + 1 < len(folded) and folded[end + 1].isalpha()
            if whole is None:
                if not inside:
                    holes.append((start, end))
            elif not folded[start - 1].isalpha():
                weight = part if inside else whole
                if weight > best.get(start, 0.0):
                    best[start] = weight

    def measures(self, text: str | None) -> tuple[float, float, float]:
        weights, n = self.matches(text)
        total = sum(weights)
        return (max(weights, default=0.0), math.log1p(total), total / math.sqrt(1 + n / 100))


def weigh(counts: DataFrame, n_pos: int, n_neg: int, lexicon_size: int, least_pos: int, least_weight: float) -> dict[str, float]:
    odds = F.log((F.col("pos") + 0.5) / (n_pos + 1)) - F.log((F.col("neg") + 0.5) / (n_neg + 1))
    rows = counts.withColumn("w", odds).filter((F.col("pos") >= least_pos) & (F.col("w") >= least_weight))
    return {r["feature"]: r["w"] for r in rows.orderBy(F.desc("w"), "feature").limit(lexicon_size).collect()}


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.02, steps: int = 50) -> np.ndarray:
    """Coefficients, the constant last, by Newton's method."""
    x = np.hstack([x, np.ones((len(x), 1))])
    beta = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        hessian = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(x.shape[1])
        step = np.linalg.solve(hessian, x.T @ (y - p) - ridge * beta)
        beta += step
        if np.abs(step).max() < 1e-8:
            break
    return beta


class ToxicityModel:
    def __init__(self, lexicon: Lexicon, beta: np.ndarray):
        self.lexicon, self.beta = lexicon, beta

    @classmethod
    def fit(cls, rows: DataFrame, training_rows: int = 20_000, lexicon_size: int = 5_000, least_pos: int = 5, least_weight: float = 2.5) -> ToxicityModel:
        """rows: text, toxic (0 or 1). Two thirds of the texts teach the lexicon, one third the coefficients."""
        rows = rows.toDF("text", "toxic").filter("toxic is not null").withColumn("key", F.xxhash64(F.coalesce("text", F.lit(""))))
        n = rows.count()
        if n > training_rows:
            rows = rows.filter(F.pmod("key", F.lit(1 << 20)) < int((1 << 20) * training_rows / n))
        rows = rows.groupBy("key").agg(F.first("text").alias("text"), F.max("toxic").alias("toxic"))
        rows = rows.persist()
        try:
            sizes = {(r["third"], r["toxic"]): r["count"] for r in rows.groupBy((F.pmod(F.shiftright("key", 20), F.lit(3)) == 0).alias("third"), "toxic").count().collect()}
            if not sizes.get((False, 1)) or not sizes.get((False, 0)):
                return cls(Lexicon(SEED), np.array([0.5, 0.5, 0.0, -3.0]))
            teach = F.pmod(F.shiftright("key", 20), F.lit(3)) != 0
            lexicon = Lexicon(weigh(feature_counts(rows.filter(teach).select("text", "toxic")), sizes[False, 1], sizes[False, 0], lexicon_size, least_pos, least_weight))
            if not sizes.get((True, 1)) or not sizes.get((True, 0)):
                return cls(lexicon, np.array([0.5, 0.5, 0.0, -3.0]))

            def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    found = [lexicon.measures(text.as_py()) for text in batch.column(0)]
                    yield pa.RecordBatch.from_arrays([*(pa.array([x[j] for x in found], pa.float64()) for j in range(3)), batch.column(1)], ["a", "b", "c", "toxic"])

            seen = rows.filter(~teach).select("text", F.col("toxic").cast("long")).mapInArrow(measure, "a double, b double, c double, toxic long").toPandas()
            return cls(lexicon, logistic(seen[["a", "b", "c"]].to_numpy(), seen["toxic"].to_numpy(float)))
        finally:
            rows.unpersist()

    def score(self, text: str | None) -> float:
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, float(np.dot(self.beta[:-1], self.lexicon.measures(text)) + self.beta[-1])))))

    def transform(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """doc_id, score."""
        model = docs.sparkSession.sparkContext.broadcast(self)

        def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = model.value
            for batch in batches:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([own.score(text.as_py()) for text in batch.column(1)], pa.float64())], ["doc_id", "score"])

        return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(score, "doc_id long, score double")

    def keep_clean(self, docs: DataFrame, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
        """The documents scored below the threshold, with their columns, in one pass."""
        model = docs.sparkSession.sparkContext.broadcast(self)
        at = docs.columns.index(text_col)

        def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = model.value
            for batch in batches:
                yield batch.filter(pa.array([own.score(text.as_py()) < threshold for text in batch.column(at)], pa.bool_()))

        return docs.mapInArrow(keep, docs.schema)


def train(docs: DataFrame, labels: DataFrame, held_out: Column, **options) -> ToxicityModel:
    """A model learned from the labelled documents that are not held out."""
    known = labels.select("doc_id", "toxic").filter("toxic is not null")
    return ToxicityModel.fit(docs.filter(~held_out).select("doc_id", "text").join(known, "doc_id").select("text", "toxic"), **options)
