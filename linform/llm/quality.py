"""Quality classifier: hashed word n-grams, logistic regression by follow-the-regularised-leader, sparse scoring.

Features of a text are word n-grams of one and two words, and n-grams of one and two word shapes (case, length
class, trailing marks, repeat of the word before), all hashed into one space; values are log counts scaled to
unit length. Training takes at most MAX_LABELLED labelled texts, those with the least hash of their id, which
one task visits in hash order for some passes; the weights (of fixed size) are broadcast, and each text is
scored as a sparse dot product, whatever its length.

Null texts count as empty: such a text has no features and scores by the bias alone. Labels that are null are not
learned from; labels that repeat are one label, labels of one id that differ are all learned from, of documents that
repeat an id the least text is. Without labels, all scores are one half. An empty table gives an empty result. Extra
columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.llm.common import asked_of, held, texts_of

#: Bits of the feature space; bound of the training sample; passes over it, and steps to make at least; rows in a batch out.
SPACE, MAX_LABELLED, PASSES, LEAST_STEPS, ROWS = 18, 12_000, 3, 4_000, 512
KEPT_WORDS = 150_000
_MARKS = re.compile(r"\W*\Z")


class Featurizer:
    """Text to (feature numbers, values). Keeps hashes of words in two generations."""

    def __init__(self, space: int = SPACE):
        self.shift = np.uint64(64 - space)
        self.new: dict[str, tuple[int, int]] = {}
        self.old: dict[str, tuple[int, int]] = {}

    def _word(self, word: str) -> tuple[int, int]:
        found = self.new.get(word)
        if found is None:
            found = self.old.get(word)
            if found is None:
                marks = _MARKS.search(word)[0][:3]
                kind = "U" if word.isupper() and len(word) > 1 else "T" if word[0].isupper() else "l"
                shape = f"{kind}{min(len(word), 40).bit_length()}{marks}"
                found = xxhash.xxh64_intdigest(word.lower().encode("utf-8", "surrogatepass"), 1), xxhash.xxh64_intdigest(shape.encode("utf-8", "surrogatepass"), 2)
            if len(self.new) >= KEPT_WORDS:
                self.old, self.new = self.new, {}
            self.new[word] = found
        return found

    def __call__(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        words = text.split()
        if not words:
            return np.zeros(0, np.int64), np.zeros(0)
        both = np.array([self._word(w) for w in words], np.uint64)
        word, shape = both[:, 0], both[:, 1].copy()
        with np.errstate(over="ignore"):
            shape[1:] ^= np.where(word[1:] == word[:-1], np.uint64(0x5851F42D4C957F2D), np.uint64(0))
            odd = np.uint64(0x9E3779B97F4A7C15)
            all_of = np.concatenate([word, word[:-1] * odd + word[1:], shape, shape[:-1] * odd + shape[1:]]) * odd >> self.shift
        at, n = np.unique(all_of, return_counts=True)
        value = np.log1p(n)
        return at.astype(np.int64), value / np.sqrt(value @ value)


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for logistic loss; the last weight is the bias."""

    def __init__(self, space: int = SPACE, alpha: float = 0.5, beta: float = 1.0, l1: float = 1e-4, l2: float = 1e-4):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((1 << space) + 1), np.zeros((1 << space) + 1)

    def weights(self, at: np.ndarray | slice = slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        step = (self.beta + np.sqrt(n)) / self.alpha + self.l2
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / step)

    def learn(self, at: np.ndarray, value: np.ndarray, label: int) -> None:
        w = self.weights(at)
        g = (1 / (1 + np.exp(-np.clip(w @ value, -40, 40))) - label) * value
        sigma = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        self.z[at] += g - sigma * w
        self.n[at] += g * g


def sampled(docs: DataFrame, known: DataFrame, label: str, max_labelled: int) -> DataFrame:
    """(h, doc_id, label, text) of at most max_labelled labels of least id hash, in one partition in that order.

    The sample is drawn from (doc_id, label) alone, so it is bounded before it is broadcast to the documents; of
    documents that repeat an id the least text is taken, so the rows are bounded, too.
    """
    order = F.xxhash64("doc_id")
    ids = known.where(F.col(label).isNotNull()).select(order.alias("h"), "doc_id", label).orderBy("h", "doc_id", label).limit(max_labelled)
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(ids), "doc_id")
    rows = rows.groupBy("h", "doc_id", label).agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))
    return rows.select("h", "doc_id", label, "text").repartition(1).sortWithinPartitions("h", "doc_id", label)


def train(docs: DataFrame, known: DataFrame, max_labelled: int = MAX_LABELLED, passes: int = PASSES, space: int = SPACE) -> np.ndarray:
    """(doc_id, text) and (doc_id, label) -> weights, learned in one task from at most max_labelled labels."""
    rows = sampled(docs, known.withColumn("label", F.col("label").cast("int")), "label", max_labelled)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features, model, kept = Featurizer(space), Ftrl(space), []
        bias_at, bias_value = np.array([1 << space]), np.ones(1)
        for batch in batches:
            labels = batch.column(2).to_pylist()
            for label, column in zip(labels, range(batch.num_rows), strict=True):
                if len(kept) < max_labelled:
                    at, value = features(batch.column(3)[column].as_py() or "")
                    kept.append((np.append(at, bias_at).astype(np.int32), np.append(value, bias_value).astype(np.float32), label))
        for _ in range(max(passes, LEAST_STEPS // max(1, len(kept)))):
            for at, value, label in kept:
                model.learn(at, value.astype(float), label)
        yield pa.RecordBatch.from_pydict({"w": pa.array([model.weights().astype(np.float32).tobytes()], pa.binary())})

    made = rows.mapInArrow(run, "w binary").collect()  # one row of fixed size
    return np.frombuffer(made[0].w, np.float32) if made else np.zeros((1 << space) + 1, np.float32)


def score(docs: DataFrame, weights: np.ndarray, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All columns of docs (one named as score_col is replaced) and the score between 0 and 1."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    kept = [c for c in docs.columns if c != score_col]
    asked, at_text = asked_of(docs, kept, text_col, "string")
    space = (len(weights) - 1).bit_length() - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, features = shared.value.astype(float), held(("quality", space), lambda: Featurizer(space))
        for whole in batches:
            for start in range(0, whole.num_rows, ROWS):
                batch = whole.slice(start, ROWS)
                out = []
                for text in texts_of(batch.column(at_text)):
                    at, value = features(text)
                    out.append(1 / (1 + np.exp(-np.clip(w[at] @ value + w[-1], -40, 40))))
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], pa.array(out, pa.float64())], names=[*kept, score_col])

    return asked.mapInArrow(run, docs.select(*kept).withColumn(score_col, F.lit(0.0)).schema)


def held_out(id_col: str = "doc_id"):
    """True for rows that are never learned from: crc32 of the id as text, modulo 5, is 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def known_labels(labels: DataFrame, label_col: str) -> DataFrame:
    """(doc_id, label) of the labels that may be learned from."""
    return labels.select("doc_id", F.col(label_col).alias("label")).where(~held_out())


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, max_labelled: int = MAX_LABELLED) -> DataFrame:
    """All columns of docs and held_out, score, predicted."""
    weights = train(docs, known_labels(labels, "quality"), max_labelled)
    return score(docs, weights).withColumn("held_out", held_out()).withColumn("predicted", (F.col("score") >= threshold).cast("int"))
