"""Mixing to target weights with soft membership.

A classifier learned from a labelled table gives each document posterior probabilities over domains. Document
rates r (how often a document is taken) are then fitted so that expected domain totals, the sums of tokens x
posterior x rate, match the targets: non-negative least squares with a small pull towards rate one, each
domain's miss weighed by its share. At the solution a rate follows from the document's posteriors and one number
a domain (the weighed miss), so the dual has as many unknowns as there are domains. It is convex, and solved
by damped Newton steps; a step is one pass that sums value, gradient and second derivative at several lengths of step,
and nothing else reaches the driver. Steps end only where the projected gradient of the rates vanishes. Documents may
have a floor below which their rate is not pushed.

Domains by default: "toxic", "low" (quality 0) and "clean <language>", known for labelled rows only; the language
of other rows is not used. At most MAX_LABELLED labelled rows are learned from, those of least id hash.

Null texts count as empty: no tokens, posteriors by the bias alone. Labels that are null aren't learned from.
Repeated rows are documents of their own. With no labels, all domains are equally likely. An empty table gives
an empty result. Columns of the same names as those added are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linform.llm.common import asked_of, held, materialise, texts_of
from linform.llm.quality import LEAST_STEPS, Ftrl, sampled

#: Bits of the feature space; bound of the training sample; passes over it; rows in a batch out; words kept.
SPACE, MAX_LABELLED, PASSES, ROWS, KEPT_WORDS = 16, 8_000, 3, 512, 200_000
#: Steps at most (beyond them the fit fails), the projected gradient at which they end, the pull towards rate one, the
#: part of the gain its slope promises that a step must bring, the lengths of step tried in one pass.
STEPS, ENOUGH, PULL, SLOW = 100, 1e-5, 1e-3, 0.01
LENGTHS = tuple(0.5**k for k in range(12))
#: Characters of a word that make its feature (endings differ more than senses), learning rate of the classifier.
STEM, RATE = 5, 0.4
LANGUAGES = ("de", "en", "es", "fr")
DOMAINS = (*(f"clean {x}" for x in LANGUAGES), "low", "toxic")


def labelled_domain() -> Column:
    """The domain of a labelled row (columns quality, toxic, lang); null if it has none of DOMAINS."""
    name = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "low").when(F.col("quality") == 1, F.concat(F.lit("clean "), "lang"))
    return F.when(name.isin(*DOMAINS), name)


class WordFeatures(dict):
    """Two feature numbers of a word, its stem and its shape's, in one integer. Most words of a corpus are rare, so the
    words that come first are kept, up to a bound, and it starts afresh only after as many others again, times four."""

    def __init__(self, space: int):
        super().__init__()
        self.space, self.mask, self.marked = space, (1 << space) - 1, np.zeros(1 << space, bool)
        self.shapes: dict[tuple[int, int, str], int] = {}
        self.stems: dict[str, int] = {}
        self.plain = [self.shape(0, n.bit_length(), "") for n in range(41)]
        self.others = 0

    def __missing__(self, word: str) -> int:
        start, n = word[:STEM], len(word)
        stem = self.stems.get(start)
        if stem is None:
            stem = (xxhash.xxh64_intdigest(start.lower().encode("utf-8", "surrogatepass"), 1) & self.mask) << self.space
            if len(self.stems) >= KEPT_WORDS:
                self.stems.clear()
            self.stems[start] = stem
        lower, end = word.islower(), n
        if not word.isalpha():
            while end and not (word[end - 1].isalnum() or word[end - 1] == "_"):
                end -= 1
        if lower and end == n:
            found = stem | self.plain[min(n, 40)]
        else:
            kind = 0 if lower else 2 if n > 1 and word.isupper() else 1 if word[0].isupper() else 0
            found = stem | self.shape(kind, min(n, 40).bit_length(), word[end : end + 3])
        if len(self) < KEPT_WORDS:
            self[word] = found
        else:
            self.others += 1
            if self.others >= 4 * KEPT_WORDS:
                self.clear()
                self.others = 0
        return found

    def shape(self, kind: int, size: int, marks: str) -> int:
        known = self.shapes.get((kind, size, marks))
        if known is None:
            known = xxhash.xxh64_intdigest(f"{kind}{size}{marks}".encode("utf-8", "surrogatepass"), 2) & self.mask
            if len(self.shapes) < KEPT_WORDS:
                self.shapes[kind, size, marks] = known
        return known

    def of(self, text: str) -> tuple[np.ndarray, np.ndarray, int]:
        """Feature numbers, their values (presence, so that a few telling words count in a long text) and the number
        of words. A word that follows itself has another shape."""
        words = text.split()
        both = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        shape = both & self.mask
        shape[1:][both[1:] == both[:-1]] ^= 0x55
        self.marked[both >> self.space] = True
        self.marked[shape] = True
        at = np.flatnonzero(self.marked)
        self.marked[at] = False
        return at, np.full(len(at), 0.3), len(words)


def train(docs: DataFrame, known: DataFrame, domains: tuple[str, ...] = DOMAINS, max_labelled: int = MAX_LABELLED, passes: int = PASSES, space: int = SPACE) -> np.ndarray:
    """(doc_id, text) and (doc_id, domain) -> a column of weights for each domain, learned from a bounded sample."""
    rows = sampled(docs, known, "domain", max_labelled)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features, models, kept = WordFeatures(space), [Ftrl(space, alpha=RATE) for _ in domains], []
        for batch in batches:
            for i, domain in enumerate(batch.column(2).to_pylist()):
                if len(kept) < max_labelled:
                    at, value, _ = features.of(batch.column(3)[i].as_py() or "")
                    kept.append((np.append(at, 1 << space).astype(np.int32), np.append(value, 1).astype(np.float32), domains.index(domain)))
        for _ in range(max(passes, LEAST_STEPS // max(1, len(kept)))):
            for at, value, label in kept:
                for d, model in enumerate(models):
                    model.learn(at, value.astype(float), int(d == label))
        yield pa.RecordBatch.from_pydict({"w": pa.array([np.stack([m.weights() for m in models], axis=1).astype(np.float32).tobytes()], pa.binary())})

    made = rows.mapInArrow(run, "w binary").collect()  # one row of fixed size
    n = (1 << space) + 1
    return np.frombuffer(made[0].w, np.float32).reshape(n, len(domains)) if made else np.zeros((n, len(domains)), np.float32)


def posteriors(docs: DataFrame, weights: np.ndarray, text_col: str = "text", keep_text: bool = True) -> DataFrame:
    """docs, with or without the text, with tokens (words of the text) and posterior (array<double>, sums to 1)."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    kept = [c for c in docs.columns if c not in ("tokens", "posterior") and (keep_text or c != text_col)]
    asked, at_text = asked_of(docs, kept, text_col, "string")
    space = (weights.shape[0] - 1).bit_length() - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, features = shared.value, held(("mixing", space), lambda: WordFeatures(space))
        for whole in batches:
            for start in range(0, whole.num_rows, ROWS):
                batch = whole.slice(start, ROWS)
                tokens, made = [], []
                for text in texts_of(batch.column(at_text)):
                    at, value, words = features.of(text)
                    score = value @ w[at] + w[-1]
                    likely = 1 / (1 + np.exp(-np.clip(score, -30, 30)))
                    tokens.append(words)
                    made.append(likely / likely.sum())
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], pa.array(tokens, pa.int64()), pa.array(made, pa.list_(pa.float64()))], names=[*kept, "tokens", "posterior"])

    schema = docs.select(*kept).withColumn("tokens", F.lit(0).cast("long")).withColumn("posterior", F.lit(None).cast("array<double>")).schema
    return asked.mapInArrow(run, schema)


def rates_from(p: np.ndarray, floor: np.ndarray, moves: np.ndarray, step: float, pull: float) -> np.ndarray:
    """Rates after the gradients in `moves` (a row each): the same steps for every document."""
    r = np.maximum(1.0, floor)
    for g in moves:
        r = np.maximum(floor, r - step * (p @ g + pull * (r - 1)))
    return r


def domain_totals(docs: DataFrame, n: int) -> np.ndarray:
    """Sums of tokens x posterior as they are."""
    total = docs.agg(*(F.sum(F.col("tokens") * F.col("posterior")[d]).alias(f"t{d}") for d in range(n))).first()
    return np.array([x or 0.0 for x in total])


@dataclass(frozen=True)
class Fit:
    """The gradient at the solution (one row), the step that takes rates of one there, the miss at each point that was
    taken (share of all tokens), and the domain totals asked for, as they were and as the rates make them."""

    moves: np.ndarray
    step: float
    misses: list[float]
    target: np.ndarray
    before: np.ndarray
    after: np.ndarray


def fit_moves(docs: DataFrame, target: np.ndarray, pull: float = PULL, steps: int = STEPS, enough: float = ENOUGH, slow: float = SLOW) -> tuple[np.ndarray, float, list[float]]:
    """As fit, without the totals."""
    found = fit(docs, target, pull, steps, enough, slow)
    return found.moves, found.step, found.misses


def fit(docs: DataFrame, target: np.ndarray, pull: float = PULL, steps: int = STEPS, enough: float = ENOUGH, slow: float = SLOW) -> Fit:
    """(tokens, posterior, floor) and target totals -> the least-squares rates, as what every document's rate follows from."""
    n, now = len(target), domain_totals(docs, len(target))
    total = max(now.sum(), 1.0)
    share = np.maximum(now / total, 1e-6)
    corner = np.triu_indices(n)

    def look(points: np.ndarray) -> np.ndarray:
        """For each point a row: the dual's value, its gradient, the upper half of its second derivative."""
        width = 1 + n + len(corner[0])

        def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = np.zeros((len(points), width))
            for batch in batches:
                p = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
                floor = batch.column(2).to_numpy(zero_copy_only=False)
                tokens = batch.column(0).to_numpy(zero_copy_only=False) / total
                for row, y in zip(held, points, strict=True):
                    push = p @ y
                    free = 1 - push / pull
                    r = np.maximum(floor, free)
                    row[0] -= tokens @ (pull / 2 * (r - 1) ** 2 + r * push)
                    row[1 : n + 1] -= (tokens * r) @ p
                    row[n + 1 :] += ((p.T * (tokens * (free > floor))) @ p)[corner] / pull
            yield pa.RecordBatch.from_pydict({"t": pa.array([held.ravel().tolist()], pa.list_(pa.float64()))})

        parts = docs.select("tokens", "posterior", "floor").mapInArrow(sums, "t array<double>")
        found = parts.agg(*(F.sum(F.col("t")[i]).alias(f"t{i}") for i in range(len(points) * width))).first()
        out = np.array([x or 0.0 for x in found]).reshape(len(points), width)
        out[:, 0] += (share * points**2).sum(axis=1) / 2 + points @ target / total
        out[:, 1 : n + 1] += share * points + target / total
        out[:, n + 1 :] += np.diag(share)[corner]
        return out

    def miss(y: np.ndarray, seen: np.ndarray) -> float:
        return float(np.abs(share * y - seen[1 : n + 1]).sum())

    y = np.zeros(n)
    seen = look(y[None])[0]
    misses = [miss(y, seen)]
    for _ in range(steps):
        gradient = seen[1 : n + 1]
        if np.abs(gradient / share).max() < enough:
            break
        second = np.zeros((n, n))
        second[corner] = seen[n + 1 :]
        second += np.triu(second, 1).T
        towards = -np.linalg.solve(second, gradient)
        points = y + np.outer(LENGTHS, towards)
        ahead = look(points)
        gains = ahead[:, 0] <= seen[0] + slow * np.array(LENGTHS) * (gradient @ towards) + 1e-14
        if not gains.any():
            raise RuntimeError("rates did not settle: no length of step gains")
        at = int(np.argmin(np.where(gains, ahead[:, 0], np.inf)))
        y, seen = points[at], ahead[at]
        misses.append(miss(y, seen))
    else:
        raise RuntimeError(f"rates did not settle in {steps} steps")
    return Fit(y[None], 1 / pull, misses, target, now, (share * y - seen[1 : n + 1]) * total + target)


def with_rates(docs: DataFrame, moves: np.ndarray, step: float, pull: float = PULL) -> DataFrame:
    """docs (posterior, floor) with rate."""
    kept = [c for c in docs.columns if c != "rate"]
    p_at, floor_at, n = kept.index("posterior"), kept.index("floor"), moves.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = batch.column(p_at).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
            r = rates_from(p, batch.column(floor_at).to_numpy(zero_copy_only=False), moves, step, pull)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(r, pa.float64())], names=[*kept, "rate"])

    return docs.select(*kept).mapInArrow(run, docs.select(*kept).withColumn("rate", F.lit(0.0)).schema)


def copies(rate: Column, id_col: str = "doc_id") -> Column:
    """A whole number of copies with the rate as its mean, by the hash of the id: the same in every run."""
    chance = F.shiftrightunsigned(F.xxhash64(F.lit("copies"), id_col), 11) / F.lit(float(1 << 53))
    return (F.floor(rate) + (chance < rate - F.floor(rate)).cast("long")).cast("int")


def mix(docs: DataFrame, classifier: np.ndarray, **how) -> DataFrame:
    """docs with tokens, posterior, floor, rate and copies, as `fitted` makes them."""
    return fitted(docs, classifier, **how)[0]


def fitted(docs: DataFrame, classifier: np.ndarray, weights: dict[str, float] | None = None, temper: float = 0.7, toxic: float = 0.0, low: float = 0.5, keep_clean: bool = False, domains: tuple[str, ...] = DOMAINS, keep_text: bool = True) -> tuple[DataFrame, Fit]:
    """docs (without the text if it is not to be kept) with tokens, posterior, floor, rate and copies, and the totals that the rates reach.

    classifier: as train gives it. weights: target share of each domain; where none are given, clean domains
    get their shares to the power `temper`, and toxic and low domains these multiples of theirs. The total is
    what the documents have; with keep_clean it is as large as no clean domain has to shrink, and documents that
    are likelier clean than not have a floor of one.
    """
    made = posteriors(docs, classifier, keep_text=keep_text)
    clean = [d for d, name in enumerate(domains) if name.startswith("clean")]
    mass = sum((F.col("posterior")[d] for d in clean), F.lit(0.0))
    made = made.withColumn("floor", F.when(F.lit(keep_clean) & (mass >= 0.5), 1.0).otherwise(0.0))
    made = materialise(made, "posteriors")
    now = domain_totals(made, len(domains))
    share = now / max(now.sum(), 1.0)
    if weights is None:
        wanted = np.array([share[d] ** temper if d in clean else 0.0 for d in range(len(domains))])
        wanted *= share[clean].sum() / max(wanted.sum(), 1e-12)
        for d, name in enumerate(domains):
            if d not in clean:
                wanted[d] = share[d] * (toxic if name == "toxic" else low)
    else:
        wanted = np.array([weights.get(name, 0.0) for name in domains])
    wanted = wanted / max(wanted.sum(), 1e-12)
    total = now.sum()
    if keep_clean:
        total *= max([1.0, *(share[d] / wanted[d] for d in clean if wanted[d] > 0)])
    found = fit(made, wanted * total)
    return with_rates(made, found.moves, found.step).withColumn("copies", copies(F.col("rate"))), found


def known_domains(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, domain) of documents that the labels table knows."""
    both = docs.select("doc_id", "lang").join(labels.select("doc_id", "quality", "toxic"), "doc_id")
    return both.select("doc_id", labelled_domain().alias("domain"))
