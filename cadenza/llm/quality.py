"""Text quality from weak labels.

Heuristic labellers vote good, bad or abstain on each text. Expectation-maximisation over the
counts of all vote patterns of the corpus estimates how often each labeller votes what on good
and on bad texts, so its accuracy, and the probability that a text with a pattern is good; no
gold labels are used. These posteriors train
a hashed linear scorer over words and style, which scores every text.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut, in_small_batches, tidy
from cadenza.llm.linear import Chosen, Logistic, choose, fit, sampled_rows
from cadenza.llm.words import word_list

#: Texts that the scorer is fitted on at most, picked by a hash, and its chosen word features.
TRAINING_ROWS = 6000
FEATURES = 2048

GOOD, BAD, ABSTAIN = 1, 0, 2
#: Bins of a style measure, as features of the scorer.
BINS = 16

_UPPER = bytes(range(65, 91))
_LETTERS = _UPPER + bytes(range(97, 123)) + bytes(range(128, 256))
_PLAIN_MARKS = b" \n\t\r.,;:'\"-()?" + bytes(range(48, 58))


def measures(data: bytes) -> dict[str, float]:
    """Style of a UTF-8 text, each from 0 to 1."""
    words = word_list(data)
    n, size = len(words), max(len(data), 1)
    letters = size - len(data.translate(None, _LETTERS))
    upper = size - len(data.translate(None, _UPPER))
    odd = len(data.translate(None, _LETTERS + _PLAIN_MARKS))
    counts = Counter(words)
    lines = [x for x in data.split(b"\n") if x.strip()]
    same_as_last = sum(map(bytes.__eq__, words[1:], words))
    pairs = Counter(zip(words, words[1:]))
    return {
        "length": min(1.0, math.log1p(n) / 10),
        "word size": min(1.0, letters / max(n, 1) / 20),
        "upper": upper / max(letters, 20),
        "odd": odd / size,
        "marks per word": min(1.0, odd / max(n, 1)),
        "distinct": 1.0 if n < 20 else min(1.0, len(counts) / n ** 0.85),
        "stutter": same_as_last / max(n - 1, 12),
        "repeated pairs": sum(c for c in pairs.values() if c > 3) / max(n - 1, 1) if n >= 20 else 0.0,
        "repeated lines": 1 - len(set(lines)) / max(len(lines), 1),
        "pipes": min(1.0, 4 * data.count(b"|") / max(n, 1)),
        "shouts": min(1.0, 4 * data.count(b"!") / max(n, 1)),
    }


#: Labellers that speak against a text: the measure, and from where on (up to where, for the first two) they vote bad; they abstain otherwise.
AGAINST = [
    ("length", 0.05),
    ("word size", 0.10),
    ("upper", 0.25),
    ("odd", 0.03),
    ("marks per word", 0.15),
    ("distinct", 0.60),
    ("stutter", 0.08),
    ("repeated pairs", 0.20),
    ("repeated lines", 0.50),
    ("pipes", 0.50),
    ("shouts", 0.50),
]
#: Labellers that speak for a text if each of their measures is so far on the good side; they abstain otherwise.
FOR = [
    {"upper": 0.10, "odd": 0.005, "marks per word": 0.02, "pipes": 0.05, "shouts": 0.10},
    {"distinct": 0.85, "stutter": 0.04, "repeated pairs": 0.06, "repeated lines": 0.25},
    {"upper": 0.15, "odd": 0.01, "stutter": 0.05, "repeated pairs": 0.10},
]
LABELLERS = len(AGAINST) + len(FOR)
_LOW_IS_BAD = {"length", "word size", "distinct"}


def votes(style: dict[str, float]) -> list[int]:
    against = [BAD if (style[k] <= x if k in _LOW_IS_BAD else style[k] >= x) else ABSTAIN for k, x in AGAINST]
    return against + [GOOD if all(style[k] >= x if k in _LOW_IS_BAD else style[k] <= x for k, x in f.items()) else ABSTAIN for f in FOR]


@dataclass(frozen=True)
class LabelModel:
    prior: float  # part of the texts that are good
    on_good: np.ndarray  # by labeller and vote (bad, good, abstain): how often it comes on good texts
    on_bad: np.ndarray

    def posterior(self, patterns: np.ndarray) -> np.ndarray:
        """Probability of good for rows of votes."""
        which = np.arange(self.on_good.shape[0])
        z = (np.log(self.on_good) - np.log(self.on_bad))[which, patterns].sum(axis=1) + np.log(self.prior / (1 - self.prior))
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))

    def accuracy(self) -> np.ndarray:
        """By labeller: how often its votes are right, abstentions left out."""
        right = self.prior * self.on_good[:, GOOD] + (1 - self.prior) * self.on_bad[:, BAD]
        wrong = self.prior * self.on_good[:, BAD] + (1 - self.prior) * self.on_bad[:, GOOD]
        return right / (right + wrong)


def first_guess(n_labellers: int) -> LabelModel:
    """Most texts are good; a vote is right far more often than not."""
    guess = lambda bad, good: np.tile([bad, good, 1 - bad - good], (n_labellers, 1))
    return LabelModel(0.85, guess(0.02, 0.50), guess(0.30, 0.10))


def expectation_maximisation(patterns: np.ndarray, counts: np.ndarray, rounds: int = 200) -> LabelModel:
    """From patterns of votes and how often each occurs."""
    model = first_guess(patterns.shape[1])
    votes_are = np.stack([patterns == v for v in (BAD, GOOD, ABSTAIN)], axis=2).astype(float)
    for _ in range(rounds):
        p = model.posterior(patterns) * counts
        # a few made-up texts keep rates away from 0
        rates = [(np.einsum("i,ijv->jv", w, votes_are) + 0.5) / (w.sum() + 1.5) for w in (p, counts - p)]
        following = LabelModel(float((p.sum() + 4) / (counts.sum() + 5)), *rates)
        moved = max(abs(following.prior - model.prior), np.abs(following.on_good - model.on_good).max(), np.abs(following.on_bad - model.on_bad).max())
        model = following
        if moved < 1e-7:
            break
    return model


def _code(vote: list[int]) -> int:
    return sum(v * 3**j for j, v in enumerate(vote))


def _decode(codes: np.ndarray) -> np.ndarray:
    return np.array([[c // 3**j % 3 for j in range(LABELLERS)] for c in codes], np.int64).reshape(len(codes), LABELLERS)


def vote_patterns(docs: DataFrame, text_col: str, *keep: str) -> DataFrame:
    """(pattern, the columns in keep) of each row whose text has words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t.as_py() for t in batch.column(0).cast(pa.binary())]
            codes = [_code(votes(measures(t))) if word_list(t) else None for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array(codes, pa.int64()), *batch.columns[1:]], ["pattern", *keep])

    kinds = dict(docs.dtypes)
    return in_small_batches(docs.select(text_col, *keep)).mapInArrow(tidy(run), ", ".join(["pattern bigint", *(f"{c} {kinds[c]}" for c in keep)])).where("pattern is not null")


def style_features(style: dict[str, float], first: int) -> list[int]:
    """Numbers from `first` on: of each measure the bins up to its own."""
    return [first + BINS * j + b for j, x in enumerate(style.values()) for b in range(min(BINS, int(math.sqrt(x) * BINS) + 1))]


@dataclass(frozen=True)
class Scorer:
    labels: LabelModel
    buckets: np.ndarray
    model: Logistic


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", training_rows: int = TRAINING_ROWS, features: int = FEATURES) -> Scorer:
    """The label model from all rows; the scorer from at most training_rows texts, those whose md5 comes first."""
    counted = vote_patterns(docs, text_col).groupBy("pattern").agg(F.count(F.lit(1)).alias("n")).orderBy("pattern").collect()  # 2^labellers rows at most, as each has one vote besides abstaining
    patterns, counts = _decode(np.array([r.pattern for r in counted], np.int64)), np.array([float(r.n) for r in counted])
    labels = expectation_maximisation(patterns, counts) if counted else first_guess(LABELLERS)
    picked = docs.where(F.col(text_col).isNotNull()).select(F.md5(text_col).alias("key")).distinct().orderBy("key").limit(training_rows)
    picked = cut(picked)
    sample = docs.join(F.broadcast(picked), F.md5(docs[text_col]) == F.col("key")).groupBy("key").agg(F.any_value(text_col).alias("text"))

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            styles = [measures(t.as_py()) for t in batch.column(0).cast(pa.binary())]
            p = labels.posterior(np.array([votes(s) for s in styles]).reshape(len(styles), LABELLERS))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p), pa.array([style_features(s, 0) for s in styles], pa.list_(pa.int32()))], ["text", "good", "style"])

    weak = cut(in_small_batches(sample.select("text")).mapInArrow(tidy(judged), "text string, good double, style array<int>"))
    buckets = choose(weak, ["good"], "text", features)
    n_style = BINS * len(measures(b""))
    rows, values = sampled_rows(weak.select("text", "good", "style"), buckets, ["good"], "text", extra="style")
    model = fit(rows, np.zeros((len(rows), 0)), values[:, 0] if len(rows) else np.zeros(0), np.ones(len(rows)), len(buckets) + n_style)
    return Scorer(labels, buckets, model)


def score(docs: DataFrame, scorer: Scorer, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of docs: id, weak_label (posterior of its votes), quality (the scorer's probability of good), good (at least the threshold).

    A null text, or one without words, has 0, 0 and false. Repeated rows and null ids are kept; further
    columns are ignored; an empty table gives no rows. There is no shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Chosen(scorer.buckets)
        for batch in batches:
            texts = [t.as_py() or b"" for t in batch.column(1).cast(pa.binary())]
            styles = [measures(t) for t in texts]
            worded = np.array([bool(word_list(t)) for t in texts], bool)
            rows = [np.concatenate([known.row(t), style_features(s, len(scorer.buckets))]).astype(np.int64) for t, s in zip(texts, styles)]
            p = scorer.model.probability(rows, np.zeros((len(rows), 0))) * worded if rows else np.zeros(0)
            weak = scorer.labels.posterior(np.array([votes(s) for s in styles]).reshape(len(styles), LABELLERS)) * worded
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(weak), pa.array(p), pa.array(p >= threshold)], ["id", "weak_label", "quality", "good"])

    return in_small_batches(docs.select(id_col, text_col)).mapInArrow(tidy(run), f"id {dict(docs.dtypes)[id_col]}, weak_label double, quality double, good boolean").withColumnRenamed("id", id_col)
