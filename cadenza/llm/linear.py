"""Hashed features of texts and logistic models over them, for the classifiers."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut, in_small_batches, tidy
from cadenza.llm.words import word_list

#: Hashed features, of which some are chosen.
BUCKETS = 1 << 18
#: Words whose features a worker remembers.
REMEMBERED = 100_000


class WordFeatures(dict):
    """Buckets of a word: the word itself and its first 3 to 6 letters, as forms of one stem begin alike."""

    def __init__(self, buckets: int = BUCKETS):
        self.buckets = buckets

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) > REMEMBERED:
            self.clear()
        found = self[word] = self.of(word)
        return found

    def of(self, word: bytes) -> tuple[int, ...]:
        text = word.decode("utf-8", "replace").lower()
        names = {"=" + text, *("^" + text[:n] for n in (3, 4, 5, 6) if len(text) >= n)}
        return tuple(sorted({xxhash.xxh64_intdigest(x) % self.buckets for x in names}))


def document_features(data: bytes | None, known: WordFeatures) -> np.ndarray:
    """Sorted buckets that the words of a text have, each once."""
    found: set[int] = set()
    for word in set(word_list(data)):
        found.update(known[word])
    out = np.fromiter(found, np.int64, len(found))
    out.sort()
    return out


def sigmoid(z):
    return 1.0 / (1.0 + np.exp(-np.clip(z, -30, 30)))


class Rows:
    """Sparse 0/1 rows, in one array of feature numbers."""

    def __init__(self, rows: list[np.ndarray]):
        self.n = len(rows)
        self.sizes = np.array([len(r) for r in rows], np.int64)
        self.features = np.concatenate(rows).astype(np.int64) if rows else np.empty(0, np.int64)
        self.row = np.repeat(np.arange(self.n), self.sizes)

    def dot(self, weights: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, weights[self.features], self.n)

    def back(self, per_row: np.ndarray, n_features: int) -> np.ndarray:
        return np.bincount(self.features, per_row[self.row], n_features)


@dataclass(frozen=True)
class Logistic:
    """Weights of sparse features, of dense columns, and a bias."""

    sparse: np.ndarray
    dense: np.ndarray
    bias: float

    def probability(self, rows: list[np.ndarray], dense: np.ndarray) -> np.ndarray:
        return sigmoid(Rows(rows).dot(self.sparse) + dense @ self.dense + self.bias)


def fit(rows: list[np.ndarray], dense: np.ndarray, target: np.ndarray, weight: np.ndarray, n_features: int, l2: float = 0.3, steps: int = 60, memory: int = 8) -> Logistic:
    """A logistic model with an L2 penalty, by limited-memory quasi-Newton steps; targets may be probabilities.

    The same data give the same model. Without rows, or with targets all alike, it is a constant.
    """
    k = dense.shape[1]
    if not rows:
        return Logistic(np.zeros(n_features), np.zeros(k), -30.0)
    x = Rows(rows)
    share = np.clip((weight * target).sum() / weight.sum(), 1e-6, 1 - 1e-6)
    at = np.zeros(n_features + k + 1)
    at[-1] = np.log(share / (1 - share))
    if share in (1e-6, 1 - 1e-6):
        return Logistic(at[:n_features], at[n_features:-1], float(at[-1]))

    def cost(p):
        z = x.dot(p[:n_features]) + dense @ p[n_features:-1] + p[-1]
        error = weight * (sigmoid(z) - target)
        slope = np.concatenate([x.back(error, n_features) + l2 * p[:n_features], dense.T @ error + l2 * p[n_features:-1], [error.sum()]])
        return (weight * (np.logaddexp(0, z) - target * z)).sum() + 0.5 * l2 * (p[:-1] ** 2).sum(), slope

    value, slope = cost(at)
    moves: deque = deque(maxlen=memory)
    for _ in range(steps):
        way, used = slope.copy(), []
        for d, g in reversed(moves):
            used.append((d @ way) / (d @ g))
            way -= used[-1] * g
        way *= (moves[-1][0] @ moves[-1][1]) / (moves[-1][1] @ moves[-1][1]) if moves else 1 / max(1.0, np.linalg.norm(slope))
        for (d, g), u in zip(moves, reversed(used)):
            way += d * (u - (g @ way) / (d @ g))
        length = 1.0
        while length > 1e-6:
            following, slope_there = cost(at - length * way)
            if following <= value - 1e-4 * length * (slope @ way):
                break
            length /= 2
        else:
            break
        move, change = -length * way, slope_there - slope
        if move @ change > 1e-12:
            moves.append((move, change))
        at, slope, gained, value = at + move, slope_there, value - following, following
        if gained < 1e-6 * max(1.0, abs(value)):
            break
    return Logistic(at[:n_features], at[n_features:-1], float(at[-1]))


class Chosen(dict):
    """Numbers of the chosen features that a word has, remembered; most words have none."""

    def __init__(self, buckets: np.ndarray, n_buckets: int = BUCKETS):
        self.number = {int(b): i for i, b in enumerate(buckets)}
        self.all = WordFeatures(n_buckets)

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) > 2 * REMEMBERED:
            self.clear()
        found = self[word] = tuple(self.number[b] for b in self.all.of(word) if b in self.number)
        return found

    def row(self, data: bytes | None) -> np.ndarray:
        """Numbers of the chosen features that a text has, each once."""
        found = set().union(*filter(None, map(self.__getitem__, set(word_list(data)))))
        return np.fromiter(found, np.int64, len(found))


def choose(docs: DataFrame, targets: list[str], text_col: str, keep: int, n_buckets: int = BUCKETS, least: int = 3, significant: float = 4.0) -> np.ndarray:
    """Buckets that tell most about each target (a column of 0 to 1; null: the row has none), over all rows of docs."""
    return choose_by_fold(docs, targets, text_col, keep, None, 1, n_buckets, least, significant)[0]


def choose_by_fold(docs: DataFrame, targets: list[str], text_col: str, keep: int, fold_col: str | None, folds: int, n_buckets: int = BUCKETS, least: int = 3, significant: float = 4.0) -> list[np.ndarray]:
    """The same over all rows and, for each fold (a column from 0 on), over the rows that are not in it.

    Rows are counted where they lie; one row for each bucket is shuffled from each task. Of each target
    the `keep` buckets with the largest z-scores of a difference of shares come to the driver.
    """
    k = len(targets)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WordFeatures(n_buckets)
        counts = np.zeros((folds, 2 * k, n_buckets))
        total = np.zeros((folds, 2 * k))
        for batch in batches:
            for i, text in enumerate(batch.column(0).cast(pa.binary())):
                row = document_features(text.as_py(), known)
                fold = batch.column(k + 1)[i].as_py()
                for j in range(k):
                    if (t := batch.column(j + 1)[i].as_py()) is not None:
                        counts[fold, j, row] += t
                        counts[fold, k + j, row] += 1 - t
                        total[fold, j] += t
                        total[fold, k + j] += 1 - t
        held = np.flatnonzero(counts.any(axis=(0, 1)))
        if total.any():
            arrays = [pa.array(np.append(held, -1)), *(pa.array(np.append(counts[f, j, held], total[f, j])) for f in range(folds) for j in range(2 * k))]
            yield pa.RecordBatch.from_arrays(arrays, names)

    names = ["bucket", *(f"c{f}_{j}" for f in range(folds) for j in range(2 * k))]
    fold = F.col(fold_col).cast("int") if fold_col else F.lit(0)
    counted = in_small_batches(docs.select(text_col, *(F.col(t).cast("double") for t in targets), fold.alias("__fold"))).mapInArrow(tidy(run), ", ".join(["bucket bigint", *(f"{c} double" for c in names[1:])]))
    table = cut(counted.groupBy("bucket").agg(*(F.sum(c).alias(c) for c in names[1:])))
    totals = table.where("bucket = -1").first()
    out = []
    for held_out in [None, *range(folds if fold_col else 0)]:
        part = [f for f in range(folds) if f != held_out]
        chosen: set[int] = set()
        for j in range(k if totals else 0):
            n1, n0 = (max(sum(totals[f"c{f}_{x}"] for f in part), 1e-9) for x in (j, k + j))
            c1, c0 = (sum((F.col(f"c{f}_{x}") for f in part), F.lit(0.0)) for x in (j, k + j))
            share = (c1 + c0 + 1) / (n1 + n0 + 2)
            z = F.abs(c1 / n1 - c0 / n0) / F.sqrt(share * (1 - share) * (1 / n1 + 1 / n0))
            best = table.where(F.col("bucket") >= 0).where((c1 + c0 >= least) & (z >= significant)).orderBy(z.desc(), "bucket").limit(keep)
            chosen.update(r.bucket for r in best.select("bucket").collect())
        out.append(np.array(sorted(chosen), np.int64))
    return out


def sampled_rows(docs: DataFrame, buckets: np.ndarray, targets: list[str], text_col: str, extra: str | None = None, n_buckets: int = BUCKETS) -> tuple[list[np.ndarray], np.ndarray]:
    """The chosen features and the targets of all rows of docs, at the driver: docs is a bounded sample. extra: a column with numbers of further features, counted from len(buckets)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Chosen(buckets, n_buckets)
        for batch in batches:
            rows = [known.row(t.as_py()) for t in batch.column(0).cast(pa.binary())]
            if extra:
                rows = [np.concatenate([r, len(buckets) + np.array(x.as_py(), np.int64)]) for r, x in zip(rows, batch.column(len(targets) + 1))]
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.list_(pa.int32())), *batch.columns[1 : len(targets) + 1]], ["features", *targets])

    found = in_small_batches(docs.select(text_col, *(F.col(t).cast("double") for t in targets), *([extra] if extra else []))).mapInArrow(tidy(run), ", ".join(["features array<int>", *(f"`{t}` double" for t in targets)])).collect()
    found.sort(key=lambda r: (list(map(int, r.features)), [r[t] for t in targets]))  # in whatever order they came, one model
    return [np.array(r.features, np.int64) for r in found], np.array([[r[t] for t in targets] for r in found]).reshape(len(found), len(targets))
