"""Toxicity by a classifier chain.

Categories are predicted in order by linear models over hashed word features; each model also
has the probabilities of the categories before it. In training these are out-of-fold: each comes
from models that have not seen the row, so a later model learns to trust them as far as they
will be right on new texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut, in_small_batches, tidy
from cadenza.llm.linear import Chosen, Logistic, choose_by_fold, fit, sampled_rows
from cadenza.llm.words import word_list

#: Labelled rows that features are chosen and models fitted on at most, half of them with the last category; features chosen for each category.
TRAINING_ROWS = 12_000
FEATURES = 2048
FOLDS = 4


@dataclass(frozen=True)
class Chain:
    categories: tuple[str, ...]
    buckets: np.ndarray
    models: tuple[Logistic, ...]

    def probabilities(self, rows: list[np.ndarray]) -> np.ndarray:
        """One column for each category."""
        found = np.zeros((len(rows), 0))
        for model in self.models:
            found = np.column_stack([found, model.probability(rows, found)])
        return found


def fit_models(rows: list[np.ndarray], labels: np.ndarray, weight: np.ndarray, n_features: int, folds: int = FOLDS, fold: np.ndarray | None = None, allowed: list[np.ndarray] | None = None) -> tuple[Logistic, ...]:
    """A model for each column of labels, in order; all but the first are given out-of-fold probabilities of those before.

    fold: the fold of each row. allowed: the features (true) of the final models, then of those fitted without fold 0, 1, ...: what a
    held-out row says has no part in the choice of the features that judge it.
    """
    models, before = [], np.zeros((len(rows), 0))
    fold = np.arange(len(rows)) % folds if fold is None else fold
    only = lambda k, which: [rows[i] if allowed is None else rows[i][allowed[k][rows[i]]] for i in which]
    every = only(0, range(len(rows)))
    for j in range(labels.shape[1]):
        target = labels[:, j]
        models.append(fit(every, before, target, weight, n_features))
        unseen = np.zeros(len(rows))
        if j + 1 < labels.shape[1]:
            for k in range(folds):
                seen, held = np.flatnonzero(fold != k), np.flatnonzero(fold == k)
                if len(held):
                    part = fit(only(k + 1, seen), before[seen], target[seen], weight[seen], n_features)
                    unseen[held] = part.probability(only(k + 1, held), before[held])
        before = np.column_stack([before, unseen])
    return tuple(models)


def train(docs: DataFrame, labels: DataFrame, categories: dict[str, str], id_col: str = "doc_id", text_col: str = "text", training_rows: int = TRAINING_ROWS, features: int = FEATURES, folds: int = FOLDS) -> Chain:
    """A chain for categories {name: SQL expression over labels, true or false}, in this order.

    Features are chosen and models fitted on at most training_rows labelled rows, picked by a hash
    of the id, half with and half without the last category as far as there are, and weighted back
    to their shares. So no text is shuffled but those of the sample. Labels that are null or whose row has no
    text are left out. Of labels that clash for one id, a category holds if one of them says so; of several texts under one
    id the one whose md5 comes first is taken. With no labels at all each probability is 0.
    """
    names, last = list(categories), list(categories)[-1]
    judged = labels.select(F.col(id_col).alias("__id"), *(F.expr(e).cast("double").alias(n) for n, e in categories.items())).dropna()
    judged = judged.groupBy("__id").agg(*(F.max(n).alias(n) for n in names))
    texts = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text")).where(F.col("__text").isNotNull())
    totals = {r[last]: r["count"] for r in judged.groupBy(last).count().collect()}
    picked = [judged.where(F.col(last) == v).orderBy(F.xxhash64("__id"), "__id").limit(training_rows // 2) for v in (0.0, 1.0)]
    sample = texts.join(F.broadcast(cut(picked[0].union(picked[1]))), "__id").groupBy("__id").agg(F.min_by("__text", F.md5("__text")).alias("__text"), *(F.max(n).alias(n) for n in names))
    sample = cut(sample.withColumn("__fold", F.pmod(F.xxhash64("__id", F.lit("fold")), F.lit(folds))))
    sets = choose_by_fold(sample, names, "__text", features, "__fold", folds)
    buckets = np.unique(np.concatenate(sets))
    rows, values = sampled_rows(sample, buckets, [*names, "__fold"], "__text")
    values, fold = values[:, :-1], values[:, -1].astype(np.int64)
    y = values[:, -1]
    share = {v: totals.get(v, 0) / max(1, (y == v).sum()) for v in (0.0, 1.0)}
    weight = np.where(y == 1, share[1.0], share[0.0])
    weight = weight * len(y) / max(weight.sum(), 1e-9)
    models = fit_models(rows, values, weight, len(buckets), folds, fold, [np.isin(buckets, chosen) for chosen in sets])
    return Chain(tuple(names), buckets, models)


def score(docs: DataFrame, chain: Chain, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """One row for each row of docs: id, p_<category> for each, rejected (the last one's is at least the threshold), then the columns in keep.

    A null text, or one without words, has probabilities of 0. Repeated rows and null ids are kept; an
    empty table gives no rows. There is no shuffle.
    """
    n = len(chain.categories)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Chosen(chain.buckets)
        for batch in batches:
            texts = [t.as_py() for t in batch.column(1).cast(pa.binary())]
            p = chain.probabilities([known.row(t) for t in texts])
            p[[not word_list(t) for t in texts]] = 0
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(p[:, j]) for j in range(n)), pa.array(p[:, -1] >= threshold), *batch.columns[2:]], names)

    kinds = dict(docs.dtypes)
    names = ["__id", *(f"__p{j}" for j in range(n)), "__rejected", *(f"__k{j}" for j in range(len(keep)))]
    schema = ", ".join([f"__id {kinds[id_col]}", *(f"__p{j} double" for j in range(n)), "__rejected boolean", *(f"__k{j} {kinds[c]}" for j, c in enumerate(keep))])
    return in_small_batches(docs.select(id_col, text_col, *keep)).mapInArrow(tidy(run), schema).toDF(id_col, *(f"p_{c}" for c in chain.categories), "rejected", *keep)


def keep_clean(docs: DataFrame, chain: Chain, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """docs without rejected rows; all columns stay as they are. There is no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Chosen(chain.buckets)
        for batch in batches:
            texts = [t.as_py() for t in batch.column(at).cast(pa.binary())]
            p = chain.probabilities([known.row(t) for t in texts])[:, -1] if texts else np.zeros(0)
            clean = [x < threshold or not word_list(t) for x, t in zip(p, texts)]
            yield batch.filter(pa.array(clean, pa.bool_()))

    at = docs.columns.index(text_col)
    return in_small_batches(docs).mapInArrow(tidy(run), docs.schema)
