"""Nearest neighbours by inner product, by collision-counting hashing.

Vectors get one more component so that all have one length; then the largest inner product is
the least distance. Random projections each give an array of the vectors sorted by their
projection. A query opens a window around its own place in each array; windows widen together
with a radius (virtual rehashing, no table is built anew). A vector that stands in enough windows
is verified by its inner product. When the k-th best one is within the radius the search
ends: a vector within the radius has been verified with a probability of at least SURE.

Windows are wide, so what lies outside them is counted: a vector that is outside of few enough is
inside of enough. That is the same count, for less than half of the entries.

Blocks of vectors are indexed and searched on their own, for blocks of queries; the best of the
blocks are merged. Of equal vectors k + 1 are indexed, those first in order, as no others can be
among the k nearest of anything. Only vectors of one dimension have inner products: each dimension is searched for itself.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cadenza.llm.common import cut

#: Rows of a block, most queries of a block, projections, half a window's width for radius 1.
BLOCK_ROWS = 65_536
BLOCK_QUERIES = 32_768
PROJECTIONS = 64
HALF_WIDTH = 2.0
#: Probability that a vector at the radius itself is verified; the step by which the radius grows.
SURE = 0.95
STEP = 1.06


def collisions_needed(projections: int, half_width: float, sure: float) -> int:
    """Windows that hold a vector at the radius: binomial; the largest number reached with probability `sure`."""
    p = math.erf(half_width / math.sqrt(2))
    tail = 0.0
    for n in range(projections + 1):
        tail += math.comb(projections, n) * p**n * (1 - p) ** (projections - n)
        if tail > 1 - sure:
            return max(n, 1)
    return projections


def _even(vectors: np.ndarray) -> np.ndarray:
    """Rows divided by a power of two near their largest component, so squares neither vanish nor overflow."""
    return np.ldexp(vectors, -np.frexp(np.abs(vectors).max(axis=-1, keepdims=True, initial=0.0))[1])


class Block:
    """Vectors with their sorted projections. verified and inside count, over all searches, the vectors verified and the window entries at the end."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, projections: int = PROJECTIONS, half_width: float = HALF_WIDTH, sure: float = SURE, seed: int = 1, nth: np.ndarray | None = None):
        self.ids, self.vectors, self.half_width = ids, np.ascontiguousarray(vectors, np.float64), half_width
        self.nth = np.zeros(len(ids), np.int64) if nth is None else nth
        exponent = np.frexp(np.abs(self.vectors).max(initial=0.0))[1]
        scaled = np.ldexp(self.vectors, -exponent)
        squares = (scaled**2).sum(axis=1)
        self.length = math.sqrt(squares.max()) if len(ids) else 1.0
        rest = np.sqrt(np.maximum(self.length**2 - squares, 0))
        self.directions = np.random.default_rng(seed).normal(size=(vectors.shape[1] + 1, projections))
        projected = (np.column_stack([scaled, rest]) @ self.directions).T.astype(np.float32)
        self.order = np.argsort(projected, axis=1, kind="stable")
        self.sorted = np.take_along_axis(projected, self.order, axis=1)
        self.small = scaled.astype(np.float32)
        self.allowed = projections - collisions_needed(projections, half_width, sure)
        self.probe = np.random.default_rng(seed + 1).choice(len(ids), min(len(ids), 1024), replace=False)
        self.verified = self.inside = self.searches = 0
        # one array each for all searches, as fresh large ones cost more than what is put into them
        self._entries = np.empty(self.order.size, np.int64)
        self._rows = np.empty_like(self.small)

    def _tally(self, parts: list[np.ndarray]) -> np.ndarray:
        """How often each vector is in some stretches of the arrays."""
        size = sum(map(len, parts))
        return np.bincount(np.concatenate(parts, out=self._entries[:size]), minlength=len(self.ids))

    def _scores(self, here: np.ndarray, query: np.ndarray) -> np.ndarray:
        """Inner products in single precision."""
        return np.einsum("ij,j->i", np.take(self.small, here, axis=0, out=self._rows[: len(here)], mode="clip"), query)

    def search(self, query_id: int, query: np.ndarray, k: int, nth: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(ids, inner products) of up to k other vectors, best first, ties by id. A vector with the query's own id and number is the query itself."""
        n, m = len(self.ids), len(self.sorted)
        unit = _even(query)
        unit = unit * (self.length / math.sqrt((unit**2).sum()))
        short = unit.astype(np.float32)
        # distances of all-alike lengths: squared, 2 length^2 - 2 scaled inner product
        distance = lambda score: math.sqrt(max(2 * self.length**2 - 2 * score, 0))
        centre = np.einsum("i,ij->j", unit, self.directions[:-1]).astype(np.float32)
        own = (self.ids == query_id) & (self.nth == nth)
        left = n - int(own.sum())
        if not left:
            return self.ids[:0], np.zeros(0)
        seen = np.einsum("ij,j->i", self.small[self.probe], short)[~own[self.probe]]
        # about as far as the k-th best is, if scores are spread normally, as those of some vectors are
        tail = math.log(max(left / k, 1.0))
        beyond = math.sqrt(max(2 * tail - math.log(max(4 * math.pi * tail, 1.0)), 0.0))
        radius = max(distance(float(seen.mean() + beyond * seen.std()) if len(seen) else self.length**2), 1e-3 * self.length)
        outside = None
        unseen = ~own
        low, high = None, None
        found, scores, n_found = [], [], 0
        while True:
            reach = np.float32(self.half_width * radius)
            new_low = [int(row.searchsorted(c - reach, "left")) for row, c in zip(self.sorted, centre)]
            new_high = [int(row.searchsorted(c + reach, "right")) for row, c in zip(self.sorted, centre)]
            if low is None:
                outside = self._tally([x for o, a, b in zip(self.order, new_low, new_high) for x in (o[:a], o[b:])])
            else:
                outside -= self._tally([x for o, a, b, c, d in zip(self.order, new_low, low, high, new_high) for x in (o[a:b], o[c:d])])
            low, high = new_low, new_high
            here = np.flatnonzero(unseen & (outside <= self.allowed))
            if len(here):
                unseen[here] = False
                found.append(here)
                scores.append(self._scores(here, short))
                n_found += len(here)
            if n_found >= k or n_found == left:
                score = np.concatenate(scores)
                kth = float(np.partition(score, -k)[-k]) if n_found >= k else -np.inf
                if n_found == left or distance(kth) <= radius:
                    break
            radius *= STEP
        self.searches += 1
        self.verified += n_found
        self.inside += sum(high) - sum(low)
        at = np.concatenate(found)
        # what single precision can't tell apart is summed in double, row by row, so that equal vectors have equal scores
        at = at[score >= kth - 1e-4 * self.length**2]
        score = (self.vectors[at] * query).sum(axis=1)
        best = np.lexsort((self.nth[at], self.ids[at], -score))[:k]
        return self.ids[at[best]], score[best]


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, v array<double>, nth), without vectors that are null, empty, zero, or hold a null or non-finite component; nth numbers the rows of one id, by v."""
    v = F.col(vector_col).cast("array<double>")
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = vectors.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), v.alias("v")).where(F.col("v").isNotNull() & sound)
    return cut(rows.withColumn("nth", F.row_number().over(Window.partitionBy("id").orderBy("v")).cast("long")))


def nearest(vectors: DataFrame, k: int = 20, query_filter: str = "id % 20 = 0", id_col: str = "vec_id", vector_col: str = "embedding", block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """query_id, rank (from 1), vec_id, score for each query's up to k nearest by inner product in double precision; ties to smaller ids; then query_row.

    Queries are the rows whose id fulfils query_filter; all rows but the query's own, of the same dimension, are
    candidates. Rows without an id and vectors that usable() leaves out take no part. Rows that share an
    id are queries and candidates each for itself, told apart by query_row (from 1). Further columns are ignored; an empty table gives no rows.
    """
    rows = usable(vectors, id_col, vector_col)
    copies = Window.partitionBy("v").orderBy("id", "nth")
    indexed = cut(rows.withColumn("copy", F.row_number().over(copies)).where(F.col("copy") <= k + 1).drop("copy"))
    asked = cut(rows.where(query_filter))
    n, n_queries = indexed.count(), asked.count()
    blocks = max(1, math.ceil(n / block_rows))
    cores = vectors.sparkSession.sparkContext.defaultParallelism
    query_blocks = max(1, math.ceil(n_queries / block_queries), min(math.ceil(cores / blocks), math.ceil(n_queries / 64)))
    spread = lambda here, there, a, b: [F.size("v").alias("d"), F.pmod(F.xxhash64("id", "nth"), F.lit(here)).cast("int").alias(a), F.explode(F.sequence(F.lit(0), F.lit(there - 1))).alias(b)]
    queries = asked.select("id", "nth", "v", *spread(query_blocks, blocks, "q", "b"))
    candidates = indexed.select("id", "nth", "v", *spread(blocks, query_blocks, "b", "q"))

    def matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        ids, nth, v = table.column("id").to_numpy(), table.column("nth").to_numpy(), table.column("v").combine_chunks()
        return ids, nth, v.flatten().to_numpy().reshape(len(ids), -1)

    def search(asked: pa.Table, held: pa.Table) -> pa.Table:
        out = []
        if len(asked) and len(held):
            held_ids, held_nth, held_vectors = matrix(held)
            block = Block(held_ids, held_vectors, nth=held_nth)
            for query_id, nth, query in zip(*matrix(asked)):
                ids, scores = block.search(query_id, query, k, nth)
                out.append((np.full(len(ids), query_id), np.full(len(ids), nth), ids, scores))
        columns = [np.concatenate(c) for c in zip(*out)] if out else [np.zeros(0, np.int64)] * 3 + [np.zeros(0)]
        return pa.table([pa.array(c) for c in columns], ["query_id", "query_row", "vec_id", "score"])

    cell = ["d", "b", "q"]
    found = queries.groupBy(*cell).cogroup(candidates.groupBy(*cell)).applyInArrow(search, "query_id bigint, query_row bigint, vec_id bigint, score double")
    best = Window.partitionBy("query_id", "query_row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "query_row")
