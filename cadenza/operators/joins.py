"""All-pairs queries: by leaf boxes, by a grid, by index probes, and by scans."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions import geometry as G
from cadenza.functions.transforms import SpectralTransform, identity
from cadenza.model import SLACK
from cadenza.operators import spectrum
from cadenza.operators.kindex import HEAD, KIndex, boxes, view
from cadenza.storage import keep

#: Of comparisons by tiles: series of one, tiles of a side at most (beyond that they grow), pairs that are compared, whose differences are taken, and that leave a task at once.
TILE_ROWS, TILES, TILE_PAIRS, GAP_PAIRS, OUT_PAIRS = 16_384, 16, 1 << 18, 20_000, 1 << 16
#: Rows of a cell that are compared with others at once.
SCAN_ROWS = 512
#: Of a join by cells: coefficients that are compared there, cells along an axis at most, and rows of a cell that are compared at once.
CELL_COEFFICIENTS, CELLS, CELL_ROWS = 7, 12, 8192
FOUND = pa.schema([("id_l", pa.int64()), ("id_r", pa.int64()), ("dist", pa.float64())])


def _spectra(index: KIndex, t: SpectralTransform) -> DataFrame:
    """series_id, leaf_id and the transformed half-spectrum."""
    whole = index.spectra.select("series_id", "leaf_id", F.concat("head_re", "mid_re", "rest_re").alias("re"), F.concat("head_im", "mid_im", "rest_im").alias("im"))
    return spectrum.transformed(whole, index.n, t) if t.name != "identity" else whole


def _points(index: KIndex, t: SpectralTransform, side: str) -> DataFrame:
    """id, leaf and transformed stored coefficients, named by side."""
    out = [F.col("series_id").alias(f"id_{side}"), F.col("leaf_id").alias(f"leaf_{side}")]
    for f in index.freqs:
        re, im = G.coefficient(f, index.space)
        a, b = complex(t.a[f]), complex(t.b[f])
        out += [(re * a.real - im * a.imag + b.real).alias(f"re{f}_{side}"), (re * a.imag + im * a.real + b.imag).alias(f"im{f}_{side}")]
    return index.features.select(*out)


def _prefix(index: KIndex, n_out: int) -> Column:
    w = A.half_weights(n_out)
    gap = lambda c: (F.col(f"{c}_l") - F.col(f"{c}_r")) * (F.col(f"{c}_l") - F.col(f"{c}_r"))
    return reduce(lambda x, y: x + y, ((gap(f"re{f}") + gap(f"im{f}")) * float(w[f]) for f in index.freqs))


def _blocks(df: DataFrame, side: str, sizes: list[int]) -> DataFrame:
    columns, at = [F.col("series_id").alias(f"id_{side}")], 0
    for k, size in enumerate(sizes):
        columns += [F.slice("re", at + 1, size).alias(f"re{k}_{side}"), F.slice("im", at + 1, size).alias(f"im{k}_{side}")]
        at += size
    return df.select(*columns)


def _near(n_out: int, sizes: list[int], eps: float) -> tuple[Column, Column]:
    """Whether two sides' blocks are within eps, given up at the first block over it; and the distance."""
    w, sums, at = A.half_weights(n_out), [], 0
    for k, size in enumerate(sizes):
        gap = lambda c: F.zip_with(f"{c}{k}_l", f"{c}{k}_r", lambda x, y: x - y)  # noqa: B023, E731
        part = A.spectral_square(gap("re"), gap("im"), w[: at + size], at)
        sums.append(part if not sums else sums[-1] + part)
        at += size
    tests = [s <= (eps + SLACK) ** 2 for s in sums[:-1]] + [sums[-1] <= eps * eps]
    return reduce(lambda x, y: x & y, tests), F.sqrt(sums[-1])


def _sizes(n_out: int, staged: bool) -> list[int]:
    h = n_out // 2 + 1
    return [HEAD, h - HEAD] if staged and h > HEAD else [h]


def _ordered(pairs: DataFrame, symmetric: bool) -> DataFrame:
    return pairs.unionByName(pairs.select(F.col("id_r").alias("id_l"), F.col("id_l").alias("id_r"), "dist")) if symmetric else pairs


def symmetric(t: SpectralTransform, other: SpectralTransform) -> bool:
    """Whether |t(x) - other(y)| is |t(y) - other(x)| for all series: other is t or its negative."""
    close = lambda x, y: np.allclose(x, y, rtol=0, atol=1e-12)
    return any(close(other.a, sign * t.a) and close(other.b, sign * t.b) for sign in (1, -1))


def _vectors(batch: pa.RecordBatch, n_out: int) -> np.ndarray:
    """Half-spectra as real vectors with the distance of the series, the first coefficients first."""
    h = n_out // 2 + 1
    parts = [batch.column(batch.schema.get_field_index(c)).flatten().to_numpy(zero_copy_only=False).reshape(-1, h) * np.sqrt(A.half_weights(n_out)) for c in ("re", "im")]
    return np.stack(parts, axis=2).reshape(-1, 2 * h)


def within(x: np.ndarray, y: np.ndarray, eps: np.ndarray | float, first: list[int] | None, exact: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places in x and y, and distances, of pairs within eps (one for all, or one for each row of x): by inner products of the numbers in `first`, if given, then of all.

    Products lose digits of large numbers. What they may lose is added to eps, and where it matters, near eps and for
    small distances (everywhere, if exact), differences decide.
    """
    eps = np.broadcast_to(np.asarray(eps, float), len(x))
    rows, cols, near = np.arange(len(x)), np.arange(len(y)), None

    def squares(a, b):
        sizes = (a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)
        return sizes - 2 * (a @ b.T), 1e-9 * sizes

    if first is not None:
        square, lost = squares(x[:, first], y[:, first])
        near = square <= (eps[:, None] + SLACK) ** 2 + lost
        rows, cols = np.flatnonzero(near.any(axis=1)), np.flatnonzero(near.any(axis=0))
        near = near[np.ix_(rows, cols)]
    square, lost = squares(x[rows], y[cols])
    some = square <= (eps[rows, None] + SLACK) ** 2 + lost
    i, j = np.nonzero(some if near is None else some & near)
    square, lost = square[i, j], lost[i, j]
    i, j = rows[i], cols[j]
    limit = eps[i] ** 2
    unsure = np.flatnonzero((square <= 1000 * lost) | (np.abs(square - limit) <= lost + 3 * SLACK * (eps[i] + SLACK)) | exact)
    for at in range(0, len(unsure), GAP_PAIRS):
        k = unsure[at : at + GAP_PAIRS]
        square[k] = np.square(x[i[k]] - y[j[k]]).sum(axis=1)
    sure = square <= limit
    return i[sure], j[sure], np.sqrt(square[sure])


def each_key(key: tuple[str, ...], compare):
    """For mapInArrow over rows sorted by key: compare(one key's rows as a batch), a generator of batches. Only one key's rows are held."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in key], axis=1)
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), len(keys)]
            for start, end in zip(cuts, cuts[1:]):
                if held and tuple(keys[start]) != now:
                    yield from compare(pa.Table.from_batches(held).combine_chunks().to_batches()[0])
                    held = []
                now = tuple(keys[start])
                held.append(batch.slice(start, end - start))
        if held:
            yield from compare(pa.Table.from_batches(held).combine_chunks().to_batches()[0])

    return run


def gathered(batches: Iterator[pa.RecordBatch], most: int = OUT_PAIRS) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about `most` rows, whatever the sizes of those that come."""
    held, rows = [], 0
    for batch in batches:
        for at in range(0, batch.num_rows, most):
            held.append(batch.slice(at, most))
            rows += held[-1].num_rows
            if rows >= most:
                yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                held, rows = [], 0
    if rows:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def _found(l: np.ndarray, r: np.ndarray, dist: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(l), pa.array(r), pa.array(dist)], FOUND.names)


def tiles_for(rows: int) -> int:
    return max(1, min(TILES, math.ceil(rows / TILE_ROWS)))


def leaf_tile(index: KIndex, leaf: str, tiles: int) -> Column:
    """The tile of a leaf: neighbouring leaves share one."""
    return F.least(F.floor(F.col(leaf) * tiles / max(index.leaves, 1)), F.lit(tiles - 1)).cast("int")


def tile_rows(spectra: DataFrame, tile: Column, sent: list[list[int]], left: bool) -> DataFrame:
    """Rows (i, j, side, a, b, reach, re, im) of series (series_id, leaf_id, re, im): sent to the pairs of tiles where sent[own] names the other side's."""
    others = F.array(*(F.array(*map(F.lit, js)).cast("array<int>") for js in sent))
    rows = spectra.select("series_id", "leaf_id", "re", "im", tile.alias("own")).select("*", F.explode(F.element_at(others, F.col("own") + 1)).alias("other"))
    i, j = ("own", "other") if left else ("other", "own")
    return rows.select(F.col(i).alias("i"), F.col(j).alias("j"), F.lit(int(left)).alias("side"), F.col("series_id").alias("a"), F.col("leaf_id").alias("b"), F.lit(0.0).alias("reach"), "re", "im")


@dataclass
class Tile:
    """Series of one side, by leaf: ids, leaves and vectors."""

    ids: np.ndarray
    leaves: np.ndarray
    x: np.ndarray


@dataclass
class Work:
    """What there is to compare, by the right side's leaf."""

    a: np.ndarray
    leaf: np.ndarray
    reach: np.ndarray

    def by_leaf(self, right: Tile) -> Iterator[tuple[int, slice, slice]]:
        """Each leaf that there is work for: the leaf, its work, and its rows on the right."""
        starts = np.flatnonzero(np.diff(self.leaf, prepend=-1)).tolist()
        for start, end in zip(starts, [*starts[1:], len(self.leaf)]):
            leaf = self.leaf[start]
            first, last = np.searchsorted(right.leaves, [leaf, leaf + 1]).tolist()
            yield leaf, slice(start, end), slice(first, last)


def in_tiles(left: DataFrame, right: DataFrame, work: DataFrame | None, tiles: tuple[int, int], n_out: int, compare, schema: str) -> DataFrame:
    """compare(i, j, left, right, work) for each pair of tiles; work: (i, j, a, b, reach), what there is to compare. Series are sent to pairs of tiles, and pairs of series only leave a task as answers, a batch at a time."""
    rows = right.unionByName(left)
    if work is not None:
        none = F.lit(None).cast("array<double>")
        rows = rows.unionByName(work.select("i", "j", F.lit(2).alias("side"), "a", "b", "reach", none.alias("re"), none.alias("im")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # a partition is a pair of tiles; should some have been put together, they are told apart
        held: dict[tuple[int, int, int], list[tuple]] = {}
        for batch in batches:
            i, j, side, a, b, reach = (batch.column(k).to_numpy() for k in range(6))
            kinds = (i.astype(np.int64) * tiles[1] + j) * 3 + side
            for kind in np.unique(kinds).tolist():
                at = np.flatnonzero(kinds == kind)
                more = reach[at] if kind % 3 == 2 else _vectors(batch.take(pa.array(at)) if len(at) < len(kinds) else batch, n_out)
                held.setdefault((kind // 3 // tiles[1], kind // 3 % tiles[1], kind % 3), []).append((a[at], b[at], more))
        for i, j in sorted({key[:2] for key in held}):
            parts = []
            for side, make in ((1, Tile), (0, Tile), (2, Work)):
                own = held.pop((i, j, side), [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0) if side == 2 else np.empty((0, 2 * (n_out // 2 + 1))))])
                a, b, more = (np.concatenate(c) for c in zip(*own))
                del own
                by = np.argsort(b, kind="stable")
                parts.append(make(a[by], b[by], more[by]))
                del a, b, more, by
            if len(parts[0].ids) and len(parts[1].ids):
                yield from gathered(compare(i, j, *parts))
        pa.default_memory_pool().release_unused()

    return rows.repartitionById(tiles[0] * tiles[1], F.col("i") * tiles[1] + F.col("j")).mapInArrow(run, schema)


def scan_join(index: KIndex, t: SpectralTransform | None, eps: float, staged: bool, t_right: SpectralTransform | None = None) -> DataFrame:
    """Each series with all after it (with all others, if the two sides' transformations aren't symmetric), over transformed spectra; staged: given up early. Quadratic: a baseline.

    Series are dealt into tiles, and each task compares two tiles as matrices; TILES bounds how often a series is sent.
    """
    t = t or identity(index.n)
    other = t_right or t
    alike, n_out = symmetric(t, other), t.n_out
    tiles = tiles_for(index.features.count())
    head = list(range(2 * HEAD)) if staged and n_out // 2 + 1 > HEAD else None
    own = F.pmod(F.xxhash64("series_id"), F.lit(tiles)).cast("int")
    later, before = ([list(range(k, tiles)) for k in range(tiles)], [list(range(k + 1)) for k in range(tiles)]) if alike else ([list(range(tiles))] * tiles,) * 2

    def compare(of_l: int, of_r: int, a: Tile, b: Tile, _) -> Iterator[pa.RecordBatch]:
        step = max(1, TILE_PAIRS // len(b.x))
        for at in range(0, len(a.x), step):
            i, j, dist = within(a.x[at : at + step], b.x, eps, head)
            l, r = a.ids[i + at], b.ids[j]
            use = l < r if alike and of_l == of_r else l != r
            l, r, dist = l[use], r[use], dist[use]
            yield _found(np.minimum(l, r), np.maximum(l, r), dist) if alike else _found(l, r, dist)

    left, right = tile_rows(_spectra(index, t), own, later, True), tile_rows(_spectra(index, other), own, before, False)
    return in_tiles(left, right, None, (tiles, tiles), n_out, compare, "id_l bigint, id_r bigint, dist double")


def _stored(index: KIndex, n_out: int) -> list[int]:
    """Places of the stored coefficients in vectors of half-spectra."""
    return [k for f in index.freqs if f <= n_out // 2 for k in (2 * f, 2 * f + 1)]


def places(ids: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Where wanted ids stand among ids."""
    by = np.argsort(ids, kind="stable")
    return by[np.searchsorted(ids, wanted, sorter=by)]


def compare_leaves(left: KIndex, right: KIndex, t_left: SpectralTransform, t_right: SpectralTransform, work: DataFrame, eps: float, order: str = "any", by_id: bool = False) -> DataFrame:
    """Pairs within eps by full records, of series that work names: (leaf_l, leaf_r), or with by_id (id_l, leaf_l, leaf_r). order: any; distinct ids; or unordered, where work has leaf_l <= leaf_r.

    Points near enough in the stored coefficients are compared in full in the same task, so only series and work are shuffled, and no pair before it is an answer.
    """
    n_out, first = t_left.n_out, _stored(right, t_left.n_out)
    tiles = tuple(tiles_for(ix.features.count()) for ix in (left, right))
    work = work.select(leaf_tile(left, "leaf_l", tiles[0]).alias("i"), leaf_tile(right, "leaf_r", tiles[1]).alias("j"), F.col("id_l" if by_id else "leaf_l").alias("a"), F.col("leaf_r").alias("b"), F.lit(0.0).alias("reach"))
    used = {(i, j) for i in range(tiles[0]) for j in range(tiles[1])}
    if not by_id:  # few rows: kept, so series are only sent where there is work
        work = keep(work)
        used = {(r.i, r.j) for r in work.select("i", "j").distinct().collect()}
    sent_l, sent_r = [[j for j in range(tiles[1]) if (i, j) in used] for i in range(tiles[0])], [[i for i in range(tiles[0]) if (i, j) in used] for j in range(tiles[1])]

    def compare(of_l: int, of_r: int, a: Tile, b: Tile, todo: Work) -> Iterator[pa.RecordBatch]:
        at = places(a.ids, todo.a) if by_id else None
        low, high = (None, None) if by_id else (np.searchsorted(a.leaves, todo.a), np.searchsorted(a.leaves, todo.a, "right"))
        for leaf, mine, theirs in todo.by_leaf(b):
            rows = at[mine] if by_id else np.concatenate([np.arange(f, e) for f, e in zip(low[mine], high[mine])])
            step = max(1, TILE_PAIRS // max(1, theirs.stop - theirs.start))
            for k in range(0, len(rows), step):
                some = rows[k : k + step]
                i, j, dist = within(a.x[some], b.x[theirs], eps, first)
                l, r = a.ids[some[i]], b.ids[theirs][j]
                if order == "unordered":
                    use = (a.leaves[some[i]] < leaf) | (l < r)
                    l, r, dist = np.minimum(l, r)[use], np.maximum(l, r)[use], dist[use]
                elif order == "distinct":
                    use = l != r
                    l, r, dist = l[use], r[use], dist[use]
                yield _found(l, r, dist)

    rows_l = tile_rows(_spectra(left, t_left), leaf_tile(left, "leaf_id", tiles[0]), sent_l, True)
    rows_r = tile_rows(_spectra(right, t_right), leaf_tile(right, "leaf_id", tiles[1]), sent_r, False)
    return in_tiles(rows_l, rows_r, work, tiles, n_out, compare, "id_l bigint, id_r bigint, dist double")


def refine_pairs(left: KIndex, right: KIndex, pairs: DataFrame, t_left: SpectralTransform, t_right: SpectralTransform, eps: float) -> DataFrame:
    """Pairs (id_l, id_r) within eps by full records; only ids are shuffled to these."""
    sizes = _sizes(t_left.n_out, True)
    near, distance = _near(t_left.n_out, sizes, eps)
    full = pairs.join(_blocks(_spectra(left, t_left), "l", sizes), "id_l").join(_blocks(_spectra(right, t_right), "r", sizes), "id_r")
    return full.where(near).select("id_l", "id_r", distance.alias("dist"))


def _meet(left: KIndex, n_out: int, eps: float) -> Column:
    """Whether boxes of two sides, mapped already, come within eps in each stored coefficient."""
    w, test = A.half_weights(n_out), F.lit(True)
    for f in left.freqs:
        reach = eps / math.sqrt(w[f])
        for a in ([f"m{f}"] if left.space == "polar" else [f"re{f}", f"im{f}"]):
            test = test & (F.col(f"lo_{a}_l") - reach - SLACK <= F.col(f"hi_{a}_r")) & (F.col(f"lo_{a}_r") <= F.col(f"hi_{a}_l") + reach + SLACK)
        if left.space == "polar":
            m = F.col(f"lo_m{f}_l")
            half = F.when(m > reach * (1 + 1e-6) + 1e-6, F.asin(F.least(F.lit(reach) / m, F.lit(1.0)))).otherwise(F.lit(math.pi))
            start, arc = F.col(f"lo_p{f}_l") - half, F.col(f"hi_p{f}_l") - F.col(f"lo_p{f}_l") + 2 * half
            test = test & ((arc >= G.TURN) | G.arcs_meet(start, arc, F.col(f"lo_p{f}_r"), F.col(f"hi_p{f}_r") - F.col(f"lo_p{f}_r")))
    return test


def _leaf_pairs(left: KIndex, right: KIndex, t_left: SpectralTransform, t_right: SpectralTransform, eps: float) -> DataFrame:
    """(leaf_l, leaf_r) whose mapped boxes come within eps: both trees are descended together, from the pair of roots, and only pairs of nodes that meet are looked into."""
    test = _meet(left, t_left.n_out, eps)
    nodes = {"_l": (left, view(left, t_left)), "_r": (right, view(right, t_right))}
    top = max(left.levels, right.levels) - 1
    at = {"_l": left.levels - 1, "_r": right.levels - 1}
    roots = [boxes(index, seen, at[side], side) for side, (index, seen) in nodes.items()]
    pairs = roots[0].join(roots[1], F.col("up_l") == F.col("up_r")).where(test)
    for level in range(top - 1, -1, -1):
        for side, (index, seen) in nodes.items():
            if at[side] > level:
                kept = [c for c in pairs.columns if not c.endswith(side)]
                below = boxes(index, seen, level, side)
                pairs = pairs.select(*kept, F.col(f"node{side}").alias("parent")).join(below, F.col("parent") == F.col(f"up{side}")).drop("parent").where(test)
                at[side] = level
    return pairs.select(F.col("node_l").alias("leaf_l"), F.col("node_r").alias("leaf_r"))


def descend(outer: DataFrame, index: KIndex, t: SpectralTransform, meets: Column) -> DataFrame:
    """outer's rows with each leaf (leaf_r) that they reach from the root: into nodes of the tree after t for which meets holds, a test over outer's columns and lo_, hi_ of the axes."""
    seen = view(index, t)
    found = outer.withColumn("node", F.lit(0).cast("long"))
    for level in range(index.levels - 1, -1, -1):
        below = boxes(index, seen, level)
        found = found.withColumnRenamed("node", "parent").join(below, F.col("parent") == F.col("up")).where(meets).select(*outer.columns, "node")
    return found.withColumnRenamed("node", "leaf_r")


def join(left: KIndex, right: KIndex, t_left: SpectralTransform | None, t_right: SpectralTransform | None, eps: float) -> DataFrame:
    """(id_l, id_r, dist) with |T_left(x) - T_right(y)| <= eps: pairs of leaves, then of points near enough in the stored coefficients, then full records."""
    t_left, t_right = t_left or identity(left.n), t_right or identity(right.n)
    return compare_leaves(left, right, t_left, t_right, _leaf_pairs(left, right, t_left, t_right, eps), eps)


def self_join(index: KIndex, t: SpectralTransform | None, eps: float, pairs: str = "unordered", t_right: SpectralTransform | None = None) -> DataFrame:
    """Pairs of different series of one relation. t_right: the other side's transformation, say with a reversal.

    Where both sides are treated alike, or one as the other's negative, a pair is the same in both orders: once, or
    ordered if asked. Otherwise the orders differ, and each (id_l, id_r) with |t(l) - t_right(r)| <= eps is a row of its own.
    """
    t = t or identity(index.n)
    other = t_right or t
    alike = symmetric(t, other)
    leaves = _leaf_pairs(index, index, t, other, eps)
    if not alike:
        return compare_leaves(index, index, t, other, leaves, eps, "distinct")
    return _ordered(compare_leaves(index, index, t, other, leaves.where("leaf_l <= leaf_r"), eps, "unordered"), pairs == "ordered")


def grid_join(left: KIndex, right: KIndex, t_left: SpectralTransform | None, t_right: SpectralTransform | None, eps: float, distinct_ids: bool = False) -> DataFrame:
    """The same by cells of width eps over the first stored coefficient: one side goes to the cells beside its own, and cells are an equi-join. distinct_ids: id_l < id_r only."""
    t_left, t_right = t_left or identity(left.n), t_right or identity(right.n)
    f = left.freqs[0]
    width = (eps + SLACK) / math.sqrt(A.half_weights(t_left.n_out)[f])
    cell = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    around = lambda c: F.explode(F.array(cell(c) - 1, cell(c), cell(c) + 1))
    a = _points(left, t_left, "l").withColumn("x", around(f"re{f}_l")).withColumn("y", around(f"im{f}_l"))
    b = _points(right, t_right, "r").withColumn("x", cell(f"re{f}_r")).withColumn("y", cell(f"im{f}_r"))
    near = a.join(b, ["x", "y"]).where(_prefix(left, t_left.n_out) <= (eps + SLACK) ** 2)
    near = near.where("id_l < id_r") if distinct_ids else near
    return refine_pairs(left, right, near.select("id_l", "id_r"), t_left, t_right, eps)


def _spread(t: SpectralTransform, h: int) -> list[int]:
    """Coefficients by how much t leaves of them, those of frequency 0 last."""
    return sorted(range(1, h), key=lambda f: -abs(t.a[f])) + [0]


def cell_join(spectra: DataFrame, n: int, t: SpectralTransform, eps: float) -> DataFrame:
    """Pairs id_l < id_r of one relation (spectra: series_id, re, im) with |t(l) - t(r)| <= eps, without a tree.

    The two coefficients of which t leaves most make cells of four axes, at least 2 eps wide. A series goes to its own cell, and
    as a left one to each cell within eps of it; a task compares a cell's two sides by CELL_COEFFICIENTS
    coefficients as matrices, and only what passes is compared in full. So no pair of leaves or points is shuffled before it is near.
    """
    h = t.n_out // 2 + 1
    full = spectrum.transformed(spectra, n, t).select("series_id", "re", "im")
    w, used = A.half_weights(t.n_out), _spread(t, h)[:CELL_COEFFICIENTS]
    axes = [F.get(c, f) * float(math.sqrt(w[f])) for f in used for c in ("re", "im")]
    grid = range(min(4, len(axes)))
    points = full.select(F.col("series_id").alias("id"), F.array(*axes).alias("x"))
    ends = points.agg(*(e(F.get("x", k)).alias(f"{name}{k}") for k in grid for name, e in (("lo", F.min), ("hi", F.max)))).first()
    reach = eps + SLACK
    width = [max(2 * reach, ((ends[f"hi{k}"] or 0.0) - (ends[f"lo{k}"] or 0.0)) / CELLS) for k in grid]
    cell = lambda k, by=0.0: F.floor((F.get("x", k) + by) / F.lit(width[k])).cast("int")
    homes = points.select(F.array(*(cell(k) for k in grid)).alias("cell"), "id", "x")
    near = points
    for k in grid:
        near = near.withColumn(f"c{k}", F.explode(F.sequence(cell(k, -reach), cell(k, reach))))
    near = near.select(F.array(*(f"c{k}" for k in grid)).alias("cell"), "id", "x")

    def compare(a: pa.Table, b: pa.Table) -> pa.Table:
        (ids_l, x), (ids_r, y) = ((s.column("id").to_numpy(), s.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, 2 * len(used))) for s in (a, b))
        out = []
        if len(ids_l) and len(ids_r):
            # in the order of a further axis, so rows meet a stretch of the other side
            along = min(4, x.shape[1] - 1)
            by_l, by_r = np.argsort(x[:, along]), np.argsort(y[:, along])
            ids_l, x, ids_r, y = ids_l[by_l], x[by_l], ids_r[by_r], y[by_r]
            for at in range(0, len(x), SCAN_ROWS):
                some, ids = x[at : at + SCAN_ROWS], ids_l[at : at + SCAN_ROWS]
                first, end = np.searchsorted(y[:, along], [some[0, along] - reach, some[-1, along] + reach])
                for begin in range(first, end, CELL_ROWS):
                    other, ids_o = y[begin : min(begin + CELL_ROWS, end)], ids_r[begin : min(begin + CELL_ROWS, end)]
                    own, size = (some * some).sum(axis=1)[:, None], (other * other).sum(axis=1)
                    i, j = np.nonzero(own + size - 2 * (some @ other.T) <= reach * reach + 1e-9 * (own + size))
                    use = ids[i] < ids_o[j]
                    out.append(pa.table({"id_l": ids[i[use]], "id_r": ids_o[j[use]]}))
        return pa.concat_tables(out) if out else FOUND.empty_table().select(["id_l", "id_r"])

    pairs = near.groupBy("cell").cogroup(homes.groupBy("cell")).applyInArrow(compare, "id_l bigint, id_r bigint")
    sizes = [h]
    within, distance = _near(t.n_out, sizes, eps)
    found = pairs.join(_blocks(full, "l", sizes), "id_l").join(_blocks(full, "r", sizes), "id_r")
    return found.where(within).select("id_l", "id_r", distance.alias("dist"))


def index_nested_loop(index: KIndex, t: SpectralTransform | None, eps: float) -> DataFrame:
    """Each series as a range query against the index, with t on the index and on the search boxes; both orders of each pair. From the root down, an outer series goes into the nodes that its search box meets."""
    t = t or identity(index.n)
    w = A.half_weights(t.n_out)
    axes, meets = {}, F.lit(True)
    for f in index.freqs:
        reach = eps / math.sqrt(w[f]) + SLACK
        if index.space == "polar":
            m = F.hypot(f"re{f}_l", f"im{f}_l")
            half = F.when(m > reach * (1 + 1e-6) + 1e-6, F.asin(F.least(F.lit(reach) / m, F.lit(1.0)))).otherwise(F.lit(math.pi))
            # computed once for a series, not for each node it is held against
            axes |= {f"m{f}_l": m, f"start{f}_l": F.atan2(f"im{f}_l", f"re{f}_l") - half, f"arc{f}_l": 2 * half}
            meets = meets & (F.col(f"lo_m{f}") <= F.col(f"m{f}_l") + reach) & (F.col(f"hi_m{f}") >= F.col(f"m{f}_l") - reach)
            meets = meets & ((F.col(f"arc{f}_l") >= G.TURN) | G.arcs_meet(F.col(f"start{f}_l"), F.col(f"arc{f}_l"), F.col(f"lo_p{f}"), F.col(f"hi_p{f}") - F.col(f"lo_p{f}")))
        else:
            for p in ("re", "im"):
                axes[f"{p}{f}_l"] = F.col(f"{p}{f}_l")
                meets = meets & (F.col(f"lo_{p}{f}") <= F.col(f"{p}{f}_l") + reach) & (F.col(f"hi_{p}{f}") >= F.col(f"{p}{f}_l") - reach)
    outer = _points(index, t, "l").select("id_l", "leaf_l", *(c.alias(name) for name, c in axes.items()))
    return compare_leaves(index, index, t, t, descend(outer, index, t, meets).select("id_l", "leaf_l", "leaf_r"), eps, "distinct", by_id=True)


def speedups(seconds: dict[str, float]) -> dict[str, float]:
    """Ratios a/b, b/c, b/d and d/c of the join methods' times."""
    return {f"{x}/{y}": seconds[x] / seconds[y] for x, y in ("ab", "bc", "bd", "dc") if seconds.get(x) and seconds.get(y)}


def tail_bound(t: SpectralTransform, freqs: tuple[int, ...]) -> float:
    """The largest multiplier beyond the stored coefficients."""
    rest = np.abs(t.a[: t.n_out // 2 + 1]).copy()
    rest[[f for f in freqs if f < len(rest)]] = 0
    return float(rest.max(initial=0))
