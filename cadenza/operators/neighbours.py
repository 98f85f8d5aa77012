"""Nearest neighbours under a transformation, in two rounds rather than a priority queue."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions import geometry as G
from cadenza.functions.safety import is_safe
from cadenza.functions.transforms import SpectralTransform, identity
from cadenza.model import SLACK
from cadenza.operators.joins import OUT_PAIRS, TILE_PAIRS, Tile, Work, _found, _points, _spectra, _stored, _vectors, descend, each_key, gathered, in_tiles, leaf_tile, places, tail_bound, tile_rows, tiles_for, within
from cadenza.operators.kindex import BROADCAST_NODES, FAN_OUT, KIndex, boxes, view
from cadenza.operators.range_search import refine, search
from cadenza.plans.planner import plan_search, prefix_square
from cadenza.storage import keep


def minmax_square(at: dict[str, tuple[float, float]], farthest: bool = False) -> Column:
    """Square of a distance within which a box surely holds a point, by the weighted axes in at {axis: (query, weight)}: each face touches one. farthest: within which it holds all its points, as is needed if one of them doesn't count."""
    near, far = {}, {}
    for a, (q, w) in at.items():
        low, high = F.col(f"lo_{a}"), F.col(f"hi_{a}")
        ends = F.pow(low - q, F.lit(2.0)) * w, F.pow(high - q, F.lit(2.0)) * w
        near[a], far[a] = F.least(*ends), F.greatest(*ends)
    every = reduce(lambda x, y: x + y, far.values())
    return every if farthest else F.least(*(every - far[a] + near[a] for a in at))


def search_nearest(index: KIndex, q, t: SpectralTransform | None, j: int, transform_query: bool = False, bound: str = "features", exclude: int | None = None) -> DataFrame:
    """(series_id, dist) of the j nearest, ties by id.

    Round one finds a distance that j series are surely within; round two is a range query for it.
    features: from an upper bound for each series, of its stored coefficients and tail energy, so no
    full record is read. mindist: the full distances of series in the leaves nearest to q, until
    there are 4 j of them. minmaxdist: from boxes alone: each leaf surely holds a point within its MINMAXDIST in the
    stored coefficients, and what the rest can add is bounded by the leaf's largest tail energy; rectangular space only.
    """
    plan = plan_search(index, q, t, math.inf, transform_query)
    others = index.features if exclude is None else index.features.where(F.col("series_id") != exclude)
    where = None if exclude is None else F.col("series_id") != exclude
    if bound == "features":
        rest = plan.weights.copy()
        rest[[f for f in index.freqs if f < len(rest)]] = 0
        q_tail = math.sqrt(float((rest * np.abs(plan.q[: len(rest)]) ** 2).sum()))
        at_most = F.sqrt(prefix_square(plan, index) + F.pow(tail_bound(plan.t, index.freqs) * F.sqrt(F.greatest("tail_energy", F.lit(0.0))) + q_tail, F.lit(2.0)))
        best = others.select(at_most.alias("u")).orderBy("u").limit(j)
    elif bound == "minmaxdist":
        if index.space != "rect" or not is_safe(plan.t, "rect").safe:
            raise ValueError("minmaxdist needs the rectangular space and a transformation that is safe there")
        rest = plan.weights.copy()
        rest[[f for f in index.freqs if f < len(rest)]] = 0
        q_tail = math.sqrt(float((rest * np.abs(plan.q[: len(rest)]) ** 2).sum()))
        leaves = view(index, plan.t).where("level = 0")
        if exclude is not None:  # a leaf's point that is surely near may be the one left out
            leaves = leaves.where("n_points > 1")
        ahead = minmax_square({f"{p}{f}": (float(x), float(plan.weights[f])) for f in index.freqs for p, x in (("re", plan.q[f].real), ("im", plan.q[f].imag))}, exclude is not None)
        at_most = F.sqrt(ahead + F.pow(tail_bound(plan.t, index.freqs) * F.sqrt(F.greatest("tail_max", F.lit(0.0))) + q_tail, F.lit(2.0)))
        best = leaves.select(at_most.alias("u")).orderBy("u").limit(j)
    else:
        square = reduce(lambda x, y: x + y, (G.box_distance_square(f, complex(plan.t.a[f]), F.lit(float(plan.q[f].real)), F.lit(float(plan.q[f].imag)), index.space) * float(plan.weights[f]) for f in index.freqs))
        leaves = index.nodes.where("level = 0").select("node_id", "n_points", square.alias("d")).orderBy("d", "node_id")
        # at most 4 j leaves are looked at, as each holds a point
        chosen, points = [], 0
        for r in leaves.limit(4 * j).collect():
            if points >= 4 * j:
                break
            chosen.append(r.node_id)
            points += r.n_points
        probe = refine(index, others.where(F.col("leaf_id").isin(chosen)), plan)
        best = probe.select(F.col("dist").alias("u")).orderBy("u").limit(j)
    found = [r.u for r in best.collect()]
    reach = max(found) * (1 + 1e-9) + SLACK if len(found) == j else math.inf
    if math.isinf(reach):
        near = refine(index, others, plan)
    else:
        near = search(index, q, t, reach, transform_query, where=where)
    return near.orderBy("dist", "series_id").limit(j)


def join_nearest(left: KIndex, right: KIndex, t: SpectralTransform | None, j: int, probe_points: int = 4, distinct_ids: bool = False) -> DataFrame:
    """(id_l, id_r, dist, rank): the j nearest of right for each of left, t on both.

    Each left series first goes down right's tree, always to the nearest node that holds probe_points * j
    points; it is compared with the points there in full, and the j-th distance is its reach. Then it goes
    down once more, into all nodes within its reach, and is compared with what it finds there; each task keeps the j nearest it has seen. If right holds fewer points, it gets them all.
    Series and the nodes they reach are shuffled, and no pairs but the j nearest of each task.
    """
    t = t or identity(left.n)
    n_out, w = t.n_out, A.half_weights(t.n_out)
    names = [f"{p}{f}_l" for f in right.freqs for p in ("re", "im")]
    outer = _points(left, t, "l")
    # boxes are mapped by view(), so the distance is taken to them as they are
    box = F.sqrt(reduce(lambda x, y: x + y, (G.box_distance_square(f, 1 + 0j, F.col(f"re{f}_l"), F.col(f"im{f}_l"), right.space) * float(w[f]) for f in right.freqs)))
    seen = view(right, t)
    need = probe_points * j
    home = outer.select("id_l", *names, F.lit(0).cast("long").alias("node"), F.lit(right.levels - 1).alias("at"))
    for level in range(right.levels - 2, -1, -1):
        below = boxes(right, seen, level).join(seen.where(F.col("level") == level).select(F.col("node_id").alias("node"), "n_points"), "node").where(F.col("n_points") >= need).drop("n_points").withColumnRenamed("node", "child")
        below = F.broadcast(below) if right.leaves <= BROADCAST_NODES * FAN_OUT**level else below
        nearest = home.where(F.col("at") == level + 1).join(below, F.col("node") == F.col("up")).groupBy("id_l").agg(F.min_by("child", F.struct(box, F.col("child"))).alias("child"))
        home = home.join(nearest, "id_l", "left").select("id_l", *names, F.coalesce("child", "node").alias("node"), F.when(F.col("child").isNull(), F.col("at")).otherwise(F.lit(level)).alias("at"))
    homes = keep(home.select("id_l", "at", "node"))
    reaching = outer.join(keep(_reaches(left, right, t, j, homes, distinct_ids)), "id_l", "left").withColumn("reach", F.coalesce("reach", F.lit(math.inf)))
    tiles = tuple(tiles_for(ix.features.count()) for ix in (left, right))
    ahead = box <= F.col("reach")
    if right.space == "polar":
        # magnitudes alone rule most nodes out, at little cost
        reaching = reaching.withColumns({f"m{f}_l": F.hypot(f"re{f}_l", f"im{f}_l") for f in right.freqs})
        side = lambda f: F.col("reach") / float(math.sqrt(w[f])) + SLACK
        ahead = reduce(lambda x, y: x & y, ((F.col(f"lo_m{f}") <= F.col(f"m{f}_l") + side(f)) & (F.col(f"hi_m{f}") >= F.col(f"m{f}_l") - side(f)) for f in right.freqs)) & ahead
    # a series is a small row, but much work
    reaching = reaching.repartition(4 * reaching.sparkSession.sparkContext.defaultParallelism)
    work = descend(reaching, right, t, ahead).select(leaf_tile(left, "leaf_l", tiles[0]).alias("i"), leaf_tile(right, "leaf_r", tiles[1]).alias("j"), F.col("id_l").alias("a"), F.col("leaf_r").alias("b"), "reach")
    first = _stored(right, n_out)

    def compare(of_l: int, of_r: int, a: Tile, b: Tile, todo: Work) -> Iterator[pa.RecordBatch]:
        at, reach = places(a.ids, todo.a), np.full(len(a.x), math.inf)
        reach[at] = todo.reach
        best, more, held = (np.empty(0, int), np.empty(0), np.empty(0, int)), [], 0

        def kept() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            row, dist, ids = (np.concatenate(c) for c in zip(best, *more))
            by = np.lexsort((ids, dist, row))
            row, dist, ids = row[by], dist[by], ids[by]
            nth = np.arange(len(row)) - np.searchsorted(row, row)
            last = nth == j - 1
            reach[row[last]] = np.minimum(reach[row[last]], dist[last] * (1 + 1e-9) + SLACK)
            return row[nth < j], dist[nth < j], ids[nth < j]

        for _, mine, theirs in todo.by_leaf(b):
            step = max(1, TILE_PAIRS // max(1, theirs.stop - theirs.start))
            for k in range(mine.start, mine.stop, step):
                some = at[k : min(k + step, mine.stop)]
                i, near, dist = within(a.x[some], b.x[theirs], reach[some], first, exact=True)
                row, ids = some[i], b.ids[theirs][near]
                use = a.ids[row] != ids if distinct_ids else slice(None)
                more.append((row[use], dist[use], ids[use]))
                held += len(more[-1][0])
                if held > OUT_PAIRS:
                    best, more, held = kept(), [], 0
        row, dist, ids = kept()
        yield _found(a.ids[row], ids, dist)

    every = [list(range(tiles[1]))] * tiles[0], [list(range(tiles[0]))] * tiles[1]
    rows_l = tile_rows(_spectra(left, t), leaf_tile(left, "leaf_id", tiles[0]), every[0], True)
    rows_r = tile_rows(_spectra(right, t), leaf_tile(right, "leaf_id", tiles[1]), every[1], False)
    full = in_tiles(rows_l, rows_r, work, tiles, n_out, compare, "id_l bigint, id_r bigint, dist double")
    rank = F.row_number().over(Window.partitionBy("id_l").orderBy("dist", "id_r"))
    return full.withColumn("rank", rank).where(F.col("rank") <= j)


def _reaches(left: KIndex, right: KIndex, t: SpectralTransform, j: int, homes: DataFrame, distinct_ids: bool) -> DataFrame:
    """(id_l, reach) from homes (id_l, at, node): a distance within which the j nearest points of each series' node are; none where it has fewer."""
    n_out = t.n_out
    levels = F.array(*(F.struct(F.lit(k).alias("at"), F.floor(F.col("leaf_id") / float(FAN_OUT**k)).cast("long").alias("node")) for k in range(right.levels)))
    used = homes.select("at", "node").distinct()
    points = _spectra(right, t).select("series_id", "re", "im", F.explode(levels).alias("u")).select("u.at", "u.node", F.lit(0).alias("side"), F.col("series_id").alias("a"), "re", "im")
    points = points.join(F.broadcast(used) if right.leaves <= BROADCAST_NODES else used, ["at", "node"], "left_semi")
    own = _spectra(left, t).join(homes, F.col("series_id") == F.col("id_l")).select("at", "node", F.lit(1).alias("side"), F.col("id_l").alias("a"), "re", "im")

    def compare(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        cut = int(np.searchsorted(batch.column(2).to_numpy(), 1))
        if cut == 0 or cut == batch.num_rows:
            return
        ids, x = batch.column(3).to_numpy(), _vectors(batch, n_out)
        x, y, ids_l, ids_r = x[cut:], x[:cut], ids[cut:], ids[:cut]
        step = max(1, TILE_PAIRS // len(y))
        for k in range(0, len(x), step):
            some = x[k : k + step]
            sizes = np.square(some).sum(axis=1)[:, None] + np.square(y).sum(axis=1)
            # products lose digits: what they may lose is added
            square = np.maximum(sizes - 2 * (some @ y.T), 0) + 1e-9 * sizes
            if distinct_ids:
                square[ids_l[k : k + step, None] == ids_r] = math.inf
            reach = np.sqrt(np.partition(square, j - 1, axis=1)[:, j - 1]) if len(y) >= j else np.full(len(some), math.inf)
            held = np.isfinite(reach)
            yield pa.RecordBatch.from_arrays([pa.array(ids_l[k : k + step][held]), pa.array(reach[held] * (1 + 1e-9) + SLACK)], ["id_l", "reach"])

    dealt = points.unionByName(own).repartition("at", "node").sortWithinPartitions("at", "node", "side")
    run = each_key(("at", "node"), compare)
    return dealt.mapInArrow(lambda batches: gathered(run(batches)), "id_l bigint, reach double")
