"""Range queries: by the index under a transformation, and by scans."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions import geometry as G
from cadenza.functions.transforms import SpectralTransform
from cadenza.model import SLACK, SeriesRelation
from cadenza.operators import spectrum
from cadenza.operators.kindex import KIndex
from cadenza.plans.planner import SearchPlan, block_squares, choose_strategy, plan_search, prefix_square, within


def surviving(index: KIndex, plan: SearchPlan, level: int) -> DataFrame:
    """Nodes of a level that the search reaches: their mapped box meets the search box, as do those of all above."""
    meets = reduce(lambda x, y: x & y, (G.box_meets(axis, f, complex(plan.t.a[f]), complex(plan.t.b[f]), index.space) for f, axis in plan.axes.items()), F.lit(True))
    alive = index.nodes.where((F.col("level") == index.levels - 1) & meets)
    for k in range(index.levels - 2, level - 1, -1):
        above = index.small(alive.select(F.col("node_id").alias("parent_id")))
        alive = index.nodes.where((F.col("level") == k) & meets).join(above, "parent_id", "left_semi")
    return alive


def candidates(index: KIndex, plan: SearchPlan, where: Column | None = None, mirror: bool = True, push_bounds: bool = True) -> DataFrame:
    """Features of series that may be within eps: in leaves reached, within the box mapped back to stored columns (compared as they are, so Parquet can skip), and near enough in the stored coefficients."""
    found = index.features
    if where is not None:
        found = found.where(where)
    if not plan.safe:
        return found
    if push_bounds:
        found = found.where(reduce(lambda x, y: x & y, (G.raw_bounds(axis, f, complex(plan.t.a[f]), complex(plan.t.b[f]), index.space) for f, axis in plan.axes.items())))
    leaves = index.small(surviving(index, plan, 0).select(F.col("node_id").alias("leaf_id")))
    near = within(prefix_square(plan, index, mirror), plan.eps + SLACK)
    return found.join(leaves, "leaf_id", "left_semi").where(near)


def _staged(plan: SearchPlan, strict: bool) -> tuple[Column, Column]:
    """A conjunction that stops at the first block over eps, and the distance."""
    blocks = block_squares(plan.t, plan.q, plan.weights)
    sums = [reduce(lambda x, y: x + y, blocks[: i + 1]) for i in range(len(blocks))]
    return reduce(lambda x, y: x & y, (within(s, plan.eps, strict and s is sums[-1]) if s is sums[-1] else within(s, plan.eps + SLACK) for s in sums)), F.sqrt(sums[-1])


def refine(index: KIndex, ids: DataFrame, plan: SearchPlan, strict: bool = False) -> DataFrame:
    """(series_id, dist) of those in ids within eps, by their full records."""
    full = index.spectra.join(ids.select("series_id"), "series_id", "left_semi")
    if plan.t.n_out == plan.t.n:
        near, distance = _staged(plan, strict)
        return full.where(near).select("series_id", distance.alias("dist"))
    whole = full.select("series_id", F.concat("head_re", "mid_re", "rest_re").alias("re"), F.concat("head_im", "mid_im", "rest_im").alias("im"))
    moved = spectrum.transformed(whole, plan.t.n, plan.t)
    h = len(plan.weights)
    re = F.zip_with("re", A.literal(plan.q[:h].real), lambda x, y: x - y)
    im = F.zip_with("im", A.literal(plan.q[:h].imag), lambda x, y: x - y)
    squares = A.spectral_square(re, im, plan.weights)
    return moved.withColumn("square", squares).where(within(F.col("square"), plan.eps, strict)).select("series_id", F.sqrt("square").alias("dist"))


def search(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False, strict: bool = False, where: Column | None = None, mean: tuple[float, float] | None = None, sd: tuple[float, float] | None = None, mirror: bool = True, push_bounds: bool = True, strategy: str = "index") -> DataFrame:
    """(series_id, dist) for all stored series x with |T(x) - q| <= eps (< if strict), exactly.

    q is a series in the time domain; it is brought to normal form if the index is over these, and
    transformed too if asked. t None: no transformation. mean and sd bound those of the raw series,
    where bounds any column of the features. strategy: index, scan, or auto.
    """
    plan = plan_search(index, q, t, eps, transform_query, mirror)
    for name, bounds in (("mean", mean), ("sd", sd)):
        if bounds:
            part = F.col(name).between(*bounds)
            where = part if where is None else where & part
    way = choose_strategy(index, plan) if strategy == "auto" else strategy
    if way == "scan" or not plan.safe:
        ids = index.features if where is None else index.features.where(where)
        return refine(index, ids, plan, strict)
    return refine(index, candidates(index, plan, where, mirror, push_bounds), plan, strict)


def single(index: KIndex, series_id: int, q, t: SpectralTransform | None, eps: float, transform_query: bool = False) -> DataFrame:
    """The query about one stored series: its own record alone is read."""
    plan = plan_search(index, q, t, eps, transform_query)
    return refine(index, index.features.where(F.col("series_id") == series_id), plan)


def scan_naive(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False) -> DataFrame:
    """All spectra, transformed whole, compared whole."""
    plan = plan_search(index, q, t, eps, transform_query)
    squares = reduce(lambda x, y: x + y, block_squares(plan.t, plan.q, plan.weights))
    return index.spectra.select("series_id", F.sqrt(squares).alias("dist")).where(F.col("dist") <= eps)


def scan_abandon(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False) -> DataFrame:
    """All spectra, each given up at the first block that takes it over eps."""
    near, distance = _staged(plan_search(index, q, t, eps, transform_query), False)
    return index.spectra.where(near).select("series_id", distance.alias("dist"))


def scan_time(r: SeriesRelation, q, weights: list[float] | None, eps: float, normal: bool = True, transform_query: bool = False, staged: int = 0) -> DataFrame:
    """All series, filtered and compared in the time domain; staged: given up if so many first values take it over eps."""
    base = spectrum.normalize(r) if normal else r
    q = np.asarray(q, float)
    target = (q - q.mean()) / q.std() if normal else q
    if transform_query and weights:
        target = sum(w * np.roll(target, j) for j, w in enumerate(weights))
    filtered = A.circular(F.col("values"), A.literal(weights)) if weights else F.col("values")
    whole = lambda x: A.euclid(x, A.literal(target))
    first = lambda x: A.euclid(F.slice(x, 1, staged), A.literal(target[:staged]))
    distance = A.let(filtered, lambda x: F.when(first(x) <= eps + SLACK, whole(x))) if staged else whole(filtered)
    return base.df.select("series_id", distance.alias("dist")).where(F.col("dist") <= eps)


def explain(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False) -> str:
    """Nodes reached by level, and the plan."""
    plan = plan_search(index, q, t, eps, transform_query)
    lines = [f"level {k}: {surviving(index, plan, k).count()} of {index.nodes.where(F.col('level') == k).count()} nodes" for k in range(index.levels - 1, -1, -1)] if plan.safe else ["no index: unsafe"]
    df = search(index, q, t, eps, transform_query)
    return "\n".join([f"strategy: {choose_strategy(index, plan)}", *lines, df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")])
