"""Least distance over transformations of either side, each at a cost."""

from __future__ import annotations

import math
from functools import reduce
from itertools import combinations_with_replacement, product

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions.transforms import SpectralTransform, identity
from cadenza.model import SLACK, SeriesRelation
from cadenza.operators import spectrum
from cadenza.storage import keep


def closure(catalog: list[SpectralTransform], budget: float, max_depth: int) -> list[SpectralTransform]:
    """All compositions of up to max_depth transformations whose costs add up to the budget at most.

    Multipliers commute, so where nothing is translated each multiset of transformations counts once. With a
    translation among them the order matters and each order counts; paths name the steps as they are applied.
    """
    n = catalog[0].n
    ordered = any(t.has_translation for t in catalog)
    found = [identity(n)]
    for depth in range(1, max_depth + 1):
        for some in product(catalog, repeat=depth) if ordered else combinations_with_replacement(catalog, depth):
            if sum(t.cost for t in some) <= budget:
                whole = some[0]
                for t in some[1:]:
                    whole = t @ whole
                names = [t.name for t in some]
                found.append(SpectralTransform("+".join(names if ordered else sorted(names)), n, whole.a, whole.b, sum(t.cost for t in some)))
    return found


def catalog_frame(spark, transforms: list[SpectralTransform]) -> DataFrame:
    """The closure as a small table (t_id, path, cost, a_re, a_im, b_re, b_im) over half-spectra."""
    rows = []
    for i, t in enumerate(transforms):
        half = t.n // 2 + 1
        rows.append((i, "" if t.name == "identity" else t.name, float(t.cost), *([float(x) for x in v[:half]] for v in (t.a.real, t.a.imag, t.b.real, t.b.imag))))
    return spark.createDataFrame(rows, "t_id int, path string, cost double, a_re array<double>, a_im array<double>, b_re array<double>, b_im array<double>")


def bounded(r: SeriesRelation, pairs: DataFrame, catalog: list[SpectralTransform], budget: float = math.inf, max_depth: int = 2, normal: bool = True, ratio: float | None = None, prefix: int = 3) -> DataFrame:
    """id_l, id_r, dist (least total), cost, path_l, path_r for pairs (id_l, id_r) of normal forms (normal) or of the series themselves.

    Distances are at least 0, so compositions that cost the plain distance or more can't help: only cheaper ones are
    tried on a pair. Of these, those whose first `prefix` coefficients with the cost come to the plain distance are
    out before the whole spectra are compared. The cost is also limited by the budget, by ratio times the plain distance if a
    ratio is given, and the number of steps by max_depth on each side. The catalogue of compositions is small (it depends on no data) and is broadcast.
    """
    if math.isinf(budget) and max_depth > 6:
        raise ValueError("compositions without a budget need a small depth")
    frame = F.broadcast(catalog_frame(r.df.sparkSession, closure(catalog, budget, max_depth)))
    spectra = spectrum.dft(spectrum.normalize(r) if normal else r).select("series_id", "re", "im")
    w = A.half_weights(r.n)
    of = lambda side: spectra.select(F.col("series_id").alias(f"id_{side}"), F.col("re").alias(f"re_{side}"), F.col("im").alias(f"im_{side}"))
    plain = F.sqrt(A.spectral_square(F.zip_with("re_l", "re_r", lambda x, y: x - y), F.zip_with("im_l", "im_r", lambda x, y: x - y), w))
    both = pairs.select("id_l", "id_r").join(of("l"), "id_l").join(of("r"), "id_r").withColumn("plain", plain)
    # each series is transformed once; its first coefficients stand beside it as plain columns
    few = min(prefix, r.n // 2 + 1)
    re = F.transform("re", lambda x, i: x * F.get("a_re", i) - F.get("im", i) * F.get("a_im", i) + F.get("b_re", i))
    im = F.transform("re", lambda x, i: x * F.get("a_im", i) + F.get("im", i) * F.get("a_re", i) + F.get("b_im", i))
    moved = keep(spectra.join(frame).select("series_id", "t_id", "path", "cost", re.alias("re"), im.alias("im")))
    firsts = [F.get(c, f).alias(f"{c}{f}") for f in range(few) for c in ("re", "im")]
    side = lambda x, s, *more: x.select(*(c.alias(f"{n}_{s}") for n, c in (("id", F.col("series_id")), ("t", F.col("t_id")))), *(F.col(c).alias(f"{c}_{s}") for c in more))
    heads = moved.select("series_id", "t_id", "cost", *firsts)
    names = [c for c in heads.columns if c not in ("series_id", "t_id")]
    cost = F.col("cost_l") + F.col("cost_r")
    most = F.lit(budget) if ratio is None else F.least(F.lit(budget), F.col("plain") * ratio)
    near = F.sqrt(reduce(lambda x, y: x + y, (F.pow(F.col(f"{c}{f}_l") - F.col(f"{c}{f}_r"), F.lit(2.0)) * float(w[f]) for f in range(few) for c in ("re", "im"))))
    tried = both.select("id_l", "id_r", "plain").join(side(heads, "l", *names), "id_l").where((F.col("cost_l") == 0) | ((F.col("cost_l") <= most) & (F.col("cost_l") < F.col("plain"))))
    hopeful = tried.join(side(heads, "r", *names), "id_r").where((cost == 0) | ((cost <= most) & (cost + near <= F.col("plain") + SLACK))).select("id_l", "id_r", "t_l", "t_r", cost.alias("cost"))
    full = hopeful.join(side(moved, "l", "path", "re", "im"), ["id_l", "t_l"]).join(side(moved, "r", "path", "re", "im"), ["id_r", "t_r"])
    cost = F.col("cost")
    # ties: the cheaper, then the shorter and first paths
    total = full.select("id_l", "id_r", (plain + cost).alias("dist"), "cost", "path_l", "path_r")
    order = F.struct(F.round("dist", 9), F.round("cost", 9), F.length("path_l") + F.length("path_r"), "path_l", "path_r")
    return total.groupBy("id_l", "id_r").agg(F.min_by(F.struct("dist", "cost", "path_l", "path_r"), order).alias("x")).select("id_l", "id_r", "x.*")


def within_range(r: SeriesRelation, pairs: DataFrame, catalog: list[SpectralTransform], eps: float, budget: float = math.inf, max_depth: int = 2, **options) -> DataFrame:
    return bounded(r, pairs, catalog, min(budget, eps), max_depth, **options).where(F.col("dist") <= eps)


def exhaustive_np(x: np.ndarray, y: np.ndarray, catalog: list[SpectralTransform], max_depth: int) -> float:
    """By trying all compositions on both sides: for tests."""
    every = closure(catalog, math.inf, max_depth)
    return min(p.cost + q.cost + float(np.linalg.norm(p.on_values(x) - q.on_values(y))) for p in every for q in every)
