"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions.geometry import TURN
from cadenza.functions.safety import SPACES
from cadenza.functions.transforms import SpectralTransform
from cadenza.model import SLACK, TINY, SeriesRelation
from cadenza.operators import kindex, spectrum
from cadenza.operators.kindex import KIndex, view
from cadenza.operators.range_search import candidates, refine, surviving
from cadenza.plans.planner import block_squares, plan_search
from cadenza.storage import keep


def timed(make, repeats: int = 3) -> float:
    """Mean seconds of running a DataFrame to the noop sink, the first time left out."""
    took = []
    for _ in range(repeats + 1):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
    return sum(took[1:]) / repeats


def energy_share(r: SeriesRelation, k: int) -> DataFrame:
    """Mean part of a normal form's energy that coefficients 1 to k and their mirror images hold."""
    s = spectrum.dft(spectrum.normalize(r))
    w = A.half_weights(r.n)
    head = w.copy()
    head[0], head[k + 1 :] = 0, 0
    whole = lambda v: A.spectral_square(F.col("re"), F.col("im"), v)
    return s.select((whole(head) / whole(w)).alias("share")).agg(F.avg("share").alias("share"))


def uncovered(index: KIndex, t: SpectralTransform) -> DataFrame:
    """Points that t takes out of their leaf's mapped box (polar)."""
    boxes = view(index, t).where("level = 0").drop("level", "parent_id", "n_points")
    both = index.features.join(boxes, F.col("leaf_id") == F.col("node_id"))
    inside = F.lit(True)
    for f in index.freqs:
        a = complex(t.a[f])
        m = F.col(f"m{f}") * abs(a)
        p = F.col(f"p{f}") + float(np.angle(a))
        inside = inside & m.between(F.col(f"lo_m{f}") - SLACK, F.col(f"hi_m{f}") + SLACK) & p.between(F.col(f"lo_p{f}") - SLACK, F.col(f"hi_p{f}") + SLACK)
    return both.agg(F.count(F.when(~inside, 1)).alias("outside"))


def _points(values: np.ndarray, space: str) -> tuple[np.ndarray, np.ndarray]:
    """All elements of series as points of a space: complex numbers, and their two coordinates in [2, series, element]. Polar ones are NaN where a magnitude is too small for an angle."""
    x = values + 0j if space == "real" else np.fft.fft(values, axis=1, norm="ortho")
    if space != "polar":
        return x, np.stack([x.real, x.imag])
    magnitude, angle = np.abs(x), np.angle(x)
    # half a turn is one angle, whatever the sign that rounding gives it
    both = np.stack([magnitude, np.where(angle <= -np.pi + SLACK, np.pi, angle)])
    return x, np.where(magnitude > TINY * (1 + np.linalg.norm(values, axis=1))[:, None], both, np.nan)


def _off(x: np.ndarray, p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """x isn't between p and q."""
    slack = SLACK * (1 + np.maximum(np.abs(p), np.abs(q)))
    return (x < np.minimum(p, q) - slack) | (x > np.maximum(p, q) + slack)


def _escaping(t: SpectralTransform, space: str, x: np.ndarray, known: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Which series t takes out of the box that the moved corners low and high span, in some element."""
    corner = lambda c: c[0] * np.exp(1j * c[1]) if space == "polar" else c[0] + 1j * c[1]
    y, p, q = (t.on_spectrum(c) for c in (x, corner(low), corner(high)))
    if space == "real":
        out = _off(y.real, p.real, q.real) | (np.abs(y.imag) > SLACK)
    elif space == "rect":
        out = _off(y.real, p.real, q.real) | _off(y.imag, p.imag, q.imag)
    else:
        ahead = lambda c: np.mod(np.angle(c) - np.angle(p) + SLACK, TURN)
        out = _off(np.abs(y), np.abs(p), np.abs(q)) | ((ahead(y) > ahead(q) + SLACK) & (np.abs(y) > TINY * (1 + np.maximum(np.abs(p), np.abs(q)))))
    return (out & known[:, np.arange(t.n_out) % t.n]).any(axis=1)


def escapes(r: SeriesRelation, transforms: list[SpectralTransform]) -> DataFrame:
    """(transform, space, series, escaped): how many series there are, and how many of them leave the box of all when its corners are moved. None does where a transformation is safe.
    The relation is made once and read twice, for the boxes and for the points; series with values that aren't finite are left out."""
    n, values = r.n, keep(r.df.select("values"))

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            m = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
            m = m[np.isfinite(m.sum(axis=1))]
            yield from (m[i : i + 1024] for i in range(0, len(m), 1024))

    def bounds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        least = np.full((len(SPACES), 2, 2, n), np.nan)
        for m in matrices(batches):
            at = np.stack([_points(m, s)[1] for s in SPACES])
            least = np.fmin(least, np.fmin.reduce(np.stack([at, -at], axis=1), axis=3, initial=np.nan))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(least.size), pa.int32()), pa.array(least.ravel())], ["k", "least"])

    # NaN is above all numbers
    least = values.mapInArrow(bounds, "k int, least double").groupBy("k").agg(F.min("least").alias("least")).orderBy("k").collect()
    corners = np.array([x.least for x in least] or np.full(len(SPACES) * 4 * n, np.nan)).reshape(len(SPACES), 2, 2, n) * np.array([1, -1])[None, :, None, None]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        series, escaped = 0, np.zeros((len(SPACES), len(transforms)), int)
        for m in matrices(batches):
            series += len(m)
            for i, s in enumerate(SPACES):
                x, at = _points(m, s)
                escaped[i] += [_escaping(t, s, x, ~np.isnan(at[0]), *corners[i]).sum() for t in transforms]
        keys = [(t.name, s) for s in SPACES for t in transforms]
        yield pa.RecordBatch.from_arrays([*map(pa.array, zip(*keys)), pa.array([series] * len(keys)), pa.array(escaped.ravel())], ["transform", "space", "series", "escaped"])

    counted = values.mapInArrow(count, "transform string, space string, series long, escaped long")
    return counted.groupBy("transform", "space").agg(F.sum("series").alias("series"), F.sum("escaped").alias("escaped"))


def candidate_counts(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False, mirror: bool = True) -> DataFrame:
    """Candidates, answers and false hits of a range query."""
    plan = plan_search(index, q, t, eps, transform_query, mirror)
    near = candidates(index, plan, mirror=mirror)
    found = refine(index, near, plan)
    return near.agg(F.count(F.lit(1)).alias("candidates")).join(found.agg(F.count(F.lit(1)).alias("answers"))).withColumn("false_hits", F.col("candidates") - F.col("answers"))


def nodes_reached(index: KIndex, q, t: SpectralTransform | None, eps: float) -> DataFrame:
    """Nodes reached and all nodes, by level: the disk accesses of a walk down the tree."""
    plan = plan_search(index, q, t, eps)
    alive = reduce(DataFrame.unionByName, (surviving(index, plan, k).select("level", "node_id") for k in range(index.levels)))
    return index.nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes")).join(alive.groupBy("level").agg(F.count(F.lit(1)).alias("reached")), "level", "left").select("level", "nodes", F.coalesce("reached", F.lit(0)).cast("long").alias("reached"))


def multiplications(index: KIndex, q, t: SpectralTransform, eps: float) -> int:
    """Complex products of a query: two corners a node and coefficient, then whole records of candidates."""
    reached = sum(r.reached for r in nodes_reached(index, q, t, eps).collect())
    near = candidate_counts(index, q, t, eps).first().candidates
    return reached * 2 * len(index.freqs) + near * (index.n // 2 + 1)


def coefficients_examined(index: KIndex, q, t: SpectralTransform, eps: float) -> DataFrame:
    """Series that a stopping scan gives up after the head, after the middle, and reads whole."""
    blocks = block_squares(*(lambda p: (p.t, p.q, p.weights))(plan_search(index, q, t, eps, True)))
    sums = [reduce(lambda x, y: x + y, blocks[: i + 1]) for i in range(len(blocks))]
    stage = F.when(sums[0] > eps * eps, "head")
    if len(sums) > 2:
        stage = stage.when(sums[1] > eps * eps, "middle")
    return index.spectra.select(stage.otherwise("whole").alias("stage")).groupBy("stage").agg(F.count(F.lit(1)).alias("n"))


def rebuilt_quality(r: SeriesRelation, t: SpectralTransform, series_id: int, eps: float, leaf_rows: int) -> DataFrame:
    """Leaves reached by one query in a transformed index and in an index over transformed series."""
    q = np.array(r.one(series_id))
    first = kindex.build(r, leaf_rows=leaf_rows)
    z = (q - q.mean()) / q.std()
    reached = lambda ix, x, tt: nodes_reached(ix, x, tt, eps).where("level = 0")
    on_the_fly = reached(first, q, t).withColumn("kind", F.lit("transformed"))
    # normal forms of the transformed series: what an index built on them would hold
    anew = kindex.build(spectrum.apply(spectrum.normalize(r), t), leaf_rows=leaf_rows)
    return on_the_fly.unionByName(reached(anew, t.on_values(z), None).withColumn("kind", F.lit("rebuilt"))).select("kind", "nodes", "reached")


def real_range(r: SeriesRelation, series_id: int, stretch: float, move: float, eps: float, dims: int = 3) -> DataFrame:
    """(series_id, dist) with |stretch * x + move - q| <= eps for plain vectors: by boxes over their first coordinates, then whole."""
    index = kindex.build(r, space="real", normal=False, dims=dims)
    q = r.one(series_id)
    box = F.lit(True)
    bounds = F.lit(True)
    for d in range(dims):
        low, high = F.col(f"lo_x{d}") * stretch + move, F.col(f"hi_x{d}") * stretch + move
        box = box & (F.least(low, high) <= q[d] + eps + SLACK) & (F.greatest(low, high) >= q[d] - eps - SLACK)
        ends = sorted(((q[d] - eps - move) / stretch, (q[d] + eps - move) / stretch))
        bounds = bounds & F.col(f"x{d}").between(ends[0] - SLACK, ends[1] + SLACK)
    leaves = index.small(index.nodes.where((F.col("level") == 0) & box).select(F.col("node_id").alias("leaf_id")))
    near = index.features.where(bounds).join(leaves, "leaf_id", "left_semi").select("series_id")
    moved = F.transform("values", lambda x: x * stretch + move)
    full = r.df.join(near, "series_id", "left_semi").select("series_id", A.euclid(moved, A.literal(q)).alias("d"))
    return full.where(F.col("d") <= eps).select("series_id", (F.round(F.col("d") + 3e-7, 4) + F.lit(0.0)).alias("dist"))


def eps_for_answers(index: KIndex, q, t: SpectralTransform | None, answers: int, transform_query: bool = False) -> float:
    """A threshold that about so many series are within."""
    plan = plan_search(index, q, t, float("inf"), transform_query)
    return refine(index, index.features, plan).orderBy("dist").limit(answers).agg(F.max("dist")).first()[0]
