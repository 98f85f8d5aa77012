"""The k-index: a bulk-packed tree of boxes over the first coefficients, and the full spectra beside it."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions.transforms import SpectralTransform
from cadenza.model import TINY, SeriesRelation
from cadenza.operators import spectrum
from cadenza.storage import keep

#: Coefficients in the first and second block of a stored spectrum.
HEAD, MID = 4, 12
FAN_OUT = 64
#: Nodes up to which surviving ones are broadcast.
BROADCAST_NODES = 1_000_000


@dataclass(frozen=True)
class KIndex:
    """features: a row for each series, small; spectra: its full record; nodes: the tree, level 0 being leaves."""

    features: DataFrame
    spectra: DataFrame
    nodes: DataFrame
    n: int
    freqs: tuple[int, ...]
    space: str
    normal: bool
    levels: int
    leaves: int
    attrs: tuple[str, ...] = ()

    @property
    def axes(self) -> list[str]:
        if self.space == "real":
            return [f"x{d}" for d in self.freqs]
        parts = ("m", "p") if self.space == "polar" else ("re", "im")
        return [f"{p}{f}" for f in self.freqs for p in parts]

    def query_values(self, series_id: int) -> np.ndarray:
        """The stored series (its normal form, if the index is over these), from its spectrum."""
        row = self.spectra.where(F.col("series_id") == series_id).select(F.concat("head_re", "mid_re", "rest_re").alias("re"), F.concat("head_im", "mid_im", "rest_im").alias("im")).first()
        if row is None:
            raise KeyError(f"no series {series_id}")
        return np.fft.irfft(np.array(row.re) + 1j * np.array(row.im), self.n, norm="ortho")

    def small(self, nodes: DataFrame) -> DataFrame:
        return F.broadcast(nodes) if self.leaves <= BROADCAST_NODES else nodes

    def save(self, path: str) -> None:
        """Features clustered by leaf, spectra, nodes and what is needed to open them again."""
        self.features.repartitionByRange("leaf_id").sortWithinPartitions("leaf_id").write.parquet(f"{path}/features")
        self.spectra.repartitionByRange("leaf_id").sortWithinPartitions("leaf_id").write.parquet(f"{path}/spectra")
        self.nodes.repartitionByRange("level", "node_id").write.parquet(f"{path}/nodes")
        meta = [(self.n, list(self.freqs), self.space, self.normal, self.levels, self.leaves, list(self.attrs))]
        self.features.sparkSession.createDataFrame(meta, META).coalesce(1).write.parquet(f"{path}/index_meta")


META = "n int, freqs array<int>, space string, normal boolean, levels int, leaves int, attrs array<string>"


def open_index(spark: SparkSession, path: str) -> KIndex:
    m = spark.read.schema(META).parquet(f"{path}/index_meta").first()
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    return KIndex(read("features"), read("spectra"), read("nodes"), m.n, tuple(m.freqs), m.space, m.normal, m.levels, m.leaves, tuple(m.attrs))


def _tiles(df: DataFrame, axes: list[str], rows: int, leaf_rows: int) -> tuple[DataFrame, int]:
    """leaf_id by nested quantiles: cuts along one axis, within each slab along the next, and so on. The tables of cuts have at most as many rows as there are leaves."""
    wanted = max(1, math.ceil(rows / leaf_rows))
    per_axis = max(1, round(wanted ** (1 / len(axes))))
    out, leaves = df.withColumn("leaf_id", F.lit(0).cast("long")), 1
    for axis in axes:
        parts = max(1, min(math.ceil(wanted / leaves), per_axis + (per_axis ** len(axes) < wanted)))
        if parts == 1:
            continue
        shares = "array(" + ",".join(f"{i / parts!r}D" for i in range(1, parts)) + ")"
        cuts = out.groupBy("leaf_id").agg(F.expr(f"percentile_approx({axis}, {shares}, 10000)").alias("cuts"))
        cuts = F.broadcast(cuts) if leaves <= BROADCAST_NODES else cuts
        slab = F.aggregate("cuts", F.lit(0), lambda n, c: n + F.when(c < F.col(axis), 1).otherwise(0))
        out = out.join(cuts, "leaf_id").withColumn("leaf_id", F.col("leaf_id") * parts + slab).drop("cuts")
        leaves *= parts
    return out, leaves


def _tree(features: DataFrame, axes: list[str], leaves: int) -> tuple[DataFrame, int]:
    """All levels: leaves hold points, each level above FAN_OUT nodes of the one below. Boxes never cross the seam of angles."""
    bounds = [x for a in axes for x in (F.min(a).alias(f"lo_{a}"), F.max(a).alias(f"hi_{a}"))]
    level = features.groupBy(F.col("leaf_id").alias("node_id")).agg(*bounds, F.max("tail_energy").alias("tail_max"), F.count(F.lit(1)).alias("n_points"))
    parent = lambda df, k: df.withColumn("level", F.lit(k)).withColumn("parent_id", F.floor(F.col("node_id") / FAN_OUT).cast("long"))
    nodes, count, k = parent(level, 0), leaves, 0
    below = nodes
    while count > 1:
        count, k = math.ceil(count / FAN_OUT), k + 1
        up = [x for a in axes for x in (F.min(f"lo_{a}").alias(f"lo_{a}"), F.max(f"hi_{a}").alias(f"hi_{a}"))]
        below = parent(below.groupBy(F.col("parent_id").alias("node_id")).agg(*up, F.max("tail_max").alias("tail_max"), F.sum("n_points").alias("n_points")), k)
        nodes = nodes.unionByName(below)
    return nodes, k + 1


def build(r: SeriesRelation, k: int = 2, space: str = "polar", normal: bool = True, leaf_rows: int = 64, dims: int | None = None) -> KIndex:
    """An index over k coefficients: from 1 on for normal forms (coefficient 0 is 0), from 0 on otherwise; or, in the real space, over the first dims values themselves.

    Features hold mean and sd too. One pass makes spectra; features alone are dealt out to leaves.
    """
    freqs = tuple(range(dims or 3)) if space == "real" else tuple(range(1, k + 1) if normal else range(k))
    base, carry = r, ["mean", "sd", *r.attrs]
    if not normal:
        form = A.normal_form(F.col("values"))
        base = SeriesRelation(r.df.withColumns({"mean": form["mean"], "sd": form["sd"]}), r.n, r.attrs)
    if space == "real":
        carry = [*carry, "values"]
    spectra = keep(spectrum.normal_dft(base) if normal else spectrum.dft(base, *carry))
    columns: dict[str, Column] = {}
    for f in freqs:
        if space == "real":
            columns[f"x{f}"] = F.get("values", f)
            continue
        re, im = F.get("re", f), F.get("im", f)
        columns[f"re{f}"], columns[f"im{f}"] = (re, im) if space == "rect" else A.polar(re, im)
    if space == "polar":
        columns = {("m" if c.startswith("re") else "p") + c[2:]: x for c, x in columns.items()}
    w = A.half_weights(r.n)
    w_tail = w.copy()
    w_tail[[f for f in freqs if f <= r.n // 2]] = 0
    features = spectra.select("series_id", "mean", "sd", *r.attrs, *(x.alias(c) for c, x in columns.items()), A.spectral_square(F.col("re"), F.col("im"), w_tail).alias("tail_energy"))
    index = KIndex(features, spectra, features, r.n, freqs, space, normal, 0, 0, r.attrs)
    tiled, leaves = _tiles(features, index.axes, features.count(), leaf_rows)
    features = keep(tiled)
    nodes, levels = _tree(features, index.axes, leaves)
    h = r.n // 2 + 1
    part = lambda c, start, size: F.slice(c, start + 1, max(size, 0)) if size > 0 else F.array().cast("array<double>")
    blocks = {f"{b}_{c}": part(c, at, min(size, h - at)) for c in ("re", "im") for b, at, size in (("head", 0, HEAD), ("mid", HEAD, MID), ("rest", HEAD + MID, h))}
    full = spectra.join(features.select("series_id", "leaf_id"), "series_id").select("series_id", "leaf_id", *(x.alias(c) for c, x in blocks.items()))
    return replace(index, features=features, spectra=full, nodes=keep(nodes), levels=levels, leaves=leaves)


def view(index: KIndex, t: SpectralTransform, materialize: bool = False) -> DataFrame:
    """The tree after t, lazily: a projection over nodes; materialize: computed once and kept. Polar angles may pass the seam; they are arcs from lo on.

    A safe t maps boxes to boxes. Otherwise these are the least boxes in this space that surely hold the mapped ones, so
    what is searched with them loses nothing: a complex multiplier turns a rectangle, a translation
    moves a sector off its arcs.
    """
    out = index.nodes
    for f in index.freqs:
        a, b = complex(t.a[f]), complex(t.b[f])
        if index.space == "polar":
            turn = math.atan2(a.imag, a.real)
            low, high, start, end = F.col(f"lo_m{f}") * abs(a), F.col(f"hi_m{f}") * abs(a), F.col(f"lo_p{f}") + turn, F.col(f"hi_p{f}") + turn
            if abs(b) > TINY:
                size = F.lit(abs(b))
                spread = F.when(low > size * (1 + 1e-9), F.asin(F.least(size / low, F.lit(1.0)))).otherwise(F.lit(math.pi))
                low, high, start, end = F.greatest(low - size, size - high, F.lit(0.0)), high + size, start - spread, end + spread
            out = out.withColumns({f"lo_m{f}": low, f"hi_m{f}": high, f"lo_p{f}": start, f"hi_p{f}": end})
        elif index.space == "rect":
            re, im = ((F.col(f"lo_{p}{f}"), F.col(f"hi_{p}{f}")) for p in ("re", "im"))
            moved = {}
            for name, x, y, shift in (("re", a.real, -a.imag, b.real), ("im", a.imag, a.real, b.imag)):
                moved[f"lo_{name}{f}"] = F.least(re[0] * x, re[1] * x) + F.least(im[0] * y, im[1] * y) + shift
                moved[f"hi_{name}{f}"] = F.greatest(re[0] * x, re[1] * x) + F.greatest(im[0] * y, im[1] * y) + shift
            out = out.withColumns(moved)
        else:
            low, high = F.col(f"lo_x{f}") * a.real + b.real, F.col(f"hi_x{f}") * a.real + b.real
            out = out.withColumns({f"lo_x{f}": F.least(low, high), f"hi_x{f}": F.greatest(low, high)})
    return keep(out) if materialize else out


def boxes(index: KIndex, nodes: DataFrame, level: int, side: str = "") -> DataFrame:
    """Nodes of one level, named by side: node, up (the parent), lo_ and hi_ of each axis; to be broadcast where their number is bounded."""
    found = nodes.where(F.col("level") == level).select(F.col("node_id").alias(f"node{side}"), F.col("parent_id").alias(f"up{side}"), *(F.col(f"{e}_{a}").alias(f"{e}_{a}{side}") for a in index.axes for e in ("lo", "hi")))
    return F.broadcast(found) if index.leaves <= BROADCAST_NODES * FAN_OUT**level else found


def append(index: KIndex, r_new: SeriesRelation) -> KIndex:
    """The index with further series: from the root down each goes to the node whose box grows least, and boxes widen. Repack when leaves have become uneven."""
    fresh = build(r_new, len(index.freqs), index.space, index.normal, leaf_rows=1 << 40)
    growth = sum((F.greatest(F.col(f"lo_{a}") - F.col(a), F.lit(0.0)) + F.greatest(F.col(a) - F.col(f"hi_{a}"), F.lit(0.0)) for a in index.axes), F.lit(0.0))
    placed = fresh.features.select("series_id", *index.axes, F.lit(0).cast("long").alias("leaf_id"))
    for level in range(index.levels - 2, -1, -1):
        below = placed.join(boxes(index, index.nodes, level), F.col("leaf_id") == F.col("up"))
        placed = below.groupBy("series_id", *index.axes).agg(F.min_by("node", F.struct(growth, F.col("node"))).alias("leaf_id"))
    placed = placed.select("series_id", "leaf_id")
    features = keep(index.features.unionByName(fresh.features.drop("leaf_id").join(placed, "series_id")))
    spectra = index.spectra.unionByName(fresh.spectra.drop("leaf_id").join(placed, "series_id"))
    nodes, levels = _tree(features, index.axes, index.leaves)
    return replace(index, features=features, spectra=spectra, nodes=keep(nodes), levels=levels)
