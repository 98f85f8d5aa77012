"""What is decided before a plan is made: folding, safety, the search box, and index or scan."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions import geometry as G
from cadenza.functions.safety import is_safe
from cadenza.functions.transforms import SpectralTransform, affine, dft, identity
from cadenza.model import check_length
from cadenza.operators.kindex import HEAD, MID, KIndex

#: Part of the relation from which on a scan is the better way (measured by bench.py's sweep of thresholds).
CROSSOVER = 1 / 3


@dataclass(frozen=True)
class SearchPlan:
    """A query against an index, in the frequency domain. weights: how often each half-spectrum coefficient counts."""

    t: SpectralTransform
    q: np.ndarray
    eps: float
    weights: np.ndarray
    axes: dict[int, G.Axis]
    safe: bool


def fold_translation(t: SpectralTransform, q: np.ndarray) -> tuple[SpectralTransform, np.ndarray]:
    """(a, 0) against q - b: the same distances."""
    return SpectralTransform(t.name, t.n, t.a, np.zeros_like(t.b), t.cost), q - t.b


def query_spectrum(index: KIndex, q, length: int) -> np.ndarray:
    """Of a series in the time domain, brought to normal form if the index is over these."""
    q = np.asarray(q, float)
    check_length(len(q), length)
    if index.normal:
        sd = q.std()
        if sd < 1e-9:
            raise ValueError("a constant series has no normal form")
        q = (q - q.mean()) / sd
    return dft(q)


def plan_search(index: KIndex, q, t: SpectralTransform | None, eps: float, transform_query: bool = False, mirror: bool = True) -> SearchPlan:
    t = t or identity(index.n)
    check_length(t.n, index.n)
    spectrum = query_spectrum(index, q, t.n if transform_query else t.n_out)
    if transform_query:
        spectrum = t.on_spectrum(spectrum)
    if t.has_translation:
        t, spectrum = fold_translation(t, spectrum)
    safe = is_safe(t, index.space).safe
    if not safe:
        warnings.warn(f"{t.name} isn't safe in the {index.space} space: the relation is scanned", stacklevel=3)
    w = A.half_weights(t.n_out)
    axes = {f: G.search_axis(complex(spectrum[f]), eps / math.sqrt(w[f] if mirror else 1.0), index.space) for f in index.freqs} if safe else {}
    return SearchPlan(t, spectrum, eps, w, axes, safe)


def within(distance_square: Column, eps: float, strict: bool = False) -> Column:
    return distance_square < eps * eps if strict else distance_square <= eps * eps


def prefix_square(plan: SearchPlan, index: KIndex, mirror: bool = True) -> Column:
    """Part of the squared distance that the stored coefficients make up."""
    out = F.lit(0.0)
    for f in index.freqs:
        out = out + G.gap_square(G.coefficient(f, index.space), complex(plan.t.a[f]), complex(plan.t.b[f]), complex(plan.q[f])) * float(plan.weights[f] if mirror else 1.0)
    return out


def block_squares(t: SpectralTransform, q: np.ndarray, weights: np.ndarray) -> list[Column]:
    """Squared distance made up by the head, mid and rest blocks of a stored spectrum (series and transformed series of one length)."""
    out, at = [], 0
    for name, size in (("head", HEAD), ("mid", MID), ("rest", len(weights))):
        end = min(at + size, len(weights))
        if end > at:
            re, im = A.times(F.col(f"{name}_re"), F.col(f"{name}_im"), t.a[at:end], t.b[at:end] - q[at:end])
            out.append(A.spectral_square(re, im, weights[:end], at))
        at = end
    return out


def choose_strategy(index: KIndex, plan: SearchPlan) -> str:
    """index or scan, by the part of all points that lies in leaves which the search box meets."""
    if not plan.safe:
        return "scan"
    meets = F.lit(True)
    for f, axis in plan.axes.items():
        meets = meets & G.box_meets(axis, f, complex(plan.t.a[f]), 0j, index.space)
    row = index.nodes.where("level = 0").agg(F.sum(F.when(meets, F.col("n_points")).otherwise(0)).alias("near"), F.sum("n_points").alias("all")).first()
    return "scan" if row["all"] and (row["near"] or 0) / row["all"] > CROSSOVER else "index"


def translation_only(n: int, b) -> SpectralTransform:
    return affine(np.ones(n), b)
