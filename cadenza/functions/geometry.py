"""Boxes, arcs and bounds, as numbers at the driver and as columns on the executors.

In the polar space an axis pair is (magnitude, angle). Angles are tested as arcs (start, width)
modulo a full turn. A coefficient with weight w counts w times in a distance, so within a distance
eps it may differ by eps / sqrt(w). All tests carry slack, so rounding loses nothing.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from cadenza.model import SLACK

TURN = 2 * math.pi


def arcs_meet(start: Column, width: Column, other_start: Column, other_width: Column) -> Column:
    ahead, behind = F.pmod(other_start - start, F.lit(TURN)), F.pmod(start - other_start, F.lit(TURN))
    return (ahead <= width + SLACK) | (behind <= other_width + SLACK) | (ahead >= TURN - SLACK) | (behind >= TURN - SLACK)


def arcs_meet_np(start: float, width: float, other_start: float, other_width: float) -> bool:
    ahead, behind = (other_start - start) % TURN, (start - other_start) % TURN
    return ahead <= width + SLACK or behind <= other_width + SLACK or max(ahead, behind) >= TURN - SLACK


@dataclass(frozen=True)
class Axis:
    """Of one coefficient: what must hold for |X - q| <= reach. In rect: re and im intervals; in polar: magnitudes and an arc, None for all angles."""

    re: tuple[float, float] | None = None
    im: tuple[float, float] | None = None
    magnitude: tuple[float, float] | None = None
    arc: tuple[float, float] | None = None


def search_axis(q: complex, reach: float, space: str) -> Axis:
    if space == "rect":
        return Axis(re=(q.real - reach, q.real + reach), im=(q.imag - reach, q.imag + reach))
    m, angle = abs(q), math.atan2(q.imag, q.real)
    arc = None
    if m > reach * (1 + 1e-6) + 1e-6:
        half = math.asin(reach / m)
        arc = (angle - half, 2 * half)
    return Axis(magnitude=(max(0.0, m - reach), m + reach), arc=arc)


def map_interval(low: Column, high: Column, a: float, b: float) -> tuple[Column, Column]:
    """a * [low, high] + b for a real a."""
    x, y = low * a + b, high * a + b
    return F.least(x, y), F.greatest(x, y)


def box_meets(axis: Axis, f: int, a: complex, b: complex, space: str) -> Column:
    """Whether the node's box on coefficient f, mapped by (a, b), meets the search axis."""
    if space == "rect":
        ok = F.lit(True)
        for part, (low, high), shift in (("re", axis.re, b.real), ("im", axis.im, b.imag)):
            x, y = map_interval(F.col(f"lo_{part}{f}"), F.col(f"hi_{part}{f}"), a.real, shift)
            ok = ok & (x <= high + SLACK) & (y >= low - SLACK)
        return ok
    size = abs(a)
    ok = (F.col(f"lo_m{f}") * size <= axis.magnitude[1] + SLACK) & (F.col(f"hi_m{f}") * size >= axis.magnitude[0] - SLACK)
    if axis.arc and size > 0:
        ok = ok & arcs_meet(F.col(f"lo_p{f}") + math.atan2(a.imag, a.real), F.col(f"hi_p{f}") - F.col(f"lo_p{f}"), F.lit(axis.arc[0]), F.lit(axis.arc[1]))
    return ok


def raw_bounds(axis: Axis, f: int, a: complex, b: complex, space: str) -> Column:
    """The search axis mapped back to stored columns, as plain comparisons that reach the Parquet scan. A zero multiplier leaves nothing to compare but constants."""
    def between(name: str, low: float, high: float) -> Column:
        return F.col(name).between(low - SLACK, high + SLACK)

    if space == "rect":
        ok = F.lit(True)
        for part, (low, high), shift in (("re", axis.re, b.real), ("im", axis.im, b.imag)):
            if abs(a.real) < 1e-12:
                ok = ok & F.lit(low - SLACK <= shift <= high + SLACK)
            else:
                x, y = sorted(((low - shift) / a.real, (high - shift) / a.real))
                ok = ok & between(f"{part}{f}", x, y)
        return ok
    size = abs(a)
    if size < 1e-12:
        return F.lit(axis.magnitude[0] <= SLACK)
    ok = between(f"m{f}", axis.magnitude[0] / size, axis.magnitude[1] / size)
    if axis.arc:
        start = (axis.arc[0] - math.atan2(a.imag, a.real) + math.pi) % TURN - math.pi
        end = start + axis.arc[1]
        inside = between(f"p{f}", start, min(end, math.pi))
        ok = ok & (inside | between(f"p{f}", -math.pi, end - TURN) if end > math.pi else inside | (F.col(f"p{f}") >= math.pi - SLACK) if start <= -math.pi + SLACK else inside)
    return ok


def coefficient(f: int, space: str) -> tuple[Column, Column]:
    """Real and imaginary part from stored columns."""
    if space == "rect":
        return F.col(f"re{f}"), F.col(f"im{f}")
    return F.col(f"m{f}") * F.cos(f"p{f}"), F.col(f"m{f}") * F.sin(f"p{f}")


def gap_square(x: tuple[Column, Column], a: complex, b: complex, q: complex) -> Column:
    """|a X + b - q|^2."""
    re = x[0] * a.real - x[1] * a.imag + (b.real - q.real)
    im = x[0] * a.imag + x[1] * a.real + (b.imag - q.imag)
    return re * re + im * im


def box_distance_square(f: int, a: complex, q_re: Column, q_im: Column, space: str) -> Column:
    """Least square of the distance from q to the mapped box of coefficient f (b is 0)."""
    if space == "rect":
        out = F.lit(0.0)
        for part, q in (("re", q_re), ("im", q_im)):
            low, high = map_interval(F.col(f"lo_{part}{f}"), F.col(f"hi_{part}{f}"), a.real, 0.0)
            d = F.greatest(low - q, q - high, F.lit(0.0))
            out = out + d * d
        return out
    low, high = F.col(f"lo_m{f}") * abs(a), F.col(f"hi_m{f}") * abs(a)
    m, angle = F.hypot(q_re, q_im), F.atan2(q_im, q_re)
    start, width = F.col(f"lo_p{f}") + math.atan2(a.imag, a.real), F.col(f"hi_p{f}") - F.col(f"lo_p{f}")
    ahead = F.pmod(angle - start, F.lit(TURN))
    radial = F.greatest(low - m, m - high, F.lit(0.0))

    def to_edge(turn: Column) -> Column:
        # the edge is a segment from low to high in direction `turn` away from q
        along = F.least(F.greatest(m * F.cos(turn), low), high)
        return m * m + along * along - 2 * m * along * F.cos(turn)

    edges = F.least(to_edge(ahead), to_edge(ahead - width))
    return F.greatest(F.when((ahead <= width + SLACK) | (ahead >= TURN - SLACK), radial * radial).otherwise(edges), F.lit(0.0))
