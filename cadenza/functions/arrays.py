"""Column functions on arrays: distances, moments, convolution, spectra."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from cadenza.model import TINY


def literal(xs: Sequence[float]) -> Column:
    """An array of doubles as one literal."""
    return F.expr("array(" + ", ".join(f"{float(x)!r}D" for x in xs) + ")").cast("array<double>")


def let(x: Column, body) -> Column:
    """body(x), with x computed once for a row: in a function over array elements it would be computed for each of them once the optimizer has put it in there."""
    return F.get(F.transform(F.array(x), body), 0)


def total(xs: Column) -> Column:
    return F.aggregate(xs, F.lit(0.0), lambda a, x: a + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def energy(xs: Column) -> Column:
    return F.aggregate(xs, F.lit(0.0), lambda a, x: a + x * x)


def euclid(a: Column, b: Column) -> Column:
    return F.sqrt(total(F.zip_with(a, b, lambda x, y: (x - y) * (x - y))))


def cityblock(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: F.abs(x - y)))


def mean(xs: Column) -> Column:
    return total(xs) / F.size(xs)


def deviation(xs: Column, m: Column, ddof: int = 0) -> Column:
    return F.sqrt(F.aggregate(xs, F.lit(0.0), lambda a, x: a + (x - m) * (x - m)) / (F.size(xs) - ddof))


def circular(xs: Column, kernel: Column, offset: int = 0) -> Column:
    """Circular convolution: the value at i is the sum of kernel[j] * xs[i - j + offset]."""
    def of(v: Column) -> Column:
        at = lambda i, j: F.get(v, F.pmod(i - j + offset, F.size(v)))
        return F.transform(v, lambda _, i: F.aggregate(F.transform(kernel, lambda w, j: w * at(i, j)), F.lit(0.0), lambda a, x: a + x))

    return let(xs, of)


def moving_average(xs: Column, m: int, align: str = "trailing") -> Column:
    """Circular. Trailing: the window ends at the value; centre: it lies around it."""
    return circular(xs, literal([1.0 / m] * m), (m - 1) // 2 if align == "center" else 0)


def moving_average_standard(xs: Column, m: int) -> Column:
    """The n - m + 1 whole windows only."""
    return let(xs, lambda v: F.transform(F.sequence(F.lit(0), F.size(v) - m), lambda i: total(F.slice(v, i + 1, m)) / m))


def cumulated(xs: Column) -> Column:
    """Running sums. Arrays are short, so each prefix is summed anew in order."""
    return let(xs, lambda v: F.transform(v, lambda _, i: total(F.slice(v, 1, i + 1))))


def normal_form(xs: Column, ddof: int = 0) -> Column:
    """struct<mean, sd, values>."""
    def of(v: Column) -> Column:
        return let(mean(v), lambda m: let(deviation(v, m, ddof), lambda s: F.struct(m.alias("mean"), s.alias("sd"), F.transform(v, lambda x: F.try_divide(x - m, s)).alias("values"))))

    return let(xs, of)


def stretch(xs: Column, m: int) -> Column:
    return F.flatten(F.transform(xs, lambda x: F.array_repeat(x, m)))


def best_window(p: Column, s: Column) -> Column:
    """Least distance of p to a window of s of its length."""
    starts = F.sequence(F.lit(1), F.size(s) - F.size(p) + 1)
    return F.array_min(F.transform(starts, lambda i: F.sqrt(F.aggregate(F.transform(p, lambda x, j: F.pow(x - F.get(s, i - 1 + j), F.lit(2.0))), F.lit(0.0), lambda a, x: a + x))))


def best_subsequence(p: Column, s: Column) -> Column:
    """Least distance of p to values of s in order, gaps allowed: rows of a table of costs, one for each value of p, kept as arrays over s."""
    far = F.lit(1e300)
    start = F.array_repeat(F.lit(0.0), F.size(s) + 1)

    def row(before: Column, x: Column) -> Column:
        # the cost when this value of p is met within the first i values of s; the first entry is impossible
        grow = lambda a, y: F.concat(a, F.array(F.least(F.element_at(a, -1), F.get(before, F.size(a) - 1) + (x - y) * (x - y))))
        return F.aggregate(s, F.array(far), grow)

    return F.sqrt(F.element_at(F.aggregate(p, start, row), -1))


def dft_pair(xs: Column, n: int, f: int) -> tuple[Column, Column]:
    """Real and imaginary part of one unitary coefficient, without Python on the executors."""
    t = 2 * np.pi * f * np.arange(n) / n
    return dot(xs, literal(np.cos(t) / np.sqrt(n))), dot(xs, literal(-np.sin(t) / np.sqrt(n)))


def half_weights(n: int) -> np.ndarray:
    """How often a half-spectrum coefficient counts: all but f = 0 and, for even n, f = n/2 have a mirror image."""
    w = np.full(n // 2 + 1, 2.0)
    w[0] = 1.0
    if n % 2 == 0:
        w[-1] = 1.0
    return w


def spectral_square(re: Column, im: Column, weights: np.ndarray, first: int = 0) -> Column:
    """Energy of half-spectrum coefficients from number `first` on."""
    w = literal(weights[first:])
    return F.aggregate(F.zip_with(F.zip_with(re, im, lambda x, y: x * x + y * y), w, lambda e, v: e * v), F.lit(0.0), lambda a, x: a + F.coalesce(x, F.lit(0.0)))


def polar(re: Column, im: Column) -> tuple[Column, Column]:
    """Magnitude and angle; the angle of next to nothing is 0."""
    m = F.hypot(re, im)
    return m, F.when(m < TINY, F.lit(0.0)).otherwise(F.atan2(im, re))


def times(re: Column, im: Column, a: np.ndarray, b: np.ndarray | None = None) -> tuple[Column, Column]:
    """a * X + b for arrays of coefficients and complex literals."""
    ar, ai = literal(a.real), literal(a.imag)
    both = F.zip_with(re, im, lambda x, y: F.struct(x.alias("x"), y.alias("y")))
    out_re = F.transform(both, lambda c, i: c["x"] * F.get(ar, i) - c["y"] * F.get(ai, i))
    out_im = F.transform(both, lambda c, i: c["x"] * F.get(ai, i) + c["y"] * F.get(ar, i))
    if b is not None and np.abs(b).max(initial=0) > 0:
        out_re = F.zip_with(out_re, literal(b.real), lambda x, y: x + y)
        out_im = F.zip_with(out_im, literal(b.imag), lambda x, y: x + y)
    return out_re, out_im
