"""Transformations of series as pairs (a, b) that act on unitary spectra as a * X + b.

The multiplier of a kernel is its un-normalised DFT: a product of two unitary spectra would be
too small by the square root of the length.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np

from cadenza.model import TINY, check_length


@dataclass(frozen=True, eq=False)
class SpectralTransform:
    """a and b have n_out coefficients; coefficient f is made from coefficient f mod n of a series of length n."""

    name: str
    n: int
    a: np.ndarray
    b: np.ndarray
    cost: float = 0.0

    @property
    def n_out(self) -> int:
        return len(self.a)

    def __matmul__(self, first: SpectralTransform) -> SpectralTransform:
        """This one after `first`."""
        check_length(first.n_out, self.n)
        source = np.arange(self.n_out) % self.n
        return SpectralTransform(f"{self.name}.{first.name}", first.n, self.a * first.a[source], self.a * first.b[source] + self.b, self.cost + first.cost)

    def power(self, p: int) -> SpectralTransform:
        return reduce(lambda x, y: x @ y, [self] * p) if p else identity(self.n)

    def with_cost(self, cost: float) -> SpectralTransform:
        return SpectralTransform(self.name, self.n, self.a, self.b, cost)

    def on_spectrum(self, x: np.ndarray) -> np.ndarray:
        return self.a * x[..., np.arange(self.n_out) % self.n] + self.b

    def on_values(self, values) -> np.ndarray:
        check_length(len(values), self.n)
        return idft(self.on_spectrum(dft(values)))

    @property
    def keeps_real(self) -> bool:
        """Real series stay real: a and b are conjugate symmetric."""
        mirror = -np.arange(self.n_out) % self.n_out
        return bool(np.allclose(self.a[mirror], self.a.conj(), atol=1e-9) and np.allclose(self.b[mirror], self.b.conj(), atol=1e-9))

    @property
    def has_translation(self) -> bool:
        return bool(np.abs(self.b).max(initial=0) > TINY)


def dft(values) -> np.ndarray:
    return np.fft.fft(np.asarray(values, float), norm="ortho")


def idft(x: np.ndarray) -> np.ndarray:
    return np.fft.ifft(x, norm="ortho").real


def affine(a, b=None, cost: float = 0.0, name: str = "affine") -> SpectralTransform:
    a = np.asarray(a, complex)
    return SpectralTransform(name, len(a), a, np.zeros(len(a), complex) if b is None else np.asarray(b, complex), cost)


def identity(n: int) -> SpectralTransform:
    return affine(np.ones(n), name="identity")


def shift(n: int, c: float) -> SpectralTransform:
    """c is added to each value: only coefficient 0 changes."""
    b = np.zeros(n, complex)
    b[0] = c * np.sqrt(n)
    return affine(np.ones(n), b, name=f"shift({c:g})")


def scale(n: int, c: float) -> SpectralTransform:
    return affine(np.full(n, c, float), name=f"scale({c:g})")


def normalizer(n: int, mean: float, sd: float) -> SpectralTransform:
    """One series' own way to its normal form."""
    return scale(n, 1 / sd) @ shift(n, -mean)


def kernel(n: int, weights, name: str = "kernel", offset: int = 0) -> SpectralTransform:
    """Circular filter: weight 0 is that of the current value, later ones of values further back; offset moves them ahead."""
    w = np.zeros(n)
    for j, x in enumerate(weights):
        w[(j - offset) % n] += x
    return affine(np.fft.fft(w), name=name)


def moving_average(n: int, m: int, align: str = "trailing") -> SpectralTransform:
    return kernel(n, [1.0 / m] * m, f"mavg{m}", (m - 1) // 2 if align == "center" else 0)


def weighted_average(n: int, weights, name: str = "wavg") -> SpectralTransform:
    w = np.asarray(weights, float)
    return kernel(n, w / w.sum(), name)


def trend_weights(m: int) -> list[float]:
    """Falling from the most recent value on, sum 1."""
    return [(m - j) / (m * (m + 1) / 2) for j in range(m)]


def center_weights(m: int) -> list[float]:
    """Heaviest in the middle, sum 1."""
    w = [min(j, m - 1 - j) + 1 for j in range(m)]
    return [x / sum(w) for x in w]


def trend(n: int, m: int) -> SpectralTransform:
    return kernel(n, trend_weights(m), f"trend{m}")


def smooth_center(n: int, m: int) -> SpectralTransform:
    return kernel(n, center_weights(m), f"center{m}")


def difference(n: int) -> SpectralTransform:
    return kernel(n, [1.0, -1.0], "diff")


def reverse(n: int) -> SpectralTransform:
    """Ups become downs."""
    return affine(-np.ones(n), name="reverse")


def stretch(n: int, m: int) -> SpectralTransform:
    """Each value m times: a series of length n becomes one of length m * n."""
    f = np.arange(m * n)
    a = np.exp(-2j * np.pi * np.outer(f, np.arange(m)) / (m * n)).sum(axis=1) / np.sqrt(m)
    return SpectralTransform(f"stretch{m}", n, a, np.zeros(m * n, complex))
