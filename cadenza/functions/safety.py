"""Whether a transformation maps boxes to boxes in a space, so that one index serves it."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from cadenza.functions.transforms import SpectralTransform
from cadenza.model import TINY

SPACES = ("real", "rect", "polar")


@dataclass(frozen=True)
class SafetyVerdict:
    safe: bool
    rule: str
    reason: str


def is_safe(t: SpectralTransform, space: str) -> SafetyVerdict:
    """space: real (plain coordinates), rect (real and imaginary parts) or polar (magnitudes and angles)."""
    real_a = np.abs(t.a.imag).max(initial=0) <= TINY
    real_b = np.abs(t.b.imag).max(initial=0) <= TINY
    if space == "real":
        ok = bool(real_a and real_b)
        return SafetyVerdict(ok, "real stretch and translation", "a and b are real" if ok else "a or b is complex")
    if space == "rect":
        return SafetyVerdict(bool(real_a), "real stretch, complex translation", "a is real" if real_a else "a complex multiplier turns boxes")
    if space == "polar":
        ok = not t.has_translation
        return SafetyVerdict(ok, "complex stretch, no translation", "b is zero" if ok else "a translation bends boxes of magnitude and angle")
    raise ValueError(f"no space {space}")
