"""Number formats and rounding-error bounds of squared and plain distances.

One operation gives the exact result times (1 + delta) plus delta', with abs(delta) <= eps and abs(delta') <= tiny. m roundings on the
longest path of a sum give at most gamma(m) times the sum of absolute terms.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class FloatFormat:
    bits: int

    @property
    def eps(self) -> float:
        return {64: 2.0**-53, 32: 2.0**-24, 16: 2.0**-11}[self.bits]

    @property
    def tiny(self) -> float:
        """Half the smallest subnormal; of 64 bit it is below every double, so 0 here."""
        return {64: 0.0, 32: 2.0**-150, 16: 2.0**-25}[self.bits]

    @property
    def top(self) -> float:
        return float(np.finfo({64: np.float64, 32: np.float32, 16: np.float16}[self.bits]).max)


def gamma(m: int, eps: float) -> float:
    return math.expm1(m * math.log1p(eps))


def depth(d: int, summation: str) -> int:
    """Additions on the longest path of a sum of d terms."""
    return math.ceil(math.log2(d)) if summation == "tree" and d > 1 else d - 1


def distance_bound(d: int, x_max: float, bits: int, kind: str = "paper", summation: str = "tree") -> float:
    """Bound of the error of a squared distance computed from norms and inner product, over all pairs.

    'paper': arithmetic roundings alone, tree summation. 'sound': also the cast of the input, the summation order really run, subnormals and the
    error of the 64-bit reference.
    """
    f = FloatFormat(bits)
    size = 4 * d * x_max**2
    if kind == "paper":
        return size * gamma(1 + depth(d, "tree") + 2, f.eps)
    if kind == "sound":
        m = 1 + depth(d, summation) + 2
        return size * (gamma(m + 2, f.eps) + gamma(m, 2.0**-53)) + (8 * d * x_max + 4 * d + 3) * f.tiny
    raise ValueError(kind)


def rowwise_bound(norm_i: np.ndarray, norm_j: np.ndarray, d: int, x_max: float, bits: int, cast: bool = True, summation: str = "sequential") -> np.ndarray:
    """The same for each pair, from norms: the absolute terms sum to at most (norm_i + norm_j) squared."""
    f = FloatFormat(bits)
    m = 1 + depth(d, summation) + 2
    g = gamma(m + (2 if cast else 0), f.eps) + gamma(m, 2.0**-53)
    return (norm_i[:, None] + norm_j) ** 2 * (g * (1 + 1e-9)) + (8 * d * x_max + 4 * d + 3) * f.tiny


def eligible(gives_raw_floats: bool, gain: float, check_cost: float) -> bool:
    """Whether an operator may be quantized: its output needs no full-precision floats, and the gain outweighs the check."""
    return not gives_raw_floats and gain > check_cost


def quantized_sign(values: np.ndarray, bits: int = 16) -> np.ndarray:
    """The sign is exact from any format that keeps non-zero values non-zero; values that vanish in the format are looked up."""
    with np.errstate(over="ignore"):
        low = values.astype({32: np.float32, 16: np.float16}[bits])
    sign = np.sign(low).astype(np.float64)
    lost = (low == 0) & (values != 0)
    sign[lost] = np.sign(values[lost])
    return sign
