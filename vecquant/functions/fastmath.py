"""Polynomial exp and log: argument reduction by powers of two and least-squares Chebyshev fits."""

from __future__ import annotations

from functools import cache

import numpy as np
from numpy.polynomial import Chebyshev

_LN2 = float(np.log(2))


@cache
def _fit(name: str, degree: int) -> Chebyshev:
    if name == "exp":
        domain, function = (-_LN2 / 2, _LN2 / 2), np.exp
    else:
        domain, function = (0.5, 1.0), np.log
    return Chebyshev.interpolate(function, degree, domain=domain)


def exp_poly(x: np.ndarray, degree: int = 9) -> np.ndarray:
    """exp by a polynomial on half an octave around zero, scaled by a power of two."""
    x = np.clip(x, -700, 700)
    k = np.rint(x / _LN2)
    return np.ldexp(_fit("exp", degree)(x - k * _LN2), k.astype(np.int64))


def log_poly(x: np.ndarray, degree: int = 16) -> np.ndarray:
    """Natural log of positive numbers by a polynomial of the mantissa, plus the exponent."""
    mantissa, exponent = np.frexp(x)
    return _fit("log", degree)(mantissa) + exponent * _LN2
