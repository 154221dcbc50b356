"""Real spherical harmonics and radial functions, as columns and in NumPy."""

from __future__ import annotations

from math import factorial, pi, sqrt

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def harmonics_column(dx: Column, dy: Column, dz: Column, r: Column, lmax: int = 2) -> Column:
    """Real harmonics of a displacement up to lmax <= 2 as straight-line expressions, flat in l*l + l + m."""
    if lmax > 2:
        raise ValueError("use the vectorised form beyond l = 2")
    x, y, z = dx / r, dy / r, dz / r
    out = [F.lit(0.5 * sqrt(1 / pi))]
    if lmax >= 1:
        c = sqrt(3 / (4 * pi))
        out += [y * c, z * c, x * c]
    if lmax >= 2:
        c = 0.5 * sqrt(15 / pi)
        out += [x * y * c, y * z * c, (z * z * 3.0 - 1.0) * (0.25 * sqrt(5 / pi)), x * z * c, (x * x - y * y) * (c / 2)]
    return F.array(*out)


def harmonics(xyz: np.ndarray, lmax: int) -> np.ndarray:
    """Real harmonics of unit vectors [n, 3] to any order: [n, (lmax + 1)**2]."""
    x, y, z = xyz.T
    n = len(xyz)
    legendre = {(0, 0): np.ones(n)}  # without the factor sin(theta)**m, which goes to the azimuth
    for m in range(1, lmax + 1):
        legendre[m, m] = legendre[m - 1, m - 1] * (2 * m - 1)
    for m in range(lmax + 1):
        for l in range(m + 1, lmax + 1):
            legendre[l, m] = (z * (2 * l - 1) * legendre[l - 1, m] - (l + m - 1) * legendre.get((l - 2, m), 0.0)) / (l - m)
    around = (x + 1j * y)[:, None] ** np.arange(lmax + 1)
    out = np.empty((n, (lmax + 1) ** 2))
    for l in range(lmax + 1):
        for m in range(l + 1):
            norm = sqrt((2 * l + 1) / (4 * pi) * factorial(l - m) / factorial(l + m)) * (sqrt(2) if m else 1.0)
            out[:, l * l + l + m] = norm * legendre[l, m] * around[:, m].real
            if m:
                out[:, l * l + l - m] = norm * legendre[l, m] * around[:, m].imag
    return out


def bessel_column(r: Column, n: int, r_cut: float) -> Column:
    """The n-th radial Bessel function with its smooth cutoff."""
    return F.lit(sqrt(2 / r_cut)) * F.sin(r * (n * pi / r_cut)) / r * envelope_column(r / r_cut)


def envelope_column(u: Column, p: int = 6) -> Column:
    """1 at 0 and, with two derivatives, 0 from 1 on."""
    a, b, c = (p + 1) * (p + 2) / 2, p * (p + 2), p * (p + 1) / 2
    return F.when(u < 1, F.lit(1.0) - F.pow(u, F.lit(p)) * a + F.pow(u, F.lit(p + 1)) * b - F.pow(u, F.lit(p + 2)) * c).otherwise(0.0)


def bessel(r: np.ndarray, n: int, r_cut: float, p: int = 6) -> np.ndarray:
    k = np.arange(1, n + 1)
    u = (r / r_cut)[:, None]
    a, b, c = (p + 1) * (p + 2) / 2, p * (p + 2), p * (p + 1) / 2
    smooth = np.where(u < 1, 1 - a * u**p + b * u ** (p + 1) - c * u ** (p + 2), 0)
    return sqrt(2 / r_cut) * np.sin(u * pi * k) / r[:, None] * smooth


def small_weight(*parts: int) -> float:
    """Deterministic weights that are exact in binary: (-3 .. 3) / 8."""
    seed = 0
    for x in parts:
        seed = seed * 31 + x + 1
    return (seed % 7 - 3) / 8.0
