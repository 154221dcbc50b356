"""Coupling coefficients of angular momenta: closed form, selection rules, real basis, and chains of couplings."""

from __future__ import annotations

from fractions import Fraction
from functools import lru_cache
from math import factorial, sqrt

import numpy as np


def index(l: int, m: int) -> int:
    """Place of (l, m) in a flat tensor."""
    return l * l + l + m


def width(lmax: int) -> int:
    return (lmax + 1) ** 2


def admissible(l1: int, m1: int, l2: int, m2: int, l3: int, m3: int) -> bool:
    """Triangle rule, conserved projection and bounded projections: necessary for a non-zero coefficient."""
    return abs(l1 - l2) <= l3 <= l1 + l2 and m1 + m2 == m3 and abs(m1) <= l1 and abs(m2) <= l2 and abs(m3) <= l3


@lru_cache(maxsize=None)
def coefficient(l1: int, m1: int, l2: int, m2: int, l3: int, m3: int) -> float:
    """The coefficient in the complex basis, summed exactly."""
    if not admissible(l1, m1, l2, m2, l3, m3):
        return 0.0
    f = factorial
    total = Fraction(0)
    for k in range(max(0, l2 - l3 - m1, l1 - l3 + m2), min(l1 + l2 - l3, l1 - m1, l2 + m2) + 1):
        total += Fraction((-1) ** k, f(k) * f(l1 + l2 - l3 - k) * f(l1 - m1 - k) * f(l2 + m2 - k) * f(l3 - l2 + m1 + k) * f(l3 - l1 - m2 + k))
    if not total:
        return 0.0
    square = Fraction((2 * l3 + 1) * f(l3 + l1 - l2) * f(l3 - l1 + l2) * f(l1 + l2 - l3), f(l1 + l2 + l3 + 1))
    square *= f(l3 + m3) * f(l3 - m3) * f(l1 - m1) * f(l1 + m1) * f(l2 - m2) * f(l2 + m2)
    return (1 if total > 0 else -1) * sqrt(square * total * total)


def to_real(l: int) -> np.ndarray:
    """Rows: real components m = -l..l as combinations of the complex ones."""
    u = np.zeros((2 * l + 1, 2 * l + 1), dtype=complex)
    for m in range(-l, l + 1):
        if m > 0:
            u[m + l, m + l], u[m + l, -m + l] = (-1) ** m / sqrt(2), 1 / sqrt(2)
        elif m < 0:
            u[m + l, -m + l], u[m + l, m + l] = -1j * (-1) ** m / sqrt(2), 1j / sqrt(2)
        else:
            u[l, l] = 1
    return u


@lru_cache(maxsize=None)
def block(l1: int, l2: int, l3: int, basis: str = "complex") -> np.ndarray:
    """Coefficients [m1, m2, m3] of one path."""
    c = np.array([[[coefficient(l1, a, l2, b, l3, m) for m in range(-l3, l3 + 1)] for b in range(-l2, l2 + 1)] for a in range(-l1, l1 + 1)])
    if basis == "complex":
        return c
    real = np.einsum("abm,xa,yb,zm->xyz", c, to_real(l1).conj(), to_real(l2).conj(), to_real(l3))
    if (l1 + l2 + l3) % 2:
        real = real * 1j  # one phase makes the block of an odd path real
    assert np.abs(real.imag).max() < 1e-12
    return np.where(np.abs(real.real) < 1e-14, 0.0, real.real)


def paths(l1max: int, l2max: int, l3max: int, parity: bool = False) -> list[tuple[int, int, int]]:
    return [(a, b, c) for a in range(l1max + 1) for b in range(l2max + 1) for c in range(l3max + 1) if abs(a - b) <= c <= a + b and not (parity and (a + b + c) % 2)]


def table(l1max: int, l2max: int, l3max: int, basis: str = "complex") -> list[tuple[int, int, int, int, int, int, int, float]]:
    """(path, l1, m1, l2, m2, l3, m3, c) of the non-zero coefficients."""
    out = []
    for p, (a, b, c) in enumerate(paths(l1max, l2max, l3max)):
        values = block(a, b, c, basis)
        out += [(p, a, int(i) - a, b, int(j) - b, c, int(k) - c, float(values[i, j, k])) for i, j, k in zip(*np.nonzero(values))]
    return out


@lru_cache(maxsize=None)
def chains(lmax: int, nu: int, l_out: int, basis: str = "complex") -> tuple[tuple[tuple[int, ...], np.ndarray], ...]:
    """For nu coupled factors of order up to lmax: (intermediate orders, tensor over the factors' flat indices and M) of
    every path that ends in l_out. One factor couples to itself."""
    if nu == 1:
        if l_out > lmax:
            return ()
        one = np.zeros((width(lmax), 2 * l_out + 1))
        for m in range(-l_out, l_out + 1):
            one[index(l_out, m), m + l_out] = 1
        return (((l_out,), one),)
    out = []
    for middle in range(nu * lmax + 1):
        for name, head in chains(lmax, nu - 1, middle, basis):
            for l in range(lmax + 1):
                if abs(middle - l) <= l_out <= middle + l:
                    last = np.zeros((2 * middle + 1, width(lmax), 2 * l_out + 1))
                    last[:, l * l : (l + 1) ** 2] = block(middle, l, l_out, basis)
                    out.append(((*name, l, l_out), np.einsum("...m,mik->...ik", head, last)))
    return tuple(out)


def chain_terms(lmax: int, nu: int, l_out: int, basis: str = "complex", canonical: bool = False) -> list[tuple[int, int, tuple[int, ...], float]]:
    """(path, M, flat indices, c) of the non-zero chain coefficients. canonical: indices sorted, equal ones added up, as
    the factors are all of one tensor."""
    out: dict[tuple[int, int, tuple[int, ...]], float] = {}
    for p, (_, tensor) in enumerate(chains(lmax, nu, l_out, basis)):
        for at in zip(*np.nonzero(np.abs(tensor) > 1e-14)):
            *lms, m = (int(x) for x in at)
            key = (p, m - l_out, tuple(sorted(lms)) if canonical else tuple(lms))
            out[key] = out.get(key, 0.0) + float(tensor[at])
    return [(*k, v) for k, v in out.items() if abs(v) > 1e-14]


def density(l1max: int, l2max: int, l3max: int) -> dict[str, float]:
    """Entries of the dense tensor, those the rules admit, those that are not zero, and the sum of squares."""
    total = width(l1max) * width(l2max) * width(l3max)
    ok = sum(admissible(a, i, b, j, c, k) for a in range(l1max + 1) for i in range(-a, a + 1) for b in range(l2max + 1) for j in range(-b, b + 1) for c in range(l3max + 1) for k in range(-c, c + 1))
    values = [x[-1] for x in table(l1max, l2max, l3max)]
    return {"total": total, "admissible": ok, "nonzero": len(values), "squares": sum(v * v for v in values)}
