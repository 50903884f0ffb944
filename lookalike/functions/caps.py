"""Spherical caps: field of a unit vector, overlap of two fields, and the boundary weight.

Projecting the sphere on the plane of the two axes, the share of points in both caps is one
integral, ``g(phi/2)/pi`` with ``g(a)`` the integral from ``a`` to ``theta`` of
``(1 - cos^2 theta / cos^2 t)^((d-2)/2)``. Hence the weight ``1 - g(phi/2)/g(0)``.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

INTERVALS, POINTS = 400, 2001


def cap_integral(a: float, theta: float, dim: int, intervals: int = INTERVALS) -> float:
    """``g(a)`` by Simpson's rule in ``u = sqrt(theta - t)``, which takes the root out of the integrand's end."""
    if a >= theta:
        return 0.0
    top = math.sqrt(theta - a)
    u = top * np.arange(intervals + 1) / intervals
    y = 2 * u * np.maximum(0.0, 1.0 - (math.cos(theta) / np.cos(theta - u * u)) ** 2) ** ((dim - 2) / 2)
    w = np.where(np.arange(intervals + 1) % 2, 4.0, 2.0)
    w[[0, -1]] = 1.0
    return float(top / intervals / 3 * (w * y).sum())


def cap_fraction(theta: float, dim: int) -> float:
    """Share of the sphere within ``theta`` of a vector."""
    return cap_integral(0.0, theta, dim) / math.pi


def overlap_ratio(phi: float, theta: float, dim: int) -> float:
    """Share of one field that lies in another at angle ``phi``."""
    return cap_integral(phi / 2, theta, dim) / cap_integral(0.0, theta, dim)


@lru_cache(maxsize=32)
def weight_table(theta: float, dim: int, points: int = POINTS) -> np.ndarray:
    """Weights at ``points`` equal steps of phi from 0 to ``2 * theta``; a few kB, computed once per worker."""
    g0 = cap_integral(0.0, theta, dim)
    g = np.array([cap_integral(theta * j / (points - 1), theta, dim) for j in range(points)])
    return np.where(g > 0, 1.0 - g / g0, 1.0)


def boundary_weight(cos: np.ndarray, theta: float, dim: int) -> np.ndarray:
    """Weight by the angle to the centroid: 0 on it, 1 from ``2 * theta`` on, linear between table points."""
    table = weight_table(theta, dim)
    at = np.arccos(np.clip(cos, -1.0, 1.0)) / (2 * theta) * (len(table) - 1)
    lo = np.minimum(np.floor(at).astype(np.int64), len(table) - 2)
    w = table[lo] + (np.minimum(at, len(table) - 1) - lo) * (table[lo + 1] - table[lo])
    return np.where(at >= len(table) - 1, 1.0, w)
