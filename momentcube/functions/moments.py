"""Moments: shift and scale to [-1, 1], change to the Chebyshev basis, stability limits, order selection."""

from __future__ import annotations

from functools import lru_cache
from math import comb

import numpy as np
from pyspark.sql import Column, functions as F

KAPPA_MAX = 1e4


@lru_cache(maxsize=None)
def chebyshev_rows(k: int) -> np.ndarray:
    """Row j holds the monomial coefficients of T_j."""
    t = np.zeros((k + 1, k + 1))
    t[0, 0] = 1
    if k:
        t[1, 1] = 1
    for j in range(2, k + 1):
        t[j, 1:] = 2 * t[j - 1, :-1]
        t[j] -= t[j - 2]
    return t


def shifted_means(mu: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Means of ((2x - lo - hi) / (hi - lo))^i from means of x^i; one row a population. mu[:, 0] = 1."""
    k = mu.shape[1] - 1
    span = np.where(hi > lo, hi - lo, 1.0)
    a, b = 2 / span, -(hi + lo) / span
    scaled = mu * np.cumprod(np.column_stack([np.ones_like(a), *[a] * k]), axis=1)
    powers = np.cumprod(np.column_stack([np.ones_like(b), *[b] * k]), axis=1)
    out = np.ones_like(mu)
    for i in range(1, k + 1):
        out[:, i] = (scaled[:, : i + 1] * powers[:, i::-1]) @ _binomials(i)
    return out


@lru_cache(maxsize=None)
def _binomials(i: int) -> np.ndarray:
    return np.array([comb(i, m) for m in range(i + 1)], dtype=float)


def chebyshev_means(mu: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Means of T_j of the scaled variable."""
    return shifted_means(mu, lo, hi) @ chebyshev_rows(mu.shape[1] - 1).T


def max_order(lo, hi):
    """Highest order that double precision supports for values centred away from zero."""
    span = np.where(hi > lo, hi - lo, 1.0)
    c = np.abs(hi + lo) / span
    return 13.06 / (0.78 + np.log10(c + 1))


def max_order_col(lo: Column, hi: Column) -> Column:
    c = F.abs(hi + lo) / (hi - lo)
    return F.when(hi > lo, F.lit(13.06) / (F.lit(0.78) + F.log10(c + 1)))


def shift_error(k: int, c: float, eps: float = 2.0**-53) -> float:
    """Bound on the error of a shifted moment: 2^k (|c| + 1)^k eps."""
    return (2 * (abs(c) + 1)) ** k * eps


@lru_cache(maxsize=None)
def nodes(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Chebyshev points on [-1, 1] (ascending) and the weights that integrate the interpolant exactly."""
    theta = np.pi * np.arange(n + 1) / n
    x = -np.cos(theta)
    w = np.ones(n + 1)
    for j in range(1, n // 2 + 1):
        w -= (1.0 if 2 * j == n else 2.0) / (4 * j * j - 1) * np.cos(2 * j * theta)
    w *= 2.0 / n
    w[[0, -1]] /= 2
    return x, w


def chebyshev_values(u: np.ndarray, k: int) -> np.ndarray:
    """T_0..T_k at u, stacked before the last axis."""
    out = [np.ones_like(u), u]
    for _ in range(2, k + 1):
        out.append(2 * u * out[-1] - out[-2])
    return np.stack(out[: k + 1], axis=-2)


@lru_cache(maxsize=None)
def uniform_means(k: int) -> np.ndarray:
    """Means of T_j under a uniform density on [-1, 1]."""
    j = np.arange(k + 1)
    with np.errstate(divide="ignore"):
        return np.where(j % 2 == 0, 1 / (1.0 - j * j), 0.0)


def condition(gram: np.ndarray) -> float:
    """Condition number of a Hessian."""
    e = np.linalg.eigvalsh(gram)
    return float(e[-1] / e[0]) if e[0] > 0 else float("inf")


def monomial_condition(k: int, lo: float, hi: float) -> float:
    """Condition number of the Hessian on raw powers at the uniform density, for contrast."""
    x, w = nodes(256)
    x = lo + (x + 1) / 2 * (hi - lo)
    v = x[None, :] ** np.arange(k + 1)[:, None]
    e = np.linalg.svd((v * (w / 2)) @ v.T, compute_uv=False)
    return float(e[0] / max(e[-1], 1e-300))


def chebyshev_condition(k: int) -> float:
    u, w = nodes(128)
    v = chebyshev_values(u, k)
    return condition((v * (w / 2)) @ v.T)


def choose_orders(kappa, power_gap: np.ndarray, log_gap: np.ndarray, kappa_max: float = KAPPA_MAX) -> tuple[int, int]:
    """Greedy (k1, k2): add the moment closest to its uniform value as long as the Hessian stays well conditioned.

    kappa(k1, k2): condition number of the Hessian at the uniform density; gaps: |observed - uniform| for each order from 1.
    """
    p, q = len(power_gap), len(log_gap)
    k1 = k2 = 0
    while k1 < p or k2 < q:
        options = sorted(([(power_gap[k1], 0)] if k1 < p else []) + ([(log_gap[k2], 1)] if k2 < q else []))
        for _, which in options:
            a, b = (k1 + 1, k2) if which == 0 else (k1, k2 + 1)
            if kappa(a, b) <= kappa_max:
                k1, k2 = a, b
                break
        else:
            break
    return k1, k2
