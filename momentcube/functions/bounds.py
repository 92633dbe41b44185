"""Rank bounds that hold for every data set with the given moments.

Range and Markov bounds are native columns (code-generated); the tight bound comes from the discrete distribution with the same
moments that puts as much mass as possible on t. All are widened by their rounding error, so no verdict is wrong through it.
rank(t) = number of values below t. If a lower bound of rank(t) exceeds n phi, then q_phi < t.
"""

from __future__ import annotations

from math import comb

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from . import moments as M

EPS = 2.0**-48
#: Orders of which Markov bounds are taken. Any order gives a true bound; a few keep the generated code of one row small enough for the JIT.
ORDERS = (2, 4, 8)


def range_verdict(xmin: Column, xmax: Column, t: Column, above: bool = True) -> Column:
    """Is q_phi > t (``above``) or q_phi < t? True or false where the extremes decide, else NULL."""
    if above:
        return F.when(t >= xmax, F.lit(False)).when(t < xmin, F.lit(True))
    return F.when(t <= xmin, F.lit(False)).when(t > xmax, F.lit(True))


def _shifted(family: str, j: int, y: str, sign: int) -> str:
    """E[(sign * (v - c))^j] with y = -sign * c, by Horner's scheme: one product and one sum for each order."""
    out = "1D"
    for i in range(1, j + 1):
        out = f"({out} * {y} + {comb(j, i) * sign**i}D * __{family}{i})"
    return out


def _power(v: str, j: int) -> str:
    return v if j == 1 else f"({v} * {v})" if j == 2 else f"pow({v}, {j}D)"


def with_markov(df: DataFrame, spec, t: Column, pad: bool = True, low: str = "__lo", high: str = "__hi") -> DataFrame:
    """``df`` of summaries with bounds on rank(t) / n added: the best of a few orders of powers and, where all values are positive, of logs.

    E[y^j] / reach^j bounds the share with y >= reach, for y = v - min and y = max - v. Steps are projections of their own, so that
    means and reciprocals are computed once; the last one is a generator of one row, through which filters on the bounds don't
    sink (they would repeat the arithmetic). No input is null, so the generated code has no null checks. SQL text: it is built faster
    than hundreds of column objects.
    """
    kept = df.columns
    own = [f"`{c}`" for c in kept]
    shift = f"{float(spec.shift) if spec.log_policy == 'shift' else 0.0!r}D"
    families = [("p", spec.s, "__least", "__most", "__at", "true")] if spec.s else []
    if spec.l:
        log = lambda c: f"coalesce(ln(greatest({c} + {shift}, 1e-300D)), 0D)"
        families.append(("l", spec.l, log("__least"), log("__most"), log("__at"), f"n_pos = n AND __least + {shift} > 0 AND __at + {shift} > 0"))
    first, second, lows, highs = [], [], [], []
    for f, names, a, b, at, usable in families:
        orders = [j for j in (range(1, len(names) + 1) if len(names) <= 4 else ORDERS) if j <= len(names)]
        first += [f"{a} AS __{f}a", f"{b} AS __{f}b", f"{at} AS __{f}t", f"coalesce({usable}, false) AS __{f}ok"]
        first += [f"coalesce({c}, 0D) * __inv AS __{f}{i}" for i, c in enumerate(names[: max(orders)], 1)]
        shares = []
        for d, sign, c, y, reach in (("u", 1, f"__{f}a", f"(-__{f}a)", f"__{f}t - __{f}a"), ("d", -1, f"__{f}b", f"__{f}b", f"__{f}b - __{f}t")):
            r, q = f"__{f}{d}r", f"__{f}{d}q"
            second += [f"pow(greatest({reach}, 1e-300D), -1D) AS {r}", f"greatest(abs(__{f}a), abs(__{f}b)) + abs({c}) AS {q}"]
            widened = f" + {EPS!r}D * {{}}" if pad else ""
            best = [f"({_shifted(f, j, y, sign)}{widened.format(_power(q, j))}) * {_power(r, j)}" for j in orders]
            shares.append(f"least({', '.join(best)})" if len(best) > 1 else best[0])
        lows.append(f"CASE WHEN __{f}ok THEN least(greatest(1D - {shares[0]}, 0D), 1D) ELSE 0D END")
        highs.append(f"CASE WHEN __{f}ok THEN least(greatest({shares[1]}, 0D), 1D) ELSE 1D END")
    one = lambda cols, pick: cols[0] if len(cols) == 1 else f"{pick}({', '.join(cols)})"
    lo = f"CASE WHEN NOT __known OR __at <= __least THEN 0D WHEN __at > __most THEN 1D ELSE {one(lows, 'greatest')} END"
    hi = f"CASE WHEN NOT __known THEN 1D WHEN __at <= __least THEN 0D WHEN __at >= __most THEN 1D ELSE {one(highs, 'least')} END"
    df = df.withColumn("__at", t.cast("double"))
    df = df.selectExpr(*own, "pow(CAST(greatest(n, 1) AS DOUBLE), -1D) AS __inv", "coalesce(xmin, 0D) AS __least", "coalesce(xmax, 0D) AS __most", "coalesce(__at, 0D) AS __at", "__at IS NOT NULL AND n > 0 AS __known")
    df = df.selectExpr("*", *first).selectExpr("*", *second)
    return df.selectExpr(*own, f"explode(array(named_struct('lo', {lo}, 'hi', {hi}))) AS __markov").selectExpr(*own, f"__markov.lo AS `{low}`", f"__markov.hi AS `{high}`")


def bound_verdict(low: Column, high: Column, phi: float, above: bool = True) -> Column:
    """Is q_phi > t (``above``) or q_phi < t, by bounds on rank(t) / n?"""
    return F.when(low > phi, F.lit(not above)).when(high < phi, F.lit(above))


def principal(mu: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(lower, upper) bounds on the share below and up to u among distributions on the line with means mu of u^i, i = 0..2m; one row a population.

    The Jacobi matrix of the moments gets a last entry that makes u a node; node masses left of u and on it give both bounds. Rows of
    which the moments don't define a matrix of full size safely go on with fewer.
    """
    mu, u = np.asarray(mu, float), np.asarray(u, float).copy()
    low, high = np.zeros(len(mu)), np.ones(len(mu))
    left = np.arange(len(mu))
    for m in range((mu.shape[1] - 1) // 2, 0, -1):
        if not len(left):
            break
        i = np.arange(m + 1)
        hankel = mu[left][:, i[:, None] + i[None, :]]
        finite = np.isfinite(hankel).all(axis=(1, 2))
        definite = np.zeros(len(left), bool)
        definite[finite] = np.linalg.eigvalsh(hankel[finite])[:, 0] > 1e-13
        r = np.zeros_like(hankel)
        r[definite] = np.linalg.cholesky(hankel[definite]).transpose(0, 2, 1)
        d = np.diagonal(r, axis1=1, axis2=2)
        usable = definite & (d.min(axis=1) >= 1e-5)
        now, r, d = left[usable], r[usable], d[usable]
        left = left[~usable]
        if not len(now):
            continue
        off = d[:, 1:] / d[:, :-1]
        first = np.stack([r[:, j, j + 1] / d[:, j] for j in range(m)], axis=1)
        alpha = first - np.concatenate([np.zeros((len(now), 1)), first[:, :-1]], axis=1)
        full = np.zeros((len(now), m + 1, m + 1))
        k = np.arange(m)
        full[:, k, k] = alpha
        full[:, k, k + 1] = full[:, k + 1, k] = off
        for _ in range(50):  # t on a node of the smaller matrix has no finite last entry: step aside by less than the widening
            small = full[:, :m, :m] - u[now][:, None, None] * np.eye(m)
            e = np.zeros((len(now), m, 1))
            e[:, -1, 0] = off[:, m - 1] ** 2
            flat = np.abs(np.linalg.det(small)) < 1e-300
            small[flat] += 1e-12 * np.eye(m)
            last = u[now] + np.linalg.solve(small, e)[:, -1, 0]
            bad = ~(np.abs(last) <= 1e9)
            if not bad.any():
                break
            u[now[bad]] += 1e-7
        full[:, m, m] = np.where(np.abs(last) <= 1e9, last, 1e9)
        nodes, vec = np.linalg.eigh(full)
        mass = vec[:, 0, :] ** 2
        at = np.abs(nodes - u[now][:, None]).argmin(axis=1)
        upto = np.cumsum(mass, axis=1)
        row = np.arange(len(now))
        pad = 1e-7 + 1e-13 / d.min(axis=1) ** 2
        low[now] = np.maximum(0.0, upto[row, at] - mass[row, at] - pad)
        high[now] = np.minimum(1.0, upto[row, at] + pad)
    return low, high


def principal_bounds(n, n_pos, lo, hi, s, l, t, families=("power", "log"), orders=None, shift=None) -> tuple[np.ndarray, np.ndarray]:
    """Bounds on rank(t) / n from both families, one row a population (s, l: rows x orders); ``orders`` (rows of k1, k2) limits the moments used; logs are of x + shift."""
    n, n_pos, lo, hi, t = (np.asarray(v, float) for v in (n, n_pos, lo, hi, t))
    shift = np.zeros(len(n)) if shift is None else np.asarray(shift, float)
    s, l = (np.asarray(v, float).reshape(len(n), -1) for v in (s, l))
    with np.errstate(invalid="ignore"):
        below, above = (n > 0) & (t <= lo), (n > 0) & (t > hi)
        inside = (n > 0) & (t > lo) & (t <= hi) & (hi > lo)
    low, high = np.where(above, 1.0, 0.0), np.where(below, 0.0, 1.0)
    for f, (name, sums) in enumerate((("power", s), ("log", l))):
        if name not in families or not sums.shape[1]:
            continue
        own = inside if name == "power" else inside & (n_pos == n) & (lo + shift > 0) & (t + shift > 0)
        rows = np.nonzero(own)[0]
        if not len(rows):
            continue
        a, b, at = (lo[rows], hi[rows], t[rows]) if name == "power" else (np.log(v[rows] + shift[rows]) for v in (lo, hi, t))
        k = np.minimum(sums.shape[1], np.floor(M.max_order(a, b)).astype(int))
        if orders is not None:
            k = np.minimum(k, np.asarray(orders)[rows, f])
        k -= k % 2
        for order in np.unique(k[k >= 2]):
            pick = k == order
            r, a1, b1 = rows[pick], a[pick], b[pick]
            mu = M.shifted_means(np.column_stack([np.ones(len(r)), sums[r, :order] / n[r][:, None]]), a1, b1)
            p, q = principal(mu, (2 * at[pick] - a1 - b1) / (b1 - a1))
            slack = np.minimum(0.5, M.shift_error(int(order), (a1 + b1) / (b1 - a1)) * 64)
            low[r], high[r] = np.maximum(low[r], p - slack), np.minimum(high[r], q + slack)
    return np.minimum(low, high), np.maximum(low, high)


def quantile_interval(bounds_at, lo: np.ndarray, hi: np.ndarray, phi: float, rounds: int = 50) -> tuple[np.ndarray, np.ndarray]:
    """The intervals that must hold the phi-quantiles, by bisection on bounds of the rank (``bounds_at``: rows of t -> low, high)."""
    ends = []
    for side in (0, 1):
        a, b = np.asarray(lo, float), np.asarray(hi, float)
        for _ in range(rounds):
            mid = (a + b) / 2
            low, high = bounds_at(mid)
            right = high < phi if side == 0 else ~(low > phi)
            a, b = np.where(right, mid, a), np.where(right, b, mid)
        ends.append(a if side == 0 else b)
    return ends[0], ends[1]


def guaranteed_error(low: Column, high: Column, phi: float) -> Column:
    """Worst rank error of an estimate with these bounds on its rank."""
    return F.greatest(F.abs(high - phi), F.abs(low - phi))
