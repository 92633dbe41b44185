"""Other estimators from the same moments: closed forms and densities on a grid of 1000 points.

All take a maxent.Batch and give quantiles, rows x phis. Columns: ``gaussian`` also as a native column.
"""

from __future__ import annotations

from math import comb
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column, functions as F

from . import moments as M

POINTS = 1000


def gaussian_col(state_n: Column, s1: Column, s2: Column, phi: float) -> Column:
    """Mean plus z standard deviations, as a column."""
    mu = s1 / state_n
    return mu + F.sqrt(F.greatest(s2 / state_n - mu * mu, F.lit(0.0))) * F.lit(NormalDist().inv_cdf(phi))


def gaussian(b, phis) -> np.ndarray:
    mu, m2 = b.power[:, 1], b.power[:, 2]
    z = np.array([NormalDist().inv_cdf(p) for p in phis])
    return np.clip(mu[:, None] + np.sqrt(np.maximum(m2 - mu * mu, 0))[:, None] * z, b.lo[:, None], b.hi[:, None])


def moment_cdf(b, phis, k: int | None = None) -> np.ndarray:
    """A step function with k + 1 levels from binomial sums of the moments scaled to [0, 1]."""
    k = min(k or b.power.shape[1] - 1, b.power.shape[1] - 1)
    span = np.where(b.hi > b.lo, b.hi - b.lo, 1)
    y = [sum(comb(i, m) * (-b.lo) ** (i - m) * b.power[:, m] for m in range(i + 1)) / span**i for i in range(k + 1)]
    mass = [sum(comb(k, j) * comb(j, a) * (-1) ** (j - a) * y[j] for j in range(a, k + 1)) for a in range(k + 1)]
    cdf = np.cumsum(np.array(mass), axis=0).T
    level = np.array([[int(np.argmax(np.append(row, np.inf) >= p - 1e-12)) for p in phis] for row in cdf])
    return np.minimum(b.lo[:, None] + level / k * span[:, None], b.hi[:, None])


def _grid(b, i, families):
    """Scaled points, constraint matrix and targets of one population on equally spaced points (in ln x if only logs are used)."""
    only_log = families == ("log",) and b.use_log[i]
    lo, hi = (np.log(b.lo[i]), np.log(b.hi[i])) if only_log else (b.lo[i], b.hi[i])
    mu = (b.log if only_log else b.power)[i : i + 1]
    k = min(mu.shape[1] - 1, int(M.max_order(np.array(lo), np.array(hi))))
    u = np.linspace(-1, 1, POINTS)
    x = lo + (u + 1) / 2 * (hi - lo)
    t = M.chebyshev_means(mu[:, : k + 1], np.array([lo]), np.array([hi]))[0]
    return (np.exp(x) if only_log else x), M.chebyshev_values(u, k), t


def _invert(x, p, phis):
    c = np.cumsum(np.maximum(p, 0))
    return np.interp(np.array(phis) * c[-1], c, x)


def grid_maxent(b, phis, families=("power",)) -> np.ndarray:
    """Largest discrete entropy under the moments, by Newton steps on the dual."""
    out = []
    for i in range(len(b.n)):
        x, A, t = _grid(b, i, families)
        lam = np.zeros(len(t))
        lam[0] = -np.log(POINTS)
        value = lambda z: np.exp(np.clip(z @ A, -700, 300)).sum() - z @ t  # noqa: B023,E731
        for _ in range(200):
            p = np.exp(np.clip(lam @ A, -700, 300))
            g = A @ p - t
            if np.abs(g).max() < 1e-9:
                break
            step = np.linalg.lstsq((A * p) @ A.T + 1e-13 * np.eye(len(t)), g, rcond=None)[0]
            size, at = 1.0, value(lam)
            while size > 1e-12 and not value(lam - size * step) <= at:
                size /= 2
            lam = lam - size * step
        out.append(_invert(x, np.exp(np.clip(lam @ A, -700, 300)), phis))
    return np.array(out)


def grid_svd(b, phis, families=("power",), cut: float = 1e-10) -> np.ndarray:
    """Least-norm masses with these moments by a pseudo-inverse; negative masses are cut off."""
    return np.array([_invert(x, np.linalg.pinv(A, rcond=cut) @ t, phis) for x, A, t in (_grid(b, i, families) for i in range(len(b.n)))])


def grid_min_peak(b, phis, families=("power",)) -> np.ndarray:
    """The masses with the smallest largest mass under the moments: a linear program, by a primal-dual interior point.

    Variables: masses p, their slack to the peak q = h - p, and h. Moments may be off by 1e-6 (grid rounding).
    """
    out = []
    for i in range(len(b.n)):
        x, A, t = _grid(b, i, families)
        out.append(_invert(x, _min_peak(A, t), phis))
    return np.array(out)


def _min_peak(A: np.ndarray, t: np.ndarray, rounds: int = 80) -> np.ndarray:
    """min h with A p = t, p + q - h 1 = 0, all >= 0. Normal equations shrink to the moments and h, as the rest is diagonal."""
    d, m = A.shape
    p, h = np.full(m, 1.0 / m), 4.0 / m
    q = h - p
    y, w = np.zeros(d), np.full(m, -1.0 / m / 2)  # multipliers of the moments and of p + q - h = 0
    zp, zq, zh = np.full(m, 1.0 / m), np.full(m, 1.0 / m), 0.5
    for _ in range(rounds):
        rp, rq = t - A @ p, h - p - q
        dp, dq, dh = -(A.T @ y) - w - zp, -w - zq, 1 + w.sum() - zh  # dual residuals of p, q, h (costs 0, 0, 1)
        mu = (p @ zp + q @ zq + h * zh) / (2 * m + 1)
        if mu < 1e-13 and np.abs(rp).max() < 1e-6:
            break
        sigma = 0.15
        cp, cq, ch = sigma * mu - p * zp, sigma * mu - q * zq, sigma * mu - h * zh
        a, c, e = p / zp, q / zq, h / zh
        # p: dzp = (cp - zp dP)/p;  dP = a (A^T dy + dw - dp) + cp/zp, likewise for q and h
        gp, gq, gh = -a * dp + cp / zp, -c * dq + cq / zq, -e * dh + ch / zh
        s = a + c
        # p + q - h: a A^T dy + s dw + e sum(dw) ... : solve for dw given dy and dh
        # dh = gh + e * (-(sum dw)); unknowns dy, H = dh
        B = a / s
        S = (A * (a - a * B)) @ A.T
        v = A @ B
        rhs_w = rq - gp - gq
        r1 = rp - A @ gp - A @ (B * rhs_w)
        # dw = (rhs_w + H - a A^T dy) / s ; H = gh - e * sum(dw)
        k0, k1, k2 = (rhs_w / s).sum(), (1 / s).sum(), A @ B
        K = np.zeros((d + 1, d + 1))
        K[:d, :d], K[:d, d] = S, v
        K[d, :d], K[d, d] = -e * k2, 1 + e * k1
        sol = np.linalg.lstsq(K + 1e-15 * np.eye(d + 1), np.append(r1, gh - e * k0), rcond=None)[0]
        ny, H = sol[:d], sol[d]
        nw = (rhs_w + H - a * (A.T @ ny)) / s
        P, Q = gp + a * (A.T @ ny + nw), gq + c * nw
        zP, zQ, zH = (cp - zp * P) / p, (cq - zq * Q) / q, (ch - zh * H) / h
        ratio = lambda v, dv: min(1.0, 0.95 * float((-v[dv < 0] / dv[dv < 0]).min())) if (dv < 0).any() else 1.0
        one = min(ratio(p, P), ratio(q, Q), ratio(np.array([h]), np.array([H])))
        two = min(ratio(zp, zP), ratio(zq, zQ), ratio(np.array([zh]), np.array([zH])))
        p, q, h = p + one * P, q + one * Q, h + one * H
        y, w = y + two * ny, w + two * nw
        zp, zq, zh = zp + two * zP, zq + two * zQ, zh + two * zH
    return p
