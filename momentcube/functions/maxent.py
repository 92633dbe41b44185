"""Quantiles of the maximum-entropy density that has given moments, for batches of populations.

Unknown: coefficients of an exponential family on a Chebyshev basis of x and of ln x. The convex potential
(integral of the density minus coefficients times targets) is minimised; the density is sampled at Chebyshev points, which
integrates its interpolant exactly and lets all populations of one shape share stacked matrix products.

solver: "chebyshev" (damped Newton; all integrals are weighted sums over the points), "cosine" (the same integrals from Chebyshev
series: the density and its products with the functions that are no polynomials in the integration variable go through a cosine
transform; in numpy the transforms cost more than the matrix products they save), "newton_romberg" (each entry integrated apart by
Romberg's rule), "lbfgs" and "gd" (gradients only).
Status: ok (moments match to 1e-9), loose (less closely, see ``ACCEPTED``), reduced (orders were dropped until the fit converged), degenerate (one
value), split (positive and negative values fitted apart), empty.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

from . import moments as M

TOLERANCE = 1e-9
GRID = 1024
#: Largest residual of a solver's result that is still used; beyond TOLERANCE it is marked "loose".
ACCEPTED = {"chebyshev": 1e-7, "cosine": 1e-7, "newton_romberg": 1e-6, "lbfgs": 1e-5, "gd": np.inf}


@dataclass
class Batch:
    """Populations as arrays, one row each. Logs are of x + off; ``halves``: (positive, mirrored negative) populations of a split by sign, with shares.

    ``above_zero``: positive populations with both families, for rows whose other values are all zero (which add nothing to sums of powers)."""

    n: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    power: np.ndarray
    log: np.ndarray
    use_log: np.ndarray
    off: np.ndarray
    mixed: np.ndarray | None = None
    halves: tuple[Batch, Batch] | None = None
    zeros: np.ndarray | None = None
    above_zero: Batch | None = None

    @classmethod
    def of(cls, n, n_pos, lo, hi, s, l, families=("power", "log"), max_k: int | None = None, shift=0.0, n_neg=None, pmin=None, nmax=None, m=None):
        n = np.asarray(n, float)
        ones = np.ones((len(n), 1))
        safe = np.where(n > 0, n, 1)[:, None]
        s, l = (np.asarray(a, float).reshape(len(n), -1)[:, :max_k] for a in (s, l))
        lo, hi, n_pos = np.asarray(lo, float), np.asarray(hi, float), np.asarray(n_pos, float)
        off = np.broadcast_to(np.nan_to_num(np.asarray(shift, float)), n.shape)
        use_log = (n_pos == n) & (n > 0) & (lo + off > 0) & (l.shape[1] > 0) & ("log" in families)
        power = np.hstack([ones, s / safe]) if "power" in families else ones
        out = cls(n, lo, hi, power, np.hstack([ones, l / safe]), use_log, off)
        m = None if m is None else np.asarray(m, float).reshape(len(n), -1)[:, :max_k]
        if m is not None and m.shape[1] and "log" in families:
            n_neg = np.nan_to_num(np.asarray(n_neg, float))
            out.mixed = (n > 0) & (n_neg > 0)
            out.zeros = (n_neg == 0) & (n_pos > 0) & (n_pos < n)
            out.above_zero = cls.of(n_pos, n_pos, pmin, hi, s, l, families)
            out.halves = tuple(cls.of(k, k, a, b, np.zeros((len(n), 0)), sums) for k, a, b, sums in ((n_pos, pmin, hi, l), (n_neg, -np.asarray(nmax, float), -lo, m)))
        return out

    def rows(self, at: np.ndarray) -> Batch:
        return Batch(self.n[at], self.lo[at], self.hi[at], self.power[at], self.log[at], self.use_log[at], self.off[at])


@dataclass
class Fit:
    """One fitted density: values on a grid of x with its distribution function, orders, status, iterations."""

    x: np.ndarray
    cdf: np.ndarray
    k1: int
    k2: int
    status: str
    iterations: int
    residual: float
    peak: float

    def quantile(self, phi: float) -> float:
        return float(np.interp(phi, self.cdf, self.x))

    def rank(self, t: float) -> float:
        return float(np.interp(t, self.x, self.cdf, left=0.0, right=1.0))


def _basis(lo, hi, k1, k2, log_domain, n, off=0.0):
    """(x, du/dv weights, V) at the integration points for rows of one shape; V: rows x functions x points."""
    v, w = M.nodes(n)
    half = (hi - lo)[:, None] / 2
    off = np.broadcast_to(off, lo.shape)[:, None]
    if log_domain or k2:
        a, b = np.log(lo[:, None] + off), np.log(hi[:, None] + off)
    if log_domain:
        x = np.exp(a + (v + 1) / 2 * (b - a))
        weight = w * x * (b - a) / 2 / half
        x = x - off
    else:
        x = lo[:, None] + (v + 1) * half
        weight = np.broadcast_to(w, x.shape)
    u = np.clip((x - lo[:, None]) / half - 1, -1, 1)
    parts = [M.chebyshev_values(u, k1)]
    if k2:
        logs = np.broadcast_to(v, x.shape) if log_domain else np.clip((np.log(np.maximum(x, lo[:, None]) + off) - a) / (b - a) * 2 - 1, -1, 1)
        parts.append(M.chebyshev_values(logs, k2)[:, 1:])
    return x, weight, np.concatenate(parts, axis=1)


def _density(theta, V):
    z = np.matmul(theta[:, None, :], V)[:, 0]
    return np.exp(np.clip(z, -700, 300, out=z), out=z)


def cosine_coefficients(y: np.ndarray) -> np.ndarray:
    """Values at the ascending Chebyshev points (last axis) -> coefficients of the interpolant, by a fast cosine transform."""
    n = y.shape[-1] - 1
    z = y[..., ::-1]
    c = np.fft.rfft(np.concatenate([z, z[..., n - 1 : 0 : -1]], axis=-1), axis=-1).real / n
    c[..., [0, n]] /= 2
    return c


@lru_cache(maxsize=None)
def _product_integrals(n: int, m: int) -> np.ndarray:
    """Integrals of T_a T_j over [-1, 1] for a <= n, j <= m: half the sum of those of T_{a+j} and T_{|a-j|}."""
    k = np.arange(n + m + 1)
    one = np.where(k % 2 == 0, 2 / (1.0 - np.where(k % 2 == 0, k, 0) ** 2.0), 0.0)
    a, j = np.arange(n + 1)[:, None], np.arange(m + 1)[None, :]
    return (one[a + j] + one[np.abs(a - j)]) / 2


class _Integrals:
    """Gradient integrals and Hessian for rows of one shape; ``take`` narrows them to rows that still move.

    transform: polynomials of the integration variable (powers in x, logs in ln x) are Chebyshev series themselves; every other
    function is replaced by its interpolant. Then an integral is a product of coefficients with integrals of T_a T_j.
    """

    def __init__(self, V, weight, k1, k2, log_domain, transform: bool):
        self.V, self.weight, self.transform = V, weight, transform
        d = k1 + k2 + 1
        n = V.shape[2] - 1
        self.own = np.array([0, *range(k1 + 1, d)] if log_domain else range(k1 + 1))
        self.rest = np.setdiff1d(np.arange(d), self.own)
        self.jacobian = weight / M.nodes(n)[1] if transform else None
        self.dual = cosine_coefficients(V[:, self.rest]) @ _product_integrals(n, n) if transform and len(self.rest) else None

    def take(self, at):
        out = object.__new__(_Integrals)
        out.__dict__.update(self.__dict__, V=self.V[at], weight=self.weight[at], jacobian=self.jacobian[at] if self.transform else None, dual=None if self.dual is None else self.dual[at])
        return out

    def hessian(self, f: np.ndarray) -> np.ndarray:
        """Integrals of f times each product of two basis functions; row 0 holds those of f times each function."""
        if not self.transform:
            fw = f * self.weight
            return (self.V * fw[:, None, :]) @ self.V.transpose(0, 2, 1)
        y, k, n, d = f * self.jacobian, len(self.own) - 1, f.shape[1] - 1, self.V.shape[1]
        H = np.empty((len(f), d, d))
        c = cosine_coefficients(y) @ _product_integrals(n, 2 * k)
        i = np.arange(k + 1)
        H[:, self.own[:, None], self.own[None, :]] = (c[:, i[:, None] + i[None, :]] + c[:, np.abs(i[:, None] - i[None, :])]) / 2
        if len(self.rest):
            series = cosine_coefficients(y[:, None, :] * self.V[:, self.rest])
            cross = series @ _product_integrals(n, k)
            H[:, self.rest[:, None], self.own[None, :]] = cross
            H[:, self.own[:, None], self.rest[None, :]] = cross.transpose(0, 2, 1)
            block = series @ self.dual.transpose(0, 2, 1)
            H[:, self.rest[:, None], self.rest[None, :]] = (block + block.transpose(0, 2, 1)) / 2
        return H


def _potential(theta, V, weight, target):
    with np.errstate(over="ignore", invalid="ignore"):
        return (_density(theta, V) * weight).sum(1) - (theta * target).sum(1)


def _newton(theta, V, weight, target, k1, k2, log_domain, transform=True, rounds=50):
    """Damped Newton steps. Rows leave when their moments match, or when six steps have hardly lowered their residual."""
    B, d = theta.shape
    steps = np.zeros(B, int)
    whole = part = _Integrals(V, weight, k1, k2, log_domain, transform)
    residual = np.full(B, np.inf)
    past: list[np.ndarray] = []
    moving = np.arange(B)
    f = _density(theta, V)
    for _ in range(rounds):
        H = part.hessian(f)
        g = H[:, 0] - target[moving]
        residual[moving] = np.abs(g).max(1)
        past.append(residual.copy())
        on = residual[moving] > TOLERANCE
        if len(past) > 16:
            on &= residual[moving] < 0.9 * past[-7][moving]
        if not on.all():
            moving, H, g = moving[on], H[on], g[on]
            if not len(moving):
                break
            part = whole.take(moving)
        H += 1e-13 * np.trace(H, axis1=1, axis2=2)[:, None, None] * np.eye(d)
        try:
            step = np.linalg.solve(H, g[:, :, None])[:, :, 0]
        except np.linalg.LinAlgError:
            step = np.stack([np.linalg.lstsq(h, v, rcond=None)[0] for h, v in zip(H, g)])
        at, goal, slope = theta[moving], target[moving], (step * g).sum(1)
        trial = at - step
        f = _density(trial, part.V)
        # close to the optimum a full step is right, and the potential no longer tells steps apart
        doubt = np.nonzero(~(np.abs(slope) < 1e-7))[0]
        if len(doubt):
            before = _potential(at[doubt], part.V[doubt], part.weight[doubt], goal[doubt])
            value = (f[doubt] * part.weight[doubt]).sum(1) - (trial[doubt] * goal[doubt]).sum(1)
            size = np.ones(len(doubt))
            for _ in range(40):
                worse = ~(value <= before - 1e-4 * size * slope[doubt] + 1e-14 * np.abs(before))
                if not worse.any():
                    break
                size[worse] /= 2
                w = doubt[worse]
                trial[w] = at[w] - size[worse][:, None] * step[w]
                f[w] = _density(trial[w], part.V[w])
                value[worse] = (f[w] * part.weight[w]).sum(1) - (trial[w] * goal[w]).sum(1)
        theta[moving] = trial
        steps[moving] += 1
    return theta, residual, steps


def _first_order(theta, V, weight, target, lbfgs: bool, rounds: int):
    theta, res, count = theta.copy(), np.zeros(len(theta)), np.zeros(len(theta), int)
    for b in range(len(theta)):
        Vb, wb, tb, x = V[b], weight[b], target[b], theta[b]
        value = lambda y: float(np.exp(np.clip(y @ Vb, -700, 300)) @ wb - y @ tb)  # noqa: B023,E731
        grad = lambda y: Vb @ (np.exp(np.clip(y @ Vb, -700, 300)) * wb) - tb  # noqa: B023,E731
        g, memory = grad(x), []
        for it in range(rounds):
            if np.abs(g).max() <= TOLERANCE:
                break
            q, coefs = g.copy(), []
            for s, y in reversed(memory) if lbfgs else ():
                c = s @ q / (y @ s)
                coefs.append(c)
                q -= c * y
            if memory and lbfgs:
                s, y = memory[-1]
                q *= (s @ y) / (y @ y)
            for (s, y), c in zip(memory, reversed(coefs)):
                q += (c - y @ q / (y @ s)) * s
            size, f0, slope = 1.0, value(x), q @ g
            if slope <= 0:
                q, slope, memory = g.copy(), g @ g, []
            while size > 1e-18 and not value(x - size * q) <= f0 - 1e-4 * size * slope:
                size /= 2
            new = x - size * q
            ng = grad(new)
            if lbfgs and (new - x) @ (ng - g) > 1e-300:
                memory = [*memory[-9:], (new - x, ng - g)]
            if size <= 1e-18:
                break
            x, g = new, ng
            count[b] = it + 1
        theta[b], res[b] = x, np.abs(g).max()
    return theta, res, count


def romberg(f, a: float, b: float, tol: float = 1e-10, levels: int = 14) -> float:
    """Integral by Richardson extrapolation of the trapezoid rule."""
    n, h = 1, b - a
    row = [h * (f(np.array([a, b])).sum()) / 2]
    for k in range(1, levels + 1):
        h /= 2
        mids = a + h * np.arange(1, 2 * n, 2)
        new = [row[0] / 2 + h * f(mids).sum()]
        for m in range(1, k + 1):
            new.append(new[-1] + (new[-1] - row[m - 1]) / (4**m - 1))
        if k > 3 and abs(new[-1] - row[-1]) <= tol * (1 + abs(new[-1])):
            return float(new[-1])
        row, n = new, n * 2
    return float(row[-1])


def _newton_romberg(theta, lo, hi, target, k1, k2, log_domain, off, rounds=60):
    out, res, count = theta.copy(), np.zeros(len(theta)), np.zeros(len(theta), int)
    for b in range(len(theta)):
        half = (hi[b] - lo[b]) / 2
        la, lb = (np.log(lo[b] + off[b]), np.log(hi[b] + off[b])) if k2 or log_domain else (0.0, 1.0)

        def rows(v):
            x = np.exp(la + (v + 1) / 2 * (lb - la)) - off[b] if log_domain else lo[b] + (v + 1) * half  # noqa: B023
            jac = (x + off[b]) * (lb - la) / 2 / half if log_domain else np.ones_like(v)  # noqa: B023
            parts = [M.chebyshev_values(np.clip((x - lo[b]) / half - 1, -1, 1), k1)]  # noqa: B023
            if k2:
                parts.append(M.chebyshev_values(np.clip((np.log(x + off[b]) - la) / (lb - la) * 2 - 1, -1, 1), k2)[1:])  # noqa: B023
            return np.concatenate(parts), jac

        d = k1 + k2 + 1
        one = lambda i, j, th: romberg(lambda v: (lambda r: r[0][i] * r[0][j] * np.exp(np.clip(th @ r[0], -700, 300)) * r[1])(rows(v)), -1.0, 1.0)  # noqa: B023,E731
        th = out[b]
        value = lambda y: one(0, 0, y) - y @ target[b]  # noqa: B023,E731
        for it in range(rounds):
            H = np.zeros((d, d))
            for i in range(d):
                for j in range(i, d):
                    H[i, j] = H[j, i] = one(i, j, th)
            g = H[0] - target[b]
            res[b] = np.abs(g).max()
            if res[b] <= 1e-8:
                break
            step, size, before = np.linalg.lstsq(H, g, rcond=None)[0], 1.0, value(th)
            while size > 1e-8 and not value(th - size * step) <= before + 1e-12:
                size /= 2
            th, count[b] = th - size * step, it + 1
        out[b] = th
    return out, res, count


def _finish(theta, lo, hi, k1, k2, log_domain, n, off):
    """x and distribution function on a grid, by integrating the Chebyshev series of the density."""
    x, weight, V = _basis(lo, hi, k1, k2, log_domain, n, off)
    f = _density(theta, V)
    c = cosine_coefficients(f * weight / M.nodes(n)[1])  # the density in the integration variable
    grid = -np.cos(np.pi * np.arange(GRID + 1) / GRID)
    up = np.zeros((len(c), n + 2))
    j = np.arange(n + 1)
    up[:, 1:] += c / (2 * (j + 1))
    up[:, 1] += c[:, 0] / 2
    up[:, 1:n] -= c[:, 2:] / (2.0 * (j[2:] - 1))
    cdf = up @ _grid_values(n + 1)
    cdf -= cdf[:, :1]
    cdf = np.maximum.accumulate(np.clip(cdf / cdf[:, -1:], 0, 1), axis=1)
    if log_domain:
        a, b = np.log(lo + off)[:, None], np.log(hi + off)[:, None]
        xs = np.exp(a + (grid + 1) / 2 * (b - a)) - off[:, None]
    else:
        xs = lo[:, None] + (grid + 1) / 2 * (hi - lo)[:, None]
    return xs, cdf, f.max(1)


@lru_cache(maxsize=None)
def _grid_values(k: int) -> np.ndarray:
    return M.chebyshev_values(-np.cos(np.pi * np.arange(GRID + 1) / GRID), k)


@lru_cache(maxsize=4096)
def _gram(spread: float, log_domain: bool, top: int) -> np.ndarray:
    """Hessian at the reference density (uniform in ln x over many orders of magnitude, else in x) over [1, powers, logs]; it depends on ln(hi / lo) alone."""
    lo, hi = np.array([1.0]), np.array([np.exp(spread)])
    _, weight, V = _basis(lo, hi, top, top, log_domain, 128)
    return (V[0] * ((M.nodes(128)[1] if log_domain else weight[0]) / 2)) @ V[0].T


@lru_cache(maxsize=1 << 18)
def _kappa(spread: float, log_domain: bool, top: int, k1: int, k2: int) -> float:
    pick = [*range(k1 + 1), *range(top + 1, top + 1 + k2)]
    return M.condition(_gram(spread, log_domain, top)[np.ix_(pick, pick)])


def _combined(neg: Fit, pos: Fit, n_neg: float, n_zero: float, n_pos: float) -> Fit:
    """One distribution function from those of mirrored negative values, zeros and positive values."""
    ends = lambda f: (np.repeat(f.x, 2), np.array([0.0, 1.0])) if len(f.x) == 1 else (f.x, f.cdf)
    n, x, c, done = n_neg + n_zero + n_pos, [], [], 0.0
    if n_neg:
        a, b = ends(neg)
        x, c, done = [-a[::-1]], [(1 - b[::-1]) * n_neg / n], n_neg / n
    if n_zero:
        x, c, done = [*x, np.zeros(2)], [*c, np.array([done, done + n_zero / n])], done + n_zero / n
    if n_pos:
        a, b = ends(pos)
        x, c = [*x, a], [*c, done + b * n_pos / n]
    return Fit(np.concatenate(x), np.concatenate(c), 0, max(neg.k2, pos.k2), "split", max(neg.iterations, pos.iterations), max(neg.residual, pos.residual), max(neg.peak, pos.peak))


def chosen_orders(b: Batch, kappa_max: float = M.KAPPA_MAX, scaled=None) -> list[tuple[int, int, bool]]:
    """(k1, k2, integrate in ln x) of each row, from its moments alone."""
    cheb, lcheb, llo, lhi = scaled or _scaled(b)
    cap, lcap = np.floor(M.max_order(b.lo, b.hi)).astype(int), np.floor(M.max_order(llo, lhi)).astype(int)
    gaps, lgaps = np.abs(cheb - M.uniform_means(cheb.shape[1] - 1)), np.abs(lcheb - M.uniform_means(lcheb.shape[1] - 1))
    out = []
    for r in range(len(b.n)):
        p = max(min(cheb.shape[1] - 1, cap[r]), 0)
        q = max(min(lcheb.shape[1] - 1, lcap[r]), 0) if b.use_log[r] else 0
        while p and not abs(cheb[r, p]) <= 1 + 1e-6:
            p -= 1
        while q and not abs(lcheb[r, q]) <= 1 + 1e-6:
            q -= 1
        if q:
            spread, domain, top = float(f"{lhi[r] - llo[r]:.3g}"), bool(lhi[r] - llo[r] > np.log(100)), max(p, q)
            k1, k2 = M.choose_orders(lambda a, c: _kappa(spread, domain, top, a, c), gaps[r, 1 : p + 1], lgaps[r, 1 : q + 1], kappa_max)  # noqa: B023
            out.append((k1, k2, bool(k2 and domain)))
        else:
            out.append((p, 0, False))
    return out


def _scaled(b: Batch):
    """Chebyshev means of both families and the ends of the logs; every row has hi > lo."""
    logs = b.use_log
    with np.errstate(invalid="ignore", divide="ignore"):
        llo, lhi = np.where(logs, np.log(np.where(logs, b.lo + b.off, 1)), 0), np.where(logs, np.log(np.where(logs, b.hi + b.off, 2)), 1)
    return M.chebyshev_means(b.power, b.lo, b.hi), M.chebyshev_means(b.log, llo, lhi), llo, lhi


def fit_batch(b: Batch, solver: str = "chebyshev", kappa_max: float = M.KAPPA_MAX) -> list[Fit]:
    """A fitted density for each row."""
    B = len(b.n)
    fits: list[Fit | None] = [None] * B
    live = b.n > 0
    mixed = b.mixed & (b.hi > b.lo) if b.mixed is not None else np.zeros(B, bool)
    if mixed.any():
        at = np.nonzero(mixed)[0]
        pos, neg = (h.rows(at) for h in b.halves)
        for i, p, q in zip(at, fit_batch(pos, solver, kappa_max), fit_batch(neg, solver, kappa_max)):
            fits[i] = _combined(q, p, b.halves[1].n[i], b.n[i] - b.halves[0].n[i] - b.halves[1].n[i], b.halves[0].n[i])
    zeros = b.zeros & (b.hi > b.lo) if b.zeros is not None else np.zeros(B, bool)
    if zeros.any():
        at = np.nonzero(zeros)[0]
        for i, p in zip(at, fit_batch(b.above_zero.rows(at), solver, kappa_max)):
            fits[i] = _combined(p, p, 0, b.n[i] - b.above_zero.n[i], b.above_zero.n[i])
        mixed = mixed | zeros
    for i in np.nonzero(~live)[0]:
        fits[i] = Fit(np.array([np.nan]), np.array([1.0]), 0, 0, "empty", 0, 0.0, 0.0)
    for i in np.nonzero(live & ~(b.hi > b.lo))[0]:
        fits[i] = Fit(np.array([b.lo[i]]), np.array([1.0]), 0, 0, "degenerate", 0, 0.0, 0.0)
    wide = np.nonzero(live & (b.hi > b.lo) & ~mixed)[0]
    if not len(wide):
        return fits  # type: ignore[return-value]
    own = b.rows(wide)
    lo, hi, off = own.lo, own.hi, own.off
    cheb, lcheb, llo, lhi = scaled = _scaled(own)
    shapes: dict[tuple, list[int]] = {}
    for r, shape in enumerate(chosen_orders(own, kappa_max, scaled)):
        shapes.setdefault(shape, []).append(r)
    tol = ACCEPTED[solver]
    queue = [(shape, rows, "", 128) for shape, rows in shapes.items()]
    while queue:
        (k1, k2, domain), rows, status, points = queue.pop()
        for start in range(0, len(rows), 256):
            part = np.array(rows[start : start + 256])
            target = np.concatenate([cheb[part, : k1 + 1], lcheb[part, 1 : k2 + 1]], axis=1)
            theta = np.zeros((len(part), k1 + k2 + 1))
            theta[:, 0] = np.log(0.5)
            if domain:  # start uniform in ln(x + off): exp(-ln(x + off)), normalised
                half_log = (lhi[part] - llo[part]) / 2
                theta[:, k1 + 1] = -half_log
                theta[:, 0] = np.log((hi[part] - lo[part]) / 2 / (2 * half_log)) - (llo[part] + lhi[part]) / 2
            if k1 + k2:
                x, weight, V = _basis(lo[part], hi[part], k1, k2, domain, points, off[part])
                if solver == "newton_romberg":
                    theta, res, count = _newton_romberg(theta, lo[part], hi[part], target, k1, k2, domain, off[part])
                elif solver in ("chebyshev", "cosine"):
                    theta, res, count = _newton(theta, V, weight, target, k1, k2, domain, solver == "cosine")
                else:
                    theta, res, count = _first_order(theta, V, weight, target, solver == "lbfgs", 3000)
                _, w2, V2 = _basis(lo[part], hi[part], k1, k2, domain, 2 * points, off[part])
                rough = np.abs(np.einsum("bdn,bn->bd", V2, _density(theta, V2) * w2) - target).max(1) > max(1e-5, 10 * tol)
            else:
                res, count, rough = np.zeros(len(part)), np.zeros(len(part), int), np.zeros(len(part), bool)
            good = (res <= tol) & ~rough
            if good.any():
                g = np.nonzero(good)[0]
                xs, cdf, peak = _finish(theta[g], lo[part[g]], hi[part[g]], k1, k2, domain, points, off[part[g]])
                for j, k in enumerate(g):
                    name = status or ("ok" if res[k] <= TOLERANCE else "loose")
                    fits[wide[part[k]]] = Fit(xs[j], cdf[j], k1, k2, name, int(count[k]), float(res[k]), float(peak[j]))
            finer = part[(res <= tol) & rough] if points < 1024 else part[:0]
            if len(finer):
                queue.append(((k1, k2, domain), finer.tolist(), status, points * 2))
            bad = np.setdiff1d(part[~good], finer)
            if len(bad):
                fewer = (k1 - 1, k2, domain) if k1 >= k2 else (k1, k2 - 1, bool(domain and k2 > 1))
                queue.append((fewer, bad.tolist(), "reduced", 128))
    return fits  # type: ignore[return-value]


def quantiles(b: Batch, phis, solver: str = "chebyshev", integer_valued: bool = False, kappa_max: float = M.KAPPA_MAX) -> tuple[np.ndarray, list[Fit]]:
    fits = fit_batch(b, solver, kappa_max)
    q = np.array([[f.quantile(p) for p in phis] for f in fits]).reshape(len(fits), len(phis))
    q = np.clip(q, b.lo[:, None], b.hi[:, None]) if len(q) else q
    return (np.round(q) if integer_valued else q), fits


def brent(f, a: float, b: float, tol: float = 1e-12, rounds: int = 200) -> float:
    """A root of f between a and b by inverse interpolation, guarded by bisection."""
    fa, fb = f(a), f(b)
    if fa * fb > 0:
        raise ValueError("no change of sign")
    c, fc, d = a, fa, b - a
    for _ in range(rounds):
        if fb * fc > 0:
            c, fc, d = a, fa, b - a
        if abs(fc) < abs(fb):
            a, b, c, fa, fb, fc = b, c, b, fb, fc, fb
        mid = (c - b) / 2
        if abs(mid) <= tol * max(1.0, abs(b)) or fb == 0:
            return b
        if a != c and fa != fc and fb != fc:
            s = a * fb * fc / ((fa - fb) * (fa - fc)) + b * fa * fc / ((fb - fa) * (fb - fc)) + c * fa * fb / ((fc - fa) * (fc - fb))
        else:
            s = b - fb * (b - a) / (fb - fa) if fb != fa else b + mid
        step = s - b
        if not 0 < step / mid < 1.5 or abs(step) > abs(d):
            step = mid
        a, fa, d = b, fb, step
        b = b + step
        fb = f(b)
    return b
