"""Arrow-batched functions over summary states (structs assembled after the merge)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from . import bounds, estimators, maxent

BATCHED = {"gaussian": estimators.gaussian, "moment_cdf": estimators.moment_cdf, "grid_maxent": estimators.grid_maxent, "grid_svd": estimators.grid_svd, "grid_min_peak": estimators.grid_min_peak}
SOLVERS = tuple(maxent.ACCEPTED)


def to_batch(st: pd.DataFrame, families=("power", "log"), max_k: int | None = None) -> maxent.Batch:
    """States as arrays; NULL states count as empty."""
    stack = lambda c: np.array([np.zeros(0) if v is None else np.asarray(v, float) for v in st[c]]) if len(st) else np.zeros((0, 0))
    whole = lambda c: pd.to_numeric(st[c]).fillna(0).to_numpy(float)
    real = lambda c: pd.to_numeric(st[c]).to_numpy(float)
    more = {}
    if "shift" in st.columns:
        more["shift"] = whole("shift")
    if "m" in st.columns and len(st) and (sums := stack("m")).ndim == 2 and sums.shape[1]:
        more |= {"n_neg": whole("n_neg"), "pmin": real("pmin"), "nmax": real("nmax"), "m": sums}
    return maxent.Batch.of(whole("n"), whole("n_pos"), real("xmin"), real("xmax"), stack("s"), stack("l"), families, max_k, **more)


def _live(st: pd.DataFrame) -> np.ndarray:
    return (st["n"].fillna(0) > 0).to_numpy()


def fits_of(st: pd.DataFrame, families=("power", "log")) -> list:
    """A fit for each state; NULL and empty states share the empty one."""
    live = _live(st)
    empty = maxent.Fit(np.array([np.nan]), np.array([1.0]), 0, 0, "empty", 0, 0.0, 0.0)
    out = [empty] * len(st)
    if live.any():
        for i, f in zip(np.nonzero(live)[0], maxent.fit_batch(to_batch(st[live], families))):
            out[i] = f
    return out


def quantiles_udf(phis, solver: str = "chebyshev", families=("power", "log"), max_k: int | None = None, integer_valued: bool = False):
    """state -> array<double>, one value for each phi; NULL for an empty or NULL state. ``solver`` may name any estimator."""
    phis = tuple(phis)

    @F.pandas_udf("array<double>")
    def estimate(st: pd.DataFrame) -> pd.Series:
        live = _live(st)
        out: list = [None] * len(st)
        if live.any():
            b = to_batch(st[live], families, max_k)
            if solver not in BATCHED:
                q = maxent.quantiles(b, phis, solver, integer_valued)[0]
            elif solver.startswith("grid_"):
                q = BATCHED[solver](b, phis, families)
            else:
                q = BATCHED[solver](b, phis)
            for i, v in zip(np.nonzero(live)[0], np.round(q) if integer_valued else q):
                out[i] = v.tolist()
        return pd.Series(out, dtype=object)

    return estimate


def info_udf(families=("power", "log")):
    """state -> orders used, status, iterations, residual, density peak."""

    @F.pandas_udf("k1 int, k2 int, status string, iterations int, residual double, peak double")
    def info(st: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([(f.k1, f.k2, f.status, f.iterations, f.residual, f.peak) for f in fits_of(st, families)], columns=["k1", "k2", "status", "iterations", "residual", "peak"])

    return info


def cdf_udf():
    """(state, x) -> estimated share of values below x."""

    @F.pandas_udf("double")
    def cdf(st: pd.DataFrame, x: pd.Series) -> pd.Series:
        return pd.Series([None if f.status == "empty" or np.isnan(v) else f.rank(v) if len(f.x) > 1 else float(f.x[0] < v) for f, v in zip(fits_of(st), x.astype(float))], dtype="float64")

    return cdf


def _tight(st: pd.DataFrame, t, families=("power", "log"), orders=None):
    """Tight bounds at t for states that are neither NULL nor empty."""
    stack = lambda c: np.array([np.asarray(v, float) for v in st[c]])
    shift = st["shift"].fillna(0.0).to_numpy(float) if "shift" in st.columns else None
    return bounds.principal_bounds(st["n"], st["n_pos"], st["xmin"], st["xmax"], stack("s"), stack("l"), t, families, orders, shift)


def bounds_udf(families=("power", "log")):
    """(state, t) -> tight bounds on the share of values below t."""

    @F.pandas_udf("lo double, hi double")
    def tight(st: pd.DataFrame, t: pd.Series) -> pd.DataFrame:
        out = pd.DataFrame({"lo": np.zeros(len(st)), "hi": np.ones(len(st))})
        at = np.nonzero(_live(st) & t.notna().to_numpy())[0]
        if len(at):
            out.loc[at, "lo"], out.loc[at, "hi"] = _tight(st.iloc[at], t.to_numpy(float)[at], families)
        return out

    return tight


def interval_udf(phi: float):
    """state -> the interval that must hold the phi-quantile."""

    @F.pandas_udf("lo double, hi double")
    def interval(st: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame({"lo": np.full(len(st), np.nan), "hi": np.full(len(st), np.nan)}).astype(object).where(lambda v: v.notna(), None)
        at = np.nonzero(_live(st))[0]
        if len(at):
            own = st.iloc[at]
            a, b = bounds.quantile_interval(lambda v: _tight(own, v), own["xmin"].to_numpy(float), own["xmax"].to_numpy(float), phi)
            out.loc[at, "lo"], out.loc[at, "hi"] = a, b
        return out.astype(float)

    return interval


def residual_udf(phi: float, stages, bound_orders: str = "all", above: bool = True):
    """Verdict and deciding stage for states that cheap stages left open.

    bound_orders "matched": the tight bounds use only moments that the fit matches, so all stages agree with it.
    """

    @F.pandas_udf("verdict boolean, stage string")
    def residual(st: pd.DataFrame, t: pd.Series) -> pd.DataFrame:
        verdict, stage = [None] * len(st), [None] * len(st)
        t = t.to_numpy(float)
        live = np.nonzero(_live(st))[0]
        fits = dict(zip(live, maxent.fit_batch(to_batch(st.iloc[live])))) if bound_orders == "matched" and len(live) else {}
        rest = live
        if "tight" in stages and len(live):
            lo, hi = _tight(st.iloc[live], t[live], orders=[(fits[i].k1, fits[i].k2) for i in live] if fits else None)
            decided = (lo > phi) | (hi < phi)
            for i, below in zip(live[decided], hi[decided] < phi):
                verdict[i], stage[i] = bool(below == above), "tight"
            rest = live[~decided]
        if len(rest):
            b = to_batch(st.iloc[rest])
            q = np.clip([fits[i].quantile(phi) for i in rest], b.lo, b.hi) if fits else maxent.quantiles(b, [phi])[0][:, 0]
            for i, v in zip(rest, q):
                verdict[i], stage[i] = bool(v > t[i] if above else v < t[i]), "maxent"
        return pd.DataFrame({"verdict": pd.Series(verdict, dtype=object), "stage": pd.Series(stage, dtype=object)})

    return residual
