"""SQL surface: scalar functions over summary states and a macro that expands to aggregates."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession, functions as F

from .functions import maxent
from .functions.udfs import _tight, bounds_udf, cdf_udf, fits_of, info_udf, to_batch
from .functions.bounds import quantile_interval
from .summary import STATE, SummarySpec


def macro(x: str, k: int = 10, log: bool = True) -> str:
    """The SELECT fragment that accumulates a summary of ``x`` as one struct."""
    power = lambda b: [" * ".join([b] * i) for i in range(1, k + 1)]
    s = ", ".join(f"sum({p})" for p in power(f"({x})"))
    l = ", ".join(f"coalesce(sum({p}), 0D)" for p in power(f"ln(CASE WHEN ({x}) > 0 THEN ({x}) END)")) if log else ""  # noqa: E741
    ends = f"'xmin', CAST(min({x}) AS DOUBLE), 'xmax', CAST(max({x}) AS DOUBLE)"
    rest = "'shift', 0D, 'n_neg', CAST(NULL AS BIGINT), 'pmin', CAST(NULL AS DOUBLE), 'nmax', CAST(NULL AS DOUBLE), 'm', CAST(array() AS ARRAY<DOUBLE>)"
    return f"named_struct('n', count({x}), 'n_pos', count(CASE WHEN ({x}) > 0 THEN 1 END), {ends}, 's', array({s}), 'l', CAST(array({l}) AS ARRAY<DOUBLE>), {rest})"


def merge_text(a: str, b: str) -> str:
    """Merge of two states as a SQL expression: additions and comparisons, no Python."""
    add = lambda f: f"zip_with({a}.{f}, {b}.{f}, (x, y) -> x + y)"
    pick = lambda how, f: f"'{f}', {how}({a}.{f}, {b}.{f})"
    both = ", ".join([
        f"'n', {a}.n + {b}.n, 'n_pos', {a}.n_pos + {b}.n_pos", pick("least", "xmin"), pick("greatest", "xmax"), f"'s', {add('s')}",
        f"'l', CASE WHEN {a}.shift = {b}.shift THEN {add('l')} ELSE CAST(array() AS ARRAY<DOUBLE>) END, 'shift', {a}.shift, 'n_neg', {a}.n_neg + {b}.n_neg", pick("least", "pmin"), pick("greatest", "nmax"), f"'m', {add('m')}"])
    return f"CASE WHEN {a} IS NULL THEN {b} WHEN {b} IS NULL THEN {a} ELSE named_struct({both}) END"


def register(spark: SparkSession) -> None:
    """moment_quantile, moment_quantiles, moment_cdf, moment_exceeds, moment_bounds, moment_interval, moment_merge, moment_info, moment_cdf_curve."""

    @F.pandas_udf("array<double>")
    def quantiles(st: pd.DataFrame, phis: pd.Series) -> pd.Series:
        return pd.Series([None if f.status == "empty" else [float(np.clip(f.quantile(p), f.x[0], f.x[-1])) for p in ps] for f, ps in zip(fits_of(st), phis)])

    @F.pandas_udf("double")
    def quantile(st: pd.DataFrame, phi: pd.Series) -> pd.Series:
        return pd.Series([f.quantile(float(p)) for f, p in zip(fits_of(st), phi)])

    @F.pandas_udf("boolean")
    def exceeds(st: pd.DataFrame, phi: pd.Series, t: pd.Series) -> pd.Series:
        """Tight bounds first; only states that they leave open are fitted. NULL for an empty state."""
        out: list = [None] * len(st)
        live = np.nonzero((st["n"].fillna(0) > 0).to_numpy())[0]
        if len(live):
            own, p, at = st.iloc[live], phi.to_numpy(float)[live], t.to_numpy(float)[live]
            low, high = _tight(own, at)
            rest = np.nonzero((low <= p) & (high >= p))[0]
            for i, v in zip(live, high < p):
                out[i] = bool(v)
            if len(rest):
                b = to_batch(own.iloc[rest])
                for i, f in zip(rest, maxent.fit_batch(b)):
                    out[live[i]] = bool(f.quantile(p[i]) > at[i])
        return pd.Series(out, dtype=object)

    @F.pandas_udf("lo double, hi double")
    def interval(st: pd.DataFrame, phi: pd.Series) -> pd.DataFrame:
        out = pd.DataFrame({"lo": np.full(len(st), np.nan), "hi": np.full(len(st), np.nan)})
        at = np.nonzero((st["n"].fillna(0) > 0).to_numpy())[0]
        for p in np.unique(phi.to_numpy(float)[at]):
            own = at[phi.to_numpy(float)[at] == p]
            part = st.iloc[own]
            out.loc[own, "lo"], out.loc[own, "hi"] = quantile_interval(lambda v: _tight(part, v), part["xmin"].to_numpy(float), part["xmax"].to_numpy(float), p)  # noqa: B023
        return out

    @F.udtf(returnType="x double, share double")
    class Curve:
        def eval(self, st, points: int):
            f = fits_of(pd.DataFrame([st.asDict()]))[0]
            for x in np.linspace(f.x[0], f.x[-1], points):
                yield float(x), f.rank(float(x)) if len(f.x) > 1 else 1.0

    named = (("moment_quantiles", quantiles), ("moment_quantile", quantile), ("moment_exceeds", exceeds), ("moment_cdf", cdf_udf()), ("moment_bounds", bounds_udf()), ("moment_interval", interval), ("moment_info", info_udf()))
    for name, f in named:
        spark.udf.register(name, f)
    spark.udtf.register("moment_cdf_curve", Curve)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION moment_merge(a {STATE}, b {STATE}) RETURNS {STATE} RETURN {merge_text('a', 'b')}")


__all__ = ["SummarySpec", "macro", "merge_text", "register"]
