"""Quantile and threshold queries over summaries; the cascade; outlier-rate search."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, functions as F

from ..functions import bounds
from ..functions.udfs import quantiles_udf, residual_udf
from ..summary import SummarySpec, as_struct, merge, merge_groups
from . import exact

STAGES = ("range", "markov", "tight", "maxent")


def _spread(df: DataFrame, parallel: int | None) -> DataFrame:
    """Estimation is heavy work on few bytes, which adaptive coalescing would put into one task."""
    return df.repartition(parallel) if parallel else df


def single(cube: DataFrame, phi: float | list[float], spec: SummarySpec = SummarySpec(), where: Column | None = None, **how) -> DataFrame:
    """Quantile(s) of one filtered population: filter and column pruning reach the scan, then one global merge and one fit."""
    return by_group(cube if where is None else cube.where(where), [], phi, spec, **how)


def by_group(cube: DataFrame, dims: list[str], phi: float | list[float], spec: SummarySpec = SummarySpec(), parallel: int | None = None, **how) -> DataFrame:
    """Merge by dimensions and estimate; ``q`` is a double for one phi, an array for several."""
    phis = phi if isinstance(phi, (list, tuple)) else [phi]
    groups = _spread(merge_groups(cube, dims, spec), parallel)
    out = groups.withColumn("q", quantiles_udf(phis, **how)(as_struct(spec)))
    return out if isinstance(phi, (list, tuple)) else out.withColumn("q", F.col("q")[0])


def direct(groups: DataFrame, phi: float, t: Column, spec: SummarySpec = SummarySpec(), parallel: int | None = None, op: str = ">") -> DataFrame:
    """Threshold by an estimate for every group: the baseline of the cascade. op: > or <."""
    q = quantiles_udf([phi])(as_struct(spec))[0]
    out = _spread(groups, parallel).withColumn("q", q)
    return out.withColumn("verdict", F.col("q") > t if op == ">" else F.col("q") < t)


def cascade(groups: DataFrame, phi: float, t: Column, spec: SummarySpec = SummarySpec(), stages=STAGES, bound_orders: str = "all", parallel: int | None = None, op: str = ">") -> DataFrame:
    """Is the phi-quantile of each group above (op >) or below (op <) t? Adds verdict and the stage that decided.

    Range and Markov checks are code-generated columns. Only groups that they leave open go on to Python, spread over ``parallel`` tasks (a
    few bytes each, which adaptive coalescing would put into one task): tight bounds, then a fit. Which groups are settled is found before the
    exchange that both branches read, and travels in it: sums of doubles depend on the order in which blocks arrive, so two branches that found
    it apart could both take a group, or both leave it out. The one-row generator keeps filters and pruning of one branch above that exchange.
    bound_orders "matched": bounds use only moments that the fit matches (found by fitting), for strict agreement.
    An empty group, or one with a NULL threshold, has the verdict NULL.
    """
    above = op == ">"
    kept = groups.columns
    df = groups.withColumn("__t", t.cast("double"))
    none = F.lit(None).cast("boolean")
    if "markov" in stages and bound_orders == "all":
        df = bounds.with_markov(df, spec, F.col("__t")).withColumn("__m", bounds.bound_verdict(F.col("__lo"), F.col("__hi"), phi, above))
    else:
        df = df.withColumn("__m", none)
    df = df.withColumn("__r", bounds.range_verdict(F.col("xmin"), F.col("xmax"), F.col("__t"), above) if "range" in stages else none)
    settled = F.col("__r").isNotNull() | F.col("__m").isNotNull() | (F.col("n") == 0) | F.col("__t").isNull()
    stage = F.when(F.col("__r").isNotNull(), "range").when(F.col("__m").isNotNull(), "markov")
    whole = F.struct(*kept, "__t", F.coalesce("__r", "__m").alias("__v"), stage.alias("__by"), F.coalesce(settled, F.lit(True)).alias("__settled"))
    tasks = parallel or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.select(F.array(whole).alias("__row")).repartition(tasks).select(F.inline("__row"))
    closed = dealt.where("__settled").select(*kept, F.col("__v").alias("verdict"), F.col("__by").alias("stage"))
    judged = dealt.where("NOT __settled").withColumn("__p", residual_udf(phi, tuple(stages), bound_orders, above)(as_struct(spec), F.col("__t")))
    return closed.unionByName(judged.select(*kept, F.col("__p.verdict").alias("verdict"), F.col("__p.stage").alias("stage")))


def exceeds(state: Column, phi: float, t: Column, op: str = ">") -> Column:
    """The predicate q_phi > t (or < t) of one state, all stages in one function: for states outside a group-by."""
    return residual_udf(phi, STAGES, above=op == ">")(state, t.cast("double"))["verdict"]


def relative(cube: DataFrame, dims: list[str], phi_group: float, phi_global: float, spec: SummarySpec = SummarySpec(), **how) -> DataFrame:
    """Groups whose quantile exceeds a global one. The threshold is one row, joined by broadcast without a trip to the driver."""
    limit = single(cube, phi_global, spec).select(F.col("q").alias("t"))
    return cascade(merge_groups(cube, dims, spec).crossJoin(F.broadcast(limit)), phi_group, F.col("t"), spec, **how)


def outlier_search(cube: DataFrame, dims: list[str], p: float = 0.01, ratio: float = 30, spec: SummarySpec = SummarySpec(), single_values: bool = False, **how) -> DataFrame:
    """Groups whose rate of values above the overall (1-p)-quantile is at least ratio * p, as q_{1 - ratio p} > t.

    single_values: every value of every single dimension is a group (columns dimension, value); else their combinations are.
    """
    limit = single(cube, 1 - p, spec).select(F.col("q").alias("t"))
    if single_values:
        cube = cube.withColumn("__d", F.explode(F.array(*[F.struct(F.lit(d).alias("dimension"), F.col(d).cast("string").alias("value")) for d in dims])))
        groups = cube.groupBy(F.col("__d.dimension"), F.col("__d.value")).agg(*merge(spec))
    else:
        groups = merge_groups(cube, dims, spec)
    return cascade(groups.crossJoin(F.broadcast(limit)), 1 - ratio * p, F.col("t"), spec, **how)


def checked_outlier_search(cube: DataFrame, df: DataFrame, dims: list[str], metric: Column, p: float = 0.01, ratio: float = 30, spec: SummarySpec = SummarySpec(), **how) -> DataFrame:
    """dims, n, above of exactly the groups whose rate of values above the overall (1-p)-quantile is over ratio * p; ``df`` has the rows behind ``cube``.

    Estimates near the threshold can fall on either side of it. So the overall quantile is selected from the rows, bounds on the groups' moments
    rule out what they prove, and the rows of every other group (found by the search, left to an estimate, or with the threshold as its least
    value, of which bounds on ranks below it say nothing) are counted.
    """
    rows = df.select(*dims, metric.cast("double").alias("__x"))
    limit = exact.by_selection(rows, F.col("__x"), round(1000 * (1 - p))).select(F.col("q").alias("t"))
    judged = cascade(merge_groups(cube, dims, spec).crossJoin(F.broadcast(limit)), 1 - ratio * p, F.col("t"), spec, **how)
    possible = judged.where(F.col("verdict") | (F.col("stage") == "maxent") | (F.col("xmin") == F.col("t"))).select(*[F.col(d).alias(f"__{d}") for d in dims], "n", "t")
    same = F.lit(True)
    for d in dims:
        same = same & F.col(d).eqNullSafe(F.col(f"__{d}"))
    counts = rows.join(possible, same).groupBy(*dims, "n").agg(F.count_if(F.col("__x") > F.col("t")).alias("above"))
    return counts.where(F.col("above") > F.lit(Decimal(str(ratio)) * Decimal(str(p))) * F.col("n"))


def by_counts(df: DataFrame, dims: list[str], metric: Column, t: Column) -> DataFrame:
    """The optimistic rival: exact counts above a known threshold."""
    return df.groupBy(*dims).agg(F.count(metric).alias("n"), F.count_if(metric > t).alias("above"))
