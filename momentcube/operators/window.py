"""Panes and sliding windows of summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..summary import SummarySpec, summarise
from .query import cascade


def panes(df: DataFrame, ts: str, metric: Column, spec: SummarySpec = SummarySpec(), seconds: int = 600, by: list[str] = ()) -> DataFrame:
    """Tumbling panes numbered from the epoch (UTC)."""
    index = F.floor(F.unix_seconds(F.col(ts).cast("timestamp")) / seconds).cast("long").alias("pane")
    return summarise(df, metric, [*by, index], spec)


def dense(p: DataFrame, first: int, last: int, spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Every pane of [first, last], empty ones included."""
    calendar = p.sparkSession.range(first, last + 1).toDF("pane")
    zero = {c: 0 for c in spec.sums if c in p.columns}
    return calendar.join(p, "pane", "left").fillna(zero)


def slide(p: DataFrame, width: int, spec: SummarySpec = SummarySpec(), mode: str = "remerge", by: list[str] = (), block: int = 1024) -> DataFrame:
    """Windows of ``width`` panes ending at each dense pane; ``full`` tells whether the series began early enough.

    The series is cut into blocks that also hold the width - 1 panes before them, so windows of one long series run on
    many tasks. remerge adds the panes of each frame; turnstile takes differences of running sums inside a block (restarted
    there, which bounds the cancellation a past spike leaves); extremes can't be undone and come from the frame.
    """
    block = max(block, 4 * width)  # a window never reaches beyond the block before its own
    own = F.expr(f"pane div {block}")
    copies = F.when(F.expr(f"pane % {block} >= {block - width + 1}"), F.array(own, own + 1)).otherwise(F.array(own))
    halo = p.withColumn("__block", F.explode(copies))
    w = Window.partitionBy(*by, "__block").orderBy("pane")
    frame = w.rowsBetween(-(width - 1), 0)
    ends = [(F.min(c) if c in ("xmin", "pmin") else F.max(c)).over(frame).alias(c) for c in spec.columns if c not in spec.sums]
    have = F.count(F.lit(1)).over(frame).alias("__have")
    if mode == "remerge":
        out = halo.select(*by, "pane", "__block", have, *[F.sum(c).over(frame).alias(c) for c in spec.sums], *ends)
    else:
        run = w.rowsBetween(Window.unboundedPreceding, 0)
        wide = halo.select(*by, "pane", "__block", have, *[F.sum(c).over(run).alias(c) for c in spec.sums], *ends)
        left = lambda c: F.col(c) - F.coalesce(F.lag(c, width).over(w), F.lit(0))
        out = wide.select(*by, "pane", "__block", "__have", *[left(c).alias(c) for c in spec.sums], *[c for c in spec.columns if c not in spec.sums])
    return out.where(F.col("__block") == own).withColumn("full", F.col("__have") == width).drop("__block", "__have")


def alert(windows: DataFrame, phi: float, t: Column, spec: SummarySpec = SummarySpec(), **how) -> DataFrame:
    return cascade(windows.where("full"), phi, t, spec, **how)
