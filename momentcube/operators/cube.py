"""Cubes of summaries: build, cells by sequence, roll-ups, dyadic ranges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..summary import SummarySpec, accumulate, clean, merge, merge_groups, summarise


def build(df: DataFrame, dims: list[str], metric: Column, spec: SummarySpec = SummarySpec(), bucket: Column | None = None) -> DataFrame:
    """One summary for each combination of dimension values and time bucket; one scan, partial sums before the shuffle."""
    by = [*dims, *([bucket.alias("bucket")] if bucket is not None else [])]
    return summarise(df, metric, by, spec)


def cells(df: DataFrame, seq: Column, size: int, metric: Column, spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Cells of ``size`` consecutive values by a sequence number that the rows carry (no global sort)."""
    return summarise(df, metric, [F.floor(seq / size).cast("long").alias("cell")], spec)


def rollup(cube: DataFrame, keep: list[str], spec: SummarySpec = SummarySpec()) -> DataFrame:
    return merge_groups(cube, keep, spec)


def grouping_sets(cube: DataFrame, sets: list[list[str]], spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Several roll-ups in one pass; dimensions that a set leaves out are NULL."""
    dims = sorted({d for s in sets for d in s})
    return cube.groupingSets([[F.col(d) for d in s] for s in sets], *dims).agg(*merge(spec))


def all_sets(cube: DataFrame, dims: list[str], spec: SummarySpec = SummarySpec()) -> DataFrame:
    return cube.cube(*dims).agg(*merge(spec))


def dyadic(panes: DataFrame, index: str, levels: int, spec: SummarySpec = SummarySpec(), by: list[str] = ()) -> DataFrame:
    """Pre-merged blocks of 2^level panes for every level: any range of panes is then a logarithmic number of merges."""
    up = panes.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(levels)))).withColumn("block", F.expr(f"shiftright({index}, level)"))
    return merge_groups(up, [*by, "level", "block"], spec)


def dyadic_cover(first: int, last: int, levels: int) -> list[tuple[int, int]]:
    """(level, block) pairs that tile [first, last)."""
    out = []
    while first < last:
        level = min(levels, (first & -first).bit_length() - 1 if first else levels)
        while first + (1 << level) > last:
            level -= 1
        out.append((level, first >> level))
        first += 1 << level
    return out


def range_merge(blocks: DataFrame, first: int, last: int, levels: int, spec: SummarySpec = SummarySpec(), by: list[str] = ()) -> DataFrame:
    cover = dyadic_cover(first, last, levels)
    wanted = F.lit(False)
    for level in sorted({a for a, _ in cover}):
        wanted = wanted | ((F.col("level") == level) & F.col("block").isin([b for a, b in cover if a == level]))
    return merge_groups(blocks.where(wanted), list(by), spec)


def merge_then_join(fact: DataFrame, key: str, metric: Column, dimension: DataFrame, on: str, keep: list[str], spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Eager aggregation: summaries by foreign key first, then the dimension joins few rows, then a second merge."""
    per_key = fact.withColumn("__x", clean(metric)).groupBy(key).agg(*accumulate(F.col("__x"), spec))
    return merge_groups(per_key.join(dimension, F.col(key) == F.col(on)), keep, spec)
