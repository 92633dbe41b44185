"""Operators around the methods: metrics, filters, joins of cells with dimensions and time, ranks, windows, nested columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..summary import SummarySpec, merge_groups


def metric(df: DataFrame, expr: str, name: str = "x") -> DataFrame:
    """A metric computed from columns; only those are read."""
    return df.withColumn(name, F.expr(expr))


def where(df: DataFrame, equals: dict | None = None, within: dict | None = None, between: dict | None = None, like: dict | None = None, known: list[str] = ()) -> DataFrame:
    """Dimension filters that reach the scan: equality, IN, BETWEEN, LIKE, NOT NULL."""
    for c, v in (equals or {}).items():
        df = df.where(F.col(c) == F.lit(v))
    for c, vs in (within or {}).items():
        df = df.where(F.col(c).isin(*vs))
    for c, (a, b) in (between or {}).items():
        df = df.where(F.col(c).between(a, b))
    for c, v in (like or {}).items():
        df = df.where(F.col(c).like(v))
    for c in known:
        df = df.where(F.col(c).isNotNull())
    return df


def last_days(df: DataFrame, ts: str, days: int) -> DataFrame:
    """Rows of the last ``days`` days before the newest row; the newest time is one row, joined by broadcast."""
    newest = df.agg(F.max(ts).alias("__last"))
    return df.crossJoin(F.broadcast(newest)).where(F.col(ts) > F.col("__last") - F.expr(f"INTERVAL {int(days)} DAY")).drop("__last")


#: Rows of a dimension up to which it is broadcast.
SMALL_DIMENSION = 1_000_000


def with_dim(facts: DataFrame, dim: DataFrame, on: str, key: str, how: str = "inner", rows: int | None = None) -> DataFrame:
    """A dimension's columns for each fact or cell. Broadcast only if ``rows`` (the caller's bound on the dimension) is small; else Spark chooses by size."""
    side = F.broadcast(dim) if rows is not None and rows <= SMALL_DIMENSION else dim
    return facts.join(side, F.col(on) == F.col(key), how)


def join_large(left: DataFrame, right: DataFrame, on: Column, strategy: str = "merge", how: str = "inner") -> DataFrame:
    """A join of two large sides by sorting (merge) or hashing one shuffled side (shuffle_hash)."""
    return left.join(right.hint(strategy), on, how)


def merge_then_join(cells: DataFrame, on: str, dim: DataFrame, key: str, keep: list[str], spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Cells merged by foreign key meet the dimension, then merge again: rows of facts are never joined."""
    return merge_groups(merge_groups(cells, [on], spec).join(dim, F.col(on) == F.col(key)), keep, spec)


def on_calendar(panes: DataFrame, pane: str, first: int, last: int, zero: list[str]) -> DataFrame:
    """Every pane of [first, last]; counts of missing ones are 0, their other columns NULL."""
    return panes.sparkSession.range(first, last + 1).toDF(pane).join(panes, pane, "left").fillna(0, zero)


def rows_of(df: DataFrame, groups: DataFrame, keys: list[str], flagged: bool = True) -> DataFrame:
    """Rows of flagged groups (semi join), or of all others (anti join)."""
    return df.join(groups.select(*keys).distinct(), keys, "left_semi" if flagged else "left_anti")


def bucketize(df: DataFrame, x: Column, edges: list[float], name: str = "bucket") -> DataFrame:
    """Number of the half-open range [edges[i], edges[i + 1]) that holds x; rows outside are dropped. Arithmetic instead of a range join."""
    place = sum((F.when(x >= F.lit(float(e)), 1).otherwise(0) for e in edges), F.lit(0)) - 1
    return df.where((x >= F.lit(float(edges[0]))) & (x < F.lit(float(edges[-1])))).withColumn(name, place)


def within_spans(df: DataFrame, ts: str, spans: list[tuple]) -> DataFrame:
    """Rows in time spans (name, start, end as literals); a row in several spans comes once for each. Spans are few and stand in the plan."""
    hit = F.array(*[F.when((F.col(ts) >= F.lit(a).cast(df.schema[ts].dataType)) & (F.col(ts) < F.lit(b).cast(df.schema[ts].dataType)), F.lit(n)) for n, a, b in spans])
    return df.withColumn("span", F.explode(F.array_compact(hit)))


def as_of(df: DataFrame, by: list[str], order: str, value: Column, name: str) -> DataFrame:
    """The latest known ``value`` up to each row of its key: one sort for each key, no join."""
    return df.withColumn(name, F.last(value, ignorenulls=True).over(Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)))


def cardinality(df: DataFrame, by: list[str], xs: list[str], approximate: bool = False) -> DataFrame:
    """Different values of metrics in each group: the guard for populations too discrete for moments."""
    count = (lambda c: F.approx_count_distinct(c, 0.01)) if approximate else F.count_distinct
    return df.groupBy(*by).agg(*[count(c).cast("long").alias(f"distinct_{c}") for c in xs])


def pivot_counts(df: DataFrame, by: list[str], column: str, values: dict[str, str]) -> DataFrame:
    """Counts of given values of a column, one column each, with partial sums before the shuffle."""
    return df.groupBy(*by).agg(*[F.count(F.when(F.col(column) == v, 1)).alias(n) for v, n in values.items()])


def ranks(df: DataFrame, by: list[str], order: list[str], tiles: int = 4) -> DataFrame:
    """row_number, rank, dense_rank, ntile, percent_rank and cume_dist of each row in its group, from one sort."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.select("*", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(tiles).over(w).cast("long").alias("nt"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


def neighbours(df: DataFrame, by: list[str], order: str, value: str) -> DataFrame:
    """The value before, after and first in order."""
    w = Window.partitionBy(*by).orderBy(order)
    return df.select("*", F.lag(value).over(w).alias("before"), F.lead(value).over(w).alias("after"), F.first(value).over(w).alias("first"))


def frames(df: DataFrame, by: list[str], order: str, value: str, rows: int, reach: int) -> DataFrame:
    """The sum over the last ``rows`` rows and the number of rows within ``reach`` of the order."""
    w = Window.partitionBy(*by).orderBy(order)
    return df.select("*", F.sum(value).over(w.rowsBetween(1 - rows, 0)).alias("row_sum"), F.count(F.lit(1)).over(w.rangeBetween(-reach, 0)).alias("near"))


def topk(df: DataFrame, by: list[str], k: int, groups: list[str] = ()) -> DataFrame:
    """The k first rows in order (a heap in each task), or of each group."""
    if not groups:
        return df.orderBy(*by).limit(k)
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*groups).orderBy(*by))).where(F.col("__r") <= k).drop("__r")


def union_cubes(a: DataFrame, b: DataFrame, dims: list[str], spec: SummarySpec = SummarySpec()) -> DataFrame:
    """Cells of both cubes merged; rows of the same dimensions become one."""
    return merge_groups(a.unionByName(b), dims, spec)


def same_verdicts(a: DataFrame, b: DataFrame, but: DataFrame | None = None) -> DataFrame:
    """Rows in both, without those of ``but``."""
    both = a.intersect(b)
    return both if but is None else both.subtract(but)


def buckets_of(df: DataFrame, ts: str, unit: str) -> DataFrame:
    """Time bucket and days since 1990."""
    return df.withColumn("bucket", F.date_trunc(unit, F.col(ts))).withColumn("day", F.datediff(F.col(ts), F.lit("1990-01-01").cast("date")))


def url_parts(df: DataFrame, url: str, text: str) -> DataFrame:
    """Length of a text, the start of a URL in capitals and its host."""
    return df.select("*", F.length(text).cast("long").alias("n"), F.upper(F.substring(url, 1, 5)).alias("scheme"), F.regexp_extract(url, "//([^/]+)", 1).alias("host"))


def vector_norm(df: DataFrame, vector: str) -> DataFrame:
    """Dimension and squared length of an array column, folded in the engine."""
    add = lambda a, v: a + v.cast("double") * v.cast("double")
    return df.select("*", F.size(vector).alias("d"), F.aggregate(vector, F.lit(0.0), add).alias("norm"))


def as_map(df: DataFrame, key: str, value: str) -> DataFrame:
    """One row: a map from dimension value to number. For few dimension values."""
    return df.agg(F.map_from_entries(F.collect_list(F.struct(key, value))).alias("by"))


def json_dim(df: DataFrame, column: str, path: str, kind: str, name: str) -> DataFrame:
    """A dimension out of a JSON column."""
    return df.withColumn(name, F.get_json_object(column, path).cast(kind))


def sessions(df: DataFrame, by: str, ts: str, gap: str) -> DataFrame:
    """Sessions of each key: rows closer than ``gap`` belong together."""
    return df.groupBy(by, F.session_window(ts, gap).alias("session")).agg(F.count(F.lit(1)).alias("rows"))


def sliding(df: DataFrame, ts: str, width: str, step: str) -> DataFrame:
    """Native sliding windows: every row goes to width/step windows. Beyond small inputs use panes."""
    return df.groupBy(F.window(ts, width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "n")
