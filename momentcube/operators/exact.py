"""Exact quantiles and error measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

PHIS = tuple(10 + 49 * i for i in range(21))  # 21 equally spaced fractions, in thousandths


def by_sort(df: DataFrame, x: Column, phi_milli: int, by: list[str] = (), bins: int | None = None) -> DataFrame:
    """The item of 0-based rank floor(phi n) of each group, by sorting.

    A sample sort: equal values are counted first (map-side), so no tie is a hot key; splitters (one number for each shuffle partition
    reach the driver) deal the values to ranges; each range of a group is sorted on its own, and counts of ranges give the offsets.
    """
    rows = df.select(*by, x.cast("double").alias("x")).where("x is not null")
    bins = bins or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = sorted(set(rows.agg(F.percentile_approx("x", [i / bins for i in range(1, bins)], 2000)).first()[0] or [])) if bins > 1 else []
    place = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c <= F.col("x"))) if cuts else F.lit(0)
    values = rows.groupBy(*by, "x").agg(F.count(F.lit(1)).alias("many")).withColumn("bin", place)
    sizes = values.groupBy(*by, "bin").agg(F.sum("many").alias("size"))
    group = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))  # as many rows as ranges
    starts = sizes.withColumn("n", F.sum("size").over(group)).withColumn("start", F.sum("size").over(group.orderBy("bin")) - F.col("size"))
    keys = [*by, "bin"]
    starts = starts.select(*[F.col(c).alias(f"__{c}") for c in keys], "n", "start")
    same = F.lit(True)
    for c in keys:
        same = same & F.col(c).eqNullSafe(F.col(f"__{c}"))
    ranked = values.join(starts, same).withColumn("upto", F.col("start") + F.sum("many").over(Window.partitionBy(*keys).orderBy("x")))
    goal = F.least(F.expr(f"{phi_milli} * n div 1000"), F.col("n") - 1)
    return ranked.where((F.col("upto") > goal) & (F.col("upto") - F.col("many") <= goal)).select(*by, "n", F.col("x").alias("q"))


def by_selection(df: DataFrame, x: Column, phi_milli: int, most: int = 1_000_000) -> DataFrame:
    """The same item of the whole table without a sort: passes narrow the range of values until at most ``most`` rows, or one value, are left.

    A pass brackets the wanted rank by approximate quantiles of the rows in range and counts what lies below and inside, so long
    tails narrow as fast as flat data. Only counts and two ends reach the driver.
    """
    rows = df.select(x.cast("double").alias("x")).where("x is not null")
    n, lo, hi = rows.agg(F.count("x"), F.min("x"), F.max("x")).first()
    schema = "n long, q double"
    if not n:
        return df.sparkSession.createDataFrame([], schema)
    goal = min(phi_milli * n // 1000, n - 1)
    skip, many, reach = 0, n, 5e-4
    while many > most and lo < hi:
        at = (goal - skip + 0.5) / many
        inside = rows.where((F.col("x") >= lo) & (F.col("x") <= hi))
        a, b = inside.agg(F.percentile_approx("x", [max(0.0, at - reach), min(1.0, at + reach)], 10_000)).first()[0]
        below, upto = rows.agg(F.count(F.when(F.col("x") < a, 1)), F.count(F.when(F.col("x") <= b, 1))).first()
        if below <= goal < upto and (a, b) != (lo, hi):
            lo, hi, skip, many = a, b, below, upto - below
        elif reach > 1:
            break
        else:
            reach *= 4
    if lo == hi:
        return df.sparkSession.createDataFrame([(n, lo)], schema)
    last = rows.where((F.col("x") >= lo) & (F.col("x") <= hi)).groupBy("x").agg(F.count(F.lit(1)).alias("many"))
    upto = last.withColumn("upto", F.sum("many").over(Window.partitionBy(F.lit(0)).orderBy("x")) + skip)
    return upto.where((F.col("upto") > goal) & (F.col("upto") - F.col("many") <= goal)).select(F.lit(n).cast("long").alias("n"), F.col("x").alias("q"))


def rank_error(df: DataFrame, x: Column, q: Column, phi_milli: int) -> DataFrame:
    """|#{x < q} - floor(phi n)| / n."""
    return df.agg(F.count(x).alias("n"), F.count_if(x < q).alias("below")).withColumn("eps", F.abs(F.col("below") - F.expr(f"{phi_milli} * n div 1000")) / F.col("n"))


def is_eps_approx(df: DataFrame, x: Column, q: Column, phi_milli: int, eps: float) -> DataFrame:
    """Is q an eps-approximate quantile: does its rank lie within (phi +- eps) n?"""
    return rank_error(df, x, q, phi_milli).withColumn("is_eps_approx", F.col("eps") <= F.lit(eps))


def avg_error(df: DataFrame, x: Column, estimates: DataFrame, column: str = "q") -> DataFrame:
    """Average and largest rank error over 21 fractions, in one pass; ``estimates`` is one row with an array."""
    return avg_errors(df, x, estimates.select(F.lit(0).alias("one"), F.col(column).alias("q")), ["one"]).drop("one")


def avg_errors(df: DataFrame, x: Column, estimates: DataFrame, names: list[str]) -> DataFrame:
    """Average and largest rank error of several estimates (rows of ``names`` and an array q, as many as were asked for) of one population.

    Equal values are counted first. Each estimate's fractions are counted by the same pass over them.
    """
    values = df.select(x.cast("double").alias("x")).where("x is not null").groupBy("x").agg(F.count(F.lit(1)).alias("many"))
    rows = values.crossJoin(F.broadcast(estimates.select(*names, F.col("q").alias("__q"))))
    below = rows.groupBy(*names).agg(F.sum("many").alias("n"), *[F.sum(F.when(F.col("x") < F.col("__q")[i], F.col("many")).otherwise(0)).alias(f"b{i}") for i in range(len(PHIS))])
    errors = F.array(*[F.abs(F.col(f"b{i}") - F.expr(f"{m} * n div 1000")) / F.col("n") for i, m in enumerate(PHIS)])
    return below.select(*names, "n", (F.aggregate(errors, F.lit(0.0), lambda a, e: a + e) / len(PHIS)).alias("eps_avg"), F.array_max(errors).alias("eps_max"))


def profile(df: DataFrame, x: Column) -> DataFrame:
    """Size, extremes, mean, standard deviation and population skew."""
    v = df.select(x.cast("double").alias("x")).where("x is not null")
    m = v.agg(F.count("x").alias("n"), F.min("x").alias("xmin"), F.max("x").alias("xmax"), F.avg("x").alias("mean"), F.stddev_pop("x").alias("sd"), F.skewness("x").alias("skew"))
    return m
