"""Uniform shuffle into shards of exact size by a hypergeometric communication matrix; DataFrame functions only.

Rows are dealt to logical partitions by a hash of their content. The counts that each partition sends to each shard
are drawn exactly: row sums are the partitions' counts, column sums the shards' sizes (counts at most one apart).
Rows are permuted within their partition by a second hash, cut by the drawn counts, exchanged, and permuted again
within their shard in sub-buckets, of which the counts give offsets, so no task sorts a whole shard.

Equal rows are told apart by an occurrence number, so they are shuffled like any others. A group of equal rows is numbered in spread
parts (a part for each logical partition, at most), of which the counts give offsets, so no task holds a hot group.

Null text: size 1, crc32 0. Repeated rows are rows of their own; an empty table gives an empty table; other columns than doc_id and text are
not looked at. The result depends on the rows and the seed only. One count for each logical partition (50,000 rows) reaches the
driver, which draws 16 numbers for it: 200,000 counts and 3.2 million draws at 10^10 rows. Equal texts are not kept together under this law.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, functions as F

from .common import materialize


def hypergeometric(rng: np.random.Generator, good: int, bad: int, sample: int) -> int:
    """Exact draw; numpy's up to its bound on the population, beyond it inversion outwards from the mode."""
    if good + bad < 1_000_000_000:
        return int(rng.hypergeometric(good, bad, sample))
    low, high = max(0, sample - bad), min(sample, good)
    lc = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    p = lambda k: math.exp(lc(good, k) + lc(bad, sample - k) - lc(good + bad, sample))
    down = up = min(high, max(low, (sample + 1) * (good + 1) // (good + bad + 2)))
    u = rng.random() - p(up)
    at = up
    while u > 0 and (down > low or up < high):
        if up < high:
            up, at = up + 1, up + 1
            u -= p(up)
        if u > 0 and down > low:
            down, at = down - 1, down - 1
            u -= p(down)
    return at


def communication_matrix(sent: list[int], shards: int, seed: int) -> list[list[int]]:
    """Counts [partition][shard] with these row sums and column sums at most one apart, as a uniform shuffle has them."""
    rng = np.random.default_rng(seed)
    n = sum(sent)
    room = [n // shards + (s < n % shards) for s in range(shards)]
    out = []
    for count in sent:
        row, left, ahead = [], count, sum(room)
        for s in range(shards):
            ahead -= room[s]
            k = hypergeometric(rng, room[s], ahead, left) if left and room[s] and ahead else min(left, room[s])
            row.append(k)
            left -= k
        room = [a - b for a, b in zip(room, row)]
        out.append(row)
    return out


def shard_rows(docs: DataFrame, shards: int = 16, seed: int = 11, per_partition: int = 50_000) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row."""
    spark = docs.sparkSession
    raw = F.col("text").cast("binary")
    keys = docs.select("doc_id", F.coalesce(F.octet_length("text") + 1, F.lit(1)).cast("long").alias("size"), F.coalesce(F.crc32(raw), F.lit(0)).cast("long").alias("text_crc32"))
    keys = materialize(keys.withColumn("h", F.xxhash64(F.lit(seed), "doc_id", "text_crc32", "size")).withColumn("salt", F.monotonically_increasing_id()))
    n = keys.count()
    parts = max(1, -(-n // per_partition))
    keys = keys.withColumn("salt", F.pmod("salt", F.lit(parts)).cast("int"))
    seen = keys.groupBy("h", "salt").agg(F.count(F.lit(1)).alias("many"))
    before = seen.selectExpr("h", "salt", "sum(many) over (partition by h order by salt rows between unbounded preceding and 1 preceding) as before").where("before > 0")
    numbered = keys.selectExpr("*", "row_number() over (partition by h, salt order by doc_id, text_crc32, size) - 1 as own").join(before, ["h", "salt"], "left")
    # a hash of row and occurrence: from here on every row is a different one
    keyed = materialize(numbered.select("doc_id", "size", "text_crc32", F.xxhash64(F.lit(seed + 3), "h", F.coalesce("before", F.lit(0)) + F.col("own")).alias("h")).withColumn("part", F.pmod("h", F.lit(parts)).cast("int")))
    counts = {r["part"]: r["many"] for r in keyed.groupBy("part").agg(F.count(F.lit(1)).alias("many")).collect()}
    matrix = communication_matrix([counts.get(p, 0) for p in range(parts)], shards, seed)
    cuts = spark.createDataFrame([(p, np.cumsum(row).tolist()) for p, row in enumerate(matrix)], "part int, cuts array<long>")
    local = keyed.withColumn("turn", F.xxhash64(F.lit(seed + 1), "h"))
    local = local.selectExpr("*", "row_number() over (partition by part order by turn, doc_id, text_crc32, size) - 1 as r").join(cuts, "part")
    sent = local.selectExpr("doc_id", "size", "text_crc32", "h", "size(filter(cuts, c -> c <= r)) as shard")
    subs = max(1, parts // shards)
    again = materialize(sent.withColumn("turn", F.xxhash64(F.lit(seed + 2), "h")).withColumn("sub", F.pmod("turn", F.lit(subs)).cast("int")))
    starts = again.groupBy("shard", "sub").agg(F.count(F.lit(1)).alias("many")).selectExpr("shard", "sub", "coalesce(sum(many) over (partition by shard order by sub rows between unbounded preceding and 1 preceding), 0) as start")
    placed = again.selectExpr("*", "row_number() over (partition by shard, sub order by turn, doc_id, text_crc32, size) - 1 as r").join(starts, ["shard", "sub"])
    return placed.selectExpr("doc_id", "size", "text_crc32", "'rows' as law", "cast(shard as int) as shard", "cast(start + r as long) as slot", "cast(null as int) as grown_shard")
