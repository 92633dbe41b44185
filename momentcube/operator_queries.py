"""A query for every operator of ``operators.ops``, with SQL written apart from it."""

from __future__ import annotations

from pyspark.sql import functions as F

from .catalog import events_cube, lineitem_cube, query_key, shown, sql_roots, S4
from .operators import cube, ops
from .sources.tables import load


def _key(name: str, sql: str):
    return query_key(sql, f"ops_{name}")


@_key("metric", "SELECT l_returnflag, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY l_returnflag")
def _(spark, sf):
    return ops.metric(load(spark, sf, "lineitem"), "l_extendedprice * (1 - l_discount)").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("x"), 2).alias("revenue"))


@_key("filter", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderpriority LIKE '1-%' AND o_totalprice BETWEEN 1000 AND 400000 AND o_orderstatus IN ('O', 'F') AND o_custkey IS NOT NULL GROUP BY o_orderstatus")
def _(spark, sf):
    kept = ops.where(load(spark, sf, "orders"), within={"o_orderstatus": ["O", "F"]}, between={"o_totalprice": (1000.0, 400000.0)}, like={"o_orderpriority": "1-%"}, known=["o_custkey"])
    return kept.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@_key("last_days", "SELECT event_type, count(*) AS n FROM events WHERE ts > (SELECT max(ts) FROM events) - INTERVAL 7 DAY GROUP BY event_type")
def _(spark, sf):
    return ops.last_days(load(spark, sf, "events"), "ts", 7).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@_key("join_dim", "SELECT n_name, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def _(spark, sf):
    own = ops.with_dim(load(spark, sf, "lineitem"), load(spark, sf, "supplier"), "l_suppkey", "s_suppkey")
    return ops.with_dim(own, load(spark, sf, "nation"), "s_nationkey", "n_nationkey", rows=200).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@_key("join_smj", "SELECT o_orderstatus, count(*) AS n, max(l_extendedprice) AS most FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
def _(spark, sf):
    both = ops.join_large(load(spark, sf, "lineitem"), load(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.max("l_extendedprice").alias("most"))


@_key("join_shj", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(spark, sf):
    both = ops.join_large(load(spark, sf, "orders"), load(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"), "shuffle_hash")
    return both.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@_key("eager_join", f"SELECT s_nationkey, {sql_roots('l_extendedprice', 4)} FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey")
def _(spark, sf):
    return shown(ops.merge_then_join(lineitem_cube(spark, sf, S4), "l_suppkey", load(spark, sf, "supplier"), "s_suppkey", ["s_nationkey"], S4), ["s_nationkey"], S4)


@_key("outer", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def _(spark, sf):
    return ops.with_dim(load(spark, sf, "customer"), load(spark, sf, "orders"), "c_custkey", "o_custkey", "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@_key("calendar", "SELECT CAST(h AS BIGINT) AS hour, count(e.event_id) AS n FROM range(720) d(h) LEFT JOIN events e ON CAST(floor((epoch(e.ts) - 1704067200) / 3600) AS BIGINT) = d.h GROUP BY d.h")
def _(spark, sf):
    hours = load(spark, sf, "events").groupBy(F.floor((F.unix_seconds(F.col("ts").cast("timestamp")) - 1704067200) / 3600).cast("long").alias("hour")).agg(F.count(F.lit(1)).alias("n"))
    return ops.on_calendar(hours, "hour", 0, 719, ["n"])


def _loud(spark, sf):
    return load(spark, sf, "events").where("value > 250")


@_key("semi", "SELECT count(*) AS n FROM events WHERE user_id IN (SELECT user_id FROM events WHERE value > 250)")
def _(spark, sf):
    return ops.rows_of(load(spark, sf, "events"), _loud(spark, sf), ["user_id"]).agg(F.count(F.lit(1)).alias("n"))


@_key("anti", "SELECT count(*) AS n FROM events WHERE user_id NOT IN (SELECT user_id FROM events WHERE value > 250)")
def _(spark, sf):
    return ops.rows_of(load(spark, sf, "events"), _loud(spark, sf), ["user_id"], flagged=False).agg(F.count(F.lit(1)).alias("n"))


@_key("range_join", "SELECT b AS bucket, count(*) AS n FROM orders JOIN (VALUES (0, 0, 100000), (1, 100000, 250000), (2, 250000, 1000000)) h(b, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY b")
def _(spark, sf):
    return ops.bucketize(load(spark, sf, "orders"), F.col("o_totalprice"), [0, 100000, 250000, 1000000]).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


@_key("interval_join", "SELECT s AS span, count(*) AS n FROM events JOIN (VALUES (1, TIMESTAMP '2024-01-10 06:00:00', TIMESTAMP '2024-01-10 08:00:00'), (2, TIMESTAMP '2024-01-10 07:00:00', TIMESTAMP '2024-01-20 16:00:00')) v(s, a, b) ON ts >= a AND ts < b GROUP BY s")
def _(spark, sf):
    spans = [(1, "2024-01-10 06:00:00", "2024-01-10 08:00:00"), (2, "2024-01-10 07:00:00", "2024-01-20 16:00:00")]
    return ops.within_spans(load(spark, sf, "events"), "ts", spans).groupBy("span").agg(F.count(F.lit(1)).alias("n"))


@_key("asof", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events")
def _(spark, sf):
    bought = F.when(F.col("event_type") == "purchase", F.col("value"))
    return ops.as_of(load(spark, sf, "events"), ["user_id"], "event_id", bought, "last_purchase").select("event_id", "last_purchase")


@_key("distinct", "SELECT l_returnflag, count(DISTINCT l_tax) AS distinct_l_tax, count(DISTINCT l_quantity) AS distinct_l_quantity FROM lineitem GROUP BY l_returnflag")
def _(spark, sf):
    return ops.cardinality(load(spark, sf, "lineitem"), ["l_returnflag"], ["l_tax", "l_quantity"])


@_key("rollup", f"SELECT l_returnflag, l_linestatus, {sql_roots('l_extendedprice', 4)} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _(spark, sf):
    return shown(cube.grouping_sets(lineitem_cube(spark, sf, S4), [["l_returnflag", "l_linestatus"], ["l_returnflag"], []], S4), ["l_returnflag", "l_linestatus"], S4)


@_key("cube", f"SELECT l_returnflag, l_linestatus, {sql_roots('l_extendedprice', 4)} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(spark, sf):
    return shown(cube.all_sets(lineitem_cube(spark, sf, S4), ["l_returnflag", "l_linestatus"], S4), ["l_returnflag", "l_linestatus"], S4)


@_key("pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'error') AS errors FROM events GROUP BY user_id")
def _(spark, sf):
    return ops.pivot_counts(load(spark, sf, "events"), ["user_id"], "event_type", {"click": "clicks", "error": "errors"})


@_key("ranks", "SELECT o_orderkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)")
def _(spark, sf):
    return ops.ranks(load(spark, sf, "orders"), ["o_orderpriority"], ["o_totalprice", "o_orderkey"]).select("o_orderkey", "rn", "rk", "dr", "nt", F.round("pr", 6).alias("pr"), F.round("cd", 6).alias("cd"))


@_key("lag", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def _(spark, sf):
    return ops.neighbours(load(spark, sf, "events"), ["user_id"], "event_id", "value").select("event_id", "before", "after", "first")


@_key("frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 4) AS row_sum, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near FROM events")
def _(spark, sf):
    return ops.frames(load(spark, sf, "events"), ["user_id"], "event_id", "value", 5, 500).select("event_id", F.round("row_sum", 4).alias("row_sum"), "near")


@_key("topk", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def _(spark, sf):
    return ops.topk(load(spark, sf, "documents").select("doc_id", "n_chars"), [F.desc("n_chars"), F.asc("doc_id")], 20)


@_key("topk_per_group", "SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def _(spark, sf):
    return ops.topk(load(spark, sf, "documents").select("source", "doc_id", "n_chars"), [F.desc("n_chars"), F.asc("doc_id")], 3, ["source"])


@_key("union", f"SELECT event_type, {sql_roots('value', 4)} FROM events GROUP BY event_type")
def _(spark, sf):
    c = events_cube(spark, sf, S4)
    return shown(ops.union_cubes(c.where("user_id % 3 = 0"), c.where("user_id % 3 <> 0"), ["event_type"], S4), ["event_type"], S4)


@_key("setops", "SELECT user_id FROM events WHERE event_type = 'click' INTERSECT SELECT user_id FROM events WHERE event_type = 'error' EXCEPT SELECT user_id FROM events WHERE value > 300")
def _(spark, sf):
    users = lambda cond: load(spark, sf, "events").where(cond).select("user_id")
    return ops.same_verdicts(users("event_type = 'click'"), users("event_type = 'error'"), users("value > 300"))


@_key("math", "SELECT o_orderkey, round(ln(o_totalprice), 8) AS l, round(sqrt(o_totalprice), 6) AS s, CAST(floor(o_totalprice) AS BIGINT) AS f, CAST(ceil(o_totalprice) AS BIGINT) AS c, greatest(o_totalprice, 1000) AS g FROM orders")
def _(spark, sf):
    x = F.col("o_totalprice")
    return load(spark, sf, "orders").select("o_orderkey", F.round(F.ln(x), 8).alias("l"), F.round(F.sqrt(x), 6).alias("s"), F.floor(x).alias("f"), F.ceil(x).alias("c"), F.greatest(x, F.lit(1000.0)).alias("g"))


@_key("date", "SELECT CAST(date_trunc('month', l_shipdate) AS TIMESTAMP) AS bucket, count(*) AS n, CAST(max(date_diff('day', DATE '1990-01-01', l_shipdate)) AS INTEGER) AS day FROM lineitem GROUP BY 1")
def _(spark, sf):
    return ops.buckets_of(load(spark, sf, "lineitem"), "l_shipdate", "MONTH").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.max("day").alias("day"))


@_key("string", "SELECT page_id, CAST(length(html) AS BIGINT) AS n, upper(substr(url, 1, 5)) AS scheme, regexp_extract(url, '//([^/]+)', 1) AS host FROM pages")
def _(spark, sf):
    return ops.url_parts(load(spark, sf, "pages"), "url", "html").select("page_id", "n", "scheme", "host")


@_key("conversations", "SELECT role, count(*) AS n, CAST(max(length(text)) AS BIGINT) AS longest FROM conversations GROUP BY role")
def _(spark, sf):
    return ops.metric(load(spark, sf, "conversations"), "length(text)").groupBy("role").agg(F.count(F.lit(1)).alias("n"), F.max("x").cast("long").alias("longest"))


@_key("array", "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS d, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS norm FROM embeddings")
def _(spark, sf):
    return ops.vector_norm(load(spark, sf, "embeddings"), "embedding").select("vec_id", "d", F.round("norm", 6).alias("norm"))


@_key("map", "SELECT count(*) FILTER (WHERE event_type = 'click') AS clicks FROM events")
def _(spark, sf):
    return ops.as_map(load(spark, sf, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "event_type", "n").select(F.col("by")["click"].alias("clicks"))


@_key("json", "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    return ops.json_dim(load(spark, sf, "events"), "props", "$.k", "int", "k").groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@_key("session", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) WHERE gap IS NULL OR gap >= INTERVAL 30 MINUTE GROUP BY user_id")
def _(spark, sf):
    return ops.sessions(load(spark, sf, "events"), "user_id", "ts", "30 minutes").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


@_key("slide_native", "SELECT CAST(floor(epoch(ts)) AS BIGINT) // 600 * 600 - 600 * i AS start, count(*) AS n FROM events, range(24) r(i) GROUP BY 1")
def _(spark, sf):
    return ops.sliding(load(spark, sf, "events"), "ts", "4 hours", "10 minutes")
