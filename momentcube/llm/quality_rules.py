"""Quality rules with adaptive thresholds: quantile sketches per language and source replace fixed cutoffs.

Every measure is a share in 1/1000. Its sketch is a histogram of 1001 cells, which merges by adding counts; the rank of a value in whole
cells is exact. A group's threshold lies where its own upper tail breaks off: of the quantiles at ``LEVELS`` the widest jump between
neighbours is taken, measured as the ratio of both after the measure's resolution is added (shares closer than that are alike). If
the ratio reaches ``JUMP``, the threshold is the geometric mean of both, else the group has none: a group without a break, whatever its level,
loses no document. No threshold comes from a constant: a share that is usual in one group is far out in another.
A document above its group's threshold in any measure is rejected. Null text counts as no words; a null language or source is a
group of its own. Rows are kept, repeats included; an empty table gives an empty table; extra columns stay as they are in ``keep_good``
(its own are named __qr_...).
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_rows, materialize

SYMBOLS = b"#*$%&|<>"
_CAPITALS = bytes(range(65, 91))
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_capitals", "n_lines")
#: measure: (numerator, denominator, resolution in 1/1000)
MEASURES = {"symbol_share": ("n_symbols", "word_chars", 10), "capital_share": ("n_capitals", "word_chars", 10), "dup_line_share": ("n_dup_lines", "n_lines", 100)}
#: Levels of the sketch's quantiles in 1/1000: at least three quarters of a group lie below any threshold.
LEVELS = (750, 800, 850, 900, 925, 950, 970, 990, 1000)
JUMP = 3


def repeated_words(words: list[bytes], width: int = 5) -> int:
    """Words that lie in a window of ``width`` words found twice or more in the text."""
    windows = len(words) - width + 1
    if windows < 2:
        return 0
    seen = Counter(zip(*(words[i:] for i in range(width))))
    if len(seen) == windows:
        return 0
    covered, end = 0, 0
    for i, w in enumerate(zip(*(words[i:] for i in range(width)))):
        if seen[w] > 1:
            covered += i + width - max(i, end)
            end = i + width
    return covered


def measure(text: str | None, repeats: bool = True) -> tuple[int, ...]:
    """The numbers of ``COUNTS``; repeated words, the dearest, only if asked for."""
    text = text or ""
    raw = text.encode()
    words = raw.split()
    spaces = len(raw) - sum(map(len, words))
    lines = [x for x in raw.split(b"\n") if x.strip(b" \t\n\r\x0b\x0c")]
    return (len(words), len(text) - spaces, len(raw) - len(raw.translate(None, SYMBOLS)), len(lines) - len(set(lines)), repeated_words(words) if repeats else 0, len(raw) - len(raw.translate(None, _CAPITALS)), len(lines))


def counted(docs: DataFrame, keep: list[str], prefix: str = "", repeats: bool = True) -> DataFrame:
    def add(batch):
        rows = [measure(t, repeats) for t in batch.column(batch.schema.get_field_index("text")).to_pylist()]
        return {prefix + n: list(v) for n, v in zip(COUNTS, zip(*rows))}

    return map_rows(docs, add, [T.StructField(prefix + n, T.LongType()) for n in COUNTS], keep)


def _share(name: str, prefix: str = ""):
    num, den, _ = MEASURES[name]
    return F.when(F.col(prefix + den) > 0, F.least(F.expr(f"{prefix}{num} * 1000 div {prefix}{den}"), F.lit(1000))).otherwise(0)


def thresholds(rows: DataFrame, prefix: str = "", group: tuple[str, str] = ("lang", "source")) -> DataFrame:
    """__qr_lang, __qr_source and the largest share allowed of each measure, from merged sketches."""
    shares = F.array(*[F.struct(F.lit(m).alias("m"), _share(m, prefix).cast("long").alias("cell")) for m in MEASURES])
    cells = rows.select(F.col(group[0]).alias("__qr_lang"), F.col(group[1]).alias("__qr_source"), F.explode(shares).alias("x")).groupBy("__qr_lang", "__qr_source", "x.m", "x.cell").agg(F.count(F.lit(1)).alias("many"))
    ran = cells.selectExpr("*", "sum(many) over (partition by __qr_lang, __qr_source, m order by cell) as upto", "sum(many) over (partition by __qr_lang, __qr_source, m) as total")
    at = ran.groupBy("__qr_lang", "__qr_source", "m").agg(*[F.min(F.when(F.col("upto") * 1000 >= F.col("total") * p, F.col("cell"))).alias(f"q{p}") for p in LEVELS])
    own = F.create_map(*[x for m, (_, _, v) in MEASURES.items() for x in (F.lit(m), F.lit(v))])
    jumps = F.array(*[F.struct(((F.col(f"q{b}") + F.col("own")) / (F.col(f"q{a}") + F.col("own"))).alias("ratio"), F.lit(-a).alias("level"), F.sqrt(((F.col(f"q{a}") + F.col("own")) * (F.col(f"q{b}") + F.col("own"))).cast("double")).alias("mean")) for a, b in zip(LEVELS, LEVELS[1:])])
    widest = at.withColumn("own", own[F.col("m")]).withColumn("jump", F.array_max(jumps))
    most = widest.withColumn("most", F.when(F.col("jump.ratio") >= JUMP, F.floor("jump.mean") - F.col("own")))
    return most.groupBy("__qr_lang", "__qr_source").agg(*[F.max(F.when(F.col("m") == m, F.col("most"))).alias(f"__qr_max_{m}") for m in MEASURES])


def judged(rows: DataFrame, limits: DataFrame, prefix: str = "", group: tuple[str, str] = ("lang", "source")) -> DataFrame:
    """Adds base_failed and kept (with the prefix)."""
    n, rep = F.col(prefix + "n_words"), F.col(prefix + "n_repeat_words")
    both = rows.join(limits, rows[group[0]].eqNullSafe(limits["__qr_lang"]) & rows[group[1]].eqNullSafe(limits["__qr_source"]), "left").drop("__qr_lang", "__qr_source")
    within = F.lit(True)
    for m in MEASURES:
        within = within & F.coalesce(_share(m, prefix) <= F.col(f"__qr_max_{m}"), F.lit(True))
    both = both.withColumn(prefix + "base_failed", (n < 10) | (rep * 100 > n * 20))
    return both.withColumn(prefix + "kept", ~F.col(prefix + "base_failed") & within).drop(*[f"__qr_max_{m}" for m in MEASURES])


def quality_report(docs: DataFrame) -> DataFrame:
    rows = materialize(counted(docs.select("doc_id", "text", "lang", "source"), ["doc_id", "lang", "source"]))
    return judged(rows, materialize(thresholds(rows))).select("doc_id", *COUNTS[:5], "base_failed", "kept")


def keep_good(docs: DataFrame) -> DataFrame:
    """Documents that pass, with their own columns.

    Thresholds depend on all texts, so these are read twice; the first time only the cheap counts are taken. Writing texts with
    their counts in between would cost more than it saves. The thresholds are written first: a row for each language and source, of which
    Spark then knows the size, so while they are small the documents are filtered where they are read, and joined by shuffle beyond.
    """
    p = "__qr_"
    limits = materialize(thresholds(counted(docs.select("text", "lang", "source"), ["lang", "source"], p, repeats=False), p))
    return judged(counted(docs, docs.columns, p), limits, p).where(f"{p}kept").select(*docs.columns)


def oracle() -> str:
    word = r"[^\x20\x09-\x0D]+"
    share = lambda m: "CASE WHEN {1} > 0 THEN least({0} * 1000 // {1}, 1000) ELSE 0 END".format(*MEASURES[m][:2])
    cells = " UNION ALL ".join(f"SELECT lang, source, '{m}' AS m, {share(m)} AS cell, {MEASURES[m][2]} AS own FROM c" for m in MEASURES)
    within = " AND ".join(f"{share(m)} <= (SELECT coalesce(max(most), 1000) FROM lim WHERE lim.m = '{m}' AND lim.lang IS NOT DISTINCT FROM c.lang AND lim.source IS NOT DISTINCT FROM c.source)" for m in MEASURES)
    return f"""WITH t AS (SELECT doc_id, lang, source, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{word}') AS w FROM documents),
    win AS (SELECT doc_id, i, array_to_string(w[i:i+4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM t WHERE len(w) > 4)),
    rep AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + 5)) AS j FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS k FROM win) WHERE k > 1) GROUP BY doc_id),
    ln AS (SELECT doc_id, count(*) AS n, count(*) - count(DISTINCT l) AS dup FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM t) WHERE regexp_matches(l, '{word}') GROUP BY doc_id),
    c AS (SELECT doc_id, lang, source, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(text, '[\\x20\\x09-\\x0D]', '', 'g')) AS BIGINT) AS word_chars,
        CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(ln.dup, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words,
        CAST(length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')) AS BIGINT) AS n_capitals, CAST(coalesce(ln.n, 0) AS BIGINT) AS n_lines FROM t LEFT JOIN rep USING (doc_id) LEFT JOIN ln USING (doc_id)),
    cell AS (SELECT lang, source, m, cell, max(own) AS own, count(*) AS many FROM ({cells}) GROUP BY lang, source, m, cell),
    ran AS (SELECT *, sum(many) OVER (PARTITION BY lang, source, m ORDER BY cell) AS upto, sum(many) OVER (PARTITION BY lang, source, m) AS total FROM cell),
    lev AS (SELECT lang, source, m, p, max(own) AS own, min(cell) FILTER (upto * 1000 >= total * p) AS q FROM ran, (SELECT unnest({list(LEVELS)}) AS p) GROUP BY lang, source, m, p),
    nxt AS (SELECT *, lead(q) OVER (PARTITION BY lang, source, m ORDER BY p) AS above FROM lev),
    top AS (SELECT lang, source, m, arg_max(struct_pack(ratio := (above + own) / (q + own), mean := sqrt(CAST((q + own) * (above + own) AS DOUBLE)), own := own), ((above + own) / (q + own), -p)) AS j FROM nxt WHERE above IS NOT NULL GROUP BY lang, source, m),
    lim AS (SELECT lang, source, m, floor(j.mean) - j.own AS most FROM top WHERE j.ratio >= {JUMP}),
    b AS (SELECT *, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed FROM c)
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND {within.replace('c.lang', 'b.lang').replace('c.source', 'b.source')}) AS kept FROM b"""
