"""Information-theoretic sanitisation of personal data; DataFrame and SQL functions only.

Protected entities are found by pattern (email, ip, card, phone). The corpus says how strongly a term reveals a unit c, which is either
a kind of entity or one entity that ``support`` different texts hold: PMI(c; term) = log2(N * df(c, term) / (df(c) * df(term))), held
against the unit's information content IC = log2(N / df(c)). A term with PMI >= remove_at * IC is removed, one with PMI >=
generalise_at * IC is generalised: to the longest beginning of it that is itself a term of the corpus, at least twice as frequent and not
disclosing, else to ``[TERM]``. Terms count only if they stand beside the unit in ``support`` different texts, so exact copies of
one document are no evidence. Documents that hold the unit lose its generalised and removed terms; terms that are to be removed go
from every other document too.

All replacements are made at once by position in the original text: an entity becomes its tag, a term inside an entity goes with it, and
nothing is searched in replaced text. Folds over matches run in blocks, so that a text with very many matches costs linear work.

Counts cover all documents. Null text counts as empty. Rows are kept, repeats included, as are extra columns of any name (results are
held in columns with two leading underscores). Positions are code points, ends exclusive. An empty table gives an empty table.
Patterns are possessive and anchored at the start of a run, which gives the same leftmost matches in linear time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import materialize

KINDS = ("email", "ip", "card", "phone")
_LOCAL = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:\G|(?<![{_LOCAL}]))[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
TAGS = {"email": "[EMAIL]", "ip": "[IP]", "card": "[CARD]", "phone": "[PHONE]"}
_PART = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
TERM = r"\p{L}{3,}"


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _valid(kind: str, m: Column) -> Column:
    if kind == "ip":
        return m.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$")
    if kind == "card":
        return F.length(_digits(m)).between(16, 19) & F.call_function("luhn_check", _digits(m))
    if kind == "phone":
        return F.length(_digits(m)).between(8, 15)
    return F.lit(True)


def _may_hold(kind: str, text: Column) -> Column:
    """A cheap necessary condition."""
    if kind == "ip":
        return text.rlike(r"[0-9]\.[0-9]")
    if kind == "card":
        return text.rlike(r"[0-9](?:[\x20-]?[0-9]){15}")
    return F.instr(text, "@" if kind == "email" else "+") > 0


_SPANS = "array<struct<start:int,end:int>>"
_HASHED = "array<struct<start:int,end:int,h:bigint>>"
_WORDS = "array<struct<start:int,end:int,tag:string>>"


def let(value: Column, body) -> Column:
    """``body(v)`` with ``value`` computed once."""
    return F.transform(F.array(value), body)[0]


def scan(items: Column, state: Column, step, emitted: str, block: int = 128) -> Column:
    """Fold over an array that emits: step(state, item) -> (state, emitted or NULL); the emitted ones, as an array of the type ``emitted``.

    An array that grows by one is copied every time; here blocks of ``block`` items fill short arrays, which are joined once.
    """
    empty = F.array().cast(emitted)

    def one(acc, x):
        after, out = step(acc["state"], x)
        return F.struct(after.alias("state"), F.concat(acc["found"], F.array(out).cast(emitted)).alias("found"))

    def whole(it):
        blocks = F.transform(F.sequence(F.lit(0), F.greatest(F.ceil(F.size(it) / F.lit(block)).cast("int") - 1, F.lit(0))), lambda b: F.slice(it, b * block + 1, F.lit(block)))
        zero = F.struct(F.struct(state.alias("state"), empty.alias("found")).alias("cur"), F.array().cast(f"array<{emitted}>").alias("parts"))
        add = lambda acc, b: F.struct(F.aggregate(b, F.struct(acc["cur"]["state"].alias("state"), empty.alias("found")), one).alias("cur"), F.concat(acc["parts"], F.array(acc["cur"]["found"])).alias("parts"))
        return F.aggregate(blocks, zero, add, lambda acc: F.flatten(F.concat(acc["parts"], F.array(acc["cur"]["found"]))))

    return F.filter(let(items, whole), lambda x: x.isNotNull())


def _located(text: Column, pattern: str, emit, emitted: str) -> Column:
    """``emit(match, start, end)`` for all matches. Split and extract walk the same matches, so running lengths give positions."""
    p = F.lit(pattern)
    pairs = F.zip_with(F.regexp_extract_all(text, p, F.lit(0)), F.split(text, p, -1), lambda m, gap: F.struct(m.alias("m"), F.length(gap).alias("gap")))

    def step(at, x):
        start = at + x["gap"]
        end = start + F.coalesce(F.length(x["m"]), F.lit(0))
        return end, F.when(x["m"].isNotNull(), emit(x["m"], start, end))

    return scan(pairs, F.lit(0), step, emitted)


def entity_spans(kind: str, text: Column) -> Column:
    """(start, end, hash of the entity) of the valid matches."""
    emit = lambda m, a, b: F.when(_valid(kind, m), F.struct(a.alias("start"), b.alias("end"), F.xxhash64(F.lit(kind), m).alias("h")))
    return F.when(_may_hold(kind, text), _located(text, PATTERNS[kind], emit, _HASHED)).otherwise(F.array().cast(_HASHED))


def _terms(text: Column) -> Column:
    """Different words of a text in lower case, those of e-mail addresses left out."""
    plain = F.when(F.instr(text, "@") > 0, F.regexp_replace(text, PATTERNS["email"], " ")).otherwise(text)
    return F.array_distinct(F.transform(F.array_distinct(F.regexp_extract_all(plain, F.lit(TERM), F.lit(0))), F.lower))


def _joined(kind: str, spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.lit(kind), s["start"].cast("string"), s["end"].cast("string"))), ",")


def _key(text: Column) -> Column:
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


def find_entities(docs: DataFrame, keep: list[str]) -> DataFrame:
    """Columns ``keep`` in the struct __row, then __email ... __phone (spans), __any, __key (of the text), and for rows with an entity __text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    found = docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("__row"), text.alias("__text"))
    found = found.select("*", *[entity_spans(k, F.col("__text")).alias(f"__{k}") for k in KINDS])
    found = found.withColumn("__any", sum((F.size(f"__{k}") for k in KINDS), F.lit(0)) > 0).withColumn("__key", _key(F.col("__text")))
    return found.withColumn("__text", F.when(F.col("__any"), F.col("__text")))


def _units() -> Column:
    """The kinds of entities that a row holds, and its entities as hashes."""
    kinds = F.array(*[F.when(F.size(f"__{k}") > 0, F.lit(k)) for k in KINDS])
    each = F.flatten(F.array(*[F.transform(f"__{k}", lambda s: s["h"].cast("string")) for k in KINDS]))
    return F.array_distinct(F.filter(F.concat(kinds, each), lambda u: u.isNotNull()))


def disclosing_terms(docs: DataFrame, found: DataFrame, generalise_at: float, remove_at: float, support: int) -> DataFrame:
    """(term, unit, level, pmi, ic, new): terms that reveal a unit too strongly; level 2 is removed, 1 generalised to ``new``."""
    n = found.count()
    holders = found.where("__any").select("__key", "__text", _units().alias("units"))
    texts = holders.groupBy("__key").agg(F.count(F.lit(1)).alias("rows"), F.first("__text").alias("__text"), F.first("units").alias("units"))
    texts = materialize(texts)
    units = texts.select("rows", F.explode("units").alias("unit")).groupBy("unit").agg(F.sum("rows").alias("nc"), F.count(F.lit(1)).alias("different"))
    units = materialize(units.where(F.col("different") >= support).select("unit", "nc"))
    everywhere = materialize(docs.select(F.explode(_terms(F.coalesce(F.col("text"), F.lit("")))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df")))
    own = texts.select("__key", "rows", F.explode("units").alias("unit")).join(units, "unit").groupBy("__key").agg(F.first("rows").alias("rows"), F.collect_list(F.struct("unit", "nc")).alias("units"))
    words = texts.select("__key", F.explode(_terms(F.col("__text"))).alias("term")).join(everywhere, "term")
    # PMI >= a * IC needs df(term) <= N^(1 - a) * df(c)^a, as df(c, term) is at most df(c): commoner terms are out before they meet the units
    most = F.pow(F.lit(float(n or 1)), F.lit(1 - generalise_at)) * F.pow(F.array_max(F.transform("units", lambda u: u["nc"])).cast("double"), F.lit(generalise_at))
    rare = words.join(own.withColumn("most", most), "__key").where(F.col("df") <= F.col("most") * (1 + 1e-9))
    beside = rare.select("term", "df", "rows", F.explode("units").alias("u")).groupBy("term", "df", "u.unit", "u.nc").agg(F.sum("rows").alias("together"), F.count(F.lit(1)).alias("different"))
    total = F.lit(float(n or 1))
    rated = beside.where(F.col("different") >= support).withColumn("pmi", F.log2(total * F.col("together") / (F.col("nc") * F.col("df")))).withColumn("ic", F.log2(total / F.col("nc")))
    level = F.when((F.col("ic") > 0) & (F.col("pmi") >= remove_at * F.col("ic")), 2).when((F.col("ic") > 0) & (F.col("pmi") >= generalise_at * F.col("ic")), 1)
    rated = materialize(rated.withColumn("level", level).where("level is not null").select("term", "df", "unit", "level", "pmi", "ic"))
    general = rated.where("level = 1").select("term", "df").distinct().withColumn("stem", F.explode(F.transform(F.sequence(F.lit(3), F.greatest(F.length("term") - 1, F.lit(3))), lambda k: F.substring("term", 1, k)))).where("stem <> term")
    known = everywhere.select(F.col("term").alias("stem"), F.col("df").alias("many")).join(rated.select(F.col("term").alias("stem")).distinct(), "stem", "left_anti")
    broader = general.join(known, "stem").where(F.col("many") >= 2 * F.col("df")).groupBy("term").agg(F.max_by("stem", F.length("stem")).alias("new"))
    return materialize(rated.join(broader, "term", "left").select("term", "unit", "level", "pmi", "ic", F.when(F.col("level") == 2, F.lit("")).otherwise(F.coalesce("new", F.lit("[TERM]"))).alias("new")))


def _word_spans(text: Column, words: Column) -> Column:
    """(start, end, replacement) of the words of a text that ``words`` (term, new) lists. They are looked up by hash, so the work doesn't grow with the list."""

    def find(buckets):
        def emit(m, a, b):
            low = F.lower(m)
            own = F.element_at(buckets, F.pmod(F.xxhash64(low), F.size(buckets)).cast("int") + 1)
            hit = F.get(F.filter(own, lambda w: w["term"] == low), F.lit(0))
            return F.when(hit.isNotNull(), F.struct(a.alias("start"), b.alias("end"), hit["new"].alias("tag")))

        return _located(text, TERM, emit, _WORDS)

    def dealt(ws):
        parts = F.floor(F.size(ws) / F.lit(4)).cast("int") + 1
        return F.transform(F.sequence(F.lit(0), parts - 1), lambda b: F.filter(ws, lambda w: F.pmod(F.xxhash64(w["term"]), parts).cast("int") == b))

    return let(let(words, dealt), find)


_ITEM = "struct<start:int,end:int,term:boolean,tag:string>"


def _apart(base: Column, terms: Column) -> Column:
    """Base spans and those terms that overlap none of them, by start. Two sweeps: one knows the ends of spans before, one the starts of spans behind."""
    item = lambda s, term, tag: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.lit(term).alias("term"), tag.alias("tag"))
    both = F.array_sort(F.concat(F.transform(base, lambda s: item(s, False, s["tag"])), F.transform(terms, lambda s: item(s, True, s["tag"]))).cast(f"array<{_ITEM}>"))
    ahead = lambda end, x: (F.when(x["term"], end).otherwise(F.greatest(end, x["end"])), F.when(~x["term"] | (x["start"] >= end), x))
    back = lambda start, x: (F.when(x["term"], start).otherwise(F.least(start, x["start"])), F.when(~x["term"] | (x["end"] <= start), x))
    once = scan(both, F.lit(0), ahead, f"array<{_ITEM}>")
    return F.reverse(scan(F.reverse(once), F.lit(2**31 - 1), back, f"array<{_ITEM}>"))


_CUT = "struct<from:int,to:int,end:int,tag:string>"


def _replaced(text: Column, items: Column, block: int = 64) -> Column:
    """The text with each span replaced by its tag; where spans overlap, the first one's tag stands for all.

    A piece is cut from a part of the text that holds ``block`` pieces, so that no cut walks the whole text.
    """

    def step(end, x):
        cut = lambda to, tag: F.struct(end.alias("from"), to.alias("to"), x["end"].alias("end"), tag.alias("tag"))
        return F.greatest(end, x["end"]), F.when(x["start"] >= end, cut(x["start"], x["tag"])).when(x["end"] > end, cut(end, F.lit("")))

    def join(cuts):
        last = F.get(cuts, F.size(cuts) - 1)["end"]
        blocks = F.transform(F.sequence(F.lit(0), F.ceil(F.size(cuts) / F.lit(block)).cast("int") - 1), lambda b: F.slice(cuts, b * block + 1, F.lit(block)))
        parts = F.transform(blocks, lambda c: F.struct(c.alias("cuts"), c[0]["from"].alias("at"), F.substring(text, c[0]["from"] + 1, F.get(c, F.size(c) - 1)["end"] - c[0]["from"]).alias("part")))
        done = F.transform(parts, lambda p: F.array_join(F.transform(p["cuts"], lambda c: F.concat(F.substring(p["part"], c["from"] - p["at"] + 1, c["to"] - c["from"]), c["tag"])), ""))
        return F.when(F.size(cuts) > 0, F.concat(F.array_join(done, ""), F.substring(text, last + 1, F.lit(2**31 - 1)))).otherwise(text)

    return let(scan(items, F.lit(0), step, f"array<{_CUT}>"), join)


def sanitise(docs: DataFrame, generalise_at: float = 0.8, remove_at: float = 0.9, support: int = 5, keep: list[str] | None = None, clean: bool = True) -> DataFrame:
    """Rows as the struct __row of their columns ``keep`` (None: all), the spans of each kind (__email ... __phone, __term) and, if ``clean``, __clean,

    the text with entities replaced by tags, generalised terms by broader ones and removed terms gone. __clean is null where nothing was found.
    """
    keep = docs.columns if keep is None else keep
    found = materialize(find_entities(docs, keep))
    terms = disclosing_terms(docs, found, generalise_at, remove_at, support)
    holders = found.where("__any").groupBy("__key").agg(F.first("__text").alias("__text"), F.first(_units()).alias("units"))
    uses = holders.select("__key", "units", F.explode(_terms(F.col("__text"))).alias("term")).join(terms.select("term", "unit", "level", "new"), "term").where(F.array_contains("units", F.col("unit")))
    gone = terms.where("level = 2").select("term", "level", "new").distinct()
    whole = docs.select(F.coalesce(F.col("text"), F.lit("")).alias("__whole")).withColumn("__key", _key(F.col("__whole")))
    mine = uses.select("__key", "term", "level", "new")
    if not gone.isEmpty():
        mine = mine.unionByName(whole.select("__key", F.explode(_terms(F.col("__whole"))).alias("term")).join(gone, "term").select("__key", "term", "level", "new").distinct())
    mine = mine.groupBy("__key", "term").agg(F.max(F.struct("level", "new")).alias("l"))
    # One list for each text, no longer than the text's own vocabulary.
    mine = materialize(mine.groupBy("__key").agg(F.array_sort(F.collect_list(F.struct(F.col("term"), F.col("l.new").alias("new")))).alias("__words")))
    bare = whole.join(mine.select("__key").join(holders.select("__key"), "__key", "left_anti"), "__key", "left_semi").groupBy("__key").agg(F.first("__whole").alias("__whole"))
    mine = materialize(mine.join(bare, "__key", "left"))
    held = found.join(mine, "__key", "left").withColumn("__text", F.coalesce("__text", "__whole"))
    with_tag = lambda tag: lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.lit(tag).alias("tag"))
    tagged = F.concat(*[F.transform(f"__{k}", with_tag(TAGS[k])) for k in KINDS]).cast(_WORDS)
    held = held.withColumn("__base", tagged).withColumn("__found", F.when(F.size("__words") > 0, _word_spans(F.col("__text"), F.col("__words"))).otherwise(F.array().cast(_WORDS)))
    held = held.withColumn("__items", _apart(F.col("__base"), F.col("__found")))
    held = held.withColumn("__term", F.transform(F.filter("__items", lambda x: x["term"]), lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"))))
    out = ["__row", *[f"__{k}" for k in KINDS], "__term"]
    if not clean:
        return held.select(*out)
    return held.withColumn("__clean", F.when(F.size("__items") > 0, _replaced(F.col("__text"), F.col("__items")))).select(*out, "__clean")


def span_digests(docs: DataFrame, **how) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term."""
    s = sanitise(docs.select("doc_id", "text"), keep=["doc_id"], clean=False, **how)
    strings = s.select("__row.doc_id", *[F.size(f"__{k}").cast("long").alias(f"n_{k}") for k in KINDS], F.size("__term").cast("long").alias("n_term"), *[_joined(k, F.col(f"__{k}")).alias(f"s_{k}") for k in (*KINDS, "term")])
    joined = lambda kinds: F.array_join(F.filter(F.array(*[F.col(f"s_{k}") for k in kinds]), lambda x: x != ""), ",")
    return strings.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2(joined(KINDS), 256).alias("base_sha256"), joined((*KINDS, "term")).alias("spans"), "n_term")


def sanitise_documents(docs: DataFrame, **how) -> DataFrame:
    """Documents with their text sanitised (and n_chars, where there is one, of the new text)."""
    s = sanitise(docs, **how)
    own = lambda c: F.col("__row")[c]
    text = F.coalesce(F.col("__clean"), own("text"))
    made = {"text": text} | ({"n_chars": F.when(F.col("__clean").isNull(), own("n_chars")).otherwise(F.length("__clean")).cast(docs.schema["n_chars"].dataType)} if "n_chars" in docs.columns else {})
    return s.select(*[made.get(c, own(c)).alias(c) for c in docs.columns])
