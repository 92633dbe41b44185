"""URL rules indexed by their rarest literal token; a URL's tokens fetch candidates, and only those run regular expressions.

A rule is a regular expression over host || path with alternatives of literal tokens: a URL that fits holds all tokens of one alternative.
In each alternative the token rarest in the corpus of URLs becomes an index key. A rule without tokens would have to be tried on every URL;
none of the production rules is one. DataFrame functions only.
Null URLs and URLs without ``://`` have an empty host and path and fit no host rule. Rows are kept as they are, repeats included; an empty
table gives an empty table. Input columns named host, path, rule or verdict give way to the results; any other column stays.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

CAPITALS, SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Up to so many rules the index is a literal in the projection (no shuffle); beyond, an equi-join on tokens.
INLINE_RULES = 200


@dataclass(frozen=True)
class Rule:
    name: str
    pattern: str
    action: str
    alternatives: tuple[tuple[str, ...], ...]
    tier: int = 0


def host_rule(action: str, host: str, path: str) -> Rule:
    """Fits the host and its subdomains where the path starts with ``path``. The last token counts only if it is closed."""
    text = host + path
    tokens = re.findall(r"[A-Za-z0-9]+(?=[^A-Za-z0-9])", text)
    return Rule(text, r"^(?:[^/]*\.)?" + re.sub(r"([^A-Za-z0-9/])", r"\\\1", text), action, (tuple(tokens),) if tokens else (), 1)


def word_rule(word: str) -> Rule:
    """Blocks a whole token anywhere in host or path, in any of the two."""
    return Rule(word, rf"(^|[^A-Za-z0-9]){word}([^A-Za-z0-9]|$)", "block", ((word,),))


HOST_RULES = (
    host_rule("block", "com", "/en/"),
    host_rule("allow", "example.com", "/en/7"),
    host_rule("allow", "net", "/de/"),
    host_rule("block", "example.net", "/de/8"),
    host_rule("block", "org", "/es/"),
)
#: The method's own verdict where no host rule fits: tokens of unwanted sites.
PATTERN_RULES = tuple(map(word_rule, ("spam", "pills", "casino", "viagra", "poker", "porn", "xxx", "adult", "warez", "torrent", "gambling", "betting", "escort", "payday"))) + (
    Rule("ads folder", r"/ads?/", "block", (("ad",), ("ads",))),
    Rule("doorway", r"(^|[^A-Za-z0-9])free[a-z]*-(download|prize)s?([^A-Za-z0-9]|$)", "block", tuple((w,) for w in ("download", "downloads", "prize", "prizes"))),
)


def parse_rules(lines) -> tuple[Rule, ...]:
    """Rules from lines of the usual filter-list syntax: ``||host/path`` (block host and subdomains), ``@@||host/path`` (allow), a bare word

    (block it as a whole token), ``! comment``. Options after ``$`` and a closing ``^`` are dropped; other lines raise ValueError.
    """
    out = []
    for line in map(str.strip, lines):
        if not line or line.startswith(("!", "[")):
            continue
        action, rest = ("allow", line[2:]) if line.startswith("@@") else ("block", line)
        rest = rest.partition("$")[0].removesuffix("^")
        if rest.startswith("||"):
            host, slash, path = rest[2:].partition("/")
            out.append(host_rule(action, host.lower(), slash + path or "/"))
        elif action == "block" and re.fullmatch(r"[A-Za-z0-9]+", rest):
            out.append(word_rule(rest))
        else:
            raise ValueError(f"not a rule: {line}")
    return tuple(out)


def parts(pages: DataFrame, url: str = "url") -> DataFrame:
    """Adds host and path. host: after the first ://, A-Z folded."""
    u = F.coalesce(F.col(url), F.lit(""))
    return pages.withColumn("host", F.translate(F.regexp_extract(u, r"://([^/?#]*)", 1), CAPITALS, SMALL)).withColumn("path", F.regexp_extract(u, r"://[^/?#]*([^?#]*)", 1))


def _tokens(target):
    return F.array_distinct(F.split(target, "[^A-Za-z0-9]+"))


def rarest_tokens(targets: DataFrame, rules: tuple[Rule, ...]) -> dict[Rule, tuple[str, ...]]:
    """The index keys of every rule. Counts cover all URLs; one number for each token of the rules comes back."""
    wanted = sorted({t for r in rules for a in r.alternatives for t in a})
    seen: dict = {}
    if wanted:
        words = targets.select(F.explode(F.array_intersect(_tokens(F.col("__target")), F.array(*map(F.lit, wanted)))).alias("t")) if len(wanted) <= INLINE_RULES else targets.select(F.explode(_tokens(F.col("__target"))).alias("t")).join(F.broadcast(targets.sparkSession.createDataFrame([(w,) for w in wanted], "t string")), "t")
        seen = {r["t"]: r["many"] for r in words.groupBy("t").agg(F.count(F.lit(1)).alias("many")).collect()}
    rarest = lambda tokens: min(tokens, key=lambda t: (seen.get(t, 0), -len(t), t))
    return {r: tuple(sorted({rarest(a) for a in r.alternatives if a})) if all(r.alternatives) else () for r in rules}


def judge(pages: DataFrame, rules: tuple[Rule, ...] = HOST_RULES + PATTERN_RULES, url: str = "url", inline: bool | None = None) -> DataFrame:
    """Rows of ``pages`` with host, path, rule and verdict added.

    The rule of the highest tier, then the longest, wins; with a fit in tier 1 the rule's name and action are returned, else
    ``block`` if a pattern rule fits and ``allow`` if none does. ``inline``: the index is a literal of the projection (None: up to
    ``INLINE_RULES`` rules), else an equi-join on tokens; both give the same rows.
    """
    kept = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    named = parts(pages.select(*[F.col(f"`{c}`") for c in kept]), url).withColumn("__target", F.concat("host", "path"))
    keys = rarest_tokens(named, rules)
    inline = len(rules) <= INLINE_RULES if inline is None else inline
    as_struct = lambda r: F.struct(F.lit(r.tier).alias("tier"), F.lit(len(r.name)).alias("size"), F.lit(r.name).alias("name"), F.lit(r.action).alias("action"), F.lit(r.pattern).alias("pattern"))
    kind = "array<struct<tier:int,size:int,name:string,action:string,pattern:string>>"
    always = F.array(*[as_struct(r) for r, ks in keys.items() if not ks]).cast(kind)
    by_token: dict[str, list[Rule]] = {}
    for r, ks in keys.items():
        for k in ks:
            by_token.setdefault(k, []).append(r)
    if inline or not by_token:
        index = F.create_map(*[x for k, rs in by_token.items() for x in (F.lit(k), F.array(*map(as_struct, rs)).cast(kind))]) if by_token else None
        known = F.array(*map(F.lit, by_token)) if by_token else F.array().cast("array<string>")
        fetched = F.flatten(F.transform(F.array_intersect(_tokens(F.col("__target")), known), lambda t: index[t])) if by_token else F.array().cast(kind)
        found = named.withColumn("__fetched", fetched)
    else:
        spark = pages.sparkSession
        rows = [(k, r.tier, len(r.name), r.name, r.action, r.pattern) for k, rs in by_token.items() for r in rs]
        table = spark.createDataFrame(rows, "token string, tier int, size int, name string, action string, pattern string")
        targets = named.select("__target").distinct().withColumn("token", F.explode(_tokens(F.col("__target"))))
        hits = targets.join(table, "token").where(F.expr("__target rlike pattern"))
        best = hits.groupBy(F.col("__target").alias("__for")).agg(F.max(F.struct("tier", "size", "name", "action", "pattern")).alias("__best"))
        found = named.join(best, named["__target"] == best["__for"], "left").withColumn("__fetched", F.when(F.col("__best").isNotNull(), F.array("__best")).otherwise(F.array()).cast(kind))
    fits = F.filter(F.concat("__fetched", always), lambda c: F.regexp_like(F.col("__target"), c["pattern"]))
    best = found.withColumn("__win", F.array_max(fits))
    named_rule = F.col("__win.tier") == 1
    out = best.withColumn("rule", F.when(named_rule, F.col("__win.name"))).withColumn("verdict", F.coalesce(F.col("__win.action"), F.lit("allow")))
    return out.select(*[F.col(f"`{c}`") for c in kept], "host", "path", "rule", "verdict")


def oracle() -> str:
    """The same verdicts in DuckDB by trying every rule on every URL."""
    hosts = sorted((r for r in HOST_RULES), key=lambda r: (-len(r.name), r.name))
    case = lambda pick: " ".join(f"WHEN regexp_matches(host || path, '{r.pattern}') THEN '{pick(r)}'" for r in hosts)
    blocked = " OR ".join(f"regexp_matches(host || path, '{r.pattern}')" for r in PATTERN_RULES)
    return f"""WITH p AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '://([^/?#]*)', 1), '{CAPITALS}', '{SMALL}') AS host,
        regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) AS path FROM pages)
    SELECT page_id, host, path, CASE {case(lambda r: r.name)} END AS rule,
        CASE {case(lambda r: r.action)} WHEN {blocked} THEN 'block' ELSE 'allow' END AS verdict FROM p"""
