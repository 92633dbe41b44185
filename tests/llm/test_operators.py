"""Every operator query against a brute-force version, on a given table and on awkward rows."""

import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import Row, types as T

from momentcube.llm import bpe, common, embeddings, packing, pii, quality_model, quality_rules, queries, sharding, simhash, toxicity, urls

from . import reference as ref

SF = "/root/testdata/sf0.01"
DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()), T.StructField("__text", T.StringType()), T.StructField("fp", T.LongType()), T.StructField("length", T.LongType()), T.StructField("score", T.DoubleType())])
AWKWARD = [
    None, "", " \n\t ", "a", "a b", "A B c d", "a b c d", "x" * 50_000, "word " * 9_000, "a@b-.c@d.e.f_g@h.i", "me@ex.com" * 300,
    "1.2.3.4.5.6.7.8 999.1.1.1 0001.02.255.255 256.1.1.1", "4111 1111 1111 1111 and 4111111111111112, 4111-1111-1111-1111-003",
    "+1 (017) 555-7713) +12 +1 2 3 4 5 6 7 8 9 0 1 2 3 4 5 6", "ü@ü.de é a.b@c.de 日本 +49 30 1234567", "😀 me@x.yz 😀 10.0.0.1", "9" * 3000, "#### $$$$ ****",
    "line\nline\nline\n\n \nother", "<|endoftext|> it's 'll \r\n x", "same text here for all", "same text here for all", "same text here for all",
]


@pytest.fixture(scope="module")
def awkward(spark):
    rows = [(i, t, None if i % 3 else "en", None if i % 4 else "s", len(t or ""), "clash", 1, 2, 0.5) for i, t in enumerate(AWKWARD)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def texts_of(df):
    return {r["doc_id"]: r["text"] for r in df.select("doc_id", "text").collect()}


@pytest.mark.parametrize("which", ["documents", "awkward"])
def test_pii_base(which, request):
    docs = request.getfixturevalue(which)
    want = {i: ref.base_spans(t) for i, t in texts_of(docs).items()}
    got = pii.span_digests(docs).collect()
    assert len(got) == len(want)
    for r in got:
        w = want[r["doc_id"]]
        assert [r["n_email"], r["n_ip"], r["n_card"], r["n_phone"]] == [len(v) for v in w.values()]
        base = ref.span_string(w)
        assert r["base_sha256"] == ref.sha(base)
        assert r["spans"] == base or r["spans"].startswith(base)


def _sanitised(spark, rows, **how):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = pii.sanitise(docs, **how).collect()
    want = ref.sanitised([t for _, t in rows], **how)
    assert len(got) == len(rows)
    for r in got:
        terms, clean = want[r["__row"]["text"] or ""]
        assert [(s["start"], s["end"]) for s in r["__term"]] == terms, r["__row"]["text"]
        assert r["__clean"] == clean, (r["__row"]["text"], r["__clean"], clean)
    return {r["__row"]["doc_id"]: r["__clean"] for r in got}


def test_pii_terms(spark):
    """A term seen only beside e-mail addresses goes; one seen everywhere stays; copies are no evidence. Every row equals a brute-force version."""
    rows = [(i, f"contact Zorblax at user{i}@mail.com please") for i in range(8)] + [(100 + i, "contact nobody please, plain prose") for i in range(60)]
    rows += [(300 + i, "quibble with copy@mail.com always") for i in range(20)] + [(400, None), (401, "")]
    clean = _sanitised(spark, rows)
    assert clean[0] == "contact  at [EMAIL] please" and clean[100] is None and clean[300] == "quibble with [EMAIL] always"
    out = {r["doc_id"]: r["text"] for r in pii.sanitise_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(out) == len(rows) and out[100] == rows[8][1] and out[0] == clean[0]


def test_pii_terms_beside_one_address(spark):
    """A term in many different texts beside one and the same address goes as well, also from a text without the address."""
    words = ("amber", "birch", "cedar", "delta", "ember", "fjord", "grove", "heath")
    rows = [(i, f"project Zorblax {w} via hot@mail.com please") for i, w in enumerate(words)] + [(100 + i, f"project nobody {w} via please plain prose") for i in range(160) for w in (words[i % 8],)]
    rows += [(100_000 + i, f"user{i}@mail.com wrote") for i in range(60)] + [(500, "but Zorblax alone")]
    clean = _sanitised(spark, rows)
    assert clean[0] == "project  amber via [EMAIL] please" and clean[100] is None and clean[500] == "but  alone"


def test_pii_terms_named_like_tags(spark):
    """Disclosing words that also occur in tags leave the tags alone; overlaps and words inside entities are settled by position."""
    rows = [(i, f"my phone Email is +49 30 12345{i}7 or mail card term to: term{i}@x{i}.de (IP {i}.1.1.1) éabc{i}@y.de") for i in range(9)]
    rows += [(50 + i, "my other is or to: plain prose") for i in range(80)]
    clean = _sanitised(spark, rows)
    assert clean[0].count("[EMAIL]") == 2 and "[PHONE]" in clean[0] and "[IP]" in clean[0] and " phone " not in clean[0]


def test_pii_generalises_to_a_broader_term(spark):
    """Between both thresholds a term becomes its longest beginning that the corpus holds more often and that discloses nothing."""
    rows = [(i, f"the zorblaxian of user{i}@mail.com and {i}") for i in range(10)] + [(100 + i, "the zorblaxian alone") for i in range(3)]
    rows += [(200 + i, "the zorblax and the zor") for i in range(40)] + [(300 + i, "the prose") for i in range(600)]
    clean = _sanitised(spark, rows, generalise_at=0.8, remove_at=0.97)
    assert clean[0] == "the zorblax of [EMAIL] and 0" and clean[100] is None


def test_pii_many_matches_in_one_text(spark):
    """Tens of thousands of addresses in one text: same spans and clean text as brute force, in time that grows with their number."""
    text = " ".join(f"u{i}@m{i % 7}.com é" for i in range(30_000))
    got = pii.sanitise(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    assert [(s["start"], s["end"]) for s in got["__email"]] == ref.base_spans(text)["email"]
    assert got["__clean"] == " ".join(["[EMAIL] é"] * 30_000)


def test_urls_both_plans(spark):
    seen = ["http://a.example.com/en/7", "http://example.com/en/75?x#y", "HTTPS://WWW.Example.COM/en/8", "x://net/de/", "x://a.net/de/8", "x://example.net/de/8/", "y://de/net/de/", "ftp://org/es/1", "://org", "org/es/", None, "", "http://com:80/en/", "http://spam.example.fr/", "http://x.fr/my-pills.html", "http://x.fr/ad/1", "http://spamx.fr/", "a://b://c/d", "http://notexample.com/en/7", "http://x.fr/free-download"]
    pages = spark.createDataFrame([(i, u, "keep", "clash") for i, u in enumerate(seen + seen[:2])], "page_id long, url string, target string, verdict string")
    a = urls.judge(pages, inline=True).orderBy("page_id").collect()
    assert a == urls.judge(pages, inline=False).orderBy("page_id").collect()
    want = [("example.com/en/7", "allow"), ("example.com/en/7", "allow"), ("com/en/", "block"), ("net/de/", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), (None, "allow"), ("org/es/", "block"), (None, "allow"), (None, "allow"), (None, "allow"), (None, "allow"), (None, "allow"), (None, "block"), (None, "block"), (None, "block"), (None, "allow"), (None, "allow"), ("com/en/", "block"), (None, "block")]
    assert [(r["rule"], r["verdict"]) for r in a[: len(want)]] == want
    assert (a[2]["host"], a[2]["path"], a[17]["host"], a[17]["path"]) == ("www.example.com", "/en/8", "b:", "//c/d")
    assert all(r["target"] == "keep" and r["verdict"] != "clash" for r in a) and urls.judge(pages).columns == ["page_id", "url", "target", "host", "path", "rule", "verdict"]
    assert urls.judge(pages.limit(0)).count() == 0


def test_urls_with_a_long_rule_list(spark):
    """Thousands of parsed rules: the join plan gives what trying every rule on every URL gives; no rule is without a key."""
    import random
    import re

    rng = random.Random(4)
    hosts = [f"site{i}.{rng.choice(('com', 'net', 'co.uk'))}" for i in range(1500)]
    lines = ["! a list", "[header]"] + [f"||{h}/p{i % 5}" for i, h in enumerate(hosts)] + [f"@@||www.{h}/p{i % 5}/ok^$document" for i, h in enumerate(hosts[::3])] + [f"bad{i}" for i in range(300)]
    rules = urls.parse_rules(lines)
    assert len(rules) == 2300 and all(r.alternatives for r in rules + urls.PATTERN_RULES)
    seen = [f"http://{rng.choice(('', 'www.', 'a.'))}{rng.choice(hosts)}/p{rng.randrange(5)}/{rng.choice(('ok', 'x', f'bad{rng.randrange(400)}'))}" for _ in range(400)]
    got = urls.judge(spark.createDataFrame(list(enumerate(seen)), "page_id long, url string"), rules).collect()
    for r in got:
        target = r["host"] + r["path"]
        fits = [x for x in rules if re.search(x.pattern, target)]
        best = max(fits, key=lambda x: (x.tier, len(x.name), x.name, x.action), default=None)
        assert r["verdict"] == (best.action if best else "allow") and r["rule"] == (best.name if best and best.tier else None)
    with pytest.raises(ValueError):
        urls.parse_rules(["##.banner"])


@pytest.mark.parametrize("which", ["documents", "awkward"])
def test_simhash(which, request):
    docs = request.getfixturevalue(which)
    want = ref.simhash_classes(texts_of(docs))
    got = simhash.fingerprint_classes(docs).collect()
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in got} == want and len(got) == len(want)


def test_simhash_links_in_long_lists():
    """Lists beyond 64 fingerprints take the table of 16 bits: same classes as all pairs."""
    rng = np.random.default_rng(1)
    low = rng.choice(65536, 900, replace=False).astype(np.uint64)
    values = low | np.uint64(0xABCDEF0000000000)
    which = next(i for i, m in enumerate(simhash.BYTE_SETS) if m & 0xFFFF == 0)
    u, v = simhash._list_edges(values, which)
    pairs = [(int(values[i]), int(values[j])) for i in range(900) for j in range(i) if int(np.bitwise_count(values[i] ^ values[j])) <= 2]
    ids = [int(x) for x in values]
    a, b = ref.classes(ids, pairs), ref.classes(ids, list(zip(map(int, u), map(int, v))))
    assert a == b


def test_near_duplicates(spark):
    rng = np.random.default_rng(5)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 6))
    base = [[word() for _ in range(300)] for _ in range(40)]
    rows = [(i, " ".join(b)) for i, b in enumerate(base)]
    rows += [(100 + i, " ".join(b).upper()) for i, b in enumerate(base[:10])]
    near = [(200 + i, " ".join([*b[:150], word(), *b[151:]])) for i, b in enumerate(base[10:30])]
    rows += near + [(500, None), (501, ""), (502, None)] + [(7, rows[7][1])]
    kept = simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    ids = sorted(r["doc_id"] for r in kept)
    assert ids == [*range(40), 500]


def test_near_duplicates_against_exact_similarity(spark):
    """No class joins documents without a path of pairs at 0.8 or more; such pairs are joined."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    sets = {r["doc_id"]: set(simhash.shingle_hashes(r["text"], 5).tolist()) for r in docs.collect()}
    holders = defaultdict(list)
    for i, s in sets.items():
        for h in s:
            holders[h].append(i)
    met = {(a, b) for ids in holders.values() for a in ids for b in ids if a < b}
    pairs = [(a, b) for a, b in met if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    empty = [i for i, s in sets.items() if not s]
    exact = ref.classes(list(sets), pairs + [(empty[0], e) for e in empty[1:]])
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicate_classes(docs).collect()}
    assert got.keys() == sets.keys() and len(pairs) > 20
    assert all(exact[i] == exact[c] for i, c in got.items())
    assert sum(got[a] == got[b] for a, b in pairs) >= 0.99 * len(pairs)


def _exact_classes(rows, similarity=0.8):
    sets = {i: set(simhash.shingle_hashes(t, 5).tolist()) for i, t in rows}
    ids = list(sets)
    pairs = [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b])]
    return ref.classes(ids, pairs), pairs


def test_near_duplicates_of_block_edits(spark):
    """Truncated, extended and block-replaced copies at 0.80-0.90 are found as scattered edits are."""
    rng = np.random.default_rng(11)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    rows, kinds = [], ("cut", "extended", "replaced", "scattered")
    for k in range(160):
        base = [word() for _ in range(int(rng.integers(60, 400)))]
        n, kind = len(base), kinds[k % 4]
        copy = list(base)
        if kind == "cut":
            copy = base[: int(n * rng.uniform(0.83, 0.9))]
        elif kind == "extended":
            copy = base + [word() for _ in range(int(n * rng.uniform(0.1, 0.2)))]
        elif kind == "replaced":
            m, at = int(n * rng.uniform(0.03, 0.07)), int(n * 0.4)
            copy[at : at + m] = [word() for _ in range(m)]
        else:
            for at in rng.choice(n, max(1, n // 60), replace=False):
                copy[at] = word()
        rows += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(copy))]
    want, pairs = _exact_classes(rows)
    assert min(Counter(kinds[a // 2 % 4] for a, _ in pairs).values()) >= 25
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicate_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want


def test_near_duplicates_in_a_family(spark):
    """Many documents of one template around 0.8: every link that is alike enough counts, not only each block's nearest."""
    rng = np.random.default_rng(3)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    base, rows = [word() for _ in range(300)], []
    for k in range(400):
        copy = list(base)
        for at in rng.choice(300, int(rng.integers(3, 10)), replace=False):
            copy[at] = word()
        rows.append((k, " ".join(copy)))
    want, pairs = _exact_classes(rows)
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicate_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert 100 < len(set(want.values())) < 300 and len(pairs) > 100
    assert len(set(got.values())) == len(set(want.values())) and got == want


def test_near_duplicates_write_nodes_and_not_links(spark, monkeypatch):
    """A family just below 0.8 has links by the square of its size to try; the rows of no table follow them, and no link is lost."""
    rng = np.random.default_rng(4)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    base, rows, written = [word() for _ in range(120)], [], []
    for k in range(600):
        copy = list(base)
        for at in rng.choice(120, 2, replace=False):
            copy[at] = word()
        rows.append((k, " ".join(copy)))

    def counted(df):
        out = common.materialize(df)
        written.append(out.count())
        return out

    monkeypatch.setattr(simhash, "materialize", counted)
    want, pairs = _exact_classes(rows)
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicate_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want and len(pairs) > 1000
    assert max(written) < 40 * len(rows), written


def test_joined_tries_every_link_of_a_cell():
    """Spanning edges of one cell against all pairs, classes joined before and links ruled out included."""
    rng = np.random.default_rng(6)
    pool = rng.integers(0, 1 << 63, 60).astype(np.uint64)
    sets = [np.unique(rng.choice(pool, int(rng.integers(0, 50)))) for _ in range(40)] + [np.unique(np.append(pool[k : k + 20], pool[:k])) for k in range(30)]
    root, far = np.arange(len(sets)) // 2 + 500, rng.choice(np.array([3, simhash.NO_LINK], dtype=np.uint16), (len(sets), len(sets)))
    far = np.minimum(far, far.T)
    pairs = [(int(root[i]), int(root[j])) for i in range(len(sets)) for j in range(i) if far[i, j] != simhash.NO_LINK and len(both := np.intersect1d(sets[i], sets[j])) and len(both) >= 0.8 * len(np.union1d(sets[i], sets[j]))]
    u, v = simhash._joined(sets, root, far, 0.8)
    ids = sorted(set(map(int, root)))
    assert len(pairs) > 20 and ref.classes(ids, list(zip(map(int, u), map(int, v)))) == ref.classes(ids, pairs)


def test_near_duplicate_filter_keeps_pairs_at_the_similarity():
    """Fingerprints of sets at exactly 0.8, few shingles or many, stay inside the distance filter."""
    rng = np.random.default_rng(8)
    for common, more in ((4, 1), (8, 2), (40, 10), (400, 100)):
        h = [rng.integers(0, 1 << 63, common + more).astype(np.uint64) for _ in range(1500)]
        far = [int(np.bitwise_count(simhash.wide_fingerprint(x) ^ simhash.wide_fingerprint(x[:common])).sum()) for x in h]
        assert np.mean(np.array(far) > simhash.max_bits(0.8)) < 0.001


def test_near_duplicates_ignore_how_often_a_line_repeats(spark):
    """Shingle sets count, not how often a shingle occurs."""
    rng = np.random.default_rng(9)
    words = ["".join(rng.choice(list("abcdefghij"), 7)) for _ in range(230)]
    rows = [(1, " ".join(words)), (2, " ".join(words + words[:20] * 80))]
    assert _exact_classes(rows)[0] == {1: 1, 2: 1}
    assert [r["doc_id"] for r in simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()] == [1]


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)] + [(5, 5)]
    got = {r["node"]: r["root"] for r in common.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    groups = defaultdict(set)
    for n, r in got.items():
        groups[r].add(n)
    assert sorted(map(len, groups.values())) == [201, 300]
    assert common.components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_sharding(documents, awkward, empty):
    for docs in (documents, awkward):
        got = sharding.shard_rows(docs, per_partition=60).collect()
        text = texts_of(docs)
        assert Counter(r["doc_id"] for r in got) == Counter(text.keys())
        for r in got:
            raw = (text[r["doc_id"]] or "").encode()
            assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 1, zlib.crc32(raw), "rows", None)
        by = defaultdict(list)
        for r in got:
            by[r["shard"]].append(r["slot"])
        assert max(map(len, by.values())) - min([len(by[s]) for s in range(16)]) <= 1
        assert all(sorted(v) == list(range(len(v))) for v in by.values())
    assert sharding.shard_rows(empty).count() == 0


def test_sharding_is_uniform_for_equal_rows_and_follows_the_matrix(spark):
    """Hundreds of equal rows spread over shards and slots like any; the cuts of a replay from the same matrix give the same shards."""
    import xxhash

    rows = [(7, "same")] * 800 + [(i, f"text {i}") for i in range(1000, 4200)]
    got = sharding.shard_rows(spark.createDataFrame(rows, "doc_id long, text string").repartition(5), per_partition=700).collect()
    same = [r for r in got if r["doc_id"] == 7]
    by = Counter(r["shard"] for r in same)
    assert sum((by[s] - 50) ** 2 / 50 for s in range(16)) < 45  # chi-square, 15 degrees of freedom
    halves = Counter(r["slot"] * 4 // 250 for r in same)
    assert sum((halves[q] - 200) ** 2 / 200 for q in range(4)) < 25

    def spark_hash(*values):
        h = 42
        for v in values:
            h = xxhash.xxh64_intdigest((v % 2**64).to_bytes(8, "little") if not isinstance(v, np.int32) else int(v).to_bytes(4, "little", signed=True), h)
        return h - 2**64 if h >= 2**63 else h

    seed, parts = 11, -(-4000 // 700)
    count, keyed = Counter(), []
    for i, t in rows:
        crc, size = zlib.crc32(t.encode()), len(t) + 1
        h = spark_hash(np.int32(seed), i, crc, size)
        keyed.append((spark_hash(np.int32(seed + 3), h, count[h]), i))
        count[h] += 1
    matrix = sharding.communication_matrix([sum(h % parts == p for h, _ in keyed) for p in range(parts)], 16, seed)
    want = Counter()
    for p in range(parts):
        own = sorted((spark_hash(np.int32(seed + 1), h), i) for h, i in keyed if h % parts == p)
        for r, (_, i) in enumerate(own):
            want[(i, int(np.searchsorted(np.cumsum(matrix[p]), r, side="right")))] += 1
    assert want == Counter((r["doc_id"], r["shard"]) for r in got)


def test_communication_matrix():
    m = np.array(sharding.communication_matrix([100, 0, 37, 5000], 16, 1))
    assert m.sum(1).tolist() == [100, 0, 37, 5000] and m.sum(0).max() - m.sum(0).min() <= 1
    rng = np.random.default_rng(0)
    big = [sharding.hypergeometric(rng, 3_000_000_000, 9_000_000_000, 1000) for _ in range(300)]
    assert 240 < np.mean(big) < 260 and 9 < np.std(big) < 19


@pytest.mark.parametrize("which", ["documents", "awkward"])
def test_bpe(which, request):
    import tiktoken

    docs = request.getfixturevalue(which)
    path, pattern = bpe.default_vocabulary()
    exact = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=bpe.codec(path, pattern).ranks, special_tokens={})
    text = texts_of(docs)
    for r in bpe.encode_digests(docs).collect():
        ids = exact.encode_ordinary(text[r["doc_id"]] or "")
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == ref.sha(np.array(ids, dtype="<u4").tobytes())
        assert r["decoded_sha256"] == ref.sha(text[r["doc_id"]] or "")


@pytest.mark.parametrize("which", ["documents", "awkward"])
def test_packing(which, request):
    from tokenizers import Tokenizer

    docs = request.getfixturevalue(which)
    full = Tokenizer.from_file(packing.default_tokenizer()[0])
    full.encode_special_tokens = True
    got = packing.pack_documents(docs).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append((r["offset"], r["length"]))
    text = texts_of(docs)
    assert by_doc.keys() == text.keys()
    total, single = 0, Counter()
    for i, rows in by_doc.items():
        ids = np.array(full.encode(text[i] or "", add_special_tokens=False).ids + [2], dtype="<u4")
        rows.sort(key=lambda r: r["piece"])
        assert [(r["start"], r["length"]) for r in rows] == packing.cut(len(ids), 1024) and sum(r["length"] for r in rows) == len(ids)
        assert all(r["length"] == 1024 for r in rows[1:])
        assert all(r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes()) for r in rows)
        total += len(ids)
        single.update(r["length"] for r in rows)
    for v in by_seq.values():
        v.sort()
        assert [o for o, _ in v] == [0, *np.cumsum([n for _, n in v])[:-1].tolist()] and sum(n for _, n in v) <= 1024
    free: list[int] = []  # best-fit decreasing, one piece at a time
    for n in sorted(single.elements(), reverse=True):
        fit = [g for g in free if g >= n]
        g = min(fit) if fit else 1024
        if fit:
            free.remove(g)
        free.append(g - n)
    assert len(by_seq) <= len(free)
    assert len(by_seq) <= -(-total // 1024) * 1.02 + 2


def test_embeddings(spark):
    rows = [(r["vec_id"], r["embedding"], r["label"]) for r in spark.read.parquet(f"{SF}/embeddings.parquet").select("vec_id", "embedding", "label").collect()]
    rng = np.random.default_rng(2)
    for k in range(60):
        src = rows[k % 7]
        rows.append((10_000 + k, [float(x + rng.normal() * 0.012) for x in src[1]], src[2]))
    rows += [(20_000, rows[0][1], rows[0][2]), (20_001, rows[0][1], None), (20_002, None, 1), (20_003, [0.0] * 64, 1), (20_004, [float("nan")] * 64, 1), (20_005, [float("inf")] + [1.0] * 63, 1), (20_006, [None] + [1.0] * 63, 1), (20_007, [], 1), (20_008, [2 * x for x in rows[0][1]], rows[0][2]), (20_009, rows[0][1][:32], rows[0][2])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    rows = [(r["vec_id"], r["embedding"], r["label"]) for r in df.collect()]
    want = ref.links(rows)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddings.near_duplicate_links(df).collect()}
    assert got == want
    assert embeddings.near_duplicate_links(df.limit(0)).count() == 0


def auc(score, y):
    order = np.argsort(score)
    rank = np.empty(len(score))
    rank[order] = np.arange(1, len(score) + 1)
    y = np.array(y, bool)
    return (rank[y].sum() - y.sum() * (y.sum() + 1) / 2) / (y.sum() * (~y).sum())


@pytest.mark.parametrize("query, column, least", [(queries.op3_quality_classifier, "quality", 0.99), (queries.op6_toxicity, "toxic", 0.9)])
def test_classifiers_on_held_out_rows(spark, query, column, least):
    sf = "/root/testdata/sf0.1"
    got = query(spark, sf)
    labels = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", column)
    rows = got.where("held_out").join(labels, "doc_id").collect()
    assert all(ref.held(r["doc_id"]) for r in rows)
    assert auc([r["score"] for r in rows], [r[column] for r in rows]) >= least
    assert np.mean([r["predicted"] == r[column] for r in rows]) >= 0.95


def test_classifiers_on_awkward_rows(awkward, empty, spark):
    labels = spark.createDataFrame([(i, i % 2, i % 2) for i in range(len(AWKWARD))] + [(None, 1, None)], "doc_id long, quality int, toxic int")
    for module in (quality_model, toxicity):
        column = "quality" if module is quality_model else "toxic"
        for known in (labels, labels.limit(0), labels.where("quality = 1")):
            model = module.fit(awkward, known, column)
            rows = module.scored(awkward.select("doc_id", "text"), model, ["doc_id"]).collect()
            assert len(rows) == len(AWKWARD) and all(0 <= r["score"] <= 1 for r in rows)
        assert module.scored(empty.select("doc_id", "text"), model, ["doc_id"]).count() == 0


def test_scores_do_not_depend_on_chunks():
    rng = np.random.default_rng(0)
    w = rng.normal(size=1 << quality_model.BUCKET_BITS).astype(np.float32)
    text = " ".join("".join(rng.choice(list("abcé"), 5)) for _ in range(4000))
    count = lambda chunk: Counter(np.concatenate(list(quality_model.feature_chunks(text, chunk))).tolist())
    assert count(1 << 20) == count(1000) == count(97)
    assert 0 <= quality_model.score(text, w, 0.0) <= 1


@pytest.mark.parametrize("which", ["documents", "awkward"])
def test_quality_rules(which, request):
    docs = request.getfixturevalue(which)
    text = texts_of(docs)
    got = quality_rules.quality_report(docs).collect()
    assert len(got) == len(text)
    for r in got:
        n, chars, sym, dup, rep = ref.quality_counts(text[r["doc_id"]])
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, sym, dup, rep)
        assert r["base_failed"] == (n < 10 or 100 * rep > 20 * n)
        assert not (r["base_failed"] and r["kept"])
    assert quality_rules.keep_good(docs).columns == docs.columns
    assert quality_rules.keep_good(docs).count() == sum(r["kept"] for r in got)


def test_quality_thresholds_follow_their_group(spark):
    """The same share is usual in one group and far out in another; a group without a break in its tail loses nothing."""
    word = lambda i: "".join(chr(97 + (i * k + k * k) % 26) for k in range(3, 9))
    plain = lambda i, n: " ".join(word(i * 50 + k) for k in range(n))
    shout = lambda i: plain(i, 20).upper()
    rows = [(i, plain(i, 20), "en", "calm") for i in range(95)] + [(95 + i, shout(i), "en", "calm") for i in range(5)]
    rows += [(200 + i, shout(i), "en", "loud") for i in range(100)]
    rows += [(400 + i, plain(i, 20), "de", None) for i in range(40)] + [(500, shout(0), "xx", "alone")]
    kept = {r["doc_id"]: r["kept"] for r in quality_rules.quality_report(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert not any(kept[95 + i] for i in range(5)) and all(kept[i] for i in range(95))
    assert all(kept[200 + i] for i in range(100)) and all(kept[400 + i] for i in range(40)) and kept[500]


def test_sampled_rows_are_not_chosen_by_length(spark):
    """Long labelled texts are fitted like short ones; the bound on bytes cuts the order by hash, never a text."""
    docs = spark.createDataFrame([(i, "x" * (200_000 if i % 2 else 20)) for i in range(60)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int")
    free = [i for i in range(60) if not ref.held(i)]
    got = quality_model.labelled_sample(docs, labels, "quality", 4000, 1 << 30)
    assert sorted(len(t) for t, _ in got) == sorted(200_000 if i % 2 else 20 for i in free)
    some = quality_model.labelled_sample(docs, labels, "quality", 4000, 1_000_000)
    assert some == got[: len(some)] and 0 < len(some) < len(got) and sum(len(t) for t, _ in some) <= 1_000_000
    assert len(quality_model.labelled_sample(docs, labels, "quality", 4000, 1)) == 1


def test_scores_are_averages_and_sums():
    """The scores against a plain average of bucket weights and a plain logistic sum of term weights."""
    rng = np.random.default_rng(6)
    w = rng.normal(size=1 << quality_model.BUCKET_BITS).astype(np.float32)
    text = "Ein Wort zwei zwei Wörter, drei"
    ids = np.concatenate(list(quality_model.feature_chunks(text)))
    assert abs(quality_model.score(text, w, 0.3) - 1 / (1 + np.exp(-(0.3 + w[ids].astype(float).mean())))) < 1e-9
    weights = {"=zwei": 1.5, "^wör": -0.5, "=fehlt": 9.0}
    assert abs(toxicity.score(text, weights, -0.2) - 1 / (1 + np.exp(-(-0.2 + 1.5 - 0.5)))) < 1e-12


def test_rank_tokenizer_equals_json_tokenizer_below_the_bound():
    """Every code point for which the faster library stands in, alone, in words, beside digits and spaces, and special strings."""
    from tokenizers import Tokenizer

    paths = packing.default_tokenizer()
    full = Tokenizer.from_file(paths[0])
    full.encode_special_tokens = True
    texts = [f"a{chr(c)}b {chr(c)} 1{chr(c)}2 {chr(c)}{chr(c)}'s\n{chr(c)}\t {chr(c)}." for c in range(ord(packing.SAME_TABLES_BELOW))] + ["a <|endoftext|> b", "<|endoftext|>"]
    for t in texts:
        assert packing.token_ids(t, paths).tolist() == full.encode(t, add_special_tokens=False).ids, repr(t)


def test_very_long_texts(spark):
    """A text beyond a million characters and beyond the chunk of shingles goes through the operators whole."""
    import tiktoken

    rng = np.random.default_rng(12)
    text = " ".join("".join(rng.choice(list("abcdeé"), 6)) for _ in range(170_000))
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    assert len(text) > 1_150_000
    path, pattern = bpe.default_vocabulary()
    exact = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=bpe.codec(path, pattern).ranks, special_tokens={})
    assert bpe.encode_digests(docs).first()["ids_sha256"] == ref.sha(np.array(exact.encode_ordinary(text), dtype="<u4").tobytes())
    assert int(simhash.fingerprint_classes(docs).first()["fingerprint"], 16) == ref.fingerprint(text)


def test_results_replace_columns_of_their_names(awkward, spark):
    """Kept columns named like a result give way to it."""
    model = quality_model.fit(awkward, spark.createDataFrame([(3, 1), (4, 0)], "doc_id long, quality int"))
    got = quality_model.scored(awkward, model, awkward.columns)
    assert got.columns.count("score") == 1 and got.where("score = 0.5").count() < len(AWKWARD)
    assert bpe.encode_documents(awkward.withColumnRenamed("fp", "token_ids")).columns.count("token_ids") == 1


def test_work_tables_need_a_shared_folder():
    """On a cluster without a named folder nothing is written to a local one."""
    class Session:
        class conf:  # noqa: N801
            get = staticmethod(lambda *a: None)

        class sparkContext:  # noqa: N801
            master = "spark://host:7077"

    with pytest.raises(ValueError):
        common.shared_folder(Session)


def test_empty_tables(empty):
    assert pii.span_digests(empty).count() == 0
    assert simhash.fingerprint_classes(empty).count() == 0
    assert simhash.drop_near_duplicates(empty).count() == 0
    assert packing.pack_documents(empty).count() == 0
    assert bpe.encode_digests(empty).count() == 0
    assert quality_rules.quality_report(empty).count() == 0
    assert pii.sanitise_documents(empty).columns == empty.columns


def test_repeated_rows_and_clashing_columns(awkward):
    twice = awkward.union(awkward)
    assert pii.span_digests(twice).count() == simhash.fingerprint_classes(twice).count() == sharding.shard_rows(twice).count() == 2 * len(AWKWARD)
    assert packing.pack_documents(twice).groupBy("sequence_id").sum("length").where("`sum(length)` > 1024").count() == 0
    assert pii.sanitise_documents(twice).count() == 2 * len(AWKWARD)


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = common.materialize(stage(spark, before, SF))
        assert after.columns == docs.columns and after.count() <= before.count()
        assert after.select("doc_id").distinct().count() == after.count()
        before = after
    packed = corpus_pipeline.STAGES[-1][1](spark, before, SF)
    assert packed.select("doc_id").distinct().count() == before.count()
    assert set(spark.createDataFrame([Row(x=1)]).columns) == {"x"}
