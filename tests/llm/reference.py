"""Plain single-machine versions of the operators, written apart from them, to compare with."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import xxhash

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def base_spans(text: str | None) -> dict[str, list[tuple[int, int]]]:
    text = text or ""
    only = lambda m: re.sub("[^0-9]", "", m[0])
    return {
        "email": [m.span() for m in EMAIL.finditer(text)],
        "ip": [m.span() for m in IP.finditer(text) if all(int(p) <= 255 for p in m[0].split("."))],
        "card": [m.span() for m in CARD.finditer(text) if 16 <= len(only(m)) <= 19 and luhn(only(m))],
        "phone": [m.span() for m in PHONE.finditer(text) if 8 <= len(only(m)) <= 15],
    }


def span_string(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, v in spans.items() for a, b in v)


def words_of(text: str) -> set[str]:
    import regex

    return {w.lower() for w in regex.findall(r"\p{L}{3,}", EMAIL.sub(" ", text))}


def sanitised(texts: list[str | None], generalise_at: float = 0.8, remove_at: float = 0.9, support: int = 5) -> dict[str, tuple[list, str | None]]:
    """text -> (spans of terms, clean text or None) by counting everything in plain loops."""
    import math

    import regex

    texts = [t or "" for t in texts]
    n, rows = len(texts), Counter(texts)
    spans = {t: base_spans(t) for t in rows}
    units = {t: {k for k, v in spans[t].items() if v} | {(k, t[a:b]) for k, v in spans[t].items() for a, b in v} for t in rows}
    df = Counter(w for t, m in rows.items() for w in words_of(t) for _ in range(m))
    nc, held = Counter(), defaultdict(set)
    for t in rows:
        for u in units[t]:
            nc[u] += rows[t]
            held[u].add(t)
    level: dict = {}
    for u, own in held.items():
        if len(own) < support:
            continue
        beside = Counter(w for t in own for w in words_of(t))
        for w, different in beside.items():
            together = sum(rows[t] for t in own if w in words_of(t))
            pmi, ic = math.log2(n * together / (nc[u] * df[w])), math.log2(n / nc[u])
            if different >= support and ic > 0 and pmi >= generalise_at * ic:
                level[(w, u)] = 2 if pmi >= remove_at * ic else 1
    flagged = {w for w, _ in level}

    def new(w, lv):
        fit = [w[:k] for k in range(3, len(w)) if w[:k] in df and w[:k] not in flagged and df[w[:k]] >= 2 * df[w]]
        return "" if lv == 2 else (fit[-1] if fit else "[TERM]")

    out = {}
    for t in rows:
        mine = {}
        for (w, u), lv in level.items():
            if u in units[t] or lv == 2:
                mine[w] = max(mine.get(w, 0), lv)
        base = sorted((a, b, f"[{k.upper()}]") for k, v in spans[t].items() for a, b in v)
        terms = [(m.start(), m.end(), new(m[0].lower(), mine[m[0].lower()])) for m in regex.finditer(r"\p{L}{3,}", t) if m[0].lower() in mine]
        terms = [x for x in terms if not any(a < x[1] and x[0] < b for a, b, _ in base)]
        clean, at = "", 0
        for a, b, tag in sorted(base + terms):
            if a >= at:
                clean += t[at:a] + tag
            at = max(at, b)
        out[t] = ([x[:2] for x in terms], clean + t[at:] if base or terms else None)
    return out


def sha(text: str | bytes) -> str:
    return hashlib.sha256(text.encode() if isinstance(text, str) else text).hexdigest()


def fingerprint(text: str | None, width: int = 3) -> int:
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    grams = [" ".join(words[i : i + width]) for i in range(len(words) - width + 1)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def classes(ids: list, linked) -> dict:
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in linked:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def simhash_classes(docs: dict[int, str | None]) -> dict[int, tuple[str, int]]:
    fp = {i: fingerprint(t) for i, t in docs.items()}
    ids = sorted(fp)
    v = np.array([fp[i] for i in ids], dtype=np.uint64)
    pairs = []
    for k in range(len(ids)):
        near = np.nonzero(np.bitwise_count(v[k] ^ v[k + 1 :]) <= 2)[0]
        pairs += [(ids[k], ids[k + 1 + j]) for j in near]
    comp = classes(ids, pairs)
    return {i: (f"{fp[i]:016x}", comp[i]) for i in ids}


def repeat_words(words: list[str]) -> int:
    at = defaultdict(list)
    for i in range(len(words) - 4):
        at[tuple(words[i : i + 5])].append(i)
    return len({j for v in at.values() if len(v) > 1 for i in v for j in range(i, i + 5)})


def quality_counts(text: str | None) -> tuple[int, int, int, int, int]:
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, repeat_words(words)


def held(doc_id) -> bool:
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 5 == 0


def links(rows: list[tuple], threshold: float = 0.98) -> dict[int, tuple[int, int]]:
    """vec_id -> (n_links, component_id) by all pairs of unique ids."""
    ok = [(i, np.array(v, float), y) for i, v, y in rows if y is not None and v is not None and all(x is not None for x in v) and np.isfinite(np.array(v, float)).all() and np.any(np.array(v, float))]
    count, pairs = Counter(), []
    for a in range(len(ok)):
        for b in range(a):
            (i, x, p), (j, y, q) = ok[a], ok[b]
            if p == q and len(x) == len(y) and x @ y / np.sqrt((x @ x) * (y @ y)) >= threshold:
                count[i] += 1
                count[j] += 1
                pairs.append((i, j))
    comp = classes([r[0] for r in rows], pairs)
    return {r[0]: (count[r[0]], comp[r[0]]) for r in rows}
