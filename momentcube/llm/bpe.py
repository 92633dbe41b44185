"""Byte-level BPE by two tiers: a minimal perfect hash over the vocabulary, then a heap over linked bytes.

Tier 1 resolves all pre-tokens of a batch at once: a polynomial hash of every pre-token comes from prefix
sums over the batch's bytes, a displacement table sends it to its only possible slot, and the slot's bytes are
compared with the pre-token's. Tier 2 merges the bytes of the pre-tokens that are no vocabulary entries.

Inputs: null text counts as empty; an empty text gives no ids. Any text is encoded whole.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from array import array
from functools import lru_cache
from itertools import chain

import numpy as np
import regex
from pyspark.sql import DataFrame, types as T

from .common import map_rows, texts

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Merged forms of rare pre-tokens kept per worker; older ones go when it is full.
REMEMBERED = 600_000


def _mix(x: np.ndarray, salt) -> np.ndarray:
    x = x ^ (_U(salt) if np.isscalar(salt) else salt)
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def _powers(base: int, n: int) -> np.ndarray:
    out = np.ones(max(n, 1), dtype=_U)
    if n > 1:
        out[1:] = _U(base)
        with np.errstate(over="ignore"):
            np.multiply.accumulate(out, out=out)
    return out


class SpanHasher:
    """64-bit hashes of byte spans of one buffer; equal spans give equal hashes wherever they lie.

    Buffers are taken in windows so that memory stays bounded; spans never cross a window.
    """

    def __init__(self, window: int = 1 << 20):
        self.window = window
        self.up, self.down = _powers(_BASE, window + 1), _powers(_INVERSE, window + 1)

    def __call__(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        n = len(data)
        if n > self.window:
            self.__init__(n)
        prefix = np.zeros(n + 1, dtype=_U)
        np.cumsum((data.astype(_U) + _U(1)) * self.up[:n], out=prefix[1:])
        return (prefix[ends] - prefix[starts]) * self.down[starts] + (ends - starts).astype(_U) * _U(0xD6E8FEB86659FD93)


class PerfectHash:
    """Minimal perfect hash of distinct byte strings, by displaced buckets placed largest first."""

    def __init__(self, keys: list[bytes], values: list[int], per_bucket: int = 4):
        n = len(keys)
        blob = np.frombuffer(b"".join(keys), dtype=np.uint8)
        ends = np.cumsum([len(k) for k in keys])
        starts = ends - np.array([len(k) for k in keys])
        self.hasher = SpanHasher()
        h = self.hasher(blob, starts, ends)
        if len(np.unique(h)) != n:
            raise ValueError("two keys share a 64-bit hash")
        self.n, self.buckets = n, max(1, -(-n // per_bucket))
        bucket = (_mix(h, 1) % _U(self.buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        counts = np.bincount(bucket, minlength=self.buckets)
        first = np.cumsum(counts) - counts
        self.shift = np.zeros(self.buckets, dtype=_U)
        slot_of = np.full(n, -1, dtype=np.int64)
        free = np.ones(n, dtype=bool)
        for b in np.argsort(-counts, kind="stable"):
            if not counts[b]:
                break
            members = order[first[b] : first[b] + counts[b]]
            own = h[members]
            trial, width = 1, 64
            while True:
                salts = np.arange(trial, trial + width, dtype=_U) * _U(0x2545F4914F6CDD1D)
                slots = (_mix(own[None, :], salts[:, None]) % _U(n)).astype(np.int64)
                good = free[slots].all(axis=1)
                if len(members) > 1:
                    ranked = np.sort(slots, axis=1)
                    good &= (ranked[:, 1:] != ranked[:, :-1]).all(axis=1)
                if good.any():
                    k = int(good.argmax())
                    self.shift[b], slot_of[members], free[slots[k]] = salts[k], slots[k], False
                    break
                trial, width = trial + width, min(width * 2, 1 << 14)
        at = np.empty(n, dtype=np.int64)
        at[slot_of] = np.arange(n)
        self.blob, self.start, self.length = blob, starts[at], (ends - starts)[at]
        self.value = np.array(values, dtype=np.int64)[at]

    def find(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The value of every span, -1 where the span is no key; bytes are compared, so hits are certain."""
        h = self.hasher(data, starts, ends)
        slot = (_mix(h, self.shift[(_mix(h, 1) % _U(self.buckets)).astype(np.int64)]) % _U(self.n)).astype(np.int64)
        length = ends - starts
        same = np.nonzero(self.length[slot] == length)[0]
        out = np.full(len(starts), -1, dtype=np.int64)
        if len(same):
            size = length[same]
            begin = np.cumsum(size) - size
            step = np.arange(int(size.sum()))
            equal = data[np.repeat(starts[same] - begin, size) + step] == self.blob[np.repeat(self.start[slot[same]] - begin, size) + step]
            hit = same[np.logical_and.reduceat(equal, begin)]
            out[hit] = self.value[slot[hit]]
        return out


def pair_table(ranks: dict[bytes, int]) -> dict[int, int]:
    """(left id, right id) packed in one number -> id of the two together, for every split of every entry."""
    return {(ranks[w[:i]] << 32) | ranks[w[i:]]: r for w, r in ranks.items() for i in range(1, len(w)) if w[:i] in ranks and w[i:] in ranks}


def merge_bytes(piece: bytes, single: list[int], pairs: dict[int, int]) -> list[int]:
    """Ids of one pre-token: the lowest-ranked adjacent pair (leftmost on ties) merges first, by a heap over linked bytes."""
    part = [single[b] for b in piece]
    n = len(part)
    get = pairs.get
    rank = [get((part[i] << 32) | part[i + 1], -1) for i in range(n - 1)]
    rank.append(-1)
    heap = [(r << 32) | i for i, r in enumerate(rank) if r >= 0]
    if not heap:
        return part
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heapq.heapify(heap)
    pop, push = heapq.heappop, heapq.heappush
    while heap:
        top = pop(heap)
        i, r = top & 0xFFFFFFFF, top >> 32
        if rank[i] != r:
            continue
        part[i] = r
        j = after[i]
        k = after[i] = after[j]
        rank[j] = -1
        if k < n:
            before[k] = i
            new = rank[i] = get((r << 32) | part[k], -1)
            if new >= 0:
                push(heap, (new << 32) | i)
        else:
            rank[i] = -1
        p = before[i]
        if p >= 0:
            new = rank[p] = get((part[p] << 32) | r, -1)
            if new >= 0:
                push(heap, (new << 32) | p)
    out, i = [], 0
    while i < n:
        out.append(part[i])
        i = after[i]
    return out


def _gather(blob: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The spans of a blob one after another."""
    ends = np.cumsum(lengths)
    return blob[np.repeat(starts - (ends - lengths), lengths) + np.arange(int(ends[-1]) if len(ends) else 0)]


_CUT = regex.compile(r"\S(?=\s)")


def windows(text: str, size: int = 1 << 20) -> list[str]:
    """A text in parts of about ``size`` characters, cut before white space, where no pre-token of the pattern runs across."""
    out, at = [], 0
    while len(text) - at > size and (m := _CUT.search(text, at + size)):
        out.append(text[at : m.end()])
        at = m.end()
    return [*out, text[at:]]


class Codec:
    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            pairs = [line.split() for line in f if line.strip()]
        self.ranks = {base64.b64decode(a): int(b) for a, b in pairs}
        self.split = regex.compile(pattern)
        self.table = PerfectHash(list(self.ranks), list(self.ranks.values()))
        words = [w for w, _ in sorted(self.ranks.items(), key=lambda x: x[1])]
        self.width = np.zeros(max(self.ranks.values()) + 1, dtype=np.int64)
        self.width[list(self.ranks.values())] = [len(w) for w in self.ranks]
        self.place = np.cumsum(self.width) - self.width
        self.blob = np.frombuffer(b"".join(words), dtype=np.uint8)
        self.single = [self.ranks[bytes([b])] for b in range(256)]
        self.pairs = pair_table(self.ranks)
        self.rare: dict[bytes, bytes] = {}

    def encode_batch(self, batch: list[str], budget: int = 1 << 20) -> list[np.ndarray]:
        """Ids (uint32) of every text. Parts of texts are taken together up to ``budget`` characters for tier 1."""
        parts = [(i, w) for i, t in enumerate(batch) for w in windows(t, budget)]
        done: list[np.ndarray] = []
        group, size = [], 0
        for _, w in parts:
            group.append(w)
            size += len(w)
            if size >= budget:
                done += self._encode(group)
                group, size = [], 0
        done += self._encode(group) if group else []
        if len(parts) == len(batch):
            return done
        own: list[list[np.ndarray]] = [[] for _ in batch]
        for (i, _), ids in zip(parts, done):
            own[i].append(ids)
        return [np.concatenate(x) for x in own]

    def _merged(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of each pre-token as packed 32-bit numbers."""
        rare, out = self.rare, []
        for piece in pieces:
            ids = rare.get(piece)
            if ids is None:
                ids = array("I", merge_bytes(piece, self.single, self.pairs)).tobytes()
                if len(piece) <= 64:
                    if len(rare) >= REMEMBERED:
                        rare.clear()
                    rare[piece] = ids
            out.append(ids)
        return out

    def _encode(self, group: list[str]) -> list[np.ndarray]:
        pieces = [self.split.findall(t) for t in group]
        many = [len(p) for p in pieces]
        count = sum(many)
        if not count:
            return [np.empty(0, dtype=np.uint32) for _ in group]
        length = np.fromiter(chain.from_iterable(map(len, ps) for ps in pieces), dtype=np.int64, count=count)
        joined = "".join(group)
        raw = joined.encode()
        ends = np.cumsum(length)
        if len(raw) != len(joined):  # the pieces cover the text: byte ends follow from the widths of the code points
            code = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
            ends = np.cumsum(1 + (code >= 0x80).astype(np.int8) + (code >= 0x800) + (code >= 0x10000), dtype=np.int64)[ends - 1]
            length = np.diff(ends, prepend=0)
        data, starts = np.frombuffer(raw, dtype=np.uint8), ends - length
        found = self.table.find(data, starts, ends)
        sizes = np.ones(count, dtype=np.int64)
        missing = np.nonzero(found < 0)[0]
        if len(missing):
            # equal misses are merged once: grouped by hash, then compared byte by byte with their first
            _, first, same = np.unique(self.table.hasher(data, starts[missing], ends[missing]), return_index=True, return_inverse=True)
            head = missing[first][same]
            alike = length[head] == length[missing]
            alike[alike] = self._equal(data, starts[head[alike]], starts[missing[alike]], length[missing[alike]])
            if not alike.all():
                first, same = np.arange(len(missing)), np.arange(len(missing))
            lists = self._merged([raw[a:b] for a, b in zip(starts[missing[first]].tolist(), ends[missing[first]].tolist())])
            widths = np.fromiter(map(len, lists), dtype=np.int64, count=len(lists)) // 4
            flat = np.frombuffer(b"".join(lists), dtype=np.uint32)
            sizes[missing] = widths[same]
        stop = np.cumsum(sizes)
        ids = np.empty(int(stop[-1]), dtype=np.uint32)
        known = found >= 0
        ids[(stop - sizes)[known]] = found[known]
        if len(missing):
            ids[np.repeat(~known, sizes)] = _gather(flat, (np.cumsum(widths) - widths)[same], widths[same])
        bounds = np.concatenate([[0], stop])[np.cumsum([0, *many])]
        return [ids[a:b] for a, b in zip(bounds[:-1], bounds[1:])]

    @staticmethod
    def _equal(data, a, b, length) -> np.ndarray:
        if not len(a):
            return np.empty(0, dtype=bool)
        begin = np.cumsum(length) - length
        step = np.arange(int(length.sum())) - np.repeat(begin, length)
        return np.logical_and.reduceat(data[np.repeat(a, length) + step] == data[np.repeat(b, length) + step], begin)

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(_gather(self.blob, self.place[part], self.width[part]).tobytes() for part in np.array_split(ids, max(1, len(ids) >> 18)))


@lru_cache(maxsize=4)
def codec(path: str, pattern: str) -> Codec:
    """One codec for each worker process; the vocabulary is read where it is installed and is of fixed size."""
    return Codec(path, pattern)


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def encode_documents(docs: DataFrame, vocabulary: tuple[str, str] | None = None, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Rows with their ids (array<int>) added."""
    path, pattern = vocabulary or default_vocabulary()

    def add(batch):
        return {"token_ids": [x.astype(np.int32) for x in codec(path, pattern).encode_batch(texts(batch, text))]}

    return map_rows(docs, add, [T.StructField("token_ids", T.ArrayType(T.IntegerType()))], keep)


def encode_digests(docs: DataFrame, vocabulary: tuple[str, str] | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every text: encoded, then decoded from the ids."""
    path, pattern = vocabulary or default_vocabulary()

    def add(batch):
        c = codec(path, pattern)
        out = {"n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
        for ids in c.encode_batch(texts(batch)):
            out["n_tokens"].append(len(ids))
            out["ids_sha256"].append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
            out["decoded_sha256"].append(hashlib.sha256(c.decode(ids)).hexdigest())
        return out

    fields = [T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    return map_rows(docs.select("doc_id", "text"), add, fields, keep=["doc_id"])
