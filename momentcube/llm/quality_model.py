"""Quality classifier: supervised subword embeddings in numpy.

Whole words, byte n-grams (3 and 4 bytes, none across white space) and a mark for each word that repeats the word before it are hashed
into buckets; a document is the average of its
buckets' learned vectors; a softmax layer follows; both are trained by stochastic gradient descent. The output is linear in the
average, so scoring needs one number for each bucket: a gather and a mean.

Fitting reads a bounded sample: of the labelled rows that may be learned from, those with the least hash of their id, ``SAMPLE_ROWS`` rows and
``SAMPLE_BYTES`` of text at most; no row is left out for its length alone. Scoring reads every text whole. Null and empty texts get the average
score of no evidence (the bias alone); without any labels all scores are 0.5. Repeated rows are scored each; an empty table gives an empty
table; kept columns named like a result give way to it.
"""

from __future__ import annotations

import zlib
from operator import eq

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from .common import held_out, map_rows, texts

BUCKET_BITS, DIM, SAMPLE_ROWS, SAMPLE_BYTES, EPOCHS, RATE = 17, 12, 4000, 48 << 20, 8, 2.0
REPEATS = 12_345


def _ngrams(b: np.ndarray) -> list[np.ndarray]:
    x = b.astype(np.uint32)
    space = b == 32
    shift = np.uint32(32 - BUCKET_BITS)
    g3 = x[:-2] | (x[1:-1] << np.uint32(8)) | (x[2:] << np.uint32(16))
    k3 = ~space[1:-1]
    g4 = g3[:-1] | (x[3:] << np.uint32(24))
    k4 = k3[:-1] & ~space[2:-1]
    return [((g3[k3] + np.uint32(0x51ED270B)) * np.uint32(0x9E3779B1)) >> shift, ((g4[k4] ^ np.uint32(0x2F0B4C47)) * np.uint32(0x85EBCA6B)) >> shift]


def feature_chunks(text: str, chunk: int = 1 << 18):
    """Bucket numbers of a whole text, some at a time."""
    words = text.encode().split()
    for i in range(0, len(words), chunk // 4):
        part = words[i : i + chunk // 4]
        h = np.fromiter(map(zlib.crc32, part), dtype=np.uint32, count=len(part))
        yield (h * np.uint32(0xC2B2AE35)) >> np.uint32(32 - BUCKET_BITS)
        again = np.fromiter(map(eq, words[i : i + chunk // 4], words[i + 1 : i + chunk // 4 + 1]), dtype=bool)
        yield np.full(4 * int(again.sum()), REPEATS, dtype=np.uint32)
    joined = b" " + b" ".join(words) + b" "
    for i in range(0, len(joined), chunk):
        b = np.frombuffer(joined[i : i + chunk + 3], dtype=np.uint8)
        if len(b) < 4:
            continue
        g3, g4 = _ngrams(b)
        # the last chunk keeps all; others leave what the next one starts with
        if i + chunk + 3 < len(joined):
            g3 = _ngrams(b[:-1])[0]
        yield g3
        yield g4


def train(sample: list[tuple[str, int]], seed: int = 3, epochs: int = EPOCHS, rate: float = RATE) -> tuple[np.ndarray, float]:
    """(weight of each bucket, bias) of the log-odds of label 1."""
    size = 1 << BUCKET_BITS
    labels = np.array([y for _, y in sample], dtype=np.int64)
    if not len(labels):
        return np.zeros(size, dtype=np.float32), 0.0
    if labels.min() == labels.max():
        ones = labels.sum()
        return np.zeros(size, dtype=np.float32), float(np.log((ones + 1) / (len(labels) - ones + 1)))
    docs = []
    for t, _ in sample:
        parts = list(feature_chunks(t))
        ids, many = np.unique(np.concatenate(parts) if parts else np.empty(0, np.uint32), return_counts=True)
        docs.append((ids.astype(np.int32), (many / max(many.sum(), 1)).astype(np.float32)))
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-1 / DIM, 1 / DIM, (size, DIM)).astype(np.float32)
    out = np.zeros((2, DIM), dtype=np.float32)
    bias = np.zeros(2, dtype=np.float32)
    total, step = epochs * len(docs), 0
    for _ in range(epochs):
        for i in rng.permutation(len(docs)):
            lr = rate * (1 - step / total)
            step += 1
            ids, share = docs[i]
            hidden = share @ vectors[ids] if len(ids) else np.zeros(DIM, dtype=np.float32)
            z = out @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[labels[i]] -= 1
            back = p @ out
            out -= lr * np.outer(p, hidden)
            bias -= lr * 0.1 * p
            if len(ids):
                vectors[ids] -= lr * DIM * share[:, None] * back[None, :]
    return (vectors @ (out[1] - out[0])).astype(np.float32), float(bias[1] - bias[0])


def score(text: str, weights: np.ndarray, bias: float) -> float:
    total, n = 0.0, 0
    for ids in feature_chunks(text):
        total += float(weights[ids].sum(dtype=np.float64))
        n += len(ids)
    z = bias + (total / n if n else 0.0)
    return float(1 / (1 + np.exp(-np.clip(z, -50, 50))))


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, rows: int, most_bytes: int) -> list[tuple[str, int]]:
    """Texts and labels from rows that may be learned from: the first by hash of their id, ``rows`` rows and ``most_bytes`` of text at most (one row at least).

    Sizes are looked at before any text: the longest start of the order that fits is fetched, long texts like short ones.
    """
    may = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).select(F.col("doc_id").alias("__id"), F.col(column).cast("int").alias("__y"))
    chosen = may.orderBy(F.xxhash64("__id"), "__id").limit(rows)
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), F.col("doc_id") == F.col("__id"))
    order = ("__h", "doc_id", "__t")
    keyed = found.withColumn("__h", F.xxhash64("doc_id")).withColumn("__t", F.xxhash64("text"))
    sizes = keyed.select(*order, F.octet_length("text").alias("size")).orderBy(*order).limit(rows)
    total, last = 0, None
    for r in sizes.collect():
        total += r["size"]
        if last is not None and total > most_bytes:
            break
        last = (r["__h"], r["doc_id"], r["__t"])
    if last is None:
        return []
    upto = F.struct(*order) <= F.struct(*[F.lit(v).cast(keyed.schema[c].dataType) for c, v in zip(order, last)])
    got = keyed.where(upto).select(*order, "text", "__y").orderBy(*order).limit(rows).collect()
    return [(r["text"], r["__y"]) for r in got]


def fit(docs: DataFrame, labels: DataFrame, column: str = "quality") -> tuple[np.ndarray, float]:
    return train(labelled_sample(docs, labels, column, SAMPLE_ROWS, SAMPLE_BYTES))


def scored(docs: DataFrame, model: tuple[np.ndarray, float], keep: list[str], threshold: float = 0.3, prefix: str = "", only_good: bool = False) -> DataFrame:
    """Columns ``keep`` with score and predicted added; ``only_good`` drops rows predicted 0 (and adds nothing)."""
    weights, bias = model

    def add(batch):
        s = [score(t, weights, bias) for t in texts(batch)]
        if only_good:
            return {"__mask__": [x >= threshold for x in s]}
        return {prefix + "score": s, prefix + "predicted": [int(x >= threshold) for x in s]}

    return map_rows(docs, add, [] if only_good else [T.StructField(prefix + "score", T.DoubleType()), T.StructField(prefix + "predicted", T.IntegerType())], keep)
