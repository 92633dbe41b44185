"""Best-fit packing of token sequences in bulk-synchronous rounds.

Lengths are whole numbers up to the capacity, so documents and gaps sorted by size are runs of equal size, at most ``capacity`` runs of
pieces whatever the number of rows. A round takes the longest run of pieces left and sweeps the gap runs for successors (the smallest gap
that is large enough); within a run, conflicts are resolved by rank: the r-th piece takes the r-th sequence. Gaps are then updated and the
next round starts. This is best-fit decreasing on all rows. The sweeps work on counts by length (``capacity`` numbers reach the driver) and
give intervals (length, ranks) -> (sequences, offset); ranks of rows and their places are distributed.

Null text counts as empty: one piece, the end token. A text longer than the capacity is cut; its first piece is the short one. Repeated rows
are packed each; an empty table gives an empty table; other columns than doc_id and text are not looked at.
"""

from __future__ import annotations

import os
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import bound_batches, give_back, materialize

END = 2
#: Below this code point (the first of the right-to-left scripts) both libraries' tables of letters, digits and spaces are equal, which a test
#: tries for every one of them; above it they follow different versions of Unicode.
SAME_TABLES_BELOW = "\u0590"


@lru_cache(maxsize=2)
def _encoders(json_path: str, rank_path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    import base64

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    full = Tokenizer.from_file(json_path)
    full.encode_special_tokens = True
    with open(rank_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return full, tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def default_tokenizer() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def token_ids(text: str, paths: tuple[str, str]) -> np.ndarray:
    """Ids of the JSON tokenizer; strings of special tokens in a text are text, as the vocabularies' description has it.

    Where the tables of both libraries are equal, the same vocabulary as ranks gives the same ids several times faster.
    """
    full, fast = _encoders(*paths)
    if not text or text.isascii() or max(text) < SAME_TABLES_BELOW:
        return np.array(fast.encode_ordinary(text), dtype=np.uint32)
    return np.array(full.encode(text, add_special_tokens=False).ids, dtype=np.uint32)


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of each piece of a document of n ids."""
    first = n % capacity or capacity
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, capacity: int = 1024, tokenizer: tuple[str, str] | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids, if asked for)."""
    paths = tokenizer or default_tokenizer()
    kind = docs.schema["doc_id"].dataType.simpleString()
    bound_batches(docs.sparkSession)

    def run(batches):
        for batch in batches:
            ids_of, col = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            out: list[list] = [[] for _ in range(6)]
            for doc, t in zip(ids_of, col):
                ids = np.append(token_ids(t or "", paths), np.uint32(END)).astype("<u4")
                for k, (s, n) in enumerate(cut(len(ids), capacity)):
                    part = ids[s : s + n]
                    for to, v in zip(out, (doc, k, s, n, zlib.crc32(part.tobytes()), part.astype(np.int32))):
                        to.append(v)
            types = [batch.schema.field(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            arrays = [pa.array(v, type=ty) for v, ty in zip(out, types)]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if with_ids:
                arrays.append(pa.array(out[5], type=pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(arrays, names=names)
        give_back()

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else ""))


def best_fit_rounds(counts: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, number, first sequence, offset): intervals of best-fit decreasing on counts by length.

    Gap runs are (first sequence, number) by gap size. A round splits at most one run, so there are at most
    two runs for each length and the work does not depend on the number of rows.
    """
    gaps: dict[int, list[tuple[int, int]]] = {}
    sizes = np.zeros(capacity + 2, dtype=bool)
    placed, fresh = [], 0
    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            ahead = np.nonzero(sizes[length : capacity + 1])[0]
            if len(ahead):
                gap = length + int(ahead[0])
                first, have = gaps[gap].pop()
                if not gaps[gap]:
                    sizes[gap] = False
                used = min(left, have)
                if used < have:
                    gaps.setdefault(gap, []).append((first + used, have - used))
                    sizes[gap] = True
            else:
                gap, per = capacity, capacity // length
                first, used = fresh, -(-left // per)
                fresh += used
                if used * per > left and used > 1:
                    fresh -= 1
                    used -= 1
            placed.append((length, rank, used, first, capacity - gap))
            left, rank = left - used, rank + used
            rest = gap - length
            if rest:
                gaps.setdefault(rest, []).append((first, used))
                sizes[rest] = True
    return placed


def pack(parts: DataFrame, capacity: int = 1024, per_salt: int = 20_000) -> DataFrame:
    """Adds sequence_id and offset to pieces. Ranks within a length are dealt in salted groups, so no length is a hot key."""
    spark = parts.sparkSession
    total = parts.count()
    salts = max(1, total // per_salt)
    salted = parts.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int"))
    cells = materialize(salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("many")))
    counts = {r["length"]: r["many"] for r in cells.groupBy("length").agg(F.sum("many").alias("many")).collect()}
    plan = best_fit_rounds(counts, capacity)
    schema = "length long, rank0 long, used long, sequence0 long, offset long"
    rounds = spark.createDataFrame(plan, schema)
    before = cells.selectExpr("length", "salt", "many", "coalesce(sum(many) over (partition by length order by salt rows between unbounded preceding and 1 preceding), 0) as before")
    # a cell holds ranks in one stretch, so it meets few intervals: pieces join those of their own cell, not all of their length
    meets = (F.col("rank0") < F.col("before") + F.col("many")) & (F.col("before") < F.col("rank0") + F.col("used"))
    own = before.join(rounds, "length").where(meets).drop("many")
    ranked = salted.selectExpr("*", "row_number() over (partition by length, salt order by doc_id, piece, ids_crc32) - 1 as within")
    joined = ranked.join(own, ["length", "salt"]).withColumn("rank", F.col("before") + F.col("within")).where((F.col("rank") >= F.col("rank0")) & (F.col("rank") < F.col("rank0") + F.col("used")))
    return joined.withColumn("sequence_id", F.col("sequence0") + F.col("rank") - F.col("rank0")).drop("salt", "before", "within", "rank", "rank0", "used", "sequence0")


def pack_documents(docs: DataFrame, capacity: int = 1024, tokenizer: tuple[str, str] | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    parts = materialize(pieces(docs, capacity, tokenizer))
    return pack(parts, capacity).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", F.col("offset").cast("long"))
