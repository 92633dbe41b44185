"""Embedding near-duplicates: random-hyperplane sign hashing in several tables, exact cosine, components.

Vectors that are null, zero, or hold null or non-finite components link with nothing, as do rows with a null label; labels
and numbers of dimensions must be equal. Equal vectors of a label are one class with a count. Each row is a vector,
so repeated rows count as other vectors. Bits a table: log2 of the number of classes, 12 at least; the number of tables follows
from the recall asked at the threshold. Within a bucket all pairs are compared in blocks of double precision;
a pair that meets in several tables counts in the first only. Blocks get the vectors in the type they came in, and
compute the signs of the tables before their own again: that is less than to ship them.
Extra columns are not looked at; an empty table gives an empty table.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import blocked, components, local_roots, map_rows, materialize
from .simhash import contiguous


def table_plan(n: int, threshold: float, recall: float) -> tuple[int, int]:
    """(bits, tables) for n vectors."""
    bits = min(62, max(12, math.ceil(math.log2(max(n, 2)))))
    meet = (1 - math.acos(min(1.0, threshold)) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(1 - meet)))


def _planes(dim: int, count: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, count))


def near_duplicate_links(rows: DataFrame, threshold: float = 0.98, recall: float = 0.9995, seed: int = 7) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of ``rows(vec_id, embedding, label)``."""
    kind = rows.schema["embedding"].dataType
    floats = isinstance(kind, T.ArrayType) and isinstance(kind.elementType, (T.FloatType, T.DoubleType))
    base = materialize(rows.select("vec_id", (F.col("embedding") if floats else F.col("embedding").cast("array<double>")).alias("embedding"), "label"))
    ok = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    valid = base.where(F.col("label").isNotNull() & F.col("embedding").isNotNull() & F.forall("embedding", ok) & F.exists("embedding", lambda x: x != 0))
    grouped = valid.groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("many"))
    classes = materialize(grouped.withColumn("node", F.struct("rep", F.xxhash64("label", "embedding").alias("h"))))
    bits, tables = table_plan(classes.count(), threshold, recall)

    def signs(x, count):
        """Keys of the first ``count`` tables for rows of one dimension. Rows are scaled, so that float and double sums agree on signs but for rounding, which costs recall at most."""
        s = (x @ _planes(x.shape[1], bits * tables, seed)[:, : bits * count]) > 0
        return s.reshape(len(x), count, bits) @ (1 << np.arange(bits, dtype=np.int64))

    def sign(batch):
        col = batch.column(batch.schema.get_field_index("embedding")).to_pylist()
        keys: list = [None] * len(col)
        for dim in {len(x) for x in col}:
            at = [i for i, x in enumerate(col) if len(x) == dim]
            for i, k in zip(at, signs(np.array([col[i] for i in at], dtype=np.float64), tables)):
                keys[i] = k
        return {"keys": keys}

    signed = materialize(map_rows(classes, sign, [T.StructField("keys", T.ArrayType(T.LongType()))]))
    lists = signed.select("node", "label", F.size("embedding").alias("dim"), F.posexplode("keys").alias("tab", "key"))
    bucket = ["label", "dim", "tab", "key"]
    cells = blocked(lists, bucket, ["node"]).join(signed.select("node", "embedding", "many"), "node")
    order = [*bucket, "ci", "cj"]
    flat = cells.select(*order, F.col("node.rep").alias("rep"), F.col("node.h").alias("h"), "chunk", "embedding", "many").repartition(*order).sortWithinPartitions(*order)

    def run(batches):
        for t in contiguous(batches, order):
            n = t.num_rows
            if n < 2:
                continue
            rep, h, many, chunk = (t.column(c).to_numpy() for c in ("rep", "h", "many", "chunk"))
            x = np.array(t.column("embedding").to_pylist(), dtype=np.float64)
            tab = t.column("tab")[0].as_py()
            keys = signs(x, tab)
            scale = np.abs(x).max(axis=1, keepdims=True)
            x = x / scale
            x /= np.sqrt((x * x).sum(axis=1))[:, None]
            links = (x @ x.T) >= threshold
            np.fill_diagonal(links, False)
            if t.column("ci")[0].as_py() != t.column("cj")[0].as_py():
                links &= chunk[:, None] != chunk[None, :]
            i, j = np.nonzero(links)
            earlier = np.zeros(len(i), dtype=bool)
            for k in range(tab):
                earlier |= keys[i, k] == keys[j, k]
            i, j = i[~earlier], j[~earlier]
            if not len(i):
                continue
            counts = np.bincount(i, weights=many[j], minlength=n).astype(np.int64)
            fresh = np.zeros((n, n), dtype=bool)
            fresh[i, j] = True
            root = local_roots(fresh)
            at = np.nonzero(counts)[0]
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in (rep[at], h[at], counts[at], rep[root[at]], h[root[at]])], names=["rep", "h", "links", "rep2", "h2"])

    kind = rows.schema["vec_id"].dataType.simpleString()
    found = materialize(flat.mapInArrow(run, f"rep {kind}, h long, links long, rep2 {kind}, h2 long"))
    counts = found.groupBy(F.struct("rep", "h").alias("node")).agg(F.sum("links").alias("others"))
    roots = components(found.select(F.struct("rep", "h").alias("u"), F.struct(F.col("rep2").alias("rep"), F.col("h2").alias("h")).alias("v")))
    placed = classes.join(counts, "node", "left").join(roots, "node", "left").select("label", "embedding", "rep", "many", F.coalesce("others", F.lit(0)).alias("others"), F.coalesce("root", "node").alias("root"))
    placed = materialize(placed)
    least = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    known = placed.join(least, "root").select(F.col("label").alias("l2"), F.col("embedding").alias("e2"), (F.col("many") - 1 + F.col("others")).alias("n"), "component_id")
    joined = base.join(known, (F.col("label") == F.col("l2")) & (F.col("embedding") == F.col("e2")), "left")
    comp = F.coalesce("component_id", "vec_id")
    return joined.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), comp.alias("component_id"), F.coalesce(F.col("vec_id") == comp, F.lit(True)).alias("kept"))
