"""Shared helpers: shared work tables, whole-row Arrow maps, blocked similarity lists, connected components."""

from __future__ import annotations

import atexit
import ctypes
import re
import shutil
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

_own_folder: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one only in local mode (tests), where both are one process; elsewhere it must be named."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_folder:
        _own_folder.append(tempfile.mkdtemp(prefix="llm-work-"))
        atexit.register(shutil.rmtree, _own_folder[0], ignore_errors=True)
    return f"file://{_own_folder[0]}"


def _hadoop(spark: SparkSession, path: str):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()), at


def materialize(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: cuts lineage and survives lost executors.

    Results are read lazily, so a table stays until the session's JVM ends, which deletes it; ``release`` deletes one that nothing reads any more.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/work-{uuid.uuid4().hex}"
    files, at = _hadoop(spark, path)
    files.deleteOnExit(at)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._work_path = path
    return out


def release(df: DataFrame) -> None:
    """Delete the files of a table that ``materialize`` returned and no later plan reads."""
    files, at = _hadoop(df.sparkSession, df._work_path)
    files.delete(at, True)
    files.cancelDeleteOnExit(at)


def held_out(doc_id: str = "doc_id"):
    """True where crc32 of the decimal id leaves remainder 0 by 5; a null id is never held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


#: Rows and bytes of text that go to a Python worker at once.
BATCH_ROWS, BATCH_BYTES = 1000, 8 << 20


def bound_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batch limits (runtime settings) so that neither side holds much text off the heap."""
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        if spark.conf.isModifiable(key) and not 0 < int(re.sub(r"[^0-9-]", "", spark.conf.get(key))) <= most:
            spark.conf.set(key, str(most))


def give_back() -> None:
    """Return freed memory of a reused worker to the system; its later tasks may need little."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to trim
        pass


def map_rows(df: DataFrame, add, fields: list[T.StructField], keep: list[str] | None = None) -> DataFrame:
    """Append columns computed by ``add(batch) -> dict of arrays`` to every row, batch by batch.

    ``keep``: the columns that stay (None: all); those named like an added column give way to it. A key ``__mask__`` in the dict drops rows.
    """
    names = [n for n in (df.columns if keep is None else keep) if n not in {f.name for f in fields}]
    schema = T.StructType([df.schema[n] for n in names] + fields)
    target = to_arrow_schema(schema)

    bound_batches(df.sparkSession)

    def run(batches):
        for k, batch in enumerate(batches):
            if not batch.num_rows:
                continue
            made = add(batch)
            mask = made.pop("__mask__", None)
            cols = [batch.column(batch.schema.get_field_index(n)) for n in names] + [pa.array(made[f.name], type=target.field(f.name).type) for f in fields]
            out = pa.RecordBatch.from_arrays([c if c.type == f.type else c.cast(f.type) for c, f in zip(cols, target)], schema=pa.schema([f.with_nullable(True) for f in target]))
            yield out if mask is None else out.filter(pa.array(mask))
            del made, cols, out, batch
            if k % 8 == 7:
                give_back()
        give_back()

    return df.mapInArrow(run, schema)


def texts(batch, name: str = "text") -> list[str]:
    return [t or "" for t in batch.column(batch.schema.get_field_index(name)).to_pylist()]


def local_roots(links: np.ndarray) -> np.ndarray:
    """Smallest index reachable inside one block, from a symmetric boolean matrix."""
    n = len(links)
    root = np.arange(n)
    i, j = np.nonzero(links)
    while len(i):
        low = root.copy()
        np.minimum.at(low, i, root[j])
        low = low[low]
        if (low == root).all():
            break
        root = low
    return root


BLOCK = 1024


def blocked(lists: DataFrame, key: list[str], ident: list[str], block: int = BLOCK) -> DataFrame:
    """Cut every list of rows into chunks of about ``block`` and deal each pair of chunks to its own group.

    Adds n_in_list, chunk, ci, cj. A list of m rows is held by no single task: each row goes to the
    m/block pairs of chunks that hold its own. Lists of one row are gone.
    """
    sizes = lists.groupBy(*key).agg(F.count(F.lit(1)).alias("n_in_list")).where("n_in_list > 1")
    rows = lists.join(sizes, key)
    parts = F.ceil(F.col("n_in_list") / F.lit(block)).cast("int")
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64(*ident), parts).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
    return rows.withColumn("ci", F.least("chunk", "other")).withColumn("cj", F.greatest("chunk", "other")).drop("other")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of ``edges(u, v)``: connected components by randomised contraction.

    Every round each node picks the neighbour (or itself) with the least salted hash and the graph is
    contracted to the picked nodes; the number of rounds is logarithmic in expectation for any shape,
    chains included. Rounds are written tables; groups are reduced with map-side minima only.
    """
    picks: list[DataFrame] = []
    e = materialize(edges.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct())
    while not e.isEmpty():
        salt = len(picks)
        rank = lambda c: F.struct(F.xxhash64(F.lit(salt), F.col(c)).alias("h"), F.col(c).alias("id"))
        both = e.union(e.select("v", "u"))
        pick = both.groupBy("u").agg(F.min(rank("v")).alias("m")).select("u", F.least(rank("u"), "m")["id"].alias("rep"))
        pick = materialize(pick)
        picks.append(pick)
        a, b = pick.toDF("u", "a"), pick.toDF("v", "b")
        old, e = e, e.join(a, "u").join(b, "v").where("a <> b")
        e = materialize(e.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct())
        release(old)
    if not picks:
        return edges.select(F.col("u").alias("node"), F.col("u").alias("root")).limit(0)
    done = picks[-1].toDF("node", "root")
    for pick in reversed(picks[:-1]):
        done = pick.toDF("node", "rep").join(done.toDF("rep", "root"), "rep", "left").select("node", F.coalesce("root", "rep").alias("root"))
    return done
