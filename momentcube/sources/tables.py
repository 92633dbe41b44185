"""Tables in and out: explicit schemas, formats, cubes partitioned by day."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table by its known schema; nothing is inferred."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def roundtrip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """Write in csv, json, orc or parquet and read again by schema."""
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.mode("overwrite").format(fmt).options(**options).save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).options(**options).load(path)


def write_cube(cube: DataFrame, path: str, bucket: str = "bucket", mode: str = "append") -> None:
    """Cells partitioned by day; mode "replace" overwrites only the days that the new cells hold."""
    days = cube.withColumn("day", F.to_date(bucket)).repartition("day")
    writer = days.write.partitionBy("day").option("partitionOverwriteMode", "dynamic")
    writer.mode("overwrite" if mode == "replace" else "append").parquet(path)


def read_cube(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)
