"""Streams: panes with a watermark, sliding alerts from a ring of panes, sinks."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import maxent
from ..functions.udfs import to_batch
from ..sources.tables import SCHEMAS
from ..summary import SummarySpec, accumulate, clean


def events(spark: SparkSession, folder: str) -> DataFrame:
    """Event files as a stream, with a time column that takes a watermark."""
    return spark.readStream.schema(SCHEMAS["events"]).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def panes(stream: DataFrame, metric: Column, delay: str = "10 minutes", width: str = "10 minutes", spec: SummarySpec = SummarySpec(), by: list[str] = ()) -> DataFrame:
    """Tumbling panes; rows later than the watermark are dropped (and counted by Spark as dropped)."""
    rows = stream.withColumn("__x", clean(metric)).withWatermark("ts", delay)
    return rows.groupBy(*by, F.window("ts", width)).agg(*accumulate(F.col("__x"), spec))


def distinct_events(stream: DataFrame, key: str = "event_id", delay: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def enrich(stream: DataFrame, dimension: DataFrame, on: str) -> DataFrame:
    return stream.join(F.broadcast(dimension), on, "left")


def ring_alerts(pane_rows: DataFrame, key: str, width: int, phi: float, threshold: float, order: int = 10) -> DataFrame:
    """For each key the last ``width`` panes are kept; each new pane gives the window that ends there and whether its quantile exceeds the threshold.

    ``pane_rows``: key, pane (long, in order for each key), summary columns. State for a key: ``width`` summaries.
    """
    spec = SummarySpec(order=order)
    cols = spec.columns

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ring = pd.DataFrame(list(state.get[0]) if state.exists else [], columns=["pane", *cols])
        new = pd.concat(list(batches))[["pane", *cols]].sort_values("pane")
        out = []
        for _, row in new.iterrows():
            row = row.astype(float)
            ring = pd.concat([ring, row.to_frame().T]) if len(ring) else row.to_frame().T
            ring = ring[ring["pane"] > row["pane"] - width]
            total = {c: ring[c].sum() for c in cols} | {"xmin": ring["xmin"].min(), "xmax": ring["xmax"].max()}
            st = pd.DataFrame([{"n": total["n"], "n_pos": total["n_pos"], "xmin": total["xmin"], "xmax": total["xmax"], "s": [total[c] for c in spec.s], "l": [total[c] for c in spec.l]}])
            q = float(maxent.quantiles(to_batch(st), [phi])[0][0, 0]) if total["n"] else float("nan")
            out.append((*k, int(row["pane"]), int(total["n"]), q, q > threshold))
        state.update(([tuple(r) for r in ring.astype(float).itertuples(index=False)],))
        yield pd.DataFrame(out, columns=[key, "pane", "n", "q", "alert"])

    kind = pane_rows.schema[key].dataType.simpleString()
    ring_type = "ring array<struct<pane:double," + ",".join(f"{c}:double" for c in cols) + ">>"
    return pane_rows.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, pane long, n long, q double, alert boolean", ring_type, "append", GroupStateTimeout.NoTimeout)


def upsert_sink(path: str):
    """A foreachBatch function that writes every micro-batch under its own number: a replayed batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write
