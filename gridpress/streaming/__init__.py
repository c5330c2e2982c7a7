"""Slabs of a time grid from streams: windows, late rows, incremental Grams, slab compression."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from gridpress.operators.codec import Archive, compress_array
from gridpress.plans.grid import GridSpec
from gridpress.plans.targets import ErrorTarget

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


#: a time after all events, in milliseconds: 1 January 9000
AFTER_ALL = 221_845_392_000_000
ROCKS = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true"}


def event_stream(spark: SparkSession, folder: str, per_trigger: int | None = 1) -> DataFrame:
    """Event files of a folder as a stream, all in one batch without per_trigger; times are taken as UTC timestamps."""
    source = spark.readStream.schema(EVENTS)
    raw = (source.option("maxFilesPerTrigger", per_trigger) if per_trigger else source).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def closed(events: DataFrame) -> DataFrame:
    """An event stream and one row after all times, which moves the watermark over every window that events open.

    Its own window stays open.  Events must come in the batch of that row: what comes later is late.
    """
    last = rate_stream(events.sparkSession, 1, AFTER_ALL)
    return events.union(last.select(*(F.col("ts") if c == "ts" else F.lit(None).cast(t).alias(c) for c, t in events.dtypes)))


def rate_stream(spark: SparkSession, rows_per_batch: int, start_ms: int = 0, step_ms: int = 1000) -> DataFrame:
    """Cells from the rate source: a time and a value by rule; each batch moves on by a step of time."""
    raw = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).option("startTimestamp", start_ms).option("advanceMillisPerBatch", step_ms).load()
    return raw.select(F.col("timestamp").alias("ts"), F.col("value").alias("idx"), (F.col("value") % 97).cast("double").alias("v"))


def with_static(df: DataFrame, table: DataFrame, on: str) -> DataFrame:
    """Stream-static join: each row with the attributes that a table has for its key, null where it has none."""
    return df.join(table, on, "left")


def cents(df: DataFrame) -> DataFrame:
    return df.withColumn("cents", F.round(F.col("value") * 100).cast("long"))


def tumbling(df: DataFrame, width: str = "1 hour", late: str | None = "1 hour") -> DataFrame:
    """Cells of time slabs: (start, type, n, cents)."""
    df = df.withWatermark("ts", late) if late else df
    return cents(df).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")).select(F.col("w.start").alias("start"), "event_type", "n", "cents")


def sliding(df: DataFrame, width: str = "2 hours", step: str = "1 hour", late: str | None = "1 hour") -> DataFrame:
    df = df.withWatermark("ts", late) if late else df
    return cents(df).groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n"), F.sum("cents").alias("cents")).select(F.col("w.start").alias("start"), "n", "cents")


def sessions(df: DataFrame, gap: str = "30 minutes", late: str | None = "1 hour") -> DataFrame:
    """Sessions that end a gap after their last row; a row just then begins the next one."""
    df = df.withWatermark("ts", late) if late else df
    # windows that touch are merged, so they are a microsecond, the least step of time, shorter
    w = F.session_window("ts", f"{gap} -1 microseconds").alias("w")
    return cents(df).groupBy(w, "user_id").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")).select("user_id", F.col("w.start").alias("start"), (F.col("w.end") + F.expr("INTERVAL '0.000001' SECOND")).alias("end"), "n", "cents")


def deduplicated(df: DataFrame, late: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def clicks_to_purchases(df: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: purchases within a time after a click of the same user."""
    c = df.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click_id")).withWatermark("ct", "2 hours")
    p = right.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id")).withWatermark("pt", "2 hours")
    return c.join(p, F.expr(f"cu = user_id AND pt >= ct AND pt <= ct + INTERVAL {within}")).select("click_id", "purchase_id", "user_id")


class GramState(StatefulProcessor):
    """Gram of a mode added up over slabs: state is one matrix for each mode."""

    def __init__(self, size: int):
        self.size = size

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("gram", "g binary, slabs long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        held = self.state.get() if self.state.exists() else None
        g = np.frombuffer(held[0]).reshape(self.size, self.size).copy() if held else np.zeros((self.size, self.size))
        n = int(held[1]) if held else 0
        for df in rows:
            for fiber in df["fiber"]:
                v = np.asarray(fiber, float)
                g += np.outer(v, v)
                n += 1
        self.state.update((g.tobytes(), n))
        yield pd.DataFrame({"mode": [key[0]], "slabs": [n], "trace": [float(np.trace(g))], "frobenius": [float(np.sqrt((g * g).sum()))]})

    def close(self) -> None:
        pass


def incremental_gram(fibers: DataFrame, size: int) -> DataFrame:
    """(mode, slabs, trace, frobenius) after each batch of (mode, fiber) rows; state in RocksDB."""
    from gridpress.session import ship

    spark = fibers.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    return fibers.groupBy("mode").transformWithStateInPandas(GramState(size), "mode int, slabs long, trace double, frobenius double", "update", "None")


def compress_slabs(target: ErrorTarget, hours: int, types: list[str], keep: Callable[[int, str, Archive], None]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: each closed day of a batch is compressed as an hour x type slab.

    A slab is bounded by its shape; keep(batch_id, day, archive) must replace what an earlier run of the batch kept.
    """

    def run(batch: DataFrame, batch_id: int) -> None:
        cells = batch.groupBy(F.to_date("start").alias("day"), F.hour("start").alias("hour"), "event_type").agg(F.sum("cents").alias("v"))
        days = cells.where(F.col("event_type").isin(types)).groupBy("day").agg(F.collect_list(F.struct("hour", "event_type", "v")).alias("cells"))
        # one row a day, of at most hours x types cells; a day without any of the types is an empty slab
        for r in cells.select("day").distinct().join(days, "day", "left").orderBy("day").toLocalIterator():
            a = np.zeros((hours, len(types)))
            for c in r.cells or ():
                a[c.hour, types.index(c.event_type)] = c.v
            keep(batch_id, str(r.day), compress_array(a, target, GridSpec(("hour", "type"), a.shape)))

    return run


def drain(query_of: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> None:
    """Run a stream over what is there into a memory table, and stop."""
    w = query_of.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        w = w.option("checkpointLocation", checkpoint)
    w.start().awaitTermination()


def to_parquet(df: DataFrame, path: str, checkpoint: str) -> None:
    """Run a stream over what is there into Parquet files; with the same checkpoint nothing is written twice."""
    df.writeStream.format("parquet").outputMode("append").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def written(df: DataFrame, name: str) -> DataFrame:
    """Rows that a stream in append mode gives over what is there: executors write them to a shared folder, none pass the driver.

    State is kept on disk.
    """
    from gridpress.session import shared_folder

    spark = df.sparkSession
    before = {k: spark.conf.get(k, None) for k in ROCKS}
    for k, v in ROCKS.items():
        spark.conf.set(k, v)
    try:
        to_parquet(df, path := shared_folder(spark, name), shared_folder(spark, f"{name}_log"))
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    return spark.read.schema(df.schema).parquet(path)
