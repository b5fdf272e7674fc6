"""Streams of events and entries: windows, late rows, and products that grow with what arrives."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nzspan.session import shared_folder


def stream_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1, table: str = "events") -> DataFrame:
    """A table's rows as a stream; event times become TIMESTAMP, as watermarks ask for it."""
    path = f"{sf_dir}/{table}.parquet"
    # a pattern, as the source takes folders only and a table may be one file
    df = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{path}*")
    return df.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in df.columns else df


def finish(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over all there is, and give the sink's final rows."""
    spark = stream.sparkSession
    name = f"nz_{uuid.uuid4().hex}"
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_folder(spark)}/stream-{name}").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def finish_to_files(stream: DataFrame) -> DataFrame:
    """Run a stream of rows that stay as they are over all there is, into Parquet in the shared folder; its keys' state lies in RocksDB, not in a heap."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        query = stream.writeStream.format("parquet").outputMode("append").option("path", f"{base}/rows").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        spark.conf.set(key, before)
    return spark.read.schema(stream.schema).parquet(f"{base}/rows")


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    return _windowed(events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type"))


def sliding(events: DataFrame, width: str = "1 day", step: str = "12 hours", late: str = "1 hour") -> DataFrame:
    return _windowed(events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w"), "event_type"))


def sessions(events: DataFrame, gap: str = "1 day", late: str = "1 hour") -> DataFrame:
    grouped = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return grouped.select(F.col("w.start").alias("start"), "user_id", "n")


def _windowed(grouped) -> DataFrame:
    return grouped.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def running_forward(entries: DataFrame, x: DataFrame) -> DataFrame:
    """(row, y) of a stream of entries: the product is linear, so the new entries' share is added."""
    return entries.join(x, "col").groupBy("row").agg(F.sum(F.col("val") * F.col("x")).alias("y"))


def running_transposed(entries: DataFrame, v: DataFrame) -> DataFrame:
    return entries.join(v, "row").groupBy("col").agg(F.sum(F.col("val") * F.col("v")).alias("u"))


def running_counts(entries: DataFrame) -> DataFrame:
    return entries.groupBy("col").agg(F.count(F.lit(1)).alias("nnz"))


def deduplicated(events: DataFrame, keys: list[str], within: str | None = "1 hour") -> DataFrame:
    """Events without repeats of their keys within a time; with None, without any repeats, and no event is too late."""
    if within is None:
        return events.dropDuplicates(keys)
    return events.withWatermark("ts", within).dropDuplicatesWithinWatermark(keys)


def paired(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs of two streams' events of one key, the right one at most `within` after the left one."""
    a = left.withWatermark("ts", late).select(F.col(key).alias("a_key"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = right.withWatermark("ts", late).select(F.col(key).alias("b_key"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return a.join(b, F.expr(f"a_key = b_key AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {within}")).select("a_key", "a_id", "b_id")


def cover_drift(entries: DataFrame, first_cols: list[int]) -> DataFrame:
    """(part, nnz) of a stream of entries under a fixed cover: running counts held by a stateful operator, one state for each part."""
    import pandas as pd

    part = sum(((F.col("col") >= c).cast("int") for c in first_cols[1:]), F.lit(0))

    def update(key, batches, state):
        n = state.get[0] if state.exists else 0
        n += sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"part": [key[0]], "nnz": [n]})

    return entries.withColumn("part", part).groupBy("part").applyInPandasWithState(update, "part int, nnz long", T.StructType([T.StructField("n", T.LongType())]), "update", "NoTimeout")
