"""Streams of gradient cells: one tensor per closed window, encoded as it closes.

Event times are cast to timestamps with a zone before a watermark is set. Late cells beyond the watermark are dropped
by Spark; residual memories live in files by worker, written once per batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from ..plans.pipeline import Codec

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_stream(spark: SparkSession, path: str, schema: str = EVENTS) -> DataFrame:
    """A Parquet folder, or one file by its folder and name, as a stream of rows with timestamp ts."""
    folder, _, name = path.rpartition("/")
    reader = spark.readStream.schema(schema)
    rows = reader.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") else reader.parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(rows: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, tensor_id, idx, value): cents of each user in each window."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    cells = rows.withWatermark("ts", late).groupBy(w.alias("w"), F.col("user_id").alias("idx")).agg(F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("value"))
    return cells.select(F.col("w.start").alias("start"), F.unix_timestamp("w.start").alias("tensor_id"), "idx", "value")


def sessions(rows: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    s = rows.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n_events"))
    return s.select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "n_events")


def without_repeats(rows: DataFrame, late: str = "1 hour") -> DataFrame:
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def encode_windows(cells: DataFrame, codec: Codec, d: int, sink: str, checkpoint: str) -> StreamingQuery:
    """Encodes the windows that each batch closes and writes their containers under sink, a folder per batch."""

    def each(batch: DataFrame, number: int) -> None:
        coo = batch.where("value <> 0").select("tensor_id", "idx", "value")
        meta = coo.groupBy("tensor_id").agg(F.count("*").alias("r")).withColumn("d", F.lit(d).cast("bigint"))
        codec.encode(coo, meta, step=number).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return cells.writeStream.outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(each).start()


class ResidualMemory(StatefulProcessor):
    """Per worker: adds the remembered residual to the arriving cells, sends the r largest and remembers the rest."""

    def __init__(self, r: int = 100) -> None:
        self.r = r

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cells = handle.getListState("cells", "idx bigint, value double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        new = pd.concat([*rows, pd.DataFrame(list(self.cells.get()), columns=["idx", "value"])])[["idx", "value"]]
        total = new.groupby("idx", as_index=False)["value"].sum()
        total = total[total["value"] != 0].iloc[(-total[total["value"] != 0]["value"].abs()).argsort(kind="stable")]
        sent, kept = total.head(self.r), total.iloc[self.r :]
        self.cells.clear()
        if len(kept):
            self.cells.put([(int(i), float(v)) for i, v in zip(kept["idx"], kept["value"], strict=True)])
        yield sent.assign(worker=key[0])[["worker", "idx", "value"]]

    def close(self) -> None:
        pass


def compensated(cells: DataFrame, r: int) -> DataFrame:
    """(worker, idx, value) sent from a stream of the same columns; needs the RocksDB state store."""
    return cells.groupBy("worker").transformWithStateInPandas(statefulProcessor=ResidualMemory(r), outputStructType="worker int, idx bigint, value double", outputMode="Append", timeMode="None")


def collected(rows: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """All available input through the query, as a table in memory: for tests and small results."""
    q = rows.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return rows.sparkSession.table(name)
