"""Streams that build and extend a matrix of events, and fold arriving rows into a fixed model.

State is bounded by watermarks; sinks are written by batch id, so that a batch that runs again replaces its
own output. Checkpoints go to the folder the caller names, which must be shared.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

KINDS = ("click", "error", "purchase", "signup", "view")


def event_stream(spark: SparkSession, path: str, schema, late: str = "1 day") -> DataFrame:
    """Events with a watermark; repeated event ids within it are dropped."""
    events = spark.readStream.schema(schema).parquet(path)
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def cell_counts(events: DataFrame) -> DataFrame:
    """Counts of (user, kind and hour of the day)."""
    kind = F.array_position(F.array(*map(F.lit, KINDS)), F.col("event_type")) - 1
    return events.groupBy(F.col("user_id").alias("row_key"), (kind * 24 + F.hour("ts")).cast("bigint").alias("col_key")).agg(F.count("*").cast("double").alias("value"))


def windowed_counts(events: DataFrame, length: str = "1 hour", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Counts by tumbling, sliding or session window."""
    window = F.session_window("ts", gap) if gap else F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy("user_id", "event_type", window.alias("w")).agg(F.count("*").alias("n")).select("user_id", "event_type", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def run_to_memory(frame: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there and returns its result."""
    frame.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return frame.sparkSession.table(name)


def run_to_files(frame: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there and returns its whole result from files below ``path``, so that no row comes to the
    driver. State is kept by RocksDB, off the executors' heaps; a batch that runs again overwrites its own folder."""
    spark, last = frame.sparkSession, []
    # a batch without data would only write the same result again
    conf = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.streaming.noDataMicroBatches.enabled": "false"}

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch-{batch_id}")
        last.append(batch_id)

    before = {k: spark.conf.get(k) for k in conf}
    try:
        for k, v in conf.items():
            spark.conf.set(k, v)
        query = frame.writeStream.outputMode("complete").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    query.awaitTermination()
    return spark.read.schema(frame.schema).parquet(f"{path}/batch-{last[-1]}") if last else spark.createDataFrame([], frame.schema)


class UserVector(StatefulProcessor):
    """Keeps one user's counts by kind; emits the vector after each batch that changes it."""

    def init(self, handle) -> None:
        self.counts = handle.getValueState("counts", ", ".join(f"c{i} bigint" for i in range(len(KINDS))))

    def handleInputRows(self, key, rows, timer_values) -> Iterator[pd.DataFrame]:
        now = list(self.counts.get()) if self.counts.exists() else [0] * len(KINDS)
        for frame in rows:
            for kind, n in frame["event_type"].value_counts().items():
                if kind in KINDS:
                    now[KINDS.index(kind)] += int(n)
        self.counts.update(tuple(now))
        yield pd.DataFrame({"user_id": [key[0]], **{f"c{i}": [v] for i, v in enumerate(now)}})

    def close(self) -> None:
        pass


def user_vectors(events: DataFrame) -> DataFrame:
    schema = "user_id bigint, " + ", ".join(f"c{i} bigint" for i in range(len(KINDS)))
    return events.groupBy("user_id").transformWithStateInPandas(UserVector(), schema, "Update", "None")


def fold_in_stream(packed: DataFrame, b, out: str, checkpoint: str) -> None:
    """Coefficients of arriving packed rows; a batch that runs again overwrites its own folder."""
    from ..operators.solvers import fold_in

    def write(batch: DataFrame, batch_id: int) -> None:
        fold_in(batch, b).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    packed.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
