"""Streams over the events table: windows, watermarks, joins, state, and probes of the index.

Each query runs over what is there (`availableNow`) and gives the table it wrote.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin.operators import probe
from probejoin.operators.rowindex import IndexCatalog
from probejoin.plans.patterns import TriplePattern
from probejoin.sources.storage import shared_folder

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def source(spark: SparkSession, path: str, files: int | None = None) -> DataFrame:
    """Events as a stream, in event time with a zone: a watermark needs one."""
    reader = spark.readStream.schema(SCHEMA)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end of the input and give the rows written. append writes files; complete and update keep the last state of each batch."""
    spark = stream.sparkSession
    out, log = shared_folder(spark, "stream"), shared_folder(spark, "stream-log")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", log).trigger(availableNow=True).start()
    else:

        def keep(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite" if mode == "complete" else "append").parquet(out)

        q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", log).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def window_counts(stream: DataFrame, kind: str) -> DataFrame:
    """Counts by window and type: tumbling (an hour), sliding (two hours by one) or session (by user, until half an hour passes; events just that far apart are in two sessions)."""
    by = {"tumbling": [F.window("ts", "1 hour").alias("w"), "event_type"], "sliding": [F.window("ts", "2 hours", "1 hour").alias("w"), "event_type"], "session": [F.session_window("ts", "1799999999 microseconds").alias("w"), "user_id"]}[kind]
    return stream.withWatermark("ts", "1 hour").groupBy(*by).agg(F.count("*").alias("n"))


def deduplicated(stream: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def interval_join(stream: DataFrame) -> DataFrame:
    """Purchases within an hour after a click of the same customer; both sides forget what is older."""
    side = lambda kind, p: stream.where(F.col("event_type") == kind).select(F.col("user_id").alias(f"{p}_user"), F.col("event_id").alias(f"{p}_id"), F.col("ts").alias(f"{p}_ts")).withWatermark(f"{p}_ts", "1 hour")
    on = F.expr("c_user = p_user AND p_ts >= c_ts AND p_ts <= c_ts + INTERVAL 1 HOUR")
    return side("click", "c").join(side("purchase", "p"), on).select(F.col("c_user").alias("user_id"), "c_id", "p_id")


def running_state(stream: DataFrame) -> DataFrame:
    """Number and last event of each customer, kept as state and given after each batch that changes it."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, last = state.get if state.exists else (0, -1)
        for frame in frames:
            n, last = n + len(frame), max(last, int(frame["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [last]})

    return stream.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, last long", "n long, last long", "update", "NoTimeout")


def probe_index(stream: DataFrame, idx: IndexCatalog, pattern: TriplePattern) -> DataFrame:
    """Events as outer mappings, the index as inner side: a stream-static join on its row key."""
    outer = stream.select("event_id", F.concat(F.lit("customer/"), "user_id").alias("x"))
    return outer.join(probe.read(idx, pattern), "x")


def index_append(stream: DataFrame, path: str, to_triples: Callable[[DataFrame], DataFrame]) -> None:
    """Append each batch's triples below path, in a folder of its number: writing a batch again replaces it."""

    def keep(batch: DataFrame, number: int) -> None:
        to_triples(batch).write.mode("overwrite").partitionBy("p").parquet(f"{path}/batch={number}")

    log = shared_folder(stream.sparkSession, "append-log")
    stream.writeStream.foreachBatch(keep).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
