"""Registry of the streaming queries with the SQL of what they give in the end."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin import oracles as sql
from probejoin.functions.terms import iri, literal
from probejoin.plans.patterns import pattern
from probejoin.queries import add, catalog, query
from probejoin.sources.storage import shared_folder, table
from probejoin.streaming import events

_SPLIT: dict[tuple[str, str], str] = {}


def split(spark: SparkSession, d: str) -> str:
    """The events as ten files in order of event time, so that a stream has several batches and none brings what an earlier one's watermark has closed.

    A stream takes files by their age, so each is written after the one before it; tasks of
    one job would end in any order.
    """
    key = (spark.sparkContext.applicationId, d)
    if key not in _SPLIT:
        dealt, path = shared_folder(spark, "events-dealt"), shared_folder(spark, "events")
        ranged = table(spark, d, "events").repartitionByRange(10, "ts").sortWithinPartitions("ts", "event_id")
        ranged.withColumn("slot", F.spark_partition_id()).write.partitionBy("slot").parquet(dealt)
        slots = spark.read.schema(f"{events.SCHEMA}, slot int").parquet(dealt)
        slots.limit(0).drop("slot").write.parquet(path)  # an empty table is a folder, too
        for k in sorted(r["slot"] for r in slots.select("slot").distinct().collect()):
            slots.where(F.col("slot") == k).drop("slot").coalesce(1).write.mode("append").parquet(path)
        _SPLIT[key] = path
    return _SPLIT[key]


def stream(spark: SparkSession, d: str) -> DataFrame:
    return events.source(spark, split(spark, d), 3)


def shown(df: DataFrame) -> DataFrame:
    """Windows as text, alike in both engines."""
    at = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return df.select(at("w.start").alias("begin"), *[c for c in df.columns if c != "w"])


add("st_source", lambda spark, d: events.finished(stream(spark, d).select("event_id", "event_type")), "SELECT event_id, event_type FROM events")
# the watermark closes a window once a later batch has moved it on; complete mode gives all of them
_HOUR = "strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S')"


def whole(df: DataFrame) -> DataFrame:
    return events.finished(df, "complete")


add("st_tumbling", lambda spark, d: shown(whole(events.window_counts(stream(spark, d), "tumbling"))), f"SELECT {_HOUR} AS begin, event_type, count(*) AS n FROM events GROUP BY 1, 2")
add("st_sliding", lambda spark, d: shown(whole(events.window_counts(stream(spark, d), "sliding"))), "SELECT strftime(date_trunc('hour', ts) - k * INTERVAL 1 HOUR, '%Y-%m-%d %H:%M:%S') AS begin, event_type, count(*) AS n FROM events, range(2) r(k) GROUP BY 1, 2")
add("st_session", lambda spark, d: shown(whole(events.window_counts(stream(spark, d), "session"))).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n")), "SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS n FROM (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) GROUP BY 1")
add("st_dedup", lambda spark, d: events.finished(events.deduplicated(stream(spark, d).unionByName(stream(spark, d)), ["event_id"]).select("event_id")), "SELECT event_id FROM events")
add("st_interval_join", lambda spark, d: events.finished(events.interval_join(stream(spark, d))), "SELECT c.user_id, c.event_id AS c_id, p.event_id AS p_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
add("st_state", lambda spark, d: events.finished(events.running_state(stream(spark, d)), "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max("last").alias("last")), "SELECT user_id, count(*) AS n, max(event_id) AS last FROM events GROUP BY 1")
add("st_probe", lambda spark, d: events.finished(events.probe_index(stream(spark, d), catalog(spark, d), pattern("?x inNation ?n"))), f"SELECT event_id, x, n FROM (SELECT event_id, 'customer/' || user_id AS x FROM events) JOIN (SELECT s AS x, o AS n FROM ({sql.of('inNation')})) USING (x)")


@query("st_late", f"SELECT {_HOUR} AS begin, count(*) AS n FROM events WHERE ts < (SELECT date_trunc('hour', max(ts) - INTERVAL 1 HOUR) FROM events) GROUP BY 1")
def st_late(spark: SparkSession, d: str) -> DataFrame:
    """Append mode: windows that the watermark has closed, then a late copy of the first events, which is dropped."""
    path = shared_folder(spark, "late")
    rows = table(spark, d, "events")
    first = rows.agg(F.min("event_id").alias("e")).first()["e"]
    out = None
    rows.write.parquet(path)
    counts = events.source(spark, path).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    target, log = shared_folder(spark, "late-out"), shared_folder(spark, "late-log")
    start = lambda: counts.writeStream.format("parquet").option("path", target).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    start()
    if first is not None:  # late rows: older than the watermark that the first run left
        rows.where(F.col("event_id") < first + 10).write.mode("append").parquet(path)
        start()
    out = spark.read.schema(counts.schema).parquet(target)
    return shown(out)


@query("st_index_append", "SELECT 'event/' || event_id AS s, 'byCustomer' AS p, 'customer/' || user_id AS o FROM events UNION ALL SELECT 'event/' || event_id, 'eventType', '\"' || event_type || '\"' FROM events")
def st_index_append(spark: SparkSession, d: str) -> DataFrame:
    path = shared_folder(spark, "appended")

    def triples(batch: DataFrame) -> DataFrame:
        s = iri("event", "event_id").alias("s")
        return batch.select(s, F.lit("byCustomer").alias("p"), iri("customer", "user_id").alias("o")).unionByName(batch.select(s, F.lit("eventType").alias("p"), literal("event_type").alias("o")))

    events.index_append(stream(spark, d), path, triples)
    return spark.read.schema("s string, o string, batch int, p string").parquet(path).select("s", "p", "o")
