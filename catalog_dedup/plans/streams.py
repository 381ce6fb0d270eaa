"""Continuous queries, run over what there is and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as tx
from ..operators.store import Store
from ..sources.formats import scratch, written
from ..sources.tables import load
from ..sources.vector_source import register
from ..streaming import windows
from .registry import query


@query("SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return windows.complete(windows.tumbling(windows.events_stream(spark, sf))).select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@query("SELECT strftime(date_trunc('hour', ts) - to_hours(k), '%Y-%m-%d %H') AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return windows.complete(windows.sliding(windows.events_stream(spark, sf))).select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "n")


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    return windows.complete(windows.sessions(windows.events_stream(spark, sf))).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("SELECT user_id, event_type FROM events GROUP BY ALL")
def stream_dedup_late(spark: SparkSession, sf: str) -> DataFrame:
    """One row per user and event type: all files fit the watermark's memory in one run."""
    return windows.run_to_end(windows.first_of_each(windows.events_stream(spark, sf), "user_id", "event_type", within="60 days")).select("user_id", "event_type")


@query("SELECT e.event_id, d.doc_id FROM events e JOIN documents d ON e.user_id = d.doc_id WHERE e.event_type = 'purchase'")
def stream_static_match(spark: SparkSession, sf: str) -> DataFrame:
    """Arrivals matched with stored rows by key."""
    arrivals = windows.events_stream(spark, sf).filter("event_type = 'purchase'").select("event_id", F.col("user_id").alias("doc_id"))
    return windows.run_to_end(windows.match_arrivals(arrivals, load(spark, sf, "documents", "doc_id"), "doc_id")).select("event_id", "doc_id")


@query("SELECT user_id, count(*) AS seen FROM events GROUP BY user_id")
def stream_running_counts(spark: SparkSession, sf: str) -> DataFrame:
    """Stateful processor; the newest update of each user counts."""
    path, seen = scratch(spark), []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        seen.append(f"{path}/{number}")

    windows.collect_updates(windows.running_counts(windows.events_stream(spark, sf)), keep)
    return spark.read.schema("user_id long, seen long").parquet(*seen).groupBy("user_id").agg(F.max("seen").alias("seen"))


@query("SELECT event_id AS id, event_type FROM events WHERE event_id % 7 <> 0")
def stream_store_upsert(spark: SparkSession, sf: str) -> DataFrame:
    """A stream written to the store batch by batch, deletions after it: the state equals the batch answer."""
    s = Store(spark, scratch(spark), "event_type string")
    windows.collect_updates(windows.events_stream(spark, sf).select(F.col("event_id").alias("id"), F.lit(1).cast("long").alias("version"), "event_type"), s.sink, "append")
    s.delete(load(spark, sf, "events", "event_id").filter("event_id % 7 = 0").select(F.col("event_id").alias("id")), 2, 10**9)
    return s.read().select("id", "event_type")


@query("SELECT vec_id AS id, len(embedding)::BIGINT AS width, label FROM embeddings")
def vector_store_source(spark: SparkSession, sf: str) -> DataFrame:
    """Packed vector blocks read through a Python data source."""
    from ..sources.vector_source import pack

    rows = load(spark, sf, "embeddings", "vec_id", "embedding", "label")
    folder = pack(rows.select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")), scratch(spark))
    register(spark)
    vectors = spark.read.format("packed_vectors").option("path", folder).load()
    return vectors.join(rows.select(F.col("vec_id").alias("id"), "label"), "id").select("id", F.size("vec").cast("long").alias("width"), "label")
