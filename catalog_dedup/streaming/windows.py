"""Continuous aggregates, sessions, deduplication, matching of arrivals and stateful counting."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import EVENT
from ..sources.formats import scratch


def events_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events as a file stream; ``files`` a trigger."""
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events.parquet").option("recursiveFileLookup", "false").parquet(sf_dir)


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what there is (availableNow) into a Parquet table and read that."""
    spark = stream.sparkSession
    path = scratch(spark)
    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/checkpoint").start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


def collect_updates(stream: DataFrame, sink: Callable[[DataFrame, int], None], mode: str = "update") -> None:
    """Run a stream over what there is with ``sink`` for every batch."""
    path = scratch(stream.sparkSession)
    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/checkpoint").foreachBatch(sink).start()
    q.awaitTermination()


def complete(stream: DataFrame) -> DataFrame:
    """The final state of an aggregating stream (complete mode), from the last batch's table."""
    spark = stream.sparkSession
    path = scratch(spark)
    last: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        last.append(f"{path}/{number}")

    collect_updates(stream, keep, "complete")
    return spark.read.schema(stream.schema).parquet(last[-1]) if last else spark.createDataFrame([], stream.schema)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    w = F.window("ts", width)
    return events.withWatermark("ts", "1 day").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = F.window("ts", width, step)
    return events.withWatermark("ts", "1 day").groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", "1 day").groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def first_of_each(events: DataFrame, *keys: str, within: str = "1 day") -> DataFrame:
    """The first row of each key as long as the watermark remembers it; later ones and late rows go."""
    return events.withWatermark("ts", within).dropDuplicatesWithinWatermark(list(keys))


def match_arrivals(arrivals: DataFrame, stored: DataFrame, key: str) -> DataFrame:
    """Stream-static join of arrivals with stored rows by a blocking key."""
    return arrivals.join(stored, key)


def running_counts(events: DataFrame) -> DataFrame:
    """user_id, seen: a stateful count per user, updated with every batch."""

    def count(key: tuple, frames: Iterator, state) -> Iterator:
        import pandas as pd

        seen = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((seen,))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [seen]})

    return events.groupBy("user_id").applyInPandasWithState(count, "user_id long, seen long", "seen long", "update", "NoTimeout")
