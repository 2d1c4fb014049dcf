"""Hybrid queries as a stream: windows over them, deduplication, last results of a user, and search by micro-batch."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def query_stream(spark: SparkSession, directory: str) -> DataFrame:
    """Each event is a query: its vector's id and its predicate's number come from the event."""
    # a pattern, since a stream's path must be a folder or a pattern and the table may be one file
    raw = spark.readStream.schema(EVENTS).parquet(f"{directory}/events.parque[t]")
    return raw.select("event_id", "ts", "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))


def windows(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", watermark: str = "1 hour") -> DataFrame:
    """Counts and mean value by window and type; works on streams and tables alike."""
    spec = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", size)}[kind]()
    keyed = events.withWatermark("ts", watermark) if events.isStreaming else events
    return keyed.groupBy(spec.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def dedupe(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    if events.isStreaming:
        return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def last_results(events: DataFrame) -> DataFrame:
    """Latest event of each user."""
    return events.groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"), F.max("ts").alias("ts"))


LATEST = "user_id long, event_id long, ts timestamp"


def last_results_stream(events: DataFrame, ttl: str = "7 days", watermark: str = "1 hour") -> DataFrame:
    """(user_id, event_id, ts) whenever a user's latest event changes, from state kept for each user.

    State of a user without events for ``ttl`` of event time is dropped; events later than the watermark are ignored, and one that is
    older than the user's latest changes nothing. Append the rows or take the last of each user.
    """
    keep = int(pd.Timedelta(ttl).total_seconds() * 1000)

    def latest(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        before = state.get if state.exists else None
        best = before
        for batch in batches:
            for ts, event in zip(batch["ts"], batch["event_id"]):
                mine = (int(ts.value // 1000), int(event))
                best = mine if best is None or mine > tuple(best) else best
        if best is not None and (before is None or tuple(best) != tuple(before)):
            state.update(tuple(best))
            yield pd.DataFrame({"user_id": [key[0]], "event_id": [best[1]], "ts": [pd.Timestamp(best[0] * 1000)]})
        if best is not None:
            state.setTimeoutTimestamp(max(best[0] // 1000 + keep, state.getCurrentWatermarkMs() + 1))

    keyed = events.withWatermark("ts", watermark).select("user_id", "event_id", "ts").groupBy("user_id")
    return keyed.applyInPandasWithState(latest, LATEST, "ts long, event_id long", "update", GroupStateTimeout.EventTimeTimeout)


def latest_of(changes: DataFrame) -> DataFrame:
    """The last change of each user."""
    return changes.groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


def drain(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there and gives the result table."""
    spark = stream.sparkSession
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def search_each(stream: DataFrame, search: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None]):
    """Searches every micro-batch against a static index and hands the results to ``sink``."""
    return stream.writeStream.foreachBatch(lambda batch, epoch: sink(search(batch), epoch)).trigger(availableNow=True).start()


def with_delta(found: DataFrame, delta: DataFrame, removed: DataFrame, k: int) -> DataFrame:
    """Index results and brute force over rows added since, without removed ids."""
    from facetgraph.operators.exact import merge

    alive = lambda df: df.join(removed.select("id"), "id", "left_anti")
    return merge([alive(found), alive(delta)], k)
