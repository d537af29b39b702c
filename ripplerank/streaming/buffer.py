"""Buffered queries as a stream: windows of requests answered in batches."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.lineage import scope, shared_path
from ..operators.decompose import batch_ppr, prepare
from ..operators.graph import Graph
from ..sources.edges import KIND

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def query_events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """Requests (ts, request_id, query) from the events table as a file stream; users ask for themselves as customers."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet")
    return as_requests(raw.parquet(f"{sf_dir}/events.parquet"))


def as_requests(events: DataFrame) -> DataFrame:
    return events.select("ts", F.col("event_id").alias("request_id"), (F.col("user_id") + KIND["customer"]).alias("query"))


def drain(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there into a memory table and return it; for bounded results."""
    spark = df.sparkSession
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", shared_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def drain_counting(df: DataFrame, name: str, mode: str = "append") -> tuple[DataFrame, int]:
    """The same, and how many rows came too late for their window or state and were dropped."""
    spark = df.sparkSession
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", shared_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(int(s["numRowsDroppedByWatermark"]) for p in q.recentProgress for s in p["stateOperators"])
    return spark.table(name), late


def windowed(requests: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, requests, queries (distinct, approximate) per tumbling or sliding window; late requests are dropped (drain_counting counts them)."""
    parts = F.window("ts", window, slide) if slide else F.window("ts", window)
    return requests.withWatermark("ts", late).groupBy(parts.alias("w")).agg(F.count("*").alias("requests"), F.approx_count_distinct("query").alias("queries")).select(
        F.col("w.start").alias("start"), "requests", "queries"
    )


def sessions(requests: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """query, start, requests per session of a user's requests."""
    return requests.withWatermark("ts", late).groupBy("query", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("requests")).select(
        "query", F.col("w.start").alias("start"), "requests"
    )


def unrepeated(requests: DataFrame, late: str = "1 hour") -> DataFrame:
    """Requests without repeats of a query within the watermark."""
    return requests.withWatermark("ts", late).dropDuplicatesWithinWatermark(["query"])


def answer_batches(g: Graph, idx: DataFrame | None, requests: DataFrame, path: str, laps: int = 2, k: int = 10, checkpoint: str | None = None, **how):
    """Answer each micro-batch as one shared batch and write it below path/batch=<id>; a replayed batch overwrites itself."""
    def answer(batch: DataFrame, number: int) -> None:
        queries = batch.select("query").distinct()
        with scope():
            batch_ppr(g, idx, queries, laps, k=k, **how).write.mode("overwrite").parquet(f"{path}/batch={number}")

    prepare(g)  # outside the scopes of the batches, which delete what they make

    return requests.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint or shared_path(g.spark, "answers")).trigger(availableNow=True).start()


def with_answers(requests: DataFrame, answers: DataFrame) -> DataFrame:
    """Stream joined to a table of cached answers (query, vertex, score, rank)."""
    return requests.join(answers, "query")


def _latest(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    count, last = state.get if state.exists else (0, None)
    for b in batches:
        count += len(b)
        newest = b["ts"].max()
        last = newest if last is None or newest > last else last
    state.update((count, last))
    yield pd.DataFrame({"query": [key[0]], "requests": [count], "last": [last]})


def per_query_state(requests: DataFrame) -> DataFrame:
    """query, requests, last: running totals per query, kept as state over micro-batches."""
    return requests.groupBy("query").applyInPandasWithState(
        _latest, "query long, requests long, last timestamp", "requests long, last timestamp", "update", GroupStateTimeout.NoTimeout
    )


def running_degrees(edges: DataFrame) -> DataFrame:
    """src, out_deg of a stream of edges (src, dst)."""
    return edges.groupBy("src").agg(F.count("*").alias("out_deg"))


