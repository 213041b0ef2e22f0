"""Streams of queries and of rows, replayed from files or from any other source."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from packvec.plans import index, search


def replay(spark: SparkSession, path: str, schema, files_a_trigger: int = 1) -> DataFrame:
    """A stream of Parquet files, some each trigger."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_trigger).parquet(path)


def stream_search(found: index.Index, queries: DataFrame, out: str, checkpoint: str, k: int = 10, plan: search.Plan = search.Plan()) -> StreamingQuery:
    """Each micro-batch of queries (query_id, qvec, pred) is one search; hits go to Parquet by batch, so a retried batch replaces its own."""

    def run(batch: DataFrame, number: int) -> None:
        search.search(found, batch, k, plan).write.mode("overwrite").parquet(f"{out}/batch={number}")

    return queries.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def upserts(rows: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Micro-batches of records (id, values, metadata) to a sink's upsert; apply must be safe to repeat for a batch number."""
    return rows.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def rates(queries: DataFrame, every: str = "1 minute", slide: str | None = None, late: str = "10 minutes", ts: str = "ts") -> DataFrame:
    """Queries a window; rows later than the watermark are dropped."""
    w = F.window(ts, every, slide) if slide else F.window(ts, every)
    return queries.withWatermark(ts, late).groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def sessions(events: DataFrame, by: str, gap: str = "30 minutes", late: str = "1 hour", ts: str = "ts") -> DataFrame:
    return events.withWatermark(ts, late).groupBy(by, F.session_window(ts, gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(by, F.col("w.start").alias("start"), "n")


def first_only(queries: DataFrame, late: str = "10 minutes", ts: str = "ts") -> DataFrame:
    """Requests whose vector and predicate were not seen within the watermark."""
    keyed = queries.withColumn("key", F.sha2(F.to_json(F.struct("qvec", "pred")), 256))
    return keyed.withWatermark(ts, late).dropDuplicatesWithinWatermark(["key"])


def with_feedback(queries: DataFrame, clicks: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Queries (query_id, ts) and the clicks (query_id, click_ts, vec_id) that follow them in time."""
    q, c = queries.withWatermark("ts", within).alias("q"), clicks.withWatermark("click_ts", within).alias("c")
    near = F.expr(f"q.query_id = c.query_id AND c.click_ts >= q.ts AND c.click_ts <= q.ts + INTERVAL {within}")
    return q.join(c, near).select("q.query_id", "q.ts", "c.click_ts", "c.vec_id")


class LastSeen(StatefulProcessor):
    """Of each request key: whether it was seen within the life time, and how often in all."""

    def __init__(self, ttl_ms: int):
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long", self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        before = self.count.get()[0] if self.count.exists() else 0
        n = sum(len(r) for r in rows)
        self.count.update((before + n,))
        yield pd.DataFrame({"key": [key[0]], "kept": [before > 0], "n": [before + n]})

    def close(self) -> None:
        pass


def cache_state(queries: DataFrame, ttl_ms: int = 3_600_000) -> DataFrame:
    """key, kept (its result is still there), n of each request key of a trigger. Needs the RocksDB state store."""
    keyed = queries.select(F.sha2(F.to_json(F.struct("qvec", "pred")), 256).alias("key"), "query_id")
    return keyed.groupBy("key").transformWithStateInPandas(LastSeen(ttl_ms), "key string, kept boolean, n long", "Update", "ProcessingTime")
