"""Streams: continuous crawling, leases with timers, live insertion into an index, windowed load."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from tilemine.operators import tsvq
from tilemine.operators.ingest import HREF


def event_stream(spark: SparkSession, folder: str, schema: str, files_per_trigger: int = 1, pattern: str = "*.parquet") -> DataFrame:
    """Files of a folder as they appear; ``ts`` becomes an instant, so that watermarks apply."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", pattern).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def crawl_stream(pages: DataFrame, seen_for: str = "1 hour") -> DataFrame:
    """Pointers in a stream of pages (page_id, html, ts), each once while it is remembered."""
    links = pages.withWatermark("ts", seen_for).select("ts", F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("url"))
    return links.dropDuplicatesWithinWatermark(["url"])


def hourly(events: DataFrame, late: str = "1 hour", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.sum("value").alias("work")).select(F.col("window.start").alias("start"), "n", "work")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def completions_in_lease(tasks: DataFrame, done: DataFrame, timeout: str = "1000 seconds", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: completions (task_id, done_at) that fall within the lease of their task (task_id, ts)."""
    a = tasks.withWatermark("ts", late).select("task_id", "ts")
    b = done.withWatermark("done_at", late).select(F.col("task_id").alias("done_id"), "done_at")
    return a.join(b, F.expr(f"task_id = done_id AND done_at >= ts AND done_at <= ts + INTERVAL {timeout}"), "inner").select("task_id", "ts", "done_at")


#: State of a completion that came before its task.
EARLY = 0


class LeaseProcessor(StatefulProcessor):
    """One state for each task: a new task is leased; a timer makes it visible again unless its completion arrives first.  A completion
    that comes before its task is held for a timeout.  State goes a timeout after the task is done or given up."""

    def __init__(self, timeout_s: int, max_attempts: int):
        self.timeout_ms, self.most = timeout_s * 1000, max_attempts

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.attempt = handle.getValueState("attempt", "attempt int")

    def _row(self, task, outcome, attempt, ms) -> pd.DataFrame:
        return pd.DataFrame({"task_id": [task], "outcome": [outcome], "attempt": [attempt], "at_s": [int(ms // 1000)]})

    def _end(self, n: int, ms: int) -> None:
        """Remember for one more timeout that the task is over, so that a late message starts nothing; then the state goes."""
        self.attempt.update((-n,))
        for t in list(self.handle.listTimers()):
            self.handle.deleteTimer(t)
        self.handle.registerTimer(ms + self.timeout_ms)

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        for part in rows:
            for r in part.sort_values("ts").itertuples():
                ms = int(r.ts.timestamp() * 1000)
                known = self.attempt.get()[0] if self.attempt.exists() else None
                if r.kind == "task" and known is None:
                    self.attempt.update((1,))
                    self.handle.registerTimer(ms + self.timeout_ms)
                    yield self._row(key[0], "leased", 1, ms)
                elif r.kind == "task" and known == EARLY:
                    yield self._row(key[0], "leased", 1, ms)
                    self._end(1, ms)
                    yield self._row(key[0], "done", 1, ms)
                elif r.kind == "done" and known is None:  # its task is late: hold it
                    self.attempt.update((EARLY,))
                    self.handle.registerTimer(ms + self.timeout_ms)
                elif r.kind == "done" and known > 0:
                    self._end(known, ms)
                    yield self._row(key[0], "done", known, ms)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        n, ms = self.attempt.get()[0], expiredTimerInfo.getExpiryTimeInMs()
        if n <= 0:
            self.attempt.clear()
        elif n >= self.most:
            self._end(n, ms)
            yield self._row(key[0], "given up", n, ms)
        else:
            self.attempt.update((n + 1,))
            self.handle.registerTimer(ms + self.timeout_ms)
            yield self._row(key[0], "leased again", n + 1, ms)

    def close(self) -> None:
        pass


def lease_stream(messages: DataFrame, timeout_s: int = 1000, max_attempts: int = 3, late: str = "0 seconds") -> DataFrame:
    """messages (task_id, ts, kind 'task' or 'done') -> (task_id, outcome, attempt, at_s).  Needs the RocksDB state store."""
    return messages.withWatermark("ts", late).groupBy("task_id").transformWithStateInPandas(LeaseProcessor(timeout_s, max_attempts), "task_id long, outcome string, attempt int, at_s long", "append", "eventTime")


def live_index(stream: DataFrame, index: tsvq.Index, target: str, checkpoint: str) -> StreamingQuery:
    """Micro-batches (id, v) fall down the tree and are written below target/batch=N: a batch that is run again replaces itself."""

    def insert(rows: DataFrame, batch: int) -> None:
        placed = tsvq.descend(tsvq.prepare(rows.dropDuplicates(["id"])), index.nodes)
        placed.select("id", "code", "v").write.mode("overwrite").parquet(f"{target}/batch={batch}")

    return stream.writeStream.foreachBatch(insert).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def with_live(index: tsvq.Index, spark: SparkSession, target: str) -> tsvq.Index:
    """The index with the streamed rows and their statistics."""
    live = spark.read.parquet(target).groupBy("id").agg(F.min_by(F.struct("code", "v"), "batch").alias("x"))  # an id of two batches counts once, from the first
    new = live.select("id", "x.code", "x.v").join(index.labelled.select("id"), "id", "left_anti").select("id", "code", "v")
    nodes = tsvq._restat(index, new, 1)
    return tsvq.Index(nodes, index.labelled.select("id", "code", "v").unionByName(new), index.manifest)


__all__ = ["LeaseProcessor", "completions_in_lease", "crawl_stream", "event_stream", "hourly", "lease_stream", "live_index", "sessions", "with_live"]
