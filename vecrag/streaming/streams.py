"""Structured Streaming forms: update and query streams, windows, state, deduplication, stream-stream joins."""

from __future__ import annotations

import time
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from vecrag.operators import index as two_tier

LATE = "1 hour"


def file_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def drain(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its rows, which go to `path`, one folder a batch; none comes to the driver.

    In complete mode a batch has all rows, so the last one's folder is read.
    """
    spark, last = stream.sparkSession, []

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        last[:] = [batch_id]

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{path}/batch={last[0]}" if mode == "complete" else f"{path}/batch=*")


def to_folder(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Append a stream to parquet files, exactly once."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()


def stream_updates(index: two_tier.Index, updates: DataFrame, path: str, checkpoint: str) -> two_tier.Index:
    """Apply (seq, op, id, v) micro-batches to an index saved at `path`; batch n writes the buckets it touches as version n + 1.

    A batch that was applied before (after a restart) finds its version there and changes nothing.
    """
    spark = index.spark
    two_tier.save_index(index, path, 0)

    def apply(batch: DataFrame, batch_id: int) -> None:
        try:
            two_tier.load_index(spark, path, batch_id + 1)
            return
        except Exception as missing:  # noqa: BLE001 - the reader's own error class differs between versions
            if "PATH_NOT_FOUND" not in str(missing):
                raise
        two_tier.update_saved(two_tier.load_index(spark, path, batch_id), batch.select("id", "op", "v", "seq"), batch_id + 1)

    updates.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return two_tier.load_index(spark, path)


def stream_search(index: two_tier.Index, queries: DataFrame, out: str, checkpoint: str, k: int = 10, **width) -> None:
    """Answer (qid, qv) micro-batches against a pinned version; results go to `out`, one folder a batch."""

    def answer(batch: DataFrame, batch_id: int) -> None:
        two_tier.search(index, batch, k, **width).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def tumbling(events: DataFrame, width: str = "10 minutes", uj: float = 1.0) -> DataFrame:
    """(start, n, uj_model): requests and their modelled energy in windows."""
    return events.withWatermark("ts", LATE).groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n", (F.col("n") * uj).alias("uj_model"))


def sliding(events: DataFrame, width: str = "1 hour", slide: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", LATE).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, stop, n) of sessions that a gap ends."""
    s = events.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def once(events: DataFrame, key: str = "event_id") -> DataFrame:
    """Repeated keys within the watermark count once."""
    return events.withWatermark("ts", LATE).dropDuplicatesWithinWatermark([key])


def updates_before(updates: DataFrame, queries: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, uts, qts): an update at most `within` before a query of the same user."""
    u = updates.select(F.col("user_id").alias("u_user"), F.col("ts").alias("uts")).withWatermark("uts", LATE)
    q = queries.select(F.col("user_id").alias("q_user"), F.col("ts").alias("qts")).withWatermark("qts", LATE)
    near = (F.col("u_user") == F.col("q_user")) & (F.col("uts") <= F.col("qts")) & (F.col("uts") >= F.col("qts") - F.expr(f"INTERVAL {within}"))
    return u.join(q, near).select(F.col("u_user").alias("user_id"), "uts", "qts")


def late_rows(batch: DataFrame, seen_until: str, late: str = LATE) -> DataFrame:
    """(late, on_time) of a micro-batch against the largest event time before it: what a watermark of `late` drops is counted."""
    limit = F.lit(seen_until).cast("timestamp") - F.expr(f"INTERVAL {late}")
    return batch.agg(F.coalesce(F.sum((F.col("ts") < limit).cast("long")), F.lit(0)).alias("late"), F.coalesce(F.sum((F.col("ts") >= limit).cast("long")), F.lit(0)).alias("on_time"))


def tumbling_with_late(events: DataFrame, name: str, path: str, checkpoint: str, width: str = "10 minutes", late: str = LATE) -> DataFrame:
    """(batch, late, on_time) of each micro-batch: rows that came too late for their window, which the windows leave out."""
    spark = events.sparkSession
    top: dict[str, str | None] = {"ts": None}

    def count(batch: DataFrame, batch_id: int) -> None:
        before = top["ts"]
        rows = late_rows(batch, before, late) if before is not None else batch.agg(F.lit(0).cast("long").alias("late"), F.count("*").alias("on_time"))
        rows.select(F.lit(batch_id).cast("long").alias("batch"), "late", "on_time").write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        newest = batch.agg(F.max("ts").cast("string")).first()[0]
        top["ts"] = max(x for x in (before, newest) if x is not None) if before or newest else None

    events.writeStream.queryName(name).foreachBatch(count).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "true").parquet(path)


class PendingUpdates(StatefulProcessor):
    """Per list: updates wait until LIMIT of them are there or a timer goes off; then they come out together, last one of
    each id. That lets a list be rewritten once for many updates. Without a waiting time there is no timer.
    """

    def __init__(self, limit: int = 8, wait_ms: int | None = None):
        self.limit, self.wait_ms = limit, wait_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.waiting = handle.getListState("waiting", "seq long, op string, id long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:  # noqa: N802
        new = [tuple(r) for part in rows for r in part[["seq", "op", "id"]].itertuples(index=False)]
        held = [tuple(r) for r in self.waiting.get()] if self.waiting.exists() else []
        if not held and self.wait_ms is not None:
            self.handle.registerTimer(timer.getCurrentProcessingTimeInMs() + self.wait_ms)
        held += new
        if len(held) >= self.limit:
            self.waiting.clear()
            yield self._out(key, held)
        else:
            self.waiting.put(held)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802
        held = [tuple(r) for r in self.waiting.get()] if self.waiting.exists() else []
        self.waiting.clear()
        if held:
            yield self._out(key, held)

    @staticmethod
    def _out(key, held: list[tuple]) -> pd.DataFrame:
        last = {i: (seq, op, i) for seq, op, i in sorted(held)}
        return pd.DataFrame([(key[0], *x) for x in sorted(last.values())], columns=["cluster_id", "seq", "op", "id"])

    def close(self) -> None:
        pass


def pending_updates(routed: DataFrame, limit: int = 8, wait_ms: int | None = 60_000) -> DataFrame:
    """(cluster_id, seq, op, id) in groups by list, from a stream of routed updates."""
    mode = "None" if wait_ms is None else "ProcessingTime"
    return routed.groupBy("cluster_id").transformWithStateInPandas(PendingUpdates(limit, wait_ms), "cluster_id long, seq long, op string, id long", "Update", mode)


class LastQuery(StatefulProcessor):
    """Per user: the last query and whether the present one repeats it (a cache hit)."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "kind string")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:  # noqa: N802
        data = pd.concat(rows).sort_values(["ts", "event_id"])
        before = self.last.get()[0] if self.last.exists() else None
        n = hits = 0
        for kind in data["event_type"]:
            n, hits, before = n + 1, hits + (kind == before), kind
        self.last.update((before,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "hits": [hits]})

    def close(self) -> None:
        pass


def cache_hits(events: DataFrame) -> DataFrame:
    """(user_id, n, hits) of each micro-batch, with state carried over batches."""
    return events.groupBy("user_id").transformWithStateInPandas(LastQuery(), "user_id long, n long, hits long", "Update", "None")


def run_name(prefix: str) -> str:
    return f"{prefix}_{time.time_ns()}"
