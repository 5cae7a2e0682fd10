"""Structured Streaming forms of routing, gathering, serving and counting."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from vecroute.plans import builder, router

REQUEST_DDL = "query_id long, ts timestamp, vec array<double>"


def requests(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """A stream of request files."""
    return spark.readStream.schema(REQUEST_DDL).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def broker_requests(spark: SparkSession, servers: str, topic: str) -> DataFrame:
    """The same from a message broker, where its connector is on the class path."""
    raw = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).load()
    return raw.select(F.from_json(F.col("value").cast("string"), REQUEST_DDL).alias("r")).select("r.*")


def routed(stream: DataFrame, index: builder.Index, branching: int, mode: str = "exact") -> DataFrame:
    """``query_id, vec, sub_id``: requests per part; stateless."""
    return router.route(stream, index.meta, branching, mode)


def without_retries(stream: DataFrame, delay: str = "10 seconds") -> DataFrame:
    """Each query once, however often it was sent within the delay."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["query_id"])


def windowed_counts(stream: DataFrame, width: str = "1 minute", slide: str | None = None, delay: str = "30 seconds", key: str | None = None) -> DataFrame:
    """Requests per window; later than the watermark they are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    grouped = stream.withWatermark("ts", delay).groupBy(w.alias("w"), *([key] if key else []))
    return grouped.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), *([key] if key else []), "n")


def session_counts(stream: DataFrame, key: str, gap: str = "5 minutes", delay: str = "30 seconds") -> DataFrame:
    out = stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").alias("start"), key, "n")


def matched_within(asked: DataFrame, answered: DataFrame, timeout: str = "5 seconds", delay: str = "10 seconds") -> DataFrame:
    """Requests joined to responses that came within the timeout; also for batch tables."""
    a = asked.select(F.col("query_id").alias("q"), F.col("ts").alias("asked_at"))
    b = answered.select("query_id", F.col("ts").alias("answered_at"))
    if asked.isStreaming:
        a, b = a.withWatermark("asked_at", delay), b.withWatermark("answered_at", delay)
    return a.join(b, F.expr(f"q = query_id AND answered_at >= asked_at AND answered_at <= asked_at + INTERVAL {timeout}")).select("query_id", "asked_at", "answered_at")


GATHER_DDL = "query_id long, rank int, item_id long, score double, complete boolean"


def gather(partials: DataFrame, k: int, timeout_ms: int = 10_000) -> DataFrame:
    """Ranked answers of a query once all its parts have answered, or what came in by the timeout.

    ``partials(query_id, ts, sub_id, expected, item_id, score)``; a part without
    answers sends one row with a null item. State per open query: the parts heard and
    at most ``k`` answers.
    """

    def answer(query_id: int, best: dict, complete: bool) -> pd.DataFrame:
        order = sorted(best.items(), key=lambda p: (-p[1], p[0]))[:k]
        return pd.DataFrame([(query_id, i + 1, item, s, complete) for i, (item, s) in enumerate(order)], columns=["query_id", "rank", "item_id", "score", "complete"]).astype({"query_id": "int64", "rank": "int32", "item_id": "int64", "score": "float64", "complete": "bool"})

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        heard, ids, scores = state.get if state.exists else ([], [], [])
        best, parts = dict(zip(ids, scores, strict=True)), set(heard)
        if state.hasTimedOut:
            state.remove()
            yield answer(key[0], best, False)
            return
        expected = None
        for pdf in batches:
            expected = int(pdf.expected.iloc[0])
            parts.update(int(s) for s in pdf.sub_id)
            for item, s in zip(pdf.item_id, pdf.score, strict=True):
                if pd.notna(item):
                    best[int(item)] = max(best.get(int(item), float("-inf")), float(s))
        if expected is not None and len(parts) >= expected:
            if state.exists:
                state.remove()
            yield answer(key[0], best, True)
            return
        top = sorted(best.items(), key=lambda p: (-p[1], p[0]))[:k]
        state.update((sorted(parts), [i for i, _ in top], [s for _, s in top]))
        state.setTimeoutDuration(timeout_ms)

    return partials.groupBy("query_id").applyInPandasWithState(step, GATHER_DDL, "parts array<int>, ids array<long>, scores array<double>", "append", GroupStateTimeout.ProcessingTimeTimeout)


def serve(stream: DataFrame, index: builder.Index, branching: int, k: int, out: str, checkpoint: str):
    """Answers every micro-batch against the index; a batch that is run again overwrites its own answers."""

    def answer(batch: DataFrame, batch_id: int) -> None:
        builder.ask(index, batch.select("query_id", "vec"), branching, k).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return stream.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def hot_items(stream: DataFrame, width: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    """``start, item_id, n``: hits per item and window, for centre weights by use."""
    return windowed_counts(stream, width, None, delay, "item_id")


def hot_sketch(log: DataFrame, eps: float = 0.001, confidence: float = 0.99, seed: int = 42) -> DataFrame:
    """A count-min sketch of the item log: bounded size, mergeable."""
    return log.agg(F.count_min_sketch("item_id", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
