"""Streams of telemetry, documents and contract observations; each has a batch twin."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tumbling(events: DataFrame, window: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Rows and units by window; works on a stream (with a watermark) and on a table alike."""
    events = events.withWatermark("ts", late) if events.isStreaming else events
    by = events.groupBy(F.window("ts", window).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("units"))
    return by.select(F.col("w.start").alias("start"), "n", F.round("units", 4).alias("units"))


def sliding_faults(events: DataFrame, window: str = "1 hour", slide: str = "15 minutes", late: str = "10 minutes") -> DataFrame:
    """Share of faults by sliding window."""
    events = events.withWatermark("ts", late) if events.isStreaming else events
    by = events.groupBy(F.window("ts", window, slide).alias("w")).agg(F.count_if(F.col("event_type") == "error").alias("faults"), F.count(F.lit(1)).alias("n"))
    return by.select(F.col("w.start").alias("start"), "faults", "n")


def sessions(events: DataFrame, gap: str | Column = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of faults of each user."""
    events = events.withWatermark("ts", late) if events.isStreaming else events
    by = events.where("event_type = 'error'").groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("faults"))
    return by.select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "faults")


def distinct_documents(docs: DataFrame, late: str = "1 day") -> DataFrame:
    """First arrival of each text within the watermark; state is digests, not texts."""
    told = docs.withColumn("digest", F.md5("text"))
    return told.withWatermark("arrived", late).dropDuplicatesWithinWatermark(["digest"]) if docs.isStreaming else told.dropDuplicates(["digest"])


def with_labels(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """A stream of documents beside a static table of labels."""
    return docs.join(labels, "doc_id", "left")


def recoveries(events: DataFrame, late: str = "1 hour", within: str = "30 minutes") -> DataFrame:
    """Faults joined with the same user's next other events within a time: a join of two streams with event-time bounds."""
    faults = events.where("event_type = 'error'").select("user_id", F.col("event_id").alias("fault"), F.col("ts").alias("failed"))
    other = events.where("event_type <> 'error'").select("user_id", F.col("event_id").alias("next"), F.col("ts").alias("seen"))
    if events.isStreaming:
        faults, other = faults.withWatermark("failed", late), other.withWatermark("seen", late)
    return faults.join(other, "user_id").where(f"seen > failed and seen <= failed + interval {within}") if not events.isStreaming else faults.alias("a").join(other.alias("b"), F.expr(f"a.user_id = b.user_id and seen > failed and seen <= failed + interval {within}"))


def contract_monitor(observations: DataFrame, window: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Pass rate by condition and window with the lower Wilson bound; ``observations`` have ``ts`` and the columns of an observation."""
    from ..operators.contract import verdict, wilson

    told = verdict(observations)
    told = told.withWatermark("ts", late) if told.isStreaming else told
    by = told.groupBy(F.window("ts", window).alias("w"), "condition").agg(F.count_if("passed").alias("passed"), F.count(F.lit(1)).alias("n"))
    low, _ = wilson(F.col("passed"), F.col("n"))
    return by.select(F.col("w.start").alias("start"), "condition", "passed", "n", F.round(low, 6).alias("low"))


AUTOMATON = "user_id long, begin timestamp, end timestamp, events long, outcome string"


def drains(events: DataFrame, within: str = "30 minutes", late: str = "1 hour"):
    """Drain and restart as a stateful automaton for each user, on a stream of events.

    A fault starts a drain; the first other event within the time restarts (``restarted``), and its lack ends the drain at the limit
    (``expired``). State is one open drain for each user and goes with it; a timer in event time ends drains that no event ends. Events
    that one batch brings are taken in their order; a row later than the watermark has no part.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    limit = pd.Timedelta(within)

    def row(user, begin, end, n, outcome):
        return (user, begin, end, n, outcome)

    def step(key, batches, state):
        (user,) = key
        out, open_ = [], None
        if state.exists:
            begin, n = state.get
            open_ = (pd.Timestamp(begin, unit="us"), n)
        if state.hasTimedOut:
            out.append(row(user, open_[0], open_[0] + limit, open_[1], "expired"))
            open_ = None
        else:
            rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
            for ts, kind in zip(rows["ts"], rows["event_type"]):
                if open_ and ts > open_[0] + limit:
                    out.append(row(user, open_[0], open_[0] + limit, open_[1], "expired"))
                    open_ = None
                if kind == "error":
                    open_ = (open_[0], open_[1] + 1) if open_ else (ts, 1)
                elif open_:
                    out.append(row(user, open_[0], ts, open_[1], "restarted"))
                    open_ = None
        if open_:
            state.update((open_[0].value // 1000, open_[1]))
            state.setTimeoutTimestamp(max((open_[0] + limit).value // 1_000_000, state.getCurrentWatermarkMs() + 1))
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["user_id", "begin", "end", "events", "outcome"])

    told = events.select("user_id", "ts", "event_id", "event_type").withWatermark("ts", late)
    return told.groupBy("user_id").applyInPandasWithState(step, AUTOMATON, "begin long, n long", "append", GroupStateTimeout.EventTimeTimeout)


def pool_counters(stream: DataFrame, path: str, checkpoint: str):
    """Incremental pool counters: each micro-batch overwrites its own partition, so a repeated batch counts once."""

    def write(batch: DataFrame, batch_id: int) -> None:
        by = batch.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).alias("chars"))
        by.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_once(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Drains what is there into Parquet and stops."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
