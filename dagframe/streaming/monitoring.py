"""The monitoring job as a stream: panes with late data, sessions, candidates of causes, and drift kept as state."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def deduplicated(stream: DataFrame, key: str = "event_id", ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """Each event once, within the watermark."""
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark([key])


def pane_counts(stream: DataFrame, *keys: str, ts: str = "ts", late: str = "1 hour", width: str = "30 minutes") -> DataFrame:
    """Counts of tumbling panes by keys; in append mode a pane comes out once the watermark has passed it."""
    return stream.withWatermark(ts, late).groupBy(F.window(ts, width), *keys).agg(F.count("*").alias("n"))


def window_counts(stream: DataFrame, *keys: str, ts: str = "ts", late: str = "1 hour", length: str = "24 hours", slide: str = "30 minutes") -> DataFrame:
    """Counts of sliding windows; for long windows prefer panes and sum them when a window is asked for."""
    return stream.withWatermark(ts, late).groupBy(F.window(ts, length, slide), *keys).agg(F.count("*").alias("n"))


def late_rows(query) -> int:
    """Rows that a stream's stateful operators dropped since they came after the watermark, over all progress reports it keeps."""
    return sum(int(op["numRowsDroppedByWatermark"]) for report in query.recentProgress for op in report["stateOperators"])


def user_sessions(frame: DataFrame, user: str = "user_id", ts: str = "ts", gap: str = "2 hours") -> DataFrame:
    """Sessions of users, as samples: start, end, events and errors."""
    grouped = frame.groupBy(F.session_window(ts, gap).alias("s"), user)
    return grouped.agg(F.count("*").alias("n_events"), F.count(F.when(F.col("event_type") == "error", 1)).alias("n_errors")).select(user, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n_events", "n_errors")


def interval_causes(events: DataFrame, within: str = "30 minutes", ts: str = "ts", user: str = "user_id") -> DataFrame:
    """Pairs of an error and another event of the same user in the time before it; batch or stream (both sides with watermarks)."""
    errors = events.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col(user).alias("u"), F.col(ts).alias("error_ts"))
    others = events.where("event_type <> 'error'").select("event_id", F.col(user), F.col(ts), "event_type")
    near = F.col("u") == F.col(user)
    return others.join(errors, near & (F.col(ts) < F.col("error_ts")) & (F.col(ts) >= F.col("error_ts") - F.expr(f"interval {within}"))).select("error_id", "event_id", user, "event_type")


def count_drift(panes: DataFrame, key: str) -> DataFrame:
    """The change of each key's count from its last pane, kept as state between batches: ``(key, n, before)``."""

    def step(keys, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        for frame in frames:
            for n in frame["n"]:
                yield pd.DataFrame({key: [keys[0]], "n": [int(n)], "before": [-1 if last is None else int(last)]})
                last = int(n)
        state.update((last,))

    return panes.groupBy(key).applyInPandasWithState(step, f"{key} string, n long, before long", "last long", "update", GroupStateTimeout.NoTimeout)


def run(stream: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str, mode: str = "append", once: bool = False, every: str = "30 minutes"):
    """Start a query that hands each batch to ``sink``; ``once`` works off what is there and ends."""
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(sink)
    return (writer.trigger(availableNow=True) if once else writer.trigger(processingTime=every)).start()


def idempotent(path: str) -> Callable[[DataFrame, int], None]:
    """A sink that writes each batch to a folder of its own number, so that a batch that runs again replaces itself."""
    return lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
