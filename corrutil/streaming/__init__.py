"""Running statistics, windows and sessions over a stream of events, and mining of closed windows.

Each function takes a streaming or a batch frame of ``ts, user_id, event_type, value`` and builds the
same plan for both.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState

from ..functions import cents
from ..plans.keyed import mine_keyed
from ..scratch import delete_tables

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, *, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def valid(events: DataFrame) -> DataFrame:
    return events.where("user_id IS NOT NULL AND event_type IS NOT NULL AND ts IS NOT NULL AND value > 0")


def window_item_stats(events: DataFrame, *, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """``start, item, n, u`` of each window: tumbling, or sliding with ``slide``."""
    span = F.window("ts", size, slide) if slide else F.window("ts", size)
    return valid(events).withWatermark("ts", late).groupBy(span.alias("w"), F.col("event_type").alias("item")).agg(F.count(F.lit(1)).alias("n"), F.sum(cents("value")).alias("u")).select(F.col("w.start").alias("start"), "item", "n", "u")


def deduplicated(events: DataFrame, *, late: str = "1 hour") -> DataFrame:
    """Each event once within the watermark."""
    seen = valid(events).withWatermark("ts", late)
    return seen.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else seen.dropDuplicates(["event_id"])


def session_baskets(events: DataFrame, *, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """One transaction for each session: ``user_id, start, item, u`` rows come from the session's array."""
    return (
        valid(events).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
        .agg(F.count(F.lit(1)).alias("n"), F.sum(cents("value")).alias("tu"), F.collect_list(F.struct(F.col("event_type").alias("item"), cents("value").alias("u"))).alias("record"))
        .select("user_id", F.col("w.start").alias("start"), "n", "tu", "record")
    )


def window_baskets(events: DataFrame, *, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """``start, tid, item, u``: a user's events in a window are one transaction."""
    return valid(events).withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "user_id", F.col("event_type").alias("item")).agg(F.sum(cents("value")).alias("u")).select(F.col("w.start").alias("start"), F.col("user_id").alias("tid"), "item", "u")


def window_item_twu(events: DataFrame, *, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """``start, item, sup, u, twu`` of each window: a user's events in it are one transaction.

    Two aggregations, one behind the other: a transaction closes with its window, then its items are counted.
    """
    baskets = valid(events).withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "user_id").agg(F.sum(cents("value")).alias("tu"), F.collect_list(F.struct(F.col("event_type").alias("item"), cents("value").alias("u"))).alias("r"))
    each = baskets.select("w", "tu", "r", F.explode(F.array_distinct(F.transform("r", lambda e: e["item"]))).alias("item"))
    own = F.aggregate(F.filter("r", lambda e: e["item"] == F.col("item")), F.lit(0).cast("bigint"), lambda acc, e: acc + e["u"])
    counted = each.withColumn("u", own).groupBy(F.window(F.window_time("w"), size).alias("v"), "item").agg(F.count(F.lit(1)).alias("sup"), F.sum("u").alias("u"), F.sum("tu").alias("twu"))
    return counted.select(F.col("v.start").alias("start"), "item", "sup", "u", "twu")


def late_rows(query: StreamingQuery) -> int:
    """Rows that came after the watermark had passed their window, of the batches that the query still remembers."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


_OPEN = "start timestamp, last timestamp, n bigint, tu bigint"


def closing_baskets(events: DataFrame, *, gap_seconds: int = 1800, late: str = "1 hour") -> DataFrame:
    """``user_id, start, n, tu`` of sessions, given out as the watermark closes them: for each user only sums are kept, not the events.

    An event out of order, but within the watermark, joins the open basket if it lies within the gap of it.
    """
    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        gap = pd.Timedelta(seconds=gap_seconds)
        done, now = [], list(state.get) if state.exists else None
        if state.hasTimedOut:
            done, now = [now], None
            state.remove()
        else:
            rows = pd.concat([pd.DataFrame({"ts": b["ts"], "u": b["u"]}) for b in batches]).sort_values("ts")
            for ts, u in zip(rows["ts"], rows["u"], strict=True):
                if now is not None and ts - now[1] >= gap:
                    done.append(now)
                    now = None
                now = [ts, ts, 1, u] if now is None else [min(now[0], ts), max(now[1], ts), now[2] + 1, now[3] + u]
            state.update(tuple(now))
            state.setTimeoutTimestamp(max(int((now[1] + gap).value // 1_000_000), state.getCurrentWatermarkMs() + 1))
        if done:
            yield pd.DataFrame({"user_id": [key[0]] * len(done), "start": [d[0] for d in done], "n": [d[2] for d in done], "tu": [int(d[3]) for d in done]})

    rows = valid(events).withWatermark("ts", late).select("user_id", "ts", cents("value").alias("u"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, start timestamp, n bigint, tu bigint", _OPEN, "append", "EventTimeTimeout")


def mine_windows(rows: DataFrame, min_util, min_cor) -> DataFrame:
    """``start, pattern, ...`` of each window in ``rows``, all windows in one run; no rows, no patterns."""
    return mine_keyed(rows, "start", min_util, min_cor)


def window_miner(sink: Callable[[DataFrame, int], None], min_util, min_cor) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch`` after ``window_baskets``: mines the windows that closed; the sink gets the batch number to stay idempotent."""
    def run(batch: DataFrame, number: int) -> None:
        found = mine_windows(batch, min_util, min_cor)
        sink(found, number)
        delete_tables(found)

    return run
