"""Streaming front end: interaction streams, windows, expiry of idle ties, the change queue's feed."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.state import GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, users: int, files_per_trigger: int = 1) -> DataFrame:
    """event_id, ts, src, dst from a folder of event files."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "*events*").parquet(folder)
    k = F.get_json_object("props", "$.k").cast("long")
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src"), F.pmod(k, F.lit(users)).alias("dst"))


def load_stream(spark: SparkSession, rate: int = 10) -> DataFrame:
    """A rate source as interactions, for speed-up tests."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rate).load()
    return raw.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), (F.col("value") % 17).alias("src"), (F.col("value") % 5).alias("dst"))


def throughput_stream(stream: DataFrame, bucket: str = "10 minutes", late: str = "1 day") -> DataFrame:
    """start, events of each bucket, closed by the watermark."""
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", bucket).alias("w"))
    return w.agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "events")


def active_ties(stream: DataFrame, length: str = "7 days", slide: str = "1 day", late: str = "1 day") -> DataFrame:
    """start, src, dst, calls in sliding windows."""
    ties = stream.where("src <> dst").withColumn("a", F.least("src", "dst")).withColumn("b", F.greatest("src", "dst"))
    w = ties.withWatermark("ts", late).groupBy(F.window("ts", length, slide).alias("w"), "a", "b")
    return w.agg(F.count(F.lit(1)).alias("calls")).select(F.col("w.start").alias("start"), F.col("a").alias("src"), F.col("b").alias("dst"), "calls")


def user_bursts(stream: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """start, src, events of sessions."""
    w = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "src")
    return w.agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "src", "events")


def deduplicated(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Replayed events once."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def reciprocated(stream: DataFrame, within: str = "1 day", late: str = "1 day") -> DataFrame:
    """Calls that are called back in time: an interval join of the stream with itself."""
    a = stream.where("src <> dst").withWatermark("ts", late).select(F.col("ts").alias("ts1"), F.col("src").alias("s1"), F.col("dst").alias("d1"))
    b = stream.where("src <> dst").withWatermark("ts", late).select(F.col("ts").alias("ts2"), F.col("src").alias("s2"), F.col("dst").alias("d2"))
    return a.join(b, F.expr(f"s1 = d2 and d1 = s2 and ts2 > ts1 and ts2 <= ts1 + interval {within}")).select("ts1", "s1", "d1", "ts2")


#: Groups that ties are dealt over; a group's ties are one state.
TIE_GROUPS = 4096


def expire_and_take(held: np.ndarray, new: np.ndarray, idle: int, watermark: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ties held (src, dst, last call) after new calls (src, dst, time), and the changes told: additions and deletions (src, dst, time).

    All times are microseconds. A tie without a new call goes once the watermark (in
    milliseconds) has passed its last call by the idle time.
    """
    both = np.concatenate([held, new])
    old = np.arange(len(both)) < len(held)
    order = np.lexsort((both[:, 2], ~old, both[:, 1], both[:, 0]))
    both, old = both[order], old[order]
    first = np.ones(len(both), bool)
    first[1:] = (both[1:, :2] != both[:-1, :2]).any(axis=1)
    tie = np.cumsum(first) - 1
    begin = np.flatnonzero(first)
    times = both[:, 2].copy()
    # calls ascend but for the last one held, which a late call doesn't set back
    after = old[begin][tie] & ~old
    times[after] = np.maximum(times[after], both[begin, 2][tie[after]])
    gap = np.zeros(len(both), bool)
    gap[1:] = ~first[1:] & (times[1:] - times[:-1] > idle)
    told = both[(first & ~old) | gap]
    before = np.flatnonzero(gap) - 1
    gone = np.stack([both[before, 0], both[before, 1], times[before] + idle], axis=1)
    end = np.append(begin[1:], len(both)) - 1 if len(both) else begin
    left = np.stack([both[end, 0], both[end, 1], times[end]], axis=1)
    # a tie with one row, held before, has no new call
    over = old[end] & ((left[:, 2] + idle) // 1000 + 1 <= watermark)
    expired = left[over]
    return left[~over], told, np.concatenate([gone, expired + [0, 0, idle]])


def expiring_ties(stream: DataFrame, idle_days: int = 7, late: str = "1 day") -> DataFrame:
    """Changes (op, src, dst, ts): add_edge at a tie's first call, del_edge once it was idle too long.

    State is one timestamp (microseconds) a tie. Ties are dealt over groups, which are
    handled as arrays; a group's event-time timer fires with the watermark, once that has
    passed its oldest last call by the idle time.
    """
    idle = idle_days * 86_400_000_000

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = np.frombuffer(state.get[0], np.int64).reshape(-1, 3) if state.exists else np.zeros((0, 3), np.int64)
        new = [np.zeros((0, 3), np.int64)]
        if not state.hasTimedOut:
            new += [f[["src", "dst", "us"]].to_numpy(np.int64) for f in frames]
        watermark = state.getCurrentWatermarkMs()
        left, told, gone = expire_and_take(held, np.concatenate(new), idle, watermark)
        if len(left):
            state.update((left.tobytes(),))
            state.setTimeoutTimestamp(max((int(left[:, 2].min()) + idle) // 1000 + 1, watermark + 1))
        else:
            state.remove()
        rows = np.concatenate([told, gone])
        op = np.repeat(["add_edge", "del_edge"], [len(told), len(gone)])
        yield pd.DataFrame({"op": op, "src": rows[:, 0], "dst": rows[:, 1], "ts": pd.to_datetime(rows[:, 2], unit="us")})

    ties = stream.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "ts")
    dealt = ties.withWatermark("ts", late).select(F.pmod(F.xxhash64("src", "dst"), F.lit(TIE_GROUPS)).alias("g"), "src", "dst", F.unix_micros("ts").alias("us"), "ts")
    return dealt.groupBy("g").applyInPandasWithState(step, "op string, src long, dst long, ts timestamp", "held binary", "append", GroupStateTimeout.EventTimeTimeout)


class TieExpiry(StatefulProcessor):
    """The same by the newer state interface (needs the RocksDB state store)."""

    def __init__(self, idle_ms: int = 7 * 86_400_000):
        self.idle = idle_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.last = handle.getValueState("last", "last long")

    def handleInputRows(self, key, rows, timerValues):
        last = self.last.get()[0] if self.last.exists() else None
        out = []
        for t in sorted(int(t.timestamp() * 1000) for f in rows for t in f.ts):
            if last is None or t - last > self.idle:
                if last is not None:
                    out.append(("del_edge", last + self.idle))
                out.append(("add_edge", t))
            last = t if last is None else max(last, t)
        for timer in list(self.handle.listTimers()):
            self.handle.deleteTimer(timer)
        self.last.update((last,))
        self.handle.registerTimer(last + self.idle)
        yield pd.DataFrame([(op, *key, pd.Timestamp(ms, unit="ms")) for op, ms in out], columns=["op", "src", "dst", "ts"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        last = self.last.get()[0]
        self.last.clear()
        yield pd.DataFrame([("del_edge", *key, pd.Timestamp(last + self.idle, unit="ms"))], columns=["op", "src", "dst", "ts"])

    def close(self) -> None:
        pass


def drain_to(stream: DataFrame, folder: str, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Run a finite stream to its end into Parquet files in a shared ``folder`` and give what they hold.

    append: rows as the watermark closes them; groups that it hasn't passed at the end stay
    open. update: with ``keys``, the last row of each key, so that open groups count too.
    complete: the result table of the last batch.
    """
    out = f"{folder}/out"
    if mode == "append":
        writer = stream.writeStream.outputMode(mode).format("parquet").option("path", out)
    else:
        # a batch that runs again writes the same folder again
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{out}/batch={n}"))
    query = writer.option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark = stream.sparkSession
    found = spark.read.schema(stream.schema).parquet(out) if mode == "append" else spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])).parquet(out)
    if mode == "append":
        return found
    if mode == "complete":
        last = found.agg(F.max("batch").alias("batch"))
        return found.join(F.broadcast(last), "batch", "left_semi").drop("batch")
    rest = [c for c in stream.columns if c not in keys]
    return found.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("r")).select(*keys, "r.*")


def for_each_batch(stream: DataFrame, checkpoint: str, work: Callable[[DataFrame, int], None]) -> None:
    """Feed micro-batches to ``work`` (which should be idempotent by batch id) until the input ends."""
    query = stream.writeStream.foreachBatch(work).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
