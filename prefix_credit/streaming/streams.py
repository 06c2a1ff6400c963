"""The same operators on unbounded input: rates, sessions, smoothed rates, queues, and the prefix tree kept up to date."""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import trie
from ..plans.forms import bounded_broadcast


def clean_stream(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Events with a watermark, each event_id once; rows later than the delay are dropped."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def stream_rates(events: DataFrame, size: str = "1 day", slide: str | None = None, tasks: int = 5) -> DataFrame:
    """(task, start, sampled, effective, eta) of each window: a user's window is a group, effective when it mixes
    purchases with other events. Two chained aggregates; rows come out once the watermark passes the window."""
    bought = F.col("event_type") == "purchase"
    groups = events.groupBy(F.window("ts", size, slide) if slide else F.window("ts", size), "user_id").agg((F.bool_or(bought) & F.bool_or(~bought)).alias("effective"))
    groups = groups.select("window", (F.col("user_id") % tasks).cast("int").alias("task"), "effective")
    out = groups.groupBy("window", "task").agg(F.count(F.lit(1)).alias("sampled"), F.count_if("effective").alias("effective"))
    return out.select("task", F.col("window.start").alias("start"), "sampled", "effective", F.try_divide(F.col("effective").cast("double"), F.col("sampled")).alias("eta"))


def stream_sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """(user_id, start, steps, r): sessions as plans; one stays open until the watermark passes its gap."""
    step = F.struct("ts", "event_id", "event_type")
    out = events.groupBy(F.session_window("ts", gap).alias("session"), "user_id").agg(F.sort_array(F.collect_list(step)).alias("e"))
    good = F.exists("e", lambda x: x["event_type"] == "purchase") & (F.element_at("e", -1)["event_type"] != "error")
    return out.select("user_id", F.col("session.start").alias("start"), F.transform("e", lambda x: x["event_type"]).alias("steps"), F.when(good, 1).otherwise(-1).alias("r"))


def stream_ema(rates: DataFrame, init: float = 0.5, beta: float = 0.8) -> DataFrame:
    """(task, start, eta, eta_ema): the smoothed rate as keyed state. Rates of one batch are taken in time order; one
    older than the state's last is given the smoothed rate as it stands and doesn't move it."""

    def fold(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        value, last = state.get if state.exists else (init, pd.Timestamp(0).value)
        rows = pd.concat(list(parts)).sort_values("start")
        out = []
        for start, eta in zip(rows["start"], rows["eta"], strict=True):
            if start.value > last:
                last = start.value
                if pd.notna(eta):
                    value = beta * value + (1 - beta) * eta
            out.append((key[0], start, eta, value))
        state.update((value, last))
        yield pd.DataFrame(out, columns=["task", "start", "eta", "eta_ema"])

    return rates.groupBy("task").applyInPandasWithState(fold, "task int, start timestamp, eta double, eta_ema double", "value double, last long", "append", GroupStateTimeout.NoTimeout)


def stream_queue(outcomes: DataFrame, r_max: int = 3) -> DataFrame:
    """The re-queue as keyed state. Input (task, seq, sample_id, requeue_no, kind): kind `hard` puts the sample at the end of
    its task's queue unless it was re-queued r_max times (requeue_no, as the draw that gave it says), `draw` takes the
    head; output (task, seq, sample_id, requeue_no) of each draw that found one. The state holds waiting samples only."""

    def serve(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, times = (deque(x) for x in state.get) if state.exists else (deque(), deque())
        out = []
        for seq, sample, no, kind in pd.concat(list(parts)).sort_values("seq")[["seq", "sample_id", "requeue_no", "kind"]].itertuples(index=False):
            if kind == "hard" and no < r_max:
                ids.append(int(sample))
                times.append(int(no) + 1)
            elif kind == "draw" and ids:
                out.append((key[0], seq, ids.popleft(), times.popleft()))
        state.update((list(ids), list(times)))
        yield pd.DataFrame(out, columns=["task", "seq", "sample_id", "requeue_no"])

    return outcomes.groupBy("task").applyInPandasWithState(serve, "task string, seq long, sample_id long, requeue_no int", "ids array<long>, times array<int>", "append", GroupStateTimeout.NoTimeout)


def stream_with_thresholds(events: DataFrame, thresholds: DataFrame, on: str) -> DataFrame:
    """Stream rows with the static threshold of their key."""
    return events.join(bounded_broadcast(thresholds), on, "left")


def stream_votes(plans: DataFrame, votes: DataFrame, within: str = "1 hour") -> DataFrame:
    """Plans (traj, ts) with votes (v_traj, v_ts, vote) that come up to `within` after them; both with watermarks, so
    the join's state is bounded."""
    soon = (F.col("traj") == F.col("v_traj")) & (F.col("v_ts") >= F.col("ts")) & (F.col("v_ts") <= F.col("ts") + F.expr(f"interval {within}"))
    return plans.join(votes, soon, "inner")


def trie_sink(path: str, gamma: float) -> Callable[[DataFrame, int], None]:
    """foreachBatch that writes the node sums of a batch of keyed steps to path/batch=N: work in proportion to the batch. A
    batch that comes twice overwrites its own folder, so a replay changes nothing."""

    def write(batch: DataFrame, batch_id: int) -> None:
        trie.node_sums(batch, gamma).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return write


def stream_trie(steps: DataFrame, path: str, checkpoint: str, gamma: float) -> StreamingQuery:
    return steps.writeStream.foreachBatch(trie_sink(path, gamma)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def latest_trie(spark: SparkSession, path: str, base: DataFrame | None = None, after: int = -1) -> DataFrame:
    """Node sums of all batches above `after`, merged with those of `base` (a tree compacted up to `after`)."""
    found = spark.read.parquet(path).filter(F.col("batch") > after).drop("batch")
    empty = found.limit(0) if base is None else base
    return trie.merge_trie(empty, found)


def compact_trie(spark: SparkSession, path: str, upto: int, to: str, base: DataFrame | None = None, after: int = -1) -> DataFrame:
    """Batches above `after` up to `upto` merged with `base` into one table at `to`; they may be deleted afterwards."""
    found = spark.read.parquet(path).filter((F.col("batch") > after) & (F.col("batch") <= upto)).drop("batch")
    trie.merge_trie(found.limit(0) if base is None else base, found).write.parquet(to)
    return spark.read.parquet(to)


def start_sink(df: DataFrame, where: str, checkpoint: str, name: str | None = None, mode: str = "append", once: bool = True) -> StreamingQuery:
    """To a Parquet folder, or to a memory table when `name` is given; `once` drains what is there and stops."""
    w = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint)
    w = w.trigger(availableNow=True) if once else w.trigger(processingTime="10 seconds")
    return w.format("memory").queryName(name).start() if name else w.format("parquet").start(where)
