"""Quota-balanced iterative rejection: queues by task, smoothed effective rates, quotas, re-queue of hard samples.

Only one row a task ever visits the driver. Pools and re-queues are DataFrames; between rounds they live in storage."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TASKS_AT_MOST = 100_000


def enqueue(pool: DataFrame, order_cols: list[str]) -> DataFrame:
    """Each task's queue: fresh_pos from 1."""
    return pool.withColumn("fresh_pos", F.row_number().over(Window.partitionBy("task").orderBy(*order_cols)).cast("long"))


def outcomes(rollouts: DataFrame, keys: list[str], tolerance: float = 1e-9) -> DataFrame:
    """(keys, effective, hard, easy) of each sample's group: effective when its rewards are not all equal."""
    return rollouts.groupBy(*keys).agg(
        (F.max("reward") - F.min("reward") > tolerance).alias("effective"),
        (~F.bool_or("correct")).alias("hard"),
        F.bool_and("correct").alias("easy"),
    )


def effective_rate(draws: DataFrame, by: list[str]) -> DataFrame:
    """sampled, effective and eta of each group of draws."""
    return draws.groupBy(*by).agg(F.count(F.lit(1)).alias("sampled"), F.count_if("effective").alias("effective")).withColumn("eta", F.try_divide(F.col("effective").cast("double"), F.col("sampled")))


def ema_step(last: float, eta: float | None, beta: float) -> float:
    """The next smoothed rate; a task that drew nothing keeps its own."""
    return last if eta is None else beta * last + (1 - beta) * eta


def ema_rates(rates: DataFrame, init: Column, beta: float, task: str = "task", iteration: str = "iter") -> DataFrame:
    """Batch replay: adds eta_ema along the iterations of each task, by one fold over its series."""
    series = rates.groupBy(task).agg(F.array_sort(F.collect_list(F.struct(F.col(iteration).alias("i"), "eta", "sampled", "effective"))).alias("s"))
    start = F.struct(init.cast("double").alias("v"), F.array().cast("array<double>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        v = F.when(x["eta"].isNull(), acc["v"]).otherwise(beta * acc["v"] + (1 - beta) * x["eta"])
        return F.struct(v.alias("v"), F.array_append(acc["out"], v).alias("out"))

    smooth = F.aggregate("s", start, step, lambda a: a["out"])
    rows = series.select(task, F.explode(F.arrays_zip(F.col("s").alias("s"), smooth.alias("e"))).alias("x"))
    return rows.select(task, F.col("x.s.i").alias(iteration), F.col("x.s.sampled").alias("sampled"), F.col("x.s.effective").alias("effective"), F.col("x.s.eta").alias("eta"), F.col("x.e").alias("eta_ema"))


def next_quota(eta_ema: Column, subset_size: Column | float, n_tasks: Column | int, floor: float, rounding: str = "ceil") -> Column:
    """Draws that should give subset_size / n_tasks effective samples; the rate is held above `floor`."""
    raw = F.round(subset_size / (n_tasks * F.greatest(eta_ema, F.lit(floor))), 9)
    return (F.ceil(raw) if rounding == "ceil" else F.floor(raw)).cast("long")


def largest_remainder(rates: DataFrame, total: int, floor: float) -> DataFrame:
    """(task, quota) that add up to `total` exactly: shares in proportion to 1 / rate, rounded down, the rest to the largest
    remainders. One row a task."""
    need = rates.select("task", (1 / F.greatest("eta_ema", F.lit(floor))).alias("w"))
    all_ = Window.partitionBy()
    raw = need.withColumn("raw", F.round(F.col("w") * total / F.sum("w").over(all_), 9)).withColumn("base", F.floor("raw"))
    place = F.row_number().over(Window.orderBy(F.desc(F.col("raw") - F.col("base")), "task"))
    return raw.withColumn("_at", place).withColumn("_left", F.lit(total) - F.sum("base").over(all_)).select("task", (F.col("base") + (F.col("_at") <= F.col("_left")).cast("long")).alias("quota"))


def quota_of(rate: float, subset_size: int, n_tasks: int, floor: float) -> int:
    return math.ceil(round(subset_size / (n_tasks * max(rate, floor)), 9))


@dataclass
class State:
    """One row a task: smoothed rate, fresh cursor, length of the fresh queue."""

    rate: dict[str, float]
    cursor: dict[str, int] = field(default_factory=dict)
    length: dict[str, int] = field(default_factory=dict)


def fresh_ranges(pool: DataFrame, ranges: list[tuple], literal_tasks: int = 500) -> DataFrame:
    """Pool rows whose position lies in its task's range: (task, lo, hi) with lo < position <= hi.

    Up to `literal_tasks` ranges go into the filter as constants, which the scan of a pool laid out by `write_pool` prunes
    files and row groups with; more are joined as a small table, under constant bounds over all of them."""
    at = F.col("fresh_pos")
    some = [(t, lo, hi) for t, lo, hi in ranges if hi > lo]
    if not some:
        return pool.limit(0)
    low, high = min(lo for _, lo, _ in some), max(hi for *_, hi in some)
    bounded = pool.filter((at > low) & (at <= high))
    if len(some) <= literal_tasks:
        hit = None
        for t, lo, hi in some:
            one = (F.col("task") == F.lit(t)) & (at > lo) & (at <= hi)
            hit = one if hit is None else hit | one
        return bounded.filter(hit)
    kind = dict(pool.dtypes)["task"]
    table = pool.sparkSession.createDataFrame(some, f"task {kind}, lo long, hi long")
    return bounded.join(F.broadcast(table), "task").filter((at > F.col("lo")) & (at <= F.col("hi"))).drop("lo", "hi")


def draw(pool: DataFrame, requeue: DataFrame, quotas: list[tuple]) -> DataFrame:
    """(task, sample_id, requeue_no, source, at): fresh rows first, by range of position, then re-queued ones in order.

    `quotas` has one row a task: (task, lo, hi, shortfall), fresh positions half-open below."""
    kind = dict(pool.dtypes)["task"]
    fresh = fresh_ranges(pool, [q[:3] for q in quotas]).select("task", "sample_id", F.lit(0).alias("requeue_no"), F.lit("fresh").alias("source"), F.col("fresh_pos").alias("at"))
    quotas = F.broadcast(pool.sparkSession.createDataFrame([(t, s) for t, _, _, s in quotas], f"task {kind}, shortfall long"))
    place = F.row_number().over(Window.partitionBy("task").orderBy("enq_round", "enq_seq"))
    again = requeue.withColumn("_at", place.cast("long")).join(quotas, "task").filter(F.col("_at") <= F.col("shortfall")).select("task", "sample_id", "requeue_no", F.lit("requeued").alias("source"), F.col("_at").alias("at"))
    return fresh.unionByName(again)


def requeue_hard(requeue: DataFrame, drawn: DataFrame, r_max: int, round_no: int) -> DataFrame:
    """The re-queue after a round: drawn rows leave, hard ones come back at the end until re-queued r_max times. Fresh
    draws go in by position, then re-queued ones by their place. Easy and effective samples leave for good."""
    left = requeue.join(drawn.filter("source = 'requeued'").select("task", "sample_id"), ["task", "sample_id"], "left_anti")
    back = drawn.filter("hard").withColumn("requeue_no", F.col("requeue_no") + 1).filter(F.col("requeue_no") <= r_max)
    order = Window.partitionBy("task").orderBy(F.when(F.col("source") == "fresh", 0).otherwise(1), "at")
    back = back.select("task", "sample_id", "requeue_no", F.lit(round_no).alias("enq_round"), F.row_number().over(order).cast("long").alias("enq_seq"))
    return left.unionByName(back)


def sample_status(history: DataFrame, r_max: int = 3) -> DataFrame:
    """Last state of each drawn sample: trained (effective), mastered (easy), and of the hard ones waiting in the re-queue
    or exhausted (re-queued r_max times)."""
    last = history.groupBy("task", "sample_id").agg(F.max_by(F.struct("effective", "hard", "requeue_no"), "iter").alias("x"), F.count(F.lit(1)).alias("draws"))
    return last.select("task", "sample_id", "draws", F.when(F.col("x.effective"), "trained").when(F.col("x.hard") & (F.col("x.requeue_no") < r_max), "waiting").when(F.col("x.hard"), "exhausted").otherwise("mastered").alias("status"))


def intensity(history: DataFrame, pool: DataFrame) -> DataFrame:
    """Draws a sample by task against the task's size."""
    size = pool.groupBy("task").agg(F.count(F.lit(1)).alias("size"))
    drawn = history.groupBy("task").agg(F.count(F.lit(1)).alias("draws"), F.countDistinct("sample_id").alias("samples"))
    return size.join(drawn, "task", "left").select("task", "size", F.coalesce("draws", F.lit(0)).alias("draws"), F.coalesce("samples", F.lit(0)).alias("samples"), (F.coalesce("draws", F.lit(0)) / F.col("size")).alias("intensity"))


def assemble_batches(rows: DataFrame, batch_size: int, tie: str = "sample_id") -> DataFrame:
    """Adds `batch`: rows dealt in turns over (task, tier), so that each batch holds near-equal numbers of each."""
    turn = F.row_number().over(Window.partitionBy("task", "tier").orderBy(tie))
    place = F.row_number().over(Window.orderBy("turn", "task", "tier", tie))
    return rows.withColumn("turn", turn).withColumn("batch", F.floor((place - 1) / batch_size)).drop("turn")


def run_iterations(
    spark: SparkSession,
    pool: DataFrame,
    rollout_fn: Callable[[DataFrame, int], DataFrame],
    path: str,
    subset_size: int,
    rounds: int,
    beta: float = 0.8,
    floor: float = 1 / 64,
    r_max: int = 3,
    probe: int = 32,
    requeue: bool = True,
    refresh: bool = True,
    signal: str = "effective",
) -> tuple[DataFrame, list[dict]]:
    """All rounds: probe, quotas, draws, rollouts, rates, re-queue. Returns the history (also at path/history) and one
    report row a task and round.

    `pool` (task, sample_id, fresh_pos); `rollout_fn(rows with task and sample_id, iteration)` gives their outcomes
    (task, sample_id, effective, hard, easy). `signal='hard_only'` takes the rate over draws that are not easy."""
    lengths = {r["task"]: r["n"] for r in pool.groupBy("task").agg(F.max("fresh_pos").alias("n")).limit(TASKS_AT_MOST).collect()}
    tasks = sorted(lengths)
    if len(tasks) == TASKS_AT_MOST:
        raise ValueError("more tasks than one driver row each can hold")

    def rates_of(drawn: DataFrame) -> dict[str, tuple[int, int, int]]:
        got = drawn.groupBy("task").agg(F.count(F.lit(1)).alias("s"), F.count_if("effective").alias("e"), F.count_if(~F.col("easy")).alias("u")).collect()
        return {r["task"]: (r["s"], r["e"], r["u"]) for r in got}

    eta = lambda x: None if x is None or (x[2] if signal == "hard_only" else x[0]) == 0 else x[1] / (x[2] if signal == "hard_only" else x[0])
    tried = rates_of(rollout_fn(pool.filter(F.col("fresh_pos") <= probe).select("task", "sample_id"), 0))
    state = State({t: eta(tried.get(t)) or 0.0 for t in tasks}, dict.fromkeys(tasks, 0), lengths)
    kinds = dict(pool.dtypes)
    empty = f"task {kinds['task']}, sample_id {kinds['sample_id']}, requeue_no int, enq_round int, enq_seq long"
    waiting, report = spark.createDataFrame([], empty), []
    waiting_n: dict[str, int] = {}
    for i in range(1, rounds + 1):
        rows = []
        for t in tasks:
            q = quota_of(state.rate[t], subset_size, len(tasks), floor)
            lo = state.cursor[t]
            hi = min(lo + q, state.length[t])
            rows.append((t, lo, hi, min(q - (hi - lo), waiting_n.get(t, 0)) if requeue else 0, q))
        picked = draw(pool, waiting, [r[:4] for r in rows])
        done = picked.join(rollout_fn(picked.select("task", "sample_id"), i), ["task", "sample_id"]).withColumn("iter", F.lit(i))
        done.write.mode("overwrite").parquet(f"{path}/history/round={i}")
        done = spark.read.parquet(f"{path}/history/round={i}")
        if requeue:
            requeue_hard(waiting, done, r_max, i).write.mode("overwrite").parquet(f"{path}/requeue/round={i}")
            waiting = spark.read.schema(empty).parquet(f"{path}/requeue/round={i}")
            waiting_n = {r["task"]: r["n"] for r in waiting.groupBy("task").agg(F.count(F.lit(1)).alias("n")).collect()}
        got = rates_of(done)
        for t, lo, hi, short, q in rows:
            state.rate[t] = ema_step(state.rate[t], eta(got.get(t)), beta)
            s, e, _ = got.get(t, (0, 0, 0))
            report.append({"iter": i, "task": t, "quota": q, "fresh": hi - lo, "requeued": short, "sampled": s, "effective": e, "eta_ema": state.rate[t]})
            state.cursor[t] = hi if refresh else 0
    history = spark.read.parquet(f"{path}/history")
    return history, report
