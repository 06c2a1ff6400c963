"""Tabular policies: smoothed conditional distributions of the next action, sampling, and updates from advantages."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.forms import bounded_broadcast
from . import trie


def with_history(steps: DataFrame, order: int) -> DataFrame:
    """Adds `history`, the last `order` actions before the step ('' at the start)."""
    by = Window.partitionBy("task", "traj").orderBy("t")
    parts = [F.coalesce(F.lag(trie.action_text(F.col("action")), k).over(by), F.lit("")) for k in range(order, 0, -1)]
    return steps.withColumn("history", F.concat_ws("|", *parts) if parts else F.lit(""))


def action_counts(steps: DataFrame, order: int = 1, by: list[str] | None = None) -> DataFrame:
    """(by, history, action, c): sufficient statistics of tabular policies, summed before the shuffle."""
    rows = with_history(steps, order).select(*(by or []), "history", trie.action_text(F.col("action")).alias("action"))
    return rows.groupBy(*(by or []), "history", "action").agg(F.count(F.lit(1)).alias("c"))


def fit_counts(seen: DataFrame, alpha: float = 1.0, vocabulary: DataFrame | None = None) -> DataFrame:
    """(history, action, p) from (history, action, c), add-`alpha` smoothed over the vocabulary of actions."""
    words = (seen if vocabulary is None else vocabulary).select("action").distinct()
    if words.limit(100_001).count() > 100_000:
        raise ValueError("a tabular policy is meant for a vocabulary of at most 100,000 actions")
    grid = seen.select("history").distinct().crossJoin(F.broadcast(words))
    full = grid.join(seen, ["history", "action"], "left").withColumn("c", F.coalesce("c", F.lit(0)) + alpha)
    return full.withColumn("p", F.col("c") / F.sum("c").over(Window.partitionBy("history"))).select("history", "action", "p")


def fit_policy(steps: DataFrame, alpha: float = 1.0, order: int = 1, vocabulary: DataFrame | None = None) -> DataFrame:
    """Policy of keyed steps; histories are those seen."""
    return fit_counts(action_counts(steps, order), alpha, vocabulary)


def update_policy(policy: DataFrame, advantages: DataFrame, step_size: float) -> DataFrame:
    """Exponentiated-weights step: p * exp(step * mean advantage of (history, action)), renormalised."""
    mean = advantages.groupBy("history", "action").agg(F.avg("advantage").alias("a"))
    raised = policy.join(mean, ["history", "action"], "left").withColumn("w", F.col("p") * F.exp(step_size * F.coalesce("a", F.lit(0.0))))
    return raised.withColumn("p", F.col("w") / F.sum("w").over(Window.partitionBy("history"))).select("history", "action", "p")


def uniform(seed: int, *cols: str | Column) -> Column:
    """A repeatable number in [0, 1) for a row."""
    return F.pmod(F.xxhash64(F.lit(seed), *cols), F.lit(1 << 52)).cast("double") / float(1 << 52)


def modular_uniform(seed: int, *cols: str | Column) -> Column:
    """The same for whole-number columns by arithmetic that any engine can repeat: a weighted sum, twice squared, modulo a
    prime."""
    m, x = 1_000_003, F.lit(seed * 15_485_863 % 1_000_003).cast("long")
    for c, by in zip(cols, (7919, 104_729, 299_993, 611_953), strict=False):
        x = x + F.pmod(F.col(c) if isinstance(c, str) else c, F.lit(m)).cast("long") * by
    x = F.pmod(x, F.lit(m))
    for _ in range(2):
        x = F.pmod(x * (x + 7919) + 104_729, F.lit(m))
    return x.cast("double") / float(m)


def tempered(policy: DataFrame, temperature: float) -> DataFrame:
    by = Window.partitionBy("history")
    hot = policy.withColumn("w", F.pow("p", F.lit(1 / temperature)))
    return hot.withColumn("p", F.col("w") / F.sum("w").over(by)).select("history", "action", "p")


def with_bounds(policy: DataFrame) -> DataFrame:
    """(history, actions, bounds): the inverse of the cumulative distribution, one row a history."""
    by = Window.partitionBy("history").orderBy("action")
    cum = policy.withColumn("hi", F.round(F.sum("p").over(by), 9))
    return cum.groupBy("history").agg(F.sort_array(F.collect_list(F.struct("hi", "action"))).alias("cdf"))


def _drawn(u: Column) -> Column:
    hit = F.filter("cdf", lambda x: x["hi"] > u)
    return F.coalesce(F.get(hit, F.lit(0))["action"], F.element_at("cdf", -1)["action"])


def sample_answers(policy: DataFrame, samples: DataFrame, k: int, temperature: float, seed: int) -> DataFrame:
    """k independent draws a sample row (sample_id, history) at a raised temperature: (sample_id, cand_no, action)."""
    draws = samples.select("sample_id", "history", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("cand_no"))
    return draws.join(with_bounds(tempered(policy, temperature)), "history").select("sample_id", "cand_no", _drawn(uniform(seed, "sample_id", "cand_no")).alias("action"))


def sample_rollouts(policy: DataFrame, tasks: DataFrame, k: int, max_steps: int, seed: int, stop: str, temperature: float = 1.0, draws: Callable[..., Column] = uniform) -> DataFrame:
    """k plans a task (column task), drawn step by step from an order-1 policy until `stop` or `max_steps`; one
    small-table join a step. (task, traj, actions array<string>)."""
    table = bounded_broadcast(with_bounds(tempered(policy, temperature)))
    now = tasks.select("task", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(k).cast("long"))).alias("traj")).withColumns({"history": F.lit(""), "actions": F.array().cast("array<string>"), "live": F.lit(True)})
    for t in range(1, max_steps + 1):
        drawn = _drawn(draws(seed, "task", "traj", F.lit(t)))
        now = now.join(table, "history", "left").withColumn("_a", F.when(F.col("live") & F.col("cdf").isNotNull(), drawn)).drop("cdf")
        now = now.select("task", "traj", F.coalesce("_a", "history").alias("history"), F.when(F.col("_a").isNotNull(), F.array_append("actions", F.col("_a"))).otherwise(F.col("actions")).alias("actions"), (F.col("live") & F.coalesce(F.col("_a") != stop, F.lit(False))).alias("live"))
    return now.select("task", "traj", "actions")
