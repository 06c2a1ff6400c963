"""Judging steps by the tree, choosing next steps, and replanning after a failure."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import trie


def settled(q: Column | str) -> Column:
    """A mean return to nine digits, the same whatever order its returns were added in: twelve digits first, since means
    of few returns often end in a five at the tenth digit, and a sum that cancels may miss zero by a last bit."""
    return F.round(F.round(q, 12), 9)


def best_children(nodes: DataFrame) -> DataFrame:
    """(task, t, parent_key, best, best_q): the best-valued continuation of each prefix, ties to the larger action text."""
    pick = F.max_by(F.struct(trie.action_text(F.col("action")).alias("action"), "q"), F.struct(settled("q").alias("q"), trie.action_text(F.col("action")).alias("action")))
    return nodes.groupBy("task", F.col("depth").alias("t"), "parent_key").agg(pick.alias("b")).select("task", "t", "parent_key", F.col("b.action").alias("best"), F.col("b.q").alias("best_q"))


def judge_steps(steps: DataFrame, nodes: DataFrame) -> DataFrame:
    """Adds `verdict` to steps whose prefix the tree knows: true when the step's node has a non-negative value, false when
    it has a negative one or was never seen under a known prefix; rows with an unknown prefix are left out."""
    known = nodes.select("task", F.col("depth").alias("t"), "parent_key").distinct()
    value = nodes.select("task", F.col("depth").alias("t"), "node_key", settled("q").alias("q"))
    return steps.join(known, ["task", "t", "parent_key"], "left_semi").join(value, ["task", "t", "node_key"], "left").withColumn("verdict", F.coalesce(F.col("q") >= 0, F.lit(False)))


def next_steps(steps: DataFrame, nodes: DataFrame) -> DataFrame:
    """Adds `best`, the tree's continuation of the step's prefix; steps of unknown prefixes are left out."""
    return steps.join(best_children(nodes), ["task", "t", "parent_key"])


def replan(steps: DataFrame, nodes: DataFrame) -> DataFrame:
    """One row a failed plan: the first step from the end back whose best sibling is worth more than it, what to do
    instead, and whether that sibling's value is positive. (task, traj, t, step, instead, instead_q, recovered)."""
    value = nodes.select("task", F.col("depth").alias("t"), "node_key", "q")
    rows = next_steps(steps.filter("r = -1"), nodes).join(value, ["task", "t", "node_key"])
    better = rows.filter(settled("best_q") > settled("q"))
    pick = F.max_by(F.struct("t", trie.action_text(F.col("action")).alias("step"), "best", "best_q"), "t")
    return better.groupBy("task", "traj").agg(pick.alias("x")).select("task", "traj", F.col("x.t").alias("t"), F.col("x.step").alias("step"), F.col("x.best").alias("instead"), F.col("x.best_q").alias("instead_q"), (settled("x.best_q") > 0).alias("recovered"))


def continue_from(starts: DataFrame, nodes: DataFrame, max_steps: int) -> DataFrame:
    """Plans taken on from a node by the best-valued child each time: `starts` (id, task, t, at: node key at depth t), at
    most `max_steps` deep. Adds the final depth and the value there."""
    best = nodes.groupBy("task", F.col("depth").alias("_d"), F.col("parent_key").alias("at")).agg(F.max_by(F.struct("node_key", "q"), F.struct(settled("q").alias("q"), trie.action_text(F.col("action")).alias("a"))).alias("_b"))
    now = starts.withColumn("end_q", F.lit(None).cast("double"))
    depths = nodes.agg(F.max("depth")).first()[0] or 0
    for _ in range(min(max_steps, depths)):
        now = now.join(best, (now["task"] == best["task"]) & (now["at"] == best["at"]) & (now["t"] + 1 == best["_d"]), "left").select(now["id"], now["task"], (now["t"] + F.col("_b").isNotNull().cast("int")).alias("t"), F.coalesce(F.col("_b.node_key"), now["at"]).alias("at"), F.coalesce(F.col("_b.q"), now["end_q"]).alias("end_q"))
    return now


def replan_and_continue(steps: DataFrame, nodes: DataFrame, max_steps: int, max_replans: int = 2) -> DataFrame:
    """One row a failed plan (task, traj, replans, success): the good prefix is kept, the best sibling taken at the last
    step that has a better one, and the plan continued by best children; if that ends badly, the next earlier such step
    is tried, up to `max_replans` times."""
    value = nodes.select("task", F.col("depth").alias("t"), "node_key", "q")
    rows = next_steps(steps.filter("r = -1"), nodes).join(value, ["task", "t", "node_key"]).filter(settled("best_q") > settled("q"))
    tries = rows.withColumn("try", F.row_number().over(Window.partitionBy("task", "traj").orderBy(F.desc("t")))).filter(F.col("try") <= max_replans)
    keyed = nodes.select("task", F.col("depth").alias("t"), "parent_key", trie.action_text(F.col("action")).alias("best"), F.col("node_key").alias("at"), F.col("q").alias("start_q"))
    starts = tries.select("task", "traj", "t", "parent_key", "best", "try").join(keyed, ["task", "t", "parent_key", "best"]).withColumn("id", F.struct("traj", "try", "start_q"))
    done = continue_from(starts.select("id", "task", "t", "at"), nodes, max_steps).withColumn("ok", settled(F.coalesce("end_q", "id.start_q")) > 0)
    return done.groupBy("task", F.col("id.traj").alias("traj")).agg(F.coalesce(F.min(F.when(F.col("ok"), F.col("id.try"))), F.max("id.try")).alias("replans"), F.bool_or("ok").alias("success"))
