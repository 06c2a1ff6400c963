"""Baselines: zero-advantage discard, exhaustive search, the stepwise agent."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import trie


def discard_sampling(outcomes: DataFrame, order: Column, wanted: int, tie: str = "sample_id", parts: int = 64) -> DataFrame:
    """Draws in one global order until `wanted` are effective; flat groups are thrown away. (…, draw_no, n_effective).

    The running count is kept by parts of the order: a bounded table of part totals, then a window inside each part."""
    rows = outcomes.withColumn("_o", order)
    cuts = rows.agg(F.percentile_approx("_o", [k / parts for k in range(1, parts)], 10_000)).first()[0] or []
    part = sum((F.when(F.col("_o") > c, 1).otherwise(0) for c in sorted(set(cuts))), F.lit(0))
    rows = rows.withColumn("_p", part)
    totals = rows.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"), F.count_if("effective").alias("_e"))
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select("_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_n0"), F.coalesce(F.sum("_e").over(before), F.lit(0)).alias("_e0"))
    inside = Window.partitionBy("_p").orderBy("_o", tie)
    run = rows.join(F.broadcast(totals), "_p").withColumn("draw_no", F.col("_n0") + F.row_number().over(inside))
    run = run.withColumn("n_effective", F.col("_e0") + F.sum(F.col("effective").cast("long")).over(inside.rowsBetween(Window.unboundedPreceding, 0)))
    return run.filter(F.col("n_effective") - F.col("effective").cast("long") < wanted).drop("_o", "_p", "_n0", "_e0")


def discard_loop(pool: DataFrame, rollout_fn: Callable[[DataFrame, int], DataFrame], order: Column, wanted: int, rounds: int, path: str, budget: int | None = None, refill: bool = True) -> DataFrame:
    """All rounds of the discard baseline, each on storage at path: uniform draws over what is left of the pool, no quotas
    and no re-queue, until `wanted` effective ones, `budget` draws or the end of the pool. With `refill` a round that
    finds the pool empty starts it anew. History: (task, sample_id, effective, hard, easy, draw_no, n_effective, iter)."""
    spark, left = pool.sparkSession, pool.select("task", "sample_id")
    for i in range(1, rounds + 1):
        if refill and left.isEmpty():
            left = pool.select("task", "sample_id")
        drawn = discard_sampling(rollout_fn(left, i), order, wanted)
        if budget is not None:
            drawn = drawn.filter(F.col("draw_no") <= budget)
        drawn.withColumn("iter", F.lit(i)).write.mode("overwrite").parquet(f"{path}/round={i}")
        done = spark.read.parquet(f"{path}/round={i}")
        left = left.join(done.select("task", "sample_id"), ["task", "sample_id"], "left_anti")
    return spark.read.parquet(path).drop("round")


def stepwise_recover(known: DataFrame, world: DataFrame, tasks: DataFrame, max_steps: int) -> DataFrame:
    """The agent that decides step by step and recovers in place: it takes the child that it thinks best (`known` nodes) of
    those that the world (`world` nodes, path keys) has at its place; when its own favourite is not there it has met an
    error and takes the best that is, an unknown child counting as worth 0. (task, steps, errors, last_q, success)."""
    thought = known.select("task", F.col("depth").alias("d"), F.col("parent_key").alias("at"), "node_key", F.round("q", 9).alias("thought"))
    favourite = thought.groupBy("task", "d", "at").agg(F.max_by("node_key", F.struct("thought", "node_key")).alias("favourite"))
    real = world.select("task", F.col("depth").alias("d"), F.col("parent_key").alias("at"), "node_key", F.round("q", 9).alias("q"))
    open_to = real.join(thought.select("task", "node_key", "thought"), ["task", "node_key"], "left").withColumn("thought", F.coalesce("thought", F.lit(0.0)))
    pick = open_to.groupBy("task", "d", "at").agg(F.max_by(F.struct("node_key", "q"), F.struct("thought", "node_key")).alias("b"))
    moves = pick.join(favourite, ["task", "d", "at"], "left")
    now = tasks.select("task", F.lit("").alias("at"), F.lit(0).alias("steps"), F.lit(0).alias("errors"), F.lit(None).cast("double").alias("last_q"))
    for t in range(1, min(max_steps, world.agg(F.max("depth")).first()[0] or 0) + 1):
        step = moves.filter(F.col("d") == t).drop("d")
        moved, missed = F.col("b").isNotNull(), F.col("favourite").isNotNull() & (F.col("favourite") != F.col("b.node_key"))
        now = now.join(step, ["task", "at"], "left").select("task", F.coalesce("b.node_key", "at").alias("at"), (F.col("steps") + moved.cast("int")).alias("steps"), (F.col("errors") + F.coalesce(moved & missed, F.lit(False)).cast("int")).alias("errors"), F.coalesce("b.q", "last_q").alias("last_q"))
    return now.select("task", "steps", "errors", "last_q", F.coalesce(F.col("last_q") > 0, F.lit(False)).alias("success"))


def expansion_cost(observed: DataFrame, alphabet: int, depth: int) -> DataFrame:
    """Nodes that a full tree would expand at each depth against those that plans visit: depth, full, full_total, observed."""
    seen = observed.groupBy("depth").agg(F.count(F.lit(1)).alias("observed"))
    levels = observed.sparkSession.range(1, depth + 1).select(F.col("id").cast("int").alias("depth"), F.pow(F.lit(float(alphabet)), F.col("id")).cast("long").alias("full"))
    return levels.withColumn("full_total", F.sum("full").over(Window.orderBy("depth"))).join(seen, "depth", "left").withColumn("observed", F.coalesce("observed", F.lit(0).cast("long")))


def exhaustive_tree(spark: SparkSession, actions: list[str], depth: int, budget: int = 100_000) -> DataFrame:
    """All action sequences up to a depth: (depth, path). Refused when it would pass the budget of nodes."""
    nodes = sum(len(actions) ** d for d in range(1, depth + 1))
    if nodes > budget:
        raise ValueError(f"{nodes} nodes are more than the budget of {budget}")
    verbs = F.broadcast(spark.createDataFrame([(a,) for a in actions], "action string"))
    level, out = verbs.select(F.lit(1).alias("depth"), F.concat(F.lit(">"), "action").alias("path")), None
    for d in range(1, depth + 1):
        out = level if out is None else out.unionByName(level)
        if d < depth:
            level = level.crossJoin(verbs).select(F.lit(d + 1).alias("depth"), F.concat("path", F.lit(">"), "action").alias("path"))
    return out


def backup_values(leaves: DataFrame, depth: int, how: str = "mean") -> DataFrame:
    """Values (path, value) of leaves at `depth` backed up level by level: (depth, path, value)."""
    agg = F.avg if how == "mean" else F.max
    level = leaves.select(F.lit(depth).alias("depth"), "path", "value")
    out = level
    for d in range(depth - 1, 0, -1):
        level = level.groupBy(F.regexp_replace("path", r">[^>]*$", "").alias("path")).agg(agg("value").alias("value")).select(F.lit(d).alias("depth"), "path", "value")
        out = out.unionByName(level)
    return out


def stepwise_agent(nodes: DataFrame, tasks: DataFrame, max_steps: int) -> DataFrame:
    """The agent that decides step by step: from the root, the best-valued child each time until no child is known.
    (task, steps, path_key, last_q); the lookup table of best children is made once."""
    best = nodes.groupBy("task", "depth", "parent_key").agg(F.max_by(F.struct("node_key", "q", F.col("action.action_type").alias("verb")), F.struct("q", trie.action_text(F.col("action")))).alias("b"))
    now = tasks.select("task", F.lit(trie.ROOT).cast(dict(nodes.dtypes)["node_key"]).alias("at"), F.lit(0).alias("steps"), F.lit(None).cast("double").alias("last_q"), F.lit(None).cast("string").alias("last_verb"))
    if dict(nodes.dtypes)["node_key"] == "string":
        now = now.withColumn("at", F.lit(""))
    for t in range(1, max_steps + 1):
        step = best.filter(F.col("depth") == t).select("task", F.col("parent_key").alias("at"), "b")
        now = now.join(step, ["task", "at"], "left").select("task", F.coalesce("b.node_key", "at").alias("at"), (F.col("steps") + F.col("b").isNotNull().cast("int")).alias("steps"), F.coalesce("b.q", "last_q").alias("last_q"), F.coalesce("b.verb", "last_verb").alias("last_verb"))
    return now
