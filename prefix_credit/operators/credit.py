"""Step credit by comparing siblings in the prefix tree, in three physical forms of one meaning.

* window: q, sibling mean and deviation by windows over step rows; everything after the task exchange stays in it;
* join: node table, sibling window, join back to the steps;
* salted: node table from partial sums without clustering by task (for tasks with millions of plans), then as join.

Node tables grow with the plans, so their joins ask for a merge: sizes after a shuffle are of compressed bytes, and
prefixes compress so well that a table taken for small fills the driver when it is broadcast.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import trie


def sibling_advantage(nodes: DataFrame, eps: float, weighting: str = "children", scale: bool = True) -> DataFrame:
    """Adds k, mu, sigma, advantage: each child against its siblings, every child once (`children`) or once a visit
    (`visits`); `scale=False` only centres."""
    by = Window.partitionBy("task", "depth", "parent_key")
    if weighting == "visits":
        total = F.sum("n").over(by)
        mu = F.sum(F.col("q") * F.col("n")).over(by) / total
        var = F.greatest(F.sum(F.col("q") * F.col("q") * F.col("n")).over(by) / total - mu * mu, F.lit(0.0))
    else:
        mu, var = F.avg("q").over(by), F.var_pop("q").over(by)
    out = nodes.withColumns({"k": F.count(F.lit(1)).over(by), "mu": mu, "sigma": F.sqrt(var + eps)})
    gap = F.col("q") - F.col("mu")
    return out.withColumn("advantage", gap / F.col("sigma") if scale else gap)


def drop_flat(rows: DataFrame, delta: float) -> DataFrame:
    """Rows whose advantage teaches something; single children never do."""
    return rows.filter((F.col("k") > 1) & (F.abs("advantage") > delta))


def _window_form(steps: DataFrame, gamma: float, eps: float) -> DataFrame:
    node = Window.partitionBy("task", "t", "parent_key", "node_key")
    parent = Window.partitionBy("task", "t", "parent_key")
    rows = steps.withColumn("q", F.avg(trie.discounted_return(gamma)).over(node)).withColumn("n", F.count(F.lit(1)).over(node))
    once = F.when(F.row_number().over(node.orderBy("traj")) == 1, F.col("q"))
    rows = rows.withColumn("_q1", once)
    rows = rows.withColumns({"k": F.count("_q1").over(parent), "mu": F.avg("_q1").over(parent), "sigma": F.sqrt(F.var_pop("_q1").over(parent) + eps)})
    return rows.withColumn("advantage", (F.col("q") - F.col("mu")) / F.col("sigma")).drop("_q1")


def _join_form(steps: DataFrame, gamma: float, eps: float, delta: float) -> DataFrame:
    nodes = drop_flat(sibling_advantage(trie.node_values(steps, gamma), eps), delta).select("task", F.col("depth").alias("t"), "node_key", "q", "n", "k", "mu", "sigma", "advantage")
    return steps.join(nodes.hint("merge"), ["task", "t", "node_key"])


def _salted_form(steps: DataFrame, gamma: float, eps: float, delta: float, salts: int) -> DataFrame:
    keys = ["task", "t", "parent_key", "node_key"]
    salted = steps.withColumn("_salt", F.pmod(F.xxhash64("traj"), F.lit(salts))).withColumn("ret", trie.discounted_return(gamma))
    part = salted.groupBy(*keys, "_salt").agg(F.sum("ret").alias("total"), F.count(F.lit(1)).alias("n"))
    nodes = part.groupBy(*keys).agg((F.sum("total") / F.sum("n")).alias("q"), F.sum("n").alias("n")).withColumnRenamed("t", "depth")
    nodes = drop_flat(sibling_advantage(nodes, eps), delta).select("task", F.col("depth").alias("t"), "node_key", "q", "n", "k", "mu", "sigma", "advantage")
    spread = nodes.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return salted.drop("ret").join(spread.hint("merge"), ["task", "t", "node_key", "_salt"]).drop("_salt")


def choose_form(plans: DataFrame, hot_plans: int = 100_000) -> str:
    """salted when a task has more than `hot_plans` plans, else window: one cheap aggregate."""
    top = plans.groupBy("task").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]
    return "salted" if (top or 0) > hot_plans else "window"


def credit_steps(plans: DataFrame, gamma: float, eps: float, delta: float, form: str = "window", keying: str = "hash", salts: int = 16, by_text: bool = False) -> DataFrame:
    """Keyed steps with q, n, k, mu, sigma, advantage, flat ones dropped."""
    if form == "auto":
        form = choose_form(plans)
    if form == "salted":
        plans = plans.repartition("task", "traj")
    steps = trie.with_prefix_keys(plans, keying, by_text)
    if form == "window":
        return drop_flat(_window_form(steps, gamma, eps), delta)
    if form == "join":
        return _join_form(steps, gamma, eps, delta)
    return _salted_form(steps, gamma, eps, delta, salts)


def credit_rows(plans: DataFrame, gamma: float, eps: float, delta: float, form: str = "window") -> DataFrame:
    """Training triplets: (task, traj, t), the raw steps before, the raw step, its advantage.

    The context is cut from the packed plan, which rides along with its steps, so that no join brings it back."""
    texts = F.transform("steps", lambda s: s["text"])
    carried = plans.withColumn("steps", F.transform("steps", lambda s, k: F.struct(s["action"].alias("action"), s["text"].alias("text"), F.slice(texts, F.lit(1), k).alias("context"))))
    rows = _with_context(carried, gamma, eps, delta, form)
    return rows.select("task", "traj", "t", "context", F.col("text").alias("step"), "advantage")


def _with_context(plans: DataFrame, gamma: float, eps: float, delta: float, form: str) -> DataFrame:
    """credit_steps with each step's context carried in its text field."""
    both = plans.withColumn("steps", F.transform("steps", lambda s: F.struct(s["action"].alias("action"), F.struct(s["text"].alias("text"), s["context"].alias("context")).alias("text"))))
    rows = credit_steps(both, gamma, eps, delta, form)
    return rows.select("task", "traj", "t", F.col("text.context").alias("context"), F.col("text.text").alias("text"), "advantage")


def trajectory_advantage(plans: DataFrame, eps: float) -> DataFrame:
    """Baseline: one advantage a plan, its label against the labels of the task's plans."""
    by = Window.partitionBy("task")
    return plans.withColumn("advantage", (F.col("r") - F.avg("r").over(by)) / F.sqrt(F.var_pop("r").over(by) + eps))


def spread(plans: DataFrame) -> DataFrame:
    """Baseline: the plan's advantage on every one of its steps."""
    return plans.select("task", "traj", "r", "advantage", F.posexplode("steps").alias("_p", "_s")).select("task", "traj", "r", (F.col("_p") + 1).alias("t"), F.col("_s.text").alias("step"), "advantage")


def contrast(plans: DataFrame, gamma: float, eps: float, delta: float, form: str = "window") -> DataFrame:
    """Kept steps by label of their plan: how many get positive and negative credit here, and how often the sign agrees
    with the whole-plan baseline."""
    steps = credit_steps(trajectory_advantage(plans, eps).withColumn("traj", F.struct("traj", F.col("advantage").alias("whole"))), gamma, eps, delta, form)
    whole = F.col("traj.whole")
    return steps.groupBy("r").agg(
        F.count(F.lit(1)).alias("steps"),
        F.count_if(F.col("advantage") > 0).alias("positive"),
        F.count_if(F.col("advantage") < 0).alias("negative"),
        F.count_if(F.signum("advantage") == F.signum(whole)).alias("same_sign"),
        F.count_if(F.abs(whole) <= delta).alias("flat_in_baseline"),
    )


