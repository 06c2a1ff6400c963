"""Co-evolution of a tabular policy and a panel of judges, round by round, with every round on storage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import credit, objective, policy, trie


def as_plans(rollouts: DataFrame) -> DataFrame:
    """(task, traj, actions array<string>) to packed plans without labels; an action is text as `trie.action_text` writes it."""
    return rollouts.select("task", "traj", F.transform("actions", lambda a: F.struct(trie.text_action(a).alias("action"), a.alias("text"))).alias("steps"))


def panel_votes(plans: DataFrame, truth: Column, weights: list[float], seed: int, skill: float = 0.8, draws: Callable[..., Column] = policy.uniform) -> DataFrame:
    """A verdict a judge: right with probability `skill` shifted by the judge's weight; (…, votes array<int>, truth)."""
    votes = [F.when(draws(seed + j, "task", "traj") < min(0.99, max(0.01, skill * w)), truth).otherwise(-truth) for j, w in enumerate(weights)]
    return plans.withColumn("truth", truth).withColumn("votes", F.array(*votes))


def weighted_label(votes: Column, weights: list[float]) -> Column:
    total = sum((F.get(votes, F.lit(j)) * F.lit(float(w)) for j, w in enumerate(weights)), F.lit(0.0))
    return F.when(total > 0, 1).otherwise(-1)


def update_judge(verdicts: DataFrame, n_judges: int, weights: list[float], rate: float, sample: int, eps: float = 1e-6, draws: Callable[..., Column] = policy.uniform) -> list[float]:
    """Group-relative step of the judges' weights: each verdict's reward is whether it agrees with the known outcome, its
    advantage is taken within the plan's group of verdicts, and a judge moves by its mean advantage."""
    few = verdicts.orderBy(draws(0, "task", "traj"), "task", "traj").limit(sample)
    rows = few.select("task", "traj", "truth", F.posexplode("votes").alias("judge", "vote"))
    rows = rows.withColumn("reward", (F.col("vote") == F.col("truth")).cast("double"))
    by = Window.partitionBy("task", "traj")
    rows = rows.withColumn("a", (F.col("reward") - F.avg("reward").over(by)) / F.sqrt(F.var_pop("reward").over(by) + eps))
    mean = {r["judge"]: r["a"] for r in rows.groupBy("judge").agg(F.avg("a").alias("a")).collect()}
    raised = [max(0.05, w * (1 + rate * mean.get(j, 0.0))) for j, w in enumerate(weights)]
    return [w * n_judges / sum(raised) for w in raised]


def sibling_rows(steps: DataFrame, gamma: float, eps: float) -> DataFrame:
    """One row a child of a branching parent: (task, depth, parent_key, node_key, history, action, q, n, k, advantage),
    flat ones too. `steps` are keyed and have their history."""
    rows = steps.withColumn("ret", trie.discounted_return(gamma))
    nodes = rows.groupBy("task", F.col("t").alias("depth"), "parent_key", "node_key", "history", trie.action_text(F.col("action")).alias("action")).agg(F.avg("ret").alias("q"), F.count(F.lit(1)).alias("n"))
    return credit.sibling_advantage(nodes, eps).filter("k > 1")


def run_rounds(spark: SparkSession, tasks: DataFrame, start: DataFrame, truth: Column, path: str, rounds: int, tasks_per_round: int, k: int, max_steps: int, stop: str, judges: int = 5, judge_sample: int = 500, gamma: float = 0.95, eps: float = 1e-6, delta: float = 0.001, step_size: float = 0.5, judge_rate: float = 0.1, kl_weight: float = 0.01, clip: float = 0.2, seed: int = 17, by: str = "sibling", draws: Callable[..., Column] = policy.uniform) -> list[dict]:
    """Rounds of: a batch of tasks -> sampled plans -> votes -> credit -> policy update -> judge update.

    `tasks` (task), taken in order, a batch a round; `start` is the policy (history, action, p); `truth` an expression over a
    packed plan giving +1/-1. `by` is sibling (step credit) or whole (the plan's advantage on each step, the baseline).
    Policies and plans are written at path/policy, path/plans; the ledger has one row a round."""
    start.write.mode("overwrite").parquet(f"{path}/policy/round=0")
    weights, ledger, last = [1.0] * judges, [], None
    reference = spark.read.parquet(f"{path}/policy/round=0")
    for i in range(1, rounds + 1):
        old = spark.read.parquet(f"{path}/policy/round={i - 1}")
        left = tasks.select("task") if last is None else tasks.select("task").filter(F.col("task") > F.lit(last))
        batch = left.orderBy("task").limit(tasks_per_round)
        plans = panel_votes(as_plans(policy.sample_rollouts(old, batch, k, max_steps, seed + 101 * i, stop, draws=draws)), truth, weights, seed + 1009 * i, draws=draws)
        plans = plans.withColumn("r", weighted_label(F.col("votes"), weights))
        plans.write.mode("overwrite").parquet(f"{path}/plans/round={i}")
        plans = spark.read.parquet(f"{path}/plans/round={i}")
        got = plans.agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("truth") == 1).cast("double")).alias("won"), F.avg((F.col("truth") == F.col("r")).cast("double")).alias("agree"), F.max("task").alias("last")).first()
        if not got["n"]:
            break
        last = got["last"]
        steps = policy.with_history(trie.with_prefix_keys(plans.select("task", "traj", "r", "steps")), 1)
        if by == "sibling":
            children = sibling_rows(steps, gamma, eps)
            held = credit.drop_flat(children, delta).select("task", F.col("depth").alias("t"), "node_key", "advantage")
            rows = steps.join(held, ["task", "t", "node_key"])
        else:
            whole = credit.trajectory_advantage(plans, eps).select("task", "traj", "advantage")
            rows = steps.join(whole.filter(F.abs("advantage") > delta), ["task", "traj"])
        rows = rows.select("task", "traj", "history", trie.action_text(F.col("action")).alias("action"), "advantage")
        rows.write.mode("overwrite").parquet(f"{path}/credit/round={i}")
        rows = spark.read.parquet(f"{path}/credit/round={i}")
        policy.update_policy(old, rows, step_size).write.mode("overwrite").parquet(f"{path}/policy/round={i}")
        new = spark.read.parquet(f"{path}/policy/round={i}")
        kl = objective.exact_kl(new, reference, ["history"])
        ratio = new.join(old.select("history", "action", F.col("p").alias("p_old")), ["history", "action"]).select("history", "action", (F.col("p") / F.col("p_old")).alias("rho"))
        if by == "sibling":
            loss = objective.sibling_loss(children.join(ratio, ["history", "action"]).join(kl, "history"), clip, kl_weight)
        else:
            terms = objective.plan_terms(steps.withColumn("action", trie.action_text(F.col("action"))).select("task", "traj", "history", "action"), ratio, kl)
            loss = objective.trajectory_loss(terms.join(whole, ["task", "traj"]), clip, kl_weight)
        loss = loss.agg(F.avg("loss")).first()[0]
        weights = update_judge(plans, judges, weights, judge_rate, judge_sample, draws=draws)
        ledger.append({"round": i, "plans": got["n"], "success": float(got["won"] or 0.0), "judge_agreement": float(got["agree"] or 0.0), "credit_rows": rows.count(), "loss": float(loss or 0.0)})
    return ledger


def success_by_seed(learnt: DataFrame, tasks: DataFrame, truth: Column, seeds: int, max_steps: int, stop: str, seed: int, draws: Callable[..., Column] = policy.uniform) -> DataFrame:
    """(seed, tasks, success_pct): one plan a task and seed from a policy, all in one sampling pass."""
    plans = as_plans(policy.sample_rollouts(learnt, tasks, seeds, max_steps, seed, stop, draws=draws))
    return plans.groupBy(F.col("traj").alias("seed")).agg(F.count(F.lit(1)).alias("tasks"), (100 * F.avg((truth == 1).cast("double"))).alias("success_pct"))
