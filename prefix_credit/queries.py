"""The experiments' workloads on the given tables, one query each; `oracles` has the same in DuckDB's SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles
from .config import BANDS, SYNONYMS
from .config import DEFAULTS as C
from .functions import actions, measures, rewards
from .operators import baselines, credit, joins, objective, policy, quota, replan, strata, trie
from .plans.forms import bounded_broadcast
from .sources import workloads as W
from .sources.tables import load, with_props, write_pool

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = oracles.ORACLES


def query(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[f.__name__] = f
    return f


def r6(x: Column | str) -> Column:
    return F.round(F.col(x) if isinstance(x, str) else x, 6) + F.lit(0.0)


def nudged(x: Column | str, digits: int = 6) -> Column:
    """Rounded a hair above: exact halves, which discounted labels make, go the same way in every engine."""
    return F.round((F.col(x) if isinstance(x, str) else x) + F.lit(1e-9), digits) + F.lit(0.0)


def rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: r6(c) for c in cols})


def longs(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("long") for c in cols})


def kept(spark: SparkSession, df: DataFrame) -> DataFrame:
    """A result that several branches read, written once to the shared folder."""
    from .session import work_dir

    at = f"{work_dir(spark)}/kept"
    df.write.parquet(at)
    return spark.read.schema(df.schema).parquet(at)


# ---- corpus ---------------------------------------------------------------------------------------------------------


@query
def capability_mix(spark, sf):
    docs = strata.capability_mix(load(spark, sf, "documents", ["lang", "source"]), ["lang", "source"])
    return rounded(docs, "share")


@query
def balanced_draw(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "lang"])
    return strata.balanced_sample(docs, "lang", 40, strata.modular_order(F.col("doc_id")), "doc_id")


# ---- stage 1 --------------------------------------------------------------------------------------------------------


def part_candidates(spark, sf, iteration: int = 0, drawn: DataFrame | None = None) -> DataFrame:
    """CAND-P (iteration 0) and its improving replay: k answers a part with reward and verdict; of `drawn` parts only."""
    rows = W.part_answers(spark, sf, drawn)
    block = F.pmod(F.col("rn") - 8 * iteration, F.col("n")) < C.candidates
    rows = rows.filter(block).withColumn("reward", rewards.distance_reward(F.col("answer"), F.col("truth")))
    at = {k: v * 0.85**iteration for k, v in C.thresholds.items()}
    return rows.withColumn("correct", rewards.correct_if(F.col("reward"), F.col("task"), at))


@query
def strata_parts(spark, sf):
    return longs(strata.stratify(part_candidates(spark, sf)), "k", "n_correct")


@query
def strata_vectors(spark, sf):
    return longs(strata.stratify(W.vector_answers(spark, sf, C.candidates)), "k", "n_correct")


@query
def tuning_set(spark, sf):
    rows = strata.stratify(part_candidates(spark, sf))
    return strata.select_for_tuning(rows, C.easy_share, strata.modular_order(F.col("sample_id"))).select("sample_id", "task", "stratum")


@query
def answer_entropy(spark, sf):
    cands = part_candidates(spark, sf).withColumn("answer", F.floor(F.col("answer") / 100))
    return rounded(strata.answer_entropy(cands), "entropy")


@query
def filter_cost_rule(spark, sf):
    """What filtering by a rule costs and keeps: candidates scored, samples kept by filter and by chance."""
    rows = strata.stratify(part_candidates(spark, sf))
    kept = strata.select_for_tuning(rows, C.easy_share, strata.modular_order(F.col("sample_id")))
    all_ = rows.groupBy("task").agg(F.sum("k").alias("scored"), F.count(F.lit(1)).alias("samples"), F.avg(F.col("n_correct") / F.col("k")).alias("p_all"))
    part = kept.groupBy("task").agg(F.count(F.lit(1)).alias("kept"), F.avg((F.col("n_correct") / F.col("k")) * (1 - F.col("n_correct") / F.col("k"))).alias("variance_kept"))
    return rounded(longs(all_.join(part, "task", "left"), "scored", "samples", "kept"), "p_all", "variance_kept")


@query
def filter_cost_judge(spark, sf):
    """The dear kind of scoring: free text judged by token overlap of each turn with the one before."""
    turns = load(spark, sf, "conversations")
    before = F.lag("text").over(Window.partitionBy("conv_id").orderBy("turn"))
    rows = turns.withColumn("before", before).filter("before is not null")
    rows = rows.withColumn("correct", rewards.semantic_reward(F.col("text"), F.col("before"), tau=0.05) == 1)
    out = strata.stratify(rows.withColumnRenamed("conv_id", "sample_id").withColumn("task", F.lit("dialogue")))
    return longs(out.groupBy("stratum").agg(F.count(F.lit(1)).alias("samples"), F.sum("k").alias("judged")), "samples", "judged")


@query
def strata_drift(spark, sf):
    """Shares of the strata over five iterations of the improving replay."""
    answers = W.part_answers(spark, sf).withColumn("reward", rewards.distance_reward(F.col("answer"), F.col("truth")))
    at = F.coalesce(*(F.when(F.col("task") == k, F.lit(v)) for k, v in C.thresholds.items()), F.lit(0.5))
    # one scan and one aggregate: each iteration has its own conditional counts
    block = lambda i: F.pmod(F.col("rn") - 8 * i, F.col("n")) < C.candidates
    each = [F.struct(F.lit(i).alias("iter"), F.count_if(block(i)).alias("k"), F.count_if(block(i) & (F.col("reward") >= at * 0.85**i)).alias("n_correct")) for i in range(5)]
    counts = answers.groupBy("sample_id").agg(F.array(*each).alias("x")).select("sample_id", F.inline("x"))
    rows = strata.banded(counts)
    return rounded(longs(measures.shares(rows, "stratum", ["iter"]), "n"), "share")


# ---- stage 2 --------------------------------------------------------------------------------------------------------


def part_outcomes(spark, sf, iteration: int) -> DataFrame:
    """(sample_id, task, effective, hard, easy) of each part's group at an iteration."""
    rows = part_candidates(spark, sf, iteration).withColumn("reward", F.col("correct").cast("double"))
    return quota.outcomes(rows, ["sample_id", "task"])


def part_rollouts(spark, sf, rows: DataFrame, iteration: int) -> DataFrame:
    """Outcomes of drawn samples (task, sample_id) only: their lines are picked before any window."""
    rows = rows.select("task", "sample_id")
    cands = part_candidates(spark, sf, iteration, rows.select("sample_id")).withColumn("reward", F.col("correct").cast("double"))
    return quota.outcomes(cands, ["task", "sample_id"])


def part_pool(spark, sf) -> DataFrame:
    return quota.enqueue(strata.rl_pool(strata.stratify(part_candidates(spark, sf))).select("sample_id", "task"), ["sample_id"])


def quota_history(spark, sf, n_rounds: int, beta: float = C.ema_beta, subset: int = C.subset_size, **how) -> tuple[DataFrame, list[dict]]:
    from .session import work_dir

    pool_at = work_dir(spark)
    write_pool(part_pool(spark, sf), f"{pool_at}/pool", 8)
    pool = spark.read.parquet(f"{pool_at}/pool")
    rollout = lambda rows, i: part_rollouts(spark, sf, rows, i)
    return quota.run_iterations(spark, pool, rollout, pool_at, subset, n_rounds, beta, C.rate_floor, C.r_max, C.probe, **how)


def _quota_round(spark, sf, i: int) -> DataFrame:
    _, report = quota_history(spark, sf, i)
    rows = [(r["task"], r["quota"], r["fresh"], r["requeued"], r["effective"], round(r["eta_ema"], 6)) for r in report if r["iter"] == i]
    return spark.createDataFrame(rows, "task string, quota long, fresh long, requeued long, effective long, eta_ema double")


@query
def quota_round1(spark, sf):
    return _quota_round(spark, sf, 1)


@query
def quota_round2(spark, sf):
    return _quota_round(spark, sf, 2)


@query
def quota_round3(spark, sf):
    return _quota_round(spark, sf, 3)


@query
def sample_status(spark, sf):
    history, _ = quota_history(spark, sf, 3)
    return longs(quota.sample_status(history).groupBy("task", "status").agg(F.count(F.lit(1)).alias("samples"), F.sum("draws").alias("draws")), "samples", "draws")


@query
def training_intensity(spark, sf):
    history, _ = quota_history(spark, sf, 3)
    return rounded(longs(quota.intensity(history, part_pool(spark, sf)), "size", "draws", "samples"), "intensity")


@query
def discard_vs_quota(spark, sf):
    """Draws and effective samples by task: zero-advantage discard against the quotas' first round."""
    drawn = baselines.discard_sampling(kept(spark, part_pool(spark, sf).join(part_outcomes(spark, sf, 1), ["sample_id", "task"])), strata.modular_order(F.col("sample_id")), C.subset_size)
    history, _ = quota_history(spark, sf, 1)
    side = lambda df, m: measures.sampling_cost(df, ["task"]).withColumn("method", F.lit(m))
    return rounded(longs(side(drawn, "discard").unionByName(side(history, "quota")), "sampled", "effective"), "cost")


@query
def task_balance(spark, sf):
    """How evenly effective samples spread over tasks, both methods."""
    rows = kept(spark, discard_vs_quota(spark, sf))
    one = lambda m: measures.task_balance(rows.filter(F.col("method") == m)).withColumn("method", F.lit(m))
    return rounded(longs(one("discard").unionByName(one("quota")), "most", "least"), "ratio", "variation", "mean_gap")


@query
def running_discard(spark, sf):
    drawn = baselines.discard_sampling(part_pool(spark, sf).join(part_outcomes(spark, sf, 1), ["sample_id", "task"]), strata.modular_order(F.col("sample_id")), C.subset_size)
    return longs(drawn.select("sample_id", "draw_no", "n_effective"), "draw_no", "n_effective")


@query
def balanced_batches(spark, sf):
    rows = part_pool(spark, sf).join(strata.stratify(part_candidates(spark, sf)).select("sample_id", F.col("stratum").alias("tier")), "sample_id")
    return longs(quota.assemble_batches(rows, C.batch_size).groupBy("batch", "task", "tier").agg(F.count(F.lit(1)).alias("n")), "batch", "n")


def daily_outcomes(spark, sf) -> DataFrame:
    """RATE-E: a user's day is a group, effective when it mixes purchases and other events."""
    ev = load(spark, sf, "events", ["ts", "user_id", "event_type"])
    bought = F.col("event_type") == "purchase"
    rows = ev.groupBy(F.to_date("ts").alias("day"), "user_id").agg((F.bool_or(bought) & F.bool_or(~bought)).alias("effective"))
    return rows.withColumn("task", (F.col("user_id") % 5).cast("int"))


def daily_series(spark, sf) -> DataFrame:
    return quota.effective_rate(daily_outcomes(spark, sf), ["task", "day"]).withColumnRenamed("day", "iter")


@query
def daily_rates(spark, sf):
    return rounded(longs(daily_series(spark, sf), "sampled", "effective").withColumnRenamed("iter", "day"), "eta")


@query
def ema_rates(spark, sf):
    out = quota.ema_rates(daily_series(spark, sf), F.lit(0.5), C.ema_beta)
    return rounded(out.select("task", F.col("iter").alias("day"), "eta", "eta_ema"), "eta", "eta_ema")


@query
def daily_quota(spark, sf):
    out = quota.ema_rates(daily_series(spark, sf), F.lit(0.5), C.ema_beta)
    return out.select("task", F.col("iter").alias("day"), quota.next_quota(F.col("eta_ema"), 800.0, 5, C.rate_floor).alias("quota"))


@query
def sliding_rate(spark, sf):
    rows = daily_series(spark, sf)
    by = Window.partitionBy("task").orderBy("iter").rowsBetween(-6, 0)
    return rounded(rows.select("task", F.col("iter").alias("day"), F.avg("eta").over(by).alias("eta_7")), "eta_7")


@query
def seesaw(spark, sf):
    rows = daily_series(spark, sf).select("task", "iter", F.round("eta", 9).alias("value"))
    return rounded(longs(measures.seesaw(rows), "falls"), "worst")


@query
def curve_drop(spark, sf):
    rows = daily_series(spark, sf).select("task", "iter", F.col("eta").alias("value"))
    return rounded(measures.curve_drop(rows, by=["task"]), "peak", "last", "drop")


# ---- stage 3 --------------------------------------------------------------------------------------------------------


def order_nodes(spark, sf) -> DataFrame:
    return trie.node_values(trie.with_prefix_keys(W.order_plans(spark, sf), "path"), C.gamma)


@query
def trie_nodes(spark, sf):
    return order_nodes(spark, sf).select("task", F.col("depth").cast("long").alias("depth"), F.col("parent_key").alias("parent_path"), F.col("node_key").alias("path"), F.col("n").cast("long").alias("n"))


@query
def node_values(spark, sf):
    return order_nodes(spark, sf).select("task", F.col("node_key").alias("path"), F.col("n").cast("long").alias("n"), nudged("q").alias("q"))


@query
def sibling_advantage(spark, sf):
    rows = credit.sibling_advantage(order_nodes(spark, sf), C.eps).filter("k > 1")
    return rows.select("task", F.col("node_key").alias("path"), F.col("k").cast("long").alias("k"), nudged("mu").alias("mu"), nudged("sigma").alias("sigma"), nudged("advantage", 5).alias("advantage"))


@query
def sibling_advantage_by_visits(spark, sf):
    rows = credit.sibling_advantage(order_nodes(spark, sf), C.eps, weighting="visits", scale=False).filter("k > 1")
    return rows.select("task", F.col("node_key").alias("path"), nudged("mu").alias("mu"), nudged("advantage").alias("advantage"))


@query
def credit_rows(spark, sf):
    rows = credit.credit_rows(W.order_plans(spark, sf), C.gamma, C.eps, C.delta)
    return rows.select("task", "traj", F.col("t").cast("long").alias("t"), F.array_join("context", " ").alias("context"), "step", nudged("advantage", 5).alias("advantage"))


@query
def credit_contrast(spark, sf):
    one = lambda plans, name: credit.contrast(plans.select("task", "traj", "r", "steps"), C.gamma, C.eps, C.delta).withColumn("source", F.lit(name))
    both = one(W.order_plans(spark, sf), "orders").unionByName(one(W.session_plans(spark, sf), "sessions"))
    return longs(both, "r", "steps", "positive", "negative", "same_sign", "flat_in_baseline")


@query
def trajectory_credit(spark, sf):
    """Baseline: one advantage a plan, spread on its steps."""
    rows = credit.spread(credit.trajectory_advantage(W.order_plans(spark, sf), C.eps))
    return rows.select("task", "traj", F.col("t").cast("long").alias("t"), r6("advantage").alias("advantage"))


@query
def trie_shape(spark, sf):
    def one(plans: DataFrame, name: str) -> DataFrame:
        nodes = trie.node_values(trie.with_prefix_keys(plans), C.gamma)
        return trie.trie_shape(nodes).agg(F.count(F.lit(1)).alias("tasks"), F.avg("branching").alias("branching"), F.avg("leaves").alias("leaves"), F.try_divide(F.sum("children").cast("double"), F.sum("branching")).alias("group_size")).withColumn("source", F.lit(name))

    out = one(W.order_plans(spark, sf), "orders").unionByName(one(W.session_plans(spark, sf), "sessions")).unionByName(one(W.dialogue_plans(spark, sf), "dialogues"))
    return rounded(longs(out, "tasks"), "branching", "leaves", "group_size")


@query
def group_size_by_verb(spark, sf):
    nodes = trie.node_values(trie.with_prefix_keys(W.session_plans(spark, sf)), C.gamma)
    return rounded(longs(trie.group_size_by_verb(nodes), "parents"), "group_size")


# ---- objective ------------------------------------------------------------------------------------------------------


def order_policies(spark, sf, plans: DataFrame | None = None) -> dict[str, DataFrame]:
    """Order-1 tabular policies fitted on plans before 1998 (old), from 1998 (new), and all (reference): one pass for the
    counts of all three, kept as a small table."""
    from .session import work_dir

    plans = W.order_plans(spark, sf) if plans is None else plans
    early = F.to_date("o_orderdate") < F.lit("1998-01-01").cast("date")
    steps = trie.with_prefix_keys(plans.select(F.struct("task", early.alias("early")).alias("task"), "traj", "r", "steps"))
    at = f"{work_dir(spark)}/counts"
    policy.action_counts(steps.withColumn("early", F.col("task.early")), 1, ["early"]).coalesce(1).write.parquet(at)
    seen = spark.read.parquet(at)
    both = seen.groupBy("history", "action").agg(F.sum("c").alias("c"))
    return {"old": policy.fit_counts(seen.filter("early"), vocabulary=seen), "new": policy.fit_counts(seen.filter("not early"), vocabulary=seen), "ref": policy.fit_counts(both)}


def order_ratios(spark, sf, plans: DataFrame | None = None) -> DataFrame:
    p = order_policies(spark, sf, plans)
    rows = p["new"].select("history", "action", F.col("p").alias("p_new"))
    for k in ("old", "ref"):
        rows = rows.join(p[k].select("history", "action", F.col("p").alias(f"p_{k}")), ["history", "action"])
    # a masked context token with another probability must not count
    arr = lambda c: F.array(F.ln(F.col(c)) - 1, F.ln(c))
    return rows.withColumn("rho", objective.step_ratio(arr("p_new"), arr("p_old"), F.array(F.lit(0), F.lit(1))))


@query
def step_ratio(spark, sf):
    return rounded(order_ratios(spark, sf), "p_new", "p_old", "p_ref", "rho")


@query
def policy_divergence(spark, sf):
    rows = order_ratios(spark, sf)
    return rounded(rows.groupBy("history").agg(F.sum(F.col("p_new") * F.ln(F.col("p_new") / F.col("p_ref"))).alias("kl")), "kl")


@query
def sibling_loss(spark, sf):
    """Loss by depth: clipped gain of each child less the weighted divergence, by children and by visits."""
    plans = kept(spark, W.order_plans(spark, sf))  # packed once, read for the policies and for the tree
    steps = policy.with_history(trie.with_prefix_keys(plans.select("task", "traj", "r", "steps")), 1)
    nodes = steps.withColumn("ret", trie.discounted_return(C.gamma)).groupBy("task", F.col("t").alias("depth"), "parent_key", "node_key", "history", trie.action_text(F.col("action")).alias("action")).agg(F.avg("ret").alias("q"), F.count(F.lit(1)).alias("n"))
    ratios = kept(spark, order_ratios(spark, sf, plans))
    kl = ratios.groupBy("history").agg(F.sum(F.col("p_new") * F.ln(F.col("p_new") / F.col("p_ref"))).alias("kl"))  # a few rows of a policy table
    rows = credit.sibling_advantage(nodes, C.eps).filter("k > 1").join(bounded_broadcast(ratios), ["history", "action"]).join(bounded_broadcast(kl), "history")
    out = objective.sibling_losses(rows, C.clip, C.kl_weight).groupBy("depth").agg(F.sum("loss").alias("loss"), F.sum("loss_by_visits").alias("loss_by_visits"), F.count(F.lit(1)).alias("parents"))
    return rounded(longs(out, "depth", "parents"), "loss", "loss_by_visits")



# ---- measures and comparisons ---------------------------------------------------------------------------------------


def part_scores(spark, sf) -> DataFrame:
    """Score sheet: share of right answers by brand (benchmark) and brand family (category) for three selections (systems)."""
    rows = kept(spark, strata.stratify(part_candidates(spark, sf)).join(load(spark, sf, "part", ["p_partkey", "p_brand"]), F.col("sample_id") == F.col("p_partkey")))
    order = strata.modular_order(F.col("sample_id"))
    pick = {
        "filtered": strata.select_for_tuning(rows.drop("p_partkey", "p_brand"), C.easy_share, order).select("sample_id"),
        "uncertain_only": rows.filter("stratum = 'uncertain'").select("sample_id"),
        "unfiltered": rows.select("sample_id"),
    }
    sheet = None
    for system, ids in pick.items():
        one = rows.join(ids, "sample_id", "left_semi").groupBy(F.col("p_brand").alias("benchmark")).agg((100 * F.sum("n_correct") / F.sum("k")).alias("value")).withColumn("system", F.lit(system))
        sheet = one if sheet is None else sheet.unionByName(one)
    return sheet.withColumn("category", F.substring("benchmark", 1, 7))


@query
def score_sheet(spark, sf):
    sheet = part_scores(spark, sf)
    cats = measures.category_means(sheet)
    return rounded(cats.unionByName(measures.overall(sheet).withColumn("category", F.lit("overall"))), "value")


@query
def podium(spark, sf):
    rows = measures.podium(part_scores(spark, sf).withColumn("value", F.round("value", 9)))
    return rounded(rows.select("system", "benchmark", F.col("place").cast("long").alias("place"), "value"), "value")


@query
def score_gain(spark, sf):
    return rounded(measures.gain(part_scores(spark, sf), "filtered", "unfiltered"), "gain")


@query
def rollup_scores(spark, sf):
    rows = part_scores(spark, sf).rollup("system", "category").agg(F.avg("value").alias("value"), F.count(F.lit(1)).alias("n"))
    return rounded(longs(rows, "n"), "value")


@query
def plan_success(spark, sf):
    plans = actions.limit_steps(W.order_plans(spark, sf, rich=True).filter("task <= 99"), C.max_steps)
    return rounded(longs(measures.success_rate(plans, ["task"]), "plans", "successes"), "success_pct")


@query
def plan_length(spark, sf):
    one = lambda plans, name: measures.length_stats(plans).withColumn("source", F.lit(name))
    out = one(W.order_plans(spark, sf), "orders").unionByName(one(W.session_plans(spark, sf), "sessions"))
    return rounded(longs(out, "plans"), "mean_steps", "median_steps")


@query
def seed_summary(spark, sf):
    """Five seeds (shifted judges): success of the first plan, of any plan, and of most plans of the first 99 tasks."""
    plans = W.order_plans(spark, sf).filter("task <= 99").select("task", "traj", "o_orderdate", "o_orderstatus")
    judged = [F.struct(F.lit(seed).alias("seed"), W.majority(W.judge_votes(F.col("traj"), F.col("o_orderstatus"), 20 * seed)).alias("r")) for seed in range(5)]
    plans = plans.withColumn("j", F.explode(F.array(*judged))).select("task", "traj", "o_orderdate", "j.*")  # one pass for all seeds
    per = plans.groupBy("seed", "task").agg((F.min_by("r", F.struct("o_orderdate", "traj")) == 1).alias("first_plan"), (F.max("r") == 1).alias("any_plan"), (F.avg("r") > 0).alias("most_plans"))
    names = ["first_plan", "any_plan", "most_plans"]
    runs = per.groupBy("seed").agg(*(F.avg(F.col(c).cast("double")).alias(c) for c in names)).unpivot(["seed"], names, "system", "value")
    return rounded(longs(measures.seed_summary(runs.withColumn("value", 100 * F.col("value"))), "runs"), "mean", "std_sample", "std_population", "var_sample")


@query
def primitive_only(spark, sf):
    plans = W.session_plans(spark, sf)
    kept = actions.restrict_vocabulary(plans, banned={"signup"})
    flagged = actions.restrict_vocabulary(plans, banned={"signup"}, on_violation="flag")
    one = kept.agg(F.count(F.lit(1)).alias("plans"), F.sum(F.size("steps")).alias("steps"), F.count_if(F.size("steps") == 0).alias("emptied"))
    two = flagged.agg(F.sum("violations").alias("violations"))
    return longs(one.crossJoin(two), "plans", "steps", "emptied", "violations")


@query
def replan_success(spark, sf):
    """Failed sessions that a better sibling could have saved, by task; and the stepwise agent beside it."""
    steps = trie.with_prefix_keys(W.session_plans(spark, sf), "path")
    nodes = trie.node_values(steps, C.gamma)
    base = W.session_plans(spark, sf).groupBy("task").agg(F.count(F.lit(1)).alias("plans"), F.count_if(F.col("r") == -1).alias("failed"))
    got = replan.replan(steps, nodes).groupBy("task").agg(F.count(F.lit(1)).alias("replanned"), F.count_if("recovered").alias("recovered"))
    out = base.join(got, "task", "left").select("task", "plans", "failed", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("replanned", "recovered")))
    return longs(out, "plans", "failed", "replanned", "recovered")


@query
def stepwise_agent(spark, sf):
    nodes = trie.node_values(trie.with_prefix_keys(W.session_plans(spark, sf), "path"), C.gamma)
    nodes = nodes.withColumn("q", F.round("q", 9))
    tasks = nodes.select("task").distinct()
    out = baselines.stepwise_agent(nodes, tasks, C.max_steps)
    return rounded(longs(out.select("task", "steps", "last_verb", "last_q"), "steps"), "last_q")


@query
def failure_monitor(spark, sf):
    labels = W.order_labels(spark, sf).orderBy("traj").limit(160)
    out = measures.judge_quality(labels.select((F.col("r") == 1).alias("said"), (F.col("o_orderstatus") == "F").alias("truth")), "said", "truth")
    return rounded(longs(out, "n"), "accuracy", "precision", "recall", "f1")


@query
def vote_margins(spark, sf):
    out = rewards.majority_label(W.order_votes(spark, sf), ["task", "traj"])
    return rounded(longs(out.groupBy("r", "margin").agg(F.count(F.lit(1)).alias("plans")), "r", "plans"), "margin")


@query
def scene_success(spark, sf):
    """First fifty orders of at most nine lines, in four categories by their largest part."""
    lines = load(spark, sf, "lineitem", ["l_orderkey", "l_partkey"]).join(load(spark, sf, "part", ["p_partkey", "p_size"]), F.col("l_partkey") == F.col("p_partkey"))
    scenes = lines.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("objects"), F.max("p_size").alias("size")).filter("objects <= 9").orderBy("l_orderkey").limit(50)
    rows = scenes.join(W.order_labels(spark, sf), F.col("l_orderkey") == F.col("traj")).withColumn("category", F.least(F.floor((F.col("size") - 1) / 12.5), F.lit(3)))
    return rounded(longs(measures.success_rate(rows, ["category"]), "category", "plans", "successes"), "success_pct")


def split_plans(spark, sf) -> tuple[DataFrame, DataFrame]:
    """Keyed steps of the first ten plans of each task, and of the rest."""
    plans = W.order_plans(spark, sf)
    at = F.row_number().over(Window.partitionBy("task").orderBy("o_orderdate", "traj"))
    plans = plans.withColumn("at", at)
    return tuple(trie.with_prefix_keys(p, "path") for p in (plans.filter("at <= 10"), plans.filter("at > 10")))


@query
def judge_step(spark, sf):
    train, test = split_plans(spark, sf)
    rows = replan.judge_steps(test, trie.node_values(train, C.gamma))
    return longs(rows.groupBy("t", "verdict", "r").agg(F.count(F.lit(1)).alias("n")), "t", "r", "n")


@query
def next_step(spark, sf):
    train, test = split_plans(spark, sf)
    rows = replan.next_steps(test, trie.node_values(train, C.gamma)).withColumn("hit", F.col("best") == trie.action_text(F.col("action")))
    return longs(rows.groupBy("t").agg(F.count(F.lit(1)).alias("n"), F.count_if("hit").alias("hits")), "t", "n", "hits")


@query
def expansion_cost(spark, sf):
    nodes = trie.node_values(trie.with_prefix_keys(W.order_plans(spark, sf)), C.gamma).select("depth")
    return longs(baselines.expansion_cost(nodes, 6, 8), "depth", "full", "full_total", "observed")


# ---- rewards --------------------------------------------------------------------------------------------------------


@query
def reward_exact(spark, sf):
    parts = load(spark, sf, "part", ["p_partkey", "p_name", "p_type"])
    noisy = F.concat(F.lit("  "), F.upper("p_type"), F.lit(" "))
    rows = parts.select(rewards.exact_reward(noisy, F.col("p_type")).alias("loose"), rewards.exact_reward(noisy, F.col("p_type"), False).alias("strict"), rewards.exact_reward(F.split("p_name", " ")[0], F.col("p_type")).alias("other"))
    return rows.agg(F.sum("loose").alias("loose"), F.sum("strict").alias("strict"), F.sum("other").alias("other"))


@query
def reward_semantic(spark, sf):
    turns = load(spark, sf, "conversations")
    before = F.lag("text").over(Window.partitionBy("conv_id").orderBy("turn"))
    rows = turns.withColumn("before", before).filter("before is not null")
    return rounded(rows.select("conv_id", "turn", rewards.token_jaccard(F.col("text"), F.col("before")).alias("jaccard"), rewards.semantic_reward(F.col("text"), F.col("before"), tau=0.1).alias("reward")), "jaccard")


def geometry(spark, sf) -> DataFrame:
    """Points and boxes from vectors: the truth of a vector is its label's mean vector."""
    v = load(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")
    flat = v.select("label", F.posexplode("v").alias("i", "x")).filter("i < 18").groupBy("label", "i").agg(F.avg("x").alias("x"))
    truth = flat.groupBy("label").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("g"))
    return v.select("vec_id", "label", F.slice("v", 1, 18).alias("v")).join(bounded_broadcast(truth), "label")


def box(v: str, at: int, dims: int) -> Column:
    """A box from 2 * dims components: low corner is the smaller of each pair."""
    x = [F.col(v)[at + k] for k in range(2 * dims)]
    return F.struct(F.array(*(F.least(x[k], x[k + dims]) for k in range(dims))).alias("lo"), F.array(*(F.greatest(x[k], x[k + dims]) + 0.05 for k in range(dims))).alias("hi"))


@query
def reward_point(spark, sf):
    unit = lambda c: F.array(*((F.col(c)[k] + 1) / 2 for k in range(2)))
    one = F.array(F.lit(1.0), F.lit(1.0))
    rows = geometry(spark, sf)
    return rounded(rows.select("vec_id", rewards.point_reward(unit("v"), unit("g"), one).alias("reward"), rewards.point_reward(unit("v"), unit("g"), one, per_axis=True).alias("per_axis")), "reward", "per_axis")


@query
def reward_distance(spark, sf):
    rows = part_candidates(spark, sf)
    return rounded(rows.groupBy("sample_id").agg(F.sum("reward").alias("reward"), F.min("reward").alias("worst")), "reward", "worst")


@query
def reward_box(spark, sf):
    """Mean IoU-F1 reward of one predicted box against one true box, in two and three dimensions."""
    rows = geometry(spark, sf)
    two = rewards.box_reward(F.array(box("v", 0, 2)), F.array(box("g", 0, 2)), 0.05)
    three = rewards.box_reward(F.array(box("v", 0, 3)), F.array(box("g", 0, 3)), 0.01)
    soft = rewards.box_reward(F.array(box("v", 0, 2)), F.array(box("g", 0, 2)), mode="soft")
    return rounded(rows.select("vec_id", two.alias("box2"), three.alias("box3"), soft.alias("soft2")), "box2", "box3", "soft2")


@query
def reward_hybrid(spark, sf):
    """Five rewards in one projection by the row's kind."""
    rows = geometry(spark, sf).withColumn("kind", F.element_at(F.array(*map(F.lit, ("exact", "semantic", "point", "distance", "box"))), (F.col("vec_id") % 5 + 1).cast("int")))
    unit = lambda c: F.array(*((F.col(c)[k] + 1) / 2 for k in range(2)))
    value = rewards.hybrid_reward(
        F.col("kind"),
        rewards.exact_reward((F.col("vec_id") % 10).cast("string"), F.col("label").cast("string")),
        rewards.semantic_reward(F.col("v"), F.col("g"), rewards.cosine, 0.2),
        rewards.point_reward(unit("v"), unit("g"), F.array(F.lit(1.0), F.lit(1.0))),
        rewards.distance_reward(F.abs(F.col("v")[0]), F.abs(F.col("g")[0])),
        rewards.box_reward(F.array(box("v", 0, 2)), F.array(box("g", 0, 2)), 0.05),
    )
    return rounded(rows.withColumn("reward", value).groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.avg("reward").alias("reward")), "reward")


# ---- relational operators that the methods use ------------------------------------------------------------------------


@query
def leakage(spark, sf):
    return joins.leaked(load(spark, sf, "documents", ["doc_id", "text"]), load(spark, sf, "benchmark"))


@query
def join_semi_drawn(spark, sf):
    """Lines of parts that the first forty places of each queue draw."""
    drawn = part_pool(spark, sf).filter("fresh_pos <= 40").select(F.col("sample_id").alias("l_partkey"))
    rows = load(spark, sf, "lineitem", ["l_partkey", "l_quantity"]).join(drawn, "l_partkey", "left_semi")
    return longs(rows.groupBy("l_partkey").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_quantity").alias("quantity")), "lines")


@query
def join_anti_leaves(spark, sf):
    nodes = order_nodes(spark, sf)
    inner = nodes.select("task", F.col("parent_key").alias("node_key")).distinct()
    return longs(nodes.join(inner, ["task", "node_key"], "left_anti").groupBy("depth").agg(F.count(F.lit(1)).alias("leaves")), "depth", "leaves")


@query
def asof_rate(spark, sf):
    """Each purchase with the rate of its task on the latest day before it."""
    ev = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type"]).filter("event_type = 'purchase'")
    left = ev.select("event_id", (F.col("user_id") % 5).cast("int").alias("task"), F.to_date("ts").alias("at"))
    right = daily_series(spark, sf).select("task", F.col("iter").alias("at"), "eta")
    return rounded(joins.as_of(left, right, ["task"], "at", "eta", strict=True).select("event_id", "eta"), "eta")


@query
def range_band(spark, sf):
    """Line prices in half-open bands, by bin and equi-join."""
    bands = spark.createDataFrame([(k, float(lo), float(hi)) for k, (lo, hi) in enumerate(BANDS)], "band long, lo double, hi double")
    rows = load(spark, sf, "lineitem", ["l_extendedprice"])
    return longs(joins.range_join(rows, bands, "l_extendedprice", "lo", "hi", 5000.0).groupBy("band").agg(F.count(F.lit(1)).alias("lines")), "lines")


@query
def cube_strata(spark, sf):
    return longs(strata.stratify(part_candidates(spark, sf)).cube("task", "stratum").agg(F.count(F.lit(1)).alias("n")), "n")


@query
def pivot_strata(spark, sf):
    rows = strata.stratify(part_candidates(spark, sf)).groupBy("task").pivot("stratum", ["easy", "uncertain", "hard"]).agg(F.count(F.lit(1)))
    return rows.select("task", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("easy", "uncertain", "hard")))


@query
def set_overlap(spark, sf):
    """Samples that filtered and random selection share, and those of one alone."""
    rows = kept(spark, strata.stratify(part_candidates(spark, sf)))
    order = strata.modular_order(F.col("sample_id"))
    a = strata.select_for_tuning(rows, C.easy_share, order).select("sample_id")
    b = strata.random_selection(rows.select("sample_id"), 500, order, "sample_id")
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).withColumn("part", F.lit(name))
    return count(a.intersect(b), "both").unionByName(count(a.exceptAll(b), "filtered_only")).unionByName(count(b.subtract(a), "random_only"))


@query
def json_actions(spark, sf):
    rows = with_props(load(spark, sf, "events", ["event_type", "props"])).withColumn("half", F.floor(F.col("k") / 50))
    return longs(rows.groupBy("event_type", "half").agg(F.count(F.lit(1)).alias("n")), "half", "n")


@query
def map_synonyms(spark, sf):
    """Step sentences with synonyms, parsed back to canonical triples."""
    lines = load(spark, sf, "lineitem", ["l_linenumber", "l_returnflag", "l_linestatus"])
    phrase = F.coalesce(*(F.when((F.col("l_returnflag") == f) & (F.col("l_linenumber") % 3 == k), F.lit(p)) for f, ps in SYNONYMS.items() for k, p in enumerate(ps)))
    text = F.concat(F.lit("Step "), "l_linenumber", F.lit(": "), phrase, F.lit(" the box on the "), "l_linestatus", F.lit("."))
    parsed = actions.parse_action(text, {f: list(ps) for f, ps in SYNONYMS.items()})
    rows = lines.withColumn("a", parsed)
    return longs(rows.groupBy(F.col("a.action_type").alias("verb"), F.col("a.receptacle_obj").alias("receptacle"), F.col("a.known").alias("known")).agg(F.count(F.lit(1)).alias("n")), "n")
