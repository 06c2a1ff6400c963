"""The experiments that set methods against their baselines, and the variants of each method; SQL beside each query.

Draws are arithmetic (`policy.modular_uniform`), so that SQL repeats the sampled plans of every round."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import oracles as O
from .config import DEFAULTS as C
from .functions import actions, measures, rewards
from .operators import baselines, credit, objective, policy, quota, replan, rounds, strata, trie
from .plans.forms import bounded_broadcast
from .queries import ORACLES, kept, longs, nudged, order_ratios, part_candidates, part_pool, part_rollouts, query, quota_history, r6, rounded, split_plans
from .session import work_dir
from .sources import workloads as W
from .sources.tables import load

STOP, STEPS, ROUNDS, SAMPLER_ROUNDS = "R/F/∅", 6, 3, 5


def delivered():
    """+1 for a plan whose last step is of a delivered line."""
    return F.when(F.element_at("steps", -1)["action"]["target_obj"] == "F", 1).otherwise(-1)


# ---- co-evolution, and the three policies of stage 3 ------------------------------------------------------------------


def first_policy(spark, sf) -> DataFrame:
    return policy.fit_policy(trie.with_prefix_keys(W.order_plans(spark, sf)), 1.0, 1)


def customers(spark, sf) -> DataFrame:
    return load(spark, sf, "customer", ["c_custkey"]).select(F.col("c_custkey").alias("task"))


def trained(spark, sf, by: str) -> tuple[str, list[dict]]:
    """Folder and ledger of three rounds of forty customers each."""
    at = work_dir(spark)
    return at, rounds.run_rounds(spark, customers(spark, sf), first_policy(spark, sf), delivered(), at, ROUNDS, C.tasks_per_round, C.trajectories, STEPS, STOP, C.judges, C.judge_trajectories, C.gamma, C.eps, C.delta, kl_weight=C.kl_weight, clip=C.clip, by=by, draws=policy.modular_uniform)


def ledger_rows(spark, ledger: list[dict]) -> DataFrame:
    df = spark.createDataFrame([tuple(r.values()) for r in ledger], "round int, plans long, success double, judge_agreement double, credit_rows long, loss double")
    return rounded(df, "success", "judge_agreement", "loss")


@query
def round_ledger(spark, sf):
    """Three co-evolution rounds with step credit; a plan is good when it ends in a delivered step."""
    return ledger_rows(spark, trained(spark, sf, "sibling")[1])


@query
def round_ledger_whole(spark, sf):
    """The same rounds with the whole plan's advantage on every step."""
    return ledger_rows(spark, trained(spark, sf, "whole")[1])


@query
def stage3_success(spark, sf):
    """Success over five seeds on 99 tasks of the policy that stage 3 starts from, and after it by either credit."""
    start = kept(spark, first_policy(spark, sf))
    learnt = {"start": start} | {by: spark.read.parquet(f"{trained(spark, sf, by)[0]}/policy/round={ROUNDS}") for by in ("whole", "sibling")}
    tasks, runs = customers(spark, sf).filter("task <= 99"), None
    for name, p in learnt.items():
        one = rounds.success_by_seed(p, tasks, delivered(), 5, STEPS, STOP, 900, policy.modular_uniform).select(F.lit(name).alias("system"), F.col("success_pct").alias("value"))
        runs = one if runs is None else runs.unionByName(one)
    return rounded(longs(measures.seed_summary(runs), "runs"), "mean", "std_sample", "std_population", "var_sample")


def u_sql(seed: int, *terms: str) -> str:
    x = " + ".join([str(seed * 15_485_863 % 1_000_003), *(f"({t}) % 1000003 * {by}" for t, by in zip(terms, (7919, 104_729, 299_993, 611_953)))])
    x = f"(({x}) % 1000003)"
    for _ in range(2):
        x = f"(({x} * ({x} + 7919) + 104729) % 1000003)"
    return f"(CAST({x} AS DOUBLE) / 1000003.0)"


def sampled_sql(name: str, table: str, first: str, k: int, seed: int) -> str:
    """CTEs that sample k plans a row of `first` (a SELECT of task) from policy `table` (history, action, p): {name} has acts."""
    sql = f""",
{name}c AS MATERIALIZED (SELECT history, action, hi, coalesce(lag(hi) OVER w, -1.0) AS lo, lead(hi) OVER w IS NULL AS fin
  FROM (SELECT history, action, round(sum(p) OVER (PARTITION BY history ORDER BY action), 9) AS hi FROM {table}) z WINDOW w AS (PARTITION BY history ORDER BY action)),
{name}0 AS MATERIALIZED (SELECT task, traj, '' AS h, true AS live, CAST([] AS VARCHAR[]) AS acts FROM ({first}) f CROSS JOIN (SELECT unnest(range(1, {k + 1})) AS traj) g)"""
    for t in range(1, STEPS + 1):
        u = u_sql(seed, "r.task", "r.traj", str(t))
        sql += f""",
{name}{t} AS MATERIALIZED (SELECT task, traj, coalesce(a, h) AS h, live AND coalesce(a <> '{STOP}', false) AS live, CASE WHEN a IS NULL THEN acts ELSE list_append(acts, a) END AS acts
  FROM (SELECT r.*, CASE WHEN live THEN c.action END AS a FROM (SELECT *, {u} AS u FROM {name}{t - 1} r) r LEFT JOIN {name}c c ON c.history = r.h AND u >= c.lo AND (u < c.hi OR c.fin)) z)"""
    return sql + f""",
{name} AS MATERIALIZED (SELECT task, traj, acts, CASE WHEN split_part(acts[-1], '/', 2) = 'F' THEN 1 ELSE -1 END AS truth FROM {name}{STEPS})"""


FIRST = f"""{O.TRO}, hs AS (SELECT *, coalesce(lag(a) OVER (PARTITION BY traj ORDER BY t), '') AS history FROM stp),
gr AS (SELECT h.history, v.action, coalesce(c.n, 0) + 1.0 AS n FROM (SELECT DISTINCT history FROM hs) h CROSS JOIN (SELECT DISTINCT a AS action FROM stp) v
       LEFT JOIN (SELECT history, a AS action, count(*) AS n FROM hs GROUP BY 1, 2) c ON c.history = h.history AND c.action = v.action),
p0 AS MATERIALIZED (SELECT history, action, CAST(n AS DOUBLE) / sum(CAST(n AS DOUBLE)) OVER (PARTITION BY history) AS p FROM gr),
cu AS MATERIALIZED (SELECT c_custkey AS task, row_number() OVER (ORDER BY c_custkey) AS no FROM customer)"""


def rounds_sql(x: str, by: str) -> str:
    """CTEs of the rounds: {x}p{i} the policy after round i, {x}l{i} its ledger row."""
    sql = f""",
{x}p0 AS (SELECT * FROM p0), {x}w0 AS (SELECT [1.0::DOUBLE, 1.0, 1.0, 1.0, 1.0] AS w)"""
    for i in range(1, ROUNDS + 1):
        b = f"{x}{i}"
        votes = ", ".join(f"CASE WHEN {u_sql(17 + 1009 * i + j, 'task', 'traj')} < least(0.99, greatest(0.01, 0.8 * w[{j + 1}])) THEN truth ELSE -truth END" for j in range(5))
        label = " + ".join(f"v[{j}] * w[{j}]" for j in range(1, 6))
        sql += sampled_sql(f"{b}s", f"{x}p{i - 1}", f"SELECT task FROM cu WHERE no > {40 * (i - 1)} AND no <= {40 * i}", 15, 17 + 101 * i)
        sql += f""",
{b}pl AS MATERIALIZED (SELECT task, traj, acts, truth, v, CASE WHEN {label} > 0 THEN 1 ELSE -1 END AS r FROM (SELECT s.*, w, [{votes}] AS v FROM {b}s s CROSS JOIN {x}w{i - 1}) z),
{b}st AS MATERIALIZED (SELECT task, traj, r, t, n_steps, acts[t] AS a, CASE WHEN t = 1 THEN '' ELSE acts[t - 1] END AS history, '>' || array_to_string(acts[1:t], '>') AS path,
    CASE WHEN t = 1 THEN '' ELSE '>' || array_to_string(acts[1:t - 1], '>') END AS parent FROM (SELECT *, unnest(range(1, len(acts) + 1)) AS t, len(acts) AS n_steps FROM {b}pl) z),
{b}nd AS MATERIALIZED (SELECT task, t, parent, path, history, a, avg(pow(0.95, n_steps - t) * r) AS q FROM {b}st GROUP BY ALL),
{b}ad AS MATERIALIZED (SELECT *, count(*) OVER w AS k, (q - avg(q) OVER w) / sqrt(var_pop(q) OVER w + 1e-6) AS adv FROM {b}nd WINDOW w AS (PARTITION BY task, t, parent)),
{b}wh AS MATERIALIZED (SELECT task, traj, (r - avg(r) OVER (PARTITION BY task)) / sqrt(var_pop(r) OVER (PARTITION BY task) + 1e-6) AS adv FROM {b}pl),
{b}rw AS MATERIALIZED (SELECT s.task, s.traj, s.history, s.a, d.adv FROM {b}st s JOIN {f'{b}ad d ON d.task = s.task AND d.path = s.path AND d.k > 1' if by == 'sibling' else f'{b}wh d ON d.task = s.task AND d.traj = s.traj'} WHERE abs(d.adv) > 0.001),
{x}p{i} AS MATERIALIZED (SELECT history, action, g / sum(g) OVER (PARTITION BY history) AS p FROM (SELECT p.history, p.action, p * exp(0.5 * coalesce(m, 0.0)) AS g FROM {x}p{i - 1} p
    LEFT JOIN (SELECT history, a, avg(adv) AS m FROM {b}rw GROUP BY 1, 2) y ON y.history = p.history AND y.a = p.action) z),
{b}kl AS MATERIALIZED (SELECT n.history, sum(n.p * ln(n.p / p0.p)) AS kl FROM {x}p{i} n JOIN p0 ON p0.history = n.history AND p0.action = n.action GROUP BY 1),
{b}ra AS MATERIALIZED (SELECT n.history, n.action, n.p / o.p AS rho, kl FROM {x}p{i} n JOIN {x}p{i - 1} o ON o.history = n.history AND o.action = n.action JOIN {b}kl k ON k.history = n.history)"""
        gain = lambda a: f"least(rho * {a}, greatest(0.8, least(rho, 1.2)) * {a}) - 0.01 * kl"
        if by == "sibling":
            sql += f""",
{b}ls AS (SELECT avg(l) AS loss FROM (SELECT -sum({gain('adv')}) / count(*) AS l FROM {b}ad d JOIN {b}ra ON {b}ra.history = d.history AND {b}ra.action = d.a WHERE k > 1 GROUP BY d.task, t, parent) z)"""
        else:
            sql += f""",
{b}tm AS (SELECT s.task, s.traj, exp(sum(ln(rho))) AS rho, avg(kl) AS kl FROM {b}st s JOIN {b}ra ON {b}ra.history = s.history AND {b}ra.action = s.a GROUP BY 1, 2),
{b}ls AS (SELECT avg(l) AS loss FROM (SELECT -avg({gain('adv')}) AS l FROM {b}tm m JOIN {b}wh h ON h.task = m.task AND h.traj = m.traj GROUP BY m.task) z)"""
        sql += f""",
{b}jd AS (SELECT task, traj, j, CAST(v[j] = truth AS INT)::DOUBLE AS ok FROM (SELECT *, unnest(range(1, 6)) AS j FROM (SELECT * FROM {b}pl ORDER BY {u_sql(0, 'task', 'traj')}, task, traj LIMIT 500) f) z),
{b}jm AS (SELECT j, avg(a) AS a FROM (SELECT j, (ok - avg(ok) OVER w) / sqrt(var_pop(ok) OVER w + 1e-6) AS a FROM {b}jd WINDOW w AS (PARTITION BY task, traj)) z GROUP BY 1),
{b}jr AS (SELECT list(greatest(0.05, w[j] * (1 + 0.1 * a)) ORDER BY j) AS rs FROM {b}jm CROSS JOIN {x}w{i - 1}),
{x}w{i} AS MATERIALIZED (SELECT list_transform(rs, lambda y: y * 5 / list_sum(rs)) AS w FROM {b}jr),
{x}l{i} AS (SELECT {i} AS round, count(*) AS plans, round(avg(CAST(truth = 1 AS INT)), 6) AS success, round(avg(CAST(truth = r AS INT)), 6) AS judge_agreement,
    (SELECT count(*) FROM {b}rw) AS credit_rows, round((SELECT loss FROM {b}ls), 6) + 0.0 AS loss FROM {b}pl)"""
    return sql


for _by, _name in (("sibling", "round_ledger"), ("whole", "round_ledger_whole")):
    ORACLES[_name] = f"WITH {FIRST}{rounds_sql('a', _by)} " + " UNION ALL ".join(f"SELECT * FROM al{i}" for i in range(1, ROUNDS + 1))
ORACLES["stage3_success"] = (
    f"WITH {FIRST}{rounds_sql('a', 'whole')}{rounds_sql('b', 'sibling')}"
    + "".join(sampled_sql(f"e{k}", p, "SELECT task FROM cu WHERE task <= 99", 5, 900) for k, p in (("x", "p0"), ("y", f"ap{ROUNDS}"), ("z", f"bp{ROUNDS}")))
    + ", ev AS ("
    + " UNION ALL ".join(f"SELECT '{n}' AS system, 100 * avg(CAST(truth = 1 AS INT)) AS value FROM e{k} GROUP BY traj" for n, k in (("start", "x"), ("whole", "y"), ("sibling", "z")))
    + ") SELECT system, count(*) AS runs, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS std_sample, round(stddev_pop(value), 6) AS std_population, round(var_samp(value), 6) AS var_sample FROM ev GROUP BY 1"
)


# ---- quota sampler against discard over rounds ------------------------------------------------------------------------


def both_samplers(spark, sf) -> DataFrame:
    """(method, iter, task, sampled, effective) of five rounds of either sampler over the same pool and outcomes."""
    pool = kept(spark, part_pool(spark, sf))
    rolled = lambda rows, i: part_rollouts(spark, sf, rows, i)
    thrown = baselines.discard_loop(pool, rolled, strata.modular_order(F.col("sample_id")), C.subset_size, SAMPLER_ROUNDS, f"{work_dir(spark)}/discard")
    history, _ = quota_history(spark, sf, SAMPLER_ROUNDS)
    side = lambda df, m: df.groupBy("iter", "task").agg(F.count(F.lit(1)).alias("sampled"), F.count_if("effective").alias("effective")).withColumn("method", F.lit(m))
    seen = side(thrown, "discard").unionByName(side(history, "quota"))
    # a task that a round did not draw at all counts 0
    every = pool.select("task").distinct().select("task", F.explode(F.sequence(F.lit(1), F.lit(SAMPLER_ROUNDS))).alias("iter"), F.explode(F.array(F.lit("discard"), F.lit("quota"))).alias("method"))
    return every.join(seen, ["task", "iter", "method"], "left").select("method", F.col("iter").cast("int").alias("iter"), "task", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("sampled", "effective")))


@query
def sampler_curve(spark, sf):
    """Effective samples and cost by round, task and sampler."""
    rows = both_samplers(spark, sf)
    return rounded(rows.withColumn("cost", F.try_divide(F.col("sampled").cast("double"), F.col("effective"))), "cost")


@query
def sampler_stability(spark, sf):
    """By sampler: fall of the worst-served task's effective samples from its best round to the last, how often a task
    got fewer than the round before and the worst such fall, and the variation over tasks in the last round."""
    rows = kept(spark, both_samplers(spark, sf)).withColumn("value", F.col("effective").cast("double"))
    least = rows.groupBy("method", "iter").agg(F.min("value").alias("value"))
    drop = measures.curve_drop(least, by=["method"])
    falls = measures.seesaw(rows.withColumn("task", F.struct("method", "task"))).groupBy(F.col("task.method").alias("method")).agg(F.sum("falls").alias("falls"), F.min("worst").alias("worst"))
    one = lambda m: measures.task_balance(rows.filter((F.col("method") == m) & (F.col("iter") == SAMPLER_ROUNDS))).select(F.lit(m).alias("method"), "variation")
    out = drop.join(falls, "method").join(one("discard").unionByName(one("quota")), "method")
    return rounded(longs(out, "falls"), "variation")


def discard_rounds_sql(n: int) -> str:
    sql = ""
    for i in range(1, n + 1):
        left = "SELECT sample_id, task FROM pool" if i == 1 else f"SELECT * FROM m{i - 1} UNION ALL SELECT sample_id, task FROM pool WHERE NOT EXISTS (SELECT 1 FROM m{i - 1})"
        sql += f""",
lf{i} AS MATERIALIZED ({left}),
x{i} AS MATERIALIZED (SELECT * FROM (SELECT *, sum(CAST(effective AS INT)) OVER (ORDER BY {O._ORDER}, sample_id ROWS UNBOUNDED PRECEDING) AS ne FROM (SELECT l.sample_id, l.task, effective FROM lf{i} l JOIN outc o ON o.sample_id = l.sample_id AND iter = {i}) z) y WHERE ne - CAST(effective AS INT) < {O.SUBSET}),
m{i} AS MATERIALIZED (SELECT sample_id, task FROM lf{i} WHERE sample_id NOT IN (SELECT sample_id FROM x{i}))"""
    return sql


_N = SAMPLER_ROUNDS
BOTH = f"""WITH {O.loop(_N)}{discard_rounds_sql(_N)},
sn AS ({" UNION ALL ".join(f"SELECT 'discard' AS method, {i} AS iter, task, effective FROM x{i} UNION ALL SELECT 'quota', {i}, task, effective FROM d{i}" for i in range(1, _N + 1))}),
cv AS MATERIALIZED (SELECT method, CAST(iter AS INT) AS iter, e.task, count(sn.effective) AS sampled, count(*) FILTER (WHERE sn.effective) AS effective FROM
  (SELECT DISTINCT pool.task, m.method, g.iter FROM pool CROSS JOIN (VALUES ('discard'), ('quota')) m(method) CROSS JOIN (SELECT unnest(range(1, {_N + 1})) AS iter) g) e LEFT JOIN sn USING (method, iter, task) GROUP BY 1, 2, 3)"""
ORACLES["sampler_curve"] = f"{BOTH} SELECT method, iter, task, sampled, effective, round(CASE WHEN effective = 0 THEN NULL ELSE sampled / CAST(effective AS DOUBLE) END, 6) AS cost FROM cv"
ORACLES["sampler_stability"] = f"""{BOTH}, le AS (SELECT method, iter, min(effective)::DOUBLE AS value FROM cv GROUP BY 1, 2),
dr AS (SELECT method, max(value) AS peak, arg_max(value, iter) AS last, max(value) - arg_max(value, iter) AS drop FROM le GROUP BY 1),
ch AS (SELECT method, effective::DOUBLE - lag(effective) OVER (PARTITION BY method, task ORDER BY iter) AS c FROM cv),
fa AS (SELECT method, count(*) FILTER (WHERE c < 0) AS falls, min(c) AS worst FROM ch GROUP BY 1),
va AS (SELECT method, round(stddev_pop(effective) / nullif(avg(effective), 0), 6) AS variation FROM cv WHERE iter = {_N} GROUP BY 1)
SELECT method, peak, last, drop, falls, worst, variation FROM dr JOIN fa USING (method) JOIN va USING (method)"""


def _ablation(name: str, sql: str, **how):
    def run(spark, sf):
        _, report = quota_history(spark, sf, 3, **how)
        rows = [(r["iter"], r["task"], r["quota"], r["fresh"], r["requeued"], r["effective"]) for r in report]
        return spark.createDataFrame(rows, "iter int, task string, quota long, fresh long, requeued long, effective long")

    run.__name__ = name
    run.__doc__ = f"Three rounds of the sampler with {how}."
    query(run)
    ORACLES[name] = f"WITH {sql} " + " UNION ALL ".join(f"SELECT {i} AS iter, q.task, q.q AS quota, coalesce(fresh, 0) AS fresh, coalesce(again, 0) AS requeued, coalesce(eff, 0) AS effective FROM q{i} q LEFT JOIN c{i} c ON c.task = q.task" for i in (1, 2, 3))


_ablation("quota_without_smoothing", O.loop(3, beta=0.0), beta=0.0)
_ablation("quota_frozen_rates", O.loop(3, beta=1.0), beta=1.0)
_ablation("quota_without_requeue", O.loop(3, requeue=False), requeue=False)
_ablation("quota_static_data", O.loop(3, refresh=False), refresh=False)


@query
def quota_shares(spark, sf):
    """Quotas that add up to 800 exactly, by largest remainder, from each task's last smoothed rate."""
    from .queries import daily_series

    rates = quota.ema_rates(daily_series(spark, sf), F.lit(0.5), C.ema_beta).groupBy("task").agg(F.round(F.max_by("eta_ema", "iter"), 9).alias("eta_ema"))
    return quota.largest_remainder(rates, 800, C.rate_floor)


ORACLES["quota_shares"] = f"""WITH {O.EMA}, l AS (SELECT task, 1 / greatest(round(arg_max(eta_ema, day), 9), 1 / 64.0) AS w FROM em GROUP BY 1),
r AS (SELECT task, round(w * 800 / sum(w) OVER (), 9) AS raw FROM l), f AS (SELECT *, floor(raw) AS b, row_number() OVER (ORDER BY raw - floor(raw) DESC, task) AS place FROM r)
SELECT task, CAST(b AS BIGINT) + CASE WHEN place <= 800 - (SELECT sum(floor(raw)) FROM r) THEN 1 ELSE 0 END AS quota FROM f"""


# ---- variants of stage 1 ----------------------------------------------------------------------------------------------


@query
def strata_soft(spark, sf):
    """Bands of accuracy instead of all and none: easy from 7 of 8 right, hard to 1 of 8."""
    rows = strata.stratify(part_candidates(spark, sf), 0.875, 0.125)
    return longs(rows, "k", "n_correct")


ORACLES["strata_soft"] = f"WITH {O.STRATA} SELECT sample_id, task, k, n_correct, CASE WHEN n_correct / CAST(k AS DOUBLE) >= 0.875 THEN 'easy' WHEN n_correct / CAST(k AS DOUBLE) <= 0.125 THEN 'hard' ELSE 'uncertain' END AS stratum FROM st"


@query
def tuning_arms(spark, sf):
    """Sizes of the training sets of each selection: the method, its share of the uncertain count, and arms that keep one
    stratum or all."""
    rows, order = kept(spark, strata.stratify(part_candidates(spark, sf))), strata.modular_order(F.col("sample_id"))
    arms = {
        "method": {},
        "share_of_uncertain": {"easy_base": "uncertain"},
        "uncertain_only": {"keep": ("uncertain",)},
        "easy_only": {"keep": ("easy",)},
        "with_hard": {"keep": ("uncertain", "easy", "hard")},
    }
    out = None
    for name, how in arms.items():
        one = strata.select_for_tuning(rows, C.easy_share, order, **how).groupBy("task", "stratum").agg(F.count(F.lit(1)).alias("n"), F.sum("sample_id").alias("ids")).withColumn("arm", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return longs(out, "n", "ids")


_ARMS = {"method": "stratum = 'uncertain' OR (stratum = 'easy' AND place <= ceil(round(ne * 0.2, 9)))", "share_of_uncertain": "stratum = 'uncertain' OR (stratum = 'easy' AND place <= ceil(round(nu * 0.2, 9)))", "uncertain_only": "stratum = 'uncertain'", "easy_only": "stratum = 'easy' AND place <= ceil(round(ne * 0.2, 9))", "with_hard": "stratum <> 'easy' OR place <= ceil(round(ne * 0.2, 9))"}
ORACLES["tuning_arms"] = f"WITH {O.STRATA}, x AS (SELECT *, row_number() OVER (PARTITION BY task, stratum ORDER BY {O._ORDER}, sample_id) AS place, count(*) FILTER (WHERE stratum = 'easy') OVER (PARTITION BY task) AS ne, count(*) FILTER (WHERE stratum = 'uncertain') OVER (PARTITION BY task) AS nu FROM st) " + " UNION ALL ".join(
    f"SELECT '{name}' AS arm, task, stratum, count(*) AS n, CAST(sum(sample_id) AS BIGINT) AS ids FROM x WHERE {where} GROUP BY 2, 3" for name, where in _ARMS.items()
)


@query
def retained_variance(spark, sf):
    """Mean variance of the verdicts of each stratum: only uncertain samples still tell something."""
    rows = strata.verdict_variance(strata.stratify(part_candidates(spark, sf)))
    return rounded(longs(rows.groupBy("stratum").agg(F.count(F.lit(1)).alias("samples"), F.avg("variance").alias("variance")), "samples"), "variance")


ORACLES["retained_variance"] = f"WITH {O.STRATA} SELECT stratum, count(*) AS samples, round(avg((n_correct / CAST(k AS DOUBLE)) * (1 - n_correct / CAST(k AS DOUBLE))), 6) AS variance FROM st GROUP BY 1"


@query
def share_draw(spark, sf):
    """A share of each language's documents without ranking."""
    docs = load(spark, sf, "documents", ["doc_id", "lang"])
    return strata.share_sample(docs, "lang", {"en": 0.05, "de": 0.2, "fr": 0.5}, strata.modular_order(F.col("doc_id")))


ORACLES["share_draw"] = "SELECT doc_id, lang FROM documents WHERE (doc_id * 7919 + 104729) % 1000003 < CASE lang WHEN 'en' THEN 0.05 WHEN 'de' THEN 0.2 WHEN 'fr' THEN 0.5 ELSE 0 END * 1000003"


@query
def accuracy_by_type(spark, sf):
    """Share of right answers by task, over the answers themselves."""
    return rounded(longs(measures.accuracy(part_candidates(spark, sf), ["task"]), "items"), "value")


ORACLES["accuracy_by_type"] = f"WITH {O.CAND} SELECT task, count(*) AS items, round(100 * avg(CASE WHEN correct THEN 1.0 ELSE 0.0 END), 6) AS value FROM cand GROUP BY 1"


# ---- objective --------------------------------------------------------------------------------------------------------


def new_plan_steps(spark, sf) -> DataFrame:
    plans = W.order_plans(spark, sf).filter(F.to_date("o_orderdate") >= F.lit("1998-01-01").cast("date"))
    steps = policy.with_history(trie.with_prefix_keys(plans.select("task", "traj", "r", "steps")), 1)
    return steps.select("task", "traj", "r", "t", "history", trie.action_text(F.col("action")).alias("action"))


@query
def sampled_divergence(spark, sf):
    """Divergence of the new policy from the reference estimated on the steps of each new plan."""
    table = bounded_broadcast(kept(spark, order_ratios(spark, sf).select("history", "action", "p_new", "p_ref")))
    rows = new_plan_steps(spark, sf).join(table, ["history", "action"]).groupBy("traj").agg(F.sort_array(F.collect_list(F.struct("t", F.ln("p_new").alias("n"), F.ln("p_ref").alias("f")))).alias("s"))
    return rounded(rows.select("traj", objective.sampled_kl(F.transform("s", lambda x: x["n"]), F.transform("s", lambda x: x["f"])).alias("kl")), "kl")


_NEW = f"WITH {O.TRO}, {O.POLICY}, ns AS (SELECT hs.task, hs.traj, hs.r, rat.* FROM hs JOIN rat ON rat.history = hs.history AND rat.action = hs.a WHERE NOT early)"
ORACLES["sampled_divergence"] = f"{_NEW} SELECT traj, round(avg(p_ref / p_new - ln(p_ref / p_new) - 1), 6) + 0.0 AS kl FROM ns GROUP BY 1"


@query
def trajectory_loss(spark, sf):
    """Baseline loss of each task: clipped gain of whole new plans less their divergence."""
    ratios = kept(spark, order_ratios(spark, sf))
    kl = objective.exact_kl(ratios.select("history", "action", F.col("p_new").alias("p")), ratios.select("history", "action", F.col("p_ref").alias("p")), ["history"])
    steps = new_plan_steps(spark, sf)
    terms = objective.plan_terms(steps, bounded_broadcast(ratios.select("history", "action", "rho")), bounded_broadcast(kl))
    labels = credit.trajectory_advantage(steps.select("task", "traj", "r").distinct(), C.eps).select("task", "traj", "advantage")
    return rounded(objective.trajectory_loss(terms.join(labels, ["task", "traj"]), C.clip, C.kl_weight), "loss")


ORACLES["trajectory_loss"] = f"""{_NEW}, kl AS (SELECT history, sum(p_new * ln(p_new / p_ref)) AS kl FROM rat GROUP BY 1),
tm AS (SELECT task, traj, any_value(r) AS r, exp(sum(ln(rho))) AS rho, avg(kl) AS kl FROM ns JOIN kl ON kl.history = ns.history GROUP BY 1, 2),
wh AS (SELECT *, (r - avg(r) OVER (PARTITION BY task)) / sqrt(var_pop(r) OVER (PARTITION BY task) + 1e-6) AS adv FROM tm)
SELECT task, round(-avg(least(rho * adv, greatest(0.8, least(rho, 1.2)) * adv) - 0.01 * kl), 6) + 0.0 AS loss FROM wh GROUP BY 1"""


@query
def exact_divergence(spark, sf):
    """Divergence of each period's policy from the other by the operator on two policy tables."""
    rows = kept(spark, order_ratios(spark, sf))
    side = lambda c: rows.select("history", "action", F.col(c).alias("p"))
    one = objective.exact_kl(side("p_new"), side("p_old"), ["history"]).withColumnRenamed("kl", "new_from_old")
    return rounded(one.join(objective.exact_kl(side("p_old"), side("p_new"), ["history"]).withColumnRenamed("kl", "old_from_new"), "history"), "new_from_old", "old_from_new")


ORACLES["exact_divergence"] = f"WITH {O.TRO}, {O.POLICY} SELECT history, round(sum(p_new * ln(p_new / p_old)), 6) + 0.0 AS new_from_old, round(sum(p_old * ln(p_old / p_new)), 6) + 0.0 AS old_from_new FROM rat GROUP BY 1"


# ---- keys, returns and stored trees -----------------------------------------------------------------------------------


@query
def credit_by_keying(spark, sf):
    """Kept steps of every form and keying: all the same."""
    plans = kept(spark, W.order_plans(spark, sf).select("task", "traj", "r", "steps"))
    out = None
    for form, keying, by_text in (("window", "hash", False), ("join", "path", False), ("salted", "hash", False), ("window", "level", False), ("window", "path", True)):
        rows = credit.credit_steps(plans, C.gamma, C.eps, C.delta, form, keying, by_text=by_text)
        one = rows.groupBy("t").agg(F.count(F.lit(1)).alias("steps"), F.sum(nudged("advantage", 5).cast("decimal(20,5)")).cast("double").alias("total")).select(F.lit(f"{form}-{keying}-{'text' if by_text else 'action'}").alias("how"), F.col("t").cast("long").alias("t"), "steps", "total")
        out = one if out is None else out.unionByName(one)
    return out


ORACLES["credit_by_keying"] = f"""{O._PRE}, {O.ADV}, s AS (SELECT stp.t, count(*) AS steps, CAST(sum(CAST(round(adv + 1e-9, 5) AS DECIMAL(20,5))) AS DOUBLE) AS total FROM stp JOIN ad ON ad.task = stp.task AND ad.path = stp.path WHERE k > 1 AND abs(adv) > 0.001 GROUP BY 1)
SELECT how, t, steps, total FROM s CROSS JOIN (VALUES ('window-hash-action'), ('join-path-action'), ('salted-hash-action'), ('window-level-action'), ('window-path-text')) h(how)"""


@query
def node_returns(spark, sf):
    """The set of returns of each node, as its size and ends."""
    nodes = trie.node_values(trie.with_prefix_keys(W.order_plans(spark, sf), "path"), C.gamma, keep_returns=True)
    return nodes.select("task", F.col("node_key").alias("path"), F.size("returns").cast("long").alias("n"), nudged(F.element_at("returns", 1)).alias("least"), nudged(F.element_at("returns", -1)).alias("most"))


ORACLES["node_returns"] = f"WITH {O.TRO} SELECT task, path, count(*) AS n, round(min(ret) + 1e-9, 6) + 0.0 AS least, round(max(ret) + 1e-9, 6) + 0.0 AS most FROM stp GROUP BY 1, 2"


@query
def merged_trie(spark, sf):
    """A stored tree of each task's first ten plans, with the rest merged in: node values as of one pass."""
    first, rest = split_plans(spark, sf)
    sums = trie.merge_trie(trie.node_sums(first, C.gamma), trie.node_sums(rest, C.gamma))
    return sums.select("task", F.col("node_key").alias("path"), F.col("n").cast("long").alias("n"), nudged(F.col("total") / F.col("n")).alias("q"))


ORACLES["merged_trie"] = f"{O._PRE} SELECT task, path, n, round(q + 1e-9, 6) + 0.0 AS q FROM nd"


@query
def prefix_counts(spark, sf):
    """Distinct prefixes by depth, exact."""
    nodes = trie.node_values(trie.with_prefix_keys(W.order_plans(spark, sf)), C.gamma)
    return longs(measures.prefix_counts(nodes, ["depth"]), "depth", "prefixes")


ORACLES["prefix_counts"] = f"{O._PRE} SELECT depth, count(*) AS prefixes FROM nd GROUP BY 1"


# ---- agents on the same tasks -----------------------------------------------------------------------------------------


def session_split(spark, sf) -> tuple[DataFrame, DataFrame]:
    """Nodes known from each user's even sessions, and the world: nodes of the odd ones."""
    plans = W.session_plans(spark, sf)
    side = lambda k: kept(spark, trie.node_values(trie.with_prefix_keys(plans.filter(F.col("traj") % 2 == k), "path"), C.gamma))
    return side(0), side(1)


@query
def stepwise_recovery(spark, sf):
    """The agent that decides step by step with errors and recovery in place, by number of errors."""
    known, world = session_split(spark, sf)
    out = baselines.stepwise_recover(known, world, world.select("task").distinct(), C.max_steps)
    return longs(out.groupBy("errors").agg(F.count(F.lit(1)).alias("tasks"), F.sum("steps").alias("steps"), F.count_if("success").alias("successes")), "errors", "tasks", "steps", "successes")


ORACLES["stepwise_recovery"] = f"""WITH RECURSIVE {O.TRE}, ndx AS (SELECT traj % 2 AS side, task, t AS depth, path, left(path, length(path) - length(any_value(a)) - 1) AS parent, round(avg(ret), 9) AS q FROM stp GROUP BY 1, 2, 3, 4),
kn AS (SELECT * FROM ndx WHERE side = 0), wo AS (SELECT * FROM ndx WHERE side = 1),
fv AS (SELECT task, parent, arg_max(path, (q, path)) AS fav FROM kn GROUP BY 1, 2),
pk AS (SELECT w.task, w.parent, arg_max(w.path, (coalesce(k.q, 0.0), w.path)) AS path, arg_max(w.q, (coalesce(k.q, 0.0), w.path)) AS q FROM wo w LEFT JOIN kn k ON k.task = w.task AND k.path = w.path GROUP BY 1, 2),
mv AS (SELECT pk.*, CASE WHEN fav <> path THEN 1 ELSE 0 END AS missed FROM pk LEFT JOIN fv ON fv.task = pk.task AND fv.parent = pk.parent),
wk AS (SELECT task, '' AS at, 0 AS steps, 0 AS errors, CAST(NULL AS DOUBLE) AS q FROM (SELECT DISTINCT task FROM wo) x
       UNION ALL SELECT wk.task, mv.path, steps + 1, errors + mv.missed, mv.q FROM wk JOIN mv ON mv.task = wk.task AND mv.parent = wk.at WHERE steps < 25),
ends AS (SELECT task, max(steps) AS steps, arg_max(errors, steps) AS errors, arg_max(q, steps) AS q FROM wk GROUP BY 1)
SELECT CAST(errors AS BIGINT) AS errors, count(*) AS tasks, CAST(sum(steps) AS BIGINT) AS steps, count(*) FILTER (WHERE coalesce(q > 0, false)) AS successes FROM ends GROUP BY 1"""


@query
def replan_and_continue(spark, sf):
    """Failed sessions replanned at their last better step and continued by best children, two tries at most."""
    steps = trie.with_prefix_keys(W.session_plans(spark, sf), "path")
    nodes = kept(spark, trie.node_values(steps, C.gamma))
    out = replan.replan_and_continue(steps, nodes, C.max_steps)
    return longs(out.groupBy("replans").agg(F.count(F.lit(1)).alias("plans"), F.count_if("success").alias("successes")), "replans", "plans", "successes")


ORACLES["replan_and_continue"] = f"""WITH RECURSIVE {O.TRE}, {O.NODES}, ch AS (SELECT task, parent, arg_max(path, (round(q, 9), a)) AS path, arg_max(q, (round(q, 9), a)) AS q FROM nd GROUP BY 1, 2),
tr AS (SELECT * FROM (SELECT stp.task, stp.traj, stp.t, ch.path, ch.q, row_number() OVER (PARTITION BY stp.task, stp.traj ORDER BY stp.t DESC) AS try
       FROM stp JOIN nd ON nd.task = stp.task AND nd.path = stp.path JOIN ch ON ch.task = nd.task AND ch.parent = nd.parent WHERE r = -1 AND round(ch.q, 9) > round(nd.q, 9)) z WHERE try <= 2),
wk AS (SELECT task, traj, try, path, q, t FROM tr UNION ALL SELECT wk.task, traj, try, ch.path, ch.q, t + 1 FROM wk JOIN ch ON ch.task = wk.task AND ch.parent = wk.path),
en AS (SELECT task, traj, try, arg_max(q, t) > 0 AS ok FROM wk GROUP BY 1, 2, 3),
pl AS (SELECT task, traj, coalesce(min(try) FILTER (WHERE ok), max(try)) AS replans, bool_or(ok) AS success FROM en GROUP BY 1, 2)
SELECT CAST(replans AS BIGINT) AS replans, count(*) AS plans, count(*) FILTER (WHERE success) AS successes FROM pl GROUP BY 1"""


# ---- rewards with many parts ------------------------------------------------------------------------------------------


@query
def reward_boxes(spark, sf):
    """Two predicted boxes against two true ones in every vector: one-to-one matching by IoU, F1 times mean IoU."""
    from .queries import box, geometry

    rows = geometry(spark, sf)
    two = lambda v: F.array(box(v, 0, 2), box(v, 4, 2))
    return rounded(rows.select("vec_id", rewards.box_reward(two("v"), two("g"), 0.05).alias("joint"), rewards.box_reward(two("v"), two("g"), mode="soft").alias("soft")), "joint", "soft")


def _corner(s: str, at: int) -> tuple[list[str], list[str]]:
    lo = [f"least({s}[{at + k + 1}], {s}[{at + k + 3}])" for k in range(2)]
    return lo, [f"(greatest({s}[{at + k + 1}], {s}[{at + k + 3}]) + 0.05)" for k in range(2)]


def _pair_iou(i: int, j: int) -> str:
    (pl, ph), (gl, gh) = _corner("v", 4 * i), _corner("g", 4 * j)
    inter = " * ".join(f"greatest(0, least({ph[k]}, {gh[k]}) - greatest({pl[k]}, {gl[k]}))" for k in range(2))
    vol = lambda lo, hi: " * ".join(f"({h} - {x})" for x, h in zip(lo, hi))
    return f"(({inter}) / (({vol(pl, ph)}) + ({vol(gl, gh)}) - ({inter})))"


ORACLES["reward_boxes"] = f"""WITH {O.GEO}, m AS (SELECT vec_id, {", ".join(f"{_pair_iou(i, j)} AS m{i}{j}" for i in (0, 1) for j in (0, 1))} FROM geo),
f AS (SELECT vec_id, greatest(m00, m01, m10, m11) AS a, CASE WHEN greatest(m00, m01, m10, m11) IN (m00, m11) AND NOT (greatest(m01, m10) > greatest(m00, m11)) THEN CASE WHEN m00 >= m11 THEN m11 ELSE m00 END ELSE CASE WHEN m01 >= m10 THEN m10 ELSE m01 END END AS b FROM m),
h AS (SELECT vec_id, a, b, CAST(a >= 0.05 AS INT) + CAST(b >= 0.05 AS INT) AS n, CASE WHEN a >= 0.05 THEN a ELSE 0 END + CASE WHEN b >= 0.05 THEN b ELSE 0 END AS s FROM f)
SELECT vec_id, round(CASE WHEN n = 0 THEN 0 ELSE (2.0 * n / 4) * (s / n) END, 6) + 0.0 AS joint, round(2 * (a + b) / 4, 6) + 0.0 AS soft FROM h"""


@query
def plan_records(spark, sf):
    """Orders as unified plan records, parsed back: the record and how many actions come out of it."""
    plans = W.order_plans(spark, sf).select("traj", F.concat(F.lit("order of "), F.col("o_orderstatus")).alias("reply"), F.transform("steps", lambda s: s["action"]).alias("actions"))
    rows = actions.to_plan_record(plans, "reply", "actions")
    return rows.select("traj", "plan", F.size(actions.parse_tagged(F.col("plan"))).cast("long").alias("actions"))


ORACLES["plan_records"] = f"WITH {O.TRO} SELECT traj, '<reply>order of ' || any_value(o_orderstatus) || '</reply><plan>' || string_agg('<act>' || replace(txt, '/', '|') || '|</act>', '' ORDER BY t) || '</plan>' AS plan, count(*) AS actions FROM (SELECT stp.*, o_orderstatus FROM stp JOIN orders ON o_orderkey = traj) z GROUP BY 1"


# ---- times of phases --------------------------------------------------------------------------------------------------


@query
def time_shares(spark, sf):
    """Time from each event to its user's next one as the minutes of a stage: users stand for three methods, purchases and
    views for sampling, the rest for training. Shares of each phase, and methods against each other."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    gap = F.lead(at).over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - at
    method = F.element_at(F.array(*map(F.lit, ("filter_rule", "filter_judge", "quota"))), (F.pmod("user_id", F.lit(3)) + 1).cast("int"))
    phase = F.when(F.col("event_type").isin("purchase", "view"), "sampling").otherwise("training")
    events = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type"]).select(F.lit("events").alias("stage"), method.alias("method"), phase.alias("phase"), gap.alias("micros"))
    rows = events.filter("micros is not null").groupBy("stage", "method", "phase").agg((F.sum("micros") / 1e6).alias("seconds"), F.count(F.lit(1)).alias("n"))
    shares = measures.phase_share(rows).select(F.concat_ws("-", "method", "phase").alias("measure"), F.col("share").alias("value"))
    of = lambda name, c: F.sum(F.when(F.col("method") == name, F.col(c))).cast("double")
    each = rows.agg(*(of(name, c).alias(f"{name}_{c}") for name in ("filter_rule", "filter_judge", "quota") for c in ("seconds", "n")))
    values = {
        "credit-overhead": measures.relative_overhead(F.col("filter_judge_seconds"), F.col("filter_rule_seconds")),
        "volume-ratio": measures.volume_ratio(F.col("quota_n"), F.col("filter_judge_n")),
        "quota-speedup": F.col("filter_judge_seconds") / F.col("quota_seconds"),
    }
    more = each.select(F.inline(F.array(*(F.struct(F.lit(k).alias("measure"), v.alias("value")) for k, v in values.items()))))
    return rounded(shares.unionByName(more), "value")


ORACLES["time_shares"] = """WITH g AS (SELECT CASE user_id % 3 WHEN 0 THEN 'filter_rule' WHEN 1 THEN 'filter_judge' ELSE 'quota' END AS method, CASE WHEN event_type IN ('purchase', 'view') THEN 'sampling' ELSE 'training' END AS phase,
  epoch_us(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) - epoch_us(ts) AS us FROM events),
p AS (SELECT method, phase, CAST(sum(us) AS DOUBLE) AS us, count(*) AS n FROM g WHERE us IS NOT NULL GROUP BY 1, 2),
m AS (SELECT sum(us) FILTER (WHERE method = 'filter_rule') AS r, sum(us) FILTER (WHERE method = 'filter_judge') AS j, sum(us) FILTER (WHERE method = 'quota') AS q,
  CAST(sum(n) FILTER (WHERE method = 'quota') AS DOUBLE) AS nq, CAST(sum(n) FILTER (WHERE method = 'filter_judge') AS DOUBLE) AS nj FROM p)
SELECT method || '-' || phase AS measure, round(us / sum(us) OVER (PARTITION BY method), 6) + 0.0 AS value FROM p
UNION ALL SELECT 'credit-overhead', round((j - r) / r, 6) + 0.0 FROM m UNION ALL SELECT 'volume-ratio', round(nq / nj, 6) + 0.0 FROM m UNION ALL SELECT 'quota-speedup', round(j / q, 6) + 0.0 FROM m"""
