"""Runs the experiments on the given tables and prints what each measure does, beside the published direction.

    python experiments.py [/root/testdata/sf0.1]
"""

from __future__ import annotations

import os
import sys
import time

os.environ["PYTHONPATH"] = os.path.dirname(os.path.abspath(__file__)) + os.pathsep + os.environ.get("PYTHONPATH", "")


def main(sf: str) -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from prefix_credit import queries as Q
    from prefix_credit.config import DEFAULTS as C
    from prefix_credit.functions import measures
    from prefix_credit.operators import baselines, credit, quota, strata, trie
    from prefix_credit.session import work_dir
    from prefix_credit.sources import workloads as W

    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "16g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")

    def show(title: str, rows: list) -> None:
        print(f"\n## {title}")
        for r in rows:
            print("  " + ", ".join(f"{k}={v:.4g}" if isinstance(v, float) else f"{k}={v}" for k, v in (r.asDict() if hasattr(r, "asDict") else r).items()))

    show("Strata over iterations (published: easy grows, uncertain falls in the end)", Q.QUERIES["strata_drift"](spark, sf).groupBy("iter").pivot("stratum", ["easy", "uncertain", "hard"]).agg(F.first("share")).orderBy("iter").collect())
    show("Filtered against unfiltered selection (published: filtered wins overall)", Q.QUERIES["score_sheet"](spark, sf).filter("category = 'overall'").orderBy(F.desc("value")).collect())

    rounds, subset = 8, 600
    at = work_dir(spark)
    Q.part_pool(spark, sf).write.parquet(f"{at}/pool")
    pool = spark.read.parquet(f"{at}/pool")
    outcomes = {i: Q.part_outcomes(spark, sf, i) for i in range(rounds + 1)}
    rollout = lambda rows, i: rows.select("task", "sample_id").join(outcomes[i], ["task", "sample_id"])
    began = time.perf_counter()
    history, report = quota.run_iterations(spark, pool, rollout, at, subset, rounds, C.ema_beta, C.rate_floor, C.r_max, C.probe)
    t_quota = time.perf_counter() - began
    began, table = time.perf_counter(), []
    left = pool.select("task", "sample_id")
    for i in range(1, rounds + 1):
        one = baselines.discard_sampling(left.join(outcomes[i], ["task", "sample_id"]), strata.modular_order(F.col("sample_id")), subset)
        one.write.parquet(f"{at}/discard/round={i}")
        one = spark.read.parquet(f"{at}/discard/round={i}")
        left = left.join(one.select("sample_id"), "sample_id", "left_anti")
        per = one.groupBy("task").agg(F.count(F.lit(1)).alias("sampled"), F.count_if("effective").alias("effective"))
        b = measures.task_balance(per).first()
        table.append({"round": i, "discard_draws": one.count(), "discard_variation": b["variation"], "discard_least": b["least"], "discard_most": b["most"]})
    t_discard = time.perf_counter() - began
    for row in table:
        eff = [r["effective"] for r in report if r["iter"] == row["round"]]
        mean = sum(eff) / len(eff)
        row |= {"quota_draws": sum(r["sampled"] for r in report if r["iter"] == row["round"]), "quota_variation": (sum((e - mean) ** 2 for e in eff) / len(eff)) ** 0.5 / mean, "quota_least": min(eff), "quota_most": max(eff)}
    show("Effective samples by task, discard against quotas (published: quotas keep tasks near K/N; discard starves hard ones)", table)
    show("Seconds of the sampling loops", [{"quota": t_quota, "discard": t_discard}])

    show("Credit by label of the plan (published: right steps of failed plans keep positive credit)", Q.QUERIES["credit_contrast"](spark, sf).orderBy("source", "r").collect())
    show("Tree shape (published: 6.06 branching, 10.26 leaves, group size 2.53)", Q.QUERIES["trie_shape"](spark, sf).collect())
    plans = W.order_plans(spark, sf).select("task", "traj", "r", "steps")
    plans.write.parquet(f"{at}/plans")
    plans = spark.read.parquet(f"{at}/plans")
    times: dict[str, list[float]] = {"whole": [], "sibling": []}
    for _ in range(4):
        for name, f in (("whole", lambda: credit.spread(credit.trajectory_advantage(plans, C.eps))), ("sibling", lambda: credit.credit_rows(plans, C.gamma, C.eps, C.delta))):
            began = time.perf_counter()
            f().write.format("noop").mode("overwrite").save()
            times[name].append(time.perf_counter() - began)
    best = {k: min(v) for k, v in times.items()}
    n = plans.agg(F.sum(F.size("steps"))).first()[0]
    show("Advantage computation alone (published: +22.29 % of a whole training round)", [{"steps": n, "whole_s": best["whole"], "sibling_s": best["sibling"], "sibling_steps_per_s": n / best["sibling"]}])
    show("Prefix tree against full search, depth 8", [{"nodes_seen": trie.node_values(trie.with_prefix_keys(plans), C.gamma).count(), "full_tree_a_task": sum(6**d for d in range(1, 9))}])
    show("Co-evolution rounds (published: success rises round by round)", Q.QUERIES["round_ledger"](spark, sf).collect())
    show("Five seeds", Q.QUERIES["seed_summary"](spark, sf).collect())
    show("Failure monitor", Q.QUERIES["failure_monitor"](spark, sf).collect())
    r = Q.QUERIES["replan_success"](spark, sf).agg(F.sum("plans").alias("plans"), F.sum("failed").alias("failed"), F.sum("recovered").alias("recovered")).first()
    show("Replanning failed sessions (published: plan and replan beats the stepwise agent)", [{"success_before_pct": 100 * (1 - r["failed"] / r["plans"]), "success_after_replan_pct": 100 * (1 - (r["failed"] - r["recovered"]) / r["plans"])}])


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1")
