"""Cost and accuracy measures: single aggregates over result tables."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def rate(flag: Column) -> Column:
    """Share of true rows; nulls are not counted."""
    return F.avg(F.when(flag, 1.0).when(~flag, 0.0))


def accuracy(rows: DataFrame, by: list[str], correct: str = "correct") -> DataFrame:
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("items"), (100 * rate(F.col(correct))).alias("value"))


def category_means(scores: DataFrame) -> DataFrame:
    """Unweighted mean over the benchmarks of a category."""
    return scores.groupBy("system", "category").agg(F.avg("value").alias("value"))


def overall(scores: DataFrame) -> DataFrame:
    """Unweighted mean over benchmarks, not over categories."""
    return scores.groupBy("system").agg(F.avg("value").alias("value"))


def podium(scores: DataFrame) -> DataFrame:
    """place 1 for the best system of a benchmark, 2 for the runner-up, else null."""
    place = F.dense_rank().over(Window.partitionBy("benchmark").orderBy(F.desc("value")))
    return scores.withColumn("place", F.when(place <= 2, place))


def gain(scores: DataFrame, method: str, baseline: str) -> DataFrame:
    """Points of the method over the baseline, by benchmark."""
    at = lambda s: F.max(F.when(F.col("system") == s, F.col("value")))
    return scores.groupBy("benchmark").agg((at(method) - at(baseline)).alias("gain"))


def success_rate(labels: DataFrame, by: list[str]) -> DataFrame:
    return labels.groupBy(*by).agg(F.count(F.lit(1)).alias("plans"), F.sum(F.when(F.col("r") == 1, 1).otherwise(0)).alias("successes"), (100 * rate(F.col("r") == 1)).alias("success_pct"))


def seed_summary(runs: DataFrame, value: str = "value") -> DataFrame:
    """Mean with sample and population deviation and variance over runs."""
    return runs.groupBy("system").agg(F.count(F.lit(1)).alias("runs"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("std_sample"), F.stddev_pop(value).alias("std_population"), F.var_samp(value).alias("var_sample"))


def shares(rows: DataFrame, label: str, by: list[str]) -> DataFrame:
    """Share of each label within `by`."""
    counted = rows.groupBy(*by, label).agg(F.count(F.lit(1)).alias("n"))
    return counted.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(*by)))


def sampling_cost(outcomes: DataFrame, by: list[str]) -> DataFrame:
    """Draws, effective draws, and draws spent on each effective one."""
    return outcomes.groupBy(*by).agg(F.count(F.lit(1)).alias("sampled"), F.count_if("effective").alias("effective")).withColumn("cost", F.try_divide(F.col("sampled").cast("double"), F.col("effective")))


def task_balance(counts: DataFrame, value: str = "effective") -> DataFrame:
    """Spread of effective samples over tasks: max/min, coefficient of variation, mean distance from the even share."""
    even = F.avg(value).over(Window.partitionBy())
    rows = counts.withColumn("_even", even)
    return rows.agg(F.max(value).alias("most"), F.min(value).alias("least"), F.try_divide(F.max(value).cast("double"), F.min(value)).alias("ratio"), F.try_divide(F.stddev_pop(value), F.avg(value)).alias("variation"), F.avg(F.abs(F.col(value) - F.col("_even"))).alias("mean_gap"))


def curve_drop(curve: DataFrame, x: str = "iter", y: str = "value", by: list[str] | None = None) -> DataFrame:
    """Best value minus last value of each curve."""
    return curve.groupBy(*(by or [])).agg(F.max(y).alias("peak"), F.max_by(y, x).alias("last"), (F.max(y) - F.max_by(y, x)).alias("drop"))


def seesaw(history: DataFrame, by: str = "task", x: str = "iter", y: str = "value") -> DataFrame:
    """How often each task got worse from one round to the next, and the worst fall."""
    change = F.col(y) - F.lag(y).over(Window.partitionBy(by).orderBy(x))
    return history.withColumn("change", change).groupBy(by).agg(F.count_if(F.col("change") < 0).alias("falls"), F.min("change").alias("worst"))


def judge_quality(rows: DataFrame, said: str, truth: str) -> DataFrame:
    """accuracy, precision, recall, f1 of boolean `said` against boolean `truth`."""
    tp, fp, fn = (F.count_if(x) for x in (F.col(said) & F.col(truth), F.col(said) & ~F.col(truth), ~F.col(said) & F.col(truth)))
    out = rows.agg(F.count(F.lit(1)).alias("n"), rate(F.col(said) == F.col(truth)).alias("accuracy"), F.try_divide(tp.cast("double"), tp + fp).alias("precision"), F.try_divide(tp.cast("double"), tp + fn).alias("recall"))
    return out.withColumn("f1", F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


def length_stats(plans: DataFrame) -> DataFrame:
    n = F.size("steps")
    return plans.agg(F.count(F.lit(1)).alias("plans"), F.avg(n).alias("mean_steps"), F.max(n).cast("long").alias("max_steps"), F.percentile(n, 0.5).alias("median_steps"))


def prefix_counts(nodes: DataFrame, by: list[str], how: str = "exact") -> DataFrame:
    """Distinct prefixes of each group: exact, approximate, or from a mergeable sketch (column `sketch` for later merges)."""
    key = F.xxhash64("task", "depth", "node_key")
    if how == "sketch":
        out = nodes.groupBy(*by).agg(F.hll_sketch_agg(key, F.lit(14)).alias("sketch"))
        return out.withColumn("prefixes", F.hll_sketch_estimate("sketch"))
    return nodes.groupBy(*by).agg((F.countDistinct(key) if how == "exact" else F.approx_count_distinct(key, 0.01)).alias("prefixes"))


def relative_overhead(method: float, baseline: float) -> float:
    return (method - baseline) / baseline


def volume_ratio(ours: float, theirs: float) -> float:
    return ours / theirs


def timed(ledger: list[tuple[str, str, str, float]], stage: str, method: str, phase: str, work: Callable[[], object]) -> object:
    """Run `work`, noting its wall time as (stage, method, phase, seconds)."""
    began = time.perf_counter()
    out = work()
    ledger.append((stage, method, phase, time.perf_counter() - began))
    return out


def phase_share(ledger: DataFrame) -> DataFrame:
    """Each phase's share of its stage and method."""
    return ledger.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("stage", "method")))


def explain_cost(df: DataFrame) -> dict[str, int]:
    """Counts of the operators that cost most in the physical plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    initial = plan.split("== Initial Plan ==")[-1]
    return {k: len(re.findall(p, initial)) for k, p in {"exchanges": r"\bExchange (?:hash|range|Single|RoundRobin)", "broadcasts": r"\bBroadcastExchange", "sorts": r"\bSort \[", "python": r"Python|Pandas|Arrow\w*Exec"}.items()}
