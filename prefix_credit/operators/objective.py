"""Step ratio, clipped gain, divergence, and the loss of sibling groups."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def masked_sum(logp: Column, mask: Column | None = None) -> Column:
    """Sum of token log-probabilities; tokens with mask 0 count nothing."""
    vals = logp if mask is None else F.zip_with(logp, mask, lambda p, m: F.when(m == 1, p).otherwise(F.lit(0.0)))
    return F.aggregate(vals, F.lit(0.0), lambda a, x: a + x)


def step_ratio(new: Column, old: Column, mask: Column | None = None, agg: str = "product") -> Column:
    """Probability of the step's tokens under the new policy over the old one; `geo_mean` takes the mean token instead."""
    gap = masked_sum(new, mask) - masked_sum(old, mask)
    if agg == "geo_mean":
        n = F.size(new) if mask is None else F.aggregate(mask, F.lit(0), lambda a, m: a + m.cast("int"))
        gap = F.try_divide(gap, n)
    return F.exp(gap)


def clipped_gain(rho: Column, advantage: Column, clip: float) -> Column:
    return F.least(rho * advantage, F.greatest(F.lit(1 - clip), F.least(rho, F.lit(1 + clip))) * advantage)


def sampled_kl(logp: Column, logp_ref: Column, mask: Column | None = None) -> Column:
    """Unbiased non-negative estimate from the sampled tokens: mean of ratio - log ratio - 1, the ratio reference over policy."""
    gap = F.zip_with(logp, logp_ref, lambda p, q: q - p)
    each = F.transform(gap, lambda g: F.exp(g) - g - 1.0)
    n = F.size(logp) if mask is None else F.aggregate(mask, F.lit(0), lambda a, m: a + m.cast("int"))
    return F.try_divide(masked_sum(each, mask), n)


def exact_kl(policy: DataFrame, reference: DataFrame, keys: list[str]) -> DataFrame:
    """Divergence from the reference of each conditional distribution (keys, action, p); both smoothed over one vocabulary."""
    ref = reference.select(*keys, "action", F.col("p").alias("p_ref"))
    return policy.join(ref, [*keys, "action"]).groupBy(*keys).agg(F.sum(F.col("p") * F.ln(F.col("p") / F.col("p_ref"))).alias("kl"))


def sibling_loss(rows: DataFrame, clip: float, kl_weight: float, norm: str = "children") -> DataFrame:
    """Loss of each parent from one row a child: rho, advantage, kl, n. `visits` divides by the children's visits."""
    term = clipped_gain(F.col("rho"), F.col("advantage"), clip) - kl_weight * F.col("kl")
    many = F.count(F.lit(1)) if norm == "children" else F.sum("n")
    return rows.groupBy("task", "depth", "parent_key").agg((-F.sum(term) / many).alias("loss"), F.count(F.lit(1)).alias("children"))


def sibling_losses(rows: DataFrame, clip: float, kl_weight: float) -> DataFrame:
    """The loss of each parent by children and by visits, in one aggregate."""
    term = clipped_gain(F.col("rho"), F.col("advantage"), clip) - kl_weight * F.col("kl")
    sums = rows.groupBy("task", "depth", "parent_key").agg(F.sum(term).alias("s"), F.count(F.lit(1)).alias("children"), F.sum("n").alias("visits"))
    return sums.select("task", "depth", "parent_key", "children", (-F.col("s") / F.col("children")).alias("loss"), (-F.col("s") / F.col("visits")).alias("loss_by_visits"))


def plan_terms(steps: DataFrame, ratios: DataFrame, kl: DataFrame) -> DataFrame:
    """(task, traj, rho, kl) of whole plans from steps (task, traj, history, action), step ratios (history, action, rho) and
    divergences (history, kl): the product of the ratios and the mean divergence."""
    rows = steps.join(ratios, ["history", "action"]).join(kl, "history")
    return rows.groupBy("task", "traj").agg(F.exp(F.sum(F.ln("rho"))).alias("rho"), F.avg("kl").alias("kl"))


def trajectory_loss(rows: DataFrame, clip: float, kl_weight: float) -> DataFrame:
    """Baseline loss of each task: clipped gain of whole plans (rho, advantage, kl a plan)."""
    term = clipped_gain(F.col("rho"), F.col("advantage"), clip) - kl_weight * F.col("kl")
    return rows.groupBy("task").agg((-F.avg(term)).alias("loss"))
