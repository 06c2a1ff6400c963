"""Rewards matched to the kind of output, thresholds, and majority votes: expressions that stay in one projection."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def normalised(text: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(text, r"\s+", " ")))


def exact_reward(a: Column, b: Column, normalise: bool = True) -> Column:
    """1.0 for equal texts, else 0.0; null if either is null."""
    return (normalised(a) == normalised(b) if normalise else a == b).cast("double")


def token_jaccard(a: Column, b: Column) -> Column:
    sa, sb = (F.array_distinct(F.filter(F.split(normalised(x), " "), lambda w: w != "")) for x in (a, b))
    return F.coalesce(F.try_divide(F.size(F.array_intersect(sa, sb)).cast("double"), F.size(F.array_union(sa, sb))), F.lit(1.0))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def semantic_reward(a: Column, b: Column, judge: Callable[[Column, Column], Column] = token_jaccard, tau: float = 0.5) -> Column:
    """1.0 when the judge's similarity reaches tau. The judge is any function of two columns, a pandas UDF included."""
    return (judge(a, b) >= tau).cast("double")


def point_reward(p: Column, g: Column, extent: Column, per_axis: bool = False) -> Column:
    """1 minus the L1 distance over the extent's sum (or the mean over axes of distance over extent), 0 at least."""
    total = lambda xs: F.aggregate(xs, F.lit(0.0), lambda s, v: s + v)
    gaps = F.zip_with(p, g, lambda x, y: F.abs(x - y))
    miss = F.try_divide(total(F.zip_with(gaps, extent, lambda d, e: F.try_divide(d, e))), F.size(p)) if per_axis else F.try_divide(total(gaps), total(extent))
    return F.greatest(F.lit(0.0), 1.0 - miss)


def distance_reward(d: Column, g: Column) -> Column:
    """The smaller of d/g and g/d; 0 when either is not positive."""
    return F.when((d > 0) & (g > 0), F.least(F.try_divide(d, g), F.try_divide(g, d))).when(d.isNotNull() & g.isNotNull(), 0.0)


def volume(lo: Column, hi: Column) -> Column:
    return F.aggregate(F.zip_with(lo, hi, lambda a, b: F.greatest(F.lit(0.0), b - a)), F.lit(1.0), lambda s, v: s * v)


def iou(a: Column, b: Column) -> Column:
    """Intersection over union of boxes struct<lo, hi> of any dimension; 0 when both are empty."""
    both = volume(F.zip_with(a["lo"], b["lo"], lambda x, y: F.greatest(x, y)), F.zip_with(a["hi"], b["hi"], lambda x, y: F.least(x, y)))
    return F.coalesce(F.try_divide(both, volume(a["lo"], a["hi"]) + volume(b["lo"], b["hi"]) - both), F.lit(0.0))


def matched(preds: Column, truths: Column) -> Column:
    """IoUs of a one-to-one matching, greedy from the largest IoU; ties to the earlier boxes."""
    pairs = F.flatten(F.transform(preds, lambda p, i: F.transform(truths, lambda g, j: F.struct((-iou(p, g)).alias("cost"), i.alias("i"), j.alias("j")))))
    start = F.struct(F.array().cast("array<int>").alias("p"), F.array().cast("array<int>").alias("g"), F.array().cast("array<double>").alias("ious"))

    def take(acc: Column, x: Column) -> Column:
        free = ~F.array_contains(acc["p"], x["i"]) & ~F.array_contains(acc["g"], x["j"]) & (x["cost"] < 0)
        grown = F.struct(F.array_append(acc["p"], x["i"]).alias("p"), F.array_append(acc["g"], x["j"]).alias("g"), F.array_append(acc["ious"], -x["cost"]).alias("ious"))
        return F.when(free, grown).otherwise(acc)

    return F.aggregate(F.array_sort(pairs), start, take, lambda acc: acc["ious"])


def box_reward(preds: Column, truths: Column, iou_at: float = 0.5, mode: str = "joint") -> Column:
    """F1 of matches at `iou_at` times their mean IoU; `soft` takes IoU sums as precision and recall instead.
    No boxes on both sides is 1, on one side 0."""
    ious = matched(preds, truths)
    total = lambda xs: F.aggregate(xs, F.lit(0.0), lambda s, v: s + v)
    n = F.size(preds) + F.size(truths)
    if mode == "soft":
        value = F.try_divide(2 * total(ious), n)
    else:
        hits = F.filter(ious, lambda v: v >= iou_at)
        value = F.try_divide(2.0 * F.size(hits), n) * F.coalesce(F.try_divide(total(hits), F.size(hits)), F.lit(0.0))
    return F.when(n == 0, 1.0).otherwise(value)


def hybrid_reward(kind: Column, exact: Column, semantic: Column, point: Column, distance: Column, box: Column) -> Column:
    """Reward of the row's kind: exact, semantic, point, distance or box; another kind gives null."""
    return F.when(kind == "exact", exact).when(kind == "semantic", semantic).when(kind == "point", point).when(kind == "distance", distance).when(kind == "box", box)


def correct_if(reward: Column, task: Column, thresholds: dict[str, float] | float, default: float = 0.5) -> Column:
    """Whether a continuous reward counts as correct, by one threshold or one a task; a null reward stays null."""
    if not isinstance(thresholds, dict):
        return reward >= thresholds
    at = F.coalesce(*(F.when(task == k, F.lit(v)) for k, v in thresholds.items()), F.lit(default))
    return reward >= at


def majority_label(votes: DataFrame, keys: list[str], tie: int = -1) -> DataFrame:
    """(keys, r, margin): the sign of the votes' sum; a tie has the label `tie`."""
    total = F.sum("vote")
    return votes.groupBy(*keys).agg(F.when(total > 0, 1).when(total < 0, -1).otherwise(tie).alias("r"), (F.abs(total) / F.count("vote")).alias("margin"))
