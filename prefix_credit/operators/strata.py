"""Difficulty-filtered selection: candidates, strata by how many of them are right, training sets and pools."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.forms import bounded_broadcast

EASY, UNCERTAIN, HARD = "easy", "uncertain", "hard"


def capability_mix(samples: DataFrame, by: list[str]) -> DataFrame:
    """Rows and share of each capability type."""
    counted = samples.groupBy(*by).agg(F.count(F.lit(1)).alias("n"))
    return counted.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy()))


def modular_order(key: Column, a: int = 7919, b: int = 104729, m: int = 1_000_003) -> Column:
    """A scattered order that any engine can repeat."""
    return F.pmod(key * a + b, F.lit(m))


def seeded_order(key: Column, seed: int) -> Column:
    return F.xxhash64(key, F.lit(seed))


def balanced_sample(samples: DataFrame, by: str, cap: int, order: Column, tie: str) -> DataFrame:
    """At most `cap` rows of each type, first in `order`."""
    at = F.row_number().over(Window.partitionBy(by).orderBy(order, tie))
    return samples.withColumn("__at", at).filter(F.col("__at") <= cap).drop("__at")


def share_sample(samples: DataFrame, by: str, shares: dict, order: Column, m: int = 1_000_003) -> DataFrame:
    """About a share of each type without ranking: rows whose place in a scattered order of `m` values is low enough."""
    at = F.coalesce(*(F.when(F.col(by) == k, F.lit(v)) for k, v in shares.items()), F.lit(0.0))
    return samples.filter(order < at * m)


def seeded_share_sample(samples: DataFrame, by: str, shares: dict, seed: int) -> DataFrame:
    """The same by Spark's own stratified sampling."""
    return samples.sampleBy(by, shares, seed)


def draw_candidates(answers: DataFrame, k: int, order_cols: list[str], key: str = "sample_id") -> DataFrame:
    """The first k recorded answers of each sample, as cand_no from 1."""
    return answers.withColumn("cand_no", F.row_number().over(Window.partitionBy(key).orderBy(*order_cols))).filter(F.col("cand_no") <= k)


def stratify(cands: DataFrame, easy_at: float = 1.0, hard_at: float = 0.0, keys: tuple[str, ...] = ("sample_id", "task")) -> DataFrame:
    """(keys, k, n_correct, stratum): all right, none right, or some. Candidates without a verdict don't count; a sample
    without any verdict has no stratum. `easy_at`, `hard_at` soften the bands."""
    return banded(cands.groupBy(*keys).agg(F.count("correct").alias("k"), F.count_if("correct").alias("n_correct")), easy_at, hard_at)


def banded(out: DataFrame, easy_at: float = 1.0, hard_at: float = 0.0) -> DataFrame:
    """Adds stratum to rows with k and n_correct."""
    share = F.col("n_correct") / F.col("k")
    return out.withColumn("stratum", F.when(F.col("k") == 0, None).when(share >= easy_at, EASY).when(share <= hard_at, HARD).otherwise(UNCERTAIN))


def select_for_tuning(strata: DataFrame, easy_share: float, order: Column, easy_base: str = "easy", keep: tuple[str, ...] = (UNCERTAIN, EASY)) -> DataFrame:
    """Every uncertain sample and a share of the easy ones of each task (of the easy count or of the uncertain count),
    first in `order`; hard ones stay out unless kept. Ranks are needed for the easy ones only."""
    whole = strata.filter(F.col("stratum").isin(*[s for s in keep if s != EASY]))
    if EASY not in keep:
        return whole
    base = strata.groupBy("task").agg(F.count_if(F.col("stratum") == (EASY if easy_base == "easy" else UNCERTAIN)).alias("__base"))
    easy = strata.filter(F.col("stratum") == EASY).join(bounded_broadcast(base), "task")
    at = F.row_number().over(Window.partitionBy("task").orderBy(order, "sample_id"))
    easy = easy.withColumn("__at", at).filter(F.col("__at") <= F.ceil(F.round(F.col("__base") * easy_share, 9))).select(*strata.columns)
    return whole.unionByName(easy)


def rl_pool(strata: DataFrame) -> DataFrame:
    """Samples that still have something to teach: uncertain and hard."""
    return strata.filter(F.col("stratum").isin(UNCERTAIN, HARD))


def answer_entropy(cands: DataFrame, answer: str = "answer") -> DataFrame:
    """(sample_id, entropy): spread of the drawn answers in nats."""
    each = cands.groupBy("sample_id", answer).agg(F.count(F.lit(1)).alias("c"))
    p = F.col("c") / F.sum("c").over(Window.partitionBy("sample_id"))
    return each.withColumn("p", p).groupBy("sample_id").agg((-F.sum(F.col("p") * F.ln("p"))).alias("entropy"))


def verdict_variance(strata: DataFrame) -> DataFrame:
    p = F.col("n_correct") / F.col("k")
    return strata.withColumn("variance", p * (1 - p))


def random_selection(samples: DataFrame, n: int, order: Column, tie: str) -> DataFrame:
    """Baseline: n samples regardless of difficulty."""
    return samples.orderBy(order, tie).limit(n)
