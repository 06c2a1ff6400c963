"""One object with the engine's methods and their defaults."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .config import DEFAULTS, Config
from .functions import rewards
from .operators import credit, objective, quota, rounds, strata, trie
from .session import work_dir


class Engine:
    def __init__(self, spark: SparkSession, sf_dir: str | None = None, conf: Config = DEFAULTS) -> None:
        self.spark, self.sf_dir, self.conf = spark, sf_dir, conf

    def strata(self, answers: DataFrame, order_cols: list[str], reward: Column, thresholds: dict[str, float] | float | None = None) -> DataFrame:
        """Recorded answers (sample_id, task, …) to strata: draw, score, threshold, classify."""
        cands = strata.draw_candidates(answers, self.conf.candidates, order_cols)
        cands = cands.withColumn("correct", rewards.correct_if(reward, F.col("task"), self.conf.thresholds if thresholds is None else thresholds))
        return strata.stratify(cands)

    def tuning_set(self, rows: DataFrame, seed: int = 0, **how) -> DataFrame:
        return strata.select_for_tuning(rows, self.conf.easy_share, strata.seeded_order(F.col("sample_id"), seed), **how)

    def iterate(self, pool: DataFrame, rollout_fn: Callable[[DataFrame, int], DataFrame], subset_size: int, n_rounds: int, path: str | None = None, **how) -> tuple[DataFrame, list[dict]]:
        c = self.conf
        return quota.run_iterations(self.spark, pool, rollout_fn, path or work_dir(self.spark), subset_size, n_rounds, c.ema_beta, c.rate_floor, c.r_max, c.probe, **how)

    def credit(self, plans: DataFrame, form: str = "auto") -> DataFrame:
        """Triplets from packed labelled plans."""
        c = self.conf
        form = credit.choose_form(plans) if form == "auto" else form
        return credit.credit_rows(plans, c.gamma, c.eps, c.delta, form)

    def trie_shape(self, plans: DataFrame) -> DataFrame:
        return trie.trie_shape(trie.node_values(trie.with_prefix_keys(plans), self.conf.gamma))

    def compare(self, plans: DataFrame) -> DataFrame:
        c = self.conf
        return credit.contrast(plans, c.gamma, c.eps, c.delta)

    def loss(self, rows: DataFrame, norm: str = "children") -> DataFrame:
        return objective.sibling_loss(rows, self.conf.clip, self.conf.kl_weight, norm)

    def co_train(self, tasks: DataFrame, start: DataFrame, truth: Column, n_rounds: int, stop: str, path: str | None = None) -> list[dict]:
        c = self.conf
        return rounds.run_rounds(self.spark, tasks, start, truth, path or work_dir(self.spark), n_rounds, c.tasks_per_round, c.trajectories, c.max_steps, stop, c.judges, c.judge_trajectories, c.gamma, c.eps, c.delta, kl_weight=c.kl_weight, clip=c.clip)
