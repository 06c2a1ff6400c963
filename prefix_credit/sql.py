"""The engine from SQL: views of the tables and derived relations, scalar functions, table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from .sources import workloads
from .sources.tables import register

# Scalar functions as SQL bodies, inlined by the optimizer.
FUNCTIONS = {
    "reward_exact": "(a STRING, b STRING) RETURNS DOUBLE RETURN CAST(lower(trim(regexp_replace(a, '\\\\s+', ' '))) = lower(trim(regexp_replace(b, '\\\\s+', ' '))) AS DOUBLE)",
    "reward_distance": "(d DOUBLE, g DOUBLE) RETURNS DOUBLE RETURN CASE WHEN d > 0 AND g > 0 THEN least(d / g, g / d) WHEN d IS NOT NULL AND g IS NOT NULL THEN 0D END",
    "reward_point": "(p ARRAY<DOUBLE>, g ARRAY<DOUBLE>, extent ARRAY<DOUBLE>) RETURNS DOUBLE RETURN greatest(0D, 1 - aggregate(zip_with(p, g, (x, y) -> abs(x - y)), 0D, (s, v) -> s + v) / aggregate(extent, 0D, (s, v) -> s + v))",
    "ema_fold": "(series ARRAY<DOUBLE>, init DOUBLE, beta DOUBLE) RETURNS DOUBLE RETURN aggregate(series, init, (s, v) -> CASE WHEN v IS NULL THEN s ELSE beta * s + (1 - beta) * v END)",
}


@F.udtf(returnType="depth int, path string, visits int, q double")
class TrieOf:
    """Nodes of one task's tree from an array of (steps array<string>, r int): a table function for small groups."""

    def eval(self, plans: list, gamma: float):
        nodes: dict[tuple, list[float]] = {}
        for p in plans:
            steps, r = p["steps"], p["r"]
            for t in range(1, len(steps) + 1):
                nodes.setdefault(tuple(steps[:t]), []).append(gamma ** (len(steps) - t) * r)
        for path, returns in sorted(nodes.items()):
            yield len(path), ">".join(path), len(returns), sum(returns) / len(returns)


@F.udtf(returnType="step int, verb string, target string, receptacle string")
class ParsePlan:
    """Actions of a tagged plan text."""

    def eval(self, text: str):
        import re

        for k, (verb, target, receptacle) in enumerate(re.findall(r"<act>([^|<]*)\|([^|<]*)\|([^<]*)</act>", text or "")):
            yield k + 1, verb, target, receptacle or None


@F.pandas_udf(DoubleType())
def overlap_judge(a: pd.Series, b: pd.Series) -> pd.Series:
    """A plugged-in judge: share of common words; stands where a model would be called."""
    words = lambda x: set((x or "").lower().split())
    return pd.Series([len(p & q) / max(1, len(p | q)) for p, q in zip(map(words, a), map(words, b), strict=True)])


def loaded_judge(load):
    """A judge that loads its model once a task: `load()` gives a function from two series to a series."""

    @F.pandas_udf(DoubleType())
    def judge(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        model = load()
        for a, b in parts:
            yield model(a, b)

    return judge


def trie_by_group(plans, gamma: float):
    """Slow reference form: each task's tree in one pandas group (packed plans with text steps)."""

    def one(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        nodes: dict[tuple, list[float]] = {}
        for steps, r in zip(pdf["steps"], pdf["r"], strict=True):
            texts = [s["text"] for s in steps]
            for t in range(1, len(texts) + 1):
                nodes.setdefault(tuple(texts[:t]), []).append(gamma ** (len(texts) - t) * r)
        return pd.DataFrame([(key[0], len(p), ">".join(p), len(v), sum(v) / len(v)) for p, v in nodes.items()], columns=["task", "depth", "path", "n", "q"])

    return plans.groupBy("task").applyInPandas(one, "task long, depth int, path string, n long, q double")


def install(spark: SparkSession, sf_dir: str) -> None:
    """Views, functions and table functions on a session."""
    register(spark, sf_dir)
    workloads.order_plans(spark, sf_dir).createOrReplaceTempView("order_plans")
    workloads.session_plans(spark, sf_dir).createOrReplaceTempView("session_plans")
    workloads.part_answers(spark, sf_dir).createOrReplaceTempView("part_answers")
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("trie_of", TrieOf)
    spark.udtf.register("parse_plan", ParsePlan)
    spark.udf.register("overlap_judge", overlap_judge)


def parse_in_batches(df, text_col: str, parser) -> object:
    """Batches of exotic plan text through a Python parser: `parser(text)` gives (verb, target, receptacle) triples."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            pdf = pdf.assign(actions=[[dict(zip(("action_type", "target_obj", "receptacle_obj"), a, strict=True)) for a in parser(t or "")] for t in pdf[text_col]])
            yield pdf

    return df.mapInPandas(run, ", ".join(f"`{c}` {t}" for c, t in df.dtypes) + ", actions array<struct<action_type:string,target_obj:string,receptacle_obj:string>>")


def policy_meets_judge(steps, verdicts):
    """Cogrouped exchange between the policy's side (task, traj, n_steps) and the judges' (task, traj, vote): mean vote and
    mean length of each task."""

    def one(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"task": [key[0]], "plans": [left["traj"].nunique()], "mean_steps": [float(left["n_steps"].mean()) if len(left) else None], "mean_vote": [float(right["vote"].mean()) if len(right) else None]})

    return steps.groupBy("task").cogroup(verdicts.groupBy("task")).applyInPandas(one, "task long, plans long, mean_steps double, mean_vote double")


@F.pandas_udf(DoubleType())
def mean_reward(v: pd.Series) -> float:
    """A custom reward summary as a grouped aggregate: the mean without the best and the worst."""
    return float(v.sort_values().iloc[1:-1].mean() if len(v) > 2 else v.mean())
