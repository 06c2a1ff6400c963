"""Relations that stand in for the experiments' data, made from the given tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import DEFAULTS, Config
from .tables import load, with_props

# Each judge's multiplier and offset, and the share of +1 votes by order status.
JUDGES = [(7, 13), (11, 29), (17, 41), (23, 53), (31, 67)]
VOTE_SHARE = {"F": 80, "O": 50, "P": 20}
LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity"]


def action(verb: Column, target: Column, receptacle: Column | None = None) -> Column:
    return F.struct(verb.cast("string").alias("action_type"), target.cast("string").alias("target_obj"), (F.lit(None) if receptacle is None else receptacle).cast("string").alias("receptacle_obj"))


def judge_votes(key: Column, status: Column, shift: int = 0) -> list[Column]:
    """One +1/-1 column a judge; `shift` moves the judges' offsets (seeds)."""
    share = F.coalesce(*(F.when(status == s, p) for s, p in VOTE_SHARE.items()))
    return [F.when((key * m + (b + shift)) % 100 < share, 1).otherwise(-1) for m, b in JUDGES]


def majority(votes: list[Column]) -> Column:
    """+1 where the votes' sum is positive, else -1 (ties are -1)."""
    return F.when(sum(votes[1:], votes[0]) > 0, 1).otherwise(-1)


def order_labels(spark: SparkSession, sf_dir: str, shift: int = 0) -> DataFrame:
    """(task, traj, r, margin, o_orderdate, o_orderstatus) of every order by five judges."""
    votes = judge_votes(F.col("o_orderkey"), F.col("o_orderstatus"), shift)
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_orderstatus"])
    return orders.select(F.col("o_custkey").alias("task"), F.col("o_orderkey").alias("traj"), majority(votes).alias("r"), (F.abs(sum(votes[1:], votes[0])) / len(votes)).alias("margin"), "o_orderdate", "o_orderstatus")


def order_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(task, traj, judge, vote): five rows an order."""
    votes = judge_votes(F.col("o_orderkey"), F.col("o_orderstatus"))
    packed = F.array(*(F.struct(F.lit(j + 1).alias("judge"), v.alias("vote")) for j, v in enumerate(votes)))
    return load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderstatus"]).select(F.col("o_custkey").alias("task"), F.col("o_orderkey").alias("traj"), F.inline(packed))


def order_plans(spark: SparkSession, sf_dir: str, conf: Config = DEFAULTS, rich: bool = False, shift: int = 0) -> DataFrame:
    """Orders as plans: lines packed to one array an order before the join, so that one row a trajectory moves on."""
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", *LINE_ORDER, "l_returnflag", "l_linestatus"])
    if rich:
        part = load(spark, sf_dir, "part", ["p_partkey", "p_name", "p_type"])
        places = load(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"]).join(load(spark, sf_dir, "nation", ["n_nationkey", "n_name"]), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")
        lines = lines.join(part, F.col("l_partkey") == F.col("p_partkey")).join(places, F.col("l_suppkey") == F.col("s_suppkey"))
        act = action(F.concat_ws(":", "p_type", "l_linestatus"), F.col("p_name"), F.col("n_name"))
    else:
        act = action(F.col("l_returnflag"), F.col("l_linestatus"))
    step = F.struct(*LINE_ORDER, act.alias("action"), F.concat_ws("/", act["action_type"], act["target_obj"], act["receptacle_obj"]).alias("text"))
    packed = lines.groupBy("l_orderkey").agg(F.sort_array(F.collect_list(step)).alias("lines"))
    packed = packed.select(F.col("l_orderkey").alias("traj"), F.transform("lines", lambda x: F.struct(x["action"].alias("action"), x["text"].alias("text"))).alias("steps"))
    plans = packed.join(order_labels(spark, sf_dir, shift), "traj")
    return take_rollouts(plans, conf.trajectories, ["o_orderdate", "traj"]).select("task", "traj", "r", "steps", "o_orderdate", "o_orderstatus", "margin")


def take_rollouts(plans: DataFrame, k: int, order_cols: list[str]) -> DataFrame:
    """The first k plans of each task."""
    return plans.withColumn("__at", F.row_number().over(Window.partitionBy("task").orderBy(*order_cols))).filter(F.col("__at") <= k).drop("__at")


def session_plans(spark: SparkSession, sf_dir: str, conf: Config = DEFAULTS, rich: bool = False, gap_seconds: int = 43_200) -> DataFrame:
    """Sessions of events as plans: a gap of over twelve hours starts the next one; a plan succeeds when it has a
    purchase and doesn't end in an error."""
    events = with_props(load(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type", "props"]))
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    since = F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(by)
    events = events.withColumn("cut", F.when(since > gap_seconds * 1_000_000, 1).otherwise(0)).withColumn("session", F.sum("cut").over(by))
    act = action(F.col("event_type"), F.floor(F.col("k") / 50)) if rich else action(F.col("event_type"), F.lit(None))
    step = F.struct("ts", "event_id", act.alias("action"), F.col("event_type").alias("text"))
    packed = events.filter(F.col("session") < conf.trajectories).groupBy("user_id", "session").agg(F.sort_array(F.collect_list(step)).alias("e"))
    steps = F.transform("e", lambda x: F.struct(x["action"].alias("action"), x["text"].alias("text")))
    good = F.exists("e", lambda x: x["text"] == "purchase") & (F.element_at("e", -1)["text"] != "error")
    return packed.select(F.col("user_id").alias("task"), F.col("session").alias("traj"), F.when(good, 1).otherwise(-1).alias("r"), steps.alias("steps"))


def dialogue_plans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations as plans: the role and the length band of each turn are the action; it succeeds when the assistant has the last word."""
    turns = load(spark, sf_dir, "conversations")
    step = F.struct("turn", action(F.col("role"), F.floor(F.length("text") / 200)).alias("action"), F.col("text").alias("text"))
    packed = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list(step)).alias("e"))
    steps = F.transform("e", lambda x: F.struct(x["action"].alias("action"), x["text"].alias("text")))
    return packed.select((F.col("conv_id") % 6).alias("task"), F.col("conv_id").alias("traj"), F.when(F.element_at("e", -1)["action"]["action_type"] == "assistant", 1).otherwise(-1).alias("r"), steps.alias("steps"))


def part_answers(spark: SparkSession, sf_dir: str, of: DataFrame | None = None) -> DataFrame:
    """Every recorded answer to "what does this part cost": (sample_id, task, rn from 0, n, answer, truth); only for the
    samples `of` (sample_id) if given."""
    lines = load(spark, sf_dir, "lineitem", ["l_partkey", "l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", "l_quantity"])
    if of is not None:
        lines = lines.join(of.select(F.col("sample_id").alias("l_partkey")), "l_partkey", "left_semi")
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_type", "p_retailprice"])
    by = Window.partitionBy("l_partkey").orderBy("l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", "l_quantity")
    rows = lines.withColumn("rn", F.row_number().over(by) - 1).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("l_partkey")))
    return rows.join(parts, F.col("l_partkey") == F.col("p_partkey")).select(F.col("p_partkey").alias("sample_id"), F.col("p_type").alias("task"), "rn", "n", (F.col("l_extendedprice") / F.col("l_quantity")).alias("answer"), F.col("p_retailprice").alias("truth"))


def nearest_blocks(v: DataFrame, k: int, block: int) -> DataFrame:
    """(vec_id, label, o_id, o_label, dot): the k best other vectors of every row of `v` (vec_id, v, label) in each block.

    Exact for any number of rows: rows are dealt into blocks of about `block`, every block as queries meets every block
    as candidates in a group of its own, and only k rows a query leave a group."""
    v = v.filter("vec_id is not null")
    blocks = max(1, -(-v.count() // block))
    part = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    queries = v.select("*", part.alias("x")).select("*", every.alias("y")).groupBy("x", "y")
    others = v.select("*", part.alias("y")).select("*", every.alias("x")).groupBy("x", "y")
    kind = {f.name: f.dataType.simpleString() for f in v.schema.fields}
    schema = f"vec_id {kind['vec_id']}, label {kind['label']}, o_id {kind['vec_id']}, o_label {kind['label']}, dot double"

    def matrix(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        rows = t["v"].to_pylist()
        lengths = np.array([-1 if r is None else len(r) for r in rows])
        out = np.zeros((len(rows), max(int(lengths.max(initial=0)), 1)))
        for i, r in enumerate(rows):
            if r:
                out[i, : len(r)] = [np.nan if x is None else x for x in r]
        return out, lengths

    def best(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.sort_by("vec_id")
        (q, q_len), (o, o_len) = matrix(left), matrix(right)
        width = max(q.shape[1], o.shape[1])
        q, o = (np.pad(m, ((0, 0), (0, width - m.shape[1]))) for m in (q, o))
        q_id, o_id = left["vec_id"].to_numpy(), right["vec_id"].to_numpy()
        at, to, dots = [np.empty(0, int)], [np.empty(0, int)], [np.empty(0)]
        for i in range(0, len(q), 256):
            dot = np.round(q[i : i + 256] @ o.T, 9)
            dot[np.isnan(dot) | (q_len[i : i + 256, None] != o_len) | (q_len[i : i + 256, None] < 0)] = -np.inf
            order = np.argsort(-dot, axis=1, kind="stable")  # ids ascend, so ties take the smaller one
            for r, row in enumerate(order):
                row = row[: k + 64] if len(row) > k + 64 and (o_id[row[: k + 64]] != q_id[i + r]).sum() >= k else row
                row = row[o_id[row] != q_id[i + r]][:k]
                at.append(np.full(len(row), i + r))
                to.append(row)
                dots.append(dot[r, row])
        at, to = np.concatenate(at), np.concatenate(to)
        return pa.table({"vec_id": left["vec_id"].take(at), "label": left["label"].take(at), "o_id": right["vec_id"].take(to), "o_label": right["label"].take(to), "dot": np.concatenate(dots)})

    return queries.cogroup(others).applyInArrow(best, schema)


def vector_answers(spark: SparkSession, sf_dir: str, k: int = 8, block: int = 4_000) -> DataFrame:
    """The k nearest other vectors of each, by inner product: (sample_id, task, cand_no, correct). Exact, by blocks."""
    v = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")
    by = Window.partitionBy("vec_id").orderBy(F.desc("dot"), "o_id")
    nearest = nearest_blocks(v, k, block).withColumn("cand_no", F.row_number().over(by)).filter(F.col("cand_no") <= k)
    return nearest.select(F.col("vec_id").alias("sample_id"), F.col("label").cast("string").alias("task"), "cand_no", (F.col("label") == F.col("o_label")).alias("correct"))
