import itertools
import random

import pytest
from pyspark.sql import functions as F

from prefix_credit.functions import actions, measures, rewards
from prefix_credit.operators import joins, objective, policy, rounds
from prefix_credit.session import work_dir
from tests.helpers import packed


def one(spark, *cols):
    return tuple(spark.range(1).select(*(c.alias(f"c{k}") for k, c in enumerate(cols))).first())


def bx(*lohi):
    d = len(lohi) // 2
    return F.struct(F.array(*map(F.lit, map(float, lohi[:d]))).alias("lo"), F.array(*map(F.lit, map(float, lohi[d:]))).alias("hi"))


BOXES = "array<struct<lo:array<double>,hi:array<double>>>"


def test_simple_rewards(spark):
    got = one(spark, rewards.exact_reward(F.lit(" A  b"), F.lit("a b")), rewards.exact_reward(F.lit("A"), F.lit("a"), False), rewards.distance_reward(F.lit(2.0), F.lit(4.0)), rewards.distance_reward(F.lit(4.0), F.lit(2.0)), rewards.distance_reward(F.lit(0.0), F.lit(2.0)), rewards.distance_reward(F.lit(-1.0), F.lit(2.0)), rewards.distance_reward(F.lit(3.0), F.lit(3.0)))
    assert got == (1.0, 0.0, 0.5, 0.5, 0.0, 0.0, 1.0)
    pt = lambda x, y: F.array(F.lit(float(x)), F.lit(float(y)))
    assert one(spark, rewards.point_reward(pt(0, 0), pt(1, 1), pt(4, 4)), rewards.point_reward(pt(0, 0), pt(9, 9), pt(4, 4)), rewards.point_reward(pt(1, 1), pt(1, 1), pt(4, 4))) == (0.75, 0.0, 1.0)
    assert one(spark, rewards.token_jaccard(F.lit("a b c"), F.lit("B c d")), rewards.token_jaccard(F.lit(""), F.lit(" ")), rewards.semantic_reward(F.lit("a b"), F.lit("a b c"), tau=0.6)) == (0.5, 1.0, 1.0)


def test_box_edges(spark):
    unit, none = F.array(bx(0, 0, 1, 1)), F.array().cast(BOXES)
    far, thin = F.array(bx(5, 5, 6, 6)), F.array(bx(0, 0, 0, 1))
    two = F.array(bx(0, 0, 1, 1), bx(0, 0, 1, 0.9))
    got = one(spark, *(rewards.box_reward(p, g) for p, g in ((unit, unit), (unit, far), (thin, unit), (none, unit), (unit, none), (none, none), (two, unit))))
    assert got == pytest.approx((1, 0, 0, 0, 0, 1, 2 / 3))
    cube = F.array(bx(0, 0, 0, 1, 1, 1))
    half = F.array(bx(0, 0, 0, 1, 1, 0.5))
    assert one(spark, rewards.box_reward(cube, half), rewards.box_reward(half, cube, mode="soft")) == pytest.approx((0.5, 0.5))


def test_box_matching_against_brute_force(spark):
    rnd = random.Random(4)
    box = lambda: (lambda x, y: {"lo": [x, y], "hi": [x + rnd.randint(1, 4), y + rnd.randint(1, 4)]})(rnd.randint(0, 5), rnd.randint(0, 5))
    cases = [(k, [box() for _ in range(rnd.randint(0, 4))], [box() for _ in range(rnd.randint(0, 4))]) for k in range(60)]
    cases = [(k, [{a: [float(v) for v in b[a]] for a in b} for b in p], [{a: [float(v) for v in b[a]] for a in b} for b in g]) for k, p, g in cases]
    df = spark.createDataFrame(cases, f"id int, p {BOXES}, g {BOXES}")
    got = {r["id"]: (r["j"], r["s"]) for r in df.select("id", rewards.box_reward(F.col("p"), F.col("g"), 0.3).alias("j"), rewards.box_reward(F.col("p"), F.col("g"), mode="soft").alias("s")).collect()}

    def iou(a, b):
        inter = 1.0
        for k in range(2):
            inter *= max(0, min(a["hi"][k], b["hi"][k]) - max(a["lo"][k], b["lo"][k]))
        area = lambda x: (x["hi"][0] - x["lo"][0]) * (x["hi"][1] - x["lo"][1])
        return inter / (area(a) + area(b) - inter)

    for k, p, g in cases:
        ious, up, ug = [], set(), set()
        for v, i, j in sorted((-iou(a, b), i, j) for (i, a), (j, b) in itertools.product(enumerate(p), enumerate(g))):
            if v < 0 and i not in up and j not in ug:
                ious.append(-v)
                up.add(i)
                ug.add(j)
        n = len(p) + len(g)
        hits = [v for v in ious if v >= 0.3]
        joint = 1.0 if not n else (2 * len(hits) / n * (sum(hits) / len(hits)) if hits else 0.0)
        assert got[k] == pytest.approx((joint, 1.0 if not n else 2 * sum(ious) / n))


def test_votes_and_ties(spark):
    votes = spark.createDataFrame([(1, 1), (1, 1), (1, -1), (2, 1), (2, -1), (2, 1), (2, -1)], "traj long, vote int")
    got = {r["traj"]: (r["r"], r["margin"]) for r in rewards.majority_label(votes, ["traj"]).collect()}
    assert got[1] == (1, pytest.approx(1 / 3)) and got[2] == (-1, 0)


def test_parse_actions(spark):
    syn = {"pick": ["pick up", "grab", "take"], "open": ["pull open"]}
    texts = ["Step 3: Grab the red cup on the table.", "pull open the drawer", "twist the knob in the wall.", "nothing here", None]
    got = [r["a"] for r in spark.createDataFrame([(t,) for t in texts], "t string").select(actions.parse_action(F.col("t"), syn).alias("a")).collect()]
    assert tuple(got[0]) == ("pick", "red cup", "table", True)
    assert tuple(got[1]) == ("open", "drawer", None, True)
    assert tuple(got[2]) == ("twist", "knob", "wall", False)
    assert got[3] is None and got[4] is None
    plans = packed(spark, [(1, 1, 1, [("put", "cup", "shelf"), ("go", "door", None)])]).withColumn("acts", F.transform("steps", lambda s: s["action"]))
    rec = actions.to_plan_record(plans.withColumn("say", F.lit("ok")), "say", "acts").withColumn("back", actions.parse_tagged(F.col("plan"))).first()
    assert rec["plan"].startswith("<reply>ok</reply><plan><act>put|cup|shelf</act>")
    assert [tuple(x) for x in rec["back"]] == [("put", "cup", "shelf"), ("go", "door", None)]


def test_restrict_vocabulary(spark):
    plans = packed(spark, [(1, 1, 1, ["go", "cook", "put"])])
    verbs = lambda df: [s["action"]["action_type"] for s in df.first()["steps"]]
    assert verbs(actions.restrict_vocabulary(plans, allowed={"go", "put"})) == ["go", "put"]
    assert actions.restrict_vocabulary(plans, banned={"cook"}, on_violation="flag").first()["violations"] == 1
    assert verbs(actions.restrict_vocabulary(plans, on_violation="expand", expansion={"cook": ["cut", "heat"]}, banned={"cook"})) == ["go", "cut", "heat", "put"]
    assert actions.limit_steps(plans, 2).isEmpty()


def test_ratio_clip_and_loss(spark):
    a = lambda *x: F.array(*map(F.lit, map(float, x)))
    got = one(spark, objective.step_ratio(a(-1, -2), a(-1, -2)), objective.step_ratio(a(-9, -1), a(-1, -2), F.array(F.lit(0), F.lit(1))), objective.step_ratio(a(-1, -1), a(-2, -2), agg="geo_mean"), objective.sampled_kl(a(-1, -1), a(-1, -1)))
    assert got == pytest.approx((1, 2.718281828, 2.718281828, 0))
    g = lambda rho, adv: objective.clipped_gain(F.lit(rho), F.lit(adv), 0.2)
    assert one(spark, g(1.0, 2.0), g(1.5, 2.0), g(1.5, -2.0), g(0.5, -2.0)) == pytest.approx((2, 2.4, -3, -1.6))
    rows = spark.createDataFrame([(1, 1, 0, 1.0, 1.0, 0.0, 3), (1, 1, 0, 1.0, -1.0, 0.0, 1)], "task long, depth int, parent_key long, rho double, advantage double, kl double, n long")
    assert objective.sibling_loss(rows, 0.2, 0.01).first()["loss"] == pytest.approx(0)
    assert objective.sibling_loss(rows.withColumn("kl", F.lit(1.0)), 0.2, 0.5, "visits").first()["loss"] == pytest.approx(0.25)
    assert objective.trajectory_loss(rows, 0.2, 0.01).first()["loss"] == pytest.approx(0)


def test_policy_sampling_and_update(spark):
    table = spark.createDataFrame([("", "go/∅/∅", 0.5), ("", "end/∅/∅", 0.5), ("go/∅/∅", "end/∅/∅", 1.0)], "history string, action string, p double")
    tasks = spark.range(200).select(F.col("id").alias("task"))
    plans = policy.sample_rollouts(table, tasks, 3, 5, 1, "end/∅/∅")
    lens = {r["n"]: r["c"] for r in plans.groupBy(F.size("actions").alias("n")).agg(F.count(F.lit(1)).alias("c")).collect()}
    assert set(lens) == {1, 2} and 230 < lens[1] < 370
    assert plans.exceptAll(policy.sample_rollouts(table, tasks, 3, 5, 1, "end/∅/∅")).isEmpty()
    adv = spark.createDataFrame([("", "go/∅/∅", 1.0), ("", "end/∅/∅", -1.0)], "history string, action string, advantage double")
    new = {(r["history"], r["action"]): r["p"] for r in policy.update_policy(table, adv, 0.5).collect()}
    assert new[("", "go/∅/∅")] == pytest.approx(2.718281828 ** 0.5 / (2.718281828**0.5 + 2.718281828**-0.5))
    assert new[("go/∅/∅", "end/∅/∅")] == pytest.approx(1)
    answers = policy.sample_answers(table, tasks.select(F.col("task").alias("sample_id"), F.lit("").alias("history")), 8, 1.2, 3)
    assert answers.count() == 1600


def test_rounds_raise_success(spark):
    table = spark.createDataFrame([(h, a, 0.25) for h in ("", "a/∅/∅", "b/∅/∅") for a in ("a/∅/∅", "b/∅/∅", "good/∅/∅", "bad/∅/∅")] + [(h, a, 0.25) for h in ("good/∅/∅", "bad/∅/∅") for a in ("a/∅/∅", "b/∅/∅", "good/∅/∅", "bad/∅/∅")], "history string, action string, p double")
    truth = F.when(F.exists("steps", lambda s: s["text"] == "good/∅/∅") & ~F.exists("steps", lambda s: s["text"] == "bad/∅/∅"), 1).otherwise(-1)
    ledger = rounds.run_rounds(spark, spark.range(80).select(F.col("id").alias("task")), table, truth, work_dir(spark), 4, 20, 15, 4, "good/∅/∅")
    assert ledger[-1]["success"] > ledger[0]["success"] + 0.1
    assert all(r["plans"] == 300 for r in ledger)


def test_measures(spark):
    sheet = spark.createDataFrame([("x", "p", "c1", 10.0), ("x", "q", "c1", 20.0), ("x", "r", "c2", 60.0), ("y", "p", "c1", 5.0), ("y", "q", "c1", 30.0), ("y", "r", "c2", 1.0)], "system string, benchmark string, category string, value double")
    over = {r["system"]: r["value"] for r in measures.overall(sheet).collect()}
    assert over == {"x": 30.0, "y": 12.0}  # over benchmarks, not categories
    cats = {(r["system"], r["category"]): r["value"] for r in measures.category_means(sheet).collect()}
    assert cats[("x", "c1")] == 15.0
    assert {r["benchmark"]: r["gain"] for r in measures.gain(sheet, "x", "y").collect()} == {"p": 5.0, "q": -10.0, "r": 59.0}
    assert {(r["system"], r["benchmark"]): r["place"] for r in measures.podium(sheet).collect()}[("y", "q")] == 1
    runs = spark.createDataFrame([("m", v) for v in (65.0, 66.0, 67.0, 66.0, 68.0)], "system string, value double")
    s = measures.seed_summary(runs).first()
    assert s["mean"] == pytest.approx(66.4) and s["var_sample"] == pytest.approx(s["std_sample"] ** 2)
    curve = spark.createDataFrame([(200, 66.05), (600, 60.0), (1000, 56.83)], "iter int, value double")
    assert measures.curve_drop(curve).first()["drop"] == pytest.approx(9.22)
    assert measures.relative_overhead(58.7, 48.0) == pytest.approx(0.2229, abs=1e-3)
    ledger = []
    measures.timed(ledger, "s", "m", "sampling", lambda: None)
    measures.timed(ledger, "s", "m", "training", lambda: None)
    assert sum(r["share"] for r in measures.phase_share(spark.createDataFrame(ledger, "stage string, method string, phase string, seconds double")).collect()) == pytest.approx(1)


def test_joins(spark):
    left = spark.createDataFrame([(1, "a", 5), (2, "a", 1), (3, "b", 5)], "id int, k string, at int")
    right = spark.createDataFrame([("a", 5, 1.0), ("a", 3, 2.0)], "k string, at int, v double")
    at = lambda strict: {r["id"]: r["v"] for r in joins.as_of(left, right, ["k"], "at", "v", strict).collect()}
    assert at(False) == {1: 1.0, 2: None, 3: None} and at(True) == {1: 2.0, 2: None, 3: None}
    docs = spark.createDataFrame([(1, "x y one two three four five six seven z"), (2, "nothing of it"), (3, None)], "doc_id long, text string")
    items = spark.createDataFrame([(9, "one two three four five six seven"), (8, "two words")], "item_id long, text string")
    assert [tuple(r) for r in joins.leaked(docs, items).collect()] == [(1, 9)]
    few = spark.createDataFrame([(1, "nothing"), (2, "of it"), (3, "six seven z"), (4, "two three four five"), (5, " "), (6, None), (7, "x y one two")], "item_id long, text string")
    assert sorted(tuple(r) for r in joins.leaked(docs, few).collect()) == [(1, 3), (1, 4), (1, 7), (2, 1), (2, 2)]
    assert joins.leaked(docs, few.limit(0)).columns == ["doc_id", "item_id"]
    v = spark.createDataFrame([(k, [float(k % 3 == j) + 0.01 * k for j in range(3)]) for k in range(9)], "id long, v array<double>")
    pairs = joins.similar(v, v, 3, tables=16, bits=4, tau=0.97).filter("left_id < right_id")
    assert not pairs.isEmpty() and pairs.filter("cosine < 0.97").isEmpty()


def test_parallel_vectors_all_pairs_without_shuffled_pairs(spark):
    """Every pair at the threshold, also across the borders of cells, and few candidates."""
    import numpy as np

    rng = np.random.default_rng(2)
    x = rng.normal(size=(600, 16))
    x[300:] = x[:300] * rng.uniform(0.2, 5, (300, 1)) + 0.001 * rng.normal(size=(300, 16))
    v = spark.createDataFrame([(k, [float(c) for c in r]) for k, r in enumerate(x)], "id long, v array<float>")
    full = x.astype(np.float32).astype(float)
    full /= np.linalg.norm(full, axis=1, keepdims=True)
    want = {(int(a), int(b)) for a, b in zip(*np.nonzero(full @ full.T >= 0.999999)) if a <= b}
    rows = joins.parallel(v, 16, 0.999999)
    got = [(r["left_id"], r["right_id"]) for r in rows.collect()]
    assert len(want) > 800 and len(got) == len(set(got)) and set(got) == want
    plan = rows._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan and "Deduplicate" not in plan
