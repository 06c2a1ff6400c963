import random

import pytest
from pyspark.sql import functions as F

from prefix_credit.functions.measures import explain_cost
from prefix_credit.operators import credit, trie
from prefix_credit.sources import workloads
from tests.helpers import ACTION, brute, packed

FIVE = [(1, 1, 1, list("ABC")), (1, 2, -1, list("ABD")), (1, 3, -1, list("AE")), (1, 4, 1, list("F")), (1, 5, 1, list("ABC"))]
EPS = 1e-6


def advantages(spark, plans, gamma=0.9, **how):
    rows = credit.credit_steps(packed(spark, plans), gamma, EPS, 0.001, **how).select("task", "traj", "t", "advantage").collect()
    return {(r["task"], r["traj"], r["t"]): r["advantage"] for r in rows}


def test_worked_example(spark):
    nodes = credit.sibling_advantage(trie.node_values(trie.with_prefix_keys(packed(spark, FIVE), "path"), 0.9, keep_returns=True), EPS)
    got = {r["node_key"].replace("/∅/∅", ""): r for r in nodes.collect()}
    for path, n, q, a in ((">A", 4, -0.0225, -0.999998), (">F", 1, 1.0, 0.999998), (">A>B", 3, 0.3, 0.999999), (">A>E", 1, -1.0, -0.999999), (">A>B>C", 2, 1.0, 1.0), (">A>B>D", 1, -1.0, -1.0)):
        assert got[path]["n"] == n == len(got[path]["returns"])
        assert got[path]["q"] == pytest.approx(q, abs=1e-6)
        assert got[path]["advantage"] == pytest.approx(a, abs=2e-6)
    shape = trie.trie_shape(nodes).first()
    assert (shape["branching"], shape["leaves"], shape["group_size"]) == (3, 4, 2.0)
    whole = {r["traj"]: r["advantage"] for r in credit.trajectory_advantage(packed(spark, FIVE), EPS).collect()}
    assert whole[1] == pytest.approx(0.816497, abs=1e-5) and whole[2] == pytest.approx(-1.224745, abs=1e-5)


def test_credit_protects_and_contrasts(spark):
    adv = advantages(spark, FIVE)
    assert adv[(1, 2, 2)] > 0.99  # right step of a failed plan
    assert adv[(1, 1, 1)] < -0.99  # a sibling start was better
    triplets = {(r["traj"], r["t"]): r for r in credit.credit_rows(packed(spark, FIVE), 0.9, EPS, 0.001).collect()}
    assert triplets[(2, 3)]["context"] == ["A", "B"] and triplets[(2, 3)]["step"] == "D"


def random_plans(seed, tasks=6, plans=15):
    rnd = random.Random(seed)
    return [(t, 100 * t + k, rnd.choice((1, -1)), [rnd.choice("ABC") for _ in range(rnd.randint(1, 6))]) for t in range(tasks) for k in range(plans)]


@pytest.mark.parametrize("how", [{}, {"form": "join"}, {"form": "salted"}, {"keying": "path"}, {"keying": "level"}, {"form": "join", "keying": "level"}, {"by_text": True}])
def test_forms_and_keyings_agree_with_brute_force(spark, how):
    plans = random_plans(3)
    want = {}
    full = brute(plans, 0.9, EPS)
    for task, traj, _, steps in plans:
        for t in range(1, len(steps) + 1):
            q, n, k, a = full[(task, tuple(steps[:t]))]
            if k > 1 and abs(a) > 0.001:
                want[(task, traj, t)] = a
    got = advantages(spark, plans, **how)
    assert got.keys() == want.keys()
    assert all(got[k] == pytest.approx(v, abs=1e-9) for k, v in want.items())


ODD = [("put", "a/b", "c"), ("put", "a", "b/c"), ("put", "a/b/c", None), ("put", None, "a"), (None, "put", "a"), ("put", "a", None), ("put", "∅", "a"), ("put", "a\\\\", "/"), ("put", "a>x", "∅"), ("x>put", "a", ""), ("put", "", "a")]


@pytest.mark.parametrize("how", [{}, {"form": "join"}, {"form": "salted"}, {"keying": "path"}, {"keying": "level"}, {"form": "join", "keying": "level"}, {"form": "salted", "keying": "path"}])
def test_signs_inside_actions_do_not_merge_prefixes(spark, how):
    rnd = random.Random(11)
    plans = [(1, 1, 1, [ODD[0]]), (1, 2, -1, [ODD[1]]), (1, 3, -1, ["z"])]
    plans += [(2 + k % 3, 10 + k, rnd.choice((1, -1)), [rnd.choice(ODD) for _ in range(rnd.randint(1, 4))]) for k in range(90)]
    full = brute([(t, k, r, [s if isinstance(s, tuple) else (s, None, None) for s in steps]) for t, k, r, steps in plans], 0.9, EPS)
    want = {}
    for task, traj, _, steps in plans:
        steps = [s if isinstance(s, tuple) else (s, None, None) for s in steps]
        for t in range(1, len(steps) + 1):
            _, _, k, a = full[(task, tuple(steps[:t]))]
            if k > 1 and abs(a) > 0.001:
                want[(task, traj, t)] = a
    got = advantages(spark, plans, **how)
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(v, abs=1e-9) for k, v in want.items())


def test_action_text_is_undone(spark):
    rows = spark.createDataFrame([(dict(zip(("action_type", "target_obj", "receptacle_obj"), a)),) for a in ODD], f"a {ACTION}")
    texts = rows.select(trie.action_text(F.col("a")).alias("t"), "a").withColumn("back", trie.text_action(F.col("t"))).collect()
    assert len({r["t"] for r in texts}) == len(ODD) and all(r["a"] == r["back"] for r in texts)


def test_sums_bounds_visits_and_leaves(spark):
    nodes = credit.sibling_advantage(trie.node_values(trie.with_prefix_keys(packed(spark, random_plans(5)), "path"), 0.95), EPS).collect()
    groups = {}
    for r in nodes:
        assert abs(r["q"]) <= 1
        groups.setdefault((r["task"], r["parent_key"]), []).append(r)
    for rows in groups.values():
        k = len(rows)
        assert sum(r["advantage"] for r in rows) == pytest.approx(0, abs=1e-6)
        assert sum(r["advantage"] ** 2 for r in rows) <= k + 1e-9
        assert all(abs(r["advantage"]) <= max(0, k - 1) ** 0.5 + 1e-9 for r in rows)
    for task in {r["task"] for r in nodes}:
        mine = [v for (t, _), v in groups.items() if t == task]
        leaves = sum(1 for r in nodes if r["task"] == task and (task, r["node_key"]) not in groups)
        assert sum(len(v) - 1 for v in mine) == leaves - 1
    at = {(r["task"], r["node_key"]): r["n"] for r in nodes}
    for (task, parent), rows in groups.items():
        if parent:
            assert at[(task, parent)] >= sum(r["n"] for r in rows)


def test_flip_duplicate_and_depth_one(spark):
    plans = random_plans(7)
    base = advantages(spark, plans)
    flipped = advantages(spark, [(t, k, -r, s) for t, k, r, s in plans])
    assert all(flipped[k] == pytest.approx(-v, abs=1e-9) for k, v in base.items())
    twice = advantages(spark, plans + [(t, k + 50, r, s) for t, k, r, s in plans])
    assert all(twice[k] == pytest.approx(v, abs=1e-9) for k, v in base.items())
    short = [(1, k, r, [v]) for k, (v, r) in enumerate(zip("ABCD", (1, -1, 1, 1)))]
    whole = {r["traj"]: r["advantage"] for r in credit.trajectory_advantage(packed(spark, short), EPS).collect()}
    for (_, traj, _), a in advantages(spark, short, gamma=1.0).items():
        assert a == pytest.approx(whole[traj], abs=1e-9)


def test_edges(spark):
    assert advantages(spark, [(1, 1, 1, list("AB"))]) == {}
    assert advantages(spark, [(1, k, 1, list("AB")) for k in range(4)]) == {}
    assert advantages(spark, [(1, 1, 1, []), (1, 2, -1, [])]) == {}
    assert advantages(spark, [(1, 1, 1, ["A"]), (1, 2, 1, ["B"])]) == {}  # siblings of equal value
    same = [(1, 1, 1, [("put", "cup", None), "X"]), (1, 2, -1, [("put", "cup", None), "Y"])]
    assert set(advantages(spark, same)) == {(1, 1, 2), (1, 2, 2)}  # null equals null in a prefix
    ends_inside = [(1, 1, 1, ["A"]), (1, 2, -1, ["A", "B"])]
    n = {r["node_key"]: r["n"] for r in trie.node_values(trie.with_prefix_keys(packed(spark, ends_inside), "path"), 0.9).collect()}
    assert sorted(n.values()) == [1, 2]


def test_variants(spark):
    nodes = trie.node_values(trie.with_prefix_keys(packed(spark, FIVE), "path"), 0.9)
    visits = {r["node_key"]: r for r in credit.sibling_advantage(nodes, EPS, weighting="visits").collect()}
    root = [r for r in visits.values() if r["depth"] == 1]
    assert root[0]["mu"] == pytest.approx((4 * -0.0225 + 1) / 5)
    flat = credit.sibling_advantage(nodes, EPS, scale=False).filter("depth = 3").collect()
    assert sorted(r["advantage"] for r in flat) == pytest.approx([-1.0, 1.0])


def test_merge_equals_batch(spark):
    plans = random_plans(9)
    keyed = lambda p: trie.node_sums(trie.with_prefix_keys(packed(spark, p)), 0.9)
    merged = trie.merge_trie(keyed(plans[:40]), keyed(plans[40:])).select("task", "node_key", "n", F.round("total", 9).alias("total"))
    whole = keyed(plans).select("task", "node_key", "n", F.round("total", 9).alias("total"))
    assert merged.exceptAll(whole).isEmpty() and whole.exceptAll(merged).isEmpty()


def test_contrast_counts(spark, sf):
    rows = {r["r"]: r for r in credit.contrast(workloads.order_plans(spark, sf).select("task", "traj", "r", "steps"), 0.95, EPS, 0.001).collect()}
    assert (rows[-1]["positive"], rows[-1]["steps"], rows[1]["negative"], rows[1]["steps"]) == (291, 1296, 288, 1309)


def test_flagship_plan_has_three_hash_exchanges(spark, sf):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        cost = explain_cost(credit.credit_rows(workloads.order_plans(spark, sf), 0.95, EPS, 0.001))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    assert cost["exchanges"] == 3 and cost["python"] == 0, cost


def test_partition_count_does_not_matter(spark, sf):
    want = None
    for n in ("4", "64"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        got = sorted((r["task"], r["traj"], r["t"], round(r["advantage"], 6)) for r in credit.credit_rows(workloads.order_plans(spark, sf), 0.95, EPS, 0.001).collect())
        want = want or got
        assert got == want
    spark.conf.set("spark.sql.shuffle.partitions", "8")


def test_hot_task_takes_the_salted_form(spark):
    plans = [(99, k, 1 if k % 3 else -1, ["A" if k % 2 else "B", "C" if k % 5 else "D"]) for k in range(3000)] + random_plans(1)
    df = packed(spark, plans)
    assert credit.choose_form(df, hot_plans=1000) == "salted" and credit.choose_form(df) == "window"
    a, b = advantages(spark, plans, form="salted"), advantages(spark, plans)
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k], abs=1e-9) for k in a)


@pytest.mark.parametrize("how", [{"form": "join", "keying": "path"}, {"form": "salted"}, {"form": "window", "keying": "level"}])
def test_node_tables_are_not_broadcast(spark, how):
    """They grow with the plans, and a shuffle's compressed bytes do not show what they take on the driver."""
    rows = credit.credit_steps(packed(spark, FIVE), 0.9, EPS, 0.001, **how)
    rows.collect()
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and "SortMergeJoin" in plan
