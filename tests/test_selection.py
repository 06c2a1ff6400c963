import numpy as np
import pytest
from pyspark.sql import functions as F

from prefix_credit.config import DEFAULTS as C
from prefix_credit.operators import baselines, quota, strata
from prefix_credit.queries import part_candidates, part_outcomes, part_pool, quota_history
from prefix_credit.sources import workloads

SF01 = "/root/testdata/sf0.01"


def cands(spark, rows):
    return spark.createDataFrame([(s, t, c) for s, t, c in rows], "sample_id long, task string, correct boolean")


def test_strata_rules(spark):
    rows = [(1, "a", True), (1, "a", True), (2, "a", True), (2, "a", False), (3, "a", False), (4, "b", True), (5, "b", None), (6, "b", True), (6, "b", None)]
    got = {r["sample_id"]: (r["k"], r["n_correct"], r["stratum"]) for r in strata.stratify(cands(spark, rows)).collect()}
    assert got == {1: (2, 2, "easy"), 2: (2, 1, "uncertain"), 3: (1, 0, "hard"), 4: (1, 1, "easy"), 5: (0, 0, None), 6: (1, 1, "easy")}


def test_strata_partition_and_move_one_way(spark):
    at = lambda k: {r["sample_id"]: r["stratum"] for r in strata.stratify(part_candidates(spark, SF01, 0).filter(F.col("rn") < k)).collect()}
    few, many = at(4), at(8)
    rank = {"hard": 0, "uncertain": 1, "easy": 2}
    assert len(many) == 2000
    for s in few:
        if many[s] == "easy":
            assert few[s] == "easy"
        if many[s] == "hard":
            assert few[s] == "hard"
    harder = {r["sample_id"]: r["stratum"] for r in strata.stratify(part_candidates(spark, SF01).withColumn("correct", F.col("reward") >= 0.9)).collect()}
    looser = {r["sample_id"]: r["stratum"] for r in strata.stratify(part_candidates(spark, SF01).withColumn("correct", F.col("reward") >= 0.5)).collect()}
    assert all(rank[harder[s]] <= rank[looser[s]] for s in harder)


def test_expected_shares_by_type(spark):
    got = {(r["task"], r["stratum"]): r["n"] for r in strata.stratify(part_candidates(spark, SF01)).groupBy("task", "stratum").agg(F.count(F.lit(1)).alias("n")).collect()}
    want = {"SMALL": (109, 213, 0), "ECONOMY": (27, 284, 0), "STANDARD": (8, 335, 0), "MEDIUM": (0, 338, 15), "LARGE": (0, 273, 67), "PROMO": (0, 144, 187)}
    for task, counts in want.items():
        assert tuple(got.get((task, s), 0) for s in ("easy", "uncertain", "hard")) == counts


def test_tuning_set_variants(spark):
    rows = spark.createDataFrame([(k, "a", 8, 8, "easy") for k in range(11)] + [(k, "a", 8, 3, "uncertain") for k in range(20, 30)] + [(40, "a", 8, 0, "hard")], "sample_id long, task string, k long, n_correct long, stratum string")
    order = F.col("sample_id")
    n = lambda **how: {r["stratum"]: r["n"] for r in strata.select_for_tuning(rows, 0.2, order, **how).groupBy("stratum").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert n() == {"easy": 3, "uncertain": 10}
    assert n(easy_base="uncertain") == {"easy": 2, "uncertain": 10}
    assert n(keep=("uncertain",)) == {"uncertain": 10}
    assert n(keep=("easy",)) == {"easy": 3}
    assert n(keep=("uncertain", "easy", "hard")) == {"easy": 3, "uncertain": 10, "hard": 1}
    assert strata.rl_pool(rows).count() == 11


def test_ema_and_quota_example(spark):
    rates = spark.createDataFrame([("t", i, 10, 1, e) for i, e in enumerate((0.25, 0.5, 1.0))], "task string, iter int, sampled long, effective long, eta double")
    out = quota.ema_rates(rates, F.lit(0.5), 0.8).withColumn("q", quota.next_quota(F.col("eta_ema"), 800.0, 4, C.rate_floor)).orderBy("iter").collect()
    assert [round(r["eta_ema"], 6) for r in out] == [0.45, 0.46, 0.568]
    assert [r["q"] for r in out] == [445, 435, 353]
    raw = quota.ema_rates(rates, F.lit(0.5), 0.0).orderBy("iter").collect()
    assert [r["eta_ema"] for r in raw] == [0.25, 0.5, 1.0]
    frozen = quota.ema_rates(rates, F.lit(0.5), 1.0).collect()
    assert {r["eta_ema"] for r in frozen} == {0.5}
    gap = rates.withColumn("eta", F.when(F.col("iter") == 1, None).otherwise(F.col("eta")))
    assert [round(r["eta_ema"], 6) for r in quota.ema_rates(gap, F.lit(0.5), 0.8).orderBy("iter").collect()] == [0.45, 0.45, 0.56]


def test_effective_rules(spark):
    rows = spark.createDataFrame([(1, 0.0, False), (1, 0.0, False), (2, 1.0, True), (2, 1.0, True), (3, 0.2, False), (3, 0.9, True), (4, 0.5, True), (4, 0.5 + 1e-12, True)], "sample_id long, reward double, correct boolean")
    got = {r["sample_id"]: (r["effective"], r["hard"], r["easy"]) for r in quota.outcomes(rows, ["sample_id"]).collect()}
    assert got == {1: (False, True, False), 2: (False, False, True), 3: (True, False, False), 4: (False, False, True)}


def test_four_rounds_as_expected(spark):
    want = {
        1: {"ECONOMY": (100, 100, 0, 83), "LARGE": (115, 115, 0, 97), "MEDIUM": (107, 107, 0, 107), "PROMO": (247, 247, 0, 190), "SMALL": (100, 100, 0, 61), "STANDARD": (100, 100, 0, 96)},
        2: {"ECONOMY": (104, 104, 0, 83), "LARGE": (116, 116, 0, 111), "MEDIUM": (106, 106, 0, 105), "PROMO": (209, 84, 57, 128), "SMALL": (109, 109, 0, 60), "STANDARD": (101, 101, 0, 98)},
        3: {"ECONOMY": (108, 80, 0, 59), "LARGE": (113, 109, 4, 113), "MEDIUM": (105, 105, 0, 104), "PROMO": (178, 0, 13, 13), "SMALL": (118, 4, 0, 2), "STANDARD": (102, 102, 0, 92)},
        4: {"ECONOMY": (112, 0, 0, 0), "LARGE": (111, 0, 19, 19), "MEDIUM": (104, 35, 1, 36), "PROMO": (154, 0, 0, 0), "SMALL": (129, 0, 0, 0), "STANDARD": (104, 32, 0, 24)},
    }
    history, report = quota_history(spark, SF01, 4, subset=600)
    for r in report:
        assert (r["quota"], r["fresh"], r["requeued"], r["effective"]) == want[r["iter"]][r["task"]], r
    draws = history.groupBy("sample_id").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("iter").alias("i"))
    assert draws.filter("n > 4 or n <> i").isEmpty()  # at most 1 + r_max draws, never twice in a round
    status = quota.sample_status(history)
    assert status.count() == history.select("sample_id").distinct().count()


def test_requeue_order_and_limit(spark):
    kinds = "task string, sample_id long, requeue_no int, enq_round int, enq_seq long"
    waiting = spark.createDataFrame([("a", 7, 3, 1, 1), ("a", 8, 1, 1, 2), ("a", 9, 1, 1, 3)], kinds)
    drawn = spark.createDataFrame([("a", 1, 0, "fresh", 5, True), ("a", 2, 0, "fresh", 4, True), ("a", 3, 0, "fresh", 6, False), ("a", 7, 3, "requeued", 1, True), ("a", 8, 1, "requeued", 2, True)], "task string, sample_id long, requeue_no int, source string, at long, hard boolean")
    out = quota.requeue_hard(waiting, drawn, 3, 2).orderBy("enq_round", "enq_seq").collect()
    assert [(r["sample_id"], r["requeue_no"]) for r in out] == [(9, 1), (2, 1), (1, 1), (8, 2)]


def test_draw_prefers_fresh(spark):
    pool = quota.enqueue(spark.createDataFrame([("a", k) for k in range(5)], "task string, sample_id long"), ["sample_id"])
    waiting = spark.createDataFrame([("a", 90, 1, 1, 2), ("a", 91, 1, 1, 1)], "task string, sample_id long, requeue_no int, enq_round int, enq_seq long")
    got = quota.draw(pool, waiting, [("a", 3, 5, 1)]).collect()
    assert sorted((r["source"], r["sample_id"]) for r in got) == [("fresh", 3), ("fresh", 4), ("requeued", 91)]


def test_discard_baseline_counts(spark):
    rows = part_pool(spark, SF01).join(part_outcomes(spark, SF01, 1), ["sample_id", "task"])
    for parts in (1, 64):
        out = baselines.discard_sampling(rows, strata.modular_order(F.col("sample_id")), 600, parts=parts)
        got = {r["task"]: r["n"] for r in out.groupBy("task").agg(F.count_if("effective").alias("n")).collect()}
        assert out.count() == 700
        assert got == {"MEDIUM": 123, "STANDARD": 116, "LARGE": 115, "ECONOMY": 103, "PROMO": 93, "SMALL": 50}


def test_ablations_run(spark):
    for how in ({"requeue": False}, {"refresh": False}, {"signal": "hard_only"}):
        _, report = quota_history(spark, "/root/testdata/sf0.001", 2, **how)
        assert len(report) == 12
        if how.get("requeue") is False:
            assert all(r["requeued"] == 0 for r in report)


def test_batches_are_even(spark):
    rows = spark.createDataFrame([(f"t{k % 3}", "u" if k % 2 else "h", k) for k in range(384)], "task string, tier string, sample_id long")
    out = quota.assemble_batches(rows, 64).groupBy("batch", "task").agg(F.count(F.lit(1)).alias("n")).collect()
    assert len(out) == 18 and all(20 <= r["n"] <= 22 for r in out)


def test_entropy(spark):
    rows = spark.createDataFrame([(1, "a"), (1, "a"), (2, "a"), (2, "b")], "sample_id long, answer string")
    got = {r["sample_id"]: r["entropy"] for r in strata.answer_entropy(rows).collect()}
    assert got[1] == pytest.approx(0) and got[2] == pytest.approx(0.693147, abs=1e-6)


def test_largest_remainder_adds_up(spark):
    rates = spark.createDataFrame([("a", 0.9), ("b", 0.3), ("c", 0.0), ("d", 0.5)], "task string, eta_ema double")
    got = {r["task"]: r["quota"] for r in quota.largest_remainder(rates, 800, 1 / 64).collect()}
    assert sum(got.values()) == 800 and got["c"] > got["b"] > got["d"] > got["a"]


def test_prefix_counts(spark):
    from prefix_credit.functions import measures

    nodes = spark.range(5000).select((F.col("id") % 5).alias("task"), F.lit(1).alias("depth"), (F.col("id") % 2000).alias("node_key"))
    exact = {r["task"]: r["prefixes"] for r in measures.prefix_counts(nodes, ["task"]).collect()}
    assert set(exact.values()) == {400}
    for how in ("approximate", "sketch"):
        assert all(abs(r["prefixes"] - 400) < 20 for r in measures.prefix_counts(nodes, ["task"], how).collect())


def test_vector_answers_of_more_rows_than_a_block(spark, tmp_path):
    rng = np.random.default_rng(4)
    m = rng.normal(size=(5_200, 8)).astype(np.float32).astype(float)
    m[17], m[4_000] = m[3], m[3]
    label = rng.integers(0, 3, len(m))
    rows = [(k, [float(x) for x in v], int(c)) for k, (v, c) in enumerate(zip(m, label, strict=True))]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    dot = np.round(m @ m.T, 9)
    np.fill_diagonal(dot, -np.inf)
    want = np.argsort(-dot, axis=1, kind="stable")[:, :8]
    for block in (700, 10_000):
        got = workloads.vector_answers(spark, str(tmp_path), 8, block).toPandas().sort_values(["sample_id", "cand_no"])
        assert len(got) == 8 * len(m) and (got.cand_no.to_numpy().reshape(-1, 8) == np.arange(1, 9)).all()
        assert (got.correct.to_numpy().reshape(-1, 8) == (label[want] == label[:, None])).all()


def test_draws_push_their_ranges_to_the_pool(spark, tmp_path):
    from prefix_credit.sources.tables import write_pool

    pool = quota.enqueue(spark.range(400).select(F.concat(F.lit("t"), F.col("id") % 4).alias("task"), F.col("id").alias("sample_id")), ["sample_id"])
    write_pool(pool, f"{tmp_path}/pool", 8)
    got = quota.fresh_ranges(spark.read.parquet(f"{tmp_path}/pool"), [("t1", 0, 5), ("t2", 90, 95), ("t3", 7, 7)])
    plan = got._jdf.queryExecution().executedPlan().toString()
    pushed = plan.split("PushedFilters")[1]  # cut short in the plan's text
    assert "LessThanOrEqual(fresh_pos,95)" in pushed and "Or(And(" in pushed and "t1" in plan and "t3" not in plan
    assert sorted(r["fresh_pos"] for r in got.collect()) == [1, 2, 3, 4, 5, 91, 92, 93, 94, 95]
    many = quota.fresh_ranges(spark.read.parquet(f"{tmp_path}/pool"), [("t1", 0, 5), ("t2", 90, 95)], literal_tasks=1)
    assert many.count() == 10 and many.columns == got.columns
