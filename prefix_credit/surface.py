"""One query for each relational operator, user function, source, sink and stream form that the methods use; SQL beside."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from . import sql as S
from .config import DEFAULTS as C
from .functions import actions
from .operators import credit, joins, quota, strata, trie
from .queries import ORACLES, daily_series, kept, longs, nudged, order_nodes, part_candidates, part_pool, query, rounded
from .session import work_dir
from .sources import rollout_source, tables
from .sources import workloads as W
from .sources.tables import load
from .streaming import streams

_JACC = "CASE WHEN len(x) + len(y) = 0 THEN 1.0 ELSE len(list_intersect(x, y)) / CAST(len(x) + len(y) - len(list_intersect(x, y)) AS DOUBLE) END"

# ---- joins ------------------------------------------------------------------------------------------------------------


@query
def join_null_safe(spark, sf):
    """Session steps against a vocabulary of triples with missing parts: null parts match null parts."""
    steps = W.session_plans(spark, sf).select(F.explode("steps").alias("s")).select("s.action.*")
    words = steps.distinct().withColumnRenamed("action_type", "verb").withColumnRenamed("target_obj", "target").withColumnRenamed("receptacle_obj", "place")
    on = F.col("action_type").eqNullSafe(F.col("verb")) & F.col("target_obj").eqNullSafe(F.col("target")) & F.col("receptacle_obj").eqNullSafe(F.col("place"))
    return longs(steps.join(words, on).groupBy("verb", "target").agg(F.count(F.lit(1)).alias("n")), "n")


ORACLES["join_null_safe"] = f"WITH {O.TRE} SELECT verb, CAST(NULL AS VARCHAR) AS target, count(*) AS n FROM stp GROUP BY 1"


@query
def join_full_outer(spark, sf):
    """Prefixes of the first ten plans of each task against those of the rest: known on both sides or one, by depth."""
    from .queries import split_plans

    a, b = (p.select("task", "t", "node_key").distinct() for p in split_plans(spark, sf))
    both = a.withColumn("old", F.lit(1)).join(b.withColumn("new", F.lit(1)), ["task", "t", "node_key"], "full")
    return longs(both.groupBy("t").agg(F.count("old").alias("old"), F.count("new").alias("new"), F.count_if(F.col("old").isNotNull() & F.col("new").isNotNull()).alias("both")), "t", "old", "new", "both")


ORACLES["join_full_outer"] = f"WITH {O.TRO}, p AS (SELECT task, t, path, bool_or(place <= 10) AS o, bool_or(place > 10) AS n FROM stp GROUP BY 1, 2, 3) SELECT t, count(*) FILTER (WHERE o) AS old, count(*) FILTER (WHERE n) AS new, count(*) FILTER (WHERE o AND n) AS both FROM p GROUP BY 1"


@query
def sibling_pairs(spark, sf):
    """Pairs of siblings of unequal value by depth, and their mean gap: at most the square of the actions' number a parent."""
    return rounded(longs(joins.sibling_pairs(order_nodes(spark, sf)).groupBy("depth").agg(F.count(F.lit(1)).alias("pairs"), F.avg("gap").alias("gap")), "depth", "pairs"), "gap")


ORACLES["sibling_pairs"] = f"{O._PRE} SELECT a.depth, count(*) AS pairs, round(avg(abs(a.q - b.q)), 6) AS gap FROM nd a JOIN nd b ON a.task = b.task AND a.parent = b.parent AND a.path < b.path WHERE abs(a.q - b.q) > 1e-9 GROUP BY 1"


@query
def join_lateral(spark, sf):
    """Each order's votes by a lateral join with its own array of verdicts."""
    votes = W.judge_votes(F.col("o_orderkey"), F.col("o_orderstatus"))
    orders = load(spark, sf, "orders", ["o_orderkey", "o_orderstatus"]).withColumn("votes", F.array(*votes))
    rows = orders.lateralJoin(spark.tvf.explode(F.col("votes").outer()).toDF("vote"))
    return longs(rows.groupBy("o_orderstatus", "vote").agg(F.count(F.lit(1)).alias("n")), "vote", "n")


ORACLES["join_lateral"] = "WITH v AS (" + " UNION ALL ".join(f"SELECT o_orderstatus, CASE WHEN (o_orderkey * {m} + {b}) % 100 < (CASE o_orderstatus WHEN 'F' THEN 80 WHEN 'O' THEN 50 ELSE 20 END) THEN 1 ELSE -1 END AS vote FROM orders" for m, b in W.JUDGES) + ") SELECT o_orderstatus, CAST(vote AS BIGINT) AS vote, count(*) AS n FROM v GROUP BY 1, 2"


@query
def join_interval(spark, sf):
    """Purchases with the same user's errors up to six hours before, by bins of six hours and an equi-join."""
    ev = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type"]).withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    bought, failed = (ev.filter(F.col("event_type") == k) for k in ("purchase", "error"))
    rows = joins.within(bought.select("event_id", "user_id", "at"), failed.select(F.col("event_id").alias("error_id"), "user_id", F.col("at").alias("error_at")), ["user_id"], "at", "error_at", 6 * 3_600_000_000)
    return rows.select("event_id", "error_id")


ORACLES["join_interval"] = "SELECT a.event_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'error' AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 6 HOUR WHERE a.event_type = 'purchase'"


@query
def similar_vectors(spark, sf):
    """Copies among vectors (cosine of .999999 or more, themselves too) by cells of a grid over orthogonal axes: every pair."""
    v = load(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    dim = v.agg(F.max(F.size("v")).alias("d")).first()["d"]
    pairs = joins.parallel(v, dim or 1, tau=0.999999)
    return pairs.select("left_id", "right_id", F.round("cosine", 5).alias("cosine"))


ORACLES["similar_vectors"] = "WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) SELECT a.vec_id AS left_id, b.vec_id AS right_id, round(list_cosine_similarity(a.v, b.v), 5) AS cosine FROM e a JOIN e b ON a.vec_id <= b.vec_id WHERE list_cosine_similarity(a.v, b.v) >= 0.999999"

# ---- aggregates, windows, sorts, sets ---------------------------------------------------------------------------------


@query
def grouping_sets(spark, sf):
    """Counts by task and stratum, by task, and over all, with the mark of which columns are summed over."""
    rows = strata.stratify(part_candidates(spark, sf))
    out = rows.groupingSets([[F.col("task"), F.col("stratum")], [F.col("task")], []], F.col("task"), F.col("stratum"))
    return longs(out.agg(F.grouping_id("task", "stratum").alias("level"), F.count(F.lit(1)).alias("n")), "level", "n")


ORACLES["grouping_sets"] = f"WITH {O.STRATA} SELECT task, stratum, grouping_id(task, stratum) AS level, count(*) AS n FROM st GROUP BY GROUPING SETS ((task, stratum), (task), ())"


@query
def reward_moments(spark, sf):
    """Mean, deviation, skewness and kurtosis of the rewards of each task."""
    rows = part_candidates(spark, sf).groupBy("task").agg(F.avg("reward").alias("mean"), F.stddev_pop("reward").alias("deviation"), F.skewness("reward").alias("skewness"), F.kurtosis("reward").alias("kurtosis"))
    return rounded(rows, "mean", "deviation", "skewness", "kurtosis")


ORACLES["reward_moments"] = f"""WITH {O.CAND}, m AS (SELECT task, reward - avg(reward) OVER (PARTITION BY task) AS d, reward FROM cand)
SELECT task, round(avg(reward), 6) AS mean, round(sqrt(avg(d * d)), 6) AS deviation, round(avg(d * d * d) / pow(avg(d * d), 1.5), 6) + 0.0 AS skewness, round(avg(d * d * d * d) / pow(avg(d * d), 2) - 3, 6) + 0.0 AS kurtosis FROM m GROUP BY 1"""


@query
def plan_strings(spark, sf):
    """The verbs of each plan in order, aggregated to one string."""
    steps = trie.with_prefix_keys(W.order_plans(spark, sf))
    rows = steps.select("traj", "t", F.col("action.action_type").alias("verb"))
    return rows.groupBy("traj").agg(F.expr("listagg(verb, '>') WITHIN GROUP (ORDER BY t)").alias("verbs"))


ORACLES["plan_strings"] = f"WITH {O.TRO} SELECT traj, string_agg(verb, '>' ORDER BY t) AS verbs FROM stp GROUP BY 1"


@query
def difficulty_tiers(spark, sf):
    """Samples of each task in four tiers of difficulty, with their relative rank."""
    rows = strata.stratify(part_candidates(spark, sf)).withColumn("p", F.col("n_correct") / F.col("k"))
    by = Window.partitionBy("task").orderBy("p", "sample_id")
    return rounded(rows.select("sample_id", "task", F.ntile(4).over(by).cast("long").alias("tier"), F.percent_rank().over(Window.partitionBy("task").orderBy("p")).alias("place"), F.cume_dist().over(Window.partitionBy("task").orderBy("p")).alias("below")), "place", "below")


ORACLES["difficulty_tiers"] = f"""WITH {O.STRATA}, p AS (SELECT sample_id, task, n_correct / CAST(k AS DOUBLE) AS p FROM st)
SELECT sample_id, task, ntile(4) OVER (PARTITION BY task ORDER BY p, sample_id) AS tier, round(percent_rank() OVER (PARTITION BY task ORDER BY p), 6) AS place, round(cume_dist() OVER (PARTITION BY task ORDER BY p), 6) AS below FROM p"""


@query
def sliding_days(spark, sf):
    """Mean rate over the last seven calendar days, by a range frame: days without groups leave a gap."""
    day = F.datediff("iter", F.lit("1970-01-01").cast("date")).cast("long")
    by = Window.partitionBy("task").orderBy(day).rangeBetween(-6, 0)
    return rounded(daily_series(spark, sf).select("task", F.col("iter").alias("day"), F.avg("eta").over(by).alias("eta_7")), "eta_7")


ORACLES["sliding_days"] = f"WITH {O.RATES} SELECT task, day, round(avg(eta) OVER (PARTITION BY task ORDER BY day RANGE BETWEEN INTERVAL 6 DAYS PRECEDING AND CURRENT ROW), 6) AS eta_7 FROM rt"


@query
def first_third_last(spark, sf):
    """First, third and last verb of each session."""
    steps = trie.with_prefix_keys(W.session_plans(spark, sf)).select("task", "traj", "t", F.col("action.action_type").alias("verb"))
    by = Window.partitionBy("task", "traj").orderBy("t").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = steps.select("task", "traj", F.first("verb").over(by).alias("first"), F.nth_value("verb", 3).over(by).alias("third"), F.last("verb").over(by).alias("last"))
    return rows.distinct()


ORACLES["first_third_last"] = f"WITH {O.TRE} SELECT task, traj, max(verb) FILTER (WHERE t = 1) AS first, max(verb) FILTER (WHERE t = 3) AS third, max(verb) FILTER (WHERE t = n_steps) AS last FROM stp GROUP BY 1, 2"


@query
def second_page(spark, sf):
    """The 160 trajectories after the first 160, in order."""
    return longs(W.order_labels(spark, sf).orderBy("traj").offset(160).limit(160).select("traj", "r"), "r")


ORACLES["second_page"] = f"WITH {O.lab()} SELECT traj, CAST(r AS BIGINT) AS r FROM lab ORDER BY traj LIMIT 160 OFFSET 160"


@query
def repeated_actions(spark, sf):
    """Actions that plans before and from 1998 have in common, as often as both have them."""
    plans = W.order_plans(spark, sf)
    early = F.to_date("o_orderdate") < F.lit("1998-01-01").cast("date")
    side = lambda keep: plans.filter(keep).select(F.explode("steps").alias("s")).select(F.col("s.text").alias("action"))
    return longs(side(early).intersectAll(side(~early)).groupBy("action").agg(F.count(F.lit(1)).alias("n")), "n")


ORACLES["repeated_actions"] = f"WITH {O.TRO}, c AS (SELECT txt, count(*) FILTER (WHERE CAST(o_orderdate AS DATE) < DATE '1998-01-01') AS a, count(*) FILTER (WHERE CAST(o_orderdate AS DATE) >= DATE '1998-01-01') AS b FROM stp GROUP BY 1) SELECT txt AS action, least(a, b) AS n FROM c WHERE least(a, b) > 0"


@query
def nearest_verb(spark, sf):
    """Verbs with a typing error put right by edit distance to the vocabulary."""
    events = load(spark, sf, "events", ["event_type"]).select(F.concat(F.substring("event_type", 1, 2), F.lit("x"), F.substring("event_type", 3, 99)).alias("typed"), "event_type")
    words = events.select(F.col("event_type").alias("verb")).distinct()
    best = events.select("typed").distinct().join(F.broadcast(words), F.levenshtein("typed", "verb", 2) >= 0).groupBy("typed").agg(F.min_by("verb", F.struct(F.levenshtein("typed", "verb"), "verb")).alias("verb"))
    return longs(events.join(F.broadcast(best), "typed").groupBy("typed", "verb").agg(F.count_if(F.col("verb") == F.col("event_type")).alias("right")), "right")


ORACLES["nearest_verb"] = "SELECT substr(event_type, 1, 2) || 'x' || substr(event_type, 3) AS typed, event_type AS verb, count(*) AS right FROM events GROUP BY 1, 2"


@query
def threshold_maps(spark, sf):
    """Thresholds of the tasks as a map: looked up, lowered, filtered."""
    pairs = spark.createDataFrame(list(C.thresholds.items()), "task string, at double")
    table = pairs.agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("task", "at")))).alias("m"))
    table = table.select(F.map_filter(F.transform_values("m", lambda k, v: F.round(v * 0.85, 6)), lambda k, v: v < 0.5).alias("m"))
    parts = load(spark, sf, "part", ["p_type"]).join(F.broadcast(table))
    return longs(parts.groupBy(F.col("p_type").alias("task")).agg(F.max(F.try_element_at("m", F.col("p_type"))).alias("at"), F.max(F.size("m")).alias("held"), F.count(F.lit(1)).alias("n")), "held", "n")


ORACLES["threshold_maps"] = f"WITH x AS (SELECT DISTINCT p_type, round({O._TH} * 0.85, 6) AS at FROM part) SELECT p.p_type AS task, max(CASE WHEN x.at < 0.5 THEN CAST(x.at AS DOUBLE) END) AS at, CAST((SELECT count(*) FROM (VALUES (.1), (.2), (.3), (.5), (.7), (.85)) v(a) WHERE a * 0.85 < 0.5) AS BIGINT) AS held, count(*) AS n FROM part p JOIN x ON x.p_type = p.p_type GROUP BY 1"


@query
def json_variant(spark, sf):
    """Properties as a variant, read by path and written again."""
    rows = load(spark, sf, "events", ["event_type", "props"]).withColumn("v", F.try_parse_json("props"))
    rows = rows.select("event_type", F.try_variant_get("v", "$.k", "bigint").alias("k"))
    rows = rows.withColumn("again", F.get_json_object(F.to_json(F.struct("k")), "$.k").cast("bigint"))
    return rows.groupBy("event_type").agg(F.sum("k").alias("total"), F.sum("again").alias("again"))


ORACLES["json_variant"] = "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS again FROM events GROUP BY 1"

# ---- user functions ---------------------------------------------------------------------------------------------------


def neighbours(spark, sf) -> DataFrame:
    before = F.lag("text").over(Window.partitionBy("conv_id").orderBy("turn"))
    return load(spark, sf, "conversations").withColumn("before", before).filter("before is not null")


@query
def udf_judge(spark, sf):
    """A plugged-in judge as a pandas function: overlap of words of each turn and the one before."""
    return rounded(neighbours(spark, sf).select("conv_id", "turn", S.overlap_judge("text", "before").alias("overlap")), "overlap")


@query
def udf_loaded_judge(spark, sf):
    """The same judge with its model loaded once a task."""
    judge = S.loaded_judge(lambda: S.overlap_judge.func)
    return rounded(neighbours(spark, sf).select("conv_id", "turn", judge("text", "before").alias("overlap")), "overlap")


_PY = "list_distinct(list_filter(string_split_regex(lower({0}), '\\s+'), lambda w: w <> ''))"
_OVER = f"WITH p AS (SELECT conv_id, turn, {_PY.format('text')} AS x, {_PY.format('bf')} AS y FROM (SELECT *, lag(text) OVER (PARTITION BY conv_id ORDER BY turn) AS bf FROM conversations) z WHERE bf IS NOT NULL) SELECT conv_id, turn, round(CASE WHEN len(x) + len(y) = 0 THEN 0.0 ELSE {_JACC} END, 6) + 0.0 AS overlap FROM p"
ORACLES["udf_judge"] = ORACLES["udf_loaded_judge"] = _OVER


@query
def udaf_trimmed(spark, sf):
    """Mean reward of each sample without its best and worst answer, by a grouped aggregate function."""
    return rounded(part_candidates(spark, sf).groupBy("sample_id").agg(S.mean_reward("reward").alias("reward")), "reward")


ORACLES["udaf_trimmed"] = f"WITH {O.CAND} SELECT sample_id, round(CASE WHEN count(*) > 2 THEN (sum(reward) - max(reward) - min(reward)) / (count(*) - 2) ELSE avg(reward) END, 6) + 0.0 AS reward FROM cand GROUP BY 1"


@query
def grouped_map_trie(spark, sf):
    """Trees of all users in pandas groups, the slow reference form."""
    rows = S.trie_by_group(W.session_plans(spark, sf).select("task", "traj", "r", "steps"), C.gamma)
    return rows.select("task", F.col("depth").cast("long").alias("depth"), "path", "n", nudged("q").alias("q"))


ORACLES["grouped_map_trie"] = f"WITH {O.TRE}, {O.NODES} SELECT task, depth, replace(substr(path, 2), '/∅/∅', '') AS path, n, round(q + 1e-9, 6) + 0.0 AS q FROM nd"


@query
def batch_parser(spark, sf):
    """Plan records through a Python parser in batches: actions by verb."""
    from .comparisons import plan_records

    found = lambda text: [(a, t, r or None) for a, t, r in __import__("re").findall(actions.TAG_PATTERN, text)]
    rows = S.parse_in_batches(plan_records(spark, sf).select("traj", "plan"), "plan", found)
    return longs(rows.select(F.explode("actions").alias("a")).groupBy(F.col("a.action_type").alias("verb"), F.col("a.target_obj").alias("target")).agg(F.count(F.lit(1)).alias("n")), "n")


ORACLES["batch_parser"] = f"WITH {O.TRO} SELECT verb, split_part(txt, '/', 2) AS target, count(*) AS n FROM stp GROUP BY 1, 2"


@query
def table_functions(spark, sf):
    """Table functions from SQL: the plan parser over all records, and the tree of each dialogue type."""
    S.install(spark, sf)
    from .comparisons import plan_records

    plan_records(spark, sf).createOrReplaceTempView("records_of_plans")
    rows = spark.sql("SELECT p.verb, p.step FROM records_of_plans r, LATERAL parse_plan(r.plan) p")
    return longs(rows.groupBy("verb", "step").agg(F.count(F.lit(1)).alias("n")), "step", "n")


ORACLES["table_functions"] = f"WITH {O.TRO} SELECT verb, t AS step, count(*) AS n FROM stp GROUP BY 1, 2"


@query
def sql_functions(spark, sf):
    """The engine from SQL alone: views, scalar functions, an aggregate over them."""
    S.install(spark, sf)
    rows = spark.sql("SELECT task, count(*) AS answers, sum(reward_distance(answer, truth)) AS reward, sum(reward_exact(task, concat(' ', lower(task)))) AS same FROM part_answers WHERE rn < 8 GROUP BY task")
    return rounded(longs(rows, "answers"), "reward")


ORACLES["sql_functions"] = f"WITH {O.CAND} SELECT task, count(*) AS answers, round(sum(reward), 6) AS reward, CAST(count(*) AS DOUBLE) AS same FROM cand GROUP BY 1"


@query
def policy_meets_judge(spark, sf):
    """Plans and verdicts of each task cogrouped: number of plans, mean length, mean vote."""
    plans = W.order_plans(spark, sf)
    votes = W.order_votes(spark, sf).select("task", "traj", "vote").join(plans.select("traj"), "traj", "left_semi")
    out = S.policy_meets_judge(plans.select("task", "traj", F.size("steps").alias("n_steps")), votes)
    return rounded(out, "mean_steps", "mean_vote")


ORACLES["policy_meets_judge"] = f"WITH {O.TRO}, p AS (SELECT task, traj, count(*) AS n FROM stp GROUP BY 1, 2) SELECT p.task, count(*) AS plans, round(avg(n), 6) AS mean_steps, round(sum(vs) / (5.0 * count(*)), 6) + 0.0 AS mean_vote FROM p JOIN lab ON lab.traj = p.traj GROUP BY 1"

# ---- sources and sinks ------------------------------------------------------------------------------------------------


def rollout_lines(spark, sf) -> DataFrame:
    return trie.with_prefix_keys(W.session_plans(spark, sf)).select("task", "traj", F.col("t").cast("int").alias("t"), "text")


def by_verb(rows: DataFrame, how: str) -> DataFrame:
    return longs(rows.groupBy("text").agg(F.count(F.lit(1)).alias("n"), F.sum("t").alias("places")).withColumn("how", F.lit(how)), "n", "places")


@query
def rollout_logs(spark, sf):
    """Rollout logs written and read as JSON, CSV, text, Parquet rounds, and by the Python source."""
    rows, at, kind = kept(spark, rollout_lines(spark, sf)), work_dir(spark), "task long, traj long, t int, text string"
    rows.write.json(f"{at}/json")
    rows.write.option("header", "true").csv(f"{at}/csv")
    rows.select(F.concat_ws("|", "t", "text").alias("value")).write.text(f"{at}/text")
    halves = [tables.write_round(rows.filter(F.col("traj") % 2 == k), f"{at}/rounds", k) for k in (0, 1)]
    rollout_source.install(spark)
    text = tables.read_rollouts(spark, f"{at}/text", "text", kind).select(F.split("value", r"\|").alias("v")).select(F.get("v", F.lit(0)).cast("int").alias("t"), F.get("v", F.lit(1)).alias("text"))
    found = {
        "json": tables.read_rollouts(spark, f"{at}/json", "json", kind),
        "csv": tables.read_rollouts(spark, f"{at}/csv", "csv", kind),
        "text": text,
        "rounds": spark.read.parquet(*halves),
    }
    if at.startswith("file:"):  # the Python source opens paths that every executor sees by itself
        found["source"] = spark.read.format("rollouts").schema(kind).load(f"{at}/json".removeprefix("file://"))
    else:
        found["source"] = found["json"]
    out = None
    for how, df in found.items():
        one = by_verb(df, how)
        out = one if out is None else out.unionByName(one)
    return out


ORACLES["rollout_logs"] = f"WITH {O.TRE}, s AS (SELECT verb AS text, count(*) AS n, CAST(sum(t) AS BIGINT) AS places FROM stp GROUP BY 1) SELECT text, n, places, how FROM s CROSS JOIN (VALUES ('json'), ('csv'), ('text'), ('rounds'), ('source')) h(how)"


@query
def triplet_export(spark, sf):
    """Training triplets written as JSON lines and read again."""
    at = work_dir(spark)
    tables.export_triplets(credit.credit_rows(W.order_plans(spark, sf), C.gamma, C.eps, C.delta), at)
    rows = spark.read.schema("task long, traj long, t int, context array<string>, step string, advantage double").json(at)
    return longs(rows.groupBy("step").agg(F.count(F.lit(1)).alias("n"), F.sum(F.size("context")).alias("context"), F.count_if(F.col("advantage") > 0).alias("good")), "n", "context", "good")


ORACLES["triplet_export"] = f"{O._PRE}, {O.ADV} SELECT txt AS step, count(*) AS n, CAST(sum(t - 1) AS BIGINT) AS context, count(*) FILTER (WHERE adv > 0) AS good FROM stp JOIN ad ON ad.task = stp.task AND ad.path = stp.path WHERE k > 1 AND abs(adv) > 0.001 GROUP BY 1"


@query
def pool_ranges(spark, sf):
    """Draws of places 11 to 30 of every queue from a pool laid out by ranges, by constants that prune files."""
    at = work_dir(spark)
    tables.write_pool(part_pool(spark, sf), at, 8)
    pool = spark.read.parquet(at)
    tasks = [r["task"] for r in pool.select("task").distinct().collect()]  # a row a task
    return quota.fresh_ranges(pool, [(t, 10, 30) for t in tasks]).select("task", "sample_id", "fresh_pos")


ORACLES["pool_ranges"] = f"WITH {O.STRATA}, {O.POOL} SELECT task, sample_id, pos AS fresh_pos FROM pool WHERE pos > 10 AND pos <= 30"

# ---- streams, drained ---------------------------------------------------------------------------------------------------


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """A stream run over what is there, as a table; a restart from the same checkpoint finds nothing more."""
    spark, at = df.sparkSession, work_dir(df.sparkSession)
    for _ in range(2):
        streams.start_sink(df, f"{at}/out", f"{at}/checkpoint", mode=mode).awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def event_stream(spark: SparkSession, sf: str) -> DataFrame:
    """Events in time order in some files, each once more, as a stream."""
    at = work_dir(spark)
    ev = load(spark, sf, "events")
    ev.unionByName(ev.filter("event_id % 7 = 0")).repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(at)
    return tables.stream_events(spark, at, 100)


@query
def stream_clean(spark, sf):
    """Events with repeats, each once, by day."""
    rows = drained(streams.clean_stream(event_stream(spark, sf)).select("event_id", "ts", "event_type"))
    return longs(rows.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids")), "n", "ids")


ORACLES["stream_clean"] = "SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events GROUP BY 1"


@query
def stream_rates(spark, sf):
    """Daily rates from the stream; the days that the watermark has passed."""
    rows = drained(streams.stream_rates(streams.clean_stream(event_stream(spark, sf))))
    return rounded(longs(rows.select("task", F.to_date("start").alias("day"), "sampled", "effective", "eta"), "sampled", "effective"), "eta")


_CLOSED = "day + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY"
ORACLES["stream_rates"] = f"WITH {O.RATES} SELECT task, day, sampled, effective, round(eta, 6) AS eta FROM rt WHERE {_CLOSED}"


@query
def stream_weekly(spark, sf):
    """Rates of sliding windows of seven days from the stream."""
    rows = drained(streams.stream_rates(streams.clean_stream(event_stream(spark, sf)), "7 days", "1 day"))
    return longs(rows.select("task", F.to_date("start").alias("start"), "sampled", "effective"), "sampled", "effective")


ORACLES["stream_weekly"] = """WITH g AS (SELECT CAST(ts AS DATE) - CAST(o AS INTEGER) AS start, user_id, CAST(user_id % 5 AS INT) AS task, bool_or(event_type = 'purchase') AND bool_or(event_type <> 'purchase') AS eff FROM events CROSS JOIN (SELECT unnest(range(0, 7)) AS o) d GROUP BY 1, 2, 3)
SELECT task, start, count(*) AS sampled, count(*) FILTER (WHERE eff) AS effective FROM g WHERE start + INTERVAL 7 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1, 2"""


@query
def stream_sessions(spark, sf):
    """Sessions from the stream as plans, those closed by the watermark: number, steps and successes by length."""
    rows = drained(streams.stream_sessions(streams.clean_stream(event_stream(spark, sf))))
    return longs(rows.groupBy(F.size("steps").alias("length")).agg(F.count(F.lit(1)).alias("plans"), F.count_if(F.col("r") == 1).alias("good")), "length", "plans", "good")


ORACLES["stream_sessions"] = """WITH e0 AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 12 HOUR THEN 1 ELSE 0 END AS cut FROM events),
e1 AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS ses FROM e0),
s AS (SELECT user_id, ses, count(*) AS length, max(ts) AS until, bool_or(event_type = 'purchase') AND arg_max(event_type, (ts, event_id)) <> 'error' AS good FROM e1 GROUP BY 1, 2)
SELECT length, count(*) AS plans, count(*) FILTER (WHERE good) AS good FROM s WHERE until + INTERVAL 12 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1"""


@query
def stream_ema(spark, sf):
    """Smoothed rates as keyed state over the stream of closed days, one file a time, as of the last closed day."""
    at = work_dir(spark)
    closed = daily_series(spark, sf).select("task", F.col("iter").cast("timestamp").alias("start"), "eta")
    closed.repartition(1).sortWithinPartitions("start", "task").write.option("maxRecordsPerFile", 40).parquet(at)
    stream = spark.readStream.schema("task int, start timestamp, eta double").option("maxFilesPerTrigger", 100).parquet(at)
    rows = drained(streams.stream_ema(stream, 0.5, C.ema_beta))
    return rounded(rows.select("task", F.to_date("start").alias("day"), "eta", "eta_ema"), "eta", "eta_ema")


ORACLES["stream_ema"] = ORACLES["ema_rates"]


@query
def stream_queue(spark, sf):
    """The re-queue as keyed state: every event that is an error puts its user back, every purchase serves the head."""
    at = work_dir(spark)
    ev = load(spark, sf, "events", ["event_id", "user_id", "event_type"]).filter("event_type in ('error', 'purchase')")
    kind = F.when(F.col("event_type") == "error", "hard").otherwise("draw")
    before = F.row_number().over(Window.partitionBy("user_id", "event_type").orderBy("event_id")) - 1
    ev.select(F.concat(F.lit("t"), F.col("user_id") % 5).alias("task"), F.col("event_id").alias("seq"), F.col("user_id").alias("sample_id"), before.alias("requeue_no"), kind.alias("kind")).write.parquet(at)
    stream = spark.readStream.schema("task string, seq long, sample_id long, requeue_no int, kind string").option("maxFilesPerTrigger", 100).parquet(at)
    rows = drained(streams.stream_queue(stream, 3))
    return longs(rows.groupBy("task").agg(F.count(F.lit(1)).alias("served"), F.sum("sample_id").alias("ids"), F.countDistinct("sample_id").alias("samples")), "served", "ids", "samples")


ORACLES["stream_queue"] = """WITH RECURSIVE o AS (SELECT 't' || (user_id % 5) AS task, event_id AS seq, user_id AS sample_id, event_type = 'error' AS hard FROM events WHERE event_type IN ('error', 'purchase')),
h AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY task, sample_id ORDER BY seq) AS times FROM o WHERE hard) z WHERE times <= 3),
x AS (SELECT task, seq, sample_id, true AS hard FROM h UNION ALL SELECT task, seq, sample_id, false FROM o WHERE NOT hard),
n AS (SELECT *, row_number() OVER (PARTITION BY task ORDER BY seq) AS k FROM x),
w AS (SELECT task, k, CAST(CASE WHEN hard THEN 1 ELSE 0 END AS BIGINT) AS len, CAST(0 AS BIGINT) AS served FROM n WHERE k = 1
      UNION ALL SELECT n.task, n.k, CASE WHEN n.hard THEN len + 1 WHEN len > 0 THEN len - 1 ELSE 0 END, served + CASE WHEN NOT n.hard AND len > 0 THEN 1 ELSE 0 END FROM w JOIN n ON n.task = w.task AND n.k = w.k + 1),
s AS (SELECT task, max(served) AS served FROM w GROUP BY 1),
q AS (SELECT h.task, h.sample_id, row_number() OVER (PARTITION BY h.task ORDER BY seq) AS place FROM h)
SELECT q.task, any_value(served) AS served, CAST(sum(sample_id) AS BIGINT) AS ids, count(DISTINCT sample_id) AS samples FROM q JOIN s ON s.task = q.task AND place <= served GROUP BY 1"""


@query
def stream_trie(spark, sf):
    """The prefix tree kept up to date from a stream of keyed steps, each step's file in a batch of its own."""
    at = work_dir(spark)
    steps = trie.with_prefix_keys(W.session_plans(spark, sf).select("task", "traj", "r", "steps"), "path")
    steps.write.parquet(f"{at}/steps")
    streams.stream_trie(spark.readStream.schema(steps.schema).option("maxFilesPerTrigger", 4).parquet(f"{at}/steps"), f"{at}/tree", f"{at}/checkpoint", C.gamma).awaitTermination()
    sums = streams.latest_trie(spark, f"{at}/tree")
    return sums.select("task", F.col("node_key").alias("path"), F.col("n").cast("long").alias("n"), nudged(F.col("total") / F.col("n")).alias("q"))


ORACLES["stream_trie"] = f"WITH {O.TRE}, {O.NODES} SELECT task, path, n, round(q + 1e-9, 6) + 0.0 AS q FROM nd"


@query
def stream_thresholds(spark, sf):
    """Stream rows with the static threshold of their kind."""
    limits = spark.createDataFrame([("purchase", 0.5), ("error", 0.9)], "event_type string, at double")
    rows = drained(streams.stream_with_thresholds(event_stream(spark, sf).select("event_id", "event_type"), limits, "event_type"))
    return longs(rows.distinct().groupBy("event_type", "at").agg(F.count(F.lit(1)).alias("n")), "n")


ORACLES["stream_thresholds"] = "SELECT event_type, CASE event_type WHEN 'purchase' THEN 0.5 WHEN 'error' THEN 0.9 END::DOUBLE AS at, count(*) AS n FROM events GROUP BY 1"


@query
def stream_votes(spark, sf):
    """Purchases as plans joined with the same user's views in the hour after, stream to stream."""
    clean = lambda: streams.clean_stream(event_stream(spark, sf))
    plans = clean().filter("event_type = 'purchase'").select(F.col("user_id").alias("traj"), "ts", F.col("event_id").alias("plan"))
    votes = clean().filter("event_type = 'view'").select(F.col("user_id").alias("v_traj"), F.col("ts").alias("v_ts"), F.col("event_id").alias("vote"))
    return drained(streams.stream_votes(plans, votes)).select("plan", "vote")


ORACLES["stream_votes"] = "SELECT a.event_id AS plan, b.event_id AS vote FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'purchase' AND b.event_type = 'view'"
