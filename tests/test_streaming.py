import uuid

import pandas as pd
import pytest
from pyspark.sql import functions as F

from prefix_credit.operators import quota, trie
from prefix_credit.sources import workloads
from prefix_credit.sources.tables import load, stream_events
from prefix_credit.streaming import streams
from tests.helpers import packed


@pytest.fixture
def folder(tmp_path):
    return str(tmp_path)


def drain(df, folder, mode="append"):
    name = f"s{uuid.uuid4().hex}"
    streams.start_sink(df, "", f"{folder}/cp-{name}", name, mode).awaitTermination()
    return df.sparkSession.table(name)


def event_files(spark, sf, folder, n=4):
    load(spark, sf, "events").orderBy("ts").coalesce(1).write.option("maxRecordsPerFile", 1000 // n).parquet(f"{folder}/events")
    return f"{folder}/events"


def test_daily_rates_equal_batch(spark, sf, folder):
    path = event_files(spark, sf, folder)
    got = drain(streams.stream_rates(streams.clean_stream(stream_events(spark, path))), folder)
    batch = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    want = streams.stream_rates(batch)
    done = got.agg(F.max("start")).first()[0]
    assert done is not None
    want = want.filter(F.col("start") <= done)
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_sliding_rates_run(spark, sf, folder):
    path = event_files(spark, sf, folder)
    got = drain(streams.stream_rates(streams.clean_stream(stream_events(spark, path)), "7 days", "1 day"), folder)
    assert got.filter("effective > sampled").isEmpty() and got.count() > 0


def test_sessions_equal_batch(spark, sf, folder):
    path = event_files(spark, sf, folder)
    got = drain(streams.stream_sessions(streams.clean_stream(stream_events(spark, path))), folder)
    want = streams.stream_sessions(load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    assert got.exceptAll(want).isEmpty()
    assert got.count() > 0.5 * want.count()


def test_late_and_duplicate_events(spark, folder):
    ts = lambda d: pd.Timestamp("2024-01-01") + pd.Timedelta(days=d)
    one = [(1, ts(0), 1, "view"), (1, ts(0), 1, "view"), (2, ts(0.1), 1, "purchase"), (3, ts(9), 2, "view")]
    two = [(4, ts(0.2), 1, "purchase"), (5, ts(20), 1, "view")]  # 4 is far too late
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    for k, rows in enumerate((one, two)):
        spark.createDataFrame(pd.DataFrame(rows, columns=["event_id", "ts", "user_id", "event_type"]), schema).coalesce(1).write.mode("append").parquet(f"{folder}/in/b={k}")
    src = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in/b=*")
    got = {(r["task"], str(r["start"])[:10]): (r["sampled"], r["effective"]) for r in drain(streams.stream_rates(streams.clean_stream(src)), folder).collect()}
    assert got[(1, "2024-01-01")] == (1, 1)


def test_ema_state_equals_fold_and_survives_restart(spark, sf, folder):
    rates = [(t, pd.Timestamp("2024-01-01") + pd.Timedelta(days=d), ((d * 7 + t * 3) % 10) / 10) for t in range(3) for d in range(8)]
    df = pd.DataFrame(rates, columns=["task", "start", "eta"])
    schema = "task int, start timestamp, eta double"
    name, cp = f"{folder}/out", f"{folder}/cp"
    for half in (df[df.start < "2024-01-05"], df[df.start >= "2024-01-05"]):
        spark.createDataFrame(half, schema).coalesce(1).write.mode("append").parquet(f"{folder}/rates")
        streams.start_sink(streams.stream_ema(spark.readStream.schema(schema).parquet(f"{folder}/rates")), name, cp).awaitTermination()  # second time: a restart
    got = {(r["task"], str(r["start"])): r["eta_ema"] for r in spark.read.parquet(name).collect()}
    fold = quota.ema_rates(spark.createDataFrame(df, schema).select("task", F.col("start").alias("iter"), "eta", F.lit(1).alias("sampled"), F.lit(1).alias("effective")), F.lit(0.5), 0.8)
    want = {(r["task"], str(r["iter"])): r["eta_ema"] for r in fold.collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(v) for k, v in want.items())


def test_trie_stream_equals_batch_and_replays(spark, folder):
    plans = [(1, k, 1 if k % 2 else -1, list("AB") if k % 3 else list("AC")) for k in range(30)]
    keyed = lambda p: trie.with_prefix_keys(packed(spark, p))
    for k in range(3):
        keyed(plans[10 * k : 10 * k + 10]).coalesce(1).write.mode("append").parquet(f"{folder}/steps")
    schema = spark.read.parquet(f"{folder}/steps").schema
    src = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/steps")
    streams.stream_trie(src, f"{folder}/trie", f"{folder}/cp", 0.9).awaitTermination()
    pick = lambda df: sorted((r["node_key"], r["n"], round(r["total"], 9)) for r in df.collect())
    want = pick(trie.node_sums(keyed(plans), 0.9))
    assert pick(streams.latest_trie(spark, f"{folder}/trie")) == want
    files = sorted(spark.read.parquet(f"{folder}/steps").inputFiles())
    assert len(files) == 3
    base = streams.compact_trie(spark, f"{folder}/trie", 1, f"{folder}/base")
    assert pick(streams.latest_trie(spark, f"{folder}/trie", base, 1)) == want
    streams.trie_sink(f"{folder}/trie", 0.9)(keyed(plans[:0]), 3)
    assert pick(streams.latest_trie(spark, f"{folder}/trie")) == want


def test_queue_state(spark, folder):
    rows = [("a", 1, 10, 0, "hard"), ("a", 2, 11, 0, "hard"), ("a", 3, 0, None, "draw"), ("a", 4, 10, 1, "hard"), ("a", 5, 0, None, "draw"), ("a", 6, 0, None, "draw"), ("a", 7, 0, None, "draw"), ("a", 8, 10, 2, "hard"), ("a", 9, 10, 3, "hard"), ("a", 10, 0, None, "draw"), ("a", 11, 0, None, "draw")]
    schema = "task string, seq long, sample_id long, requeue_no int, kind string"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{folder}/q")
    got = sorted((r["seq"], r["sample_id"]) for r in drain(streams.stream_queue(spark.readStream.schema(schema).parquet(f"{folder}/q")), folder).collect())
    assert got == [(3, 10), (5, 11), (6, 10), (10, 10)]  # 10 came back three times, not four


def test_static_and_interval_joins(spark, sf, folder):
    path = event_files(spark, sf, folder)
    th = spark.createDataFrame([("view", 0.1), ("purchase", 0.9)], "event_type string, th double")
    assert drain(streams.stream_with_thresholds(stream_events(spark, path), th, "event_type"), folder).count() == 1000
    ev = stream_events(spark, path).withWatermark("ts", "1 hour")
    plans = ev.filter("event_type = 'purchase'").select(F.col("user_id").alias("traj"), "ts")
    votes = stream_events(spark, path).withColumnRenamed("ts", "v_ts").withWatermark("v_ts", "1 hour").filter("event_type = 'view'").select(F.col("user_id").alias("v_traj"), "v_ts", F.lit(1).alias("vote"))
    got = drain(streams.stream_votes(plans, votes, "12 hours"), folder)
    b = load(spark, sf, "events")
    want = b.filter("event_type = 'purchase'").alias("p").join(b.filter("event_type = 'view'").alias("v"), F.expr("p.user_id = v.user_id and v.ts >= p.ts and v.ts <= p.ts + interval 12 hours")).count()
    assert got.count() == want
