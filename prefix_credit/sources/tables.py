"""Sources and sinks: declared-schema loads, rollout logs in, rounds and triplets out, streams, SQL views."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import TABLES


def load(spark: SparkSession, sf_dir: str, name: str, cols: Sequence[str] | None = None) -> DataFrame:
    """A given table by its declared schema; only `cols` are read from the files."""
    df = spark.read.schema(TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_rollouts(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Rollout logs from json, csv (with a header) or text (one plan a line, column `value`)."""
    if fmt == "text":
        return spark.read.text(path)
    return spark.read.schema(schema).option("header", "true").format(fmt).load(path)


def with_props(events: DataFrame) -> DataFrame:
    """events with `k` from the json properties; malformed json gives null."""
    return events.withColumn("k", F.from_json("props", "k int")["k"])


def write_round(df: DataFrame, path: str, round_no: int) -> str:
    """Write one round to its own folder, replacing an unfinished try; returns the folder."""
    at = f"{path}/round={round_no}"
    df.write.mode("overwrite").parquet(at)
    return at


def export_triplets(rows: DataFrame, path: str, per_file: int = 1_000_000) -> None:
    """Training triplets as JSON lines."""
    rows.write.mode("overwrite").option("maxRecordsPerFile", per_file).json(path)


def write_pool(pool: DataFrame, path: str, files: int) -> None:
    """The pool laid out by (task, fresh_pos) ranges, so that a draw prunes files and row groups."""
    pool.repartitionByRange(files, "task", "fresh_pos").sortWithinPartitions("task", "fresh_pos").write.mode("overwrite").parquet(path)


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet events as a stream, with `ts` as a time-zoned timestamp for watermarks."""
    return spark.readStream.schema(TABLES["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def register(spark: SparkSession, sf_dir: str) -> None:
    """All given tables as temporary views."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
