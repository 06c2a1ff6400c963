"""Session settings for the engine, and folders for rounds."""

from __future__ import annotations

import uuid

from pyspark.sql import SparkSession

# Settings that the plans rely on; all can be set on a running session.
RUNTIME = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
}


def session(master: str = "local[*]", partitions: int = 8) -> SparkSession:
    """A session for local use; on a cluster use the one that is there."""
    b = SparkSession.builder.master(master).config("spark.sql.shuffle.partitions", str(partitions)).config("spark.ui.enabled", "false")
    for k, v in RUNTIME.items():
        b = b.config(k, v)
    return b.getOrCreate()


def work_dir(spark: SparkSession) -> str:
    """A new folder under the cluster's shared checkpoint folder; a local one only under a local master that names none."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"file:///tmp/prefix_credit_rounds/{sc.applicationId}"
    return f"{base}/rounds/{uuid.uuid4().hex}"
