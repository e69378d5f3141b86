"""Shared scratch space and table reading.

Intermediate tables go to the folder that the session names in ``spark.checkpoint.dir``.  Where that is
unset, a local session (tests, a laptop) makes a temporary folder and names it as checkpoint folder; a
cluster, whose executors could not share such a folder, gets an error.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if known:
        return known.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    root = "file://" + tempfile.mkdtemp(prefix="outline-engine-")
    spark.sparkContext.setCheckpointDir(root)
    return root


def scratch(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that no other run uses."""
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut, and a lost executor costs a re-read."""
    path = scratch(df.sparkSession, name)
    writer = df.write.partitionBy(*partition_by) if partition_by else df.write
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, name: str, key: str, parts: int) -> DataFrame:
    """As ``materialise``, but dealt by ``key`` into files of ``parts`` buckets, which are grouped later without an exchange.

    Each task writes what it has; the catalog knows the table until the frame is made, and its files stay.
    """
    spark = df.sparkSession
    entry = f"{name}_{uuid.uuid4().hex}".replace("-", "_")
    df.write.format("parquet").bucketBy(parts, key).option("path", scratch(spark, name)).saveAsTable(entry)
    stored = spark.table(entry)
    spark.sql(f"DROP TABLE {entry}")
    return stored
