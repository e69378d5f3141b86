"""Writing derived tables, and the outline text format."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def stored(df: DataFrame) -> DataFrame:
    """``df`` as a table in the folder that the session shares (``spark.checkpoint.dir``), read back.

    For skinny tables that a plan reads many times: they are made once, and a lost executor costs a re-read.
    A local session without that setting gets a temporary folder; a cluster gets an error.
    """
    spark = df.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="outline-engine-")
        spark.sparkContext.setCheckpointDir(root)
    path = f"{root.rstrip('/')}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def write_tree(tree: DataFrame, path: str, corpus: str) -> None:
    """One folder per corpus; writing a corpus again replaces its folder only."""
    tree.sortWithinPartitions("doc_id", "pos").write.mode("overwrite").parquet(f"{path}/corpus={corpus}")


def write_bucketed(df: DataFrame, name: str, buckets: int) -> None:
    """A table dealt by document, so that later joins and windows on doc_id need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "doc_id").sortBy("doc_id", "pos").saveAsTable(name)


def read_contents(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """Tables of contents from CSV files (doc_id, pos, level, title, with a header line), and the malformed lines.

    A line with a missing document, position or level, or of another shape, is malformed and is returned as it is.
    """
    schema = "doc_id bigint, pos int, level int, title string, broken string"
    rows = spark.read.schema(schema).option("header", True).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "broken").csv(path)
    # Without the other columns the reader would not parse a line, and find none broken.
    whole = F.col("broken").isNull() & F.col("doc_id").isNotNull() & F.col("pos").isNotNull() & F.col("level").isNotNull()
    return rows.where(whole).drop("broken"), rows.where(~whole)


def read_outlines(spark: SparkSession, path: str) -> DataFrame:
    """doc_id (file name), line number, prefix, title, level of outline text files: ``prefix | title`` lines."""
    lines = spark.read.text(path, wholetext=True).select(F.regexp_extract(F.input_file_name(), r"([^/]+)$", 1).alias("doc_id"), F.posexplode(F.split("value", "\n")).alias("line", "text"))
    cut = lines.where(F.col("text").contains(" | ")).withColumn("prefix", F.substring_index("text", " | ", 1))
    return cut.select("doc_id", "line", "prefix", F.expr("substring(text, length(prefix) + 4)").alias("title"), (F.size(F.split("prefix", r"\.")) - 1).alias("level"))
