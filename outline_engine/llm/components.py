"""Connected components of an edge table, by alternating large and small stars.

Each round is a few equi-joins and aggregations whose result is written to the shared folder, so
lineage stays short and a lost executor costs a re-read.  Rounds end when a round changes no edge.

The edges of a node are dealt to as many tasks as an exchange has, by their other end: a hub, to which
most edges of a large component point, is nowhere gathered but as one least node per task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.llm.storage import materialise


def _stars(pairs: DataFrame) -> DataFrame:
    """``pairs``: (u, v).  Links every v, and u, to the least node around u."""
    parts = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = pairs.withColumn("slice", F.pmod(F.xxhash64("v"), F.lit(parts)))
    least = dealt.groupBy("u", "slice").agg(F.min("v").alias("m"))
    least = least.select("u", "slice", F.least(F.min("m").over(Window.partitionBy("u")), F.col("u")).alias("m"))
    return dealt.join(least, ["u", "slice"]).drop("slice")


def components(edges: DataFrame) -> DataFrame:
    """node, root: the least node that each node of ``edges`` (a, b) reaches.  Isolated nodes have no row."""
    kept = materialise(
        edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "edges"
    )

    def mark(df: DataFrame) -> tuple:
        row = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s")).first()
        return row["n"], row["s"]

    state = mark(kept)
    while True:
        both = kept.select(F.col("a").alias("u"), F.col("b").alias("v")).union(kept.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = _stars(both).where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        down = _stars(large.select(F.col("a").alias("u"), F.col("b").alias("v")))
        small = down.where("v <> m").select(F.col("v").alias("a"), F.col("m").alias("b")).union(down.select(F.col("u").alias("a"), F.col("m").alias("b")))
        kept = materialise(small.where("a <> b").distinct(), "edges")
        now = mark(kept)
        if now == state:
            return kept.select(F.col("a").alias("node"), F.col("b").alias("root"))
        state = now
