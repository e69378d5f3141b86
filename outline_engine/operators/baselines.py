"""Comparison trees: chain, flat, per part, in batches, from outside, and simulated model outputs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.operators import assembly, depth

Infer = Callable[[DataFrame], DataFrame]


def infer(h: DataFrame, method: str = "local", strategy: str = "bands", root: str = "auto") -> DataFrame:
    """The two stages: depths of style groups, then assembly.

    The methods take the first style for the root's alone.  Where it occurs again, ``root="auto"`` puts a
    virtual root above; this makes all depths one larger and changes nothing else.
    """
    return assembly.assemble(depth.banded(h, depth.METHODS[method](depth.groups(h))), strategy, root)


def infer_part(h: DataFrame) -> DataFrame:
    """A part of a document, whose headers without a parent will hang below the document's root."""
    return infer(h, root="first")


def deep(h: DataFrame) -> DataFrame:
    """A chain: each header is a child of the one before, and all spans reach the end.  Also what span coverage alone chooses."""
    order = Window.partitionBy("doc_id").orderBy("pos")
    return h.select("doc_id", "pos", F.lag("pos").over(order).alias("parent_pos"), (F.max("pos").over(Window.partitionBy("doc_id")) + 1).cast("int").alias("span_end"))


def wide(h: DataFrame) -> DataFrame:
    """The first header above all others."""
    order, doc = Window.partitionBy("doc_id").orderBy("pos"), Window.partitionBy("doc_id")
    first, end = F.min("pos").over(doc), F.max("pos").over(doc) + 1
    return h.select("doc_id", "pos", F.when(F.col("pos") > first, first).alias("parent_pos"), F.when(F.col("pos") == first, end).otherwise(F.coalesce(F.lead("pos").over(order), end)).cast("int").alias("span_end"))


def per_part(h: DataFrame, part: Column, infer_fn: Infer = infer_part) -> DataFrame:
    """Infer each part of a document by itself and hang all below the document's root.

    ``part`` numbers a header's part; the root's is null.  A part stands for a document whose root is
    its first header.
    """
    marked = h.withColumn("__part", part)
    parts = marked.where("__part IS NOT NULL").withColumn("__doc", F.col("doc_id"))
    keys = parts.select("__doc", "__part").distinct().withColumn("doc_id", F.xxhash64("__doc", "__part"))
    inner = infer_fn(parts.drop("doc_id").join(keys, ["__doc", "__part"]).select(*h.columns))
    root = h.groupBy("doc_id").agg(F.min("pos").alias("root"), (F.max("pos") + 1).cast("int").alias("end"))
    named = inner.join(keys, "doc_id").select(F.col("__doc").alias("doc_id"), "pos", "parent_pos", "span_end")
    hung = named.join(root, "doc_id").select("doc_id", "pos", F.coalesce("parent_pos", "root").alias("parent_pos"), "span_end")
    return hung.union(root.select("doc_id", F.col("root").alias("pos"), F.lit(None).cast("int").alias("parent_pos"), F.col("end").alias("span_end")))


def batched(h: DataFrame, headers_each: int, infer_fn: Infer = infer_part) -> DataFrame:
    """Infer runs of so many headers by themselves, as a model with a bounded window would."""
    return per_part(h, F.when(F.col("pos") > 0, F.floor((F.col("pos") - 1) / headers_each)), infer_fn)


def mixed(a: Column, b: Column, seed: int, mod: int) -> Column:
    """A hash of two numbers that DuckDB can repeat."""
    return F.pmod(a.cast("bigint") * 7919 + b.cast("bigint") * 104729 + F.lit(seed * 31), F.lit(mod))


def perturbed(h: DataFrame, drop_percent: int, seed: int = 1) -> DataFrame:
    """Headers with a share missed (never the root)."""
    return h.where((F.col("pos") == 0) | (mixed(F.col("doc_id"), F.col("pos"), seed, 100) >= drop_percent))


def simulated_model(h: DataFrame, *, deep_drop: int, tail_drop: int, seed: int = 2) -> DataFrame:
    """The true tree as a model reports it: low-level headers and those late in the document are missed more often."""
    doc = Window.partitionBy("doc_id")
    late = F.col("pos") * 2 > F.max("pos").over(doc)
    drop = F.when(F.col("rk") >= 2, deep_drop).otherwise(0) + F.when(late, tail_drop).otherwise(0)
    kept = h.withColumn("__drop", drop).where((F.col("pos") == 0) | (mixed(F.col("doc_id"), F.col("pos"), seed, 100) >= F.col("__drop"))).drop("__drop")
    return assembly.truth(kept)


def external(json_rows: DataFrame) -> DataFrame:
    """Trees given from outside as JSON lists of {pos, level}: doc_id, tree."""
    parsed = json_rows.select("doc_id", F.explode(F.from_json("tree", "array<struct<pos:int,level:int>>")).alias("x"))
    return assembly.by_bands(parsed.select("doc_id", F.col("x.pos").alias("pos"), F.col("x.level").alias("band")))


def from_contents(entries: DataFrame) -> DataFrame:
    """True trees from a table of contents: doc_id, pos, level."""
    return assembly.by_bands(entries.select("doc_id", "pos", F.col("level").alias("band")))


def prior_global(h: DataFrame, well: DataFrame) -> DataFrame:
    """The earlier algorithm, for well-formatted documents only: on its class it is global-first.

    ``well``: doc_id, well, as ``classes.formats`` gives them; other documents get no tree.
    """
    return infer(h.join(well.where("well").select("doc_id"), "doc_id", "left_semi"), "global")


APPROACHES: dict[str, Infer] = {"local": infer, "global": lambda h: infer(h, "global"), "half": lambda h: infer(h, "half"), "deep": deep, "wide": wide}
