"""Style groups and their semantic depths: local-first, global-first, and every blend between."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Blended depths are rounded to this many digits before they are ranked to bands.
DIGITS = 9


def groups(h: DataFrame) -> DataFrame:
    """A row per document and style: number by first use, first position, group of the header before that, size."""
    by = Window.partitionBy("doc_id").orderBy("pos")
    found = h.select("doc_id", "pos", "style").withColumn("prev_style", F.lag("style").over(by)).groupBy("doc_id", "style").agg(F.min("pos").alias("opener"), F.min_by("prev_style", "pos").alias("prev_style"), F.count("*").alias("n_nodes"))
    numbered = found.withColumn("g", (F.row_number().over(Window.partitionBy("doc_id").orderBy("opener")) - 1).cast("int"))
    before = numbered.select("doc_id", F.col("style").alias("prev_style"), F.col("g").alias("prev_g"))
    return numbered.join(before, ["doc_id", "prev_style"], "left").select("doc_id", "style", "g", "opener", "prev_g", "n_nodes")


def blend(g: DataFrame, k: Column | float) -> DataFrame:
    """doc_id, style, g, sd: one scan over a document's groups in order of first use.

    A group's depth is one more than ``k`` times the depth of the group before its opener plus
    ``1 - k`` times the largest depth so far; ``k`` may differ from group to group.  1 is local-first,
    0 is global-first.  Only the groups of a document are gathered, few against its headers.
    """
    k = k if isinstance(k, Column) else F.lit(float(k))
    rows = g.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("g", "prev_g", k.cast("double").alias("k"), "style"))).alias("gs"))

    def step(state: Column, x: Column) -> Column:
        grown = F.round(x["k"] * F.get(state["d"], x["prev_g"]) + (1 - x["k"]) * state["top"] + 1, DIGITS)
        d = F.when(x["g"] == 0, F.lit(0.0)).otherwise(grown)
        return F.struct(F.concat(state["d"], F.array(d)).alias("d"), F.greatest(state["top"], d).alias("top"))

    start = F.struct(F.array().cast("array<double>").alias("d"), F.lit(0.0).alias("top"))
    scanned = rows.select("doc_id", "gs", F.aggregate("gs", start, step, lambda s: s["d"]).alias("d"))
    return scanned.select("doc_id", F.explode(F.arrays_zip(F.col("gs"), F.col("d"))).alias("x")).select("doc_id", F.col("x.gs.style").alias("style"), F.col("x.gs.g").alias("g"), F.col("x.d").alias("sd"))


def local(g: DataFrame) -> DataFrame:
    return blend(g, 1.0)


def global_first(g: DataFrame) -> DataFrame:
    """Each new group is one deeper than all before it, so its depth is its number."""
    return g.select("doc_id", "style", "g", F.col("g").cast("double").alias("sd"))


def local_by_jumps(g: DataFrame) -> DataFrame:
    """Local-first depth by pointer doubling: log2 of the number of groups rounds of equi-joins."""
    at = g.select("doc_id", "style", "g", F.col("prev_g").alias("to"), F.when(F.col("prev_g").isNull(), 0).otherwise(1).alias("far"))
    most = g.agg(F.max("g")).first()[0] or 0
    span = 1
    while span <= most:
        ends = at.select("doc_id", F.col("g").alias("to"), F.col("to").alias("on"), F.col("far").alias("more"))
        at = at.join(ends, ["doc_id", "to"], "left").select("doc_id", "style", "g", F.col("on").alias("to"), (F.col("far") + F.coalesce("more", F.lit(0))).alias("far"))
        span *= 2
    return at.select("doc_id", "style", "g", F.col("far").cast("double").alias("sd"))


def blend_finished(g: DataFrame, k: float) -> DataFrame:
    """Mix of the finished local and global depths.  For comparison only: it has no guarantee."""
    a, b = local(g).withColumnRenamed("sd", "a"), global_first(g).select("doc_id", "g", F.col("sd").alias("b"))
    return a.join(b, ["doc_id", "g"]).select("doc_id", "style", "g", F.round(k * F.col("a") + (1 - k) * F.col("b"), DIGITS).alias("sd"))


def with_k(g: DataFrame, table: DataFrame, default: float = 1.0) -> DataFrame:
    """Groups with the k of a table (doc_id, style, k), for ``blend(g, F.col("k"))``."""
    return g.join(table.select("doc_id", "style", F.col("k").cast("double").alias("k")), ["doc_id", "style"], "left").withColumn("k", F.coalesce("k", F.lit(float(default))))


def k_by(condition: Column, k: float = 1.0, otherwise: float = 0.0) -> Column:
    """A k that depends on a feature of the group's style."""
    return F.when(condition, float(k)).otherwise(float(otherwise))


def hashed_k(seed: int, steps: int = 8) -> Column:
    """A k per group that depends on nothing but its number: pseudo-random in steps of 1/steps."""
    return F.pmod(F.col("g").cast("bigint") * 2654435761 + F.lit(seed * 40503), F.lit(steps + 1)) / F.lit(steps)


def banded(h: DataFrame, depths: DataFrame) -> DataFrame:
    """Headers with sd and band, the rank of sd in the document.

    The depths of a document come as one row with a map of its few styles, so headers stay where they
    are, dealt by document.
    """
    ranked = depths.withColumn("band", (F.dense_rank().over(Window.partitionBy("doc_id").orderBy("sd")) - 1).cast("int"))
    maps = ranked.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("style", F.struct("sd", "band")))).alias("m"))
    return h.join(maps, "doc_id").withColumn("at", F.try_element_at("m", F.col("style"))).select(*h.columns, F.col("at.sd").alias("sd"), F.col("at.band").alias("band"))


def all_bands(g: DataFrame, ks: dict[str, float]) -> DataFrame:
    """doc_id, m: a map from the styles of a document to their bands under each blend of ``ks``, from one scan.

    A document stands once per blend under a key of its own.
    """
    keyed = g.select("style", "g", "prev_g", F.col("doc_id").alias("own"), F.posexplode(F.array(*[F.lit(float(k)) for k in ks.values()])).alias("a", "k")).withColumn("doc_id", F.struct("own", "a"))
    ranked = blend(keyed, F.col("k")).withColumn("band", (F.dense_rank().over(Window.partitionBy("doc_id").orderBy("sd")) - 1).cast("int"))
    by_style = ranked.groupBy(F.col("doc_id.own").alias("doc_id"), "style").agg(*[F.max(F.when(F.col("doc_id.a") == i, F.col("band"))).alias(n) for i, n in enumerate(ks)])
    return by_style.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("style", F.struct(*ks)))).alias("m"))


METHODS = {"local": local, "global": global_first, "half": lambda g: blend(g, 0.5)}
