"""Document classes, robustness and excess, per document."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.operators import assembly, depth

Keep = Callable[[DataFrame], DataFrame]
#: Blends by method.
K_OF = {"local": 1.0, "global": 0.0, "half": 0.5}


def certify(tree: DataFrame, true: DataFrame) -> DataFrame:
    """doc_id, robust (every span holds the true one), excess (headers beyond the true spans)."""
    t = true.select("doc_id", "pos", F.col("span_end").alias("true_end"))
    return tree.join(t, ["doc_id", "pos"]).groupBy("doc_id").agg(F.bool_and(F.col("span_end") >= F.col("true_end")).alias("robust"), F.sum(F.greatest(F.lit(0), F.col("span_end") - F.col("true_end"))).cast("bigint").alias("excess"))


def robust_by_edges(tree: DataFrame, true: DataFrame) -> DataFrame:
    """doc_id, robust: each true parent is still an ancestor."""
    edges = true.where("parent_pos IS NOT NULL").select("doc_id", "pos", "parent_pos")
    above = tree.select("doc_id", F.col("pos").alias("parent_pos"), "span_end")
    held = edges.join(above, ["doc_id", "parent_pos"]).groupBy("doc_id").agg(F.bool_and((F.col("parent_pos") < F.col("pos")) & (F.col("pos") < F.col("span_end"))).alias("r"))
    return true.select("doc_id").distinct().join(held, "doc_id", "left").select("doc_id", F.coalesce("r", F.lit(True)).alias("robust"))


def conformant(h: DataFrame, true: DataFrame, depths: DataFrame) -> DataFrame:
    """doc_id, conformant: along every true edge the depth grows."""
    at = depth.banded(h.select("doc_id", "pos", "style"), depths).select("doc_id", "pos", "band")
    edges = true.where("parent_pos IS NOT NULL").join(at, ["doc_id", "pos"]).join(at.select("doc_id", F.col("pos").alias("parent_pos"), F.col("band").alias("above")), ["doc_id", "parent_pos"])
    held = edges.groupBy("doc_id").agg(F.bool_and(F.col("above") < F.col("band")).alias("c"))
    return true.select("doc_id").distinct().join(held, "doc_id", "left").select("doc_id", F.coalesce("c", F.lit(True)).alias("conformant"))


def conformant_by_openers(h: DataFrame, true: DataFrame) -> DataFrame:
    """doc_id, conformant under global-first, from the order of openers alone."""
    openers = h.groupBy("doc_id", "style").agg(F.min("pos").alias("opener"))
    styles = h.select("doc_id", "pos", "style")
    child = true.where("parent_pos IS NOT NULL").join(styles, ["doc_id", "pos"]).select("doc_id", "parent_pos", "style")
    pairs = child.join(styles.select("doc_id", F.col("pos").alias("parent_pos"), F.col("style").alias("above")), ["doc_id", "parent_pos"]).select("doc_id", "style", "above").distinct()
    first = pairs.join(openers, ["doc_id", "style"]).join(openers.select("doc_id", F.col("style").alias("above"), F.col("opener").alias("above_opener")), ["doc_id", "above"])
    held = first.groupBy("doc_id").agg(F.bool_and(F.col("above_opener") < F.col("opener")).alias("c"))
    return true.select("doc_id").distinct().join(held, "doc_id", "left").select("doc_id", F.coalesce("c", F.lit(True)).alias("conformant"))


def excess_words(tree: DataFrame, true: DataFrame, h: DataFrame) -> DataFrame:
    """doc_id, excess_headers, excess_words: what the spans hold beyond the true ones."""
    from outline_engine.operators import metrics

    t = true.select("doc_id", "pos", F.col("span_end").alias("true_end"))
    beyond = tree.join(t, ["doc_id", "pos"]).where("span_end > true_end").select("doc_id", "true_end", "span_end")
    sums = metrics.with_words(beyond, h, "true_end", "span_end", "w").groupBy("doc_id").agg(F.sum(F.col("span_end") - F.col("true_end")).alias("n"), F.sum("w").alias("w"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("bigint")
    return true.select("doc_id").distinct().join(sums, "doc_id", "left").select("doc_id", zero("n").alias("excess_headers"), zero("w").alias("excess_words"))


def formats(h: DataFrame, true: DataFrame, keep: Keep = lambda df: df) -> DataFrame:
    """doc_id, well, loose, aligned.

    ``keep`` may store what is read several times.
    """
    nodes = keep(assembly.levels(true).join(h.select("doc_id", "pos", "style"), ["doc_id", "pos"]))
    up = nodes.select("doc_id", F.col("pos").alias("parent_pos"), F.col("style").alias("parent_style"))
    order = Window.partitionBy("doc_id").orderBy("pos")
    lagged = nodes.withColumn("prev_pos", F.lag("pos").over(order))
    found = lagged.groupBy("doc_id", "style").agg(F.min("pos").alias("opener"), F.min_by("parent_pos", "pos").alias("up_pos"), F.min_by("prev_pos", "pos").alias("prev_pos"), (F.min("level") == F.max("level")).alias("one_level"))
    openers = keep(found.join(up.withColumnRenamed("parent_pos", "up_pos").withColumnRenamed("parent_style", "up_style"), ["doc_id", "up_pos"], "left"))
    # Well: children of one parent share a style; a style's parents have the style that its opener's parent has.
    siblings = nodes.where("parent_pos IS NOT NULL").groupBy("doc_id", "parent_pos").agg((F.min("style") == F.max("style")).alias("ok")).groupBy("doc_id").agg(F.bool_and("ok").alias("same"))
    pairs = keep(nodes.join(up, ["doc_id", "parent_pos"]).select("doc_id", "style", "parent_style").distinct())
    pattern = pairs.join(openers.select("doc_id", "style", "up_style"), ["doc_id", "style"]).groupBy("doc_id").agg(F.bool_and(F.col("parent_style") == F.col("up_style")).alias("pattern"))
    # Loose: some ancestor of the opener has the parent's style.  Paths of openers only.
    firsts = openers.select("doc_id", "style", F.col("opener").alias("pos"))
    path = assembly.closure(nodes, firsts).join(firsts, ["doc_id", "pos"])
    above = path.join(h.select("doc_id", F.col("pos").alias("anc_pos"), F.col("style").alias("parent_style")), ["doc_id", "anc_pos"]).select("doc_id", "style", "parent_style").distinct()
    off = pairs.join(above, ["doc_id", "style", "parent_style"], "left_anti").select("doc_id").distinct().withColumn("off", F.lit(True))
    # Aligned: an opener is the first child of its parent, and a style has one level.
    line = openers.groupBy("doc_id").agg(F.bool_and(F.col("one_level") & (F.col("up_pos").isNull() | (F.col("up_pos") == F.col("prev_pos")))).alias("aligned"))
    whole = gathered([line, keep(siblings), keep(pattern), keep(off)])
    yes = lambda c: F.coalesce(F.col(c), F.lit(True))
    return whole.select("doc_id", (yes("same") & yes("pattern")).alias("well"), F.col("off").isNull().alias("loose"), yes("aligned").alias("aligned"))


def gathered(parts: list[DataFrame]) -> DataFrame:
    """The columns of ``parts``, each a row per document, by one exchange and no join."""
    rows = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)
    return rows.groupBy("doc_id").agg(*[F.max(c).alias(c) for c in rows.columns if c != "doc_id"])


def flags(h: DataFrame, keep: Keep = lambda df: df) -> DataFrame:
    """Every class flag of each document, with robustness and excess under the three depth methods.

    The methods share one pass: a header has a band for each, and a document stands once per method under
    a key of its own where trees are assembled.  ``keep`` may store the headers, true tree and groups,
    which are read many times, and the parts of the result, so that no plan holds all of them.
    """
    h = keep(h.select("doc_id", "pos", "style", "rk"))
    true, maps = keep(assembly.truth(h)), keep(depth.all_bands(depth.groups(h), K_OF))
    names = list(K_OF)
    at = h.join(maps, "doc_id").select("doc_id", "pos", F.try_element_at("m", F.col("style")).alias("at")).select("doc_id", "pos", "at.*")
    nodes = keep(true.join(at, ["doc_id", "pos"]))
    keyed = nodes.select("pos", F.col("doc_id").alias("own"), F.posexplode(F.array(*names)).alias("a", "band")).select(F.struct("own", "a").alias("doc_id"), "pos", "band")
    tree = assembly.assemble(keyed).select(F.col("doc_id.own").alias("doc_id"), F.col("doc_id.a").alias("a"), "pos", F.col("span_end").alias("found_end"))
    spans = tree.join(nodes.select("doc_id", "pos", F.col("span_end").alias("true_end")), ["doc_id", "pos"])
    own = lambda i, c: F.when(F.col("a") == i, c)
    beyond = F.greatest(F.lit(0), F.col("found_end") - F.col("true_end"))
    certified = spans.groupBy("doc_id").agg(*[x for i, m in enumerate(names) for x in (F.bool_and(own(i, F.col("found_end") >= F.col("true_end"))).alias(f"robust_{m}"), F.sum(own(i, beyond)).cast("bigint").alias(f"excess_{m}"))])
    above = nodes.select("doc_id", F.col("pos").alias("parent_pos"), *[F.col(m).alias(f"up_{m}") for m in names])
    edges = nodes.where("parent_pos IS NOT NULL").join(above, ["doc_id", "parent_pos"])
    conf = edges.groupBy("doc_id").agg(*[F.bool_and(F.col(f"up_{m}") < F.col(m)).alias(f"conf_{m}") for m in names])
    whole = gathered([keep(formats(h, true, keep)), keep(certified), keep(conf)])
    return whole.select("doc_id", "well", "loose", "aligned", *[x for m in names for x in (f"robust_{m}", f"excess_{m}", F.coalesce(f"conf_{m}", F.lit(True)).alias(f"conf_{m}"))])


def flags_of(corpora: dict[str, DataFrame], keep: Keep = lambda df: df) -> DataFrame:
    """``flags`` of several corpora in one pass, with the column corpus: a document stands under a key of its own."""
    key = lambda name: F.struct(F.lit(name).alias("corpus"), F.col("doc_id").cast("bigint").alias("own")).alias("doc_id")
    parts = [keep(h.select(key(name), F.col("pos").cast("int").alias("pos"), "style", F.col("rk").cast("int").alias("rk"))) for name, h in corpora.items()]
    found = flags(reduce(DataFrame.unionByName, parts), keep)
    return found.select(F.col("doc_id.own").alias("doc_id"), *[c for c in found.columns if c != "doc_id"], F.col("doc_id.corpus").alias("corpus"))


def frequency(f: DataFrame) -> DataFrame:
    """One row per region of the class diagram."""
    return f.groupBy("well", "loose", "aligned", "conf_local", "conf_global").agg(F.count("*").alias("n_docs"))


def valid_tree(tree: DataFrame) -> DataFrame:
    """doc_id, valid: one root, parents before their children, and children inside their parents' spans."""
    up = tree.select("doc_id", F.col("pos").alias("parent_pos"), F.col("span_end").alias("up_end"))
    held = tree.join(up, ["doc_id", "parent_pos"], "left").withColumn("ok", F.when(F.col("parent_pos").isNull(), True).otherwise((F.col("parent_pos") < F.col("pos")) & (F.col("pos") < F.col("up_end")) & (F.col("span_end") <= F.col("up_end"))))
    return held.groupBy("doc_id").agg((F.bool_and(F.coalesce("ok", F.lit(False))) & (F.count_if(F.col("parent_pos").isNull()) == 1)).alias("valid"))


def tree_depth(tree: DataFrame) -> DataFrame:
    """doc_id, depth (nodes on the longest path down), n_headers."""
    return assembly.levels(tree).groupBy("doc_id").agg((F.max("level") + 1).alias("depth"), F.count("*").alias("n_headers"))
