"""Accuracy of trees: spans, ancestor lists, headers; robustness reports; costs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.functions.text import norm_words
from outline_engine.operators import assembly, depth


def shares(common: Column, true: Column, found: Column) -> list[Column]:
    """Recall, precision and F-1 of sizes; two empty sets agree, and an empty side is not blamed for the other."""
    rec = F.when(true == 0, 1.0).otherwise(common / F.nullif(true, F.lit(0)))
    prec = F.when(found == 0, 1.0).otherwise(common / F.nullif(found, F.lit(0)))
    f1 = F.when(true + found == 0, 1.0).otherwise(2 * common / F.nullif(true + found, F.lit(0)))
    return [rec.alias("rec"), prec.alias("prec"), f1.alias("f1")]


#: Blends by approach; the two others have bands of their own.
K_OF = {"local": 1.0, "global": 0.0, "half": 0.5}


def all_trees(h: DataFrame, approaches: tuple[str, ...] = ("local", "global", "half", "deep", "wide")) -> DataFrame:
    """approach, doc_id and tree columns of several approaches from one pass.

    A document stands once per approach under a key of its own, so groups, depths and assembly of all
    approaches share their exchanges.  A flat tree is that of bands 0 and 1.  A chain would have as many
    bands as headers, so its tree is stated and not assembled.
    """
    names = F.array(*[F.lit(a) for a in approaches])
    keyed = h.select("pos", "style", F.col("doc_id").alias("own"), F.posexplode(names).alias("a", "approach")).withColumn("doc_id", F.col("own") * len(approaches) + F.col("a"))
    scanned = keyed.where(F.col("approach").isin(*K_OF))
    k = F.coalesce(*[F.when(F.pmod(F.col("doc_id"), F.lit(len(approaches))) == i, F.lit(K_OF[a])) for i, a in enumerate(approaches) if a in K_OF], F.lit(1.0))
    banded = [depth.banded(scanned, depth.blend(depth.groups(scanned.select("doc_id", "pos", "style")), k)).select("doc_id", "pos", "band")]
    if "wide" in approaches:
        banded.append(keyed.where("approach = 'wide'").select("doc_id", "pos", F.least("pos", F.lit(1)).alias("band")))
    made = reduce(DataFrame.union, banded)
    trees = assembly.by_bands(made)
    if "deep" in approaches:
        chain = keyed.where(F.col("approach") == "deep")
        end = (F.max("pos").over(Window.partitionBy("doc_id")) + 1).cast("int")
        trees = trees.union(chain.select("doc_id", "pos", F.when(F.col("pos") > 0, F.col("pos") - 1).alias("parent_pos"), end.alias("span_end")))
    approach = F.get(names, F.pmod(F.col("doc_id"), F.lit(len(approaches))).cast("int"))
    return trees.select(approach.alias("approach"), F.floor(F.col("doc_id") / len(approaches)).cast("bigint").alias("doc_id"), "pos", "parent_pos", "span_end")


def running_words(h: DataFrame) -> DataFrame:
    """doc_id, pos, upto: words of the text up to and with the one below the header."""
    return h.select("doc_id", "pos", F.sum("body_words").over(Window.partitionBy("doc_id").orderBy("pos")).alias("upto"))


def with_words(spans: DataFrame, h: DataFrame, begin: str, end: str, name: str) -> DataFrame:
    """``spans`` with the words in [begin, end), from two prefix sums."""
    w = running_words(h)
    last = w.select("doc_id", (F.col("pos") + 1).alias(end), F.col("upto").alias("__to"))
    first = w.select("doc_id", (F.col("pos") + 1).alias(begin), F.col("upto").alias("__from"))
    joined = spans.join(last, ["doc_id", end], "left").join(first, ["doc_id", begin], "left")
    zero = lambda c: F.coalesce(c, F.lit(0))
    return joined.withColumn(name, zero("__to") - zero("__from")).drop("__to", "__from")


def _nearest(trees: DataFrame, true: DataFrame, approaches: tuple[str, ...] | None) -> DataFrame:
    """approach, doc_id, pos, true_end of each true header below the root, with u and u_end: the header of the tree
    that it is, or the nearest earlier one, whose span covers it."""
    heads = true.where("pos > 0").select("doc_id", "pos", F.col("span_end").alias("true_end"))
    if approaches is None:
        named = heads.crossJoin(F.broadcast(trees.select("approach").distinct()))
    else:
        named = heads.withColumn("approach", F.explode(F.array(*[F.lit(a) for a in approaches])))
    asks = named.select("approach", "doc_id", "pos", "true_end", F.lit(None).cast("int").alias("u"), F.lit(None).cast("int").alias("u_end"))
    have = trees.select("approach", "doc_id", "pos", F.lit(None).cast("int").alias("true_end"), F.col("pos").alias("u"), F.col("span_end").alias("u_end"))
    order = Window.partitionBy("approach", "doc_id").orderBy("pos", F.col("u").isNull())
    near = have.union(asks).withColumn("x", F.last(F.when(F.col("u").isNotNull(), F.struct("u", "u_end")), ignorenulls=True).over(order)).where("true_end IS NOT NULL")
    return near.select("approach", "doc_id", "pos", "true_end", F.col("x.u").alias("u"), F.col("x.u_end").alias("u_end"))


def topdown(trees: DataFrame, h: DataFrame, true: DataFrame, approaches: tuple[str, ...] | None = None) -> DataFrame:
    """approach, doc_id, pos, rec, prec, f1 of each true header's span, in words.

    A header that the tree has starts its span where the true one starts, so the smaller word count is
    the intersection.  For one that is missing, the nearest earlier header of the tree stands in, and
    the words that both spans cover are their intersection.  ``approaches`` saves finding out their names.
    """
    near = _nearest(trees, true, approaches)
    spans = near.withColumn("both_end", F.greatest("pos", F.least("true_end", "u_end")))
    sized = with_words(with_words(with_words(spans, h, "pos", "true_end", "true_w"), h, "u", "u_end", "found_w"), h, "pos", "both_end", "both_w")
    return sized.select("approach", "doc_id", "pos", *shares(F.col("both_w"), F.col("true_w"), F.col("found_w")))


def bottomup(trees: DataFrame, true: DataFrame, approaches: tuple[str, ...] | None = None) -> DataFrame:
    """approach, doc_id, pos, rec, prec, f1 of each true header's list of ancestors (itself with them, the root without).

    For a header that the tree lacks, the list of the nearest earlier header of the tree stands in.
    """
    heads = assembly.levels(true).where("pos > 0").select("doc_id", "pos", F.col("level").alias("true_n"))
    own = true.where("pos > 0").select("doc_id", "pos", F.col("pos").alias("anc_pos"))
    lists = assembly.closure(true).where("anc_pos > 0").union(own)
    keyed = trees.withColumn("key", F.struct("doc_id", "approach"))
    level = assembly.levels(keyed.select(F.col("key").alias("doc_id"), "pos", "parent_pos", "span_end")).select(F.col("doc_id.approach").alias("approach"), F.col("doc_id.doc_id").alias("doc_id"), F.col("pos").alias("u"), F.col("level").alias("found_n"))
    near = _nearest(trees, true, approaches).select("approach", "doc_id", "pos", "u")
    at = trees.select("approach", "doc_id", F.col("pos").alias("anc_pos"), "span_end")
    held = lists.join(near, ["doc_id", "pos"]).join(at, ["approach", "doc_id", "anc_pos"]).where("anc_pos <= u AND u < span_end").groupBy("approach", "doc_id", "pos").agg(F.count("*").alias("both_n"))
    scored = near.join(heads, ["doc_id", "pos"]).join(level, ["approach", "doc_id", "u"], "left").join(held, ["approach", "doc_id", "pos"], "left")
    zero = lambda c: F.coalesce(c, F.lit(0))
    return scored.select("approach", "doc_id", "pos", *shares(zero("both_n"), F.col("true_n"), zero("found_n")))


def averages(scores: DataFrame, *by: str) -> DataFrame:
    return scores.groupBy(*by).agg(F.count("*").alias("n"), *[F.round(F.avg(c), 6).alias(c) for c in ("rec", "prec", "f1")])


def stratified(per_set: DataFrame, *by: str) -> DataFrame:
    """Means of data set means."""
    return per_set.groupBy(*by).agg(*[F.round(F.avg(c), 6).alias(c) for c in ("rec", "prec", "f1")])


def header_scores(detected: DataFrame, true: DataFrame) -> DataFrame:
    """Recall, precision and F-1 of found headers by position."""
    both = true.select("doc_id", "pos", F.lit(1).alias("t")).join(detected.select("doc_id", "pos", F.lit(1).alias("d")), ["doc_id", "pos"], "full")
    sums = both.agg(F.count("t").alias("true_n"), F.count("d").alias("found_n"), F.count_if(F.col("t").isNotNull() & F.col("d").isNotNull()).alias("both_n"))
    return sums.select("true_n", "found_n", "both_n", *[F.round(c, 6).alias(n) for c, n in zip(shares(F.col("both_n"), F.col("true_n"), F.col("found_n")), ("rec", "prec", "f1"), strict=True)])


def fabricated(reported: DataFrame, docs: DataFrame) -> DataFrame:
    """Share of reported headers (doc_id, title) whose normalised words do not stand in their document (doc_id, text)."""
    padded = lambda c: F.concat(F.lit(" "), F.array_join(norm_words(c), " "), F.lit(" "))
    made = reported.select("doc_id", "title").join(docs.select("doc_id", "text"), "doc_id", "left")
    marked = made.withColumn("made_up", ~F.coalesce(F.contains(padded(F.col("text")), padded(F.col("title"))), F.lit(False)))
    return marked.agg(F.count("*").alias("reported"), F.count_if("made_up").alias("fabricated")).select("reported", "fabricated", F.round(F.col("fabricated") / F.nullif(F.col("reported"), F.lit(0)), 6).alias("share"))


def bag_overlap(pairs: DataFrame, tokens: DataFrame) -> DataFrame:
    """id, true_n, found_n, both_n: the exact multiset measure, for spans that do not nest.

    ``pairs``: id, doc_id, a_begin, a_end, b_begin, b_end; ``tokens``: doc_id, pos, token, n.
    """
    inside = lambda x: (F.col("pos") >= F.col(f"{x}_begin")) & (F.col("pos") < F.col(f"{x}_end"))
    found = pairs.join(tokens, "doc_id").where(inside("a") | inside("b"))
    bags = found.groupBy("id", "token").agg(F.sum(F.when(inside("a"), F.col("n")).otherwise(0)).alias("a"), F.sum(F.when(inside("b"), F.col("n")).otherwise(0)).alias("b"))
    return bags.groupBy("id").agg(F.sum("a").alias("true_n"), F.sum("b").alias("found_n"), F.sum(F.least("a", "b")).alias("both_n"))


def by_depth_ratio(scores: DataFrame, tree: DataFrame, true: DataFrame) -> DataFrame:
    """Mean precision of documents by the ratio of found depth to true depth, in quarters."""
    deepest = lambda t, n: assembly.levels(t).groupBy("doc_id").agg((F.max("level") + 1).alias(n))
    ratio = deepest(tree, "found").join(deepest(true, "true_"), "doc_id").withColumn("ratio", F.floor(F.col("found") / F.col("true_") * 4) / 4)
    per_doc = scores.groupBy("doc_id").agg(F.avg("prec").alias("prec"))
    return per_doc.join(ratio, "doc_id").groupBy("ratio").agg(F.count("*").alias("n_docs"), F.round(F.avg("prec"), 6).alias("prec"))


def usd(usage: DataFrame, in_price: float, out_price: float) -> DataFrame:
    """Cost of token counts at prices for a million tokens."""
    cost = (F.col("in_tokens") * F.lit(in_price) + F.col("out_tokens") * F.lit(out_price)) / 1_000_000
    return usage.withColumn("usd", F.round(cost, 6).cast("decimal(18,6)"))
