"""Corpora with headers, built from the given tables.

Each builder returns the HEADERS schema: a root at position 0, then the headers in reading order.
``rk`` is the rank of a header's true level; the true parent is the nearest earlier header of smaller
rank, so truth needs no more than this column.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

LEDGER_VARIANTS = ("level", "leaf", "parity", "memo", "all")
#: Modulus of the peer rule of composites, and its buckets on the ring.
RING, RING_BUCKET = 1_000_003, 4_096


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def n_words(text: Column) -> Column:
    return F.size(F.regexp_extract_all(text, F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)))


def line_style(line: Column) -> Column:
    """Size by number of words, capitals, closing mark and list number of a line, as one key."""
    n = n_words(line)
    size = F.when(n <= 3, "18").when(n <= 6, "14").otherwise("12")
    caps = F.when(line.rlike("[A-Za-zÀ-ÿ]") & ~line.rlike("[a-zß-öø-ÿ]"), "C").otherwise("c")
    last = F.substring(line, -1, 1)
    mark = F.when(last.isin(*".!?:,"), last).otherwise("")
    number = F.when(line.rlike(r"^\d+[.)] "), "n").otherwise("")
    return F.concat_ws("|", size, caps, mark, number)


def _folded(rows: DataFrame, *order: str) -> DataFrame:
    """Fold ordered phrase rows (doc_id, order, style or null, rk, title, words) to headers."""
    by = Window.partitionBy("doc_id").orderBy(*order)
    owned = rows.withColumn("pos", (F.count("style").over(by.rowsBetween(Window.unboundedPreceding, 0)) - 1).cast("int"))
    return owned.groupBy("doc_id", "pos").agg(
        F.max("style").alias("style"), F.max("rk").alias("rk"), F.max("title").alias("title"), F.sum(F.when(F.col("style").isNull(), F.col("words")).otherwise(0)).cast("bigint").alias("body_words")
    )


def line_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, ln, line, words, style (null: text) of every non-blank line."""
    docs = read(spark, sf_dir, "documents")
    lines = docs.select("doc_id", F.posexplode(F.split("text", "\n")).alias("ln", "line"))
    words = n_words(F.col("line"))
    header = (words <= 10) & ~F.contains("line", F.lit(" | "))
    return lines.withColumn("words", words).where("words > 0").withColumn("style", F.when(header, line_style(F.col("line"))))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    rank = {"18": 2, "14": 3, "12": 4}
    found = line_phrases(spark, sf_dir)
    size = F.substring("style", 1, 2)
    rk = F.coalesce(*[F.when(size == s, r) for s, r in rank.items()])
    rows = found.select("doc_id", "ln", "style", rk.alias("rk"), F.when(F.col("style").isNotNull(), F.col("line")).alias("title"), "words")
    roots = read(spark, sf_dir, "documents").select("doc_id", F.lit(-1).alias("ln"), F.lit("ROOT").alias("style"), F.lit(0).alias("rk"), F.lit("").alias("title"), F.lit(0).alias("words"))
    return _folded(rows.union(roots), "ln")


def peers(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """comp_id, slot, doc_id: each document with ``k`` others of its language.

    The rule takes the k least of (7919 x + 104729 D) mod RING, which are the documents that follow a
    point of a ring.  Ranks on the ring come from bucket counts and ranks within buckets, so the peers
    are found by equi-joins of k+1 rows a document and not from all pairs.
    """
    docs = read(spark, sf_dir, "documents").select("doc_id", "lang")
    at = docs.withColumn("ring", (F.col("doc_id") * 7919) % RING).withColumn("bucket", F.floor(F.col("ring") / RING_BUCKET))
    sizes = at.groupBy("lang", "bucket").agg(F.count("*").alias("n"))
    totals = sizes.groupBy("lang").agg(F.sum("n").alias("total"))
    buckets = totals.select("lang", "total", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(RING // RING_BUCKET).cast("bigint"))).alias("bucket"))
    before = Window.partitionBy("lang").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = buckets.join(sizes, ["lang", "bucket"], "left").withColumn("first", F.coalesce(F.sum(F.coalesce("n", F.lit(0))).over(before), F.lit(0))).select("lang", "bucket", "total", "first")
    # Points and queries together, so a query's rank is the number of points before it.
    points = at.select("lang", "bucket", "ring", "doc_id", F.lit(1).alias("is_point"))
    turned = (RING - (F.col("doc_id") * 104729) % RING) % RING
    asks = docs.select("lang", F.floor(turned / RING_BUCKET).alias("bucket"), turned.alias("ring"), "doc_id", F.lit(0).alias("is_point"))
    order = Window.partitionBy("lang", "bucket").orderBy("ring", "is_point", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    ranked = points.union(asks).withColumn("r", F.coalesce(F.sum("is_point").over(order), F.lit(0))).join(starts, ["lang", "bucket"]).withColumn("r", F.col("r") + F.col("first"))
    by_rank = ranked.where("is_point = 1").select("lang", F.col("r").alias("rank"), F.col("doc_id").alias("peer"))
    steps = ranked.where("is_point = 0").select("lang", F.col("doc_id").alias("comp_id"), "total", "r", F.explode(F.sequence(F.lit(0), F.least(F.lit(k), F.col("total") - 1).cast("int"))).alias("step"))
    near = steps.withColumn("rank", (F.col("r") + F.col("step")) % F.col("total")).join(by_rank, ["lang", "rank"]).where("peer <> comp_id")
    nearest = near.withColumn("place", F.row_number().over(Window.partitionBy("comp_id").orderBy("step"))).where(F.col("place") <= k).select("comp_id", F.col("peer").alias("doc_id"))
    members = nearest.union(docs.select(F.col("doc_id").alias("comp_id"), "doc_id"))
    slot = Window.partitionBy("comp_id").orderBy((F.col("doc_id") * 31 + F.col("comp_id") * 17) % 1009, "doc_id")
    return members.withColumn("slot", F.row_number().over(slot))


def composite(spark: SparkSession, sf_dir: str, size: int) -> DataFrame:
    """Documents one after the other, each under a title, below one root."""
    members, single = peers(spark, sf_dir, size - 1), lines(spark, sf_dir)
    inner = members.join(single, "doc_id").select(
        F.col("comp_id").alias("doc_id"),
        "slot",
        F.col("pos").alias("inner"),
        F.when(F.col("pos") == 0, "TITLE").otherwise(F.col("style")).alias("style"),
        F.when(F.col("pos") == 0, 1).otherwise(F.col("rk")).alias("rk"),
        F.when(F.col("pos") == 0, F.concat(F.lit("Document "), members["doc_id"].cast("string"))).otherwise(F.col("title")).alias("title"),
        "body_words",
    )
    roots = members.select("comp_id").distinct().select(F.col("comp_id").alias("doc_id"), F.lit(0).alias("slot"), F.lit(0).alias("inner"), F.lit("ROOT").alias("style"), F.lit(0).alias("rk"), F.lit("").alias("title"), F.lit(0).cast("bigint").alias("body_words"))
    order = Window.partitionBy("doc_id").orderBy("slot", "inner")
    return inner.union(roots).select("doc_id", (F.row_number().over(order) - 1).alias("pos"), "style", "rk", "title", "body_words")


#: Tags that open a phrase; the value is the rank of a header, null for text.
HTML_RANKS = {"title": 0, "nav": 1, "li": 2, "h1": 1, "b": 2, "footer": 1}


def html(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", "").alias("html"))
    parts = pages.select("doc_id", F.posexplode(F.regexp_extract_all("html", F.lit(r"<[a-z][a-z0-9]*[^>]*>[^<]*"), F.lit(0))).alias("ln", "part"))
    tag = F.regexp_extract("part", r"^<([a-z][a-z0-9]*)", 1)
    text = F.trim(F.regexp_replace("part", r"^<[^>]*>", ""))
    rk = F.coalesce(*[F.when(F.col("tag") == t, r) for t, r in HTML_RANKS.items()])
    rows = parts.select("doc_id", "ln", tag.alias("tag"), text.alias("said")).withColumn("rk", rk)
    shaped = rows.select("doc_id", "ln", F.when(F.col("rk").isNotNull(), F.col("tag")).alias("style"), "rk", F.when(F.col("rk").isNotNull(), F.col("said")).alias("title"), n_words(F.col("said")).alias("words"))
    return _folded(shaped, "ln").where("pos >= 0")


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = read(spark, sf_dir, "conversations").select(F.col("conv_id").alias("doc_id"), "turn", "role", F.coalesce("text", F.lit("")).alias("text"))
    first = F.substring_index("text", "\n", 1)
    turns = said.select("doc_id", "turn", F.col("role").alias("style"), F.when(F.col("role") == "assistant", 2).otherwise(1).alias("rk"), first.alias("title"), (n_words(F.col("text")) - n_words(first)).cast("bigint").alias("body_words"))
    roots = said.select("doc_id").distinct().select("doc_id", F.lit(-1).cast("bigint").alias("turn"), F.lit("ROOT").alias("style"), F.lit(0).alias("rk"), F.lit("").alias("title"), F.lit(0).cast("bigint").alias("body_words"))
    order = Window.partitionBy("doc_id").orderBy("turn")
    return turns.union(roots).select("doc_id", (F.row_number().over(order) - 1).alias("pos"), "style", "rk", "title", "body_words")


def ledger(spark: SparkSession, sf_dir: str, variant: str) -> DataFrame:
    """Regions as documents: nations, their customers, their orders; line items are text below orders."""
    nation = read(spark, sf_dir, "nation").withColumn("place", F.row_number().over(Window.partitionBy("n_regionkey").orderBy("n_nationkey")) - 1)
    customer = read(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    orders = read(spark, sf_dir, "orders").join(customer, F.col("o_custkey") == F.col("c_custkey"))
    items = read(spark, sf_dir, "lineitem").join(read(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey")).join(read(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    item_words = items.groupBy("l_orderkey").agg(F.sum(n_words(F.concat_ws(" ", "p_name", "s_name"))).alias("w"))
    orders = orders.join(item_words, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    customer_style = {"all": F.concat(F.lit("customer "), F.col("c_mktsegment")), "parity": F.concat(F.lit("customer "), (F.col("place") % 2).cast("string"))}.get(variant, F.lit("customer"))
    order_style = F.concat(F.lit("order "), F.col("o_orderpriority")) if variant in ("leaf", "all") else F.lit("order")

    def rows(df: DataFrame, n, c, o, sub, style, rk, title, words) -> DataFrame:
        doc = F.col("r_regionkey") if "r_regionkey" in df.columns else F.col("n_regionkey")
        cell = lambda v: v if isinstance(v, Column) else F.lit(v)
        return df.select(doc.cast("bigint").alias("doc_id"), *[cell(v).cast("bigint").alias(a) for v, a in ((n, "n"), (c, "c"), (o, "o"), (sub, "sub"))], cell(style).alias("style"), cell(rk).alias("rk"), cell(title).alias("title"), cell(words).cast("bigint").alias("body_words"))

    key = F.col("n_nationkey")
    found = rows(read(spark, sf_dir, "region"), -1, -1, -1, 0, "region", 0, F.col("r_name"), 0)
    found = found.union(rows(nation, key, -1, -1, 0, "nation", 1, F.col("n_name"), 0))
    found = found.union(rows(customer, key, F.col("c_custkey"), -1, 0, customer_style, 2, F.col("c_name"), 0))
    found = found.union(rows(orders, key, F.col("c_custkey"), F.col("o_orderkey"), 0, order_style, 3, F.concat(F.lit("Order "), F.col("o_orderkey").cast("string")), F.coalesce("w", F.lit(0))))
    if variant == "memo":
        found = found.union(rows(nation.where("place = 1"), key, -1, -1, 1, "memo", 2, "Memo", 0))
        found = found.union(rows(orders.where("place >= 1 AND o_orderstatus = 'P'"), key, F.col("c_custkey"), F.col("o_orderkey"), 1, "memo", 4, "Memo", 0))
    order = Window.partitionBy("doc_id").orderBy("n", "c", "o", "sub")
    return found.select("doc_id", (F.row_number().over(order) - 1).alias("pos"), "style", "rk", "title", "body_words")


CORPORA = {
    "lines": lines,
    "composite1": lambda s, d: composite(s, d, 1),
    "composite4": lambda s, d: composite(s, d, 4),
    "composite8": lambda s, d: composite(s, d, 8),
    "html": html,
    "dialogue": dialogue,
    **{v: (lambda s, d, v=v: ledger(s, d, v)) for v in LEDGER_VARIANTS},
}
