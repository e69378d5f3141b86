"""Document fingerprints from closed syncmers over words.

Words are the letters of the alphabet here: a k-mer is ``K`` consecutive words, its inner
substrings are single words, and a k-mer is an anchor if the word with the least hash is its first
or its last.  Whether a k-mer is an anchor depends on its own words only, so an edit changes the
anchors that it touches and no others, and equal passages have equal anchors wherever they stand.
Han, Kana and Thai characters, written without blanks, are words of their own.

A fingerprint lists all anchors with their positions, ordered by hash and position.  The likeness of
two fingerprints is the Jaccard similarity of their sets of hashes; ``match`` finds the difference of
positions at which most anchors agree, by the first occurrence of each.

Defined cases: a null or empty text, or one of white space only, has an empty fingerprint, which is
like another empty one (1.0) and unlike all else (0.0); a text of fewer than ``K`` words has one
anchor, all its words; repeated rows have equal fingerprints.  Of rows that share a ``doc_id`` the
one with the smallest text stands for the id as a neighbour; a row with a null id has no neighbour,
so its edited text only loses its tail.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from outline_engine.llm.columns import indices, let, text_of, words_of
from outline_engine.llm.storage import materialise, table

K = 3
_ALONE = r"\x{0E00}-\x{0E7F}\x{3040}-\x{30FF}\x{3400}-\x{9FFF}\x{F900}-\x{FAFF}\x{20000}-\x{3FFFF}"
TOKEN = rf"[{_ALONE}]|[^\x20\x09-\x0D{_ALONE}]+"

ANCHORS = "array<struct<hash:int,pos:int>>"


def anchors(text: Column) -> Column:
    """All anchors of a text in reading order."""

    def chosen(words: Column, hashes: Column) -> Column:
        starts = F.filter(
            indices(F.size(words) - (K - 1)),
            lambda i: (F.get(hashes, i + 1) >= F.get(hashes, i)) | (F.get(hashes, i + 1) >= F.get(hashes, i + 2)),
        )
        return F.transform(starts, lambda i: F.struct(_short(F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2))).alias("hash"), i.alias("pos")))

    def few(words: Column) -> Column:
        return F.array(F.struct(_short(F.xxhash64(F.array_join(words, " "))).alias("hash"), F.lit(0).alias("pos")))

    def pick(words: Column) -> Column:
        hashed = F.transform(words, lambda w: F.xxhash64(w))
        return F.when(F.size(words) == 0, F.array().cast(ANCHORS)).when(F.size(words) < K, few(words)).otherwise(let(hashed, lambda h: chosen(words, h)))

    return let(F.when(text.rlike(f"[{_ALONE}]"), F.regexp_extract_all(text, F.lit(TOKEN), F.lit(0))).otherwise(words_of(text)), pick)


def _short(h: Column) -> Column:
    return F.shiftright(h, 32).cast("int")


def sketch(text: Column) -> Column:
    """All anchors of a text, by hash and position."""
    return F.sort_array(anchors(text))


def firsts(found: Column) -> Column:
    """The first occurrence of each hash of a sketch."""
    return let(found, lambda o: F.filter(o, lambda x, i: (i == 0) | (F.get(o, F.greatest(i - 1, F.lit(0)))["hash"] != x["hash"])))


def spell(found: Column) -> Column:
    """A sketch as text: 8 hexadecimal digits of the hash and the position, joined by points."""
    return F.lower(F.array_join(F.transform(found, lambda x: F.concat(F.lpad(F.hex(x["hash"].cast("long").bitwiseAND(F.lit(0xFFFFFFFF))), 8, "0"), F.lit(":"), x["pos"].cast("string"))), "."))


def hashes(found: Column) -> Column:
    return F.transform(found, lambda e: e["hash"])


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two sets of hashes, each hash once."""

    def compare(x: Column, y: Column) -> Column:
        shared = F.size(F.array_intersect(x, y))
        return let(shared, lambda n: F.when(F.size(x) + F.size(y) == 0, F.lit(1.0)).otherwise(n / (F.size(x) + F.size(y) - n)))

    return F.round(let(a, lambda x: let(b, lambda y: compare(x, y))), 6)


def match(a: Column, b: Column) -> Column:
    """n, the most anchors (of ``firsts``) that agree in one difference of positions (b's less a's), and this difference, d.

    Of equally frequent ones the nearest to zero; n is 0 and d null without a common anchor.
    """
    sided = lambda found, side: F.transform(found, lambda e: F.struct(e["hash"].alias("hash"), F.lit(side).alias("side"), e["pos"].alias("pos")))
    after = lambda o, i: F.get(o, i + 1)
    moves = let(
        F.sort_array(F.concat(sided(a, 0), sided(b, 1))),
        lambda o: F.filter(F.transform(o, lambda x, i: F.when(after(o, i)["hash"] == x["hash"], after(o, i)["pos"] - x["pos"])), lambda d: d.isNotNull()),
    )
    none = F.lit(None).cast("int")
    start = F.struct(none.alias("d"), F.lit(0).alias("n"), F.struct(F.lit(0).alias("n"), F.lit(0).alias("far"), none.alias("d")).alias("best"))

    def step(s: Column, d: Column) -> Column:
        n = F.when(s["d"] == d, s["n"] + 1).otherwise(F.lit(1))
        return F.struct(d.alias("d"), n.alias("n"), F.least(s["best"], F.struct((-n).alias("n"), F.abs(d).alias("far"), d.alias("d"))).alias("best"))

    return F.aggregate(F.sort_array(moves), start, step, lambda s: F.struct((-s["best"]["n"]).alias("n"), s["best"]["d"].alias("d")))


def shift(a: Column, b: Column) -> Column:
    """The most frequent difference of positions (b's less a's) of common anchors; null without any."""
    return match(firsts(a), firsts(b))["d"]


def neighbours(docs: DataFrame) -> DataFrame:
    """doc_id and prev_id, the document before it (the next larger id).

    Ids are ranged and stored, then each range is ordered by itself; a range's first id follows the
    last id of the range before, which is looked up in a table of a row per range.
    """
    slim = docs.select("doc_id").where("doc_id IS NOT NULL").distinct()
    ranged = materialise(slim.repartitionByRange(F.desc("doc_id")).withColumn("part", F.spark_partition_id()), "fingerprint-order")
    order = Window.partitionBy("part").orderBy(F.desc("doc_id"))
    linked = ranged.withColumn("before", F.lag("doc_id").over(order))
    ends = ranged.groupBy("part").agg(F.min("doc_id").alias("last"))
    every = Window.orderBy("part")
    whole = every.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ends = ends.select("part", F.coalesce(F.lag("last").over(every), F.last("last").over(whole)).alias("entry"))
    return linked.join(ends, "part").select("doc_id", F.coalesce("before", "entry").alias("prev_id"))


def compare_edits(docs: DataFrame) -> DataFrame:
    """Fingerprint each text and its edit: the last third replaced by the head of the next document.

    kept_anchors agree in place (kept_shift words on) between text and edit, borrowed_anchors between the next text and the edit.
    """
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    near = neighbours(docs)
    texts = docs.select(F.col("doc_id"), text_of().alias("text"))
    # Both sides of the join start from this one exchange of the texts.
    base = texts.where("doc_id IS NOT NULL").repartition(parts, "doc_id")
    one = base.withColumn("rank", F.row_number().over(Window.partitionBy("doc_id").orderBy("text"))).where("rank = 1")
    # A text is shorter than its anchors are, so it is what travels to the document before.
    sent = one.join(near, "doc_id").select(F.col("prev_id").alias("doc_id"), F.col("text").alias("follower"))
    joined = base.join(sent, "doc_id", "left").unionByName(texts.where("doc_id IS NULL"), allowMissingColumns=True)
    n = F.length("text")
    third = F.floor(n / 3).cast("int")
    edited = joined.withColumn("follower", text_of("follower")).select(
        "doc_id",
        "text",
        "follower",
        F.concat(F.substring("text", F.lit(1), n - third), F.substring("follower", F.lit(1), third)).alias("edited"),
    )
    made = edited.select(
        "doc_id",
        F.length("text").cast("long").alias("n_chars"),
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        sketch(F.col("text")).alias("own"),
        sketch(F.col("edited")).alias("other"),
        firsts(sketch(F.col("follower"))).alias("next"),
    ).withColumns({"own_first": firsts(F.col("own")), "other_first": firsts(F.col("other"))})
    made = made.withColumns({"kept": match(F.col("own_first"), F.col("other_first")), "borrowed": match(F.col("next"), F.col("other_first"))})
    return made.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        spell(F.col("own")).alias("fingerprint"),
        spell(F.col("other")).alias("edited_fingerprint"),
        likeness(hashes(F.col("own_first")), hashes(F.col("other_first"))).alias("near_edited"),
        likeness(hashes(F.col("own_first")), hashes(F.col("next"))).alias("near_next"),
        F.col("kept.n").alias("kept_anchors"),
        F.col("kept.d").alias("kept_shift"),
        F.col("borrowed.n").alias("borrowed_anchors"),
        F.col("borrowed.d").alias("borrowed_shift"),
    )


def op10_syncmers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_edits(table(spark, sf_dir, "documents"))
