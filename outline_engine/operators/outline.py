"""Numbered outlines, section reading, pattern and vector retrieval, and the questions asked with them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.operators import assembly

MAX_ROUNDS, CONTEXT = 100, 1000


def numbered(tree: DataFrame) -> DataFrame:
    """doc_id, pos, level, prefix: child numbers down the path, joined by points; empty at the root."""
    child = tree.withColumn("no", F.row_number().over(Window.partitionBy("doc_id", "parent_pos").orderBy("pos"))).select("doc_id", "pos", F.when(F.col("parent_pos").isNull(), None).otherwise(F.col("no")).alias("no"))
    own = tree.select("doc_id", "pos", F.col("pos").alias("anc_pos"))
    path = assembly.closure(tree).union(own).join(child.select("doc_id", F.col("pos").alias("anc_pos"), "no"), ["doc_id", "anc_pos"])
    grouped = path.groupBy("doc_id", "pos").agg((F.count("*") - 1).cast("int").alias("level"), F.array_sort(F.collect_list(F.when(F.col("no").isNotNull(), F.struct("anc_pos", "no")))).alias("p"))
    return grouped.select("doc_id", "pos", "level", F.array_join(F.transform("p", lambda x: x["no"].cast("string")), ".").alias("prefix"))


def render(tree: DataFrame, h: DataFrame) -> DataFrame:
    """doc_id, outline: a line per header, prefix bar title."""
    lines = numbered(tree).join(h.select("doc_id", "pos", "title"), ["doc_id", "pos"]).where("pos > 0")
    row = F.struct("pos", F.concat_ws(" | ", "prefix", "title").alias("line"))
    return lines.groupBy("doc_id").agg(F.array_sort(F.collect_list(row)).alias("ls")).select("doc_id", F.array_join(F.transform("ls", lambda x: x["line"]), "\n").alias("outline"))


def children(tree: DataFrame) -> DataFrame:
    """doc_id, pos, children: positions in order."""
    up = tree.where("parent_pos IS NOT NULL").groupBy("doc_id", "parent_pos").agg(F.array_sort(F.collect_list("pos")).alias("children"))
    return up.withColumnRenamed("parent_pos", "pos")


def breadcrumb(tree: DataFrame) -> DataFrame:
    """doc_id, pos, path: the positions from the root to the header."""
    own = tree.select("doc_id", "pos", F.col("pos").alias("anc_pos"))
    return assembly.closure(tree).union(own).groupBy("doc_id", "pos").agg(F.array_sort(F.collect_list("anc_pos")).alias("path"))


def read_section(requests: DataFrame, tree: DataFrame, phrases: DataFrame) -> DataFrame:
    """Text below the headers asked for by prefix.  ``phrases``: doc_id, pos (the header they follow), ln, line."""
    at = numbered(tree).join(tree.select("doc_id", "pos", "span_end"), ["doc_id", "pos"])
    spans = requests.join(at, ["doc_id", "prefix"]).select("doc_id", "prefix", F.col("pos").alias("begin"), "span_end")
    inside = phrases.join(spans, "doc_id").where("pos >= begin AND pos < span_end")
    return inside.groupBy("doc_id", "prefix").agg(F.array_sort(F.collect_list(F.struct("ln", "line"))).alias("ls")).select("doc_id", "prefix", F.array_join(F.transform("ls", lambda x: x["line"]), "\n").alias("section"))


def grep(calls: DataFrame, docs: DataFrame) -> DataFrame:
    """Each call of a pattern in a session gives its next match; other patterns do not move its cursor.

    ``calls``: session, call_no, doc_id, pattern (a regular expression).  Returns the match number, its
    position (from 1, null when there is none left) and up to CONTEXT characters around it.  A pattern that
    matches the empty text finds nothing.
    """
    turn = F.row_number().over(Window.partitionBy("session", "pattern").orderBy("call_no"))
    asked = calls.withColumn("match_no", turn).join(docs.select("doc_id", "text"), "doc_id")
    cut = asked.withColumn("hits", F.when(F.regexp_like(F.lit(""), F.col("pattern")), F.array().cast("array<string>")).otherwise(F.regexp_extract_all("text", F.col("pattern"), F.lit(0)))).withColumn("pieces", F.split("text", F.col("pattern")))
    sizes = lambda xs: F.aggregate(xs, F.lit(0), lambda a, x: a + F.length(x))
    before = sizes(F.slice("pieces", 1, F.col("match_no"))) + sizes(F.slice("hits", 1, F.col("match_no") - 1))
    hit = F.get("hits", F.col("match_no") - 1)
    placed = cut.withColumn("at", F.when(hit.isNotNull(), before + 1)).withColumn("n", F.length(hit))
    begin = F.greatest(F.col("at") + F.floor(F.col("n") / 2).cast("int") - CONTEXT // 2, F.lit(1))
    return placed.select("session", "call_no", "doc_id", "pattern", "match_no", "at", F.when(F.col("at").isNotNull(), F.substring("text", begin, F.lit(CONTEXT))).alias("context"))


LETTERS = "abcdefghijklmnopqrstuvwxyz"


def letters(text: Column) -> Column:
    """A small deterministic stand-in for an encoder: counts of letters."""
    return F.array(*[(F.length(text) - F.length(F.replace(text, F.lit(x), F.lit("")))).cast("double") for x in LETTERS])


def chunks(docs: DataFrame) -> DataFrame:
    """doc_id, chunk_no, text of CONTEXT characters each."""
    n = F.ceil(F.length("text") / CONTEXT).cast("int")
    cut = docs.where("length(text) > 0").select("doc_id", "text", F.explode(F.sequence(F.lit(1), n)).alias("chunk_no"))
    return cut.select("doc_id", "chunk_no", F.substring("text", (F.col("chunk_no") - 1) * CONTEXT + 1, F.lit(CONTEXT)).alias("text"))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return F.coalesce(F.round(dot(a, b) / F.nullif(F.sqrt(dot(a, a) * dot(b, b)), F.lit(0.0)), 6), F.lit(0.0))


def embed_search(questions: DataFrame, docs: DataFrame) -> DataFrame:
    """Chunks of a question's own document in descending order of cosine; call number c gets rank c."""
    scored = chunks(docs).join(questions.select("doc_id", "question"), "doc_id").withColumn("score", cosine(letters(F.col("text")), letters(F.col("question"))))
    return scored.select("doc_id", "chunk_no", "score", F.row_number().over(Window.partitionBy("doc_id").orderBy(F.desc("score"), "chunk_no")).alias("rank"))


def answer(trees: DataFrame, questions: DataFrame, true: DataFrame, h: DataFrame) -> DataFrame:
    """The tree agent by a fixed policy, for each approach: it reads the outline, then opens the section named in
    the question.  ``questions``: doc_id, pos.  Gives whether the section holds all of the true one, and words read."""
    from outline_engine.operators import metrics

    asked = questions.join(true.select("doc_id", "pos", F.col("span_end").alias("true_end")), ["doc_id", "pos"])
    opened = asked.join(trees, ["doc_id", "pos"])
    read = metrics.with_words(opened, h, "pos", "span_end", "section_words")
    sizes = h.groupBy("doc_id").agg((F.count("*") - 1).alias("outline_lines"))
    return read.join(sizes, "doc_id").select("approach", "doc_id", "pos", (F.col("span_end") >= F.col("true_end")).alias("found"), "section_words", "outline_lines")


def agent_rounds(ranked: DataFrame, *, rounds: int = MAX_ROUNDS, prompt_tokens: int = 500) -> DataFrame:
    """An agent that opens sections in order until one has the answer or ``rounds`` are over.

    ``ranked``: q_id, rank, words, has_answer.  Every round pays for all that was read before, so tokens
    grow with the square of the rounds.
    """
    order = Window.partitionBy("q_id").orderBy("rank")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    live = ranked.where(F.col("rank") <= rounds).withColumn("done", F.coalesce(F.max(F.col("has_answer").cast("int")).over(before), F.lit(0))).where("done = 0")
    paid = live.withColumn("paid", prompt_tokens + F.coalesce(F.sum("words").over(before), F.lit(0)) + F.col("words"))
    return paid.groupBy("q_id").agg(F.count("*").alias("rounds"), F.sum("paid").alias("in_tokens"), F.max(F.col("has_answer").cast("int")).alias("answered"))
