"""Questions over outlines: strategies and agents by one fixed policy, their accuracy, tokens and cost.

No language model runs here.  A question asks for the contents of all sections below a header; an agent
answers with those whose text it has read, so a strategy's accuracy is what its reading reaches.  The
measures take any answers, and ``usage`` any agent's tokens.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.operators.metrics import usd
from outline_engine.operators.outline import CONTEXT, MAX_ROUNDS

CHARS_PER_WORD, CHARS_PER_TOKEN, PROMPT_TOKENS = 6, 4, 500
#: Prices for a million tokens read and written, and the tokens a model takes at once.
IN_PRICE, OUT_PRICE, LIMIT = 2.5, 10.0, 128_000


def set_f1(answer: Column, gold: Column) -> Column:
    """F-1 of two arrays as sets; two empty ones agree."""
    a, g = F.array_distinct(answer), F.array_distinct(gold)
    return F.when(F.size(a) + F.size(g) == 0, 1.0).otherwise(2 * F.size(F.array_intersect(a, g)) / F.nullif(F.size(a) + F.size(g), F.lit(0)))


def exact(answer: Column, gold: Column) -> Column:
    return F.coalesce((answer == gold).cast("int"), F.lit(0))


def judged(answer: Column, gold: Column) -> Column:
    """1 where the normalised words of a free answer agree with the gold answer's by an F-1 of a half: a stand-in for a judge."""
    from outline_engine.functions.text import norm_words

    return (set_f1(norm_words(answer), norm_words(gold)) >= 0.5).cast("int")


def layout(h: DataFrame) -> DataFrame:
    """doc_id, pos, begin, size: where each header's line and text lie, in characters, if a word has six."""
    size = F.length("title") + 1 + CHARS_PER_WORD * F.col("body_words")
    order = Window.partitionBy("doc_id").orderBy("pos")
    return h.select("doc_id", "pos", "title", size.cast("bigint").alias("size")).withColumn("begin", F.sum("size").over(order) - F.col("size"))


def asked_parts(h: DataFrame, true: DataFrame, asked: DataFrame) -> DataFrame:
    """doc_id, pos (of the question), part, rank: the true children of the headers ``asked`` about, with the places of both."""
    at = layout(h)
    child = true.join(asked.select("doc_id", F.col("pos").alias("parent_pos")), ["doc_id", "parent_pos"]).select("doc_id", F.col("parent_pos").alias("q"), F.col("pos").alias("part"))
    child = child.withColumn("rank", F.row_number().over(Window.partitionBy("doc_id", "q").orderBy("part")))
    placed = child.join(at.select("doc_id", F.col("pos").alias("part"), F.col("begin").alias("part_begin"), F.col("size").alias("part_size")), ["doc_id", "part"])
    head = at.select("doc_id", F.col("pos").alias("q"), F.col("begin").alias("q_begin"), F.length("title").alias("q_length"))
    sums = at.groupBy("doc_id").agg(F.sum("size").alias("doc_chars"), F.sum(F.length("title") + 8).alias("outline_chars"))
    return placed.join(head, ["doc_id", "q"]).join(sums, "doc_id")


TEXT_STRATEGIES = ("in context", "grep agent", "outline and context", "tree agent")
AGENTS = ("grep agent", "embed agent", "tree agent", "tree and grep agent", "tree and embed agent")


def reading(parts: DataFrame, trees: DataFrame, h: DataFrame, approaches: tuple[str, ...], strategies: tuple[str, ...]) -> DataFrame:
    """approach, strategy, doc_id, q, gold, seen, context, rounds: what each strategy reads of each question with each tree.

    ``trees``: approach, doc_id, pos, span_end.  A part counts as read if its last character is.  In context, all is read if it fits the limit.  The
    pattern agent gets the characters around the question's header, the chunk agent the chunk with it.
    The tree agent reads the header's section; one that the tree lacks is not found.  With the outline at hand, pattern and chunk
    agents ask for the titles in the section one by one, as many as rounds allow.
    """
    section = trees.select("approach", "doc_id", F.col("pos").alias("q"), F.col("span_end").alias("q_end"))
    ends = layout(h).select("doc_id", (F.col("pos") + 1).alias("q_end"), (F.col("begin") + F.col("size")).alias("section_stop"))
    named = parts.withColumn("approach", F.explode(F.array(*[F.lit(a) for a in approaches])))
    x = named.join(section, ["approach", "doc_id", "q"], "left").join(ends, ["doc_id", "q_end"], "left")
    stop = F.col("part_begin") + F.col("part_size")
    middle = F.col("q_begin") + F.floor(F.col("q_length") / 2)
    tokens = lambda chars: F.ceil(chars / CHARS_PER_TOKEN)
    inside = F.coalesce(F.col("part") < F.col("q_end"), F.lit(False))
    doc, outline, section_chars = F.col("doc_chars"), F.col("outline_chars"), F.coalesce(F.col("section_stop") - F.col("q_begin"), F.lit(0))
    fits = lambda chars: tokens(chars) + PROMPT_TOKENS <= LIMIT
    listed = inside & (F.col("rank") <= MAX_ROUNDS) & fits(outline)
    one = F.lit(1)
    ways = {
        "in context": (fits(doc), doc, one),
        "outline and context": (fits(doc + outline), doc + outline, one),
        "grep agent": (stop <= middle + CONTEXT // 2, F.lit(CONTEXT), one),
        "embed agent": (F.floor(F.col("q_begin") / CONTEXT) == F.floor((stop - 1) / CONTEXT), F.lit(CONTEXT), one),
        "tree agent": (inside & fits(outline + section_chars), outline + section_chars, one),
        "tree and grep agent": (listed, outline, None),
        "tree and embed agent": (listed, outline, None),
    }
    row = lambda name, seen, chars, rounds: F.struct(F.lit(name).alias("strategy"), seen.alias("seen"), tokens(chars).cast("bigint").alias("context"), (F.lit(None).cast("bigint") if rounds is None else rounds.cast("bigint")).alias("rounds"))
    each = x.select("approach", "doc_id", "q", F.explode(F.array(*[row(n, *ways[n]) for n in strategies])).alias("w")).select("approach", "doc_id", "q", "w.*")
    grouped = each.groupBy("approach", "strategy", "doc_id", "q").agg(F.count("*").alias("gold"), F.count_if("seen").alias("seen"), F.max("context").alias("context"), F.max("rounds").alias("rounds"))
    return grouped.withColumn("rounds", F.coalesce("rounds", F.greatest("seen", F.lit(1))))


def usage(read: DataFrame) -> DataFrame:
    """With in_tokens and out_tokens: every round pays for the prompt and all that earlier rounds have read."""
    hits = F.when(F.col("strategy").isin("tree and grep agent", "tree and embed agent"), CONTEXT // CHARS_PER_TOKEN).otherwise(0)
    n = F.col("rounds")
    paid = n * (PROMPT_TOKENS + F.col("context")) + hits * F.floor(n * (n + 1) / 2)
    return read.withColumn("in_tokens", paid.cast("bigint")).withColumn("out_tokens", (50 * n).cast("bigint"))


def report(read: DataFrame, *by: str) -> DataFrame:
    """Questions, mean set F-1, exact and judged shares, tokens and cost ``by`` strategy or approach."""
    f1 = 2 * F.col("seen") / (F.col("seen") + F.col("gold"))
    scored = usage(read).withColumn("f1", f1)
    sums = scored.groupBy(*by).agg(
        F.count("*").alias("questions"),
        F.round(F.avg("f1"), 6).alias("set_f1"),
        F.round(F.avg((F.col("f1") == 1).cast("double")), 6).alias("exact"),
        F.round(F.avg((F.col("f1") >= 0.5).cast("double")), 6).alias("judged"),
        F.sum("in_tokens").alias("in_tokens"),
        F.sum("out_tokens").alias("out_tokens"),
    )
    return usd(sums, IN_PRICE, OUT_PRICE).withColumn("usd", F.col("usd").cast("double"))
