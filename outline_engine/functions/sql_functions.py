"""SQL names for the engine: views of a corpus, and tree building as a table function."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from outline_engine.functions import text
from outline_engine.operators import assembly, baselines, depth, metrics, outline
from outline_engine.sources.corpora import CORPORA
from outline_engine.streaming.online import settle


@F.udtf(returnType="pos int, parent_pos int, sd double")
class BuildTree:
    """``build_tree(TABLE(headers) PARTITION BY doc_id ORDER BY pos)``: local-first parents and depths in order."""

    def __init__(self):
        self.state = {"depths": {}, "open": [], "last": 0.0, "top": 0.0}

    def eval(self, row: Row):
        parent, sd = settle(self.state, row["pos"], row["style"], 1.0)
        yield row["pos"], parent, sd


@F.udtf(returnType="ln int, tag string, said string")
class HtmlPhrases:
    """``html_phrases(html)``: the tags of a page in order, each with the text up to the next tag."""

    def eval(self, html: str):
        for ln, (tag, said) in enumerate(re.findall(r"<([A-Za-z][A-Za-z0-9]*)[^>]*>([^<]*)", html or "")):
            yield ln, tag.lower(), said.strip()


@F.udtf(returnType="match_no int, at int, context string")
class GrepStream:
    """``grep_stream(text, pattern)``: matches one by one, with the characters around each."""

    def eval(self, text: str, pattern: str):
        for no, found in enumerate((m for m in re.finditer(pattern, text or "") if m[0]), 1):
            begin = max(found.start() + len(found[0]) // 2 - outline.CONTEXT // 2, 0)
            yield no, found.start() + 1, text[begin : begin + outline.CONTEXT]


def explained(df: DataFrame, *, python: bool = False, most_exchanges: int | None = None) -> str:
    """The physical plan, checked: no Python node unless allowed, and at most so many exchanges."""
    plan = df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    tree = plan.split("\n\n")[0]
    if not python and re.search(r"EvalPython|MapInArrow|MapInPandas|FlatMapGroupsIn", tree):
        raise AssertionError(f"a Python node in\n{tree}")
    n = len(re.findall(r"(?<!Reused)(?<!Broadcast)Exchange \(", tree))
    if most_exchanges is not None and n > most_exchanges:
        raise AssertionError(f"{n} exchanges in\n{tree}")
    return plan


def register(spark: SparkSession, sf_dir: str, corpus: str = "lines") -> None:
    """Views headers, style_groups, depths, true_tree, tree, spans, outline and metrics_topdown of a corpus, and the functions
    build_tree, html_phrases, grep_stream (tables), norm_words, covers, f1."""
    h = CORPORA[corpus](spark, sf_dir)
    h.createOrReplaceTempView("headers")
    assembly.truth(h).createOrReplaceTempView("true_tree")
    tree = baselines.infer(h)
    tree.createOrReplaceTempView("tree")
    tree.select("doc_id", "pos", "span_end").createOrReplaceTempView("spans")
    depth.groups(h).createOrReplaceTempView("style_groups")
    depth.local(depth.groups(h)).createOrReplaceTempView("depths")
    outline.render(tree, h).createOrReplaceTempView("outline")
    metrics.topdown(tree.withColumn("approach", F.lit("local")), h, assembly.truth(h), ("local",)).createOrReplaceTempView("metrics_topdown")
    spark.udtf.register("build_tree", BuildTree)
    spark.udtf.register("html_phrases", HtmlPhrases)
    spark.udtf.register("grep_stream", GrepStream)
    # Backslashes are doubled: the SQL parser halves them.
    marks = r"[^\\p{L}\\p{N}\\x20\\x09-\\x0D]"
    words = rf"array_remove(split(trim(regexp_replace(regexp_replace(translate(lower(coalesce(t, '')), '{text.MARKED}', '{text.PLAIN}'), '{marks}', ''), '[\\x20\\x09-\\x0D]+', ' ')), ' '), '')"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION norm_words(t STRING) RETURNS ARRAY<STRING> RETURN {words}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION covers(pos INT, span_end INT, at INT) RETURNS BOOLEAN RETURN pos <= at AND at < span_end")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION f1(a DOUBLE, b DOUBLE, c DOUBLE) RETURNS DOUBLE RETURN CASE WHEN b + c = 0 THEN 1 ELSE 2 * a / (b + c) END")
