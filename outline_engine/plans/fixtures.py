"""Small documents with known trees: a filing excerpt and the two documents that tell local from global; the same patterns in the ledgers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.operators import metrics
from outline_engine.plans import sql_twins as sql
from outline_engine.schemas import HEADERS
from outline_engine.sources.corpora import CORPORA
from outline_engine.sources.sinks import stored

#: positions, style groups, true parents; the last position's span ends at ``end``.
DOCUMENTS = {
    "filing": {"pos": (1, 10, 12, 16, 20, 22), "style": (1, 2, 3, 2, 4, 5), "parent": (None, 1, 10, 1, 16, 16)},
    "local_only": {"pos": (1, 2, 3, 4, 5, 6, 7), "style": (1, 2, 3, 4, 2, 5, 4), "parent": (None, 1, 2, 3, 1, 5, 6)},
    "global_only": {"pos": (1, 2, 3, 4, 5, 6, 7, 8, 9), "style": (1, 2, 3, 4, 2, 5, 3, 4, 5), "parent": (None, 1, 2, 3, 1, 5, 5, 7, 8)},
}
#: Parents by method.
PARENTS = {
    ("filing", "local"): (None, 1, 10, 1, 16, 20),
    ("filing", "global"): (None, 1, 10, 1, 16, 20),
    ("filing", "half"): (None, 1, 10, 1, 16, 20),
    ("local_only", "local"): (None, 1, 2, 3, 1, 5, 6),
    ("local_only", "global"): (None, 1, 2, 3, 1, 5, 5),
    ("local_only", "half"): (None, 1, 2, 3, 1, 5, 5),
    ("global_only", "local"): (None, 1, 2, 3, 1, 5, 5, 7, 5),
    ("global_only", "global"): (None, 1, 2, 3, 1, 5, 5, 7, 8),
    ("global_only", "half"): (None, 1, 2, 3, 1, 5, 5, 7, 7),
}


def headers(spark: SparkSession, name: str) -> DataFrame:
    doc = DOCUMENTS[name]
    ranks: dict = {}
    for p, up in zip(doc["pos"], doc["parent"], strict=True):
        ranks[p] = 0 if up is None else ranks[up] + 1
    rows = [(1, p, f"S{s}", ranks[p], f"header {p}", 1) for p, s in zip(doc["pos"], doc["style"], strict=True)]
    return spark.createDataFrame(rows, HEADERS)


#: The ledger that carries each pattern: sections of several styles under one parent, styles that only local-first and
#: styles that only global-first puts right.
LEDGERS = {"filing": "all", "local_only": "parity", "global_only": "memo"}
METHODS = ("local", "global", "half")


def query(spark: SparkSession, sf_dir: str, *, name: str) -> DataFrame:
    """doc_id, pos and the parent under each method, on the ledger with the pattern of the fixture."""
    trees = metrics.all_trees(stored(CORPORA[LEDGERS[name]](spark, sf_dir).select("doc_id", "pos", "style")), METHODS)
    return trees.groupBy("doc_id", "pos").agg(*[F.max(F.when(F.col("approach") == m, F.col("parent_pos"))).alias(m) for m in METHODS])


def oracle(name: str) -> str:
    joins = " ".join(f"JOIN {m}_t USING (doc_id, pos)" for m in METHODS[1:])
    parents = ", ".join(f'{m}_t.parent_pos AS "{m}"' for m in METHODS)
    return f"WITH RECURSIVE {sql.CORPORA[LEDGERS[name]]},{sql.trees(*METHODS)} SELECT doc_id, pos, {parents} FROM {METHODS[0]}_t {joins}"
