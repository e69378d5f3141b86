"""Token totals kept by signed deltas.

Changes come in batches.  A change row has a sign (+1 for what comes, -1 for what goes), the source,
the language, the tokenizer version and a token count; a revised count is the old one going and the
new one coming, which leaves the number of documents as it is.  A batch is summed by source, language
and version, written to a folder of its own, and then published by a row of the ledger: a reader meets
all of a batch or nothing of it, and what a crash leaves unpublished is never read.  An id that the
ledger has is not committed again, so a replay changes nothing.  Totals are the sums over all published
folders.  One writer commits at a time.

Summing is partial before the exchange, so a source with a third of all rows moves a few rows per
task.  ``compact`` writes the totals so far as one folder; the new ledger has the ids of all batches
that went into it, so that their replay changes nothing there either.

Defined cases: null sources, languages and versions are totals of their own; null counts are zero
tokens; keys whose totals are all zero are not shown; no batches give an empty result.  Of the query:
null and empty texts have no tokens and are copies of each other; texts of any length are counted
whole; repeated rows are copies, of which one stays; rows without an id always stay; other columns
are never read.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm.columns import text_of
from outline_engine.llm.storage import materialise, scratch, table
from outline_engine.llm.vocabularies import default_path, rank_file_encoder

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, documents long, tokens long"
VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def changes(counts: DataFrame, tokenizer: str, tokens: Column, sign: int) -> DataFrame:
    """Change rows for documents with columns source and lang."""
    return counts.select(F.lit(sign).alias("sign"), F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.lit(tokenizer).alias("tokenizer"), tokens.cast("long").alias("tokens"))


class Rollup:
    """Batches under a folder of any store that Spark writes to."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root

    def ledger(self) -> list[tuple[int, str]]:
        """Committed batch ids and their folders: a row per batch since the last ``compact``, and one per batch before."""
        try:
            rows = self.spark.read.schema("batch long, folder string").parquet(f"{self.root}/ledger")
            return sorted({(r["batch"], r["folder"]) for r in rows.collect()})
        except AnalysisException as none:
            if "PATH_NOT_FOUND" not in str(none):
                raise
            return []

    def publish(self, batches: list[int], folder: str) -> None:
        self.spark.createDataFrame([(b, folder) for b in batches], "batch long, folder string").coalesce(1).write.mode("append").parquet(f"{self.root}/ledger")

    def commit(self, batch: int, rows: DataFrame) -> bool:
        """Whether the batch was new."""
        if any(batch == known for known, _ in self.ledger()):
            return False
        sums = rows.groupBy(*KEYS).agg(F.sum("sign").cast("long").alias("documents"), F.sum(F.col("sign") * F.coalesce("tokens", F.lit(0))).cast("long").alias("tokens"))
        folder = f"batch-{batch}-{uuid.uuid4().hex}"
        sums.write.parquet(f"{self.root}/{folder}")
        self.publish([batch], folder)
        return True

    def totals(self) -> DataFrame:
        folders = sorted({f"{self.root}/{folder}" for _, folder in self.ledger()})
        deltas = self.spark.read.schema(SCHEMA).parquet(*folders) if folders else self.spark.createDataFrame([], SCHEMA)
        sums = deltas.groupBy(*KEYS).agg(F.sum("documents").alias("documents"), F.sum("tokens").alias("tokens"))
        return sums.where("documents <> 0 OR tokens <> 0")

    def compact(self, root: str) -> Rollup:
        """A rollup under ``root`` with the totals of this one in one folder."""
        made, known = Rollup(self.spark, root), [batch for batch, _ in self.ledger()]
        if known and not made.ledger():
            folder = f"base-{uuid.uuid4().hex}"
            self.totals().write.parquet(f"{root}/{folder}")
            made.publish(known, folder)
        return made


def token_counts(docs: DataFrame, *, vocabulary: str | None = None) -> DataFrame:
    """doc_id, source, lang, digest and n_bytes of the text, n_tokens; a row per row of ``docs``."""
    path = vocabulary or default_path(VOCABULARY)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = rank_file_encoder(path)
        for one in batches:
            n = [len(encoder.encode_ordinary(t.as_py())) for t in one.column("text")]
            yield pa.RecordBatch.from_arrays([one.column(c) for c in kept] + [pa.array(n, type=pa.int64())], names=[*kept, "n_tokens"])

    kept = ["doc_id", "source", "lang", "digest", "n_bytes"]
    text = text_of()
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").cast("string").alias("source"),
        F.col("lang").cast("string").alias("lang"),
        F.sha2(text.cast("binary"), 256).alias("digest"),
        F.octet_length(text).cast("long").alias("n_bytes"),
        text.alias("text"),
    )
    return rows.mapInArrow(run, "doc_id long, source string, lang string, digest string, n_bytes long, n_tokens long")


def op6_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents come, under two tokenizer versions; copies go; counts are revised by an end token; a batch is replayed."""
    counts = materialise(token_counts(table(spark, sf_dir, "documents")), "token-counts")
    # One row of each text stays.  The aggregation is partial, so a text with very many copies is no task of its own.
    row = F.struct("source", "lang", "n_tokens", "n_bytes")
    firsts = counts.where("doc_id IS NOT NULL").groupBy("digest").agg(F.min_by(row, F.struct("doc_id", "source", "lang")).alias("row")).select("row.*")
    left = materialise(firsts.union(counts.where("doc_id IS NULL").select("source", "lang", "n_tokens", "n_bytes")), "token-counts-left")
    rollup = Rollup(spark, scratch(spark, "token-rollup"))

    def both(rows: DataFrame, sign: int) -> DataFrame:
        return changes(rows, "byte_bpe_multi_50k", F.col("n_tokens"), sign).union(changes(rows, "utf8_bytes", F.col("n_bytes"), sign))

    rollup.commit(1, both(counts, 1))
    gone = both(counts, -1).union(both(left, 1))
    rollup.commit(2, gone)
    rollup.commit(3, changes(left, "byte_bpe_multi_50k", F.col("n_tokens"), -1).union(changes(left, "byte_bpe_multi_50k", F.col("n_tokens") + 1, 1)))
    rollup.commit(2, gone)
    return rollup.totals()
