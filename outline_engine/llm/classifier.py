"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

A document's statistics (lengths, character classes, repetition) are put on scales on which classes
look roughly normal.  Training needs per class the count, the sums and the sums of products only:
one aggregation over all labelled rows, two rows to the driver.  A class covariance is shrunk
towards the pooled one (``POOL``) and then towards a multiple of the identity (``RIDGE``).  A score
is the posterior of class 1, from Mahalanobis log-densities with Cholesky factors made once.

Labels, language, source and id are no inputs of a score.

Defined cases: a null or empty text has all statistics zero and is scored like any other; rows whose
label is null or not 0/1 teach nothing; if a class has no training row, every score is the share of
class 1 among the training rows (one half without any); repeated rows count again; rows with a null
id are scored and count as held out; other columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import log, log1p, sqrt
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm.columns import text_of
from outline_engine.llm.storage import materialise, table

FEATURES = ("words", "word_length", "symbols", "capitals", "punctuation", "digits", "distinct", "stutter", "lines")
POOL, RIDGE = 0.1, 0.02
THRESHOLD = 0.3

_SYMBOLS = np.frombuffer(b"#*$%&|<>@^~=_\\/{}[]+`", dtype=np.uint8)
_POINTS = np.frombuffer(b".,;:!?'\"()-", dtype=np.uint8)


def statistics(text: str) -> tuple[float, ...]:
    data = text.encode("utf-8", "surrogatepass")
    words = data.split()
    n = len(words)
    if not n:
        return (0.0,) * len(FEATURES)
    seen = np.bincount(np.frombuffer(data, dtype=np.uint8), minlength=256)
    capitals, small = int(seen[65:91].sum()), int(seen[97:123].sum())
    # A letter outside ASCII is taken for one small letter: its lead byte counts.
    small += int(seen[0xC2:0xF5].sum())
    size = len(data)
    in_words = size - int(seen[9:14].sum()) - int(seen[32])
    # Shares of short texts are drawn towards a usual value, as if so many usual characters followed.
    return (
        log1p(n),
        log((in_words + 50) / (n + 10)),
        sqrt(int(seen[_SYMBOLS].sum()) / (size + 20)),
        sqrt((capitals + 4) / (capitals + small + 100)),
        sqrt((int(seen[_POINTS].sum()) + 3) / (size + 100)),
        sqrt(int(seen[48:58].sum()) / (size + 100)),
        log1p(len(set(words)) + 50) / log1p(n + 50),
        sqrt(sum(map(eq, words, words[1:])) / (n + 10)),
        sqrt((int(seen[10]) + 1) / (size + 100)),
    )


def with_statistics(docs: DataFrame) -> DataFrame:
    """doc_id and x, the statistics, a row per row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            made = np.array([statistics(t.as_py()) for t in one.column("text")], dtype=np.float64)
            x = pa.ListArray.from_arrays(pa.array(range(0, made.size + 1, len(FEATURES)), type=pa.int32()), pa.array(made.ravel())) if made.size else pa.array([], type=pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([one.column("doc_id"), x], names=["doc_id", "x"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(run, "doc_id long, x array<double>")


@dataclass(frozen=True)
class Discriminant:
    """Per class: log prior, mean, inverse Cholesky factor and log-determinant, on standardised inputs."""

    centre: np.ndarray
    scale: np.ndarray
    classes: tuple[tuple[float, np.ndarray, np.ndarray, float], ...]
    share: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        if len(self.classes) < 2:
            return np.full(len(x), self.share)
        z = (x - self.centre) / self.scale
        density = [prior - 0.5 * (((z - mean) @ factor.T) ** 2).sum(axis=1) - 0.5 * size for prior, mean, factor, size in self.classes]
        return 1.0 / (1.0 + np.exp(np.clip(density[0] - density[1], -700, 700)))


def fit(labelled: DataFrame) -> Discriminant:
    """``labelled``: x and label.  All rows count; the sums are exact whatever the number of rows."""
    d = len(FEATURES)
    cells = [F.get("x", F.lit(i)) for i in range(d)]
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    sums = [F.sum(cells[i]).alias(f"s{i}") for i in range(d)] + [F.sum(cells[i] * cells[j]).alias(f"p{i}_{j}") for i, j in pairs]
    found = {}
    for row in labelled.where("label IN (0, 1)").groupBy("label").agg(F.count("*").alias("n"), *sums).collect():
        product = np.zeros((d, d))
        for i, j in pairs:
            product[i, j] = product[j, i] = row[f"p{i}_{j}"]
        found[int(row["label"])] = (row["n"], np.array([row[f"s{i}"] for i in range(d)]), product)
    total = sum(n for n, _, _ in found.values())
    share = found[1][0] / total if 1 in found else (0.0 if total else 0.5)
    if len(found) < 2:
        return Discriminant(np.zeros(d), np.ones(d), (), share)
    centre = sum(s for _, s, _ in found.values()) / total
    spread = sum(np.diag(p) for _, _, p in found.values()) / total - centre**2
    scale = np.sqrt(np.maximum(spread, 1e-12))
    scatter, means = {}, {}
    for k, (n, s, p) in found.items():
        mean = s / n
        means[k] = (mean - centre) / scale
        scatter[k] = (p / n - np.outer(mean, mean)) / np.outer(scale, scale)
    pooled = sum(found[k][0] * scatter[k] for k in found) / total
    classes = []
    for k in (0, 1):
        cov = (1 - POOL) * scatter[k] + POOL * pooled
        cov = (1 - RIDGE) * cov + RIDGE * max(np.trace(cov) / d, 1e-6) * np.eye(d)
        factor = np.linalg.cholesky(cov)
        classes.append((log(found[k][0] / total), means[k], np.linalg.inv(factor), 2 * float(np.log(np.diag(factor)).sum())))
    return Discriminant(centre, scale, tuple(classes), share)


def with_scores(features: DataFrame, model: Discriminant, kept: list[str]) -> DataFrame:
    """The ``kept`` columns of ``features`` and score, from column x."""
    schema = ", ".join(f"{c} {features.schema[c].dataType.simpleString()}" for c in kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            x = one.column("x").flatten().to_numpy(zero_copy_only=False).reshape(one.num_rows, len(FEATURES))
            yield pa.RecordBatch.from_arrays([*(one.column(c) for c in kept), pa.array(model.scores(x))], names=[*kept, "score"])

    return features.select(*kept, "x").mapInArrow(run, f"{schema}, score double")


def held_out(doc_id: str = "doc_id") -> Column:
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def learn(features: DataFrame, labels: DataFrame) -> Discriminant:
    """Fit on the labelled rows that are not held out."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label"))
    return fit(features.where(~held_out()).join(known, "doc_id").select("x", "label"))


def op7_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    features = materialise(with_statistics(table(spark, sf_dir, "documents")), "quality-statistics")
    model = learn(features, table(spark, sf_dir, "labels"))
    scored = with_scores(features, model, ["doc_id"])
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_predicted(docs: DataFrame, model: Discriminant) -> DataFrame:
    """The rows of ``docs`` that the model takes for class 1, in one pass over the texts."""
    whole = docs.select(text_of().alias("text"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    schema = f"row {whole.schema['row'].dataType.simpleString()}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            x = np.array([statistics(t.as_py()) for t in one.column("text")], dtype=np.float64).reshape(one.num_rows, len(FEATURES))
            yield pa.RecordBatch.from_arrays([one.column("row")], names=["row"]).filter(pa.array(model.scores(x) >= THRESHOLD))

    return whole.mapInArrow(run, schema).select("row.*")
