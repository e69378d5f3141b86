"""Packing of tokenised documents into fixed windows by the online sum-of-squares rule.

Each task packs its own documents in the order in which it reads them, in one pass and without a
shuffle.  A level array counts, for every fill level, the partially filled windows at that level.
A document longer than a window is cut into whole windows; what is left goes to the level (or to a
new window) for which the sum of the squared counts grows least.  Ties take the fullest level.

Windows still open when a task ends, or when more than ``MAX_OPEN`` are open, are closed together:
pieces of the emptiest are cut to fill the fullest, so a task leaves one padded window at most.

Defined cases: a null or empty text is a document of the end id alone; repeated rows are documents
of their own; a null id is carried as null; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm.storage import table
from outline_engine.llm.vocabularies import default_path, slices, word_memo_encoder

CAPACITY = 2048
END_ID = 1
MAX_OPEN = 4096
#: Sequence ids of a task start at its partition's number times this.
IDS_PER_TASK = 1 << 36
_ROWS = 20_000


class LevelPacker:
    """Sum-of-squares packing.  ``close`` gets the pieces of each finished window, in order."""

    def __init__(self, capacity: int, close: Callable[[list], None], max_open: int = MAX_OPEN):
        self.capacity, self.close, self.max_open = capacity, close, max_open
        self.counts = np.zeros(capacity + 1, dtype=np.int64)
        self.windows: list[list[list]] = [[] for _ in range(capacity + 1)]
        self.open = 0

    def add(self, doc, ids: bytes) -> None:
        """``ids``: the document's little-endian 32-bit ids, its end id included."""
        total, whole = len(ids) // 4, len(ids) // 4 // self.capacity * self.capacity
        for start in range(0, whole, self.capacity):
            self.close([(doc, start, ids[4 * start : 4 * (start + self.capacity)], total)])
        if whole < total:
            self._place((doc, whole, ids[4 * whole :], total), total - whole)

    def _place(self, piece: tuple, size: int) -> None:
        counts, top = self.counts, self.capacity - size
        level, least = 0, 2 * int(counts[size]) + 1
        if self.open and top:
            here = counts[1 : top + 1]
            growth = 2 * (counts[1 + size : self.capacity + 1] - here + 1)
            growth[-1] -= 1  # a full window is counted no more
            growth[here == 0] = np.iinfo(np.int64).max
            best = top - 1 - int(np.argmin(growth[::-1]))
            if growth[best] <= least:
                level = best + 1
        if level:
            window = self.windows[level].pop()
            counts[level] -= 1
        else:
            window = []
            self.open += 1
        window.append(piece)
        if level + size == self.capacity:
            self.open -= 1
            self.close(window)
            return
        self.windows[level + size].append(window)
        counts[level + size] += 1
        if self.open > self.max_open:
            self.finish()

    def finish(self) -> None:
        """Close all open windows; all but one become full by cutting pieces of the emptiest."""
        rest = [(level, w) for level in range(self.capacity - 1, 0, -1) for w in self.windows[level]]
        self.windows = [[] for _ in range(self.capacity + 1)]
        self.counts[:] = 0
        self.open = 0
        first, last = 0, len(rest) - 1
        while first <= last:
            level, window = rest[first]
            while level < self.capacity and last > first:
                left, donor = rest[last]
                doc, start, ids, total = donor.pop()
                room = self.capacity - level
                if len(ids) // 4 > room:
                    donor.append((doc, start + room, ids[4 * room :], total))
                    ids = ids[: 4 * room]
                window.append((doc, start, ids, total))
                level += len(ids) // 4
                rest[last] = (left - len(ids) // 4, donor)
                if not donor:
                    last -= 1
            self.close(window)
            first += 1


def pack(docs: DataFrame, *, capacity: int = CAPACITY, tokenizer: str | None = None, end_id: int = END_ID, emit_ids: bool = False) -> DataFrame:
    """One row per piece of ``docs`` (``doc_id``, ``text``); with ``emit_ids`` also the ids themselves.

    ``sequence_id`` and ``offset`` say where the piece lies; the offsets of a sequence have no gaps.
    """
    path = tokenizer or default_path("word_bpe_49k.json")
    id_type = docs.schema["doc_id"].dataType.simpleString()
    fields = f"doc_id {id_type}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + (", ids array<int>" if emit_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = word_memo_encoder(path)
        end = int(end_id).to_bytes(4, "little")
        first = TaskContext.get().partitionId() * IDS_PER_TASK
        rows: list[tuple] = []
        made = [0]

        def close(window: list) -> None:
            offset, sequence = 0, first + made[0]
            made[0] += 1
            for doc, start, ids, total in window:
                length = len(ids) // 4
                row = (doc, start, length, zlib.crc32(ids), total, sequence, offset)
                rows.append((*row, np.frombuffer(ids, "<i4")) if emit_ids else row)
                offset += length

        def batch() -> pa.RecordBatch:
            columns = list(zip(*rows, strict=True))
            rows.clear()
            arrays = [pa.array(columns[0], type=id_arrow)] + [pa.array(c, type=pa.int64()) for c in columns[1:7]]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            if emit_ids:
                arrays.append(pa.array(columns[7], type=pa.list_(pa.int32())))
                names.append("ids")
            return pa.RecordBatch.from_arrays(arrays, names=names)

        packer = LevelPacker(capacity, close)
        id_arrow = pa.int64()
        for one in batches:
            id_arrow = one.schema.field("doc_id").type
            docs_, texts = one.column("doc_id").to_pylist(), [t or "" for t in one.column("text").to_pylist()]
            for i, j in slices(texts):
                for doc, ids in zip(docs_[i:j], encoder.encode(texts[i:j]), strict=True):
                    packer.add(doc, ids + end)
                if len(rows) >= _ROWS:
                    yield batch()
        packer.finish()
        if rows:
            yield batch()

    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(run, fields)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
