"""Blocks of tokenised documents, whose distinct words are looked up part by part.

A reading task cuts its documents into blocks of about ``BLOCK_TOKENS`` tokens.  A block keeps its
token stream as codes of its own distinct words; the list of these is dealt to parts by a hash of the
word, frequent ones first.  A word's code is its rank in the part's list, times the number of parts,
plus the part, so frequent words have small codes.  What a part finds out about its words goes back to
the blocks as columns in the order of the list, so no dictionary of the corpus is ever in one place, and
a word that a block has a million times travels once.  The number of parts follows the bytes of text: a
part's share is bounded, a worker holds one block or one part at a time.

Columns of numbers are packed: as many byte planes as the largest needs, compressed.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from outline_engine.llm.columns import text_of
from outline_engine.llm.storage import bucketed, materialise

BLOCK_TOKENS = 1_500_000
#: Bytes of text for a part.
PART_BYTES = 8 << 20
#: Exchanges have as many partitions as there are parts, up to this number.
MOST_TASKS = 20_000
#: Kinds of rows: a document, a block's token stream, a block's words of a part.
DOC, TEXT, WORDS = 0, 1, 2
#: Of later tables: a part's answer to a block.
ANSWER = 3
_BLOB = "block long, kind int, part int, a binary, b binary, c binary, d binary"
_NAMES = ("block", "kind", "part", "a", "b", "c", "d")
_TYPES = (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary())


def pack(x: np.ndarray) -> bytes:
    """Whole numbers from 0 up."""
    import zstandard

    width = max(1, (int(x.max()).bit_length() + 7) // 8) if len(x) else 1
    planes = x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T
    return bytes([width]) + zstandard.ZstdCompressor(level=3).compress(planes.tobytes())


def unpack(packed: bytes) -> np.ndarray:
    import zstandard

    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(packed[1:]), np.uint8).reshape(packed[0], -1)
    x = np.zeros((planes.shape[1], 8), np.uint8)
    x[:, : packed[0]] = planes.T
    return x.view("<i8").ravel()


def pack_words(words: list[bytes]) -> tuple[bytes, bytes]:
    import zstandard

    return zstandard.ZstdCompressor(level=3).compress(b"".join(words)), pack(np.fromiter(map(len, words), np.int64, len(words)))


def unpack_words(data: bytes, lengths: bytes) -> list[bytes]:
    import zstandard

    whole = zstandard.ZstdDecompressor().decompress(data)
    ends = np.cumsum(unpack(lengths)).tolist()
    return [whole[i:j] for i, j in zip([0, *ends], ends, strict=False)]


def places(codes: np.ndarray, parts: int, listed: list[int], sizes: list[int]) -> np.ndarray:
    """Where the words of ``codes`` stand in a block's lists one after another: those of the parts ``listed``, of ``sizes`` words."""
    begins = np.zeros(max(listed, default=0) + 1, np.int64)
    begins[listed] = np.cumsum(sizes, dtype=np.int64) - np.array(sizes, dtype=np.int64)
    return begins[codes % parts] + codes // parts


def parts_for(docs: DataFrame) -> int:
    total = docs.agg(F.sum(F.octet_length(text_of()))).first()[0] or 0
    return max(1, total // PART_BYTES + 1)


def dealt(rows: DataFrame, key: str, parts: int) -> DataFrame:
    """Rows dealt by ``key``, for a grouped map.  The number is given so that small blobs of much work are not put together."""
    return rows.repartition(min(parts, MOST_TASKS), key)


class Numbers(dict):
    """Words to numbers in the order in which they are met."""

    def __missing__(self, word) -> int:
        self[word] = n = len(self)
        return n


def blobs(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [()] * len(_NAMES)
    return pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(columns, _TYPES, strict=True)], names=list(_NAMES))


def cut(docs: DataFrame, kept: list[str], flag: Column, tokens: Callable[[str], list], parts: int, name: str, *, counted: bool = True, block_tokens: int | None = None, by_block: bool = False) -> DataFrame:
    """Stored rows of three kinds.

    DOC: the ``kept`` columns, block and part (here the number of the document in its block).
    TEXT: block, a the codes of its tokens, b the number of tokens of each document, c its flag.
    WORDS: block, part, a and b the part's words, if ``counted`` c how often each occurs, d how often in flagged documents.
    With ``by_block`` they are stored in buckets by block, as many as ``dealt`` gives partitions.
    """
    schema = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in kept)
    bound = block_tokens or BLOCK_TOKENS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get().partitionId() << 32
        made, numbers, held, lengths, flags, size, heads = 0, Numbers(), [], [], [], 0, []

        def widened(batch: pa.RecordBatch, own: dict) -> pa.RecordBatch:
            n = batch.num_rows
            return pa.RecordBatch.from_arrays([*(own.get(c, None) if c in own else pa.nulls(n, types[c]) for c in kept), *batch.columns], names=[*kept, *_NAMES])

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal made, numbers, held, lengths, flags, size, heads
            block, made = task + made, made + 1
            yield from heads
            words = [w if isinstance(w, bytes) else w.encode("utf-8", "surrogatepass") for w in numbers]
            part = np.fromiter(map(zlib.crc32, words), np.int64, len(words)) % parts
            stream = np.concatenate(held) if held else np.zeros(0, np.int32)
            marked = np.repeat(np.array(flags, dtype=bool), lengths)
            every, some = np.bincount(stream, minlength=len(words)), np.bincount(stream[marked], minlength=len(words))
            # Words of equal count, most of them, stand by their bytes, so that neighbours share their beginnings.
            order = np.array(sorted(range(len(words)), key=words.__getitem__), dtype=np.int64)
            order = order[np.lexsort((-every[order], part[order]))]
            cuts = np.flatnonzero(np.diff(part[order], prepend=-1, append=-1))
            codes = np.empty_like(order)
            codes[order] = (np.arange(len(order)) - np.repeat(cuts[:-1], np.diff(cuts))) * parts + part[order]
            rows = [(block, TEXT, None, pack(codes[stream]), pack(np.array(lengths, dtype=np.int64)), pack(np.array(flags, dtype=np.int64)), None)]
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                of = order[i:j]
                rows.append((block, WORDS, int(part[of[0]]), *pack_words([words[k] for k in of]), *((pack(every[of]), pack(some[of])) if counted else (None, None))))
            yield widened(blobs(rows), {})
            numbers, held, lengths, flags, size, heads = Numbers(), [], [], [], 0, []

        types: dict = {}
        for batch in batches:
            types = {c: batch.schema.field(c).type for c in kept}
            for begin in range(0, batch.num_rows, 1000):
                one = batch.slice(begin, 1000)
                first = len(lengths)
                for text, marked in zip(one.column("__text"), one.column("__flag"), strict=True):
                    found = tokens(text.as_py())
                    held.append(np.fromiter(map(numbers.__getitem__, found), np.int32, len(found)))
                    lengths.append(len(found))
                    flags.append(bool(marked.as_py()))
                    size += len(found)
                head = blobs([(task + made, DOC, i, None, None, None, None) for i in range(first, len(lengths))])
                heads.append(widened(head, {c: one.column(c) for c in kept}))
                if size >= bound:
                    yield from flush()
        if lengths:
            yield from flush()

    rows = docs.select(*kept, text_of().alias("__text"), flag.alias("__flag")).mapInArrow(run, f"{schema}, {_BLOB}")
    return bucketed(rows, name, "block", min(parts, MOST_TASKS)) if by_block else materialise(rows, name)


def of_kind(rows: DataFrame, kind: int) -> DataFrame:
    return rows.where(F.col("kind") == kind)


def blob_rows(rows: DataFrame, *kinds: int) -> DataFrame:
    return rows.where(F.col("kind").isin(*kinds)).select(*_NAMES)
