"""Byte-level BPE by higher-order functions: ranked merges folded over the bytes of words.

A text is cut into words by the vocabulary's pattern.  A word's UTF-8 bytes become an array of
one-byte pieces; a fold merges, step by step, the adjacent pair of least rank, looked up in a literal
map of ranks, until no pair has one.  Bytes are held as the characters of the same number, so pieces
are strings.  The literal is an array of small maps by hash, so a look-up reads one or two keys.

The fold runs over every distinct word of the corpus, once.  Texts are cut once, into blocks (see
``blocks``), which ask for the ids of their distinct words part by part; a text's ids are those of its
words in order.  Nothing that grows with the corpus is broadcast or held by a worker, and no text is
moved: blocks are stored in buckets, to which the ids come.  Decoding concatenates the binary pieces of the ids.

A fold copies a word's pieces at every step, so its cost is the square of the word's length.  Words of
over ``LONGEST`` bytes are merged by the same ranks in the same order with a heap instead.

Defined cases: a null or empty text has no ids and decodes to no bytes; a very long text is one block;
repeated rows are encoded alike; null ids of documents are carried; an empty table gives an empty
result; other columns are never read.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm import blocks
from outline_engine.llm.blocks import ANSWER, TEXT, WORDS, Numbers, blob_rows, dealt, of_kind, pack, unpack, unpack_words
from outline_engine.llm.columns import let
from outline_engine.llm.storage import materialise, table
from outline_engine.llm.vocabularies import default_path, read_ranks

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
LONGEST = 1024
_NONE = 2**31 - 1
_RANK_SLOTS = 1 << 16
#: A further kind of rows: a word of a part.
LISTED = 5
#: Blocks hold little more than their distinct words here, of which larger ones have fewer.
BLOCK_TOKENS = 4_000_000
#: White space as Unicode has it, which the pattern's \s means.
_SPACE = r"\t-\r\x20\x85\xA0\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}"

_LATIN_SPACE = "\t-\r\x20\x85\xA0"
_PYTHON_SPACE = re.sub(r"\\x\{(\w+)\}", lambda m: chr(int(m[1], 16)), _SPACE)


def _slot(key: Column, slots: int) -> Column:
    return F.xxhash64(key).bitwiseAND(F.lit(slots - 1)).cast("int")


def _slot_of(key: str, slots: int) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(key.encode(), 42) & (slots - 1)


def rank_literal(ranks: dict[bytes, int]) -> Column:
    slots: list[dict[str, int]] = [{} for _ in range(_RANK_SLOTS)]
    for piece, rank in ranks.items():
        key = piece.decode("latin-1")
        slots[_slot_of(key, _RANK_SLOTS)][key] = rank
    return F.from_json(F.lit(json.dumps(slots)), "array<map<string,int>>")


def folded(word: Column, ranks: Column) -> Column:
    """The ids of a word."""

    def rank(piece: Column) -> Column:
        return F.try_element_at(F.get(ranks, _slot(piece, _RANK_SLOTS)), piece)

    def pair(a: Column, b: Column) -> Column:
        return F.coalesce(rank(F.concat(a, b)), F.lit(_NONE))

    def merged(state: Column, k: Column) -> Column:
        """Pieces k and k+1 become one; the ranks beside it are looked up anew."""
        p, r = state["p"], state["r"]
        whole = F.concat(F.get(p, k - 1), F.get(p, k))
        none = F.array().cast("array<int>")
        before = F.when(k > 1, F.array(pair(F.get(p, k - 2), whole))).otherwise(none)
        after = F.when(k < F.size(r), F.array(pair(whole, F.get(p, k + 1)))).otherwise(none)
        return F.struct(
            F.concat(F.slice(p, 1, k - 1), F.array(whole), F.slice(p, k + 2, F.size(p))).alias("p"),
            F.concat(F.slice(r, 1, F.greatest(k - 2, F.lit(0))), before, after, F.slice(r, k + 2, F.size(r))).alias("r"),
        )

    def step(state: Column, _: Column) -> Column:
        least = F.coalesce(F.array_min(state["r"]), F.lit(_NONE))
        return let(least, lambda m: F.when(m == _NONE, state).otherwise(let(F.array_position(state["r"], m).cast("int"), lambda k: merged(state, k))))

    def fold(p: Column) -> Column:
        first = F.struct(p.alias("p"), F.zip_with(F.slice(p, 1, F.size(p) - 1), F.slice(p, 2, F.size(p)), pair).alias("r"))
        return F.aggregate(F.sequence(F.lit(2), F.greatest(F.size(p), F.lit(2))), first, step, lambda s: F.transform(s["p"], rank))

    def of_bytes(b: Column) -> Column:
        known = rank(b)
        return F.when(known.isNotNull(), F.array(known)).otherwise(let(F.split(b, ""), fold))

    return let(F.decode(F.encode(word, "UTF-8"), "ISO-8859-1"), of_bytes)


def decoded(ids: Column, pieces: Column) -> Column:
    """The bytes of an array of ids; ``pieces``: all pieces by id, as in ``piece_literal``."""
    return F.encode(F.array_join(F.transform(ids, lambda i: F.get(pieces, i)), ""), "ISO-8859-1")


def piece_literal(ranks: dict[bytes, int]) -> Column:
    listed = [""] * (max(ranks.values()) + 1)
    for piece, rank in ranks.items():
        listed[rank] = piece.decode("latin-1")
    return F.from_json(F.lit(json.dumps(listed)), "array<string>")


def python_pattern(pattern: str) -> str:
    """The pattern for Python's engine, whose \\s has four controls too many."""
    return pattern.replace(r"[^\s", f"[^{_PYTHON_SPACE}").replace(r"\s", f"[{_PYTHON_SPACE}]").replace(r"\S", f"[^{_PYTHON_SPACE}]")


def latin_pattern(pattern: str) -> str:
    """The pattern for texts of Latin-1 characters only, with classes that Python's plain engine knows."""

    def those(category: str) -> str:
        return "".join(re.escape(c) for c in map(chr, range(256)) if unicodedata.category(c)[0] == category)

    letters, digits = those("L"), those("N")
    pattern = pattern.replace(r"[^\s\p{L}\p{N}]", f"[^{_LATIN_SPACE}{letters}{digits}]").replace(r"\p{L}", f"[{letters}]").replace(r"\p{N}", f"[{digits}]")
    return pattern.replace(r"\s", f"[{_LATIN_SPACE}]").replace(r"\S", f"[^{_LATIN_SPACE}]")


def cutter(pattern: str) -> Callable[[str], list[str]]:
    whole, latin = python_pattern(pattern), latin_pattern(pattern)
    wide = re.compile("[^\x00-\xff]").search

    def words(text: str) -> list[str]:
        import regex

        return re.findall(latin, text) if wide(text) is None else regex.findall(whole, text)

    return words


def merge(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The ids of a long word: the pair of least rank, the first of equal ones, is taken from a heap; parts are chained."""
    n = len(piece)
    end, before, after = list(range(1, n + 1)), list(range(-1, n - 1)), list(range(1, n + 1))
    heap: list[tuple[int, int, int, int]] = []

    def offer(i: int) -> None:
        j = after[i]
        if j < n and (rank := ranks.get(piece[i : end[j]])) is not None:
            heapq.heappush(heap, (rank, i, end[i], end[j]))

    for i in range(n):
        offer(i)
    while heap:
        _, i, middle, last = heapq.heappop(heap)
        if end[i] != middle or middle >= n or end[middle] != last:
            continue
        end[i], end[middle], after[i] = last, -1, after[middle]
        if last < n:
            before[last] = i
        offer(i)
        if before[i] >= 0:
            offer(before[i])
    found, i = [], 0
    while i < n:
        found.append(ranks[piece[i : end[i]]])
        i = end[i]
    return found


def list_words(rows: DataFrame) -> DataFrame:
    """Of the WORDS ``rows``: LISTED rows, each word of a part once with its number, and ANSWER rows for the blocks (a the numbers of their words); stored."""

    def run(found: pa.Table) -> pa.Table:
        part, numbers, answers = found.column("part")[0].as_py(), Numbers(), []
        for block, a, b in zip(*(found.column(c).to_pylist() for c in ("block", "a", "b")), strict=True):
            words = unpack_words(a, b)
            answers.append((block, ANSWER, part, pack(np.fromiter(map(numbers.__getitem__, words), np.int64, len(words))), None, None, None))
        n = len(numbers)
        listed = blocks.blobs([(None, LISTED, part, None, None, None, None)] * n)
        words = pa.array([w.decode() for w in numbers], type=pa.string())
        told = blocks.blobs(answers)
        return pa.concat_tables(
            pa.Table.from_batches([x.append_column("number", place).append_column("word", w)])
            for x, place, w in ((listed, pa.array(np.arange(n)), words), (told, pa.nulls(len(answers), pa.int64()), pa.nulls(len(answers), pa.string())))
        )

    return materialise(rows.groupBy("part").applyInArrow(run, f"{blocks._BLOB}, number long, word string"), "bpe-words")


def word_ids(words: DataFrame, path: str) -> DataFrame:
    """part, number, ids of the rows part, number, word; stored."""
    literal = rank_literal(read_ranks(path))

    def long(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranks = read_ranks(path)
        for one in batches:
            ids = pa.array([merge(w.as_py().encode(), ranks) for w in one.column("word")], type=pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([one.column("part"), one.column("number"), ids], names=["part", "number", "ids"])

    is_long = F.octet_length("word") > LONGEST
    folds = words.where(~is_long).select("part", "number", let(literal, lambda r: folded(F.col("word"), r)).alias("ids"))
    return materialise(folds.union(words.where(is_long).mapInArrow(long, "part int, number long, ids array<int>")), "bpe-ids")


def gathered(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The pieces of ``flat`` from ``starts`` on, of ``sizes``, one after another."""
    ends = np.cumsum(sizes)
    return flat[np.repeat(starts - (ends - sizes), sizes) + np.arange(ends[-1] if len(ends) else 0)]


def run(docs: DataFrame, *, vocabulary: str | None = None, digests: bool = False) -> DataFrame:
    """Encode and decode: doc_id, ids and decoded bytes, or their number and digests; a row per row of ``docs``."""
    import public_tokenizers

    path = vocabulary or default_path(VOCABULARY)
    parts = blocks.parts_for(docs)
    made = blocks.cut(docs, ["doc_id"], F.lit(False), cutter(public_tokenizers.PATTERN), parts, "bpe-blocks", counted=False, block_tokens=BLOCK_TOKENS, by_block=True)
    listed = list_words(dealt(blob_rows(made, WORDS), "part", parts))
    encoded = word_ids(of_kind(listed, LISTED).select("part", "number", "word"), path)

    def answer(asked: pa.Table, known: pa.Table) -> pa.Table:
        order = np.argsort(known.column("number").to_numpy())
        ids = known.column("ids").combine_chunks()
        flat, ends = ids.flatten().to_numpy(zero_copy_only=False), np.asarray(ids.offsets, dtype=np.int64) - ids.offsets[0].as_py()
        starts, sizes = ends[:-1][order], np.diff(ends)[order]
        rows = []
        for block, part, a in zip(*(asked.column(c).to_pylist() for c in ("block", "part", "a")), strict=True):
            at = unpack(a)
            rows.append((block, ANSWER, part, pack(sizes[at]), pack(gathered(flat, starts[at], sizes[at])), None, None))
        return pa.Table.from_batches([blocks.blobs(rows)])

    asked = dealt(blob_rows(listed, ANSWER), "part", parts)
    answers = asked.groupBy("part").cogroup(dealt(encoded, "part", parts).groupBy("part")).applyInArrow(answer, blocks._BLOB)

    def join(text: pa.Table, found: pa.Table) -> pa.Table:
        stream, lengths = unpack(text.column("a")[0].as_py()), unpack(text.column("b")[0].as_py())
        told = sorted((part, i) for i, part in enumerate(found.column("part").to_pylist()))
        none = [np.zeros(0, np.int64)]
        listed = [unpack(found.column("a")[i].as_py()) for _, i in told]
        stream = blocks.places(stream, parts, [part for part, _ in told], [len(x) for x in listed])
        sizes, flat = np.concatenate(listed or none), np.concatenate([unpack(found.column("b")[i].as_py()) for _, i in told] or none)
        starts = np.cumsum(sizes) - sizes
        ids = gathered(flat, starts[stream], sizes[stream]).astype("<u4")
        ends = np.concatenate([[0], np.cumsum(sizes[stream])])[np.cumsum(lengths)]
        pieces = [piece for piece, _ in sorted(read_ranks(path).items(), key=lambda x: x[1])]
        rows = []
        for i, (begin, end) in enumerate(zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)):
            own = ids[begin:end]
            whole = b"".join(map(pieces.__getitem__, own.tolist()))
            rows.append((i, len(own), hashlib.sha256(own.tobytes()).hexdigest(), hashlib.sha256(whole).hexdigest()) if digests else (i, own.astype(np.int32), whole))
        columns = [pa.array(c, type=t) for c, t in zip(zip(*rows, strict=True), types, strict=True)]
        return pa.Table.from_arrays([pa.array(np.full(len(rows), text.column("block")[0].as_py())), *columns], names=["block", "part", *names])

    types = [pa.int32(), pa.int64(), pa.string(), pa.string()] if digests else [pa.int32(), pa.list_(pa.int32()), pa.binary()]
    names = ["n_tokens", "ids_sha256", "decoded_sha256"] if digests else ["ids", "decoded"]
    schema = "n_tokens long, ids_sha256 string, decoded_sha256 string" if digests else "ids array<int>, decoded binary"
    texts = blob_rows(made, TEXT).groupBy("block")
    whole = texts.cogroup(dealt(answers, "block", parts).groupBy("block")).applyInArrow(join, f"block long, part int, {schema}")
    return of_kind(made, blocks.DOC).select("doc_id", "block", "part").join(whole, ["block", "part"]).select("doc_id", *names)


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run(table(spark, sf_dir, "documents"), digests=True)
