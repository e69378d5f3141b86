"""Language-model scores: a Katz backoff trigram model with Good-Turing discounts over the full vocabulary.

Tokens are lower-cased (A-Z) words and an end mark; two start marks are context only.  A count r of at
most ``KNOWN_RELIABLE`` is discounted by Good-Turing's ratio in Katz' form, order by order.  What this
takes from the followers of a context goes to the words not seen after it, in proportion to their
probability one order lower, with a weight that makes the probabilities after each context add up to
one exactly.  A context without discounted mass has half a count added for the unseen ones.  Below the
unigrams stands one class of all words never seen in training, with what the unigrams leave.

Every word has a number of its own: none is merged with others and none is left out.  Texts are read
once, into blocks (see ``blocks``).  The word table numbers and counts the distinct words of all blocks.
Then each block asks for its distinct trigrams, dealt by their middle word: in its part are all trigrams
around it, hence its bigrams too, and the counts of both contexts.  The counts are stored by part;
probabilities are evaluated recursively from there, trigram from bigram from unigram, and go back to
the blocks in the order in which they asked, where they are added up by document.

A middle word with more than ``HOT_TOKENS`` occurrences is split over several parts by the word before
it.  Its bigrams are then summed over these parts in a table of their own, and each part gets those it has.

Defined cases: a null or empty text has the end mark alone; rows are scored one by one, repeated ids or
not; a null id counts as the text "" for the split; a very long text is one block; without any training
row every token is of the unseen class, whose probability is one; an empty table gives an empty result;
columns other than those kept are never read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm import blocks
from outline_engine.llm.blocks import TEXT, WORDS, Numbers, blob_rows, dealt, of_kind, pack, pack_words, unpack, unpack_words
from outline_engine.llm.storage import materialise, table

KNOWN_RELIABLE = 5
HOT_TOKENS = 2_000_000
#: A word that no text has stands for the end mark; number 0 is the start mark.
END_MARK = b" "
START = 0
#: Further kinds of rows: a part's answers about words and about trigrams, its word table.
NUMBERED, SCORED, TABLE = blocks.ANSWER, 4, 5
_MIX = np.uint64(0x9E3779B97F4A7C15)


def words(text: str) -> list[bytes]:
    return [*text.encode("utf-8", "surrogatepass").lower().split(), END_MARK]


def discounts(counts_of_counts: dict[int, int]) -> np.ndarray:
    """Katz' Good-Turing ratios for r = 0 .. KNOWN_RELIABLE; all others are 1.

    Where the counts of counts give no ratio between 0 and 1, absolute discounting of n1/(n1+2 n2) stands in.
    """
    k = KNOWN_RELIABLE
    n = [counts_of_counts.get(r, 0) for r in range(k + 2)]
    ratios = np.ones(k + 1)
    common = (k + 1) * n[k + 1] / n[1] if n[1] else 1.0
    least = n[1] / (n[1] + 2 * n[2]) if n[1] else 0.0
    for r in range(1, k + 1):
        ratio = ((r + 1) * n[r + 1] / n[r] / r - common) / (1 - common) if n[r] and common < 1 else 0.0
        ratios[r] = ratio if 0 < ratio < 1 else 1 - least / r
    return ratios


def discounted(counts: np.ndarray, ratios: np.ndarray) -> np.ndarray:
    return counts * np.where(counts <= KNOWN_RELIABLE, ratios[np.minimum(counts, KNOWN_RELIABLE)], 1.0)


def small_counts(counts: np.ndarray) -> list[int]:
    """How many of ``counts`` are 1, 2, .. KNOWN_RELIABLE + 1."""
    return np.bincount(counts[counts <= KNOWN_RELIABLE + 1], minlength=KNOWN_RELIABLE + 2)[1:].tolist()


@dataclass
class Unigrams:
    """What every part needs of the word table: sums, discounts, and the hot middle words with their parts."""

    tokens: int
    types: int
    ratios: np.ndarray
    unseen: float
    hot: np.ndarray
    hot_first: np.ndarray
    hot_parts: np.ndarray

    def share(self, counts: np.ndarray) -> np.ndarray:
        return np.where(counts > 0, discounted(counts, self.ratios) / (self.tokens + 0.5), self.unseen)


@dataclass
class Model:
    """``words`` and ``grams`` are stored tables, a row per part."""

    unigrams: Unigrams
    words: DataFrame
    grams: DataFrame
    two: np.ndarray
    three: np.ndarray


def number_words(rows: DataFrame, parts: int) -> DataFrame:
    """Of the WORDS rows of all blocks: NUMBERED rows (a numbers, b training counts) and a TABLE row a part (a and b words, c training counts, d the numbers), with its sums; stored.

    Numbers follow the counts within a part, so that frequent words have small ones.
    """

    def run(found: pa.Table) -> Iterator[pa.RecordBatch]:
        part, numbers, places, every, some = found.column("part")[0].as_py(), Numbers(), [], [], []
        columns = [found.column(c).to_pylist() for c in "abcd"]
        for a, b, c, d in zip(*columns, strict=True):
            listed = unpack_words(a, b)
            places.append(np.fromiter(map(numbers.__getitem__, listed), np.int64, len(listed)))
            every.append(unpack(c))
            some.append(unpack(d))
        place = np.concatenate(places)
        n, c = (np.bincount(place, np.concatenate(x), len(numbers)).astype(np.int64) for x in (every, some))
        order = np.lexsort((np.arange(len(n)), -c, -n))
        ids = np.empty_like(order)
        ids[order] = 1 + np.arange(len(order)) * parts + part
        rows = [(b, NUMBERED, part, pack(ids[p]), pack(c[p]), None, None) for b, p in zip(found.column("block").to_pylist(), places, strict=True)]
        rows.append((None, TABLE, part, *pack_words(list(numbers)), pack(c), pack(ids)))
        often = np.flatnonzero(n > HOT_TOKENS)
        sums = {"tokens": int(c.sum()), "types": int((c > 0).sum()), "small": small_counts(c), "often": ids[often].tolist(), "often_n": n[often].tolist()}
        made = blobs_with(rows, sums)
        for i in range(0, made.num_rows, 1000):
            yield made.slice(i, 1000)

    def blobs_with(rows: list[tuple], sums: dict) -> pa.RecordBatch:
        made = blocks.blobs(rows)
        wide = [pa.array([None] * (len(rows) - 1) + [sums[k]], type=t) for k, t in zip(sums, (pa.int64(), pa.int64(), *[pa.list_(pa.int64())] * 3), strict=True)]
        return pa.RecordBatch.from_arrays([*made.columns, *wide], names=[*made.schema.names, *sums])

    schema = f"{blocks._BLOB}, tokens long, types long, small array<long>, often array<long>, often_n array<long>"
    return materialise(dealt(rows, "part", parts).groupBy("part").applyInArrow(lambda found: pa.Table.from_batches(run(found)), schema), "lm-words")


def sum_words(numbered: DataFrame, parts: int) -> Unigrams:
    rows = of_kind(numbered, TABLE)
    sums = rows.agg(F.sum("tokens").alias("n"), F.sum("types").alias("v"), *[F.sum(F.get("small", F.lit(i))).alias(f"n{i + 1}") for i in range(KNOWN_RELIABLE + 1)]).first()
    ratios = discounts({i + 1: sums[f"n{i + 1}"] or 0 for i in range(KNOWN_RELIABLE + 1)})
    tokens, types = sums["n"] or 0, sums["v"] or 0
    taken = sum((sums[f"n{r}"] or 0) * r * (1 - ratios[r]) for r in range(1, KNOWN_RELIABLE + 1))
    unseen = (taken + 0.5) / (tokens + 0.5)
    hot = sorted((i, n) for r in rows.where(F.size("often") > 0).select("often", "often_n").collect() for i, n in zip(r["often"], r["often_n"], strict=True))
    each = np.array([-(-n // HOT_TOKENS) for _, n in hot], dtype=np.int64)
    return Unigrams(tokens, types, ratios, unseen, np.array([i for i, _ in hot], dtype=np.int64), parts + np.cumsum(each) - each, each)


def sorted_by(*columns: np.ndarray) -> np.ndarray:
    """The order by the columns, the first before the second; numbers are put side by side where they fit in 63 bits."""
    widths = [int(c.max()).bit_length() if len(c) else 0 for c in columns]
    if sum(widths) > 63:
        return np.lexsort(columns[::-1])
    key = np.zeros(len(columns[0]), np.int64)
    for c, w in zip(columns, widths, strict=True):
        key = (key << w) | c
    return np.argsort(key)


def starts_of(*columns: np.ndarray) -> np.ndarray:
    """Whether a row of sorted columns differs from the one before."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return new


@dataclass
class Block:
    """A block's trigrams: distinct ones in order of (middle, first, last word), and where its tokens are among them."""

    lengths: np.ndarray
    known: np.ndarray
    counts: np.ndarray
    order: np.ndarray
    of_token: np.ndarray
    middle: np.ndarray
    first: np.ndarray
    last: np.ndarray
    n: np.ndarray
    last_count: np.ndarray
    part: np.ndarray


def read_block(found: pa.Table, unigrams: Unigrams, parts: int) -> Block | None:
    """``found``: a block's TEXT and NUMBERED rows, in any order, with others."""
    kinds = found.column("kind").to_pylist()
    if TEXT not in kinds:
        return None
    at = kinds.index(TEXT)
    stream, lengths, flags = (unpack(found.column(c)[at].as_py()) for c in "abc")
    answers = sorted((found.column("part")[i].as_py(), i) for i, k in enumerate(kinds) if k == NUMBERED)
    none = [np.zeros(0, np.int64)]
    told = [unpack(found.column("a")[i].as_py()) for _, i in answers]
    stream = blocks.places(stream, parts, [part for part, _ in answers], [len(x) for x in told])
    ids = np.concatenate(told or none)
    counts = np.concatenate([unpack(found.column("b")[i].as_py()) for _, i in answers] or none)
    # Words by their numbers; the start mark is number 0 of both.
    by_id = np.argsort(ids)
    small = np.empty(len(ids), np.int32)
    small[by_id] = np.arange(1, len(ids) + 1)
    number, count = np.concatenate([[START], ids[by_id]]), np.concatenate([[0], counts[by_id]])
    w3 = small[stream]
    w2, w1 = np.roll(w3, 1), np.roll(w3, 2)
    begins = np.cumsum(lengths) - lengths
    w2[begins] = w1[begins] = 0
    w1[(begins + 1)[lengths > 1]] = 0
    order = sorted_by(w2, w1, w3)
    s2, s1, s3 = w2[order], w1[order], w3[order]
    new = starts_of(s2, s1, s3)
    starts = np.flatnonzero(new)
    marked = np.repeat(flags, lengths)[order]
    n = np.add.reduceat(marked, starts) if len(starts) else marked
    middle, first, last = number[s2[starts]], number[s1[starts]], number[s3[starts]]
    hashed = lambda x: ((x.astype(np.uint64) * _MIX) >> np.uint64(33)).astype(np.int64)
    part = hashed(middle) % parts
    if len(unigrams.hot):
        place = np.minimum(np.searchsorted(unigrams.hot, middle), len(unigrams.hot) - 1)
        split = unigrams.hot[place] == middle
        part = np.where(split, unigrams.hot_first[place] + hashed(first) % unigrams.hot_parts[place], part)
    return Block(lengths, counts[stream] > 0, counts[stream], order, np.cumsum(new) - 1, middle, first, last, n, count[s3[starts]], part)


def by_part(part: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(part, kind="stable")
    cuts = np.flatnonzero(np.diff(part[order], prepend=-1, append=-1))
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        yield int(part[order[i]]), order[i:j]


_ASK = ("middle", "first", "last", "n", "counts")


def steps(x: np.ndarray, new: np.ndarray) -> np.ndarray:
    """Numbers that ascend within runs, as differences; ``new`` marks where runs begin."""
    return x - np.where(new, 0, np.concatenate([[0], x[:-1]]))


def climbed(d: np.ndarray, new: np.ndarray) -> np.ndarray:
    """The numbers of ``steps``."""
    whole = np.cumsum(d)
    starts = np.flatnonzero(new)
    return whole - np.repeat((whole - d)[starts], np.diff(starts, append=len(d)))


def packed_grams(middle: np.ndarray, first: np.ndarray, last: np.ndarray, n: np.ndarray, last_count: np.ndarray) -> list[bytes]:
    """Trigrams in order, their counts, and the counts of their distinct last words."""
    at = np.unique(last, return_index=True)[1]
    return [pack(np.diff(middle, prepend=0)), pack(steps(first, starts_of(middle))), pack(last), pack(n), pack(last_count[at])]


def unpacked_grams(packed: list[bytes]) -> tuple[np.ndarray, ...]:
    d, first, last, n, counts = map(unpack, packed)
    middle = np.cumsum(d)
    return middle, climbed(first, starts_of(middle)), last, n, counts[np.unique(last, return_inverse=True)[1]]


def count_grams(asked: DataFrame) -> DataFrame:
    """A row per part: its distinct trigrams and their training counts, how many counts are small, and where each block's requests are among them; stored.

    ``hot``: the part has some of one middle word's trigrams; ``small2`` is then null.
    """

    def run(found: pa.Table) -> pa.Table:
        grams = [unpacked_grams(x) for x in zip(*(found.column(c).to_pylist() for c in _ASK), strict=True)]
        sizes = [len(x[0]) for x in grams]
        columns = [np.concatenate(x) for x in zip(*grams, strict=True)]
        del grams
        listed, rank = np.unique(columns[0], return_inverse=True)
        order = sorted_by(rank, columns[1], columns[2])
        new = starts_of(*(c[order] for c in (rank, columns[1], columns[2])))
        starts = np.flatnonzero(new)
        first, last, last_count = (columns[i][order][starts] for i in (1, 2, 4))
        n = np.add.reduceat(columns[3][order], starts)
        rank = rank[order][starts]
        place = np.empty(len(order), np.int64)
        place[order] = np.cumsum(new) - 1
        hot = bool(found.column("hot")[0].as_py())
        pairs, of_pair = pairs_of(rank, last)
        n2 = np.bincount(of_pair, n, len(pairs)).astype(np.int64)
        row = {
            "part": found.column("part")[0].as_py(),
            "hot": hot,
            **dict(zip(_ASK, packed_grams(listed[rank], first, last, n, last_count), strict=True)),
            "blocks": found.column("block").to_pylist(),
            "places": [pack(np.diff(x, prepend=0)) for x in np.split(place, np.cumsum(sizes)[:-1])],
            "small3": small_counts(n),
            "small2": None if hot else small_counts(n2),
        }
        return pa.Table.from_pylist([row], schema=shape)

    many = pa.list_(pa.int64())
    binary = {c: pa.binary() for c in _ASK}
    shape = pa.schema({"part": pa.int32(), "hot": pa.bool_(), **binary, "blocks": many, "places": pa.list_(pa.binary()), "small3": many, "small2": many})
    schema = "part int, hot boolean, middle binary, first binary, last binary, n binary, counts binary, blocks array<long>, places array<binary>, small3 array<long>, small2 array<long>"
    return materialise(asked.groupBy("part").applyInArrow(run, schema), "lm-grams")


def pairs_of(rank: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of trigrams by (middle, last): a trigram of each bigram, and the bigram of each trigram."""
    order = sorted_by(rank, last)
    new = starts_of(rank[order], last[order])
    of = np.empty(len(order), np.int64)
    of[order] = np.cumsum(new) - 1
    return order[new], of


def weights(total: np.ndarray, kept: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What a context's discounted counts are divided by, and its backoff weight; ``known``: its followers' probability one order lower."""
    # All that the lower order knows was seen here: its followers share everything, and none is left to back off to.
    closed = (total > 0) & (1 - known < 1e-9)
    whole = np.where(closed, kept, total + np.where(total - kept < 1e-9, 0.5, 0.0))
    with np.errstate(divide="ignore", invalid="ignore"):
        return whole, np.where(total > 0, np.where(closed, 1e-30, (1 - kept / whole) / (1 - known)), 1.0)


def backed_off(context: np.ndarray, n: np.ndarray, lower: np.ndarray, ratios: np.ndarray, sums: tuple | None = None) -> np.ndarray:
    """The probability of each n-gram of a part, from its count and its probability one order lower.

    ``sums``: total, kept and known of the contexts, where not all of their n-grams are here.
    """
    held = discounted(n, ratios)
    size = int(context.max()) + 1 if len(context) else 0
    total, kept, known = sums or (np.bincount(context, x, size) for x in (n, held, np.where(n > 0, lower, 0.0)))
    whole, weight = weights(total, kept, known)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(n > 0, held / whole[context], weight[context] * lower)


def evaluate(row: dict, unigrams: Unigrams, two: np.ndarray, three: np.ndarray, hot: tuple | None = None) -> np.ndarray:
    """The probabilities of a part's trigrams.  ``hot``: for its bigrams in order, their counts, and the sums of their one context."""
    middle, first, last, n, last_count = unpacked_grams([row[c] for c in _ASK])
    rank = np.cumsum(starts_of(middle)) - 1
    pairs, of_pair = pairs_of(rank, last)
    n2 = hot[0] if hot else np.bincount(of_pair, n, len(pairs)).astype(np.int64)
    lower = backed_off(rank[pairs], n2, unigrams.share(last_count[pairs]), two, hot[1] if hot else None)
    return backed_off(np.cumsum(starts_of(middle, first)) - 1, n, lower[of_pair], three)


def answers(row: dict, value: np.ndarray) -> pa.Table:
    with np.errstate(divide="ignore"):
        logs = np.log10(value).astype("<f4")
    rows = [(b, SCORED, row["part"], logs[np.cumsum(unpack(p))].tobytes(), None, None, None) for b, p in zip(row["blocks"], row["places"], strict=True)]
    return pa.Table.from_batches([blocks.blobs(rows)])


def train(asked: DataFrame, unigrams: Unigrams, numbered: DataFrame) -> tuple[Model, DataFrame]:
    """The model, and the SCORED rows for the blocks that asked."""
    grams = count_grams(asked)
    sums = grams.agg(*[F.sum(F.get(f"small{o}", F.lit(i))).alias(f"o{o}n{i + 1}") for o in (2, 3) for i in range(KNOWN_RELIABLE + 1)]).first()
    small = {o: {i + 1: sums[f"o{o}n{i + 1}"] or 0 for i in range(KNOWN_RELIABLE + 1)} for o in (2, 3)}
    three = discounts(small[3])
    split = None
    if len(unigrams.hot):
        split = hot_pairs(grams, small[2])
    two = discounts(small[2])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            for i in range(one.num_rows):
                row = one.slice(i, 1).to_pylist()[0]
                yield from answers(row, evaluate(row, unigrams, two, three)).to_batches(1000)

    scored = grams.where("NOT hot").mapInArrow(score, blocks._BLOB)
    if split is not None:
        scored = scored.union(hot_scores(grams, split, unigrams, two, three))
    return Model(unigrams, of_kind(numbered, TABLE), grams, two, three), scored


def hot_pairs(grams: DataFrame, small: dict[int, int]) -> DataFrame:
    """The bigrams of the split middle words: part, middle, last, c1 (the last word's count) and n over all parts; their small counts go into ``small``."""

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            for i in range(one.num_rows):
                row = one.slice(i, 1).to_pylist()[0]
                middle, _, last, n, last_count = unpacked_grams([row[c] for c in _ASK])
                pairs, of_pair = pairs_of(np.zeros_like(middle), last)
                n2 = np.bincount(of_pair, n, len(pairs)).astype(np.int64)
                columns = [np.full(len(pairs), row["part"], np.int32), middle[pairs], last[pairs], n2, last_count[pairs]]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["part", "middle", "last", "here", "c1"])

    here = grams.where("hot").mapInArrow(listed, "part int, middle long, last long, here long, c1 long")
    here = materialise(here, "lm-hot-pairs")
    total = here.groupBy("middle", "last").agg(F.sum("here").alias("n"))
    found = materialise(here.drop("here").join(total, ["middle", "last"]), "lm-hot-counts")
    once = found.where(F.col("n").between(1, KNOWN_RELIABLE + 1)).select("middle", "last", "n").distinct()
    for r in once.groupBy("n").agg(F.count("*").alias("many")).collect():
        small[r["n"]] = small.get(r["n"], 0) + r["many"]
    return found


def hot_scores(grams: DataFrame, split: DataFrame, unigrams: Unigrams, two: np.ndarray, three: np.ndarray) -> DataFrame:
    """SCORED rows of the parts of split middle words, whose bigram counts and sums come from ``split``."""

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            middle, n, c1 = (one.column(c).to_numpy() for c in ("middle", "n", "c1"))
            listed, rank = np.unique(middle, return_inverse=True)
            sums = [np.bincount(rank, x, len(listed)) for x in (n, discounted(n, two), np.where(n > 0, unigrams.share(c1), 0.0))]
            yield pa.RecordBatch.from_arrays([pa.array(listed), *(pa.array(x.astype(float)) for x in sums)], names=["middle", "total", "kept", "known"])

    once = split.groupBy("middle", "last").agg(F.first("n").alias("n"), F.first("c1").alias("c1"))
    sums = once.select("middle", "n", "c1").mapInArrow(summed, "middle long, total double, kept double, known double")
    # A row for each split word, of which there are at most tokens / HOT_TOKENS.
    of_word = {r["middle"]: (r["total"], r["kept"], r["known"]) for r in sums.groupBy("middle").agg(*[F.sum(c).alias(c) for c in ("total", "kept", "known")]).collect()}

    def score(found: pa.Table, pairs: pa.Table) -> pa.Table:
        made = [pa.Table.from_batches([blocks.blobs([])])]
        for row in found.to_pylist():
            middle = int(unpack(row["middle"])[0])
            order = np.argsort(pairs.column("last").to_numpy())
            n2 = pairs.column("n").to_numpy()[order]
            made.append(answers(row, evaluate(row, unigrams, two, three, (n2, tuple(np.array([x]) for x in of_word[middle])))))
        return pa.concat_tables(made)

    pairs = split.select("part", "last", "n")
    return grams.where("hot").groupBy("part").cogroup(pairs.groupBy("part")).applyInArrow(score, blocks._BLOB)


def score(docs: DataFrame, kept: list[str], learns: Column) -> tuple[DataFrame, Model]:
    """The ``kept`` columns of each row, with n_tokens, n_known, base_score and score, and the model learnt from the rows where ``learns`` is true."""
    parts = blocks.parts_for(docs)
    made = blocks.cut(docs, kept, F.coalesce(learns, F.lit(False)), words, parts, "lm-blocks")
    numbered = number_words(blob_rows(made, WORDS), parts)
    unigrams = sum_words(numbered, parts)
    everything = parts + int(unigrams.hot_parts.sum())
    known = blob_rows(made, TEXT).union(blob_rows(numbered, NUMBERED))

    def ask(found: pa.Table) -> pa.Table:
        block = read_block(found, unigrams, parts)
        if block is None:
            return shape.empty_table()
        rows = []
        for part, of in by_part(block.part):
            grams = (x[of] for x in (block.middle, block.first, block.last, block.n, block.last_count))
            rows.append((found.column("block")[0].as_py(), part, part >= parts, *packed_grams(*grams)))
        return pa.Table.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), shape, strict=True)], schema=shape)

    shape = pa.schema({"block": pa.int64(), "part": pa.int32(), "hot": pa.bool_(), **{c: pa.binary() for c in _ASK}})
    asked = dealt(known, "block", parts).groupBy("block").applyInArrow(ask, "block long, part int, hot boolean, " + ", ".join(f"{c} binary" for c in _ASK))
    model, scored = train(dealt(asked, "part", everything), unigrams, numbered)
    base_total = unigrams.tokens + 0.5 * (unigrams.types + 1)

    def total(found: pa.Table) -> pa.Table:
        block = read_block(found, unigrams, parts)
        if block is None:
            return sums.empty_table()
        value = np.zeros(len(block.part))
        told = {found.column("part")[i].as_py(): i for i, k in enumerate(found.column("kind").to_pylist()) if k == SCORED}
        for part, of in by_part(block.part):
            value[of] = np.frombuffer(found.column("a")[told[part]].as_py(), "<f4")
        docs_ = len(block.lengths)
        doc = np.repeat(np.arange(docs_), block.lengths)
        columns = [
            np.full(docs_, found.column("block")[0].as_py()),
            np.arange(docs_, dtype=np.int32),
            block.lengths,
            np.bincount(doc, block.known, docs_).astype(np.int64),
            np.bincount(doc, np.log10((block.counts + 0.5) / base_total), docs_),
            np.bincount(doc[block.order], value[block.of_token], docs_),
        ]
        return pa.Table.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, sums, strict=True)], schema=sums)

    sums = pa.schema({"block": pa.int64(), "part": pa.int32(), "n_tokens": pa.int64(), "n_known": pa.int64(), "base_score": pa.float64(), "score": pa.float64()})
    whole = dealt(known.union(scored), "block", parts).groupBy("block").applyInArrow(total, "block long, part int, n_tokens long, n_known long, base_score double, score double")
    heads = of_kind(made, blocks.DOC).select(*kept, "block", "part")
    return heads.join(whole, ["block", "part"]).select(*kept, "n_tokens", "n_known", "base_score", "score"), model


def held_out() -> Column:
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 5 == 1


def op4_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored, model = score(table(spark, sf_dir, "documents").select("doc_id", "text"), ["doc_id"], ~held_out())
    return scored.select("doc_id", held_out().alias("held_out"), "n_tokens", "n_known", F.lit(model.unigrams.tokens).cast("long").alias("train_tokens"), "base_score", "score")
