"""SimHash near-duplicates by deletion-variant signatures.

A fingerprint has one or more 64-bit lanes.  It is cut into so few segments that two linked ones
differ in some segment by one bit at most: with s segments this is sure up to 2s-1 differing bits.
Each distinct fingerprint is indexed under every segment with one bit left out, so such a pair meets
under an equal key; the pair is then verified on all bits.  Equal fingerprints are folded before.

The rows of a key are brought together by a sort, in runs.  A run gives at most a spanning forest of
its links, and only those whose first common key it is: by induction over the order of keys this
joins the same documents as all links would, while a run of many near copies gives no square of
pairs.  Groups are the connected components.

Near copies for the pipeline are texts whose sets of five-word shingles have a Jaccard similarity of
``NEAR_SIMILARITY`` or more.  They meet by the deletion variants of a 64-bit lane, within ``CLOSE_BITS``.
No cut of a fingerprint into segments is sure to meet at the distance of that similarity, so the rest
of the candidates meet under equal bands of minima.  The exact similarity of the two sets decides; in
long runs, pairs that their fingerprints or a sketch of their sets rule out are not looked at.

Defined cases: a null or empty text has fingerprint zero; repeated rows are copies of each other; a
row with a null id gets the group of its fingerprint, null if no other row has it; an empty table
gives an empty result; other columns are never read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import accumulate, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from outline_engine.llm.columns import text_of
from outline_engine.llm.components import components
from outline_engine.llm.storage import materialise, table

SEED = 42
#: (first bit, width) of the segments of a lane: 22 + 21 + 21 bits.
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Runs up to this size are compared by shifting; larger ones by a search.
SHORT_RUN = 12
_ROWS = 200_000


def shingles(text: str, words_each: int) -> list[bytes]:
    """The shingles of a text in reading order; a text of fewer words is one shingle, an empty one has none."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return []
    line = b" ".join(words)
    ends = list(accumulate(map(len, words), lambda a, n: a + n + 1))
    starts = [0, *(e + 1 for e in ends[:-1])]
    return [line[a:b] for a, b in zip(starts, ends[words_each - 1 :], strict=False)] or [line]


def shingle_bits(text: str, words_each: int, seeds: tuple[int, ...]) -> list[int]:
    """The lanes of a text, as unsigned numbers."""
    import xxhash

    pieces = shingles(text, words_each)
    if not pieces:
        return [0] * len(seeds)
    lanes = []
    for seed in seeds:
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, pieces, repeat(seed)), dtype="<u8", count=len(pieces))
        counts = np.zeros(64, dtype=np.int64)
        for i in range(0, len(hashes), 4096):
            counts += np.unpackbits(hashes[i : i + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        lanes.append(int(np.packbits(2 * counts > len(pieces), bitorder="little").view("<u8")[0]))
    return lanes


def fingerprints(docs: DataFrame, *, words_each: int = 4, seeds: tuple[int, ...] = (SEED,)) -> DataFrame:
    """doc_id and lanes f0, f1, .. (64-bit patterns as signed longs), a row per row of ``docs``."""
    names = [f"f{i}" for i in range(len(seeds))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            made = [shingle_bits(t.as_py() or "", words_each, seeds) for t in one.column("text")]
            lanes = np.array(made, dtype=np.uint64).reshape(len(made), len(seeds)).view(np.int64)
            yield pa.RecordBatch.from_arrays([one.column("doc_id"), *(pa.array(lanes[:, i]) for i in range(len(seeds)))], names=["doc_id", *names])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"))
    return texts.mapInArrow(run, "doc_id long, " + ", ".join(f"{n} long" for n in names))


def variants(classes: DataFrame, lanes: int) -> DataFrame:
    """key, node, lanes: each fingerprint under every segment without one of its bits.

    A key is the number of the variant (bits 32 and up) and the segment's other bits.
    """
    keys, number = [], 0
    for lane in range(lanes):
        for first, width in SEGMENTS:
            segment = F.shiftrightunsigned(f"f{lane}", first).bitwiseAND(F.lit((1 << width) - 1))
            for bit in range(width):
                keys.append(segment.bitwiseAND(F.lit(((1 << width) - 1) & ~(1 << bit))).bitwiseOR(F.lit(number << 32)))
                number += 1
    return classes.select(F.explode(F.array(*keys)).alias("key"), "node", *[f"f{i}" for i in range(lanes)])


def first_variant(x: np.ndarray) -> np.ndarray:
    """For rows of lane differences: the number of the first variant under which the pair meets, -1 if none."""
    found = np.full(len(x), -1, dtype=np.int64)
    number = x.shape[1] * 64
    for lane in range(x.shape[1] - 1, -1, -1):
        for first, width in reversed(SEGMENTS):
            number -= width
            part = (x[:, lane] >> np.uint64(first)) & np.uint64((1 << width) - 1)
            ones = np.bitwise_count(part)
            at = np.bitwise_count(part - np.uint64(1)).astype(np.int64)
            found = np.where(ones == 0, number, np.where(ones == 1, number + at, found))
    return found


def run_links(key: np.ndarray, node: np.ndarray, lanes: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal ``key`` (sorted): a spanning forest of each, less what an earlier variant gives."""
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    sizes = np.diff(np.r_[starts, len(key)])
    size_of = np.repeat(sizes, sizes)
    left, right = [], []
    few = np.flatnonzero((size_of > 1) & (size_of <= SHORT_RUN))
    for step in range(1, SHORT_RUN):
        i = few[few + step < len(key)]
        i = i[key[i] == key[i + step]]
        if not len(i):
            break
        i = i[np.bitwise_count(lanes[i] ^ lanes[i + step]).sum(axis=1, dtype=np.int64) <= most]
        left.append(i)
        right.append(i + step)
    for begin, size in zip(starts[sizes > SHORT_RUN], sizes[sizes > SHORT_RUN], strict=True):
        waiting = np.arange(begin + 1, begin + size)
        queue, at = [begin], 0
        while len(waiting):
            if at == len(queue):
                queue.append(waiting[0])
                waiting = waiting[1:]
                continue
            near = np.bitwise_count(lanes[waiting] ^ lanes[queue[at]]).sum(axis=1, dtype=np.int64) <= most
            if near.any():
                hit = waiting[near]
                left.append(np.full(len(hit), queue[at]))
                right.append(hit)
                queue.extend(hit)
                waiting = waiting[~near]
            at += 1
    if not left:
        return node[:0], node[:0]
    a, b = np.concatenate(left).astype(np.int64), np.concatenate(right).astype(np.int64)
    own = first_variant(lanes[a] ^ lanes[b]) == key[a] >> 32
    return node[a[own]], node[b[own]]


def met(keyed: DataFrame, find: Callable[..., Iterator[tuple[np.ndarray, np.ndarray]]]) -> DataFrame:
    """Pairs (a, b) that ``find`` gives for the runs of equal keys of ``keyed`` (key, node, other longs and, if any, sketch)."""
    parts = int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sketched = "sketch" in keyed.columns
    names = [c for c in keyed.columns if c not in ("key", "node", "sketch")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        sketches: list[pa.Array] = []
        rows = 0

        def settle(final: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held, sketches, rows
            data = np.concatenate(held, axis=1) if held else np.zeros((2 + len(names), 0), dtype=np.int64)
            end = data.shape[1] if final else int(np.searchsorted(data[0], data[0][-1]))
            held = [data[:, end:]]
            rows = data.shape[1] - end
            more = [pa.concat_arrays(sketches)] if sketches else []
            sketches = [x.slice(end) for x in more]
            if end:
                done = data[:, :end]
                for a, b in find(done[0], done[1], np.ascontiguousarray(done[2:].T).view(np.uint64), *[x.slice(0, end) for x in more]):
                    if len(a):
                        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

        bound = _ROWS
        for one in batches:
            held.append(np.stack([one.column(c).to_numpy(zero_copy_only=False) for c in ("key", "node", *names)]))
            if sketched:
                sketches.append(one.column("sketch"))
            rows += one.num_rows
            if rows >= bound:
                yield from settle(False)
                bound = max(_ROWS, 2 * rows)
        yield from settle(True)

    dealt = keyed.repartition(parts, "key").sortWithinPartitions("key", "node")
    return dealt.mapInArrow(run, "a long, b long")


def links(classes: DataFrame, lanes: int, most: int) -> DataFrame:
    """Edges (a, b) that join the ``classes`` (node, f0, ..) within ``most`` differing bits of each other."""
    return met(variants(classes, lanes), lambda key, node, prints: iter([run_links(key, node, prints, most)]))


def groups(docs: DataFrame, *, words_each: int = 4, seeds: tuple[int, ...] = (SEED,), most: int = 4) -> DataFrame:
    """doc_id, lanes and component_id, the smallest doc_id that each row reaches over links."""
    names = [f"f{i}" for i in range(len(seeds))]
    prints = materialise(fingerprints(docs, words_each=words_each, seeds=seeds), "simhash")
    classes = prints.groupBy(*names).agg(F.min("doc_id").alias("node")).where("node IS NOT NULL")
    classes = materialise(classes, "simhash-classes")
    roots = components(links(classes, len(seeds), most))
    named = classes.join(roots, "node", "left").select(*names, F.coalesce("root", "node").alias("component_id"))
    return prints.join(named, names, "left")


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = groups(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("f0"), 16, "0")).alias("fingerprint"), "component_id")


#: Near copies are texts of at least this Jaccard similarity of their sets of ``NEAR_WORDS``-word shingles.
NEAR_SIMILARITY = 0.8
NEAR_WORDS = 5
#: Bands of so many minima: at similarity 0.8 a pair shares no band with probability (1 - 0.8^5)^32 = 3e-6.
BANDS = 32
ROWS_EACH = 5
#: Fingerprints of sets, three lanes, 192 bits.  At similarity 0.8 about 29 bits differ, with a deviation
#: of 5; a pair over ``NEAR_BITS``, six deviations more, is not looked at.
NEAR_LANES = 3
NEAR_BITS = 60
#: The first lane is a fingerprint whose deletion variants meet up to so many bits.
CLOSE_BITS = 4
#: Least number of bits of a sketch; one of more than half as many shingles has twice as many bits, and so on.
SKETCH_BITS = 2048
_ODD = np.random.default_rng(SEED).integers(0, 1 << 63, size=BANDS * ROWS_EACH + NEAR_LANES + ROWS_EACH + BANDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


def shingle_set(text: str) -> np.ndarray:
    """The hashes of a text's distinct shingles, sorted."""
    import xxhash

    pieces = shingles(text, NEAR_WORDS)
    return np.unique(np.fromiter(map(xxhash.xxh64_intdigest, pieces, repeat(SEED)), dtype="<u8", count=len(pieces)))


def near_print(found: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    """Of a set of shingles: a number for the set, its lanes, and the keys of its bands."""
    import xxhash

    whole = xxhash.xxh3_64_intdigest(found.tobytes())
    counts = np.zeros((NEAR_LANES, 64), dtype=np.int64)
    least = np.full(BANDS * ROWS_EACH, np.iinfo(np.uint64).max, dtype=np.uint64)
    minima, lanes, rows, bands = np.split(_ODD, np.cumsum([BANDS * ROWS_EACH, NEAR_LANES, ROWS_EACH]))
    for i in range(0, len(found), 1024):
        some = found[i : i + 1024]
        np.minimum(least, (minima[:, None] * some).min(axis=1), out=least)
        bits = _mixed(lanes[:, None] * some).view(np.uint8).reshape(NEAR_LANES, -1, 8)
        counts += np.unpackbits(bits, axis=2, bitorder="little").sum(axis=1, dtype=np.int64)
    made = np.packbits(2 * counts > len(found), axis=1, bitorder="little").view("<u8").ravel()
    keys = _mixed((_mixed(least).reshape(BANDS, ROWS_EACH) * rows).sum(axis=1, dtype=np.uint64) + bands)
    return whole, made, keys


def near_prints(docs: DataFrame) -> DataFrame:
    """doc_id, same (a number for the text), node (one for its set of shingles), lanes and bands (keys)."""
    names = [f"f{i}" for i in range(NEAR_LANES)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            if not one.num_rows:
                continue
            made = [near_print(shingle_set(t.as_py())) for t in one.column("text")]
            nodes = np.array([x[0] for x in made], dtype=np.uint64).view(np.int64)
            lanes = np.stack([x[1] for x in made]).astype(np.uint64).view(np.int64)
            keys = np.concatenate([x[2] for x in made]).view(np.int64)
            bands = pa.ListArray.from_arrays(pa.array(np.arange(0, len(keys) + 1, BANDS), pa.int32()), pa.array(keys))
            yield pa.RecordBatch.from_arrays(
                [one.column("doc_id"), one.column("same"), pa.array(nodes), *(pa.array(np.ascontiguousarray(lanes[:, i])) for i in range(NEAR_LANES)), bands],
                names=["doc_id", "same", "node", *names, "bands"],
            )

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text_of()).alias("same"), text_of().alias("text"))
    return texts.mapInArrow(run, f"doc_id long, same long, node long, {', '.join(f'{n} long' for n in names)}, bands array<long>")


def near_pairs(key: np.ndarray, node: np.ndarray, lanes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs within runs of equal ``key`` (sorted) that differ in ``NEAR_BITS`` at most, then the keys of long runs with null.

    All of a run of up to ``SHORT_RUN``; of a longer run first those of a spanning forest with the
    least differences.  What the forest leaves apart is looked at by ``apart_pairs``.
    """
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    sizes = np.diff(np.r_[starts, len(key)])
    size_of = np.repeat(sizes, sizes)
    left, right = [], []
    few = np.flatnonzero((size_of > 1) & (size_of <= SHORT_RUN))
    for step in range(1, SHORT_RUN):
        i = few[few + step < len(key)]
        i = i[key[i] == key[i + step]]
        i = i[np.bitwise_count(lanes[i] ^ lanes[i + step]).sum(axis=1, dtype=np.int64) <= NEAR_BITS]
        left.append(i)
        right.append(i + step)
    for begin, size in zip(starts[sizes > SHORT_RUN], sizes[sizes > SHORT_RUN], strict=True):
        outside, at = np.arange(begin + 1, begin + size), begin
        far, nearest = np.full(size - 1, 1 << 30), np.full(size - 1, begin)
        while len(outside):
            now = np.bitwise_count(lanes[outside] ^ lanes[at]).sum(axis=1, dtype=np.int64)
            nearer = now < far
            far[nearer], nearest[nearer] = now[nearer], at
            i = int(far.argmin())
            at = outside[i]
            if far[i] <= NEAR_BITS:
                left.append(nearest[i : i + 1].copy())
                right.append(outside[i : i + 1].copy())
            outside[i], far[i], nearest[i] = outside[-1], far[-1], nearest[-1]
            outside, far, nearest = outside[:-1], far[:-1], nearest[:-1]
    a, b = np.concatenate(left), np.concatenate(right)
    yield node[a], node[b]
    long = key[starts[sizes > SHORT_RUN]]
    yield long, pa.nulls(len(long), pa.int64())


def set_sketch(found: np.ndarray) -> bytes:
    """Parities of the numbers of a set's hashes in as many buckets as there are bits.

    Two sets differ in at least as many hashes as their sketches in bits, so a sketch rules pairs out and
    loses none.  Half the buckets are the longer sketch's two halves by exclusive or.
    """
    bits = SKETCH_BITS
    while bits < 2 * len(found):
        bits *= 2
    odd = np.bincount((found & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def set_sketches(sets: DataFrame) -> DataFrame:
    """node, size and sketch of ``sets`` (node, found)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for one in batches:
            found = [x.values.to_numpy().view(np.uint64) for x in one.column("found")]
            yield pa.RecordBatch.from_arrays([one.column("node"), pa.array([len(x) for x in found], pa.int64()), pa.array([set_sketch(x) for x in found], pa.binary())], names=["node", "size", "sketch"])

    return sets.select("node", "found").mapInArrow(run, "node long, size long, sketch binary")


def sketch_tables(sketches: list[bytes]) -> dict[tuple[int, int], tuple[np.ndarray, np.ndarray]]:
    """By words of the sketches and words that they are folded to: which rows, and their sketches."""
    words = np.array([len(x) // 8 for x in sketches])
    out = {}
    lengths = sorted({*words.tolist()})
    for n in lengths:
        rows = np.flatnonzero(words == n)
        table, short = np.stack([np.frombuffer(sketches[i], dtype="<u8") for i in rows]), n
        while short >= lengths[0]:
            out[n, short] = rows, table
            short //= 2
            table = table[:, :short] ^ table[:, short:]
    return out


def apart_pairs(key: np.ndarray, node: np.ndarray, columns: np.ndarray, sketch: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of long runs of equal ``key`` (sorted) with different roots that may be similar enough.

    ``columns``: lanes, sizes of the sets, roots.  A pair has ``NEAR_BITS`` at most, and sketches that allow
    the similarity: sets of sizes n and m and similarity s differ in (1 - s) / (1 + s) * (n + m) hashes.
    """
    lanes, size, root = columns[:, :-2], columns[:, -2].astype(np.int64), columns[:, -1]
    share = (1 - NEAR_SIMILARITY) / (1 + NEAR_SIMILARITY)
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    left, right, held = [node[:0]], [node[:0]], 0
    for begin, end in zip(starts, [*starts[1:], len(key)], strict=True):
        if end - begin <= SHORT_RUN or (root[begin:end] == root[begin]).all():
            continue
        tables = sketch_tables(sketch.slice(begin, end - begin).to_pylist())
        own = {(n, short): dict(zip(rows.tolist(), table, strict=True)) for (n, short), (rows, table) in tables.items()}
        lengths = sorted({n for n, _ in tables})
        words = {i: n for n in lengths for i in tables[n, n][0].tolist()}
        for i in range(begin, end - 1):
            parts, n = [], words[i - begin]
            for m in lengths:
                short = min(n, m)
                rows, table = tables[m, short]
                some = (rows > i - begin) & (root[rows + begin] != root[i])
                rows, table = rows[some] + begin, table[some]
                bits = np.bitwise_count(table ^ own[n, short][i - begin]).sum(axis=1, dtype=np.int64)
                parts.append(rows[bits <= share * (size[rows] + size[i]) + 1e-6])
            other = np.concatenate(parts)
            other = other[np.bitwise_count(lanes[other] ^ lanes[i]).sum(axis=1, dtype=np.int64) <= NEAR_BITS]
            left.append(np.full(len(other), node[i]))
            right.append(node[other])
            held += len(other)
            if held > _ROWS:
                yield np.concatenate(left), np.concatenate(right)
                left, right, held = [node[:0]], [node[:0]], 0
    yield np.concatenate(left), np.concatenate(right)


def shingle_sets(texts: DataFrame) -> DataFrame:
    """node and found, the hashes of its shingles, for rows (node, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 500):
                one = batch.slice(begin, 500)
                found = [pa.array(shingle_set(t.as_py()).view(np.int64)) for t in one.column("text")]
                ends = np.cumsum([0, *map(len, found)])
                yield pa.RecordBatch.from_arrays([one.column("node"), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.concat_arrays(found))], names=["node", "found"])

    return texts.mapInArrow(run, "node long, found array<long>")


def sets_of(docs: DataFrame, classes: DataFrame, pairs: DataFrame) -> DataFrame:
    """node, found: the shingles of the ``classes`` (node, same) that the ``pairs`` (a, b) name; stored."""
    involved = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(classes.select("node", "same"), "node")
    texts = docs.select(F.xxhash64(text_of()).alias("same"), text_of().alias("text")).join(involved, "same").groupBy("node").agg(F.first("text").alias("text"))
    return materialise(shingle_sets(texts), "near-sets")


def similar(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """Those of the ``pairs`` (a, b) of ``sets`` (node, found) that are similar enough, exactly; stored."""
    both = pairs.join(sets.select(F.col("node").alias("a"), F.col("found").alias("x")), "a").join(sets.select(F.col("node").alias("b"), F.col("found").alias("y")), "b")
    shared = F.size(F.array_intersect("x", "y"))
    sizes = both.select("a", "b", shared.alias("shared"), (F.size("x") + F.size("y")).alias("sizes"))
    return materialise(sizes.where(F.col("shared") >= NEAR_SIMILARITY * (F.col("sizes") - F.col("shared"))).select("a", "b"), "near-links")


def near_links(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """Edges (a, b) that join the ``classes`` (node, same, lanes, bands) as all pairs of similar sets would.

    Pairs of close fingerprints, of short runs, and of the forests of long runs are settled first.  Then
    those pairs of long runs are that are still in different groups and whose sketches allow the similarity.
    The groups found by then are given as stars.  Of a node of such a pair the forest of the run has a link
    that differs no more than the pair, so its set is at hand.
    """
    names = [f"f{i}" for i in range(NEAR_LANES)]
    ordered = lambda found: found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    keyed = classes.select(F.explode("bands").alias("key"), "node", *names)
    close = links(classes.select("node", "f0"), 1, CLOSE_BITS)
    seen = materialise(met(keyed, near_pairs).union(close), "near-runs")
    tried = materialise(ordered(seen.where("b IS NOT NULL")), "near-pairs")
    sets = sets_of(docs, classes, tried)
    found = similar(sets, tried)
    long = seen.where("b IS NULL").select(F.col("a").alias("key"))
    if long.isEmpty():
        return found
    roots = components(found)
    stars = roots.select(F.col("node").alias("a"), F.col("root").alias("b"))
    inside = materialise(keyed.join(long, "key"), "near-runs")
    sketches = set_sketches(sets.join(inside.select("node").distinct(), "node", "left_semi"))
    rooted = inside.join(sketches, "node").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    rest = materialise(ordered(met(rooted.select("key", "node", *names, "size", "root", "sketch"), apart_pairs)).join(tried, ["a", "b"], "left_anti"), "near-pairs")
    if rest.isEmpty():
        return stars
    # The sets that these pairs name are cut out before two joins would deal all of them.
    named = sets.join(rest.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "node", "left_semi")
    return stars.union(similar(named, rest))


def near_groups(docs: DataFrame) -> DataFrame:
    """doc_id and component_id, the smallest doc_id that each row reaches over near copies, of rows with an id.

    Texts that share an id are joined.
    """
    prints = materialise(near_prints(docs), "near-prints")
    names = [f"f{i}" for i in range(NEAR_LANES)]
    classes = materialise(prints.groupBy("node").agg(F.min("same").alias("same"), *[F.first(c).alias(c) for c in (*names, "bands")]), "near-classes")
    rows = prints.select("doc_id", "node").distinct()
    shared = rows.withColumn("first", F.min("node").over(Window.partitionBy("doc_id"))).where("node <> first").select(F.col("node").alias("a"), F.col("first").alias("b"))
    roots = components(near_links(docs, classes).union(shared))
    rooted = rows.join(roots, "node", "left").select("doc_id", F.coalesce("root", "node").alias("root"))
    least = rooted.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return rooted.join(least, "root").select("doc_id", "component_id")


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """``docs`` with one row for each group of near copies: that of the smallest doc_id.

    Rows with a null id are never grouped and stay.
    """
    found = near_groups(docs.where("doc_id IS NOT NULL"))
    stays = found.where("doc_id = component_id").select(F.col("doc_id").alias("__stays")).distinct()
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    one = Window.partitionBy("__stays").orderBy(text_of("row.text"))
    first = whole.join(stays, F.col("row.doc_id") == F.col("__stays")).withColumn("__rank", F.row_number().over(one)).where("__rank = 1")
    return first.select("row.*").union(docs.where("doc_id IS NULL"))
