"""The training-data operators against brute force, round trips and odd inputs."""

import hashlib
import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from outline_engine.llm import blocks, bpe, chat, classifier, components, fingerprints, katz, packing, quality_rules, rollups, simhash, warc
from outline_engine.llm.storage import scratch, table
from outline_engine.llm.vocabularies import default_path, rank_file_encoder

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, row string"
ODD = [
    (1, None, None, None, None, 1.0, "x"),
    (2, "", "en", "s", 0, 1.0, "x"),
    (3, "one", "en", "s", 3, 1.0, "x"),
    (4, "a b c d e f g h", "en", "s", 15, 1.0, "x"),
    (4, "a b c d e f g h", "en", "s", 15, 1.0, "x"),
    (5, "A B C D E F G H", "xx", "s", 15, 1.0, "x"),
    (6, "word " * 30_000, "en", "s", 150_000, 1.0, "x"),
    (None, "null id \x1c\x85　 日本語テキスト😀 <|endoftext|>", None, None, 9, 1.0, "x"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# Chat formatting.
def test_chat_folds_events(spark):
    log = [
        (1, 1, 1, "start", "user", "he"), (1, 1, 2, "delta", None, "llo"), (1, 2, 3, "start", "assistant", "bad"), (1, 2, 4, "regenerate", None, ""),
        (1, 2, 5, "delta", None, "go"), (1, 2, 6, "delta", None, "od"), (1, 1, 7, "edit", None, "hi"), (1, 3, 8, "start", "user", "gone"), (1, 3, 9, "delete", None, None), (2, 1, 1, "start", None, None),
    ]
    events = spark.createDataFrame(log, "conv_id long, turn long, seq long, kind string, role string, text string")
    got = sorted(tuple(r) for r in chat.reconstruct(events).collect())
    assert got == [(1, 1, "user", "hi"), (1, 2, "assistant", "good"), (2, 1, "", "")]


def test_chat_template_is_reversible(spark):
    rng = random.Random(3)
    bits = ["<", "\\", "/", "turn", "</turn>", "<turn user>\n", "\n", ">", "x", "\\### Assistant:", "é😀", "%25"]
    rows = [(c, t, rng.choice(["user", "assistant", "a<b>%\n"]), "".join(rng.choices(bits, k=rng.randint(0, 8)))) for c in range(60) for t in range(rng.randint(1, 5))]
    done = chat.render(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    got = done.select("conv_id", "formatted", "spans", chat.parse(F.col("formatted")).alias("turns"), chat.learned_text(F.col("formatted"), F.col("spans")).alias("learned")).collect()
    for r in got:
        want = sorted((t, role, text) for c, t, role, text in rows if c == r["conv_id"])
        assert [(x["role"], x["text"]) for x in r["turns"]] == [(role, text) for _, role, text in want]
        assert r["learned"] == "".join(text for _, role, text in want if role == "assistant")
        assert r["formatted"].count("</turn>") == len(want)
        for span, (_, role, text) in zip(r["spans"], want, strict=True):
            inside = r["formatted"][span["start"] : span["start"] + span["length"]]
            assert inside.replace("\\", "") == text.replace("\\", "") and span["loss"] == (role == "assistant")


def test_chat_logs_of_finished_turns(spark, small):
    rows = [(c, t, "assistant" if t % 2 else "user", "é😀\\ <turn> " * (t * c * 40)) for c in range(12) for t in range(3)] + [(None, None, None, None), (50, 1, None, None), (51, 1, "user", "x" * 200_000)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    log = chat.streamed(turns)
    kinds = {r["kind"]: r["n"] for r in log.groupBy("kind").agg(F.count("*").alias("n")).collect()}
    assert set(kinds) == {"start", "delta", "edit", "regenerate"} and log.groupBy("conv_id", "turn").count().agg(F.max("count")).first()[0] <= chat.MOST_DELTAS + 3
    key = lambda r: (r[0] or 0, r[1] or 0)
    want = sorted(((c, t, role or "", text or "") for c, t, role, text in rows), key=key)
    assert sorted((tuple(r) for r in chat.reconstruct(log.withColumn("n", F.lit(1))).collect()), key=key) == want
    assert chat.render(chat.reconstruct(log.where("false"))).count() == 0


# SimHash.
def brute_groups(prints, most):
    parent = {i: i for i in range(len(prints))}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(prints)):
        for j in range(i):
            if prints[i][1] is not None and bin(prints[i][1] ^ prints[j][1]).count("1") <= most:
                parent[find(i)] = find(j)
    best = defaultdict(lambda: math.inf)
    for i, (doc, _) in enumerate(prints):
        best[find(i)] = min(best[find(i)], doc)
    return sorted((doc, best[find(i)]) for i, (doc, _) in enumerate(prints))


def test_simhash_links_are_those_of_brute_force(spark):
    rng = random.Random(8)
    centres = [rng.getrandbits(64) for _ in range(12)]
    prints = [(i, centres[i % 12] ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4)))) for i in range(600)]
    signed = [(i, f - (1 << 64) if f >> 63 else f) for i, f in prints]
    classes = spark.createDataFrame(signed, "node long, f0 long").dropDuplicates(["f0"])
    kept = {r["node"]: r["f0"] % (1 << 64) for r in classes.collect()}
    roots = {r["node"]: r["root"] for r in components.components(simhash.links(classes, 1, 4)).collect()}
    assert sorted((n, roots.get(n, n)) for n in kept) == brute_groups(sorted(kept.items()), 4)


def test_simhash_odd_rows(spark, odd, empty):
    got = simhash.groups(odd).collect()
    assert len(got) == len(ODD)
    by = defaultdict(set)
    for r in got:
        by[r["doc_id"]].add((r["f0"], r["component_id"]))
    assert by[1] == by[2] == {(0, 1)} and {c for _, c in by[5]} == {4}
    assert simhash.groups(empty).count() == 0
    kept = simhash.drop_near_copies(odd)
    assert kept.columns == odd.columns
    assert sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 3, 4, 6]


def test_near_copies_go(spark):
    rng = random.Random(1)
    words = [f"w{i}" for i in range(3000)]
    base = [rng.choices(words, k=200) for _ in range(40)]
    docs = [(i, " ".join(w)) for i, w in enumerate(base)]
    for i, w in enumerate(base[:20]):
        copy = list(w)
        copy[50] = "changed"
        docs.append((100 + i, " ".join(copy)))
    kept = simhash.drop_near_copies(spark.createDataFrame(docs, "doc_id long, text string"))
    assert sorted(r["doc_id"] for r in kept.collect()) == list(range(40))


# BPE.
def test_bpe_is_tiktoken(spark, odd, empty, monkeypatch):
    monkeypatch.setattr(bpe, "BLOCK_TOKENS", 900)
    monkeypatch.setattr(blocks, "PART_BYTES", 4000)
    enc = rank_file_encoder(default_path(bpe.VOCABULARY))
    rng = random.Random(2)
    letters = "abcdefgh ABC  \n\t\r'stremld019²½ßüéñ日本カ한국😀́\xa0\x85\x1c|#*!?"
    texts = ["".join(rng.choices(letters, k=rng.randint(0, 50))) for _ in range(300)] + [None, "a" * 3000 + " b", "I'll <|endoftext|> don't", "x" + "abcdefgh" * 700, "ha" * 500]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = bpe.run(df).collect()
    assert len(got) == len(texts)
    for r in got:
        text = texts[r["doc_id"]] or ""
        assert list(r["ids"]) == enc.encode_ordinary(text) and bytes(r["decoded"]) == text.encode()
    for w in ("", "a", " the", "zzzqqq", "a" * 200, "日本語", "".join(rng.choices("abetr ", k=2000))):
        assert bpe.merge(w.encode(), enc._mergeable_ranks) == (enc._core_bpe.encode_single_piece(w.encode()) if w else [])
    assert bpe.run(odd).count() == len(ODD)
    assert bpe.run(empty, digests=True).count() == 0


def test_plain_engine_cuts_latin_texts_alike():
    import public_tokenizers
    import regex

    cut, pattern, rng = bpe.cutter(public_tokenizers.PATTERN), bpe.python_pattern(public_tokenizers.PATTERN), random.Random(6)
    texts = ["".join(rng.choices([*map(chr, range(256)), *" 'sta1 \n"], k=400)) for _ in range(300)]
    for text in [*texts, *(t + "\u3000x" for t in texts[:50]), "", *map(chr, range(256))]:
        assert cut(text) == regex.findall(pattern, text)


def test_bpe_decodes_ids_by_columns(spark):
    enc = rank_file_encoder(default_path(bpe.VOCABULARY))
    texts = ["", "naïve 日本語 😀", "plain words"]
    df = spark.createDataFrame([(t, enc.encode_ordinary(t)) for t in texts], "text string, ids array<int>")
    pieces = bpe.piece_literal(enc._mergeable_ranks)
    assert all(bytes(r["b"]).decode() == r["text"] for r in df.select("text", bpe.let(pieces, lambda p: bpe.decoded(F.col("ids"), p)).alias("b")).collect())


# Language model.
@pytest.mark.parametrize("hot", [10**9, 40])
def test_katz_is_brute_force_and_normalised(spark, monkeypatch, hot):
    for name, value in (("BLOCK_TOKENS", 700), ("PART_BYTES", 2500)):
        monkeypatch.setattr(blocks, name, value)
    monkeypatch.setattr(katz, "HOT_TOKENS", hot)
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(60)]
    docs = [(i, " ".join(rng.choices(vocab, weights=[1 / (k + 1) for k in range(60)], k=rng.randint(0, 40)))) for i in range(150)] + [(500, "never seen words W0"), (501, None)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    scored, model = katz.score(df, ["doc_id"], F.col("doc_id") < 120)
    got = {r["doc_id"]: r for r in scored.collect()}
    assert (len(model.unigrams.hot) > 3) == (hot == 40) and model.grams.where("hot").isEmpty() == (hot != 40)
    tokens = {i: [*(t or "").lower().split(), "<end>"] for i, t in docs}
    train = [tokens[i] for i in range(120)]
    c = Counter(w for d in train for w in d)
    n, v = sum(c.values()), len(c)
    after = [None, c, defaultdict(Counter), defaultdict(Counter)]
    for d in train:
        for x, y, z in zip(["<s>", "<s>", *d], ["<s>", *d], d):
            after[2][y][z] += 1
            after[3][x, y][z] += 1
    ratios = [None, katz.discounts(Counter(x for x in c.values() if x <= 6)), *(katz.discounts(Counter(x for f in after[o].values() for x in f.values() if x <= 6)) for o in (2, 3))]
    cut = lambda x, order: x * ratios[order][x] if x <= 5 else x
    unseen = 1 - sum(cut(x, 1) for x in c.values()) / (n + 0.5)

    def prob(order, context, w):
        if order == 1:
            return cut(c[w], 1) / (n + 0.5) if w in c else unseen
        lower = lambda x: prob(order - 1, context[1:], x)
        f = after[order].get(context if order == 3 else context[0])
        if not f:
            return lower(w)
        held, left = sum(cut(x, order) for x in f.values()), 1 - sum(map(lower, f))
        whole = held if left < 1e-9 else sum(f.values()) + (0.5 if sum(f.values()) - held < 1e-9 else 0)
        return cut(f[w], order) / whole if w in f else (1 - held / whole) / left * lower(w)

    for i, d in tokens.items():
        want = sum(math.log10(prob(3, (x, y), z)) for x, y, z in zip(["<s>", "<s>", *d], ["<s>", *d], d))
        base = sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in d)
        r = got[i]
        assert r["score"] == pytest.approx(want, abs=1e-4) and r["base_score"] == pytest.approx(base, abs=1e-6)
        assert (r["n_tokens"], r["n_known"]) == (len(d), sum(w in c for w in d))
    for context in [*list(after[3])[:8], ("<s>", "<s>"), ("w0", "w1"), ("unheard-of", "w3")]:
        total = sum(prob(3, context, w) for w in c) + prob(3, context, "unheard-of")
        assert total == pytest.approx(1.0, abs=1e-9)


def test_katz_odd_rows(spark, odd, empty):
    assert katz.score(odd, ["doc_id"], F.lit(True))[0].count() == len(ODD)
    none = katz.score(odd, ["doc_id", "row"], F.col("n_chars") < 0)[0].collect()
    assert len(none) == len(ODD) and all(r["n_known"] == 0 and r["score"] == 0 and r["row"] == "x" for r in none)
    assert katz.score(empty, ["doc_id"], F.lit(True))[0].count() == 0


def test_packed_numbers():
    for x in ([], [0], [255, 256, 0], [2**40, 3], [2**62]):
        assert blocks.unpack(blocks.pack(np.array(x, dtype=np.int64))).tolist() == x
    words = [b"a", b"", b"\n b", "é".encode()]
    assert blocks.unpack_words(*blocks.pack_words(words)) == words and blocks.unpack_words(*blocks.pack_words([])) == []


# Quality rules.
def test_repeated_windows(spark):
    texts = ["a b c a b c", "a b c d", "", "x x x x", "a b c d a b c e a b c", "p q"]

    def brute(text):
        w = text.split()
        seen = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        return len({j for i in range(len(w) - 2) if seen[tuple(w[i : i + 3])] > 1 for j in range(i, i + 3)})

    df = spark.createDataFrame([(t,) for t in texts], "text string")
    got = {r[0]: r[1] for r in df.select("text", quality_rules.repeated_words(quality_rules.words_of(F.col("text")))).collect()}
    assert got == {t: brute(t) for t in texts}


def test_rules_odd_rows(spark, odd, empty):
    got = quality_rules.judge(odd).select("row.doc_id", "base_failed", "kept", "n_words").collect()
    assert len(got) == len(ODD) and not any(r["kept"] for r in got)
    assert {r["n_words"] for r in got if r["doc_id"] == 6} == {30_000}
    assert quality_rules.judge(empty).count() == 0 and quality_rules.keep_good(odd).columns == odd.columns


def test_rules_keep_clean_and_drop_junk(spark, small):
    small = small.replace("0.001", "0.01")
    kept = quality_rules.keep_good(table(spark, small, "documents"))
    labels = table(spark, small, "labels").join(kept.select("doc_id", F.lit(1).alias("k")), "doc_id", "left").join(table(spark, small, "documents"), "doc_id").where(F.length("text") > 600)
    share = {r["quality"]: r["s"] for r in labels.groupBy("quality").agg(F.avg(F.coalesce("k", F.lit(0))).alias("s")).collect()}
    assert share[1] > 0.97 and share[0] < 0.6


# Rollups.
def test_rollup_is_idempotent(spark):
    r = rollups.Rollup(spark, scratch(spark, "rollup-test"))
    rows = spark.createDataFrame([("a", "en", 5), ("a", "en", 7), (None, "fr", None), ("b", "en", 1)], "source string, lang string, n long")
    r.commit(1, rollups.changes(rows, "t1", F.col("n"), 1))
    gone = rollups.changes(rows.where("n = 7 OR source = 'b'"), "t1", F.col("n"), -1)
    for _ in range(2):
        r.commit(2, gone)
    want = [("a", "en", "t1", 1, 5), (None, "fr", "t1", 1, 0)]
    shown = lambda x: sorted(map(repr, (tuple(i) for i in x.totals().select(*rollups.KEYS, "documents", "tokens").collect())))
    assert shown(r) == sorted(map(repr, want)) == shown(r.compact(scratch(spark, "rollup-test")))
    base = r.compact(scratch(spark, "rollup-test"))
    assert not base.commit(1, rollups.changes(rows, "t1", F.col("n"), 1)) and shown(base) == shown(r) == shown(r.compact(base.root))
    assert base.commit(3, rollups.changes(rows, "t2", F.col("n"), 1)) and base.totals().count() == 5
    # A batch that was written but not published is not there.
    rollups.changes(rows, "t1", F.col("n"), 1).write.parquet(f"{r.root}/batch-9-crashed")
    none = rollups.Rollup(spark, scratch(spark, "rollup-test"))
    assert shown(r) == sorted(map(repr, want)) and none.totals().count() == 0 and none.compact(scratch(spark, "rollup-test")).totals().count() == 0


def test_rollup_odd_rows(spark, odd, empty):
    counts = rollups.token_counts(odd).collect()
    assert len(counts) == len(ODD) and {r["n_tokens"] for r in counts if r["doc_id"] in (1, 2)} == {0}
    assert rollups.token_counts(empty).count() == 0


def test_rollup_query(spark, small):
    docs, want, seen = table(spark, small, "documents").orderBy("doc_id").collect(), defaultdict(lambda: [0, 0]), set()
    enc = rank_file_encoder(default_path(rollups.VOCABULARY))
    for r in docs:
        if r["text"] not in seen:
            seen.add(r["text"])
            for name, n in (("byte_bpe_multi_50k", len(enc.encode_ordinary(r["text"])) + 1), ("utf8_bytes", len(r["text"].encode()))):
                cell = want[r["source"], r["lang"], name]
                cell[0], cell[1] = cell[0] + 1, cell[1] + n
    got = {(r["source"], r["lang"], r["tokenizer"]): [r["documents"], r["tokens"]] for r in rollups.op6_token_rollup(spark, small).collect()}
    assert got == want


# Classifier.
def test_classifier_on_held_out_rows(spark, small):
    small = small.replace("0.001", "0.01")
    got = classifier.op7_classifier(spark, small).join(table(spark, small, "labels"), "doc_id").where("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in got]) > 0.95


def test_classifier_odd_rows(spark, odd, empty):
    x = classifier.with_statistics(odd)
    assert x.count() == len(ODD)
    labels = spark.createDataFrame([(3, 1), (4, 0), (6, 1), (5, None)], "doc_id long, quality int")
    model = classifier.learn(x, labels)
    scores = [r["score"] for r in classifier.with_scores(x, model, ["doc_id"]).collect()]
    assert len(scores) == len(ODD) and all(0 <= s <= 1 for s in scores)
    alone = classifier.learn(x, spark.createDataFrame([], "doc_id long, quality int"))
    assert {r["score"] for r in classifier.with_scores(x, alone, ["doc_id"]).collect()} == {0.5}
    assert classifier.keep_predicted(odd, model).columns == odd.columns and classifier.with_statistics(empty).count() == 0


# WARC.
def test_warc_round_trip(spark):
    same = "x" * 120
    pages = [(5, "http://a/ü?x=1%20y", same), (3, "http://b\r\nX: y", same), (9, None, same), (1, "u", "short"), (2, "u", "short"), (7, "u", None), (None, "u", same), (8, "u", "é" * 500_000)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").repartition(3)
    root = scratch(spark, "warc-test")
    index = warc.write(df, root)
    got = {r["page_id"]: r for r in warc.read(index, root).collect()}
    assert len(got) == len(pages)
    for page, url, html in pages:
        r, body = got[page], (html or "").encode()
        assert (r["url"], r["payload_bytes"], r["payload_digest"]) == (url, len(body), hashlib.sha256(body).hexdigest())
        assert (r["record_type"], r["refers_to"]) == (("revisit", 3) if page in (5, 9) else ("response", None))
        assert r["payload"] is None if page in (5, 9) else bytes(r["payload"]) == body
    assert warc.read(index.where("page_id = 8"), root).count() == 1
    assert warc.read(warc.write(df.where("false"), scratch(spark, "warc-test")), root).count() == 0


def test_near_ranges_are_read_at_once():
    assert warc.ranges([(0, 10), (10, 10), (20 + warc.GAP, 5), (30 + 3 * warc.GAP, 5)]) == [(0, 3, 0, 25 + warc.GAP), (3, 4, 30 + 3 * warc.GAP, 35 + 3 * warc.GAP)]


# Packing.
def check_pieces(rows, texts, skip=()):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(default_path("word_bpe_49k.json"))
    tok.encode_special_tokens = True
    by_seq = defaultdict(list)
    for r in rows:
        by_seq[r["sequence_id"]].append((r["offset"], r["length"]))
    for pieces in by_seq.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 2048
    want = Counter(hashlib.sha256(np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4").tobytes()).hexdigest() for t in texts)
    whole = defaultdict(list)
    for r in rows:
        if r["doc_id"] not in skip:
            whole[r["doc_id"]].append(r)
        assert r["ids_crc32"] == zlib.crc32(np.array(r["ids"], "<u4").tobytes())
    got = Counter(hashlib.sha256(np.concatenate([np.array(r["ids"], "<u4") for r in sorted(rs, key=lambda r: r["start"])]).tobytes()).hexdigest() for rs in whole.values())
    return want, got, sum(length for p in by_seq.values() for _, length in p) / (2048 * len(by_seq))


def test_packing(spark, small):
    docs = table(spark, small, "documents")
    rows = packing.pack(docs, emit_ids=True).collect()
    want, got, fill = check_pieces(rows, [r["text"] for r in docs.collect()])
    assert want == got and fill > 0.98


def test_packing_odd_rows(spark, odd, empty):
    rows = [r for r in packing.pack(odd, emit_ids=True).collect()]
    assert sum(r["length"] for r in rows if r["doc_id"] == 1) == 1 == sum(r["length"] for r in rows if r["doc_id"] == 2)
    want, got, _ = check_pieces(rows, [t for i, t, *_ in ODD if i != 4], skip=(4,))
    assert want == got and packing.pack(empty).count() == 0


def test_packer_places_by_least_squares():
    rng, capacity, closed = random.Random(5), 40, []
    packer = packing.LevelPacker(capacity, closed.append, 10**9)
    levels, done = Counter(), []  # levels of open windows, and the documents of closed ones
    windows = defaultdict(list)
    for doc in range(2000):
        size = rng.choice([rng.randint(1, 39), rng.randint(1, 8), 40])
        packer.add(doc, bytes(4 * size))
        if size == capacity:
            done.append([doc])
            continue
        best = None
        for level in [*sorted((k for k, n in levels.items() if n and k + size <= capacity), reverse=True), 0]:
            after = levels.copy()
            after[level] -= level > 0
            after[level + size] += level + size < capacity
            cost = sum(n * n for n in after.values())
            if best is None or cost < best[0]:
                best = (cost, level, after)
        _, level, levels = best
        window = [*(windows[level].pop() if level else []), doc]
        done.append(window) if level + size == capacity else windows[level + size].append(window)
    assert [[p[0] for p in w] for w in closed] == done


def test_packer_closes_when_many_windows_are_open():
    closed = []
    packer = packing.LevelPacker(10, closed.append, max_open=5)
    for i in range(40):
        packer.add(i, bytes(4 * 6))
    packer.finish()
    assert sum(len(p[2]) // 4 for w in closed for p in w) == 240 and sum(sum(len(p[2]) // 4 for p in w) < 10 for w in closed) <= 8


# Fingerprints.
def test_fingerprints_of_edits(spark, small):
    rows = fingerprints.op10_syncmers(spark, small).collect()
    docs = {r["doc_id"]: r["text"] for r in table(spark, small, "documents").collect()}
    ids = sorted(docs, reverse=True)
    after = dict(zip(ids, ids[1:] + ids[:1], strict=True))
    for r in rows:
        text, k = docs[r["doc_id"]], len(docs[r["doc_id"]]) // 3
        edited = text[: len(text) - k] + docs[after[r["doc_id"]]][:k]
        assert r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest() and r["n_chars"] == len(text)
    long = [r for r in rows if r["n_chars"] > 300]
    assert np.mean([r["near_edited"] > r["near_next"] for r in long]) > 0.99 and np.mean([r["near_edited"] for r in long]) > 0.4


def test_fingerprints_odd_rows(spark, odd, empty):
    rows = fingerprints.compare_edits(odd).collect()
    assert len(rows) == len(ODD)
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["fingerprint"] == "" == by[2]["fingerprint"] and by[2]["near_edited"] == 1.0
    assert len({r["fingerprint"] for r in rows if r["doc_id"] == 4}) == 1
    assert fingerprints.compare_edits(empty).count() == 0
    one = fingerprints.compare_edits(spark.createDataFrame([(1, "a b c d e f")], "doc_id long, text string")).first()
    assert one["near_next"] == 1.0
    moved = spark.createDataFrame([("q r s t u v w x y z " * 3 + "a1 b2 c3 d4 e5 f6 g7 h8", "a1 b2 c3 d4 e5 f6 g7 h8")], "a string, b string")
    assert moved.select(fingerprints.shift(fingerprints.sketch(F.col("a")), fingerprints.sketch(F.col("b")))).first()[0] == -30


# Pipeline.
def test_pipeline(spark, small):
    import corpus_pipeline

    docs = table(spark, small, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, docs, small)
        assert kept.columns == docs.columns
        assert kept.select("doc_id").subtract(docs.select("doc_id")).count() == 0
        docs = kept.cache()
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, small)
    assert pieces.select("doc_id").distinct().count() == docs.count()
    assert corpus_pipeline.run(spark, small).groupBy("doc_id").count().count() == docs.count()


def brute_near_copies(docs, bound=0.8):
    """The ids that stay if the smallest of each group of texts with exact similarity ``bound`` stays; and the linked pairs."""
    sets = {i: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} or {tuple(w)} for i, w in ((i, t.lower().split()) for i, t in docs)}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    holders, pairs = defaultdict(list), {}
    for i, found in sets.items():
        for near in {j for x in found for j in holders[x]}:
            shared = len(found & sets[near])
            if shared >= bound * (len(found) + len(sets[near]) - shared):
                pairs[near, i] = shared / (len(found) + len(sets[near]) - shared)
                a, b = sorted((find(near), find(i)))
                parent[b] = a
        for x in found:
            holders[x].append(i)
    return sorted(i for i in sets if find(i) == i), pairs


def planted(rng, similarity, n, first, words=455):
    """``n`` texts and a copy of each with single words changed until the exact similarity is just above (or, negative, below)."""
    out = []
    for i in range(n):
        base = [f"w{rng.randrange(5000)}" for _ in range(words)]
        copy, free = list(base), list(range(5, words - 5, 10))
        rng.shuffle(free)
        total = words - 4
        lost = int(total * (1 - abs(similarity)) / (1 + abs(similarity)) / 5) + (similarity < 0)
        for at in free[:lost]:
            copy[at] = f"x{rng.randrange(5000)}"
        out += [(first + 2 * i, " ".join(base)), (first + 2 * i + 1, " ".join(copy))]
    return out


def test_near_copies_are_those_of_brute_force(spark):
    rng = random.Random(11)
    docs = [r for k, s in enumerate((0.8, 0.85, 0.9, -0.79)) for r in planted(rng, s, 60, 1000 * k)]
    want, pairs = brute_near_copies(docs)
    assert len(pairs) == 180 and len(want) == 300 and min(pairs.values()) < 0.81
    kept = simhash.drop_near_copies(spark.createDataFrame(docs, "doc_id long, text string").repartition(4))
    assert sorted(r["doc_id"] for r in kept.collect()) == want


def test_near_copies_of_a_long_run_are_joined(spark):
    rng = random.Random(12)
    base = [f"w{i}" for i in range(300)]
    docs = []
    for i in range(120):
        copy = list(base)
        for at in rng.sample(range(5, 295), 4):
            copy[at] = f"x{i}"
        docs.append((i, " ".join(copy)))
    want, _ = brute_near_copies(docs)
    kept = simhash.drop_near_copies(spark.createDataFrame(docs, "doc_id long, text string"))
    assert sorted(r["doc_id"] for r in kept.collect()) == want


def test_long_runs_give_few_pairs_and_lose_no_link():
    rng = random.Random(13)
    sets = []
    for words in (300, 1500, 2600):
        base = [f"w{words}-{i}" for i in range(words)]
        for _ in range(70):
            copy = list(base)
            for at in rng.sample(range(words), rng.randint(words // 150, words // 25)):
                copy[at] = f"x{rng.randrange(10**6)}"
            sets.append(simhash.shingle_set(" ".join(copy)))
    n = len(sets)
    lanes = np.stack([simhash.near_print(x)[1] for x in sets]).astype(np.uint64)
    columns = np.column_stack([lanes, np.array([len(x) for x in sets], dtype=np.uint64), np.arange(n, dtype=np.uint64)])
    sketches = pa.array([simhash.set_sketch(x) for x in sets])
    assert len({len(x) for x in sketches.to_pylist()}) > 1
    found = simhash.apart_pairs(np.zeros(n, dtype=np.int64), np.arange(n), columns, sketches)
    got = {(min(x, y), max(x, y)) for a, b in found for x, y in zip(a.tolist(), b.tolist(), strict=True)}
    likeness = {(i, j): (lambda c: c / (len(sets[i]) + len(sets[j]) - c))(len(np.intersect1d(sets[i], sets[j]))) for i in range(n) for j in range(i + 1, n)}
    want = {p for p, x in likeness.items() if x >= 0.8}
    within = {p for p in likeness if np.bitwise_count(lanes[p[0]] ^ lanes[p[1]]).sum() <= simhash.NEAR_BITS}
    assert want and want <= got and min(likeness[p] for p in got) > 0.6
    # Fingerprints alone let through several times as many.
    assert len(got) - len(want) < 0.25 * (len(within) - len(want))


def test_near_copies_meet_by_deletion_variants(spark):
    words = [f"w{i}" for i in range(2000)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join([*words[:-1], "end"])), (3, " ".join(reversed(words)))], "doc_id long, text string")
    rows = [(*r[:-1], [r["doc_id"] * 100 + i for i in range(simhash.BANDS)]) for r in simhash.near_prints(docs).collect()]
    classes = spark.createDataFrame(rows, "doc_id long, same long, node long, f0 long, f1 long, f2 long, bands array<long>")
    nodes = {r[0]: r[2] for r in rows}
    # No band is shared, so the fingerprints alone bring the two together.
    assert [{r["a"], r["b"]} for r in simhash.near_links(docs, classes).collect()] == [{nodes[1], nodes[2]}]


def test_fingerprints_hold_all_anchors(spark):
    rng = random.Random(6)
    passage = [f"p{i}" for i in range(50)]
    one, two = [f"a{rng.randrange(10**6)}" for _ in range(6000)], [f"b{rng.randrange(10**6)}" for _ in range(6000)]
    docs = [(2, " ".join([*one, *passage])), (1, " ".join([*two[:100], *passage, *two[100:]]))]
    rows = {r["doc_id"]: r for r in fingerprints.compare_edits(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    for i, text in docs:
        every = spark.createDataFrame([(text,)], "text string").select(fingerprints.anchors(F.col("text"))).first()[0]
        assert len(every) > 3000 and rows[i]["fingerprint"].count(":") == len(every)
    found = spark.createDataFrame([(docs[0][1], docs[1][1])], "a string, b string").select(
        *[fingerprints.sketch(F.col(c)).alias(c) for c in "ab"]
    ).select("a", "b", fingerprints.shift(F.col("a"), F.col("b")).alias("d")).first()
    a, b = ({x["hash"] for x in found[c]} for c in "ab")
    assert found["d"] == 100 - 6000 and len(a & b) > 20
    assert rows[2]["near_next"] == pytest.approx(len(a & b) / len(a | b), abs=1e-6) and rows[2]["near_next"] > 0
    # The edit of 2 ends with the head of 1, passage included.
    assert rows[2]["kept_shift"] == 0 and rows[2]["kept_anchors"] > 1500
    assert rows[2]["borrowed_anchors"] > 500 and 3800 < rows[2]["borrowed_shift"] < 4300


def test_sketches_are_sorted_without_a_comparator(spark):
    rows = spark.createDataFrame([("b a c a b a c d",), ("",)], "text string").select(fingerprints.sketch(F.col("text")).alias("found"), fingerprints.anchors(F.col("text")).alias("read"))
    for found, read in rows.collect():
        assert found == sorted(read)
    # array_sort calls a function for each comparison of two anchors.
    assert "array_sort" not in rows._jdf.queryExecution().optimizedPlan().toString()


def test_rules_count_more_than_the_ten_most_common_words(spark):
    docs = [(i, " ".join(f"w{k:02d}" for k in range(24) for _ in range(24 - k)), "en") for i in range(10)]
    docs += [(10, " ".join(f"w{k:02d}" for k in range(10) for _ in range(24 - k)) + " zz" * 105, "en")]
    got = {r["doc_id"]: r for r in quality_rules.measure(spark.createDataFrame(docs, "doc_id long, text string, lang string"), ["doc_id"]).select("row.doc_id", "bins").collect()}
    assert got[0]["bins"][10:] != got[10]["bins"][10:] and len(got[0]["bins"]) == 25
