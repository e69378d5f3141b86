"""Rule-based quality verdicts: counts with fixed limits, and divergence from a language's habits.

Per language, one pass over the corpus gives two reference histograms: character classes, and the
``COMMON`` most frequent words with one bin for all others.  A document is compared with its
language's references by Jensen-Shannon distance (base 2, so 0 to 1).  A histogram of few
observations is noise, hence the guards: the word test needs ``LEAST_WORDS`` words, the character
test ``LEAST_CHARS`` characters, and a reference ``LEAST_REFERENCE`` words; below them it passes.

Everything is DataFrame expressions.  The reference table has a row per language; it is broadcast
only when it is seen to have at most ``BROADCAST_LANGUAGES`` rows.

Defined cases: a null text is empty and fails (fewer than 50 words); null languages form a language
of their own; repeated rows are judged alike; an empty table gives an empty result; other columns
of the input are never read and never clash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from outline_engine.llm.columns import indices, let, text_of, words_of
from outline_engine.llm.storage import materialise, table

LEAST_BASE_WORDS = 50
MOST_REPEATED_PERCENT = 50
COMMON = 24
LEAST_WORDS = 80
LEAST_CHARS = 200
LEAST_REFERENCE = 1000
CHAR_LIMIT = 0.20
WORD_LIMIT = 0.45
BROADCAST_LANGUAGES = 4096

SYMBOLS = "#*$%&|<>"
PUNCTUATION = r"[.,;:!?'\"()\-]"
OTHER = r"[^\p{L}\p{N}\x20\x09-\x0D.,;:!?'\"()\-]"


def scanned(text: Column) -> Column:
    """chars: counts of capitals, digits, blanks, line ends, punctuation, other signs, remaining letters;
    n_symbols; n_space.  Plain small letters and blanks, most of a text, are taken out first."""
    n = F.length(text)
    blanks = n - F.length(F.replace(text, F.lit(" "), F.lit("")))

    def counts(rest: Column) -> Column:
        tabs, ends = F.regexp_count(rest, F.lit(r"\t")), F.regexp_count(rest, F.lit(r"[\x0A-\x0D]"))
        six = F.array(
            F.regexp_count(rest, F.lit(r"\p{Lu}")),
            F.regexp_count(rest, F.lit(r"\p{N}")),
            blanks + tabs,
            ends,
            F.regexp_count(rest, F.lit(PUNCTUATION)),
            F.regexp_count(rest, F.lit(OTHER)),
        )
        return F.struct(
            let(six, lambda c: F.concat(c, F.array(n - F.aggregate(c, F.lit(0), lambda a, x: a + x)))).alias("chars"),
            (F.length(rest) - F.length(F.translate(rest, SYMBOLS, ""))).cast("long").alias("n_symbols"),
            (blanks + tabs + ends).cast("long").alias("n_space"),
        )

    return let(F.regexp_replace(text, "[a-zß-öø-ÿ ]+", ""), counts)


def repeated_words(words: Column) -> Column:
    """Number of words inside 3-word windows that occur at least twice in the text."""
    windows = F.transform(indices(F.size(words) - 2), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))

    def same(i: Column, j: Column) -> Column:
        return (F.get(words, i) == F.get(words, j)) & (F.get(words, i + 1) == F.get(words, j + 1)) & (F.get(words, i + 2) == F.get(words, j + 2))

    def place(packed: Column) -> Column:
        return packed.bitwiseAND(F.lit(0xFFFFFF)).cast("int")

    def covered(hashes: Column) -> Column:
        # 40 bits of the hash and the window's number in one long sort fast; equal neighbours are compared word by word.
        ordered = F.array_sort(F.transform(hashes, lambda h, i: h.bitwiseAND(F.lit(~0xFFFFFF)).bitwiseOR(i.cast("long"))))
        # Pairs of equal neighbours, each as its two windows' numbers; few in a usual text.
        pairs = let(
            ordered,
            lambda o: F.transform(
                F.filter(indices(F.size(o) - 1), lambda j: F.shiftright(F.get(o, j).bitwiseXOR(F.get(o, j + 1)), 24) == 0),
                lambda j: F.array(place(F.get(o, j)), place(F.get(o, j + 1))),
            ),
        )
        again = F.array_sort(F.array_distinct(F.flatten(F.filter(pairs, lambda p: same(F.get(p, F.lit(0)), F.get(p, F.lit(1)))))))
        return let(again, lambda a: F.aggregate(F.transform(a, lambda i, j: F.least(F.lit(3), F.coalesce(F.get(a, j + 1) - i, F.lit(3)))), F.lit(0), lambda s, x: s + x))

    return let(windows, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))


def repeated_lines(text: Column) -> Column:
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return let(lines, lambda ls: F.size(ls) - F.size(F.array_distinct(ls)))


def _small(df: DataFrame) -> DataFrame:
    """``df``, a row per language, to be broadcast if it has few rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_LANGUAGES else df


def common_words(docs: DataFrame) -> DataFrame:
    """ref_lang, ref_words, padded (the common words between blanks), ref_common (counts; the last: all other words); stored."""
    texts = docs.select(F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("lang"), text_of().alias("text"))
    counted = texts.select("lang", F.explode(words_of(F.col("text"))).alias("word")).groupBy("lang", "word").agg(F.count("*").alias("n"))
    by_count = Window.partitionBy("lang").orderBy(F.desc("n"), "word")
    top = counted.withColumn("rank", F.row_number().over(by_count)).where(F.col("rank") <= COMMON)
    top = top.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("rank", "word", "n"))).alias("top"))
    sums = counted.groupBy("lang").agg(F.sum("n").alias("n_words"))
    counts = F.transform("top", lambda x: x["n"])
    return materialise(
        sums.join(top, "lang").select(
            F.col("lang").alias("ref_lang"),
            F.col("n_words").alias("ref_words"),
            F.transform("top", lambda x: F.concat(F.lit(" "), x["word"], F.lit(" "))).alias("padded"),
            F.concat(counts, F.array(F.col("n_words") - F.aggregate(counts, F.lit(0).cast("long"), lambda a, x: a + x))).alias("ref_common"),
        ),
        "common-words",
    )


def divergence(counts: Column, reference: Column) -> Column:
    """Jensen-Shannon distance of two histograms given as counts; null if either is empty."""

    def shares(c: Column) -> Column:
        total = F.aggregate(c, F.lit(0.0), lambda a, x: a + x)
        return let(total, lambda t: F.when(t > 0, F.transform(c, lambda x: x / t)))

    def part(p: Column, q: Column) -> Column:
        return F.when(p > 0, p * F.log2(2 * p / (p + q))).otherwise(0.0)

    both = F.zip_with(shares(counts), shares(reference), lambda p, q: (part(p, q) + part(q, p)) / 2)
    return F.round(F.sqrt(F.greatest(F.aggregate(both, F.lit(0.0), lambda a, x: a + x), F.lit(0.0))), 6)


def measure(docs: DataFrame, carried: list[str]) -> DataFrame:
    """The ``carried`` columns of ``docs`` as struct ``row``, with statistics and histograms; stored, from one pass over the texts."""
    row = F.struct(*[F.col(f"`{c}`") for c in carried]).alias("row")
    rows = docs.select(row, F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("lang"), text_of().alias("text"))
    joined = rows.join(_small(common_words(docs)), F.col("lang") == F.col("ref_lang"), "left")
    counted = joined.withColumn("words", words_of(F.col("text"))).withColumn("scan", scanned(F.col("text")))
    # Between doubled blanks, every occurrence of a word has two of its own.
    spaced = F.concat(F.lit(" "), F.array_join("words", "  "), F.lit(" "))
    held = lambda t, k: F.coalesce((F.octet_length(t) - F.octet_length(F.replace(t, F.get("padded", F.lit(k)), F.lit("")))) / F.octet_length(F.get("padded", F.lit(k))), F.lit(0)).cast("int")
    hits = let(spaced, lambda t: F.array(*[held(t, k) for k in range(COMMON)]))
    bins = let(hits, lambda h: F.concat(F.slice(h, 1, F.size("padded")), F.array(F.size("words") - F.aggregate(h, F.lit(0), lambda a, x: a + x))))
    return materialise(
        counted.select(
            "row",
            "lang",
            "ref_words",
            "ref_common",
            F.size("words").cast("long").alias("n_words"),
            (F.length("text") - F.col("scan.n_space")).cast("long").alias("word_chars"),
            F.col("scan.n_symbols").alias("n_symbols"),
            repeated_lines(F.col("text")).cast("long").alias("n_dup_lines"),
            repeated_words(F.col("words")).cast("long").alias("n_repeat_words"),
            F.length("text").alias("n_chars"),
            F.col("scan.chars").alias("chars"),
            bins.alias("bins"),
        ),
        "quality-counts",
    )


def judge(docs: DataFrame, carried: list[str] | None = None) -> DataFrame:
    """``carried`` columns of each row of ``docs`` (all by default) as struct ``row``, with its statistics and verdict."""
    counted = measure(docs, docs.columns if carried is None else carried)
    sums = counted.groupBy(F.col("lang").alias("char_lang")).agg(F.array(*[F.sum(F.get("chars", F.lit(i))) for i in range(7)]).alias("ref_chars"))
    stats = counted.join(_small(sums), F.col("lang") == F.col("char_lang")).select(
        "row",
        "ref_words",
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        "n_chars",
        divergence(F.col("chars"), F.col("ref_chars")).alias("char_divergence"),
        divergence(F.col("bins"), F.col("ref_common")).alias("word_divergence"),
    )
    failed = (F.col("n_words") < LEAST_BASE_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED_PERCENT * F.col("n_words"))
    judged = F.coalesce(F.col("ref_words"), F.lit(0)) >= LEAST_REFERENCE
    odd_chars = judged & (F.col("n_chars") >= LEAST_CHARS) & (F.col("char_divergence") > CHAR_LIMIT)
    odd_words = judged & (F.col("n_words") >= LEAST_WORDS) & (F.col("word_divergence") > WORD_LIMIT)
    verdict = ~F.coalesce(odd_chars, F.lit(False)) & ~F.coalesce(odd_words, F.lit(False))
    return stats.withColumn("base_failed", failed).withColumn("kept", ~failed & verdict).drop("ref_words", "n_chars")


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"), ["doc_id"]).select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "char_divergence", "word_divergence")


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the rules keep."""
    return judge(docs).where("kept").select("row.*")


_SPACE = r"[\x20\x09-\x0D]"
OP5_SQL = rf"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, coalesce(lang, '') AS lang, coalesce(text, '') AS text,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents
), c AS (
  SELECT *, len(words) AS n_words, length(text) AS n,
    [len(regexp_extract_all(text, '\p{{Lu}}')), len(regexp_extract_all(text, '\p{{N}}')), len(regexp_extract_all(text, '[\x20\x09]')),
     len(regexp_extract_all(text, '[\x0A-\x0D]')), len(regexp_extract_all(text, '[.,;:!?''"()\-]')),
     len(regexp_extract_all(text, '[^\p{{L}}\p{{N}}\x20\x09-\x0D.,;:!?''"()\-]'))] AS six FROM d
), k AS (SELECT *, list_append(six, n - list_sum(six)) AS chars FROM c
), w AS (SELECT r, lang, unnest(words) AS word, generate_subscripts(words, 1) AS i FROM d
), lw AS (SELECT lang, word, count(*) AS cnt FROM w GROUP BY ALL
), top AS (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY cnt DESC, word) AS k FROM lw QUALIFY k <= {COMMON}
), ref AS (
  SELECT lang, sum(n_words) AS ref_words, [{", ".join(f"sum(chars[{i}])" for i in range(1, 8))}] AS ref_chars FROM k GROUP BY lang
), refbin AS (
  SELECT lang, k, cnt FROM top UNION ALL
  SELECT lang, 0, ref_words - coalesce((SELECT sum(cnt) FROM top t WHERE t.lang = ref.lang), 0) FROM ref
), hit AS (SELECT w.r, t.k, count(*) AS cnt FROM w JOIN top t USING (lang, word) GROUP BY ALL
), docbin AS (
  SELECT k.r, b.k, CASE WHEN b.k = 0 THEN k.n_words - coalesce((SELECT sum(cnt) FROM hit h WHERE h.r = k.r), 0) ELSE coalesce(h.cnt, 0) END AS p, k.n_words AS pt, b.cnt AS q, ref.ref_words AS qt
  FROM k JOIN refbin b USING (lang) JOIN ref USING (lang) LEFT JOIN hit h ON h.r = k.r AND h.k = b.k
), charbin AS (
  SELECT k.r, unnest(k.chars) AS p, k.n AS pt, unnest(ref.ref_chars) AS q, list_sum(ref.ref_chars) AS qt FROM k JOIN ref USING (lang)
), wd AS (
  SELECT r, round(sqrt(greatest(sum(((CASE WHEN p > 0 THEN p / pt * log2(2 * (p / pt) / (p / pt + q / qt)) ELSE 0 END) + (CASE WHEN q > 0 THEN q / qt * log2(2 * (q / qt) / (p / pt + q / qt)) ELSE 0 END)) / 2), 0)), 6) AS word_divergence
  FROM docbin WHERE pt > 0 GROUP BY r
), cd AS (
  SELECT r, round(sqrt(greatest(sum(((CASE WHEN p > 0 THEN p / pt * log2(2 * (p / pt) / (p / pt + q / qt)) ELSE 0 END) + (CASE WHEN q > 0 THEN q / qt * log2(2 * (q / qt) / (p / pt + q / qt)) ELSE 0 END)) / 2), 0)), 6) AS char_divergence
  FROM charbin WHERE pt > 0 GROUP BY r
), win AS (
  SELECT r, i, concat_ws(' ', word, lead(word) OVER x, lead(word, 2) OVER x) AS g, lead(word, 2) OVER x AS third FROM w WINDOW x AS (PARTITION BY r ORDER BY i)
), twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM win WHERE third IS NOT NULL) WHERE n > 1
), rep AS (SELECT r, count(*) AS n_repeat_words FROM (SELECT r, i FROM twice UNION SELECT r, i + 1 FROM twice UNION SELECT r, i + 2 FROM twice) GROUP BY r
), ln AS (SELECT r, unnest(string_split(text, chr(10))) AS line FROM d
), dup AS (SELECT r, count(*) - count(DISTINCT line) AS n_dup_lines FROM ln WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY r
), s AS (
  SELECT k.doc_id, CAST(k.n_words AS BIGINT) AS n_words, CAST(length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
    CAST(len(regexp_extract_all(text, '[#*$%&|<>]')) AS BIGINT) AS n_symbols, CAST(coalesce(n_dup_lines, 0) AS BIGINT) AS n_dup_lines,
    CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words, n, ref_words, char_divergence, word_divergence
  FROM k JOIN ref USING (lang) LEFT JOIN cd USING (r) LEFT JOIN wd USING (r) LEFT JOIN rep USING (r) LEFT JOIN dup USING (r)
), f AS (SELECT *, n_words < {LEAST_BASE_WORDS} OR 100 * n_repeat_words > {MOST_REPEATED_PERCENT} * n_words AS base_failed FROM s)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, char_divergence, word_divergence,
  NOT base_failed AND NOT coalesce(ref_words >= {LEAST_REFERENCE} AND n >= {LEAST_CHARS} AND char_divergence > {CHAR_LIMIT}, false)
    AND NOT coalesce(ref_words >= {LEAST_REFERENCE} AND n_words >= {LEAST_WORDS} AND word_divergence > {WORD_LIMIT}, false) AS kept
FROM f
"""
