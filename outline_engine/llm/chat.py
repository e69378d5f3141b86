"""Chat transcripts from event logs: fold events into messages, then render with a reversible template.

An event log has ``conv_id, turn, seq, kind, role, text``.  Kinds: ``start`` opens a turn with its
first text, ``delta`` appends, ``edit`` replaces the text so far, ``regenerate`` throws it away (the
deltas after it form the new one), ``delete`` removes the turn unless a later start, edit or
regenerate brings it back.  A turn's events are folded by ``seq``; its role is the last one named.
A log is folded by (conversation, turn) and a conversation rendered as one row of output, so all of a
conversation is in one task in the end; no other task waits for it.

Template: ``<turn ROLE>`` newline TEXT ``</turn>`` newline.  In texts a backslash is put after the
``<`` of every ``<turn`` or ``</turn``, however many backslashes are already there, so the markers
cannot occur in a text and removing one backslash restores it.  In roles ``% < >`` and newlines are
percent-encoded.  ``spans`` has a row per turn: where its text lies in the output, in code points,
and whether it is under the loss mask (assistant turns).

Defined cases: null texts and roles are empty; unknown kinds and events without a conversation's
turn number count as deltas of the turn "null"; equal ``seq`` values are ordered by kind, then text;
repeated rows are events of their own; a conversation's text is bounded by a string's 2 GB; an empty log
gives an empty result; other columns are never read.  Everything is DataFrame expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from outline_engine.llm.columns import let
from outline_engine.llm.storage import table

CLOSE = "</turn>\n"
LEARNED_ROLE = "assistant"
#: Deltas of a log made from finished turns: so many characters each, or more so that there are at most this many.
DELTA_CHARS = 200
MOST_DELTAS = 64


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\\*/?turn)", r"<\\$1")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*/?turn)", "<$1")


def escape_role(role: Column) -> Column:
    for char, code in (("%", "%25"), ("<", "%3C"), (">", "%3E"), ("\n", "%0A")):
        role = F.replace(role, F.lit(char), F.lit(code))
    return role


def unescape_role(role: Column) -> Column:
    for char, code in (("\n", "%0A"), (">", "%3E"), ("<", "%3C"), ("%", "%25")):
        role = F.replace(role, F.lit(code), F.lit(char))
    return role


def reconstruct(events: DataFrame) -> DataFrame:
    """conv_id, turn, role, text: the final messages of an event log."""
    kind = F.lower(F.coalesce(F.col("kind").cast("string"), F.lit("")))
    event = F.struct("seq", kind.alias("kind"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), F.col("role").cast("string").alias("role"))
    logs = events.groupBy("conv_id", "turn").agg(F.array_sort(F.collect_list(event)).alias("log"))
    renews = lambda e: e["kind"].isin("start", "edit", "regenerate", "delete")

    def final(log: Column) -> Column:
        last = F.array_max(F.transform(log, lambda e, i: F.when(renews(e), i).otherwise(0)))
        live = let(last, lambda k: F.slice(log, k + 1, F.size(log)))
        named = F.filter(log, lambda e: e["role"].isNotNull())
        return F.struct(
            F.array_join(F.transform(live, lambda e: F.when(e["kind"].isin("regenerate", "delete"), F.lit("")).otherwise(e["text"])), "").alias("text"),
            (F.get(live, F.lit(0))["kind"] == "delete").alias("gone"),
            F.coalesce(F.try_element_at(named, F.lit(-1))["role"], F.lit("")).alias("role"),
        )

    folded = logs.select("conv_id", "turn", let(F.col("log"), final).alias("m"))
    return folded.where("NOT m.gone").select("conv_id", "turn", "m.role", "m.text")


def render(messages: DataFrame) -> DataFrame:
    """conv_id, n_turns, formatted, spans: each conversation's turns in order, in the template."""
    head = F.concat(F.lit("<turn "), escape_role(F.col("role")), F.lit(">\n"))
    cut = messages.select("conv_id", "turn", head.alias("head"), escape(F.col("text")).alias("body"), (F.col("role") == LEARNED_ROLE).alias("loss"))
    sized = cut.withColumn("head_n", F.length("head").cast("long")).withColumn("n", F.length("body").cast("long"))
    before = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, -1)
    placed = sized.withColumn("start", F.coalesce(F.sum(F.col("head_n") + F.col("n") + len(CLOSE)).over(before), F.lit(0)) + F.col("head_n"))
    turn = F.struct("turn", F.concat("head", "body", F.lit(CLOSE)).alias("segment"), F.struct("start", F.col("n").alias("length"), "loss").alias("span"))
    grouped = placed.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("turns"))
    return grouped.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.array_join(F.transform("turns", lambda t: t["segment"]), "").alias("formatted"),
        F.transform("turns", lambda t: t["span"]).alias("spans"),
    )


def parse(formatted: Column) -> Column:
    """The (role, text) turns of a rendered conversation."""
    pieces = F.split(formatted, CLOSE)
    return F.transform(
        let(pieces, lambda p: F.slice(p, 1, F.size(p) - 1)),
        lambda p: F.struct(
            unescape_role(F.regexp_extract(p, r"^<turn ([^>]*)>\n", 1)).alias("role"),
            unescape(F.regexp_replace(p, r"^<turn [^>]*>\n", "")).alias("text"),
        ),
    )


def learned_text(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped.  The output is cut at its turn ends once, so cost is linear."""

    def texts(pieces: Column, at: Column) -> Column:
        def under(piece: Column, i: Column) -> Column:
            before = F.get(at, F.greatest(i - 1, F.lit(0)))
            begin = F.when(i == 0, F.lit(0)).otherwise(before["start"] + before["length"] + len(CLOSE))
            own = F.get(at, i)
            return F.when(own["loss"], unescape(F.substring(piece, (own["start"] - begin + 1).cast("int"), own["length"].cast("int")))).otherwise("")

        return F.array_join(F.transform(F.slice(pieces, 1, F.size(at)), under), "")

    return let(F.split(formatted, CLOSE), lambda p: let(spans, lambda s: texts(p, s)))


def streamed(turns: DataFrame) -> DataFrame:
    """The events that would have led to ``turns`` (conv_id, turn, role, text): texts come in deltas; by a hash, some turns are drafts first that are edited, some are regenerated."""
    text, fate = F.coalesce("text", F.lit("")), F.pmod(F.xxhash64("conv_id", "turn"), F.lit(4))
    size = F.greatest(F.lit(DELTA_CHARS), F.ceil(F.length(text) / MOST_DELTAS)).cast("int")
    none = F.array().cast("array<struct<kind:string,role:string,text:string>>")

    def event(kind: Column | str, text: Column, role: Column | None = None) -> Column:
        return F.struct((F.lit(kind) if isinstance(kind, str) else kind).alias("kind"), (F.lit(None).cast("string") if role is None else role).alias("role"), text.alias("text"))

    draft = event("start", F.concat(F.lit("draft "), F.reverse(F.substring(text, F.lit(1), F.lit(DELTA_CHARS)))), F.col("role"))
    before = F.when(fate == 0, F.array(draft, event("delta", F.lit(" and more")), event("regenerate", F.lit("")))).when(fate == 1, F.array(draft)).otherwise(none)
    first = F.when(fate == 0, "delta").when(fate == 1, "edit").otherwise("start")
    deltas = F.transform(
        F.sequence(F.lit(0), F.greatest(F.ceil(F.length(text) / size), F.lit(1)).cast("int") - 1),
        lambda i: event(F.when(i == 0, first).otherwise("delta"), F.substring(text, i * size + 1, size), F.when((i == 0) & (fate > 1), F.col("role"))),
    )
    told = turns.select("conv_id", "turn", F.posexplode(F.concat(before, deltas)).alias("seq", "e"))
    return told.select("conv_id", "turn", F.col("seq").cast("long").alias("seq"), "e.kind", "e.role", "e.text")


def op1_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    said = r"\### Assistant: </turn> ok"
    probe = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise(LEARNED_ROLE).alias("role"), F.lit(said).alias("text"))
    numbered = rows.unionByName(probe).withColumn("line", F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "role", "text")).cast("long"))
    done = render(reconstruct(streamed(numbered.select("conv_id", F.col("line").alias("turn"), "role", "text"))))
    back = F.array_join(F.transform(parse(F.col("formatted")), lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    learned = done.select("conv_id", "n_turns", "formatted", back.alias("back"), learned_text(F.col("formatted"), F.col("spans")).alias("learned"))
    digest = lambda c: F.sha2(F.col(c).cast("binary"), 256)
    return learned.select(
        "conv_id",
        "n_turns",
        digest("back").alias("turns_sha256"),
        F.length("learned").cast("long").alias("loss_chars"),
        digest("learned").alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


OP1_SQL = r"""
WITH r AS (
  SELECT conv_id, turn, role, text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '\### Assistant: </turn> ok'), (-7, 1, 'assistant', '\### Assistant: </turn> ok')
), t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, role AS r0, text AS t0,
    replace(replace(replace(replace(coalesce(role, ''), '%', '%25'), '<', '%3C'), '>', '%3E'), chr(10), '%0A') AS safe_role,
    regexp_replace(coalesce(text, ''), '<(\\*/?turn)', '<\\\1', 'g') AS safe_text FROM r
), c AS (
  SELECT conv_id, CAST(count(*) AS BIGINT) AS n_turns,
    string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, r0 NULLS FIRST, t0 NULLS FIRST) AS turns,
    coalesce(string_agg(text, '' ORDER BY turn, r0 NULLS FIRST, t0 NULLS FIRST) FILTER (role = 'assistant'), '') AS learned,
    CAST(sum(length('<turn >') + 1 + length(safe_role) + length(safe_text) + length('</turn>') + 1) AS BIGINT) AS formatted_chars
  FROM t GROUP BY conv_id
)
SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, CAST(length(learned) AS BIGINT) AS loss_chars, sha256(learned) AS loss_sha256, formatted_chars FROM c
"""
