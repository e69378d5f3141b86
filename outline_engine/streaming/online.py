"""Trees of documents that arrive header by header.

A header's depth and parent are settled when it arrives and never change, so the stream is append
only.  A document's state is its styles' depths, its open path, its next position and headers that came
before their turn; the path is as long as the tree is deep.  Headers whose position has passed are
reported as late and change nothing.

With ``idle_ms``, a document from which nothing has come for so many milliseconds is closed: headers that still wait
for one before them are settled in order, its state is given up, and what comes later starts a new one.
With ``spans``, a row tells the end of a header's span as soon as it leaves the path, the rest when the
document is closed.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUTPUT = "doc_id bigint, pos int, parent_pos int, sd double, late boolean, span_end int"
STATE = "state string"


def settle(state: dict, pos: int, style: str, k: float) -> tuple[int | None, float]:
    """One header: its parent and depth.  ``state``: depths by style, open [pos, depth] path, last and top depth."""
    depths, open_ = state["depths"], state["open"]
    if style not in depths:
        depths[style] = round(k * state["last"] + (1 - k) * state["top"] + 1, 9) if depths else 0.0
        state["top"] = max(state["top"], depths[style])
    sd = depths[style]
    while open_ and open_[-1][1] >= sd:
        state.setdefault("closed", []).append(open_.pop()[0])
    parent = open_[-1][0] if open_ else None
    open_.append([pos, sd])
    state["last"] = sd
    return parent, sd


def infer(headers: DataFrame, k: float = 1.0, *, spans: bool = False, idle_ms: int | None = None) -> DataFrame:
    """doc_id, pos, parent_pos, sd, late, span_end (null but in rows of ends) for a stream of doc_id, pos (from 0 without gaps), style."""
    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout

    def step(key: tuple, frames: Iterator[pd.DataFrame], group: GroupState) -> Iterator[pd.DataFrame]:
        state = json.loads(group.get[0]) if group.exists else {"depths": {}, "open": [], "last": 0.0, "top": 0.0, "next": 0, "held": {}}
        out = []

        def take(pos: int) -> None:
            parent, sd = settle(state, pos, state["held"].pop(str(pos)), k)
            out.append((key[0], pos, parent, sd, False, None))
            if spans:
                out.extend((key[0], p, None, None, False, pos) for p in state.get("closed", ()))
            state["closed"], state["next"] = [], pos + 1

        if group.hasTimedOut:
            for pos in sorted(map(int, state["held"])):
                take(pos)
            if spans:
                out.extend((key[0], p, None, None, False, state["next"]) for p, _ in reversed(state["open"]))
            group.remove()
        else:
            for frame in frames:
                for pos, style in zip(frame["pos"].tolist(), frame["style"].tolist(), strict=True):
                    if pos < state["next"] or str(pos) in state["held"]:
                        out.append((key[0], pos, None, None, True, None))
                    else:
                        state["held"][str(pos)] = style
            while str(state["next"]) in state["held"]:
                take(state["next"])
            group.update((json.dumps(state),))
            if idle_ms:
                group.setTimeoutDuration(idle_ms)
        if out:
            made = pd.DataFrame(out, columns=["doc_id", "pos", "parent_pos", "sd", "late", "span_end"])
            yield made.astype({"parent_pos": "Int32", "pos": "int32", "span_end": "Int32", "sd": "float64"})

    slim = headers.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("pos").cast("int").alias("pos"), "style")
    return slim.groupBy("doc_id").applyInPandasWithState(step, OUTPUT, STATE, "append", timeout)


def once(headers: DataFrame, late: str = "1 hour") -> DataFrame:
    """A stream of headers with event time ``ts``, each (doc_id, pos) once; what the watermark has passed is forgotten."""
    return headers.withWatermark("ts", late).dropDuplicatesWithinWatermark(["doc_id", "pos"])


def with_styles(headers: DataFrame, names: DataFrame) -> DataFrame:
    """A stream of headers joined with a small static table (style, name) of style names."""
    return headers.join(F.broadcast(names), "style", "left")


def activity(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Counts of event types in windows, closed when the watermark passes."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return timed.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")
