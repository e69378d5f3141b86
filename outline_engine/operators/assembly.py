"""Header trees from banded headers.

A header's parent is the nearest earlier header of a smaller band, and its span ends at the next
header of the same or a smaller band: on the rightmost path, these are what is left open.  Three
strategies give the same rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from outline_engine.schemas import TREE


def by_bands(h: DataFrame, root: str = "first") -> DataFrame:
    """Each header stands in its own band and all deeper ones of its document; two frames over (document,
    band) then see just the headers that count.  A long document is spread over as many tasks as it has bands.

    ``root``: "first" takes the headers of the least band as they are; "auto" puts a virtual root before
    them, at the position before the first, where there are several; "virtual" always does.  The frame of
    the least band holds just these headers, so it costs no exchange.
    """
    doc = Window.partitionBy("doc_id")
    rows = h.select("doc_id", "pos", "band").withColumn("last", F.max("band").over(doc)).withColumn("end", F.max("pos").over(doc) + 1)
    if root != "first":
        rows = rows.withColumn("least", F.min("band").over(doc))
    spread = rows.withColumn("b", F.explode(F.sequence("band", "last")))
    order = Window.partitionBy("doc_id", "b").orderBy("pos")
    parent = F.last(F.when(F.col("band") < F.col("b"), F.col("pos")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1))
    after = F.lead("pos").over(order)
    found = spread.withColumn("parent_pos", parent).withColumn("span_end", F.coalesce(after, "end"))
    if root == "first":
        return found.where("b = band").select("doc_id", "pos", "parent_pos", F.col("span_end").cast("int"))
    frame = Window.partitionBy("doc_id", "b")
    top = (F.col("band") == F.col("least")) & (F.count("*").over(frame) > (0 if root == "virtual" else 1))
    first = F.min("pos").over(frame)
    marked = found.withColumn("root", F.when(top, (first - 1).cast("int"))).withColumn("opens", first == F.col("pos")).where("b = band")
    own = F.struct("pos", F.coalesce("parent_pos", "root").alias("parent_pos"), F.col("span_end").cast("int").alias("span_end"))
    above = F.struct(F.col("root").alias("pos"), F.lit(None).cast("int").alias("parent_pos"), F.col("end").cast("int").alias("span_end"))
    return marked.select("doc_id", F.explode(F.when(F.col("root").isNotNull() & F.col("opens"), F.array(above, own)).otherwise(F.array(own))).alias("x")).select("doc_id", "x.*")


def with_root(tree: DataFrame, root: str = "auto") -> DataFrame:
    """The same policy for a tree that is made already."""
    if root == "first":
        return tree
    doc = Window.partitionBy("doc_id")
    orphan = F.col("parent_pos").isNull()
    marked = tree.withColumn("n", F.count_if(orphan).over(doc)).withColumn("root", (F.min("pos").over(doc) - 1).cast("int")).withColumn("end", F.max("span_end").over(doc))
    needed = F.col("n") > (0 if root == "virtual" else 1)
    own = F.struct("pos", F.when(orphan & needed, F.col("root")).otherwise(F.col("parent_pos")).alias("parent_pos"), "span_end")
    above = F.struct(F.col("root").alias("pos"), F.lit(None).cast("int").alias("parent_pos"), F.col("end").alias("span_end"))
    return marked.select("doc_id", F.explode(F.when(needed & (F.col("pos") == F.col("root") + 1), F.array(above, own)).otherwise(F.array(own))).alias("x")).select("doc_id", "x.*")


def by_fold(h: DataFrame) -> DataFrame:
    """One fold over a document's headers with the open path as state.  Copies its output, so for short documents."""
    docs = h.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("pos", "band"))).alias("hs"))

    def step(state: Column, x: Column) -> Column:
        open_ = F.filter(state["open"], lambda o: o["band"] < x["band"])
        closed = F.transform(F.filter(state["open"], lambda o: o["band"] >= x["band"]), lambda o: F.struct(o["pos"].alias("pos"), o["parent"].alias("parent"), x["pos"].alias("end")))
        parent = F.try_element_at(open_, F.lit(-1))["pos"]
        return F.struct(F.concat(open_, F.array(F.struct(x["pos"].alias("pos"), x["band"].alias("band"), parent.alias("parent")))).alias("open"), F.concat(state["done"], closed).alias("done"))

    start = F.struct(F.array().cast("array<struct<pos:int,band:int,parent:int>>").alias("open"), F.array().cast("array<struct<pos:int,parent:int,end:int>>").alias("done"))
    end = F.array_max(F.transform("hs", lambda x: x["pos"])) + 1
    done = F.aggregate("hs", start, step, lambda s: F.struct(s["done"].alias("done"), s["open"].alias("open")))
    folded = docs.select("doc_id", end.cast("int").alias("end"), done.alias("s"))
    rest = F.transform("s.open", lambda o: F.struct(o["pos"].alias("pos"), o["parent"].alias("parent"), F.col("end").alias("end")))
    return folded.select("doc_id", F.explode(F.concat("s.done", rest)).alias("x")).select("doc_id", F.col("x.pos").alias("pos"), F.col("x.parent").alias("parent_pos"), F.col("x.end").alias("span_end"))


def stack_tree(rows: list[tuple[int, int]]) -> list[tuple[int, int | None, int]]:
    """(pos, parent, span end) of (pos, band) rows in order."""
    out, open_ = {}, []
    end = rows[-1][0] + 1 if rows else 0
    for pos, band in rows:
        while open_ and open_[-1][1] >= band:
            done = open_.pop()[0]
            out[done] = (done, out[done][1], pos)
        out[pos] = (pos, open_[-1][0] if open_ else None, end)
        open_.append((pos, band))
    return [out[p] for p, _ in rows]


def by_stack(h: DataFrame) -> DataFrame:
    """A stack over documents' headers, sorted in their partitions and streamed by Arrow batches.

    The one strategy whose cost is linear in headers whatever the number of bands; a task holds the
    headers of one document at a time.
    """
    kind = h.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        doc, rows = None, []

        def made() -> pa.RecordBatch:
            found = stack_tree(rows)
            cols = list(zip(*found, strict=True))
            return pa.RecordBatch.from_arrays([pa.array([doc] * len(found)), *(pa.array(c, type=pa.int32()) for c in cols)], names=["doc_id", "pos", "parent_pos", "span_end"])

        for one in batches:
            for d, p, b in zip(*(one.column(c).to_pylist() for c in ("doc_id", "pos", "band")), strict=True):
                if d != doc and rows:
                    yield made()
                    rows = []
                doc = d
                rows.append((p, b))
        if rows:
            yield made()

    dealt = h.select("doc_id", F.col("pos").cast("int").alias("pos"), F.col("band").cast("int").alias("band")).repartition("doc_id").sortWithinPartitions("doc_id", "pos")
    return dealt.mapInArrow(run, TREE.replace("bigint", kind))


STRATEGIES = {"bands": by_bands, "fold": by_fold, "stack": by_stack}


def assemble(h: DataFrame, strategy: str = "bands", root: str = "first") -> DataFrame:
    return by_bands(h, root) if strategy == "bands" else with_root(STRATEGIES[strategy](h), root)


def truth(h: DataFrame) -> DataFrame:
    """The true tree: the same rule on the ranks of the true levels."""
    return by_bands(h.select("doc_id", "pos", F.col("rk").alias("band")))


def levels(tree: DataFrame) -> DataFrame:
    """The tree with ``level``, the number of ancestors, from one running sum of spans opened and closed."""
    opened = tree.select("doc_id", "pos", "parent_pos", "span_end", F.col("pos").alias("at"), F.lit(1).alias("step"))
    closed = tree.select("doc_id", F.lit(None).cast("int").alias("pos"), F.lit(None).cast("int").alias("parent_pos"), F.lit(None).cast("int").alias("span_end"), F.col("span_end").alias("at"), F.lit(-1).alias("step"))
    order = Window.partitionBy("doc_id").orderBy("at", "step")
    summed = opened.union(closed).withColumn("level", F.coalesce(F.sum("step").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("int"))
    return summed.where("pos IS NOT NULL").select("doc_id", "pos", "parent_pos", "span_end", "level")


def closure(tree: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """doc_id, pos, anc_pos for all proper ancestors: at each level above, the last node before.

    ``of``: only those of these nodes (doc_id, pos).  A tree that has its ``level`` keeps it.
    """
    nodes = tree if "level" in tree.columns else levels(tree)
    at = nodes.select("doc_id", F.col("level").alias("b"), "pos", F.lit(True).alias("is_node"))
    asks = (nodes if of is None else nodes.join(of.select("doc_id", "pos"), ["doc_id", "pos"], "left_semi")).where("level > 0").select("doc_id", F.explode(F.sequence(F.lit(0), F.col("level") - 1)).alias("b"), "pos", F.lit(False).alias("is_node"))
    order = Window.partitionBy("doc_id", "b").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    found = at.union(asks).withColumn("anc_pos", F.last(F.when(F.col("is_node"), F.col("pos")), ignorenulls=True).over(order))
    return found.where("NOT is_node").select("doc_id", "pos", "anc_pos")


def candidates(h: DataFrame, tree: DataFrame) -> DataFrame:
    """For each header: how many parents span coverage allows, how many the depths leave, and the choice."""
    path = closure(tree.select("doc_id", "pos", "parent_pos", "span_end"))
    band = h.select("doc_id", "pos", "band")
    prev = Window.partitionBy("doc_id").orderBy("pos")
    before = h.select("doc_id", "pos", F.lag("pos").over(prev).alias("prev_pos")).where("prev_pos IS NOT NULL")
    reach = before.join(path.select("doc_id", F.col("pos").alias("prev_pos"), "anc_pos"), ["doc_id", "prev_pos"]).select("doc_id", "pos", "anc_pos").union(before.select("doc_id", "pos", F.col("prev_pos").alias("anc_pos")))
    both = reach.join(band, ["doc_id", "pos"]).join(band.select("doc_id", F.col("pos").alias("anc_pos"), F.col("band").alias("anc_band")), ["doc_id", "anc_pos"])
    return both.groupBy("doc_id", "pos").agg(
        F.count("*").alias("covering"), F.count_if(F.col("anc_band") < F.col("band")).alias("allowed"), F.max(F.when(F.col("anc_band") < F.col("band"), F.col("anc_pos"))).alias("chosen")
    )
