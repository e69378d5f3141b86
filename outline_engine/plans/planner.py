"""Choices made before a plan is built, each a named rule with a reason."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from outline_engine.operators import assembly, baselines, depth

#: Folds copy their output; beyond this many headers in a document they are not chosen.
FOLD_HEADERS = 2_000
#: Bands repeat a header once per deeper band; beyond this many the stack is cheaper.
MOST_BANDS = 64


@dataclass
class Plan:
    method: str
    k: float = 1.0
    strategy: str = "auto"
    rules: list[str] = field(default_factory=list)

    def run(self, headers: DataFrame) -> DataFrame:
        if self.method in ("deep", "wide"):
            return baselines.APPROACHES[self.method](headers)
        slim = headers.select("doc_id", "pos", "style")
        g = depth.groups(slim)
        depths = depth.global_first(g) if self.method == "global" else depth.blend(g, self.k)
        return assembly.assemble(depth.banded(slim, depths), "bands" if self.strategy == "auto" else self.strategy)


def plan(method: str = "local", k: float = 1.0, longest: int | None = None, styles: int | None = None) -> Plan:
    """``longest`` and ``styles``: the most headers and styles of a document, if known (see ``measure``)."""
    made = Plan(method, k, rules=["text columns are cut off before the exchange", "depths are scanned on groups, not headers"])
    if method == "half":
        made.method, made.k = "blend", k
    if made.method in ("blend", "local"):
        made.k = 1.0 if method == "local" else made.k
        if made.k == 0.0:
            made.method = "global"
            made.rules.append("a blend of 0 is the closed form of global-first")
        elif made.k == 1.0:
            made.rules.append("a blend of 1 is local-first")
    if made.method in ("deep", "wide"):
        made.rules.append("chains and flat trees are stated without assembly")
    if longest is not None and styles is not None:
        made.strategy = "fold" if longest <= FOLD_HEADERS else "stack" if styles > MOST_BANDS else "bands"
        made.rules.append(f"assembly by {made.strategy} for documents of up to {longest} headers and {styles} styles")
    return made


def measure(headers: DataFrame) -> dict[str, int]:
    """The most headers and (about) the most styles of a document, from one aggregation."""
    row = headers.groupBy("doc_id").agg(F.count("*").alias("n"), F.approx_count_distinct("style").alias("s")).agg(F.max("n").alias("longest"), F.max("s").alias("styles")).first()
    return {"longest": row["longest"] or 0, "styles": row["styles"] or 0}
