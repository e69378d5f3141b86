"""Worked examples, theorems on random documents, and strategies against one another."""

import random

import pytest
from pyspark.sql import functions as F

from outline_engine.operators import assembly, baselines, classes, depth
from outline_engine.plans import fixtures, planner
from outline_engine.schemas import HEADERS
from outline_engine.sources.sinks import stored


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


@pytest.mark.parametrize("name", list(fixtures.DOCUMENTS))
def test_worked_examples(spark, name):
    doc, h = fixtures.DOCUMENTS[name], fixtures.headers(spark, name)
    for m in ("local", "global", "half"):
        assert [r[1] for r in rows(baselines.infer(h, m), "pos", "parent_pos")] == list(fixtures.PARENTS[name, m])
    assert [r[1] for r in rows(assembly.truth(h), "pos", "parent_pos")] == list(doc["parent"])


def test_contrast_documents(spark):
    for name, robust in (("local_only", (True, False)), ("global_only", (False, True))):
        f = classes.flags(fixtures.headers(spark, name)).first()
        assert (f["robust_local"], f["robust_global"]) == robust
        assert (f["conf_local"], f["conf_global"]) == robust


def test_candidates_of_the_filing(spark):
    h = fixtures.headers(spark, "filing")
    banded = depth.banded(h, depth.local(depth.groups(h)))
    found = {r["pos"]: r for r in assembly.candidates(banded, assembly.by_bands(banded)).collect()}
    assert (found[20]["covering"], found[20]["allowed"], found[20]["chosen"]) == (2, 2, 16)


@pytest.fixture(scope="module")
def random_headers(spark):
    rng = random.Random(5)
    out = []
    for doc in range(120):
        path = [0]
        out.append((doc, 0, "root", 0, "", 0))
        for pos in range(1, rng.randint(1, 25)):
            rk = rng.randint(1, min(len(path), 4))
            path = path[:rk] + [pos]
            out.append((doc, pos, f"s{rk}" if rng.random() < 0.7 else f"x{rng.randint(0, 4)}", rk, f"t{pos}", rng.randint(0, 9)))
    return spark.createDataFrame(out, HEADERS).cache()


def test_strategies_agree(spark, random_headers):
    h = depth.banded(random_headers, depth.blend(depth.groups(random_headers), 0.5))
    want = rows(assembly.by_stack(h), "doc_id", "pos", "parent_pos", "span_end")
    for s in ("bands", "fold"):
        assert rows(assembly.assemble(h, s), "doc_id", "pos", "parent_pos", "span_end") == want


def test_flags_share_a_pass_and_need_no_large_plan(spark, random_headers):
    shifted = random_headers.withColumn("doc_id", F.col("doc_id") * 2**55 - 2**60)
    plans = []

    def keep(df):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString().count("Join "))
        return stored(df)

    both = {"plain": random_headers, "shifted": shifted}
    found = classes.flags_of(both, keep)
    assert "Join " not in found._jdf.queryExecution().optimizedPlan().toString() and max(plans) <= 4
    columns = classes.flags(random_headers).columns
    want = rows(classes.flags(random_headers), *columns)
    for name, h in both.items():
        assert rows(found.where(F.col("corpus") == name), *columns) == (want if name == "plain" else [(r[0] * 2**55 - 2**60, *r[1:]) for r in want])


def test_theorems_on_random_documents(spark, random_headers):
    h = random_headers
    f = classes.flags(h).collect()
    for r in f:
        for m in ("local", "global", "half"):
            assert r[f"robust_{m}"] == r[f"conf_{m}"]
            assert not r["loose"] or r[f"robust_{m}"]
        assert not r["well"] or r["loose"]
        assert not r["aligned"] or r["robust_local"]
    true = assembly.truth(h)
    for m in ("local", "global", "half"):
        tree = baselines.infer(h, m)
        assert all(r["valid"] for r in classes.valid_tree(tree).collect())
        spans = {r["doc_id"]: r["robust"] for r in classes.certify(tree, true).collect()}
        edges = {r["doc_id"]: r["robust"] for r in classes.robust_by_edges(tree, true).collect()}
        assert spans == edges
    sizes = depth.groups(h).groupBy("doc_id").agg(F.count("*").alias("m"))
    assert classes.tree_depth(baselines.infer(h)).join(sizes, "doc_id").where("depth > m").count() == 0


def test_any_mix_of_depths_is_robust_on_loose_documents(spark, random_headers):
    """Along every true edge of a loose document each blend grows by one at least, so its tree is robust."""
    h = random_headers
    true, g = assembly.truth(h), depth.groups(h)
    kinds = {r["doc_id"]: r for r in classes.formats(h, true).collect()}
    edges = true.where("parent_pos IS NOT NULL").select("doc_id", "pos", "parent_pos")
    table = g.select("doc_id", "style", (F.col("g") % 3 / 2).alias("k"))
    for d in (depth.blend(g, depth.hashed_k(3)), depth.blend(g, depth.hashed_k(11, 5)), depth.blend(depth.with_k(g, table), F.col("k")), depth.blend(g, depth.k_by(F.col("style").startswith("s")))):
        at = depth.banded(h, d)
        robust = {r["doc_id"]: r["robust"] for r in classes.certify(assembly.by_bands(at), true).collect()}
        assert all(robust[doc] for doc, r in kinds.items() if r["loose"])
        sd = at.select("doc_id", "pos", "sd")
        gap = edges.join(sd, ["doc_id", "pos"]).join(sd.select("doc_id", F.col("pos").alias("parent_pos"), F.col("sd").alias("up")), ["doc_id", "parent_pos"]).groupBy("doc_id").agg(F.min(F.col("sd") - F.col("up")).alias("gap")).collect()
        assert all(r["gap"] >= 1 - 1e-6 for r in gap if kinds[r["doc_id"]]["loose"])


def test_local_depth_is_true_depth_on_aligned_documents(spark, random_headers):
    true = assembly.truth(random_headers)
    aligned = {r["doc_id"] for r in classes.formats(random_headers, true).collect() if r["aligned"]}
    level = {(r["doc_id"], r["pos"]): r["level"] for r in assembly.levels(true).collect()}
    sd = depth.banded(random_headers, depth.local(depth.groups(random_headers))).collect()
    assert aligned and all(r["sd"] == level[r["doc_id"], r["pos"]] for r in sd if r["doc_id"] in aligned)


def test_global_conformance_is_the_order_of_openers(spark, random_headers):
    true = assembly.truth(random_headers)
    want = classes.conformant(random_headers, true, depth.global_first(depth.groups(random_headers)))
    assert rows(classes.conformant_by_openers(random_headers, true), "doc_id", "conformant") == rows(want, "doc_id", "conformant")


def test_mixing_finished_depths_has_no_guarantee(spark):
    """Scanned, a child of k 1 is one deeper than its parent whatever the parent's k; finished depths mixed by group are not."""
    local, whole = {"p": 1, "c": 2}, {"p": 4, "c": 5}
    assert 0 * local["p"] + 1 * whole["p"] > 1 * local["c"] + 0 * whole["c"]
    h = spark.createDataFrame([(1, i, s, 0, "", 0) for i, s in enumerate("rabcpd")], HEADERS)
    g = depth.groups(h)
    done = {r["style"]: r["sd"] for r in depth.blend_finished(g, 0.25).collect()}
    assert done == {r["style"]: r["sd"] for r in depth.global_first(g).collect()}


def test_virtual_root(spark):
    """A first style that occurs again gets a virtual root above, in every strategy; all else stays."""
    h = spark.createDataFrame([(1, p, s, 0, "", 0) for p, s in enumerate("abacb")] + [(2, p, s, 0, "", 0) for p, s in enumerate("abcb")] + [(3, 5, "a", 0, "", 0)], HEADERS)
    want = [(1, -1, None, 5), (1, 0, -1, 2), (1, 1, 0, 2), (1, 2, -1, 5), (1, 3, 2, 4), (1, 4, 2, 5)]
    for strategy in assembly.STRATEGIES:
        got = rows(baselines.infer(h, strategy=strategy), "doc_id", "pos", "parent_pos", "span_end")
        assert [r for r in got if r[0] == 1] == sorted(want, key=lambda r: r[1])
        assert [r[1:3] for r in got if r[0] == 2] == [(0, None), (1, 0), (2, 1), (3, 0)]
        assert [r[1:] for r in rows(baselines.infer(h, strategy=strategy, root="virtual"), "doc_id", "pos", "parent_pos", "span_end") if r[0] == 3] == [(4, None, 6), (5, 4, 6)]
        assert all(r["valid"] for r in classes.valid_tree(baselines.infer(h, strategy=strategy)).collect())
    plain = classes.valid_tree(baselines.infer(h, root="first")).collect()
    assert {r["doc_id"]: r["valid"] for r in plain} == {1: False, 2: True, 3: True}


def test_earlier_algorithm_is_for_its_class(spark, random_headers):
    well = classes.formats(random_headers, assembly.truth(random_headers)).select("doc_id", "well")
    got = {r["doc_id"] for r in baselines.prior_global(random_headers, well).select("doc_id").distinct().collect()}
    assert got == {r["doc_id"] for r in well.where("well").collect()} and len(got) < well.count()


def test_jumps_and_closed_form(spark, random_headers):
    g = depth.groups(random_headers)
    assert rows(depth.local_by_jumps(g), "doc_id", "g", "sd") == rows(depth.local(g), "doc_id", "g", "sd")
    assert rows(depth.blend(g, 0.0), "doc_id", "g", "sd") == rows(depth.global_first(g), "doc_id", "g", "sd")


def test_planner(spark, random_headers):
    p = planner.plan("half", k=0.0, **planner.measure(random_headers))
    assert p.method == "global" and p.strategy == "fold"
    assert rows(p.run(random_headers), "doc_id", "pos", "parent_pos") == rows(baselines.infer(random_headers, "global"), "doc_id", "pos", "parent_pos")
    plan = baselines.infer(random_headers)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "body_words" not in plan.split("InMemory")[0]


def test_edges_of_input(spark):
    empty = spark.createDataFrame([], HEADERS)
    assert baselines.infer(empty).count() == 0
    one = spark.createDataFrame([(1, 0, "root", 0, "", 0)], HEADERS)
    assert rows(baselines.infer(one), "pos", "parent_pos", "span_end") == [(0, None, 1)]
    same = spark.createDataFrame([(1, 0, "root", 0, "", 0)] + [(1, p, "a", 1, "", 0) for p in range(1, 6)], HEADERS)
    assert [r[1] for r in rows(baselines.infer(same), "pos", "parent_pos")] == [None, 0, 0, 0, 0, 0]
    chain = spark.createDataFrame([(1, p, f"s{p}", p, "", 0) for p in range(40)], HEADERS)
    assert rows(baselines.infer(chain), "pos", "parent_pos", "span_end") == rows(baselines.deep(chain), "pos", "parent_pos", "span_end")
