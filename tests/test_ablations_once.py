"""Ablations of the tree level share one pass over the texts and one over the touches."""

from pyspark.sql import functions as F

from fixtrace.functions import ctree
from fixtrace.functions.text import digest
from fixtrace.operators import backtrack, similarity
from fixtrace.plans import workloads
from fixtrace.plans.lab import lab_of
from fixtrace.sources import code


def test_variants_are_as_compared_one_by_one(spark, small):
    odd = spark.createDataFrame([("a = b + 1;", "if ("), ("f(1, 2);", "f(12);"), ("copy_block(a, b, c);", "memcpy(a, c, b);"), (None, "x;"), ("x;", "x;")], "pre string, post string")
    pairs = lab_of(spark, small).pairs.select("pre", "post").distinct().limit(400).unionByName(odd).localCheckpoint()
    variants = [*workloads.ABLATIONS.values(), (2, ctree.RULES)]
    got = similarity.tree_variants(pairs, code.callees(spark), variants)
    got = {(r.pre, r.post): r.sims for r in pairs.distinct().select("pre", "post", digest("pre", "post").alias("pair")).join(got, "pair").collect()}
    for k, (depth, rules) in enumerate(variants):
        want = {(r.pre, r.post): r.sim_b for r in similarity.compare(pairs, code.callees(spark), None, depth, rules).collect()}
        assert {p: s[k] for p, s in got.items()} == want and len(want) > 300
    assert any(len(set(s)) > 1 for s in got.values())


def test_digests_tell_where_a_text_ends(spark):
    row = spark.createDataFrame([("ab", "c", "a", "bc")], "p string, q string, r string, s string").select(digest("p", "q").alias("x"), digest("r", "s").alias("y"), digest("p").alias("z")).first()
    assert len({bytes(row.x), bytes(row.y), bytes(row.z)}) == 3 and len(row.x) == 16


def test_ablations_sort_the_touches_once(spark, small, monkeypatch):
    calls, many, one = [], backtrack.many_stops, backtrack.statement_stops
    monkeypatch.setattr(backtrack, "many_stops", lambda *a, **k: calls.append("many") or many(*a, **k))
    monkeypatch.setattr(backtrack, "statement_stops", lambda *a, **k: calls.append("one") or one(*a, **k))
    rows = workloads.w12_ablations(spark, small).collect()
    assert calls == ["many"] and len(rows) == len(workloads.ABLATIONS)
    lab = lab_of(spark, small)
    full = next(r for r in rows if r.without == "full")
    assert full.n_refactorings == lab.pairs.where("edit_kind = 1").count()
    want = workloads.m.macro(workloads._score(lab, "two_level"), []).select(*(F.round(c, 6).alias(c) for c in ("precision", "recall", "f1"))).first()
    assert (full.precision, full.recall, full.f1) == (want.precision, want.recall, want.f1)
