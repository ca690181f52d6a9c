from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from fixtrace.operators import blame, reach
from fixtrace.plans.lab import Lab
from fixtrace.sources.history import History


@pytest.fixture(scope="module")
def history(spark, small):
    return History(spark, small)


@pytest.fixture(scope="module")
def ancestors(history):
    parents = defaultdict(list)
    for r in history.commit_edge.collect():
        parents[r.child_id].append(r.parent_id)
    out = {}
    for r in sorted(history.commit.collect(), key=lambda r: (r.repo_id, r.seq)):
        out[r.commit_id] = {r.commit_id}.union(*(out[p] for p in parents[r.commit_id]))
    return out


def test_labels_edges_and_doubling_agree(history, ancestors):
    want = {(c, a) for c, s in ancestors.items() for a in s}
    commit = history.commit
    by_labels = commit.alias("a").join(commit.alias("b"), reach.contains("a", "b")).select("b.commit_id", "a.commit_id")
    assert {tuple(r) for r in by_labels.collect()} == want
    doubled = reach.double_edges(history.commit_edge)
    assert {(r.child_id, r.ancestor_id) for r in doubled.collect()} <= want
    assert {(r.child_id, r.ancestor_id) for r in doubled.collect()} >= {p for p in want if p[0] != p[1]}


def test_predecessors_are_the_latest_contained_touches(history, ancestors):
    slots = defaultdict(list)
    for r in history.touch.collect():
        slots[r.file_id, r.slot].append(r.commit_id)
    want = set()
    for (file, slot), commits in slots.items():
        for c in commits:
            held = [x for x in commits if x != c and x in ancestors[c]]
            want |= {(file, slot, c, x) for x in held if not any(y != x and x in ancestors[y] for y in held)}
    got = blame.predecessors(history.touch).select("file_id", "slot", "commit_id", "pred_commit_id")
    assert {tuple(r) for r in got.collect()} == want


def test_edit_kinds_keep_their_margins(spark, small):
    lab = Lab(spark, small)
    rows = lab.pairs.join(lab.sims, ["pre", "post"]).groupBy("edit_kind").agg(F.min("sim_a").alias("a0"), F.max("sim_a").alias("a1"), F.min("sim_b").alias("b0"), F.max("sim_b").alias("b1"))
    got = {r.edit_kind: r for r in rows.collect()}
    assert got[0].a0 >= 0.9 and got[3].a0 >= 0.9
    assert got[1].a1 < 0.9 and got[1].b0 >= 0.8
    assert got[2].a1 < 0.9 and got[2].b1 < 0.8


def test_affected_versions_hold_the_origin_and_not_the_fix(spark, small):
    lab = Lab(spark, small)
    bounds = lab.arrivals(lab.truth_origin).join(lab.fixes.select("vuln_id", F.col("arrival").alias("fixed_at")), "vuln_id")
    rows = lab.truth.join(bounds.drop("repo_id"), "vuln_id").join(lab.tags.select("repo_id", "tag_no", "seq"), ["repo_id", "tag_no"])
    assert rows.where("seq < arrival or seq >= fixed_at").count() == 0 and rows.count() > 0


def test_method_order(spark):
    """Two levels beat the line level, which beats blaming the last change."""
    from fixtrace.operators import measures as m
    from fixtrace.plans.workloads import _score

    lab = Lab(spark, "/root/testdata/sf0.01")
    f1 = {n: m.macro(_score(lab, n), []).first().f1 for n in ("two_level", "line_only", "blame_basic", "claims")}
    assert f1["two_level"] > f1["line_only"] > f1["blame_basic"] and f1["two_level"] > f1["claims"]


def test_sweeps_walk_merges_and_compare_both_levels(spark):
    """At the engine's own parameters a sweep scores what the engine scores."""
    from fixtrace.operators import measures as m
    from fixtrace.plans.workloads import _PARAMS, _score, _swept

    lab = Lab(spark, "/root/testdata/sf0.01")
    got = _swept(lab, spark.createDataFrame([(0, 900, 800, 700, 2.0)], _PARAMS)).first()
    want = m.macro(_score(lab, "two_level"), []).first()
    assert (got.precision, got.recall, got.f1) == pytest.approx((want.precision, want.recall, want.f1))
    both = lab.pairs.select("pre", "post").distinct().join(lab.sims_both, ["pre", "post"])
    assert both.where("sim_a >= 0.9 and sim_b is not null").count() > 0


def test_edges_give_the_holders_of_every_source(history, ancestors, small, spark):
    from fixtrace.plans.workloads import w16_closure_check

    got = reach.holders(history.commit_edge, history.commit)
    assert {(r.child_id, r.ancestor_id) for r in got.collect()} == {p for c, held in ancestors.items() for p in ((c, x) for x in held | {c})}
    row = w16_closure_check(spark, small).first()
    lab = Lab(spark, small)
    asked = {r.fix_commit_id for r in lab.cases.collect()} | {r.origin_commit_id for r in lab.truth_origin.collect()}
    assert row.n_differ == 0 and row.n_pairs == sum(len((held | {c}) & asked) for c, held in ancestors.items())
