"""Walks, sweeps and anchors that read the touches once equal their plain forms."""

import random

import pytest
from pyspark.sql import functions as F

from fixtrace.operators import backtrack, measures


@pytest.fixture(scope="module")
def lanes(spark):
    """Touches of two slots with branches of some length, similarities, and statements fixed at several positions."""
    rng = random.Random(3)
    rows = []
    for slot in (1, 2):
        for seq in range(1, 150):
            kind = rng.random()
            a, b = rng.choice((-1, 100, 400, 650, 900, 1001)), rng.choice((-1, 100, 400, 800))
            if kind < 0.35:
                rows.append((1, slot, "main", seq // 9, seq, 1000 * slot + seq, seq, None, *((-1, -1) if not any(r[1] == slot for r in rows) else (a, b))))
            elif kind < 0.6:
                block = seq // 9
                rows.append((1, slot, "feature", block, seq, 1000 * slot + seq, max(block * 9 - rng.choice((1,)), 0), (block + 2) * 9 if block % 5 else None, a, b))
    levels = spark.createDataFrame(rows, "file_id int, slot int, lane string, block int, seq int, commit_id long, fork int, mseq int, a int, b int")
    stmts = [(v, s, 1, 5 + 6 * v) for v in range(24) for s in (1, 2)]
    return levels.localCheckpoint(), spark.createDataFrame(stmts, "vuln_id long, slot int, file_id int, fix_seq int")


GRID = [(100, 100), (400, 800), (700, 400), (900, 800), (1000, 1000), (1001, 1)]


def stops(df):
    return {(r.vuln_id, r.slot): (r.stop_commit, r.stop_seq) for r in df.collect()}


def test_a_sweep_stops_where_each_walk_stops(lanes):
    levels, stmts = lanes
    got = backtrack.swept_stops(stmts, levels, GRID, width=16).collect()
    for k, (x, y) in enumerate(GRID):
        lost = levels.withColumn("lost", (F.col("a") < x) & (F.col("b") < y))
        want = stops(backtrack.statement_stops(stmts, lost))
        plain = stops(backtrack.statement_stops(stmts, lost, "first_parent"))
        assert {(r.vuln_id, r.slot): (r.stop_commit, r.stop_seq) for r in got if r.k == k} == want and want
        assert k or want != plain  # some branch decides


def test_runs_of_tags_are_scored_as_their_tags_are(spark):
    rng = random.Random(8)
    rows = [(p, v, v % 3, rng.choice((None, *range(12))), rng.choice((None, *range(12))), rng.randrange(12)) for p in (1, 2) for v in range(40)] + [(1, 99, 7, None, 11, 3)]
    spans = spark.createDataFrame(rows, "p int, vuln_id long, repo_id int, first int, real int, stop int")
    tags = lambda c: [(p, v, r, n) for p, v, r, first, real, stop in rows for n in range((first if c == "first" else real) if (first if c == "first" else real) is not None else stop, stop)]
    pred, truth = (spark.createDataFrame(tags(c), "p int, vuln_id long, repo_id int, tag_no int") for c in ("first", "real"))
    cells = lambda df: {(r.p, r.repo_id): (r.tp, r.fp, r.fn) for r in df.collect()}
    want = cells(measures.confusion(pred, truth, ["p", "repo_id"]))
    assert cells(measures.confusion_of_spans(spans, ["p", "repo_id"])) == want and (1, 7) not in want


def test_touches_are_not_copied_for_each_point_of_a_grid(spark, lanes, monkeypatch):
    """More pairs of thresholds mean more columns, not more rows to sort."""
    levels, stmts = lanes
    seen = []
    settle = backtrack.settle
    monkeypatch.setattr(backtrack, "settle", lambda df: seen.append(settle(df)) or seen[-1])
    for grid in (GRID[:1], GRID):
        backtrack.swept_stops(stmts, levels, grid)
    assert seen[0].count() == seen[1].count() == stmts.count() + levels.where("lane = 'feature' and mseq is not null").select("slot", "block").distinct().count()


def naive_walk(stmts, preds, lost):
    out = set()
    for v, s, f, start in stmts:
        now, k = {start}, 0
        while now:
            step = {(c, p) for c in now if not k or (f, s, c) not in lost for x, y, c2, p in preds if (x, y, c2) == (f, s, c)}
            out |= {(v, s, f, c, p) for c, p in step}
            now, k = {p for _, p in step}, k + 1
    return out


def test_a_walk_takes_all_steps_of_a_slot_at_once(spark):
    rng = random.Random(4)
    preds = [(f, s, c, p) for f in (1, 2) for s in (1, 2) for c in range(2, 40) for p in rng.sample(range(max(1, c - 4), c), min(2, c - 1))]
    lost = {(f, s, c) for f in (1, 2) for s in (1, 2) for c in range(1, 40) if rng.random() < 0.15}
    stmts = [(v, 1 + v % 2, 1 + v // 2 % 2, rng.randrange(5, 40)) for v in range(12)]
    df = spark.createDataFrame(preds, "file_id int, slot int, commit_id long, pred_commit_id long")
    compared = spark.createDataFrame([(*x, x[2], True) for x in lost], "file_id int, slot int, commit_id long, seq int, lost boolean")
    got = backtrack.walk(spark.createDataFrame(stmts, "vuln_id long, slot int, file_id int, fix_commit_id long"), df, compared)
    rows = [(r.vuln_id, r.slot, r.file_id, r.commit_id, r.pred_commit_id) for r in got.collect()]
    assert len(rows) == len(set(rows)) and set(rows) == naive_walk(stmts, preds, lost)
    assert got._jdf.queryExecution().optimizedPlan().toString().count("FlatMapCoGroupsInArrow") == 1


def test_all_paths_of_a_braid_are_walked_once(spark):
    """Forty diamonds in a row hold 2^40 paths and 160 steps."""
    preds = [(7, 0, c, p) for k in range(0, 120, 3) for c, p in ((k + 3, k + 2), (k + 3, k + 1), (k + 2, k), (k + 1, k))]
    df = spark.createDataFrame(preds, "file_id int, slot int, commit_id long, pred_commit_id long")
    stmts = spark.createDataFrame([(1, 0, 7, 120)], "vuln_id long, slot int, file_id int, fix_commit_id long")
    compared = spark.createDataFrame([(7, 0, k, k, k == 0) for k in range(120)], "file_id int, slot int, commit_id long, seq int, lost boolean")
    assert backtrack.walk(stmts, df, compared).count() == 160
    assert stops(backtrack.exact_stops(stmts, df, compared)) == {(1, 0): (0, 0)}


def test_an_anchor_is_not_held_against_all_touches(spark):
    rng = random.Random(6)
    touches = [(1, s, q, 100 * s + q, "main", None if q == 1 else f"t{rng.randrange(5)}") for s in (1, 2) for q in range(1, 90)]
    compared = spark.createDataFrame(touches, "file_id int, slot int, seq int, commit_id long, lane string, pre string")
    stmts = spark.createDataFrame([(v, 1 + v % 2, 1, 1 + 4 * v, f"t{v % 5}") for v in range(23)], "vuln_id long, slot int, file_id int, fix_seq int, text string")
    alike = lambda pre, post: F.col(pre).substr(2, 1).cast("int") + F.col(post).substr(2, 1).cast("int") != 4
    asked = []

    def compare(pairs):
        asked.append(pairs.count())
        return pairs.where("pre is not null").distinct().withColumn("similar", alike("pre", "post"))

    every = stmts.select("file_id", "slot", F.col("text").alias("post")).join(compared.select("file_id", "slot", "pre"), ["file_id", "slot"]).select("pre", "post")
    flags = every.where("pre is not null").distinct().withColumn("similar", alike("pre", "post"))
    want = stops(backtrack.anchored_stops(stmts, compared, flags))
    assert stops(backtrack.anchored_walk(stmts, compared, compare, 2, 2)) == want and len(want) == 22
    assert len(asked) > 2 and sum(asked) < every.count() / 3
    assert backtrack.anchored_walk(stmts.limit(0), compared, compare).count() == 0
