"""Scores of all methods come from runs of tags and one pass over the touches, and equal those of each method by itself."""

import random

import pytest
from pyspark.sql import functions as F

from fixtrace.operators import backtrack, baselines, measures, versions
from fixtrace.plans import lab as labs
from fixtrace.plans import workloads


def test_all_scores_equal_each_methods_own(spark, small):
    lab = labs.lab_of(spark, small)
    cells = lambda df: {tuple(r) for r in df.collect()}
    names = ["method", "precision", "recall", "n_projects", "undefined_precision", "high_precision", "full_recall", "f1"]
    got = workloads.w03_method_scores(spark, small).select(names)
    want = set()
    for name in labs.METHODS:
        own = workloads.rounded(measures.macro(workloads._score(lab, name), ["method"]), "precision", "recall", "f1")
        want |= cells(own.select(names))
    assert cells(got) == want and len(want) == len(labs.METHODS)


def test_scores_write_no_row_for_each_affected_tag(spark, small, monkeypatch):
    """Neither the truth nor a walk is spread over tags, and the touches are sorted for all walks at once."""
    passes = []
    swept = backtrack.swept_stops

    def refuse(*_, **__):
        raise AssertionError("versions are spread over tags")

    monkeypatch.setattr(versions, "affected_versions", refuse)
    monkeypatch.setattr(backtrack, "statement_stops", refuse)
    monkeypatch.setattr(baselines, "statement_stops", refuse)
    monkeypatch.setattr(backtrack, "swept_stops", lambda *a, **k: passes.append(1) or swept(*a, **k))
    lab = labs.Lab(spark, small)
    monkeypatch.setattr(workloads, "lab_of", lambda *_: lab)
    assert workloads.w03_method_scores(spark, small).count() == len(labs.METHODS)
    assert len(passes) == 1 and "truth" not in lab.__dict__


def test_runs_are_counted_as_their_tags_are(spark):
    rng = random.Random(4)
    truth = [(m, v, v % 3, rng.choice((None, *range(12))), rng.randrange(12)) for m in "ab" for v in range(30)] + [("a", 90, 7, None, 4)]
    found = []
    for m, v, *_ in truth[:-1]:
        cuts = sorted(rng.sample(range(1, 16), 2 * rng.randrange(4)))
        found += [(m, v, a, b - 1) for a, b in zip(cuts[::2], cuts[1::2], strict=True)]
    repo = {(m, v): r for m, v, r, *_ in truth}
    kind = "m string, vuln_id long, repo_id int, tag_no int"
    pred = spark.createDataFrame([(m, v, repo[m, v], n) for m, v, a, b in found for n in range(a, b + 1)], kind)
    real = spark.createDataFrame([(m, v, r, n) for m, v, r, x, stop in truth if x is not None for n in range(x + 1, stop + 1)], kind)
    cells = lambda df: {(r.m, r.repo_id): (r.tp, r.fp, r.fn) for r in df.collect()}
    want = cells(measures.confusion(pred, real, ["m", "repo_id"]))
    runs = spark.createDataFrame(found, "m string, vuln_id long, first int, last int")
    got = measures.confusion_of_runs(runs, spark.createDataFrame(truth, "m string, vuln_id long, repo_id int, real int, stop int"), "m")
    assert cells(got) == want and ("a", 7) not in want


@pytest.mark.parametrize("untouched", ["kept", "excluded"])
def test_own_scores_of_commits(spark, untouched):
    """Against all touches before each fix, with stretches that end inside, and cases that no commit answers."""
    rng = random.Random(6)
    touches = [(f, s, 1000 * f + q, q, "main", rng.random() < 0.15) for f in (1, 2, 3) for q in range(1, 120) for s in range(1, 5) if rng.random() < 0.3 and not (f == 3 and q < 60)]
    touches = [(f, s, c, q, lane, lost and f != 2) for f, s, c, q, lane, lost in touches] + [(1, 1, 5, 70, "feature", True)]
    stmts = [(v, s, 1 + v % 3, 3 + 5 * v, rng.choice((1.0, 2.0))) for v in range(24) for s in rng.sample(range(1, 5), rng.choice((1, 2, 3)))]
    df = spark.createDataFrame(touches, "file_id int, slot int, commit_id long, seq int, lane string, lost boolean")
    asked = spark.createDataFrame(stmts, "vuln_id long, slot int, file_id int, fix_seq int, weight double")
    want = {}
    for v in range(24):
        mine = {s: w for n, s, _, _, w in stmts if n == v}
        f, fix = next((x[2], x[3]) for x in stmts if x[0] == v)
        known = [t for t in touches if t[0] == f and t[1] in mine and t[3] < fix and t[4] == "main"]
        total, rows = sum(mine[s] for s in {t[1] for t in known}), {}
        for _, s, c, q, _, lost in known:
            w, own = rows.get((q, c), (0.0, 0.0))
            rows[q, c] = w + mine[s] * lost, own + mine[s]
        score = {k: 1 - w / (total if untouched == "kept" else own) for k, (w, own) in rows.items()}
        below = [k for k, x in score.items() if round(x * 1000, 6) < 699.5]
        if rows:
            at = max(below) if below else min(rows)
            want[v] = (at[1], at[0], pytest.approx(score[at]), "found" if below else "initial")
    cells = lambda d: {r.vuln_id: (r.origin_commit_id, r.origin_seq, r.score, r.origin_kind) for r in d.collect()}
    assert cells(backtrack.per_commit(asked, df, untouched=untouched)) == want
    assert cells(backtrack.per_commit_both(asked, df, stretch=2).where(F.col("untouched") == untouched)) == want
    assert {x[3] for x in want.values()} == {"found", "initial"} and len(want) < 24
