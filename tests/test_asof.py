import random

from pyspark.sql import functions as F

from fixtrace.operators import baselines
from fixtrace.operators.asof import inside, last_before
from fixtrace.sources import code


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_last_before_and_inside_equal_all_pairs(spark):
    rng = random.Random(2)
    rows = [(rng.randrange(3), rng.randrange(40), k) for k in range(60)]
    asked = [(k, rng.randrange(4), *sorted((rng.randrange(40), rng.randrange(45)))) for k in range(50)]
    r = spark.createDataFrame(rows, "slot int, seq int, commit_id long")
    a = spark.createDataFrame(asked, "q int, slot int, start int, fix_seq int")
    for inclusive in (False, True):
        want = {q: max((t[1:] for t in rows if t[0] == s and t[1] < to + inclusive), default=None) for q, s, _, to in asked}
        got = {x.q: tuple(x.met) for x in last_before(a, r, F.struct("seq", "commit_id"), ["slot"], inclusive=inclusive).collect()}
        assert got == {q: x for q, x in want.items() if x}
    got = sorted((x.q, x.commit_id) for x in inside(a, r, ["slot"], "start", "fix_seq", "seq", width=7).collect())
    assert got == sorted((q, c) for q, s, lo, hi in asked for t, n, c in rows if s == t and lo < n <= hi)


def test_blame_pairs_no_line_with_all_touches(spark):
    deleted = spark.createDataFrame([(9, 1, 2, 50)], "vuln_id long, file_id int, slot int, fix_seq int")
    content = spark.createDataFrame([(1, 2, k, 100 + k, "main") for k in range(60)], "file_id int, slot int, seq int, commit_id long, lane string")
    found = baselines.blame_basic(deleted, content)
    assert "Join" not in plan(found) and [tuple(x) for x in found.collect()] == [(9, 149, 49)]


def test_a_statement_is_filled_from_one_template(spark):
    rows = spark.createDataFrame([(7, 2, 1, 0, 0, 0)], "file_id int, slot int, n0 int, n1 int, n2 int, n3 int")
    assert plan(code.with_text(rows.repartition(1))).count("regexp_replace") <= 8  # three marks and the layout, in two branches
