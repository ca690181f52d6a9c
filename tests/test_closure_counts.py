from fixtrace.operators import reach


def test_pairs_are_counted_not_written(spark):
    """Main 1-2-4-6, a branch 3-5 from 2 merged at 6, and one commit of which the labels tell less than the edges."""
    edges = spark.createDataFrame([(1, c, p) for c, p in ((2, 1), (4, 2), (6, 4), (3, 2), (5, 3), (6, 5))], "repo_id int, child_id long, parent_id long")
    rows = [(1, k, k, "feature" if k in (3, 5) else "main", 0, 2 if k in (3, 5) else k, 6 if k in (3, 5) else None) for k in range(1, 7)] + [(2, 9, 1, "main", 0, 1, None)]
    kinds = "repo_id int, commit_id long, seq int, lane string, block int, fork int, mseq int"
    commits = spark.createDataFrame(rows, kinds)
    for most in (1, 3, 100):
        got = {r.repo_id: (r.n_pairs, r.n_differ) for r in reach.disagreements(edges, commits, commits, most).collect()}
        assert got == {1: (19, 0), 2: (1, 0)}  # 1 + 2 + 3 + 3 + 4 + 6
    worse = spark.createDataFrame([(*r[:6], 7) if r[1] in (3, 5) else r for r in rows], kinds)
    assert {r.repo_id: (r.n_pairs, r.n_differ) for r in reach.disagreements(edges, worse, worse).collect()} == {1: (19, 2), 2: (1, 0)}
    assert reach.disagreements(edges, commits, commits.limit(0)).count() == 0


def test_no_pairs_in_the_plan(spark, small):
    from fixtrace.plans import workloads

    plan = workloads.w16_closure_check(spark, small)._jdf.queryExecution().optimizedPlan().toString()
    assert "ancestor_id" not in plan and "FlatMapCoGroupsInArrow" in plan
