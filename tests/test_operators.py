import pytest
from pyspark.sql import functions as F

from fixtrace.functions.text import alike, cosine, edit_budget, line_similarity, version_key
from fixtrace.operators import backtrack, extraction, judge, measures, versions, weights
from fixtrace.sources import code


def tags_of(spark):
    rows = [(1, f"2.{k}", k, 1000 + k, k * 10) for k in range(35, 43)]
    return spark.createDataFrame(rows, "repo_id int, tag string, tag_no int, commit_id long, seq int")


def test_version_difference(spark):
    origin = spark.createDataFrame([(7, 1, 345)], "vuln_id long, repo_id int, arrival int")
    fix = spark.createDataFrame([(7, 1, 355)], "vuln_id long, repo_id int, arrival int")
    got = versions.affected_versions(origin.withColumn("arrival", F.lit(350)), fix, tags_of(spark))
    assert [r.tag for r in got.collect()] == ["2.35"]
    assert [(r.lo, r.hi) for r in versions.as_ranges(got).collect()] == [(35, 36)]
    both = spark.createDataFrame([(7, 1, 355), (7, 1, 375)], "vuln_id long, repo_id int, arrival int")
    assert {r.tag_no for r in versions.affected_versions(origin.withColumn("arrival", F.lit(350)), both, tags_of(spark), "all").collect()} == {35, 36, 37}


@pytest.mark.parametrize(("lost", "want"), [((), 1.0), (("s1",), 5 / 7), (("s1", "b1"), 4 / 7)])
def test_score_arithmetic(spark, lost, want):
    rows = [(n, 2.0 if n[0] == "s" else 1.0, n not in lost) for n in ("s1", "s2", "b1", "b2", "b3")]
    df = spark.createDataFrame(rows, "n string, w double, ok boolean")
    assert df.agg(weights.score(F.col("ok"), F.col("w")).alias("x")).first().x == pytest.approx(want)


def test_vote_agreement_and_jaccard(spark):
    rows = [(1, k, "a") for k in range(10)] + [(1, k, "b") for k in range(6)] + [(1, k, "c") for k in range(5)] + [(1, 0, "c")]
    runs = spark.createDataFrame(rows, "vuln_id long, run_no int, stmt string")
    assert {(r.stmt, r.votes) for r in measures.vote(runs).collect()} == {("a", 10), ("b", 6)}
    assert measures.agreement(runs).first().agreement == pytest.approx(1 / 3)
    sets = [{"a"} | ({"b"} if k < 6 else set()) | ({"c"} if k < 5 else set()) for k in range(10)]
    pairs = [len(x & y) / len(x | y) for i, x in enumerate(sets) for y in sets[i + 1 :]]
    assert measures.mean_jaccard(runs).first().mean_jaccard == pytest.approx(sum(pairs) / 45)


def test_claim_audit(spark):
    tags = spark.createDataFrame([(1, k) for k in range(1, 10)], "repo_id int, tag_no int")
    real = {1: [4, 5], 2: [4, 5, 6], 3: [4, 5], 4: [4], 5: [4, 5], 6: [5, 6]}
    found = spark.createDataFrame([(v, t) for v, ts in real.items() for t in ts], "vuln_id long, tag_no int")
    claims = {1: [1, 2, 3, 4, 5], 2: [4], 3: [4, 5], 4: None, 5: [4], 6: [4, 5]}
    df = spark.createDataFrame([(v, 1, c) for v, c in claims.items()], "vuln_id long, repo_id int, claimed array<int>")
    got = {r.vuln_id: (r.audit, r.pattern_found) for r in measures.audit(df, found, tags).collect()}
    assert got == {1: ("over_inclusive", "all_before"), 2: ("incomplete", "single_version"), 3: ("correct", None), 4: ("missing", None), 5: ("incomplete", "single_version"), 6: ("mixed", None)}


@pytest.mark.parametrize(("p", "r", "want"), [(0.918, 0.945, 0.931), (0.668, 0.418, 0.514), (0.756, 0.851, 0.801), (0.842, 0.881, 0.861), (0.372, 0.625, 0.466)])
def test_printed_scores_follow(spark, p, r, want):
    assert spark.range(1).select(measures.f1(F.lit(p), F.lit(r)).alias("x")).first().x == pytest.approx(want, abs=0.001)


def test_bounded_and_full_edit_decisions_agree(spark):
    texts = ["", "a", "abc", "abd", "if (a > b) c = a;", "if (a > b) c = b;", "while (x) y();", "é", "e", "x" * 40, "x" * 36 + "yyyy"]
    df = spark.createDataFrame([(x, y) for x in texts for y in texts], "a string, b string")
    for permille in (100, 500, 800, 900, 1000):
        full = F.round(line_similarity(F.col("a"), F.col("b")) * 1000, 6) >= permille
        assert df.where(full != alike(F.col("a"), F.col("b"), permille)).count() == 0
    assert spark.range(1).select(edit_budget(F.lit("x" * 10), F.lit(""), 900).alias("k")).first().k == 1


def test_cosine_and_version_order(spark):
    row = spark.range(1).select(cosine(F.array(F.lit(1.0), F.lit(0.0)), F.array(F.lit(1.0), F.lit(1.0))).alias("c"), (version_key(F.lit("v2.10")) > version_key(F.lit("v2.9"))).alias("later")).first()
    assert row.c == pytest.approx(0.5**0.5) and row.later


def test_sensitive_statements_and_wrappers(spark):
    table = weights.sensitive_table(spark)
    wrappers = weights.sensitive_wrappers(code.callees(spark), table)
    assert {(0, "copy_block"), (2, "take_block"), (4, "drop_block")} <= {tuple(r) for r in wrappers.collect()}
    rows = [(0, "memcpy(a, b, n);"), (0, "copy_block(a, n, b);"), (0, "f(a);"), (1, "x = a * b;"), (1, "x = a;"), (5, "memcpy(a, b, n);")]
    got = weights.assign_weights(spark.createDataFrame(rows, "vuln_type int, text string"), table, wrappers)
    assert {(r.vuln_type, r.text, r.weight) for r in got.collect()} == {(t, s, w) for (t, s), w in zip(rows, [2.0, 2.0, 1.0, 2.0, 1.0, 1.0], strict=True)}


PATCH = """diff --git a/lib/x.c b/lib/x.c
--- a/lib/x.c
+++ b/lib/x.c
@@ -10,3 +10,3 @@ int f(void)
 int a;
-if (n > 5) {
+if (n > 5 || n < 0) {
 g(n);
diff --git a/ChangeLog b/ChangeLog
--- a/ChangeLog
+++ b/ChangeLog
@@ -1,1 +1,2 @@
+fixed
 old
"""


def test_patch_lines(spark):
    diff = extraction.parse_patch(spark.createDataFrame([(1, PATCH), (2, None)], "commit_id long, text string"))
    got = {(r.path, r.op, r.old_no, r.new_no, r.text) for r in diff.collect()}
    assert ("lib/x.c", "del", 11, None, "if (n > 5) {") in got and ("lib/x.c", "add", None, 11, "if (n > 5 || n < 0) {") in got
    assert ("lib/x.c", "ctx", 12, 12, "g(n);") in got and ("ChangeLog", "add", None, 1, "fixed") in got
    code_only = extraction.drop_irrelevant(diff)
    assert {r.path for r in code_only.collect()} == {"lib/x.c"}
    row = extraction.classify_patch(code_only).first()
    assert (row.added, row.deleted, row.patch_class, row.large) == (1, 1, "both", False)


ODD_PATCH = """--- a/src/ring.c
+++ b/src/ring.c
@@ -20,4 +20,5 @@ static int turn(void)
 int k;
--- i;
+++ j;
+*p = 0;
+k = 1;
 done();
-- x
@@ -40,6 +41,6 @@
 /* a note
-   old words
+ * new words
  */
-n = 1; /* one */
+n = 2; // two
 }
-/* gone */

\\ No newline at end of file
--- a/old/lost.c
+++ /dev/null
@@ -1 +0,0 @@
-int lost;
--- not part of any hunk
+++ nor this
"""


def test_hunks_are_as_long_as_their_headers_say(spark):
    diff = extraction.parse_patch(spark.createDataFrame([(1, ODD_PATCH), (2, ""), (3, "no patch")], "commit_id long, text string").withColumn("path", F.lit("clash")))
    got = [(r.path, r.op, r.old_no, r.new_no, r.text) for r in diff.orderBy("hunk", F.coalesce("new_no", "old_no"), "op").collect()]
    assert {("src/ring.c", "del", 21, None, "-- i;"), ("src/ring.c", "add", None, 21, "++ j;"), ("src/ring.c", "add", None, 22, "*p = 0;"), ("src/ring.c", "add", None, 23, "k = 1;")} <= set(got)
    assert ("old/lost.c", "del", 1, None, "int lost;") in got and not [r for r in got if "not part" in r[4] or "nor this" in r[4]]
    assert ("src/ring.c", "ctx", 22, 24, "done();") in got and ("src/ring.c", "del", 23, None, "- x") in got
    code = {(r.op, r.text) for r in extraction.drop_irrelevant(diff).where("op <> 'ctx'").collect()}
    assert code == {("del", "-- i;"), ("add", "++ j;"), ("add", "*p = 0;"), ("add", "k = 1;"), ("del", "- x"), ("del", "n = 1; /* one */"), ("add", "n = 2; // two"), ("del", "int lost;")}
    assert extraction.parse_patch(spark.createDataFrame([], "commit_id long, text string")).count() == 0


def test_judge_runs_are_kept_and_parsed(spark):
    cases = spark.createDataFrame([(5, ["overflow"], "d")], "vuln_id long, weakness array<string>, description string")
    flows = spark.createDataFrame([(5, "3 n = a * b; 4 p = malloc(n); 9 f(x);")], "vuln_id long, flow string")
    prompts = judge.build_prompts(cases, flows)
    assert judge.examples_are_apart(spark, cases)
    runs = judge.run_judge(prompts, judge.RuleProvider(0.0))
    named = judge.named_statements(prompts, runs)
    assert {(r.line_no, r["count"]) for r in named.groupBy("line_no").count().collect()} == {(3, 10), (4, 10)}
    again = judge.run_judge(prompts, judge.HttpProvider("none"), cache=runs)  # all runs are cached, so nothing is asked
    assert again.count() == 10
    bad = spark.createDataFrame([("no format",), ("vulnerability logic: x\nvulnerable lines: 3, 3, 7",)], "a string")
    assert [r.x.lines for r in bad.select(judge.parse_answer(F.col("a")).alias("x")).collect()] == [None, [3, 7]]


def test_cost(spark):
    runs = spark.createDataFrame([(1, 1_000_000, 1_000_000)], "vuln_id long, tokens_in int, tokens_out int")
    assert measures.judge_cost(runs).first().cost == pytest.approx(1.40)


def test_walks_have_no_step_limit(spark):
    n = 67
    stmts = spark.createDataFrame([(1, 0, 7, n)], "vuln_id long, slot int, file_id long, fix_commit_id long")
    preds = spark.createDataFrame([(7, 0, k, k - 1) for k in range(1, n + 1)], "file_id long, slot int, commit_id long, pred_commit_id long")
    compared = spark.createDataFrame([(7, 0, k, k, k == 0) for k in range(n)], "file_id long, slot int, commit_id long, seq long, lost boolean")
    stop = backtrack.exact_stops(stmts, preds, compared).first()
    assert stop is not None and (stop.stop_commit, stop.stop_seq) == (0, 0)
