"""Per-version methods by the spans of lines equal a look at every case and tag, and pair no case with all tags."""

import random

import pytest
from pyspark.sql import functions as F

from fixtrace.functions.text import simhash64
from fixtrace.operators import baselines, versions
from fixtrace.plans import workloads
from fixtrace.plans.lab import PER_VERSION

TAGS = 12


@pytest.fixture(scope="module")
def made(spark):
    """Two files, slots that share lines, a slot that starts late; cases, tags, touches and every version by brute force."""
    rng = random.Random(5)
    touches = [(1, f, s, f * 10000 + s * 100 + q, q, "main", f"x{rng.randrange(4)} = {rng.randrange(3)};") for f in (1, 2) for s in range(1, 7) for q in range(1, 60) if rng.random() < 0.2 and (s < 6 or q > 30)]
    cases = [(100 + k, 1, 1 + k % 2, 8 + 7 * k) for k in range(7)]
    tags = [(1, f"v{n}", n, n, 5 * n) for n in range(1, TAGS + 1)]
    t = spark.createDataFrame(touches, "repo_id int, file_id int, slot int, commit_id long, seq int, lane string, text string")
    c = spark.createDataFrame(cases, "vuln_id long, repo_id int, file_id int, fix_seq int")
    g = spark.createDataFrame(tags, "repo_id int, tag string, tag_no int, commit_id long, seq int")
    at = lambda f, q: {x[2]: x[6] for x in sorted(touches, key=lambda x: x[4]) if x[1] == f and x[4] <= q}
    held = {(v, n): lines for v, _, f, _ in cases for _, _, n, _, q in tags if (lines := at(f, q))}
    bodies = {v: at(f, q - 1) for v, _, f, q in cases}
    return t, c, g, held, bodies


def frames(spark, made):
    t, c, g, _, _ = made
    return c, versions.line_spans(c, g, t).localCheckpoint(), baselines.vulnerable_bodies(c, t).localCheckpoint()


def brute(spark, made):
    rows = [(v, 1, n, lines) for (v, n), lines in made[3].items()]
    return spark.createDataFrame(rows, "vuln_id long, repo_id int, tag_no int, lines map<int,string>")


def pairs(df):
    rows = [(r.vuln_id, r.tag_no) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def test_files_and_bodies_are_whole(spark, made):
    c, spans, bodies = frames(spark, made)
    files = {(r.file_id, r.tag_no): r.lines for r in versions.file_lines(spans, width=5).collect()}
    of = {r.vuln_id: r.file_id for r in c.collect()}
    assert {(v, n): files[of[v], n] for v, n in made[3]} == made[3]
    assert {r.vuln_id: r.body for r in bodies.collect()} == made[4]


def test_hybrid_reads_only_near_versions(spark, made):
    c, spans, bodies = frames(spark, made)
    claims = spark.createDataFrame([(100 + k, 2, 9) for k in range(6)], "vuln_id long, lo int, hi int")
    near = baselines.line_candidates(c, bodies, spans, baselines.hybrid_needs(), claims)
    want = pairs(baselines.hybrid(brute(spark, made).where("tag_no between 2 and 9 and vuln_id < 106"), bodies))
    assert pairs(baselines.hybrid(near, bodies)) == want and 0 < len(want) <= near.count() < 6 * 8


@pytest.mark.parametrize("width", [1, 2, 4, 9])
def test_windows_are_sought_in_near_versions(spark, made, width):
    c, spans, bodies = frames(spark, made)
    near = baselines.line_candidates(c, bodies, spans, baselines.window_needs(width))
    want = pairs(baselines.window_match(brute(spark, made), bodies, width, 0.3))
    assert pairs(baselines.window_match(near, bodies, width, 0.3)) == want and want and near.count() < len(made[3])


def test_presence_comes_from_spans(spark, made):
    c, spans, bodies = frames(spark, made)
    rng = random.Random(1)
    draw = lambda n: [f"x{rng.randrange(4)} = {rng.randrange(3)};" for _ in range(n)]
    changed = [(100 + k, draw(k % 3), draw(2 - k % 2)) for k in range(7)] + [(999, [], [])]
    got = pairs(baselines.patch_presence(c, spans, spark.createDataFrame(changed, "vuln_id long, deleted array<string>, added array<string>"), 1.0, 0.9))
    want = set()
    for v, deleted, added in changed:
        for (w, n), lines in made[3].items():
            here, d, a = set(lines.values()), set(deleted), set(added)
            if w == v and (not d or len(here & d) / len(d) >= 1.0) and (not a or len(here & a) / len(a) <= 0.9):
                want.add((v, n))
    assert got == want and 0 < len(want) < len(made[3])


def test_versions_are_not_made_distinct_again(spark, small):
    for name in PER_VERSION:
        df = workloads.method_query(name)(spark, small)
        assert df.count() == df.distinct().count()
    plan = workloads.method_query("patch_presence")(spark, small)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.lstrip().startswith("Project") or plan.lstrip().startswith("Generate")  # tags are told apart last, nothing is shuffled after


def test_graphs_are_built_for_near_versions_only(spark, made):
    c, spans, bodies = frames(spark, made)
    marks = spark.createDataFrame([(v, s, b[s], 1.0 + s % 2) for v, b in made[4].items() for s in list(b)[:2]], "vuln_id long, slot int, pre string, weight double")
    near = baselines.line_candidates(c, bodies, spans, F.lit(1))
    want = set()
    weighted = {v: ({b[s]: 1.0 + s % 2 for s in list(b)[:2]}, set(list(b)[:2])) for v, b in made[4].items()}
    for (v, n), lines in made[3].items():
        one, two = (baselines.weighted_graph(sorted(x.items()), weighted[v][1], weighted[v][0]) for x in (made[4][v], lines))
        if baselines.weighted_jaccard(one, two) >= 0.3:
            want.add((v, n))
    assert pairs(baselines.dependence_match(near, bodies, marks, 0.3)) == want and want


def test_each_file_is_digested_once(spark, made):
    c, spans, bodies = frames(spark, made)
    tokens = spark.createDataFrame([(1, []), (2, ["a"]), (3, ["a", "b", "a", "="]), (4, [f"t{k}" for k in range(300)])], "k int, t array<string>")
    spaced = tokens.select("k", simhash64(F.col("t")).alias("want"), F.create_map(F.lit(1), F.array_join("t", " ")).alias("lines"))
    got = baselines.digests(spaced, "lines", "k int, want long").collect()
    assert len(got) == 4 and all(r.digest == r.want for r in got)
    found = pairs(baselines.function_digest(c, versions.file_lines(spans), bodies, 6))
    digest = lambda df, col: df.withColumn("d", simhash64(baselines._tokens(col)))
    every = digest(brute(spark, made), "lines").join(digest(bodies, "body").select("vuln_id", F.col("d").alias("e")), "vuln_id")
    want = pairs(every.where(F.bit_count(F.col("d").bitwiseXOR(F.col("e"))) <= 6))
    assert found == want and 0 < len(want) < len(made[3])
