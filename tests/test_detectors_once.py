"""Detectors tell each change once: whole functions by streams of a file, text pairs in one frame."""

import collections
import math

from fixtrace.functions import ctree
from fixtrace.functions.text import squash
from fixtrace.operators import detectors
from fixtrace.plans.lab import lab_of
from pyspark.sql import functions as F


def test_functions_along_a_file_are_the_whole_ones(spark, small):
    """The same counts as from whole files put together one by one."""
    lab = lab_of(spark, small)
    content = lab.content.select("file_id", "slot", "seq", "lane", "text").collect()
    main = collections.defaultdict(list)
    for r in sorted(content, key=lambda r: r.seq):
        if r.lane == "main":
            main[r.file_id].append(r)
    found = collections.defaultdict(int)
    for r in lab.pairs.select("*", squash(F.col("pre")).alias("p"), squash(F.col("post")).alias("q")).collect():
        pos = r.seq - 1 if r.lane == "main" else r.fork
        held = {t.slot: t.text for t in main[r.file_id] if t.seq <= pos and t.slot != r.slot}
        before, after = ([x for _, x in sorted((held | {r.slot: text}).items())] for text in (r.p, r.q))
        found[r.file_id // 1000, r.edit_kind != 2, r.pre, r.post, *before, "|", *after] += 1
    want = collections.Counter()
    for (repo, same, _, _, *lines), n in found.items():
        at = lines.index("|")
        p, q = detectors.function_features(lines[:at]), detectors.function_features(lines[at + 1 :])
        changed = tuple(v for k, (x, y) in enumerate(zip(p, q, strict=True)) if x != y for v in (k, abs(x - y)))
        want[repo, same, changed, round(sum(map(min, p, q)) / max(sum(p), sum(q), 1), 12), n] += 1
    rows = lab.function_changes.collect()
    assert want and want == collections.Counter((r.repo_id, r.same, tuple(r.changed), round(r.share, 12), r.n) for r in rows)
    assert len({(r.repo_id, r.same, r.draw, bytes(r.digest)) for r in rows}) == len(rows) == len(found)


def test_a_constant_is_no_reason_to_parse_again(monkeypatch):
    parse, n = ctree.parse, []
    monkeypatch.setattr(ctree, "parse", lambda text: n.append(text) or parse(text))
    lines = lambda k: [f"if (once_{k % 2} != 0 && b == {k}) c = b;", f"c = c + {k};"]
    rows = {tuple(detectors.function_features(lines(k))) for k in range(100, 200)}
    assert len(rows) == 1 and len(n) <= 12  # two spellings of the first line, one of the second, for trees and for flow


def test_cosines_of_a_pair_make_no_rows(spark):
    pairs = spark.createDataFrame([("a = b;", "a = c;"), ("", "x"), ("f(f(f(f(1))));", "g(f(f(1)));"), ("ab", "ab")], "pre string, post string")
    df = detectors.vector(pairs)
    assert "Generate" not in df._jdf.queryExecution().executedPlan().toString()

    def plain(a, b):
        p, q = (collections.Counter(t[k : k + 3] for k in range(len(t) - 2)) for t in (a, b))
        size = math.sqrt(sum(n * n for n in p.values())) * math.sqrt(sum(n * n for n in q.values()))
        return sum(n * q[g] for g, n in p.items()) / size if size else 0.0

    got = df.collect()
    assert len(got) == 4 and all(abs(r.similarity - plain(r.pre, r.post)) < 1e-12 for r in got)


def test_grid_counts_by_thresholds_reached(spark):
    rows = spark.createDataFrame([(True, 1.0, 2), (True, 0.3, 1), (False, 0.05, 4), (False, 0.9999999, 1), (True, None, 8), (None, 0.5, 16)], "same boolean, similarity double, n long").withColumn("d", F.lit("x"))
    df = detectors.at_thresholds(rows, ["d"])
    got = {r.theta: (r.tp, r.fp, r.fn) for r in df.collect()}
    assert got == {t: (3 if t <= 0.3 else 2, 1, 0 if t <= 0.3 else 1) for t in detectors.GRID}


def test_texts_are_joined_to_their_changes_once(spark, small):
    lab = lab_of(spark, small)
    got = detectors.by_text(lab.changes, lab.sims_both)
    count = lambda df: collections.Counter((r.repo_id, r.same, r.n, round(r.similarity, 9)) for r in df.collect())
    one = {"edit": detectors.edit(lab.changes), "md5": detectors.md5(lab.changes), "vector": detectors.vector(lab.changes), "tree": detectors.tree(lab.changes, lab.sims_both), "two_level": detectors.two_level(lab.changes, lab.sims_both)}
    for name, scored in one.items():
        assert count(got.where(F.col("detector") == name)) == count(detectors.weighed(lab.changes, scored)), name
