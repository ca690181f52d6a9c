import hashlib
import html
import random
import re
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from fixtrace.llm import extraction, licenses, lines, mixing, packing, quality, rules, textkit, urls

LOWER = {k: k + 32 for k in range(65, 91)}
TEXTS = [
    None, "", " ", "\n", "\n\n", "one two\nthree", "A a A a A a A a", "é É ñ\u00a0x\x0by", "# $ % a|b <c>", "word " * 60, "x" * 3000, "Mit License and MIT-license, the Apache License Version 2.0",
    "GNU General Public License v3\nGeneral\tPublic LICENSE", "licensed under the MIT license. SPDX-License-Identifier: Apache-2.0", "a\n\na \nA\nb b b b", "𝔘nicode 😀 mit license",
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(k, t, "en", "s", len(t or "")) for k, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("words", F.lit(1)).withColumn("key", F.lit("x"))


def test_word_hashes_follow_words():
    for t in TEXTS:
        words = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        got = textkit.word_hashes(t)
        assert len(got) == len(words)
        assert len(set(got.tolist())) == len(set(words))
    long = " ".join(f"w{k % 977}" for k in range(400_000))  # over one chunk
    assert len(np.unique(textkit.word_hashes(long))) == 977


def test_rule_measures(spark, docs):
    got = {r.doc_id: r for r in rules.ledger(docs).collect()}
    for k, t in enumerate(TEXTS):
        words = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        seen, twice = set(), 0
        for line in (t or "").split("\n"):
            if re.search(r"[^\x20\x09-\x0D]", line):
                twice += line in seen
                seen.add(line)
        three = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        covered = {i + j for i, x in enumerate(three) if three.count(x) > 1 for j in range(3)}
        want = (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t or ""), twice, len(covered))
        r = got[k]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, t
    book = rules.ledger(docs)
    counts = {r.rule: r for r in rules.ablation(book, "base").collect()}
    assert counts["few_words"].n_failed == sum(len((t or "").split()) < 50 for t in TEXTS)
    assert rules.ledger(docs.where("false")).count() == 0


def test_license_places(spark, docs):
    got = {r.doc_id: r for r in licenses.label_texts(docs).collect()}
    phrases = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))
    for k, t in enumerate(TEXTS):
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
        places = sorted((i, lab) for p, lab in phrases for i in range(len(w)) if w[i : i + len(p.split())] == p.split())
        r = got[k]
        assert (r.n_words, r.n_base) == (len(w), len(places))
        assert (r.first_word, r.last_word) == ((places[0][0], places[-1][0]) if places else (None, None))
        base = sorted({x for _, x in places})
        assert r.base_labels == ",".join(base) and set(base) <= set(r.labels.split(",")) | {""} and 0 <= r.score <= 1
    assert {"apache-2.0", "mit"} <= set(got[13].labels.split(","))
    assert licenses.label_texts(docs.where("false")).count() == 0
    assert 400 <= len(licenses.rule_rows()) <= 500


def test_texts_that_hold_no_stem_are_scanned(spark):
    want = {
        "All rights reserved.": "all-rights-reserved", "Permission is hereby granted, free of charge": "permission-notice", "Redistribution and use in source and binary forms": "redistribution",
        "released under the GPL": "gpl", "Distributed under MIT": "mit", "available under the terms of Apache 2.0": "apache-2.0", "in the public\ndomain": "public-domain", "in the public  domain": "public-domain", "no such words": "",
    }
    docs = spark.createDataFrame(list(enumerate(want)) * 2, "doc_id long, text string")
    got = licenses.label_texts(docs).collect()
    assert len(got) == 2 * len(want)
    for r in got:
        assert list(want.values())[r.doc_id] in r.labels.split(",")
    assert licenses.scan(docs.where("doc_id = 0"))[1].count() == 1  # a repeated row adds no detection


def examples(pattern):
    """Every text that a rule's expression matches, one digit for all."""
    from re import _parser

    def item(op, arg):
        if str(op) == "LITERAL":
            return [chr(arg)]
        if str(op) == "IN":
            return ["7"] if str(arg[0][0]) == "RANGE" else [chr(x) for _, x in arg]
        if str(op) == "SUBPATTERN":
            return several(arg[3])
        if str(op) == "BRANCH":
            return [x for part in arg[1] for x in several(part)]
        if str(op) == "ANY":
            return ["z"]
        if str(op) == "MIN_REPEAT":  # words between, at least one
            return ["zz y"]
        if str(op) == "MAX_REPEAT":
            return [x * n for n in {min(arg[0], 9), min(arg[1], 9)} for x in several(arg[2])]
        assert str(op) == "ASSERT"
        return [""]

    def several(parts):
        out = [""]
        for op, arg in parts:
            out = [a + b for a in out for b in item(op, arg)]
        return out

    return sorted(set(several(_parser.parse(pattern))))


def test_every_alternative_of_every_rule_is_detected(spark):
    for rule, _, pattern, keyword, _, _ in licenses.rule_rows():
        assert all(keyword in x.split() for x in examples(pattern)), rule
    cases = [(label, form.format(x)) for label, name, _ in licenses.FAMILIES for x in examples(name) for form in ("licensed under the {}", "spdx license identifier {}", "{} license")]
    cases += [(label, x) for label, pattern, *_ in licenses.NOTICES + licenses.SENTENCES for x in examples(pattern)]
    assert {("mpl", "mpl license"), ("eupl", "licensed under the eupl"), ("cc-by", "cc by license"), ("agpl", "agplv3 license"), ("gpl-2.0", "gpl version2 license")} <= set(cases)
    docs = spark.createDataFrame([(k, x) for k, (_, x) in enumerate(cases)] + [(-1, "SPDX-License-Identifier: MPL-2.0")], "doc_id long, text string")
    got = {r.doc_id: r.labels.split(",") for r in licenses.label_texts(docs).collect()}
    assert not [c for k, c in enumerate(cases) if c[0] not in got[k]] and "mpl" in got[-1]


def test_overlaps_are_resolved_by_priority_then_containment(spark):
    rng = random.Random(3)
    names = [x for _, name, _ in licenses.FAMILIES for x in examples(name)[:1]] + ["version 2 0", "license", "licensed under the", "spdx license identifier", "dual licensed under", "the", "terms of the", "copyright 2001"]
    names += [x for _, pattern, *_ in licenses.SENTENCES for x in examples(pattern)[:1]]
    texts = ["x released under the apache license version 2.0 y"] + [" ".join(rng.choice(names) for _ in range(12)) for _ in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {}
    for r in licenses.scan(docs)[1].collect():
        got.setdefault(r.doc_id, set()).add((r["first"], r["last"], r.priority, r.rule))
    for k, text in enumerate(texts):
        joined = " " + " ".join(re.findall(licenses.WORDS, text.translate(LOWER))) + " "
        every = []
        for rule, _, pattern, _, priority, _ in licenses.rule_rows():
            for m in re.finditer(pattern, joined):
                first = joined[: m.start()].count(" ")
                every.append((first, first + m[0].count(" ") - 1, priority, rule))
        stays = set()
        for a in every:
            higher = any(b[2] > a[2] and b[0] <= a[1] and a[0] <= b[1] for b in every)
            inside = any(b != a and b[2] == a[2] and b[0] <= a[0] and a[1] <= b[1] and (b[:2] != a[:2] or b[3] < a[3]) for b in every)
            if not higher and not inside:
                stays.add(a)
        assert got.get(k, set()) == stays, text
    assert len({r[0] for r in licenses.rule_rows()}) == len(licenses.rule_rows())


def test_line_runs(spark):
    shared, longer = "This very line is shared by a number of documents", "Another line of more than forty code points, é too"
    texts = {k: f"head {k}\n  {shared.upper() if k % 2 else shared}\t\nshort\n{longer if k < 4 else 'x'}" for k in range(1, 8)} | {20: None, 21: "", 22: shared + "\n" + shared, 23: "\n"}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string").withColumn("h1", F.lit(3))
    for params in (lines.Params(), lines.Params(batches=5, fanout=2), lines.Params(batches=1)):
        got = {r.doc_id: r for r in lines.drop_lines(df, params).collect()}
        for k, t in texts.items():
            want = [x for x in (t or "").split("\n") if not (x.strip(" \t\n\x0b\x0c\r").translate(LOWER) == shared.lower() and k != 22)]
            assert got[k].text == "\n".join(want) and got[k].n_lines == (t or "").count("\n") + 1
            assert got[k].n_dropped == got[k].n_lines - len(want)
            assert got[k].h1 == 3
    assert lines.drop_lines(df.where("false")).count() == 0


def test_new_batches_keep_only_novel_lines(spark, tmp_path):
    runs = lines.LineRuns(spark, f"file://{tmp_path}/runs", fanout=2)
    key = lambda *rows: spark.createDataFrame(list(rows), "doc_id long, h1 long, h2 long")
    for k in range(5):
        runs.ingest(key((k, 1, 1), (k, 10 + k, 0)))
    assert {(r.h1, r.n_docs, r.last_doc) for r in runs.merged().collect()} == {(1, 5, 4)} | {(10 + k, 1, k) for k in range(5)}
    fresh = runs.novel(key((9, 1, 1), (9, 99, 0)))
    assert [r.h1 for r in fresh.collect()] == [99]
    plan = fresh._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "LeftAnti" in plan
    assert sum(map(len, runs.levels)) <= 3
    runs.drop()
    assert not (tmp_path / "runs").exists()


def test_runs_hold_counts_and_each_key_once(spark, tmp_path):
    runs = lines.LineRuns(spark, f"file://{tmp_path}/told", fanout=3)
    key = lambda *rows: spark.createDataFrame(list(rows), "doc_id long, h1 long, h2 long")
    told = lambda: [(sorted((r.h1, r.n_docs, r.last_doc) for r in runs.counts([p]).collect()), sorted(r.h1 for r in runs.keys([p]).collect())) for p in runs.paths()]
    runs.ingest(key((9, 1, 1), (9, 2, 2)))
    runs.ingest(key((3, 1, 1), (4, 1, 1), (4, 3, 3)))
    assert told() == [([(1, 1, 9), (2, 1, 9)], [1, 2]), ([(1, 2, 4), (3, 1, 4)], [3])]
    runs.ingest(key((5, 3, 3)))
    assert told() == [([(1, 3, 9), (2, 1, 9), (3, 2, 5)], [1, 2, 3])] and runs.levels[0] == []
    runs.ingest(key((6, 2, 2), (6, 7, 7)))
    assert told() == [([(2, 1, 6), (7, 1, 6)], [7]), ([(1, 3, 9), (2, 1, 9), (3, 2, 5)], [1, 2, 3])]
    runs.drop()


@pytest.mark.parametrize("short", [0, 16])
def test_lines_are_looked_up_by_bisection(spark, monkeypatch, short):
    monkeypatch.setattr(lines, "SHORT", short)
    rows = [(n, sorted(range(0, 2 * n, 2)), x) for n in (0, 1, 2, 3, 8, 33) for x in range(-1, 2 * n + 1)]
    df = spark.createDataFrame(rows, "n int, found array<int>, x int")
    assert df.where(lines._holds(F.col("found"), F.col("x")) != F.array_contains("found", F.col("x"))).count() == 0


def test_many_lost_lines_and_repeated_rows(spark, duck):
    line = lambda k: f"line {k} is longer than forty code points, as it has to be"
    long = "\n".join(line(k) for k in range(4_000))
    rows = [(k, long) for k in range(1, 6)] + [(7, line(3))] * 3 + [(None, line(3))]
    got = lines.drop_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: r.n_dropped for r in got if r.doc_id} == {1: 4_000, 2: 4_000, 3: 4_000, 4: 4_000, 5: 1, 7: 0}
    few = [(1, line(1)), (1, line(1)), (2, line(1)), (3, line(1)), (9, line(1)), (9, line(1))]
    import pandas as pd

    import duckdb

    con = duckdb.connect()
    con.register("documents", pd.DataFrame(few, columns=["doc_id", "text"]))
    want = sorted((r[0], r[2]) for r in con.execute(lines.OP7_SQL).fetchall())
    assert sorted((r.doc_id, r.n_dropped) for r in lines.drop_lines(spark.createDataFrame(few, "doc_id long, text string")).collect()) == want


def test_batches_grow_with_the_keys(spark, monkeypatch):
    assert [lines.batch_count(n, lines.Params()) for n in (0, 2**18, 2**22)] == [4, 5, 9]
    seen, ingest = [], lines.LineRuns.ingest
    monkeypatch.setattr(lines.LineRuns, "ingest", lambda self, keys: seen.append(1) or ingest(self, keys))
    docs = spark.createDataFrame([(k, f"line {k % 9} of more than forty code points, shared by some") for k in range(40)], "doc_id long, text string")
    got = lines.drop_lines(docs, lines.Params(batches=2, fanout=2, batch_keys=10)).collect()
    assert len(seen) == 5 and {r.doc_id for r in got if not r.n_dropped} == {*range(31, 40)} | {k for k in range(40) if 40 // 9 + (k % 9 < 4) < 5}


def test_line_sql(spark, small, duck):
    from tests.compare import normal

    assert normal(lines.op7_line_runs(spark, small).toPandas()) == normal(duck.execute(lines.OP7_SQL).df())
    assert normal(urls.op8_url_sweep(spark, small).toPandas()) == normal(duck.execute(urls.OP8_SQL).df())
    assert normal(mixing.op10_raked_mixture(spark, small).toPandas()) == normal(duck.execute(mixing.oracle()).df())


def test_urls(spark):
    want = {
        "http://Example.COM/en/71?x#y": ("example.com", "/en/71", "example.com/en/7", "allow"), "https://a.b.com/en/": ("a.b.com", "/en/", "com/en/", "block"), "http://notexample.com/en/7": ("notexample.com", "/en/7", "com/en/", "block"),
        "x://net/de/8": ("net", "/de/8", "net/de/", "block"), "x://m.example.net/de/8/": ("m.example.net", "/de/8/", "example.net/de/8", "allow"), "http://org?/es/": ("org", "", None, "allow"), "no scheme": ("", "", None, "allow"),
        "": ("", "", None, "allow"), "http://": ("", "", None, "allow"), "http://com.": ("com.", "", None, "allow"), "http://com/de": ("com", "/de", None, "allow"),
    }
    rows = [(k, u) for k, u in enumerate(want)] + [(90, None)] + [(100 + k, "http://hot.example.com/en/7") for k in range(200)]
    df = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit("clash"))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(df, urls.rule_frame(spark), ranges=7).collect()}
    assert len(got) == len(rows) and got[90] == ("", "", None, "allow")
    for k, w in enumerate(want.values()):
        assert got[k] == w
    assert urls.judge(df.where("false"), urls.rule_frame(spark)).count() == 0


def test_url_rules_are_the_contracts(spark):
    rules = {("com", "/en/"): "block", ("example.com", "/en/7"): "allow", ("net", "/de/"): "allow", ("example.net", "/de/8"): "block", ("org", "/es/"): "block"}
    assert {(h, p): v for v, h, p in urls.RULES} == rules
    want = {f"http://{w}{h}{p}{t}": (h + p, v) for (h, p), v in rules.items() for w in ("", "m.") for t in ("", "x")}
    df = spark.createDataFrame(list(enumerate(want)), "page_id long, url string")
    got = {r.page_id: (r.rule, r.verdict) for r in urls.judge(df, urls.rule_frame(spark)).collect()}
    assert got == dict(enumerate(want.values()))


PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{}</style><script>var a="<p>no</p>";</script></head><body>
<header class="site"><a href="/">Home</a></header><nav><ul><li><a href="/a">a</a></li></ul></nav><div class="cookie-notice">We use cookies, yes.</div>
<main><article><h1>Title &amp; more</h1><p><b>First,  a
paragraph<br>with&nbsp;words &#233;.<p>Second one, it is longer, with commas, and an <a href="/x">inline link</a> too.</p>
<div class="ad-slot">Buy now, cheap, today.</div><form><input><label>Mail</label></form><blockquote>Quoted, in full.</blockquote><ul><li>point one</li><li>point two</li></ul></article></main>
<aside>Other, things, here.</aside><section id="comments"><p>Great, post, thanks, for, all, of, this.</p></section><footer>&copy; us</footer></body></html>"""


def test_main_text():
    want = ["Title & more", "First, a paragraph with\u00a0words é.".replace("\u00a0", " "), "Second one, it is longer, with commas, and an inline link too.", "Quoted, in full.", "point one", "point two"]
    assert extraction.main_text(PAGE).split("\n") == want
    for text, out in ((None, ""), ("", ""), ("plain  text &lt;3", "plain text <3"), ("<p>a", "a"), ("<script>x", ""), ("<div><p>a</p>b<p>c</div>", "a\nb\nc"), ("<", "<")):
        assert extraction.main_text(text) == out
    assert extraction.main_text("<div>" * 3000 + "deep" + "</div>" * 3000) == "deep"
    assert extraction.main_text('<p "' * 2000 + ">x") == "x"  # quotes that are never closed end at the first >


@pytest.mark.parametrize(
    ("page", "n_chars"),
    [
        ("<a " * 350_000, 1_049_999), ("<div>text" * 100_000, 499_999), ('<p "' * 250_000 + ">x", 1), ('<a href="x' * 100_000 + ">t", 1), ("<div " + "a" * 1_000_000 + ">x", 1),
        ("<p><button>" + "<b>" * 100_000 + "<div>x" * 50_000, 0), ("<" * 1_000_000, 1_000_000), ("<b>x<div>y</div>" * 30_000, 119_999), ("<div a" + " " * 1_000_000 + "b>x", 1), ("<ul><li>a" * 50_000, 99_999),
    ],
    ids=["no end", "deep", "open quotes", "open values", "long name", "deep inline", "no tags", "inline", "blanks", "lists"],
)
def test_long_broken_pages_take_linear_time(page, n_chars):
    began = time.process_time()
    assert len(extraction.main_text(page)) == n_chars
    assert time.process_time() - began < 20  # seconds for about a megabyte; a quadratic way takes hours


def test_points_pass_up_as_climbing_gives_them():
    """The pass from the leaves up gives each container what climbing from every block would."""
    for page in (PAGE, "<div><p>a, b<div>c, d<span>e</span></div>f, g</div>" * 3, "<ul><li>x<ul><li>y, z</ul></ul>"):
        nodes = extraction.parse(page)
        want = {}
        for owner, text, linked in extraction._blocks(nodes[0]):
            points = (1 + text.count(",") + min(len(text) / 100, 3)) * (1 - linked / len(text))
            node, share = owner, 1.0
            while node is not None:
                if node is not owner or owner.tag not in extraction._LEAVES:
                    want[node] = want.get(node, 0.0) + points * share
                    share /= 2
                node = node.parent
        extraction.score(nodes, list(extraction._blocks(nodes[0])))
        for node, points in want.items():
            assert node.held == pytest.approx(points)


def test_articles_of_all_pages(spark, small):
    pages = {r.page_id: r for r in spark.read.parquet(f"{small}/pages.parquet").collect()}
    for r in extraction.op3_tree_scoring_extraction(spark, small).collect():
        inner = re.search(r"<article>(.*?)(?:</article>|\Z)", pages[r.page_id].html, re.S)[1]
        blocks = (" ".join(html.unescape(x).split()) for x in re.split(r"</?(?:p|h1)>", re.sub(r"</?b>", "", inner.replace("<br>", " "))))
        assert r.text == "\n".join(x for x in blocks if x) and r.n_chars == len(r.text)


def test_ids_equal_the_tokenizer_and_pieces_round_trip(spark, small):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    extra = ["a<|endoftext|>b", "<|endoftext|>", " <|endoftext|> x", "it's 12 &\n\n  tabs\t", "é" * 700]
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").collect()] + [(10_000 + k, t) for k, t in enumerate([*TEXTS, *extra])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    pieces = packing.pack(df).collect()
    of, seq = {}, {}
    for p in pieces:
        of.setdefault(p.doc_id, []).append(p)
        seq.setdefault(p.sequence_id, []).append(p)
    for k, t in rows:
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [0], "<u4")
        at = 0
        for p in sorted(of[k], key=lambda p: p.start):
            assert p.start == at and p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(ids[at : at + p.length].tobytes())
            at += p.length
        assert at == len(ids)
    for parts in seq.values():
        at = 0
        for p in sorted(parts, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 1024 and at & (at - 1) == 0 and len({(p.tier, p.step_group) for p in parts}) == 1
    groups = {}
    for p in pieces:
        groups[p.step_group] = groups.get(p.step_group, 0) + p.length
    assert max(groups.values()) <= 65_536
    assert packing.pack(df.where("false")).count() == 0


def test_quality_scores_hold_out(spark):
    sf = "/root/testdata/sf0.01"
    got = quality.op1_quality_classifier(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").toPandas()
    held = got[got.held_out]
    assert set(held.doc_id) == {i for i in got.doc_id if zlib.crc32(str(i).encode()) % 5 == 0}
    good, bad = held[held.quality == 1].score, held[held.quality == 0].score
    assert np.mean([[g > b for b in bad] for g in good]) > 0.95
    assert (held.predicted == held.quality).mean() > 0.95 and held.score.between(0, 1).all()


def test_quality_without_labels_or_rows(spark, docs):
    none = spark.createDataFrame([(1, None, 0)], "doc_id long, quality int, toxic int")
    assert {r.score for r in quality.classify(docs, none).collect()} == {0.5}
    assert quality.classify(docs.where("false"), none).count() == 0
    assert (np.diff(quality.pool_adjacent(np.array([0.3, 0.1, 0.5, 0.4, 0.9]), np.ones(5))) >= 0).all()


def test_quality_learns_once_from_repeated_labels(spark, docs):
    free = [k for k in range(2, 200) if zlib.crc32(str(k).encode()) % 5]
    rows = [(k, "word " * 30 if k % 2 else "## !! " * 30, "en", "s", 1) for k in free]
    texts = spark.createDataFrame(rows, docs.schema.names[:5])
    labels = spark.createDataFrame([(k, k % 2, 0) for k in free], "doc_id long, quality int, toxic int")
    hot = labels.unionByName(spark.range(3000).select(F.lit(free[0]).alias("doc_id"), F.lit(free[0] % 2).alias("quality"), F.lit(0).alias("toxic")))
    params = quality.Params(max_rows=500)
    one, two = ({r.doc_id: r.score for r in quality.classify(texts, x, params).collect()} for x in (labels, hot))
    assert one == pytest.approx(two) and all((s > 0.5) == (k % 2 == 1) for k, s in one.items())


def test_features_approximate_the_kernel_and_ridge_is_exact(spark):
    """Random features against the Gaussian kernel itself; the partition-summed solution against one over all rows."""
    rng = np.random.default_rng(2)
    x = rng.normal(0, 0.7, (60, len(quality.STATISTICS)))
    n, gamma = 20_000, 0.02
    omega, phase = rng.normal(0, np.sqrt(2 * gamma), (x.shape[1], n)), rng.uniform(0, 2 * np.pi, n)
    model = quality.Model(np.zeros(x.shape[1]), np.ones(x.shape[1]), omega, phase, np.zeros(n), np.zeros(1), np.zeros(1))
    z = model.features(x)[:, :n]
    kernel = np.exp(-gamma * ((x[:, None] - x[None]) ** 2).sum(2))
    assert np.abs(z @ z.T - kernel).max() < 0.05
    sf = "/root/testdata/sf0.001"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    params = quality.Params(features=16)
    got = quality.fit(docs.repartition(7), labels, params)
    y = {r.doc_id: float(r.quality) for r in labels.collect() if zlib.crc32(str(r.doc_id).encode()) % 5}
    rows = [(r.doc_id, quality.statistics(r.text)) for r in docs.collect() if r.doc_id in y]
    every = np.array([s for _, s in rows])
    assert np.allclose(got.mean, every.mean(0)) and np.allclose(got.scale, np.where(every.std(0) > 1e-9, every.std(0), 1.0))
    train = [(i, s) for i, s in rows if zlib.crc32(str(i).encode()) % 5 != 1]
    a, b = got.features(np.array([s for _, s in train])), np.array([y[i] for i, _ in train])
    penalty = np.append(np.full(a.shape[1] - 1, params.ridge * len(b)), 1e-6)
    assert np.allclose(got.weight, np.linalg.solve(a.T @ a + np.diag(penalty), a.T @ b), atol=1e-6)


def test_mixing_meets_targets(spark):
    rows = [(k, "w " * (1 + k % 7), "en" if k % 3 else "de", "a" if k % 4 else "b", 1) for k in range(4000)] + [(9001, None, None, None, 0), (9002, "", "en", "a", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("keep_p", F.lit(7.0))
    params = mixing.Params(targets={"source": {"a": 0.5, "b": 0.5}, "lang": {"en": 0.6, "de": 0.4}, "topic": {"brief": 1.0}}, budget=0.4, sweeps=20)
    out = mixing.mix(df, params).toPandas()
    assert len(out) == len(rows)
    kept = out.assign(w=out.keep_p * out.tokens)
    for axis, want in (("source", {"a": 0.5, "b": 0.5}), ("lang", {"en": 0.6, "de": 0.4})):
        share = kept.groupby(axis).w.sum() / kept.w.sum()
        for k, v in want.items():
            assert share[k] == pytest.approx(v, abs=0.01)
    assert kept.w.sum() / out.tokens.sum() == pytest.approx(0.4, abs=0.01)
    assert (out.kept * out.tokens).sum() / out.tokens.sum() == pytest.approx(0.4, abs=0.04)
    assert mixing.mix(df.where("false"), params).count() == 0
    few = mixing.Params(targets={"source": {"a": 1.0}}, sweeps=2, fills=3)
    wide = mixing.Params(targets={"source": {"a": 1.0}}, sweeps=2, fills=3, max_cells=1)
    one, two = ({(r.doc_id, r.keep_p, r.kept) for r in mixing.mix(df, p).collect()} for p in (few, wide))
    assert one == two and {p for i, p, _ in one if i == 4} == {0.0}  # a value that targets leave out


def test_mixing_of_a_null_id(spark):
    rows = [(None, "w " * 900, "en", "a", 1), (1, "w " * 900, "en", "a", 1)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long"), mixing.Params(budget=1.0)).collect()
    assert {r.doc_id: r.kept for r in got} == {None: False, 1: True}


def test_digest_of_all_lines_dropped(spark, tmp_path):
    line = "one line of more than forty code points, alone in its text"
    spark.createDataFrame([(k, line) for k in range(6)], "doc_id long, text string").write.parquet(f"file://{tmp_path}/documents.parquet")
    got = {r.doc_id: r.kept_sha256 for r in lines.op7_line_runs(spark, f"file://{tmp_path}").collect()}
    assert got == {k: hashlib.sha256(b"" if k < 5 else line.encode()).hexdigest() for k in range(6)}
