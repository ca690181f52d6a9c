"""Texts of one shape are parsed once, and get the labels that they have when each is parsed."""

import itertools
import random

from fixtrace.functions import ctree
from fixtrace.operators import similarity
from fixtrace.plans.lab import lab_of
from fixtrace.sources import code

ODDITIES = (
    "x = 1.5 + a;", "x = 0x1F | 7;", 'f("a 1", b);', "for (;;) { x = 1; }", "for (;;) { x = 2; }", "foo_t a = b;", "bar_t a = b;", "x = (foo *) y;", "if (", "", "x = empty + b;",
    "x = e + empty;", "x = f + empty;", "x = é + b;", "a = b /* 1 */ + 2; // 3", "a = a;", "if (x) a = b; else a = a;", "if (x) a = b; else a = c;", "arr[1] = arr[2];", "p = q; take_block(p, 7);",
    "take_block(z, n);", "x = a1.b + 3;", "switch (m) { case 3: a(); break; case 12: b(); break; default: c(); }", "x = 13 * 2 + 2 * 13 + 1 * 4;", "x = 0 != b;", "x = 00 != b;",
)


def _texts():
    rng = random.Random(5)
    out = list(ODDITIES)
    for form in itertools.chain(*code.PLAIN, *code.LISTED):
        for _ in range(12):
            mark = {"S": str(rng.choice([1, 2, 12])), "F": str(rng.choice([3, 12, 4003])), "K": str(rng.choice([0, 1, 2, 5, 10, 101, 133, 999]))}
            words = ctree.WORD.split(form)
            words = [mark[w] if w == "K" else w[:-1] + mark[w[-1]] if w[-2:] in ("_S", "_F") else w for w in words]
            out.append("".join(words))
    names = ["a", "b", "ab", "a_b", "z9", "sum", "int_a", "emp", "emptyy", "brea", "p", "n", "9", "10", "1", "100", "0", "2"]
    for form in ("%s = %s + %s * %s;", "if (%s == %s || %s < %s - 1) f(a, 2);", "x = (%s * %s + 3 != %s & %s);", "copy_block(%s + %s, %s * 4, %s);", "while (%s + 2 > g(%s, %s)) %s--;"):
        out += [form % tuple(rng.choices(names, k=4)) for _ in range(150)]
    return out


def test_shapes_give_the_labels_of_each_text():
    texts = _texts()
    for rows, depth in (((), 0), (tuple((n, tuple(p), b) for n, _, p, b in code.CALLEES), 1), ((("f", ("a", "k"), "a = a + k * 13 + 5;"), ("g", ("u", "v", "w"), "f(u, 2); copy(v, w, 7);")), 2)):
        shapes = ctree.Shapes(rows, depth)
        for text in texts:
            names = ctree.labels(text, ctree.definitions(rows), depth)
            assert shapes.codes(text) == (None if names is None else ctree.code_points(names)), text


def test_other_names_and_constants_are_not_parsed_again(monkeypatch):
    parse, n = ctree.parse, []
    monkeypatch.setattr(ctree, "parse", lambda text: n.append(text) or parse(text))
    shapes = ctree.Shapes(())
    got = {shapes.codes(f"if ((mask_{s} & {k}) != 0 && idle_{f} == 0) seen_{f} = mask_{s};  /* kept */") for s in (1, 2, 7) for f in (3, 4003) for k in range(200, 300)}
    assert len(got) == 600 and len(n) == 1


def test_pairs_carry_how_often_they_occur(spark, small):
    lab = lab_of(spark, small)
    assert lab.sims.agg({"n": "sum"}).first()[0] == lab.pairs.count()
    pairs = spark.createDataFrame([("a = b + 1;", "a = 1 + b;")] * 3 + [("if (", "if (x) y = 1;")], "pre string, post string")
    got = {r.pre: r for r in similarity.compare(pairs, code.callees(spark), None, counted=True).collect()}
    assert got["a = b + 1;"].n == 3 and got["a = b + 1;"].sim_b == 1.0 and got["if ("].n == 1 and got["if ("].sim_b is None
