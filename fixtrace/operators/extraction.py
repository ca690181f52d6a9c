"""Extraction: patches to changed lines, dependence slices around them, the flow that a judge reads."""

from __future__ import annotations

import functools
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.functions import ctree

#: Paths whose lines say nothing about code.
IRRELEVANT = (r"(?i)(^|/)(change|changelog|news|readme|copying|authors|license)[^/]*$", r"(?i)\.(md|txt|rst|po|html?)$", r"(?i)(^|/)(tests?|docs?)/")


HUNK = r"^@@ -(\d+)(?:,(\d+))? \+(\d+)(?:,(\d+))? @@ ?(.*)$"


def parse_patch(patches: DataFrame) -> DataFrame:
    """Unified diffs (commit_id, text) to lines: path, function, hunk, op, old_no, new_no, text.

    A hunk is as long as its header says, so a removed line ``-- i;`` is no file header and what stands after a hunk
    is no content.  The path is the new one, of deleted files the old one.  Text outside a hunk is dropped; an empty
    line inside one is an empty line of context.
    """
    lines = patches.select("commit_id", F.posexplode(F.split(F.coalesce("text", F.lit("")), r"\r?\n")).alias("at", "line"))
    w = W.partitionBy("commit_id").orderBy("at").rowsBetween(W.unboundedPreceding, W.currentRow)
    is_hunk = F.col("line").rlike(HUNK)
    many = lambda k: F.coalesce(F.regexp_extract("header", HUNK, k).try_cast("int"), F.lit(1))
    marked = lines.withColumns({"hunk": F.count(F.when(is_hunk, 1)).over(w), "header": F.last(F.when(is_hunk, F.col("line")), ignorenulls=True).over(w)})
    first = F.when(F.col("line") == "", " ").otherwise(F.col("line").substr(1, 1))
    op = F.when(~is_hunk & first.isin("+", "-", " "), F.when(first == "+", "add").when(first == "-", "del").otherwise("ctx"))
    marked = marked.withColumn("op", op).withColumns({"is_old": F.coalesce((F.col("op") != "add").cast("int"), F.lit(0)), "is_new": F.coalesce((F.col("op") != "del").cast("int"), F.lit(0))})
    inside = W.partitionBy("commit_id", "hunk").orderBy("at").rowsBetween(W.unboundedPreceding, W.currentRow)
    marked = marked.withColumns({"n_old": F.sum("is_old").over(inside), "n_new": F.sum("is_new").over(inside)})
    going = (F.col("n_old") - F.col("is_old") < many(2)) | (F.col("n_new") - F.col("is_new") < many(4))
    marked = marked.withColumn("body", (F.col("hunk") > 0) & F.col("op").isNotNull() & going)
    name = lambda mark: F.when(~F.col("body") & F.col("line").startswith(mark), F.regexp_extract("line", r"^(?:---|\+\+\+) (?:[ab]/)?([^\t]*)", 1))
    old, new = (F.last(name(mark), ignorenulls=True).over(w) for mark in ("--- ", "+++ "))
    marked = marked.withColumns({"old_path": old, "new_path": new})
    return marked.where("body").select(
        "commit_id", F.when(F.col("new_path") == "/dev/null", F.col("old_path")).otherwise(F.col("new_path")).alias("path"),
        F.regexp_extract("header", HUNK, 5).alias("func"), F.col("hunk").cast("int").alias("hunk"), "op",
        F.when(F.col("op") != "add", F.regexp_extract("header", HUNK, 1).cast("int") + F.col("n_old") - 1).cast("int").alias("old_no"),
        F.when(F.col("op") != "del", F.regexp_extract("header", HUNK, 3).cast("int") + F.col("n_new") - 1).cast("int").alias("new_no"), F.expr("substring(line, 2)").alias("text"),
    )


def drop_irrelevant(diff: DataFrame, patterns=IRRELEVANT) -> DataFrame:
    """Lines of files that hold code; changes of blanks and comments only go too.

    Whether a changed line starts inside a block comment is told on its own side of the hunk (old lines for what is
    removed, new ones for what is added): by the last comment mark before it, or, where the hunk may begin inside a
    comment, by whether an end of one comes next.  ``*p = 0;`` is code, `` * text`` inside a comment is not.
    """
    bad = F.lit(False)
    for p in patterns:
        bad = bad | F.coalesce(F.col("path").rlike(p), F.lit(False))
    bare = F.regexp_replace(F.regexp_replace("text", r'"(?:[^"\\\\]|\\\\.)*"', '""'), r"//.*$", "")
    marks = F.regexp_extract_all(bare, F.lit(r"/\*|\*/"), F.lit(0))
    rows = diff.withColumns({"__bare": bare, "__marks": marks}).withColumns({"__first": F.get("__marks", F.lit(0)), "__last": F.get("__marks", F.size("__marks") - 1)})
    out = []
    for side, number in (("del", "old_no"), ("add", "new_no")):
        w = W.partitionBy("commit_id", "path", "hunk").orderBy(number)
        before = F.last("__last", ignorenulls=True).over(w.rowsBetween(W.unboundedPreceding, -1))
        after = F.first("__first", ignorenulls=True).over(w.rowsBetween(W.currentRow, W.unboundedFollowing))
        held = rows.where(F.col("op").isin(side, "ctx")).withColumn("__in", F.coalesce(before == "/*", after == "*/", F.lit(False)))
        out.append(held.where(F.col("op") == side))
    changed = out[0].unionByName(out[1])
    text = F.when(F.col("__in"), F.regexp_replace("__bare", r"^.*?(\*/|$)", "")).otherwise(F.col("__bare"))
    code = F.trim(F.regexp_replace(F.regexp_replace(text, r"/\*.*?\*/", " "), r"/\*.*$", " ")) != ""
    kept = changed.where(code).select(diff.columns).unionByName(diff.where("op = 'ctx'"))
    return kept.where(~bad)


def classify_patch(diff: DataFrame, large: int = 50) -> DataFrame:
    """Class and size of each commit's change."""
    n = diff.groupBy("commit_id").agg(F.count_if(F.col("op") == "add").alias("added"), F.count_if(F.col("op") == "del").alias("deleted")).where("added + deleted > 0")
    kind = F.when(F.col("added") == 0, "del").when(F.col("deleted") == 0, "add").otherwise("both")
    return n.withColumns({"patch_class": kind, "large": F.col("added") + F.col("deleted") > large})


def _names(tree: tuple) -> set[str]:
    """Variables read anywhere in a tree; the callee of a call is no variable."""
    if len(tree) == 1:
        return {tree[0][3:]} if tree[0].startswith("id:") else set()
    parts = tree[2:] if tree[0] == "call" and len(tree[1]) == 1 else tree[1:]
    return set().union(*map(_names, parts)) if parts else set()


def _root(tree: tuple) -> set[str]:
    """The variable that an assignment to this place defines."""
    while len(tree) > 1 and tree[0] in ("index", "->", ".", "u*", "cast"):
        tree = tree[-1] if tree[0] == "cast" else tree[1]
    return _names(tree)


def facts(tree: tuple) -> tuple[set[str], set[str], set[str]]:
    """Variables defined, variables used, functions called in one statement."""
    defs: set[str] = set()
    uses: set[str] = set()

    def walk(t: tuple) -> None:
        label = t[0]
        if label in ctree.ASSIGN and len(t) == 3:
            defs.update(_root(t[1]))
            if label != "=" or len(t[1]) > 1:
                uses.update(_names(t[1]))
            walk(t[2])
            return
        if label in ("p++", "p--", "u++", "u--"):
            defs.update(_root(t[1]))
        if label == "call":
            for x in t[2:]:
                if x[0] == "u&":
                    defs.update(_root(x[1]))
        if len(t) == 1:
            uses.update(_names(t))
            return
        for x in t[2:] if label == "call" and len(t[1]) == 1 else t[1:]:
            walk(x)

    walk(tree)
    return defs, uses, set(ctree.calls(tree))


class Stmt:
    """One line: what it defines and uses, and the lines it governs (``body``, ``orelse``)."""

    __slots__ = ("no", "kind", "defs", "sure", "uses", "calls", "body", "orelse", "jump")

    def __init__(self, no: int, kind: str, defs: frozenset[str], sure: frozenset[str], uses: frozenset[str], calls: frozenset[str], jump: str = ""):
        self.no, self.kind, self.defs, self.sure, self.uses, self.calls, self.jump = no, kind, defs, sure, uses, calls, jump
        self.body: list[Stmt] | None = None
        self.orelse: list[Stmt] = []


def _sure(tree: tuple) -> set[str]:
    """Variables that a statement replaces whenever it runs: plain names assigned outside any condition."""
    label = tree[0]
    if label == "block":
        return set().union(*map(_sure, tree[1:])) if tree[1:] else set()
    if label == "decl":
        return _sure(tree[2]) if tree[2][0] == "=" else set()
    if label == "=":
        return (_names(tree[1]) if len(tree[1]) == 1 else set()) | _sure(tree[2])
    if label in ctree.ASSIGN or label in ("p++", "p--", "u++", "u--"):
        return _names(tree[1]) if len(tree[1]) == 1 else set()
    return set()


@functools.lru_cache(maxsize=50_000)
def _line_facts(text: str) -> tuple:
    """Kind, variables defined, surely defined and used, functions called, and jump of a line."""
    bare = text.strip()
    head = bare.lstrip("} ")
    test = re.sub(r"^else\b\s*", "", head)
    word = (re.match(r"[A-Za-z_]*", test) or [""])[0]
    tree = None
    for form in (bare, bare + "}", bare + ";", test or ";", test + "}", test.rstrip("{").strip() + " ;", "do {" + bare):
        try:
            tree = ctree.parse(form)
            break
        except ctree.Unparsed:
            continue
    kind = {"if": "cond", "switch": "cond", "for": "loop", "while": "loop", "do": "loop", "return": "return"}.get(word, "cond" if head.startswith("else") else "other")
    defs, uses, calls = facts(tree or ("block",))
    if kind == "other":
        kind = "assign" if defs else "call" if calls else "other"
    jump = word if word in ("break", "continue", "return", "goto") else "label" if word in ("case", "default") else word if kind == "loop" or word == "switch" else "else" if head.startswith("else") and word != "if" else ""
    return kind, frozenset(defs), frozenset(_sure(tree)) if tree else frozenset(), frozenset(uses), frozenset(calls), jump


@functools.lru_cache(maxsize=50_000)
def _line_braces(text: str) -> tuple[int, str, int, bool]:
    """Braces that a line closes at its start, what follows these, how many it opens beyond that, and whether it ends a statement."""
    bare = re.sub(r'"(?:[^"\\]|\\.)*"|\'(?:[^\'\\]|\\.)*\'', "0", text.strip())
    head = bare.lstrip("} ")
    return bare[: len(bare) - len(head)].count("}"), head, head.count("{") - head.count("}"), bare.endswith((";", "}"))


@functools.lru_cache(maxsize=50_000)
def _line_read(text: str) -> tuple:
    return _line_facts(ctree.plain_numbers(text))


def _read_line(no: int, text: str) -> Stmt:
    kind, defs, sure, uses, calls, jump = _line_read(text)
    return Stmt(no, kind, defs, sure, uses, calls, jump)


def structure(lines: list[tuple[int, str]]) -> list[Stmt]:
    """The lines of a function as nested statements, by braces, or by the next line where a condition has none."""
    out: list[Stmt] = []
    stack: list[tuple[list[Stmt], bool]] = [(out, False)]  # a list of statements, and whether it ends with its first

    def done() -> None:
        while stack[-1][1] and stack[-1][0]:
            stack.pop()

    for no, text in lines:
        closed, head, opens, ended = _line_braces(text)
        for _ in range(closed):
            if len(stack) > 1:
                stack.pop()
                if not head.startswith("else"):
                    done()
        if (head or closed) and not head.strip(" ;"):
            continue
        s = _read_line(no, text)
        at = stack[-1][0]
        if head.startswith("else") and at:
            owner = at[-1]
            while owner.orelse and owner.orelse[-1].kind == "cond":
                owner = owner.orelse[-1]
            at = owner.orelse
        at.append(s)
        if opens > 0:
            s.body = []
            for _ in range(opens):
                stack.append((s.body, False))
        elif s.kind in ("cond", "loop") and not ended:
            s.body = []
            stack.append((s.body, True))
        else:
            done()
    return out


def dependence(lines: list[tuple[int, str]]) -> tuple[dict, list[tuple[int, int, str, str]]]:
    """Statements and dependence edges (source, target, kind, variable) of one function given as numbered lines.

    Data edges join each use to every definition that may reach it: branches meet, loops carry definitions around,
    and only an assignment to a plain variable replaces earlier ones.  Control edges join a condition or loop to all
    it governs, its else branch included.  A goto is taken to leave the function.
    """
    stmts: dict[int, dict] = {}
    edges: dict[tuple[int, int, str, str], None] = {}

    def meet(*states):
        held = [x for x in states if x is not None]
        return {v: frozenset().union(*(x.get(v, frozenset()) for x in held)) for v in set().union(*held)} if held else None

    def use(s: Stmt, state: dict) -> None:
        for v in sorted(s.uses):
            for d in sorted(state.get(v, ())):
                edges[d, s.no, "data", v] = None

    def define(s: Stmt, state: dict) -> dict:
        return state | {v: frozenset({s.no}) if v in s.sure else state.get(v, frozenset()) | {s.no} for v in s.defs}

    def run(block: list[Stmt], state, jumps: dict, entry=None):
        for s in block:
            if s.jump == "label":
                state = meet(state, entry)
            if state is None:
                continue
            if s.kind == "loop" and s.body is not None:
                after, back = state, None
                while True:
                    top = meet(state, back)
                    if s.jump != "do":
                        use(s, top)
                    ends = {"break": [], "continue": []}
                    end = run(s.body, define(s, top), ends)
                    new = meet(back, end, *ends["continue"])
                    after = meet(end if s.jump == "do" else define(s, top), *ends["continue"], *ends["break"])
                    if new == back:
                        break
                    back = new
                state = after
            elif s.kind == "cond" and s.body is not None:
                use(s, state)
                state = define(s, state)
                if s.jump == "else":
                    state = run(s.body, state, jumps, entry)
                elif s.jump == "switch":
                    ends = {"break": [], "continue": jumps["continue"]}
                    state = meet(run(s.body, None, ends, state), state if not any(x.jump == "label" for x in s.body) else None, *ends["break"])
                else:
                    state = meet(run(s.body, state, jumps, entry), run(s.orelse, state, jumps, entry))
            else:
                use(s, state)
                state = define(s, state)
                if s.body is not None:
                    state = run(s.body, state, jumps, entry)
                if s.orelse:
                    state = meet(state, run(s.orelse, state, jumps, entry))
                if s.jump in ("break", "continue", "return", "goto"):
                    if s.jump in jumps:
                        jumps[s.jump].append(state)
                    state = None
        return state

    def govern(block: list[Stmt], over: list[int]) -> None:
        for s in block:
            stmts[s.no] = {"kind": s.kind, "defs": s.defs, "uses": s.uses, "calls": s.calls}
            for g in over:
                edges[g, s.no, "control", ""] = None
            mine = [*over, s.no] if s.kind in ("cond", "loop") else over
            govern(s.body or [], mine)
            govern(s.orelse, [*over, s.no])

    found = structure(lines)
    govern(found, [])
    run(found, {}, {"break": [], "continue": []})
    return dict(sorted(stmts.items())), list(edges)


def slice_lines(lines: list[tuple[int, str]], seeds: set[int], direction: str = "both") -> dict[int, str]:
    """Line numbers of the slice and why each is in it: seed, back or fwd.

    Assignments pass the criterion on to what they define; a condition that tests a criterion variable brings what
    it governs; a call on one is kept; nothing is followed past a return.
    """
    stmts, edges = dependence(lines)
    reason = {no: "seed" for no in seeds if no in stmts}
    if direction in ("both", "back"):
        todo, into = list(reason), {}
        for a, b, _, _ in edges:
            into.setdefault(b, []).append(a)
        while todo:
            for a in into.get(todo.pop(), []):
                if a not in reason:
                    reason[a] = "back"
                    todo.append(a)
    if direction in ("both", "fwd"):
        criterion = set().union(*(stmts[no]["defs"] | stmts[no]["uses"] for no in seeds if no in stmts)) if reason else set()
        governed: dict[int, set[int]] = {}
        for a, b, kind, _ in edges:
            if kind == "control":
                governed.setdefault(a, set()).add(b)
        start = min(seeds, default=0)
        taken = {no for no in reason if reason[no] == "seed"}
        for no in [n for n in sorted(stmts) if n >= start]:
            s = stmts[no]
            hit = no in taken or bool(s["uses"] & criterion) and s["kind"] != "return"
            if not hit:
                continue
            reason.setdefault(no, "fwd")
            if s["kind"] in ("cond", "loop"):
                for g in governed.get(no, ()):
                    reason.setdefault(g, "fwd")
            if s["kind"] in ("assign", "loop"):
                criterion |= s["defs"]
    return reason


def slices(functions: DataFrame, seeds: DataFrame, direction: str = "both") -> DataFrame:
    """(func_id, line_no, text, direction) of the slice of each function; one group per function.

    ``functions``: func_id, line_no, text; ``seeds``: func_id, line_no.  Functions without seeds have no slice.
    """
    marked = functions.join(seeds.select("func_id", "line_no", F.lit(True).alias("seed")).distinct(), ["func_id", "line_no"], "left")

    def run(t: pa.Table) -> pa.Table:
        rows = sorted(zip(t.column("line_no").to_pylist(), t.column("text").to_pylist(), t.column("seed").to_pylist(), strict=True), key=lambda r: r[0])
        found = slice_lines([(n, x or "") for n, x, _ in rows], {n for n, _, s in rows if s}, direction)
        text = {n: x for n, x, _ in rows}
        at = sorted(found)
        return pa.table({"func_id": pa.array([t.column("func_id")[0].as_py()] * len(at), pa.string()), "line_no": pa.array(at, pa.int32()), "text": pa.array([text[n] for n in at], pa.string()), "direction": pa.array([found[n] for n in at], pa.string())})

    return marked.select("func_id", "line_no", "text", "seed").groupBy("func_id").applyInArrow(run, "func_id string, line_no int, text string, direction string")


def merge_flows(*flows: DataFrame) -> DataFrame:
    """Slices of several functions as one flow, each line once."""
    out = flows[0]
    for f in flows[1:]:
        out = out.unionByName(f)
    return out.dropDuplicates(["func_id", "line_no"])


def render_flow(flow: DataFrame, by: str = "func_id") -> DataFrame:
    """One text per case: statements in order, each behind its line number."""
    lines = F.array_sort(F.collect_list(F.struct("line_no", F.concat_ws(" ", F.col("line_no").cast("string"), F.trim("text")).alias("s"))))
    return flow.groupBy(by).agg(F.array_join(F.transform(lines, lambda x: x["s"]), " ").alias("flow"))
