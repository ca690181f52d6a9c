"""Two-level similarity of statement changes: bounded edit distance, then edit distance over tree labels."""

from __future__ import annotations

import functools

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fixtrace.functions import ctree
from fixtrace.functions.store import drop, settle
from fixtrace.functions.text import alike, digest, line_similarity, squash
from fixtrace.operators import weights

THETA_LINE, THETA_TREE, THETA_SCORE = 900, 800, 700


def reachable(callees: DataFrame, depth: int) -> DataFrame:
    """(name, defs, and repo_id if ``callees`` has it): each definition with those its body calls, ``depth`` levels in all."""
    keys = [c for c in ("repo_id",) if c in callees.columns]
    own = callees.select(*keys, "name", F.struct("name", "params", "body").alias("d"))
    calls = callees.select(*keys, F.col("name").alias("root"), F.explode(weights.called(F.col("body"))).alias("name"))
    found, edge = own.select(*keys, F.col("name").alias("root"), "name", "d"), calls
    for _ in range(depth - 1):
        more = edge.join(own, [*keys, "name"]).select(*keys, "root", "name", "d")
        found = found.unionByName(more)
        edge = edge.join(calls.select(*keys, F.col("root").alias("name"), F.col("name").alias("next")), [*keys, "name"]).select(*keys, "root", F.col("next").alias("name")).distinct()
    return found.groupBy(*keys, F.col("root").alias("name")).agg(F.collect_set("d").alias("defs"))


@functools.lru_cache(maxsize=256)
def _shapes(defs: tuple[tuple[str, tuple[str, ...], str], ...], depth: int, rules) -> ctree.Shapes:
    return ctree.Shapes(defs, depth, rules, held=2_000)


def tree_codes(texts: DataFrame, callees: DataFrame, depth: int = 1, rules=ctree.RULES) -> DataFrame:
    """(text, codes, parse_ok): the flattened normal form of each text, one code point for each label.

    Definitions are joined to the texts that call them, by name, and by ``repo_id`` where both sides have one, so none
    travel with the task.
    """
    keys = [c for c in ("repo_id",) if c in texts.columns and c in callees.columns]
    once = texts.select(*keys, "text").distinct()
    if depth:
        called = once.select(*keys, "text", F.explode(weights.called(F.col("text"))).alias("name"))
        held = called.join(reachable(callees, depth), [*keys, "name"]).groupBy(*keys, "text").agg(F.flatten(F.collect_list("defs")).alias("defs"))
        once = once.join(held, [*keys, "text"], "left")
    else:
        once = once.withColumn("defs", F.lit(None).cast("array<struct<name:string,params:array<string>,body:string>>"))

    def run(batches):
        for b in batches:
            codes = []
            for text, defs in zip(b.column("text").to_pylist(), b.column("defs").to_pylist(), strict=True):
                # in one order, whatever order they were collected in
                known = tuple(sorted((d["name"], tuple(d["params"]), d["body"]) for d in defs or ()))
                codes.append(_shapes(known, depth, frozenset(rules)).codes(text or ""))
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), b.column("text"), pa.array(codes, pa.string()), pa.array([c is not None for c in codes])], [*keys, "text", "codes", "parse_ok"])

    return once.select(*keys, "text", "defs").mapInArrow(run, "".join(f"{k} int, " for k in keys) + "text string, codes string, parse_ok boolean")


def tree_variants(pairs: DataFrame, callees: DataFrame, variants: list[tuple[int, frozenset]]) -> DataFrame:
    """(pair, sims): the tree level of each distinct pair of texts, told by its ``digest``, for each (depth, rules) of ``variants``.

    Null where a text does not parse.  All forms of a text are made at once; one that is as the first is noted only,
    and two such need no distance of their own.
    """
    known = pairs.where("pre is not null and post is not null").select("pre", "post").distinct()
    known = settle(known.select("pre", "post", digest("pre", "post").alias("pair"), digest("pre").alias("p"), digest("post").alias("q")))
    once = known.select(F.explode(F.array("pre", "post")).alias("text")).distinct()
    called = once.select("text", F.explode(weights.called(F.col("text"))).alias("name"))
    deep = max(d for d, _ in variants)
    defs = called.join(reachable(callees, max(deep, 1)), "name").groupBy("text").agg(F.flatten(F.collect_list("defs")).alias("defs"))

    def run(batches):
        for b in batches:
            codes = []
            for text, defs in zip(b.column("text").to_pylist(), b.column("defs").to_pylist(), strict=True):
                held = tuple(sorted((d["name"], tuple(d["params"]), d["body"]) for d in defs or ()))
                own = [_shapes(held if depth else (), depth, frozenset(rules)).codes(text) for depth, rules in variants]
                codes.append([own[0], *(None if c is None else "" if c == own[0] else c for c in own[1:])])
            yield pa.RecordBatch.from_arrays([b.column("h"), pa.array(codes, pa.list_(pa.string()))], ["h", "codes"])

    codes = once.join(defs, "text", "left").select(digest("text").alias("h"), "text", "defs").mapInArrow(run, "h binary, codes array<string>")
    codes = settle(codes)
    side = lambda c: codes.select(F.col("h").alias(c), F.col("codes").alias(f"code_{c}"))
    met = known.select("pair", "p", "q").join(side("p"), "p").join(side("q"), "q")
    form = lambda c, k: F.when(F.get(c, F.lit(k)) == "", F.get(c, F.lit(0))).otherwise(F.get(c, F.lit(k)))
    level = lambda k: F.when(form("code_p", k).isNotNull() & form("code_q", k).isNotNull(), line_similarity(form("code_p", k), form("code_q", k)))
    met = met.withColumn("first", level(0))
    as_first = lambda k: (F.get("code_p", F.lit(k)) == "") & (F.get("code_q", F.lit(k)) == "")
    found = settle(met.select("pair", F.array("first", *(F.when(as_first(k), F.col("first")).otherwise(level(k)) for k in range(1, len(variants)))).alias("sims")))
    drop(known, codes)
    return found


def compare(pairs: DataFrame, callees: DataFrame, *args, **kwargs) -> DataFrame:
    """As ``settled``, with the last step not yet taken."""
    return _compare(pairs, callees, *args, **kwargs)[0]


def settled(pairs: DataFrame, callees: DataFrame, *args, **kwargs) -> DataFrame:
    """(pre, post, sim_a, sim_b, and repo_id where both inputs have it) for each distinct pair of texts; ``counted``: how often it occurs as ``n``.

    ``sim_b`` is computed only where ``sim_a`` is below ``theta_line`` (null for all pairs: everywhere) and both
    texts parse; a missing text is unlike any other.  What is kept on the way is deleted.
    """
    found, *parts = _compare(pairs, callees, *args, **kwargs)
    found = settle(found)
    drop(*parts)
    return found


def _compare(pairs: DataFrame, callees: DataFrame, theta_line: int | None = THETA_LINE, depth: int = 1, rules=ctree.RULES, counted: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    keys = [c for c in ("repo_id",) if c in pairs.columns and c in callees.columns]
    known = pairs.where("pre is not null and post is not null").select(*keys, "pre", "post")
    known = known.groupBy(known.columns).agg(F.count("*").alias("n")) if counted else known.distinct()
    # read twice below; edit distances are not made again
    a = settle(known.withColumn("sim_a", line_similarity(squash(F.col("pre")), squash(F.col("post")))))
    far = F.lit(True) if theta_line is None else F.round(F.col("sim_a") * 1000) < theta_line
    texts = a.where(far).select(*keys, F.explode(F.array("pre", "post")).alias("text"))
    codes = settle(tree_codes(texts, callees, depth, rules).where("parse_ok").select(*keys, "text", "codes"))
    side = lambda c: codes.select(*keys, F.col("text").alias(c), F.col("codes").alias(f"code_{c}"))
    met = a.join(side("pre"), [*keys, "pre"], "left").join(side("post"), [*keys, "post"], "left")
    b = F.when(far & F.col("code_pre").isNotNull() & F.col("code_post").isNotNull(), line_similarity(F.col("code_pre"), F.col("code_post")))
    return met.select(*keys, "pre", "post", "sim_a", b.alias("sim_b"), *(["n"] if counted else [])), a, codes


def stage(a="sim_a", b="sim_b", theta_line: int = THETA_LINE, theta_tree: int = THETA_TREE):
    """Whether a compared pair is similar: by line, else by tree."""
    permille = lambda c: F.round(F.col(c) * 1000)
    return F.coalesce(permille(a) >= theta_line, F.lit(False)) | F.coalesce(permille(b) >= theta_tree, F.lit(False))


def refactoring(a="sim_a", b="sim_b", theta_line: int = THETA_LINE, theta_tree: int = THETA_TREE):
    """Low line similarity and high tree similarity."""
    return (F.round(F.col(a) * 1000) < theta_line) & F.coalesce(F.round(F.col(b) * 1000) >= theta_tree, F.lit(False))


def line_only(pairs: DataFrame, permille: int) -> DataFrame:
    """The line level alone, by bounded distance: pairs with ``similar``."""
    return pairs.withColumn("similar", alike(squash(F.col("pre")), squash(F.col("post")), permille))


def map_lines(pre: DataFrame, post: DataFrame) -> DataFrame:
    """For each post line of a hunk its best pre line; ties by line distance, then number."""
    met = post.alias("q").join(pre.alias("p"), ["commit_id", "file_id", "hunk"])
    sim = line_similarity(squash(F.col("p.text")), squash(F.col("q.text")))
    rows = met.select("commit_id", "file_id", "hunk", F.col("q.no").alias("post_no"), F.col("p.no").alias("pre_no"), sim.alias("sim"))
    best = F.max_by(F.struct("pre_no", "sim"), F.struct("sim", -F.abs(F.col("pre_no") - F.col("post_no")), -F.col("pre_no"))).alias("x")
    return rows.groupBy("commit_id", "file_id", "hunk", "post_no").agg(best).select("commit_id", "file_id", "hunk", "post_no", "x.pre_no", "x.sim")
