"""Comparison methods: claims, blame, and per-version clone detectors."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fixtrace.functions.store import settle
from fixtrace.functions.text import squash
from fixtrace.operators import versions
from fixtrace.operators.asof import last_before
from fixtrace.operators.backtrack import statement_stops
from fixtrace.operators.extraction import dependence, slice_lines


def advisory_versions(claims: DataFrame, tags: DataFrame) -> DataFrame:
    """Tags inside the claimed [lo, hi] of tag numbers; a claim without bounds names none."""
    c = claims.where("lo is not null and hi is not null").select("vuln_id", "repo_id", "lo", "hi")
    return c.join(tags, "repo_id").where("tag_no between lo and hi").select("vuln_id", "repo_id", "tag_no", "tag")


def earliest(rows: DataFrame) -> DataFrame:
    """Of the commits (vuln_id, seq, commit_id) found for a case the earliest."""
    best = F.min(F.struct("seq", "commit_id")).alias("x")
    return rows.groupBy("vuln_id").agg(best).select("vuln_id", F.col("x.commit_id").alias("origin_commit_id"), F.col("x.seq").alias("origin_seq"))


def blame_basic(deleted: DataFrame, content: DataFrame) -> DataFrame:
    """Last main-lane change of each deleted line before the fix; of several the earliest.  None for add-only fixes."""
    asked = deleted.select("vuln_id", "file_id", "slot", "fix_seq")
    last = last_before(asked, content.where("lane = 'main'"), F.struct("seq", "commit_id"), ["file_id", "slot"])
    return earliest(last.select("vuln_id", "met.*"))


def blame_annotated(deleted: DataFrame, compared: DataFrame) -> DataFrame:
    """As the basic method, past changes of comments, blanks and layout only."""
    real = compared.where(F.col("pre").isNull() | (squash(F.col("pre")) != squash(F.col("text"))))
    return blame_basic(deleted, real)


def blame_tracked(deleted: DataFrame, compared_by_line: DataFrame) -> DataFrame:
    """Follow each deleted line by edit distance to the earliest commit that has it."""
    stops = statement_stops(deleted, compared_by_line, merges="first_parent")
    return earliest(stops.select("vuln_id", F.col("stop_seq").alias("seq"), F.col("stop_commit").alias("commit_id")))


def version_bodies(cases: DataFrame, snapshots: DataFrame) -> DataFrame:
    """(vuln_id, repo_id, tag_no, lines): the patched file at each tag, lines squashed, as a map from slot."""
    rows = cases.select("vuln_id", "repo_id", "file_id").join(snapshots, ["repo_id", "file_id"])
    return rows.groupBy("vuln_id", "repo_id", "tag_no").agg(F.map_from_entries(F.collect_list(F.struct("slot", squash(F.col("text")).alias("s")))).alias("lines"))


def vulnerable_bodies(cases: DataFrame, content: DataFrame) -> DataFrame:
    """(vuln_id, body, fixed): the file just before and just after the fix, as maps from slot."""
    main = content.where("lane = 'main'")
    rows = cases.select("vuln_id", "file_id", "fix_seq").join(main.select("file_id", "slot").distinct(), "file_id")
    asked = rows.select("vuln_id", "file_id", "slot", F.explode(F.array(F.lit(0), F.lit(1))).alias("later"), "fix_seq").withColumn("fix_seq", F.col("fix_seq") + F.col("later"))
    per = last_before(asked, main, F.struct("text"), ["file_id", "slot"]).select("vuln_id", "later", F.struct("slot", squash(F.col("met.text")).alias("s")).alias("e"))
    side = lambda k: F.map_from_entries(F.collect_list(F.when(F.col("later") == k, F.col("e"))))
    return per.groupBy("vuln_id").agg(side(0).alias("body"), side(1).alias("fixed"))


def _tokens(lines):
    return F.flatten(F.transform(F.filter(F.map_values(lines), lambda x: x.isNotNull()), lambda x: F.regexp_extract_all(x, F.lit(r"\w+|[^\w\s]+"), F.lit(0))))


def _majority(batches):
    """64-bit digests of token hashes: the majority of each bit."""
    for b in batches:
        h = b.column("h")
        sizes = h.value_lengths().to_numpy(zero_copy_only=False)
        bits = np.unpackbits(h.flatten().to_numpy(zero_copy_only=False).astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones = np.zeros((len(sizes), 64), np.int64)
        some = np.flatnonzero(sizes)
        if len(some):
            ones[some] = np.add.reduceat(bits, (np.cumsum(sizes) - sizes)[some], axis=0, dtype=np.int64)
        digest = np.packbits(ones * 2 > sizes[:, None], axis=1, bitorder="little").view("<i8").ravel()
        keys = [c for c in b.schema.names if c != "h"]
        yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keys), pa.array(digest)], [*keys, "digest"])


def digests(rows: DataFrame, lines: str, kinds: str) -> DataFrame:
    """The other columns of ``rows``, of the types ``kinds``, with the digest of ``lines`` (``text.simhash64``), a token hashed once."""
    hashed = rows.withColumn("h", F.transform(_tokens(lines), lambda t: F.xxhash64(t))).drop(lines)
    return hashed.mapInArrow(_majority, f"{kinds}, digest bigint")


def function_digest(cases: DataFrame, files: DataFrame, bodies: DataFrame, limit: int = 6) -> DataFrame:
    """Versions whose file digest is within ``limit`` bits of the vulnerable one's.

    ``files``: repo_id, file_id, tag_no, lines; each is digested once, not once for each case that patches it.
    """
    wanted = digests(bodies.select("vuln_id", "body"), "body", "vuln_id bigint").withColumnRenamed("digest", "wanted").join(cases.select("vuln_id", "file_id"), "vuln_id")
    found = digests(files.select("repo_id", "file_id", "tag_no", "lines"), "lines", "repo_id int, file_id int, tag_no int")
    near = F.bit_count(F.col("digest").bitwiseXOR(F.col("wanted"))) <= limit
    return found.join(wanted, "file_id").where(near).select("vuln_id", "repo_id", "tag_no")


def line_candidates(cases: DataFrame, bodies: DataFrame, spans: DataFrame, needed: Column, within: DataFrame | None = None) -> DataFrame:
    """(vuln_id, repo_id, tag_no, lines): the versions that hold at least ``needed`` (of ``body``) distinct lines of the vulnerable file.

    ``within``: (vuln_id, lo, hi), the tags that may count.  Only these versions are built, so a method that asks
    for more lines than ``needed`` has all its versions here and judges them by its own rule.
    """
    held = bodies.select("vuln_id", F.array_distinct(F.map_values("body")).alias("own"), needed.alias("needed")).join(cases.select("vuln_id", "file_id"), "vuln_id")
    wanted = held.select("vuln_id", "file_id", F.explode("own").alias("line"), F.lit(1).alias("n"))
    ranges = versions.line_counts(cases, wanted, spans, ("n",)).join(held.select("vuln_id", "needed"), "vuln_id").where("n >= needed").drop("n", "needed")
    if within is not None:
        ranges = ranges.join(within.select("vuln_id", "lo", "hi"), "vuln_id").withColumns({"first": F.greatest("first", "lo"), "last": F.least("last", "hi")}).where("first <= last").drop("lo", "hi")
    near = settle(versions.each_tag(ranges))
    return near.join(versions.file_lines(spans, near.select("file_id", "tag_no")).drop("repo_id"), ["file_id", "tag_no"]).select("vuln_id", "repo_id", "tag_no", "lines")


def hybrid(versions: DataFrame, bodies: DataFrame, least: float = 0.5) -> DataFrame:
    """Versions, given those inside the claim, whose line set is near the vulnerable one's; inherits the claim's errors."""
    a, b = F.map_values("lines"), F.map_values("body")
    near = F.size(F.array_intersect(a, b)) >= least * F.size(F.array_union(a, b))
    return versions.join(bodies.select("vuln_id", "body"), "vuln_id").where(near).select("vuln_id", "repo_id", "tag_no")


def hybrid_needs(least: float = 0.5) -> Column:
    """Lines that a version near enough shares at least: the union is no smaller than the vulnerable set."""
    return F.ceil(F.lit(least) * F.size(F.array_distinct(F.map_values("body"))) - 1e-9).cast("int")


def patch_presence(cases: DataFrame, spans: DataFrame, changed: DataFrame, del_min: float = 1.0, add_max: float = 0.9) -> DataFrame:
    """Vulnerable where all deleted lines are there and the added ones mostly are not.

    ``changed``: vuln_id, deleted and added arrays of squashed lines.  Runs of tags come from the spans of these
    lines and are told apart into tags at the end, in the task that found them.
    """
    return versions.each_tag(patch_runs(cases, spans, changed, del_min, add_max))


def patch_runs(cases: DataFrame, spans: DataFrame, changed: DataFrame, del_min: float = 1.0, add_max: float = 0.9) -> DataFrame:
    """(vuln_id, repo_id, first, last): the versions of ``patch_presence`` as runs of tags, none twice for a case."""
    sets = cases.select("vuln_id", "file_id").join(changed.select("vuln_id", F.array_distinct("deleted").alias("d"), F.array_distinct("added").alias("a")), "vuln_id")
    has = lambda c: F.array_contains(c, F.col("line")).cast("int")
    wanted = sets.withColumn("line", F.explode(F.array_union("d", "a"))).select("vuln_id", "file_id", "line", has("d").alias("n_d"), has("a").alias("n_a"))
    rows = versions.line_counts(cases, wanted, spans, ("n_d", "n_a")).join(sets.select("vuln_id", F.size("d").alias("all_d"), F.size("a").alias("all_a")), "vuln_id")
    share = lambda n, of, none: F.coalesce(F.when(F.col(of) > 0, F.col(n) / F.col(of)), F.lit(none))
    rows = rows.where((share("n_d", "all_d", 1.0) >= del_min) & (share("n_a", "all_a", 0.0) <= add_max))
    return rows.select("vuln_id", "repo_id", "first", "last")


def weighted_graph(lines: list[tuple[int, str]], seeds: set[int], weights: dict[str, float]) -> dict[tuple, float]:
    """The dependence graph around some lines, by text: weights of its critical statements and of the edges between.

    Critical is what the slice both ways from the seeds holds.  A statement weighs what ``weights`` says, else 1; an
    edge weighs as much as the heavier of its ends.
    """
    text = dict(lines)
    _, edges = dependence(lines)
    critical = set(slice_lines(lines, seeds))
    of = lambda no: weights.get(text[no], 1.0)
    out: dict[tuple, float] = {("stmt", text[no]): of(no) for no in critical}
    for a, b, kind, variable in edges:
        if a in critical and b in critical:
            out[kind, text[a], text[b], variable] = max(of(a), of(b))
    return out


def weighted_jaccard(a: dict[tuple, float], b: dict[tuple, float]) -> float:
    """Sum of the lesser weights over the sum of the greater ones."""
    keys = a.keys() | b.keys()
    total = sum(max(a.get(k, 0.0), b.get(k, 0.0)) for k in keys)
    return sum(min(a.get(k, 0.0), b.get(k, 0.0)) for k in keys) / total if total else 0.0


def dependence_match(versions: DataFrame, bodies: DataFrame, weighted: DataFrame, least: float = 0.7) -> DataFrame:
    """Versions whose weighted dependence graph around the patched statements is near the vulnerable one's.

    ``weighted``: vuln_id, slot, pre (squashed text), weight of the patch's statements.  Each distinct body of a
    case is compared once, in Arrow batches, and the vulnerable graph is built once for the rows of a case that follow
    each other.  A version without the lines for ``least`` of that graph's weight is never near and has no graph built.
    """
    entries = lambda c: F.array_sort(F.map_entries(c))
    critical = weighted.groupBy("vuln_id").agg(F.collect_list(F.struct("slot", "pre", "weight")).alias("critical"))
    rows = versions.select("vuln_id", "repo_id", "tag_no", entries("lines").alias("lines"))
    wanted = bodies.select("vuln_id", entries("body").alias("body")).join(critical, "vuln_id")
    asked = rows.select("vuln_id", "lines").distinct().join(wanted, "vuln_id")

    def run(batches):
        pairs = lambda x: [(e["key"], e["value"] or "") for e in x]
        last, weights, seeds, one, least_held = None, {}, set(), {}, 0.0
        for b in batches:
            keep = []
            for no, lines, body, marks in zip(*(b.column(c).to_pylist() for c in ("vuln_id", "lines", "body", "critical")), strict=True):
                if no != last:
                    last, weights, seeds = no, {m["pre"]: m["weight"] for m in marks}, {m["slot"] for m in marks}
                    one = weighted_graph(pairs(body), seeds, weights)
                    least_held = least * sum(one.values()) - 1e-9
                two = pairs(lines)
                held = {t for _, t in two}
                # ("stmt", text) or (kind, text, text, variable): what of the graph these lines could give at most
                near = sum(w for k, w in one.items() if k[1] in held and (k[0] == "stmt" or k[2] in held)) >= least_held
                keep.append(near and weighted_jaccard(one, weighted_graph(two, seeds, weights)) >= least)
            yield pa.RecordBatch.from_arrays([b.column("vuln_id"), b.column("lines")], ["vuln_id", "lines"]).filter(pa.array(keep, pa.bool_()))

    kind = "array<struct<key:int,value:string>>"
    near = asked.select("vuln_id", "lines", "body", "critical").sortWithinPartitions("vuln_id").mapInArrow(run, f"vuln_id bigint, lines {kind}")
    return rows.join(near, ["vuln_id", "lines"], "left_semi").select("vuln_id", "repo_id", "tag_no")


def _in_order(lines) -> Column:
    return F.transform(F.array_sort(F.map_entries(lines)), lambda e: e["value"])


def window_match(versions: DataFrame, bodies: DataFrame, width: int = 4, least: float = 0.5) -> DataFrame:
    """Versions that hold at least the share ``least`` of the runs of ``width`` neighbouring lines of the vulnerable file, by hash."""

    def windows(lines):
        values = _in_order(lines)
        many = F.transform(F.sequence(F.lit(1), F.size(values) - width + 1), lambda k: F.xxhash64(F.array_join(F.slice(values, k, width), "\n")))
        return F.when(F.size(values) >= width, many).otherwise(F.array(F.xxhash64(F.array_join(values, "\n"))))

    rows = versions.join(bodies.select("vuln_id", "body"), "vuln_id").withColumns({"w": windows("body"), "h": windows("lines")})
    return rows.where(F.size(F.array_intersect("w", "h")) >= least * F.size(F.array_distinct("w"))).select("vuln_id", "repo_id", "tag_no")


def window_needs(width: int = 4) -> Column:
    """Distinct lines that any version with a window of the vulnerable file holds at least: those of its poorest window."""
    values = _in_order("body")
    some = F.transform(F.sequence(F.lit(1), F.size(values) - width + 1), lambda k: F.size(F.array_distinct(F.slice(values, k, width))))
    return F.when(F.size(values) >= width, F.array_min(some)).otherwise(F.size(F.array_distinct(values)))
