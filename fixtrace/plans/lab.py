"""The derived frames that workloads share, each computed once per scale directory."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.functions.store import drop, settle
from fixtrace.functions.text import line_similarity, squash
from fixtrace.operators import backtrack, baselines, blame, detectors, judge, similarity, versions, weights
from fixtrace.operators.asof import last_before
from fixtrace.operators.reach import arrival
from fixtrace.sources import code
from fixtrace.sources.history import History

WEAKNESS = tuple(weights.SENSITIVE)
#: A threshold above all similarities in permille: it is never reached.
_ANY = 2000


class Lab(History):
    """History plus texts, similarity, statements, truth and claims."""

    @functools.cached_property
    def cases(self) -> DataFrame:
        return settle(self.fix_case)

    @functools.cached_property
    def content(self) -> DataFrame:
        """Touches of patched files with main-path state, their text, the text before as ``pre`` and the line level between both."""
        files = self.cases.select("file_id").distinct()
        touches = self.touch.join(F.broadcast(files), "file_id", "left_semi").drop("committed_at", "op", "part")
        rows = code.with_text(blame.main_path(touches)).drop("n0", "n1", "n2", "n3").withColumn("line", squash(F.col("text")))
        rows = blame.with_before(rows, "text", "line").withColumnRenamed("pre_text", "pre")
        return settle(rows.withColumn("sim_a", F.when(F.col("pre") != F.col("text"), line_similarity(F.col("pre_line"), F.col("line")))).drop("line", "pre_line"))

    @functools.cached_property
    def pairs(self) -> DataFrame:
        """(file_id, slot, commit_id, pre, post) of touches with a predecessor."""
        return self.content.where("pred0 is not null").select("file_id", "slot", "commit_id", "seq", "lane", "fork", "edit_kind", "pre", F.col("text").alias("post"))

    @functools.cached_property
    def changes(self) -> DataFrame:
        """(pre, post, repo_id, same, n): distinct changes with their planted kind, and how often each occurs."""
        kept = F.col("edit_kind") != 2
        rows = self.pairs.groupBy("pre", "post", (F.col("file_id") / 1000).cast("int").alias("repo_id"), kept.alias("same"))
        return settle(rows.agg(F.count("*").alias("n")))

    @functools.cached_property
    def function_changes(self) -> DataFrame:
        """The whole file around each change, other statements as the main lane has them there, so that only the change
        tells both apart."""
        main = F.col("lane") == "main"
        repo = (F.col("file_id") / 1000).cast("int")
        held = self.content.where(main).select("file_id", "slot", F.col("seq").alias("pos"), F.lit(0).alias("kind"), "text")
        asked = self.pairs.select(
            "file_id", "slot", F.when(main, F.col("seq") - 1).otherwise(F.col("fork")).alias("pos"), F.lit(1).alias("kind"), squash(F.col("pre")).alias("text"),
            squash(F.col("post")).alias("post"), (F.col("edit_kind") != 2).alias("same"), F.xxhash64("pre", "post", repo).alias("draw"),
        )
        return detectors.function_changes(held.unionByName(asked, allowMissingColumns=True))

    @functools.cached_property
    def callees(self) -> DataFrame:
        return code.callees(self.spark)

    @functools.cached_property
    def sims(self) -> DataFrame:
        """(pre, post, sim_a, sim_b, n) of distinct text pairs; the tree level where the line level is below its threshold."""
        return similarity.settled(self.pairs, self.callees, counted=True)

    @functools.cached_property
    def sims_both(self) -> DataFrame:
        """As ``sims`` with both levels of every pair, for sweeps."""
        return similarity.settled(self.pairs, self.callees, theta_line=None)

    @functools.cached_property
    def watched(self) -> frozenset[str]:
        """Names that the rule judge watches: the sensitive table and the wrappers found, a few for each definition."""
        table = weights.sensitive_table(self.spark)
        found = weights.sensitive_wrappers(self.callees, table).select("fn").distinct().limit(10_001).collect()
        if len(found) > 10_000:
            raise ValueError("too many wrappers to hand to a judge; split them by repository")
        return judge.LISTED | {r.fn for r in found}

    @functools.cached_property
    def added(self) -> DataFrame:
        """(vuln_id, line_no) of lines that only the fix brings: slots it adds to that had no text before."""
        slots = self.line.where("flag = 'A'").select(F.col("commit_id").alias("vuln_id"), F.col("slot").alias("line_no"))
        return slots.join(self.cases.select("vuln_id"), "vuln_id", "left_semi").join(self.statements.select("vuln_id", F.col("slot").alias("line_no")), ["vuln_id", "line_no"], "left_anti")

    def anchored(self, pairs: DataFrame) -> DataFrame:
        return similarity.settled(pairs, self.callees).select("pre", "post", similarity.stage().alias("similar"))

    def by_line(self, permille: int) -> DataFrame:
        """Touches compared by the line level alone."""
        return backtrack.compared_touches(self.content.withColumn("similar", F.round(F.col("sim_a") * 1000) >= permille))

    @functools.cached_property
    def levels(self) -> DataFrame:
        """Main-path touches with both similarities to the text before in permille (``a``, ``b``), for sweeps."""
        permille = lambda c: F.coalesce(F.round(F.col(c) * 1000).cast("int"), F.lit(-1))
        flags = self.sims_both.select("pre", "post", F.lit(None).cast("boolean").alias("similar"), permille("sim_a").alias("a"), permille("sim_b").alias("b"))
        rows = backtrack.compared_touches(self.content, flags)
        a = F.when(F.col("kind") == 1, 1001).otherwise(F.coalesce("a", F.lit(-1)))
        return settle(rows.select(*backtrack.PLACE, a.alias("a"), F.coalesce("b", F.lit(-1)).alias("b")))

    @property
    def graded(self) -> DataFrame:
        """``compared`` as ``levels`` has it, with the tree level only where the line level is below its threshold.

        999 is the most that unequal squashed texts can have in ``a``, so 1000 and more tell that nothing but layout changed.
        """
        permille = lambda c: F.coalesce(F.round(F.col(c) * 1000).cast("int"), F.lit(-1))
        a = F.when(F.col("kind") == 1, 1001).when(F.col("sim_a") < 1, F.least(permille("sim_a"), F.lit(999))).otherwise(permille("sim_a"))
        return self.compared.select(*backtrack.PLACE, a.alias("a"), permille("sim_b").alias("b"))

    @functools.cached_property
    def compared(self) -> DataFrame:
        """Touches with both levels; only changes that the line level does not settle are told by distinct texts."""
        near = F.round(F.col("sim_a") * 1000) >= similarity.THETA_LINE
        far = similarity.settled(self.content.where(~near).select("pre", F.col("text").alias("post")), self.callees)
        flags = far.select("pre", "post", similarity.stage().alias("similar"), "sim_b")
        rows = backtrack.compared_touches(self.content.withColumn("similar", F.when(near, True)), flags)
        out = settle(rows)
        drop(far)
        return out

    @functools.cached_property
    def statements(self) -> DataFrame:
        """The patch's statements that existed before the fix, with weights: the slots the fix adds to or deletes."""
        slots = self.line.where("flag in ('A', 'R')").select(F.col("commit_id").alias("fix_commit_id"), "slot", "flag")
        rows = self.cases.join(slots, "fix_commit_id")
        before = self.content.where("lane = 'main'").select("file_id", "slot", "seq", "text")
        held = last_before(rows, before, F.struct("text"), ["file_id", "slot"])
        out = held.select("vuln_id", "slot", *(c for c in rows.columns if c not in ("vuln_id", "slot")), "met.text")
        table = weights.sensitive_table(self.spark)
        return settle(weights.assign_weights(out, table, weights.sensitive_wrappers(code.callees(self.spark), table)))

    def arrivals(self, origins: DataFrame) -> DataFrame:
        """Origins (vuln_id, origin_commit_id) with repo and first main position that holds them."""
        c = self.commit.select(F.col("commit_id").alias("origin_commit_id"), "repo_id", arrival().alias("arrival"))
        return origins.join(c, "origin_commit_id").select("vuln_id", "repo_id", "arrival")

    @functools.cached_property
    def fixes(self) -> DataFrame:
        return self.cases.select("vuln_id", "repo_id", F.col("fix_seq").alias("arrival"))

    @functools.cached_property
    def tags(self) -> DataFrame:
        return settle(self.version_tag)

    def affected(self, origins: DataFrame) -> DataFrame:
        return versions.affected_versions(self.arrivals(origins), self.fixes, self.tags)

    @functools.cached_property
    def truth_origin(self) -> DataFrame:
        """(vuln_id, trigger_slot, origin_commit_id): the planted origin of the trigger slot; null without history."""
        rows = self.cases.select("vuln_id", "file_id", "fix_seq", F.col("trigger_slot").alias("slot"))
        met = last_before(rows, self.content.where("lane = 'main'"), F.struct("rewritten_by"), ["file_id", "slot"])
        last = met.select("vuln_id", F.col("met.rewritten_by").alias("origin_commit_id"))
        return rows.select("vuln_id", F.col("slot").alias("trigger_slot")).join(last, "vuln_id", "left")

    @functools.cached_property
    def truth(self) -> DataFrame:
        return settle(self.affected(self.truth_origin.where("origin_commit_id is not null")))

    @functools.cached_property
    def truth_runs(self) -> DataFrame:
        """(vuln_id, repo_id, real, stop): the tags of ``truth`` are those in (real, stop] by number; ``real`` is null without an origin."""
        place = self.cases.select("vuln_id", "repo_id", F.col("fix_seq").alias("seq"))
        fixed = versions.tags_before(place, self.tags).select("vuln_id", "repo_id", F.col("n_tags").alias("stop"))
        known = self.first_tags(self.truth_origin.where("origin_commit_id is not null")).select("vuln_id", F.col("ahead").alias("real"))
        return settle(fixed.join(known, "vuln_id", "left"))

    def first_tags(self, origins: DataFrame) -> DataFrame:
        """Origins that are touches of patched files, with ``ahead``: how many tags of the repository come before the first that holds it."""
        came = self.content.select(F.col("commit_id").alias("origin_commit_id"), "repo_id", arrival().alias("seq")).where("seq is not null")
        came = came.join(origins.select("origin_commit_id").distinct(), "origin_commit_id", "left_semi").distinct()
        return origins.join(versions.tags_before(came, self.tags).select("origin_commit_id", F.col("n_tags").alias("ahead")), "origin_commit_id")

    @functools.cached_property
    def claims(self) -> DataFrame:
        """Synthesised claims: the pattern follows the claiming supplier; ``claimed`` holds tag numbers or null."""
        suppliers = self._table("supplier").select("s_suppkey")
        many = suppliers.agg(F.min("s_suppkey").alias("first"), F.count("*").alias("n"))
        source = F.col("first") + F.pmod(F.expr("vuln_id div 16"), F.col("n"))
        rows = self.cases.join(F.broadcast(many)).select("vuln_id", "repo_id", "severity", source.alias("source_id"))
        real = self.truth_runs.where("real < stop").select("vuln_id", (F.col("real") + 1).alias("a"), F.col("stop").alias("b"))
        rows = rows.join(real, "vuln_id", "left").withColumn("pattern", F.element_at(F.array(*map(F.lit, ("exact", "single", "all_before", "missing", "stale"))), (F.col("source_id") % 5 + 1).cast("int")))
        p = F.col("pattern")
        lo = F.when(p == "single", F.col("b")).when(p == "all_before", F.lit(1)).when(p != "missing", F.col("a"))
        hi = F.when(p == "stale", F.col("b") - 1).when(p != "missing", F.col("b"))
        rows = rows.withColumns({"lo": F.when(F.col("a").isNotNull(), lo).cast("int"), "hi": F.when(F.col("a").isNotNull(), hi).cast("int")})
        claimed = F.when(p == "missing", None).when(F.col("lo") <= F.col("hi"), F.sequence("lo", "hi")).otherwise(F.array().cast("array<int>"))
        return rows.withColumn("claimed", claimed).drop("a", "b")

    def deleted(self) -> DataFrame:
        return self.statements.where("flag = 'R'")

    # methods: each gives (vuln_id, repo_id, tag_no)

    def engine(self, merges: str = "earliest", stmts: DataFrame | None = None, compared: DataFrame | None = None) -> DataFrame:
        s = self.statements if stmts is None else stmts
        stops = backtrack.statement_stops(s, self.compared if compared is None else compared, merges)
        return backtrack.cumulative(s, stops)

    @functools.cached_property
    def spans(self) -> DataFrame:
        """The tags at which each line of a patched file stands."""
        return settle(versions.line_spans(self.cases, self.tags, self.content))

    @functools.cached_property
    def bodies(self) -> DataFrame:
        """Files before and after the fix, for the per-version detectors."""
        return settle(baselines.vulnerable_bodies(self.cases, self.content))

    def near(self, needed, within: DataFrame | None = None) -> DataFrame:
        return baselines.line_candidates(self.cases, self.bodies, self.spans, needed, within)

    def method(self, name: str) -> DataFrame:
        claimed = lambda: baselines.advisory_versions(self.claims, self.tags)
        if name == "two_level":
            return self.affected(self.engine())
        if name == "all_paths":
            preds = blame.predecessors(self.content)
            return self.affected(backtrack.cumulative(self.statements, settle(backtrack.exact_stops(self.statements, preds, self.compared))))
        if name == "per_commit":
            return self.affected(backtrack.per_commit(self.statements, self.compared))
        if name == "touched_only":
            return self.affected(backtrack.per_commit(self.statements, self.compared, untouched="excluded"))
        if name == "anchor":
            return self.affected(backtrack.cumulative(self.statements, settle(backtrack.anchored_walk(self.statements, self.content, self.anchored))))
        if name == "first_parent":
            return self.affected(self.engine("first_parent"))
        if name == "line_only":
            return self.affected(self.engine(compared=self.by_line(similarity.THETA_LINE)))
        if name == "unweighted":
            return self.affected(self.engine(stmts=self.statements.withColumn("weight", F.lit(1.0))))
        if name == "claims":
            return claimed()
        if name == "blame_basic":
            return self.affected(baselines.blame_basic(self.deleted(), self.content))
        if name == "blame_annotated":
            return self.affected(baselines.blame_annotated(self.deleted(), self.content))
        if name == "blame_tracked":
            return self.affected(baselines.blame_tracked(self.deleted(), self.by_line(750)))
        if name == "function_digest":
            return baselines.function_digest(self.cases, versions.file_lines(self.spans), self.bodies)
        if name == "hybrid":
            bounds = self.claims.where("lo is not null and hi is not null")
            return baselines.hybrid(self.near(baselines.hybrid_needs(), bounds), self.bodies)
        if name == "patch_presence":
            return versions.each_tag(self.patch_runs())
        if name == "dependence_match":
            return baselines.dependence_match(self.near(F.lit(1)), self.bodies, self.statements.select("vuln_id", "slot", squash(F.col("text")).alias("pre"), "weight"))
        if name == "window_match":
            return baselines.window_match(self.near(baselines.window_needs()), self.bodies)
        raise KeyError(name)

    def patch_runs(self) -> DataFrame:
        return baselines.patch_runs(self.cases, self.spans, self.changed())

    def walked_origins(self) -> DataFrame:
        """(method, vuln_id, origin_commit_id) of all methods that walk back, as ``method`` finds them one by one.

        Walks that differ in what they call lost are stops of one pass over the touches, and one running sum of lost
        weight serves all methods that have one.
        """
        grid = [(similarity.THETA_LINE, similarity.THETA_TREE), (similarity.THETA_LINE, _ANY), (similarity.THETA_LINE, similarity.THETA_TREE), (_ANY, _ANY), (1000, _ANY), (750, _ANY)]
        stops = settle(backtrack.swept_stops(self.statements, self.graded, grid, straight=(2, 3, 4, 5)))
        of = lambda k: stops.where(F.col("k") == k).drop("k")
        preds = blame.predecessors(self.content)
        sums = {
            "two_level": of(0), "unweighted": of(0), "line_only": of(1), "first_parent": of(2),
            "all_paths": backtrack.exact_stops(self.statements, preds, self.compared), "anchor": backtrack.anchored_walk(self.statements, self.content, self.anchored),
        }
        columns = ["vuln_id", "slot", "stop_commit", "stop_seq"]
        named = [s.select(F.lit(n).alias("method"), *columns) for n, s in sums.items()]
        lost = settle(functools.reduce(DataFrame.unionByName, named))
        stmts = self.statements.select("vuln_id", "slot", "weight", F.explode(F.array(*map(F.lit, sums))).alias("method"))
        stmts = stmts.withColumn("weight", F.when(F.col("method") == "unweighted", 1.0).otherwise(F.col("weight")))
        held = self.deleted().select("vuln_id", "slot")
        found = [backtrack.cumulative(stmts, lost, by=("method",))]
        for k, name in enumerate(BLAME, 3):
            last = of(k).join(held, ["vuln_id", "slot"], "left_semi").select("vuln_id", F.col("stop_seq").alias("seq"), F.col("stop_commit").alias("commit_id"))
            found.append(baselines.earliest(last).withColumn("method", F.lit(name)))
        kinds = F.when(F.col("untouched") == "kept", "per_commit").otherwise("touched_only")
        found.append(backtrack.per_commit_both(self.statements, self.compared).withColumn("method", kinds))
        return functools.reduce(DataFrame.unionByName, (f.select("method", "vuln_id", "origin_commit_id") for f in found))

    def found_runs(self) -> DataFrame:
        """(method, vuln_id, first, last): what every method of ``METHODS`` finds, as runs of tags by number, none twice for a case."""
        walked = self.first_tags(settle(self.walked_origins())).join(self.truth_runs.select("vuln_id", "stop"), "vuln_id")
        out = [walked.select("method", "vuln_id", (F.col("ahead") + 1).alias("first"), F.col("stop").alias("last")).where("first <= last")]
        for name in PER_VERSION:
            if name == "claims":
                runs = self.claims.select("vuln_id", F.col("lo").alias("first"), F.col("hi").alias("last")).where("first <= last")
            elif name == "patch_presence":
                runs = self.patch_runs().select("vuln_id", "first", "last")
            else:
                runs = self.method(name).select("vuln_id", F.col("tag_no").alias("first"), F.col("tag_no").alias("last"))
            out.append(runs.withColumn("method", F.lit(name)))
        return functools.reduce(DataFrame.unionByName, out)

    def changed(self) -> DataFrame:
        """(vuln_id, deleted, added): squashed lines a fix removes and puts in their place."""
        after = self.content.select(F.col("commit_id").alias("fix_commit_id"), "slot", squash(F.col("text")).alias("after"))
        rows = self.statements.join(after, ["fix_commit_id", "slot"])
        removed = F.filter(F.collect_list(F.when(F.col("flag") == "R", squash(F.col("text")))), lambda x: x.isNotNull())
        return rows.groupBy("vuln_id").agg(removed.alias("deleted"), F.collect_list("after").alias("added"))


@functools.lru_cache(maxsize=2)
def _lab(spark, sf_dir: str, state: tuple) -> Lab:
    return Lab(spark, sf_dir)


def lab_of(spark, sf_dir: str) -> Lab:
    """The lab of a session and directory; queries share its frames until a file of the directory changes."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(sf_dir)
    found = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listStatus(path)
    return _lab(spark, sf_dir, tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in found)))


METHODS = ("two_level", "all_paths", "per_commit", "touched_only", "anchor", "first_parent", "line_only", "unweighted", "claims", "blame_basic", "blame_annotated", "blame_tracked", "function_digest", "hybrid", "patch_presence", "dependence_match", "window_match")
#: Methods that give a version of a case once by how they are made.
PER_VERSION = ("claims", "function_digest", "hybrid", "patch_presence", "dependence_match", "window_match")
BLAME = ("blame_basic", "blame_annotated", "blame_tracked")
