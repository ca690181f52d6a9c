"""Containment of commits: by branch labels, and by doubling for any acyclic graph."""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fixtrace.functions.store import settle


def contains(inner: str, outer: str) -> Column:
    """Whether the commit aliased ``outer`` has ``inner`` in its history, from the labels of both.

    A main commit holds the main commits up to it and the branches merged up to it; a branch commit holds what its
    fork point holds and the earlier commits of its own branch.
    """
    a, b = (lambda c: F.col(f"{inner}.{c}")), (lambda c: F.col(f"{outer}.{c}"))
    same_branch = (a("lane") == "feature") & (b("lane") == "feature") & (a("block") == b("block")) & (a("seq") <= b("seq"))
    arrived = F.coalesce(a("mseq"), F.when(a("lane") == "main", a("seq"))) <= b("fork")
    return (a("repo_id") == b("repo_id")) & (F.coalesce(arrived, F.lit(False)) | same_branch)


def arrival(seq: str = "seq", lane: str = "lane", mseq: str = "mseq") -> Column:
    """The first main position that holds a commit; null for a branch that was never merged."""
    return F.when(F.col(lane) == "main", F.col(seq)).otherwise(F.col(mseq))


def double_edges(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """(repo_id, child_id, ancestor_id) of the whole closure, commits among their own ancestors.

    Paths double in length each round, so rounds grow with the logarithm of the depth; meant for graphs without
    branch labels and for checking those.
    """
    step = edges.select("repo_id", "child_id", F.col("parent_id").alias("ancestor_id"))
    nodes = step.select("repo_id", F.col("child_id").alias("n")).union(step.select("repo_id", "ancestor_id")).distinct()
    now = settle(step.union(nodes.select("repo_id", "n", F.col("n"))).distinct())
    size = now.count()
    for _ in range(max_rounds):
        left, right = now.alias("l"), now.alias("r")
        met = left.join(right, (F.col("l.repo_id") == F.col("r.repo_id")) & (F.col("l.ancestor_id") == F.col("r.child_id")))
        now = settle(met.select("l.repo_id", "l.child_id", "r.ancestor_id").distinct())
        if size == (size := now.count()):
            return now
    raise RuntimeError("the graph is deeper than the rounds allow, or has a cycle")


def recursive(edges: DataFrame, sources: DataFrame) -> DataFrame:
    """(repo_id, child_id, ancestor_id) of the holders of some commits by Spark's recursive SQL.

    For short graphs: Spark stops with an error beyond 100 levels, and counts each path on its own until the end.
    """
    return edges.sparkSession.sql(
        """WITH RECURSIVE held(repo_id, child_id, ancestor_id) AS (
             SELECT repo_id, commit_id, commit_id FROM {sources}
             UNION ALL SELECT e.repo_id, e.child_id, h.ancestor_id FROM held h JOIN {edges} e ON e.repo_id = h.repo_id AND e.parent_id = h.child_id)
           SELECT DISTINCT repo_id, child_id, ancestor_id FROM held""",
        sources=sources.select("repo_id", "commit_id").distinct(), edges=edges.select("repo_id", "child_id", "parent_id").distinct(),
    )


def holders(edges: DataFrame, sources: DataFrame, blocks: int = 4) -> DataFrame:
    """(repo_id, child_id, ancestor_id): every commit that holds a source, the source among them, by edges alone.

    ``sources``: repo_id, commit_id.  A task walks the edges of one repository once, parents first, with a bit for
    each source of its block.
    """
    no = F.pmod(F.xxhash64("commit_id"), F.lit(blocks))
    ids = sources.select("repo_id", "commit_id").distinct().select(F.col("repo_id").cast("long").alias("repo_id"), F.col("commit_id").cast("long").alias("commit_id"), no.alias("no"))
    dealt = edges.select("repo_id", F.col("child_id").cast("long").alias("child_id"), F.col("parent_id").cast("long").alias("parent_id")).distinct()
    met = ids.select(F.col("repo_id").alias("r"), F.col("no").alias("n")).distinct()
    dealt = dealt.join(met, F.col("repo_id") == F.col("r")).select(F.col("r").alias("repo_id"), F.col("n").alias("no"), "child_id", "parent_id")

    def walk(e: pa.Table, s: pa.Table) -> pa.Table:
        found = sorted(s.column("commit_id").to_pylist())
        mask = {c: 1 << k for k, c in enumerate(found)}
        after, waits = {}, {}
        for child, parent in zip(e.column("child_id").to_pylist(), e.column("parent_id").to_pylist(), strict=True):
            after.setdefault(parent, []).append(child)
            waits[child] = waits.get(child, 0) + 1
        nodes = {*found, *after, *waits}
        todo = [c for c in nodes if c not in waits]
        child_id, ancestor_id, done, at = [], [], 0, np.array(found, np.int64)
        while todo:
            c = todo.pop()
            done += 1
            held = mask.pop(c, 0)
            if held:
                bits = np.frombuffer(held.to_bytes((len(found) + 7) // 8, "little"), np.uint8)
                got = at[np.flatnonzero(np.unpackbits(bits, bitorder="little"))]
                ancestor_id.append(got)
                child_id.append(np.full(len(got), c, np.int64))
            for x in after.get(c, ()):
                if held:
                    mask[x] = mask.get(x, 0) | held
                waits[x] -= 1
                if not waits[x]:
                    todo.append(x)
        if done < len(nodes):
            raise RuntimeError("the graph has a cycle")
        empty = [np.zeros(0, np.int64)]
        child, ancestor = np.concatenate(child_id or empty), np.concatenate(ancestor_id or empty)
        repo = s.column("repo_id")[0].as_py() if len(s) else 0
        return pa.table({"repo_id": np.full(len(child), repo, np.int64), "child_id": child, "ancestor_id": ancestor})

    return dealt.groupBy("repo_id", "no").cogroup(ids.groupBy("repo_id", "no")).applyInArrow(walk, "repo_id long, child_id long, ancestor_id long")


def disagreements(edges: DataFrame, commits: DataFrame, sources: DataFrame, most: int = 8192) -> DataFrame:
    """(repo_id, n_pairs, n_differ): pairs of a commit and a source it holds by edges or by branch labels, and those that one of both lacks.

    ``commits`` and ``sources``: repo_id, commit_id, seq, lane, block, fork, mseq.  A task walks a repository once for
    each block of about ``most`` sources, with a bit for each, and counts bits: no pair is ever written.
    """
    whole = F.col("repo_id").cast("long").alias("repo_id")
    found = sources.select(whole, F.col("commit_id").alias("commit_id"), "seq", "block", (F.col("lane") == "main").alias("main"), F.coalesce("mseq", F.when(F.col("lane") == "main", F.col("seq"))).alias("arrival")).distinct()
    largest = found.groupBy("repo_id").count().agg(F.max("count")).first()[0] or 0
    found = found.withColumn("no", F.pmod(F.xxhash64("commit_id"), F.lit(-(-largest // most) or 1)))
    met = found.select(F.col("repo_id").alias("r"), F.col("no").alias("n")).distinct()
    none = F.lit(None).cast("int")
    rows = edges.select(whole, F.col("child_id").alias("commit_id"), "parent_id", none.alias("seq"), none.alias("block"), F.lit(None).cast("boolean").alias("main"), none.alias("fork"))
    rows = rows.unionByName(commits.select(whole, "commit_id", F.lit(None).cast("bigint").alias("parent_id"), "seq", "block", (F.col("lane") == "main").alias("main"), "fork"))
    rows = rows.join(F.broadcast(met), F.col("repo_id") == F.col("r")).drop("r").withColumnRenamed("n", "no")

    def count(t: pa.Table, s: pa.Table) -> pa.Table:
        known = sorted(zip(*(s.column(c).to_pylist() for c in ("commit_id", "seq", "block", "main", "arrival")), strict=True), key=lambda r: (r[4] is None, r[4] or 0, r[0]))
        came = [r[4] for r in known if r[4] is not None]
        mask, branch = {}, {}
        for k, (c, seq, block, main, _) in enumerate(known):
            mask[c] = 1 << k
            if not main:
                branch.setdefault(block, []).append((seq, 1 << k))
        after, waits, label = {}, dict.fromkeys(mask, 0), {}
        for c, parent, seq, block, main, fork in zip(*(t.column(c).to_pylist() for c in ("commit_id", "parent_id", "seq", "block", "main", "fork")), strict=True):
            waits.setdefault(c, 0)
            if parent is not None:
                waits.setdefault(parent, 0)
                waits[c] += 1
                after.setdefault(parent, []).append(c)
            elif seq is not None:
                label[c] = (seq, block, main, fork)
        todo, done, n_pairs, n_differ = [c for c, n in waits.items() if not n], 0, 0, 0
        while todo:
            c = todo.pop()
            done += 1
            held, told = mask.pop(c, 0), 0
            if c in label:
                seq, block, main, fork = label[c]
                told = (1 << bisect.bisect_right(came, fork)) - 1 if fork is not None else 0
                if not main:
                    for q, bit in branch.get(block, ()):
                        if q <= seq:
                            told |= bit
            n_pairs += (held | told).bit_count()
            n_differ += (held ^ told).bit_count()
            for x in after.get(c, ()):
                if held:
                    mask[x] = mask.get(x, 0) | held
                waits[x] -= 1
                if not waits[x]:
                    todo.append(x)
        if done < len(waits):
            raise RuntimeError("the graph has a cycle")
        return pa.table({"repo_id": pa.array([s.column("repo_id")[0].as_py()] if len(s) else [], pa.int64()), "n_pairs": pa.array([n_pairs] if len(s) else [], pa.int64()), "n_differ": pa.array([n_differ] if len(s) else [], pa.int64())})

    per = rows.groupBy("repo_id", "no").cogroup(found.groupBy("repo_id", "no")).applyInArrow(count, "repo_id long, n_pairs long, n_differ long")
    return per.groupBy("repo_id").agg(F.sum("n_pairs").alias("n_pairs"), F.sum("n_differ").alias("n_differ"))
