"""Backtracking: from the statements of a fix to the commit that introduced them.

The loop of comparing, deciding and going to the parent becomes one set of adjacent comparisons that all cases
share, then per statement the latest touch where it is lost, then per case a running sum of lost weight.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from fixtrace.functions.store import settle
from fixtrace.functions.text import digest
from fixtrace.operators.asof import inside, last_before

PLACE = ["file_id", "slot", "commit_id", "seq", "block", "lane", "fork", "mseq"]


def compared_touches(content: DataFrame, flags: DataFrame | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Places of main-path touches with ``lost``: whether the statement was not there, by similarity, before the touch.

    ``content``: touches with ``text`` and the text before as ``pre``, and ``similar`` where it is known already;
    ``flags``: (pre, post, similar and others) of the distinct texts for which it is not, or their ``digest`` as
    ``pair``.  Also ``kind``, 0 without a text before, 1 with the same and 2 with another, the other columns of
    ``flags``, and those of ``content`` in ``keep``.
    """
    kind = F.when(F.col("pre").isNull(), 0).when(F.col("pre") == F.col("text"), 1).when(F.col("text").isNotNull(), 2)
    held = [*keep, *(c for c in ("sim_a", "similar") if c in content.columns)]
    rows = content.select(*PLACE, kind.alias("kind"), "pre", "text", *held)
    if flags is not None:
        told = flags.select((F.col("pair") if "pair" in flags.columns else digest("pre", "post")).alias("__pair"), *(c for c in flags.columns if c not in ("pre", "post", "pair")))
        asked = F.coalesce(F.col("kind") == 2, F.lit(False)) & (F.col("similar").isNull() if "similar" in rows.columns else F.lit(True))
        rows, left = rows.where(~asked), rows.where(asked).select(*PLACE, "kind", *(c for c in held if c not in flags.columns), digest("pre", "text").alias("__pair"))
        rows = rows.unionByName(left.join(told, "__pair", "left").drop("__pair"), allowMissingColumns=True)
    return rows.drop("pre", "text").withColumn("lost", (F.col("kind") == 0) | ~((F.col("kind") == 1) | F.coalesce("similar", F.lit(False))))


def statement_stops(stmts: DataFrame, compared: DataFrame, merges: str = "earliest", by: tuple[str, ...] = ()) -> DataFrame:
    """(vuln_id, slot, stop_commit, stop_seq): where the walk back from the fix loses each statement.

    ``by``: columns of ``compared`` that number separate walks, as the rows of a sweep; they are kept.

    On the main lane that is the last lost touch before the fix.  With ``merges='earliest'`` a branch merged after
    it and before the fix is walked as well: to its own last lost touch, else to the main lane's last lost touch
    at its fork; the earliest stop counts.  ``first_parent`` follows the main lane only.
    """
    s = stmts.select("vuln_id", "slot", "file_id", "fix_seq")
    lost = compared.where("lost").select(*by, "file_id", "slot", "lane", "block", "seq", "commit_id", "fork", "mseq")
    note = F.struct("seq", "commit_id")
    lost_main, key = lost.where("lane = 'main'"), [*by, "file_id", "slot"]
    asked = s.crossJoin(F.broadcast(compared.select(*by).distinct())) if by else s
    on_main = last_before(asked.distinct(), lost_main, note, key).withColumnRenamed("met", "stop")
    if merges == "earliest":
        branches = compared.where("lane = 'feature' and mseq is not null").groupBy(*by, "file_id", "slot", "block").agg(
            F.first("fork").alias("at_fork"), F.first("mseq").alias("at"), F.max(F.when(F.col("lost"), note)).alias("own")
        )
        reached = inside(on_main.withColumn("stop_seq", F.col("stop.seq")), branches, key, "stop_seq", "fix_seq", "at").drop("stop_seq")
        held = reached.where("own is not null").select(*by, "vuln_id", "slot", F.col("own").alias("stop"))
        outside = reached.where("own is null").select(*by, "vuln_id", "slot", "file_id", "at_fork")
        forked = last_before(outside, lost_main, note, key, "at_fork", inclusive=True).select(*by, "vuln_id", "slot", F.col("met").alias("stop"))
        every = on_main.select(*by, "vuln_id", "slot", "stop").unionByName(held).unionByName(forked)
        met = reached.select(*by, "vuln_id").distinct().withColumn("met_merge", F.lit(True))
        on_main = every.groupBy(*by, "vuln_id", "slot").agg(F.min("stop").alias("stop")).join(met, [*by, "vuln_id"], "left")
    else:
        on_main = on_main.withColumn("met_merge", F.lit(False))
    return on_main.select(*by, "vuln_id", "slot", F.col("stop.commit_id").alias("stop_commit"), F.col("stop.seq").alias("stop_seq"), F.coalesce("met_merge", F.lit(False)).alias("met_merge"))


def swept_stops(stmts: DataFrame, levels: DataFrame, grid: list[tuple[int, int]], width: int = 256, straight: tuple[int, ...] = ()) -> DataFrame:
    """(k, vuln_id, slot, stop_commit, stop_seq): ``statement_stops`` over merges for each pair (line, tree) of thresholds in ``grid``.

    ``levels``: touches with both similarities in permille as ``a`` and ``b``, -1 where there is none, 1001 as ``a``
    of equal texts.  A touch is lost where both are below.  The touches are sorted once, with a column for each pair
    instead of a copy of the rows.  Of the branches merged after a stop only those that forked before it can stop earlier.
    ``straight``: places in ``grid`` whose walks follow the main lane only.
    """
    lost = [(F.col("a") < x) & (F.col("b") < y) for x, y in grid]
    most = [max((t[i] for t in grid), default=0) for i in (0, 1)]
    return many_stops(stmts, levels, lost, (F.col("a") < most[0]) & (F.col("b") < most[1]), ("a", "b"), width, straight)


def many_stops(stmts: DataFrame, levels: DataFrame, lost: list[Column], some: Column, marks: tuple[str, ...], width: int = 256, straight: tuple[int, ...] = ()) -> DataFrame:
    """``swept_stops`` for walks that each call other touches lost: ``lost`` tells by the int columns ``marks``, ``some`` is true where any of it is."""
    note = F.struct("seq", "commit_id")
    none = F.lit(None)
    main = levels.where("lane = 'main'").where(some)
    shown = main.select("file_id", "slot", F.col("seq").alias("pos"), F.lit(1).alias("kind"), "seq", "commit_id", *marks, none.cast("long").alias("vuln_id"), none.cast("int").alias("block"))
    blank = [none.cast("int").alias("seq"), none.cast("long").alias("commit_id"), *(none.cast("int").alias(c) for c in marks)]
    asked = stmts.select("file_id", "slot", F.col("fix_seq").alias("pos"), F.lit(0).alias("kind"), *blank, F.col("vuln_id").cast("long").alias("vuln_id"), none.cast("int").alias("block")).distinct()
    feature = levels.where("lane = 'feature' and mseq is not null")
    forks = feature.select("file_id", "slot", F.col("fork").alias("pos"), F.lit(2).alias("kind"), *blank, none.cast("long").alias("vuln_id"), "block").distinct()
    events = shown.unionByName(asked).unionByName(forks).repartition("file_id", "slot").sortWithinPartitions("file_id", "slot", "pos", "kind")
    order = W.partitionBy("file_id", "slot").orderBy("pos", "kind").rowsBetween(W.unboundedPreceding, W.currentRow)
    last = [F.last(F.when((F.col("kind") == 1) & gone, note), ignorenulls=True).over(order).alias(f"m{k}") for k, gone in enumerate(lost)]
    met = events.select("file_id", "slot", "pos", "kind", "vuln_id", "block", *last).where("kind <> 1")
    met = settle(met.select("file_id", "slot", "pos", "kind", "vuln_id", "block", F.array(*(F.col(f"m{k}") for k in range(len(lost)))).alias("met")))
    on_main = met.where("kind = 0").select("vuln_id", "file_id", "slot", F.col("pos").alias("fix_seq"), F.posexplode("met").alias("k", "stop")).where("stop is not null")
    own = feature.groupBy("file_id", "slot", "block").agg(F.first("fork").alias("at_fork"), F.first("mseq").alias("at"), F.array(*(F.max(F.when(gone, note)) for gone in lost)).alias("own"))
    held = own.join(met.where("kind = 2").select("file_id", "slot", "block", "met"), ["file_id", "slot", "block"])
    held = held.select("file_id", "slot", "at_fork", "at", F.zip_with("own", "met", lambda x, y: F.coalesce(x, y)).alias("ends"))
    piece = lambda c: F.floor(F.col(c) / width).cast("long")
    spread = held.where("at_fork < at").withColumn("__piece", F.explode(F.sequence(piece("at_fork"), piece("at"))))
    crossed = on_main.where(~F.col("k").isin(*straight)).withColumn("__piece", piece("stop.seq")).join(spread, ["file_id", "slot", "__piece"]).where("at_fork < stop.seq and at > stop.seq and at <= fix_seq")
    earlier = crossed.select("k", "vuln_id", "slot", F.get("ends", F.col("k")).alias("stop")).where("stop is not null")
    every = on_main.select("k", "vuln_id", "slot", "stop").unionByName(earlier).groupBy("k", "vuln_id", "slot").agg(F.min("stop").alias("stop"))
    return every.select("k", "vuln_id", "slot", F.col("stop.commit_id").alias("stop_commit"), F.col("stop.seq").alias("stop_seq"))


def cumulative(stmts: DataFrame, stops: DataFrame, theta: int | Column = 700, by: tuple[str, ...] = ()) -> DataFrame:
    """(vuln_id, origin_commit_id, origin_seq, score): the latest commit at which the kept weight falls below theta.

    A statement once lost stays lost, so the score only falls going back and one running sum replaces the loop.
    Statements without any history count as lost only after all others.  ``by``: columns of both inputs that number
    separate walks; ``theta`` may be one of them.
    """
    held = stmts.select(*by, "vuln_id", "slot", "weight").join(stops, [*by, "vuln_id", "slot"])
    total = stmts.join(stops, [*by, "vuln_id", "slot"], "left_semi").groupBy(*by, "vuln_id").agg(F.sum("weight").alias("total"))
    per = held.groupBy(*by, "vuln_id", "stop_commit", "stop_seq").agg(F.sum("weight").alias("w")).join(total, [*by, "vuln_id"])
    gone = F.sum("w").over(W.partitionBy(*by, "vuln_id").orderBy(F.desc("stop_seq"), F.desc("stop_commit")).rowsBetween(W.unboundedPreceding, W.currentRow))
    scored = per.withColumn("score", 1 - gone / F.col("total")).where(F.round(F.col("score") * 1000) < theta)
    best = F.max_by(F.struct("stop_commit", "stop_seq", "score"), F.struct("stop_seq", "stop_commit")).alias("x")
    return scored.groupBy(*by, "vuln_id").agg(best).select(*by, "vuln_id", F.col("x.stop_commit").alias("origin_commit_id"), F.col("x.stop_seq").alias("origin_seq"), "x.score")


def anchored_stops(stmts: DataFrame, compared: DataFrame, flags: DataFrame) -> DataFrame:
    """As ``statement_stops`` along first parents, each text before a touch held against the text at the fix.

    ``flags``: (pre, post, similar) with the statement's text as ``post``.  No chain of small edits can drift away
    from the patched statement, but one that was often edited is lost early.
    """
    main = compared.where("lane = 'main'").select("file_id", "slot", "seq", "commit_id", "pre")
    rows = stmts.select("vuln_id", "slot", "file_id", "fix_seq", F.col("text").alias("post")).join(main, ["file_id", "slot"]).where("seq < fix_seq")
    rows = rows.join(flags, ["pre", "post"], "left")
    lost = F.col("pre").isNull() | ~((F.col("pre") == F.col("post")) | F.coalesce("similar", F.lit(False)))
    stops = rows.where(lost).groupBy("vuln_id", "slot").agg(F.max(F.struct("seq", "commit_id")).alias("stop"))
    return stops.select("vuln_id", "slot", F.col("stop.commit_id").alias("stop_commit"), F.col("stop.seq").alias("stop_seq"), F.lit(False).alias("met_merge"))


def anchored_walk(stmts: DataFrame, compared: DataFrame, compare: Callable[[DataFrame], DataFrame], first: int = 8, grow: int = 4) -> DataFrame:
    """As ``anchored_stops``, looking back from the fix in stretches of ``first`` touches, then ``grow`` times as many, until each is lost.

    ``compare``: (pre, post) to (pre, post, similar).  The last lost touch is all that counts, so a statement that is
    lost is not compared further back; the first touch of a slot has nothing before it and is always lost.
    """
    main = compared.where("lane = 'main'").select("file_id", "slot", "seq", "commit_id", "pre")
    main = settle(main.withColumn("idx", F.row_number().over(W.partitionBy("file_id", "slot").orderBy("seq"))))
    rows = stmts.select("vuln_id", "slot", "file_id", "fix_seq", F.col("text").alias("post"))
    asked = settle(last_before(rows, main, F.struct("idx"), ["file_id", "slot"]).select("vuln_id", "slot", "file_id", "post", F.col("met.idx").alias("upto")))
    out, n = None, first
    while out is None or asked.limit(1).count():
        tried = asked.withColumn("idx", F.explode(F.sequence(F.greatest(F.col("upto") - n + 1, F.lit(1)), F.col("upto"))))
        tried = settle(tried.join(main, ["file_id", "slot", "idx"]))
        flags = compare(tried.select("pre", "post"))
        gone = F.col("pre").isNull() | ~((F.col("pre") == F.col("post")) | F.coalesce("similar", F.lit(False)))
        found = tried.join(flags, ["pre", "post"], "left").where(gone).groupBy("vuln_id", "slot").agg(F.max(F.struct("seq", "commit_id")).alias("stop"))
        found = settle(found)
        out = found if out is None else out.unionByName(found)
        asked = settle(asked.join(found, ["vuln_id", "slot"], "left_anti").withColumn("upto", F.col("upto") - n).where("upto >= 1"))
        n *= grow
    return out.select("vuln_id", "slot", F.col("stop.commit_id").alias("stop_commit"), F.col("stop.seq").alias("stop_seq"), F.lit(False).alias("met_merge"))


def per_commit(stmts: DataFrame, compared: DataFrame, theta: int = 700, untouched: str = "kept") -> DataFrame:
    """The latest commit before the fix whose own score is below theta.

    Statements that a commit leaves alone count as kept, or with ``untouched='excluded'`` not at all.
    """
    if untouched not in ("kept", "excluded"):
        raise ValueError(untouched)
    return per_commit_both(stmts, compared, theta).where(F.col("untouched") == untouched).drop("untouched")


def per_commit_both(stmts: DataFrame, compared: DataFrame, theta: int = 700, stretch: int = 256) -> DataFrame:
    """``per_commit`` both ways, told apart by ``untouched``.

    A task holds the main touches of a file and looks back from each of its fixes in growing stretches, so a fix is
    not paired with all touches before it.
    """
    kinds = dict(stmts.dtypes) | {"commit_id": "bigint"}
    number = T._parse_datatype_string(kinds["vuln_id"])
    fields = [("untouched", T.StringType()), ("vuln_id", number), ("origin_commit_id", T.LongType()), ("origin_seq", T.IntegerType()), ("score", T.DoubleType()), ("origin_kind", T.StringType())]
    schema = T.StructType([T.StructField(*f) for f in fields])
    arrow = to_arrow_schema(schema)
    file = F.col("file_id").cast("long").alias("file_id")
    slot = F.col("slot").cast("long").alias("slot")
    touches = compared.where("lane = 'main'").select(file, slot, F.col("seq").cast("long").alias("seq"), F.col("commit_id").cast("long").alias("commit_id"), "lost")
    asked = stmts.select(file, slot, "vuln_id", F.col("fix_seq").cast("long").alias("fix_seq"), F.col("weight").cast("double").alias("weight"))

    def run(t: pa.Table, s: pa.Table) -> pa.Table:
        out: list[list] = [[] for _ in fields]
        if not len(t) or not len(s):
            return pa.table([pa.array(x, f.type) for x, f in zip(out, arrow, strict=True)], schema=arrow)
        slots, col = np.unique(s.column("slot").to_numpy(), return_inverse=True)
        seq, commit, place, lost = (t.column(c).to_numpy() for c in ("seq", "commit_id", "slot", "lost"))
        held = np.isin(place, slots)
        seq, commit, place, lost = seq[held], commit[held], np.searchsorted(slots, place[held]), lost[held]
        # a row for each commit of the file, in order, and a column for each slot asked for
        both, row = np.unique(np.stack([seq, commit], axis=1), axis=0, return_inverse=True)
        row = row.ravel()
        seqs, n, k = both[:, 0], len(both), len(slots)
        met, gone, begin = np.zeros((n, k), bool), np.zeros((n, k), bool), np.full(k, n)
        met[row, place] = True
        gone[row[lost], place[lost]] = True
        np.minimum.at(begin, place, row)
        order = np.argsort(s.column("vuln_id").to_numpy(), kind="stable")
        no, fix, weight, col = s.column("vuln_id").to_numpy()[order], s.column("fix_seq").to_numpy()[order], s.column("weight").to_numpy()[order], col.ravel()[order]
        starts = np.flatnonzero(np.r_[True, no[1:] != no[:-1]])
        for a, b in zip(starts, np.r_[starts[1:], len(no)], strict=True):
            end = int(np.searchsorted(seqs, fix[a]))
            known = begin[col[a:b]] < end
            mine, w = col[a:b][known], weight[a:b][known]
            if not len(mine):
                continue
            total, first = w.sum(), int(begin[mine].min())

            def scores(lo: int, hi: int, kind: str):
                left = gone[lo:hi, mine] @ w
                own = met[lo:hi, mine]
                whole = np.full(hi - lo, total) if kind == "kept" else own @ w
                some = own.any(axis=1)
                return some, 1 - np.divide(left, whole, out=np.zeros(hi - lo), where=some)

            for kind in ("kept", "excluded"):
                hi, step, at = end, stretch, -1
                while hi > first and at < 0:
                    lo = max(first, hi - step)
                    some, score = scores(lo, hi, kind)
                    # a rounded number is below a whole one where the number is below that less a half
                    below = np.flatnonzero(some & (score * 1000 < theta - 0.5))
                    if len(below):
                        at, value = lo + int(below[-1]), float(score[below[-1]])
                    hi, step = lo, step * 4
                if at < 0:
                    at, value, how = first, float(scores(first, first + 1, kind)[1][0]), "initial"
                else:
                    how = "found"
                for x, v in zip(out, (kind, no[a].item(), int(both[at, 1]), int(seqs[at]), value, how), strict=True):
                    x.append(v)
        return pa.table([pa.array(x, f.type) for x, f in zip(out, arrow, strict=True)], schema=arrow)

    return touches.groupBy("file_id").cogroup(asked.groupBy("file_id")).applyInArrow(run, schema)


def walk(stmts: DataFrame, preds: DataFrame, compared: DataFrame) -> DataFrame:
    """Every comparison that a walk over all parent paths makes, and in which round back it is made first.

    (vuln_id, slot, file_id, commit_id, pred_commit_id, round); a path ends where its statement is lost.  For
    validation and for counting comparisons.  A walk never leaves its slot of a file, so a task holds one slot and
    takes all steps of its statements; the number of rounds costs no pass over the touches.
    """
    kinds = dict(preds.dtypes) | {"vuln_id": dict(stmts.dtypes)["vuln_id"]}
    lost = compared.where("lost").select("file_id", "slot", "commit_id", F.lit(None).cast("long").alias("pred_commit_id"))
    rows = preds.select("file_id", "slot", "commit_id", "pred_commit_id").unionByName(lost)
    own = lambda df: [F.col(c).cast(kinds[c]).alias(c) for c in ("file_id", "slot")]
    rows = rows.select(*own(rows), "commit_id", "pred_commit_id")
    asked = stmts.select(*own(stmts), F.col("vuln_id").alias("vuln_id"), F.col("fix_commit_id").alias("start")).distinct()
    schema = T.StructType([T.StructField(c, T._parse_datatype_string(k)) for c, k in (("vuln_id", kinds["vuln_id"]), ("slot", kinds["slot"]), ("file_id", kinds["file_id"]), ("commit_id", "bigint"), ("pred_commit_id", "bigint"), ("round", "int"))])
    arrow = to_arrow_schema(schema)

    def run(t: pa.Table, s: pa.Table) -> pa.Table:
        out: list[list] = [[], [], [], []]
        after: dict = {}
        gone = set()
        if len(s):
            for c, p in zip(t.column("commit_id").to_pylist(), t.column("pred_commit_id").to_pylist(), strict=True):
                if p is None:
                    gone.add(c)
                else:
                    after.setdefault(c, set()).add(p)
        for no, start in zip(s.column("vuln_id").to_pylist(), s.column("start").to_pylist(), strict=True):
            seen, now, k = {start}, [start], 0
            while now:
                ahead = []
                for c in now:
                    if k and c in gone:
                        continue
                    for p in after.get(c, ()):
                        for column, v in zip(out, (no, c, p, k), strict=True):
                            column.append(v)
                        if p not in seen:
                            seen.add(p)
                            ahead.append(p)
                now, k = ahead, k + 1
        n = len(out[0])
        slot, file = (pa.array([s.column(c)[0].as_py()] * n if n else [], arrow.field(c).type) for c in ("slot", "file_id"))
        return pa.table([pa.array(out[0], arrow.field("vuln_id").type), slot, file, *(pa.array(x, pa.int64()) for x in out[1:3]), pa.array(out[3], pa.int32())], schema=arrow)

    return rows.groupBy("file_id", "slot").cogroup(asked.groupBy("file_id", "slot")).applyInArrow(run, schema)


def exact_stops(stmts: DataFrame, preds: DataFrame, compared: DataFrame) -> DataFrame:
    """As ``statement_stops``, by walking every parent path step by step: the earliest lost touch that any path meets."""
    steps = walk(stmts, preds, compared)
    reached = steps.select("vuln_id", "slot", "file_id", F.col("pred_commit_id").alias("commit_id")).distinct()
    lost = compared.where("lost").select("file_id", "slot", "commit_id", "seq")
    found = reached.join(lost, ["file_id", "slot", "commit_id"]).groupBy("vuln_id", "slot").agg(F.min(F.struct("seq", "commit_id")).alias("stop"))
    return found.select("vuln_id", "slot", F.col("stop.commit_id").alias("stop_commit"), F.col("stop.seq").alias("stop_seq"))
