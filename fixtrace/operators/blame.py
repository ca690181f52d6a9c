"""Blame: the last earlier touch of a statement slot along each parent path."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

_SELF = ["repo_id", "file_id", "slot", "commit_id", "seq", "block", "lane", "fork", "mseq"]


def predecessors(touches: DataFrame) -> DataFrame:
    """(file_id, slot, commit_id, pred_commit_id, path_no): the touches a touch was made upon, none held by another.

    Per (file, slot) the events stand in main order: touches of the main lane, branches arriving where they merge,
    and the questions.  A question sees the last main touch and the branches that arrived after it; of these, one
    that another holds is dropped.  Inside a branch the branch's own earlier touch wins.
    """
    t = touches.select(*_SELF)
    own = F.lag("commit_id").over(W.partitionBy("file_id", "slot", "block").orderBy("seq"))
    branch = t.where("lane = 'feature'").withColumn("own", own)
    inside = branch.where("own is not null").select("file_id", "slot", "commit_id", F.col("own").alias("pred_commit_id"), F.lit(0).alias("path_no"))
    last = F.row_number().over(W.partitionBy("file_id", "slot", "block").orderBy(F.desc("seq")))
    tips = t.where("lane = 'feature' and mseq is not null").withColumn("k", last).where("k = 1")
    note = F.struct("commit_id", "seq", F.col("fork").alias("at_fork"), F.col("mseq").alias("at"))
    none = F.lit(None)
    events = (
        t.where("lane = 'main'").select("file_id", "slot", F.col("seq").alias("pos"), F.lit(2).alias("kind"), "commit_id", F.struct("commit_id", "seq").alias("main"), none.alias("tip"))
        .unionByName(tips.select("file_id", "slot", F.col("mseq").alias("pos"), F.lit(0).alias("kind"), "commit_id", none.alias("main"), note.alias("tip")))
        .unionByName(t.where("lane = 'main'").select("file_id", "slot", F.col("seq").alias("pos"), F.lit(1).alias("kind"), "commit_id", none.alias("main"), none.alias("tip")))
        .unionByName(branch.where("own is null").select("file_id", "slot", F.col("fork").alias("pos"), F.lit(3).alias("kind"), "commit_id", none.alias("main"), none.alias("tip")))
    )
    order = W.partitionBy("file_id", "slot").orderBy("pos", "kind", "commit_id")
    so_far = order.rowsBetween(W.unboundedPreceding, W.currentRow)
    marked = events.withColumns({"m": F.last("main", ignorenulls=True).over(so_far), "run": F.count("main").over(so_far)})
    in_run = W.partitionBy("file_id", "slot", "run").orderBy("pos", "kind", "commit_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    asked = marked.withColumn("tips", F.collect_list("tip").over(in_run)).where(F.col("kind").isin(1, 3))
    free = F.filter("tips", lambda f: ~F.exists("tips", lambda g: (g["commit_id"] != f["commit_id"]) & (f["at"] <= g["at_fork"])))
    main_stays = F.col("m").isNotNull() & ~F.exists("tips", lambda g: F.col("m.seq") <= g["at_fork"])
    base = F.when(main_stays, F.array(F.col("m.commit_id"))).otherwise(F.array().cast("array<bigint>"))
    found = F.concat(base, F.transform(free, lambda f: f["commit_id"]))
    outside = asked.select("file_id", "slot", "commit_id", F.posexplode(found).alias("path_no", "pred_commit_id"))
    return inside.unionByName(outside.select("file_id", "slot", "commit_id", "pred_commit_id", "path_no"))


def main_path(touches: DataFrame) -> DataFrame:
    """Each touch with ``pred0``, the touch its text was derived from along first parents, and path counts.

    n0 .. n3 count the edits of each kind on that path up to and with the touch; ``rewritten_by`` is the commit that
    last rewrote the slot on it (the first touch if none did).  The touches of a slot are shuffled
    once and stand in one order: main ones where they are, those of a branch where it forks.
    """
    kinds, main = range(4), F.col("lane") == "main"
    line, branch = _lines()
    upto = line.rowsBetween(W.unboundedPreceding, W.currentRow)
    known = lambda c, w: F.last(F.when(main, c), ignorenulls=True).over(w)
    kind = lambda k: (F.col("edit_kind") == k).cast("int")
    rewrite = F.when(F.col("edit_kind") == 2, F.col("commit_id"))
    rows = touches.withColumns({f"__n{k}": F.sum(F.when(main, kind(k))).over(upto) for k in kinds} | {
        "__base": known(F.col("commit_id"), line.rowsBetween(W.unboundedPreceding, -1)),
        "__rewritten": F.coalesce(known(rewrite, upto), F.first(F.when(main, F.col("commit_id")), ignorenulls=True).over(upto)),
    })
    b = branch.rowsBetween(W.unboundedPreceding, W.currentRow)
    first = F.when(F.col("__base").isNull(), F.first("commit_id").over(b))
    found = rows.withColumns({f"n{k}": F.when(main, F.col(f"__n{k}")).otherwise(F.sum(kind(k)).over(b) + F.coalesce(f"__n{k}", F.lit(0))) for k in kinds} | {
        "rewritten_by": F.when(main, F.col("__rewritten")).otherwise(F.coalesce(F.last(rewrite, ignorenulls=True).over(b), "__rewritten", first)),
        "pred0": F.when(main, F.col("__base")).otherwise(F.coalesce(F.lag("commit_id").over(branch), "__base")),
    })
    return found.drop("__base", "__rewritten", *(f"__n{k}" for k in kinds))


def _lines():
    """Windows over the touches of a slot: main ones in order, each branch's behind the main touch it forks from; and over each branch."""
    main = F.col("lane") == "main"
    line = W.partitionBy("file_id", "slot").orderBy(F.when(main, F.col("seq")).otherwise(F.col("fork")), F.when(main, 0).otherwise(1), "seq")
    return line, W.partitionBy("file_id", "slot", "lane", "block").orderBy("seq")


def with_before(rows: DataFrame, *names: str) -> DataFrame:
    """``rows`` of ``main_path`` with the columns ``names`` of ``pred0`` as ``pre_`` ones: carried on along the slot, not joined."""
    line, branch = _lines()
    held = F.struct(*names)
    own = rows.withColumn("__own", F.when(F.col("lane") != "main", F.lag(held).over(branch)))
    main = F.last(F.when(F.col("lane") == "main", held), ignorenulls=True).over(line.rowsBetween(W.unboundedPreceding, -1))
    found = own.withColumn("__met", F.coalesce("__own", main))
    return found.withColumns({f"pre_{c}": F.col(f"__met.{c}") for c in names}).drop("__own", "__met")
