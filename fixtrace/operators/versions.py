"""Version tags that hold a commit, affected versions, ranges and file snapshots."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.functions.text import squash


def tags_between(spans: DataFrame, tags: DataFrame, width: int = 1024) -> DataFrame:
    """``spans`` (repo_id, start, stop and more) joined to the tags whose position is in [start, stop); null stop: no end.

    A range join by pieces of the main lane: keys are (repository, piece), so neither a large repository nor a long
    span meets in one task, and a span is copied once for each piece that it reaches, not for each tag.
    """
    piece = lambda c: F.floor(F.col(c) / width).cast("long")
    ends = tags.groupBy("repo_id").agg(F.max("seq").alias("__end"))
    rows = spans.join(ends, "repo_id").withColumn("__last", F.least(F.coalesce(F.col("stop") - 1, "__end"), "__end")).where("start <= __last")
    rows = rows.withColumn("__piece", F.explode(F.sequence(piece("start"), piece("__last"))))
    marks = tags.select("repo_id", "tag_no", "tag", F.col("seq").alias("__seq"), piece("seq").alias("__piece"))
    return rows.join(marks, ["repo_id", "__piece"]).where("__seq between start and __last").drop("__piece", "__seq", "__last", "__end", "start", "stop")


def tags_containing(commits: DataFrame, tags: DataFrame) -> DataFrame:
    """(vuln_id, repo_id, tag_no, tag): tags whose history holds the commit; ``commits`` has vuln_id, repo_id, arrival.

    A tag contains the commit where the commit is an ancestor of the tagged one, which is the direction that the
    worked range of two neighbouring versions needs.
    """
    spans = commits.where("arrival is not null").select("vuln_id", "repo_id", F.col("arrival").alias("start"), F.lit(None).cast("int").alias("stop"))
    return tags_between(spans, tags).select("vuln_id", "repo_id", "tag_no", "tag")


def affected_versions(origins: DataFrame, fixes: DataFrame, tags: DataFrame, fix_mode: str = "any") -> DataFrame:
    """Tags that hold the origin but not the fix; with several fixes, ``any`` or ``all`` of them must be held.

    Tags lie on the main lane, where whatever holds a position holds all before it: the affected ones are those from
    the origin's arrival to the first (``any``) or last (``all``) fix.  A fix that never arrived fixes nothing.
    """
    came = F.min("arrival") if fix_mode == "any" else F.when(F.count("arrival") == F.count("*"), F.max("arrival"))
    fixed = fixes.groupBy("vuln_id", "repo_id").agg(came.alias("stop"))
    spans = origins.where("arrival is not null").select("vuln_id", "repo_id", F.col("arrival").alias("start")).distinct().join(fixed, ["vuln_id", "repo_id"], "left")
    return tags_between(spans, tags).select("vuln_id", "repo_id", "tag_no", "tag").distinct()


def as_ranges(affected: DataFrame) -> DataFrame:
    """Half-open runs [lo, hi) of neighbouring tag numbers."""
    island = F.col("tag_no") - F.row_number().over(W.partitionBy("vuln_id").orderBy("tag_no"))
    runs = affected.select("vuln_id", "tag_no").distinct().withColumn("island", island)
    return runs.groupBy("vuln_id", "island").agg(F.min("tag_no").alias("lo"), (F.max("tag_no") + 1).alias("hi")).drop("island")


def snapshot(files: DataFrame, tags: DataFrame, content: DataFrame) -> DataFrame:
    """The main-lane text of every slot of some files as of every tag: one row for each (file, tag, slot).

    ``files``: repo_id, file_id, which restrict the expansion to patched files; ``content``: main touches with text.
    """
    rows = content.where("lane = 'main'").join(files.select("repo_id", "file_id").distinct(), ["repo_id", "file_id"])
    until = F.lead("seq").over(W.partitionBy("file_id", "slot").orderBy("seq"))
    spans = rows.withColumns({"start": F.col("seq"), "stop": until})
    return tags_between(spans, tags).select("repo_id", "file_id", "tag_no", "slot", "commit_id", "text")


def tags_before(rows: DataFrame, tags: DataFrame, width: int = 1024) -> DataFrame:
    """``rows`` (repo_id, seq and more) with ``n_tags``: how many tags of the repository lie before the position.

    Counts per piece of the main lane are added up, and a window stands in one piece, so none holds a repository.
    """
    piece = lambda c: F.floor(F.col(c) / width).cast("long")
    per = tags.groupBy("repo_id", piece("seq").alias("__piece")).agg(F.count("*").alias("n"))
    ends = per.groupBy("repo_id").agg((F.max("__piece") + 1).alias("__end"))
    every = ends.select("repo_id", F.explode(F.sequence(F.lit(0).cast("long"), "__end")).alias("__piece")).join(per, ["repo_id", "__piece"], "left")
    ahead = F.coalesce(F.sum("n").over(W.partitionBy("repo_id").orderBy("__piece").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    ahead = every.select("repo_id", "__piece", ahead.alias("__ahead"))
    asked = rows.join(F.broadcast(ends), "repo_id").select("repo_id", F.least(piece("seq"), "__end").alias("__piece"), F.col("seq").alias("__pos"), F.lit(0).alias("__kind"), F.struct(*rows.columns).alias("__row"))
    marks = tags.select("repo_id", piece("seq").alias("__piece"), F.col("seq").alias("__pos"), F.lit(1).alias("__kind"), F.lit(None).alias("__row"))
    order = W.partitionBy("repo_id", "__piece").orderBy("__pos", "__kind").rowsBetween(W.unboundedPreceding, W.currentRow)
    met = asked.unionByName(marks).withColumn("__in", F.sum("__kind").over(order)).where("__kind = 0")
    return met.join(F.broadcast(ahead), ["repo_id", "__piece"]).select("__row.*", (F.col("__in") + F.col("__ahead")).cast("int").alias("n_tags"))


def line_spans(files: DataFrame, tags: DataFrame, content: DataFrame) -> DataFrame:
    """(repo_id, file_id, slot, line, first, last): the tags, by number, at which a slot of some files holds a squashed line.

    Tags are numbered from 1 along the main lane, as ``version_tag`` does.  A touch that no tag shows has no row.
    """
    rows = content.where("lane = 'main'").join(F.broadcast(files.select("repo_id", "file_id").distinct()), ["repo_id", "file_id"])
    rows = tags_before(rows.select("repo_id", "file_id", "slot", "seq", "text"), tags)
    total = tags.groupBy("repo_id").agg(F.count("*").cast("int").alias("__n"))
    until = F.lead("n_tags").over(W.partitionBy("repo_id", "file_id", "slot").orderBy("seq"))
    spans = rows.withColumn("last", until).join(F.broadcast(total), "repo_id").select("repo_id", "file_id", "slot", "text", (F.col("n_tags") + 1).alias("first"), F.coalesce("last", "__n").alias("last"))
    return spans.where("first <= last").select("repo_id", "file_id", "slot", squash(F.col("text")).alias("line"), "first", "last")


def line_counts(cases: DataFrame, wanted: DataFrame, spans: DataFrame, marks: tuple[str, ...]) -> DataFrame:
    """(vuln_id, repo_id, file_id, first, last, and the sum of each mark over the lines held): tags over which no sum changes.

    ``wanted``: vuln_id, file_id, line, once each, and a number for each mark.  Every tag at which the file has a
    line is in one row.  Lines meet where they are held, so a case is never paired with the tags of its repository.
    """
    met = wanted.join(spans.drop("repo_id"), ["file_id", "line"])
    w = W.partitionBy("vuln_id", "line").orderBy("first", "last")
    reach = F.max("last").over(w.rowsBetween(W.unboundedPreceding, -1))  # slots may hold one line at once
    met = met.withColumn("__run", (reach.isNull() | (F.col("first") > reach)).cast("int")).withColumn("__run", F.sum("__run").over(w.rowsBetween(W.unboundedPreceding, W.currentRow)))
    met = met.groupBy("vuln_id", "line", "__run").agg(F.min("first").alias("first"), F.max("last").alias("last"), *(F.first(m).alias(m) for m in marks))
    edge = lambda at, sign: met.select("vuln_id", at.alias("first"), *((sign * F.col(m)).alias(m) for m in marks))
    own = cases.select("vuln_id", "repo_id", "file_id").join(spans.groupBy("file_id").agg(F.min("first").alias("__from"), F.max("last").alias("__to")), "file_id")
    begin = own.select("vuln_id", F.col("__from").alias("first"), *(F.lit(0).alias(m) for m in marks))
    events = edge(F.col("first"), 1).unionByName(edge(F.col("last") + 1, -1)).unionByName(begin)
    events = events.groupBy("vuln_id", "first").agg(*(F.sum(m).alias(m) for m in marks))
    at = W.partitionBy("vuln_id").orderBy("first")
    so_far = at.rowsBetween(W.unboundedPreceding, W.currentRow)
    rows = events.select("vuln_id", "first", F.lead("first").over(at).alias("__next"), *(F.sum(m).over(so_far).alias(m) for m in marks)).join(own, "vuln_id")
    return rows.select("vuln_id", "repo_id", "file_id", "first", F.coalesce(F.col("__next") - 1, "__to").alias("last"), *marks).where("first <= last")


def each_tag(ranges: DataFrame) -> DataFrame:
    """A row for each tag number from ``first`` to ``last``."""
    return ranges.withColumn("tag_no", F.explode(F.sequence(F.col("first").cast("int"), F.col("last").cast("int")))).drop("first", "last")


def file_lines(spans: DataFrame, asked: DataFrame | None = None, width: int = 16) -> DataFrame:
    """(repo_id, file_id, tag_no, lines): a file at a tag as a map from slot to line; once for a file, however many cases patch it.

    ``asked``: (file_id, tag_no), or all tags that show the file.  Files are cut into pieces of ``width`` tags.
    """
    piece = lambda c: F.floor(c / width).cast("int")
    spread = spans.withColumn("__piece", F.explode(F.sequence(piece(F.col("first")), piece(F.col("last")))))
    held = spread.groupBy("repo_id", "file_id", "__piece").agg(F.collect_list(F.struct("slot", "line", "first", "last")).alias("held"))
    if asked is None:
        held = held.withColumn("tags", F.sequence(F.col("__piece") * width, F.col("__piece") * width + width - 1))
    else:
        held = held.join(asked.groupBy("file_id", piece(F.col("tag_no")).alias("__piece")).agg(F.collect_set("tag_no").alias("tags")), ["file_id", "__piece"])
    rows = held.select("repo_id", "file_id", "held", F.explode("tags").alias("tag_no"))
    now = F.filter("held", lambda x: F.col("tag_no").between(x["first"], x["last"]))
    rows = rows.select("repo_id", "file_id", "tag_no", F.transform(now, lambda x: F.struct(x["slot"].alias("slot"), x["line"].alias("line"))).alias("now"))
    return rows.where(F.size("now") > 0).select("repo_id", "file_id", F.col("tag_no").cast("int").alias("tag_no"), F.map_from_entries("now").alias("lines"))
