"""Line deduplication over levelled sorted runs of line hashes.

A run is a pair of tables sorted by hash: ``counts`` (h1, h2, n_docs, last_doc), in how many documents of its batches a
line key occurs and the largest ``doc_id`` that holds it, and ``keys`` (h1, h2), those of its keys that no older run
holds.  ``LineRuns.ingest`` aggregates a new batch, merge-anti-joins it with the keys of the runs (both sides sorted by
hash) and adds what is left as keys of its own, so over all runs a key stands once.  The batch becomes a run of level 0;
``fanout`` runs of a level are compacted into one of the next.  Counts add up and maxima combine, so the verdict over
all runs does not depend on how rows were batched or when runs were compacted.  ``drop_lines`` adds a batch for each
doubling of the keys beyond ``batch_keys``; every batch reads the keys held so far, so this work grows as n log n.

A key is the line stripped of ``[\\x20\\x09-\\x0D]`` at both ends, A-Z lower-cased, told by two 64-bit hashes.

Defined results: a null or empty text is one empty line; every row counts as one document, and rows that repeat a
``doc_id`` share the fate of that id; an empty table gives no rows; long texts are handled whole, and a line is
looked up among its document's lost ones by bisection.  Only ``doc_id`` and ``text`` are read; ``drop_lines``
replaces ``text`` and any columns called n_lines or n_dropped, other columns pass through it untouched.
"""

from __future__ import annotations

import functools
import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.llm.common import BLANKS, fold_lower, remove, settle, shared_dir, table


@dataclass(frozen=True)
class Params:
    """``batches`` is the least number of batches."""

    min_chars: int = 40
    min_docs: int = 5
    batches: int = 4
    fanout: int = 4
    batch_keys: int = 2**18


def batch_count(n_keys: int, params: Params) -> int:
    return params.batches + (n_keys // params.batch_keys).bit_length()


def _split(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def line_key(line: Column) -> Column:
    return fold_lower(F.btrim(line, F.lit(BLANKS)))


def _hashes(key: Column) -> Column:
    """Two independent 64-bit hashes of a key."""
    return F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(7), key).alias("h2"))


def long_keys(docs: DataFrame, params: Params) -> DataFrame:
    """(doc_id, h1, h2) once for each document and line key of at least ``min_chars`` code points."""
    keys = F.array_distinct(F.transform(F.filter(_split(F.col("text")), lambda x: F.char_length(x) >= params.min_chars), line_key))
    rows = docs.select("doc_id", F.explode(keys).alias("key")).where(F.char_length("key") >= params.min_chars)
    return rows.select("doc_id", _hashes(F.col("key")).alias("h")).select("doc_id", "h.h1", "h.h2")


COUNTS, KEYS = "h1 bigint, h2 bigint, n_docs bigint, last_doc bigint", "h1 bigint, h2 bigint"


class LineRuns:
    """The runs under one folder of the shared store; ``drop`` removes them."""

    def __init__(self, spark: SparkSession, folder: str, fanout: int = 4):
        self.spark, self.folder, self.fanout = spark, folder, fanout
        self.levels: list[list[str]] = []
        self.written = 0

    def _new(self) -> str:
        self.written += 1
        return f"{self.folder}/run{self.written}"

    def _add(self, path: str, level: int) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)

    def paths(self) -> list[str]:
        return [p for level in self.levels for p in level]

    def counts(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(COUNTS).parquet(*(f"{p}/counts" for p in paths))

    def keys(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(KEYS).parquet(*(f"{p}/keys" for p in paths))

    @staticmethod
    def _folded(counts: DataFrame) -> DataFrame:
        return counts.groupBy("h1", "h2").agg(F.sum("n_docs").alias("n_docs"), F.max("last_doc").alias("last_doc"))

    def merged(self) -> DataFrame:
        """One row for each key over all runs."""
        paths = self.paths()
        if not paths:
            return self.spark.createDataFrame([], COUNTS)
        return self.counts(paths) if len(paths) == 1 else self._folded(self.counts(paths))

    def novel(self, keys: DataFrame) -> DataFrame:
        """Rows of ``keys`` whose hash no run holds: a merge anti-join of sorted sides."""
        return keys.join(self.keys(self.paths()).hint("merge"), ["h1", "h2"], "left_anti") if self.paths() else keys

    def ingest(self, keys: DataFrame) -> None:
        """Add a batch of (doc_id, h1, h2) as a run: its counts, and the keys that it adds; compact full levels."""
        path = self._new()
        batch = keys.groupBy("h1", "h2").agg(F.count("*").alias("n_docs"), F.max("doc_id").alias("last_doc"))
        batch.sortWithinPartitions("h1", "h2").write.parquet(f"{path}/counts")
        self.novel(self.counts([path]).select("h1", "h2")).sortWithinPartitions("h1", "h2").write.parquet(f"{path}/keys")
        self._add(path, 0)
        level = 0
        while len(self.levels[level]) >= self.fanout:
            full, self.levels[level] = self.levels[level], []
            path = self._new()
            self._folded(self.counts(full)).sortWithinPartitions("h1", "h2").write.parquet(f"{path}/counts")
            self.keys(full).sortWithinPartitions("h1", "h2").write.parquet(f"{path}/keys")
            self._add(path, level + 1)
            for old in full:
                remove(self.spark, old)
            level += 1

    def drop(self) -> None:
        remove(self.spark, self.folder)
        self.levels = []


SHORT = 16


def _holds(found: Column, wanted: Column) -> Column:
    """Whether a sorted array holds a value: by bisection, but a short array is looked through."""
    size = F.size(found)
    rounds = F.ceil(F.log2(size + 1)).cast("int")

    def halve(now: Column, _: Column) -> Column:
        middle = F.shiftright(now["lo"] + now["hi"], 1)
        below = F.get(found, middle) < wanted
        return F.struct(F.when(below, middle + 1).otherwise(now["lo"]).alias("lo"), F.when(below, now["hi"]).otherwise(middle).alias("hi"))

    start = F.struct(F.lit(0).alias("lo"), size.alias("hi"))
    at = F.aggregate(F.sequence(F.lit(1), F.greatest(rounds, F.lit(1))), start, lambda now, k: F.when(now["lo"] < now["hi"], halve(now, k)).otherwise(now), lambda now: now["lo"])
    return F.when(size <= SHORT, F.array_contains(found, wanted)).otherwise(F.coalesce(F.get(found, at) == wanted, F.lit(False)))


def drop_lines(docs: DataFrame, params: Params = Params()) -> DataFrame:
    """``docs`` with ``text`` freed of shared lines, and n_lines, n_dropped."""
    spark = docs.sparkSession
    keys = settle(long_keys(docs.select("doc_id", "text"), params))
    runs = LineRuns(spark, f"{shared_dir(spark)}/line-runs-{uuid.uuid4().hex}", params.fanout)
    try:
        batches = batch_count(keys.count(), params)
        for k in range(batches):
            runs.ingest(keys.where(F.pmod(F.xxhash64("doc_id"), F.lit(batches)) == k))
        shared = runs.merged().where(F.col("n_docs") >= params.min_docs).select("h1", "h2", "last_doc")
        lost = keys.join(shared, ["h1", "h2"]).where(F.col("doc_id") != F.col("last_doc"))
        lost = settle(lost.groupBy("doc_id").agg(F.array_sort(F.collect_set(F.struct("h1", "h2"))).alias("__lost")))
    finally:
        runs.drop()
    joined = docs.join(lost.withColumnRenamed("doc_id", "__doc"), F.col("doc_id").eqNullSafe(F.col("__doc")), "left").drop("__doc")
    lines = _split(F.col("text"))

    def stays(line: Column) -> Column:
        key = line_key(line)
        return (F.char_length(key) < params.min_chars) | ~_holds(F.col("__lost"), _hashes(key))

    kept = F.when(F.col("__lost").isNull(), lines).otherwise(F.filter(lines, stays))
    out = joined.withColumns({"n_lines": F.size(lines).cast("long"), "__kept": kept})
    out = out.withColumns({"n_dropped": F.col("n_lines") - F.size("__kept"), "text": F.array_join("__kept", "\n")})
    return out.drop("__lost", "__kept")


def op7_line_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = drop_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


OP7_SQL = """
WITH l AS (
  SELECT doc_id, row, i, lines[i] AS line, translate(trim(lines[i], chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM (SELECT doc_id, row, lines, unnest(range(1, len(lines) + 1)) AS i FROM (SELECT doc_id, row_number() OVER () AS row, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents))
), shared AS (
  SELECT key, max(doc_id) AS last_doc FROM l WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT row) >= 5
), marked AS (
  SELECT l.doc_id, row, i, line, coalesce(l.doc_id <> last_doc, FALSE) AS dropped FROM l LEFT JOIN shared USING (key)
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE dropped) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT dropped), '')) AS kept_sha256
FROM marked GROUP BY doc_id, row
"""
