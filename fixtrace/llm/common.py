"""Helpers that every operator of this subpackage shares."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The white space of the contracts: space, tab, line feed, vertical tab, form feed, carriage return.
BLANKS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; a local one only in local mode without it."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext.getCheckpointDir()
        if not held and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = held.rsplit("/", 1)[0] if held else tempfile.mkdtemp(prefix="fixtrace-")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(found)
    return found


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of any file system that Spark opens."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def settle(df: DataFrame) -> DataFrame:
    """Compute once into the shared checkpoint folder and cut the lineage there, so a lost executor loses nothing."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def look_up(rows: DataFrame, key: str, found: DataFrame, weight: str, share: int = 1000) -> DataFrame:
    """``rows`` left-joined to ``found`` (one row for each ``key``) without its ``weight`` column.

    ``weight`` is the number of rows that a key has.  Keys with over 1/``share`` of all rows, of which there are fewer
    than ``share``, are looked up by broadcast where their rows are; the rest, none of it hot, by a shuffle.
    """
    total = found.agg(F.sum(weight)).first()[0] or 0
    hot = F.col(weight) * share > F.lit(total)
    few, rest = (found.where(c).drop(weight) for c in (hot, ~hot))
    marked = rows.join(F.broadcast(few.withColumn("__hot", F.lit(True))), key, "left")
    bare = marked.where("__hot is null").select(rows.columns)
    return marked.where("__hot").drop("__hot").unionByName(bare.where(F.col(key).isNotNull()).join(rest, key, "left").select(marked.drop("__hot").columns)).unionByName(
        bare.where(F.col(key).isNull()), allowMissingColumns=True
    )


def fold_lower(col):
    """Lower-case A-Z and nothing else."""
    return F.translate(col, UPPER, LOWER)


def held_out(doc_id):
    """Every fifth document by the CRC-32 of its id as text."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def by_batch(kernel: Callable[[pa.RecordBatch], pa.RecordBatch | None]):
    """A ``mapInArrow`` function that applies ``kernel`` to each non-empty batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows and (out := kernel(batch)) is not None:
                yield out

    return run
