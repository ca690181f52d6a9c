"""Cutting lineage in the folder that driver and executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` as the session has it; a local folder only in local mode without it."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    held = spark.sparkContext.getCheckpointDir()
    if not found:
        if not held and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = held.rsplit("/", 1)[0] if held else tempfile.mkdtemp(prefix="fixtrace-")
    if held is None:
        spark.sparkContext.setCheckpointDir(found)
    return found


#: Whether Spark deletes the shuffle files of an action when it ends.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settle(df: DataFrame) -> DataFrame:
    """Computed once, kept in the shared folder, lineage cut; what was shuffled for it is deleted."""
    spark = df.sparkSession
    shared_dir(spark)
    held = spark.conf.get(CLEAN, None)
    spark.conf.set(CLEAN, "true")
    try:
        return df.select("*").checkpoint(eager=True)  # a plan of its own, made under the setting
    finally:
        spark.conf.unset(CLEAN) if held is None else spark.conf.set(CLEAN, held)


def drop(*frames: DataFrame) -> None:
    """Deletes the files of settled frames that nothing reads any more."""
    for df in frames:
        found = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
        if found.isDefined():
            path = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(found.get())
            path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
