"""Where results go: partitioned and bucketed tables, reports, upserts by partition."""

from __future__ import annotations

from pyspark.sql import DataFrame


def save_history(touches: DataFrame, table: str, buckets: int = 64) -> None:
    """Touches bucketed by statement slot, so windows and joins on it need no shuffle later."""
    touches.write.mode("overwrite").bucketBy(buckets, "file_id", "slot").sortBy("file_id", "slot", "seq").saveAsTable(table)


def save_by_project(df: DataFrame, path: str) -> None:
    df.repartition("repo_id").write.mode("overwrite").partitionBy("repo_id").parquet(path)


def upsert_by_project(df: DataFrame, path: str) -> None:
    """Replace only the projects that ``df`` holds."""
    df.repartition("repo_id").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("repo_id").parquet(path)


def report(df: DataFrame, path: str) -> None:
    df.coalesce(1).write.mode("overwrite").option("header", True).csv(path)
