"""Commit logs and claim files from outside.

A log export has one line per commit: id, parents (space separated), epoch seconds and subject, split by tabs.
``read_log`` parses it with Spark's text reader, so any file system that Spark opens will do; ``CommitLogSource`` is
the same as a Python data source, one partition per file, for ``spark.read.format("commitlog")``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

LOG = "commit_id string, parents array<string>, committed_at timestamp, subject string"


def read_log(spark: SparkSession, path: str) -> DataFrame:
    """Malformed lines are dropped; roots have no parents."""
    parts = F.split("value", "\t", 4)
    rows = spark.read.text(path).where(F.size(parts) == 4).select(parts.alias("p"))
    return rows.select(
        F.get("p", 0).alias("commit_id"), F.filter(F.split(F.get("p", 1), " "), lambda x: x != "").alias("parents"),
        F.timestamp_seconds(F.get("p", 2).try_cast("bigint")).alias("committed_at"), F.get("p", 3).alias("subject"),
    )


def edges(log: DataFrame) -> DataFrame:
    """(child_id, parent_id, parent_no) of a log."""
    return log.select(F.col("commit_id").alias("child_id"), F.posexplode("parents").alias("parent_no", "parent_id"))


def read_claims(spark: SparkSession, path: str) -> DataFrame:
    """Affected-version claims from JSON lines: vuln_id, source, lo, hi, lo_incl, hi_incl, versions."""
    return spark.read.schema("vuln_id bigint, source string, lo string, hi string, lo_incl boolean, hi_incl boolean, versions array<string>").json(path)


def read_claim_table(spark: SparkSession, path: str) -> DataFrame:
    """The same claims from CSV with a header; versions are separated by semicolons, malformed rows are dropped."""
    rows = spark.read.option("header", True).option("mode", "DROPMALFORMED").schema("vuln_id bigint, source string, lo string, hi string, lo_incl boolean, hi_incl boolean, versions string").csv(path)
    return rows.withColumn("versions", F.split("versions", ";"))


def read_bundles(spark: SparkSession, path: str, pattern: str = "*.patch") -> DataFrame:
    """(path, text) of whole patch files of a folder, whatever bytes they hold; bytes that are no UTF-8 are replaced."""
    rows = spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", True).load(path)
    return rows.select("path", F.decode(F.col("content"), "UTF-8").alias("text"))


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _LogReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(self.path)
        info = store.get_file_info(base)
        if info.type != fs.FileType.Directory:
            return [_File(self.path)]
        prefix = self.path.rstrip("/")
        return [_File(f"{prefix}/{f.base_name}") for f in store.get_file_info(fs.FileSelector(base)) if f.type == fs.FileType.File]

    def read(self, partition):
        import datetime as dt

        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(partition.path)
        with store.open_input_stream(base) as f:
            text = f.read().decode("utf-8", "replace")
        for line in text.split("\n"):
            parts = line.split("\t", 3)
            if len(parts) == 4:
                when = dt.datetime.fromtimestamp(int(parts[2]), dt.UTC) if parts[2].lstrip("-").isdigit() else None
                yield parts[0], [p for p in parts[1].split(" ") if p], when, parts[3]


class CommitLogSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "commitlog"

    def schema(self) -> str:
        return LOG

    def reader(self, schema) -> DataSourceReader:
        path = self.options.get("path", "")
        return _LogReader(path if "://" in path else f"file://{path}")
