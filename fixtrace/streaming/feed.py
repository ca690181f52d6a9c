"""Streams over the event feed: windows, duplicates, online votes, late rows, upserts.

Each query below drains the rows there are (``availableNow``) into the shared folder and returns what was written,
so batch twins can check it; the building blocks take any streaming frame.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from fixtrace.functions.store import shared_dir


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of its files."""
    held = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(held).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need an instant; files may hold local times


def windowed(stream: DataFrame, length: str = "1 day", slide: str | None = None, late: str | None = "2 hours") -> DataFrame:
    """Counts per window and type; ``late=None`` where the stream has its watermark already."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    marked = stream.withWatermark("ts", late) if late else stream
    out = marked.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n_events"), F.sum("value").alias("value"))
    return out.select(F.col("w.start").alias("window_start"), "event_type", "n_events", F.round("value", 4).alias("value"))


def bursts(stream: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Activity sessions per user."""
    out = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n_events"))
    return out.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n_events")


def once(stream: DataFrame, keys: list[str], late: str = "2 hours") -> DataFrame:
    """Repeated deliveries within the watermark dropped."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def matched(claims: DataFrame, fixes: DataFrame, bound: str = "7 days") -> DataFrame:
    """Claims joined to fixes of the same record within a time bound; both sides carry watermarks ``ts``, ``fix_ts``."""
    return claims.join(fixes, F.expr(f"vuln_id = fix_vuln_id and fix_ts between ts and ts + interval {bound}"))


def enriched(stream: DataFrame, static: DataFrame, on: list[str]) -> DataFrame:
    """Stream rows with the columns of a static table; the table is read anew for each batch, and rows without a match stay."""
    return stream.join(static, on, "left")


def online_vote(runs: DataFrame, quorum: int = 6) -> DataFrame:
    """(vuln_id, stmt, votes) as soon as a statement reaches the quorum; state is the set of runs as ten bits."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        bits = state.get[0] if state.exists else 0
        had = bits.bit_count()
        for b in batches:
            for n in b["run_no"].unique():
                bits |= 1 << int(n)
        state.update((bits,))
        if had < quorum <= bits.bit_count():
            yield pd.DataFrame({"vuln_id": [key[0]], "stmt": [key[1]], "votes": [bits.bit_count()]})

    return runs.groupBy("vuln_id", "stmt").applyInPandasWithState(step, "vuln_id long, stmt string, votes long", "bits long", "append", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over the rows there are and return what it wrote."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")  # a repeated batch replaces itself

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out/*")


def daily_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drain(windowed(events(spark, sf_dir)), "complete")


def by_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    users = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), F.col("c_nationkey").cast("int").alias("repo_id"))
    known = enriched(events(spark, sf_dir).select("user_id", "event_type", "value"), users, ["user_id"])
    return drain(known.groupBy("repo_id", "event_type").agg(F.count("*").alias("n_events")), "complete")


def voted(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = events(spark, sf_dir).select(F.col("user_id").alias("vuln_id"), (F.col("event_id") % 10).cast("int").alias("run_no"), F.col("event_type").alias("stmt"))
    return drain(online_vote(runs)).select("vuln_id", "stmt")
