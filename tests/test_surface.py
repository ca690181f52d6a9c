import time

import pandas as pd
import pytest
from pyspark.sql import functions as F

from fixtrace.functions.register import register_all
from fixtrace.operators.cost import StageTimer, time_ratio
from fixtrace.sources import commitlog, sinks
from fixtrace.streaming import feed

LOG = "c3\tc2 c1\t300\tmerge\nc2\tc1\t200\tsecond\nc1\t\t100\tfirst\nbroken line\n"


def test_commit_logs(spark, tmp_path):
    (tmp_path / "log").mkdir()
    (tmp_path / "log" / "a.txt").write_text(LOG)
    register_all(spark)
    want = [("c1", []), ("c2", ["c1"]), ("c3", ["c2", "c1"])]
    for df in (commitlog.read_log(spark, f"file://{tmp_path}/log"), spark.read.format("commitlog").load(f"file://{tmp_path}/log")):
        assert sorted((r.commit_id, r.parents) for r in df.collect()) == want
    assert commitlog.edges(commitlog.read_log(spark, f"file://{tmp_path}/log")).count() == 3


def test_sql_surface(spark):
    register_all(spark)
    got = spark.sql("SELECT tree_codes('x = b + a;') = tree_codes('x = a + b;') AS same, tree_codes('if (') IS NULL AS none").first()
    assert got.same and got.none
    rows = spark.sql("SELECT * FROM explode_patch('@@ -3,1 +3,1 @@\n-a\n+b')").collect()
    assert [(r.op, r.old_no, r.new_no, r.text) for r in rows] == [("del", 3, None, "a"), ("add", None, 3, "b")]
    odd = spark.sql("SELECT * FROM explode_patch('@@ -3 +3,2 @@\n--- i;\n+++ j;\n+k;\n--- a/next')").collect()
    assert [(r.op, r.text) for r in odd] == [("del", "-- i;"), ("add", "++ j;"), ("add", "k;")]
    assert [r.tag for r in spark.sql("SELECT * FROM flatten_html('<p><B>x</B>') ORDER BY position").collect()] == ["p", "b", "b"]
    spark.createDataFrame([(1, True, 2.0), (1, False, 1.0), (1, False, 1.0)], "k int, s boolean, w double").createOrReplaceTempView("st")
    assert spark.sql("SELECT weighted_score(s, w) AS x FROM st GROUP BY k").first().x == pytest.approx(0.5)


def test_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "repo_id int, x string")
    path = f"file://{tmp_path}/out"
    sinks.save_by_project(df, path)
    sinks.upsert_by_project(spark.createDataFrame([(2, "c")], "repo_id int, x string"), path)
    assert sorted((r.repo_id, r.x) for r in spark.read.parquet(path).collect()) == [(1, "a"), (2, "c")]
    sinks.report(df, f"{path}-csv")
    assert spark.read.option("header", True).csv(f"{path}-csv").count() == 2


def test_late_rows_and_repeats(spark, tmp_path):
    """A row later than the watermark is left out; a repeated delivery counts once."""
    rows = [(1, "2024-01-01 00:10:00"), (1, "2024-01-01 00:10:00"), (2, "2024-01-01 09:00:00")]
    for k, part in enumerate([rows, [(4, "2024-01-02 09:00:00")], [(3, "2024-01-01 00:20:00"), (5, "2024-01-03 09:00:00")], [(6, "2024-01-04 09:00:00")]]):
        pd.DataFrame({"event_id": [r[0] for r in part], "ts": pd.to_datetime([r[1] for r in part]), "event_type": "x", "value": 1.0, "user_id": 1}).to_parquet(f"{tmp_path}/{k}.parquet", coerce_timestamps="us")
    s = spark.readStream.schema("event_id long, ts timestamp, event_type string, value double, user_id long").option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}")
    out = feed.drain(feed.windowed(feed.once(s, ["event_id"]), "1 hour", late=None)).collect()
    got = {str(r.window_start): r.n_events for r in out}
    assert got["2024-01-01 00:00:00"] == 1 and got["2024-01-01 09:00:00"] == 1


def test_sessions_and_claims_in_time(spark, small):
    e = feed.events(spark, small)
    assert feed.drain(feed.bursts(e)).count() > 0
    assert feed.windowed(e, "1 day", "6 hours").isStreaming
    claims = e.select(F.col("user_id").alias("vuln_id"), "ts").withWatermark("ts", "1 hour")
    fixes = e.select(F.col("user_id").alias("fix_vuln_id"), F.col("ts").alias("fix_ts")).withWatermark("fix_ts", "1 hour")
    assert feed.matched(claims, fixes).isStreaming


def test_stream_static_join_keeps_rows_without_a_match(spark, tmp_path):
    pd.DataFrame({"user_id": [1, 2, 2], "event_type": "x"}).to_parquet(f"{tmp_path}/0.parquet")
    s = spark.readStream.schema("user_id long, event_type string").parquet(f"file://{tmp_path}")
    got = feed.drain(feed.enriched(s, spark.createDataFrame([(2, "b"), (3, "c")], "user_id long, name string"), ["user_id"]))
    assert sorted((r.user_id, r.name or "") for r in got.collect()) == [(1, ""), (2, "b"), (2, "b")]


def test_claims_meet_fixes_in_time(spark, tmp_path):
    for name, rows in (("c", [(1, "2024-01-01"), (1, "2024-02-01"), (2, "2024-01-01"), (9, "2024-06-01")]), ("f", [(1, "2024-01-05"), (2, "2024-01-09"), (9, "2024-06-02")])):
        (tmp_path / name).mkdir()
        pd.DataFrame({"id": [r[0] for r in rows], "at": pd.to_datetime([r[1] for r in rows])}).to_parquet(f"{tmp_path}/{name}/0.parquet", coerce_timestamps="us")
    read = lambda name: spark.readStream.schema("id long, at timestamp").parquet(f"file://{tmp_path}/{name}")
    claims = read("c").select(F.col("id").alias("vuln_id"), F.col("at").alias("ts")).withWatermark("ts", "1 hour")
    fixes = read("f").select(F.col("id").alias("fix_vuln_id"), F.col("at").alias("fix_ts")).withWatermark("fix_ts", "1 hour")
    got = feed.drain(feed.matched(claims, fixes)).collect()
    assert sorted((r.vuln_id, str(r.ts)[:10], str(r.fix_ts)[:10]) for r in got) == [(1, "2024-01-01", "2024-01-05"), (9, "2024-06-01", "2024-06-02")]


def test_timing():
    t = StageTimer()
    with t.stage("slice"):
        time.sleep(0.02)
    assert t.per_case(2) == {"slice": t.seconds["slice"] / 2} and 0.02 <= t.seconds["slice"] < 5
    assert time_ratio(28.61, 122, 3) == pytest.approx(377.5, abs=0.1)


def test_votes_reach_their_quorum_over_batches(spark, tmp_path):
    for k, part in enumerate([[0, 1, 2], [2, 3], [4, 5]]):
        pd.DataFrame({"vuln_id": 1, "run_no": part, "stmt": "a"}).astype({"run_no": "int32"}).to_parquet(f"{tmp_path}/{k}.parquet")
    s = spark.readStream.schema("vuln_id long, run_no int, stmt string").option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}")
    assert [(r.stmt, r.votes) for r in feed.drain(feed.online_vote(s)).collect()] == [("a", 6)]
