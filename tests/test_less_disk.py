"""What is shuffled or kept on the way is gone once a frame is settled, and texts are not shuffled to meet the text before."""

import time

from pyspark.sql import functions as F

from fixtrace.functions import store
from fixtrace.operators import backtrack, similarity
from fixtrace.plans.lab import lab_of
from fixtrace.sources import code


def test_settling_leaves_no_shuffle_files(spark):
    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: sum(1 for k in range(len(f)) if "shuffle_" in f[k]) if (f := disk.getAllFiles().mkString("\n").split("\n")) else 0
    before = files()
    df = store.settle(spark.range(5_000).groupBy((F.col("id") % 97).alias("k")).agg(F.sum("id").alias("n")))
    for _ in range(50):
        if files() <= before:
            break
        time.sleep(0.1)
    assert files() <= before and df.count() == 97
    assert spark.conf.get(store.CLEAN, None) in (None, "false")


def test_similarities_keep_only_their_result(spark):
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(spark.sparkContext.getCheckpointDir() or store.shared_dir(spark))
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    store.settle(spark.range(1))
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(spark.sparkContext.getCheckpointDir())
    count = lambda: len(fs.listStatus(path))
    pairs = spark.createDataFrame([("a = b + 1;", "a = 1 + b;"), ("x = f(y);", "while (z) z--;")], "pre string, post string")
    n = count()
    rows = similarity.settled(pairs, code.callees(spark))
    assert count() == n + 1 and rows.count() == 2
    store.drop(rows)
    assert count() == n


def test_the_text_before_is_carried_not_joined(spark, small):
    lab = lab_of(spark, small)
    rows = lab.content.select("file_id", "slot", "commit_id", "pred0", "text", "pre").collect()
    text = {(r.file_id, r.slot, r.commit_id): r.text for r in rows}
    assert any(r.pred0 for r in rows) and all(r.pre == (None if r.pred0 is None else text[r.file_id, r.slot, r.pred0]) for r in rows)
    assert "Exchange" not in lab.pairs._jdf.queryExecution().executedPlan().toString()


def test_touches_are_lost_as_their_distinct_pairs_tell(spark, small):
    lab = lab_of(spark, small)
    told = {(r.pre, r.post): r.similar for r in lab.sims.select("pre", "post", similarity.stage().alias("similar")).collect()}
    want = {(r.file_id, r.slot, r.commit_id): r.pre is None or not (r.pre == r.text or told[r.pre, r.text]) for r in lab.content.collect()}
    got = lab.compared.collect()
    assert {(r.file_id, r.slot, r.commit_id): r.lost for r in got} == want and len(got) == len(want) and len(set(want.values())) == 2
    flags = lab.sims.select("pre", "post", similarity.stage().alias("similar"))
    plain = backtrack.compared_touches(lab.content, flags).collect()
    assert {(r.file_id, r.slot, r.commit_id): r.lost for r in plain} == want
    assert not {"text", "pre"} & set(lab.compared.columns)
