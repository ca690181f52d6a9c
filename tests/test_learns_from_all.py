"""The function model learns from every change of the even repositories, however many there are."""

from pyspark.sql import functions as F

from fixtrace.operators import detectors


def test_rows_beyond_twenty_thousand_are_learned_from(spark):
    # 30,000 changes of a common kind with low numbers, and 10,000 of another kind with high ones
    draw = F.when(F.col("id") < 30_000, F.col("id")).otherwise(F.lit(900_000) + F.col("id"))
    place = F.when(F.col("id") < 30_000, F.lit(1)).otherwise(F.lit(5))
    learned = spark.range(40_000).select(F.lit(2).alias("repo_id"), (F.col("id") >= 30_000).alias("same"), draw.alias("draw"), place.alias("place"))
    asked = spark.createDataFrame([(1, False, 1, 1), (1, True, 2, 5)], "repo_id int, same boolean, draw long, place int")
    rows = learned.unionByName(asked).select(
        "repo_id", "same", "draw", F.unhex(F.lpad(F.hex("draw"), 32, "0")).alias("digest"), F.array("place", F.lit(2)).cast("array<int>").alias("changed"), F.lit(0.5).alias("share"), F.lit(1).cast("long").alias("n")
    )
    got = {(r.repo_id, r.same): (r.n, r.similarity) for r in detectors.function_model(rows).collect()}
    assert set(got) == {(2, False), (2, True), (1, False), (1, True)}
    assert got[2, False][0] == 30_000 and got[2, True][0] == 10_000
    assert got[1, True][1] > 0.9 and got[1, False][1] < 0.1


def test_equal_changes_weigh_as_often_as_they_occur(spark):
    """A rare answer among equal features moves their score by its share, not by one of two."""
    rows = spark.range(1_000).select(F.lit(2).alias("repo_id"), (F.col("id") % 10 == 0).alias("same"), F.col("id").alias("draw"), F.array(F.lit(3), F.lit(1)).alias("changed"), F.lit(0.5).alias("share"), F.lit(1).cast("long").alias("n"))
    got = {r.similarity for r in detectors.function_model(rows.withColumn("digest", F.unhex(F.hex("draw")))).collect()}
    assert len(got) == 1 and abs(got.pop() - 0.1) < 0.01
