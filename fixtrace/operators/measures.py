"""Accuracy, consistency, cost and audit measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def f1(p: Column, r: Column) -> Column:
    return F.when(p + r > 0, 2 * p * r / (p + r))


def confusion(pred: DataFrame, truth: DataFrame, by: list[str]) -> DataFrame:
    """tp, fp, fn per ``by``; both sides are distinct (vuln_id, tag_no) pairs with the columns of ``by``."""
    keys = list(dict.fromkeys([*by, "vuln_id", "tag_no"]))
    p = pred.select(*keys).distinct().withColumn("in_pred", F.lit(1))
    t = truth.select(*keys).distinct().withColumn("in_truth", F.lit(1))
    both = p.join(t, keys, "full_outer")
    has = lambda c: F.col(c).isNotNull()
    return both.groupBy(*by).agg(F.count_if(has("in_pred") & has("in_truth")).alias("tp"), F.count_if(has("in_pred") & ~has("in_truth")).alias("fp"), F.count_if(~has("in_pred") & has("in_truth")).alias("fn"))


def confusion_of_spans(spans: DataFrame, by: list[str]) -> DataFrame:
    """``confusion`` where each case has one run of tags in either set: (first, stop] found and (real, stop] true, by number of tags.

    ``first`` or ``real`` is null where there is none.  Groups without any tag have no row.
    """
    size = lambda c: F.coalesce(F.greatest(F.col("stop") - c, F.lit(0)), F.lit(0))
    both = F.when(F.col("first").isNotNull() & F.col("real").isNotNull(), size(F.greatest("first", "real"))).otherwise(0)
    found = F.when(F.col("first").isNotNull(), size(F.col("first"))).otherwise(0)
    real = F.when(F.col("real").isNotNull(), size(F.col("real"))).otherwise(0)
    rows = spans.select(*by, both.alias("both"), found.alias("found"), real.alias("wanted")).where("found + wanted > 0")
    return rows.groupBy(*by).agg(F.sum("both").alias("tp"), F.sum(F.col("found") - F.col("both")).alias("fp"), F.sum(F.col("wanted") - F.col("both")).alias("fn"))


def confusion_of_runs(found: DataFrame, truth: DataFrame, by: str) -> DataFrame:
    """``confusion`` by (``by``, repo_id) without a row for each tag.

    ``found``: ``by``, vuln_id, first and last, runs of tags by number, none twice for a case; ``truth``: ``by``,
    vuln_id, repo_id, real and stop, where (real, stop] are the true tags and ``real`` is null where there are none.
    """
    size = lambda a, b: F.coalesce(F.greatest(F.col(b) - F.col(a), F.lit(0)), F.lit(0)).cast("long")
    # the runs of a case are added up first: only one row for a case meets the truth and is summed again
    runs = found.select(by, "vuln_id", (F.col("first") - 1).alias("ahead"), "last").join(truth.drop("repo_id"), [by, "vuln_id"])
    runs = runs.withColumns({"from": F.when(F.col("real").isNotNull(), F.greatest("ahead", "real")), "to": F.least("last", "stop")})
    per = runs.groupBy(by, "vuln_id").agg(F.sum(size("from", "to")).alias("both"), F.sum(size("ahead", "last")).alias("found"))
    rows = truth.select(by, "vuln_id", "repo_id", size("real", "stop").alias("wanted")).join(per, [by, "vuln_id"], "left")
    rows = rows.withColumns({c: F.coalesce(c, F.lit(0)) for c in ("both", "found")}).where("found + wanted > 0")
    return rows.groupBy(by, "repo_id").agg(F.sum("both").alias("tp"), F.sum(F.col("found") - F.col("both")).alias("fp"), F.sum(F.col("wanted") - F.col("both")).alias("fn"))


def rates(counts: DataFrame) -> DataFrame:
    """Precision, recall and F1 of counted rows; undefined where the denominator is zero."""
    p = F.when(F.col("tp") + F.col("fp") > 0, F.col("tp") / (F.col("tp") + F.col("fp")))
    r = F.when(F.col("tp") + F.col("fn") > 0, F.col("tp") / (F.col("tp") + F.col("fn")))
    return counts.withColumns({"precision": p, "recall": r}).withColumn("f1", f1(F.col("precision"), F.col("recall")))


def macro(per_project: DataFrame, by: list[str]) -> DataFrame:
    """Means of the projects' rates; F1 from the means; projects where a rate is undefined are counted, not averaged."""
    out = per_project.groupBy(*by).agg(
        F.avg("precision").alias("precision"), F.avg("recall").alias("recall"), F.count("*").alias("n_projects"),
        F.count_if(F.col("precision").isNull()).alias("undefined_precision"), F.count_if(F.col("precision") > 0.9).alias("high_precision"), F.count_if(F.col("recall") == 1).alias("full_recall"),
    )
    return out.withColumn("f1", f1(F.col("precision"), F.col("recall")))


def vote(runs: DataFrame, quorum: int = 6) -> DataFrame:
    """(vuln_id, stmt, votes) of statements named in at least ``quorum`` distinct runs."""
    return runs.groupBy("vuln_id", "stmt").agg(F.count_distinct("run_no").alias("votes")).where(F.col("votes") >= quorum)


def agreement(runs: DataFrame, of: int = 10) -> DataFrame:
    """Statements in every run over distinct statements, pooled over cases."""
    per = runs.groupBy("vuln_id", "stmt").agg(F.count_distinct("run_no").alias("n"))
    return per.agg(F.count_if(F.col("n") == of).alias("n_unanimous"), F.count("*").alias("n_statements")).withColumn("agreement", F.col("n_unanimous") / F.col("n_statements"))


def mean_jaccard(runs: DataFrame, only_varying: bool = True) -> DataFrame:
    """Mean Jaccard of the answers of each pair of runs, averaged per case, then over cases."""
    answers = runs.groupBy("vuln_id", "run_no").agg(F.collect_set("stmt").alias("s"))
    a, b = answers.alias("a"), answers.alias("b")
    met = a.join(b, (F.col("a.vuln_id") == F.col("b.vuln_id")) & (F.col("a.run_no") < F.col("b.run_no")))
    j = F.size(F.array_intersect("a.s", "b.s")) / F.size(F.array_union("a.s", "b.s"))
    per = met.select(F.col("a.vuln_id").alias("vuln_id"), j.alias("j")).groupBy("vuln_id").agg(F.avg("j").alias("j"), F.min("j").alias("least"))
    if only_varying:
        per = per.where("least < 1")
    return per.agg(F.count("*").alias("n_cases"), F.avg("j").alias("mean_jaccard"))


def judge_cost(runs: DataFrame, price_in: str = "0.30", price_out: str = "1.10") -> DataFrame:
    """Cost per case in decimals; prices are per million tokens."""
    per = runs.groupBy("vuln_id").agg(F.sum("tokens_in").cast("decimal(18,0)").alias("tokens_in"), F.sum("tokens_out").cast("decimal(18,0)").alias("tokens_out"))
    cost = (F.col("tokens_in") * F.lit(price_in).cast("decimal(6,2)") + F.col("tokens_out") * F.lit(price_out).cast("decimal(6,2)")) / F.lit(1_000_000)
    return per.withColumn("cost", cost.cast("double"))


#: Classes of an audited claim.
CLASSES = ("correct", "incomplete", "over_inclusive", "mixed", "missing")


def audit(claims: DataFrame, found: DataFrame, tags: DataFrame) -> DataFrame:
    """Class of each claim against the versions found.

    ``claims``: vuln_id and repo_id of every claim, with an array of claimed tag numbers (null: no information).
    correct, incomplete (claims too little), over-inclusive (too much), mixed (both), missing.
    """
    real = found.groupBy("vuln_id").agg(F.collect_set("tag_no").alias("real"))
    first = tags.groupBy("repo_id").agg(F.min("tag_no").alias("first_tag"))
    rows = claims.join(real, "vuln_id", "left").join(F.broadcast(first), "repo_id", "left")
    none = F.array().cast("array<int>")
    rows = rows.withColumn("real", F.coalesce("real", none))
    less, more = F.size(F.array_except("real", "claimed")), F.size(F.array_except("claimed", "real"))
    kind = F.when(F.col("claimed").isNull(), "missing").when((less > 0) & (more > 0), "mixed").when(less > 0, "incomplete").when(more > 0, "over_inclusive").otherwise("correct")
    sub = F.when(F.col("claimed").isNull(), None).when((kind == "incomplete") & (F.size("claimed") == 1), "single_version").when((kind == "over_inclusive") & (F.array_min("claimed") == F.col("first_tag")), "all_before")
    return rows.withColumns({"audit": kind, "pattern_found": sub, "n_missing": F.when(F.col("claimed").isNotNull(), less), "n_extra": F.when(F.col("claimed").isNotNull(), more)})


def band(severity: Column) -> Column:
    return F.when(severity >= 9, "critical").when(severity >= 7, "high").when(severity >= 4, "medium").otherwise("low")


def relative_gain(new: Column, old: Column) -> Column:
    return F.when(old > 0, (new - old) / old)
