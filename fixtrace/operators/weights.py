"""Statement weights from sensitive functions, and the weighted similarity score."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Sensitive functions by vulnerability type; for integer overflow, operators too.
SENSITIVE = {
    "buffer overflow": "strcpy strncpy memcpy memset read write gets gets_s strcat".split(),
    "integer overflow": "+ * << memcpy".split(),
    "null dereference": "malloc calloc realloc strdup".split(),
    "pointer out of bounds": "memcpy memmove".split(),
    "use after free": "free malloc calloc".split(),
    "format string": "sprintf printf scanf".split(),
    "command execution": "fopen popen system".split(),
}
KEYWORDS = ("if", "while", "for", "switch", "return", "sizeof", "do", "else")


def sensitive_table(spark: SparkSession) -> DataFrame:
    rows = [(k, name, fn) for k, (name, fns) in enumerate(SENSITIVE.items()) for fn in fns]
    return spark.createDataFrame(rows, "vuln_type int, type_name string, fn string")


def called(text: Column) -> Column:
    """Names called in a statement."""
    return F.array_except(F.array_distinct(F.regexp_extract_all(text, F.lit(r"([A-Za-z_]\w*)\s*\("), F.lit(1))), F.array(*map(F.lit, KEYWORDS)))


def arithmetic(text: Column) -> Column:
    """Overflow-prone operators of a statement."""
    has = lambda pattern, op: F.when(text.rlike(pattern), F.array(F.lit(op))).otherwise(F.array().cast("array<string>"))
    return F.concat(has(r"[^+]\+[^+]", "+"), has(r"[\w)\]]\s*\*\s*[\w(]", "*"), has("<<", "<<"))


def sensitive_wrappers(callees: DataFrame, sensitive: DataFrame, depth: int = 1) -> DataFrame:
    """(vuln_type, fn) of the project's own functions whose bodies call a sensitive one, ``depth`` levels up."""
    edges = callees.select("name", F.explode(called(F.col("body"))).alias("fn"))
    known, found = sensitive.select("vuln_type", "fn"), None
    for _ in range(depth):
        new = edges.join(known, "fn").select("vuln_type", F.col("name").alias("fn")).distinct()
        found = new if found is None else found.union(new).distinct()
        known = known.union(new).distinct()
    return found


def assign_weights(stmts: DataFrame, sensitive: DataFrame, wrappers: DataFrame, ratio: float = 2.0, base: float = 1.0) -> DataFrame:
    """``stmts`` (vuln_type, text) with ``sensitive`` and ``weight``; the tables are constants and broadcast."""
    listed = sensitive.select("vuln_type", "fn").union(wrappers.select("vuln_type", "fn")).groupBy("vuln_type").agg(F.collect_set("fn").alias("listed"))
    out = stmts.join(F.broadcast(listed), "vuln_type", "left")
    names = F.array_union(called(F.col("text")), arithmetic(F.col("text")))
    hit = F.coalesce(F.arrays_overlap(names, F.col("listed")), F.lit(False))
    return out.withColumn("sensitive", hit).withColumn("weight", F.when(F.col("sensitive"), base * ratio).otherwise(base)).drop("listed")


def score(similar: Column, weight: Column) -> Column:
    """Aggregate: the weight of similar statements over all weight; null without statements."""
    total = F.sum(weight)
    return F.when(total > 0, F.sum(F.when(similar, weight).otherwise(0.0)) / total)
