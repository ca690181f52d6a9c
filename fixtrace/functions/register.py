"""The methods as SQL functions: ``register_all(spark)``, then use them in ``spark.sql``."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from fixtrace.functions import ctree


def _struct(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in kinds.items()])


@pandas_udf(T.StringType())
def tree_codes(text: pd.Series) -> pd.Series:
    """Flattened normal form of a statement, one code point for each label; null where it does not parse."""
    found = (ctree.labels(x or "") for x in text)
    return pd.Series([None if f is None else ctree.code_points(f) for f in found])


@pandas_udf(T.DoubleType())
def weighted_score(similar: pd.Series, weight: pd.Series) -> float:
    """The weighted share of similar statements, as a grouped aggregate."""
    total = weight.sum()
    return float(weight[similar].sum() / total) if total else None


@udtf(returnType=_struct(hunk=T.IntegerType(), op=T.StringType(), old_no=T.IntegerType(), new_no=T.IntegerType(), text=T.StringType()))
class ExplodePatch:
    """Lines of one file's unified diff; a hunk is as long as its header says."""

    def eval(self, text: str):
        hunk = old = new = to_old = to_new = 0
        for line in (text or "").split("\n"):
            m = re.match(r"@@ -(\d+)(?:,(\d+))? \+(\d+)(?:,(\d+))? @@", line)
            if m:
                hunk, old, new = hunk + 1, int(m[1]), int(m[3])
                to_old, to_new = old + int(m[2] or 1), new + int(m[4] or 1)
            elif old < to_old or new < to_new:
                if line[:1] == "+":
                    yield hunk, "add", None, new, line[1:]
                    new += 1
                elif line[:1] == "-":
                    yield hunk, "del", old, None, line[1:]
                    old += 1
                elif line[:1] in (" ", ""):
                    yield hunk, "ctx", old, new, line[1:]
                    old, new = old + 1, new + 1


@udtf(returnType=_struct(position=T.IntegerType(), tag=T.StringType(), closing=T.BooleanType()))
class FlattenHtml:
    """Tags of a page in order."""

    def eval(self, html: str):
        for k, m in enumerate(re.finditer(r"<(/?)([a-zA-Z][a-zA-Z0-9]*)", html or "")):
            yield k, m[2].lower(), bool(m[1])


def register_all(spark: SparkSession) -> None:
    from fixtrace.sources.commitlog import CommitLogSource

    spark.udf.register("tree_codes", tree_codes)
    spark.udf.register("weighted_score", weighted_score)
    spark.udtf.register("explode_patch", ExplodePatch)
    spark.udtf.register("flatten_html", FlattenHtml)
    spark.dataSource.register(CommitLogSource)
