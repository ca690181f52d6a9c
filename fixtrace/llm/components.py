"""Connected components of a link table: local contraction, then alternating star contraction.

Links are first contracted inside tasks of a bounded number of links, each giving stars of its own part; where one
task held them all, these are the components.  Otherwise rounds of large star (every node's larger neighbours are
pointed at its least one) and small star (its smaller ones at the least of them) follow.  Both steps are an
aggregation, which combines on the map side, and a join that Spark may split where a node is hot; no
neighbourhood is ever gathered.  Rounds grow with the logarithm of the longest path, and each is settled in the
shared checkpoint folder.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fixtrace.llm.common import settle


def least_reached(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of some links and the least node each reaches."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        for end in (x, y, label[x], label[y]):
            np.minimum.at(new, end, low)
        while not np.array_equal(new, jumped := new[new]):
            new = jumped
        if np.array_equal(new, label):
            return nodes, nodes[label]
        label = new


def _contract(batches):
    found = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
    if found:
        nodes, least = least_reached(*(np.concatenate(c) for c in zip(*found, strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(least), pa.array(nodes)], ["lo", "hi"])


def _edges(df: DataFrame) -> DataFrame:
    return df.where("lo < hi").distinct()


def components(links: DataFrame, task_links: int = 1_000_000, max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of ``links`` (long columns ``a``, ``b``); component is the least node reached."""
    pairs = settle(links.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")))
    tasks = max(1, math.ceil(pairs.count() / task_links))
    stars = settle(pairs.coalesce(tasks).mapInArrow(_contract, "lo bigint, hi bigint"))
    if tasks == 1:
        return stars.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    now, before = settle(_edges(stars)), None
    for _ in range(max_rounds):
        sign = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("lo", "hi").cast("decimal(38,0)")).alias("h")).first()
        if sign == before or not sign["n"]:
            break
        before = sign
        both = now.select(F.col("lo").alias("u"), F.col("hi").alias("v")).unionAll(now.select(F.col("hi"), F.col("lo")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = _edges(both.where("v > u").join(least, "u").select(F.col("m").alias("lo"), F.col("v").alias("hi")))
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi").select(F.col("m"), F.explode(F.array("lo", "hi")).alias("x"))
        now = settle(_edges(small.select(F.col("m").alias("lo"), F.col("x").alias("hi"))))
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    members = now.groupBy("hi").agg(F.min("lo").alias("component")).withColumnRenamed("hi", "node")
    alone = stars.select(F.col("lo").alias("node")).distinct().join(members.select("node"), "node", "left_anti")
    return members.unionByName(alone.withColumn("component", F.col("node")))
