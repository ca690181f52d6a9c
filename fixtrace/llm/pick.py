"""Taking some documents by id without shuffling the texts of all.

Ids are hashed into a bitmap of a fixed number of bits, OR-ed together by Spark and handed to the tasks; rows whose
bit is not set are told apart while they are read, and only the rest is joined by id.  The bitmap's size does not
depend on the data: with more ids it lets more rows through, and the join still decides.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fixtrace.llm.common import by_batch

BITS = 1 << 23


def _bit(ids: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = ids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (x >> np.uint64(41)).astype(np.int64)


def bitmap(ids: DataFrame) -> np.ndarray:
    """The bitmap of a column of long ids, as BITS / 64 words."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        at = _bit(batch.column(0).drop_null().to_numpy())
        word, back = np.unique(at >> 6, return_inverse=True)
        bits = np.zeros(len(word), np.uint64)
        np.bitwise_or.at(bits, back, np.uint64(1) << (at & 63).astype(np.uint64))
        return pa.RecordBatch.from_arrays([pa.array(word), pa.array(bits.view(np.int64))], ["word", "bits"])

    out = np.zeros(BITS // 64, np.int64)
    for r in ids.mapInArrow(by_batch(kernel), "word bigint, bits bigint").groupBy("word").agg(F.bit_or("bits").alias("bits")).toLocalIterator():
        out[r.word] = r.bits
    return out.view(np.uint64)


def filtered(docs: DataFrame, bits: np.ndarray, hit: bool) -> DataFrame:
    """Rows whose id's bit is set, or is not; a null id never is.  Columns stay as they are."""
    held = docs.sparkSession.sparkContext.broadcast(bits)

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids = batch.column("doc_id")
        at = _bit(ids.fill_null(0).to_numpy())
        found = (held.value[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)).astype(bool) & ~ids.is_null().to_numpy(zero_copy_only=False)
        return batch.filter(pa.array(found if hit else ~found))

    return docs.mapInArrow(by_batch(kernel), docs.schema)


def pick(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose ``doc_id`` is in ``ids``."""
    return filtered(docs, bitmap(ids.select("doc_id")), True).join(ids, "doc_id", "left_semi")


def leave(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose ``doc_id`` is not in ``ids``."""
    bits = bitmap(ids.select("doc_id"))
    return filtered(docs, bits, False).unionByName(filtered(docs, bits, True).join(ids, "doc_id", "left_anti"))
