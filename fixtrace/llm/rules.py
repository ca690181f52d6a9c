"""Quality rules as a bitmask ledger.

``ledger`` measures every document once (one Arrow pass over whole texts) and evaluates every rule once on the
measurements; bit k of ``failures`` is set where rule k fails.  Policies are versioned sets of rule names; applying
one is a bitwise AND on the stored ledger, and ablations are bitwise aggregations over it, so neither reads a text
again.

Defined results: a null or empty text has no words, so it fails ``few_words``; repeated rows are judged one by one;
an empty table gives no rows.  Only ``doc_id`` and ``text`` are read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.llm.common import by_batch, table
from fixtrace.llm.textkit import spans, windows, word_hashes

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_marked")


def measure(text: str | None) -> tuple[int, ...]:
    """The measurements of one text, in the order of ``MEASURES``."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    if not raw:
        return (0,) * len(MEASURES)
    a = np.frombuffer(raw, np.uint8)
    begin, end = spans(a)
    heads = np.concatenate([[0], np.cumsum((a & 0xC0) != 0x80)])
    three = windows(word_hashes(raw), 3)
    repeated = 0
    if len(three):
        _, back, times = np.unique(three, return_inverse=True, return_counts=True)
        covered = np.zeros(len(begin), bool)
        at = np.flatnonzero(times[back] > 1)
        for k in range(3):
            covered[at + k] = True
        repeated = int(covered.sum())
    seen: set[bytes] = set()
    twice = filled = 0
    for line in raw.split(b"\n"):
        if line.strip(b" \t\n\x0b\x0c\r"):
            filled += 1
            twice += line in seen
            seen.add(line)
    return (
        len(begin), int((heads[end] - heads[begin]).sum()), int(_SYMBOL[a].sum()), twice, repeated, filled,
        int(((a >= 65) & (a <= 90)).sum()), int(_SYMBOL[a[end - 1]].sum()) if len(end) else 0,
    )


@dataclass(frozen=True)
class Rule:
    """A rule fails where ``fails`` holds; its bit is its place in ``RULES``."""

    name: str
    fails: str


RULES = (
    Rule("few_words", "n_words < 50"),
    Rule("repeated_windows", "100 * n_repeat_words > 50 * n_words"),
    Rule("many_symbols", "10 * n_symbols > 3 * n_words"),
    Rule("repeated_lines", "n_lines >= 4 and 10 * n_dup_lines > 5 * n_lines"),
    Rule("short_mean_word", "word_chars < 2 * n_words"),
    Rule("long_mean_word", "word_chars > 20 * n_words"),
    Rule("shouting", "10 * n_upper > 6 * word_chars"),
    Rule("symbol_ends", "10 * n_marked > 5 * n_words"),
)
#: Policies by version: the rules that reject.
POLICIES = {
    "base": ("few_words", "repeated_windows"),
    "v1": ("few_words", "repeated_windows", "many_symbols", "repeated_lines", "short_mean_word", "long_mean_word"),
    "v2": tuple(r.name for r in RULES),
}


def mask(names) -> int:
    return sum(1 << k for k, r in enumerate(RULES) if r.name in set(names))


def ledger(docs: DataFrame) -> DataFrame:
    """doc_id, all measurements and the failure bits of every rule."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = zip(*(measure(x.as_py()) for x in batch.column(1)), strict=True)
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in found)], ["doc_id", *MEASURES])

    measured = docs.select("doc_id", "text").mapInArrow(by_batch(kernel), "doc_id bigint, " + ", ".join(f"{m} bigint" for m in MEASURES))
    bits = F.lit(0).cast("long")
    for k, r in enumerate(RULES):
        bits = bits.bitwiseOR(F.when(F.expr(r.fails), F.lit(1 << k)).otherwise(F.lit(0)).cast("long"))
    return measured.withColumn("failures", bits)


def rejects(policy: str) -> Column:
    """Whether a policy rejects a ledger row."""
    return F.col("failures").bitwiseAND(F.lit(mask(POLICIES[policy])).cast("long")) != 0


def ablation(book: DataFrame, policy: str) -> DataFrame:
    """For each rule of a policy: documents that fail it, and those that only it rejects."""
    chosen = mask(POLICIES[policy])
    counts = []
    for k, r in enumerate(RULES):
        if chosen >> k & 1:
            failed = F.col("failures").bitwiseAND(F.lit(1 << k).cast("long")) != 0
            alone = F.col("failures").bitwiseAND(F.lit(chosen).cast("long")) == (1 << k)
            counts.append(F.struct(F.lit(r.name).alias("rule"), F.count_if(failed).alias("n_failed"), F.count_if(alone).alias("n_alone")))
    return book.agg(F.array(*counts).alias("x")).select(F.inline("x"))


def op9_rule_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = ledger(table(spark, sf_dir, "documents"))
    return book.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        rejects("base").alias("base_failed"), (~rejects("v2")).alias("kept"), "failures",
    )


OP9_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
three AS (SELECT doc_id, i, ws[i] AS a, ws[i + 1] AS b, ws[i + 2] AS c FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM d)),
again AS (SELECT doc_id, i FROM three QUALIFY count(*) OVER (PARTITION BY doc_id, a, b, c) > 1),
covered AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM again, (SELECT unnest([0, 1, 2]) AS k) GROUP BY doc_id),
filled AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT x) AS twice FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^\x20\x09-\x0D]') GROUP BY doc_id),
m AS (
  SELECT d.doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars, (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    coalesce(twice, 0) AS n_dup_lines, coalesce(n, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines,
    length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS n_upper, len(list_filter(ws, lambda x: regexp_matches(x, '[#*$%&|<>]$'))) AS n_marked
  FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN filled USING (doc_id)
), f AS (
  SELECT *, (n_words < 50)::BIGINT + 2 * (100 * n_repeat_words > 50 * n_words)::BIGINT + 4 * (10 * n_symbols > 3 * n_words)::BIGINT + 8 * (n_lines >= 4 AND 10 * n_dup_lines > 5 * n_lines)::BIGINT
    + 16 * (word_chars < 2 * n_words)::BIGINT + 32 * (word_chars > 20 * n_words)::BIGINT + 64 * (10 * n_upper > 6 * word_chars)::BIGINT + 128 * (10 * n_marked > 5 * n_words)::BIGINT AS failures FROM m
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failures & 3) <> 0 AS base_failed, failures = 0 AS kept, failures FROM f
"""
