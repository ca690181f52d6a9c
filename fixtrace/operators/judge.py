"""Prompts, judged runs, answers and votes.

The judge is a plug: recorded answers, deterministic offline rules, or a remote service that a user supplies.
Runs are keyed by the digest of their prompt and kept, so a prompt is judged once however often plans re-run.
"""

from __future__ import annotations

import random
import re
from typing import Protocol

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.functions.store import settle
from fixtrace.operators.weights import SENSITIVE

STRATEGIES = ("zero_shot", "few_shot", "few_shot_reason")
ROLE = "Act as an experienced reviewer of security flaws in C code. You get a vulnerability record and numbered statements around its fix."
FORMAT = "Answer in two parts only. First 'vulnerability logic:' and a short text; then 'vulnerable lines:' and a list of line numbers. Leave out lines that the fix added."
REASON = "Work in two steps: first tell how the flaw comes about, then name the statements that take part in it."
#: Two worked examples of our own making; a guard keeps their ids out of what is evaluated.
EXAMPLES = (
    (-1, "integer overflow", "A count from the file is multiplied without a bound.", "3 total = count * width; 5 area = malloc(total);", "The product wraps, so the block is too small for what is written to it.", "3, 5"),
    (-2, "use after free", "A list entry is used after its release.", "7 free(node); 9 last = node->next;", "The entry is read after it was released.", "7, 9"),
)


def build_prompts(cases: DataFrame, flows: DataFrame, strategy: str = "few_shot_reason", evidence: str = "flow") -> DataFrame:
    """(vuln_id, strategy, messages, digest) from records (vuln_id, weakness, description) and rendered flows."""
    if strategy not in STRATEGIES:
        raise ValueError(strategy)
    held = cases.where(~F.col("vuln_id").isin(*(x[0] for x in EXAMPLES)))
    shots = "" if strategy == "zero_shot" else "\n\n".join(
        f"Example {k}\nweakness: {w}\ndescription: {d}\nstatements: {f}\nvulnerability logic: {logic}\nvulnerable lines: {lines}" for k, (_, w, d, f, logic, lines) in enumerate(EXAMPLES, 1)
    )
    system = "\n\n".join(x for x in (ROLE, shots, REASON if strategy == "few_shot_reason" else "", FORMAT) if x)
    user = F.concat_ws("\n", F.concat(F.lit("record: "), F.col("vuln_id").cast("string")), F.concat(F.lit("weakness: "), F.array_join("weakness", ", ")), F.concat(F.lit("description: "), F.col("description")), F.concat(F.lit("statements: "), F.col(evidence)))
    message = lambda role, text: F.struct(F.lit(role).alias("role"), text.alias("text"))
    out = held.join(flows, "vuln_id").select("vuln_id", F.lit(strategy).alias("strategy"), F.array(message("system", F.lit(system)), message("user", user)).alias("messages"))
    return out.withColumn("digest", F.sha2(F.concat_ws("\x1f", F.transform("messages", lambda m: m["text"])), 256))


#: Functions of the sensitive table, over all types.
LISTED = frozenset(fn for fns in SENSITIVE.values() for fn in fns if fn[0].isalpha())


class Provider(Protocol):
    def answer(self, messages: list[dict], run_no: int, digest: str) -> tuple[str, int, int]:
        """The answer's text, tokens in and tokens out."""


class RuleProvider:
    """Offline rules, told apart by ``noise``: no model, and no measure of one.

    Statements that call one of ``names`` (the sensitive table, and wrappers that a caller found) or multiply are
    named; the seed (digest, run) adds and drops some.
    """

    def __init__(self, noise: float = 0.15, names: frozenset[str] = LISTED):
        self.noise, self.names = noise, names

    def answer(self, messages, run_no, digest):
        flow = messages[-1]["text"].rpartition("statements: ")[2]
        rng = random.Random(f"{digest}/{run_no}")
        reasoned = REASON in messages[0]["text"]
        noise = self.noise * (1 if reasoned else 1.5) * (1 if "Example 1" in messages[0]["text"] else 1.5)
        named = []
        for m in re.finditer(r"(?:(?<=^)|(?<=\s))(\d+) (?=[A-Za-z_({])(.*?)(?=\s\d+ [A-Za-z_({]|$)", flow):
            hot = self.names & set(re.findall(r"([A-Za-z_]\w*)\s*\(", m[2])) or re.search(r"[\w)\]]\s*\*\s*[\w(]|<<", m[2])
            if (rng.random() < 1 - noise) if hot else (rng.random() < noise):
                named.append(m[1])
        text = f"vulnerability logic: rule based.\nvulnerable lines: {', '.join(named)}"
        return text, sum(len(m["text"].split()) for m in messages), len(text.split())


class ReplayProvider:
    """Recorded answers by (digest, run_no)."""

    def __init__(self, rows: dict[tuple[str, int], tuple[str, int, int]]):
        self.rows = rows

    def answer(self, messages, run_no, digest):
        return self.rows.get((digest, run_no), ("", 0, 0))


class HttpProvider:
    """The shape of a remote judge; a subclass sends ``messages`` and returns the answer."""

    def __init__(self, url: str, temperature: float = 1.0, max_tokens: int = 1024):
        self.url, self.temperature, self.max_tokens = url, temperature, max_tokens

    def answer(self, messages, run_no, digest):
        raise NotImplementedError("no service is configured")


def run_judge(prompts: DataFrame, provider: Provider, runs: int = 10, cache: DataFrame | None = None) -> DataFrame:
    """(digest, run_no, answer, tokens_in, tokens_out), each prompt judged ``runs`` times and kept.

    Pairs that ``cache`` holds are not judged again.
    """
    spark = prompts.sparkSession
    once = prompts.select("digest", "messages").dropDuplicates(["digest"])
    wanted = once.withColumn("run_no", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    if cache is not None:
        wanted = wanted.join(cache.select("digest", "run_no"), ["digest", "run_no"], "left_anti")

    def call(batches):
        for b in batches:
            rows = [(r["digest"], r["run_no"], *provider.answer(r["messages"], r["run_no"], r["digest"])) for r in b.to_pylist()]
            names = ["digest", "run_no", "answer", "tokens_in", "tokens_out"]
            kinds = [pa.string(), pa.int32(), pa.string(), pa.int32(), pa.int32()]
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

    done = settle(wanted.repartition("digest", "run_no").select("digest", "run_no", "messages").mapInArrow(call, "digest string, run_no int, answer string, tokens_in int, tokens_out int"))
    return done if cache is None else done.unionByName(cache.join(once.select("digest"), "digest", "left_semi"))


def parse_answer(answer: Column) -> Column:
    """struct(logic, lines): null lines where the fixed format is missing."""
    lines = F.regexp_extract(answer, r"(?is)vulnerable lines\s*:\s*([^\n]*)", 1)
    numbers = F.array_distinct(F.transform(F.regexp_extract_all(lines, F.lit(r"\d+"), F.lit(0)), lambda x: x.try_cast("int")))
    well = answer.rlike(r"(?is)vulnerability logic\s*:.*vulnerable lines\s*:")
    return F.struct(F.trim(F.regexp_extract(answer, r"(?is)vulnerability logic\s*:\s*(.*?)\s*vulnerable lines\s*:", 1)).alias("logic"), F.when(well, numbers).alias("lines"))


def named_statements(prompts: DataFrame, runs: DataFrame, added: DataFrame | None = None) -> DataFrame:
    """(vuln_id, run_no, line_no); lines that the fix added do not exist before it and are excluded."""
    out = prompts.select("vuln_id", "digest").join(runs, "digest").select("vuln_id", "run_no", F.explode(parse_answer(F.col("answer"))["lines"]).alias("line_no"))
    return out if added is None else out.join(added.select("vuln_id", "line_no"), ["vuln_id", "line_no"], "left_anti")


def examples_are_apart(spark: SparkSession, cases: DataFrame) -> bool:
    ids = [x[0] for x in EXAMPLES]
    return cases.where(F.col("vuln_id").isin(*ids)).limit(1).count() == 0
