"""Mixing sources to target weights by iterative proportional fitting, DataFrame functions only.

Documents are counted into cells (source, language, topic) of token weight.  Sweeps of raking scale the cells to
the target marginals in turn; the fitted over the present weight of a cell is its ratio.  Keep probabilities are
ratios times one factor, capped at 1, with the factor set so that the expected tokens kept are ``budget`` of all;
a document is kept where the uniform number of its id's digest lies below its cell's probability.

Where no targets are given, a marginal's targets are its present shares to the power ``temper``, so large sources
shrink and small ones grow.  The cell table is small by construction (sources x languages x topics); up to
``max_cells`` rows it is raked by windows in one task and broadcast, beyond that every total is an aggregation that is
joined back, settled after each sweep, and the cells are joined by key.

Defined results: null source or language is ``unknown``; a null or empty text has no tokens, counts nothing and
takes its cell's probability; cells without tokens have ratio 1; a value that given targets leave out has share 0, so
its documents go; a null ``doc_id`` draws no number and is never kept; repeated rows draw the same number; an empty
table gives no rows.  Only the columns of ``documents`` are read; columns called topic, tokens, keep_p or kept are
replaced.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.llm.common import settle, table

#: The first predicate that holds names the topic; the same text serves Spark and the SQL twin.
TOPICS = (("table", "text LIKE '% | %'"), ("legal", "text LIKE '%icense%'"), ("contact", "text LIKE '%@%'"), ("brief", "length(text) < 600"))
AXES = ("source", "lang", "topic")


@dataclass(frozen=True)
class Params:
    """``targets``: axis to {value: share}; an axis left out is tempered."""

    targets: dict = field(default_factory=dict)
    temper: tuple[float, float, float] = (0.7, 0.8, 0.9)
    sweeps: int = 6
    fills: int = 8
    budget: float = 0.8
    max_cells: int = 100_000


def with_cells(docs: DataFrame) -> DataFrame:
    topic = "CASE " + " ".join(f"WHEN {p} THEN '{n}'" for n, p in TOPICS) + " ELSE 'prose' END"
    tokens = F.coalesce(F.size(F.regexp_extract_all(F.col("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))), F.lit(0)).cast("double")
    return docs.withColumns({
        "__source": F.coalesce("source", F.lit("unknown")), "__lang": F.coalesce("lang", F.lit("unknown")),
        "__topic": F.expr(topic), "__tokens": F.when(F.col("text").isNull(), 0.0).otherwise(tokens),
    })


def _with_total(cells: DataFrame, value, keys: tuple[str, ...], name: str, wide: bool) -> DataFrame:
    """``cells`` with the total of ``value`` over rows of equal ``keys`` (none: over all rows)."""
    if not wide:
        return cells.withColumn(name, F.sum(value).over(W.partitionBy(*keys)))
    totals = cells.groupBy(*keys).agg(F.sum(value).alias(name))
    return cells.join(totals, list(keys)) if keys else cells.join(F.broadcast(totals))


def fit_cells(cells: DataFrame, params: Params, wide: bool = False) -> DataFrame:
    """source, lang, topic, tokens, ratio and keep_p of each cell; ``wide`` where one task shall not hold all cells."""
    rest = settle if wide else (lambda df: df)
    tokens = F.col("tokens")
    cells = _with_total(cells, tokens, (), "all", wide)
    for axis, power in zip(AXES, params.temper, strict=True):
        if given := params.targets.get(axis):
            named = F.coalesce(*(F.when(F.col(axis) == k, F.lit(float(v))) for k, v in given.items()), F.lit(0.0))
            cells = cells.withColumn(f"t_{axis}", named)
        else:
            cells = _with_total(cells, tokens, (axis,), "here", wide)
            raw = F.pow(F.col("here") / F.col("all"), F.lit(power)) * tokens / F.col("here")
            cells = cells.withColumn("raw", F.when(tokens > 0, raw).otherwise(0.0)).drop("here")
            cells = _with_total(_with_total(cells, F.col("raw"), (axis,), "of_axis", wide), F.col("raw"), (), "of_all", wide)
            cells = cells.withColumn(f"t_{axis}", F.when(F.col("of_all") > 0, F.col("of_axis") / F.col("of_all")).otherwise(0.0)).drop("raw", "of_axis", "of_all")
    cells = rest(cells.withColumn("w", tokens))
    for _ in range(params.sweeps):
        for axis in AXES:
            cells = _with_total(cells, F.col("w"), (axis,), "total", wide)
            cells = cells.withColumn("w", F.when(F.col("total") > 0, F.col("w") * F.col(f"t_{axis}") / F.col("total")).otherwise(0.0)).drop("total")
        cells = rest(cells)
    cells = _with_total(cells, F.col("w"), (), "fitted", wide)
    cells = cells.withColumn("ratio", F.when((tokens > 0) & (F.col("fitted") > 0), F.col("w") / F.col("fitted") / (tokens / F.col("all"))).otherwise(1.0))
    cells = cells.withColumn("keep_p", F.least(F.lit(1.0), F.col("ratio") * params.budget))
    for _ in range(params.fills):  # raise the factor until the uncapped cells make up for the capped ones
        cells = _with_total(cells, F.col("keep_p") * tokens, (), "sum", wide)
        scale = F.when(F.col("sum") > 0, params.budget * F.col("all") / F.col("sum")).otherwise(1.0)
        cells = rest(cells.withColumn("keep_p", F.least(F.lit(1.0), F.col("keep_p") * scale)).drop("sum"))
    return cells.select(*AXES, "tokens", "ratio", "keep_p")


def mix(docs: DataFrame, params: Params = Params()) -> DataFrame:
    """``docs`` with topic, tokens, keep_p and kept."""
    marked = with_cells(docs)
    counted = settle(marked.groupBy(*(F.col(f"__{a}").alias(a) for a in AXES)).agg(F.sum("__tokens").alias("tokens")))
    small = counted.count() <= params.max_cells
    cells = settle(fit_cells(counted.coalesce(1).sortWithinPartitions(*AXES) if small else counted, params, not small))
    cells = cells.select(*(F.col(a).alias(f"__{a}") for a in AXES), F.col("keep_p").alias("__p"))
    drawn = F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0
    out = marked.join(F.broadcast(cells) if small else cells, [f"__{a}" for a in AXES])
    out = out.withColumns({"topic": F.col("__topic"), "tokens": F.col("__tokens").cast("long"), "kept": F.coalesce(drawn < F.col("__p"), F.lit(False)), "keep_p": F.round("__p", 6)})
    return out.drop(*(f"__{a}" for a in AXES), "__tokens", "__p")


def op10_raked_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mix(table(spark, sf_dir, "documents").select("doc_id", "text", "source", "lang"))
    return out.select("doc_id", "source", "lang", "topic", "tokens", "keep_p", "kept")


def oracle(params: Params = Params()) -> str:
    """The same computation for DuckDB, built from the same parameters."""
    topic = "CASE " + " ".join(f"WHEN {p} THEN '{n}'" for n, p in TOPICS) + " ELSE 'prose' END"
    steps = [
        f"""d AS (SELECT doc_id, source AS src, lang AS lng, coalesce(source, 'unknown') AS source, coalesce(lang, 'unknown') AS lang, {topic} AS topic,
        coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::DOUBLE AS tokens FROM documents)""",
        "c0 AS (SELECT source, lang, topic, sum(tokens) AS tokens FROM d GROUP BY ALL)",
    ]
    now = "c0"
    for k, (axis, power) in enumerate(zip(AXES, params.temper, strict=True)):
        steps.append(f"r{k} AS (SELECT *, CASE WHEN tokens > 0 THEN pow(sum(tokens) OVER (PARTITION BY {axis}) / sum(tokens) OVER (), {power}) * tokens / sum(tokens) OVER (PARTITION BY {axis}) ELSE 0 END AS raw FROM {now})")
        steps.append(f"t{k} AS (SELECT * EXCLUDE (raw), sum(raw) OVER (PARTITION BY {axis}) / sum(raw) OVER () AS t_{axis} FROM r{k})")
        now = f"t{k}"
    steps.append(f"w AS (SELECT *, tokens AS w FROM {now})")
    now = "w"
    for k in range(params.sweeps):
        for axis in AXES:
            steps.append(f"w{k}{axis} AS MATERIALIZED (SELECT * REPLACE (CASE WHEN sum(w) OVER (PARTITION BY {axis}) > 0 THEN w * t_{axis} / sum(w) OVER (PARTITION BY {axis}) ELSE 0 END AS w) FROM {now})")
            now = f"w{k}{axis}"
    steps.append(f"q AS (SELECT *, CASE WHEN tokens > 0 AND sum(w) OVER () > 0 THEN w / sum(w) OVER () / (tokens / sum(tokens) OVER ()) ELSE 1 END AS ratio FROM {now})")
    steps.append(f"p AS (SELECT *, least(1.0::DOUBLE, ratio * {params.budget}) AS keep_p FROM q)")
    now = "p"
    for k in range(params.fills):
        steps.append(f"p{k} AS MATERIALIZED (SELECT * REPLACE (least(1.0::DOUBLE, keep_p * CASE WHEN sum(keep_p * tokens) OVER () > 0 THEN {params.budget} * sum(tokens) OVER () / sum(keep_p * tokens) OVER () ELSE 1 END) AS keep_p) FROM {now})")
        now = f"p{k}"
    return "WITH " + ",\n".join(steps) + f"""
SELECT doc_id, src AS source, lng AS lang, topic, d.tokens::BIGINT AS tokens, round(keep_p, 6) AS keep_p,
       ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0::DOUBLE < keep_p AS kept
FROM d JOIN {now} USING (source, lang, topic)"""
