"""The corpus pipeline: five stages over ``documents``, each built on one operator of ``fixtrace.llm``.

Every stage but the last returns the columns of ``documents``; rows that it rejects are gone, texts that it edits
are the next stage's texts.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.llm import common, lines, mixing, ngrams, packing, pick, quality

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    docs = docs.select(*COLUMNS)
    return quality.keep(docs, quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that five documents share stay in the largest doc_id only."""
    out = lines.drop_lines(docs.select(*COLUMNS))
    return out.withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five words, 0.8) the smallest doc_id stays."""
    docs = docs.select(*COLUMNS)
    copies = common.settle(ngrams.link(docs).where("doc_id <> component_id").select("doc_id").distinct())
    return pick.leave(docs, copies).select(*COLUMNS)


def mixing_to_targets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are sampled by the calibrated probability of their cell."""
    return mixing.mix(docs.select(*COLUMNS)).where("kept").select(*COLUMNS)


def multi_length_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences."""
    return packing.pack(docs)


STAGES = [
    ("quality classifier", quality_classifier),
    ("line dedup", line_dedup),
    ("n-gram Jaccard join", ngram_jaccard_join),
    ("mixing sources to target weights", mixing_to_targets),
    ("packing", multi_length_packing),
]
#: Tokenising and the classifier cannot be said in SQL; the tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's rows are written once to the shared folder and reread; the folder of the stage before goes then."""
    docs, held = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    base = f"{common.shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES[:-1]):
        path = f"{base}/{k}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if held:
            common.remove(spark, held)
        held = path
    return STAGES[-1][1](spark, docs, sf_dir)
