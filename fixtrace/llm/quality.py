"""Quality classifier: document statistics, random Fourier features, ridge, isotonic calibration.

``statistics`` turns a whole text into a fixed vector (one Arrow pass, no shuffle).  ``fit`` joins a bounded
labelled sample, broadcast, to its texts, draws random Fourier features that approximate a Gaussian kernel over the standardised statistics, sums the
normal equations partition by partition, solves the ridge system on the driver (its size depends only on the
number of features) and calibrates raw scores by pool-adjacent-violators over a fixed number of score bins that
Spark aggregates.  ``score`` applies the model in one Arrow pass.

Defined results: null and empty texts have all-zero counts and still get a score; a repeated row is scored like
its twin; null labels are not learned from, and of several labels of one ``doc_id`` the mean is; with no labelled row at
all every score is the prior 0.5, and without rows to calibrate by, the ridge score cut to 0 .. 1.  Only ``doc_id``
and ``text`` are read, so extra columns cannot clash.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.llm.common import by_batch, held_out, settle, table
from fixtrace.llm.textkit import spans, windows, word_hashes

#: Byte classes: 0 other, 1 upper, 2 lower, 3 digit, 4 space, 5 line feed, 6 sentence mark, 7 shout, 8 symbol,
#: 9 pipe, 10 non-ASCII, 11 bracket or quote.
_CLASS = np.zeros(256, np.uint8)
_CLASS[65:91], _CLASS[97:123], _CLASS[48:58], _CLASS[128:] = 1, 2, 3, 10
for _k, _chars in ((4, b" \t\r\x0b\x0c"), (5, b"\n"), (6, b".,;:"), (7, b"!?"), (8, b"#*$%&<>@~^=+_/\\"), (9, b"|"), (11, b"()[]{}'\"`")):
    _CLASS[list(_chars)] = _k

STATISTICS = (
    "log_bytes", "log_words", "log_lines", "upper", "digit", "blank", "sentence", "shout", "symbol", "pipe", "wide",
    "bracket", "mean_word", "sd_word", "short_words", "long_words", "distinct", "top_word", "repeats", "marked_ends",
    "capital_starts", "line_words", "short_lines", "repeated_lines",
)


def statistics(text: str | None) -> list[float]:
    """The statistics of one text, in the order of ``STATISTICS``; shares lie in [0, 1]."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    if not raw:
        return [0.0] * len(STATISTICS)
    a = np.frombuffer(raw, np.uint8)
    n = len(a)
    kind = _CLASS[a]
    count = np.bincount(kind, minlength=12) / n
    begin, end = spans(a)
    lines = raw.split(b"\n")
    m = len(begin)
    if not m:
        return [np.log1p(n), 0.0, np.log1p(len(lines)), *count[[1, 3, 4, 6, 7, 8, 9, 10, 11]], *[0.0] * 12]
    length = end - begin
    words = word_hashes(raw)
    seen, times = np.unique(words, return_counts=True)
    three = windows(words, 3)
    filled = [x for x in lines if x.strip()]
    return [
        np.log1p(n), np.log1p(m), np.log1p(len(lines)), *count[[1, 3, 4, 6, 7, 8, 9, 10, 11]],
        float(length.mean()), float(length.std()), float((length <= 2).mean()), float((length >= 12).mean()),
        len(seen) / m, float(times.max()) / m, 1 - len(np.unique(three)) / len(three) if len(three) else 0.0,
        float(np.isin(kind[end - 1], (6, 7, 8, 9)).mean()), float((kind[begin] == 1).mean()),
        float(np.log1p(m / max(len(filled), 1))), sum(len(x) < 30 for x in filled) / max(len(filled), 1),
        1 - len(set(filled)) / max(len(filled), 1),
    ]


def batch_stats(batch: pa.RecordBatch) -> np.ndarray:
    return np.array([statistics(x.as_py()) for x in batch.column("text")], np.float64).reshape(batch.num_rows, len(STATISTICS))


def text_stats(docs: DataFrame) -> DataFrame:
    """doc_id, ``y`` and ``stats``, one row for each labelled document."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = pa.array(batch_stats(batch).tolist(), pa.list_(pa.float64()))
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("y"), found], ["doc_id", "y", "stats"])

    return docs.select("doc_id", "y", "text").mapInArrow(by_batch(kernel), "doc_id bigint, y double, stats array<double>")


@dataclass(frozen=True)
class Params:
    """``max_rows`` bounds the labelled sample that is learned from; the bound holds at every size."""

    features: int = 192
    gamma: float = 0.02
    ridge: float = 1e-3
    bins: int = 512
    max_rows: int = 40_000
    seed: int = 11
    threshold: float = 0.3


@dataclass(frozen=True)
class Model:
    mean: np.ndarray
    scale: np.ndarray
    omega: np.ndarray
    phase: np.ndarray
    weight: np.ndarray
    knots: np.ndarray
    levels: np.ndarray
    slope: float = 0.002

    def features(self, stats: np.ndarray) -> np.ndarray:
        x = np.clip((stats - self.mean) / self.scale, -6, 6)
        return np.hstack([np.cos(x @ self.omega + self.phase) * np.sqrt(2 / len(self.phase)), x, np.ones((len(x), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return np.clip(self.features(stats) @ self.weight, -1, 2)

    def calibrated(self, raw: np.ndarray) -> np.ndarray:
        """Isotonic level plus a slight slope, so that ties within a level keep the ridge order."""
        return (1 - self.slope) * np.interp(raw, self.knots, self.levels) + self.slope * (raw + 1) / 3


def pool_adjacent(y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Weighted isotonic regression of ``y``, in the order given."""
    blocks: list[list[float]] = []
    for value, w in zip(y, weight, strict=True):
        blocks.append([value, w, 1])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            v, w2, n = blocks.pop()
            b = blocks[-1]
            blocks[-1] = [(b[0] * b[1] + v * w2) / (b[1] + w2), b[1] + w2, b[2] + n]
    return np.concatenate([np.full(n, v) for v, _, n in blocks])


def spark_sample(sample: DataFrame, max_rows: int) -> DataFrame:
    """The sample, settled; broadcasting it is safe only while it holds about ``max_rows`` rows."""
    sample = settle(sample)
    if (n := sample.count()) > 1.2 * max_rows + 1000:
        raise RuntimeError(f"a sample of {n} labelled rows is over the bound of {max_rows}")
    return sample


def _stack(batch: pa.RecordBatch, name: str) -> np.ndarray:
    return batch.column(name).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)


def fit(docs: DataFrame, labels: DataFrame, params: Params = Params()) -> Model:
    """Learn from rows of ``labels`` that are not held out; one fifth of the ids calibrates, the rest fits."""
    d = len(STATISTICS)
    known = labels.select(F.col("doc_id"), F.col("quality").cast("double").alias("y")).where("doc_id is not null and y is not null")
    known = settle(known.where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.avg("y").alias("y")))
    share = min(1.0, params.max_rows / max(known.count(), 1))
    sample = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(share * 1_000_000))
    sample = spark_sample(sample, params.max_rows)
    rows = settle(text_stats(docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")))
    rows = rows.withColumn("calibrates", F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 1).coalesce(16)
    moments = rows.agg(F.count("*").alias("n"), *(f(F.col("stats")[k]).alias(f"{a}{k}") for k in range(d) for a, f in (("m", F.avg), ("s", F.stddev_pop)))).first()
    rng = np.random.default_rng(params.seed)
    omega, phase = rng.normal(0, np.sqrt(2 * params.gamma), (d, params.features)), rng.uniform(0, 2 * np.pi, params.features)
    mean, scale = (np.array([moments[f"{a}{k}"] or 0.0 for k in range(d)]) for a in "ms")
    model = Model(mean, np.where(scale > 1e-9, scale, 1.0), omega, phase, np.zeros(params.features + d + 1), np.array([-1.0, 2.0]), np.array([0.5, 0.5]), 0.0)
    if not moments["n"]:
        return model
    wide = params.features + d + 1

    def partial(batches):
        gram, moment = np.zeros((wide, wide)), np.zeros(wide)
        for batch in batches:
            if batch.num_rows:
                z, y = model.features(_stack(batch, "stats")), batch.column("y").to_numpy()
                gram += z.T @ z
                moment += z.T @ y
        yield pa.RecordBatch.from_arrays([pa.array([gram.tobytes()]), pa.array([moment.tobytes()])], ["gram", "moment"])

    gram, moment = np.zeros((wide, wide)), np.zeros(wide)
    for r in rows.where("not calibrates").select("stats", "y").mapInArrow(partial, "gram binary, moment binary").toLocalIterator():
        gram += np.frombuffer(r.gram).reshape(wide, wide)
        moment += np.frombuffer(r.moment)
    penalty = np.full(wide, params.ridge * max(gram[-1, -1], 1.0))
    penalty[-1] = 1e-6
    model = Model(model.mean, model.scale, omega, phase, np.linalg.solve(gram + np.diag(penalty), moment), np.array([0.0, 1.0]), np.array([0.0, 1.0]))

    def bin_of(batch: pa.RecordBatch) -> pa.RecordBatch:
        at = np.floor((model.raw(_stack(batch, "stats")) + 1) / 3 * params.bins).astype(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(at), batch.column("y")], ["bin", "y"])

    binned = rows.where("calibrates").select("stats", "y").mapInArrow(by_batch(bin_of), "bin bigint, y double")
    found = sorted(binned.groupBy("bin").agg(F.sum("y").alias("y"), F.count("*").alias("n")).collect())
    if not found:
        return model
    at, y, n = (np.array(x, float) for x in zip(*found, strict=True))
    return Model(model.mean, model.scale, omega, phase, model.weight, (at + 0.5) / params.bins * 3 - 1, pool_adjacent((y + 0.5) / (n + 1), n))


def score(docs: DataFrame, model: Model, params: Params = Params()) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of ``docs``, in one pass."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        s = model.calibrated(model.raw(batch_stats(batch)))
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.clip(s, 0, 1))], ["doc_id", "score"])

    out = docs.select("doc_id", "text").mapInArrow(by_batch(kernel), "doc_id bigint, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= params.threshold).cast("int").alias("predicted"))


def keep(docs: DataFrame, model: Model, params: Params = Params()) -> DataFrame:
    """The rows of ``docs``, columns as they are, that score at least the threshold; texts are not shuffled."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        return batch.filter(pa.array(model.calibrated(model.raw(batch_stats(batch))) >= params.threshold))

    return docs.mapInArrow(by_batch(kernel), docs.schema)


def classify(docs: DataFrame, labels: DataFrame, params: Params = Params()) -> DataFrame:
    """Score every document with a model learned from the labelled ones."""
    return score(docs, fit(docs, labels, params), params)


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
