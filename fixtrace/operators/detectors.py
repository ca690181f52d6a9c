"""Clone detectors on statement changes, for comparison at their own best thresholds.

``pairs``: distinct (pre, post, repo_id, same) with ``n``, how often each occurs; ``same`` tells whether the change
kept the statement.  Each detector gives a similarity in [0, 1] of distinct text pairs; ``at_thresholds`` turns
similarities into counts on a grid, so no text pair is compared twice however often it occurs.
"""

from __future__ import annotations

import functools
import hashlib
import math
import zlib
from collections import Counter
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.functions import ctree
from fixtrace.functions.store import settle
from fixtrace.functions.text import line_similarity, squash
from fixtrace.operators.extraction import dependence
from fixtrace.operators.measures import rates

GRID = tuple(k / 10 for k in range(1, 11))
TREE_BUCKETS, FLOW_BUCKETS = 48, 16


def once(pairs: DataFrame) -> DataFrame:
    return pairs.select("pre", "post").distinct()


def edit(pairs: DataFrame) -> DataFrame:
    """(pre, post, similarity) by edit distance."""
    return once(pairs).withColumn("similarity", line_similarity(squash(F.col("pre")), squash(F.col("post"))))


def md5(pairs: DataFrame) -> DataFrame:
    """Share of equal statement digests, statements split at semicolons and braces."""
    return with_digests(once(pairs), "similarity")


def with_digests(rows: DataFrame, name: str) -> DataFrame:
    parts = lambda c: F.transform(F.filter(F.split(squash(F.col(c)), r"[;{}]"), lambda x: F.trim(x) != ""), lambda x: F.md5(F.trim(x).cast("binary")))
    share = F.size(F.array_intersect("__p", "__q")) / F.greatest(F.size(F.array_union("__p", "__q")), F.lit(1))
    return rows.withColumns({"__p": parts("pre"), "__q": parts("post")}).withColumn(name, share).drop("__p", "__q")


def _grams(text: str) -> Counter:
    return Counter(text[k : k + 3] for k in range(len(text) - 2))


def _cosines(pre: pa.Array, post: pa.Array) -> pa.Array:
    out = []
    for a, b in zip(pre.to_pylist(), post.to_pylist(), strict=True):
        p, q = _grams(a or ""), _grams(b or "")
        few, many = (p, q) if len(p) <= len(q) else (q, p)
        dot = sum(n * many.get(g, 0) for g, n in few.items())
        out.append(dot / (math.sqrt(sum(n * n for n in p.values())) * math.sqrt(sum(n * n for n in q.values()))) if dot else 0.0)
    return pa.array(out, pa.float64())


def cosine() -> Column:
    """Cosine of the character-trigram counts of ``pre`` and ``post``."""
    return F.arrow_udf(_cosines, "double")(squash(F.col("pre")), squash(F.col("post")))


def vector(pairs: DataFrame) -> DataFrame:
    """Cosine of sparse character-trigram counts; a stand-in for learned embeddings, which need a model.

    A pair is told in one place: no trigram is a row.
    """
    return once(pairs).withColumn("similarity", cosine())


def tree(pairs: DataFrame, sims: DataFrame) -> DataFrame:
    """The tree level alone; 0 where a text does not parse."""
    return once(pairs).join(sims, ["pre", "post"]).select("pre", "post", F.coalesce("sim_b", F.lit(0.0)).alias("similarity"))


def two_level(pairs: DataFrame, sims: DataFrame) -> DataFrame:
    """The greater of line and tree similarity."""
    return once(pairs).join(sims, ["pre", "post"]).select("pre", "post", F.greatest("sim_a", F.coalesce("sim_b", F.lit(0.0))).alias("similarity"))


def by_text(pairs: DataFrame, sims: DataFrame) -> DataFrame:
    """(detector, repo_id, same, n, similarity) of the five detectors that compare texts, joined to the changes once.

    ``sims``: pre, post, sim_a, sim_b of each distinct pair, both levels everywhere.
    """
    told = with_digests(sims.select("pre", "post", F.col("sim_a").alias("edit"), F.coalesce("sim_b", F.lit(0.0)).alias("tree")), "md5").withColumn("vector", cosine())
    met = pairs.join(told.withColumn("two_level", F.greatest("edit", "tree")), ["pre", "post"])
    each = F.array(*(F.struct(F.lit(d).alias("detector"), F.col(d).alias("similarity")) for d in ("edit", "md5", "vector", "tree", "two_level")))
    return met.select("repo_id", "same", "n", F.explode(each).alias("x")).select("x.detector", "repo_id", "same", "n", "x.similarity")


@functools.lru_cache(maxsize=50_000)
def _tree_counts(text: str) -> tuple[tuple[int, int], ...]:
    """Counts of hashed (parent, child) labels of a statement; names and constants are told by kind only."""
    out: dict[int, int] = {}
    plain = lambda t: t[0].partition(":")[0]

    def walk(t: tuple) -> None:
        for x in t[1:]:
            at = zlib.crc32(f"{plain(t)}>{plain(x)}".encode()) % TREE_BUCKETS
            out[at] = out.get(at, 0) + 1
            walk(x)

    try:
        walk(ctree.parse(text))
    except (ctree.Unparsed, RecursionError):
        pass
    return tuple(out.items())


@functools.lru_cache(maxsize=100_000)
def _counts(lines: tuple[str, ...]) -> tuple[int, ...]:
    """Fused features of a whole function: its tree edges by label, its flow edges (control and data) by statement kind.

    Nothing in them depends on the value of a number, so lines come with plain ones and a function is seen again.
    """
    out = [0] * (TREE_BUCKETS + FLOW_BUCKETS)
    for text in lines:
        for at, n in _tree_counts(text):
            out[at] += n
    stmts, edges = dependence(list(enumerate(lines)))
    for a, b, kind, _ in edges:
        out[TREE_BUCKETS + zlib.crc32(f"{kind}:{stmts[a]['kind']}>{stmts[b]['kind']}".encode()) % FLOW_BUCKETS] += 1
    for s in stmts.values():
        out[TREE_BUCKETS + zlib.crc32(s["kind"].encode()) % FLOW_BUCKETS] += 1
    return tuple(out)


def function_features(lines: list[str]) -> tuple[int, ...]:
    return _counts(tuple(map(ctree.plain_numbers, lines)))


@functools.lru_cache(maxsize=100_000)
def _apart(before: tuple[str, ...], after: tuple[str, ...]) -> tuple[list[int], float]:
    """Where the features of two functions differ and by how much (place, difference, place, ...), and the share they have in common."""
    p, q = _counts(before), _counts(after)
    changed = [v for k, (x, y) in enumerate(zip(p, q, strict=True)) if x != y for v in (k, abs(x - y))]
    return changed, sum(map(min, p, q)) / max(sum(p), sum(q), 1)


def function_changes(events: DataFrame) -> DataFrame:
    """(repo_id, same, draw, digest, changed, share, n): distinct changes of whole functions with what their features have apart.

    ``events``: file_id, pos, kind, slot, text, post, same, draw.  Kind 0: from ``pos`` on the slot holds ``text``.
    Kind 1: a change of the slot from ``text`` to ``post``, the other slots as they are at ``pos``.  A file is read once
    in order with one text held for each slot; ``digest`` is of the whole function before and after.
    """

    def run(batches):
        file, held, numbered = None, {}, functools.lru_cache(maxsize=50_000)(ctree.plain_numbers)
        for b in batches:
            out: list[list] = [[] for _ in range(6)]
            for at, kind, slot, text, post, same, draw in zip(*(b.column(c).to_pylist() for c in ("file_id", "kind", "slot", "text", "post", "same", "draw")), strict=True):
                if at != file:
                    file, held = at, {}
                if kind == 0:
                    if text is not None:
                        held[slot] = text
                    continue
                rest = sorted(k for k in held if k != slot)
                own = sum(k < slot for k in rest)
                lines = [held[k] for k in rest]
                whole = [[*lines[:own], x or "", *lines[own:]] for x in (text, post)]
                changed, share = _apart(*(tuple(map(numbered, x)) for x in whole))
                told = "\0".join(["\0".join(x) for x in whole] + [str(len(s)) for x in whole for s in x])
                for column, v in zip(out, (at // 1000, same, draw, hashlib.blake2b(told.encode("utf-8", "surrogatepass"), digest_size=16).digest(), changed, share), strict=True):
                    column.append(v)
            kinds = (pa.int32(), pa.bool_(), pa.int64(), pa.binary(), pa.list_(pa.int32()), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], ["repo_id", "same", "draw", "digest", "changed", "share"])

    order = events.select("file_id", "pos", "kind", "slot", "text", "post", "same", "draw").repartition("file_id").sortWithinPartitions("file_id", "pos", "kind", "slot")
    rows = order.mapInArrow(run, "repo_id int, same boolean, draw long, digest binary, changed array<int>, share double")
    return rows.groupBy("repo_id", "same", "draw", "digest", "changed", "share").agg(F.count("*").alias("n"))


class _Net:
    """A classifier of two classes with one hidden layer, learned by L-BFGS from all rows, equal ones once with their number.

    ``slopes`` gives loss and slope, each a sum over rows, of any batch; whoever holds the rows adds them up.
    """

    def __init__(self, inputs: int, hidden: int = 16, seed: int = 3):
        self.shapes = ((inputs, hidden), (hidden,), (hidden, 2), (2,))
        draw = np.random.default_rng(seed)
        self.start = np.concatenate([draw.normal(0, s[0] ** -0.5, s).ravel() if len(s) == 2 else np.zeros(s) for s in self.shapes])

    def _parts(self, flat: np.ndarray) -> list[np.ndarray]:
        ends = np.cumsum([math.prod(s) for s in self.shapes])
        return [x.reshape(s) for x, s in zip(np.split(flat, ends[:-1]), self.shapes, strict=True)]

    def _forward(self, flat: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, b, c, d = self._parts(flat)
        hidden = 1 / (1 + np.exp(-np.clip(x @ a + b, -500, 500)))
        out = hidden @ c + d
        return hidden, out - np.logaddexp(out[:, :1], out[:, 1:])

    def scores(self, flat: np.ndarray, x: np.ndarray) -> np.ndarray:
        return np.exp(self._forward(flat, x)[1][:, 1])

    def slopes(self, flat: np.ndarray, x: np.ndarray, label: np.ndarray, n: np.ndarray) -> np.ndarray:
        hidden, logs = self._forward(flat, x)
        hit = np.stack([1 - label, label], axis=1)
        off = (np.exp(logs) - hit) * n[:, None]
        back = (off @ self._parts(flat)[2].T) * hidden * (1 - hidden)
        return np.concatenate([[-(hit * logs).sum(axis=1) @ n], (x.T @ back).ravel(), back.sum(axis=0), (hidden.T @ off).ravel(), off.sum(axis=0)])

    def learn(self, summed: Callable[[np.ndarray], np.ndarray], total: float, rounds: int = 80, near: float = 1e-6, memory: int = 10) -> np.ndarray:
        """The weights found; ``summed`` gives ``slopes`` of given weights over all rows, whose number is ``total``."""
        at, past = self.start, []
        now = summed(at) / total
        for _ in range(rounds):
            loss, slope = now[0], now[1:]
            way, steps = slope.copy(), []
            for s, y in reversed(past):
                steps.append((s @ way) / (s @ y))
                way -= steps[-1] * y
            if past:
                way *= (past[-1][0] @ past[-1][1]) / (past[-1][1] @ past[-1][1])
            for (s, y), k in zip(past, reversed(steps), strict=True):
                way += s * (k - (y @ way) / (s @ y))
            fall, size = -(slope @ way), 1.0 if past else min(1.0, 1 / max(np.abs(slope).sum(), 1e-12))
            for _ in range(20):
                ahead = summed(at - size * way) / total
                if ahead[0] <= loss + 1e-4 * size * fall:
                    break
                size /= 2
            else:
                break
            moved, turned = -size * way, ahead[1:] - slope
            if moved @ turned > 1e-12 * (turned @ turned):
                past = [*past, (moved, turned)][-memory:]
            at, now = at + moved, ahead
            if abs(loss - now[0]) <= near * max(abs(loss), abs(now[0]), near):
                break
        return at


def _dense(batch: pa.RecordBatch) -> np.ndarray:
    """The features of a batch: a column for the difference in each place, and the share in common."""
    changed = batch.column("changed")
    out = np.zeros((len(batch), TREE_BUCKETS + FLOW_BUCKETS + 1))
    pairs = changed.flatten().to_numpy(zero_copy_only=False).reshape(-1, 2)
    row = np.repeat(np.arange(len(batch)), pa.compute.list_value_length(changed).to_numpy(zero_copy_only=False) // 2)
    out[row, pairs[:, 0]] = np.log1p(pairs[:, 1].astype(float))
    out[:, -1] = batch.column("share").to_numpy(zero_copy_only=False)
    return out


def function_model(functions: DataFrame, seed: int = 3, held: int = 50_000) -> DataFrame:
    """(repo_id, same, n, similarity) of whole functions before and after a change.

    ``functions``: as ``function_changes`` gives them.  A neural classifier over fused tree and flow features, learned
    from every row of the even repositories, scores all rows; equal features are read once with their number, about
    ``held`` of them in a task.
    """
    rows = settle(functions.groupBy("repo_id", "same", "changed", "share").agg(F.sum("n").alias("n"), F.count("*").alias("rows")))
    learned = rows.where("repo_id % 2 = 0").groupBy("changed", "share", F.col("same").cast("double").alias("label")).agg(F.sum("rows").cast("double").alias("n"))
    learned = settle(learned)
    total, kinds = learned.agg(F.sum("n"), F.count("*")).first()
    # summed in one order, however the rows were cut before
    learned = settle(learned.repartition(kinds // held + 1, "changed", "share").sortWithinPartitions("changed", "share", "label"))
    net = _Net(TREE_BUCKETS + FLOW_BUCKETS + 1, seed=seed)

    def summed(flat: np.ndarray) -> np.ndarray:
        def run(batches):
            found = 0.0
            for b in batches:
                found = found + net.slopes(flat, _dense(b), *(b.column(c).to_numpy(zero_copy_only=False) for c in ("label", "n")))
            if np.ndim(found):
                yield pa.RecordBatch.from_arrays([pa.array([found.tolist()], pa.list_(pa.float64()))], ["found"])

        return np.sum([r.found for r in learned.mapInArrow(run, "found array<double>").collect()], axis=0)

    flat = net.learn(summed, total) if total else net.start

    def scored(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("repo_id", "same", "n")), pa.array(net.scores(flat, _dense(b)))], ["repo_id", "same", "n", "similarity"])

    return rows.select("repo_id", "same", "n", "changed", "share").mapInArrow(scored, "repo_id int, same boolean, n long, similarity double")


def weighed(pairs: DataFrame, scored: DataFrame) -> DataFrame:
    """The rows of ``pairs`` with the similarity of their texts."""
    return pairs.join(scored, ["pre", "post"])


def at_thresholds(rows: DataFrame, by: list[str]) -> DataFrame:
    """tp, fp, fn and rates of ``similarity >= theta`` against ``same`` for each theta of the grid."""
    reached = functools.reduce(Column.__add__, ((F.round(F.col("similarity"), 6) >= t).cast("int") for t in GRID))
    levels = rows.groupBy(*by, "same", reached.alias("reached")).agg(F.sum("n").alias("n"))  # thresholds ascend, so a row reaches the first few
    points = levels.select(*by, "same", "reached", "n", F.posexplode(F.array(*map(F.lit, GRID))).alias("k", "theta"))
    hit = F.col("reached") > F.col("k")
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0))
    return rates(points.groupBy(*by, "theta").agg(total(hit & F.col("same")).alias("tp"), total(hit & ~F.col("same")).alias("fp"), total(~hit & F.col("same")).alias("fn")))


def compared(rows: DataFrame) -> DataFrame:
    """Scores of each detector on odd repositories, with ``best`` at the threshold that even repositories chose.

    ``rows``: detector, repo_id, same, n, similarity.
    """
    found = settle(at_thresholds(rows.withColumn("odd", F.col("repo_id") % 2 == 1), ["detector", "odd"]))
    first = F.row_number().over(W.partitionBy("detector").orderBy(F.desc_nulls_last("f1"), "theta")) == 1
    chosen = found.where("not odd").withColumn("best", first).select("detector", "theta", "best")
    return found.where("odd").join(chosen, ["detector", "theta"]).drop("odd")
