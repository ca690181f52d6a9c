"""Near-duplicate embeddings: spherical k-means cells, blocked cosine products, one representative per group.

Equal vectors collapse to one representative first (told by two 64-bit hashes), so copies cost nothing further.
Centroids are fitted on a bounded sample; every vector lives in its nearest cell and also visits some of
its nearest ones, and a pair is compared in each cell where one of the two lives.  Cells are cut into blocks of a
bounded size by hash, and each pair of blocks is one matrix product in a task of its own, so a hot cell is spread.
A pair that two cells see is counted in the lower-numbered one only.  Blocks return link counts and a spanning
forest, never pairs.

Recall: a pair is missed only if neither vector visits the other's cell.  A fixed number of probes would miss more
with more cells, so beyond 50 cells probes grow with the cells (``probe_count``).  Visits, and with them shuffled
rows, grow alike.  On unit vectors drawn at random in 64 dimensions, a hard case, at least 99.6 % of pairs at cosine
0.9 were found with 50 to 8,192 cells; the tests measure recall against brute force and with many cells.

Defined results: a vector that is null, empty, zero or has null or non-finite components links with nothing and is
kept; any other is compared, however large or small its components; vectors of different lengths never link; repeated rows of one ``vec_id`` are copies of each other; an empty
table gives no rows.  Only ``vec_id`` and ``embedding`` are read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.llm.common import look_up, settle, table
from fixtrace.llm.components import components


@dataclass(frozen=True)
class Params:
    """``sample_rows`` bounds only the sample the centroids are fitted on; every row is indexed and compared.

    ``probes`` holds for up to 50 cells.
    """

    threshold: float = 0.9
    probes: int = 8
    cell_rows: int = 2000
    max_cells: int = 8192
    sample_rows: int = 20_000
    rounds: int = 8
    block_rows: int = 4096
    seed: int = 5


def probe_count(cells: int, params: Params) -> int:
    """Cells that a vector visits: the power that keeps recall level, found by measuring from 50 to 8,192 cells."""
    return min(cells, math.ceil(params.probes * max(1.0, cells / 50) ** 0.375))


def unit(x: np.ndarray) -> np.ndarray:
    """Rows at length one; scaled by their greatest component first, so that no square leaves the range of doubles."""
    x = x / np.abs(x).max(1)[:, None]
    return x / np.linalg.norm(x, axis=1)[:, None]


def spherical_kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    """Unit centroids of unit rows; a cell that empties keeps its centroid."""
    rng = np.random.default_rng(seed)
    centre = x[np.sort(rng.choice(len(x), min(k, len(x)), replace=False))].copy()
    for _ in range(rounds):
        near = np.concatenate([(x[s : s + 4096] @ centre.T).argmax(1) for s in range(0, len(x), 4096)])
        total = np.zeros_like(centre)
        np.add.at(total, near, x)
        size = np.linalg.norm(total, axis=1)
        centre = np.where(size[:, None] > 1e-12, total / np.maximum(size, 1e-12)[:, None], centre)
    return centre


def _compare(a: np.ndarray, meta_a: dict, b: np.ndarray, meta_b: dict, cell: int, same: bool, threshold: float):
    """Link counts of both blocks and a local component label of every row that links."""
    na = len(a)
    counts = np.zeros(na if same else na + len(b), np.int64)
    label = np.arange(len(counts))
    shift = 0 if same else na
    for at in range(0, na, 512):
        hit = a[at : at + 512] @ b.T >= threshold
        i, j = np.nonzero(hit)
        i += at
        if same:
            i, j = i[i < j], j[i < j]
        home_a, home_b = meta_a["home"][i], meta_b["home"][j]
        lives_a, lives_b = home_a == cell, home_b == cell
        a_sees = (meta_a["probes"][i] == home_b[:, None]).any(1)  # a visits the cell b lives in
        b_sees = (meta_b["probes"][j] == home_a[:, None]).any(1)
        ok = lives_a & lives_b | lives_a & ~lives_b & (~a_sees | (cell < home_b)) | lives_b & ~lives_a & (~b_sees | (cell < home_a))
        i, j = i[ok], j[ok]
        np.add.at(counts, i, meta_b["copies"][j])
        np.add.at(counts, j + shift, meta_a["copies"][i])
        if len(i):
            order = np.argsort(i, kind="stable")
            i, j = i[order], j[order] + shift
            first = np.flatnonzero(np.diff(i, prepend=-1))
            for s, e in zip(first, [*first[1:], len(i)], strict=True):
                found = np.unique(np.append(label[j[s:e]], label[i[s]]))
                if len(found) > 1:
                    label[np.isin(label, found)] = found[0]
    return counts, label


def link(vectors: DataFrame, params: Params = Params()) -> DataFrame:
    """vec_id, n_links, component_id and kept for each row of ``vectors``."""
    spark = vectors.sparkSession
    e = F.col("embedding").cast("array<double>")
    fine = F.coalesce(
        (F.size(e) > 0) & F.forall(e, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists(e, lambda v: v != 0), F.lit(False)
    )
    rows = vectors.select("vec_id", e.alias("e"), fine.alias("fine"))
    keyed = rows.select("vec_id", F.when(F.col("fine"), F.xxhash64("e")).alias("h1"), F.when(F.col("fine"), F.xxhash64(F.lit(3), "e")).alias("h2"), F.when(F.col("fine"), F.col("e")).alias("e"))
    reps = settle(keyed.where("h1 is not null").groupBy("h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.any_value("e").alias("e")))
    sized = reps.groupBy(F.size("e").alias("d")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "d").limit(1).collect()
    if not sized:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    dims, n = sized[0]["d"], sized[0]["n"]
    part = min(1.0, params.sample_rows / n)
    drawn = reps.where(F.size("e") == dims).where(F.pmod(F.xxhash64("rep"), F.lit(1_000_000)) < math.ceil(1_000_000 * part)).orderBy("rep").limit(params.sample_rows + params.sample_rows // 8).select("e").toPandas()
    x = np.array(drawn["e"].tolist(), np.float64).reshape(len(drawn), dims)
    cells = max(1, min(params.max_cells, math.ceil(n / params.cell_rows)))
    centre = spherical_kmeans(unit(x), cells, params.rounds, params.seed) if len(x) else np.eye(1, dims)
    probes = probe_count(len(centre), params)

    def assign(batches):
        for b in batches:
            for k0 in range(0, b.num_rows, 4096):
                piece = b.slice(k0, 4096)
                raw = [np.asarray(v, np.float64) for v in piece.column("e").to_pylist()]
                usual = np.array([len(v) == dims for v in raw])
                home = np.array([-len(v) for v in raw], np.int64)
                near = np.repeat(home[:, None], probes, 1)
                if usual.any():
                    u = np.array([v for v in raw if len(v) == dims])
                    s = unit(u) @ centre.T
                    top = np.argpartition(-s, probes - 1, axis=1)[:, :probes] if probes < s.shape[1] else np.tile(np.arange(probes), (len(u), 1))
                    near[usual], home[usual] = top, s.argmax(1)
                yield pa.RecordBatch.from_arrays(
                    [piece.column("rep"), piece.column("copies"), pa.array([v.tobytes() for v in raw], pa.binary()), pa.array(home), pa.array(near.tolist(), pa.list_(pa.int64()))],
                    ["rep", "copies", "v", "home", "near"],
                )

    assigned = settle(reps.select("rep", "copies", "e").mapInArrow(assign, "rep bigint, copies bigint, v binary, home bigint, near array<bigint>"))
    visits = assigned.withColumn("cell", F.explode(F.array_union("near", F.array("home"))))
    sizes = visits.groupBy("cell").agg(F.count("*").alias("rows"))  # one row for each cell: at most max_cells and odd lengths
    blocks = sizes.select("cell", F.ceil(F.col("rows") / params.block_rows).alias("blocks"))
    member = visits.join(blocks, "cell").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other")
    task = member.select("*", other).select("cell", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rep", "copies", "v", "home", "near")

    def group(t: pa.Table) -> pa.Table:
        cell, i, j = (t.column(c)[0].as_py() for c in ("cell", "i", "j"))
        t = t.sort_by("rep")
        block, rep = t.column("block").to_numpy(), t.column("rep").to_numpy()
        v, copies, home = unit(np.frombuffer(b"".join(t.column("v").to_pylist()), np.float64).reshape(len(rep), -1)), t.column("copies").to_numpy(), t.column("home").to_numpy()
        near = t.column("near").combine_chunks().flatten().to_numpy().reshape(len(rep), -1)
        side = [np.flatnonzero(block == k) for k in (i, j)]
        meta = [{"home": home[s], "probes": near[s], "copies": copies[s]} for s in side]
        counts, label = _compare(v[side[0]], meta[0], v[side[1]], meta[1], cell, i == j, params.threshold)
        ids = rep[side[0]] if i == j else np.concatenate([rep[side[0]], rep[side[1]]])
        root = np.full(len(ids), np.iinfo(np.int64).max)
        np.minimum.at(root, label, ids)
        got = counts > 0
        return pa.table({"rep": ids[got], "links": counts[got], "root": root[label[got]]})

    found = settle(task.groupBy("cell", "i", "j").applyInArrow(group, "rep bigint, links bigint, root bigint"))
    linked = found.groupBy("rep").agg(F.sum("links").alias("links"))
    joined = components(found.select(F.col("rep").alias("a"), F.col("root").alias("b"))).withColumnRenamed("node", "rep")
    per_rep = reps.select("h1", "h2", "rep", "copies").join(linked, "rep", "left").join(joined, "rep", "left")
    per_rep = settle(per_rep.select(F.struct("h1", "h2").alias("h"), "copies", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("component", "rep").alias("component")))
    out = look_up(keyed.select("vec_id", F.when(F.col("h1").isNotNull(), F.struct("h1", "h2")).alias("h")), "h", per_rep, "copies")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))


def op5_cell_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link(table(spark, sf_dir, "embeddings"))


OP5_SQL = """
WITH RECURSIVE v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings),
fine AS (SELECT vec_id, e FROM v WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM fine a JOIN fine b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.9),
reach AS (SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
least AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a)
SELECT vec_id, (SELECT count(*) FROM links WHERE a = vec_id) AS n_links, component_id, vec_id = component_id AS kept FROM least
"""
