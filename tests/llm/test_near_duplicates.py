import random
import re
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from fixtrace.llm import common, components, ngrams, vectors


def word_set(text, width):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate({k: k + 32 for k in range(65, 91)}))
    return {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} or ({tuple(w)} if w else set())


def brute(texts, params):
    """Least id reached from each id over all pairs."""
    found = {i: word_set(x, params.width) for i, x in texts}
    parent = {i: i for i in found}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(found)
    for k, i in enumerate(ids):
        for j in ids[k + 1 :]:
            both = len(found[i] & found[j])
            if found[i] and found[j] and params.over * both >= params.per * (len(found[i]) + len(found[j]) - both):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(found[i]), root(i)) for i in ids}


def corpus(seed):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    fresh = lambda n: [rng.choice(words) for _ in range(n)]
    passage = fresh(60)
    out = [None, "", " \t\n", "one", "One", "a b c", "a b c d", "a b c d e"]
    base = fresh(120)
    for _ in range(40):  # a cloud around one base, some links and some not
        x = list(base)
        for _ in range(rng.randrange(0, 14)):
            x[rng.randrange(len(x))] = rng.choice(words)
        out.append(" ".join(x))
    for n in (5, 8, 12, 20, 40, 90, 300, 900):
        x = fresh(n)
        out += [" ".join(x), " ".join(x), " ".join(x).upper()]
        for k in range(1, 6):
            y = list(x)
            for _ in range(max(1, n * k // 100)):
                y[rng.randrange(len(y))] = rng.choice(words)
            out.append("  ".join(y))
        out.append(" ".join(x + fresh(n // 8)))
    out += [" ".join(passage + fresh(rng.randrange(1, 40))) for _ in range(30)]
    return [(k + 3, x) for k, x in enumerate(out)]


@pytest.mark.parametrize(("seed", "params"), [(1, ngrams.Params(4, 85)), (2, ngrams.Params()), (3, ngrams.Params(4, 85, bucket=3, block=8))])
def test_components_equal_all_pairs(spark, seed, params):
    rows = corpus(seed)
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("component", F.lit("clash")).withColumn("node", F.lit(0)).repartition(3)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngrams.link(docs, params).collect()}
    assert got == brute(rows, params)


def test_no_rows_and_repeated_rows(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert ngrams.link(docs).count() == 0
    twice = spark.createDataFrame([(1, "a b c d e f g h"), (1, "a b c d e f g h"), (None, "a b c d e f g h"), (2, "A b c d e f g h")], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.component_id) for r in ngrams.link(twice).collect()) == [(0, None), (1, 1), (1, 1), (2, 1)]


def test_bands_hold_every_linked_size():
    for per in (80, 85):
        for a in range(1, 400):
            for b in range(a, a * 100 // per + 1):
                differ = ngrams.room(a, b, ngrams.Params(per=per))
                one, two = ({x[0]: x for x in ngrams.bands(per, 100, n)} for n in (a, b))
                common = one.keys() & two.keys()
                if a != b or differ >= 1:
                    assert any(one[k][1] - one[k][2] > differ for k in common) or differ == 0


def test_whole_sketches_bound_the_difference():
    rng = np.random.default_rng(4)
    for n in (10, 200, 3000):
        a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
        b = np.unique(np.concatenate([a[n // 10 :], rng.integers(0, 2**63, n // 7).astype(np.uint64)]))
        x, y = (ngrams.whole_sketch(s, ngrams.sketch_bits(len(s))) for s in (a, b))
        size = min(len(x), len(y))
        apart = int(np.bitwise_count(ngrams.fold(x, size) ^ ngrams.fold(y, size)).sum())
        assert apart <= len(np.setxor1d(a, b))


@pytest.mark.parametrize("task_links", [10**6, 40])
def test_component_rounds(spark, task_links):
    rng = random.Random(9)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(160)] + [(1000 + k, 1001 + k) for k in range(60)]
    near = defaultdict(set)
    for a, b in links:
        near[a].add(b)
        near[b].add(a)
    want = {}
    for n in sorted(near):
        todo = [n]
        while todo:
            x = todo.pop()
            if x not in want:
                want[x] = n
                todo += near[x]
    got = components.components(spark.createDataFrame(links, "a long, b long").repartition(5), task_links)
    assert {r.node: r.component for r in got.collect()} == want


def planted(n, seed):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, 64))
    near = x[: n // 5] / np.linalg.norm(x[: n // 5], axis=1)[:, None]
    z = rng.normal(size=near.shape)
    z -= (z * near).sum(1)[:, None] * near
    z /= np.linalg.norm(z, axis=1)[:, None]
    c = rng.uniform(0.88, 0.99, len(near))[:, None]
    return np.concatenate([x, c * near + np.sqrt(1 - c * c) * z]).astype(np.float32)


@pytest.mark.parametrize("cells", [50, 500, 2000, 8192])
def test_recall_stays_level_with_more_cells(cells):
    rng = np.random.default_rng(1)
    unit = lambda n: (x := rng.normal(size=(n, 64))) / np.linalg.norm(x, axis=1)[:, None]
    centre = vectors.spherical_kmeans(unit(20_000), cells, 8 if cells < 8192 else 2, 5)
    a, z = unit(6000), unit(6000)
    z -= (z * a).sum(1)[:, None] * a
    b = 0.9 * a + 0.19**0.5 * z / np.linalg.norm(z, axis=1)[:, None]
    s, t, i = a @ centre.T, b @ centre.T, np.arange(6000)
    rank = np.minimum((s > s[i, t.argmax(1)][:, None]).sum(1), (t > t[i, s.argmax(1)][:, None]).sum(1))
    recall = (rank < vectors.probe_count(cells, vectors.Params())).mean()
    print(cells, vectors.probe_count(cells, vectors.Params()), recall)
    assert recall >= 0.99


def test_vector_links_against_all_pairs(spark):
    x = planted(1500, 3)
    rows = [(k, [float(v) for v in r]) for k, r in enumerate(x)]
    hot = rows[0][1]
    rows += [(5000 + k, hot) for k in range(50)]
    odd = [(9000, None), (9001, []), (9002, [0.0] * 64), (9003, [float("nan")] * 64), (9004, [None] * 64), (9005, [1.0, 2.0]), (9006, [2.0, 4.0]), (9007, [float("inf")] + [1.0] * 63)]
    odd += [(9010, [1e160, 0.0, 0.0]), (9011, [1e160, 0.0, 0.0]), (9012, [1e-160, 0.0, 0.0]), (9013, [0.0, 1e-300, 0.0]), (9014, [1.7e308, 1.7e308, 1.7e308])]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>").withColumn("rep", F.lit(1)).withColumn("h", F.lit(1))
    got = {r.vec_id: r for r in vectors.link(df, vectors.Params(cell_rows=100, block_rows=64)).collect()}
    full = np.array([r for _, r in rows], np.float32).astype(float)
    full /= np.linalg.norm(full, axis=1)[:, None]
    s = full @ full.T >= 0.9
    np.fill_diagonal(s, False)
    want, have = s.sum(1), np.array([got[i].n_links for i, _ in rows])
    assert (have <= want).all() and have.sum() >= 0.97 * want.sum()
    assert got[5001].n_links >= 50 and got[5001].component_id == 0 and not got[5001].kept
    assert all(got[i].n_links == 0 and got[i].kept for i in (9000, 9001, 9002, 9003, 9004, 9007))
    assert got[9005].n_links == 1 and got[9006].component_id == 9005
    assert [got[9010 + k].n_links for k in range(5)] == [2, 2, 2, 0, 0] and got[9012].component_id == 9010
    assert vectors.link(df.where("false")).count() == 0


def test_hot_keys_are_looked_up_by_broadcast(spark):
    rows = spark.createDataFrame([(k, 1 if k % 3 else k) for k in range(3000)] + [(9000, None)], "i long, key long")
    found = rows.where("key is not null").groupBy("key").agg(F.count("*").alias("n"), F.max("i").alias("most"))
    got = common.look_up(rows, "key", found, "n")
    assert "n" not in got.columns and got.count() == 3001
    assert got.where("key = 1 and most = 2999").count() == 2000 and got.where("key is null and most is null and i = 9000").count() == 1
    assert got.where("key <> 1 and most = i").count() == 1000
    assert common.look_up(rows.where("false"), "key", found.where("false"), "n").count() == 0


def shuffled(spark):
    """Bytes that the session's tasks have shuffled so far."""
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty(30_000)
    found = sc.statusStore().executorList(False)
    return sum(found.apply(k).totalShuffleWrite() for k in range(found.size()))


def test_a_cloud_is_not_shuffled_once_for_each_block(spark):
    params, rng, moved = ngrams.Params(block=8), random.Random(5), []
    for n in (250, 1000):
        docs = spark.createDataFrame([(k, " ".join(f"w{rng.randrange(10**6)}" for _ in range(60))) for k in range(n)], "doc_id long, text string")
        reps = ngrams.settle(ngrams.sets(docs, params).selectExpr("node", "doc_id as doc", "n_shingles as n", "sketch"))
        clouds = ngrams.settle(reps.selectExpr("node", "0L as cloud", "node as c"))
        before = shuffled(spark)
        assert ngrams.cloud_links(clouds, reps, docs, params).count() == 0
        moved.append(shuffled(spark) - before)
    assert 0 < moved[1] < 6 * moved[0]  # four times the sets; by blocks it was their square


@pytest.mark.parametrize("chunk", [3000, 1 << 24])
def test_chunks_of_clouds_give_the_same_components(spark, chunk):
    params = ngrams.Params(4, 85, bucket=3, block=8, chunk=chunk)
    rows = corpus(3)[:90]
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngrams.link(spark.createDataFrame(rows, "doc_id long, text string"), params).collect()} == brute(rows, params)
