import re

import corpus_pipeline
from fixtrace.llm import lines, ngrams, quality
from tests.llm.test_near_duplicates import brute


def test_stages(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    kept = []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, small).write.parquet(f"file://{tmp_path}/{k}")
        docs = spark.read.parquet(f"file://{tmp_path}/{k}")
        kept.append(docs.toPandas())
        if k < 4:
            assert set(docs.columns) == set(corpus_pipeline.COLUMNS), name
    start = spark.read.parquet(f"{small}/documents.parquet").toPandas()
    scores = quality.op1_quality_classifier(spark, small).toPandas()
    assert set(kept[0].doc_id) == set(scores[scores.predicted == 1].doc_id)
    first = dict(zip(start.doc_id, start.text, strict=True))
    strip = lambda x: x.strip(" \t\n\x0b\x0c\r").translate({k: k + 32 for k in range(65, 91)})
    holders = {}
    for r in kept[0].itertuples():
        for key in {strip(x) for x in r.text.split("\n")}:
            holders.setdefault(key, []).append(r.doc_id)
    shared = {k for k, v in holders.items() if len(k) >= lines.Params().min_chars and len(v) >= lines.Params().min_docs}
    for r in kept[1].itertuples():
        assert r.text == "\n".join(x for x in first[r.doc_id].split("\n") if strip(x) not in shared or max(holders[strip(x)]) == r.doc_id)
        assert r.n_chars == len(r.text)
    want = brute(list(zip(kept[1].doc_id, kept[1].text, strict=True)), ngrams.Params())
    assert set(kept[2].doc_id) == {i for i, (_, c) in want.items() if i == c}
    assert set(kept[3].doc_id) <= set(kept[2].doc_id) and len(kept[3]) > 0.5 * len(kept[2])
    totals = kept[4].groupby("doc_id").length.sum()
    assert set(totals.index) == set(kept[3].doc_id)
    assert re.match("[a-z]", corpus_pipeline.STAGES[0][0])


def test_run_computes_each_stage_once(spark, small):
    out = corpus_pipeline.run(spark, small)
    assert all(re.search(r"/pipeline-\w+/3/", f) for f in out.inputFiles())  # the last stage reads what the fourth wrote
    docs = spark.read.parquet(f"{small}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:4]:
        docs = spark.createDataFrame(stage(spark, docs, small).toPandas(), docs.schema)
    kept = out.groupBy("doc_id").agg({"length": "sum"}).toPandas()
    assert set(kept.doc_id) == {r.doc_id for r in docs.select("doc_id").collect()}
