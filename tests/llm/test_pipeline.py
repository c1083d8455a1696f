"""The corpus pipeline stage by stage, against brute force on the smallest given table."""

import collections
import re

import corpus_pipeline
from tests_support import brute_lines, brute_near, brute_windows

SMALL = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns, state = docs.columns, None
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = spark.createDataFrame(stage(spark, docs, SMALL).collect(), docs.schema)
        after = {r.doc_id: r.text for r in docs.collect()}
        assert docs.columns == columns and all(r.n_chars == len(r.text) for r in docs.collect())
        if name == "quality rules":
            assert all(before[i] == t for i, t in after.items()) and len(after) < len(before)
        elif name == "line dedup":
            assert after == brute_lines(before)
        elif name == "near-dedup":
            assert after == {i: before[i] for i, (_, _, kept) in brute_near(before, 5, 80).items() if kept}
        else:
            want = {i: w for i, (n, gone, w) in brute_windows(before, 20).items() if gone == 0 or gone < n}
            assert {i: " ".join(re.findall(r"[^\x20\x09-\x0D]+", t)) for i, t in after.items()} == want
        state = after
    rows = corpus_pipeline.STAGES[-1][1](spark, docs, SMALL).collect()
    assert {r.doc_id for r in rows} == state.keys()
    used = collections.Counter()
    for r in rows:
        used[r.sequence_id] += r.length
    assert max(used.values()) <= 1024


def test_run(spark):
    rows = corpus_pipeline.run(spark, SMALL).collect()
    assert rows and {"doc_id", "piece", "start", "length", "sequence_id", "offset"} <= set(rows[0].asDict())


def test_clean_documents_stay(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = {r.doc_id for r in spark.read.parquet(f"{SMALL}/labels.parquet").where("quality = 1").collect()}
    kept = {r.doc_id for r in corpus_pipeline.quality(spark, docs, SMALL).collect()}
    lost = [r.doc_id for r in docs.collect() if r.doc_id in labels - kept and len(r.text.split()) >= 10]
    assert not lost
