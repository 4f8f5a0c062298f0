"""The pipeline against a brute-force version of its stages on a small fixture."""

import re

import corpus_pipeline as cp
from deltaring.llm import mixing, packing, pseudonyms, resample
from deltaring.llm.tokens import tokenizer_path

from .test_neardup import brute as components
from .test_packing import check as check_packing

SF = "/root/testdata/sf0.001"


def test_stages_one_by_one(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    done = []
    for name, stage in cp.STAGES:
        docs = stage(spark, docs, SF)
        docs.write.parquet(f"{tmp_path}/{len(done)}")
        docs = spark.read.parquet(f"{tmp_path}/{len(done)}")
        done.append(docs)
    first = spark.read.parquet(f"{SF}/documents.parquet")
    for d in done[:-1]:
        assert d.columns == cp.COLUMNS
    chosen = {r.doc_id for r in resample.resampled_documents(first, labels).where("selected").collect()}
    assert {r.doc_id for r in done[0].collect()} == chosen
    rows = done[0].collect()
    kept = {d for d, (_, c) in components([(r.doc_id, r.text) for r in rows]).items() if d == c}
    assert sorted(r.doc_id for r in done[1].collect()) == sorted(kept)
    masked = {r.doc_id: r.text for r in pseudonyms.pseudonymised(done[1], cp.PSEUDONYM_KEY).collect()}
    assert {r.doc_id: r.text for r in done[2].collect()} == masked
    takes = {r.doc_id: r.taken for r in mixing.mixed_documents(done[2]).collect() if r.taken}
    got: dict = {}
    for r in done[3].collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + len(re.findall(r"[^\x20\x09-\x0D]+", r.text))
    assert got == takes
    check_packing(done[4].collect(), [(r.doc_id, r.text) for r in done[3].collect()], tokenizer_path())
    assert packing.Capacity().tokens == 4096


def test_run_equals_its_stages(spark):
    a = sorted(tuple(r) for r in cp.run(spark, SF).collect())
    assert a == sorted(tuple(r) for r in cp.run(spark, SF).collect()) and len(a) > 100


def test_odd_rows(spark, odd, empty, tmp_path):
    for name, docs in (("odd", odd), ("empty", empty)):
        for at, (_, stage) in enumerate(cp.STAGES):
            stage(spark, docs, SF).write.parquet(f"{tmp_path}/{name}{at}")
            docs = spark.read.parquet(f"{tmp_path}/{name}{at}")
        assert (docs.count() > 0) == (name == "odd")
