import re

from conftest import SF

import corpus_pipeline
from ebbset.llm import jaccard
from ebbset.llm._spark import written


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    junk = spark.createDataFrame([(10**6, "12 34", "en", "s", 5), (10**6 + 1, None, None, "s", 0), (10**6 + 2, "write to some.one@example.org for the report of the week", "en", "s", 55)], docs.schema)
    now = docs.union(junk)
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        now = written(lambda stage=stage, now=now: stage(spark, now, SF), name)
        seen[name] = now
        if name != "packing":
            assert now.columns == docs.columns
    ids = {n: {r.doc_id for r in d.select("doc_id").distinct().collect()} for n, d in seen.items()}
    assert 10**6 not in ids["language_id"] and 10**6 + 1 not in ids["language_id"]
    assert ids["language_id"] - {10**6 + 2} == {r.doc_id for r in docs.collect()}
    assert jaccard.near_copies(seen["near_copies"], jaccard.Measure(5, 80, 100)).where("node <> component").count() == 0
    assert sum(r.n_chars for r in seen["substring_dedup"].collect()) < sum(r.n_chars for r in seen["near_copies"].collect())
    text = {r.doc_id: r.text for r in seen["personal_data"].collect()}
    assert text[10**6 + 2] == "write to [EMAIL] for the report of the week"
    assert not any(re.search(r"[\w.]+@mail\d\.example\.com", t) for t in text.values())
    assert ids["packing"] == ids["personal_data"]


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 100
