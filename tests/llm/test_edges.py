import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from ebbset.llm import langid, pii

LONG = "the quick report of the week was read by all of them and then kept " * 3000
TEXTS = [(1, "the cat sat on the mat and looked at the other cat of the house", "en"), (2, None, "en"), (3, "", None), (4, LONG, "en"), (4, LONG, "en"), (5, "mail a.b@example.org now please to the cat", None)]


def clashing(spark):
    """Documents with nulls, repeats, an empty and a very long text, and columns whose names operators might use."""
    d = spark.createDataFrame(TEXTS, "doc_id long, text string, lang string")
    for name in ("__m0", "__g0", "__l0", "__found", "__spans", "spans", "a.b", "node", "component", "region", "c0", "key", "x y"):
        d = d.withColumn(name, F.lit(name))
    return d


@pytest.mark.parametrize("name,stage", corpus_pipeline.STAGES)
def test_stages_take_any_columns_and_rows(spark, name, stage):
    docs = clashing(spark)
    out = stage(spark, docs, "")
    rows = out.collect()
    empty = stage(spark, docs.where("false"), "")
    assert empty.columns == out.columns and empty.count() == 0
    if name != "packing":
        assert out.columns == docs.columns and all(r["a.b"] == "a.b" for r in rows)
    ids = [r.doc_id for r in rows]
    if name == "language_id":
        assert sorted(ids) == [1, 4, 4, 5]
    if name in ("near_copies", "substring_dedup", "personal_data"):
        assert sorted(ids) == [1, 2, 3, 4, 4, 5]
    if name == "personal_data":
        assert [r.text for r in rows if r.doc_id == 5] == ["mail [EMAIL] now please to the cat"]


def test_texts_of_no_known_language_go(spark):
    base = [(i, "the cat sat on the mat and the dog ran after the bird in the garden of the house", "en") for i in range(30)]
    odd = [(100, "\u043f\u0440\u0438\u0432\u0435\u0442 \u043c\u0438\u0440 \u043a\u0430\u043a \u0434\u0435\u043b\u0430", None), (101, "zqxjkvw qzxvkj wqzjxk", None), (102, "12 34", None)]
    kept = langid.keep_known(spark.createDataFrame(base + odd, "doc_id long, text string, lang string"))
    assert sorted(r.doc_id for r in kept.collect()) == list(range(30))


def test_spans_beside_a_column_of_that_name(spark):
    found = pii.find(clashing(spark), to="mine")
    assert found.columns[-1] == "mine" and found.count() == len(TEXTS)
