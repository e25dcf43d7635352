from ebbset.llm import bpe


def test_rank_tables_stay_out_of_plans(spark):
    """Every description of a plan is made on the driver, and Spark keeps some of each query."""
    docs = spark.createDataFrame([(1, "a few words, and a few more")], "doc_id long, text string")
    rows, _ = bpe._folded(docs, None, 20, 0)
    assert len(rows._jdf.queryExecution().toString()) < 200_000
