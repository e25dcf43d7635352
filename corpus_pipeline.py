"""From raw documents to packed training sequences, stage by stage.

Each stage takes what the one before it wrote and calls one operator: language identification drops documents that no
learned language codes below a measured rate, the n-gram Jaccard join keeps one document of each group of near copies (five words, 0.8),
chaining cuts passages that an earlier document has, personal data is masked, and what is left is packed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ebbset.llm import chaining, jaccard, langid, packing, pii
from ebbset.llm._spark import quoted, unused, written
from ebbset.session import ship


def _measured(docs: DataFrame) -> DataFrame:
    """n_chars of the text as it is now."""
    if "n_chars" not in docs.columns:
        return docs
    return docs.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return langid.keep_known(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return jaccard.keep_first(docs, jaccard.Measure(width=5, low=80, high=100))


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return _measured(chaining.cut_repeats(docs))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    to = unused(docs, "found")
    masked = pii.find(docs, to=to).withColumn("text", pii.mask(F.col("text"), F.col(to)))
    return _measured(masked.select(*[quoted(c) for c in docs.columns]))


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return packing.pack(docs)


STAGES = [
    ("language_id", language),
    ("near_copies", near_copies),
    ("substring_dedup", passages),
    ("personal_data", personal_data),
    ("packing", sequences),
]

#: Code lengths, chaining and packing have no SQL form; tests hold the operators against brute force and the stages against planted cases.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(lambda stage=stage, docs=docs: stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
