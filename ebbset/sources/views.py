"""Set views over the given tables in long form (set_id, item_id), and the readers they come from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ebbset.functions.hashing import key_of


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text):
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != "")


def doc_shingles(spark: SparkSession, sf_dir: str, width: int = 3) -> DataFrame:
    w = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), words("text").alias("w")).where(F.size("w") >= width)
    every = F.transform(F.sequence(F.lit(1), F.size("w") - width + 1), lambda i: F.array_join(F.slice("w", i, width), " "))
    return w.select("set_id", F.explode(F.array_distinct(every)).alias("s")).select("set_id", key_of(F.col("s")).alias("item_id")).distinct()


def doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), F.explode(F.array_distinct(words("text"))).alias("s"))
    return w.select("set_id", key_of(F.col("s")).alias("item_id")).distinct()


def event_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The listening log: set_id, item_id, ts, event_id, genre."""
    e = table(spark, sf_dir, "events")
    return e.select(F.col("user_id").alias("set_id"), F.get_json_object("props", "$.k").cast("long").alias("item_id"), "ts", "event_id", F.col("event_type").alias("genre"))


def user_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_topics(spark, sf_dir).select("set_id", "item_id").distinct()


def topic_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_topics(spark, sf_dir).select(F.col("item_id").alias("set_id"), F.col("set_id").alias("item_id")).distinct()


def supplier_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("set_id"), F.col("l_partkey").alias("item_id")).distinct()


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines with their buyer: set_id, item_id, bought, shipped, returned."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_shipdate", "l_returnflag")
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.select(F.col("o_custkey").alias("set_id"), F.col("l_partkey").alias("item_id"), F.col("o_orderdate").alias("bought"), F.col("l_shipdate").alias("shipped"), (F.col("l_returnflag") == "R").alias("returned"))


def customer_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return purchases(spark, sf_dir).select("set_id", "item_id").distinct()


def customer_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), key_of(F.col("p_brand")).alias("brand_id"))
    return purchases(spark, sf_dir).join(p, "item_id").select("set_id", F.col("brand_id").alias("item_id")).distinct()


VIEWS = {
    "doc_shingles": doc_shingles, "doc_words": doc_words, "user_topics": user_topics, "topic_users": topic_users,
    "supplier_parts": supplier_parts, "customer_parts": customer_parts, "customer_brands": customer_brands,
}
