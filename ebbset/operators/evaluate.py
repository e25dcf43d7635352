"""Accuracy and cost measures. Pairs that never meet enter by subtraction, never as rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def confusion(found: DataFrame, exact: DataFrame, r1: float, r2: float, sets: int) -> DataFrame:
    """tp, fp, fn, tn, gray_missed of reported pairs. exact: left_id, right_id, sim of all pairs of similarity r2 at least (others
    may be among them); found and exact pairs have the weight of how many pairs each stands for.

    Reported pairs count as right from r2 on, missed ones as wrong from r1 on; missed pairs between are in no class.
    """
    hit = exact.join(found.select("left_id", "right_id", F.lit(1).alias("hit")), ["left_id", "right_id"], "left")
    got, sim = F.col("hit").isNotNull(), F.col("sim")
    many = lambda c, n: F.coalesce(F.sum(F.when(c, F.col("weight"))), F.lit(0)).alias(n)
    sums = hit.agg(many(got & (sim >= r2), "tp"), many(got & (sim < r2), "fp0"), many(~got & (sim >= r1), "fn"), many(~got & (sim < r1) & (sim >= r2), "gray_missed"), many(got, "met"))
    n = found.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("reported"))
    every = sets * (sets - 1) // 2
    fp = F.col("fp0") + F.col("reported") - F.col("met")
    out = sums.join(F.broadcast(n)).select("tp", fp.alias("fp"), "fn", "gray_missed", "reported")
    return out.select("tp", "fp", "fn", "gray_missed", (F.lit(every) - F.col("tp") - F.col("fp") - F.col("fn") - F.col("gray_missed")).alias("tn"), "reported")


def rates(c: DataFrame) -> DataFrame:
    """accuracy, recall (as defined by the two thresholds), precision, share of pairs reported."""
    one = lambda a, b: F.round(F.when(b == 0, 1.0).otherwise(a / b), 6)
    tp, fp, fn, tn = (F.col(x) for x in ("tp", "fp", "fn", "tn"))
    total = tp + fp + fn + tn + F.col("gray_missed")
    return c.select(one(tp + tn, tp + tn + fp + fn).alias("accuracy"), one(tp, tp + fn).alias("recall"), one(tp, tp + fp).alias("precision"), one(F.col("reported"), total).alias("reported_share"))


def strict_recall(found: DataFrame, exact: DataFrame, r1: float) -> DataFrame:
    """Hits among the pairs of similarity r1 and more."""
    hit = exact.where(F.col("sim") >= r1).join(found.withColumn("hit", F.lit(1)), ["left_id", "right_id"], "left")
    return hit.agg(F.count("hit").alias("hits"), F.count("*").alias("pairs"))


def recall_by_band(found: DataFrame, exact: DataFrame, width: int = 10) -> DataFrame:
    hit = exact.join(found.withColumn("hit", F.lit(1)), ["left_id", "right_id"], "left")
    return hit.groupBy(F.floor(F.col("inter") * width / F.col("uni")).alias("band")).agg(F.count("hit").alias("hits"), F.count("*").alias("pairs"))


def squared_deviation(estimates: DataFrame, exact: DataFrame, split: float = 0.2) -> DataFrame:
    """Average squared deviation of estimates, for pairs below and from the split on."""
    both = estimates.select("left_id", "right_id", "est").join(exact.select("left_id", "right_id", "sim"), ["left_id", "right_id"], "left").withColumn("sim", F.coalesce("sim", F.lit(0.0)))
    side = F.when(F.col("sim") < split, "low").otherwise("high").alias("side")
    return both.groupBy(side).agg(F.count("*").alias("pairs"), F.round(F.avg(F.pow(F.col("est") - F.col("sim"), 2)), 8).alias("deviation"))


def sensitivity_curve(found: DataFrame, exact: DataFrame, bins: int = 20) -> DataFrame:
    """Share of pairs found, by similarity. exact: left_id, right_id, inter, uni, and the weight of pairs that one stands for."""
    hit = exact.join(found.select("left_id", "right_id", F.lit(1).alias("hit")), ["left_id", "right_id"], "left")
    many = F.coalesce(F.sum(F.when(F.col("hit").isNotNull(), F.col("weight"))), F.lit(0)).alias("hits")
    return hit.groupBy(F.floor(F.col("inter") * bins / F.col("uni")).alias("bin")).agg(F.sum("weight").alias("pairs"), many)
