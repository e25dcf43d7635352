"""What the sketch is compared with: min-hash over stored profiles, min-hash that ignores removals, rescans, no filter."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.functions.hashing import hash_input, shift_hash
from ebbset.operators.candidates import SIGNATURE_BITS
from ebbset.params import SketchParams


def plain_minhash(net: DataFrame, p: SketchParams) -> DataFrame:
    """set_id, card, sig: minima over whole profiles, which must be stored to survive removals."""
    x = net.withColumn("x", hash_input(F.col("item_id")))
    minima = [F.min(shift_hash(F.col("x"), ab, SIGNATURE_BITS)).cast("int") for ab in p.draw("minhash", p.rows * p.bands)]
    return x.groupBy("set_id").agg(F.count("*").alias("card"), F.array(*minima).alias("sig")).withColumn("level", F.lit(0))


def stale_minhash(updates: DataFrame, p: SketchParams) -> DataFrame:
    """Minima over everything ever inserted: what a sketch without removals drifts to."""
    return plain_minhash(updates.where("delta > 0").select("set_id", "item_id").distinct(), p)


def drift(updates: DataFrame, net: DataFrame, p: SketchParams) -> DataFrame:
    """Per set: how many minima are wrong because of removals."""
    old, new = stale_minhash(updates, p).select("set_id", F.col("sig").alias("old")), plain_minhash(net, p).select("set_id", F.col("sig").alias("new"))
    wrong = F.size(F.filter(F.zip_with("old", "new", lambda a, b: a != b), lambda x: x))
    return old.join(new, "set_id").select("set_id", wrong.alias("wrong"))


def rescan_cost(updates: DataFrame) -> DataFrame:
    """Per set: removals, and items a naive recomputation reads for them (the profile after each)."""
    w = Window.partitionBy("set_id").orderBy("ts", "seq", "item_id", F.col("delta").desc()).rowsBetween(Window.unboundedPreceding, 0)
    now = updates.withColumn("now", F.sum("delta").over(w)).where("delta < 0")
    return now.groupBy("set_id").agg(F.count("*").alias("removals"), F.sum(F.greatest("now", F.lit(0))).cast("long").alias("rescanned"))


def spark_ml_minhash(net: DataFrame, universe_bits: int = 18, tables: int = 8, most: float = 0.5) -> DataFrame:
    """Spark's own MinHashLSH as an outside reference; vectors are made on the JVM."""
    from pyspark.ml.feature import CountVectorizerModel, MinHashLSH

    size = 1 << universe_bits
    held = net.groupBy("set_id").agg(F.collect_set((hash_input(F.col("item_id")) % size).cast("string")).alias("i"))
    vectors = CountVectorizerModel.from_vocabulary([str(i) for i in range(size)], inputCol="i", outputCol="features", minTF=1.0)
    rows = vectors.transform(held).select("set_id", "features")
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=5).fit(rows)
    near = model.approxSimilarityJoin(rows, rows, most, distCol="distance").where("datasetA.set_id < datasetB.set_id")
    return near.select(F.col("datasetA.set_id").alias("left_id"), F.col("datasetB.set_id").alias("right_id"), F.round("distance", 6).alias("distance"))


class StoredProfiles:
    """Min-hash that is right under removals because it keeps the whole set, and reads it again whenever an item that may
    hold a minimum goes."""

    def __init__(self, p: SketchParams):
        self.hashes = p.draw("minhash", p.rows * p.bands)
        self.items: dict[int, int] = {}
        self.sig: list[int] | None = None
        self.evaluated = self.rescans = 0

    def _ranks(self, x: int) -> list[int]:
        self.evaluated += len(self.hashes)
        return [((a * x + b) & 0xFFFFFFFF) >> (32 - SIGNATURE_BITS) for a, b in self.hashes]

    def update(self, item: int, x: int, delta: int, inputs: dict[int, int]) -> None:
        was = self.items.get(item, 0) > 0
        self.items[item] = self.items.get(item, 0) + delta
        now = self.items[item] > 0
        if not self.items[item]:
            del self.items[item]
        if now and not was:
            new = self._ranks(x)
            self.sig = new if self.sig is None else list(map(min, self.sig, new))
        elif was and not now:
            self.rescans += 1
            rows = [self._ranks(inputs[i]) for i, n in self.items.items() if n > 0]
            self.sig = [min(c) for c in zip(*rows, strict=True)] if rows else None


def _online(rows, p: SketchParams):
    import pandas as pd

    own = StoredProfiles(p)
    inputs = dict(zip(rows.item_id.tolist(), rows.x.tolist(), strict=True))
    order = rows.sort_values(["ts", "seq", "item_id", "delta"], ascending=[True, True, True, False])
    for item, x, delta in zip(order.item_id.tolist(), order.x.tolist(), order.delta.tolist(), strict=True):
        own.update(item, x, delta, inputs)
    sig = [] if own.sig is None else [own.sig]
    return pd.DataFrame({"set_id": rows.set_id.iloc[0], "sig": pd.Series(sig, dtype=object), "evaluated": own.evaluated, "rescans": own.rescans})


def online_minhash(updates: DataFrame, p: SketchParams) -> DataFrame:
    """set_id, sig, evaluated, rescans: updates replayed in order, one set at a time (a selection of sets)."""
    from functools import partial

    rows = updates.withColumn("x", hash_input(F.col("item_id"))).select("set_id", "item_id", "x", "delta", "ts", "seq")
    return rows.groupBy("set_id").applyInPandas(partial(_online, p=p), "set_id long, sig array<int>, evaluated long, rescans long")
