"""Update streams (set_id, item_id, delta, ts, seq): built from tables, thinned, expired, and netted to sets."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.functions.hashing import key_of
from ebbset.params import flip_rates


def insert_stream(view: DataFrame) -> DataFrame:
    return view.select("set_id", "item_id", F.lit(1).alias("delta"), F.lit(None).cast("timestamp_ntz").alias("ts"), F.lit(0).cast("long").alias("seq"))


def chance(*parts, salt: str):
    """A number from 0 to 9999 fixed by the parts."""
    return key_of(F.concat_ws(":", *[p.cast("string") for p in parts], F.lit(salt)), 7) % 10000


def with_random_deletions(updates: DataFrame, rate: float = 0.1, seed: int = 1) -> DataFrame:
    """Each insertion, with that chance, followed at once by its removal."""
    gone = chance(F.col("set_id"), F.col("item_id"), salt=f"del{seed}") < int(rate * 10000)
    steps = F.when((F.col("delta") == 1) & gone, F.array(F.lit(1), F.lit(-1))).otherwise(F.array("delta"))
    return updates.select("set_id", "item_id", F.posexplode(steps).alias("p", "d"), "ts", "seq").select("set_id", "item_id", F.col("d").alias("delta"), "ts", (F.col("seq") + F.col("p")).alias("seq"))


def adoption_expiry_stream(log: DataFrame, adopt_after: int = 5, idle_days: int = 180, horizon: str = "2024-01-31") -> DataFrame:
    """+1 at the adopt_after-th use of an item, -1 once it has been idle for so long (by the horizon)."""
    w = Window.partitionBy("set_id", "item_id").orderBy("ts", "event_id")
    idle = F.expr(f"interval {idle_days} days")
    gap = F.col("ts") > F.lag("ts").over(w) + idle
    runs = log.withColumn("run", F.sum(F.coalesce(gap, F.lit(False)).cast("int")).over(w))
    own = Window.partitionBy("set_id", "item_id", "run").orderBy("ts", "event_id")
    runs = runs.withColumn("nth", F.row_number().over(own)).withColumn("last", F.max("ts").over(Window.partitionBy("set_id", "item_id", "run")))
    adopted = runs.where(F.col("nth") == adopt_after).withColumn("end", F.col("last") + idle)
    ends = F.when(F.col("end") <= F.to_timestamp_ntz(F.lit(horizon)), F.array(F.struct(F.lit(1).alias("delta"), F.col("ts").alias("at")), F.struct(F.lit(-1).alias("delta"), F.col("end").alias("at"))))
    steps = F.coalesce(ends, F.array(F.struct(F.lit(1).alias("delta"), F.col("ts").alias("at"))))
    return adopted.select("set_id", "item_id", F.explode(steps).alias("e"), F.col("event_id").alias("seq")).select("set_id", "item_id", "e.delta", F.col("e.at").alias("ts"), "seq")


def return_stream(purchases: DataFrame) -> DataFrame:
    """+1 when bought, -1 when a returned line was shipped."""
    back = F.when(F.col("returned"), F.array(F.struct(F.lit(1).alias("delta"), F.col("bought").alias("at")), F.struct(F.lit(-1).alias("delta"), F.col("shipped").alias("at"))))
    steps = F.coalesce(back, F.array(F.struct(F.lit(1).alias("delta"), F.col("bought").alias("at"))))
    return purchases.select("set_id", "item_id", F.explode(steps).alias("e")).select("set_id", "item_id", "e.delta", F.col("e.at").alias("ts"), F.lit(0).cast("long").alias("seq"))


def dense_sets_only(updates: DataFrame, universe: int, min_density: float) -> DataFrame:
    """Updates of the sets that hold at least this share of the universe, averaged over their updates."""
    w = Window.partitionBy("set_id").orderBy("ts", "seq", "item_id", F.col("delta").desc()).rowsBetween(Window.unboundedPreceding, 0)
    dense = updates.withColumn("now", F.sum("delta").over(w)).groupBy("set_id").agg(F.avg("now").alias("m")).where(F.col("m") >= min_density * universe)
    return updates.join(dense, "set_id", "left_semi")


def map_items(updates: DataFrame, mapping: DataFrame) -> DataFrame:
    """Items replaced by coarser ones. mapping: (item_id, coarse_id)."""
    return updates.join(mapping, "item_id").withColumn("item_id", F.col("coarse_id")).select(*updates.columns)


def to_transitions(updates: DataFrame) -> DataFrame:
    """Only the updates that make an item present or absent."""
    w = Window.partitionBy("set_id", "item_id").orderBy("ts", "seq", F.col("delta").desc()).rowsBetween(Window.unboundedPreceding, 0)
    after = updates.withColumn("now", F.sum("delta").over(w))
    turn = ((F.col("now") == 1) & (F.col("delta") == 1)) | ((F.col("now") == 0) & (F.col("delta") == -1))
    return after.where(turn).select(*updates.columns)


def net_sets(updates: DataFrame) -> DataFrame:
    """The current sets: items whose insertions outnumber their removals."""
    return updates.groupBy("set_id", "item_id").agg(F.sum("delta").alias("n")).where("n > 0").select("set_id", "item_id")


def cardinalities(net: DataFrame) -> DataFrame:
    return net.groupBy("set_id").agg(F.count("*").alias("card"))


def audit(updates: DataFrame) -> DataFrame:
    """Items removed more often than inserted: data errors, treated as absent."""
    return updates.groupBy("set_id", "item_id").agg(F.sum("delta").cast("long").alias("net")).where("net < 0")


def planted_from_view(view: DataFrame, every: int, similarity: float, density: float, universe: int, shift: int = 10_000_000, seed: int = 3) -> DataFrame:
    """The view plus, for each set whose id is divisible by `every`, a copy of about this similarity."""
    drop, add = flip_rates(similarity, density)
    base = view.where(F.col("set_id") % every == 0)
    kept = base.where(chance(F.col("set_id"), F.col("item_id"), salt=f"drop{seed}") >= int(drop * 10000))
    some = base.select("set_id").distinct().select("set_id", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(universe).cast("long"))).alias("item_id"))
    new = some.where(chance(F.col("set_id"), F.col("item_id"), salt=f"add{seed}") < int(add * 10000)).join(base, ["set_id", "item_id"], "left_anti")
    copy = kept.union(new).select((F.col("set_id") + shift).alias("set_id"), "item_id")
    return view.union(copy)


#: Ids that a set lacks, and rows of a batch, looked at together.
SPAN, ROWS = 8 << 20, 1 << 16


def _drawn(batches, rate: float, universe: int, seed: int):
    """Of each set the ids from 1 to `universe` that it lacks, each with that chance: the ranks of the drawn ones among the
    lacking are reached by geometric steps, so work grows with what is drawn."""
    for batch in batches:
        for set_id, items in zip(batch.column("set_id").to_pylist(), batch.column("items"), strict=True):
            own = np.unique(np.asarray(items.values))
            own = own[(own >= 1) & (own <= universe)]
            before = own - 1 - np.arange(len(own))  # how many lacking ids are smaller
            rng = np.random.default_rng([seed, set_id & ((1 << 63) - 1)])
            at, end = -1, universe - len(own)
            while at < end:
                rank = at + np.cumsum(rng.geometric(rate, max(16, int(min(SPAN, end - at) * rate * 1.1))))
                at, rank = int(rank[-1]), rank[rank < end]
                new = rank + 1 + np.searchsorted(before, rank, side="right")
                for k in range(0, len(new), ROWS):
                    part = new[k : k + ROWS]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), set_id, np.int64)), pa.array(part)], ["set_id", "item_id"])


def planted_by_draws(view: DataFrame, every: int, similarity: float, density: float, universe: int, shift: int = 10_000_000, seed: int = 3) -> DataFrame:
    """planted_from_view() for large universes: the same chances, but no dice for each id that a set lacks."""
    drop, add = flip_rates(similarity, density)
    base = view.where(F.col("set_id") % every == 0)
    copy = base.where(chance(F.col("set_id"), F.col("item_id"), salt=f"drop{seed}") >= int(drop * 10000))
    rate = int(add * 10000) / 10000
    if rate:
        held = base.select(F.col("set_id").cast("long"), F.col("item_id").cast("long")).groupBy("set_id").agg(F.collect_list("item_id").alias("items"))
        copy = copy.union(held.mapInArrow(partial(_drawn, rate=rate, universe=universe, seed=seed), "set_id long, item_id long"))
    return view.union(copy.select((F.col("set_id") + shift).alias("set_id"), "item_id"))


def complement_view(view: DataFrame, universe: DataFrame, most: int = 10_000) -> DataFrame:
    """The items that each set lacks, for similarities that weigh those more; only for universes of a checked size."""
    n = universe.count()
    if n > most:
        raise ValueError(f"a universe of {n} items is too large to complement")
    every = view.select("set_id").distinct().join(F.broadcast(universe.select("item_id").distinct()), F.lit(True))
    return every.join(view, ["set_id", "item_id"], "left_anti")
