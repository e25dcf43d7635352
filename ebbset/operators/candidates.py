"""From sketches to scored pairs: levels to visit, min-hash signatures, bands, candidate pairs, estimates."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.functions.hashing import shift_hash
from ebbset.operators import blocks
from ebbset.params import JACCARD, Similarity, SketchParams

SIGNATURE_BITS = 24


def level_windows(cards: DataFrame, p: SketchParams) -> DataFrame:
    """(set_id, card, level): the grid levels at which a set is filed. Compares powers of two, never logarithms."""
    grid = F.explode(F.array(*[F.lit(k) for k in p.grid])).alias("level")
    top = F.lit(float(2 ** p.grid[-1]))
    high = F.greatest(F.lit(p.alpha) * F.col("card"), F.lit(1.0))
    low = F.least(F.lit(p.alpha) * F.col("card") / F.lit(2.0**p.width), top)
    at = F.pow(F.lit(2.0), F.col("level"))
    return cards.select("set_id", "card", grid).where((at <= high) & (at >= low) | ((F.col("level") == 0) & (low <= 1)))


def occupied(sketch: DataFrame, windows: DataFrame) -> DataFrame:
    """(set_id, level, card, buckets): the non-empty buckets of the visited levels, at most as many as there are."""
    own = sketch.select("set_id", "level", "bucket").join(windows, ["set_id", "level"])
    return own.groupBy("set_id", "level", "card").agg(F.sort_array(F.collect_list("bucket")).alias("buckets"))


def signatures(held: DataFrame, p: SketchParams) -> DataFrame:
    """Min-hashes of the bucket numbers, native; one array of rows * bands numbers per (set, level)."""
    hashes = [F.array_min(F.transform("buckets", partial(_hashed, ab))).cast("int") for ab in p.draw("minhash", p.rows * p.bands)]
    return held.select("set_id", "level", "card", F.array(*hashes).alias("sig"))


def _hashed(ab, b):
    return shift_hash(b.cast("long"), ab, SIGNATURE_BITS)


def _look_up(batches, ranks):
    for batch in batches:
        lists = batch.column("buckets")
        at = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()))])
        sig = np.minimum.reduceat(ranks[np.asarray(lists.flatten())], at[:-1], axis=0) if len(batch) else np.zeros((0, ranks.shape[1]), np.int32)
        flat = pa.array(sig.ravel())
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("set_id", "level", "card")), pa.ListArray.from_arrays(pa.array(np.arange(len(batch) + 1, dtype=np.int32) * ranks.shape[1]), flat)], ["set_id", "level", "card", "sig"])


def signatures_fast(held: DataFrame, p: SketchParams) -> DataFrame:
    """The same signatures by a table of all buckets' hashes (buckets x functions, fixed size) on Arrow batches."""
    b = np.arange(p.buckets, dtype=np.uint64)
    ranks = np.stack([((np.uint64(a) * b + np.uint64(c)) & np.uint64(0xFFFFFFFF)) >> np.uint64(32 - SIGNATURE_BITS) for a, c in p.draw("minhash", p.rows * p.bands)], axis=1).astype(np.int32)
    return held.mapInArrow(partial(_look_up, ranks=ranks), "set_id long, level int, card long, sig array<int>")


def bands(signed: DataFrame, p: SketchParams) -> DataFrame:
    """(set_id, level, card, band, band_key), keys spelled out."""
    keys = F.array(*[F.array_join(F.slice("sig", j * p.rows + 1, p.rows), "-") for j in range(p.bands)])
    return signed.select("set_id", "level", "card", F.posexplode(keys).alias("band", "band_key"))


def hashed_bands(signed: DataFrame, p: SketchParams) -> DataFrame:
    """The same with 64-bit keys, for production: keys that collide can only add candidates."""
    keys = F.array(*[F.xxhash64(F.slice("sig", j * p.rows + 1, p.rows)) for j in range(p.bands)])
    return signed.select("set_id", "level", "card", F.posexplode(keys).alias("band", "band_key"))


def candidates(banded: DataFrame, r1: float) -> DataFrame:
    """Pairs with an equal band at a common level and a size ratio of r1 at least.

    Band keys that one set alone has are dropped before the join, on the join's own partitioning.
    """
    key = ["level", "band", "band_key"]
    rows = banded.withColumn("n", F.count("*").over(Window.partitionBy(*key))).where("n > 1").drop("n")
    left, right = rows.withColumnsRenamed({"set_id": "left_id", "card": "a"}), rows.withColumnsRenamed({"set_id": "right_id", "card": "b"})
    fits = (F.col("a") >= r1 * F.col("b")) & (F.col("b") >= r1 * F.col("a"))
    return left.join(right, key).where((F.col("left_id") < F.col("right_id")) & fits).select("left_id", "right_id").distinct()


def between(banded: DataFrame, queries: DataFrame, r1: float) -> DataFrame:
    """(query_id, set_id) of new sets, banded alike, and those of a stored index that share a band with them."""
    key = ["level", "band", "band_key"]
    q = queries.withColumnsRenamed({"set_id": "query_id", "card": "a"})
    fits = (F.col("a") >= r1 * F.col("card")) & (F.col("card") >= r1 * F.col("a"))
    return q.join(banded, key).where(fits & (F.col("query_id") != F.col("set_id"))).select("query_id", "set_id").distinct()


def sorted_candidates(banded: DataFrame, r1: float) -> DataFrame:
    """The same pairs as candidates(), from runs of equal keys in sorted partitions instead of a join."""
    rows = banded.repartition("band_key").sortWithinPartitions("level", "band", "band_key", "set_id")
    kind = banded.schema["band_key"].dataType.simpleString()
    rows = rows.select("level", "band", F.col("band_key").cast("string"), "set_id", "card") if kind != "string" else rows
    return rows.select("level", "band", "band_key", "set_id", "card").mapInArrow(partial(_run_pairs, r1=r1), "left_id long, right_id long").distinct()


def _run_pairs(batches, r1: float):
    """Each set with those before it in its run; a run is held, as all its pairs are the answer."""
    last, run = None, []
    for batch in batches:
        out = []
        for level, band, key, own, card in zip(*(batch.column(c).to_pylist() for c in ("level", "band", "band_key", "set_id", "card")), strict=True):
            if (level, band, key) != last:
                last, run = (level, band, key), []
            out += [(other, own) for other, size in run if other != own and size >= r1 * card and card >= r1 * size]
            run.append((own, card))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["left_id", "right_id"])


def signature_classes(signed: DataFrame) -> DataFrame:
    """(set_id, rep): sets with equal signatures at all their levels, named by the smallest.

    Pairs of representatives and this membership say all that pairs of members would, without their square.
    """
    whole = signed.groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct("level", F.xxhash64("sig").alias("h")))).alias("all"))
    named = whole.select("set_id", F.xxhash64("all").alias("name"))
    return named.join(named.groupBy("name").agg(F.min("set_id").alias("rep")), "name").select("set_id", "rep")


def fixed_level(cards: DataFrame, level: int) -> DataFrame:
    """(set_id, card, level) with one level for all sets: similarities that weigh what neither set has depend on the
    universe, not on the sets' sizes."""
    return cards.select("set_id", "card", F.lit(level).alias("level"))


def size_candidates(cards: DataFrame, r1: float) -> DataFrame:
    """left_id, right_id, same: pairs of sizes within the ratio r1, each size named by its smallest set, and with `same` that
    set and each other one of its size; all pairs of sets follow from these. A range join made an equality join on
    logarithmic size classes."""
    named = cards.groupBy("card").agg(F.min("set_id").alias("rep"))
    rows = named.withColumn("cls", F.floor(F.log(F.col("card").cast("double")) / F.log(F.lit(1 / r1))))
    left = rows.select(F.col("rep").alias("u"), F.col("card").alias("a"), F.explode(F.array(F.col("cls"), F.col("cls") + 1)).alias("cls"))
    right = rows.select(F.col("rep").alias("v"), F.col("card").alias("b"), "cls")
    near = left.join(right, "cls").where((F.col("u") != F.col("v")) & (F.col("a") <= F.col("b")) & (F.col("a") >= r1 * F.col("b")))
    pairs = near.select(F.least("u", "v").alias("left_id"), F.greatest("u", "v").alias("right_id")).distinct().withColumn("same", F.lit(False))
    members = cards.join(F.broadcast(named), "card").where("set_id <> rep").select(F.col("rep").alias("left_id"), F.col("set_id").alias("right_id"), F.lit(True).alias("same"))
    return pairs.union(members)


def estimate_pairs(pairs: DataFrame, words: DataFrame, cards: DataFrame, p: SketchParams) -> DataFrame:
    """left_id, right_id, level, both, either, est: occupied buckets of two bitmaps at the level the larger set calls for."""
    a, b = cards.select(F.col("set_id").alias("left_id"), F.col("card").alias("a")), cards.select(F.col("set_id").alias("right_id"), F.col("card").alias("b"))
    target = F.lit(p.alpha * p.r1) * F.greatest("a", "b")
    level = sum((F.when(target >= 2.0**k, 1).otherwise(0) for k in range(1, p.log_m + 1)), F.lit(0)).cast("int")
    asked = pairs.join(a, "left_id").join(b, "right_id").select("left_id", "right_id", level.alias("level"))
    left, right = words.withColumnsRenamed({"set_id": "left_id", "words": "lw"}), words.withColumnsRenamed({"set_id": "right_id", "words": "rw"})
    met = asked.join(left, ["left_id", "level"], "left").join(right, ["right_id", "level"], "left")
    none = F.array(*[F.lit(0).cast("long")] * max(1, p.buckets // 64))
    lw, rw = F.coalesce("lw", none), F.coalesce("rw", none)
    count = lambda x: F.aggregate(x, F.lit(0).cast("long"), lambda s, v: s + F.bit_count(v))
    both, either = count(F.zip_with(lw, rw, lambda x, y: x.bitwiseAND(y))), count(F.zip_with(lw, rw, lambda x, y: x.bitwiseOR(y)))
    out = met.select("left_id", "right_id", "level", both.alias("both"), either.alias("either"))
    return out.withColumn("est", F.when(F.col("either") == 0, 1.0).otherwise(F.col("both") / F.col("either")))


def estimate_all(words: DataFrame, cards: DataFrame, p: SketchParams) -> DataFrame:
    """estimate_pairs() of every pair of sets: each set's bitmaps are one row, and those rows meet without a shuffle."""
    none = F.array(*[F.lit(0).cast("long")] * max(1, p.buckets // 64))
    held = words.groupBy("set_id").agg(F.map_from_entries(F.collect_list(F.struct("level", "words"))).alias("m"))
    every = F.transform(F.sequence(F.lit(0), F.lit(p.log_m)), lambda k: F.coalesce(F.try_element_at("m", k), none))
    sets = blocks.stored(cards.join(held, "set_id", "left").select("set_id", "card", every.alias("w")).repartition(64), "bitmaps")
    left, right = sets.toDF("left_id", "a", "lw"), sets.toDF("right_id", "b", "rw")
    target = F.lit(p.alpha * p.r1) * F.greatest("a", "b")
    level = sum((F.when(target >= 2.0**k, 1).otherwise(0) for k in range(1, p.log_m + 1)), F.lit(0)).cast("int")
    met = left.join(F.broadcast(right), F.col("left_id") < F.col("right_id")).withColumn("level", level)
    met = met.select("left_id", "right_id", "level", F.get("lw", F.col("level")).alias("x"), F.get("rw", F.col("level")).alias("y"))
    bits = lambda f: sum((F.bit_count(f(F.get("x", F.lit(i)), F.get("y", F.lit(i)))).cast("long") for i in range(max(1, p.buckets // 64))), F.lit(0).cast("long"))
    out = met.select("left_id", "right_id", "level", bits(lambda x, y: x.bitwiseAND(y)).alias("both"), bits(lambda x, y: x.bitwiseOR(y)).alias("either"))
    return out.withColumn("est", F.when(F.col("either") == 0, 1.0).otherwise(F.col("both") / F.col("either")))


def corrected(both, na, nb, buckets: int):
    """Jaccard from occupancies freed of bucket collisions: each count n of buckets stands for -c ln(1 - n / c) items."""
    items = lambda n: -buckets * F.log(1 - F.least(n, F.lit(buckets - 1)) / buckets)
    union = items(na + nb - both)
    return F.when(union == 0, 1.0).otherwise((items(na) + items(nb) - union) / union)


def estimate_rational(pairs: DataFrame, sampled_universe: int, s: Similarity = JACCARD) -> DataFrame:
    """Any rational similarity of a level's samples, the universe being what of it was sampled."""
    from ebbset.operators.similarity import rational_similarity

    return pairs.withColumn("est", rational_similarity(F.col("both"), F.col("either"), F.col("either") - F.col("both"), F.lit(sampled_universe), s))


def find_pairs(net: DataFrame, sketch: DataFrame, cards: DataFrame, p: SketchParams) -> DataFrame:
    """Candidate pairs of a sketch, by the fast signatures."""
    held = occupied(sketch, level_windows(cards, p))
    return candidates(bands(signatures_fast(held, p), p), p.r1)


