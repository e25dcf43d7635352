"""The leveled bucket sketch: counters per set, sampling level and bucket, linear in the updates.

Cells are a long table (set_id, level, bucket, cnt) without zeros: a live item takes two at most, so a sketch is never
larger than twice its set and, for large sets, bounded by levels times buckets. Level 0 receives every item; under the
shared bucket hash it is the sum of the other levels and is derived on the same partitioning instead of doubling the
stream.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.functions.hashing import hash_input, level_of, shift_hash
from ebbset.params import SketchParams


def bits_of(n: int) -> int:
    return n.bit_length() - 1


def placed(updates: DataFrame, p: SketchParams, mode: str = "scrambled") -> DataFrame:
    """Updates with the level and, under the shared hash, the bucket of their item."""
    x = updates.withColumn("x", hash_input(F.col("item_id"), mode))
    level = level_of(shift_hash(F.col("x"), p.draw("level", 1)[0], p.log_m), p.log_m)
    return x.withColumn("level", level).withColumn("bucket", shift_hash(F.col("x"), p.draw("bucket", 1)[0], bits_of(p.buckets)).cast("int"))


def cells(updates: DataFrame, p: SketchParams, mode: str = "scrambled", ids: bool = False) -> DataFrame:
    """The sketch's non-zero counters; ids also keeps the sum of item ids, which names the item of a cell that holds one."""
    rows = placed(updates, p, mode)
    sums = [F.sum("delta").cast("long").alias("cnt")] + ([F.sum(F.col("delta") * F.col("item_id")).cast("long").alias("idsum")] if ids else [])
    if p.bucket_hash == "per_level":
        ab = p.draw("per-level", p.log_m + 1)
        own = F.element_at(F.array(*[shift_hash(F.col("x"), v, bits_of(p.buckets)).cast("int") for v in ab]), F.col("level") + 1)
        zero = shift_hash(F.col("x"), ab[0], bits_of(p.buckets)).cast("int")
        at = F.explode(F.array(F.struct("level", own.alias("bucket")), F.struct(F.lit(0).alias("level"), zero.alias("bucket")))).alias("c")
        rows = rows.select("set_id", "item_id", "delta", at).select("set_id", "item_id", "delta", "c.*")
        return rows.groupBy("set_id", "level", "bucket").agg(*sums).where("cnt <> 0")
    # partial sums first, so that hot sets collapse before the shuffle by set; level 0 then needs no shuffle of its own
    leveled = rows.groupBy("set_id", "level", "bucket").agg(*sums).repartition("set_id")
    names = ["cnt", *(["idsum"] if ids else [])]
    zero = leveled.groupBy("set_id", "bucket").agg(*[F.sum(c).alias(c) for c in names]).select("set_id", F.lit(0).alias("level"), "bucket", *names)
    return leveled.select("set_id", "level", "bucket", *names).union(zero).where("cnt <> 0")


def merged(a: DataFrame, b: DataFrame, sign: int = 1) -> DataFrame:
    """The sketch of two streams together, or of their difference."""
    both = a.select("set_id", "level", "bucket", "cnt").union(b.select("set_id", "level", "bucket", (F.col("cnt") * sign).alias("cnt")))
    return both.groupBy("set_id", "level", "bucket").agg(F.sum("cnt").alias("cnt")).where("cnt <> 0")


def packed(sketch: DataFrame, p: SketchParams) -> DataFrame:
    """Occupancy bitmaps: set_id, level, words (64 buckets each)."""
    size = max(1, p.buckets // 64)
    bit = F.expr("shiftleft(1L, bucket % 64)")
    word = sketch.groupBy("set_id", "level", F.floor(F.col("bucket") / 64).cast("int").alias("word")).agg(F.bit_or(bit).alias("bits"))
    sums = [F.coalesce(F.bit_or(F.when(F.col("word") == i, F.col("bits"))), F.lit(0)) for i in range(size)]
    return word.groupBy("set_id", "level").agg(F.array(*sums).alias("words"))


def collision_report(net: DataFrame, p: SketchParams) -> DataFrame:
    """Per level: items sampled, cells they fill, and cells that hold one item only."""
    own = placed(net.withColumn("delta", F.lit(1)), p)
    both = own.select("set_id", "level", "bucket").union(own.select("set_id", F.lit(0).alias("level"), "bucket"))
    cell = both.groupBy("set_id", "level", "bucket").agg(F.count("*").alias("n"))
    return cell.groupBy("level").agg(F.sum("n").alias("items"), F.count("*").alias("cells"), F.count_if(F.col("n") == 1).alias("perfect"))


def space_report(sketch: DataFrame, net: DataFrame, p: SketchParams) -> DataFrame:
    """Cells, bits and stored items of all sets together: dense_bits is what full arrays would take."""
    a = sketch.agg(F.count("*").alias("cells"), F.countDistinct("set_id", "level").alias("arrays"))
    b = net.agg(F.count("*").alias("items"), F.countDistinct("set_id").alias("sets"))
    return a.join(F.broadcast(b)).select("cells", "items", "sets", (F.col("arrays") * p.buckets).alias("bitmap_bits"), (F.col("sets") * (p.log_m + 1) * p.buckets * p.log_m).alias("dense_bits"))


def first_bucket(sketch: DataFrame) -> DataFrame:
    """The simplest fingerprint: the smallest non-empty bucket."""
    return sketch.groupBy("set_id", "level").agg(F.min("bucket").alias("first_bucket"))


def sampled(view: DataFrame, p: SketchParams, level: int, nested: bool = False) -> DataFrame:
    """The items of one sampling level (rate 2**-level), or of all deeper levels, which is a sample of the same rate."""
    own = placed(view.withColumn("delta", F.lit(1)), p)
    return own.where(F.col("level") > level if nested else F.col("level") == level).select("set_id", "item_id")
