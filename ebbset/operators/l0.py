"""Linear distinct-count sketches and the distances they give.

A cell sums field coefficients of the items in a bucket, signed by the update and taken modulo a prime, so sketches add
and subtract: the sum of two counts a union, their difference a symmetric difference. Plain counters would not do, as
two items in one bucket could cancel. Items lie at one level each (rate 2**-k); the items of all levels from k on are a
sample of rate 2**(1 - k).
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.functions.hashing import PRIME, coefficient, hash_input, level_of, shift_hash
from ebbset.operators import blocks
from ebbset.params import Similarity, SketchParams

#: Right sets whose bitmaps a left one meets at a time.
STEP = 256


def l0_cells(updates: DataFrame, p: SketchParams, reps: int = 3) -> DataFrame:
    """set_id, rep, level, bucket, cell (modulo the prime, non-zero)."""
    x = updates.withColumn("x", hash_input(F.col("item_id")))
    bits = p.buckets.bit_length() - 1
    one = []
    for r in range(reps):
        level, bucket, weight = p.draw(f"l0-level-{r}", 1)[0], p.draw(f"l0-bucket-{r}", 1)[0], p.draw(f"l0-weight-{r}", 1)[0]
        one.append(F.struct(F.lit(r).alias("rep"), level_of(shift_hash(F.col("x"), level, p.log_m), p.log_m).alias("level"), shift_hash(F.col("x"), bucket, bits).cast("int").alias("bucket"), coefficient(F.col("x"), weight).alias("w")))
    rows = x.select("set_id", "delta", F.explode(F.array(*one)).alias("c")).select("set_id", "delta", "c.*")
    cell = F.pmod(F.sum(F.col("delta") * F.col("w")), F.lit(PRIME)).alias("cell")
    return rows.groupBy("set_id", "rep", "level", "bucket").agg(cell).where("cell <> 0")


def combined(pairs: DataFrame, sketch: DataFrame, sign: int) -> DataFrame:
    """Cells of left + sign * right for each pair, as sets named by (left_id, right_id)."""
    left = pairs.join(sketch, F.col("left_id") == F.col("set_id")).select("left_id", "right_id", "rep", "level", "bucket", "cell")
    right = pairs.join(sketch, F.col("right_id") == F.col("set_id")).select("left_id", "right_id", "rep", "level", "bucket", (F.col("cell") * sign).alias("cell"))
    total = left.union(right).groupBy("left_id", "right_id", "rep", "level", "bucket").agg(F.pmod(F.sum("cell"), F.lit(PRIME)).alias("cell"))
    return total.where("cell <> 0")


def l0_estimate(cells: DataFrame, by: list[str], p: SketchParams) -> DataFrame:
    """Number of non-zero items: per repetition from the densest sample that fills at most 0.7 of its buckets, then the
    median of the repetitions."""
    nested = cells.select(*by, "rep", "bucket", F.explode(F.expr("sequence(1, level)")).alias("k")).groupBy(*by, "rep", "k").agg(F.countDistinct("bucket").alias("used"))
    k = p.buckets
    items = -F.lit(float(k)) * F.log(1 - F.least(F.col("used"), F.lit(k - 1)) / k) * F.pow(F.lit(2.0), F.col("k") - 1)
    fit = nested.groupBy(*by, "rep").agg(F.min_by(items, F.when(F.col("used") <= 0.7 * k, F.col("k"))).alias("est"), F.max_by(items, "k").alias("top"))
    return fit.groupBy(*by).agg(F.median(F.coalesce("est", "top")).alias("items"))


def sizes(pairs: DataFrame, sketch: DataFrame, p: SketchParams) -> DataFrame:
    """left_id, right_id, and estimates of the union and the symmetric difference."""
    by = ["left_id", "right_id"]
    union = l0_estimate(combined(pairs, sketch, 1), by, p).withColumnRenamed("items", "uni")
    apart = l0_estimate(combined(pairs, sketch, -1), by, p).withColumnRenamed("items", "symdiff")
    return pairs.select(*by).join(union, by, "left").join(apart, by, "left").select(*by, F.coalesce("uni", F.lit(0.0)).alias("uni"), F.coalesce("symdiff", F.lit(0.0)).alias("symdiff"))


def _bitmaps(key: np.ndarray, at: np.ndarray, cells: int) -> np.ndarray:
    """Which cells each set has, 64 to a word."""
    out = np.zeros((len(at) - 1, cells // 64), np.uint64)
    code = key >> 31
    np.add.at(out.reshape(-1), np.repeat(np.arange(len(at) - 1), np.diff(at)) * (cells // 64) + (code >> 6), np.uint64(1) << (code & 63).astype(np.uint64))
    return out


def _items(held: np.ndarray, p: SketchParams, reps: int) -> np.ndarray:
    """l0_estimate() of bitmaps (one a row): the densest sample of each repetition that fits, and their median."""
    k, deep = p.buckets, held.reshape(len(held), reps, p.log_m, -1)
    nested = np.bitwise_or.accumulate(deep[:, :, ::-1], axis=2)[:, :, ::-1]
    used = np.bitwise_count(nested).sum(axis=-1, dtype=np.int64)
    fit = (used > 0) & (used <= 0.7 * k)
    level = np.where(fit.any(axis=2), fit.argmax(axis=2), np.maximum((used > 0).sum(axis=2) - 1, 0))
    some = np.minimum(np.take_along_axis(used, level[:, :, None], 2)[:, :, 0], k - 1)
    est = np.sort(np.where(some > 0, -k * np.log(1 - some / k) * 2.0**level, np.inf), axis=1)
    n = (some > 0).sum(axis=1)
    row = np.arange(len(held))
    return np.where(n > 0, (est[row, np.maximum(n - 1, 0) // 2] + est[row, np.minimum(n // 2, reps - 1)]) / 2, 0.0)


def _fitting(flat: np.ndarray, p: SketchParams, reps: int) -> tuple[np.ndarray, np.ndarray]:
    """_items() of bitmaps of all levels together, and which of them that holds for: where every repetition's densest sample
    fits."""
    used = np.bitwise_count(flat.reshape(len(flat), reps, -1)).sum(axis=-1, dtype=np.int64)
    est = np.sort(-p.buckets * np.log(1 - np.minimum(used, p.buckets - 1) / p.buckets), axis=1)
    return (est[:, (reps - 1) // 2] + est[:, reps // 2]) / 2, ((used > 0) & (used <= 0.7 * p.buckets)).all(axis=1)


def _spans(own: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each one begins and ends among sorted keys; asked in order, which is several times as fast."""
    order = np.argsort(own)
    asked, begin, end = own[order], np.empty(len(own), np.int64), np.empty(len(own), np.int64)
    begin[order], end[order] = np.searchsorted(keys, asked, "left"), np.searchsorted(keys, asked, "right")
    return begin, end


def _cleared(held: np.ndarray, own: np.ndarray, begin: np.ndarray, end: np.ndarray, owner: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Bitmaps, by place, without the cells of a set's keys that others hold at these spans; both have these cells."""
    some = np.flatnonzero(end > begin)
    begin, size = begin[some], (end - begin)[some]
    met = place[owner[np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(begin, size)]]
    code = np.repeat(own[some] >> 31, size)[met >= 0]
    met = met[met >= 0]
    np.subtract.at(held.reshape(-1), met * held.shape[1] + (code >> 6), np.uint64(1) << (code & 63).astype(np.uint64))
    return held


def _met(batches, p: SketchParams, reps: int, many_blocks: int):
    cells = reps * p.log_m * p.buckets
    for table in blocks.groups(batches, "pair"):
        second = np.asarray(table.column("second"))
        ids, size, pair = np.asarray(table.column("set_id")), np.asarray(table.column("card")), table.column("pair")[0].as_py()
        same = pair // many_blocks == pair % many_blocks
        first = ~second
        one = table.filter(pa.array(first))
        two = one if same else table.filter(pa.array(second))
        if not len(one) or not len(two):
            continue
        left_id, na = ids[first], size[first]
        right_id, nb = (left_id, na) if same else (ids[second], size[second])
        (left, at), (right, to) = blocks.lists(one.column("items")), blocks.lists(two.column("items"))
        (key, kat), (other, oat) = blocks.lists(one.column("keys")), blocks.lists(two.column("keys"))
        mine, theirs = _bitmaps(key, kat, cells), _bitmaps(other, oat, cells)
        levels = lambda held: np.bitwise_or.reduce(held.reshape(len(held), reps, p.log_m, -1), axis=2)
        flat, others = levels(mine), levels(theirs)
        owner = np.repeat(np.arange(len(right_id)), np.diff(oat))
        order = np.argsort(other, kind="stable")
        ranked, owner = other[order], owner[order]
        many = len(right_id)
        for lo, hi, count in blocks.counts(left, at, right, to):
            count = count.reshape(hi - lo, many)
            near = key[kat[lo] : kat[hi]]
            alike, gone = _spans(near, ranked), _spans((near >> 31 << 31) + PRIME - (near & PRIME), ranked)
            for i in range(lo, hi):
                hit = np.flatnonzero(count[i - lo])
                if same:
                    hit = hit[left_id[i] < right_id[hit]]
                x, y = kat[i] - kat[lo], kat[i + 1] - kat[lo]
                own, equal, zero = near[x:y], [c[x:y] for c in alike], [c[x:y] for c in gone]
                some = (zero[1] > zero[0]).any()
                for s in range(0, len(hit), STEP):
                    j = hit[s : s + STEP]
                    place = np.full(many, -1)
                    place[j] = np.arange(len(j))
                    both = mine[i] | theirs[j]
                    if some:
                        union = _items(_cleared(both.copy(), own, *zero, owner, place), p, reps)
                    else:
                        union, fits = _fitting(flat[i] | others[j], p, reps)
                        if not fits.all():
                            union[~fits] = _items(both[~fits], p, reps)
                    both = _cleared(both, own, *equal, owner, place)
                    apart, fits = _fitting(levels(both), p, reps)
                    if not fits.all():
                        apart[~fits] = _items(both[~fits], p, reps)
                    inter = count[i - lo, j]
                    a, b = np.minimum(left_id[i], right_id[j]), np.maximum(left_id[i], right_id[j])
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in (a, b, inter, na[i] + nb[j] - inter, union, apart)], ["left_id", "right_id", "inter", "uni", "uni_est", "symdiff_est"])


def exact_and_estimated(net: DataFrame, sketch: DataFrame, p: SketchParams, reps: int) -> DataFrame:
    """left_id, right_id, inter, uni of all pairs that share an item, and the estimates that sizes() gives of them.

    Pairs are met block against block, as bitmaps of cells: a union has those of both, a symmetric difference not those of
    the same sum. So neither the pairs nor their cells are rows of a shuffle.
    """
    code = (F.col("rep") * p.log_m + F.col("level") - 1) * p.buckets + F.col("bucket")
    keys = sketch.groupBy("set_id").agg(F.collect_list(code.cast("long") * (1 << 31) + F.col("cell")).alias("keys"))
    sets, many, items = blocks.held_sets(net)
    shape = "left_id long, right_id long, inter long, uni long, uni_est double, symdiff_est double"
    if not many:
        return net.sparkSession.createDataFrame([], shape)
    held = blocks.stored(sets.join(keys, "set_id", "left").withColumn("keys", F.coalesce("keys", F.array().cast("array<long>"))), "keyed")
    rows, many_blocks = blocks.paired(held, many, items)
    return rows.mapInArrow(partial(_met, p=p, reps=reps, many_blocks=many_blocks), shape)


def distance_of(uni, symdiff, universe: int, s: Similarity, root: float = 1.0):
    """1 - S from the sizes of union and symmetric difference; root is the exponent of a root similarity."""
    den = s.y * universe + (s.x - s.y) * uni + (s.zp - s.x) * symdiff
    if s.y > s.x:  # by complements, whose symmetric difference is the same
        inter = F.greatest(uni - symdiff, F.lit(0.0))
        den = (s.y - s.x) * (universe - inter) + s.x * universe + (s.zp - s.y) * symdiff
    plain = F.when(den <= 0, 0.0).otherwise(F.least(F.lit(1.0), (s.zp - s.z) * symdiff / den))
    return F.pow(plain, F.lit(root))


def sketched_distance(pairs: DataFrame, sketch: DataFrame, universe: int, s: Similarity, p: SketchParams, root: float = 1.0) -> DataFrame:
    """1 - S within 1 +- eps for metric similarities (and for Dice's, which isn't one); the similarity is additive only."""
    z = sizes(pairs, sketch, p)
    return z.select("left_id", "right_id", distance_of(F.col("uni"), F.col("symdiff"), universe, s, root).alias("distance"))
