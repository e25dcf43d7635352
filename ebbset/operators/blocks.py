"""Exact intersections of all pairs of sets, block against block, so that shared items are never rows of a shuffle.

Sets are dealt into blocks; a task gets two of them and counts what their sets share by an inverted index, some sets of
the one against all of the other at a time. What is shuffled is each set once a block, whatever sets share.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.session import scratch

#: Sets and items of a block at most (on average), pairs and shared items looked at together.
SETS, ITEMS, CELLS, MATCHES = 8192, 4 << 20, 4 << 20, 8 << 20
#: Where so many products of a matrix cost no more than a match, sets are multiplied as rows of zeros and ones, of so many
#: cells at most.
DENSE, ONES = 200, 16 << 20
#: Blocks at least, where there are that many sets, to keep several tasks busy.
FEWEST = 8


def stored(df: DataFrame, name: str) -> DataFrame:
    """The rows as files in the shared folder, computed once."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def paired(sets: DataFrame, many: int, items: int) -> tuple[DataFrame, int]:
    """Sets with a number `pair` of two blocks, once for every block, and whether they belong to its second one; rows are
    partitioned and sorted by that number."""
    b = max(min(FEWEST, many), math.ceil(many / SETS), math.ceil(items / ITEMS))
    own = F.pmod(F.xxhash64("set_id"), F.lit(b)).alias("own")
    both = sets.select("*", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(b - 1))))
    low, high = F.least("own", "other"), F.greatest("own", "other")
    rows = both.withColumn("pair", (low * b + high).cast("long")).withColumn("second", F.col("own") > F.col("other")).drop("own", "other")
    tasks = b * (b + 1) // 2
    return rows.repartitionByRange(tasks, "pair").sortWithinPartitions("pair"), b


def groups(batches, key: str) -> Iterator[pa.Table]:
    """Whole runs of equal keys of sorted batches, one at a time."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        keys = np.asarray(batch.column(key))
        cut = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(cut[:-1], cut[1:], strict=True):
            if a == b:
                continue
            if held and keys[a] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = keys[a]
    if held:
        yield pa.Table.from_batches(held)


def lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of a list column."""
    size = np.concatenate([[0], *[np.asarray(c.value_lengths()) for c in column.chunks]]).astype(np.int64)
    flat = [np.asarray(c.flatten()) for c in column.chunks]
    return np.concatenate(flat) if flat else np.zeros(0, np.int64), np.cumsum(size)


def strips(left: np.ndarray, at: np.ndarray, right: np.ndarray, to: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from, to, cell, item): for some left sets at a time the cells (left set - from) * right sets + right set that an
    item of the left sets, given by its place, falls into."""
    many = len(to) - 1
    owner = np.repeat(np.arange(many), np.diff(to))
    order = np.argsort(right, kind="stable")
    ranked, owner = right[order], owner[order]
    begin, end = np.searchsorted(ranked, left, "left"), np.searchsorted(ranked, left, "right")
    met = np.concatenate([[0], np.cumsum(end - begin)])
    lo, n, most = 0, len(at) - 1, max(1, CELLS // max(1, many))
    while lo < n:
        hi = max(lo + 1, min(n, lo + most, int(np.searchsorted(met[at], met[at[lo]] + MATCHES, "right")) - 1))
        a, b = int(at[lo]), int(at[hi])
        size = end[a:b] - begin[a:b]
        item = np.repeat(np.arange(a, b), size)
        spot = owner[np.arange(len(item)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(begin[a:b], size)]
        row = np.repeat(np.arange(hi - lo), np.diff(at[lo : hi + 1]))
        yield lo, hi, np.repeat(row, size) * many + spot, item
        lo = hi


def _ones(flat: np.ndarray, at: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Sets as rows that are one at the items they have of the known (sorted) ones."""
    out = np.zeros((len(at) - 1, len(known)), np.float32)
    place = np.minimum(np.searchsorted(known, flat), len(known) - 1)
    has = known[place] == flat
    out[np.repeat(np.arange(len(at) - 1), np.diff(at))[has], place[has]] = 1
    return out


def counts(left: np.ndarray, at: np.ndarray, right: np.ndarray, to: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
    """(from, to, count by cell) as strips() has them: by products of matrices where sets are dense enough."""
    many = len(to) - 1
    a, na = np.unique(left, return_counts=True)
    b, nb = np.unique(right, return_counts=True)
    known, i, j = np.intersect1d(a, b, assume_unique=True, return_indices=True)
    lo, n = 0, len(at) - 1
    if not len(known) or n * many * len(known) > DENSE * int(na[i] @ nb[j]) or (n + many) * len(known) > ONES:
        for lo, hi, cell, _ in strips(left, at, right, to):
            yield lo, hi, np.bincount(cell, minlength=(hi - lo) * many)
        return
    mine, other = _ones(left, at, known), _ones(right, to, known).T
    for lo in range(0, n, max(1, CELLS // max(1, many))):
        hi = min(n, lo + max(1, CELLS // max(1, many)))
        yield lo, hi, np.rint(mine[lo:hi] @ other).astype(np.int64).ravel()


def _crossed(batches, marks: int, many_blocks: int):
    for table in groups(batches, "pair"):
        second = np.asarray(table.column("second"))
        ids = np.asarray(table.column("set_id"))
        first = ~second
        one = table.filter(pa.array(first))
        pair = table.column("pair")[0].as_py()
        same = pair // many_blocks == pair % many_blocks  # a block against itself
        two = one if same else table.filter(pa.array(second))
        left_id, right_id = ids[first], ids[first] if same else ids[second]
        left, at = lists(one.column("items"))
        right, to = lists(two.column("items"))
        if not len(left_id) or not len(right_id):
            continue
        na, nb = np.asarray(one.column("card")), np.asarray(two.column("card"))
        many = len(right_id)
        if marks:
            bits, more = lists(one.column("marks"))[0], lists(two.column("marks"))[0]
            mine = [np.add.reduceat(bits >> i & 1, at[:-1]) for i in range(marks)]
            other = [np.add.reduceat(more >> i & 1, to[:-1]) for i in range(marks)]
        steps = strips(left, at, right, to) if marks else ((*c, None) for c in counts(left, at, right, to))
        for lo, hi, cell, item in steps:
            count = np.bincount(cell, minlength=(hi - lo) * many) if marks else cell
            hit = np.flatnonzero(count)
            i, j = hit // many + lo, hit % many
            if same:
                keep = left_id[i] < right_id[j]
                hit, i, j = hit[keep], i[keep], j[keep]
            if not len(hit):
                continue
            a, b, inter = left_id[i], right_id[j], count[hit]
            cols = [pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(inter), pa.array(na[i] + nb[j] - inter)]
            names = ["left_id", "right_id", "inter", "uni"]
            for m in range(marks):
                z = np.bincount(cell[(bits[item] >> m & 1) == 1], minlength=(hi - lo) * many)[hit]
                cols += [pa.array(z), pa.array(np.where(z > 0, mine[m][i] + other[m][j] - z, 0))]
                names += [f"zi{m}", f"zu{m}"]
            whole = pa.RecordBatch.from_arrays(cols, names)
            for k in range(0, len(whole), 1 << 16):
                yield whole.slice(k, 1 << 16)


def held_sets(view: DataFrame, marks=None) -> tuple[DataFrame, int, int]:
    """(set_id, items, their marks, card) in files, how many sets and how many items."""
    view = view.where("set_id is not null")
    if marks is None:
        held = view.groupBy("set_id").agg(F.collect_list(F.col("item_id").cast("long")).alias("items"), F.count("*").alias("card"))
    else:
        both = view.where("item_id is not null").select("set_id", F.struct(F.col("item_id").cast("long").alias("item_id"), marks.cast("int").alias("m")).alias("x")).groupBy("set_id").agg(F.collect_list("x").alias("x"), F.count("*").alias("card"))
        held = both.select("set_id", F.col("x.item_id").alias("items"), F.col("x.m").alias("marks"), "card")
    sets = stored(held.withColumn("set_id", F.col("set_id").cast("long")), "sets")
    many, items = sets.agg(F.count("*"), F.coalesce(F.sum(F.size("items")), F.lit(0))).first()
    return sets, many, items


def exact_pairs(view: DataFrame, marks=None, bits: int = 0) -> DataFrame:
    """left_id, right_id, inter, uni of all pairs that share an item. marks: a whole number of an item whose bits say which
    of so many samples it is in; zi and zu of each then are sizes of intersection and union in the sample (0 if disjoint)."""
    return pairs_of(*held_sets(view, marks), bits)


def pairs_of(sets: DataFrame, many: int, items: int, bits: int = 0) -> DataFrame:
    """The same of sets as held_sets() gives them."""
    shape = "left_id long, right_id long, inter long, uni long" + "".join(f", zi{i} long, zu{i} long" for i in range(bits))
    if not many:
        return sets.sparkSession.createDataFrame([], shape)
    rows, many_blocks = paired(sets, many, items)
    return rows.mapInArrow(partial(_crossed, marks=bits, many_blocks=many_blocks), shape)
