"""Exact n-gram Jaccard join in metric space.

The space is that of shingle sets under the Jaccard distance. Measured against whole documents nearly all distances in
a corpus are 1, so document pivots alone would leave one far region that holds almost everything. The first level
therefore uses pivots in restricted universes: shingles are dealt into as many classes as a linked pair can differ in
plus some, so a linked pair agrees wholly in at least one class. Each distinct restricted set is the pivot of a
Voronoi region of radius 0, and a triangle-inequality window on size (the distance to the empty set) also replicates a
document into the next size class where a partner could lie there. Documents whose shingle counts by class are too far
apart in L1 to link are parted. What remains connected is joined recursively and exactly by document pivots: two
far-apart documents become pivots, what links with them is linked, each document goes to the nearer one, and those
within twice the threshold of the boundary go to both sides.

Equal sets (by 128 bits of hash) are one set from the start, named by its smallest document. Sets are connected in
steps whose links grow with the sets, not with what they share: first each set with the least one it shares a region
with, then only where a region still holds several groups. Likewise a large connected group is joined block by block,
each with the group's first set, and pairs of blocks only meet where that leaves several groups.

Defined results: null and empty texts have no shingles and link with nothing; repeated rows of one doc_id act as one
document per distinct text, all with the same component; ties in pivot choice go to the earlier set. Extra columns of
the input are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.llm._spark import components, quoted, written
from ebbset.llm._text import U, bytes_of, mix, pieces, runs, shingle_sets, signed

#: A region joins in one task up to so many bytes of text and documents; beyond, block by block.
BLOCK_BYTES, BLOCK_ROWS = 4 << 20, 2048
#: From so many sets on a region is split by pivots.
LEAF = 16
#: Classes whose shingle counts a summary keeps, at least and at most, and shingles a class in between.
LEAST_COUNTERS, MOST_COUNTERS, PER_COUNTER = 64, 1 << 15, 6


@dataclass(frozen=True)
class Measure:
    """Sets link when high * intersection >= low * union."""

    width: int = 5
    low: int = 80
    high: int = 100

    def size_class(self, n: int) -> tuple[int, int, int]:
        """Number, smallest and largest size of the class of a set size."""
        lo, number = 1, 0
        while True:
            up = max(lo, int(lo * 1.5) - 1)
            if n <= up:
                return number, lo, up
            lo, number = up + 1, number + 1

    def classes(self, lo: int, up: int) -> tuple[int, int]:
        """How many classes the shingles of a size class are dealt into, and how many a set may leave out: a linked pair
        agrees in one class more than that at least. Room for classes of less than two shingles where they are few,
        else for empty ones."""
        differ = 2 * up * (self.high - self.low) // (self.high + self.low)
        if not differ:
            return 1, 0
        for size, few, room, most in ((0.5 * (lo + up), 2, 1, 1.3), (lo * self.low / self.high, 1, 3, 2.0)):
            m = differ + 1
            while m <= most * (differ + 1) + 2:
                mean = size / m
                thin = m * math.exp(-mean) * (1 + mean if few == 2 else 1)
                if math.ceil(thin + room * math.sqrt(thin)) <= m - differ - 1:
                    return m, m - differ - 1
                m += 1
        return m, m - differ - 1

    def reaches(self, n: int) -> list[tuple[int, int, int]]:
        """(number, classes, spare) of the size classes that hold n or its larger partners."""
        number, lo, up = self.size_class(n)
        out = [(number, *self.classes(lo, up))]
        if self.high * n >= self.low * (up + 1):
            _, lo, top = self.size_class(up + 1)
            out.append((number + 1, *self.classes(lo, top)))
        return out

    def linked(self, inter: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self.high * inter >= self.low * (a + b - inter)


def region_keys(sets: list[np.ndarray], measure: Measure, plans: dict[int, list]) -> Iterator[tuple[int, np.ndarray]]:
    """(row, keys of the regions it lies in): those of its restricted sets."""
    for row, own in enumerate(sets):
        if not len(own):
            continue
        n = len(own)
        if n not in plans:
            plans[n] = measure.reaches(n)
        deal, value = mix(own, 1) >> U(20), mix(own, 2)
        for number, m, spare in plans[n]:
            if m == 1:
                yield row, mix(np.array([value.sum(dtype=np.uint64)]) + U(number * 977))
                continue
            place = (deal % U(m)).astype(np.int64)
            total = np.zeros(m, np.uint64)
            np.add.at(total, place, value)
            count = np.bincount(place, minlength=m)
            # of two linked sets the one that leaves out more decides: it leaves out `spare` at most, so an agreeing class stays
            least = next(t for t in (3, 2, 1, 0) if (count < t).sum() <= spare)
            keys = mix(mix(total) + np.arange(m, dtype=np.uint64) + U(number << 32))
            yield row, keys[count >= least]


def names(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """128 bits that name each set."""
    out = np.zeros((2, len(sets)), np.uint64)
    for i, s in enumerate(sets):
        out[0, i], out[1, i] = mix(s, 3).sum(dtype=np.uint64), mix(s, 7).sum(dtype=np.uint64)
    return mix(out[0]), mix(out[1])


def _emit(batches, measure: Measure):
    """Region keys of each distinct set of a task."""
    plans, seen = {}, set()
    for batch in batches:
        for part in pieces(batch):
            sets = shingle_sets(part.column("text"), measure.width)
            high, low = names(sets)
            for row, tag in enumerate(zip(high.tolist(), low.tolist(), strict=True)):
                if tag in seen:
                    sets[row] = sets[row][:0]
                seen.add(tag)
            keys, rows = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
            for row, found in region_keys(sets, measure, plans):
                keys.append(found)
                rows.append(np.full(len(found), row))
            key, row = np.concatenate(keys), np.concatenate(rows)
            yield pa.RecordBatch.from_arrays([signed(key), signed(high[row]), signed(low[row])], ["key", "high", "low"])


def _shared(batches):
    """Regions that hold two sets at least, named by their sets: equal regions count once. first: the least set's name."""
    for table in runs(batches, ["key"]):
        key, high, low = (np.asarray(table.column(c)) for c in ("key", "high", "low"))
        fresh = np.ones(len(key), bool)
        fresh[1:] = (key[1:] != key[:-1]) | (high[1:] != high[:-1]) | (low[1:] != low[:-1])
        key, high, low = key[fresh], high[fresh], low[fresh]
        first = np.ones(len(key), bool)
        first[1:] = key[1:] != key[:-1]
        at = np.flatnonzero(first)
        count = np.diff(np.append(at, len(key)))
        name = np.repeat(mix(np.add.reduceat(mix(high.view(np.uint64), 6), at) + count.astype(np.uint64)), count)
        keep = np.repeat(count > 1, count)
        if keep.any():
            head = np.repeat(at, count)
            _, one = np.unique(np.stack([name[keep].view(np.int64), high[keep], low[keep]], axis=1), axis=0, return_index=True)
            cols = [x[keep][one] for x in (name.view(np.int64), high, low, high[head], low[head])]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["key", "high", "low", "first_high", "first_low"])


def counters(n: int) -> int:
    """How many classes a set of n shingles is counted in: a power of two, so that longer counts fold into shorter ones."""
    size = LEAST_COUNTERS
    while size * PER_COUNTER < n and size < MOST_COUNTERS:
        size *= 2
    return size


def _summary(batches, width: int):
    """Set size, name, and the number of shingles in each class, at most 255."""
    for batch in batches:
        for part in pieces(batch):
            sets = shingle_sets(part.column("text"), width)
            counts = []
            for own in sets:
                many = counters(len(own))
                counts.append(np.minimum(np.bincount((mix(own, 5) % U(many)).astype(np.int64), minlength=many), 255).astype(np.uint8).tobytes())
            size = pa.array([len(s) for s in sets], pa.int64())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), size, *map(signed, names(sets)), pa.array(counts, pa.binary())], ["doc_id", "n_shingles", "high", "low", "counts"])


class _Counts:
    """The class counts of a table's rows."""

    def __init__(self, flat: np.ndarray, offsets: np.ndarray, size: np.ndarray, measure: Measure):
        self.flat, self.at, self.many, self.size, self.measure = flat, offsets[:-1], np.diff(offsets), size, measure

    def _folded(self, rows: np.ndarray, many: int, to: int) -> np.ndarray:
        found = self.flat[self.at[rows][:, None] + np.arange(many)].reshape(len(rows), many // to, to)
        return found.sum(axis=1, dtype=np.int32)

    def may_link(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether sets may link: counts that differ by more than linked sets of these sizes can rule it out."""
        out = np.zeros(len(a), bool)
        size, other = self.size[a], self.size[b]
        within = self.measure.high * np.minimum(size, other) >= self.measure.low * np.maximum(size, other)
        kind = np.where(within, self.many[a] * (1 << 20) + self.many[b], -1)
        for k in np.unique(kind[within]):
            mine = np.flatnonzero(kind == k)
            left, right = int(k >> 20), int(k & ((1 << 20) - 1))
            to = min(left, right)
            step = max(1, (4 << 20) // max(left, right))
            for i in range(0, len(mine), step):
                m = mine[i : i + step]
                out[m] = np.abs(self._folded(a[m], left, to) - self._folded(b[m], right, to)).sum(axis=1) * (self.measure.high + self.measure.low) <= (self.measure.high - self.measure.low) * (self.size[a[m]] + self.size[b[m]])
        return out


def _may_link(batches, measure: Measure):
    """Of pairs of sets those whose class counts don't rule a link out."""
    for batch in batches:
        n = len(batch)
        size = np.concatenate([np.asarray(batch.column(c)) for c in ("n_a", "n_b")])
        both = pa.concat_arrays([batch.column("counts_a"), batch.column("counts_b")])
        near = _Counts(*bytes_of(both), size, measure).may_link(np.arange(n), np.arange(n) + n)
        yield batch.select(["a", "b"]).filter(pa.array(near))


def _region_links(batches, measure: Measure):
    """Links that connect, in each region, whatever sets of different groups may link in it; batches are sorted by key."""
    for table in runs(batches, ["key"]):
        key, rep, size, group = (np.asarray(table.column(c)) for c in ("key", "rep", "n_shingles", "component"))
        counts = _Counts(*bytes_of(table.column("counts").combine_chunks()), size, measure)
        cut = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)]]).tolist()
        links = []
        for lo, hi in zip(cut[:-1], cut[1:], strict=True):
            links += [(a + lo, b + lo) for a, b in _group_links(counts, np.arange(lo, hi), group[lo:hi])]
        if links:
            found = rep[np.array(links)]
            yield pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], ["a", "b"])


def _group_links(counts: _Counts, every: np.ndarray, group: np.ndarray) -> list[tuple[int, int]]:
    """One link less than the groups they connect: each set is held against those that nothing connects with it yet."""
    group = np.unique(group, return_inverse=True)[1]
    links = []
    for a in range(len(every)):
        if (group == group[0]).all():
            break
        others = np.flatnonzero(group[a + 1 :] != group[a]) + a + 1
        hit = others[counts.may_link(np.full(len(others), every[a]), every[others])] if len(others) else others
        for g, b in dict(zip(group[hit].tolist(), hit.tolist(), strict=True)).items():
            links.append((a, b))
            group[group == g] = group[a]
    return links


class _Forest:
    def __init__(self, n: int):
        self.up = list(range(n))
        self.links: list[tuple[int, int]] = []

    def find(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a: int, b: int) -> None:
        x, y = self.find(a), self.find(b)
        if x != y:
            self.up[max(x, y)] = min(x, y)
            self.links.append((a, b))


def _overlap(pivot: np.ndarray, own: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Intersection sizes of one set with each of those held end to end."""
    at = np.minimum(np.searchsorted(pivot, own), len(pivot) - 1)
    hit = np.concatenate([[0], np.cumsum(pivot[at] == own)])
    return hit[offsets[1:]] - hit[offsets[:-1]]


def join_region(sets: list[np.ndarray], measure: Measure, groups: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that connect whatever the links of these non-empty sets connect, by recursive pivot splits.

    groups: what is connected already.
    """
    forest = _Forest(len(sets))
    if groups is not None:
        _, first, own = np.unique(groups, return_index=True, return_inverse=True)
        for i, g in enumerate(own.tolist()):
            forest.join(int(first[g]), i)
        forest.links.clear()
    size = np.array([len(s) for s in sets])
    window = 2 * (1 - measure.low / measure.high) + 1e-9
    todo = [(np.arange(len(sets)), 0)]
    while todo:
        rows, depth = todo.pop()
        roots = {forest.find(int(r)) for r in rows}
        if len(roots) < 2:
            continue
        own, offsets = np.concatenate([sets[r] for r in rows]), np.concatenate([[0], np.cumsum(size[rows])])

        def look(p, rows=rows, own=own, offsets=offsets):
            inter = _overlap(sets[p], own, offsets)
            for r in rows[measure.linked(inter, size[p], size[rows])]:
                forest.join(int(p), int(r))
            return 1 - inter / (size[p] + size[rows] - inter)

        near = look(rows[0])
        if len(rows) > LEAF and depth < 40:
            far = look(rows[int(np.argmax(near))])
            left, right = near <= far, near > far
            right |= left & (far - near <= window)
            if right.sum() < 0.9 * len(rows) and left.sum() < 0.9 * len(rows):
                todo += [(rows[left], depth + 1), (rows[right], depth + 1)]
                continue
        _leaf(sets, rows, size, measure, forest)
    return forest.links


def _leaf(sets, rows, size, measure: Measure, forest: _Forest) -> None:
    """All intersection sizes of a leaf as products of 0/1 blocks; links already connected are not followed up."""
    if len(rows) <= 6:
        for i in range(1, len(rows)):
            for j in range(i):
                a, b = int(rows[j]), int(rows[i])
                if forest.find(a) != forest.find(b):
                    inter = len(np.intersect1d(sets[a], sets[b], assume_unique=True))
                    if measure.linked(inter, size[a], size[b]):
                        forest.join(a, b)
        return
    own = np.concatenate([sets[r] for r in rows])
    row = np.repeat(np.arange(len(rows)), size[rows])
    _, column, count = np.unique(own, return_inverse=True, return_counts=True)
    keep = count[column] > 1
    number = np.cumsum(count > 1) - 1
    column, row = number[column[keep]], row[keep]
    order = np.argsort(column, kind="stable")
    column, row = column[order], row[order]
    wide = 2048
    for at in range(0, len(rows), 256):
        block = slice(at, min(at + 256, len(rows)))
        inter = np.zeros((block.stop - at, len(rows)), np.float32)
        for c in range(0, int(column[-1]) + 1 if len(column) else 0, wide):
            lo, hi = np.searchsorted(column, [c, c + wide])
            bits = np.zeros((len(rows), wide), np.float32)
            bits[row[lo:hi], column[lo:hi] - c] = 1
            inter += bits[block] @ bits.T
        near = measure.linked(np.rint(inter).astype(np.int64), size[rows[block]][:, None], size[rows][None, :])
        for i, j in zip(*np.nonzero(np.triu(near, at + 1)), strict=True):
            forest.join(int(rows[at + i]), int(rows[j]))


def _join_regions(batches, measure: Measure):
    for table in runs(batches, ["region", "i", "j"]):
        group = np.stack([np.asarray(table.column(k)) for k in ("region", "i", "j")], axis=1)
        cut = np.concatenate([[0], np.flatnonzero((group[1:] != group[:-1]).any(axis=1)) + 1, [len(group)]])
        batch = table.combine_chunks().to_batches()
        ids, known = np.asarray(table.column("doc_id")), np.asarray(table.column("joined"))
        sets = [s for b in batch for part in pieces(b) for s in shingle_sets(part.column("text"), measure.width)]
        out = []
        for lo, hi in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            keep = [r for r in range(lo, hi) if len(sets[r])]
            if len(keep) > 1:
                out += [(ids[keep[a]], ids[keep[b]]) for a, b in join_region([sets[r] for r in keep], measure, known[keep])]
        if out:
            pairs = np.array(out, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])


def summaries(docs: DataFrame, measure: Measure) -> DataFrame:
    """doc_id, n_shingles, the set's name and its class counts, of every row with an id."""
    return _plain(docs).mapInArrow(partial(_summary, width=measure.width), "doc_id long, n_shingles long, high long, low long, counts binary")


def _plain(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")


def _shared_keys(docs: DataFrame, measure: Measure) -> DataFrame:
    keys = docs.where("text is not null").mapInArrow(partial(_emit, measure=measure), "key long, high long, low long")
    shared = keys.repartition("key").sortWithinPartitions("key", "high", "low").mapInArrow(_shared, "key long, high long, low long, first_high long, first_low long")
    return shared.distinct()


def _candidates(docs: DataFrame, sets: DataFrame, measure: Measure) -> DataFrame:
    """(node, component) of sets that links may connect."""
    shared = written(lambda: _shared_keys(docs, measure), "region-keys", large=True)
    # each set with the least one that it shares a region with
    least = shared.groupBy("high", "low").agg(F.min(F.struct("first_high", "first_low")).alias("f"))
    pairs = least.select("high", "low", F.col("f.first_high").alias("fh"), F.col("f.first_low").alias("fl")).where("high <> fh or low <> fl")
    own = lambda x: [F.col("rep").alias(x), F.col("n_shingles").alias(f"n_{x}"), F.col("counts").alias(f"counts_{x}")]
    pairs = pairs.join(sets.select("high", "low", *own("a")), ["high", "low"]).join(sets.select(F.col("high").alias("fh"), F.col("low").alias("fl"), *own("b")), ["fh", "fl"])
    links = lambda: pairs.select("a", "n_a", "counts_a", "b", "n_b", "counts_b").mapInArrow(partial(_may_link, measure=measure), "a long, b long")
    near = written(lambda: components(links), "near")
    # regions that still hold several groups
    member = lambda: shared.select("key", "high", "low").join(sets.select("high", "low", "rep"), ["high", "low"]).join(near, F.col("rep") == F.col("node"), "left").select("key", "high", "low", "rep", F.coalesce("component", "rep").alias("component"))
    rows = written(member, "region-sets")
    open_ = rows.groupBy("key").agg(F.min("component").alias("p"), F.max("component").alias("q")).where("p < q").select("key")
    rows = rows.join(open_, "key").join(sets.select("high", "low", "n_shingles", "counts"), ["high", "low"]).select("key", "rep", "component", "n_shingles", "counts")
    more = lambda: rows.repartition("key").sortWithinPartitions("key", "rep").mapInArrow(partial(_region_links, measure=measure), "a long, b long")
    return components(lambda: near.select(F.col("node").alias("a"), F.col("component").alias("b")).union(more()))


def near_copies(docs: DataFrame, measure: Measure, held: DataFrame | None = None) -> DataFrame:
    """(node, component) for each document with a set: the smallest document that links connect with it.

    Ids must be whole numbers. held: the documents' summaries, if written already.
    """
    docs = _plain(docs)
    held = held if held is not None else written(lambda: summaries(docs, measure), "summaries")
    by_set = lambda: held.where("n_shingles > 0").groupBy("high", "low").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n_shingles"), F.first("counts").alias("counts"))
    sets = written(by_set, "sets")
    region = written(lambda: _candidates(docs, sets, measure), "regions")
    named = held.where("n_shingles > 0").select("doc_id", "high", "low").join(sets.select("high", "low", "rep"), ["high", "low"]).select("doc_id", "rep").distinct()
    named = written(lambda: named, "named")
    # different texts under one id are one document
    least = named.groupBy("doc_id").agg(F.min("rep").alias("a"))
    same = named.join(least, "doc_id").where("a < rep").select("a", F.col("rep").alias("b"))
    found = components(lambda: _joined(docs, region, measure).union(same))
    return named.join(found, F.col("rep") == F.col("node"), "left").groupBy(F.col("doc_id").alias("node")).agg(F.min(F.coalesce("component", "rep")).alias("component"))


def _joined(docs: DataFrame, region: DataFrame, measure: Measure) -> DataFrame:
    """Links that connect the sets of each region exactly.

    A large region is joined block by block, each with the region's first set; its pairs of blocks meet where that leaves
    several groups.
    """
    shape = "a long, b long"
    texts = docs.join(region, F.col("doc_id") == F.col("node")).select("doc_id", "text", F.col("component").alias("region"))
    size = texts.groupBy("region").agg(F.count("*").alias("n"), F.sum(F.coalesce(F.octet_length("text"), F.lit(0))).alias("bytes"))
    blocks = F.greatest(F.ceil(F.col("bytes") / BLOCK_BYTES), F.ceil(F.col("n") / BLOCK_ROWS)).cast("int")
    size = written(lambda: size.where("n > 1").select("region", blocks.alias("blocks")), "region-sizes")
    own = F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int")
    rows = texts.join(size, "region").withColumn("own", own)
    # the region's first set goes to every block
    at = F.when(F.col("doc_id") == F.col("region"), F.expr("sequence(0, blocks - 1)")).otherwise(F.array("own"))
    first = rows.select("region", F.explode(at).alias("i"), "doc_id", "text").select("region", "i", F.col("i").alias("j"), "doc_id", F.col("doc_id").alias("joined"), "text")
    key = ["region", "i", "j"]
    join = lambda r: r.repartition(*key).sortWithinPartitions(*key, "doc_id").mapInArrow(partial(_join_regions, measure=measure), shape)
    links = written(lambda: join(first), "block-links", large=True)
    large = size.where("blocks > 1")
    if not large.take(1):
        return links
    now = written(lambda: components(lambda: links), "joined-blocks")
    left = rows.where("blocks > 1").join(now, F.col("doc_id") == F.col("node"), "left").select("region", "blocks", "own", "doc_id", "text", F.coalesce("component", "doc_id").alias("joined"))
    open_ = left.groupBy("region").agg(F.min("joined").alias("p"), F.max("joined").alias("q")).where("p < q").select("region")
    both = left.join(open_, "region").withColumn("other", F.explode(F.expr("sequence(0, blocks - 1)"))).where("own <> other")
    both = both.select("region", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "doc_id", "joined", "text")
    return links.union(join(both))


def jaccard_components(docs: DataFrame, measure: Measure) -> DataFrame:
    """doc_id, n_shingles, component_id of every row (component_id: the smallest doc_id reachable by links)."""
    held = written(lambda: summaries(docs, measure), "summaries")
    found = near_copies(docs, measure, held)
    return held.join(found, F.col("doc_id") == F.col("node"), "left").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def keep_first(docs: DataFrame, measure: Measure) -> DataFrame:
    """The documents without all but the first of each component."""
    later = near_copies(docs, measure).where("node <> component").select(F.col("node").alias("doc_id"))
    return docs.join(later, "doc_id", "left_anti").select([quoted(c) for c in docs.columns])
