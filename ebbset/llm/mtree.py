"""Exact top-k inner product search in M-trees.

One more component makes all candidates equally long, so that a query's largest inner products are its least angles, a
metric. Candidates are dealt to regions of their nearest pivot; each region (in parts, where it is large) becomes an
M-tree of paged nodes: routing objects with covering radius and distance to their parent, entries with distance to
theirs. Queries search best first: each keeps a queue of nodes by their lower bound, nodes and entries that the stored
distance to the parent alone rules out are not measured, and a query ends when its next node can't hold one of its k
best any more. A query searches the region of its own nearest pivot first; its k-th best there rules out the regions
whose radii lie farther, and goes along as a limit to the others.

Defined results: vectors that are null or hold null or non-finite components take no part; fewer than k candidates give
as many ranks; ties go to the smaller id; rows with the query's id are not its candidates; repeated rows count once;
queries with equal ids and different vectors each give their own candidates and the best count; vectors of different
lengths are compared as if padded with zeros; extra columns are ignored.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.llm._spark import written
from ebbset.llm._text import runs

PAGE, FAN = 64, 16
#: Rows a tree and queries a block, about; regions at most (their pivots and radii go to all tasks).
PART_ROWS, BLOCK_QUERIES, MOST_REGIONS = 8192, 4096, 1024
#: Angles are good to this; bounds are widened by it.
SLACK = 1e-6
NONE = np.iinfo(np.int64).min


@dataclass
class Node:
    """A routing object, its covering radius and its distance to the parent's; below it nodes or a page of entries."""

    center: int
    radius: float
    to_parent: float
    children: list[Node] = field(default_factory=list)
    rows: np.ndarray | None = None
    #: Distances of a page's entries to the routing object.
    far: np.ndarray | None = None


def dots(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All inner products of integer rows, exactly."""
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * a.shape[1]
    if most < 2**52:
        return np.rint(a.astype(np.float64) @ b.astype(np.float64).T).astype(np.int64)
    return a @ b.T


def on_sphere(vectors: np.ndarray, most: float) -> np.ndarray:
    """Candidates as points of the unit sphere with one more component; most: the largest squared length of all."""
    own = vectors.astype(np.float64)
    rest = np.sqrt(np.maximum(most - (own**2).sum(axis=1), 0))[:, None]
    return np.concatenate([own, rest if most else rest + 1], axis=1) / np.sqrt(most or 1.0)


def directions(queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Queries as points of the same sphere, and their lengths; without length a query is a quarter turn from all."""
    own = queries.astype(np.float64)
    length = np.sqrt((own**2).sum(axis=1))
    return np.concatenate([own / np.where(length, length, 1.0)[:, None], np.zeros((len(own), 1))], axis=1), length


def angles(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip(a @ b.T, -1, 1))


class Tree:
    """An M-tree over integer vectors, loaded in bulk. most: the largest squared length among all candidates."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, most: float | None = None):
        self.ids, self.vectors = ids, vectors
        self.repeats = len(np.unique(ids)) < len(ids)
        self.most = float((vectors.astype(np.float64) ** 2).sum(axis=1).max(initial=0.0)) if most is None else most
        self.points = on_sphere(vectors, self.most)
        #: Distances and inner products computed by searches.
        self.measured = 0
        self.root = self._load(np.arange(len(ids)), None)

    def _far(self, center: int, rows: np.ndarray) -> np.ndarray:
        return angles(self.points[rows], self.points[center][None])[:, 0]

    def _load(self, rows: np.ndarray, parent: int | None) -> Node:
        mean = self.points[rows].mean(axis=0)
        center = int(rows[np.argmax(self.points[rows] @ mean)])
        far = self._far(center, rows)
        node = Node(center, float(far.max(initial=0.0)), float(self._far(center, np.array([parent]))[0]) if parent is not None else 0.0)
        if len(rows) <= PAGE:
            node.rows, node.far = rows, far
            return node
        groups = [rows]
        while len(groups) < FAN:
            big = max(range(len(groups)), key=lambda i: len(groups[i]))
            if len(groups[big]) <= PAGE:
                break
            groups += self._split(groups.pop(big))
        node.children = [self._load(g, center) for g in groups]
        return node

    def _split(self, rows: np.ndarray) -> list[np.ndarray]:
        """Two groups by the nearer of two far-apart objects; equal objects are halved."""
        a = int(rows[np.argmax(self._far(int(rows[0]), rows))])
        to_a = self._far(a, rows)
        b = int(rows[np.argmax(to_a)])
        left = to_a <= self._far(b, rows)
        if left.all() or not left.any():
            left = np.arange(len(rows)) < len(rows) // 2
        return [rows[left], rows[~left]]

    def search(self, ids: np.ndarray, queries: np.ndarray, k: int, least: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query number, id, score) of each query's k best under other ids; least: scores below which none is wanted."""
        n = len(ids)
        best, owner, found = np.full((n, k), NONE), np.full((n, k), np.iinfo(np.int64).max), np.zeros((n, k), bool)
        least = np.full(n, NONE) if least is None else least
        points, length = directions(queries)
        scale = length * np.sqrt(self.most)

        def limit(who: np.ndarray) -> np.ndarray:
            """The widest angle that one of the k best can still have."""
            kth = np.maximum(np.where(found[who].all(axis=1), best[who].min(axis=1), NONE), least[who])
            known = kth > NONE
            cosine = np.where(known, kth, 0) / np.where(scale[who], scale[who], 1.0)
            return np.where(known, np.arccos(np.clip(cosine, -1, 1)), np.pi) + SLACK

        def read(leaf: Node, who: np.ndarray, own: np.ndarray) -> None:
            near = (np.abs(own[:, None] - leaf.far[None]) <= limit(who)[:, None]).any(axis=0)
            rows = leaf.rows[near]
            score = dots(queries[who], self.vectors[rows])
            self.measured += score.size
            other = np.broadcast_to(self.ids[rows], score.shape)
            ok = other != ids[who][:, None]
            s = np.concatenate([best[who], np.where(ok, score, NONE)], axis=1)
            o = np.concatenate([owner[who], np.where(ok, other, np.iinfo(np.int64).max)], axis=1)
            f = np.concatenate([found[who], ok], axis=1)
            order = np.lexsort((o, np.where(f, -s, np.iinfo(np.int64).max)), axis=1)
            if self.repeats:
                # rows of one id and score count once
                s, o, f = (np.take_along_axis(x, order, axis=1) for x in (s, o, f))
                f[:, 1:] &= (s[:, 1:] != s[:, :-1]) | (o[:, 1:] != o[:, :-1])
                order = np.argsort(~f, axis=1, kind="stable")
            order = order[:, :k]
            best[who], owner[who], found[who] = (np.take_along_axis(x, order, axis=1) for x in (s, o, f))

        # one queue a query: lower bound, turn, distance to the routing object, node
        self.measured += n
        start = angles(points, self.points[[self.root.center]])[:, 0]
        queues = [[(0.0, 0, float(d), self.root)] for d in start]
        turn, active = 0, list(range(n))
        while active:
            bound = limit(np.array(active))
            now: dict[int, tuple[Node, list[int], list[float]]] = {}
            left = []
            for q, most in zip(active, bound.tolist(), strict=True):
                if queues[q] and queues[q][0][0] <= most:
                    _, _, d, node = heapq.heappop(queues[q])
                    at = now.setdefault(id(node), (node, [], []))
                    at[1].append(q)
                    at[2].append(d)
                    left.append(q)
                else:
                    queues[q] = []
            active = left
            for node, who, own in now.values():
                who, own = np.array(who), np.array(own)
                if node.rows is not None:
                    read(node, who, own)
                    continue
                most = limit(who)
                for c in node.children:
                    near = np.flatnonzero(np.abs(own - c.to_parent) - c.radius <= most)
                    if not len(near):
                        continue
                    self.measured += len(near)
                    d = angles(points[who[near]], self.points[[c.center]])[:, 0]
                    low = np.maximum(d - c.radius, 0.0)
                    for i in np.flatnonzero(low <= most[near]).tolist():
                        turn += 1
                        heapq.heappush(queues[who[near[i]]], (float(low[i]), turn, float(d[i]), c))
        q, j = np.nonzero(found)
        return q, owner[q, j], best[q, j]


def _matrix(lists: pa.Array, width: int) -> np.ndarray:
    """Integer vectors, padded with zeros to one length."""
    size = np.asarray(lists.value_lengths()).astype(np.int64)
    flat = np.asarray(lists.flatten()).astype(np.int64)
    out = np.zeros((len(size), width), np.int64)
    row = np.repeat(np.arange(len(size)), size)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def _homes(batches, pivots: np.ndarray, most: float):
    """Each row with the region of its nearest pivot, its distance from it, and the region nearest to it as a query."""
    for batch in batches:
        vectors = _matrix(batch.column("vector"), pivots.shape[1] - 1)
        far = angles(on_sphere(vectors, most), pivots)
        region = far.argmin(axis=1)
        asks = angles(directions(vectors)[0], pivots).argmin(axis=1)
        cols = [pa.array(region.astype(np.int32)), pa.array(far[np.arange(len(far)), region]), pa.array(asks.astype(np.int32))]
        yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("vector"), *cols], ["vec_id", "vector", "region", "far", "asks"])


def _others(batches, pivots: np.ndarray, radii: np.ndarray, most: float):
    """Each query once for every other region that may hold one of its k best."""
    for batch in batches:
        vectors = _matrix(batch.column("vector"), pivots.shape[1] - 1)
        points, length = directions(vectors)
        known = np.asarray(batch.column("least").is_valid())
        kth = np.asarray(batch.column("least").fill_null(0)).astype(np.float64)
        scale = length * np.sqrt(most)
        limit = np.where(known, np.arccos(np.clip(kth / np.where(scale, scale, 1.0), -1, 1)), np.pi) + SLACK
        row, region = np.nonzero(angles(points, pivots) - radii[None] <= limit[:, None])
        other = region != np.asarray(batch.column("asks"))[row]
        row, region = row[other], region[other]
        took = batch.select(["vec_id", "vector", "least"]).take(pa.array(row))
        yield pa.RecordBatch.from_arrays([*took.columns, pa.array(region.astype(np.int32))], ["vec_id", "vector", "least", "region"])


def _search(batches, k: int, width: int, most: float):
    for table in runs(batches, ["region", "part", "block"]):
        table = table.combine_chunks()
        keys = np.stack([np.asarray(table.column(c)) for c in ("region", "part", "block")], axis=1)
        ids, ask, tag = (np.asarray(table.column(c)) for c in ("vec_id", "ask", "tag"))
        least = np.asarray(table.column("least").fill_null(NONE))
        vectors = _matrix(table.column("vector").chunk(0), width)
        cut = np.concatenate([[0], np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1, [len(keys)]])
        for a, b in zip(cut[:-1], cut[1:], strict=True):
            own = np.arange(a, b)
            q, c = own[ask[a:b]], own[~ask[a:b]]
            if len(q) and len(c):
                at, found, score = Tree(ids[c], vectors[c], most).search(ids[q], vectors[q], k, least[q])
                yield pa.RecordBatch.from_arrays([pa.array(ids[q][at]), pa.array(tag[q][at]), pa.array(found), pa.array(score)], ["query_id", "tag", "vec_id", "score"])


def _searched(queries: DataFrame, rows: DataFrame, k: int, width: int, most: float) -> DataFrame:
    """The k best of each query in the region it asks for. queries: vec_id, vector, least, region.

    A region's candidates are dealt to parts, its queries to blocks; every part meets every block of its own region.
    """
    spark = rows.sparkSession
    parts = {r.region: -(-r.n // PART_ROWS) for r in rows.groupBy("region").agg(F.count("*").alias("n")).collect()}  # MOST_REGIONS rows at most
    blocks = {r.region: -(-r.n // BLOCK_QUERIES) for r in queries.groupBy("region").agg(F.count("*").alias("n")).collect()}
    sizes = spark.createDataFrame([(r, parts[r], blocks[r]) for r in parts if r in blocks], "region int, parts int, blocks int")
    tag = F.xxhash64("vector").alias("tag")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    dealt = lambda n: F.pmod(F.xxhash64("vec_id", "vector"), F.col(n)).cast("int")
    left = rows.join(F.broadcast(sizes), "region").select("region", dealt("parts").alias("part"), every("blocks").alias("block"), F.lit(False).alias("ask"), "vec_id", tag, F.lit(None).cast("long").alias("least"), "vector")
    right = queries.join(F.broadcast(sizes), "region").select("region", every("parts").alias("part"), dealt("blocks").alias("block"), F.lit(True).alias("ask"), "vec_id", tag, "least", "vector")
    key = ["region", "part", "block"]
    met = left.union(right).repartition(*key).sortWithinPartitions(*key, "vec_id")
    return met.mapInArrow(partial(_search, k=k, width=width, most=most), "query_id long, tag long, vec_id long, score long").distinct()


def top_k(vectors: DataFrame, every: int = 50, k: int = 5, scale: int = 256) -> DataFrame:
    """query_id, rank, vec_id, score: the k best of each row whose vec_id is divisible by `every`."""
    plain = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("e")).where("vec_id is not null and e is not null")
    limit = F.lit(float("inf"))
    whole = F.forall("e", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < limit))
    plain = plain.where(whole).select("vec_id", F.transform("e", lambda x: F.floor(x * scale)).alias("vector")).distinct()
    square = F.aggregate("vector", F.lit(0.0), lambda s, x: s + x.cast("double") * x)
    size = plain.agg(F.count("*").alias("n"), F.max(square).alias("most"), F.max(F.size("vector")).alias("width")).first()
    most, width = float(size.most or 0.0), size.width or 1
    regions = max(1, min(MOST_REGIONS, -(-size.n // PART_ROWS)))
    chosen = plain.orderBy(F.xxhash64("vec_id", "vector")).limit(regions).toArrow()
    pivots = on_sphere(_matrix(chosen.column("vector").combine_chunks(), width), most) if len(chosen) else np.zeros((1, width + 1))
    rows = written(lambda: plain.mapInArrow(partial(_homes, pivots=pivots, most=most), "vec_id long, vector array<long>, region int, far double, asks int"), "regions")
    asked = rows.where(F.col("vec_id") % every == 0).select("vec_id", "vector", "asks")
    first = written(lambda: _searched(asked.select("vec_id", "vector", F.lit(None).cast("long").alias("least"), F.col("asks").alias("region")), rows, k, width, most), "first-region")
    # a query's k-th best in its own region limits the search of the others
    best = F.row_number().over(Window.partitionBy("query_id", "tag").orderBy(F.desc("score"), "vec_id"))
    kth = first.withColumn("r", best).where(F.col("r") == k).select(F.col("query_id").alias("vec_id"), "tag", F.col("score").alias("least"))
    limited = asked.withColumn("tag", F.xxhash64("vector")).join(kth, ["vec_id", "tag"], "left").select("vec_id", "vector", "asks", "least")
    radii = np.full(len(pivots), -10.0)
    for r in rows.groupBy("region").agg(F.max("far").alias("far")).collect():
        radii[r.region] = r.far
    more = written(lambda: limited.mapInArrow(partial(_others, pivots=pivots, radii=radii, most=most), "vec_id long, vector array<long>, least long, region int"), "other-regions")
    found = first.union(_searched(more, rows, k, width, most)).select("query_id", "vec_id", "score").distinct()
    order = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", order.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
