"""Uses of similar pairs: recommendation, showcase users, genre profiles, maps, trees, ordered heatmaps, groups."""

from __future__ import annotations

import tempfile

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Most sets whose whole distance matrix is handled at once.
SELECTION = 5000


def recommend(scored: DataFrame, net: DataFrame, users: int = 5, items: int = 5) -> DataFrame:
    """set_id, rank, item_id, score: items of the most similar sets that a set hasn't got. scored: left_id, right_id, inter, uni."""
    both = scored.select(F.col("left_id").alias("set_id"), F.col("right_id").alias("other"), "inter", "uni").union(scored.select("right_id", "left_id", "inter", "uni"))
    sim = F.round(F.col("inter") / F.col("uni"), 9)
    near = both.withColumn("sim", sim).withColumn("r", F.row_number().over(Window.partitionBy("set_id").orderBy(F.desc("sim"), "other"))).where(F.col("r") <= users)
    theirs = near.join(net.select(F.col("set_id").alias("other"), "item_id"), "other").groupBy("set_id", "item_id").agg(F.round(F.sum("sim"), 6).alias("score"))
    new = theirs.join(net, ["set_id", "item_id"], "left_anti")
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy(F.desc("score"), "item_id"))
    return new.withColumn("rank", rank).where(F.col("rank") <= items).select("set_id", "rank", "item_id", "score")


def genre_profiles(log: DataFrame) -> DataFrame:
    """set_id, genre, share: normalised sums of the items' normalised genre vectors."""
    item = log.groupBy("item_id", "genre").agg(F.count("*").alias("n"))
    item = item.select("item_id", "genre", (F.col("n") / F.sum("n").over(Window.partitionBy("item_id"))).alias("v"))
    own = log.select("set_id", "item_id").distinct().join(item, "item_id").groupBy("set_id", "genre").agg(F.sum("v").alias("v"))
    return own.select("set_id", "genre", F.round(F.col("v") / F.sum("v").over(Window.partitionBy("set_id")), 6).alias("share"))


def top_genres(profiles: DataFrame, k: int = 3) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy(F.desc("share"), "genre"))
    return profiles.withColumn("rank", rank).where(F.col("rank") <= k).select("set_id", "rank", "genre", "share")


def showcase(scored: DataFrame, cards: DataFrame, threshold: float, random: int = 10, salt: str = "show") -> DataFrame:
    """set_id, kind: the sets of the most similar pairs, and some others by a hash of their id."""
    top = scored.where(F.col("inter") >= threshold * F.col("uni")).select(F.explode(F.array("left_id", "right_id")).alias("set_id")).distinct()
    rest = cards.select("set_id").join(top, "set_id", "left_anti").orderBy(F.md5(F.concat(F.col("set_id").cast("string"), F.lit(salt))), "set_id").limit(random)
    return top.withColumn("kind", F.lit("top")).union(rest.withColumn("kind", F.lit("random")))


def edges(scored: DataFrame, chosen: DataFrame, least: float = 0.1) -> DataFrame:
    a, b = chosen.select(F.col("set_id").alias("left_id")), chosen.select(F.col("set_id").alias("right_id"))
    return scored.where(F.col("inter") >= least * F.col("uni")).join(a, "left_id", "left_semi").join(b, "right_id", "left_semi").select("left_id", "right_id", "inter", "uni")


def matrix_of(pairs: DataFrame, ids: list[int], value: str = "distance", rest: float = 1.0) -> np.ndarray:
    """The symmetric matrix of a bounded selection; pairs without a row get `rest`, the diagonal 0."""
    if len(ids) > SELECTION:
        raise ValueError(f"a matrix of {len(ids)} sets is too large")
    at = {x: i for i, x in enumerate(ids)}
    out = np.full((len(ids), len(ids)), rest)
    np.fill_diagonal(out, 0.0)
    for a, b, v in pairs.select("left_id", "right_id", value).where(F.col("left_id").isin(ids) & F.col("right_id").isin(ids)).collect():
        out[at[a], at[b]] = out[at[b], at[a]] = v
    return out


def stress(d: np.ndarray, x: np.ndarray) -> float:
    own = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    return float(((own - d) ** 2).sum() / 2)


def mds_2d(d: np.ndarray, rounds: int = 200) -> np.ndarray:
    """Points in the plane whose distances follow the matrix: classical scaling, then stress majorisation."""
    n = len(d)
    centre = np.eye(n) - 1 / max(n, 1)
    values, vectors = np.linalg.eigh(-0.5 * centre @ (d**2) @ centre)
    x = vectors[:, ::-1][:, :2] * np.sqrt(np.maximum(values[::-1][:2], 1e-12))
    x = x if x.shape[1] == 2 else np.pad(x, ((0, 0), (0, 2 - x.shape[1])))
    for _ in range(rounds):
        own = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
        ratio = np.divide(d, own, out=np.zeros_like(d), where=own > 1e-12)
        b = -ratio
        np.fill_diagonal(b, ratio.sum(axis=1))
        x = b @ x / n
    return x


def hierarchical(d: np.ndarray, linkage: str = "single") -> list[tuple[int, int, float, int]]:
    """Merges (a, b, height, size); clusters are numbered from n on. Linkage: single, complete or average."""
    n = len(d)
    dist, size, alive = {(i, j): float(d[i, j]) for i in range(n) for j in range(i)}, dict.fromkeys(range(n), 1), set(range(n))
    get = lambda a, b: dist[max(a, b), min(a, b)]
    out = []
    for new in range(n, 2 * n - 1):
        a, b = min(((j, i) for i in alive for j in alive if j < i), key=lambda p: (get(*p), p))
        out.append((a, b, get(a, b), size[a] + size[b]))
        alive -= {a, b}
        for c in alive:
            u, v = get(a, c), get(b, c)
            dist[new, c] = {"single": min(u, v), "complete": max(u, v), "average": (u * size[a] + v * size[b]) / (size[a] + size[b])}[linkage]
        size[new] = size[a] + size[b]
        alive.add(new)
    return out


def cut(merges: list, n: int, height: float) -> list[int]:
    """Cluster numbers of the leaves below a height: the smallest leaf of each."""
    own = {i: [i] for i in range(n)}
    for k, (a, b, h, _) in enumerate(merges):
        if h <= height:
            own[n + k] = own.pop(a) + own.pop(b)
        else:
            own[n + k] = []
    label = [0] * n
    for leaves in own.values():
        for i in leaves:
            label[i] = min(leaves)
    return label


def leaf_order(merges: list, d: np.ndarray) -> list[int]:
    """The order of a tree's leaves, among those its branches can be turned to, with the least sum of neighbours'
    distances: a table of best sums by outer leaves, built from the merges up."""
    n = len(d)
    best = {i: {(i, i): (0.0, [i])} for i in range(n)}
    for k, (a, b, _, _) in enumerate(merges):
        table: dict[tuple[int, int], tuple[float, list[int]]] = {}
        for (i, u), (x, left) in best[a].items():
            for (v, j), (y, right) in best[b].items():
                total = x + y + d[u, v]
                if (i, j) not in table or total < table[i, j][0]:
                    table[i, j] = (total, left + right)
                    table[j, i] = (total, (left + right)[::-1])
        best[n + k] = table
        del best[a], best[b]
    return min(best[n + len(merges) - 1].values(), key=lambda x: x[0])[1] if merges else list(range(n))


def neighbour_joining(d: np.ndarray) -> list[tuple[int, int, float, float]]:
    """Joins (a, b, length to a, length to b) of an unrooted tree; nodes are numbered from n on, the last join is an edge."""
    n, alive, out = len(d), list(range(len(d))), []
    dist = {(i, j): float(d[i, j]) for i in alive for j in alive}
    new = n
    while len(alive) > 2:
        r = {i: sum(dist[i, j] for j in alive) for i in alive}
        m = len(alive)
        a, b = min(((i, j) for i in alive for j in alive if i < j), key=lambda p: ((m - 2) * dist[p] - r[p[0]] - r[p[1]], p))
        la = dist[a, b] / 2 + (r[a] - r[b]) / (2 * (m - 2))
        out.append((a, b, la, dist[a, b] - la))
        alive = [c for c in alive if c not in (a, b)]
        for c in alive:
            dist[new, c] = dist[c, new] = (dist[a, c] + dist[b, c] - dist[a, b]) / 2
        dist[new, new] = 0.0
        alive.append(new)
        new += 1
    if len(alive) == 2:
        out.append((alive[0], alive[1], dist[alive[0], alive[1]], 0.0))
    return out


def heatmap_rows(spark, matrix: np.ndarray, order: list[int]) -> DataFrame:
    rows = [(i, j, float(matrix[a, b])) for i, a in enumerate(order) for j, b in enumerate(order)]
    return spark.createDataFrame(rows, "row_pos int, col_pos int, value double")


def near_duplicate_groups(pairs: DataFrame, most_rounds: int = 50) -> DataFrame:
    """set_id, group_id: the smallest set reachable by pairs. Labels spread by minima and jump to their labels' labels;
    each round is checkpointed to the session's checkpoint folder."""
    spark = pairs.sparkSession
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="ebbset-"))
    both = pairs.select(F.col("left_id").alias("set_id"), F.col("right_id").alias("other")).union(pairs.select("right_id", "left_id")).distinct().checkpoint()
    now = both.groupBy("set_id").agg(F.least("set_id", F.min("other")).alias("group_id")).checkpoint()
    for _ in range(most_rounds):
        near = both.join(now.withColumnsRenamed({"set_id": "other", "group_id": "g"}), "other").groupBy("set_id").agg(F.min("g").alias("g"))
        step = now.join(near, "set_id").select("set_id", F.least("group_id", "g").alias("h"))
        jump = now.select(F.col("set_id").alias("h"), F.col("group_id").alias("j"))
        after = step.join(jump, "h", "left").select("set_id", F.least("h", F.coalesce("j", "h")).alias("group_id")).checkpoint()
        moved = after.join(now.withColumnRenamed("group_id", "was"), "set_id").where("group_id <> was").limit(1).count()
        now = after
        if not moved:
            return now
    raise RuntimeError("groups did not settle")
