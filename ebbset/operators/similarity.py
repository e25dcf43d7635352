"""Exact similarities: rational and root similarities of pairs, all pairs by inverted index, histograms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ebbset.operators import blocks
from ebbset.params import JACCARD, Similarity


def rational_similarity(inter: Column, union: Column, symdiff: Column, universe: Column, s: Similarity) -> Column:
    """The similarity from set sizes; 1 where it is 0 / 0."""
    base = s.x * inter + s.y * (universe - union)
    den = (base + s.zp * symdiff).cast("double")
    return F.when(den == 0, F.lit(1.0)).otherwise((base + s.z * symdiff).cast("double") / den)


def root_similarity(sim: Column, a: float) -> Column:
    return 1 - F.pow(1 - sim, F.lit(a))


def denominator_forms(inter: Column, union: Column, symdiff: Column, universe: Column, s: Similarity) -> dict[str, Column]:
    """The denominator as defined, by union and difference, by complements, and by intersection and union."""
    not_union = universe - inter  # size of the union of the complements
    return {
        "den": s.x * inter + s.y * (universe - union) + s.zp * symdiff,
        "den_union": s.y * universe + (s.x - s.y) * union + (s.zp - s.x) * symdiff,
        "den_complement": (s.y - s.x) * not_union + s.x * universe + (s.zp - s.y) * symdiff,
        "den_inter": s.y * universe + (s.x - s.zp) * inter + (s.zp - s.y) * union,
    }


def exact_pairs(view: DataFrame) -> DataFrame:
    """left_id, right_id, inter, uni of all pairs that share an item: the ground truth."""
    return blocks.exact_pairs(view)


def of_pairs(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """left_id, right_id, inter, uni of given pairs. sets: set_id, items (distinct)."""
    left, right = sets.select(F.col("set_id").alias("left_id"), F.col("items").alias("x")), sets.select(F.col("set_id").alias("right_id"), F.col("items").alias("y"))
    inter = F.size(F.array_intersect("x", "y")).cast("long").alias("inter")
    met = pairs.select("left_id", "right_id").join(left, "left_id").join(right, "right_id").select("left_id", "right_id", inter, (F.size("x") + F.size("y")).alias("both"))
    return met.select("left_id", "right_id", "inter", (F.col("both") - F.col("inter")).alias("uni"))


def items_of(view: DataFrame) -> DataFrame:
    """set_id, items, in files."""
    return blocks.stored(view.groupBy("set_id").agg(F.collect_list("item_id").alias("items")), "items")


def similar_pairs(view: DataFrame, low: float) -> DataFrame:
    """left_id, right_id, inter, uni of all pairs of similarity `low` (above 0) at least, and of no other.

    Two such sets share an item among the rarest of each, so many that fewer than the needed ones are left; only pairs that
    do, at places and of sizes that leave enough items to share, are counted out.
    """
    rare = view.groupBy("item_id").agg(F.count("*").alias("n"))
    ranked = view.join(rare, "item_id").groupBy("set_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("n", "item_id"))), lambda x: x["item_id"]).alias("items"))
    sets = blocks.stored(ranked, "ranked")
    size = F.size("items")
    head = (size - F.ceil(size * low - 1e-6) + 1).cast("int")
    tokens = sets.select("set_id", size.alias("card"), F.posexplode(F.slice("items", F.lit(1), head)).alias("at", "item_id")).withColumn("left", F.col("card") - F.col("at"))
    tokens = tokens.join(rare.where("n > 1").select("item_id"), "item_id", "left_semi").select("item_id", "set_id", "card", "left")
    a, b = tokens.withColumnsRenamed({"set_id": "left_id", "card": "a", "left": "la"}), tokens.withColumnsRenamed({"set_id": "right_id", "card": "b", "left": "lb"})
    fits = (F.col("a") >= low * F.col("b") - 1e-6) & (F.col("b") >= low * F.col("a") - 1e-6)
    room = F.least("la", "lb") >= low / (1 + low) * (F.col("a") + F.col("b")) - 1e-6
    near = a.join(b, "item_id").where((F.col("left_id") < F.col("right_id")) & fits & room).select("left_id", "right_id").distinct()
    return of_pairs(near, sets).where(F.col("inter") >= (low - 1e-12) * F.col("uni"))


def class_pairs(view: DataFrame) -> DataFrame:
    """left_id, right_id, inter, uni, same: pairs between classes of equal sets, each named by its smallest, that share an
    item; with `same` a class and another set in it. Together they say what all pairs would, without the square of a class."""
    held = view.groupBy("set_id").agg(F.sort_array(F.collect_list(F.col("item_id").cast("long"))).alias("items"), F.count("*").alias("all"))
    named = blocks.stored(held.select(F.col("set_id").cast("long").alias("set_id"), "items", "all", F.min("set_id").over(Window.partitionBy("items")).alias("rep"), F.size("items").cast("long").alias("card")), "classes")
    own = named.where("set_id = rep").select("set_id", "items", F.col("all").alias("card"))
    many, items = own.agg(F.count("*"), F.coalesce(F.sum(F.size("items")), F.lit(0))).first()
    members = named.where("set_id <> rep").select(F.col("rep").alias("left_id"), F.col("set_id").alias("right_id"), F.col("card").alias("inter"), F.col("card").alias("uni"), F.lit(True).alias("same"))
    return blocks.pairs_of(own, many, items).withColumn("same", F.lit(False)).union(members)


def scored(pairs: DataFrame, universe: int, s: Similarity = JACCARD, name: str = "sim") -> DataFrame:
    inter, uni = F.col("inter"), F.col("uni")
    return pairs.withColumn(name, rational_similarity(inter, uni, uni - inter, F.lit(universe), s))


def similarity_histogram(view: DataFrame, bins: int = 20) -> DataFrame:
    """Number of pairs by Jaccard similarity in bins of 1 / bins; disjoint pairs enter bin 0 by subtraction."""
    pairs = exact_pairs(view).groupBy(F.floor(F.col("inter") * bins / F.col("uni")).alias("bin")).agg(F.count("*").alias("n"))
    sets = view.agg(F.countDistinct("set_id").alias("m"))
    rest = sets.join(F.broadcast(pairs.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("met")))).select(F.lit(0).cast("long").alias("bin"), (F.expr("m * (m - 1) div 2") - F.col("met")).alias("n"))
    return pairs.union(rest).groupBy("bin").agg(F.sum("n").alias("pairs")).where("pairs > 0")


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u * v), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def lp_norm(vector: Column, p: float) -> Column:
    """The l_p norm of an array; p = 0 counts what isn't zero."""
    if p == 0:
        return F.size(F.filter(vector, lambda v: v != 0)).cast("double")
    return F.pow(F.aggregate(vector, F.lit(0.0), lambda s, v: s + F.pow(F.abs(v), F.lit(p))), F.lit(1 / p))
