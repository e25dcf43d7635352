"""The benchmark of planted pairs: sparse rows of given sets with copies of given similarities, and ids from a dictionary."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.functions.hashing import key_of
from ebbset.params import flip_rates

#: Planted rows have their base's id plus this; every so many rows one is a base.
SHIFT, EVERY = 10_000_000, 10


def rows(view: DataFrame, columns: int) -> DataFrame:
    """set_id, item_id: given sets as sparse rows of that many columns, items being dealt to columns by a hash."""
    column = F.pmod(key_of(F.concat(F.col("item_id").cast("string"), F.lit(":column"))), F.lit(columns)) + 1
    return view.select("set_id", column.alias("item_id")).distinct()


def rows_sql(view: str, columns: int) -> str:
    return f"SELECT DISTINCT set_id, 1 + ('0x' || substr(md5(item_id || ':column'), 1, 15))::BIGINT % {columns} AS item_id FROM ({view})"


def _rates(bands: tuple[float, ...]) -> list[tuple[int, int]]:
    """Chances in 10,000 to drop an item, and to add another for one that the base has, by band."""
    return [(int(10_000 * drop), int(10_000 * drop)) for drop, _ in (flip_rates(b, 0.05) for b in bands)]


def planted(view: DataFrame, columns: int, bands: tuple[float, ...]) -> DataFrame:
    """The rows and, of each EVERY-th, a copy about as alike as its band says: items are dropped with some chance, and
    with the same chance a random one comes in, which keeps the density."""
    view = rows(view, columns)
    base = view.where(F.col("set_id") % EVERY == 0)
    rate = F.element_at(F.array(*[F.lit(d) for d, _ in _rates(bands)]), (F.floor(F.col("set_id") / EVERY) % len(bands) + 1).cast("int"))
    dice = lambda salt: key_of(F.concat_ws(":", F.col("set_id").cast("string"), F.col("item_id").cast("string"), F.lit(salt)), 7) % 10_000
    new = F.expr(f"1 + pmod(cast(conv(substr(md5(concat(set_id, ':', item_id, ':new')), 1, 15), 16, 10) as bigint), {columns})")
    kept = base.where(dice("drop") >= rate).select((F.col("set_id") + SHIFT).alias("set_id"), "item_id")
    more = base.where(dice("add") < rate).select((F.col("set_id") + SHIFT).alias("set_id"), new.alias("item_id"))
    return view.union(kept.union(more).distinct())


def planted_sql(view: str, columns: int, bands: tuple[float, ...]) -> str:
    rate = f"([{', '.join(str(d) for d, _ in _rates(bands))}])[(set_id // {EVERY}) % {len(bands)} + 1]"
    dice = lambda salt: f"('0x' || substr(md5(set_id || ':' || item_id || ':{salt}'), 1, 7))::BIGINT % 10000"
    new = f"1 + ('0x' || substr(md5(set_id || ':' || item_id || ':new'), 1, 15))::BIGINT % {columns}"
    base = f"(SELECT * FROM ({rows_sql(view, columns)}) WHERE set_id % {EVERY} = 0)"
    return f"""SELECT set_id, item_id FROM ({rows_sql(view, columns)}) UNION ALL
        SELECT set_id + {SHIFT}, item_id FROM (SELECT set_id, item_id FROM {base} WHERE {dice('drop')} >= {rate} UNION SELECT set_id, {new} FROM {base} WHERE {dice('add')} < {rate})"""


def dictionary(keys: DataFrame) -> DataFrame:
    """item_key, item_id: distinct keys numbered from 1 in their order, without bringing them together.

    Keys are range-partitioned; the partitions' counts (a row each) give where each one's numbers begin.
    """
    own = keys.select("item_key").where("item_key is not null").distinct().repartitionByRange("item_key").withColumn("part", F.spark_partition_id())
    local = own.withColumn("n", F.row_number().over(Window.partitionBy("part").orderBy("item_key")))
    count = own.groupBy("part").agg(F.count("*").alias("many"))
    before = count.withColumnRenamed("part", "p").withColumnRenamed("many", "m")
    begin = count.join(F.broadcast(before), F.col("p") < F.col("part"), "left").groupBy("part").agg(F.coalesce(F.sum("m"), F.lit(0)).alias("begin"))
    return local.join(F.broadcast(begin), "part").select("item_key", (F.col("n") + F.col("begin")).cast("long").alias("item_id"))
