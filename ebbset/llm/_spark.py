"""Session helpers: the shared folder, written intermediate tables, connected components."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def shared_folder(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; one of our own only where that is unset (local tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = f"file://{tempfile.mkdtemp(prefix='ebbset-')}"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def written(build: Callable[[], DataFrame], name: str, large: bool = False, batch: int | None = None) -> DataFrame:
    """The rows of build() as a table written to the shared folder: cuts the lineage and outlives executors.

    What build() makes is referred to by nothing afterwards; large: it shuffles texts or more, whose files go at once.
    batch: rows an Arrow batch, where rows are long; the session's setting comes back afterwards.
    """

    def run() -> tuple[SparkSession, StructType, str]:
        df = build()
        session = df.sparkSession
        path, before = new_path(session, name), session.conf.get(BATCH)
        try:
            if batch:
                session.conf.set(BATCH, str(min(batch, int(before)) if int(before) > 0 else batch))
            df.write.parquet(path)
        finally:
            session.conf.set(BATCH, before)
        return session, df.schema, path

    spark, schema, path = run()
    if large:
        release(spark)
    return spark.read.schema(schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of plans that nothing refers to any more, instead of at the driver's next GC."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)  # until listeners have let go of the plan and the cleaner has run


def quoted(name: str) -> str:
    """A column's name as a reference, whatever characters it has."""
    return f"`{name.replace('`', '``')}`"


def numbered(df: DataFrame) -> DataFrame:
    """The table with columns called c0, c1 and so on, as Arrow functions can't refer to every name."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def unused(df: DataFrame, name: str) -> str:
    """A column name that the table doesn't have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def _round(now: DataFrame) -> DataFrame:
    both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.least("a", F.min("b")).alias("m"))
    large = both.where("b > a").join(low, "a").select(F.col("m").alias("a"), "b").where("a < b").distinct()
    low = large.groupBy("b").agg(F.min("a").alias("m"))
    return large.join(low, "b").select(F.col("m").alias("a"), F.explode(F.array("a", "b")).alias("b")).where("a < b").distinct()


def components(links: Callable[[], DataFrame], most_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of the links (a, b): the smallest node reachable.

    Stars alternate: each node hands its larger neighbours to the smallest node next to it, then keeps only links to
    smaller ones. Hubs are reduced by partial minima before any shuffle; each round is written to the shared folder.
    Self links are kept as nodes of their own. Ends when a round changes nothing; raises after most_rounds.
    """
    e = written(lambda: links().select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
    nodes = e.select(F.col("a").alias("node")).union(e.select(F.col("b").alias("node"))).distinct()
    now = e.where("a < b")
    seen = None
    for _ in range(most_rounds):
        now = written(partial(_round, now), "stars")
        state = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if seen == state:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    root = now.groupBy("b").agg(F.min("a").alias("m"))
    return nodes.join(root, F.col("node") == F.col("b"), "left").select("node", F.coalesce("m", "node").alias("component"))
