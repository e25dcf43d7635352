"""Sketches kept under a stream: lazily as summed counters, or eagerly with signatures rebuilt after each update."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from functools import partial

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ebbset.operators.candidates import SIGNATURE_BITS
from ebbset.operators.sketch import placed
from ebbset.params import SketchParams
from ebbset.session import scratch


def stream_cells(updates: DataFrame, p: SketchParams) -> DataFrame:
    """Running counters of a streaming (or static) update stream; zeros are kept, as a stream must report them."""
    rows = placed(updates, p)
    both = F.explode(F.array("level", F.lit(0))).alias("level")
    return rows.select("set_id", both, "bucket", "delta").groupBy("set_id", "level", "bucket").agg(F.sum("delta").cast("long").alias("cnt"))


def drained(stream: DataFrame, name: str, mode: str = "update") -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote to a memory table."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


ROCKS, PROVIDER = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.streaming.stateStore.providerClass"


def appended(stream: DataFrame) -> DataFrame:
    """Runs a stream over all that is there and returns the rows that it appended, as files in the shared folder."""
    spark = stream.sparkSession
    path, log = scratch(spark, "appended"), scratch(spark, "progress")
    q = stream.writeStream.format("parquet").option("checkpointLocation", log).outputMode("append").trigger(availableNow=True).start(path)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def aggregated(stream: DataFrame) -> DataFrame:
    """Runs an aggregation of a stream over all that is there and returns its groups from the state store: key, value.

    Executors keep the state on disk and read it, so the driver holds no groups. value has the aggregates' buffers: sum, count.
    """
    spark = stream.sparkSession
    log, before = scratch(spark, "state"), spark.conf.get(PROVIDER)
    try:
        spark.conf.set(PROVIDER, ROCKS)
        q = stream.writeStream.format("noop").option("checkpointLocation", log).outputMode("update").trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.set(PROVIDER, before)
    return spark.read.format("statestore").load(log).select("key", "value")


def read_updates(spark: SparkSession, path: str, schema: str = "set_id long, item_id long, delta int, seq long") -> DataFrame:
    return spark.readStream.schema(schema).parquet(path)


class EagerSketch:
    """One set's sketch with signatures per level, kept after every update.

    A bucket that fills folds its hashes into the minima; one that empties makes its level's signature be rebuilt from the
    buckets left, with `selective` only if the level is one that the set is filed at, else when it next becomes one. A
    bucket that stays filled changes nothing. Counts what it does.
    """

    def __init__(self, p: SketchParams, selective: bool = True):
        self.p, self.selective = p, selective
        self.hashes = p.draw("minhash", p.rows * p.bands)
        self.cells: dict[tuple[int, int], int] = {}
        self.items: dict[int, int] = {}
        self.sigs: dict[int, list[int]] = {}
        self.stale: set[int] = set()
        self.card = self.evaluated = self.rebuilt = 0

    def _ranks(self, bucket: int) -> list[int]:
        self.evaluated += len(self.hashes)
        return [((a * bucket + b) & 0xFFFFFFFF) >> (32 - SIGNATURE_BITS) for a, b in self.hashes]

    def window(self) -> list[int]:
        high, low = max(self.p.alpha * self.card, 1.0), min(self.p.alpha * self.card / 2**self.p.width, float(2 ** self.p.grid[-1]))
        return [k for k in self.p.grid if low <= 2**k <= high or (k == 0 and low <= 1)]

    def update(self, item: int | None, level: int | None, bucket: int | None, delta: int) -> None:
        was = self.items.get(item, 0) > 0
        self.items[item] = self.items.get(item, 0) + delta
        self.card += (self.items[item] > 0) - was
        if not self.items[item]:
            del self.items[item]
        for k in {level, 0} if level is not None else ():
            before = self.cells.get((k, bucket), 0)
            after = before + delta
            self.cells[k, bucket] = after
            if not after:
                del self.cells[k, bucket]
            if not before and after:
                if k not in self.stale:
                    new = self._ranks(bucket)
                    self.sigs[k] = list(map(min, self.sigs[k], new)) if k in self.sigs else new
            elif before and not after:
                self.stale.add(k)
        due = self.stale & set(self.window()) if self.selective else set(self.stale)
        for k in due:
            self.rebuild(k)

    def rebuild(self, k: int) -> None:
        self.rebuilt += 1
        self.stale.discard(k)
        rows = [self._ranks(b) for (level, b) in self.cells if level == k]
        self.sigs.pop(k, None)
        if rows:
            self.sigs[k] = [min(c) for c in zip(*rows, strict=True)]

    def current(self) -> dict[int, list[int]]:
        """Signatures of the levels the set is filed at."""
        return {k: self.sigs[k] for k in self.window() if k in self.sigs}


def _taken(own: EagerSketch, rows: pd.DataFrame) -> None:
    """Updates in their order; a null item counts as one, but lies in no bucket."""
    for item, level, bucket, delta in rows.sort_values(["seq", "item_id"])[["item_id", "level", "bucket", "delta"]].itertuples(index=False):
        if pd.isna(item):
            own.update(None, None, None, int(delta))
        else:
            own.update(int(item), int(level), int(bucket), int(delta))


def _reported(set_id: int, own: EagerSketch) -> pd.DataFrame:
    """The current signatures. A set without any has no rows, of which Arrow can't tell that they would hold lists."""
    sigs = own.current()
    return pd.DataFrame({"set_id": set_id, "level": list(sigs), "card": own.card, "sig": pd.Series(list(sigs.values()), dtype=object), "evaluated": own.evaluated, "rebuilt": own.rebuilt})


def _replayed(rows: pd.DataFrame, p: SketchParams, selective: bool) -> pd.DataFrame:
    own = EagerSketch(p, selective)
    _taken(own, rows)
    return _reported(rows.set_id.iloc[0], own)


EAGER = "set_id long, level int, card long, sig array<int>, evaluated long, rebuilt long"


def eager_signatures(updates: DataFrame, p: SketchParams, selective: bool = True) -> DataFrame:
    """Batch replay of a bounded selection of sets: final signatures and what maintaining them cost."""
    return placed(updates.where("set_id is not null"), p).groupBy("set_id").applyInPandas(partial(_replayed, p=p, selective=selective), EAGER)


def _maintained(key: tuple, batches: Iterator[pd.DataFrame], state, p: SketchParams, selective: bool) -> Iterator[pd.DataFrame]:
    own = pickle.loads(state.get[0]) if state.exists else EagerSketch(p, selective)
    for rows in batches:
        _taken(own, rows)
    state.update((pickle.dumps(own),))
    yield _reported(key[0], own)


def eager_stream(updates: DataFrame, p: SketchParams, selective: bool = True) -> DataFrame:
    """The same as a stateful stream: each micro-batch reports the signatures of the sets it touched."""
    return placed(updates, p).groupBy("set_id").applyInPandasWithState(partial(_maintained, p=p, selective=selective), EAGER, "held binary", "update", "NoTimeout")
