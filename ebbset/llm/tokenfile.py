"""Token ids in Parquet list columns.

Rows are dealt by ranges of doc_id and sorted, so files, row groups and pages hold ascending ids and their statistics
allow selective reads; ids are dictionary encoded (16 bits for a 50k vocabulary), places and lengths delta encoded.
Each row keeps where it starts in its file; a small table of file totals, one row a file, turns that into global starts.

Defined results: null text counts as empty and gives the end id alone; repeated ids keep all their rows, ordered by
text; an empty table gives a readable file without rows. Only doc_id and text of the input are used.
"""

from __future__ import annotations

import zlib
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ebbset.llm._spark import new_path
from ebbset.llm._text import list_array, pieces
from ebbset.llm.tokens import piece_encoder, vocabulary

SCHEMA = "doc_id long, part int, part_start long, n_tokens int, ids array<int>"
ROW_GROUP, PAGE = 16 << 20, 64 << 10


def _encode(batches, path: str | None, end_id: int):
    encoder, total = piece_encoder(path or vocabulary("byte_bpe_50k.json")), 0
    task = TaskContext.get()
    number = task.partitionId() if task else 0
    for batch in batches:
        for part in pieces(batch):
            ids, offsets = encoder.encode(part.column("text"))
            ends = offsets[1:] + np.arange(1, len(offsets))
            own = np.insert(ids.astype(np.int32), offsets[1:], end_id)
            offsets = np.concatenate([[0], ends])
            size = np.diff(offsets)
            yield pa.RecordBatch.from_arrays(
                [
                    part.column("doc_id"), pa.array(np.full(len(part), number, np.int32)), pa.array(total + offsets[:-1]),
                    pa.array(size.astype(np.int32)), list_array(own, offsets, pa.int32()),
                ],
                ["doc_id", "part", "part_start", "n_tokens", "ids"],
            )
            total += int(offsets[-1])


def write_tokens(docs: DataFrame, to: str, end_id: int = 2, path: str | None = None, row_group: int = ROW_GROUP, page: int = PAGE) -> None:
    """Writes the token files of the documents in ascending doc_id order. path: the vocabulary file."""
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = plain.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    (
        dealt.mapInArrow(partial(_encode, path=path, end_id=end_id), SCHEMA)
        .write.option("parquet.block.size", row_group).option("parquet.page.size", page).option("parquet.enable.dictionary", "true")
        .option("parquet.writer.version", "PARQUET_2_0").option("compression", "zstd").parquet(to)
    )


def read_tokens(spark: SparkSession, at: str, columns: list[str] | None = None, low: int | None = None, high: int | None = None) -> DataFrame:
    """Rows of token files; a range of doc_id reads only the row groups and pages that may hold it."""
    rows = spark.read.schema(SCHEMA).parquet(at)
    if low is not None:
        rows = rows.where(F.col("doc_id") >= low)
    if high is not None:
        rows = rows.where(F.col("doc_id") <= high)
    return rows.select(*columns) if columns else rows


def starts(spark: SparkSession, at: str) -> DataFrame:
    """(part, base): ids in all earlier files. One row a file."""
    size = read_tokens(spark, at, ["part", "n_tokens"]).groupBy("part").agg(F.sum(F.col("n_tokens").cast("long")).alias("n"))
    found, base = [], 0
    for part, n in sorted(size.collect()):
        found.append((part, base))
        base += n
    return spark.createDataFrame(found, "part int, base long")


def _sums(batches):
    for batch in batches:
        ids = batch.column("ids")
        at = np.asarray(ids.offsets)
        raw = np.asarray(ids.values).astype("<u4").tobytes()
        crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        size = pa.array(np.diff(at).astype(np.int64))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("part"), batch.column("part_start"), size, pa.array(crc, pa.int64())], ["doc_id", "part", "part_start", "n_tokens", "ids_crc32"])


def round_trip(docs: DataFrame, end_id: int = 2, path: str | None = None) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, from files written and read back."""
    spark = docs.sparkSession
    to = new_path(spark, "tokens")
    write_tokens(docs, to, end_id, path)
    rows = read_tokens(spark, to).mapInArrow(_sums, "doc_id long, part int, part_start long, n_tokens long, ids_crc32 long")
    return rows.join(F.broadcast(starts(spark, to)), "part").select("doc_id", (F.col("base") + F.col("part_start")).alias("start"), "n_tokens", "ids_crc32")
