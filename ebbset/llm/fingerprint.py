"""Bottom-k sketches of word shingles as document fingerprints.

A sketch holds the k least distinct hashes of a text's shingles and stands for the whole set: sketches of parts merge by
keeping the k least of their union, the k-th hash estimates how many distinct shingles there are, and the least k of a
union estimate resemblance and containment. A sketch of fewer than k hashes is the whole set and gives exact values.

Defined results: null and empty texts have an empty sketch (two empty ones resemble each other fully); equal texts have
equal fingerprints; a text of fewer words than the width counts as one shingle. For neighbours, rows are ordered by
doc_id descending, rows with equal ids by text; a lone row is its own neighbour; rows without an id come last. Extra
columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import math
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ebbset.llm._text import pieces, shingle_sets

WIDTH, K = 5, 128
SPACE = 2.0**64


def sketch(own: np.ndarray, k: int = K) -> np.ndarray:
    """The k least of sorted distinct hashes."""
    return own[:k]


def sketches(text: pa.Array, width: int = WIDTH, k: int = K) -> list[np.ndarray]:
    return [sketch(s, k) for s in shingle_sets(text, width)]


def merged(a: np.ndarray, b: np.ndarray, k: int = K) -> np.ndarray:
    """The sketch of two parts' union; shingles that span the parts are not in it."""
    return np.union1d(a, b)[:k]


def distinct(a: np.ndarray, k: int = K) -> float:
    """Estimated number of distinct shingles."""
    return float(len(a)) if len(a) < k else (k - 1) * SPACE / (float(a[k - 1]) + 1)


def resemblance(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated Jaccard similarity."""
    least = np.union1d(a, b)[:k]
    if not len(least):
        return 1.0
    return float(np.isin(least, np.intersect1d(a, b, assume_unique=True)).sum()) / len(least)


def containment(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated share of a's shingles that b has too."""
    if not len(a):
        return 1.0
    both = resemblance(a, b, k) * distinct(merged(a, b, k), k)
    return min(1.0, both / distinct(a, k))


def encoded(a: np.ndarray) -> str:
    """As lowercase hex, 16 digits a hash in ascending order."""
    return a.astype(">u8").tobytes().hex()


def decoded(text: str) -> np.ndarray:
    return np.frombuffer(bytes.fromhex(text), ">u8").astype(np.uint64)


def _encoded(batches, width: int, k: int):
    for batch in batches:
        for part in pieces(batch):
            own = sketches(part.column("text"), width, k)
            cols = [part.column("doc_id"), pa.array([encoded(s) for s in own], pa.string()), pa.array([distinct(s, k) for s in own], pa.float64())]
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "fingerprint", "n_distinct"])


def fingerprints(docs: DataFrame, width: int = WIDTH, k: int = K) -> DataFrame:
    """doc_id, fingerprint, n_distinct (estimated number of distinct shingles) of each row."""
    return _plain(docs).mapInArrow(partial(_encoded, width=width, k=k), "doc_id long, fingerprint string, n_distinct double")


def _plain(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


ROW = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
NAMES = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]


def edited(text: str, following: str) -> str:
    """The text, its later half (rounded down) replaced by as many first code points of the following one, or all."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _judged(ids: list, texts: list[str], width: int, k: int):
    """Result rows of all but the last of consecutive documents."""
    changed = [edited(a, b) for a, b in zip(texts[:-1], texts[1:], strict=True)]
    own, other = sketches(pa.array(texts, pa.large_string()), width, k), sketches(pa.array(changed, pa.large_string()), width, k)
    cols = [
        pa.array(ids[:-1], pa.int64()), pa.array([len(t) for t in texts[:-1]], pa.int64()), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in changed], pa.string()),
        pa.array([encoded(s) for s in own[:-1]], pa.string()), pa.array([encoded(s) for s in other], pa.string()),
        pa.array([resemblance(a, b, k) for a, b in zip(own[:-1], other, strict=True)], pa.float64()), pa.array([resemblance(a, b, k) for a, b in zip(own[:-1], own[1:], strict=True)], pa.float64()),
    ]
    return cols


def _parts(batches):
    """(part, ids, texts) of stretches of rows with one part number, a few MB at a time; rows are sorted by part."""
    for batch in batches:
        for cut in pieces(batch):
            part = np.asarray(cut.column("part"))
            ends = np.append(np.flatnonzero(part[1:] != part[:-1]) + 1, len(part)).tolist()
            for a, b in zip([0, *ends[:-1]], ends, strict=True):
                own = cut.slice(a, b - a)
                yield int(part[a]), own.column("doc_id").to_pylist(), own.column("text").to_pylist()


def _in_order(batches, width: int, k: int):
    """Rows judged by the next row of their part."""
    held = None
    for part, ids, texts in _parts(batches):
        if held is not None and held[0] == part:
            ids, texts = [held[1], *ids], [held[2], *texts]
        held = part, ids[-1], texts[-1]
        if len(ids) > 1:
            yield pa.RecordBatch.from_arrays(_judged(ids, texts, width, k), NAMES)


def _edges(batches):
    """Each part's first text and last row."""
    held = None

    def out():
        part, first, doc, last = held
        return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([first], pa.string()), pa.array([doc], pa.int64()), pa.array([last], pa.string())], ["part", "first_text", "open_id", "open_text"])

    for part, ids, texts in _parts(batches):
        if held is not None and held[0] != part:
            yield out()
            held = None
        held = part, held[1] if held else texts[0], ids[-1], texts[-1]
    if held is not None:
        yield out()


def _across(batches, width: int, k: int):
    for batch in batches:
        for doc, text, following in zip(*(batch.column(c).to_pylist() for c in ("open_id", "open_text", "next_text")), strict=True):
            yield pa.RecordBatch.from_arrays(_judged([doc, None], [text, following], width, k), NAMES)


def part_of(key, bounds: list[int]):
    """How many of the sorted bounds are at most the key, by whole rows of bounds first; 0 for null."""
    side = max(1, math.isqrt(len(bounds)))
    rows = [bounds[i : i + side] for i in range(0, len(bounds), side)]
    if not rows:
        return F.lit(0)
    heads = F.array(*[F.lit(r[0]) for r in rows])
    table = F.from_json(F.lit(json.dumps(rows)), "array<array<bigint>>")
    row = F.size(F.filter(heads, lambda b: b <= key))
    within = F.size(F.filter(F.coalesce(F.get(table, row - 1), F.array().cast("array<bigint>")), lambda b: b <= key))
    return F.when(key.isNull(), 0).otherwise(F.greatest(row - 1, F.lit(0)) * side + within)


def neighbours(docs: DataFrame, width: int = WIDTH, k: int = K) -> DataFrame:
    """Fingerprints of each text and of the text edited with the next one, and their likeness.

    Documents are dealt by ranges of their ids, with bounds from quantiles of the ids alone; within a range the next row
    is at hand, and only each range's first text and last row meet those of other ranges: one row a range.
    """
    spark = docs.sparkSession
    plain = _plain(docs)
    many = int(spark.conf.get("spark.sql.shuffle.partitions"))
    found = plain.agg(F.percentile_approx("doc_id", [i / many for i in range(1, many)], 100 * many).alias("q")).first().q if many > 1 else None
    dealt = plain.withColumn("part", (-part_of(F.col("doc_id"), sorted(set(found or [])))).cast("int"))
    dealt = dealt.repartition(many, "part").sortWithinPartitions("part", F.col("doc_id").desc(), "text")
    inner = dealt.mapInArrow(partial(_in_order, width=width, k=k), ROW)
    edges = dealt.mapInArrow(_edges, "part int, first_text string, open_id long, open_text string")
    order = Window.orderBy("part")
    whole = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    following = F.coalesce(F.lead("first_text").over(order), F.first("first_text").over(whole))
    last = edges.select("open_id", "open_text", following.alias("next_text"))
    return inner.union(last.mapInArrow(partial(_across, width=width, k=k), ROW))
