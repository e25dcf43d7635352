"""Repeated byte windows by depth-limited suffix order.

A byte goes if a window of `depth` bytes covers it that also starts in a document with a smaller id. To find the equal
windows of a corpus, suffixes are ordered by most-significant-digit passes of eight bytes and only through `depth`
bytes; a group that is still together then is exactly a repeated window. Suffixes enter the passes already dealt out:
every window has a minimal gram (least hash among its grams of `gram` bytes), equal windows have equal ones, and those
that occur in one document only are dropped before any window is written out. Consecutive windows with one minimal gram
travel as one row with their joint bytes.

Copies of a whole text are settled first by hashes of the text: they go entirely, so groups of copies never meet in a
task. What remains of a hot group are the windows around one gram.

Defined results: null text counts as empty; texts shorter than `depth` lose nothing; documents with equal id never
remove each other's bytes (each row is judged by its own text); rows without an id are left out; extra columns are
ignored.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.llm._spark import written
from ebbset.llm._text import STEP, bytes_of, mix, pieces, runs, signed

DEPTH, GRAM = 50, 18
#: Bytes of text that are hashed at a time.
CHUNK = 2 << 20


def least_over(x: np.ndarray, width: int) -> np.ndarray:
    """At each place the least of the `width` values from there on (fewer at the end)."""
    out, have = x.copy(), 1
    while have < width:
        step = min(have, width - have)
        out[: len(out) - step] = np.minimum(out[: len(out) - step], out[step:])
        have += step
    return out


def segments(data: np.ndarray, offsets: np.ndarray, depth: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Stretches of windows with one minimal gram: its hash, the row, the first and the last window's start."""
    none = np.zeros(0, np.int64)
    size = np.maximum(np.diff(offsets) - depth + 1, 0)
    if not size.sum():
        return np.zeros(0, np.uint64), none, none, none
    padded = np.concatenate([data, np.zeros(gram + 8, np.uint8)])
    eight = np.lib.stride_tricks.as_strided(padded, (len(data) + gram, 8), (1, 1)).copy().view(np.uint64).ravel()
    n = len(data)
    hashes = mix(eight[:n])
    for at in [*range(8, gram - 8, 8), gram - 8]:
        hashes = mix(hashes * STEP + eight[at : n + at])
    least = least_over(hashes, depth - gram + 1)
    row = np.repeat(np.arange(len(size)), size)
    start = np.arange(len(row)) + np.repeat(offsets[:-1] - (np.cumsum(size) - size), size)
    least = least[start]
    first = np.ones(len(row), bool)
    first[1:] = (least[1:] != least[:-1]) | (row[1:] != row[:-1])
    at = np.flatnonzero(first)
    last = np.append(at[1:], len(row)) - 1
    return least[at], row[at], start[at], start[last]


def _grams(batches, depth: int, gram: int):
    for batch in batches:
        for part in pieces(batch, most=CHUNK):
            data, offsets = bytes_of(part.column("text"))
            least, row, _, _ = segments(data, offsets, depth, gram)
            yield pa.RecordBatch.from_arrays([signed(least), part.column("doc_id").take(pa.array(row))], ["gram", "doc_id"])


def _shared(batches):
    """Rows whose gram occurs under two ids at least; batches are sorted by gram, then id."""
    for table in runs(batches, ["gram"]):
        gram, doc = np.asarray(table.column("gram")), np.asarray(table.column("doc_id"))
        first = np.ones(len(gram), bool)
        first[1:] = gram[1:] != gram[:-1]
        at = np.flatnonzero(first)
        end = np.append(at[1:], len(gram)) - 1
        keep = np.repeat(doc[at] != doc[end], end - at + 1)
        keep[1:] &= first[1:] | (doc[1:] != doc[:-1])
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(gram[keep]), pa.array(doc[keep])], ["gram", "doc_id"])


def _stretches(batches, depth: int, gram: int):
    """The windows of shared grams: gram, doc_id, tag, first start, joint bytes."""
    for batch in batches:
        for part in pieces(batch, most=CHUNK):
            data, offsets = bytes_of(part.column("text"))
            least, row, first, last = segments(data, offsets, depth, gram)
            lists = part.column("grams")
            held = np.asarray(lists.flatten()).view(np.uint64)
            owner = np.repeat(np.arange(len(part)), np.asarray(lists.value_lengths()))
            # rows of few documents: membership by a hash of row and gram
            keep = np.isin(mix(least ^ mix(row.astype(np.uint64))), mix(held ^ mix(owner.astype(np.uint64))))
            least, row, first, last = least[keep], row[keep], first[keep], last[keep]
            size = last - first + depth
            ends = np.concatenate([[0], np.cumsum(size)])
            place = np.arange(int(ends[-1])) + np.repeat(first - ends[:-1], size)
            joint = pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(data[place].tobytes())])
            take = pa.array(row)
            yield pa.RecordBatch.from_arrays(
                [signed(least), part.column("doc_id").take(take), part.column("tag").take(take), pa.array(first - offsets[row]), joint],
                ["gram", "doc_id", "tag", "first", "joint"],
            )


def order_suffixes(data: np.ndarray, start: np.ndarray, group: np.ndarray, doc: np.ndarray, depth: int) -> np.ndarray:
    """Marks the windows (by start in data) that also occur, in the same group, under a smaller id."""
    out = np.zeros(len(start), bool)
    live = np.arange(len(start))
    for at in [*range(0, depth - 8, 8), depth - 8]:
        if not len(live):
            return out
        digit = data[(start[live] + at)[:, None] + np.arange(8)].view(">u8").ravel().astype(np.uint64)
        order = np.lexsort((digit, group))
        live, group, digit = live[order], group[order], digit[order]
        fresh = np.ones(len(live), bool)
        fresh[1:] = (group[1:] != group[:-1]) | (digit[1:] != digit[:-1])
        begin = np.flatnonzero(fresh)
        count = np.diff(np.append(begin, len(live)))
        low, high = np.minimum.reduceat(doc[live], begin), np.maximum.reduceat(doc[live], begin)
        keep = np.repeat(low < high, count)
        group = np.repeat(np.arange(len(begin)), count)[keep]
        low = np.repeat(low, count)[keep]
        live = live[keep]
    out[live] = doc[live] > low
    return out


def _repeats(batches, depth: int):
    """Covered stretches (doc_id, tag, low, high), from whole groups of one gram."""
    for table in runs(batches, ["gram"]):
        table = table.combine_chunks()
        gram, doc, first = (np.asarray(table.column(c)) for c in ("gram", "doc_id", "first"))
        data, offsets = bytes_of(table.column("joint").chunk(0))
        many = np.diff(offsets) - depth + 1
        row = np.repeat(np.arange(len(gram)), many)
        within = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
        fresh = np.ones(len(gram), np.int64)
        fresh[1:] = gram[1:] != gram[:-1]
        hit = order_suffixes(data, offsets[row] + within, np.cumsum(fresh)[row], doc[row], depth)
        row, within = row[hit], within[hit]
        if not len(row):
            continue
        begin = np.ones(len(row), bool)
        begin[1:] = (row[1:] != row[:-1]) | (within[1:] != within[:-1] + 1)
        at = np.flatnonzero(begin)
        end = np.append(at[1:], len(row)) - 1
        own = pa.array(row[at])
        yield pa.RecordBatch.from_arrays(
            [table.column("doc_id").chunk(0).take(own), table.column("tag").chunk(0).take(own), pa.array(first[row[at]] + within[at]), pa.array(first[row[end]] + within[end] + depth)],
            ["doc_id", "tag", "low", "high"],
        )


def union(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs of touching or overlapping spans."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _cut(batches, depth: int):
    for batch in batches:
        rows = []
        for doc, text, copy, tag, spans in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "text", "copy", "tag", "spans")), strict=True):
            raw = (text or "").encode()
            if copy:
                gone = [(0, len(raw))] if len(raw) >= depth else []
            else:
                gone = union([(s["low"], s["high"]) for s in spans or [] if s["tag"] == tag])
            kept, at = [], 0
            for a, b in gone:
                kept.append(raw[at:a])
                at = b
            kept.append(raw[at:])
            rows.append((doc, len(raw), sum(b - a for a, b in gone), len(gone), b"".join(kept), [x for s in gone for x in s]))
        if rows:
            doc, size, gone, many, kept, spans = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays(
                [pa.array(doc, pa.int64()), pa.array(size, pa.int64()), pa.array(gone, pa.int64()), pa.array(many, pa.int64()), pa.array(kept, pa.binary()), pa.array(spans, pa.list_(pa.int64()))],
                ["doc_id", "n_bytes", "n_removed", "n_spans", "kept", "removed"],
            )


def repeated_windows(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (binary) and removed (flat list of byte bounds) of every row."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).where("doc_id is not null")
    tag = F.xxhash64("text")
    copy = written(lambda: _copies(docs), "copies", large=True)
    shared = written(lambda: _shared_grams(docs, copy, depth, gram), "shared-grams", large=True)
    lists = shared.groupBy("doc_id").agg(F.collect_list("gram").alias("grams"))
    rows = docs.join(lists, "doc_id").select("doc_id", tag.alias("tag"), "text", "grams")
    stretches = rows.mapInArrow(partial(_stretches, depth=depth, gram=gram), "gram long, doc_id long, tag long, first long, joint binary")
    spans = stretches.repartition("gram").sortWithinPartitions("gram").mapInArrow(partial(_repeats, depth=depth), "doc_id long, tag long, low long, high long")
    spans = spans.groupBy("doc_id").agg(F.collect_list(F.struct("tag", "low", "high")).alias("spans"))
    judged = docs.join(spans, "doc_id", "left")
    own = copy.groupBy("doc_id").agg(F.collect_list("tag").alias("copies"))
    judged = judged.join(own, "doc_id", "left").select("doc_id", "text", F.coalesce(F.array_contains("copies", tag), F.lit(False)).alias("copy"), tag.alias("tag"), "spans")
    return judged.mapInArrow(partial(_cut, depth=depth), "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, removed array<long>")


def _copies(docs: DataFrame) -> DataFrame:
    """(doc_id, tag) of texts that also occur under a smaller id."""
    tags = docs.select("doc_id", F.xxhash64("text").alias("tag"), F.md5("text").alias("sum"), F.octet_length("text").alias("size"))
    first = tags.groupBy("sum", "size").agg(F.min("doc_id").alias("low"), F.count("*").alias("n")).where("n > 1").select("sum", "size", "low")
    return tags.join(first, ["sum", "size"]).where("doc_id > low").select("doc_id", "tag").distinct()


def _shared_grams(docs: DataFrame, copy: DataFrame, depth: int, gram: int) -> DataFrame:
    own = copy.groupBy("doc_id").agg(F.collect_list("tag").alias("copies"))
    firsts = docs.join(own, "doc_id", "left").where(~F.coalesce(F.array_contains("copies", F.xxhash64("text")), F.lit(False))).select("doc_id", "text")
    grams = firsts.mapInArrow(partial(_grams, depth=depth, gram=gram), "gram long, doc_id long")
    return grams.repartition("gram").sortWithinPartitions("gram", "doc_id").mapInArrow(_shared, "gram long, doc_id long")


def digest(docs: DataFrame) -> DataFrame:
    found = repeated_windows(docs)
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
