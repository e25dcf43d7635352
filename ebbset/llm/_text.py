"""Vectorised text primitives shared by the operators: byte views, words, shingles, hashes.

All functions take Arrow string arrays cut into pieces of a few MB, so memory is bounded by the piece
(or by one document, where that is longer). Null text counts as empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 4 << 20
#: Words hashed at a time, few enough for their bytes' terms to stay in a processor's cache.
BLOCK = 1 << 14
U = np.uint64

_rng = np.random.Generator(np.random.PCG64(20240517))
#: One random word per byte value; the second table folds A-Z onto a-z.
BYTE_HASH = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
BYTE_HASH_LOWER = BYTE_HASH.copy()
BYTE_HASH_LOWER[65:91] = BYTE_HASH[97:123]
SLOT = _rng.integers(1, 2**63, 64, dtype=np.uint64) * U(2) + U(1)
STEP = U(0x9E3779B97F4A7C15)
#: Space and the control characters 9 to 13 separate words.
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective 64-bit finaliser, one per salt."""
    x = np.asarray(x, dtype=np.uint64) + U((salt * 0xD1B54A32D192ED03 + 0x8CB92BA72F3D8DD7) & (2**64 - 1))
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def bytes_of(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows end to end, and the rows' offsets in them."""
    if text.null_count:
        text = pc.fill_null(text, "" if pa.types.is_string(text.type) or pa.types.is_large_string(text.type) else b"")
    wide = pa.types.is_large_string(text.type) or pa.types.is_large_binary(text.type)
    _, offsets, data = text.buffers()
    offsets = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64) if len(text) else np.zeros(1, np.int64)
    data = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def pieces(batch: pa.RecordBatch, column: str = "text", most: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in row slices of at most that many bytes of text each, one row at least."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    ends = np.cumsum(sizes)
    at = 0
    while at < len(sizes):
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield batch.slice(at, to - at)
        at = to


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First byte and end of each word, and the number of the first word of each row (one more entry than rows)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    word = ~IS_SPACE[data]
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1]
    last[:-1] &= ~word[1:]
    inner = offsets[1:-1]
    inner = inner[(inner > 0) & (inner < len(data))]
    first[inner] = word[inner]
    last[inner - 1] = word[inner - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, table: np.ndarray = BYTE_HASH_LOWER) -> np.ndarray:
    """A 64-bit hash of each word; the default table ignores the case of A-Z."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    sizes = ends - starts
    power = np.ones(int(sizes.max()), np.uint64)
    power[1:] = STEP
    np.multiply.accumulate(power, out=power)
    out = np.empty(len(starts), np.uint64)
    for lo in range(0, len(starts), BLOCK):
        own = sizes[lo : lo + BLOCK]
        first = np.cumsum(own) - own
        place = np.arange(int(first[-1] + own[-1]), dtype=np.int64) - np.repeat(first, own)
        terms = table[data[place + np.repeat(starts[lo : lo + BLOCK], own)]]
        terms *= power[place]
        out[lo : lo + BLOCK] = np.add.reduceat(terms, first)
    return mix(out + sizes.astype(np.uint64))


def shingle_hashes(words: np.ndarray, first_word: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all word shingles in row order, and each row's offsets in them.

    A row of fewer words than the width gives its whole sequence as one; a row without words gives none.
    """
    counts = np.diff(first_word)
    sizes = np.where(counts >= width, counts - width + 1, (counts > 0).astype(np.int64))
    offsets = np.concatenate([[0], np.cumsum(sizes)])
    out = np.empty(int(offsets[-1]), np.uint64)
    if len(words) >= width:
        total = words[: len(words) - width + 1] * SLOT[0]
        for j in range(1, width):
            total = total + words[j : len(words) - width + 1 + j] * SLOT[j]
        row = np.repeat(np.arange(len(counts)), np.where(counts >= width, sizes, 0))
        whole = np.where(counts >= width, sizes, 0)
        within = np.arange(len(row)) - np.repeat(np.cumsum(whole) - whole, whole)
        out[offsets[row] + within] = mix(total[first_word[row] + within])
    for r in np.flatnonzero((counts > 0) & (counts < width)):
        own = words[first_word[r] : first_word[r + 1]]
        out[offsets[r]] = mix(np.array([(own * SLOT[: len(own)]).sum(dtype=np.uint64)]), salt=64 + len(own))[0]
    return out, offsets


def shingle_sets(text: pa.Array, width: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each row."""
    data, offsets = bytes_of(text)
    starts, ends, first = words_of(data, offsets)
    hashes, at = shingle_hashes(word_hashes(data, starts, ends), first, width)
    return [np.unique(hashes[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def list_array(values: np.ndarray, offsets: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values, type=kind))


def runs(batches: Iterator[pa.RecordBatch], keys: list[str], most: int = 1 << 62) -> Iterator[pa.Table]:
    """Whole groups from batches sorted by the keys, several groups at a time: each table ends where a group ends."""
    held: list[pa.RecordBatch] = []

    def last_start(batch: pa.RecordBatch) -> int:
        """Where the batch's last group begins."""
        change = np.zeros(len(batch), bool)
        for k in keys:
            col = batch.column(k)
            if len(col) > 1:
                change[1:] |= np.asarray(pc.not_equal(col[1:], col[:-1]))
        found = np.flatnonzero(change)
        return int(found[-1]) if len(found) else 0

    def key(batch: pa.RecordBatch, row: int) -> tuple:
        return tuple(batch.column(k)[row].as_py() for k in keys)

    for batch in batches:
        if not len(batch):
            continue
        if held and key(held[-1], len(held[-1]) - 1) != key(batch, 0):
            yield pa.Table.from_batches(held)
            held = []
        cut = last_start(batch)
        if cut:
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            held = [batch.slice(cut)]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held)
