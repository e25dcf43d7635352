"""Sum-of-squares online packing of tokenised documents into fixed windows.

Each document gives its ids and an end id. Whole windows are cut off its front; the rest goes, as documents arrive, to
the fill level that leaves the smallest sum of squared counts of partly filled windows, which an array of counts by
level tracks. Each task packs its own rows, so there is no shuffle and memory holds only the partly filled windows of
one task. When its rows end, windows stand as the rule filled them, but that the emptiest ones are taken apart, one at a
time, and their items placed in the others by the same rule, cut where none has room. The last one is cut at powers of
two, so that a task pads nothing.

Defined results: null text counts as empty and gives the end id alone; repeated rows and ties are packed one by one in
row order; an empty table gives no pieces. Results depend on how rows are dealt to tasks; every id is in one piece.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ebbset.llm._text import pieces
from ebbset.llm.tokens import piece_encoder, vocabulary

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Sequences of one task are numbered from its partition's number times this.
PER_TASK = 1 << 36


class LevelPacker:
    """Windows of one size; place() says where the next item goes."""

    def __init__(self, window: int):
        self.window = window
        self.count = np.zeros(window + 1, np.int64)
        self.open: list[list[int]] = [[] for _ in range(window)]
        self.held: dict[int, list] = {}
        self.next = 0
        #: Windows filled up, and windows taken apart at the end.
        self.closed = self.dissolved = 0

    def fresh(self) -> int:
        self.next += 1
        return self.next - 1

    def level(self, size: int, opening: bool = True) -> int:
        """The level whose choice for an item of this size leaves the least sum of squares; the fullest among equals.

        Level 0 opens a window; without `opening`, 0 says that no window has room.
        """
        most = self.window - size
        worst = np.iinfo(np.int64).max
        cost = np.empty(most + 1, np.int64)
        cost[0] = (2 * self.count[size] + 1 if size < self.window else 0) if opening else worst
        if most:
            cost[1:] = 2 * (self.count[size + 1 : self.window + 1] - self.count[1 : most + 1]) + 2
            cost[most] = 1 - 2 * self.count[most]
            cost[1:][self.count[1 : most + 1] == 0] = worst
        found = most - int(np.argmin(cost[::-1]))
        return found if cost[found] < worst else 0

    def place(self, size: int, item, skip: int = 0, opening: bool = True) -> list | None:
        """Puts an item of less than a window somewhere; the finished window's (sequence, items) if that fills it."""
        return self._put(self.level(size, opening), size, item, skip)

    def _put(self, at: int, size: int, item, skip: int) -> list | None:
        if at:
            sequence = self.open[at].pop()
            self.count[at] -= 1
        else:
            sequence = self.fresh()
            self.held[sequence] = []
        self.held[sequence].append((at, size, skip, item))
        if at + size == self.window:
            self.closed += 1
            return [(sequence, self.held.pop(sequence))]
        self.open[at + size].append(sequence)
        self.count[at + size] += 1
        return None

    def _emptiest(self) -> list:
        at = int(np.flatnonzero(self.count[: self.window])[0])
        self.count[at] -= 1
        self.dissolved += 1
        return self.held.pop(self.open[at].pop())

    def rest(self) -> Iterator[tuple[int, int, int, int, object]]:
        """(sequence, offset, size, skip, item) of what the partly filled windows hold, refilled without padding.

        Windows stand as the rule filled them. While there are several, the emptiest is taken apart and its items are
        placed in the others by the same rule; one that fits nowhere is cut, its front filling the fullest window up. The
        last window is cut at powers of two.
        """
        items: list[tuple] = []
        while self.held and not items:
            for _, size, skip, item in self._emptiest():
                while size:
                    levels = np.flatnonzero(self.count[: self.window])
                    if not len(levels):
                        items.append((size, skip, item))
                        break
                    at, take = self.level(size, opening=False), size
                    if not at:
                        at = int(levels[-1])
                        take = self.window - at
                    for sequence, own in self._put(at, take, item, skip) or []:
                        yield from ((sequence, a, n, before, x) for a, n, before, x in own)
                    size, skip = size - take, skip + take
        left = sum(size for size, _, _ in items)
        plan = [self.window] * (left // self.window) + [1 << b for b in range((left % self.window).bit_length() - 1, -1, -1) if left >> b & 1]
        todo, size, skip, item = iter(items), 0, 0, None
        for room in plan:
            sequence, at = self.fresh(), 0
            while at < room:
                if not size:
                    size, skip, item = next(todo)
                take = min(size, room - at)
                yield sequence, at, take, skip, item
                at, size, skip = at + take, size - take, skip + take


def _pack(batches, path: str | None, window: int, end_id: int):
    task = TaskContext.get()
    base = (task.partitionId() if task else 0) * PER_TASK
    encoder, packer = piece_encoder(path or vocabulary("byte_bpe_50k.json")), LevelPacker(window)
    rows: list[tuple] = []

    def put(sequence, offset, skip, length, item):
        doc, start, ids, total = item
        rows.append((doc, start + skip, length, zlib.crc32(ids[4 * skip : 4 * (skip + length)]), total, base + sequence, offset))

    def out():
        made = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])
        rows.clear()
        return made

    for batch in batches:
        for part in pieces(batch):
            ids, offsets = encoder.encode(part.column("text"))
            raw = ids.astype("<u4", copy=False)
            end = np.array([end_id], "<u4").tobytes()
            for doc, a, b in zip(part.column("doc_id").to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                own, total, start = raw[a:b].tobytes() + end, b - a + 1, 0
                while total - start >= window:
                    put(packer.fresh(), 0, 0, window, (doc, start, own[4 * start : 4 * (start + window)], total))
                    start += window
                if start < total:
                    done = packer.place(total - start, (doc, start, own[4 * start :], total))
                    for sequence, items in done or []:
                        for at, size, skip, item in items:
                            put(sequence, at, skip, size, item)
            if len(rows) >= 4096:
                yield out()
    for sequence, at, size, skip, item in packer.rest():
        put(sequence, at, skip, size, item)
    if rows:
        yield out()


def pack(docs: DataFrame, window: int = 1024, end_id: int = 0, path: str | None = None) -> DataFrame:
    """Pieces of packed sequences: where each lies in its document and in its sequence. path: the vocabulary file."""
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return plain.mapInArrow(partial(_pack, path=path, window=window, end_id=end_id), SCHEMA)
