"""Byte-level tokens at speed: vectorised pre-token splitting and piece caches.

The splitting pattern is that of the public tokenizers' file; here character classes are looked up for all code points
of a few MB at once, and the pieces tile the UTF-8 bytes, so an Arrow array of them needs no copy. Only distinct pieces
of a slice are encoded, and a bounded cache keeps what recurs.
"""

from __future__ import annotations

import base64
import functools
import itertools
import json

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

from ebbset.llm._text import bytes_of

LETTER, NUMBER, OTHER, SPACE = 0, 1, 2, 3
#: About so many pieces are cached per worker, from slices without a piece of more than so many bytes.
CACHE_PIECE, CACHE_SIZE = 256, 400_000


@functools.cache
def _classes() -> np.ndarray:
    """The class of each code point."""
    out = np.full(0x110000, OTHER, np.uint8)
    for low in range(0, 0x110000, 1 << 12):  # by blocks, as a string of all takes much memory
        block = "".join(chr(c) for c in range(low, low + (1 << 12)) if not 0xD800 <= c < 0xE000)
        for number, pattern in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+"), (SPACE, r"\s+")):
            for m in regex.finditer(pattern, block):
                out[ord(m[0][0]) : ord(m[0][-1]) + 1] = number
    out[0xD800:0xE000] = OTHER
    return out


def piece_starts(points: np.ndarray, row_starts: np.ndarray) -> np.ndarray:
    """Where pieces begin among the code points; rows begin at row_starts (sorted, none empty)."""
    n = len(points)
    if not n:
        return np.zeros(0, np.int64)
    kind = _classes()[points]
    head = np.zeros(n, bool)
    head[row_starts] = True
    tail = np.ones(n, bool)
    tail[:-1] = head[1:]
    change = np.ones(n, bool)
    change[1:] = kind[1:] != kind[:-1]
    start = change | head
    # a single blank joins what follows; the last character of a longer white run is a piece or joins likewise
    space = kind == SPACE
    last_space = space & ~tail
    last_space[:-1] &= ~space[1:]
    start |= last_space
    joins = np.zeros(n, bool)
    joins[1:] = (last_space & (points == 32))[:-1]
    start &= ~(joins & ~head)
    # contractions, where an apostrophe begins a piece
    mark = np.flatnonzero((points == 39) & start & ~tail)
    if len(mark):
        padded = np.concatenate([points, np.zeros(2, points.dtype)])
        row_end = np.append(row_starts[1:], n)[np.searchsorted(row_starts, mark, side="right") - 1]
        a = padded[mark + 1]
        b = np.where(mark + 2 < row_end, padded[mark + 2], 0)
        one = (a == 115) | (a == 116) | (a == 109) | (a == 100)
        two = ((a == 114) & (b == 101)) | ((a == 118) & (b == 101)) | ((a == 108) & (b == 108))
        long = np.where(one, 2, np.where(two, 3, 0))
        at, long = mark[long > 0], long[long > 0]
        for j in (1, 2):
            start[at[long > j] + j] = False
        stop = at + long
        start[stop[stop < n]] = True
    return np.flatnonzero(start)


def split_pieces(text: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """All pieces of all rows as one binary array, and the number of each row's first piece (one more entry than rows)."""
    data, offsets = bytes_of(text)
    raw = data.tobytes()
    points = np.frombuffer(raw.decode("utf-8").encode("utf-32-le"), np.uint32)
    lead = np.flatnonzero((data & 0xC0) != 0x80) if len(points) != len(data) else None
    sizes = np.diff(offsets)
    begin = offsets[:-1][sizes > 0]
    starts = piece_starts(points, begin if lead is None else np.searchsorted(lead, begin))
    starts = starts if lead is None else lead[starts]
    ends = np.append(starts, len(data)).astype(np.int32)
    found = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(raw)])
    return found, np.searchsorted(starts, offsets)


def byte_alphabet() -> dict[str, int]:
    """The byte that each letter of a byte-level vocabulary stands for: printable Latin-1 as is, the rest from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def byte_ranks(path: str) -> dict[bytes, int]:
    """Token bytes and ids of a byte-level vocabulary file (tokenizers JSON or base64 rank lines), specials left out."""
    if path.endswith(".json"):
        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        letter, special = byte_alphabet(), {x["content"] for x in file["added_tokens"]}
        return {bytes(letter[c] for c in token): i for token, i in file["model"]["vocab"].items() if token not in special}
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class PieceEncoder:
    """Ids that the tokenizers library gives texts under a byte-level vocabulary file, without special tokens added.

    Pieces are merged by the library's model, each distinct one once while it is cached. A text that spells out a special
    token is left to the library as a whole, which reads that token in it.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.ranks = byte_ranks(path)
        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.alphabet = {b: c for c, b in byte_alphabet().items()}
        self.known = pa.array([], pa.binary())
        self.size, self.flat = np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def lists(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """How many ids each piece has, and all ids end to end."""
        merge = self.model.tokenize
        found = [[t.id for t in merge(p.decode("latin-1").translate(self.alphabet))] for p in pieces]
        size = np.fromiter(map(len, found), np.int64, len(found))
        return size, np.fromiter(itertools.chain.from_iterable(found), np.uint32, int(size.sum()))

    def encode(self, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows end to end as 32-bit numbers, and the rows' offsets in them."""
        ids, at = self._encode(text)
        spelled = np.zeros(len(text), bool)
        for token in self.special:
            spelled |= np.asarray(pc.fill_null(pc.match_substring(text, token), False))
        if not spelled.any():
            return ids, at
        rows = [ids[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]
        for r in np.flatnonzero(spelled).tolist():
            rows[r] = np.array(self.library.encode(text[r].as_py(), add_special_tokens=False).ids, np.uint32)
        return np.concatenate(rows), np.concatenate([[0], np.cumsum([len(r) for r in rows])])

    def _encode(self, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        pieces, first = split_pieces(text)
        at = pc.index_in(pieces, value_set=self.known)
        index = np.asarray(pc.fill_null(at, -1)).astype(np.int64)
        lost = np.flatnonzero(index < 0)
        size, flat = self.size, self.flat
        if len(lost):
            coded = pieces.take(pa.array(lost)).dictionary_encode()
            index[lost] = len(size) + np.asarray(coded.indices)
            more, ids = self.lists(coded.dictionary.to_pylist())
            size, flat = np.concatenate([size, more]), np.concatenate([flat, ids])
            if len(self.known) < CACHE_SIZE and pc.max(pc.binary_length(coded.dictionary)).as_py() <= CACHE_PIECE:
                self.known = pa.concat_arrays([self.known, coded.dictionary])
                self.size, self.flat = size, flat
        return gather(size, flat, index, first)


def gather(size: np.ndarray, flat: np.ndarray, index: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The lists named by the index end to end, and the offsets that positions in the index turn into."""
    base = np.cumsum(size) - size
    take = size[index]
    ends = np.concatenate([[0], np.cumsum(take)])
    place = np.arange(int(ends[-1])) + np.repeat(base[index] - ends[:-1], take)
    return flat[place], ends[first]


@functools.lru_cache(maxsize=2)
def piece_encoder(path: str) -> PieceEncoder:
    """One encoder per worker process."""
    return PieceEncoder(path)


def vocabulary(name: str) -> str:
    """Where a public tokenizer file lies on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)
