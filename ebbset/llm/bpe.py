"""Byte-level BPE in Spark: ranked merges folded by higher-order functions over distinct words.

Words are the matches of the splitting pattern. A word's bytes become one character a token; each step of merges() looks
the neighbouring pairs up in a rank map and replaces every place of the pair of least rank, until no pair has a
rank. The ranks are an array of small maps found by a hash of the key, since one large map would be searched from end
to end. They come from a scalar subquery: as a literal they stood in every description of a plan that the driver makes,
some MB each time. Replacing all places at once keeps a long word to as many steps as it has distinct merges.

Each distinct word is folded once a task, not once an occurrence: a task's rows name their words by numbers, and a word
travels with the first row that has it. After about WORDS words a task begins anew, which bounds its memory. Words that
most parts of the corpus have are folded once for all: they are broadcast with their tokens, COMMON bytes of them at
most, so that the fold's work grows with the words and not with the tasks. Decoding concatenates the tokens' binary pieces, word by word in Spark, and the words'
bytes by row on Arrow batches.

Defined results: null text counts as empty and gives no ids; repeated rows are encoded alike; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ebbset.llm._spark import written
from ebbset.llm._text import list_array, pieces
from ebbset.llm.tokens import byte_ranks, gather, split_pieces, vocabulary

#: A task numbers about so many distinct words before it begins anew.
WORDS = 300_000
#: Bytes of words that are folded beforehand and broadcast, and of text that a task splits at a time.
COMMON, CHUNK = 4 << 20, 1 << 20
#: Words whose tokens are put together at a time (or those of one document).
GATHER = 200_000
#: Rows an Arrow batch, as rows hold whole texts' words.
ROWS = 2000
SLOTS = 1 << 16
#: A token's character is its id plus this, past the surrogates from there on.
FIRST, SURROGATES, GAP = 256, 0xD800, 2048


def letter(token: int) -> str:
    at = token + FIRST
    return chr(at if at < SURROGATES else at + GAP)


def _token(char: Column) -> Column:
    at = F.ascii(char)
    return F.when(at < SURROGATES, at - FIRST).otherwise(at - FIRST - GAP)


def rank_slots(ranks: dict[bytes, int]) -> list[dict[str, str]]:
    """Every pair of tokens that is a token: maps from pairs to tokens, dealt by the pairs' hashes."""
    slots: list[dict[str, str]] = [{} for _ in range(SLOTS)]
    for whole, rank in ranks.items():
        for cut in range(1, len(whole)):
            left, right = ranks.get(whole[:cut]), ranks.get(whole[cut:])
            if left is not None and right is not None:
                pair = letter(left) + letter(right)
                slots[xxhash.xxh64_intdigest(pair.encode(), 42) & (SLOTS - 1)][pair] = letter(rank)
    return slots


def tables(spark: SparkSession, ranks: dict[bytes, int]) -> DataFrame:
    """One row: slots (rank_slots) and pieces (the bytes of each id, in hex)."""
    pieces = [""] * (max(ranks.values()) + 1)
    for token, rank in ranks.items():
        pieces[rank] = token.hex()

    def build() -> DataFrame:
        row = [json.dumps(x, separators=(",", ":")) for x in (rank_slots(ranks), pieces)]
        texts = spark.createDataFrame([row], "slots string, pieces string")
        return texts.select(F.from_json("slots", "array<map<string,string>>").alias("slots"), F.from_json("pieces", "array<string>").alias("pieces"))

    return written(build, "ranks")


def _let(value: Column, use) -> Column:
    """use(value), with the value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _beside(df: DataFrame, held: DataFrame, name: str) -> DataFrame:
    """The rows with one of the tables as a column to be used once: Spark then puts the subquery in its place, which may
    not be written inside a higher-order function, and no row carries it."""
    return df.select("*", held.select(name).scalar().alias(name))


def merges(word: Column, ranks: dict[bytes, int], table: Column) -> Column:
    """A binary word of at least one byte as a string of its tokens' characters; table: the slots of tables()."""
    single = "".join(letter(ranks[bytes([b])]) for b in range(256))
    start = F.translate(F.decode(word, "ISO-8859-1"), "".join(map(chr, range(256))), single)

    def merged(pair: Column) -> Column:
        return F.try_element_at(F.get(table, F.xxhash64(pair).bitwiseAND(F.lit(SLOTS - 1)).cast("int")), pair)

    def state(text: Column, more: bool) -> Column:
        return F.struct(text.alias("text"), F.lit(more).alias("more"))

    def replaced(now: Column, pairs: Column, tokens: Column) -> Column:
        least = F.array_min(tokens)
        pair = F.get(pairs, F.array_position(tokens, least).cast("int") - 1)
        return F.when(least.isNull(), state(now["text"], False)).otherwise(state(F.replace(now["text"], pair, least), True))

    def step(now: Column, _: Column) -> Column:
        chars = F.split(now["text"], "")
        pairs = F.zip_with(chars, F.slice(chars, F.lit(2), F.greatest(F.size(chars) - 1, F.lit(0))), lambda a, b: F.concat(a, b))
        return F.when(~now["more"], now).otherwise(_let(pairs, lambda p: _let(F.transform(p, merged), lambda t: replaced(now, p, t))))

    steps = F.sequence(F.lit(1), F.octet_length(word))
    return F.aggregate(steps, state(start, True), step, lambda s: s["text"])


def tokens_of(folded: Column) -> Column:
    """Ids of a folded word."""
    return F.transform(F.split(folded, ""), _token)


def decoded(ids: Column, table: Column) -> Column:
    """The bytes of an array of ids: their pieces end to end; table: the pieces of tables()."""
    return F.unhex(F.array_join(F.transform(ids, lambda i: F.get(table, i)), ""))


def _plain(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def _distinct(batches):
    for batch in batches:
        for part in pieces(batch):
            words = split_pieces(part.column("text"))[0].unique()
            yield pa.RecordBatch.from_arrays([words], ["word"])


def common(docs: DataFrame, ranks: dict[bytes, int], held: DataFrame, most: int = COMMON) -> pa.Table:
    """word, ids, texts of the words that the most stretches of a few MB have, about `most` bytes of them at most."""
    level = F.floor(F.log2(F.count("*")) * 8).cast("int")
    counts = written(lambda: _plain(docs).mapInArrow(_distinct, "word binary").groupBy("word").agg(level.alias("level")).where("level > 0"), "word-counts")
    sizes = counts.groupBy("level").agg(F.sum(F.octet_length("word")).alias("n")).collect()  # some hundred rows
    share, left = {}, most
    for r in sorted(sizes, key=lambda r: -r.level):
        share[r.level] = min(1.0, left / max(1, r.n))
        left = max(0, left - r.n)
    part = F.create_map(*[F.lit(x) for pair in share.items() for x in pair]) if share else F.create_map(F.lit(0), F.lit(0.0))
    chosen = counts.where(F.pmod(F.xxhash64("word"), F.lit(1 << 20)) < F.element_at(part, F.col("level")) * (1 << 20))
    folded = _beside(chosen, held, "slots").select("word", tokens_of(merges(F.col("word"), ranks, F.col("slots"))).alias("ids"))
    return _beside(folded, held, "pieces").select("word", "ids", decoded(F.col("ids"), F.col("pieces")).alias("texts")).toArrow()


def _numbered(batches, words, most: int):
    """Each row's words as numbers, with the words that neither the common ones nor a row before it have; `anew` where
    the numbers begin after the common ones again."""
    fixed = words.value
    known, anew = fixed, True
    for batch in batches:
        for part in pieces(batch, most=CHUNK):
            if len(known) > len(fixed) + most:
                known, anew = fixed, True
            found, first = split_pieces(part.column("text"))
            coded = found.dictionary_encode()
            place = np.asarray(pc.fill_null(pc.index_in(coded.dictionary, value_set=known), -1)).astype(np.int64)
            fresh = place < 0
            place[fresh] = len(known) + np.arange(int(fresh.sum()))
            number = np.asarray(coded.indices)
            # words are numbered as they appear, so a row's new ones are a stretch
            opening = np.unique(number, return_index=True)[1][fresh]
            begin = np.searchsorted(opening, first).astype(np.int32)
            reset = np.zeros(len(part), bool)
            reset[:1], anew = anew, False
            new = coded.dictionary.filter(pa.array(fresh))
            known = pa.concat_arrays([known, new])
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), list_array(place[number].astype(np.int32), first, pa.int32()), pa.ListArray.from_arrays(pa.array(begin), new), pa.array(reset)],
                ["doc_id", "codes", "fresh", "anew"],
            )


class _Words:
    """Lists of numbers that grow in place."""

    def __init__(self, kind):
        self.flat, self.ends, self.n, self.used = np.zeros(1 << 16, kind), np.zeros(1 << 12, np.int64), 0, 0

    def cut(self, n: int) -> None:
        self.n, self.used = n, int(self.ends[n - 1]) if n else 0

    def add(self, size: np.ndarray, flat: np.ndarray) -> None:
        while self.used + len(flat) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        while self.n + len(size) > len(self.ends):
            self.ends = np.concatenate([self.ends, np.zeros_like(self.ends)])
        self.flat[self.used : self.used + len(flat)] = flat
        self.ends[self.n : self.n + len(size)] = self.used + np.cumsum(size)
        self.n, self.used = self.n + len(size), self.used + len(flat)

    def take(self, index: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return gather(np.diff(self.ends[: self.n], prepend=0), self.flat, index, first)


def _joined(batches, words):
    """Ids of each row and the bytes they decode to, from the common words and those seen so far."""
    ids, texts = _Words(np.int32), _Words(np.uint8)
    sizes, flat, lengths, raws = words.value
    ids.add(sizes, flat)
    texts.add(lengths, raws)
    for batch in batches:
        cut = np.flatnonzero(np.asarray(batch.column("anew")))
        for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(batch)], strict=True):
            if a == b:
                continue
            part = batch.slice(a, b - a)
            if part.column("anew")[0].as_py():
                ids.cut(len(sizes))
                texts.cut(len(sizes))
            lists, raw = part.column("ids").flatten(), part.column("texts").flatten()
            ids.add(np.asarray(pc.list_value_length(lists), np.int64), np.asarray(lists.flatten()))
            texts.add(np.asarray(pc.binary_length(raw), np.int64), np.frombuffer(b"".join(raw.to_pylist()), np.uint8))
            ends = np.cumsum(np.asarray(part.column("codes").value_lengths()))
            lo = 0
            while lo < len(part):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + GATHER, side="right")))
                yield _gathered(part.slice(lo, hi - lo), ids, texts)
                lo = hi


def _gathered(part: pa.RecordBatch, ids: _Words, texts: _Words) -> pa.RecordBatch:
    codes = part.column("codes")
    index = np.asarray(codes.flatten()).astype(np.int64)
    first = np.concatenate([[0], np.cumsum(np.asarray(codes.value_lengths()))]).astype(np.int64)
    found, ends = ids.take(index, first)
    back, bounds = texts.take(index, first)
    raw = pa.Array.from_buffers(pa.binary(), len(part), [None, pa.py_buffer(bounds.astype(np.int32).tobytes()), pa.py_buffer(back.tobytes())])
    return pa.RecordBatch.from_arrays([part.column("doc_id"), list_array(found, ends, pa.int32()), raw], ["doc_id", "ids", "decoded"])


def _folded(docs: DataFrame, path: str | None, words: int, most: int) -> tuple[DataFrame, Broadcast]:
    """Rows of word numbers with the folded words that each adds, and the common words' tokens."""
    ranks = byte_ranks(path or vocabulary("byte_bpe_50k.tiktoken"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    held_ranks = tables(docs.sparkSession, ranks)
    table = common(docs, ranks, held_ranks, most).combine_chunks()
    word, lists, texts = (pa.concat_arrays(table.column(c).chunks) if table.num_rows else None for c in ("word", "ids", "texts"))
    none = np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.uint8)
    held = pa.array([], pa.binary()), none
    if word is not None:
        sizes = np.asarray(lists.value_lengths(), np.int64), np.asarray(pc.binary_length(texts), np.int64)
        held = word.cast(pa.binary()), (sizes[0], np.asarray(lists.flatten()).astype(np.int32), sizes[1], np.frombuffer(b"".join(texts.to_pylist()), np.uint8))
    names, shared = map(docs.sparkSession.sparkContext.broadcast, held)
    rows = _plain(docs).mapInArrow(partial(_numbered, words=names, most=words), f"doc_id {kind}, codes array<int>, fresh array<binary>, anew boolean")
    ids = F.transform("fresh", lambda w: tokens_of(merges(w, ranks, F.col("slots"))))
    rows = _beside(rows, held_ranks, "slots").select("doc_id", "codes", "anew", ids.alias("ids"))
    texts = F.transform("ids", lambda i: decoded(i, F.col("pieces")))
    return _beside(rows, held_ranks, "pieces").select("doc_id", "codes", "anew", "ids", texts.alias("texts")), shared


def encode(docs: DataFrame, path: str | None = None, words: int = WORDS, most: int = COMMON) -> DataFrame:
    """doc_id, ids (array) and decoded (binary) of each row. path: the file of ranks."""
    rows, shared = _folded(docs, path, words, most)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(partial(_joined, words=shared), f"doc_id {kind}, ids array<int>, decoded binary")


def _digests(batches, words):
    """Sums of what _joined gives, in the same Python process, so that ids and bytes don't pass through Spark again."""
    for batch in _joined(batches, words):
        ids = batch.column("ids")
        at, flat = np.asarray(ids.offsets), np.asarray(ids.values).astype("<u4")
        sums = [hashlib.sha256(flat[a:b].tobytes()).hexdigest() for a, b in zip(at[:-1], at[1:], strict=True)]
        back = [hashlib.sha256(x).hexdigest() for x in batch.column("decoded").to_pylist()]
        cols = [batch.column("doc_id"), pa.array(np.diff(at).astype(np.int64)), pa.array(sums, pa.string()), pa.array(back, pa.string())]
        yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def digest(docs: DataFrame) -> DataFrame:
    kind = docs.schema["doc_id"].dataType.simpleString()
    shape = f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string"

    def build() -> DataFrame:
        rows, shared = _folded(docs, None, WORDS, COMMON)
        return rows.mapInArrow(partial(_digests, words=shared), shape)

    return written(build, "digests", batch=ROWS)
