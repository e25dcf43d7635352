import hashlib
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from conftest import SF

from ebbset.llm import bpe, chaining, fingerprint, jaccard, langid, mtree, packing, pii, queries, suffix, tokenfile, tokens
from ebbset.llm._spark import components

SPACE = r"[^\x20\x09-\x0D]+"
SCHEMA = "doc_id long, text string, lang string, node int, seed int, part int, region int, words int, spans int, key int"


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)


def words(t):
    return re.findall(SPACE, lower(t or ""))


@pytest.fixture(scope="module")
def rows():
    r = random.Random(4)
    lex = [f"w{i}" for i in range(400)]
    para = [r.choice(lex) for _ in range(70)]
    out = []
    for i in range(24):
        own = [r.choice(lex) for _ in range(150 if i == 5 else r.randint(1, 200))]
        if i % 3 == 0:
            at = r.randint(0, len(own))
            own[at:at] = para if i % 2 else [w if r.random() > 0.05 else "x" for w in para]
        out.append((i, " ".join(own)))
    out += [(30 + i, out[5][1]) for i in range(4)]
    for i in range(6):
        own = out[6][1].split(" ")
        own[r.randrange(len(own))] = f"e{i}"
        out.append((40 + i, " ".join(own)))
    out += [(50, None), (51, ""), (52, "  \n"), (53, "a"), (54, "é" * 60 + "🎉" + "é" * 60), (55, "é" * 60), (56, "a" * 4000), (57, "b" + "a" * 300), (58, "it's 1234 <|endoftext|> we'll\n\n  x"), (59, "one two three four")]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    """Columns whose names the operators use themselves come along."""
    return spark.createDataFrame([(i, t, "en", 1, 2, 3, 4, 5, 6, 7) for i, t in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


def test_components(spark):
    e = spark.createDataFrame([(5, 3), (3, 9), (2, 2), (7, 8), (8, 1), (1, 6)], "a long, b long")
    assert dict(map(tuple, components(lambda: e).collect())) == {3: 3, 5: 3, 9: 3, 2: 2, 1: 1, 6: 1, 7: 1, 8: 1}


def groups(rows, width, low):
    sets, up = {}, {}
    for i, t in rows:
        w = words(t)
        sets[i] = {tuple(w[j : j + width]) for j in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
        up[i] = i

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= low * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in sets}


@pytest.mark.parametrize(("width", "low"), [(4, 85), (5, 80), (2, 30)])
def test_jaccard_join(docs, none, rows, width, low):
    m = jaccard.Measure(width, low, 100)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.jaccard_components(docs, m).collect()}
    assert got == groups(rows, width, low)
    kept = {r.doc_id for r in jaccard.keep_first(docs, m).collect()}
    assert kept == {i for i, (_, c) in groups(rows, width, low).items() if i == c}
    assert jaccard.jaccard_components(none, m).count() == 0


def test_region_join_splits_exactly():
    r = np.random.default_rng(2)
    base = r.integers(0, 2**60, (6, 120)).astype(np.uint64)
    sets = []
    for k in range(600):
        own = base[k % 6].copy()
        swap = r.random(120) < r.choice([0.02, 0.06, 0.12])
        own[swap] = r.integers(0, 2**60, swap.sum())
        sets.append(np.unique(own))
    m = jaccard.Measure(4, 85, 100)
    up = list(range(600))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    def merge(links):
        for a, b in links:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
        return [root(i) for i in range(600)]

    got = merge(jaccard.join_region(sets, m))
    up = list(range(600))
    plain = [(a, b) for a in range(600) for b in range(a) if 100 * len(np.intersect1d(sets[a], sets[b])) >= 85 * len(np.union1d(sets[a], sets[b]))]
    assert got == merge(plain)


def test_suffix_windows(docs, none, rows):
    low = {}
    for i, t in sorted(rows):
        b = (t or "").encode()
        for s in range(len(b) - 49):
            low.setdefault(b[s : s + 50], i)
    got = {r.doc_id: r for r in suffix.digest(docs).collect()}
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for s in range(len(b) - 49):
            if low[b[s : s + 50]] < i:
                gone[s : s + 50] = True
        kept = bytes(np.frombuffer(b, np.uint8)[~gone])
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        r = got[i]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(b), gone.sum(), spans, hashlib.sha256(kept).hexdigest()), i
    assert suffix.digest(none).count() == 0


def test_chained_passages(docs, none, rows):
    text = dict(rows)
    found = chaining.passages(docs).collect()
    hit = {r.doc_id for r in found}
    assert {3, 6, 9, 12, 15, 18, 21} <= hit  # the planted passage, exact or with words changed, after its first place
    assert {31, 32, 33, *range(40, 46)} <= hit
    assert not hit & {1, 2, 4, 7, 8}
    for r in found:
        assert r.ref_id < r.doc_id and r.n_equal >= 0.8 * r.n_words >= 40
        assert len(words(text[r.doc_id][r.start : r.end])) == r.n_words
    cut = {r.doc_id: r for r in chaining.cut_repeats(docs).collect()}
    assert len(cut) == len(rows) and all(cut[i].text == text[i] for i in text if i not in hit)
    assert chaining.passages(none).count() == 0


def test_chain_against_all_orders():
    r = random.Random(1)
    for _ in range(30):
        n = r.randint(1, 12)
        at, to = np.array([r.randint(0, 60) for _ in range(n)]), np.array([r.randint(0, 60) for _ in range(n)])
        gap, order = 1 / 64, np.argsort(at)
        best = {}
        for i in order:
            best[i] = 1 + max([0, *(best[j] - gap * (at[i] - at[j] + to[i] - to[j]) for j in best if at[j] < at[i] and to[j] < to[i])])
        top = chaining.chain(at, to, gap)[0]
        score = len(top) - gap * (at[top[-1]] - at[top[0]] + to[top[-1]] - to[top[0]])
        assert abs(score - max(best.values())) < 1e-9


def test_language(spark, none, docs):
    d = spark.read.parquet(f"{SF}/documents.parquet")
    own = {r.doc_id: r for r in langid.digest(d).collect()}
    held = [r for r in d.select("doc_id", "lang").collect() if own[r.doc_id].held_out]
    assert sum(own[r.doc_id].lang_pred == r.lang for r in held) >= 0.97 * len(held)
    assert all((zlib.crc32(str(i).encode()) % 3 == 1) == r.held_out for i, r in own.items())
    got = {r.doc_id: r for r in langid.digest(docs).collect()}
    assert got[50].lang_pred == got[51].lang_pred == got[52].lang_pred == "und" and got[53].lang_pred == "en"
    assert all(0 <= r.score <= 1 for r in got.values())
    assert langid.digest(none).count() == 0
    assert {r.doc_id for r in langid.keep_known(docs).collect()} >= {0, 1, 2} and langid.keep_known(docs).columns == docs.columns


def test_code_lengths_are_those_of_the_trees():
    words_ = pa.array([b"ab", b"abc", b"zz"], pa.binary())
    lang, key, n = [], [], []
    for name, own in (("p", [b"ab", b"ab", b"abd"]), ("q", [b"zz"])):
        counts = defaultdict(int)
        last, deep, _ = langid.symbols(pa.array(own, pa.binary()))
        for x, k in zip(last, deep, strict=True):
            for order in range(min(int(k), langid.ORDER) + 1):
                counts[int(langid.gram(np.array([x]), order)[0])] += 1
        for g, c in counts.items():
            lang.append(name), key.append(g), n.append(c)
    trees = langid.Trees.frozen(np.array(lang, object), np.array(key, np.uint64), np.array(n))

    def plain(word, name):
        table = defaultdict(dict)
        for w, g, c in zip(lang, key, n, strict=True):
            if w == name:
                table[int(langid.context(np.array([g], np.uint64))[0])][g & 255] = c
        s, bits = b" " + word + b" ", 0.0
        for i in range(1, len(s)):
            for order in range(min(i, langid.ORDER), -1, -1):
                ctx = (int.from_bytes(s[i - order : i], "big") if order else 0) | order << 48
                own = table.get(ctx)
                if not own:
                    continue
                total, kinds = sum(own.values()), len(own)
                if s[i] in own:
                    bits += np.log2((total + kinds) / own[s[i]])
                    break
                bits += np.log2((total + kinds) / kinds)
            else:
                bits += 8
        return bits

    got = trees.lengths(words_)
    for i, w in enumerate((b"ab", b"abc", b"zz")):
        for j, name in enumerate(trees.langs):
            assert abs(got[i, j] - plain(w, name)) < 1e-3


def test_fingerprints(docs, none, rows):
    got = {r.doc_id: r for r in fingerprint.neighbours(docs).collect()}
    order = sorted(((i, t or "") for i, t in rows), reverse=True)
    for n, (i, t) in enumerate(order):
        following = order[(n + 1) % len(order)][1]
        half = len(t) // 2
        e = t[: len(t) - half] + following[:half]
        assert (got[i].n_chars, got[i].edited_sha256) == (len(t), hashlib.sha256(e.encode()).hexdigest())
    assert got[30].fingerprint == got[31].fingerprint and got[31].near_next == 1.0
    assert fingerprint.neighbours(none).count() == 0
    assert len(fingerprint.fingerprints(docs).collect()) == len(rows)


def test_sketch_estimates():
    r = np.random.default_rng(3)
    a, b = np.unique(r.integers(0, 2**64, 4000, np.uint64)), np.unique(r.integers(0, 2**64, 2000, np.uint64))
    x, y = np.unique(np.concatenate([a, b])), a
    sx, sy = fingerprint.sketch(x, 256), fingerprint.sketch(y, 256)
    assert abs(fingerprint.resemblance(sx, sy, 256) - 2 / 3) < 0.12
    assert fingerprint.containment(sy, sx, 256) > 0.9 and abs(fingerprint.containment(sx, sy, 256) - 2 / 3) < 0.15
    assert abs(fingerprint.distinct(sx, 256) - 6000) < 1200
    assert (fingerprint.merged(sy, fingerprint.sketch(b, 256), 256) == sx).all()
    assert (fingerprint.decoded(fingerprint.encoded(sx)) == sx).all()


def library(name):
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path(name))


def test_pieces_and_ids_equal_the_libraries(rows):
    import public_tokenizers
    import regex
    import tiktoken

    r = random.Random(9)
    alphabet = ["a", "b", "'s", "'", "'re", "'ve", "ll", " ", "  ", "\n", "\t", "1", "²", "é", "漢", "!", "?", "'l", "r", " ", " ", "😀"]
    texts = ["".join(r.choice(alphabet) for _ in range(r.randint(0, 14))) for _ in range(3000)] + [t or "" for _, t in rows]
    found, first = tokens.split_pieces(pa.array(texts))
    got = [p.decode() for p in found.to_pylist()]
    assert all(got[first[i] : first[i + 1]] == regex.findall(public_tokenizers.PATTERN, t) for i, t in enumerate(texts))
    encoder = tokens.PieceEncoder(tokens.vocabulary("byte_bpe_50k.json"))
    ids, at = encoder.encode(pa.array(texts))
    want = library("byte_bpe_50k.json").encode_batch(texts, add_special_tokens=False)
    assert all(ids[at[i] : at[i + 1]].tolist() == e.ids for i, e in enumerate(want))
    ranks = tokens.byte_ranks(tokens.vocabulary("byte_bpe_50k.tiktoken"))
    assert ranks == encoder.ranks
    t = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    assert all(ids[at[i] : at[i + 1]].tolist() == t.encode_ordinary(x) for i, x in enumerate(texts) if "<|endoftext|>" not in x)


def test_bpe_folds(docs, none, rows):
    import public_tokenizers
    import tiktoken

    ranks = tokens.byte_ranks(tokens.vocabulary("byte_bpe_50k.tiktoken"))
    t = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = {i: t.encode_ordinary(x or "") for i, x in rows}
    got = {r.doc_id: r for r in bpe.digest(docs).collect()}
    for i, t in rows:
        assert got[i].n_tokens == len(want[i])
        assert got[i].ids_sha256 == hashlib.sha256(np.array(want[i], "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert bpe.digest(none).count() == 0


def test_folds_of_few_letters_runs_and_long_words(spark):
    """Overlapping places, runs, long words, and tasks that begin anew; a special token's text is ordinary text."""
    import public_tokenizers
    import tiktoken

    r = random.Random(4)
    texts = ["".join(r.choice("aab=-_") for _ in range(r.randint(1, 24))) for _ in range(600)]
    texts += ["=" * n for n in (1, 2, 3, 63, 64, 65, 1000)] + ["a" * 20_000, "".join(r.choice("etaoin") for _ in range(3000)), "x<|endoftext|>y", "é漢😀" * 30, None, ""]
    ranks = tokens.byte_ranks(tokens.vocabulary("byte_bpe_50k.tiktoken"))
    t = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    docs = docs.union(docs.selectExpr("doc_id + 1000", "text"))
    texts += [None] * (1000 - len(texts)) + texts
    for words, most in ((bpe.WORDS, bpe.COMMON), (20, 100), (20, 0)):
        got = {x.doc_id: x for x in bpe.encode(docs, words=words, most=most).collect()}
        for i, x in enumerate(texts):
            assert i not in got or got[i].ids == t.encode_ordinary(x or "") and bytes(got[i].decoded) == (x or "").encode()
        assert len(got) == docs.count()


def test_token_files(spark, docs, none, rows, tmp_path):
    t, at = library("byte_bpe_50k.json"), 0
    got = {r.doc_id: r for r in tokenfile.round_trip(docs).collect()}
    for i, text in sorted(rows):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    assert tokenfile.round_trip(none).count() == 0
    tokenfile.write_tokens(docs, str(tmp_path / "t"))
    some = tokenfile.read_tokens(spark, str(tmp_path / "t"), ["doc_id", "n_tokens"], 5, 9)
    assert sorted(r.doc_id for r in some.collect()) == [5, 6, 7, 8, 9]
    plan = some._jdf.queryExecution().toString()
    assert "GreaterThanOrEqual(doc_id,5)" in plan and "ids" not in plan.split("ReadSchema")[1].split("\n")[0]


def test_packing(docs, none, rows):
    t = library("byte_bpe_50k.json")
    found = packing.pack(docs).collect()
    seq, own = defaultdict(list), defaultdict(list)
    for r in found:
        ids = [*t.encode(dict(rows)[r.doc_id] or "", add_special_tokens=False).ids, 0]
        assert r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes())
        seq[r.sequence_id].append((r.offset, r.length))
        own[r.doc_id].append((r.start, r.length, r.doc_tokens))
    for parts in seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024 and at & (at - 1) == 0  # nothing is padded
    for parts in own.values():
        at = 0
        for start, length, total in sorted(parts):
            assert start == at
            at += length
        assert at == total
    assert len(own) == len(rows) and packing.pack(none).count() == 0


def test_level_choice_is_the_least_sum_of_squares():
    r = random.Random(5)
    p = packing.LevelPacker(32)
    for _ in range(400):
        size = r.randint(1, 31)
        before = p.count.copy()

        def after(level, size=size, before=before):
            c = before.copy()
            if level:
                c[level] -= 1
            if level + size < 32:
                c[level + size] += 1
            return int((c[1:32] ** 2).sum())

        allowed = [0, *(h for h in range(1, 33 - size) if before[h])]
        assert after(p.level(size)) == min(map(after, allowed))
        p.place(size, None)


@pytest.mark.parametrize("n", [0, 1, 2, 7, 400])
def test_rest_keeps_what_the_rule_filled(n):
    r = random.Random(n)
    p, done, sizes = packing.LevelPacker(64), [], {}
    for i in range(n):
        sizes[i] = r.randint(1, 63)
        done += [(s, at, size, skip, x) for s, own in p.place(sizes[i], i) or [] for at, size, skip, x in own]
    by_rule, held = p.closed, {s: [x for *_, x in own] for s, own in p.held.items()}
    rest = list(p.rest())
    rows = done + rest
    spots, parts = {}, {}
    for s, at, size, skip, x in rows:
        spots.setdefault(s, []).append((at, size))
        parts.setdefault(x, []).append((skip, size))
    for own in spots.values():
        own.sort()
        assert all(a + n == b for (a, n), (b, _) in zip(own[:-1], own[1:], strict=True)) and own[0][0] == 0
        total = sum(n for _, n in own)
        assert total == 64 or total & (total - 1) == 0
    for x, own in parts.items():
        own.sort()
        assert own[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(own[:-1], own[1:], strict=True)) and sum(n for _, n in own) == sizes[x]
    assert set(parts) == set(sizes)
    # most windows that were open at the end stand, in the order in which the rule filled them
    stood = sum([x for t, _, _, _, x in rest if t == s][: len(own)] == own for s, own in held.items())
    assert p.dissolved <= max(1, len(held)) and stood >= len(held) - p.dissolved
    if n == 400:
        assert by_rule > 5 * p.dissolved


def test_top_k(spark, duck):
    got = sorted(map(tuple, queries.op8_mtree_top_k(spark, SF).collect()))
    assert got == sorted(duck.sql(queries.ORACLE["op8_mtree_top_k"]).fetchall())
    odd = [(0, [1.0, 2.0]), (1, [1.0, 2.0]), (2, [1.0, 2.0]), (3, None), (4, [float("nan"), 1.0]), (5, [None, 1.0]), (6, [float("inf"), 1.0]), (50, [-1.0, 0.5])]
    v = spark.createDataFrame([(i, e, 1, 2) for i, e in odd], "vec_id long, embedding array<float>, part int, block int")
    got = [tuple(r) for r in mtree.top_k(v).orderBy("query_id", "rank").collect()]
    s = 256 * 256 * 5
    assert got == [(0, 1, 1, s), (0, 2, 2, s), (0, 3, 50, 0), (50, 1, 0, 0), (50, 2, 1, 0), (50, 3, 2, 0)]
    assert mtree.top_k(v.where("false")).count() == 0


def test_tree_search_is_exact_and_prunes():
    r = np.random.default_rng(7)
    x = (r.normal(size=(3000, 3)) * 100).astype(np.int64)
    tree = mtree.Tree(np.arange(3000), x)
    q, found, score = tree.search(np.arange(0, 3000, 60), x[::60], 5)
    want = x[::60] @ x.T
    for n, i in enumerate(range(0, 3000, 60)):
        best = sorted((-want[n, j], j) for j in range(3000) if j != i)[:5]
        assert sorted(zip(-score[q == n], found[q == n], strict=True)) == best
    assert tree.measured < 0.5 * want.size


BASE = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
]


def passes(kind, m):
    digits = [int(c) for c in m if c.isdigit() and c.isascii()]
    if kind == "ip":
        return all(int(p) <= 255 for p in m.split("."))
    if kind == "card":
        return 14 <= len(digits) <= 19 and sum(d if k % 2 == 0 else d * 2 - 9 * (d > 4) for k, d in enumerate(digits[::-1])) % 10 == 0
    return kind != "phone" or 10 <= len(digits) <= 15


def test_personal_data(spark, docs, none, rows):
    r = random.Random(8)
    parts = ["a@b.c", "_d@e.f", "x.y+z@mail.example.com", "1.2.3.4", "300.1.1.1", "007.0.0.255", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (988) 555-2485", "+49 30 1234567", " ", "é", "😀", ",", "-", "12", "."]
    more = [(100 + i, "".join(r.choice(parts) for _ in range(r.randint(1, 12)))) for i in range(300)] + [(990, "9" * 20000), (991, "a" * 50000 + "@" + "b" * 9000), (992, "1.1." * 3000)]
    every = docs.select("doc_id", "text").union(spark.createDataFrame(more, "doc_id long, text string"))
    got = {x.doc_id: x for x in pii.digest(every).collect()}
    for i, t in [*rows, *(m for m in more if m[0] != 991)]:
        spans = sorted((m.start(), k, n, m.end()) for k, (n, p) in enumerate(BASE) for m in re.finditer(p, t or "") if passes(n, m[0]))
        assert got[i].base_sha256 == hashlib.sha256(",".join(f"{n}:{a}:{b}" for a, _, n, b in spans).encode()).hexdigest(), t
        assert got[i].n_email == sum(s[2] == "email" for s in spans)
    extra = spark.createDataFrame([(1, "Konto DE89 3704 0044 0532 0130 00, not DE88 3704 0044 0532 0130 00; phone 415-555-2671; order 415-555-2671 me@x.org")], "doc_id long, text string")
    row = pii.digest(extra).first()
    assert [s.split(":")[0] for s in row.spans.split(",")] == ["iban", "local_phone", "email"]
    masked = pii.find(extra).select(pii.mask(pii.F.col("text"), pii.F.col("spans"))).first()[0]
    assert masked == "Konto [IBAN], not DE88 3704 0044 0532 0130 00; phone [LOCAL_PHONE]; order 415-555-2671 [EMAIL]"
    assert pii.digest(none).count() == 0


def test_repeated_ids_do_not_crash(spark):
    d = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (1, "x y z"), (None, "n"), (2, None)], "doc_id long, text string")
    assert jaccard.jaccard_components(d, jaccard.Measure()).count() == 4
    assert suffix.digest(d).count() == 4 and chaining.passages(d).count() == 0
    assert fingerprint.neighbours(d).count() == 5 and bpe.digest(d).count() == 5
    assert packing.pack(d).count() >= 5 and tokenfile.round_trip(d).count() == 5 and pii.digest(d).count() == 5
