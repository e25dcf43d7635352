import random

import numpy as np
from test_operators import groups

from ebbset.llm import jaccard

M = jaccard.Measure(4, 85, 100)


def test_links_between_members_of_different_stars(spark):
    """Arcs of repeated phrases: h takes a, p takes b, and only a and b link the two."""
    r, rows = random.Random(3), []
    for i in range(300):
        phrase = [f"x{r.randrange(10**9)}" for _ in range(8)]
        arc = lambda low, n: " ".join(phrase[j % 8] for j in range(low, low + n + 3))  # noqa: E731, B023
        rows += [(4 * i, arc(2, 6)), (4 * i + 1, arc(3, 7)), (4 * i + 2, arc(1, 7)), (4 * i + 3, arc(1, 8))]
    want = groups(rows[:4], 4, 85)
    assert {c for _, c in want.values()} == {0}
    got = {x.doc_id: x.component_id for x in jaccard.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string"), M).collect()}
    assert got == {i: i // 4 * 4 for i, _ in rows}


def test_group_links_connect_all_that_may_link():
    r = np.random.default_rng(4)
    for _ in range(40):
        n, many = int(r.integers(3, 40)), 64
        flat, at = [np.full(many, 2)], r.integers(0, 2, n)
        for i in range(1, n):
            own = flat[int(r.integers(0, i))].copy()
            own[r.integers(0, many, 3 + 5 * at[i])] += 1
            flat.append(own)
        size = np.array([x.sum() for x in flat])
        counts = jaccard._Counts(np.concatenate(flat).astype(np.uint8), np.arange(n + 1) * many, size, M)
        known = r.integers(0, n, n)

        def connected(links):
            group = known.tolist()  # noqa: B023
            for a, b in links:
                group = [min(group[a], group[b]) if g in (group[a], group[b]) else g for g in group]
            return [[i for i, h in enumerate(group) if h == g] for g in group]

        plain = connected([(a, b) for a in range(n) for b in range(a) if counts.may_link(np.array([a]), np.array([b]))[0]])
        links = jaccard._group_links(counts, np.arange(n), known)
        assert connected(links) == plain and len(links) < len(set(known.tolist()))


def test_pivot_splits_decide(monkeypatch):
    """Regions above the leaf size are split by pivots, without loss, and leaves see a part of the pairs only."""
    r, seen, leaf = np.random.default_rng(5), [], jaccard._leaf

    def counted(sets, rows, *more):
        seen.append(len(rows))
        return leaf(sets, rows, *more)

    monkeypatch.setattr(jaccard, "_leaf", counted)
    sets, own = [], r.integers(0, 2**63, 100, dtype=np.int64).astype(np.uint64)
    for i in range(240):
        own = own.copy()
        own[r.integers(0, 100, 20 if i % 60 == 59 else 1)] = r.integers(0, 2**63)
        sets.append(np.unique(own))
    links = jaccard.join_region(sets, M)
    group = list(range(len(sets)))
    for a, b in links:
        group = [min(group[a], group[b]) if g in (group[a], group[b]) else g for g in group]
    want = list(range(len(sets)))
    for a in range(len(sets)):
        for b in range(a):
            inter = len(np.intersect1d(sets[a], sets[b]))
            if 100 * inter >= 85 * (len(sets[a]) + len(sets[b]) - inter):
                want = [min(want[a], want[b]) if g in (want[a], want[b]) else g for g in want]
    assert group == want and sum(n * n for n in seen) < len(sets) ** 2 and len(seen) != 1


def test_blocks_meet_where_their_first_set_does_not_connect_them(spark, monkeypatch):
    """Chains of links across blocks, copies, different texts under one id."""
    monkeypatch.setattr(jaccard, "BLOCK_ROWS", 4)
    r, rows = random.Random(8), []
    for c in range(12):
        words = [f"c{c}w{r.randrange(10**9)}" for _ in range(40)]
        for k in range(25):
            rows.append((len(rows), " ".join(words)))
            words[r.randrange(40)] = f"n{r.randrange(10**9)}"
    rows += [(i + 1000, rows[i][1]) for i in range(0, 300, 7)] + [(900, None), (901, ""), (902, "a b")]
    want = groups(rows, 4, 85)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in jaccard.jaccard_components(docs, M).collect()}
    assert got == want
    two = spark.createDataFrame([(1, rows[0][1]), (5, rows[0][1]), (5, rows[40][1]), (7, rows[40][1])], "doc_id long, text string")
    assert {x.doc_id: x.component_id for x in jaccard.jaccard_components(two, M).collect()} == {1: 1, 5: 1, 7: 1}
