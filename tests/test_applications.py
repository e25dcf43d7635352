import itertools

import numpy as np

from ebbset.operators import applications as A

BLOCKS = np.array([[0, 0.1, 0.9, 0.8], [0.1, 0, 0.85, 0.9], [0.9, 0.85, 0, 0.2], [0.8, 0.9, 0.2, 0]])


def test_map_lowers_stress_and_parts_blocks():
    x = A.mds_2d(BLOCKS)
    assert A.stress(BLOCKS, x) <= A.stress(BLOCKS, A.mds_2d(BLOCKS, rounds=0)) + 1e-12
    assert np.linalg.norm(x[0] - x[1]) < np.linalg.norm(x[0] - x[2])


def test_trees():
    for linkage in ("single", "complete", "average"):
        assert A.cut(A.hierarchical(BLOCKS, linkage), 4, 0.5) == [0, 0, 2, 2]
    joins = A.neighbour_joining(BLOCKS)
    assert {frozenset(j[:2]) for j in joins} & {frozenset((0, 1)), frozenset((2, 3))}


def test_leaf_order_is_the_best_the_tree_allows():
    r = np.random.default_rng(1)
    d = r.random((7, 7))
    d = (d + d.T) / 2
    np.fill_diagonal(d, 0)
    tree = A.hierarchical(d, "average")

    def turns(node):
        if node < 7:
            return [[node]]
        a, b = tree[node - 7][:2]
        return [x + y for u, v in ((a, b), (b, a)) for x, y in itertools.product(turns(u), turns(v))]

    cost = lambda o: sum(d[a, b] for a, b in zip(o[:-1], o[1:], strict=True))
    assert abs(cost(A.leaf_order(tree, d)) - min(map(cost, turns(12)))) < 1e-12
