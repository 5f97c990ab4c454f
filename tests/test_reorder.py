"""Orderings against exhaustive search, and the closed forms of the size table."""

import itertools
from collections import Counter

import numpy as np
import pytest

from symmat.operators import measure, reorder
from tests.test_kernel import MATRIX


def edges(m, seed):
    rng = np.random.default_rng(seed)
    return [(i, j, float(w)) for (i, j) in itertools.combinations(range(m), 2) if (w := rng.integers(0, 10) / 10) > 0]


def test_repetitions_of_the_worked_matrix():
    got = {(a + 1, b + 1): round(w * 6) for a, b, w in reorder.local_edges(*np.nonzero(MATRIX), MATRIX[MATRIX != 0], 6, 5)}
    assert got == {(1, 2): 2, (1, 3): 2, (1, 4): 2, (2, 3): 1, (2, 4): 1, (3, 4): 3, (3, 5): 1}


@pytest.mark.parametrize("seed", range(4))
def test_orderings_are_permutations_and_matching_is_best(seed):
    m = 6
    e = edges(m, seed)
    w = {(a, b): x for a, b, x in e}
    for name, f in reorder.ALGORITHMS.items():
        assert sorted(f(e, m)) == list(range(m)), name
    cost = np.zeros((m, m))
    for (a, b), x in w.items():
        cost[a, b] = -x
    best = min(sum(cost[i, p[i]] for i in range(m)) for p in itertools.permutations(range(m)))
    assert cost[np.arange(m), reorder.assignment(cost)].sum() == pytest.approx(best)
    top = max(reorder.order_score(list(p), e) for p in itertools.permutations(range(m)))
    found = reorder.order_score(reorder.tour(e, m), e)
    assert reorder.order_score(reorder.paths(e, m), e) - 1e-9 <= found <= top + 1e-9 and found >= 0.9 * top


def best_path(e, m):
    """The largest score of any order, by subsets and ends."""
    w = np.zeros((m, m))
    for a, b, x in e:
        w[a, b] = w[b, a] = x
    best = np.full((1 << m, m), -1.0)
    best[1 << np.arange(m), np.arange(m)] = 0
    for s in range(1 << m):
        for a in range(m):
            if best[s, a] >= 0:
                for b in range(m):
                    if not s >> b & 1:
                        best[s | 1 << b, b] = max(best[s | 1 << b, b], best[s, a] + w[a, b])
    return best[-1].max()


@pytest.mark.parametrize("seed", range(3))
def test_tours_are_near_the_best_of_ten_columns(seed):
    e = edges(10, 20 + seed)
    found = reorder.order_score(reorder.tour(e, 10), e)
    assert found >= 0.97 * best_path(e, 10) and found >= reorder.order_score(reorder.paths(e, 10), e) - 1e-9


@pytest.mark.parametrize("seed", range(4))
def test_path_covers_take_the_heaviest_edge_that_fits(seed):
    m, e = 9, edges(9, 40 + seed)
    kept = []
    for a, b, w in sorted(e, key=lambda x: (-x[2], x[0], x[1])):  # with a plain search for circles
        near = lambda c: [y if x == c else x for x, y in kept if c in (x, y)]
        seen, todo = {a}, [a]
        while todo:
            for c in near(todo.pop()):
                if c not in seen:
                    seen.add(c)
                    todo.append(c)
        if len(near(a)) < 2 and len(near(b)) < 2 and b not in seen:
            kept.append((a, b))
    assert reorder.path_links(e, m) == kept
    order = reorder.paths(e, m)
    assert all(abs(order.index(a) - order.index(b)) == 1 for a, b in kept)


def test_coalesced_paths_join_by_the_least_weight():
    # 0-1 is heaviest; the path 0-1 then weighs min(w02, w12) = 0.2 to 2, so 2-3 comes first
    e = [(0, 1, 0.9), (0, 2, 0.2), (1, 2, 0.8), (2, 3, 0.5), (0, 3, 0.1), (1, 3, 0.1)]
    order = reorder.paths_coalesced(e, 4)
    assert abs(order.index(0) - order.index(1)) == 1 and abs(order.index(2) - order.index(3)) == 1
    assert reorder.path_links(e, 4) == [(0, 1), (1, 2), (2, 3)]


def test_similarity_of_two_columns_of_the_worked_matrix():
    found = {(a + 1, b + 1): w for a, b, w in reorder.local_edges(*np.nonzero(MATRIX), MATRIX[MATRIX != 0], 6, 5)}
    assert found[2, 4] == pytest.approx(1 / 6)


def test_local_scores_in_portions(monkeypatch):
    x = np.random.default_rng(7).integers(0, 3, (300, 8)).astype(float)
    args = (*np.nonzero(x), x[x != 0], 300, 8)
    want = reorder.local_edges(*args)
    for i, j, w in want:
        both = [(a, b) for a, b in zip(x[:, i], x[:, j]) if a and b]
        assert w * 300 == pytest.approx(len(both) - len(set(both)))
    monkeypatch.setattr(reorder, "PORTION", 50)
    assert reorder.local_edges(*args) == want


# Rows, columns, nonzero percent, distinct nonzeros, stream percent of the seven published matrices.
TABLE = [
    (5_000_000, 18, 98.82, 20_352_142, 74.80), (11_000_000, 28, 92.11, 8_083_943, 50.46), (14_462_943, 29, 72.66, 7_794, 38.06), (581_012, 54, 22.00, 6_682, 11.95),
    (2_458_285, 68, 43.03, 45, 22.25), (325_834, 174, 97.50, 897_176, 50.62), (2_000_000, 784, 25.25, 255, 12.69),
]


@pytest.mark.parametrize("n,m,pct,distinct,want", TABLE)
def test_stream_size_in_closed_form(n, m, pct, distinct, want):
    assert measure.stream_pct(n, m, round(n * m * pct / 100), distinct) == pytest.approx(want, abs=0.011)


@pytest.mark.parametrize("m,share", [(6, 0.8), (200, 0.02)])
def test_pair_counts_are_those_of_all_pairs(m, share):
    rng = np.random.default_rng(4)
    x = rng.integers(1, 4, (300, m)) * (rng.random((300, m)) < share)
    x[:, 2] = rng.permutation(300) + 1  # many values: pairs are sorted
    row, col = np.nonzero(x)
    want = Counter((i, j, r[i], r[j]) for r in x.tolist() for i, j in itertools.combinations(range(m), 2) if r[i] and r[j])
    got = {(i, j, a, b): c for i, j, vi, vj, n in reorder.pair_counts(row, col, x[row, col].astype(float), 300, m) for a, b, c in zip(vi, vj, n)}
    assert got == want
