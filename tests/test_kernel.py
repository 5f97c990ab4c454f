"""Worked examples and invariants of the kernels, without Spark."""

import time

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from symmat.operators import codec
from symmat.operators.kernel import METHODS, Grammar, Ready, check, expand, normalise, prune_useless, replace_pairs

# The worked 6 x 5 matrix.
MATRIX = np.array([
    [1.2, 3.4, 5.6, 0.0, 2.3],
    [2.3, 0.0, 2.3, 4.5, 1.7],
    [1.2, 3.4, 2.3, 4.5, 0.0],
    [3.4, 0.0, 5.6, 0.0, 2.3],
    [2.3, 0.0, 2.3, 4.5, 0.0],
    [1.2, 3.4, 2.3, 4.5, 3.4],
])


def stream(m):
    r, c = np.nonzero(m)
    v = np.unique(m[m != 0])
    return 1 + np.searchsorted(v, m[r, c]) * m.shape[1] + c, r, v


def test_worked_products():
    s, r, v = stream(MATRIX)
    assert (len(s), len(v), len(s) + 6) == (23, 6, 29)
    g = METHODS["exact"](s, r, 6, len(v) * 5)
    assert len(g.rules) == 5 and len(g.marked()) == 16 and not check(g, s, r)
    for form in (g, normalise(g)):
        k = Ready(form, 5, v)
        np.testing.assert_allclose(k.right(np.arange(1.0, 6)), [36.3, 35.7, 32.9, 31.7, 27.2, 49.9])
        np.testing.assert_allclose(k.left(np.arange(1.0, 7)), [41.7, 34.0, 64.8, 72.0, 35.3])
    n = normalise(g)
    assert len(n.rules) == 9 and len(n.marked()) == 12 and np.array_equal(np.bincount(n.row), np.ones(6))


def test_worked_loop():
    s, r, v = stream(MATRIX)
    k = Ready(METHODS["exact"](s, r, 6, len(v) * 5), 5, v)
    x = np.ones(5)
    for _ in range(3):
        z = k.left(k.right(x))
        x, top = z / np.abs(z).max(), np.abs(z).max()
    np.testing.assert_allclose(x, [0.552915, 0.534150, 1, 0.871139, 0.502548], atol=1e-6)
    assert top == pytest.approx(180.4373, abs=1e-4)


def test_pair_replacement_is_exact_step_by_step():
    rng = np.random.default_rng(2)
    m = rng.integers(0, 3, (40, 6)).astype(float)
    s, r, v = stream(m)
    lines = [s[r == i].tolist() for i in range(40)]
    heap = METHODS["heap"](s, r, 40, len(v) * 6)
    steps = 0
    while True:  # brute force: recount all pairs at each step
        count: dict = {}
        for line in lines:
            for p in zip(line, line[1:]):
                count[p] = count.get(p, 0) + 1
        best = max(count.items(), key=lambda e: (e[1], [-x for x in e[0]]), default=(None, 0))
        if best[1] < 2:
            break
        steps += 1
        for line in lines:
            for i in range(len(line) - 1):
                if (line[i], line[i + 1]) == best[0]:
                    line[i : i + 2] = [len(v) * 6 + steps]
                    break
    assert steps == len(heap.rules) and sum(map(len, lines)) == len(heap.c)


@pytest.mark.parametrize("n,m,k,theta", [(60, 6, 2, 1.0), (80, 9, 1, 1.0), (200, 5, 4, 1.0), (50, 12, 1, 1.0), (80, 9, 1, 0.5)])
def test_each_rule_was_among_the_most_frequent_pairs(n, m, k, theta):
    """The rules in the order they are made, one after the other over plain rows, all pairs counted at each."""
    x = np.random.default_rng(n + m).integers(0, k + 1, (n, m)).astype(float)
    s, r, _ = stream(x)
    _, dense = np.unique(s, return_inverse=True)
    rules, c, row = replace_pairs(dense, r, theta)
    lines = [dense[r == i].tolist() for i in range(n)]
    new, best = int(dense.max()), None
    for a, b in rules.tolist():
        count: dict = {}
        for line in lines:
            for p in zip(line, line[1:]):
                count[p] = count.get(p, 0) + 1
        top = max(count.values())
        assert count[a, b] >= 2 and (count[a, b] == top if theta == 1 else count[a, b] >= theta * top - 1)
        new += 1
        for line in lines:
            for i in range(len(line) - 1):
                if (line[i], line[i + 1]) == (a, b):
                    line[i : i + 2] = [new]
                    break
    assert [y for line in lines for y in line] == c.tolist() and [i for i, line in enumerate(lines) for _ in line] == row.tolist()


def test_building_takes_time_in_proportion_to_the_symbols():
    def seconds(n):
        rng = np.random.default_rng(1)
        x = rng.integers(0, 12, (n, 8)) * (rng.random((n, 8)) < 0.8)
        s, r, v = stream(x.astype(float))
        start = time.process_time()
        g = METHODS["exact"](s, r, n, len(v) * 8)
        took = time.process_time() - start
        assert len(g.rules)
        return took

    seconds(2_000)
    assert seconds(80_000) < 8 * seconds(20_000) + 0.5  # four times the rows


@pytest.mark.parametrize("limit", [0, 1, 7])
def test_a_limit_of_rules_holds(limit):
    s, r, v = stream(np.random.default_rng(3).integers(0, 2, (40, 8)).astype(float))
    g = METHODS["exact"](s, r, 40, len(v) * 8, max_rules=limit)
    assert len(g.rules) == limit and np.array_equal(expand(g)[0], s)
    wide = METHODS["exact"](s + (1 << 40), r, 40, (1 << 40) + len(v) * 8)
    assert np.array_equal(expand(wide)[0], s + (1 << 40))


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 2**32 - 1), st.integers(0, 30), st.integers(1, 8), st.integers(1, 4), st.sampled_from(sorted(METHODS)))
def test_grammars_and_codecs_lose_nothing(seed, n, m, k, method):
    x = np.random.default_rng(seed).integers(0, k + 1, (n, m)).astype(float)
    s, r, v = stream(x) if n else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
    g = METHODS[method](s, r, n, len(v) * m)
    assert not check(g, s, r, exhausted=method in ("exact", "heap", "batched"))
    ready = Ready(g, m, v)
    a, b = np.arange(1.0, m + 1), 1 + np.arange(n) % 7.0
    np.testing.assert_allclose(ready.right(a), x @ a)
    np.testing.assert_allclose(ready.left(b), b @ x)
    for name in ("g32", "gpack", "gans"):
        c, q, w = codec.encode(g, name)
        h = codec.decode(name, c, q, w, len(g.c) + n, len(g.rules), g.space)
        assert np.array_equal(h.c, g.c) and np.array_equal(h.rules, g.rules) and np.array_equal(h.row, g.row)


def test_row_order_does_not_change_sizes():
    rng = np.random.default_rng(4)
    x = rng.integers(0, 3, (200, 7)).astype(float)
    sizes = set()
    for _ in range(3):
        s, r, v = stream(x[rng.permutation(200)])
        g = METHODS["exact"](s, r, 200, len(v) * 7)
        sizes.add((len(g.c), len(g.rules)))
    assert len(sizes) == 1


def test_packed_ranges_and_wide_ids():
    values = np.random.default_rng(1).integers(0, 1 << 61, 500)
    data = codec.pack(values, 61)
    assert np.array_equal(codec.unpack(data, 61, 500), values) and np.array_equal(codec.unpack(data, 61, 20, 100), values[100:120])
    big = np.array([5, 1 << 40, 300, 70_000, 0, 5])
    assert np.array_equal(codec.ans_decode(codec.ans_encode(big)), big)
    assert np.array_equal(codec.ans_decode(codec.ans_encode(np.zeros(9, int))), np.zeros(9))
    with pytest.raises(ValueError):
        codec.encode(Grammar(np.zeros((0, 2), np.int64), np.array([1]), np.array([0]), 1, 1 << 33), "g32")


def test_tables_of_frequencies_are_short_and_short_strings_stay_packed():
    r = np.random.default_rng(2)
    for n, k in ((1, 2), (50, 40), (700, 300), (5000, 60), (5000, 4000)):
        c = r.integers(0, k, n)
        assert np.array_equal(codec.ans_decode(codec.ans_encode(c)), c)
        g = Grammar(np.zeros((0, 2), np.int64), 1 + c, np.arange(n), n, k + 1)
        coded, packed = codec.encode(g, "gans"), codec.encode(g, "gpack")
        assert len(coded[0]) <= len(packed[0]) + 1
        h = codec.decode("gans", *coded, 2 * n, 0, g.space)
        assert np.array_equal(h.c, g.c) and np.array_equal(h.row, g.row)
    values = r.integers(1, 1 << 15, 300)
    assert np.array_equal(codec._from_gamma(codec._gamma(values), 300), values)


def test_useless_rules_go():
    g = Grammar(np.array([[1, 2], [1, 3]]), np.array([5]), np.array([0]), 1, 4)
    p = prune_useless(g)
    assert len(p.rules) == 1 and np.array_equal(expand(p)[0], [1, 2])
    g = Grammar(np.array([[1, 2], [1, 3]]), np.array([6]), np.array([0]), 1, 4)
    assert np.array_equal(expand(prune_useless(g))[0], [1, 3])
