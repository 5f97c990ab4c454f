"""Numpy kernels that run inside one task: grammar construction, checks, and products over one row block.

A block is a list of rows, each a sequence of symbols. Symbols 1..space are terminals (1 + code * m + column), higher ones
are rules, in an order that puts children first; 0 is the row mark. A row holds a symbol at most once, so pairs never
overlap and a pair's count is the number of rows that hold it.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np


@dataclass
class Grammar:
    """Rules (q x 2, children first), final string and its rows (``c``, ``row``), ``n`` rows, ``space`` terminal ids."""

    rules: np.ndarray
    c: np.ndarray
    row: np.ndarray
    n: int
    space: int

    @property
    def levels(self) -> np.ndarray:
        """Depth of each rule: 1 over its deeper child, terminals being 0."""
        q = len(self.rules)
        level = np.zeros(q, np.int64)
        child = self.rules - self.space - 1
        while q:
            under = np.where(child >= 0, level[np.maximum(child, 0)], 0).max(axis=1) + 1
            if (under == level).all():
                break
            level = under
        return level

    @property
    def n_max(self) -> int:
        return self.space + len(self.rules)

    def marked(self) -> np.ndarray:
        """The final string with a 0 after every row."""
        counts = np.bincount(self.row, minlength=self.n)
        out = np.zeros(len(self.c) + self.n, np.int64)
        out[np.arange(len(self.c)) + self.row] = self.c
        assert len(counts) == self.n
        return out


def from_marked(marked: np.ndarray, rules: np.ndarray, space: int) -> Grammar:
    mark = marked == 0
    row = np.cumsum(mark) - mark
    return Grammar(rules, marked[~mark], row[~mark], int(mark.sum()), space)


class _Pairs:
    """Pairs that still repeat: their counts, where they occur, and a queue of buckets by count.

    A pair lies in the bucket of a count it once had and moves down when it is met there; a list of occurrences is read
    once, when its pair is replaced, and skips positions that hold another pair by then. All work is thus in proportion
    to the symbols, but for the sorting of keys.
    """

    def __init__(self, least: int, room: int) -> None:
        self.least, self.size, self.used = least, 0, 0
        self.count, self.first, self.n = (np.zeros(1024, np.int64) for _ in range(3))
        self.left, self.right = np.zeros(1024, np.int64), np.zeros(1024, np.int64)
        self.where = np.zeros(max(16, room), np.int32)
        self.buckets: dict[int, list[np.ndarray]] = {}

    def add(self, key: np.ndarray, pos: np.ndarray, of: np.ndarray) -> None:
        """Pairs ``key`` at positions ``pos`` become known; ``of`` (position -> pair, -1 for none) is brought up to date."""
        order = np.argsort(key, kind="stable")
        key, pos = key[order], pos[order]
        edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]])) if len(key) else np.zeros(1, np.int64)
        n = np.diff(edge)
        good = n >= self.least
        of[pos] = -1
        held = np.repeat(good, n)
        pos, n, key = pos[held], n[good], key[edge[:-1]][good]
        if not len(n):
            return
        new = np.arange(self.size, self.size + len(n))
        self._grow(len(n), len(pos))
        at = slice(self.size, self.size + len(n))
        self.count[at] = self.n[at] = n
        self.first[at] = self.used + np.cumsum(n) - n
        self.left[at], self.right[at] = key >> 32, key & 0xFFFFFFFF
        self.where[self.used : self.used + len(pos)] = pos
        self.size, self.used = self.size + len(n), self.used + len(pos)
        of[pos] = np.repeat(new, n)
        self.push(new)

    def _grow(self, pairs: int, places: int) -> None:
        if self.size + pairs > len(self.count):
            more = max(pairs, len(self.count))
            for name in ("count", "first", "n", "left", "right"):
                setattr(self, name, np.append(getattr(self, name), np.zeros(more, np.int64)))
        if self.used + places > len(self.where):
            self.where = np.append(self.where, np.zeros(max(places, len(self.where) // 2), np.int32))

    def push(self, pairs: np.ndarray) -> None:
        count = self.count[pairs]
        pairs, count = pairs[count >= self.least], count[count >= self.least]
        order = np.argsort(count, kind="stable")
        pairs, count = pairs[order], count[order]
        edge = np.flatnonzero(np.concatenate([[True], count[1:] != count[:-1], [True]])) if len(pairs) else [0]
        for a, b in zip(edge[:-1], edge[1:]):
            self.buckets.setdefault(int(count[a]), []).append(pairs[a:b])

    def take(self, level: int) -> np.ndarray:
        """The pairs of exactly this count; others of the bucket move to theirs."""
        held = self.buckets.pop(level, None)
        if held is None:
            return np.zeros(0, np.int64)
        pairs = np.concatenate(held)
        same = self.count[pairs] == level
        self.push(pairs[~same])
        return pairs[same]

    def occurrences(self, pairs: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of ``pairs``, and which of them each holds."""
        n = self.n[pairs]
        which = np.repeat(np.arange(len(pairs)), n)
        pos = self.where[np.repeat(self.first[pairs] - (np.cumsum(n) - n), n) + np.arange(len(which))]
        now = of[pos] == pairs[which]
        return pos[now], which[now]


def _lot(pairs: np.ndarray) -> np.ndarray:
    """A fixed shuffle of pair numbers, for ties."""
    x = pairs.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((x ^ (x >> np.uint64(29))) >> np.uint64(1)).astype(np.int64)


def replace_pairs(symbols: np.ndarray, row: np.ndarray, theta: float = 1.0, min_count: int = 2, max_rules: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pair replacement of dense symbols 0..u-1; rules in the order made (symbols u, u+1, ...), what is left, and its rows.

    A step takes the pairs of the best count (from ``theta`` times it on), and of pairs that overlap somewhere all but the
    first by count and lot; the others are replaced at once. With theta = 1 this is exact replacement under one order of
    ties: taken one after the other, each would still be the most frequent. Occurrences are linked, and only pairs beside a
    replaced one are counted anew.
    """
    length = len(symbols)
    u = int(symbols.max()) + 1 if length else 0
    s = np.append(symbols, 0).astype(np.int32)
    ends = np.append(row[1:] != row[:-1], True) if length else np.zeros(0, bool)
    after = np.append(np.where(ends, length, np.arange(1, length + 1)), length).astype(np.int32)
    before = np.append(np.where(np.append(True, ends[:-1]), -1, np.arange(-1, length - 1)), -1).astype(np.int32) if length else np.array([-1], np.int32)
    of = np.full(length + 1, -1, np.int32)
    gone = np.zeros(length + 1, bool)
    pairs = _Pairs(min_count, length)
    start = np.flatnonzero(~ends)
    pairs.add(s[start].astype(np.int64) << 32 | s[start + 1], start, of)
    made: list[np.ndarray] = []
    total, level = 0, max(pairs.buckets, default=0)
    rank = np.zeros(0, np.int64)
    while level >= min_count and (max_rules is None or total < max_rules):
        pool = pairs.take(level)
        if not len(pool):
            level -= 1
            continue
        if theta < 1:
            down = range(level - 1, max(min_count, int(np.ceil(theta * level - 1e-9))) - 1, -1)
            pool = np.concatenate([pool, *(pairs.take(c) for c in down if c in pairs.buckets)])
        pos, which = pairs.occurrences(pool, of)
        chosen = np.ones(len(pool), bool)
        if len(pool) > 1:
            if len(rank) < pairs.size:
                rank = np.full(2 * pairs.size, -1, np.int64)
            rank[pool] = np.arange(len(pool))
            beside = of[after[pos]]
            next_to = np.where(beside >= 0, rank[np.maximum(beside, 0)], -1)
            meet = next_to >= 0
            a, b = which[meet], next_to[meet]
            rank[pool] = -1
            weight = pairs.count[pool]
            lot = _lot(pool)
            first = (weight[a] > weight[b]) | ((weight[a] == weight[b]) & ((lot[a] < lot[b]) | ((lot[a] == lot[b]) & (a < b))))
            chosen[np.where(first, b, a)] = False
        at = np.flatnonzero(chosen)
        at = at[np.lexsort((pairs.right[pool[at]], pairs.left[pool[at]]))]
        if max_rules is not None:
            at = at[: max_rules - total]
        number = np.full(len(pool), -1, np.int64)
        number[at] = u + total + np.arange(len(at))
        made.append(np.stack([pairs.left[pool[at]], pairs.right[pool[at]]], axis=1))
        total += len(at)
        to = number[which]
        i, to = pos[to >= 0], to[to >= 0]
        j = after[i]
        old = np.concatenate([before[i], j])
        old = old[old >= 0]
        old = np.unique(old[of[old] >= 0])
        lost, times = np.unique(of[old], return_counts=True)
        pairs.count[lost] -= times
        of[j] = -1
        of[i] = -1
        s[i], gone[j] = to, True
        k = after[j]
        after[i] = k
        before[k] = i  # the cell past the end takes what has no follower
        before[length] = -1
        h = before[i]
        touched = np.unique(np.concatenate([i[k < length], h[h >= 0]]))
        pairs.count[pool[at]] = 0
        pairs.add(s[touched].astype(np.int64) << 32 | s[after[touched]], touched, of)
        pairs.push(pool[number < 0])
    keep = ~gone[:length]
    return np.concatenate([*made, np.zeros((0, 2), np.int64)]).astype(np.int64), s[:length][keep].astype(np.int64), row[keep]


def build(symbols: np.ndarray, row: np.ndarray, n: int, space: int, theta: float = 1.0, min_count: int = 2, max_rules: int | None = None) -> Grammar:
    """Pair replacement (see ``replace_pairs``) of one block; rules come out by level. Symbol ids may be of any size."""
    used, dense = np.unique(symbols, return_inverse=True)
    rules, c, left = replace_pairs(dense, np.asarray(row), theta, max(2, min_count), max_rules)
    wide = np.concatenate([used, space + 1 + np.arange(len(rules))]).astype(np.int64)
    return level_order(Grammar(wide[rules].reshape(-1, 2), wide[c] if len(c) else np.zeros(0, np.int64), left, n, space))


def build_by_heap(symbols: np.ndarray, row: np.ndarray, n: int, space: int) -> Grammar:
    """Exact pair replacement, one pair a step: linked positions, the rows of each pair, and a heap with stale entries. Ties go to the smaller pair."""
    lines: list[list[int]] = [[] for _ in range(n)]
    for x, r in zip(symbols.tolist(), row.tolist()):
        lines[r].append(x)
    where: dict[tuple[int, int], set[int]] = {}
    for r, line in enumerate(lines):
        for pair in zip(line, line[1:]):
            where.setdefault(pair, set()).add(r)
    heap = [(-len(v), k) for k, v in where.items()]
    heapq.heapify(heap)
    rules: list[tuple[int, int]] = []
    while heap:
        count, pair = heapq.heappop(heap)
        if -count != len(where.get(pair, ())):
            continue
        if -count < 2:
            break
        rules.append(pair)
        new = space + len(rules)
        touched = set()
        for r in list(where[pair]):
            line = lines[r]
            for p in zip(line, line[1:]):
                where[p].discard(r)
                touched.add(p)
            i = line.index(pair[0])
            line[i : i + 2] = [new]
            for p in zip(line, line[1:]):
                where.setdefault(p, set()).add(r)
                touched.add(p)
        for p in touched:
            if len(where[p]) >= 2:
                heapq.heappush(heap, (-len(where[p]), p))
    c = [x for line in lines for x in line]
    rows = [r for r, line in enumerate(lines) for _ in line]
    return level_order(Grammar(np.array(rules, np.int64).reshape(-1, 2), np.array(c, np.int64), np.array(rows, np.int64), n, space))


def build_by_phrase(symbols: np.ndarray, row: np.ndarray, n: int, space: int, by: str = "longest") -> Grammar:
    """Irreducible grammars by repeated phrases: ``longest`` replaces the longest repeated phrase, ``greedy`` the one that saves most symbols.

    A phrase of k symbols becomes k - 1 binary rules, shared where they are the same. Phrases lie inside a row.
    """
    lines: list[list[int]] = [[] for _ in range(n)]
    for x, r in zip(symbols.tolist(), row.tolist()):
        lines[r].append(x)
    rules: list[tuple[int, int]] = []
    known: dict[tuple[int, int], int] = {}

    def join(a: int, b: int) -> int:
        if (a, b) not in known:
            rules.append((a, b))
            known[a, b] = space + len(rules)
        return known[a, b]

    while True:
        best: tuple[int, tuple[int, ...]] | None = None
        most = max((len(x) for x in lines), default=0)
        for k in range(most, 1, -1) if by == "longest" else range(2, most + 1):
            seen: dict[tuple[int, ...], int] = {}
            for line in lines:
                for i in range(len(line) - k + 1):
                    p = tuple(line[i : i + k])
                    seen[p] = seen.get(p, 0) + 1
            for p, c in seen.items():
                if c >= 2:
                    gain = k if by == "longest" else c * (k - 1) - k
                    if best is None or gain > best[0] or (gain == best[0] and p < best[1]):
                        best = (gain, p)
            if best and by == "longest" or not any(c >= 2 for c in seen.values()) and by == "greedy":
                break
        if best is None or by == "greedy" and best[0] < 0:
            break
        phrase = best[1]
        new = phrase[0]
        for x in phrase[1:]:
            new = join(new, x)
        k = len(phrase)
        for line in lines:
            for i in range(len(line) - k + 1):
                if tuple(line[i : i + k]) == phrase:
                    line[i : i + k] = [new]
                    break
    c = [x for line in lines for x in line]
    rows = [r for r, line in enumerate(lines) for _ in line]
    return level_order(Grammar(np.array(rules, np.int64).reshape(-1, 2), np.array(c, np.int64), np.array(rows, np.int64), n, space))


def build_sequential(symbols: np.ndarray, row: np.ndarray, n: int, space: int) -> Grammar:
    """One pass over the rows: each row is parsed by the rules so far, and a pair that an earlier row left as it is becomes a rule in both places."""
    rules: list[tuple[int, int]] = []
    rule_of: dict[tuple[int, int], int] = {}
    left_in: dict[tuple[int, int], int] = {}
    lines: list[list[int]] = [[] for _ in range(n)]
    for x, r in zip(symbols.tolist(), row.tolist()):
        lines[r].append(x)

    def settle(r: int) -> None:
        line, i = lines[r], 0
        while i + 1 < len(line):
            pair = (line[i], line[i + 1])
            if pair not in rule_of and left_in.get(pair, r) != r:
                rules.append(pair)
                rule_of[pair] = space + len(rules)
                other = left_in.pop(pair)
                o = lines[other]
                if pair[0] in o:
                    j = o.index(pair[0])
                    if j + 1 < len(o) and o[j + 1] == pair[1]:
                        o[j : j + 2] = [rule_of[pair]]
                        for p in zip(o[max(0, j - 1) : j + 1], o[max(0, j - 1) + 1 : j + 2]):
                            left_in.setdefault(p, other)
            if pair in rule_of:
                line[i : i + 2] = [rule_of[pair]]
                i = max(0, i - 1)
            else:
                i += 1
        for p in zip(line, line[1:]):
            left_in.setdefault(p, r)

    for r in range(n):
        settle(r)
    c = [x for line in lines for x in line]
    rows = [r for r, line in enumerate(lines) for _ in line]
    return level_order(prune_useless(Grammar(np.array(rules, np.int64).reshape(-1, 2), np.array(c, np.int64), np.array(rows, np.int64), n, space)))


METHODS = {
    "exact": build,
    "batched": lambda *a, theta=0.5, **k: build(*a, theta=theta, **k),
    "heap": lambda *a, **k: build_by_heap(*a),
    "longest": lambda *a, **k: build_by_phrase(*a, by="longest"),
    "greedy": lambda *a, **k: build_by_phrase(*a, by="greedy"),
    "sequential": lambda *a, **k: build_sequential(*a),
}


def level_order(g: Grammar) -> Grammar:
    """The same grammar with rules numbered by (level, former number): children stay lower, levels become ranges."""
    order = np.argsort(g.levels, kind="stable")
    to = np.empty(len(order), np.int64)
    to[order] = np.arange(len(order))
    move = lambda x: np.where(x > g.space, to[np.maximum(x - g.space - 1, 0)] + g.space + 1, x) if len(order) else x
    return Grammar(move(g.rules[order]), move(g.c), g.row, g.n, g.space)


def prune_useless(g: Grammar) -> Grammar:
    """Without rules that neither the final string nor a useful rule uses, found in one backward sweep."""
    q = len(g.rules)
    used = np.zeros(q + 1, bool)
    used[np.maximum(g.c - g.space, 0)] = True
    for i in range(q, 0, -1):
        if used[i]:
            used[np.maximum(g.rules[i - 1] - g.space, 0)] = True
    used = used[1:]
    to = np.cumsum(used) - 1
    move = lambda x: np.where(x > g.space, to[np.maximum(x - g.space - 1, 0)] + g.space + 1, x) if q else x
    return Grammar(move(g.rules[used]), move(g.c), g.row, g.n, g.space)


def normalise(g: Grammar) -> Grammar:
    """Row normal form: each row is one symbol, by a left fold of its symbols with shared rules; an empty row stays empty."""
    rules = [tuple(x) for x in g.rules.tolist()]
    known = {x: g.space + i + 1 for i, x in enumerate(rules)}
    c, rows = [], []
    starts = np.searchsorted(g.row, np.arange(g.n + 1))
    for r in range(g.n):
        line = g.c[starts[r] : starts[r + 1]].tolist()
        if line:
            x = line[0]
            for y in line[1:]:
                if (x, y) not in known:
                    rules.append((x, y))
                    known[x, y] = g.space + len(rules)
                x = known[x, y]
            c.append(x)
            rows.append(r)
    return level_order(Grammar(np.array(rules, np.int64).reshape(-1, 2), np.array(c, np.int64), np.array(rows, np.int64), g.n, g.space))


def expand(g: Grammar, symbols: np.ndarray | None = None, row: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Terminals of the final string (or of the given symbols) and their rows, one level of rules a step."""
    c, row = (g.c, g.row) if symbols is None else (symbols, row)
    while (c > g.space).any():
        rule = c > g.space
        width = 1 + rule
        at = np.cumsum(width) - width
        out = np.empty(int(width.sum()), np.int64)
        out[at[~rule]] = c[~rule]
        out[at[rule]], out[at[rule] + 1] = g.rules[c[rule] - g.space - 1].T
        c, row = out, np.repeat(row, width)
    return c, row


def check(g: Grammar, symbols: np.ndarray, row: np.ndarray, exhausted: bool = True) -> list[str]:
    """What is wrong with ``g`` as a grammar of the rows; empty if nothing."""
    wrong = []
    if (g.rules <= 0).any():
        wrong.append("a rule holds a row mark")
    if (g.rules[:, 0] == g.rules[:, 1]).any():
        wrong.append("a rule has equal sides")
    if (g.rules >= g.space + 1 + np.arange(len(g.rules))[:, None]).any():
        wrong.append("a rule comes before its child")
    c, r = expand(g)
    if not (np.array_equal(c, symbols) and np.array_equal(r, row)):
        wrong.append("the expansion is another string")
    if len(prune_useless(g).rules) != len(g.rules):
        wrong.append("a rule is useless")
    pair = np.stack([g.row, g.c], axis=1)
    if len(np.unique(pair, axis=0)) != len(pair):
        wrong.append("a row holds a symbol twice")
    if exhausted and len(g.c) > 1:
        same = g.row[1:] == g.row[:-1]
        _, n = np.unique(np.stack([g.c[:-1][same], g.c[1:][same]], axis=1), axis=0, return_counts=True)
        if len(n) and n.max() > 1:
            wrong.append("a pair repeats")
    return wrong


class Ready:
    """A block ready for products: dense ids (used terminals, then rules by level), value and column of each terminal."""

    def __init__(self, g: Grammar, m: int, values: np.ndarray) -> None:
        own = np.concatenate([g.c[g.c <= g.space], g.rules[g.rules <= g.space]])
        if g.space <= 8 * len(own):  # a table of all terminals is no larger than what it numbers
            number = np.zeros(g.space + 1, np.int32)
            number[own] = 1
            used = np.flatnonzero(number)
            number[used] = np.arange(len(used))
            place = lambda x: number[np.minimum(x, g.space)]
        else:
            used = np.unique(own)
            place = lambda x: np.searchsorted(used, x)
        dense = lambda x: np.where(x > g.space, x - g.space - 1 + len(used), place(x))
        small = lambda a: a.astype(np.int32) if g.n_max < 1 << 31 or not len(a) or int(a.max()) < 1 << 31 else a
        self.c, self.rules, self.row, self.n, self.m = small(dense(g.c)), small(dense(g.rules)), small(g.row), g.n, m
        self.col = (used - 1) % m if len(used) else used
        self.value = values[(used - 1) // m] if len(used) else np.zeros(0)
        self.bounds = np.searchsorted(g.levels, np.arange(1, (g.levels.max() if len(g.rules) else 0) + 2))
        self.used = used

    @property
    def nbytes(self) -> int:
        return sum(a.nbytes for a in (self.c, self.rules, self.row, self.col, self.value, self.used, self.bounds))

    def symbol_values(self, x: np.ndarray) -> np.ndarray:
        """Val of every terminal and rule: each level is one vector addition. ``x``: m, or m x k."""
        t = len(self.used)
        u = np.empty((t + len(self.rules), *x.shape[1:]))
        u[:t] = (self.value.reshape(-1, *[1] * (x.ndim - 1))) * x[self.col]
        for a, b in zip(self.bounds[:-1], self.bounds[1:]):
            u[t + a : t + b] = u[self.rules[a:b, 0]] + u[self.rules[a:b, 1]]
        return u

    def right(self, x: np.ndarray) -> np.ndarray:
        u = self.symbol_values(x)[self.c]
        if u.ndim == 1:
            return np.bincount(self.row, u, self.n).astype(float)  # without symbols, bincount counts in integers
        return np.stack([np.bincount(self.row, u[:, k], self.n) for k in range(u.shape[1])], axis=1)

    def symbol_sums(self, y: np.ndarray) -> np.ndarray:
        """Sum of y over the rows that each terminal and rule reaches: seeded by the final string, pushed down level by level."""
        t = len(self.used)
        g = np.bincount(self.c, y[self.row], t + len(self.rules)).astype(float)
        for a, b in zip(self.bounds[-2::-1], self.bounds[:0:-1]):
            g += np.bincount(self.rules[a:b].ravel(), np.repeat(g[t + a : t + b], 2), len(g))
        return g

    def left(self, y: np.ndarray) -> np.ndarray:
        if y.ndim == 2:
            return np.stack([self.left(y[:, k]) for k in range(y.shape[1])], axis=1)
        return np.bincount(self.col, self.symbol_sums(y)[: len(self.used)] * self.value, self.m).astype(float)

    @property
    def additions(self) -> int:
        return len(self.c) + len(self.rules)
