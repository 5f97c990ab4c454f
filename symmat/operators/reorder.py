"""Column reordering: similarity by repeated value pairs, pruning, ordering algorithms, and blockwise choice."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..model import MatrixView, cut

Edges = list[tuple[int, int, float]]
#: Pairs of cells of one column that are compared at once.
PORTION = 1 << 22


def value_pairs(view: MatrixView) -> DataFrame:
    """(ci, cj, vi, vj) of each row and column pair ci < cj with both cells nonzero; made inside the row, without a join."""
    cells = F.arrays_zip("cols", "vals")
    rest = F.transform(cells, lambda x, i: F.struct(x["cols"].alias("ci"), x["vals"].alias("vi"), F.slice(cells, i + 2, F.size("cols")).alias("others")))
    one = view.rows.select(F.explode(rest).alias("a")).select("a.ci", "a.vi", F.explode("a.others").alias("b"))
    return one.select("ci", F.col("b.cols").alias("cj"), "vi", F.col("b.vals").alias("vj"))


def repetitions(view: MatrixView, engine: str = "hash", blocks: int | None = None) -> DataFrame:
    """(ci, cj, rep): rows with both columns nonzero, less the distinct value pairs among them; pairs that meet at least once.

    ``hash``: pairs are counted in portions of rows where these lie, so that no row a pair is made but of those that differ; two aggregations add the counts. ``sort``: pairs are range-sorted; each task counts its repeats and
    says where it begins and ends, and equal neighbours over a border count once more, so a pair of values that fills all
    rows lies in many tasks. ``sketch``: distinct pairs are estimated by a HyperLogLog sketch. ``block``: repetitions within
    each of ``blocks`` row blocks (None: of bounded size), added up; one task a block, no row a pair.
    """
    if engine == "block":
        m = view.m

        def local(key: tuple, rows: pa.Table) -> pa.Table:
            found = local_edges(*_cells_of(rows), 1, m)
            return pa.table({"ci": pa.array([e[0] for e in found], pa.int32()), "cj": pa.array([e[1] for e in found], pa.int32()), "rep": pa.array([int(e[2]) for e in found], pa.int64())})

        if blocks is None:
            from .multiply import block_count

            blocks = block_count(view)
        made = view.rows.withColumn("block", view.block_of(blocks)).groupBy("block").applyInArrow(local, "ci int, cj int, rep long")
        return made.groupBy("ci", "cj").agg(F.sum("rep").alias("rep"))
    if engine == "hash":
        m = view.m
        counted = view.rows.select("cols", "vals").mapInArrow(lambda batches: _counted_pairs(batches, m), "ci int, cj int, vi double, vj double, c long")
        return counted.groupBy("ci", "cj", "vi", "vj").agg(F.sum("c").alias("c")).groupBy("ci", "cj").agg(F.sum(F.col("c") - 1).alias("rep"))
    pairs = value_pairs(view)
    if engine == "sketch":
        both = F.concat_ws("|", F.col("vi").cast("string"), F.col("vj").cast("string"))
        est = F.hll_sketch_estimate(F.hll_sketch_agg(both))
        return pairs.groupBy("ci", "cj").agg(F.count("*").alias("n"), est.alias("d")).select("ci", "cj", F.greatest(F.lit(0), F.col("n") - F.col("d")).cast("long").alias("rep"))
    if engine != "sort":
        raise ValueError(engine)

    names = ["ci", "cj", "vi", "vj"]

    def run(batches):
        from pyspark import TaskContext

        part, first, last = TaskContext.get().partitionId(), None, None
        for b in batches:
            if not len(b):
                continue
            k = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(float) for c in names], axis=1)
            before = np.vstack([k[:1] * np.nan if last is None else last, k[:-1]])
            again = (k == before).all(axis=1)
            first, last = k[0] if first is None else first, k[-1:]
            cols, at = np.unique(k[:, :2], axis=0, return_inverse=True)
            rep = np.bincount(at, again, len(cols)).astype(np.int64)
            none = pa.nulls(len(cols), pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([pa.array(cols[:, 0].astype(np.int32)), pa.array(cols[:, 1].astype(np.int32)), pa.array(rep), pa.nulls(len(cols), pa.int32()), none, none], names=out_names)
        if first is not None:
            ends = [pa.array([x.tolist()], pa.list_(pa.float64())) for x in (first, last[0])]
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int32()), pa.nulls(1, pa.int32()), pa.array([0]), pa.array([part], pa.int32()), *ends], names=out_names)

    out_names = ["ci", "cj", "rep", "part", "first", "last"]
    ordered = pairs.withColumn("deal", F.rand(3)).repartitionByRange(*names, "deal").sortWithinPartitions(*names)
    counted = cut(ordered.mapInArrow(run, "ci int, cj int, rep long, part int, first array<double>, last array<double>"))
    ends = counted.where("part IS NOT NULL").orderBy("part").collect()  # a row per task
    joined = [(int(b.first[0]), int(b.first[1]), 1) for a, b in zip(ends, ends[1:]) if a.last == b.first]
    more = view.rows.sparkSession.createDataFrame(joined, "ci int, cj int, rep long")
    return counted.where("part IS NULL").select("ci", "cj", "rep").union(more).groupBy("ci", "cj").agg(F.sum("rep").alias("rep"))


def pair_counts(row: np.ndarray, col: np.ndarray, val: np.ndarray, n: int, m: int) -> Iterable[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(ci, cj, values, values, count) of the pairs in ``n`` rows (cells sorted by row and column), for each two columns that meet.

    Columns are coded on their own, 0 for no cell. Where two columns have few codes their pairs are counted in place, else sorted.
    A column that meets few of the cells behind it looks only at these.
    """
    ends = np.searchsorted(row, row, side="right")
    order = np.argsort(col, kind="stable")
    first = np.searchsorted(col[order], np.arange(m + 1))
    own = [order[a:b] for a, b in zip(first[:-1], first[1:])]
    value, code = [], []
    for at in own:
        v, k = np.unique(val[at], return_inverse=True)
        value.append(v)
        code.append((k + 1).astype(np.int32))
    full, place = np.zeros(n, np.int32), np.zeros(len(col), np.int32)
    for at, k in zip(own, code):
        place[at] = k
    for i in range(m):
        if not len(own[i]):
            continue
        more = ends[own[i]] - own[i] - 1
        if len(order) - first[i + 1] > 8 * more.sum():
            mine = np.repeat(own[i], more)
            other = np.arange(len(mine)) - np.repeat(np.cumsum(more) - more, more) + mine + 1
            met = np.stack([col[other], place[mine], place[other]], axis=1)
            for j in np.unique(met[:, 0]):
                pairs, c = np.unique(met[met[:, 0] == j, 1:], axis=0, return_counts=True)
                yield i, int(j), value[i][pairs[:, 0] - 1], value[j][pairs[:, 1] - 1], c
            continue
        rows_i = row[own[i]]
        full[rows_i] = code[i]
        for j in range(i + 1, m):
            if not len(own[j]):
                continue
            a, b, width = full[row[own[j]]], code[j], len(value[j]) + 1
            size = (len(value[i]) + 1) * width
            key = a.astype(np.int64) * width + b
            if size <= max(1 << 16, 4 * len(key)):
                c = np.bincount(key, minlength=size)
                c[:width] = 0  # no cell in column i
                key = np.flatnonzero(c)
                c = c[key]
            else:
                key, c = np.unique(key[a > 0], return_counts=True)
            if len(key):
                yield i, j, value[i][key // width - 1], value[j][key % width - 1], c
        full[rows_i] = 0


def _counted_pairs(batches: Iterable[pa.RecordBatch], m: int) -> Iterable[pa.RecordBatch]:
    """``pair_counts`` of portions of at most PORTION cells or so."""

    def flush(held: list[pa.RecordBatch]) -> Iterable[pa.RecordBatch]:
        rows = pa.Table.from_batches(held)
        for i, j, vi, vj, c in pair_counts(*_cells_of(rows), len(rows), m):
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(c), i, np.int32)), pa.array(np.full(len(c), j, np.int32)), pa.array(vi), pa.array(vj), pa.array(c.astype(np.int64))], names=["ci", "cj", "vi", "vj", "c"])

    held, cells = [], 0
    for batch in batches:
        held.append(batch)
        cells += len(batch) + len(batch.column("cols").flatten())
        if cells >= PORTION:
            yield from flush(held)
            held, cells = [], 0
    if cells:
        yield from flush(held)


def similarity(view: MatrixView, engine: str = "hash", sample: float | None = None, seed: int = 1, blocks: int | None = None) -> DataFrame:
    """(ci, cj, rep, score): repetitions over the number of rows. ``sample`` takes a share of the rows (scores come out low)."""
    if sample:  # by a hash of the row id: the same rows however the table is dealt
        drawn = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "row_id")), 1, 6), 16, 10).cast("long")
        view = MatrixView(view.rows.where(drawn < int(sample * (1 << 24))), view.m, view.names)
    n = view.n
    return repetitions(view, engine, blocks).select("ci", "cj", "rep", (F.col("rep") / F.lit(float(max(1, n)))).alias("score"))


def prune_local(scores: DataFrame, k: int, mode: str = "either") -> DataFrame:
    """Edges that are among the k best of either end ('both': of both ends)."""
    both = scores.select("ci", "cj", "rep", "score", F.col("ci").alias("own"), F.col("cj").alias("other")).union(scores.select("ci", "cj", "rep", "score", F.col("cj").alias("own"), F.col("ci").alias("other")))
    rank = F.row_number().over(Window.partitionBy("own").orderBy(F.desc("rep"), "other"))
    kept = both.withColumn("r", rank).where(F.col("r") <= k).groupBy("ci", "cj", "rep", "score").agg(F.count("*").alias("ends"))
    return kept.where(F.col("ends") >= (2 if mode == "both" else 1)).drop("ends")


def prune_global(scores: DataFrame, k: int, m: int, undirected: bool = False) -> DataFrame:
    """The best entries: m * k of the symmetric matrix, thus half as many edges (all of them with ``undirected``)."""
    return scores.orderBy(F.desc("rep"), "ci", "cj").limit(m * k if undirected else m * k // 2)


def edges_of(scores: DataFrame) -> Edges:
    """The edges on the driver: at most m * k of a pruned graph."""
    return [(r.ci, r.cj, r.score) for r in scores.select("ci", "cj", "score").collect()]


def _cells_of(rows: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row index, column and value of the cells of a table of rows."""
    cols = rows.column("cols").combine_chunks()
    vals = rows.column("vals").combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return np.repeat(np.arange(len(rows)), np.diff(cols.offsets.to_numpy())), cols.flatten().to_numpy(zero_copy_only=False).astype(np.int64), vals


def local_edges(row: np.ndarray, col: np.ndarray, val: np.ndarray, n: int, m: int, k: int | None = None) -> Edges:
    """The same scores from the cells of one block (row index, column, value; sorted by row), without Spark.

    Column by column: its cells meet the cells behind them in their rows, so work follows the pairs of cells there are, and
    memory those of one column, which go in portions.
    """
    _, code = np.unique(val, return_inverse=True)
    size = int(code.max()) + 1 if len(code) else 1
    ends = np.searchsorted(row, row, side="right")
    order = np.argsort(col, kind="stable")
    first = np.searchsorted(col[order], np.arange(m + 1))
    out: Edges = []
    for c in range(m):
        own = order[first[c] : first[c + 1]]
        more = ends[own] - own - 1
        met, distinct = np.zeros(m, np.int64), [np.zeros(0, np.int64)]
        portion = np.cumsum(more) // PORTION
        for a, b in zip(np.searchsorted(portion, np.unique(portion)), np.searchsorted(portion, np.unique(portion), side="right")):
            some, k_more = own[a:b], more[a:b]
            mine = np.repeat(some, k_more)
            other = np.arange(len(mine)) - np.repeat(np.cumsum(k_more) - k_more, k_more) + mine + 1
            met += np.bincount(col[other], minlength=m)
            distinct.append(np.unique((col[other] * size + code[mine]) * size + code[other]))
        pairs = distinct[-1] if len(distinct) == 2 else np.unique(np.concatenate(distinct))
        rep = met - np.bincount(pairs // (size * size), minlength=m)
        out += [(c, int(d), int(rep[d]) / n) for d in np.flatnonzero(rep > 0)]
    return out if k is None else prune_edges(out, k)


def prune_edges(edges: Edges, k: int) -> Edges:
    """Local pruning of a driver-side edge list."""
    best: dict[int, list] = {}
    for e in edges:
        for own, other in ((e[0], e[1]), (e[1], e[0])):
            best.setdefault(own, []).append((-e[2], other, e))
    return sorted({x[2] for own in best.values() for x in sorted(own)[:k]})


class _Forest:
    def __init__(self, m: int) -> None:
        self.up = list(range(m))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x


def _chains(links: Iterable[tuple[int, int]], m: int) -> list[int]:
    """Fragments end to end, by their smallest column; each starts at its smaller end."""
    near: list[list[int]] = [[] for _ in range(m)]
    for a, b in links:
        near[a].append(b)
        near[b].append(a)
    parts, seen = [], [False] * m
    for s in range(m):
        if seen[s] or len(near[s]) > 1:
            continue
        path, x = [], s
        while x is not None:
            seen[x] = True
            path.append(x)
            x = next((y for y in near[x] if not seen[y]), None)
        parts.append(path if path[0] <= path[-1] else path[::-1])
    return [c for p in sorted(parts, key=min) for c in p]


def path_links(edges: Edges, m: int) -> list[tuple[int, int]]:
    """Greedy path cover: edges by falling weight, kept where both ends are free and no circle closes."""
    degree, forest, kept = [0] * m, _Forest(m), []
    for a, b, w in sorted(edges, key=lambda e: (-e[2], e[0], e[1])):
        if w > 0 and degree[a] < 2 and degree[b] < 2 and forest.root(a) != forest.root(b):
            forest.up[forest.root(a)] = forest.root(b)
            degree[a] += 1
            degree[b] += 1
            kept.append((a, b))
    return kept


def paths(edges: Edges, m: int) -> list[int]:
    """The fragments of the greedy path cover, end to end."""
    return _chains(path_links(edges, m), m)


def paths_coalesced(edges: Edges, m: int, absent: str = "zero") -> list[int]:
    """Path cover in which a path's weight to any other is the least of its members'; absent edges count as zero, or are ignored."""
    w = {(a, b): x for a, b, x in edges} | {(b, a): x for a, b, x in edges}
    members = {c: [c] for c in range(m)}
    between = {(a, b): x for a, b, x in edges if x > 0}
    kept = []
    while between:
        (a, b), top = max(between.items(), key=lambda e: (e[1], -e[0][0], -e[0][1]))
        if top <= 0:
            break
        ends = lambda p: (p[0], p[-1]) if len(p) > 1 else (p[0],)
        x, y = max(((x, y) for x in ends(members[a]) for y in ends(members[b])), key=lambda e: (w.get(e, 0.0), -e[0], -e[1]))
        pa_, pb = members[a], members.pop(b)
        pa_ = pa_ if pa_[-1] == x else pa_[::-1]
        members[a] = pa_ + (pb if pb[0] == y else pb[::-1])
        kept.append((x, y))
        fresh = {}
        for (p, q), v in between.items():
            if {p, q} == {a, b}:
                continue
            p2, q2 = (a if p == b else p), (a if q == b else q)
            if a in (p2, q2):
                other = q2 if p2 == a else p2
                key = (min(a, other), max(a, other))
                cross = [w.get((s, t)) for s in members[a] for t in members[other]]
                fresh[key] = min((c for c in cross if c is not None), default=0.0) if absent == "ignore" else min(0.0 if c is None else c for c in cross)
            else:
                fresh[p, q] = v
        between = {k: v for k, v in fresh.items() if v > 0}
    return _chains(kept, m)


def assignment(cost: np.ndarray) -> np.ndarray:
    """Minimum-cost assignment of rows to columns by shortest augmenting paths."""
    n = len(cost)
    u, v = np.zeros(n + 1), np.zeros(n + 1)
    match, way = np.zeros(n + 1, int), np.zeros(n + 1, int)
    for i in range(1, n + 1):
        match[0], j0 = i, 0
        least, used = np.full(n + 1, np.inf), np.zeros(n + 1, bool)
        while True:
            used[j0] = True
            i0 = match[j0]
            now = cost[i0 - 1] - u[i0] - v[1:]
            better = ~used[1:] & (now < least[1:])
            least[1:][better], way[1:][better] = now[better], j0
            free = np.where(used[1:], np.inf, least[1:])
            j1 = int(free.argmin()) + 1
            d = free[j1 - 1]
            u[match[used]] += d
            v[used] -= d
            least[1:][~used[1:]] -= d
            j0 = j1
            if not match[j0]:
                break
        while j0:
            match[j0], j0 = match[way[j0]], way[j0]
    out = np.empty(n, int)
    out[match[1:] - 1] = np.arange(n)
    return out


def matching(edges: Edges, m: int) -> list[int]:
    """Maximum-weight matching of column copies, from lower to higher columns only; matched links chain columns without circles."""
    cost = np.zeros((m, m))
    for a, b, w in edges:
        cost[min(a, b), max(a, b)] = -w
    to = assignment(cost)
    return _chains([(i, int(j)) for i, j in enumerate(to) if cost[i, j] < 0], m)


def tour(edges: Edges, m: int, seed: int = 1, restarts: int = 4, depth: int = 5) -> list[int]:
    """Tour heuristic in the style of variable-depth exchanges: greedy and nearest-neighbour starts, then or-moves and chains of 2-opt moves.

    A city of zero weight to all others closes the path to a tour, so the result is a path.
    """
    w = np.zeros((m, m))
    for a, b, x in edges:
        w[a, b] = w[b, a] = x
    rng = np.random.default_rng(seed)

    def score(o: list[int]) -> float:
        return float(w[o[:-1], o[1:]].sum())

    def nearest(start: int) -> list[int]:
        left, out = set(range(m)) - {start}, [start]
        while left:
            out.append(max(left, key=lambda c: (w[out[-1], c], -c)))
            left.remove(out[-1])
        return out

    rim = np.zeros((m + 1, m + 1))  # city m is the end of the path: no weight to any other
    rim[:m, :m] = w

    def best_reversal(o: np.ndarray) -> tuple[float, int, int]:
        """Gain of reversing o[i..j], for all i < j at once; the largest."""
        left, right = np.append(m, o[:-1]), np.append(o[1:], m)
        g = rim[left[:, None], o[None]] + rim[o[:, None], right[None]] - rim[left, o][:, None] - rim[o, right][None]
        g[np.tril_indices(m)] = -np.inf
        i, j = divmod(int(g.argmax()), m)
        return float(g[i, j]), i, j

    def moved(o: np.ndarray) -> np.ndarray:
        """One sweep of or-moves: each piece of one to three cities in turn goes to its best place, either way round, if that gains."""
        for size in (1, 2, 3):
            for i in range(m - size + 1):
                piece, rest = o[i : i + size], np.concatenate([o[:i], o[i + size :]])
                before, after = o[i - 1] if i else m, o[i + size] if i + size < m else m
                off = rim[before, after] - rim[before, piece[0]] - rim[piece[-1], after]
                a, b = np.append(m, rest), np.append(rest, m)
                best, found = 1e-12, None
                for p in (piece, piece[::-1]):
                    g = off - rim[a, b] + rim[a, p[0]] + rim[p[-1], b]
                    at = int(g.argmax())
                    if g[at] > best:
                        best, found = float(g[at]), np.concatenate([rest[:at], p, rest[at:]])
                o = o if found is None else found
        return o

    def improve(start: list[int]) -> list[int]:
        o = np.array(start)
        while True:
            total, trial, best, best_total = 0.0, o.copy(), None, 1e-12
            for _ in range(depth):  # a chain of best reversals, of which the best prefix counts
                g, i, j = best_reversal(trial)
                trial[i : j + 1] = trial[i : j + 1][::-1].copy()
                total += g
                if total > best_total:
                    best, best_total = trial.copy(), total
                if g <= 0:
                    break
            if best is None:
                best = moved(o)
                if np.array_equal(best, o):
                    return o.tolist()
            o = best

    starts = [paths(edges, m), *(nearest(int(s)) for s in rng.permutation(m)[:restarts])]
    return max((improve(s) for s in starts), key=lambda o: (score(o), [-c for c in o])) if m > 1 else list(range(m))


def identity(edges: Edges, m: int) -> list[int]:
    return list(range(m))


def reverse(edges: Edges, m: int) -> list[int]:
    return list(range(m))[::-1]


def shuffled(edges: Edges, m: int, seed: int = 1) -> list[int]:
    return np.random.default_rng(seed).permutation(m).tolist()


ALGORITHMS = {"paths": paths, "coalesced": paths_coalesced, "matching": matching, "tour": tour, "identity": identity, "reverse": reverse, "shuffled": shuffled}


def order_score(order: list[int], edges: Edges) -> float:
    w = {(a, b): x for a, b, x in edges} | {(b, a): x for a, b, x in edges}
    return sum(w.get(p, 0.0) for p in zip(order, order[1:]))


def blockwise(view: MatrixView, blocks: int = 16, algorithms: tuple[str, ...] = ("paths", "matching"), k: int = 16, codec: str = "gans", method: str = "exact", fallback: bool = True):
    """Per block, an order by each algorithm on the block's own pruned scores, compressed; the algorithm of the least total wins for the whole matrix.

    Returns (blocks of the winner, totals per algorithm). With ``fallback`` the identity competes too, since reordering may
    lose. All of a block's work is one task (a piece's, where a block is too large for one); the driver adds a number per algorithm.
    """
    from ..model import BLOCK_SCHEMA, Blocks
    from .kernel import METHODS
    from .multiply import _ARROW, block_symbols, in_pieces, pack_block, shared_values

    values, m = shared_values(view), view.m
    names = (*algorithms, "identity") if fallback else algorithms
    shared = view.rows.sparkSession.sparkContext.broadcast(values)

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("row_id")
        edges = local_edges(*_cells_of(rows), len(rows), m, k)
        out = []
        for name in names:
            order = np.array(ALGORITHMS[name](edges, m))
            ids, sym, row, used = block_symbols(rows, m, shared.value, order)
            g = METHODS[method](sym, row, len(ids), len(used) * m)
            out.append(pack_block(key[0].as_py(), ids, len(sym) + len(ids), g, codec, None if shared.value is not None else used, key[1].as_py()) | {"algorithm": name})
        return pa.Table.from_pylist(out, _ARROW.append(pa.field("algorithm", pa.string())))

    made = cut(in_pieces(view, blocks).applyInArrow(work, BLOCK_SCHEMA + ", algorithm string"))
    totals = {r.algorithm: r.b for r in made.groupBy("algorithm").agg(F.sum(F.col("c_bytes") + F.col("r_bytes") + F.col("v_bytes")).alias("b")).collect()}
    best = min(names, key=lambda a: (totals.get(a, 0), names.index(a)))
    return Blocks(made.where(F.col("algorithm") == best).drop("algorithm"), m, codec, values), totals
