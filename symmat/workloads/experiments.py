"""The experiments: size tables, product loops over codecs and block counts, reordering sweeps, rival comparison.

Each function takes the stand-ins to run; the registered queries run every stand-in, a query each. Seconds and resident
sizes are measured; sizes, vectors and orders are the same at every run.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Blocks, MatrixView, adopt, cut, outer, scratch, stored
from ..operators import baseline, encode, measure, multiply, reorder
from ..operators.kernel import METHODS
from ..plans import choose
from ..sources import matrices as src
from . import standins

CODECS = ("stream", "g32", "gpack", "gans")
BLOCKS = (1, 4, 8, 12, 16)
#: Rounds of the product loop in a registered query; the benchmark of the reference takes 500.
ROUNDS = 5
#: Stand-ins with several related columns, for the reordering sweeps.
REORDERED = ("lineitem_dense", "lineitem_measures", "lineitem_onehot", "star_codes", "events_user_day", "doc_chars", "nation_adjacency", "embeddings_q1")
HASHED = 784
#: Jobs of the size table that run side by side.
JOBS = 4
#: Tasks a core over which the orders of few pieces are shared out.
LOTS = 4


def _tidy(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(str(a), str(b), str(c), float(v)) for a, b, c, v in rows], "matrix string, method string, metric string, value double")


def _view(spark: SparkSession, sf_dir: str, name: str) -> MatrixView:
    """A stand-in's rows, materialised; the numbered table behind them is given back. To be called in a ``scratch``."""
    with scratch(spark):
        v = standins.view(spark, sf_dir, name)
        with outer():
            rows = stored(v.rows)
    return MatrixView(rows, v.m, v.names)


def _mean(view: MatrixView, nbytes: float) -> float:
    return measure.size_pct(nbytes, view.n, view.m)


def sizes(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = standins.NAMES, blocks: int = 1, byte_blocks: int = 8) -> DataFrame:
    """Features, and sizes in percent of dense under every method; byte compressors run over ``byte_blocks`` row blocks.

    Lines are numbered once for all their stand-ins. The measures are jobs of their own, a few at a time, so that
    cores do not wait for the slowest compressor of one stand-in; those with most to compress begin.
    """
    views: dict[str, MatrixView] = {}

    def compressed(name: str) -> list[tuple]:
        v = views[name]
        both = baseline.byte_sizes(v, ("gzip", "xz"), byte_blocks).groupBy("method").agg(F.sum("bytes").alias("b")).union(baseline.sparse_sizes(v))
        return [(name, r.method, "size_pct", _mean(v, r.b)) for r in both.collect()]

    def coded(name: str) -> list[tuple]:
        return [(name, c, "size_pct", p) for c, p in choose.report(views[name], blocks).items() if c != "stream"]

    def looked_at(name: str) -> list[tuple]:
        f = measure.features(views[name]).first()
        return [(name, "matrix", k, f[k]) for k in ("n", "m", "nonzero_pct", "distinct")]

    def materialised(v: MatrixView) -> MatrixView:
        kept = MatrixView(stored(v.rows), v.m, v.names)
        kept.n  # noqa: B018  counted before the long jobs
        return kept

    works = (looked_at, compressed, coded)
    with scratch(spark) as own, ThreadPoolExecutor(JOBS, initializer=adopt, initargs=(own,)) as pool:
        with scratch(spark):
            lines = standins.numbered_lines(spark, sf_dir)
            made = {name: pool.submit(inheritable_thread_target(spark)(materialised), standins.view(spark, sf_dir, name, lines)) for name in names}
            views |= {name: f.result() for name, f in made.items()}
        by_size = sorted(names, key=lambda name: -views[name].n * views[name].m)
        found = {(name, work): pool.submit(inheritable_thread_target(spark)(work), name) for work in (compressed, coded, looked_at) for name in by_size}
        rows = [r for name in names for work in works for r in found[name, work].result()]
    return _tidy(spark, rows)


def counted_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of the size table that follows from counts, in bytes, for every stand-in: dense, csr, csr_iv and stream."""
    out = None
    for name in standins.NAMES:
        one = baseline.sparse_sizes(standins.view(spark, sf_dir, name)).select(F.lit(name).alias("matrix"), "method", "bytes")
        out = one if out is None else out.union(one)
    return out


def counted_sizes_sql() -> str:
    parts = []
    for name in standins.NAMES:
        m = standins.width(name)
        parts.append(
            f"SELECT '{name}' AS matrix, unnest(['csr', 'csr_iv', 'stream', 'dense']) AS method, unnest([12 * t + 8 * (n + 1), (4 + CASE WHEN v < 65536 THEN 2 ELSE 4 END) * t + 8 * (n + 1) + 8 * v, 4 * (t + n) + 8 * v, 8 * n * {m}])::BIGINT AS bytes"
            f" FROM (SELECT count(*) AS t, count(DISTINCT val) AS v, (SELECT count(*) FROM ({standins.rows_sql(name)}) r) AS n FROM ({standins.long_sql(name)}) c) z"
        )
    return " UNION ALL ".join(parts)


def _of_codec(every: Blocks, codec: str) -> Blocks:
    return Blocks(every.df.where(F.col("codec") == codec), every.m, codec, every.values)


def loop_vectors(spark: SparkSession, sf_dir: str, name: str, codecs: tuple[str, ...] = CODECS, blocks: tuple[int, ...] = BLOCKS, rounds: int = 3) -> DataFrame:
    """(codec, blocks, col, x): the loop's vector after ``rounds`` rounds, which must be the dense one for every codec and block count."""
    rows = []
    v = standins.view(spark, sf_dir, name)
    v = MatrixView(cut(v.rows), v.m, v.names)
    for b in blocks:
        every = choose.candidates(v, b, codecs)
        for codec in codecs:
            x, _ = multiply.iterate(_of_codec(every, codec), np.ones(v.m), rounds)
            rows += [(codec, b, c, round(float(z), 6) + 0.0) for c, z in enumerate(x) if round(float(z), 6)]
    return spark.createDataFrame(rows, "codec string, blocks int, col int, x double")


def loops(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = standins.NAMES, codecs: tuple[str, ...] = CODECS, blocks: tuple[int, ...] = BLOCKS, rounds: int = ROUNDS, peaks: tuple[int, ...] = (1,)) -> DataFrame:
    """Seconds a round, memory and speed-up of the product loop by codec and number of blocks.

    seconds: of the fused product in its task, decoded blocks at hand, mean of ``rounds``; of several blocks the slowest, as they
    run side by side, the pieces of a block one after the other. size_pct, memory_pct and gap_pct: encoded bytes, what the product needs by count, and the difference.
    peak_pct: what fresh processes took beyond what they held before, decoding and multiplying, summed over the blocks.
    speed_up and memory_ratio compare with the first block count.
    """
    rows: list[tuple] = []
    for name in names:
        with scratch(spark):
            rows += _looped(_view(spark, sf_dir, name), name, codecs, blocks, rounds, peaks)
    return _tidy(spark, rows)


#: What of a piece the loop experiment looks at.
_FACTS = ("block", "codec", "r_len", "c_bytes", "r_bytes", "v_bytes", "seconds")


def _measured(m: int):
    """The facts of the pieces, and under gpack and gans their resident sizes."""
    schema = "block int, codec string, r_len long, c_bytes long, r_bytes long, v_bytes long, seconds double, base_kb long, encoded_kb long, peak_kb long"
    return lambda made, shared: made.mapInArrow(measure.peaks_of_pieces(m, shared, codecs=("gpack", "gans"), kept=_FACTS), schema)


def _looped(v: MatrixView, name: str, codecs: tuple[str, ...], blocks: tuple[int, ...], rounds: int, peaks: tuple[int, ...]) -> list[tuple]:
    rows: list[tuple] = []
    first: dict[tuple, float] = {}
    for b in blocks:
        # the encoded pieces go from the task that makes them to the processes that measure them; numbers alone are kept
        every = choose.candidates(v, b, codecs, rounds, ready=True, keep=_measured(v.m) if b in peaks else lambda made, _: made.select(*_FACTS))
        own = every.df.groupBy("codec", "block").agg(F.sum("seconds").alias("seconds"), F.sum(F.col("c_bytes") + F.col("r_bytes") + F.col("v_bytes")).alias("bytes"), F.sum("r_len").alias("rules"))
        facts = own.groupBy("codec").agg(F.max("seconds").alias("s"), F.sum("bytes").alias("bytes"), F.sum("rules").alias("rules"), F.count("*").alias("blocks"))
        for r in facts.collect():
            key = f"{r.codec}/{b}"
            encoded = r.bytes + (8 * len(every.values) if every.values is not None else 0)
            total = measure.product_bytes(encoded, r.rules, v.n, v.m, r.blocks)
            first.setdefault((r.codec, "s"), r.s)
            first.setdefault((r.codec, "m"), total)
            rows += [(name, key, "seconds", r.s), (name, key, "speed_up", first[r.codec, "s"] / max(1e-9, r.s)), (name, key, "size_pct", _mean(v, encoded))]
            rows += [(name, key, "memory_pct", _mean(v, total)), (name, key, "gap_pct", _mean(v, total - encoded)), (name, key, "memory_ratio", total / first[r.codec, "m"])]
        if b in peaks:
            for r in measure.peaks_of_blocks(every.df.where(F.col("peak_kb").isNotNull())).groupBy("codec").agg(F.sum(F.col("peak_kb") - F.col("base_kb")).alias("kb")).collect():
                rows.append((name, f"{r.codec}/{b}", "peak_pct", _mean(v, 1024 * r.kb)))
    return rows


def sizes_of_orders(view: MatrixView, orders: list[tuple[int, ...]], codec: str = "gans", blocks: int = 1) -> list[int]:
    """Bytes of the matrix under each column order, all orders in one job: a piece's rows come to a task once, which tries every order; the orders of few pieces are shared out."""
    values, m = multiply.shared_values(view), view.m
    sc = view.rows.sparkSession.sparkContext
    shared = sc.broadcast((values, [np.array(o) for o in orders]))
    most, each = view.piece_count(blocks)
    lots = max(1, min(len(orders), -(-LOTS * sc.defaultParallelism // (most * each))))

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        v, own = shared.value
        ids, sym, row, used = multiply.block_symbols(rows, m, v, None)
        col, found = (sym - 1) % m, []
        at = range(key[2].as_py(), len(own), lots)
        for i in at:
            rank = np.empty(m, np.int64)
            rank[own[i]] = np.arange(m)
            to = np.argsort(row * m + rank[col])
            g = METHODS["exact"](sym[to], row, len(ids), len(used) * m)
            p = multiply.pack_block(0, ids[:0], 0, g, codec, None if v is not None else used)
            found.append(p["c_bytes"] + p["r_bytes"] + p["v_bytes"])
        return pa.table({"at": pa.array(at, pa.int32()), "bytes": pa.array(found, pa.int64())})

    made = multiply.in_pieces(view, blocks, lots=lots).applyInArrow(work, "at int, bytes long")
    found = {r["at"]: r.b for r in made.groupBy("at").agg(F.sum("bytes").alias("b")).collect()}
    fixed = 8 * len(values) if values is not None else 0
    return [found.get(i, 0) + fixed for i in range(len(orders))]


def reordering(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = REORDERED, algorithms: tuple[str, ...] = ("tour", "paths", "matching", "coalesced"), ks: tuple[int, ...] = (4, 8, 16), codec: str = "gans") -> DataFrame:
    """Sizes after each ordering and pruning (local and global by k, and none), the ordering's seconds and score; the given order for comparison."""
    rows: list[tuple] = []
    for name in names:
        with scratch(spark):
            rows += _reordered(_view(spark, sf_dir, name), name, algorithms, ks, codec)
    return _tidy(spark, rows)


def _reordered(v: MatrixView, name: str, algorithms: tuple[str, ...], ks: tuple[int, ...], codec: str) -> list[tuple]:
    rows: list[tuple] = []
    scores = cut(reorder.similarity(v))
    every = reorder.edges_of(scores)
    graphs = {f"local/{k}": reorder.edges_of(reorder.prune_local(scores, k)) for k in ks} | {f"global/{k}": reorder.edges_of(reorder.prune_global(scores, k, v.m)) for k in ks} | {"full": every}
    orders = {("identity", "-"): tuple(range(v.m))}
    for a in algorithms:
        for label, edges in graphs.items():
            start = time.perf_counter()
            orders[a, label] = tuple(reorder.ALGORITHMS[a](edges, v.m))
            rows.append((name, f"{a}/{label}", "seconds", time.perf_counter() - start))
            rows.append((name, f"{a}/{label}", "score", reorder.order_score(list(orders[a, label]), every)))
    distinct = sorted(set(orders.values()))
    size = dict(zip(distinct, sizes_of_orders(v, distinct, codec)))
    rows += [(name, f"{a}/{label}", "size_pct", _mean(v, size[o])) for (a, label), o in orders.items()]
    return rows


def rivals(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = REORDERED, blocks: int = 16, k: int = 16, rounds: int = ROUNDS) -> DataFrame:
    """Blockwise reordered grammars against column groups and the given order: size, seconds to compress, seconds a round of the loop, memory and its gain."""
    rows: list[tuple] = []
    for name in names:
        v = standins.view(spark, sf_dir, name)
        v = MatrixView(cut(v.rows), v.m, v.names)
        x = np.ones(v.m)
        for codec in ("gpack", "gans"):
            plain = multiply.compress(v, blocks, codec).prepared()
            start = time.perf_counter()
            g, totals = reorder.blockwise(v, blocks, k=k, codec=codec)
            g = g.prepared()
            rows.append((name, f"{codec}/blockwise", "compress_seconds", time.perf_counter() - start))
            used = {}
            for label, h in (("blockwise", g), ("given", plain)):
                multiply.iterate(h, x, 1)
                memory = measure.memory_model(h, v.n)
                used[label] = memory["total"]
                rows += [(name, f"{codec}/{label}", "seconds", measure.timing(lambda h=h: multiply.iterate(h, x, rounds)) / rounds), (name, f"{codec}/{label}", "size_pct", _mean(v, memory["encoded"])), (name, f"{codec}/{label}", "memory_pct", memory["pct"])]  # noqa: B023
                h.release()
            rows.append((name, f"{codec}/blockwise", "memory_gain", measure.improvement(used["given"], used["blockwise"])))
            rows += [(name, f"{codec}/{a}", "total_bytes", b) for a, b in totals.items()]
        start = time.perf_counter()
        groups = baseline.column_groups(v, blocks).prepared()
        stored = sum(groups.sizes.values())
        rows.append((name, "column_groups", "compress_seconds", time.perf_counter() - start))
        baseline.groups_gram(groups, x)
        s = measure.timing(lambda: baseline.groups_gram(groups, x), rounds)  # noqa: B023
        rows += [(name, "column_groups", "seconds", s), (name, "column_groups", "size_pct", _mean(v, stored)), (name, "column_groups", "memory_pct", _mean(v, stored + 8 * (v.n + v.m)))]
    return _tidy(spark, rows)


def entropy_slack(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = REORDERED, orders: tuple[int, ...] = (0, 1, 2)) -> DataFrame:
    """Bits of the encoded grammar against the stream's entropy bounds."""
    rows: list[tuple] = []
    for name in names:
        with scratch(spark):
            v = _view(spark, sf_dir, name)
            with scratch(spark):  # the dictionary
                codes = encode.dictionary(v)
                with outer():
                    s, marks = stored(encode.stream(v, codes)), encode.row_marks(v)
            bits = 8 * (measure.size(g := multiply.compress(v, 1, "gans").prepared()) - 8 * len(g.values if g.values is not None else ()))
            for k in orders:
                e = stored(measure.entropy(s, k, marks)).first()  # what an order shuffles goes before the next
                rows += [(name, f"order {k}", "bound_bits", e.total * e.h), (name, f"order {k}", "grammar_bits", bits), (name, f"order {k}", "slack", bits / max(1e-9, e.total * e.h))]
            g.release()
    return _tidy(spark, rows)


def ordering_times(spark: SparkSession, sf_dir: str, algorithms: tuple[str, ...] = ("paths", "matching", "tour")) -> DataFrame:
    """Seconds of the ordering algorithms at full width: character counts, and words hashed into 784 columns."""
    rows = []
    wide = {"doc_chars": standins.view(spark, sf_dir, "doc_chars"), f"hashed_words_{HASHED}": src.from_hashed_words(src.table(spark, sf_dir, "documents"), "text", HASHED, "doc_id")}
    for name, v in wide.items():
        v = MatrixView(cut(v.rows), v.m, v.names)
        edges = reorder.edges_of(reorder.prune_local(reorder.similarity(v, "block", blocks=16), 16))
        rows += [(name, "columns", "m", v.m), *((name, a, "seconds", measure.timing(lambda a=a: reorder.ALGORITHMS[a](edges, v.m))) for a in algorithms)]  # noqa: B023
    return _tidy(spark, rows)


def _each(function, names):
    return {f"w_{function.__name__}_{name}": (lambda spark, d, f=function, n=name: f(spark, d, (n,))) for name in names}


QUERIES = {
    "w_sizes": sizes, "w_ordering_times": ordering_times,
    **_each(loops, standins.NAMES), **_each(reordering, REORDERED), **_each(rivals, REORDERED), **_each(entropy_slack, REORDERED),
}
