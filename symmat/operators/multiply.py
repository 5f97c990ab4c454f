"""Compression into row blocks, and products on the compressed form."""

from __future__ import annotations

import math
from collections import OrderedDict
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..model import BLOCK_SCHEMA, BROADCAST_BYTES, Blocks, MatrixView, cut
from . import codec as codecs
from .kernel import METHODS, Grammar, Ready, expand, normalise

#: Bytes of symbols that one block holds; several times that is a block's peak while its grammar is built.
TARGET_BYTES = 64 << 20
_ARROW = pa.schema([
    ("block", pa.int32()), ("n_rows", pa.int64()), ("row_ids", pa.list_(pa.int64())), ("codec", pa.string()), ("width", pa.int32()), ("space", pa.int64()), ("c_len", pa.int64()), ("r_len", pa.int64()),
    ("s_len", pa.int64()), ("depth", pa.int32()), ("c", pa.binary()), ("r", pa.binary()), ("v", pa.list_(pa.float64())), ("c_bytes", pa.int64()), ("r_bytes", pa.int64()), ("v_bytes", pa.int64()), ("piece", pa.int32()),
])


def block_symbols(rows: pa.Table, m: int, values: np.ndarray | None, order: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a block's rows: row ids in order, symbols, row index of each, and the dictionary."""
    ids = rows.column("row_id").to_numpy()
    if (ids[1:] <= ids[:-1]).any():
        rows = rows.sort_by("row_id")
        ids = rows.column("row_id").to_numpy()
    cols = rows.column("cols").combine_chunks()
    vals = rows.column("vals").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float)
    row = np.repeat(np.arange(len(ids)), np.diff(cols.offsets.to_numpy()))
    col = cols.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    v = np.unique(vals) if values is None else values
    sym = 1 + np.searchsorted(v, vals) * m + col
    if order is not None:
        rank = np.empty(m, np.int64)
        rank[order] = np.arange(m)
        to = np.lexsort((rank[col], row))
        sym, row = sym[to], row[to]
    return ids, sym, row, v


def pack_block(block: int, ids: np.ndarray, s_len: int, g: Grammar, codec: str, local: np.ndarray | None, piece: int = 0) -> dict:
    c, r, width = codecs.encode(g, codec)
    v = None if local is None else np.asarray(local, float)
    depth = int(g.levels.max()) if len(g.rules) else 0
    return {"block": block, "n_rows": g.n, "row_ids": np.asarray(ids, np.int64), "codec": codec, "width": width, "space": g.space, "c_len": len(g.c) + g.n, "r_len": len(g.rules), "s_len": s_len, "depth": depth,
            "c": c, "r": r, "v": v, "c_bytes": len(c), "r_bytes": len(r), "v_bytes": 0 if v is None else 8 * len(v), "piece": piece}


def shared_values(view: MatrixView) -> np.ndarray | None:
    """The sorted distinct nonzeros if they are few enough to broadcast, else None.

    They are counted where they lie; only if they are few do they come to the driver, as packed doubles. Found once a view.
    """
    key = ("values", BROADCAST_BYTES)
    if key not in view.memo:
        view.memo[key] = _distinct(view)
    return view.memo[key]


def _distinct(view: MatrixView) -> np.ndarray | None:
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held = np.ascontiguousarray(batch.column("val").to_numpy(zero_copy_only=False), "<f8")
            yield pa.RecordBatch.from_arrays([pa.array([len(held)], pa.int64()), pa.array([held.tobytes()], pa.binary())], names=["n", "held"])

    packed = cut(view.cells.select("val").distinct().mapInArrow(pack, "n long, held binary"))
    if 8 * (packed.agg(F.sum("n")).first()[0] or 0) > BROADCAST_BYTES:
        return None
    return np.sort(np.concatenate([np.zeros(0), *(np.frombuffer(r.held, "<f8") for r in packed.select("held").collect())]))


#: Cells that a task packs at once.
PACK_CELLS = 1 << 20
#: Pieces are dealt over so many tasks at most.
MOST_TASKS = 1 << 12
_ROWS = pa.schema([("row_id", pa.int64()), ("cols", pa.list_(pa.int32())), ("vals", pa.list_(pa.float64()))])


def pack_rows(ids: np.ndarray, n: np.ndarray, cols: np.ndarray, vals: np.ndarray) -> bytes:
    """Rows as compressed bytes: ids as differences, lengths, columns, and the values column by column, where alike ones are neighbours."""
    by_column = np.argsort(cols, kind="stable")
    parts = [np.diff(ids, prepend=0).astype("<i8"), n.astype("<i4"), cols.astype("<i4"), vals[by_column].astype("<f8")]
    packed = [pa.compress(p.tobytes(), codec="zstd", asbytes=True) for p in parts]
    return np.array([len(ids), len(cols), *map(len, packed)], "<i8").tobytes() + b"".join(packed)


def unpack_rows(data: bytes) -> pa.Table:
    """What ``pack_rows`` packed, as a table (row_id, cols, vals)."""
    rows, cells, *sizes = np.frombuffer(data, "<i8", 6).tolist()
    at, parts = 48, []
    for size, kind, count in zip(sizes, ("<i8", "<i4", "<i4", "<f8"), (rows, rows, cells, cells)):
        raw = pa.decompress(data[at : at + size], decompressed_size=np.dtype(kind).itemsize * count, codec="zstd", asbytes=True) if count else b""
        parts.append(np.frombuffer(raw, kind))
        at += size
    gaps, n, cols, sorted_vals = parts
    vals = np.empty(cells)
    vals[np.argsort(cols, kind="stable")] = sorted_vals
    ends = pa.array(np.append(0, np.cumsum(n)).astype(np.int32))
    return pa.Table.from_arrays([pa.array(np.cumsum(gaps)), pa.ListArray.from_arrays(ends, pa.array(cols)), pa.ListArray.from_arrays(ends, pa.array(vals))], schema=_ROWS)


def _packed(batches: Iterator[pa.RecordBatch], each: int, tasks: int, lots: int) -> Iterator[pa.RecordBatch]:
    """Rows with their (block, piece) as one record per piece and portion of the input, for each of ``lots``."""

    def flush(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(held).combine_chunks()
        block, piece, ids = (rows.column(k).to_numpy().astype(np.int64) for k in ("block", "piece", "row_id"))
        cols, vals = rows.column("cols").combine_chunks(), rows.column("vals").combine_chunks()
        cells, values = cols.flatten().to_numpy(zero_copy_only=False), vals.flatten().to_numpy(zero_copy_only=False)
        n = np.diff(cols.offsets.to_numpy()).astype(np.int64)
        number = block * each + piece
        if (number[1:] < number[:-1]).any():
            to = np.argsort(number, kind="stable")
            first = (np.cumsum(n) - n)[to]
            block, piece, ids, n, number = block[to], piece[to], ids[to], n[to], number[to]
            at = np.repeat(first - (np.cumsum(n) - n), n) + np.arange(len(cells))
            cells, values = cells[at], values[at]
        ends = np.append(0, np.cumsum(n))
        edge = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1], [True]]))
        for a, b in zip(edge[:-1], edge[1:]):
            data = pack_rows(ids[a:b], n[a:b], cells[ends[a] : ends[b]], values[ends[a] : ends[b]])
            to = [(int(number[a]) * lots + k) % tasks for k in range(lots)]
            yield pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), pa.array([block[a]] * lots, pa.int32()), pa.array([piece[a]] * lots, pa.int32()), pa.array(range(lots), pa.int32()), pa.array([data] * lots, pa.binary())], names=["to", "block", "piece", "lot", "data"])

    held, cells = [], 0
    for batch in batches:
        if len(batch):
            held.append(batch)
            cells += len(batch) + len(batch.column("cols").flatten())
        if cells >= PACK_CELLS:
            yield from flush(held)
            held, cells = [], 0
    if held:
        yield from flush(held)


@dataclass(frozen=True)
class Pieces:
    """The rows of a view by block and piece; each piece may go to ``lots`` tasks, which share the work on it.

    Rows travel packed, column by column, as a record per piece and portion of the input; pieces are dealt evenly by number.
    """

    view: MatrixView
    blocks: int
    symbols: int | None = None
    lots: int = 1

    def applyInArrow(self, work, schema: str) -> DataFrame:  # noqa: N802  as of a grouped DataFrame
        """``work`` gets the key (block, piece, lot) and the piece's rows in order of row_id."""
        block, piece = self.view.pieces_of(self.blocks, self.symbols)
        most, each = self.view.piece_count(self.blocks, self.symbols)
        lots, tasks = self.lots, min(MOST_TASKS, most * each * self.lots)
        names = [f.name for f in StructType.fromDDL(schema)]
        rows = self.view.rows.select(block.cast("int").alias("block"), piece.cast("int").alias("piece"), "row_id", "cols", "vals")
        sent = rows.mapInArrow(lambda batches: _packed(batches, each, tasks, lots), "to int, block int, piece int, lot int, data binary")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            def done(key: tuple[int, int, int], held: list[pa.Table]) -> Iterator[pa.RecordBatch]:
                rows = pa.concat_tables(held).combine_chunks()
                held.clear()
                ids = rows.column("row_id").to_numpy()
                rows = rows if (ids[1:] > ids[:-1]).all() else rows.sort_by("row_id")
                yield from work(tuple(pa.scalar(k, pa.int32()) for k in key), rows).select(names).combine_chunks().to_batches()

            now, held = None, []
            for batch in batches:
                for i in range(len(batch)):
                    key = tuple(batch.column(k)[i].as_py() for k in ("block", "piece", "lot"))
                    if held and key != now:
                        yield from done(now, held)
                    now = key
                    held.append(unpack_rows(batch.column("data")[i].as_py()))
            if held:
                yield from done(now, held)

        dealt = sent.repartitionById(tasks, "to").sortWithinPartitions("block", "piece", "lot").drop("to")
        return dealt.mapInArrow(run, schema)


def in_pieces(view: MatrixView, blocks: int, symbols: int | None = None, lots: int = 1) -> Pieces:
    """The rows of ``view`` grouped by block and piece, for a task each."""
    return Pieces(view, blocks, symbols, lots)


def block_count(view: MatrixView, target_bytes: int = TARGET_BYTES) -> int:
    """Blocks so that none holds much more than ``target_bytes`` of symbols (4 bytes each)."""
    cells = view.rows.agg(F.sum(F.size("cols") + 1)).first()[0] or 0
    return max(1, -(-4 * cells // target_bytes))


def compress(view: MatrixView, blocks: int | None = 1, codec: str = "gpack", method: str = "exact", scope: str = "global", order: Sequence[int] | dict[int, Sequence[int]] | None = None, row_normal: bool = False, piece_symbols: int | None = None, **options) -> Blocks:
    """Row blocks of ``view``, compressed: one shuffle brings a block's rows to one task, where its grammar is built and encoded.

    ``blocks``: how many; None for blocks of bounded size (``block_count``). One that is too large for a task is built in pieces
    (``MatrixView.pieces_of``, at most ``piece_symbols`` each), ranges of its rows with a grammar each; it keeps its number. ``scope``: one dictionary for all blocks (checked to be small enough to broadcast, else as 'block'), or one per block.
    ``order``: a permutation of the columns, or one per block; decoding and products do not need it. codec 'stream' keeps
    the symbols as they are.
    """
    spark, m = view.rows.sparkSession, view.m
    blocks = block_count(view) if blocks is None else blocks
    values = shared_values(view) if scope == "global" else None
    shared = spark.sparkContext.broadcast((values, {k: np.array(o) for k, o in order.items()} if isinstance(order, dict) else None if order is None else np.array(order)))

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        v, orders = shared.value
        b = key[0].as_py()
        ids, sym, row, used = block_symbols(rows, m, v, orders.get(b) if isinstance(orders, dict) else orders)
        space = len(used) * m
        if codec == "stream":
            g = Grammar(np.zeros((0, 2), np.int64), sym, row, len(ids), space)
        else:
            g = METHODS[method](sym, row, len(ids), space, **options)
            g = normalise(g) if row_normal else g
        return pa.Table.from_pylist([pack_block(b, ids, len(sym) + len(ids), g, codec, used if v is None else None, key[1].as_py())], _ARROW)

    made = in_pieces(view, blocks, piece_symbols).applyInArrow(work, BLOCK_SCHEMA)
    return Blocks(made, m, codec, values)


#: Blocks that a worker keeps decoded between products, and the bytes they may take.
_READY: OrderedDict[tuple[str, int, int], tuple[Ready, np.ndarray]] = OrderedDict()
KEEP_BYTES = 512 << 20


def _at(batch: pa.RecordBatch, i: int, name: str):
    return batch.column(name)[i].as_py()


def _numbers(batch: pa.RecordBatch, i: int, name: str) -> np.ndarray | None:
    cell = batch.column(name)[i]
    return cell.values.to_numpy(zero_copy_only=False) if cell.is_valid else None


def _grammar(batch: pa.RecordBatch, i: int) -> Grammar:
    return codecs.decode(*(_at(batch, i, k) for k in ("codec", "c", "r", "width", "c_len", "r_len", "space")))


def _ready(g_uid: str, batch: pa.RecordBatch, i: int, m: int, values: np.ndarray | None) -> tuple[Ready, np.ndarray]:
    """Block i of a batch, decoded. Kept while there is room: blocks of other matrices make room, oldest first; of one matrix
    those met first stay, so that scan after scan finds the same ones."""
    key = (g_uid, _at(batch, i, "block"), _at(batch, i, "piece"))
    if key in _READY:
        return _READY[key]
    own = _numbers(batch, i, "v")
    found = Ready(_grammar(batch, i), m, values if own is None else own), _numbers(batch, i, "row_ids").astype(np.int64)
    size = found[0].nbytes + found[1].nbytes
    held = sum(r.nbytes + ids.nbytes for r, ids in _READY.values())
    for other in [k for k in _READY if k[0] != g_uid]:
        if held + size <= KEEP_BYTES:
            break
        r, ids = _READY.pop(other)
        held -= r.nbytes + ids.nbytes
    if held + size <= KEEP_BYTES:
        _READY[key] = found
    return found


def _each(g: Blocks, extra):
    """Runs over the blocks of a task, piece by piece: (block number, ready block, row ids, what was broadcast)."""
    uid, m, shared = g.uid, g.m, g.shared

    def blocks(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(len(batch)):
                ready, ids = _ready(uid, batch, i, m, shared.value)
                yield _at(batch, i, "block"), ready, ids, extra.value

    return blocks


def _broadcast(g: Blocks, extra):
    return g.df.sparkSession.sparkContext.broadcast(extra)


def right(g: Blocks, x: np.ndarray) -> DataFrame:
    """y = Mx on the blocks: (row_id, y), or (row_id, y array) for an m x k matrix x. No shuffle; x (m numbers) is broadcast."""
    x = np.asarray(x, float)
    each = _each(g, _broadcast(g, x))

    def run(batches):
        for _, ready, ids, vec in each(batches):
            y = ready.right(vec)
            out = pa.array(y) if y.ndim == 1 else _lists(y)
            yield pa.RecordBatch.from_arrays([pa.array(ids), out], names=["row_id", "y"])

    return g.df.mapInArrow(run, "row_id long, y double" if x.ndim == 1 else "row_id long, y array<double>")


def _lists(y: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(np.arange(len(y) + 1, dtype=np.int32) * y.shape[1], pa.array(y.ravel()))


def _partials(g: Blocks, work, extra, width: int) -> DataFrame:
    """One vector of ``width`` numbers per task: the sum over its blocks, in block order."""
    each = _each(g, extra)

    def run(batches):
        total, first = np.zeros(width), None
        for block, ready, ids, vec in each(batches):
            total, first = total + work(ready, ids, vec, block), (block, int(ids.min(initial=0))) if first is None else first
        if first is not None:
            yield pa.RecordBatch.from_arrays([pa.array([first[0]], pa.int32()), pa.array([first[1]], pa.int64()), _lists(total[None])], names=["block", "row_id", "x"])

    return g.df.mapInArrow(run, "block int, row_id long, x array<double>")


def _sum(g: Blocks, work, extra, width: int) -> np.ndarray:
    """The sum of the tasks' partial vectors, in block order; where they would weigh too much on the driver, first per position.

    What was broadcast for it is given back at the end.
    """
    shared = _broadcast(g, extra)
    parts = _partials(g, work, shared, width)
    if parts.rdd.getNumPartitions() * width * 8 > BROADCAST_BYTES:
        col = parts.select("block", F.posexplode("x").alias("col", "x")).groupBy("col").agg(F.sum("x").alias("x"))
        out = np.zeros(width)
        for r in col.toLocalIterator():
            out[r.col] = r.x
    else:
        out = sum((np.array(r.x) for r in sorted(parts.collect(), key=lambda r: (r.block, r.row_id))), np.zeros(width))
    shared.unpersist()
    return out


def left(g: Blocks, y: DataFrame) -> DataFrame:
    """y'M on the blocks: (col, x); y as (row_id, y), or (row_id, y array of k) for k vectors at once, x then being an array.

    Each piece of a block meets its part of y by a join on both numbers; then m partial sums a piece are added.
    """
    many = dict(y.dtypes)["y"].startswith("array")
    spans = g.df.select("block", "piece", F.explode("row_ids").alias("row_id"))
    own = spans.join(y, "row_id").groupBy("block", "piece").agg(F.array_sort(F.collect_list(F.struct("row_id", "y"))).alias("ys"))
    joined = g.df.join(own.select("block", "piece", F.col("ys.y").alias("ys"), F.col("ys.row_id").alias("yids")), ["block", "piece"], "left")
    shared, uid, m = g.shared, g.uid, g.m

    def run(batches):
        for batch in batches:
            for i in range(len(batch)):
                ready, ids = _ready(uid, batch, i, m, shared.value)
                at, given = _numbers(batch, i, "yids"), batch.column("ys")[i]
                if at is None:
                    continue
                if many:
                    vec = given.values.flatten().to_numpy(zero_copy_only=False).reshape(len(at), -1)
                    part = np.zeros((len(ids), vec.shape[1]))
                else:
                    vec, part = given.values.to_numpy(zero_copy_only=False), np.zeros(len(ids))
                part[np.searchsorted(ids, at)] = vec
                x = ready.left(part)
                if not many:
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(m, dtype=np.int32)), pa.array(x)], names=["col", "x"])
                else:
                    k = x.shape[1]
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(m, dtype=np.int32), k)), pa.array(np.tile(np.arange(k, dtype=np.int32), m)), pa.array(x.ravel())], names=["col", "at", "x"])

    if not many:
        return joined.mapInArrow(run, "col int, x double").groupBy("col").agg(F.sum("x").alias("x"))
    each = joined.mapInArrow(run, "col int, at int, x double").groupBy("col", "at").agg(F.sum("x").alias("x"))
    return each.groupBy("col").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda e: e["x"]).alias("x"))


def left_by(g: Blocks, y_of) -> np.ndarray:
    """y'M where y is a function of the row ids (a vectorised formula, importable on the workers): nothing but m numbers a task travels."""
    return _sum(g, lambda ready, ids, f, _: ready.left(f(ids).astype(float)), y_of, g.m)


def gram_apply(g: Blocks, x: np.ndarray) -> np.ndarray:
    """M'(Mx) in one pass: each block's y stays in its task."""
    return _sum(g, lambda ready, ids, v, _: ready.left(ready.right(v)), np.asarray(x, float), g.m)


def iterate(g: Blocks, x0: np.ndarray, rounds: int = 500) -> tuple[np.ndarray, list[float]]:
    """Rounds of y = Mx, z = y'M, x = z / max|z|; the norms too. A zero z ends it with x = 0. A round broadcasts x and adds the tasks' vectors; the dictionary was sent before."""
    x, norms = np.asarray(x0, float), []
    for _ in range(rounds):
        z = gram_apply(g, x)
        top = float(np.abs(z).max()) if len(z) else 0.0
        norms.append(top)
        if not top:
            return np.zeros_like(z), norms
        x = z / top
    return x, norms


def cgls(g: Blocks, b: DataFrame, rounds: int = 50, tolerance: float = 1e-10) -> np.ndarray:
    """Least squares min |Mx - b| by conjugate gradient on the normal equations; one fused pass a round."""
    r = np.zeros(g.m)
    for row in left(g, b).collect():
        r[row.col] = row.x
    x, p, rr = np.zeros(g.m), r.copy(), float(r @ r)
    start = rr
    for _ in range(rounds):
        if rr <= tolerance**2 * max(start, 1e-300):
            break
        q = gram_apply(g, p)
        a = rr / float(p @ q)
        x, r = x + a * p, r - a * q
        new = float(r @ r)
        p, rr = r + new / rr * p, new
    return x


def ones(ids: np.ndarray) -> np.ndarray:
    return np.ones(len(ids))


def column_sums(g: Blocks) -> np.ndarray:
    return left_by(g, ones)


def row_sums(g: Blocks) -> DataFrame:
    return right(g, np.ones(g.m))


def norms(g: Blocks) -> DataFrame:
    """(col, x): the Euclidean norm of every column, from how many rows hold each terminal: the grammar is walked once."""
    squares = symbol_sums(g, ones).groupBy("col").agg(F.sqrt(F.sum(F.col("val") * F.col("val") * F.col("total"))).alias("x"))
    every = g.df.sparkSession.range(g.m).select(F.col("id").cast("int").alias("col"))
    return every.join(squares, "col", "left").select("col", F.coalesce("x", F.lit(0.0)).alias("x"))


def transposed(g: Blocks) -> Transposed:
    """M' without moving a cell: its right product is the left product of M, and the other way round."""
    return Transposed(g)


class Transposed:
    def __init__(self, g: Blocks) -> None:
        self.blocks = g

    def right(self, y: DataFrame) -> DataFrame:
        return left(self.blocks, y)

    def left(self, x: np.ndarray) -> DataFrame:
        return right(self.blocks, x)

    def transposed(self) -> Blocks:
        return self.blocks


def scale(g: Blocks, factor: float) -> Blocks:
    """factor * M: only the dictionary changes. (A factor of zero would make stored cells zero, and is refused.)"""
    if factor == 0 or not math.isfinite(factor):
        raise ValueError("factor must be finite and not zero")
    df = g.df.withColumn("v", F.transform("v", lambda v: v * factor))
    return Blocks(df, g.m, g.codec, None if g.values is None else np.asarray(g.values) * factor)


def decode(g: Blocks, ids: Sequence[int] | None = None) -> DataFrame:
    """The long matrix (row_id, col, val), or only the rows ``ids``: blocks are pruned by their row ids, rows before expansion."""
    df = g.df if ids is None else g.df.where(F.arrays_overlap("row_ids", F.lit(list(ids))))
    shared, m, wanted = g.shared, g.m, None if ids is None else np.array(list(ids))

    def run(batches):
        for batch in batches:
            for i in range(len(batch)):
                gr, own = _grammar(batch, i), _numbers(batch, i, "row_ids").astype(np.int64)
                c, r = gr.c, gr.row
                if wanted is not None:
                    keep = np.isin(own[r], wanted)
                    c, r = c[keep], r[keep]
                c, r = expand(gr, c, r)
                v = _numbers(batch, i, "v")
                v = shared.value if v is None else v
                yield pa.RecordBatch.from_arrays([pa.array(own[r]), pa.array(((c - 1) % m).astype(np.int32)), pa.array(v[(c - 1) // m] if len(c) else np.zeros(0))], names=["row_id", "col", "val"])

    return df.mapInArrow(run, "row_id long, col int, val double")


def symbol_sums(g: Blocks, y_of) -> DataFrame:
    """(col, val, total): for each distinct terminal, the sum of y over the rows that hold it, by one backward pass a block."""
    each = _each(g, _broadcast(g, y_of))

    def run(batches):
        for _, ready, ids, f in each(batches):
            s = ready.symbol_sums(f(ids).astype(float))[: len(ready.used)]
            yield pa.RecordBatch.from_arrays([pa.array(ready.col.astype(np.int32)), pa.array(ready.value), pa.array(s)], names=["col", "val", "total"])

    return g.df.mapInArrow(run, "col int, val double, total double").groupBy("col", "val").agg(F.sum("total").alias("total"))


def symbol_values(g: Blocks, x: np.ndarray) -> DataFrame:
    """(block, symbol, w): Val of every used terminal and rule of each block under x; symbols are numbered in each piece of a block."""
    each = _each(g, _broadcast(g, np.asarray(x, float)))

    def run(batches):
        for block, ready, _, vec in each(batches):
            w = ready.symbol_values(vec)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(w), block, np.int32)), pa.array(np.arange(len(w))), pa.array(w)], names=["block", "symbol", "w"])

    return g.df.mapInArrow(run, "block int, symbol long, w double")


def reach(g: Blocks) -> DataFrame:
    """(block, symbol, row_id): the rows whose expansion holds each used terminal or rule; for inspection, its size is that of all expansions."""
    each = _each(g, _broadcast(g, None))

    def run(batches):
        for block, ready, ids, _ in each(batches):
            t = len(ready.used)
            sym, row = ready.c, ready.row
            parts = [(sym, row)]
            while len(sym := sym[(is_rule := sym >= t)]):
                row = np.repeat(row[is_rule], 2)
                sym = ready.rules[sym - t].ravel()
                parts.append((sym, row))
            s, r = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
            col = np.where(s < t, ready.col[np.minimum(s, t - 1)], -1) if t else s
            val = np.where(s < t, ready.value[np.minimum(s, t - 1)], np.nan) if t else s.astype(float)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), block, np.int32)), pa.array(s.astype(np.int64)), pa.array(ids[r]), pa.array(col.astype(np.int32)), pa.array(val)], names=["block", "symbol", "row_id", "col", "val"])

    return g.df.mapInArrow(run, "block int, symbol long, row_id long, col int, val double")
