"""Baselines: dense doubles, byte compressors, sparse rows, and compression by groups of correlated columns."""

from __future__ import annotations

import bz2
import lzma
import zlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MatrixView, cut
from .multiply import in_pieces

#: Symbols of a piece that is a whole block.
WHOLE = 1 << 62


def dense_bytes(n: int, m: int) -> int:
    return 8 * n * m


def _gzip(data: bytes) -> int:
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return len(z.compress(data)) + len(z.flush())


def _huffman(data: bytes) -> int:
    """Bytes of an optimal prefix code over byte values: code lengths by repeated merging, plus one length byte a symbol."""
    import heapq

    counts = [int(c) for c in np.bincount(np.frombuffer(data, np.uint8), minlength=256) if c]
    total, heap = 0, counts[:]
    heapq.heapify(heap)
    while len(heap) > 1:
        both = heapq.heappop(heap) + heapq.heappop(heap)
        total += both
        heapq.heappush(heap, both)
    return -(-max(total, len(data) if len(counts) == 1 else 0) // 8) + len(counts)


def _runs(data: bytes) -> int:
    """Run-length code of the doubles: 8 bytes a value and 4 a length."""
    v = np.frombuffer(data, "<u8")
    return 12 * (1 + int((v[1:] != v[:-1]).sum())) if len(v) else 0


COMPRESSORS = {"gzip": _gzip, "xz": lambda d: len(lzma.compress(d, preset=6)), "bz2": lambda d: len(bz2.compress(d)), "huffman": _huffman, "rle": _runs}


def byte_sizes(view: MatrixView, names: tuple[str, ...] = ("gzip", "xz"), blocks: int = 1) -> DataFrame:
    """(block, method, bytes) of byte compressors over each block's row-major doubles; a task per block and method."""
    m = view.m

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        name = names[key[2].as_py()]
        size = COMPRESSORS[name](memoryview(_dense(rows, m)).cast("B"))
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "method": pa.array([name]), "bytes": pa.array([size], pa.int64())})

    return in_pieces(view, blocks, WHOLE, len(names)).applyInArrow(work, "block int, method string, bytes long")


def sparse_sizes(view: MatrixView) -> DataFrame:
    """(method, bytes) of csr (8 + 4 bytes a nonzero), csr_iv (codes of 2 or 4 bytes) and the symbol stream, from counts alone."""
    f = view.cells.agg(F.count("*").alias("t"), F.count_distinct("val").alias("v"))
    n = view.n
    first = 8 * (n + 1)
    code = F.when(F.col("v") < 1 << 16, 2).otherwise(4)
    each = {"csr": 12 * F.col("t") + first, "csr_iv": (4 + code) * F.col("t") + first + 8 * F.col("v"), "stream": 4 * (F.col("t") + n) + 8 * F.col("v"), "dense": F.lit(dense_bytes(n, view.m))}
    return f.select(F.explode(F.array(*[F.struct(F.lit(k).alias("method"), e.cast("long").alias("bytes")) for k, e in each.items()])).alias("x")).select("x.*")


@dataclass(frozen=True, eq=False)
class ColumnGroups:
    """``groups``: tuples of columns. ``encoded``: a row per piece of a block: block, row_ids, parts (an array, one struct a
    group: scheme, tuples, lengths, data), bytes, piece."""

    groups: tuple[tuple[int, ...], ...]
    encoded: DataFrame
    m: int

    @property
    def sizes(self) -> dict[str, int]:
        """Bytes by group, over all blocks, as stored."""
        each = self.encoded.select(F.posexplode("parts").alias("g", "p")).groupBy("g").agg(F.sum("p.bytes").alias("b")).collect()
        return {",".join(map(str, self.groups[r.g])): r.b for r in each}

    def schemes(self) -> DataFrame:
        """(g, scheme, blocks, bytes): what each group's blocks are stored as."""
        return self.encoded.select("block", F.posexplode("parts").alias("g", "p")).groupBy("g", "p.scheme").agg(F.count_distinct("block").alias("blocks"), F.sum("p.bytes").alias("bytes"))

    def prepared(self) -> ColumnGroups:
        return replace(self, encoded=cut(self.encoded).persist())


SCHEMES = ("offsets", "runs", "codes", "raw")
_PART = pa.struct([("scheme", pa.string()), ("tuples", pa.binary()), ("lengths", pa.binary()), ("data", pa.binary()), ("bytes", pa.int64())])
_PART_SQL = "scheme string, tuples binary, lengths binary, data binary, bytes long"


def _costs(n: int, width: int, distinct: int, held: int, runs: int) -> dict[str, float]:
    """Bytes of each scheme for a group: offset lists per tuple, runs per tuple, one code a row, raw values."""
    return {"offsets": 4 * held + (8 * width + 4) * distinct, "runs": 8 * runs + (8 * width + 4) * distinct, "codes": _code_type(distinct).itemsize * n + 8 * width * distinct, "raw": 8 * n * width}


def _code_type(distinct: int) -> np.dtype:
    """Codes 0 (all zero) to ``distinct``."""
    return np.dtype("u1" if distinct < 255 else "<u2" if distinct < (1 << 16) - 1 else "<u4")


def encode_group(x: np.ndarray, scheme: str | None = None) -> dict:
    """One group of columns (n x width) of one block, in the scheme given or the smallest. Rows of zeros are not held, but in ``raw``."""
    n, width = x.shape
    tuples, code = np.unique(x, axis=0, return_inverse=True)
    code = code.reshape(-1)
    zero = ~(tuples != 0).any(axis=1)
    number = np.cumsum(~zero) * ~zero  # 0 for the tuple of zeros, 1.. for the others
    code, tuples = number[code], tuples[~zero]
    held = np.flatnonzero(code)
    order = held[np.argsort(code[held], kind="stable")]
    own = code[order]
    fresh = np.ones(len(order), bool)
    fresh[1:] = (own[1:] != own[:-1]) | (order[1:] != order[:-1] + 1)
    cost = _costs(n, width, len(tuples), len(held), int(fresh.sum()))
    scheme = min(cost, key=cost.get) if scheme is None else scheme
    lengths = b""
    if scheme == "offsets":
        lengths, data = np.bincount(own, minlength=len(tuples) + 1)[1:].astype("<u4").tobytes(), order.astype("<u4").tobytes()
    elif scheme == "runs":
        first = np.flatnonzero(fresh)
        size = np.diff(np.append(first, len(order)))
        lengths = np.bincount(own[first], minlength=len(tuples) + 1)[1:].astype("<u4").tobytes()
        data = np.stack([order[first], size], axis=1).astype("<u4").tobytes()
    elif scheme == "codes":
        data = code.astype(_code_type(len(tuples))).tobytes()
    else:
        tuples, data = tuples[:0], x.astype("<f8").tobytes()
    raw = tuples.astype("<f8").tobytes()
    return {"scheme": scheme, "tuples": raw, "lengths": lengths, "data": data, "bytes": len(raw) + len(lengths) + len(data)}


class GroupPart:
    """An encoded group, read in place for products; nothing of it is expanded to rows x columns but ``raw``, which is."""

    def __init__(self, part: dict, n: int, width: int) -> None:
        self.scheme, self.n = part["scheme"], n
        self.tuples = np.frombuffer(part["tuples"], "<f8").reshape(-1, width)
        self.lengths = np.frombuffer(part["lengths"], "<u4").astype(np.int64)
        kind = {"offsets": "<u4", "runs": "<u4", "codes": _code_type(len(self.tuples)), "raw": "<f8"}[self.scheme]
        self.data = np.frombuffer(part["data"], kind)
        if self.scheme in ("runs", "raw"):
            self.data = self.data.reshape(-1, 2 if self.scheme == "runs" else width)

    def right(self, x: np.ndarray) -> np.ndarray:
        """The group's share of Mx: each distinct tuple meets x once."""
        if self.scheme == "raw":
            return self.data @ x
        t = self.tuples @ x
        if self.scheme == "codes":
            return np.append(0.0, t)[self.data]
        y = np.zeros(self.n)
        if self.scheme == "offsets":
            y[self.data] = np.repeat(t, self.lengths)
            return y
        w = np.repeat(t, self.lengths)
        start, size = self.data[:, 0].astype(np.int64), self.data[:, 1].astype(np.int64)
        y[np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())] = np.repeat(w, size)
        return y

    def left(self, y: np.ndarray) -> np.ndarray:
        """The group's columns of y'M: y is summed per tuple, by runs from running sums, and each tuple spread once."""
        if self.scheme == "raw":
            return y @ self.data
        k = len(self.tuples)
        if self.scheme == "codes":
            s = np.bincount(self.data, y, k + 1)[1:]
        else:
            tuple_of = np.repeat(np.arange(k), self.lengths)
            if self.scheme == "offsets":
                s = np.bincount(tuple_of, y[self.data], k)
            else:
                upto = np.append(0.0, np.cumsum(y))
                start, size = self.data[:, 0].astype(np.int64), self.data[:, 1].astype(np.int64)
                s = np.bincount(tuple_of, upto[start + size] - upto[start], k)
        return s @ self.tuples

    def dense(self) -> np.ndarray:
        return np.stack([self.right(e) for e in np.eye(self.data.shape[1] if self.scheme == "raw" else self.tuples.shape[1])], axis=1)


def column_groups(view: MatrixView, blocks: int = 1, sample: int = 20_000, seed: int = 1) -> ColumnGroups:
    """Correlated columns are grouped greedily on a sample of rows while a merge makes the estimated size smaller; in each block of rows, every group is stored in its smallest scheme.

    Planning sees at most ``sample`` rows, drawn by a hash of the row id; encoding is one shuffle of rows to blocks.
    """
    m, n = view.m, view.n
    dense = view.rows.select("row_id", F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda c: F.coalesce(F.get("vals", F.array_position("cols", c.cast("int")).cast("int") - 1), F.lit(0.0))).alias("v"))
    some = dense.orderBy(F.xxhash64("row_id", F.lit(seed))).limit(sample).orderBy("row_id").toPandas()
    x = np.array(some["v"].tolist()) if len(some) else np.zeros((0, m))
    share = n / max(1, len(x))
    coded = [np.unique(x[:, c], return_inverse=True)[1] if len(x) else np.zeros(0, int) for c in range(m)]

    def estimate(cols: tuple[int, ...]) -> tuple[float, str]:
        key = np.zeros(len(x), np.int64)
        for c in cols:
            _, key = np.unique(key * (len(x) + 1) + coded[c], return_inverse=True)
        held = (x[:, list(cols)] != 0).any(axis=1)
        _, counts = np.unique(key[held], return_counts=True)
        once = (counts == 1).sum()
        distinct = len(counts) + once * (share - 1) * 0.5  # tuples seen once hint at unseen ones
        runs = 1 + (key[1:] != key[:-1]).sum() if len(key) else 0
        cost = _costs(n, len(cols), int(distinct), int(held.sum() * share), int(runs * share))
        best = min(cost, key=cost.get)
        return cost[best], best

    groups = {(c,): estimate((c,)) for c in range(m)}
    tried: dict[tuple, tuple[float, str]] = {}
    while len(groups) > 1:
        best = None
        for a in groups:
            for b in groups:
                if a < b:
                    both = tuple(sorted(a + b))
                    if both not in tried:
                        tried[both] = estimate(both)
                    saved = groups[a][0] + groups[b][0] - tried[both][0]
                    if saved > 0 and (best is None or saved > best[0]):
                        best = (saved, a, b, both)
        if best is None:
            break
        _, a, b, both = best
        del groups[a], groups[b]
        groups[both] = tried[both]
    named = tuple(sorted(groups))

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("row_id")
        parts = [encode_group(x) for x in (_dense(rows, m)[:, list(cols)] for cols in named)]
        table = {"block": pa.array([key[0].as_py()], pa.int32()), "row_ids": pa.array([rows.column("row_id").to_pylist()], pa.list_(pa.int64())), "parts": pa.array([parts], pa.list_(_PART)), "bytes": pa.array([sum(p["bytes"] for p in parts)], pa.int64()), "piece": pa.array([key[1].as_py()], pa.int32())}
        return pa.table(table)

    made = in_pieces(view, blocks).applyInArrow(work, f"block int, row_ids array<long>, parts array<struct<{_PART_SQL.replace(' ', ':').replace(',:', ',')}>>, bytes long, piece int")
    return ColumnGroups(named, made, m)


def _dense(rows: pa.Table, m: int) -> np.ndarray:
    out = np.zeros((len(rows), m))
    cols = rows.column("cols").combine_chunks()
    out[np.repeat(np.arange(len(rows)), np.diff(cols.offsets.to_numpy())), cols.flatten().to_numpy(zero_copy_only=False)] = rows.column("vals").combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return out


def _blocks(g: ColumnGroups):
    """Runs over the blocks of a task: (row ids, groups with their parts, the row)."""
    groups = g.groups

    def each(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids = np.array(row["row_ids"], np.int64)
                yield ids, [(list(cols), GroupPart(p, len(ids), len(cols))) for cols, p in zip(groups, row["parts"])], row

    return each


def groups_right(g: ColumnGroups, x: np.ndarray) -> DataFrame:
    """y = Mx on the encoded groups: (row_id, y). No shuffle."""
    each, x = _blocks(g), np.asarray(x, float)

    def run(batches):
        for ids, parts, _ in each(batches):
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(sum((p.right(x[cols]) for cols, p in parts), np.zeros(len(ids))))], names=["row_id", "y"])

    return g.encoded.mapInArrow(run, "row_id long, y double")


def groups_left(g: ColumnGroups, y: DataFrame) -> DataFrame:
    """y'M on the encoded groups, y as (row_id, y): (col, x). Blocks meet their part of y by a join."""
    own = g.encoded.select("block", "piece", F.explode("row_ids").alias("row_id")).join(y, "row_id").groupBy("block", "piece").agg(F.array_sort(F.collect_list(F.struct("row_id", "y"))).alias("ys"))
    joined = g.encoded.join(own.select("block", "piece", F.col("ys.row_id").alias("yids"), F.col("ys.y").alias("ys")), ["block", "piece"])
    each, m = _blocks(g), g.m

    def run(batches):
        for ids, parts, row in each(batches):
            vec, x = np.zeros(len(ids)), np.zeros(m)
            vec[np.searchsorted(ids, row["yids"])] = row["ys"]
            for cols, p in parts:
                x[cols] = p.left(vec)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m, dtype=np.int32)), pa.array(x)], names=["col", "x"])

    return joined.mapInArrow(run, "col int, x double").groupBy("col").agg(F.sum("x").alias("x"))


def groups_gram(g: ColumnGroups, x: np.ndarray) -> np.ndarray:
    """M'(Mx) in one pass, as the grammar blocks do it."""
    each, m, x = _blocks(g), g.m, np.asarray(x, float)

    def run(batches):
        total = np.zeros(m)
        for ids, parts, _ in each(batches):
            y = sum((p.right(x[cols]) for cols, p in parts), np.zeros(len(ids)))
            for cols, p in parts:
                total[cols] += p.left(y)
        yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], names=["x"])

    return sum((np.array(r.x) for r in g.encoded.mapInArrow(run, "x array<double>").collect()), np.zeros(m))


def groups_decode(g: ColumnGroups) -> DataFrame:
    """The long matrix (row_id, col, val) back from the groups."""
    each = _blocks(g)

    def run(batches):
        for ids, parts, _ in each(batches):
            for cols, p in parts:
                x = p.dense()
                r, c = np.nonzero(x)
                yield pa.RecordBatch.from_arrays([pa.array(ids[r]), pa.array(np.array(cols, np.int32)[c]), pa.array(x[r, c])], names=["row_id", "col", "val"])

    return g.encoded.mapInArrow(run, "row_id long, col int, val double")
