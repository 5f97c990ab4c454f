"""Relational representations: value dictionary, symbol stream, sparse rows, decoding, and products by one scan."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import MatrixView
from ..sources.matrices import with_row_ids


def dictionary(view: MatrixView, order: str = "value") -> DataFrame:
    """(code, value) of the distinct nonzeros: by ``value``, by falling ``frequency``, or ``any`` order (hash ranges, no sort of values)."""
    distinct = view.cells.groupBy(F.col("val").alias("value")).agg(F.count("*").alias("n"))
    if order == "value":
        return with_row_ids(distinct.select("value"), ["value"], "code").select("code", "value")
    if order == "frequency":
        return with_row_ids(distinct.select((-F.col("n")).alias("k"), "value"), ["k", "value"], "code").select("code", "value")
    return with_row_ids(distinct.select(F.xxhash64("value").alias("h"), "value"), ["h", "value"], "code").select("code", "value")


def symbol_of(code: Column, col: Column, m: int) -> Column:
    return F.lit(1).cast("long") + code * F.lit(m) + col


def code_of(sym: Column, m: int) -> Column:
    return F.floor((sym - 1) / F.lit(m)).cast("long")


def column_of(sym: Column, m: int) -> Column:
    return F.pmod(sym - 1, F.lit(m)).cast("int")


def stream(view: MatrixView, codes: DataFrame | None = None, order: Sequence[int] | DataFrame | str | None = None, blocks: int = 1) -> DataFrame:
    """The symbol stream (block, row_id, pos, sym); the row key stands for the row mark.

    ``order``: None, one permutation for all rows (position -> column), a DataFrame (block, col, rank) with one per block,
    'row_greedy' (each row on its own: frequent symbols first, so equal ones line up), or 'row_partner' (each row on its own:
    every symbol next to the one that it meets in most rows).
    """
    if isinstance(order, str) and order not in ("row_greedy", "row_partner"):
        raise ValueError(order)
    codes = dictionary(view) if codes is None else codes
    cells = view.cells.join(codes, F.col("val") == F.col("value")).select(view.block_of(blocks).alias("block"), "row_id", "col", symbol_of(F.col("code"), F.col("col"), view.m).alias("sym"))
    if order is None:
        cells = cells.withColumn("rank", F.col("col"))
    elif order == "row_partner":
        return _by_partner(cells)
    elif isinstance(order, str):
        often = cells.groupBy("sym").agg((-F.count("*")).alias("rank"))
        cells = cells.join(often, "sym")
    elif isinstance(order, DataFrame):
        cells = cells.join(order, ["block", "col"])
    else:
        ranks = cells.sparkSession.createDataFrame([(int(c), r) for r, c in enumerate(order)], "col int, rank int")
        cells = cells.join(F.broadcast(ranks), "col")
    at = F.row_number().over(Window.partitionBy("row_id").orderBy("rank", "sym")) - 1
    return cells.select("block", "row_id", at.alias("pos"), "sym")


def _by_partner(cells: DataFrame) -> DataFrame:
    """Each row led by its most frequent symbol; after a symbol comes its best partner of those left in the row.

    Partners are counted over all rows: pairs are made inside the row, combined on the map side, and join the row's own
    pairs again by key, so a row's task sees only its own symbols and their counts.
    """
    rows = cells.groupBy("block", "row_id").agg(F.array_sort(F.collect_list("sym")).alias("syms"))
    ahead = F.transform("syms", lambda a, i: F.struct(a.alias("a"), F.slice("syms", i + 2, F.size("syms")).alias("rest")))
    pairs = rows.select("block", "row_id", F.explode(ahead).alias("x")).select("block", "row_id", "x.a", F.explode("x.rest").alias("b"))
    often = pairs.groupBy("a", "b").agg(F.count("*").alias("n"))
    single = cells.groupBy("sym").agg(F.count("*").alias("n"))
    met = pairs.join(often, ["a", "b"]).groupBy("block", "row_id").agg(F.collect_list(F.struct("n", "a", "b")).alias("met"))
    own = cells.join(single, "sym").groupBy("block", "row_id").agg(F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), "sym"))).alias("own"))
    both = own.join(met, ["block", "row_id"], "left").select("block", "row_id", F.col("own.sym").alias("syms"), F.coalesce("met", F.array().cast("array<struct<n:bigint,a:bigint,b:bigint>>")).alias("met"))

    def step(acc: Column, _: Column) -> Column:
        last = F.element_at(acc["out"], -1)
        near = F.filter("met", lambda e: ((e["a"] == last) & F.array_contains(acc["left"], e["b"])) | ((e["b"] == last) & F.array_contains(acc["left"], e["a"])))
        best = F.array_max(F.transform(near, lambda e: F.struct(e["n"].alias("n"), (-F.when(e["a"] == last, e["b"]).otherwise(e["a"])).alias("s"))))
        pick = -best["s"]
        return F.struct(F.array_append(acc["out"], pick).alias("out"), F.array_remove(acc["left"], pick).alias("left"))

    start = F.struct(F.slice("syms", 1, 1).alias("out"), F.slice("syms", 2, F.size("syms")).alias("left"))
    line = F.aggregate(F.slice("syms", 2, F.size("syms")), start, step, lambda acc: acc["out"])
    return both.select("block", "row_id", F.posexplode(line).alias("pos", "sym"))


def row_marks(view: MatrixView, blocks: int = 1) -> DataFrame:
    """(block, row_id, pos, sym = 0): the mark behind every row, rows without symbols included."""
    return view.rows.select(view.block_of(blocks).alias("block"), "row_id", F.size("cols").alias("pos"), F.lit(0).cast("long").alias("sym"))


def decode_stream(symbols: DataFrame, codes: DataFrame, m: int) -> DataFrame:
    """The long matrix (row_id, col, val) back from the stream."""
    own = symbols.select("row_id", code_of(F.col("sym"), m).alias("code"), column_of(F.col("sym"), m).alias("col"))
    return own.join(codes, "code").select("row_id", "col", F.col("value").alias("val"))


def right_scan(symbols: DataFrame, codes: DataFrame, m: int, x: DataFrame) -> DataFrame:
    """y = Mx by one scan of the stream: (row_id, y). ``x``: (col, x)."""
    return decode_stream(symbols, codes, m).join(x, "col").groupBy("row_id").agg(F.sum(F.col("val") * F.col("x")).alias("y"))


def left_scan(symbols: DataFrame, codes: DataFrame, m: int, y: DataFrame) -> DataFrame:
    """y'M by one scan of the stream: (col, x). ``y``: (row_id, y)."""
    return decode_stream(symbols, codes, m).join(y, "row_id").groupBy("col").agg(F.sum(F.col("val") * F.col("y")).alias("x"))


def right_dense(view: MatrixView, x: DataFrame) -> DataFrame:
    """Join and aggregate on the long matrix; rows without cells get 0."""
    some = view.cells.join(x, "col").groupBy("row_id").agg(F.sum(F.col("val") * F.col("x")).alias("y"))
    return view.rows.select("row_id").join(some, "row_id", "left").select("row_id", F.coalesce("y", F.lit(0.0)).alias("y"))


def left_dense(view: MatrixView, y: DataFrame) -> DataFrame:
    return view.cells.join(y, "row_id").groupBy("col").agg(F.sum(F.col("val") * F.col("y")).alias("x"))


def csr_pointers(view: MatrixView, per_chunk: int = 65_536) -> DataFrame:
    """(row_id, nnz, first): where each row's nonzeros begin. Running sums are taken per chunk of rows and offset by chunk totals."""
    rows = view.rows.select("row_id", F.size("cols").cast("long").alias("nnz"), F.floor(F.col("row_id") / per_chunk).alias("chunk"))
    totals = rows.groupBy("chunk").agg(F.sum("nnz").alias("t"))
    start = F.coalesce(F.sum("t").over(Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inside = F.coalesce(F.sum("nnz").over(Window.partitionBy("chunk").orderBy("row_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("inside", inside).join(F.broadcast(totals.select("chunk", start.alias("start"))), "chunk").select("row_id", "nnz", (F.col("start") + F.col("inside")).cast("long").alias("first"))


def csr(view: MatrixView, blocks: int = 1) -> DataFrame:
    """Per block: nz array<double>, idx array<int>, first array<long> (positions inside the block)."""
    return _csr(view, blocks, "vals", pa.float64())


def csr_iv(view: MatrixView, codes: DataFrame | None = None, blocks: int = 1) -> DataFrame:
    """As csr, with dictionary codes in place of values."""
    codes = dictionary(view) if codes is None else codes
    coded = view.cells.join(codes, F.col("val") == F.col("value")).groupBy("row_id").agg(F.array_sort(F.collect_list(F.struct("col", "code"))).alias("x"))
    rows = view.rows.select("row_id").join(coded, "row_id", "left").select("row_id", F.coalesce(F.col("x.col"), F.array().cast("array<int>")).alias("cols"), F.coalesce(F.col("x.code"), F.array().cast("array<bigint>")).alias("codes"))
    view.n  # noqa: B018  the same rows, counted once
    return _csr(MatrixView(rows, view.m, memo=view.memo), blocks, "codes", pa.int32())


def _csr(view: MatrixView, blocks: int, what: str, kind: pa.DataType) -> DataFrame:
    """A block's rows meet in one task, where its arrays are laid end to end."""

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("row_id")
        cols, held = rows.column("cols").combine_chunks(), rows.column(what).combine_chunks()
        ends = cols.offsets.to_numpy().astype(np.int64)
        lists = [held.flatten().cast(kind), cols.flatten().cast(pa.int32()), pa.array(ends - ends[0])]
        return pa.table([pa.array([key[0].as_py()], pa.int32()), *(pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x) for x in lists)], names=["block", "nz", "idx", "first"])

    number = "double" if kind == pa.float64() else "int"
    return view.rows.select(view.block_of(blocks).alias("block"), "row_id", "cols", what).groupBy("block").applyInArrow(work, f"block int, nz array<{number}>, idx array<int>, first array<long>")
