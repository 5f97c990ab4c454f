"""SQL surface: views of a matrix and its stream, symbol arithmetic, and a table function that expands blocks."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import Blocks, MatrixView
from ..operators import codec as codecs
from ..operators import encode, multiply
from ..operators.kernel import expand


@F.udtf(returnType="row_index: long, sym: long")
class ExpandBlock:
    """Rows of (row_index, sym) from a block's encoded final string and rules."""

    def eval(self, codec: str, c: bytes, r: bytes, width: int, c_len: int, r_len: int, space: int) -> Iterator[tuple[int, int]]:
        g = codecs.decode(codec, bytes(c), bytes(r), width, c_len, r_len, space)
        sym, row = expand(g)
        yield from zip(row.tolist(), sym.tolist())


@F.pandas_udf(T.IntegerType())
def bit_width(largest: pd.Series) -> pd.Series:
    return largest.map(lambda v: codecs.width_of(int(v))).astype("int32")


@F.pandas_udf(T.DoubleType())
def entropy_of(counts: pd.Series) -> float:
    """Order-0 entropy in bits of a group of counts."""
    p = counts[counts > 0] / counts.sum()
    return float(-(p * np.log2(p)).sum()) if len(p) else math.nan


def register(spark: SparkSession) -> None:
    """symbol_of, code_of and column_of as SQL expressions; bit_width, entropy_of and expand_block as functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION symbol_of(code BIGINT, col BIGINT, m BIGINT) RETURNS BIGINT RETURN 1 + code * m + col")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION code_of(sym BIGINT, m BIGINT) RETURNS BIGINT RETURN (sym - 1) DIV m")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION column_of(sym BIGINT, m BIGINT) RETURNS INT RETURN CAST((sym - 1) % m AS INT)")
    spark.udf.register("bit_width", bit_width)
    spark.udf.register("entropy_of", entropy_of)
    spark.udtf.register("expand_block", ExpandBlock)


def views(view: MatrixView, prefix: str = "symmat_") -> DataFrame:
    """Views <prefix>matrix, <prefix>dict and <prefix>stream; returns the dictionary."""
    codes = encode.dictionary(view)
    view.cells.createOrReplaceTempView(f"{prefix}matrix")
    codes.createOrReplaceTempView(f"{prefix}dict")
    encode.stream(view, codes).createOrReplaceTempView(f"{prefix}stream")
    return codes


def grammar_views(g: Blocks, prefix: str = "symmat_") -> None:
    """Views <prefix>blocks (a row per piece of a block), <prefix>final (block, piece, row_id, pos, sym) and <prefix>rules (block, piece, rule, left, right).

    Symbols above the piece's ``space`` are rules; final strings and rules are decoded where they lie, without a shuffle.
    """
    g.df.createOrReplaceTempView(f"{prefix}blocks")

    def final(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                h, ids = multiply._grammar(batch, i), multiply._numbers(batch, i, "row_ids").astype(np.int64)
                pos = np.arange(len(h.c)) - np.searchsorted(h.row, h.row)
                block, piece = (np.full(len(h.c), multiply._at(batch, i, k), np.int32) for k in ("block", "piece"))
                yield pa.RecordBatch.from_arrays([pa.array(block), pa.array(piece), pa.array(ids[h.row]), pa.array(pos.astype(np.int64)), pa.array(h.c.astype(np.int64))], names=["block", "piece", "row_id", "pos", "sym"])

    def rules(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                h = multiply._grammar(batch, i)
                q = len(h.rules)
                block, piece = (np.full(q, multiply._at(batch, i, k), np.int32) for k in ("block", "piece"))
                yield pa.RecordBatch.from_arrays([pa.array(block), pa.array(piece), pa.array(h.space + 1 + np.arange(q)), pa.array(h.rules[:, 0].astype(np.int64)), pa.array(h.rules[:, 1].astype(np.int64))], names=["block", "piece", "rule", "left", "right"])

    g.df.mapInArrow(final, "block int, piece int, row_id long, pos long, sym long").createOrReplaceTempView(f"{prefix}final")
    g.df.mapInArrow(rules, "block int, piece int, rule long, left long, right long").createOrReplaceTempView(f"{prefix}rules")


def expand_by_sql(spark: SparkSession, view: MatrixView, blocks: int = 2) -> DataFrame:
    """The long matrix from the views of final strings and rules, by one recursive SQL query."""
    register(spark)
    g = multiply.compress(view, blocks, "gpack", scope="block").prepared()
    grammar_views(g)
    m = view.m
    return spark.sql(
        f"""WITH RECURSIVE kids AS (SELECT block, piece, rule, explode(array(left, right)) AS kid FROM symmat_rules),
        t AS (SELECT block, piece, row_id, sym FROM symmat_final UNION ALL SELECT t.block, t.piece, t.row_id, k.kid FROM t JOIN kids k ON t.block = k.block AND t.piece = k.piece AND t.sym = k.rule)
        SELECT t.row_id, CAST((t.sym - 1) % {m} AS INT) AS col, element_at(b.v, CAST((t.sym - 1) DIV {m} + 1 AS INT)) AS val FROM t JOIN symmat_blocks b ON t.block = b.block AND t.piece = b.piece WHERE t.sym <= b.space"""
    )


def right_by_sql(spark: SparkSession, view: MatrixView) -> DataFrame:
    """y = Mx for x = (1, 2, ...) as one SQL query over the stream."""
    register(spark)
    views(view)
    view.rows.select("row_id").createOrReplaceTempView("symmat_rows")
    m = view.m
    return spark.sql(
        f"""SELECT r.row_id, coalesce(sum(d.value * (column_of(s.sym, {m}) + 1)), 0) AS y FROM symmat_rows r LEFT JOIN symmat_stream s ON r.row_id = s.row_id
        LEFT JOIN symmat_dict d ON code_of(s.sym, {m}) = d.code GROUP BY r.row_id"""
    )


def expand_by_udtf(spark: SparkSession, view: MatrixView, blocks: int = 2) -> DataFrame:
    """The long matrix from compressed blocks by a lateral join with the table function."""
    register(spark)
    g: Blocks = multiply.compress(view, blocks, "gans", scope="block")
    g.df.createOrReplaceTempView("symmat_blocks")
    m = view.m
    return spark.sql(
        f"""SELECT element_at(b.row_ids, CAST(e.row_index + 1 AS INT)) AS row_id, CAST((e.sym - 1) % {m} AS INT) AS col, element_at(b.v, CAST((e.sym - 1) DIV {m} + 1 AS INT)) AS val
        FROM symmat_blocks b, LATERAL expand_block(b.codec, b.c, b.r, b.width, b.c_len, b.r_len, b.space) e"""
    )
