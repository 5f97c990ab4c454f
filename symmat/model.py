"""Matrices as DataFrames: rows of parallel arrays, and compressed row blocks."""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Arrays of a value dictionary or vector up to this size may be broadcast; beyond it dictionaries are kept per block.
BROADCAST_BYTES = 64 << 20
#: Symbols and row marks of a piece: of a larger block, the rows that one task builds, holds and multiplies at once.
PIECE_SYMBOLS = 1 << 19
#: Block borders up to so many are compared in one expression; more are searched in Arrow batches.
EDGES = 128
BLOCK_SCHEMA = (
    "block int, n_rows long, row_ids array<long>, codec string, width int, space long, c_len long, r_len long, s_len long, depth int,"
    " c binary, r binary, v array<double>, c_bytes long, r_bytes long, v_bytes long, piece int"
)


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the cluster names; a local one only where none is named and Spark itself runs in one process."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="symmat-checkpoint-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared checkpoint folder and cut the lineage."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


class _Scratch(threading.local):
    """A thread's folders of ``stored`` tables by the scratch that gives them back, innermost last."""

    def __init__(self) -> None:
        self.open: list[list[str]] = []


_SCRATCH = _Scratch()


def stored(df: DataFrame) -> DataFrame:
    """As ``cut``, for tables: compressed columns in the shared folder, where a checkpoint holds plain rows; the shuffles behind them are given back at once.

    The files go with the ``scratch`` around the call, else when Spark ends.
    """
    if len({c.lower() for c in df.columns}) < len(df.columns):
        return cut(df)  # names that files cannot hold
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/stored-{uuid.uuid4().hex}"
    with _giving_back(spark):
        df.write.option("compression", "zstd").parquet(folder)
    path, files = _files(spark, folder)
    files.deleteOnExit(path)
    if _SCRATCH.open:
        _SCRATCH.open[-1].append(folder)
    return spark.read.schema(df.schema).parquet(folder)


_LOCK, _WRITING = threading.Lock(), []


@contextmanager
def _giving_back(spark: SparkSession) -> Iterator[None]:
    """Spark deletes the shuffles of queries that start within, at their end; threads may overlap."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    with _LOCK:
        _WRITING.append(_WRITING[0] if _WRITING else spark.conf.get(key, "false"))
        spark.conf.set(key, "true")
    try:
        yield
    finally:
        with _LOCK:
            before = _WRITING.pop()
            if not _WRITING:
                spark.conf.set(key, before)


def _files(spark: SparkSession, folder: str):
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    return path, path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


@contextmanager
def scratch(spark: SparkSession) -> Iterator[list[str]]:
    """What is ``stored`` within is deleted at the end: for results that are on the driver by then, or stored further out."""
    own: list[str] = []
    _SCRATCH.open.append(own)
    try:
        yield own
    finally:
        _SCRATCH.open.pop()
        for folder in own:
            path, files = _files(spark, folder)
            files.delete(path, True)


def adopt(own: list[str]) -> None:
    """In a thread of its own: what it stores belongs to this scratch of another's."""
    _SCRATCH.open[:] = [own]


@contextmanager
def outer() -> Iterator[None]:
    """What is ``stored`` within stays until the scratch around the innermost one ends."""
    own = _SCRATCH.open.pop()
    try:
        yield
    finally:
        _SCRATCH.open.append(own)


@dataclass(frozen=True)
class MatrixView:
    """A matrix as rows (row_id long, cols array<int>, vals array<double>): one DataFrame row per matrix row, zeros left out.

    Empty rows have empty arrays. Cells of a row are in column order. ``m`` and ``names`` are fixed, ``n`` is counted once
    when it is asked for. Every pass over the matrix is narrow: a row's symbols never need a shuffle to meet.
    """

    rows: DataFrame
    m: int
    names: tuple[str, ...] = ()
    memo: dict = field(default_factory=dict, compare=False)

    def _count(self) -> None:
        if "n" not in self.memo:
            r = self.rows.agg(F.count("*").alias("n"), F.min("row_id").alias("low"), F.max("row_id").alias("high"), F.max(F.size("cols")).alias("widest")).first()
            self.memo.update(n=r.n, low=r.low, high=r.high, widest=r.widest or 0)

    @property
    def n(self) -> int:
        self._count()
        return self.memo["n"]

    def block_of(self, blocks: int) -> Column:
        """The block (0-based) of a row by its row_id: ``blocks`` ranges of rows, as even as can be; fewer where there are fewer rows.

        Ids 0..n-1 are divided. Any others (gaps, huge, negative) are numbered once, and the first id of each block decides.
        """
        n = self.n
        per = max(1, -(-n // blocks))
        if blocks <= 1 or n <= 1:
            return F.lit(0)
        if (self.memo["low"], self.memo["high"]) == (0, n - 1):
            return F.floor(F.expr(f"row_id DIV {per}L")).cast("int")
        return self._span(per, per)

    def _ranges(self, blocks: int, symbols: int | None = None) -> tuple[int, int]:
        """Rows of a block and of a piece."""
        n = self.n
        per = max(1, -(-n // max(1, blocks)))
        rows = min(per, max(1, (PIECE_SYMBOLS if symbols is None else symbols) // (self.memo["widest"] + 1)))
        return per, -(-per // -(-per // rows))

    def piece_count(self, blocks: int, symbols: int | None = None) -> tuple[int, int]:
        """The most blocks there can be, and the pieces of each."""
        per, rows = self._ranges(blocks, symbols)
        return max(1, -(-self.n // per)), -(-per // rows)

    def pieces_of(self, blocks: int, symbols: int | None = None) -> tuple[Column, Column]:
        """The block of a row, and its piece (0-based) in there: ranges of rows with ``symbols`` (None: PIECE_SYMBOLS) at most, marks included.

        Rows count as the widest one, so that no range exceeds it (but one of a single row); a block has as many pieces as it needs.
        """
        n, (per, rows) = self.n, self._ranges(blocks, symbols)
        if rows == per:
            return self.block_of(blocks), F.lit(0)
        if (self.memo["low"], self.memo["high"]) == (0, n - 1):
            return F.expr(f"row_id DIV {per}L").cast("int"), F.expr(f"row_id % {per}L DIV {rows}L").cast("int")
        at, each = self._span(per, rows), -(-per // rows)
        return F.floor(at / each).cast("int"), F.pmod(at, F.lit(each)).cast("int")

    def _span(self, per: int, rows: int) -> Column:
        """The number of a row's range: blocks of ``per`` rows, each cut into ranges of ``rows``; any ids, by the first id of each range."""
        if ("edges", per, rows) not in self.memo:
            from .sources.matrices import with_row_ids

            numbered = with_row_ids(self.rows.select(F.col("row_id").alias("key")), ["key"], "at")
            firsts = numbered.where((F.col("at") > 0) & (F.pmod("at", F.lit(per)) % rows == 0)).orderBy("at")  # a number per range
            self.memo["edges", per, rows] = [r.key for r in firsts.select("key").collect()]
        edges = self.memo["edges", per, rows]
        if len(edges) <= EDGES:
            return F.size(F.filter(F.array(*[F.lit(e).cast("long") for e in edges]), lambda e: e <= F.col("row_id")))
        bounds = np.array(edges, np.int64)

        @F.pandas_udf("int")
        def placed(ids: pd.Series) -> pd.Series:
            return pd.Series(np.searchsorted(bounds, ids.to_numpy(), side="right").astype(np.int32))

        return placed("row_id")

    @property
    def cells(self) -> DataFrame:
        """The long form (row_id, col, val) of the nonzero cells."""
        return self.rows.select("row_id", F.explode(F.arrays_zip("cols", "vals")).alias("x")).select("row_id", F.col("x.cols").alias("col"), F.col("x.vals").alias("val"))

    def select(self, keep: list[int]) -> MatrixView:
        """The columns ``keep``, renumbered in that order."""
        to = F.create_map(*[F.lit(x) for pair in ((c, i) for i, c in enumerate(keep)) for x in pair])
        kept = F.filter(F.arrays_zip("cols", "vals"), lambda x: F.array_contains(F.lit(keep), x["cols"]))
        moved = F.array_sort(F.transform(kept, lambda x: F.struct(F.element_at(to, x["cols"]).alias("cols"), x["vals"].alias("vals"))))
        rows = self.rows.withColumn("x", moved).select("row_id", F.col("x.cols").alias("cols"), F.col("x.vals").alias("vals"))
        return MatrixView(rows, len(keep), tuple(self.names[i] for i in keep) if self.names else ())

    def where(self, condition) -> MatrixView:
        return MatrixView(self.rows.where(condition), self.m, self.names)


@dataclass(frozen=True, eq=False)
class Blocks:
    """A matrix as compressed row blocks (schema BLOCK_SCHEMA), with its value dictionary: an array shared by all blocks, or one in each block.

    A large block is several rows of ``df``, its pieces, each with a grammar (and dictionary, where it is not shared) of its own.
    """

    df: DataFrame
    m: int
    codec: str
    values: np.ndarray | None = None
    uid: str = field(default_factory=lambda: uuid.uuid4().hex)
    memo: dict = field(default_factory=dict)

    @property
    def shared(self):
        """The dictionary as a broadcast, sent once however many products follow."""
        if "values" not in self.memo:
            self.memo["values"] = self.df.sparkSession.sparkContext.broadcast(None if self.values is None else np.asarray(self.values, float))
        return self.memo["values"]

    def save(self, path: str) -> None:
        """Parquet, a folder per block, beside the shared dictionary and the width of the matrix."""
        spark = self.df.sparkSession
        self.df.withColumn("part", F.col("block")).write.mode("overwrite").partitionBy("part").parquet(f"{path}/blocks")
        meta = [(self.m, self.codec, None if self.values is None else [float(v) for v in self.values])]
        spark.createDataFrame(meta, "m int, codec string, values array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str, blocks: list[int] | None = None) -> Blocks:
        """The blocks saved at ``path``, or only those of these numbers (other folders are not read)."""
        meta = spark.read.parquet(f"{path}/meta").first()
        df = spark.read.parquet(f"{path}/blocks")
        df = (df if blocks is None else df.where(F.col("part").isin(blocks))).drop("part")
        return Blocks(df, meta["m"], meta["codec"], None if meta["values"] is None else np.array(meta["values"]))

    def prepared(self) -> Blocks:
        """The same blocks, materialised once for repeated products: in the checkpoint folder, and kept in memory where it suffices."""
        return replace(self, df=cut(self.df).persist(StorageLevel.MEMORY_AND_DISK))

    def release(self) -> None:
        """Give back memory and the broadcast dictionary."""
        self.df.unpersist()
        if "values" in self.memo:
            self.memo.pop("values").unpersist()

    def explain(self) -> DataFrame:
        """Shape of every block, over its pieces: rows, symbols before and after, rules, depth, width, bytes."""
        total, most = (lambda c: F.sum(c).alias(c)), (lambda c: F.max(c).alias(c))
        return self.df.groupBy("block", "codec").agg(*map(total, ("n_rows", "s_len", "c_len", "r_len")), *map(most, ("depth", "width")), *map(total, ("c_bytes", "r_bytes", "v_bytes")))
