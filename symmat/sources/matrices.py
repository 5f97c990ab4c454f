"""Matrix views from tables: wide columns, arrays, long cells, maps, JSON, text, one-hot indicators, files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import MatrixView, stored

#: Whole numbers beyond this have no exact double.
EXACT = 1 << 53


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_row_ids(df: DataFrame, order: list[str] | None = None, name: str = "row_id") -> DataFrame:
    """``df`` with consecutive numbers from 0 in the order of ``order`` (default: all columns).

    A range-partitioned sort gives every partition its share; the counts of the partitions (one number each) give the
    offsets. No window spans the table.
    """
    parted = stored(df.orderBy(*(order or df.columns)).withColumn("__at", F.monotonically_increasing_id()))
    sizes = parted.groupBy(F.shiftright("__at", 33).alias("__p")).agg(F.count("*").alias("n")).orderBy("__p")
    before = F.coalesce(F.sum("n").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("__p", before.alias("__o"))
    low = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    return parted.withColumn("__p", F.shiftright("__at", 33)).join(F.broadcast(offsets), "__p").withColumn(name, F.col("__o") + low).drop("__at", "__p", "__o")


def _cell(c: Column, kind: str, nulls: str, bit_exact: bool) -> Column:
    if kind in ("bigint", "long") or kind.startswith("decimal"):
        c = F.when(F.abs(c) > EXACT, F.raise_error(F.lit("a whole number beyond 2**53 has no exact double"))).otherwise(c)
    v = c.cast("double")
    if nulls == "error":
        v = F.when(v.isNull(), F.raise_error(F.lit("a null cell; choose nulls='zero'"))).otherwise(v)
    else:
        v = F.coalesce(v, F.lit(0.0))
    return v if bit_exact else v + F.lit(0.0)  # -0.0 + 0.0 is 0.0


def _sparse(values: Column, bit_exact: bool = False) -> tuple[Column, Column]:
    pairs = F.transform(values, lambda v, i: F.struct(i.alias("c"), v.alias("v")))
    full = (lambda x: (x["v"] != 0) | (F.hex(x["v"].cast("string")) == "2D302E30")) if bit_exact else (lambda x: x["v"] != 0)
    kept = F.filter(pairs, full)
    return F.transform(kept, lambda x: x["c"]), F.transform(kept, lambda x: x["v"])


def from_wide(df: DataFrame, columns: list[str], row_id: str = "row_id", nulls: str = "error", bit_exact: bool = False) -> MatrixView:
    """One matrix column per DataFrame column; any numeric or boolean type."""
    kinds = dict(df.dtypes)
    values = F.array(*[_cell(F.col(c), kinds.get(c, "double"), nulls, bit_exact) for c in columns])
    cols, vals = _sparse(F.col("__v"), bit_exact)
    rows = df.select(F.col(row_id).cast("long").alias("row_id"), values.alias("__v")).select("row_id", cols.alias("cols"), vals.alias("vals"))
    return MatrixView(rows, len(columns), tuple(columns))


def from_expressions(df: DataFrame, columns: dict[str, str], row_id: str = "row_id") -> MatrixView:
    """One matrix column per SQL expression."""
    named = df.selectExpr(row_id, *[f"CAST({e} AS DOUBLE) AS `{n}`" for n, e in columns.items()])
    return from_wide(named, list(columns), row_id)


def from_array(df: DataFrame, column: str, m: int, row_id: str = "row_id", nulls: str = "error") -> MatrixView:
    """One matrix column per array position."""
    values = F.transform(F.col(column), lambda x: _cell(x, "double", nulls, False))
    cols, vals = _sparse(F.col("__v"))
    return MatrixView(df.select(F.col(row_id).cast("long").alias("row_id"), values.alias("__v")).select("row_id", cols.alias("cols"), vals.alias("vals")), m)


def from_long(cells: DataFrame, m: int, row_id: str = "row_id", col: str = "col", val: str = "val", rows: DataFrame | None = None) -> MatrixView:
    """From (row, column, value) cells, at most one per place; ``rows`` (row_id) names rows that may be empty."""
    base = cells.select(F.col(row_id).cast("long").alias("row_id"), F.struct(F.col(col).cast("int").alias("c"), (F.col(val).cast("double") + 0.0).alias("v")).alias("x")).where("x.v <> 0")
    packed = base.groupBy("row_id").agg(F.array_sort(F.collect_list("x")).alias("x"))
    if rows is not None:
        packed = rows.select(F.col(row_id).cast("long").alias("row_id")).distinct().join(packed, "row_id", "left")
    empty = F.array().cast("array<struct<c:int,v:double>>")
    packed = packed.withColumn("x", F.coalesce("x", empty))
    return MatrixView(packed.select("row_id", F.col("x.c").alias("cols"), F.col("x.v").alias("vals")), m)


def from_map(df: DataFrame, column: str, keys: list[str], row_id: str = "row_id") -> MatrixView:
    values = F.array(*[F.coalesce(F.col(column)[k].cast("double"), F.lit(0.0)) for k in keys])
    cols, vals = _sparse(F.col("__v"))
    return MatrixView(df.select(F.col(row_id).cast("long").alias("row_id"), values.alias("__v")).select("row_id", cols.alias("cols"), vals.alias("vals")), len(keys), tuple(keys))


def from_json(df: DataFrame, column: str, keys: list[str], row_id: str = "row_id") -> MatrixView:
    """Numbers of a flat JSON object by key."""
    return from_map(df.withColumn("__m", F.from_json(column, "map<string,string>")), "__m", keys, row_id)


def from_characters(df: DataFrame, column: str, codes: range, row_id: str = "row_id") -> MatrixView:
    """Occurrences of single characters in a text; ASCII ones are counted among the text's bytes, in one pass for all of them."""
    text = F.coalesce(F.col(column), F.lit(""))
    if min(codes) < 0 or max(codes) > 127:
        return from_wide(df.select(row_id, *[(F.length(text) - F.length(F.replace(text, F.lit(chr(c)), F.lit("")))).cast("double").alias(f"c{c}") for c in codes]), [f"c{c}" for c in codes], row_id)
    first, step, m = codes.start, codes.step, len(codes)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 1024):
                part = batch.slice(at, 1024)
                raw = part.column("text").cast(pa.large_binary())
                ends = np.frombuffer(raw.buffers()[1], np.int64, len(raw) + 1, 8 * raw.offset)
                byte = np.frombuffer(raw.buffers()[2], np.uint8)[ends[0] : ends[-1]] if ends[-1] else np.zeros(0, np.uint8)
                row = np.repeat(np.arange(len(raw)), np.diff(ends))
                every = np.bincount(row * 256 + byte, minlength=256 * len(raw)).reshape(-1, 256)[:, [first + step * k for k in range(m)]]
                r, c = np.nonzero(every)
                held = pa.array(np.append(0, np.cumsum(np.bincount(r, minlength=len(raw)))).astype(np.int32))
                lists = (pa.ListArray.from_arrays(held, pa.array(x)) for x in (c.astype(np.int32), every[r, c].astype(float)))
                yield pa.RecordBatch.from_arrays([part.column("row_id"), *lists], names=["row_id", "cols", "vals"])

    rows = df.select(F.col(row_id).cast("long").alias("row_id"), text.cast("string").alias("text")).mapInArrow(count, "row_id long, cols array<int>, vals array<double>")
    return MatrixView(rows, m, tuple(f"c{c}" for c in codes))


def from_hashed_words(df: DataFrame, column: str, m: int, row_id: str = "row_id") -> MatrixView:
    """Counts of words hashed into ``m`` columns."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(column), F.lit(""))), r"\W+"), lambda w: w != "")
    hashed = df.select(F.col(row_id).alias("row_id"), F.explode(words).alias("w")).groupBy("row_id", F.pmod(F.xxhash64("w"), F.lit(m)).cast("int").alias("col")).agg(F.count("*").cast("double").alias("val"))
    return from_long(hashed, m, rows=df.select(F.col(row_id).alias("row_id")))


def one_hot(df: DataFrame, column: str, levels: list, row_id: str = "row_id") -> MatrixView:
    return from_wide(df.select(row_id, *[(F.col(column) == F.lit(v)).cast("double").alias(f"{column}={v}") for v in levels]), [f"{column}={v}" for v in levels], row_id)


def typed_dictionary(df: DataFrame, columns: list[str], row_id: str = "row_id") -> tuple[MatrixView, DataFrame]:
    """Cells of any type as codes 1, 2, ... per column, null being 0, and the dictionary (col, code, value). For storage and decoding, not for products."""
    long = df.select(row_id, F.explode(F.array(*[F.struct(F.lit(i).alias("col"), F.col(c).cast("string").alias("value")) for i, c in enumerate(columns)])).alias("x")).select(row_id, "x.*").where("value IS NOT NULL")
    codes = with_row_ids(long.select("col", "value").distinct(), ["col", "value"], "code").withColumn("code", F.col("code") + 1)
    view = from_long(long.join(codes, ["col", "value"]), len(columns), row_id, "col", "code", rows=df.select(row_id))
    return view, codes


def read_matrix_market(spark: SparkSession, path: str) -> MatrixView:
    """A coordinate Matrix-Market text file."""
    lines = spark.read.text(path).where(~F.col("value").startswith("%"))
    parts = lines.select(F.split(F.trim("value"), r"\s+").alias("p"), F.monotonically_increasing_id().alias("at"))
    n, m, _ = (int(x) for x in parts.orderBy("at").first()["p"])
    first = parts.agg(F.min("at")).first()[0]
    return from_long(_coordinates(parts.where(F.col("at") != first)), m, rows=spark.range(n).withColumnRenamed("id", "row_id"))


def read_libsvm(spark: SparkSession, path: str, m: int) -> MatrixView:
    """Lines are rows in the order of file names and of places in a file; Spark itself deals files and their parts by size."""
    place = {"file": F.col("_metadata.file_path"), "start": F.col("_metadata.file_block_start"), "at": F.monotonically_increasing_id()}
    lines = with_row_ids(spark.read.text(path).withColumns(place), list(place)).select("row_id", "value")
    feats = lines.select("row_id", F.explode(F.slice(F.split(F.trim("value"), r"\s+"), 2, 1 << 30)).alias("f")).where("f LIKE '%:%'")
    cells = feats.select("row_id", (F.split("f", ":")[0].cast("int") - 1).alias("col"), F.split("f", ":")[1].cast("double").alias("val"))
    return from_long(cells, m, rows=lines.select("row_id"))


def write_matrix_market(view: MatrixView, path: str) -> None:
    """A folder of Matrix-Market coordinate text: the head in a part of its own, then the cells; ids count from 1."""
    spark = view.rows.sparkSession
    t = view.rows.agg(F.sum(F.size("cols"))).first()[0] or 0
    top = (view.rows.agg(F.max("row_id")).first()[0] or 0) + 1
    head = spark.createDataFrame([("%%MatrixMarket matrix coordinate real general",), (f"{top} {view.m} {t}",)], "value string").coalesce(1)
    head.write.mode("overwrite").text(f"{path}/head")
    view.cells.select(F.concat_ws(" ", F.col("row_id") + 1, F.col("col") + 1, F.col("val")).alias("value")).write.mode("overwrite").text(f"{path}/cells")


def read_matrix_market_parts(spark: SparkSession, path: str) -> MatrixView:
    """What ``write_matrix_market`` wrote."""
    n, m, _ = (int(x) for x in spark.read.text(f"{path}/head").where(~F.col("value").startswith("%")).first()["value"].split())
    return from_long(_coordinates(spark.read.text(f"{path}/cells").select(F.split(F.trim("value"), r"\s+").alias("p"))), m, rows=spark.range(n).withColumnRenamed("id", "row_id"))


def _coordinates(parts: DataFrame) -> DataFrame:
    return parts.select((F.col("p")[0].cast("long") - 1).alias("row_id"), (F.col("p")[1].cast("int") - 1).alias("col"), F.col("p")[2].cast("double").alias("val"))


def write_libsvm(view: MatrixView, path: str) -> None:
    """A line per row, in order of row_id: a zero label, then column:value, columns from 1."""
    pairs = F.transform(F.arrays_zip("cols", "vals"), lambda x: F.concat_ws(":", x["cols"] + 1, x["vals"]))
    view.rows.orderBy("row_id").select(F.concat_ws(" ", F.lit("0"), pairs).alias("value")).write.mode("overwrite").text(path)


def quantise(view: MatrixView, decimals: int) -> MatrixView:
    """Values rounded first (lossy), then treated as any matrix; what becomes zero drops out."""
    pairs = F.filter(F.transform(F.arrays_zip("cols", "vals"), lambda x: F.struct(x["cols"].alias("c"), (F.round(x["vals"], decimals) + 0.0).alias("v"))), lambda x: x["v"] != 0)
    rows = view.rows.withColumn("x", pairs).select("row_id", F.col("x.c").alias("cols"), F.col("x.v").alias("vals"))
    return MatrixView(rows, view.m, view.names)
