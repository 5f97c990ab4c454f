"""Streams of rows: every micro-batch becomes further blocks, so products and sums never rebuild old ones."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Blocks, MatrixView, shared_folder
from ..operators import multiply
from ..sources import matrices as src

TYPES = ("click", "view", "error", "purchase", "signup")
DAYS = 30


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/symmat-stream-{uuid.uuid4().hex}"


class BlockSink:
    """A foreachBatch target: compresses each micro-batch into blocks with their own dictionaries and appends them as Parquet, one folder a batch.

    A batch that is delivered again overwrites its own folder, so it counts once. Late rows of a matrix row are cells of a
    further block under the same row id: products add over all blocks of a row.
    """

    def __init__(self, path: str, m: int, codec: str = "gpack", rows_per_block: int = 65_536) -> None:
        self.path, self.m, self.codec, self.rows_per_block = path, m, codec, rows_per_block

    def __call__(self, cells: DataFrame, batch: int) -> None:
        view = src.from_long(cells, self.m)
        blocks = max(1, -(-view.n // self.rows_per_block))
        made = multiply.compress(view, blocks, self.codec, scope="block")
        made.df.write.mode("overwrite").parquet(f"{self.path}/batch={batch}")

    def blocks(self, spark: SparkSession) -> Blocks:
        return Blocks(spark.read.parquet(self.path).withColumn("block", F.pmod(F.xxhash64("batch", "block"), F.lit(1 << 31)).cast("int")).drop("batch"), self.m, self.codec)


def right(blocks: Blocks, x: np.ndarray) -> DataFrame:
    """y = Mx where a row may lie in several blocks."""
    return multiply.right(blocks, x).groupBy("row_id").agg(F.sum("y").alias("y"))


def compact(sink: BlockSink, spark: SparkSession, path: str) -> None:
    """All batches rebuilt as one set of blocks at ``path``, each row in one block again."""
    cells = multiply.decode(sink.blocks(spark)).groupBy("row_id", "col").agg(F.sum("val").alias("val"))
    view = src.from_long(cells, sink.m)
    multiply.compress(view, max(1, -(-view.n // sink.rows_per_block)), sink.codec, scope="block").df.write.mode("overwrite").parquet(f"{path}/batch=0")


def event_cells(events: DataFrame) -> DataFrame:
    """(row_id, col, val) of user by type and day of month; an event adds 1 to its cell."""
    kinds = F.array(*[F.lit(t) for t in TYPES])
    at = F.array_position(kinds, F.col("event_type")) - 1
    return events.where(F.col("event_type").isin(*TYPES) & (F.dayofmonth("ts") <= DAYS)).select(F.col("user_id").alias("row_id"), (at * DAYS + F.dayofmonth("ts") - 1).cast("int").alias("col"))


def replay_events(spark: SparkSession, sf_dir: str, batches: int = 4) -> DataFrame:
    """The events table as a stream of files, block by block; returns y = Mx, x = (1, 2, ...), over all blocks."""
    folder = _folder(spark)
    table = src.table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    table.repartition(batches, "event_id").write.parquet(f"{folder}/in")
    sink = BlockSink(f"{folder}/blocks", len(TYPES) * DAYS)

    def each(df: DataFrame, batch: int) -> None:
        sink(event_cells(df).groupBy("row_id", "col").agg(F.count("*").cast("double").alias("val")), batch)

    stream = spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    query = stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    some = right(sink.blocks(spark), np.arange(1.0, sink.m + 1))
    users = src.table(spark, sf_dir, "events").select(F.col("user_id").alias("row_id")).distinct()
    return users.join(some, "row_id", "left").select("row_id", F.coalesce("y", F.lit(0.0)).alias("y"))


def left_stream(cells: DataFrame, y_of_row=lambda row: 1 + F.pmod(row, F.lit(7))) -> DataFrame:
    """A streaming left product: running sums of val * y per column, y a formula of the row id."""
    return cells.groupBy("col").agg(F.sum(F.col("val") * y_of_row(F.col("row_id"))).alias("x"))


def windowed(events: DataFrame, length: str = "1 day", late: str = "2 days", slide: str | None = None) -> DataFrame:
    """Counts by type in tumbling or sliding windows under a watermark."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", late).groupBy(F.window("ts", length, slide), "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 days") -> DataFrame:
    """Events per user and session."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def daily_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``windowed`` over the whole table as a stream drained once into Parquet: (day, event_type, n)."""
    folder = _folder(spark)
    table = src.table(spark, sf_dir, "events").select("ts", "event_type")
    table.write.parquet(f"{folder}/in")
    stream = spark.readStream.schema(table.schema).parquet(f"{folder}/in")
    counts = windowed(stream).select(F.col("window.start").cast("date").alias("day"), "event_type", "n")

    def each(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{folder}/out/batch={batch}")

    query = counts.writeStream.outputMode("complete").foreachBatch(each).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.parquet(f"{folder}/out")
    last = out.agg(F.max("batch")).first()[0]
    return out.where(F.col("batch") == last).drop("batch")
