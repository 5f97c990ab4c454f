"""Cost and accuracy measures: features, sizes, shape, operations, entropy, time, memory, exactness."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..model import Blocks, MatrixView

#: Rows whose symbols are put in order together.
SPAN = 1 << 14


def features(view: MatrixView) -> DataFrame:
    """One row: n, m, t, nonzero_pct, distinct."""
    n = view.n
    return view.cells.agg(F.count("*").alias("t"), F.count_distinct("val").alias("distinct")).select(
        F.lit(n).cast("long").alias("n"), F.lit(view.m).cast("long").alias("m"), "t", (F.col("t") * 100.0 / F.lit(n * view.m)).alias("nonzero_pct"), "distinct"
    )


def stream_pct(n: int, m: int, t: int, distinct: int) -> float:
    """Size of the uncompressed stream in percent of dense, in closed form."""
    return 100.0 * (4 * (t + n) + 8 * distinct) / (8 * n * m)


def size_pct(nbytes: float, n: int, m: int) -> float:
    return 100.0 * nbytes / (8 * n * m)


def size(g: Blocks) -> int:
    """Bytes of all blocks and of the shared dictionary."""
    own = g.df.agg(F.sum(F.col("c_bytes") + F.col("r_bytes") + F.col("v_bytes"))).first()[0] or 0
    return own + (8 * len(g.values) if g.values is not None else 0)


def shape(g: Blocks) -> DataFrame:
    """One row: symbols of the stream and final strings (marks included), rules, largest id, width, depth."""
    return g.df.agg(F.sum("s_len").alias("s_len"), F.sum("c_len").alias("c_len"), F.sum("r_len").alias("r_len"), F.max(F.col("space") + F.col("r_len")).alias("n_max"), F.max("width").alias("width"), F.max("depth").alias("depth"))


def grammar_size(g: Blocks) -> int:
    """Sum of the lengths of right-hand sides, the final string being one of them."""
    return g.df.agg(F.sum(F.col("c_len") + 2 * F.col("r_len"))).first()[0]


def operations(g: Blocks) -> DataFrame:
    """Additions of one product on the compressed blocks, on the stream, and on the dense matrix."""
    return g.df.agg(F.sum(F.col("c_len") + F.col("r_len")).alias("compressed"), F.sum("s_len").alias("stream"), (F.sum("n_rows") * g.m).alias("dense"))


def _contexts(symbols: DataFrame, k: int) -> tuple[DataFrame, list[Column]]:
    """``symbols`` and the columns of each one's k predecessors within its block, nearest first; -1 where there is none.

    Spans of rows are numbered on their own; the k symbols before a span come from the tails of the up to k spans before it.
    """
    spanned = symbols.withColumn("span", F.floor(F.col("row_id") / SPAN))
    own = Window.partitionBy("block", "span").orderBy("row_id", "pos")
    placed = spanned.withColumn("at", F.row_number().over(own)).withColumns({f"p{i}": F.lag("sym", i).over(own) for i in range(1, k + 1)})
    sizes = placed.groupBy("block", "span").agg(F.max("at").alias("n"))
    ends = placed.join(sizes, ["block", "span"]).where(F.col("at") > F.col("n") - k)
    tails = ends.groupBy("block", "span").agg(F.array_sort(F.collect_list(F.struct("at", "sym")))["sym"].alias("tail"))
    earlier = F.flatten(F.collect_list("tail").over(Window.partitionBy("block").orderBy("span").rowsBetween(-k, -1)))
    before = tails.select("block", "span", earlier.alias("before"))
    joined = placed.join(before, ["block", "span"])
    at_border = [F.get("before", F.size("before") - (i + 1 - F.col("at"))) for i in range(1, k + 1)]
    return joined, [F.coalesce(f"p{i}", at_border[i - 1], F.lit(-1)).alias(f"x{i}") for i in range(1, k + 1)]


def entropy(symbols: DataFrame, k: int = 0, marks: DataFrame | None = None) -> DataFrame:
    """(total, h): symbols of the stream (marks included) and its order-k empirical entropy in bits; contexts do not cross blocks.

    ``symbols``: (block, row_id, pos, sym). ``marks``: the mark behind each row (``encode.row_marks``), so that empty rows
    count; without it, only rows that have symbols get one.
    """
    if marks is None:
        marks = symbols.groupBy("block", "row_id").agg((F.max("pos") + 1).alias("pos")).withColumn("sym", F.lit(0).cast("long"))
    every = symbols.select("block", "row_id", "pos", "sym").unionByName(marks.select("block", "row_id", "pos", "sym"))
    every, context = _contexts(every, k) if k else (every, [])
    names = [f"x{i}" for i in range(1, k + 1)]
    pair = every.select(*context, "sym").groupBy(*names, "sym").agg(F.count("*").alias("c"))
    # of a context: its count cc, and the sum of c log c over its symbols; no pair is joined with its context
    own = pair.groupBy(*names).agg(F.sum("c").alias("cc"), F.sum(F.col("c") * F.log2("c")).alias("d"))
    return own.agg(F.sum("cc").alias("total"), (F.sum(F.col("cc") * F.log2("cc") - F.col("d")) / F.sum("cc")).alias("h"))


def observed(view: MatrixView) -> tuple[MatrixView, Observation]:
    """The same matrix, whose next action also counts rows, cells and the largest absolute value, at no further pass."""
    seen = Observation()
    rows = view.rows.observe(seen, F.count("*").alias("n"), F.sum(F.size("cols")).alias("t"), F.max(F.array_max(F.transform("vals", F.abs))).alias("largest"))
    return MatrixView(rows, view.m, view.names, view.memo), seen


def timing(action: Callable[[], object], rounds: int = 1) -> float:
    """Mean seconds of an action."""
    start = time.perf_counter()
    for _ in range(rounds):
        action()
    return (time.perf_counter() - start) / rounds


def product_bytes(encoded: int, rules: int, n: int, m: int, blocks: int) -> int:
    """Bytes that a product needs by count: the encoded matrix, a value a rule, both vectors, a partial vector a block."""
    return encoded + 8 * rules + 8 * (n + m) + 8 * blocks * m


def memory_model(g: Blocks, n: int) -> dict[str, float]:
    """``product_bytes`` of blocks, the encoded bytes in it, and their percent of dense."""
    s = g.df.agg(F.sum("r_len").alias("r"), F.count_distinct("block").alias("b")).first()
    encoded = size(g)
    total = product_bytes(encoded, s.r, n, g.m, s.b)
    return {"encoded": encoded, "total": total, "pct": size_pct(total, n, g.m), "gap_pct": size_pct(total - encoded, n, g.m)}


def product_peaks(g: Blocks, rounds: int = 1) -> DataFrame:
    """(block, codec, base_kb, encoded_kb, peak_kb): each block's largest resident size while it is decoded and multiplied by both sides.

    Every piece of a block is run in a process of its own (``peak``), started afresh, whose peak is its own: base_kb is that
    process before it holds the piece, encoded_kb with the encoded piece, peak_kb after ``rounds`` of right and left products. What
    the pieces of a block took beyond their bases is added up, as if they were held at once.
    """
    return peaks_of_blocks(g.df.mapInArrow(peaks_of_pieces(g.m, g.shared, rounds), "block int, codec string, base_kb long, encoded_kb long, peak_kb long"))


def peaks_of_blocks(each: DataFrame) -> DataFrame:
    """The pieces' resident sizes, added up by block and codec."""
    base = F.max("base_kb")
    took = {k: (base + F.sum(F.col(k) - F.col("base_kb"))).alias(k) for k in ("encoded_kb", "peak_kb")}
    return each.groupBy("block", "codec").agg(base.alias("base_kb"), took["encoded_kb"], took["peak_kb"])


def peaks_of_pieces(m: int, shared, rounds: int = 1, codecs: tuple[str, ...] | None = None, kept: tuple[str, ...] = ("block", "codec")):
    """Runs over batches of pieces: the columns ``kept`` and base_kb, encoded_kb, peak_kb, null for other codecs than ``codecs``."""

    def run(batches):
        import os
        import pickle
        import subprocess
        import sys

        for batch in batches:
            for i in range(len(batch)):
                one, said = batch.slice(i, 1), [None] * 3
                if codecs is None or one.column("codec")[0].as_py() in codecs:
                    sink = pa.BufferOutputStream()
                    with pa.ipc.new_stream(sink, one.schema) as writer:
                        writer.write_batch(one)
                    load = pickle.dumps((sink.getvalue().to_pybytes(), m, shared.value, rounds))
                    out = subprocess.run([sys.executable, "-m", "symmat.operators.peak"], input=load, capture_output=True, check=True, env=os.environ | {"PYTHONPATH": os.pathsep.join(sys.path)}).stdout.split()
                    said = [int(x) for x in out[-3:]]
                yield pa.RecordBatch.from_arrays([*(one.column(k) for k in kept), *(pa.array([x], pa.int64()) for x in said)], names=[*kept, "base_kb", "encoded_kb", "peak_kb"])

    return run


def improvement(before: float, after: float) -> float:
    return (before - after) / before


def ratio(a: float, b: float) -> float:
    return a / b


def max_abs_err(a: DataFrame, b: DataFrame, key: str, value: str) -> float:
    """The largest absolute difference of two keyed columns; a key on one side alone counts as infinite."""
    both = a.select(key, F.col(value).alias("p")).join(b.select(key, F.col(value).alias("q")), key, "full_outer")
    diff = F.when(F.col("p").isNull() | F.col("q").isNull(), F.lit(float("inf"))).otherwise(F.abs(F.col("p") - F.col("q")))
    return both.agg(F.max(diff)).first()[0] or 0.0
