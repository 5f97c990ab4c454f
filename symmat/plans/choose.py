"""Planning: block counts, and the codec of least time under a memory budget."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import BLOCK_SCHEMA, Blocks, MatrixView, cut, stored
from ..operators import measure, multiply
from ..operators.codec import NAMES
from ..operators.kernel import METHODS, Grammar
from ..operators.multiply import block_count  # noqa: F401

def candidates(view: MatrixView, blocks: int, codecs: tuple[str, ...] = NAMES, rounds: int = 1, ready: bool = False, keep: Callable[[DataFrame, Broadcast], DataFrame] | None = None) -> Blocks:
    """Every block (piece by piece) under every codec, with the seconds of a fused product: BLOCK_SCHEMA, seconds. The grammar is built once.

    The seconds are those of decoding and multiplying, or, with ``ready``, of multiplying a decoded block; means of ``rounds``.
    ``keep``: what of the table is materialised, by it and the broadcast dictionary, where the encoded bytes need not outlive the pass.
    """
    values, m = multiply.shared_values(view), view.m
    shared = view.rows.sparkSession.sparkContext.broadcast(values)

    def work(key: tuple, rows: pa.Table) -> pa.Table:
        import time

        from ..operators import codec as cd
        from ..operators.kernel import Ready

        ids, sym, row, used = multiply.block_symbols(rows, m, shared.value, None)
        flat = Grammar(np.zeros((0, 2), np.int64), sym, row, len(ids), len(used) * m)
        g = METHODS["exact"](sym, row, len(ids), len(used) * m)
        out = []
        for name in codecs:
            packed = multiply.pack_block(key[0].as_py(), ids, len(sym) + len(ids), flat if name == "stream" else g, name, None if shared.value is not None else used, key[1].as_py())
            decoded = lambda p=packed, n=name: Ready(cd.decode(n, p["c"], p["r"], p["width"], p["c_len"], p["r_len"], p["space"]), m, used)
            kept = decoded() if ready else None
            start = time.perf_counter()
            for _ in range(rounds):
                one = kept or decoded()
                one.left(one.right(np.ones(m)))
            out.append(packed | {"seconds": (time.perf_counter() - start) / rounds})
        return pa.Table.from_pylist(out, multiply._ARROW.append(pa.field("seconds", pa.float64())))

    made = multiply.in_pieces(view, blocks).applyInArrow(work, BLOCK_SCHEMA + ", seconds double")
    return Blocks(cut(made) if keep is None else stored(keep(made, shared)), m, "mixed", values)


def choose(view: MatrixView, budget_bytes: int, blocks: int = 1, per_block: bool = True) -> Blocks:
    """The codec of least measured time whose bytes (and working space) fit the budget; raises if none does.

    Per matrix: the fastest codec that fits. Per block: start from each block's smallest codec, then take, by time saved per
    byte, the upgrades that still fit. What is compared is a few numbers per block and codec.
    """
    every = candidates(view, blocks)
    facts = every.df.groupBy("block", "codec").agg(F.sum(F.col("c_bytes") + F.col("r_bytes") + F.col("v_bytes") + 8 * F.col("r_len")).alias("b"), F.sum("seconds").alias("seconds")).collect()
    fixed = (8 * len(every.values) if every.values is not None else 0) + 8 * (view.n + view.m)
    if not per_block:
        total = {c: (sum(f.seconds for f in facts if f.codec == c), sum(f.b for f in facts if f.codec == c)) for c in NAMES}
        fit = [c for c in NAMES if fixed + total[c][1] <= budget_bytes]
        if not fit:
            raise ValueError("no codec fits the budget")
        pick = {f.block: min(fit, key=lambda c: total[c][0]) for f in facts}
    else:
        own: dict[int, list] = {}
        for f in facts:
            own.setdefault(f.block, []).append(f)
        now = {b: min(fs, key=lambda f: (f.b, f.seconds)) for b, fs in own.items()}
        room = budget_bytes - fixed - sum(f.b for f in now.values())
        if room < 0:
            raise ValueError("no codec fits the budget")
        steps = sorted(((now[b].seconds - f.seconds) / max(1, f.b - now[b].b), b, f) for b, fs in own.items() for f in fs if f.seconds < now[b].seconds)[::-1]
        for _, b, f in steps:
            cost = f.b - now[b].b
            if f.seconds < now[b].seconds and cost <= room:
                room, now[b] = room - cost, f
        pick = {b: f.codec for b, f in now.items()}
    wanted = view.rows.sparkSession.createDataFrame(list(pick.items()), "block int, codec string")
    return Blocks(every.df.join(F.broadcast(wanted), ["block", "codec"], "left_semi").drop("seconds"), view.m, "mixed", every.values)


def cluster_rows(view: MatrixView, key) -> MatrixView:
    """Rows renumbered in the order of ``key`` (an expression over cols and vals), so that blocks hold rows that are alike; (row_id) is new, ``old_id`` kept."""
    from ..sources.matrices import with_row_ids

    rows = with_row_ids(view.rows.withColumn("k", key).withColumnRenamed("row_id", "old_id"), ["k", "old_id"])
    return MatrixView(rows.select("row_id", "cols", "vals", "old_id"), view.m, view.names)


def report(view: MatrixView, blocks: int = 1) -> dict[str, float]:
    """Sizes in percent of dense of all codecs on one build."""
    every = candidates(view, blocks, keep=lambda made, _: made.select("codec", "c_bytes", "r_bytes", "v_bytes"))
    fixed = 8 * len(every.values) if every.values is not None else 0
    return {r.codec: measure.size_pct(r.b + fixed, view.n, view.m) for r in every.df.groupBy("codec").agg(F.sum(F.col("c_bytes") + F.col("r_bytes") + F.col("v_bytes")).alias("b")).collect()}
