"""Peak resident size of one block's products, in a process of its own; light to import, as every measure starts one.

    python -m symmat.operators.peak < load

``load`` is a pickled tuple: an Arrow stream with the block's row, the matrix's width, the shared dictionary or None, rounds.
"""

from __future__ import annotations

import pickle
import sys

import numpy as np
import pyarrow as pa

from . import codec
from .kernel import Ready


def resident_peak() -> int:
    """Largest resident size of this process so far, in kB."""
    with open("/proc/self/status") as f:
        return next(int(line.split()[1]) for line in f if line.startswith("VmHWM"))


def of_block(load: bytes, m: int, values: np.ndarray | None, rounds: int) -> tuple[int, int, int]:
    """Peaks before, with, and after products on the one block in ``load``."""
    base = resident_peak()
    row = {k: v[0] for k, v in next(iter(pa.ipc.open_stream(load))).to_pydict().items() if k != "row_ids"}
    held = resident_peak()
    own = values if row["v"] is None else np.array(row["v"])
    for _ in range(rounds):
        g = codec.decode(*(row[k] for k in ("codec", "c", "r", "width", "c_len", "r_len", "space")))
        ready = Ready(g, m, own)
        ready.left(ready.right(np.ones(m)))
    return base, held, resident_peak()


if __name__ == "__main__":
    print(*of_block(*pickle.load(sys.stdin.buffer)))
