"""A table of fixed size that tells which keys of a large table may be wanted, so that a scan can leave out most others."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F

CELLS = 1 << 24


def mark(wanted: DataFrame, column: str):
    """Broadcast bits, one per cell of the numbers in ``column``: at most CELLS / 8 bytes, whatever the table's size."""
    cell = F.pmod(column, F.lit(CELLS))
    cells = wanted.groupBy(F.shiftright(cell, 15).cast("int").alias("row")).agg(F.bitmap_construct_agg(cell.bitwiseAND(F.lit(0x7FFF))).alias("bits"))
    marked = np.zeros(CELLS // 8, np.uint8)
    for r in cells.collect():
        marked[r.row * 4096 : r.row * 4096 + len(r.bits)] = np.frombuffer(r.bits, np.uint8)
    return wanted.sparkSession.sparkContext.broadcast(marked)


def is_marked(marked: np.ndarray, numbers: np.ndarray) -> np.ndarray:
    c = np.mod(numbers, CELLS)
    return (marked[c >> 3] >> (c & 7).astype(np.uint8) & 1).astype(bool)
