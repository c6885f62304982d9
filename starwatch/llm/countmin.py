"""Count-min sketches in tiles: one partial sketch per task, merged tile by tile in a tree.

Counters saturate at 2, as only "at least twice" is ever asked. A partial sketch is
sent as the sorted cells it touched (delta coded, compressed), so it never exceeds
what the task has seen, nor the sketch. The merged sketch has a fixed size, given by its
parameters: a bit per cell.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import free, materialise

BLOCKS = "tile int, part long, once binary, twice binary"
FAN_IN = 256


@dataclass(frozen=True)
class SketchShape:
    """``rows`` hash functions over 2**``log_width`` cells each, in tiles of 2**``log_tile``."""

    rows: int = 2
    log_width: int = 27
    log_tile: int = 22

    @property
    def tiles(self) -> int:
        return self.rows << (self.log_width - self.log_tile)

    def cells(self, values: np.ndarray, row: int) -> np.ndarray:
        """Cell of each 64-bit value in one row; rows use different bits of the value."""
        shift = (64 - self.log_width) if row == 0 else 3
        odd = np.uint64(0x9E3779B97F4A7C15 if row == 0 else 0xC2B2AE3D27D4EB4F)
        return ((values * odd) >> np.uint64(shift)) & np.uint64((1 << self.log_width) - 1)


def _pack(cells: np.ndarray) -> bytes:
    return zlib.compress(np.diff(cells.astype(np.uint32), prepend=np.uint32(0)).astype("<u4").tobytes(), 1)


def _unpack(block: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(zlib.decompress(block), "<u4"), dtype=np.int64)


class Partial:
    """A task's sketch: which cells it has hit once and twice or more."""

    def __init__(self, shape: SketchShape, limit: int = 1_000_000):
        self.shape, self.limit = shape, limit
        self.waiting: list[np.ndarray] = []
        self.n = 0
        self.parts = 0

    def add(self, values: np.ndarray):
        """Take values; yields a block of rows (tile, part, once, twice) when enough wait."""
        self.waiting.append(values)
        self.n += len(values)
        if self.n >= self.limit:
            yield self.flush()

    def flush(self) -> list[tuple[int, bytes, bytes]]:
        values = np.concatenate(self.waiting) if self.waiting else np.zeros(0, np.uint64)
        self.waiting, self.n = [], 0
        out, tile_cells = [], np.uint64(1 << self.shape.log_tile)
        per_row = self.shape.tiles // self.shape.rows
        for row in range(self.shape.rows):
            cells, counts = np.unique(self.shape.cells(values, row), return_counts=True)
            edges = np.searchsorted(cells, np.arange(per_row + 1, dtype=np.uint64) * tile_cells)
            for t in range(per_row):
                a, b = edges[t], edges[t + 1]
                if b > a:
                    local = cells[a:b] - np.uint64(t) * tile_cells
                    out.append((row * per_row + t, _pack(local), _pack(local[counts[a:b] > 1])))
        return out


def merge(blocks: DataFrame, shape: SketchShape) -> bytes:
    """Merge partial sketches; the bits "count is 2 or more" of all cells, row after row.

    The tree merges at most FAN_IN blocks in a task at each step, whatever their number.
    What comes to the driver is rows * 2**log_width bits at most (compressed).
    """
    tile_size = 1 << shape.log_tile

    def step(pdf: pd.DataFrame) -> pd.DataFrame:
        one, two = np.zeros(tile_size, bool), np.zeros(tile_size, bool)
        for once, twice in zip(pdf["once"], pdf["twice"], strict=True):
            cells = _unpack(once)
            two[cells[one[cells]]] = True
            one[cells] = True
            two[_unpack(twice)] = True
        return pd.DataFrame({"tile": [int(pdf["tile"].iloc[0])], "part": [int(pdf["part"].iloc[0]) // FAN_IN], "once": [_pack(np.flatnonzero(one))], "twice": [_pack(np.flatnonzero(two))]})

    left = blocks.agg(F.max("part")).first()[0]
    while left is not None:
        before, blocks = blocks, materialise(blocks.groupBy("tile", F.floor(F.col("part") / FAN_IN).alias("_group")).applyInPandas(step, BLOCKS), "sketch")
        free(before)
        left = left // FAN_IN
        if left == 0:
            break
    bits = np.zeros(shape.tiles * tile_size // 8, np.uint8)
    for r in blocks.select("tile", "twice").toLocalIterator():
        tile = np.zeros(tile_size, bool)
        tile[_unpack(bytes(r.twice))] = True
        bits[r.tile * tile_size // 8 : (r.tile + 1) * tile_size // 8] = np.packbits(tile, bitorder="little")
    free(blocks)
    return bits.tobytes()


def at_least_twice(bits: np.ndarray, shape: SketchShape, values: np.ndarray) -> np.ndarray:
    """Whether the estimate (the minimum over the rows) of each value is 2 or more."""
    out = np.ones(len(values), bool)
    for row in range(shape.rows):
        cell = shape.cells(values, row).astype(np.int64) + (row << shape.log_width)
        out &= (bits[cell >> 3] >> (cell & 7).astype(np.uint8)) & np.uint8(1) == 1
    return out
