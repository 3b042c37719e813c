"""Space-filling curve keys as column expressions and as numpy."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def curve_bits(d: int) -> int:
    return min(16, 62 // d)


def lattice(value: Column, low: float, high: float, bits: int) -> Column:
    """A coordinate as a whole number of ``bits`` bits; the ends are clamped."""
    top = (1 << bits) - 1
    span = high - low if high > low else 1.0
    return F.greatest(F.lit(0), F.least(F.lit(top), F.floor((value - low) / span * top))).cast("long")


def z_key(cells: Sequence[Column], bits: int) -> Column:
    """Interleaved bits: bit t of axis a goes to place t d + a. Shifts and masks only."""
    d, key = len(cells), F.lit(0).cast("long")
    for a, cell in enumerate(cells):
        for t in range(bits):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(cell, t).bitwiseAND(F.lit(1)), t * d + a))
    return key


def z_key_sql(cells: Sequence[str], bits: int) -> str:
    d = len(cells)
    return " + ".join(f"((({cell}) >> {t}) & 1) * {1 << (t * d + a)}" for a, cell in enumerate(cells) for t in range(bits))


def z_key_np(cells: np.ndarray, bits: int) -> np.ndarray:
    d, key = cells.shape[1], np.zeros(len(cells), np.int64)
    for a in range(d):
        for t in range(bits):
            key |= ((cells[:, a] >> t) & 1) << (t * d + a)
    return key


def hilbert_key_np(cells: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert index of d-dimensional cells, most significant bits first: undo the rotations and reflections level by level, then Gray-decode."""
    x = cells.astype(np.int64).T.copy()
    d = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(d):
            on = (x[i] & q) != 0
            swap = (x[0] ^ x[i]) & p
            flipped = x[0] ^ p
            x[0] = np.where(on, flipped, x[0] ^ swap)
            if i:
                x[i] = np.where(on, x[i], x[i] ^ swap)
        q >>= 1
    for i in range(1, d):
        x[i] ^= x[i - 1]
    t = np.zeros(x.shape[1], np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where((x[d - 1] & q) != 0, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    key = np.zeros(x.shape[1], np.int64)
    for b in reversed(range(bits)):
        for i in range(d):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def hilbert_udf(bits: int):
    """The Hilbert index of an array of cells, by batch."""

    @F.arrow_udf("long")
    def key(cells: pa.Array) -> pa.Array:
        flat = cells.fill_null([]).flatten().fill_null(0).to_numpy(zero_copy_only=False)
        return pa.array(hilbert_key_np(flat.reshape(len(cells), -1), bits) if len(cells) else np.zeros(0, np.int64))

    return key


def hilbert_sql(x: str, y: str, bits: int, source: str, keep: str) -> str:
    """DuckDB SQL that walks the curve's four states from the top bit down (two axes)."""
    return f"""WITH RECURSIVE walk AS (SELECT {keep}, CAST({x} AS BIGINT) AS px, CAST({y} AS BIGINT) AS py, CAST(0 AS BIGINT) AS hkey, {bits - 1} AS b FROM {source}
UNION ALL SELECT {keep},
CASE WHEN (py >> b) & 1 = 0 THEN CASE WHEN (px >> b) & 1 = 1 THEN ((1 << b) - 1) - (py & ((1 << b) - 1)) ELSE py & ((1 << b) - 1) END ELSE px & ((1 << b) - 1) END,
CASE WHEN (py >> b) & 1 = 0 THEN CASE WHEN (px >> b) & 1 = 1 THEN ((1 << b) - 1) - (px & ((1 << b) - 1)) ELSE px & ((1 << b) - 1) END ELSE py & ((1 << b) - 1) END,
hkey * 4 + xor(3 * ((px >> b) & 1), (py >> b) & 1), b - 1 FROM walk WHERE b >= 0)
SELECT {keep}, hkey FROM walk WHERE b = -1"""
