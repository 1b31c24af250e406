"""Recursive space-filling curves on three-dimensional grids: Morton and Hilbert codes of up to 63 bits.

Morton codes are bit arithmetic inside generated code. Hilbert codes follow a table of orientations, derived here from
the Gray-code construction of compact Hilbert indices; one form runs on Arrow batches, another is all expressions.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import GridSpec, quantise

# fixed values: (shift, mask) pairs that spread 21 bits to every third place of 63
SPREAD = [(32, 0x1F00000000FFFF), (16, 0x1F0000FF0000FF), (8, 0x100F00F00F00F00F), (4, 0x10C30C30C30C30C3), (2, 0x1249249249249249)]
CURVES = ("none", "morton", "hilbert")


def _or(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out.bitwiseOR(p)
    return out


def _spread(c: Column) -> Column:
    out = c.cast("long")
    for shift, mask in SPREAD:
        out = out.bitwiseOR(F.shiftleft(out, shift)).bitwiseAND(F.lit(mask))
    return out


def _gather(code: Column) -> Column:
    out = code.bitwiseAND(F.lit(SPREAD[-1][1]))
    for (shift, _), mask in zip(SPREAD[::-1], [m for _, m in SPREAD[-2::-1]] + [0x1FFFFF], strict=True):
        out = out.bitwiseOR(F.shiftright(out, shift)).bitwiseAND(F.lit(mask))
    return out.cast("int")


def morton_encode(cx: Column, cy: Column, cz: Column, method: str = "masks", axis_order: str = "xyz") -> Column:
    """The first axis of ``axis_order`` gives the highest bit of each level. ``table`` looks bytes up in a literal array."""
    axes = dict(zip("xyz", (cx, cy, cz), strict=True))
    parts = [axes[a] for a in axis_order]
    if method == "table":
        row = F.array(*(F.lit(int(np_spread(np.array([b]))[0])).cast("long") for b in range(256)))
        byte = lambda c, s: F.element_at(row, F.shiftright(c, s).bitwiseAND(F.lit(255)) + 1)
        spread = [_or([F.shiftleft(byte(c, s), 3 * s) for s in (0, 8, 16)]) for c in parts]
    else:
        spread = [_spread(c) for c in parts]
    return _or([F.shiftleft(s, 2 - i) for i, s in enumerate(spread)])


def morton_decode(code: Column, axis_order: str = "xyz") -> dict[str, Column]:
    return {a: _gather(F.shiftright(code, 2 - i)) for i, a in enumerate(axis_order)}


def np_spread(c: np.ndarray) -> np.ndarray:
    out = c.astype(np.int64)
    for shift, mask in SPREAD:
        out = (out | out << shift) & mask
    return out


def np_morton(cells: np.ndarray) -> np.ndarray:
    return np_spread(cells[:, 0]) << 2 | np_spread(cells[:, 1]) << 1 | np_spread(cells[:, 2])


def np_morton_decode(code: np.ndarray) -> np.ndarray:
    def gather(x: np.ndarray) -> np.ndarray:
        out = x & SPREAD[-1][1]
        for (shift, _), mask in zip(SPREAD[::-1], [m for _, m in SPREAD[-2::-1]] + [0x1FFFFF], strict=True):
            out = (out | out >> shift) & mask
        return out

    return np.stack([gather(code >> 2), gather(code >> 1), gather(code)], axis=1)


@cache
def orientation_table() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(digit, following, octant): by state and octant the curve digit and the next state; by state and digit the octant."""

    def rotate(v: int, by: int) -> int:
        by %= 3
        return (v << by | v >> (3 - by)) & 7

    def entry(w: int) -> int:
        v = 2 * ((w - 1) // 2)
        return 0 if w == 0 else v ^ v >> 1

    def ones(v: int) -> int:
        return (~v & v + 1).bit_length() - 1

    states, rows = [(0, 0)], []
    for e, d in states:  # grows while it is walked
        digit, following = [0] * 8, [0] * 8
        for b in range(8):
            g = rotate(b ^ e, -(d + 1))
            w = g ^ g >> 1 ^ g >> 2
            turn = 0 if w == 0 else ones(w - 1) % 3 if w % 2 == 0 else ones(w) % 3
            nxt = (e ^ rotate(entry(w), d + 1), (d + turn + 1) % 3)
            if nxt not in states:
                states.append(nxt)
            digit[b], following[b] = w, states.index(nxt)
        rows.append((digit, following))
    digit, following = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    return digit, following, np.argsort(digit, axis=1)


def np_hilbert(cells: np.ndarray, levels: int) -> np.ndarray:
    digit, following, _ = orientation_table()
    state, code = np.zeros(len(cells), np.int64), np.zeros(len(cells), np.int64)
    for s in range(levels - 1, -1, -1):
        b = (cells[:, 0] >> s & 1) << 2 | (cells[:, 1] >> s & 1) << 1 | (cells[:, 2] >> s & 1)
        code = code << 3 | digit[state, b]
        state = following[state, b]
    return code


def np_hilbert_decode(code: np.ndarray, levels: int) -> np.ndarray:
    _, following, octant = orientation_table()
    state, out = np.zeros(len(code), np.int64), np.zeros((len(code), 3), np.int64)
    for s in range(levels - 1, -1, -1):
        b = octant[state, code >> 3 * s & 7]
        for i in range(3):
            out[:, i] |= (b >> (2 - i) & 1) << s
        state = following[state, b]
    return out


def np_encode(cells: np.ndarray, curve: str, levels: int) -> np.ndarray:
    return np_morton(cells) if curve == "morton" else np_hilbert(cells, levels)


def np_decode(code: np.ndarray, curve: str, levels: int) -> np.ndarray:
    return np_morton_decode(code) if curve == "morton" else np_hilbert_decode(code, levels)


def hilbert_encode(cx: Column, cy: Column, cz: Column, levels: int, method: str = "arrow") -> Column:
    if method == "arrow":

        @F.pandas_udf("long")
        def encode(batches: Iterator[tuple[pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
            for x, y, z in batches:
                yield pd.Series(np_hilbert(np.stack([x, y, z], axis=1).astype(np.int64), levels))

        return encode(cx, cy, cz)
    digit, following, _ = orientation_table()
    digits, states = (F.array(*(F.lit(int(v)) for v in t.ravel())) for t in (digit, following))

    def step(acc: Column, s: Column) -> Column:
        bit = lambda c: F.call_function("getbit", c, s)
        at = acc["state"] * 8 + bit(cx) * 4 + bit(cy) * 2 + bit(cz) + 1
        code = acc["code"] * 8 + F.element_at(digits, at.cast("int"))
        return F.struct(code.alias("code"), F.element_at(states, at.cast("int")).cast("long").alias("state"))

    start = F.struct(F.lit(0).cast("long").alias("code"), F.lit(0).cast("long").alias("state"))
    return F.aggregate(F.sequence(F.lit(levels - 1), F.lit(0), F.lit(-1)), start, step)["code"]


def hilbert_decode(code: Column, levels: int) -> Column:
    @F.pandas_udf("cx int, cy int, cz int")
    def decode(codes: pd.Series) -> pd.DataFrame:
        return pd.DataFrame(np_hilbert_decode(codes.to_numpy(), levels).astype(np.int32), columns=["cx", "cy", "cz"])

    return decode(code)


def encode(df: DataFrame, grid: GridSpec, curve: str, method: str | None = None) -> DataFrame:
    """Adds cx, cy, cz and ``code``; a narrow projection."""
    cells = quantise(df, grid)
    c = (F.col("cx"), F.col("cy"), F.col("cz"))
    if curve == "none":
        return cells.withColumn("code", F.lit(0).cast("long"))
    code = morton_encode(*c, **({"method": method} if method else {})) if curve == "morton" else hilbert_encode(*c, grid.levels, method or "arrow")
    return cells.withColumn("code", code)


# -- checks on small grids ------------------------------------------------------------------------------------------
def all_cells(level: int) -> np.ndarray:
    return np.array([*product(range(1 << level), repeat=3)], np.int64)


def check_recursive(curve: str, level: int) -> bool:
    """Each octant's codes are one run: a cell's code starts with its parent's."""
    if level == 0:
        return True
    cells = all_cells(level)
    return bool((np_encode(cells, curve, level) >> 3 == np_encode(cells >> 1, curve, level - 1)).all())


def check_continuous(curve: str, level: int) -> bool:
    """Successive codes are cells that differ by one at most on every axis."""
    path = np_decode(np.arange(8**level), curve, level)
    return bool((np.abs(np.diff(path, axis=0)).max(axis=1) <= 1).all())


def encode2(curve: str, cells: np.ndarray, level: int) -> np.ndarray:
    """Two-dimensional curves, for illustration: z-order, or Hilbert by reflecting and swapping quadrants."""
    x, y, code = cells[:, 0].copy(), cells[:, 1].copy(), np.zeros(len(cells), np.int64)
    for s in range(level - 1, -1, -1):
        bx, by = x >> s & 1, y >> s & 1
        if curve == "morton":
            code = code << 2 | bx << 1 | by
            continue
        code = code << 2 | (3 * bx ^ by)
        flip, swap = (by == 0) & (bx == 1), by == 0
        mask = (1 << s) - 1
        x, y = np.where(flip, mask - (x & mask), x & mask), np.where(flip, mask - (y & mask), y & mask)
        x, y = np.where(swap, y, x), np.where(swap, x, y)
    return code
