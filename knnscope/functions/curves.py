"""Space-filling curves as column expressions (for tables) and on numpy arrays (for the few cells on the driver).

All three curves are hierarchical: a cell of a coarser level owns one contiguous range of the keys of the finest, so a
stored key serves every level.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("hilbert", "z", "peano")


def base(kind: str) -> int:
    """Into how many parts a side is cut at each level."""
    if kind not in KINDS:
        raise ValueError(f"no curve {kind}")
    return 3 if kind == "peano" else 2


def cell_columns(x: Column, y: Column, domain, n: int) -> tuple[Column, Column]:
    """Cell numbers along both sides of a square ``domain = (x0, y0, side)`` cut into n x n half-open cells."""
    x0, y0, side = domain
    return tuple(F.floor((c - F.lit(float(o))) / F.lit(side / n)).cast("long") for c, o in ((x, x0), (y, y0)))


def _spread(v: Column) -> Column:
    """Put a zero bit between the bits of a number below 2^31."""
    for shift, mask in (
        (16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555),
    ):
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
    return v


def z_column(cx: Column, cy: Column, order: int) -> Column:
    """Interleaved bits by shifts and masks, which stay inside generated code. x has the higher bit of each pair."""
    return F.shiftleft(_spread(cx.cast("long")), 1).bitwiseOR(_spread(cy.cast("long")))


def hilbert_column(cx: Column, cy: Column, order: int) -> Column:
    """Top-down over the bits: the quadrant's number in the current orientation, then the orientation inside it."""

    def down(s: Column, level: Column) -> Column:
        half = F.pow(F.lit(2.0), level).cast("long")
        right, top = F.floor(s["x"] / half).cast("long"), F.floor(s["y"] / half).cast("long")
        x, y = s["x"] % half, s["y"] % half
        turned = (top == 0) & (right == 1)
        return F.struct(
            F.when(top == 1, x).when(turned, half - 1 - y).otherwise(y).alias("x"),
            F.when(top == 1, y).when(turned, half - 1 - x).otherwise(x).alias("y"),
            (s["key"] * 4 + F.when(right == 1, 3 - top).otherwise(top)).alias("key"),
        )

    start = F.struct(cx.cast("long").alias("x"), cy.cast("long").alias("y"), F.lit(0).cast("long").alias("key"))
    return F.aggregate(F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1)), start, down, lambda s: s["key"])


def peano_column(cx: Column, cy: Column, order: int) -> Column:
    """Ternary digits of x and y in turn; a digit is mirrored while the other side's digits so far add up to odd."""

    def down(s: Column, level: Column) -> Column:
        third = F.pow(F.lit(3.0), level).cast("long")
        dx, dy = F.floor(s["x"] / third).cast("long"), F.floor(s["y"] / third).cast("long")
        kx = F.when(s["oy"], 2 - dx).otherwise(dx)
        ox = s["ox"] != (dx == 1)
        ky = F.when(ox, 2 - dy).otherwise(dy)
        return F.struct(
            (s["x"] % third).alias("x"), (s["y"] % third).alias("y"), ox.alias("ox"), (s["oy"] != (dy == 1)).alias("oy"),
            (s["key"] * 9 + kx * 3 + ky).alias("key"),
        )

    start = F.struct(
        cx.cast("long").alias("x"), cy.cast("long").alias("y"), F.lit(False).alias("ox"), F.lit(False).alias("oy"),
        F.lit(0).cast("long").alias("key"),
    )
    return F.aggregate(F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1)), start, down, lambda s: s["key"])


def key_column(kind: str, cx: Column, cy: Column, order: int) -> Column:
    return {"hilbert": hilbert_column, "z": z_column, "peano": peano_column}[kind](cx, cy, order)


def z_column_nd(cells: Column, dims: int, bits: int) -> Column:
    """Interleaved bits of an array of ``dims`` cell numbers, the first one's highest (for more than two dimensions)."""
    parts = [
        F.shiftleft(F.shiftright(F.element_at(cells, d + 1).cast("long"), b).bitwiseAND(F.lit(1)), b * dims + dims - 1 - d)
        for b in range(bits)
        for d in range(dims)
    ]
    key = parts[0]
    for p in parts[1:]:
        key = key.bitwiseOR(p)
    return key


def keys(kind: str, cx, cy, order: int) -> np.ndarray:
    """The keys of cells given as integer arrays."""
    x, y = np.array(cx, np.int64), np.array(cy, np.int64)
    key = np.zeros_like(x)
    if kind == "z":
        for b in range(order - 1, -1, -1):
            key = key * 4 + (x >> b & 1) * 2 + (y >> b & 1)
        return key
    if kind == "hilbert":
        for b in range(order - 1, -1, -1):
            half = 1 << b
            right, top = x >> b, y >> b
            x, y = x & (half - 1), y & (half - 1)
            key = key * 4 + np.where(right == 1, 3 - top, top)
            turned = (top == 0) & (right == 1)
            x, y = np.where(top == 1, x, np.where(turned, half - 1 - y, y)), np.where(top == 1, y, np.where(turned, half - 1 - x, x))
        return key
    ox, oy = np.zeros_like(x, bool), np.zeros_like(x, bool)
    for b in range(order - 1, -1, -1):
        third = 3**b
        dx, dy = x // third, y // third
        x, y = x % third, y % third
        kx = np.where(oy, 2 - dx, dx)
        ox = ox ^ (dx == 1)
        key = key * 9 + kx * 3 + np.where(ox, 2 - dy, dy)
        oy = oy ^ (dy == 1)
    return key


def cells(kind: str, key, order: int) -> tuple[np.ndarray, np.ndarray]:
    """The inverse of ``keys``."""
    key = np.array(key, np.int64)
    if kind == "z":
        x = y = np.zeros_like(key)
        for b in range(order - 1, -1, -1):
            q = key >> 2 * b & 3
            x, y = x * 2 + (q >> 1), y * 2 + (q & 1)
        return x, y
    if kind == "hilbert":
        x, y = np.zeros_like(key), np.zeros_like(key)
        for b in range(order):  # bottom-up: undo the orientation of each level
            q, half = key >> 2 * b & 3, 1 << b
            right, top = (q >= 2).astype(np.int64), ((q == 1) | (q == 2)).astype(np.int64)
            turned = (top == 0) & (right == 1)
            x, y = np.where(top == 1, x, np.where(turned, half - 1 - y, y)), np.where(top == 1, y, np.where(turned, half - 1 - x, x))
            x, y = x + right * half, y + top * half
        return x, y
    x, y = np.zeros_like(key), np.zeros_like(key)
    ox, oy = np.zeros_like(key, bool), np.zeros_like(key, bool)
    for b in range(order - 1, -1, -1):
        q = key // 9**b % 9
        dx = np.where(oy, 2 - q // 3, q // 3)
        ox = ox ^ (dx == 1)
        dy = np.where(ox, 2 - q % 3, q % 3)
        oy = oy ^ (dy == 1)
        x, y = x * 3 + dx, y * 3 + dy
    return x, y
