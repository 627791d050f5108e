"""Quantizers and their inverse as Column expressions that stay in generated code."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CELL = ("i", "j", "k")


def scaled(value: Column, low: float, high: float, factor: float) -> Column:
    """Position in lattice units of a value of an axis with extent [low, high]; 0 on an axis without extent."""
    if high == low:
        return F.lit(0.0)
    return (value - F.lit(low)) / F.lit(high - low) * F.lit(factor)


def squared(a: list[Column], b: list[Column]) -> Column:
    return reduce(lambda s, t: s + t, [(x - y) * (x - y) for x, y in zip(a, b, strict=True)])


def corners(u: list[Column]) -> tuple[list[Column], list[Column]]:
    """The even and the odd corner of the unit cube around a point."""
    floor = [F.floor(x) for x in u]
    odd = [F.pmod(f, F.lit(2)) for f in floor]
    return [f + b for f, b in zip(floor, odd, strict=True)], [f + 1 - b for f, b in zip(floor, odd, strict=True)]


def bcc_cell(u: list[Column]) -> list[Column]:
    """Nearest body-centred-cubic point: the nearer of two corners, ties to the even one."""
    even, odd = corners(u)
    near = squared(u, even) <= squared(u, odd)
    return [F.when(near, e).otherwise(o).cast("long") for e, o in zip(even, odd, strict=True)]


def bcc_cell_linear(u: list[Column]) -> list[Column]:
    """The same choice by a linear test on the fractional parts."""
    floor = [F.floor(x) for x in u]
    odd = [F.pmod(f, F.lit(2)) for f in floor]
    lean = reduce(lambda s, t: s + t, [(x - f) * (1 - 2 * b) for x, f, b in zip(u, floor, odd, strict=True)])
    far = lean > F.lit(1.5) - reduce(lambda s, t: s + t, odd)
    return [(f + F.when(far, 1 - b).otherwise(b)).cast("long") for f, b in zip(floor, odd, strict=True)]


def cube_cell(u: list[Column]) -> list[Column]:
    return [F.floor(x + F.lit(0.5)).cast("long") for x in u]


def scalar_cell(u: list[Column], factors: list[float]) -> list[Column]:
    """Independent steps per axis."""
    return [F.floor(x * F.lit(f) + F.lit(0.5)).cast("long") for x, f in zip(u, factors, strict=True)]


def fcc_cell(u: list[Column]) -> list[Column]:
    """Nearest point of even coordinate sum: round, then move the worst axis if the sum is odd; ties to the first axis."""
    near = [F.floor(x + F.lit(0.5)).cast("long") for x in u]
    gap = [x - n for x, n in zip(u, near, strict=True)]
    size = [F.abs(g) for g in gap]
    odd = F.pmod(near[0] + near[1] + near[2], F.lit(2)) == 1
    first = (size[0] >= size[1]) & (size[0] >= size[2])
    second = ~first & (size[1] >= size[2])
    moved = [odd & first, odd & second, odd & ~first & ~second]
    return [(n + F.when(m, F.when(g >= 0, 1).otherwise(-1)).otherwise(0)).cast("long") for n, m, g in zip(near, moved, gap, strict=True)]


def prism_cell(u: list[Column], edge: float, height: float) -> list[Column]:
    """Nearest centre of hexagonal prisms: the nearer of two rectangular cosets in the plane, rounding along the third axis.

    Plane centres are (sqrt(3) edge * a / 2, 1.5 edge * b) with a and b of one parity.
    """
    sx, sy = math.sqrt(3) * edge / 2, 1.5 * edge
    a, b = u[0] / F.lit(sx), u[1] / F.lit(sy)
    sets = [([F.floor((p - s) / 2 + 0.5) * 2 + s for p in (a, b)]) for s in (0, 1)]
    off = [squared([u[0], u[1]], [p * F.lit(sx), q * F.lit(sy)]) for p, q in sets]
    near = off[0] <= off[1]
    plane = [F.when(near, p).otherwise(q) for p, q in zip(*sets, strict=True)]
    return [plane[0].cast("long"), plane[1].cast("long"), F.floor(u[2] / F.lit(height) + 0.5).cast("long")]


QUANTIZERS = {"bcc": bcc_cell, "cube": cube_cell, "cube_mse": cube_cell, "fcc": fcc_cell}


def assign(cloud: DataFrame, factor: float, shape: str = "bcc") -> DataFrame:
    """Add u, v, w (lattice position) and the cell i, j, k to a cloud on the unit cube."""
    at = cloud.withColumns({c: F.col(a) * F.lit(factor) for c, a in zip(("u", "v", "w"), ("x", "y", "z"), strict=True)})
    cell = QUANTIZERS[shape]([F.col("u"), F.col("v"), F.col("w")])
    return at.withColumns(dict(zip(CELL, cell, strict=True)))


def error_squared() -> Column:
    """Squared error in lattice units of a row of ``assign``."""
    return squared([F.col(c) for c in ("u", "v", "w")], [F.col(c).cast("double") for c in CELL])


def nearest_centre_brute(assigned: DataFrame) -> DataFrame:
    """Distance to the nearest lattice point among all 27 corners around: the proof oracle for ``bcc_cell``."""
    spark = assigned.sparkSession
    steps = spark.range(64).select(*[(F.floor(F.col("id") / 4**a) % 4 - 1).cast("long").alias(n) for a, n in enumerate(("da", "db", "dc"))])
    place = [F.floor(F.col(c)) + F.col(d) for c, d in (("u", "da"), ("v", "db"), ("w", "dc"))]
    parity = [F.pmod(p, F.lit(2)) for p in place]
    near = assigned.crossJoin(F.broadcast(steps)).where((parity[0] == parity[1]) & (parity[1] == parity[2]))  # 64 fixed offsets
    return near.groupBy("pid").agg(F.min(squared([F.col("u"), F.col("v"), F.col("w")], [p.cast("double") for p in place])).alias("brute"))
