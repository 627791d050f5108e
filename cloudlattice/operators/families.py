"""Sizes and errors of every codec for many clouds and bounds in one plan.

Rows of all clouds carry ``dataset`` and their stored order; a bound's constants join
as literals (``eb`` and the columns of ``Bound``), so that one scan of a cloud serves
all bounds and codecs. A coded stream costs the lesser of entropy-coded symbols
with a dictionary and the best Exp-Golomb order, for every codec alike.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cloudlattice.functions import curves, quantize
from cloudlattice.functions.bits import bit_length
from cloudlattice.functions.lattice import bcc_factor, cube_factor
from cloudlattice.operators import cells as tables

AXES = ("x", "y", "z")
GROUP = ["dataset", "eb"]
#: Bits of a dictionary entry besides the symbol's own, and the orders of the code that needs no dictionary.
SYMBOL_BITS, ORDERS = 8, (0, 6, 12, 18, 24, 30, 36)
VECTOR, DIGITS = 1024, 10
#: Fixed-point bits of a transform block, its header, and the digits of the base -2 form.
FIXED, BLOCK_HEADER, NEGABINARY = 30, 10, 0xAAAAAAAAAA


@dataclass(frozen=True)
class Bound:
    """Constants of one relative bound (of the unit cube's diagonal)."""

    eb: float
    bcc: float
    cube: float
    step: float
    levels: int
    blocks: int
    least: int
    hilbert: int

    @classmethod
    def of(cls, eb: float) -> Bound:
        bcc, cube = bcc_factor(eb), cube_factor(eb)
        half = (int(bcc) + 4) // 2
        return cls(eb, bcc, cube, 2 * eb, max(1, math.ceil(math.log2(1 / (2 * eb)))), (int(cube) + 2) // 8 + 1, math.floor(math.log2(eb)), max(1, (half - 1).bit_length()))


FIELDS = tuple(Bound.__dataclass_fields__)


def stored(cloud: DataFrame, name: str, slice_bits: int) -> DataFrame:
    """dataset, slice, rn (place in the slice), x, y, z, the ones before (px, py, pz) and raw values, in the order of pid."""
    w = Window.partitionBy("slice").orderBy("pid")
    at = cloud.withColumn("slice", F.shiftright("pid", slice_bits))
    return at.select(F.lit(name).alias("dataset"), "slice", (F.row_number().over(w) - 1).alias("rn"), *AXES, *[F.lag(a).over(w).alias(f"p{a}") for a in AXES], *[f"r{a}" for a in AXES])


def bounded(rows: DataFrame, bounds: tuple[float, ...], keep: list[str]) -> DataFrame:
    """Every row for every bound."""
    pairs = F.array(*[F.struct(*[F.lit(getattr(Bound.of(eb), f)).alias(f) for f in FIELDS]) for eb in bounds])
    return rows.select(*keep, F.inline(pairs))


def symbol_costs(counts: DataFrame, by: list[str]) -> DataFrame:
    """Bits of each stream from its histogram (columns of ``by``, v not negative, c)."""
    golomb = [F.sum(((bit_length(F.shiftright("v", k) + 1) - 1) * 2 + 1 + k) * F.col("c")).alias(f"g{k}") for k in ORDERS]
    sums = counts.groupBy(*by).agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("l"), F.sum(bit_length(F.col("v")) + SYMBOL_BITS).alias("d"), *golomb)
    coded = F.col("t") * F.log2(F.col("t").cast("double")) - F.col("l") + F.col("d")
    return sums.select(*by, F.least(coded, *[F.col(f"g{k}").cast("double") for k in ORDERS]).alias("bits"))


def stream_bits(symbols: DataFrame, by: list[str]) -> DataFrame:
    """Bits of all streams of a group (columns of ``by``, s the stream, v, c)."""
    counts = symbols.groupBy(*by, "s", "v").agg(F.sum("c").alias("c"))
    return symbol_costs(counts, [*by, "s"]).groupBy(*by).agg(F.sum("bits").alias("bits"))


def entry(stream: str, value: Column, count: Column | None = None) -> Column:
    return F.struct(F.lit(stream).alias("s"), value.cast("long").alias("v"), (F.lit(1) if count is None else count).cast("long").alias("c"))


def cells_of(points: DataFrame, shape: str, by: list[str]) -> DataFrame:
    """by, i, j, k, n."""
    cell = quantize.QUANTIZERS[shape]([F.col(a) * F.col(shape) for a in AXES])
    return points.select(*by, *[c.alias(n) for c, n in zip(cell, quantize.CELL, strict=True)]).groupBy(*by, *quantize.CELL).agg(F.count(F.lit(1)).alias("n"))


def leveled_hilbert():
    """Hilbert keys of cells whose number of bits an axis differs from row to row."""

    @F.pandas_udf("long")
    def key(i: pd.Series, j: pd.Series, k: pd.Series, bits: pd.Series) -> pd.Series:
        out = np.zeros(len(i), np.int64)
        i, j, k, bits = (s.to_numpy() for s in (i, j, k, bits))
        for b in np.unique(bits):
            at = bits == b
            out[at] = curves.hilbert_numpy(i[at], j[at], k[at], int(b))
        return pd.Series(out)

    return key


def keyed(cells: DataFrame, curve: str) -> DataFrame:
    """Gap-free keys of lattice cells (``morton``, ``hilbert`` with column ``hilbert``) or keys of cubes (``cube``)."""
    if curve == "cube":
        return curves.with_morton(cells, {c: F.col(c) for c in quantize.CELL})
    if curve == "morton":
        return curves.attach(cells, "morton", 1 << curves.BITS)
    half = [F.shiftright(F.col(c).cast("long"), 1) for c in quantize.CELL]
    return cells.withColumn("key", F.shiftleft(leveled_hilbert()(*half, F.col("hilbert")), 1).bitwiseOR(F.col("i").cast("long").bitwiseAND(F.lit(1))))


def sequence_bits(keys: DataFrame, by: list[str]) -> DataFrame:
    """by, bits: keys in order as residuals, with counts apart or repeated keys, whichever is less."""
    stream = tables.residuals_by(keys.select(*by, "key", "n"), by)
    zero = entry("off", F.lit(0), F.col("n") - 1)
    symbols = stream.select(*by, F.inline(F.array(entry("on", F.col("delta")), entry("counts", F.col("n") - 1), entry("off", F.col("delta")), zero))).where("c > 0")
    counts = symbols.groupBy(*by, "s", "v").agg(F.sum("c").alias("c"))
    costs = symbol_costs(counts, [*by, "s"])
    pick = lambda *names: F.sum(F.when(F.col("s").isin(*names), F.col("bits")))
    return costs.groupBy(*by).agg(F.least(pick("on", "counts"), pick("off")).alias("bits"))


def predictive(points: DataFrame) -> DataFrame:
    """Residuals of the value before in stored order, by axis."""
    whole = lambda c: F.floor(F.col(c) / F.col("step") + F.lit(0.5))
    gap = [whole(a) - F.coalesce(whole(f"p{a}"), F.lit(0)) for a in AXES]
    folded = [F.when(g >= 0, g * 2).otherwise(-g * 2 - 1) for g in gap]
    return stream_bits(points.select(*GROUP, F.inline(F.array(*[entry(a, v) for a, v in zip(AXES, folded, strict=True)]))), GROUP)


def particle_block(cubes: DataFrame) -> DataFrame:
    """Cubes by block of eight an axis, then by place in the block: residuals of both, and counts."""
    i, j, k = (F.col(c) for c in quantize.CELL)
    big, small = [F.shiftright(c, 3) for c in (i, j, k)], [c.bitwiseAND(F.lit(7)) for c in (i, j, k)]
    at = cubes.select(*GROUP, ((big[2] * F.col("blocks") + big[1]) * F.col("blocks") + big[0]).cast("long").alias("block"), ((small[2] * 8 + small[1]) * 8 + small[0]).cast("long").alias("local"), "n")
    firsts = tables.residuals_by(at.select(*GROUP, F.col("block").alias("key")).distinct(), GROUP).select(*GROUP, F.col("key").alias("block"), F.col("delta").alias("dblock"))
    inside = Window.partitionBy(*GROUP, "block").orderBy("local")
    laid = at.join(firsts, [*GROUP, "block"]).select(*GROUP, "n", F.when(F.row_number().over(inside) == 1, F.col("dblock")).otherwise(0).alias("dblock"), (F.col("local") - F.lag("local", 1, 0).over(inside)).alias("dlocal"))
    return stream_bits(laid.select(*GROUP, F.inline(F.array(entry("block", F.col("dblock")), entry("local", F.col("dlocal")), entry("n", F.col("n") - 1)))), GROUP)


def grid_keys(points: DataFrame) -> DataFrame:
    """dataset, eb, levels, key, n on a grid of 2^levels cubes an axis."""
    width = F.expr("shiftleft(1L, levels)")
    cell = {c: F.least(F.floor(F.col(a) * width.cast("double")), width - 1) for a, c in zip(AXES, quantize.CELL, strict=True)}
    at = points.select(*GROUP, "levels", *[v.cast("long").alias(c) for c, v in cell.items()])
    return curves.with_morton(at, {c: F.col(c) for c in cell}).groupBy(*GROUP, "levels", "key").agg(F.count(F.lit(1)).alias("n"))


def kdtree_split(keys: DataFrame) -> DataFrame:
    """Every node of a tree of halves, cut on the axes in turn, codes how many of its points lie in the lower one."""
    nodes = keys.withColumn("level", F.explode(F.sequence(F.lit(1), F.col("levels") * 3)))
    nodes = nodes.groupBy(*GROUP, "level", F.expr("shiftright(key, 3 * levels - level + 1)").alias("node")).agg(F.sum("n").alias("n"))
    return nodes.groupBy(*GROUP).agg(F.sum(bit_length(F.col("n"))).cast("double").alias("bits"))


def octree_occupancy(keys: DataFrame) -> DataFrame:
    """Child masks by entropy given the parent's mask, and the counts of the leaves."""
    levels = keys.withColumn("level", F.explode(F.sequence(F.lit(1), F.col("levels"))))
    children = levels.select(*GROUP, "level", F.expr("shiftright(key, 3 * (levels - level))").alias("child")).distinct()
    masks = children.groupBy(*GROUP, "level", F.shiftright("child", 3).alias("node")).agg(F.bit_or(F.expr("shiftleft(1, cast(child & 7 as int))")).alias("mask"))
    above = masks.select(*GROUP, (F.col("level") + 1).alias("level"), F.col("node").alias("up"), F.col("mask").alias("above"))
    seen = masks.withColumn("up", F.shiftright("node", 3)).join(above, [*GROUP, "level", "up"], "left")
    counts = seen.groupBy(*GROUP, F.coalesce("above", F.lit(0)).alias("above"), "mask").agg(F.count(F.lit(1)).alias("c"))
    by_parent = counts.groupBy(*GROUP, "above").agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("l"))
    shape = by_parent.groupBy(*GROUP).agg(F.sum(F.col("t") * F.log2(F.col("t").cast("double")) - F.col("l")).alias("shape"))
    leaves = keys.groupBy(*GROUP).agg(F.sum((bit_length(F.col("n")) - 1) * 2 + 1).alias("leaves"))
    return shape.join(leaves, GROUP).select(*GROUP, (F.col("shape") + F.col("leaves")).alias("bits"))


def float_bounded(points: DataFrame) -> DataFrame:
    """Fixed-point values as byte columns; each costs the least of plain bytes, a small dictionary and runs."""
    whole = lambda c: F.floor(F.col(c) * F.expr("shiftleft(1L, levels)").cast("double") + F.lit(0.5))
    rows = points.select(*GROUP, "levels", F.inline(F.array(*[F.struct(F.lit(a).alias("axis"), whole(a).alias("q"), whole(f"p{a}").alias("before")) for a in AXES])))
    rows = rows.withColumn("place", F.explode(F.sequence(F.lit(0), F.floor(F.col("levels") / 8).cast("int"))))
    byte = lambda c: F.expr(f"shiftright({c}, 8 * place) & 255")
    starts = F.when(F.col("before").isNull() | (byte("before") != byte("q")), 1).otherwise(0)
    seen = rows.select(*GROUP, "axis", "place", byte("q").alias("b"), starts.alias("starts")).groupBy(*GROUP, "axis", "place", "b").agg(F.count(F.lit(1)).alias("c"), F.sum("starts").alias("starts"))
    columns = seen.groupBy(*GROUP, "axis", "place").agg(F.count(F.lit(1)).alias("kinds"), F.sum("c").alias("n"), F.sum("starts").alias("runs"))
    small = F.when(F.col("kinds") <= 16, bit_length(F.col("kinds") - 1) * F.col("n") + F.col("kinds") * 8)
    return columns.groupBy(*GROUP).agg(F.sum(F.least(F.col("n") * 8, F.col("runs") * 16, small)).cast("double").alias("bits"))


def float_lossless(rows: DataFrame, exact_bits: Column) -> DataFrame:
    """dataset, bits: decimal exponent, frame of reference and patches of vectors of stored values."""
    scale = F.pow(F.lit(10.0), F.col("e").cast("double"))
    values = rows.select("dataset", "slice", F.floor(F.col("rn") / VECTOR).alias("vector"), exact_bits.alias("patch"), F.inline(F.array(*[F.struct(F.lit(a).alias("axis"), F.col(f"r{a}").alias("v")) for a in AXES])))
    tried = values.withColumn("e", F.explode(F.sequence(F.lit(0), F.lit(DIGITS))))
    fits = F.abs(F.col("v") * scale) < F.lit(9e15)
    whole = F.floor(F.when(fits, F.col("v") * scale).otherwise(0.0) + F.lit(0.5))
    sized = tried.select("dataset", "axis", "slice", "vector", "patch", "e", F.when(fits & (whole / scale == F.col("v")), whole).alias("q")).groupBy("dataset", "axis", "slice", "vector", "e").agg(F.max("patch").alias("patch"), F.count(F.lit(1)).alias("n"), F.count("q").alias("good"), F.coalesce(F.max("q") - F.min("q"), F.lit(0)).alias("span"))
    cost = bit_length(F.col("span")) * F.col("n") + (F.col("n") - F.col("good")) * F.col("patch") + 80
    best = sized.withColumn("cost", cost).groupBy("dataset", "axis", "slice", "vector").agg(F.min("cost").alias("bits"))
    return best.groupBy("dataset").agg(F.sum("bits").cast("double").alias("bits"))


def array_transform(points: DataFrame) -> DataFrame:
    """dataset, eb, bits, mse, worst of blocks of four values an axis.

    A block shares an exponent; its fixed-point values go through an integer lifting
    transform to base -2 digits, whose planes below the bound are cut. A kept plane costs
    a group bit, a significant value its digits and a bit more.
    """
    at = points.select(*GROUP, "least", "slice", F.shiftright("rn", 2).alias("block"), (F.col("rn") % 4).alias("place"), F.inline(F.array(*[F.struct(F.lit(a).alias("axis"), F.col(a).alias("v")) for a in AXES])))
    pick = [F.max(F.when(F.col("place") == k, F.col("v"))).alias(f"v{k}") for k in range(4)]
    rows = at.groupBy(*GROUP, "least", "slice", "block", "axis").agg(*pick)
    names = "abcd"
    held = F.greatest(*[F.coalesce(f"v{k}", F.lit(0.0)) for k in range(4)])
    rows = rows.withColumn("e", bit_length(F.floor(held * F.lit(float(1 << FIXED)))) - FIXED)
    rows = rows.withColumn("scale", F.expr(f"cast(shiftleft(1L, {FIXED} - e) AS double)"))
    rows = rows.withColumns({n: F.floor(F.coalesce(f"v{k}", F.lit(0.0)) * F.col("scale") + F.lit(0.5)) for k, n in enumerate(names)})
    for target, value in lifting():
        rows = rows.withColumn(target, F.expr(value))
    rows = rows.withColumns({n: (F.col(n) + F.lit(NEGABINARY)).bitwiseXOR(F.lit(NEGABINARY)) for n in names})
    rows = rows.withColumn("kept", F.least(F.lit(FIXED + 2), F.greatest(F.lit(0), F.col("e") - F.col("least") + 4))).withColumn("cut", F.lit(FIXED + 2) - F.col("kept"))
    digits = [F.greatest(bit_length(F.col(n)) - F.col("cut"), F.lit(0)) for n in names]
    spent = sum((d + F.when(d > 0, 1).otherwise(0) for d in digits), F.lit(BLOCK_HEADER)) + F.col("kept")
    rows = rows.withColumn("spent", spent)
    rows = rows.withColumns({n: F.expr(f"shiftleft(shiftright({n}, cut), cut)") for n in names})
    rows = rows.withColumns({n: F.col(n).bitwiseXOR(F.lit(NEGABINARY)) - F.lit(NEGABINARY) for n in names})
    for target, value in unlifting():
        rows = rows.withColumn(target, F.expr(value))
    gaps = [F.pow(F.col(n) / F.col("scale") - F.col(f"v{k}"), F.lit(2.0)).alias(f"g{k}") for k, n in enumerate(names)]
    blocks = rows.select(*GROUP, "slice", "block", "spent", *gaps).groupBy(*GROUP, "slice", "block").agg(F.sum("spent").alias("spent"), *[F.sum(f"g{k}").alias(f"g{k}") for k in range(4)])
    each = F.array(*[F.col(f"g{k}") for k in range(4)])
    worst, total = F.array_max(each), F.aggregate(each, F.lit(0.0), lambda s, g: s + F.coalesce(g, F.lit(0.0)))
    count = F.size(F.filter(each, lambda g: g.isNotNull()))
    return blocks.groupBy(*GROUP).agg(F.sum("spent").cast("double").alias("bits"), (F.sum(total) / F.sum(count)).alias("mse"), F.max(worst).alias("worst"))


def lifting() -> list[tuple[str, str]]:
    """Steps of the block transform over values a, b, c, d: an orthogonal-like integer lifting of four values."""
    return [("a", "a + d"), ("a", "shiftright(a, 1)"), ("d", "d - a"), ("c", "c + b"), ("c", "shiftright(c, 1)"), ("b", "b - c"), ("a", "a + c"), ("a", "shiftright(a, 1)"), ("c", "c - a"), ("d", "d + b"), ("d", "shiftright(d, 1)"), ("b", "b - d"), ("d", "d + shiftright(b, 1)"), ("b", "b - shiftright(d, 1)")]


def unlifting() -> list[tuple[str, str]]:
    """The steps that undo ``lifting``, but for the bits that its halvings lose."""
    back = {"a + d": "a - d", "d - a": "d + a", "c + b": "c - b", "b - c": "b + c", "a + c": "a - c", "c - a": "c + a", "d + b": "d - b", "b - d": "b + d", "d + shiftright(b, 1)": "d - shiftright(b, 1)", "b - shiftright(d, 1)": "b + shiftright(d, 1)"}
    return [(t, f"{t} * 2" if v == f"shiftright({t}, 1)" else back[v]) for t, v in reversed(lifting())]


def point_errors(points: DataFrame) -> DataFrame:
    """dataset, eb, n, and mean and largest squared error of the lattice, cubes, steps, grid and fixed point."""
    e2 = {}
    for shape in ("bcc", "cube"):
        u = [F.col(a) * F.col(shape) for a in AXES]
        cell = quantize.QUANTIZERS[shape](u)
        e2[shape] = quantize.squared(u, cell) / (F.col(shape) * F.col(shape))
    width = F.expr("shiftleft(1L, levels)").cast("double")
    step = [F.floor(F.col(a) / F.col("step") + F.lit(0.5)) * F.col("step") for a in AXES]
    grid = [(F.least(F.floor(F.col(a) * width).cast("double"), width - 1) + F.lit(0.5)) / width for a in AXES]
    fixed = [F.floor(F.col(a) * width + F.lit(0.5)) / width for a in AXES]
    e2 |= {name: quantize.squared([F.col(a) for a in AXES], back) for name, back in (("steps", step), ("grid", grid), ("fixed", fixed))}
    named = points.select(*GROUP, *[e.alias(n) for n, e in e2.items()])
    return named.groupBy(*GROUP).agg(F.count(F.lit(1)).alias("n"), *[f(n).alias(f"{n}_{k}") for n in e2 for k, f in (("mse", F.avg), ("worst", F.max))])


#: Codec: what its error is the error of.
ERRORS = {"to_morton": "bcc", "to_hilbert": "bcc", "cube_pipeline": "cube", "array_predictive": "steps", "particle_block": "cube", "kdtree_split": "grid", "octree_occupancy": "grid", "float_bounded": "fixed"}


def variants(points: DataFrame, by: list[str], codecs: tuple[str, ...] = ("to_morton", "to_hilbert", "cube_pipeline")) -> DataFrame:
    """by, codec, bits of this method's variants."""
    parts = []
    for codec in codecs:
        shape, curve = {"to_morton": ("bcc", "morton"), "to_hilbert": ("bcc", "hilbert"), "cube_pipeline": ("cube", "cube")}[codec]
        cells = cells_of(points, shape, [*by, "hilbert"])
        parts.append(sequence_bits(keyed(cells, curve), by).withColumn("codec", F.lit(codec)))
    return reduce(DataFrame.unionByName, parts)


def all_sizes(rows: DataFrame, bounds: tuple[float, ...], exact_bits: Column) -> DataFrame:
    """dataset, eb, codec, n, bits, mse, worst of every codec at every bound; errors as squares on the unit cube."""
    points = bounded(rows, bounds, ["dataset", "slice", "rn", *AXES, *[f"p{a}" for a in AXES]])
    keys = grid_keys(points)
    sized = {"array_predictive": predictive(points), "particle_block": particle_block(cells_of(points, "cube", [*GROUP, "blocks"])), "kdtree_split": kdtree_split(keys), "octree_occupancy": octree_occupancy(keys), "float_bounded": float_bounded(points)}
    bits = reduce(DataFrame.unionByName, [d.withColumn("codec", F.lit(c)) for c, d in sized.items()]).unionByName(variants(points, GROUP))
    errors = point_errors(points)
    kinds = F.array(*[F.struct(F.lit(k).alias("kind"), F.col(f"{k}_mse").alias("mse"), F.col(f"{k}_worst").alias("worst")) for k in dict.fromkeys(ERRORS.values())])
    long = errors.select(*GROUP, "n", F.inline(kinds))
    kind = F.element_at(F.create_map(*[F.lit(x) for pair in ERRORS.items() for x in pair]), F.col("codec"))
    columns = [*GROUP, "codec", "n", "bits", "mse", "worst"]
    simple = bits.withColumn("kind", kind).join(long, [*GROUP, "kind"]).select(columns)
    lossless = errors.select(*GROUP, "n").join(float_lossless(rows, exact_bits), "dataset").select(*GROUP, F.lit("float_lossless").alias("codec"), "n", "bits", F.lit(0.0).alias("mse"), F.lit(0.0).alias("worst"))
    transform = errors.select(*GROUP, "n").join(array_transform(points).withColumn("codec", F.lit("array_transform")), GROUP).select(columns)
    return simple.unionByName(lossless).unionByName(transform)
