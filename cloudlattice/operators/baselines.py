"""Baseline codec families, as sizes in bits from plain aggregations.

Every axis of an axis-bounded codec gets eps / sqrt(3), so that the whole point keeps eps.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.functions.bits import bit_length
from cloudlattice.functions.curves import with_morton
from cloudlattice.operators import cells as tables

GROUP = 1024
AXES = ("x", "y", "z")


def axis_steps(cloud: DataFrame, eb: float) -> DataFrame:
    """pid and the axes as whole steps of twice the axis bound (the unit cube's diagonal is sqrt 3)."""
    step = 2 * eb
    return cloud.select("pid", *[F.floor(F.col(a) / F.lit(step) + F.lit(0.5)).cast("long").alias(a) for a in AXES])


def slices(df: DataFrame, width: int = 1 << 16) -> DataFrame:
    """Stored order is that of pid; a codec's slice is a range of it, so windows stay bounded."""
    return df.withColumn("slice", F.floor(F.col("pid") / F.lit(width)))


def predictive(cloud: DataFrame, eb: float, predictor: str = "previous") -> DataFrame:
    """axis, residual, c: histogram of prediction residuals in stored order.

    ``previous`` is the first-order predictor, ``linear`` the second, ``middle`` predicts
    odd places from both neighbours and even places from the even place before.
    """
    w = Window.partitionBy("slice").orderBy("pid")
    at = slices(axis_steps(cloud, eb))
    out = None
    for a in AXES:
        one, two = F.coalesce(F.lag(a, 1).over(w), F.lit(0)), F.coalesce(F.lag(a, 2).over(w), F.lit(0))
        if predictor == "previous":
            guess = one
        elif predictor == "linear":
            guess = one * 2 - two
        else:
            after = F.coalesce(F.lead(a, 1).over(w), F.lag(a, 1).over(w), F.lit(0))
            guess = F.when(F.pmod(F.row_number().over(w), F.lit(2)) == 0, F.floor((one + after) / 2)).otherwise(two)
        part = at.select(F.lit(a).alias("axis"), (F.col(a) - guess).alias("residual")).groupBy("axis", "residual").agg(F.count(F.lit(1)).alias("c"))
        out = part if out is None else out.unionByName(part)
    return out


def transform_blocks(cloud: DataFrame, eb: float) -> DataFrame:
    """Blocks of four per axis: lifted coefficients a..d of steps an eighth of the bound, and kept bits.

    The lifting is an integer Haar pair of levels; its planes below the bound are cut.
    """
    fine = axis_steps(cloud, eb / 8).withColumn("block", F.floor(F.col("pid") / 4)).withColumn("place", F.pmod("pid", F.lit(4)))
    pick = lambda a, k: F.coalesce(F.max(F.when(F.col("place") == k, F.col(a))), F.lit(0))
    out = None
    for axis in AXES:
        b = fine.groupBy("block").agg(*[pick(axis, k).alias(f"v{k}") for k in range(4)])
        low = lambda p, q: F.floor((F.col(p) + F.col(q)) / 2)
        lifted = b.select("block", low("v0", "v1").alias("s0"), (F.col("v0") - F.col("v1")).alias("c2"), low("v2", "v3").alias("s1"), (F.col("v2") - F.col("v3")).alias("c3"))
        coefficients = lifted.select("block", low("s0", "s1").alias("c0"), (F.col("s0") - F.col("s1")).alias("c1"), "c2", "c3")
        # two planes of an eighth step are below the bound; a sign bit for each kept coefficient
        kept = [F.greatest(bit_length(F.abs(F.col(f"c{k}"))) - 2, F.lit(0)) for k in range(4)]
        width = F.greatest(*kept)
        part = coefficients.select(F.lit(axis).alias("axis"), "block", "c0", "c1", "c2", "c3", (width * 4 + F.when(width > 0, 4).otherwise(0) + 6).cast("long").alias("bits"))
        out = part if out is None else out.unionByName(part)
    return out


def block_deltas(cloud: DataFrame, factor: float, bits: int = 3) -> DataFrame:
    """Cube cells by block, then place in the block: (block, local, n, dblock, dlocal)."""
    cells = tables.occupied(cloud, factor, "cube")
    extent = (int(factor) + 2) // (1 << bits) + 1
    big = [F.shiftright(c, bits) for c in quantize.CELL]
    small = [F.col(c).bitwiseAND(F.lit((1 << bits) - 1)) for c in quantize.CELL]
    block = ((big[2] * extent + big[1]) * extent + big[0]).cast("long")
    local = ((small[2] * (1 << bits) + small[1]) * (1 << bits) + small[0]).cast("long")
    at = cells.select(block.alias("block"), local.alias("local"), "n")
    inside = Window.partitionBy("block").orderBy("local")
    firsts = tables.residuals(at.groupBy("block").agg(F.count(F.lit(1)).alias("cells")).withColumnRenamed("block", "key")).select(F.col("key").alias("block"), F.col("delta").alias("dblock"))
    return at.join(firsts, "block").select("block", "local", "n", F.when(F.row_number().over(inside) == 1, F.col("dblock")).otherwise(0).alias("dblock"), (F.col("local") - F.lag("local", 1, 0).over(inside)).alias("dlocal"))


def cube_keys(cloud: DataFrame, bits: int) -> DataFrame:
    """Z-order keys of a grid of 2^bits cubes an axis, with counts; whole-number arithmetic from here on."""
    top = (1 << bits) - 1
    cell = [F.least(F.floor(F.col(a) * F.lit(float(1 << bits))), F.lit(top)).cast("long") for a in AXES]
    at = cloud.select(*[c.alias(n) for c, n in zip(cell, quantize.CELL, strict=True)])
    return with_morton(at, {c: F.col(c) for c in quantize.CELL}).groupBy("key").agg(F.count(F.lit(1)).alias("n"))


def kdtree_bits(keys: DataFrame, bits: int) -> DataFrame:
    """level, nodes, split_bits: each node codes how many of its points lie in its lower half.

    A node is a key prefix, and its halves are the next bit; all levels come from one explode.
    """
    levels = F.explode(F.sequence(F.lit(1), F.lit(3 * bits)))
    prefixes = keys.withColumn("level", levels).groupBy("level", F.expr(f"shiftright(key, {3 * bits} - level)").alias("half")).agg(F.sum("n").alias("n"))
    nodes = prefixes.groupBy("level", F.shiftright("half", 1).alias("node")).agg(F.sum("n").alias("n"))
    # one of n + 1 values
    return nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum(bit_length(F.col("n"))).alias("split_bits"))


def octree_masks(keys: DataFrame, bits: int) -> DataFrame:
    """level, node, mask: which of a node's eight children hold points."""
    levels = F.explode(F.sequence(F.lit(1), F.lit(bits)))
    child = keys.withColumn("level", levels).select("level", F.expr(f"shiftright(key, 3 * ({bits} - level))").alias("child")).distinct()
    bit = F.expr("shiftleft(1, cast(child & 7 as int))")
    return child.groupBy("level", F.shiftright("child", 3).alias("node")).agg(F.bit_or(bit).alias("mask"))


def octree_bits(masks: DataFrame) -> DataFrame:
    """nodes, plain bits (eight a node), entropy bits and entropy bits given the level's parent mask."""
    parent = masks.select((F.col("level") + 1).alias("level"), F.col("node").alias("up"), F.col("mask").alias("above"))
    seen = masks.withColumn("up", F.shiftright("node", 3)).join(parent, ["level", "up"], "left").withColumn("above", F.coalesce("above", F.lit(0)))

    def bits(*by: str) -> DataFrame:
        c = seen.groupBy(*by, "mask").agg(F.count(F.lit(1)).alias("c"))
        total = c.groupBy(*by).agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("s"))
        return total.agg(F.sum(F.col("t") * F.log2(F.col("t").cast("double")) - F.col("s")).alias("b"))

    plain = seen.agg(F.count(F.lit(1)).alias("nodes"))
    return plain.crossJoin(bits().withColumnRenamed("b", "entropy_bits")).crossJoin(bits("above").withColumnRenamed("b", "context_bits")).select("nodes", (F.col("nodes") * 8).alias("plain_bits"), "entropy_bits", "context_bits")  # single rows


def float_lossless(column: DataFrame, digits: int = 10) -> DataFrame:
    """vector, e, bits, exceptions for groups of 1024 values (columns pid, v): decimal exponent, frame of reference, patches.

    The exponent of a vector is the one of fewest bits among all candidates; a value
    that the scaled integer does not give back exactly is stored as it is.
    """
    tried = column.withColumn("vector", F.floor(F.col("pid") / GROUP)).withColumn("e", F.explode(F.sequence(F.lit(0), F.lit(digits))))
    scale = F.pow(F.lit(10.0), F.col("e").cast("double"))
    whole = F.floor(F.col("v") * scale + F.lit(0.5))
    exact = whole / scale == F.col("v")
    sized = tried.select("vector", "e", F.when(exact, whole).alias("q")).groupBy("vector", "e").agg(F.count(F.lit(1)).alias("n"), F.count("q").alias("good"), F.min("q").alias("lo"), F.max("q").alias("hi"))
    cost = bit_length(F.coalesce(F.col("hi") - F.col("lo"), F.lit(0))) * F.col("n") + (F.col("n") - F.col("good")) * 80 + 80
    ranked = sized.withColumn("bits", cost.cast("long")).groupBy("vector").agg(F.min(F.struct("bits", "e", (F.col("n") - F.col("good")).alias("exceptions"), "n")).alias("b"))
    return ranked.select("vector", F.col("b.e").alias("e"), F.col("b.bits").alias("bits"), F.col("b.exceptions").alias("exceptions"), F.col("b.n").alias("n"))


def float_bounded(column: DataFrame, eb: float) -> DataFrame:
    """place, values, n, bits of each byte column of a bounded fixed-point form (column v in [0, 1]).

    A byte column costs the least of plain bytes and a dictionary of at most 16 values.
    """
    fraction = math.ceil(math.log2(1 / (2 * eb)))
    at = column.select(F.floor(F.col("v") * F.lit(float(1 << fraction)) + F.lit(0.5)).cast("long").alias("q"))
    places = F.explode(F.sequence(F.lit(0), F.lit(fraction // 8)))
    byte = at.withColumn("place", places).select("place", F.expr("shiftright(q, 8 * place) & 255").alias("b"))
    seen = byte.groupBy("place", "b").agg(F.count(F.lit(1)).alias("c")).groupBy("place").agg(F.count(F.lit(1)).alias("values"), F.sum("c").alias("n"))
    small = bit_length(F.col("values") - 1) * F.col("n") + F.col("values") * 8
    return seen.withColumn("bits", F.when(F.col("values") <= 16, F.least(small, F.col("n") * 8)).otherwise(F.col("n") * 8).cast("long"))


def transform_energy(cloud: DataFrame) -> DataFrame:
    """Share of energy in the lower half of an eight-point cosine transform over stored order, by axis."""
    basis = [[math.cos(math.pi * (p + 0.5) * k / 8) * math.sqrt((1 if k == 0 else 2) / 8) for p in range(8)] for k in range(8)]
    placed = cloud.withColumn("block", F.floor(F.col("pid") / 8)).withColumn("place", F.pmod("pid", F.lit(8)))
    weight = lambda k: F.element_at(F.array(*[F.lit(b) for b in basis[k]]), (F.col("place") + 1).cast("int"))
    out = None
    for a in AXES:
        c = placed.groupBy("block").agg(*[F.sum(F.col(a) * weight(k)).alias(f"c{k}") for k in range(1, 8)])
        e = lambda ks: sum((F.col(f"c{k}") * F.col(f"c{k}") for k in ks), F.lit(0.0))
        part = c.agg((F.sum(e(range(1, 4))) / F.sum(e(range(1, 8)))).alias("low_share")).select(F.lit(a).alias("axis"), "low_share")
        out = part if out is None else out.unionByName(part)
    return out


def stencil_hits(cells: DataFrame) -> DataFrame:
    """Share of cells whose three lower neighbours, two lattice units down each axis, are occupied too."""
    steps = F.explode(F.array(*[F.struct(*[F.lit(2 if a == b else 0).alias(c) for b, c in enumerate("abc")]) for a in range(3)]))
    asked = cells.select("i", "j", "k", steps.alias("s")).select(F.struct("i", "j", "k").alias("of"), (F.col("i") - F.col("s.a")).alias("i"), (F.col("j") - F.col("s.b")).alias("j"), (F.col("k") - F.col("s.c")).alias("k"))
    met = asked.join(cells.select("i", "j", "k"), ["i", "j", "k"]).groupBy("of").agg(F.count(F.lit(1)).alias("m"))
    return met.agg(F.sum(F.when(F.col("m") == 3, 1).otherwise(0)).cast("long").alias("predictable")).crossJoin(cells.agg(F.count(F.lit(1)).alias("n_cells")))  # single rows
