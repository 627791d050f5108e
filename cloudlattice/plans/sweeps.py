"""Many clouds and bounds in one plan: one scan of a cloud serves all its bounds."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.functions.lattice import bcc_factor, cube_factor
from cloudlattice.sources import clouds

#: The bounds of the published ratios, and two that reach the dense regime on small tables.
BOUNDS = (1e-5, 5e-5, 1e-4, 5e-4, 1e-3, 5e-3)
WIDE = (*BOUNDS, 2e-2, 5e-2)
FACTORS = {"bcc": bcc_factor, "cube": cube_factor, "cube_mse": lambda eb: cube_factor(eb, "mse")}


def points(spark: SparkSession, sf_dir: str, names: tuple[str, ...], bounds: tuple[float, ...], shape: str = "bcc") -> DataFrame:
    """dataset, eb, factor, u, v, w for every point and bound."""
    pairs = F.array(*[F.struct(F.lit(eb).alias("eb"), F.lit(FACTORS[shape](eb)).alias("factor")) for eb in bounds])
    parts = []
    for name in names:
        at = clouds.unit(spark, sf_dir, name).withColumn("b", F.explode(pairs))
        parts.append(at.select(F.lit(name).alias("dataset"), F.col("b.eb").alias("eb"), F.col("b.factor").alias("factor"), *[(F.col(a) * F.col("b.factor")).alias(u) for a, u in zip("xyz", "uvw", strict=True)]))
    return reduce(DataFrame.unionByName, parts)


def celled(at: DataFrame, shape: str = "bcc") -> DataFrame:
    cell = quantize.QUANTIZERS[shape]([F.col(u) for u in "uvw"])
    return at.withColumns(dict(zip(quantize.CELL, cell, strict=True)))


def cells(spark: SparkSession, sf_dir: str, names: tuple[str, ...], bounds: tuple[float, ...], shape: str = "bcc") -> DataFrame:
    """dataset, eb, i, j, k, n."""
    return celled(points(spark, sf_dir, names, bounds, shape), shape).groupBy("dataset", "eb", *quantize.CELL).agg(F.count(F.lit(1)).alias("n"))


def occupied(spark: SparkSession, sf_dir: str, names: tuple[str, ...], bounds: tuple[float, ...], shapes: tuple[str, ...]) -> DataFrame:
    """dataset, eb, shape, m: occupied cells of several lattices, from one scan of each cloud.

    A row that is shuffled is two numbers: which sequence, and the cell with 21 bits an axis.
    """
    sets = [(name, eb, shape) for name in names for eb in bounds for shape in shapes]
    number = {s: k for k, s in enumerate(sets)}
    parts = []
    for name in names:
        factors = F.array(*[F.struct(F.lit(number[name, eb, shapes[0]]).alias("s"), *[F.lit(FACTORS[s](eb)).alias(s) for s in shapes]) for eb in bounds])
        at = clouds.unit(spark, sf_dir, name).select("x", "y", "z", F.inline(factors))
        packed = {}
        for shape in shapes:
            i, j, k = (c.cast("long") for c in quantize.QUANTIZERS[shape]([F.col(a) * F.col(shape) for a in "xyz"]))
            packed[f"{shape}_cell"] = F.shiftleft(i, 42).bitwiseOR(F.shiftleft(j, 21)).bitwiseOR(k)
        # a projection of its own, in which the parts that the three coordinates share are computed once
        cells = [F.struct((F.col("s") + n).alias("s"), F.col(f"{shape}_cell").alias("cell")) for n, shape in enumerate(shapes)]
        parts.append(at.select("s", *[c.alias(n) for n, c in packed.items()]).select(F.inline(F.array(*cells))))
    counted = reduce(DataFrame.unionByName, parts).distinct().groupBy("s").agg(F.count(F.lit(1)).alias("m"))
    named = spark.createDataFrame([(k, *s) for s, k in number.items()], "s int, dataset string, eb double, shape string")
    return counted.join(F.broadcast(named), "s").select("dataset", "eb", "shape", "m")  # a row for each sequence


def errors(at: DataFrame, shape: str = "bcc") -> Column:
    """Error in units of eps of a row of ``celled``; eps is sqrt(5)/2, sqrt(3)/2 or 1/(2 sqrt 0.475) lattice units."""
    del at
    unit = {"bcc": 5**0.5 / 2, "cube": 3**0.5 / 2, "cube_mse": 0.5 / 0.475**0.5}[shape]
    return F.sqrt(quantize.error_squared()) / F.lit(unit)
