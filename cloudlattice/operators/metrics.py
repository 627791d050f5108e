"""Measures of distortion and size."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.functions.lattice import RAW_BYTES


def distortion(cloud: DataFrame, factor: float, shape: str = "bcc", diagonal: float = math.sqrt(3)) -> DataFrame:
    """n, mse, psnr (peak: the diagonal), max_err and max_rel of a cloud on the unit cube."""
    e2 = quantize.error_squared() / F.lit(factor * factor)
    sums = quantize.assign(cloud, factor, shape).agg(F.count(F.lit(1)).alias("n"), F.avg(e2).alias("mse"), F.sqrt(F.max(e2)).alias("max_err"))
    return sums.withColumns({"psnr": F.log10(F.lit(diagonal**2) / F.col("mse")) * 10, "max_rel": F.col("max_err") / F.lit(diagonal)})


#: A centre's neighbours within sqrt 5 lattice units: as far as the cell of a point that is nearer than the covering radius may lie.
NEIGHBOURS = tuple((a, b, c) for a in (-1, 1) for b in (-1, 1) for c in (-1, 1)) + tuple(tuple(s if k == a else 0 for k in range(3)) for a in range(3) for s in (-2, 2))


def hausdorff(cloud: DataFrame, factor: float) -> DataFrame:
    """Both directed distances between points and centres. A centre's nearest point may lie in a neighbouring cell."""
    at = quantize.assign(cloud, factor)
    around = F.array(*[F.struct(*[F.lit(v).alias(n) for v, n in zip(step, "abc", strict=True)]) for step in ((0, 0, 0), *NEIGHBOURS)])
    told = at.select("u", "v", "w", *quantize.CELL, F.inline(around)).select("u", "v", "w", (F.col("i") + F.col("a")).alias("i"), (F.col("j") + F.col("b")).alias("j"), (F.col("k") + F.col("c")).alias("k"), (F.abs("a") + F.abs("b") + F.abs("c") == 0).alias("own"))
    e2 = quantize.error_squared()
    near = told.groupBy(*quantize.CELL).agg(F.min(e2).alias("near"), F.max(F.when(F.col("own"), e2)).alias("far")).where("far is not null")
    return near.agg((F.sqrt(F.max("far")) / F.lit(factor)).alias("from_points"), (F.sqrt(F.max("near")) / F.lit(factor)).alias("from_cells"))


def precision(cloud: DataFrame, factor: float) -> DataFrame:
    """Largest error with centres written in single and in double precision."""
    at = quantize.assign(cloud, factor)
    centre = [(F.col(c) / F.lit(factor)).cast("float").cast("double") for c in quantize.CELL]
    return at.agg(F.sqrt(F.max(quantize.squared([F.col(a) for a in "xyz"], centre))).alias("single"), (F.sqrt(F.max(quantize.error_squared())) / F.lit(factor)).alias("double"))


def ratio(points: int, size: float) -> float:
    return points * RAW_BYTES / size if size else float("nan")


def best_under_targets(results: DataFrame, targets: tuple[float, ...]) -> DataFrame:
    """For each dataset, codec and target the highest ratio whose measured largest relative error is at most the target, and its bound."""
    kept = results.withColumn("target", F.explode(F.array(*[F.lit(t) for t in targets]))).where(F.col("max_rel") <= F.col("target"))
    return kept.groupBy("dataset", "codec", "target").agg(F.max("cr").alias("cr"), F.max(F.struct("cr", "eb"))["eb"].alias("eb"))


def falls(results: DataFrame) -> DataFrame:
    """Steps in which the measure falls as the stride shrinks (columns dataset, eb, stride, value): none if it is monotone."""
    from pyspark.sql import Window

    w = Window.partitionBy("dataset", "eb").orderBy(F.desc("stride"))
    return results.withColumn("fall", (F.lead("value").over(w) < F.col("value")).cast("int")).groupBy("dataset", "eb").agg(F.sum(F.coalesce("fall", F.lit(0))).cast("long").alias("falls"))
