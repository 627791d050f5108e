"""Comparison of methods over blocks: ranks, Friedman's statistic, critical difference, Pareto fronts."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# fixed values: studentised range quantiles over sqrt 2 at 0.05, for 2 to 9 methods
CRITICAL = {2: 1.960, 3: 2.343, 4: 2.569, 5: 2.728, 6: 2.850, 7: 2.949, 8: 3.031, 9: 3.102}


def ranks(results: DataFrame) -> DataFrame:
    """Rank of each codec in its block by falling ratio, ties averaged; blocks with a missing value are left out.

    Columns dataset, eb, codec, value.
    """
    block = Window.partitionBy("dataset", "eb")
    codecs = results.select("codec").distinct().count()
    full = results.withColumn("_n", F.count("value").over(block)).where(F.col("_n") == codecs)
    same = Window.partitionBy("dataset", "eb", "value")
    rank = F.rank().over(block.orderBy(F.desc("value"))) + (F.count(F.lit(1)).over(same) - 1) / 2
    return full.select("dataset", "eb", "codec", rank.cast("double").alias("rank"))


def mean_ranks(ranked: DataFrame) -> DataFrame:
    return ranked.groupBy("codec").agg(F.count(F.lit(1)).alias("blocks"), F.avg("rank").alias("mean_rank"))


def chi_square_tail(x: float, freedom: int) -> float:
    """Upper tail by the continued fraction or the series of the incomplete gamma function."""
    a, x = freedom / 2, x / 2
    front = math.exp(-x + a * math.log(x) - math.lgamma(a)) if x > 0 else 0.0
    if x < a + 1:
        term = total = 1 / a
        n = a
        while term > total * 1e-16:
            n += 1
            term *= x / n
            total += term
        return 1 - front * total
    b, c = x + 1 - a, 1e300
    d = 1 / b
    h = d
    for i in range(1, 500):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b)
        c = b + an / c
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return front * h


def friedman(mean: list[float], blocks: int) -> tuple[float, float]:
    """Statistic and p-value from the mean ranks."""
    k = len(mean)
    chi = 12 * blocks / (k * (k + 1)) * (sum(r * r for r in mean) - k * (k + 1) ** 2 / 4)
    return chi, chi_square_tail(chi, k - 1)


def critical_difference(k: int, blocks: int) -> float:
    return CRITICAL[k] * math.sqrt(k * (k + 1) / (6 * blocks))


def cliques(mean: dict[str, float], difference: float) -> list[list[str]]:
    """Longest runs of methods whose mean ranks differ by no more."""
    order = sorted(mean, key=lambda c: (mean[c], c))
    runs = []
    for a in range(len(order)):
        b = max(x for x in range(a, len(order)) if mean[order[x]] - mean[order[a]] <= difference)
        if b > a and not any(set(order[a : b + 1]) <= set(r) for r in runs):
            runs.append(order[a : b + 1])
    return runs


def pareto(results: DataFrame) -> DataFrame:
    """Rows (dataset, codec, psnr, cr) that no row of the dataset beats in one measure without losing in the other.

    By one pass in falling psnr, not by comparing all pairs.
    """
    strictly = Window.partitionBy("dataset").orderBy(F.desc("psnr"), F.desc("cr")).rowsBetween(Window.unboundedPreceding, -1)
    best = results.withColumn("_best", F.max("cr").over(strictly))
    # equal rows are kept together: the first of them decides
    first = best.withColumn("_lead", F.first("_best").over(Window.partitionBy("dataset", "psnr", "cr").orderBy(F.col("_best").asc_nulls_first())))
    return first.where(F.col("_lead").isNull() | (F.col("cr") > F.col("_lead"))).drop("_best", "_lead")
