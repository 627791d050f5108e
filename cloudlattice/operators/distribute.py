"""Ownership of key ranges, balance, and what combining before the shuffle saves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prefix_owner(parts: int, span: int) -> Column:
    """The key range cut evenly; cheap, and uneven where the cloud is."""
    return F.floor(F.col("key") * parts / F.lit(span)).cast("int")


def exact_splitters(keys: DataFrame, parts: int) -> list[int]:
    """Keys that cut the occupied cells into equal shares, from exact percentiles, which hold a count for every distinct key: for small tables and checks."""
    row = keys.agg(F.percentile("key", [p / parts for p in range(1, parts)]).alias("s")).first()
    return [int(x) for x in row["s"] or []]


def sample_splitters(keys: DataFrame, parts: int, share: float = 0.1, seed: int = 1) -> list[int]:
    """The same from a sample, as a large run takes them: only the splitters reach the driver."""
    row = keys.sample(share, seed).agg(F.percentile_approx("key", [p / parts for p in range(1, parts)], 10_000).alias("s")).first()
    return sorted({int(x) for x in row["s"] or []})


def splitter_owner(splitters: list[int]) -> Column:
    return sum((F.when(F.col("key") > s, 1).otherwise(0) for s in splitters), F.lit(0)).cast("int")


def balance(owned: DataFrame) -> DataFrame:
    """Largest against mean number of cells of a part (column owner)."""
    sizes = owned.groupBy("owner").agg(F.count(F.lit(1)).alias("c"))
    return sizes.agg(F.count(F.lit(1)).alias("parts"), F.max("c").alias("largest"), (F.max("c") / F.avg("c")).alias("balance"))


def shared_cells(owned: DataFrame) -> DataFrame:
    """Cells that more than one part claims: none where owners come from keys."""
    return owned.groupBy("i", "j", "k").agg(F.countDistinct("owner").alias("owners")).agg(F.count(F.lit(1)).alias("n_cells"), F.sum(F.when(F.col("owners") > 1, 1).otherwise(0)).cast("long").alias("shared"))


def shuffle_saving(points: DataFrame, slices: int) -> DataFrame:
    """Rows that leave the slices as (cell, count) pairs, against points (columns pid, i, j, k)."""
    pairs = points.select(F.pmod("pid", F.lit(slices)).alias("slice"), "i", "j", "k").distinct()
    return pairs.agg(F.count(F.lit(1)).alias("pairs")).crossJoin(points.agg(F.count(F.lit(1)).alias("points")))  # single rows
