"""Counts, filters and profiles on cells, with chunk boxes to skip most of the decoding."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LO, HI, CELL, CENTRE = ("lo_i", "lo_j", "lo_k"), ("hi_i", "hi_j", "hi_k"), ("i", "j", "k"), ("cx", "cy", "cz")
#: Widens the class of chunks that are decoded, so that skipping never differs from counting.
SLACK = 1e-12


def total(parts: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, parts)


def distance_squared(factor: float) -> Column:
    """From a cell's centre to the ball's, in one order of operations for every path."""
    gap = [F.col(c) / F.lit(factor) - F.col(p) for c, p in zip(CELL, CENTRE, strict=True)]
    return total([g * g for g in gap])


def within(factor: float) -> Column:
    """Whether a cell's centre lies in the ball; as a coalesced value, so that no null test of the cell is pushed down through the steps that make it."""
    return F.coalesce(distance_squared(factor) <= F.col("r") * F.col("r"), F.lit(False))


def box_distances(factor: float) -> tuple[Column, Column]:
    """Smallest and largest squared distance from a ball's centre to a box of centres."""
    near, far = [], []
    for lo, hi, p in zip(LO, HI, CENTRE, strict=True):
        a, b, c = F.col(lo) / F.lit(factor), F.col(hi) / F.lit(factor), F.col(p)
        gap = F.greatest(a - c, c - b, F.lit(0.0))
        reach = F.greatest(F.abs(c - a), F.abs(b - c))
        near.append(gap * gap)
        far.append(reach * reach)
    return total(near), total(far)


def classify(sidecars: DataFrame, balls: DataFrame, factor: float) -> DataFrame:
    """(chunk, qid, class) for every pair: disjoint, contained or boundary.

    The pairs are wanted themselves; balls are a stated set of queries, and the
    sidecars of chunks stand for the points.
    """
    near, far = box_distances(factor)
    r2 = F.col("r") * F.col("r")
    kind = F.when(near > r2 + SLACK, "disjoint").when(far <= r2 - SLACK, "contained").otherwise("boundary")
    return sidecars.select("chunk", "n_points", *LO, *HI).crossJoin(balls).select("chunk", "qid", "n_points", kind.alias("class"))


def count_full(cells: DataFrame, balls: DataFrame, factor: float) -> DataFrame:
    """Every cell against every ball."""
    inside = cells.crossJoin(balls).where(within(factor))  # the baseline: all cells, all queries
    return balls.select("qid").join(inside.groupBy("qid").agg(F.sum("n").alias("n_points")), "qid", "left").select("qid", F.coalesce("n_points", F.lit(0)).alias("n_points"))


def count_index(sidecars: DataFrame, cells: DataFrame, balls: DataFrame, factor: float) -> DataFrame:
    """Skip disjoint chunks, add the totals of contained ones, look only into boundary ones.

    ``cells`` has a chunk column; decode only what ``boundary`` names to build it.
    """
    classes = classify(sidecars, balls, factor)
    whole = classes.where("class = 'contained'").select("qid", F.col("n_points").alias("n"))
    edge = classes.where("class = 'boundary'").select("chunk", "qid")
    looked = cells.join(edge, "chunk").join(balls, "qid").where(within(factor)).select("qid", "n")
    sums = whole.unionByName(looked).groupBy("qid").agg(F.sum("n").alias("n_points"))
    return balls.select("qid").join(sums, "qid", "left").select("qid", F.coalesce("n_points", F.lit(0)).alias("n_points"))


def count_chunks(chunks: DataFrame, balls: DataFrame, factor: float, curve: str, layout: str, extent: int, delta: bool = True) -> DataFrame:
    """``count_index`` on container rows: a boundary chunk is decoded where it lies, and only its counts leave the task.

    A chunk carries the balls that cross it (a stated set); distances are computed in the same order
    of operations as in ``distance_squared``, so counts equal those of the full path.
    """
    from cloudlattice.functions import curves
    from cloudlattice.operators.container import decode_chunk

    classes = classify(chunks, balls, factor)
    whole = classes.where("class = 'contained'").groupBy("qid").agg(F.sum("n_points").alias("n"))
    asked = classes.where("class = 'boundary'").select("chunk", "qid").join(F.broadcast(balls), "qid").groupBy("chunk").agg(F.collect_list(F.struct("qid", *CENTRE, "r")).alias("balls"))
    side = extent if layout == "raw" else (extent + 1) // 2

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):  # a chunk at a time
                row = batch.slice(at, 1).to_pylist()[0]
                key, n = decode_chunk(row, delta)
                cell = curves.cells_numpy(key if layout == "raw" else key >> 1, curve, side)
                place = [(c if layout == "raw" else c * 2 + (key & 1)) / factor for c in cell]
                sums = []
                for b in row["balls"]:
                    x, y, z = (p - b[c] for p, c in zip(place, CENTRE, strict=True))
                    sums.append(int(n[x * x + y * y + z * z <= b["r"] * b["r"]].sum()))
                yield pa.RecordBatch.from_arrays([pa.array([b["qid"] for b in row["balls"]], pa.int64()), pa.array(sums, pa.int64())], ["qid", "n"])

    wanted = ["chunk", "key_first", "n_points", "n_cells", "rle", "cell_blob", "count_blob"]
    looked = chunks.select(*wanted).join(asked, "chunk").select(*wanted, "balls").mapInArrow(task, "qid long, n long")
    sums = whole.unionByName(looked).groupBy("qid").agg(F.sum("n").alias("n_points"))
    return balls.select("qid").join(sums, "qid", "left").select("qid", F.coalesce("n_points", F.lit(0)).alias("n_points"))


def boundary(sidecars: DataFrame, balls: DataFrame, factor: float) -> DataFrame:
    return classify(sidecars, balls, factor).where("class = 'boundary'").select("chunk").distinct()


def skip_report(sidecars: DataFrame, balls: DataFrame, factor: float) -> DataFrame:
    one = lambda c: F.sum(F.when(F.col("class") == c, 1).otherwise(0))
    return classify(sidecars, balls, factor).agg(F.count(F.lit(1)).alias("pairs"), one("disjoint").alias("skipped"), one("contained").alias("contained"), one("boundary").alias("decoded"))


def box_filter(cells: DataFrame, low: tuple[float, ...], high: tuple[float, ...], factor: float) -> DataFrame:
    """Cells whose centre lies in a box."""
    keep = [(F.col(c) / F.lit(factor) >= F.lit(a)) & (F.col(c) / F.lit(factor) <= F.lit(b)) for c, a, b in zip(CELL, low, high, strict=True)]
    return cells.where(keep[0] & keep[1] & keep[2])


def interval(cells: DataFrame, balls: DataFrame, factor: float, eps: float) -> DataFrame:
    """Counts that hold for the points themselves: none outside r + eps can be inside r, all inside r - eps are."""
    low = count_full(cells, balls.withColumn("r", F.greatest(F.col("r") - eps, F.lit(0.0))), factor).withColumnRenamed("n_points", "at_least")
    return low.join(count_full(cells, balls.withColumn("r", F.col("r") + eps), factor).withColumnRenamed("n_points", "at_most"), "qid")


def profile(points: DataFrame, weight: Column, shells: int, widest: float) -> DataFrame:
    """Points in shells of equal width around the middle of the unit cube (columns x, y, z)."""
    gap = [F.col(c) - F.lit(0.5) for c in "xyz"]
    shell = F.least(F.floor(F.sqrt(total([g * g for g in gap])) * F.lit(shells / widest)), F.lit(shells - 1)).cast("int")
    return points.groupBy(shell.alias("shell")).agg(F.sum(weight).cast("long").alias("n"))
