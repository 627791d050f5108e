"""Cell tables: run-length form, densities, residuals, and set operations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cloudlattice.functions import curves, quantize

CELL = ["i", "j", "k"]


def occupied(cloud: DataFrame, factor: float, shape: str = "bcc") -> DataFrame:
    """Cells of a cloud on the unit cube with the number of points in each; combined before the shuffle."""
    return run_lengths(quantize.assign(cloud, factor, shape).select(*CELL))


def run_lengths(cells: DataFrame) -> DataFrame:
    """(cell, count); a table that already has counts is merged. Merging is associative, so parts and batches may be merged in any order."""
    count = F.sum("n") if "n" in cells.columns else F.count(F.lit(1))
    return cells.groupBy(*CELL).agg(count.cast("long").alias("n"))


def expand(cells: DataFrame, most: int = 1 << 20) -> DataFrame:
    """Cells repeated by their counts, in slices so that a huge count never becomes one array."""
    slices = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / most)))
    sliced = cells.withColumn("_s", slices).withColumn("_m", F.least(F.lit(most).cast("long"), F.col("n") - F.col("_s") * most))
    return sliced.select(*CELL, F.explode(F.array_repeat(F.lit(1), F.col("_m").cast("int"))).alias("_")).drop("_")


def density(cells: DataFrame) -> DataFrame:
    """n_points, n_cells, max_n and their ratio rho."""
    return cells.agg(F.sum("n").alias("n_points"), F.count(F.lit(1)).alias("n_cells"), F.max("n").alias("max_n")).withColumn("rho", F.col("n_points") / F.col("n_cells"))


def extent(cells: DataFrame) -> int:
    """One more than the largest coordinate; one row to the driver."""
    top = cells.agg(F.max(F.greatest(*CELL))).first()[0]
    return (top or 0) + 1


def residuals(keyed: DataFrame, chunk: Column | None = None, parts: int = 16) -> DataFrame:
    """Keys in order with the difference to the one before, which starts from 0 in every chunk.

    Without a chunk the order is global: the table is cut into key ranges, each range
    has its own window, and only the last key of each range is carried on to the
    next one that is not empty. No window is without a partition.
    """
    if chunk is not None:
        within = Window.partitionBy("chunk").orderBy("key")
        return keyed.withColumn("chunk", chunk).withColumn("delta", F.col("key") - F.lag("key", 1, 0).over(within))
    span = keyed.agg(F.coalesce(F.max("key"), F.lit(0))).first()[0] // parts + 1
    ranged = keyed.withColumn("range", F.floor(F.col("key") / span))
    edges = ranged.groupBy("range").agg(F.max("key").alias("last"))
    carried = edges.withColumn("before", F.coalesce(F.lag("last").over(Window.orderBy("range")), F.lit(0)))  # at most ``parts`` rows
    within = Window.partitionBy("range").orderBy("key")
    # a left join: an inner one would push a null test of the key down through all the steps that make it
    joined = ranged.join(F.broadcast(carried.select("range", "before")), "range", "left")
    return joined.withColumn("delta", F.col("key") - F.coalesce(F.lag("key").over(within), F.col("before"))).drop("range", "before")


def residuals_by(keyed: DataFrame, by: list[str], parts: int = 16) -> DataFrame:
    """Global residuals of many sequences in one plan, each in its own key ranges with carried edges."""
    span = keyed.groupBy(*by).agg((F.floor(F.max("key") / parts) + 1).alias("span"))
    ranged = keyed.join(F.broadcast(span), by, "left").withColumn("range", F.floor(F.col("key") / F.col("span")))  # a row for each sequence
    edges = ranged.groupBy(*by, "range").agg(F.max("key").alias("last"))
    carried = edges.select(*by, "range", F.coalesce(F.lag("last").over(Window.partitionBy(*by).orderBy("range")), F.lit(0)).alias("before"))
    within = Window.partitionBy(*by, "range").orderBy("key")
    joined = ranged.join(F.broadcast(carried), [*by, "range"], "left")
    return joined.withColumn("delta", F.col("key") - F.coalesce(F.lag("key").over(within), F.col("before"))).drop("range", "before", "span")


def undelta(stream: DataFrame) -> DataFrame:
    """Keys again from the residuals of chunks (columns chunk, pos, delta)."""
    within = Window.partitionBy("chunk").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return stream.withColumn("key", F.sum("delta").over(within))


def keyed(cloud: DataFrame, factor: float, curve: str = "morton", layout: str = "packed", shape: str = "bcc") -> DataFrame:
    cells = occupied(cloud, factor, shape)
    return curves.attach(cells, curve, int(factor) + 3, layout)


def merged(*tables: DataFrame) -> DataFrame:
    return run_lengths(stacked(list(tables)))


def stacked(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def hybrid_blocks(cells: DataFrame, shift: int, sparse: float) -> DataFrame:
    """Blocks 2^shift lattice units wide with points n, cells m and ``kind``: those of under ``sparse`` points a cell enumerate points."""
    blocks = cells.groupBy(*[F.shiftright(c, shift).alias(c) for c in CELL]).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("m"))
    return blocks.withColumn("kind", F.when(F.col("n") < F.col("m") * F.lit(sparse), "points").otherwise("cells"))


def as_of(rows: DataFrame, kind: str, frame: str, asking: str, by: list[str], time: str) -> DataFrame:
    """Rows of kind ``asking`` with ``seen``, the time of the last ``frame`` of the same ``by`` at or before them: one window, no join."""
    earlier = Window.partitionBy(*by).orderBy(time).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return rows.withColumn("seen", F.max(F.when(F.col(kind) == frame, F.col(time))).over(earlier)).where(F.col(kind) == asking)


def changes(before: DataFrame, after: DataFrame) -> DataFrame:
    """Cells that appear, vanish or keep between two frames, with both counts."""
    both = before.withColumnRenamed("n", "n_before").join(after.withColumnRenamed("n", "n_after"), CELL, "full")
    return both.select(*CELL, F.coalesce("n_before", F.lit(0)).alias("n_before"), F.coalesce("n_after", F.lit(0)).alias("n_after"))


def occupancy_map(cells: DataFrame, shift: int) -> DataFrame:
    """Counts on a grid 2^shift lattice units wide."""
    return cells.groupBy(*[F.shiftright(c, shift).alias(c) for c in CELL]).agg(F.sum("n").alias("n"))


def dense_regions(grid: DataFrame, least: int) -> DataFrame:
    """Grid cells of at least ``least`` points with the smallest label of their 26-connected region.

    Labels spread to neighbours until none changes; each round is one equi-join on cells.
    """
    label = lambda: (F.col("i") * (1 << 21) + F.col("j")) * (1 << 21) + F.col("k")
    state = grid.where(F.col("n") >= least).withColumn("region", label().cast("long"))
    steps = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c")) for a in (-1, 0, 1) for b in (-1, 0, 1) for c in (-1, 0, 1)])
    held = None
    while True:
        told = state.withColumn("s", F.explode(steps)).groupBy((F.col("i") + F.col("s.a")).alias("i"), (F.col("j") + F.col("s.b")).alias("j"), (F.col("k") + F.col("s.c")).alias("k")).agg(F.min("region").alias("least"))
        after = state.join(told, CELL).select(*CELL, "n", F.least("region", "least").alias("region"), (F.col("least") < F.col("region")).alias("moved"))
        kept = bool(after.sparkSession.sparkContext.getCheckpointDir())
        after = after.checkpoint() if kept else after.persist()
        moved = after.where("moved").limit(1).count()
        if held is not None and not kept:
            held.unpersist()
        if not moved:
            return after.drop("moved")
        state, held = after.drop("moved"), after
