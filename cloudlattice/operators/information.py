"""Entropies, divergences and codes' lengths as aggregations."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cloudlattice.functions import lattice


def rounded(value: Column, digits: int = 6) -> Column:
    """Half up at a fixed digit, alike in every engine."""
    p = float(10**digits)
    return F.floor(value * F.lit(p) + F.lit(0.5)) / F.lit(p)


def entropy(counts: DataFrame, count: str = "c") -> DataFrame:
    """Bits a symbol of a histogram: log2 N - (1/N) sum c log2 c."""
    return counts.agg(F.sum(count).alias("total"), F.sum(F.col(count) * F.log2(F.col(count).cast("double"))).alias("s")).select("total", (F.log2(F.col("total").cast("double")) - F.col("s") / F.col("total")).alias("h"))


def histogram(df: DataFrame, *symbols: str) -> DataFrame:
    return df.groupBy(*symbols).agg(F.count(F.lit(1)).alias("c"))


def joint_and_marginal(cells: DataFrame) -> DataFrame:
    """Entropies of the cell and of each axis over points, by grouping sets in one pass."""
    sets = cells.groupingSets([["i", "j", "k"], ["i"], ["j"], ["k"]], "i", "j", "k").agg(F.sum("n").alias("c"), F.grouping_id().alias("g"))
    # bits of the grouping id: 0 all axes, 3 only i, 5 only j, 6 only k
    part = F.sum(F.col("c") * F.log2(F.col("c").cast("double")))
    each = sets.groupBy("g").agg(F.sum("c").alias("total"), part.alias("s")).select("g", (F.log2(F.col("total").cast("double")) - F.col("s") / F.col("total")).alias("h"))
    pick = lambda g: F.max(F.when(F.col("g") == g, F.col("h")))
    return each.agg(pick(0).alias("h_joint"), pick(3).alias("h_i"), pick(5).alias("h_j"), pick(6).alias("h_k"))


def log_gamma(x: Column) -> Column:
    """Stirling's series after four steps of the recurrence; better than 1e-9 from 1 on."""
    y = x + 4.0
    series = (y - 0.5) * F.ln(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y * y * y) + 1 / (1260 * y * y * y * y * y)
    return series - F.ln(x) - F.ln(x + 1.0) - F.ln(x + 2.0) - F.ln(x + 3.0)


def two_part_information(cells: DataFrame, sites: float) -> DataFrame:
    """Structural bits log2 C(sites, M) and statistical bits N H(n / N)."""
    totals = cells.agg(F.count(F.lit(1)).alias("m"), F.sum("n").alias("n"), F.sum(F.col("n") * F.log2(F.col("n").cast("double"))).alias("s"))
    m, all_ = F.col("m").cast("double"), F.lit(float(sites))
    choose = (log_gamma(all_ + 1.0) - log_gamma(m + 1.0) - log_gamma(all_ - m + 1.0)) / math.log(2)
    return totals.select("m", "n", choose.alias("structural_bits"), (F.col("n") * F.log2(F.col("n").cast("double")) - F.col("s")).alias("statistical_bits"))


def theory_bins(shape: str, bins: int = 64) -> list[float]:
    """Probability of each of ``bins`` equal steps of error / eps for a point uniform in its cell.

    Truncated octahedra by the closed law up to where caps overlap, the rest in
    proportion to a midpoint grid; cubes by the grid.
    """
    return list(_theory(shape, bins))


def _theory(shape: str, bins: int, grid: int = 96) -> tuple[float, ...]:
    import numpy as np

    at = (np.arange(grid) + 0.5) / grid
    x, y, z = np.meshgrid(at, at, at, indexing="ij")
    if shape == "bcc":
        # the unit cube with one even and one odd corner holds every kind of point
        r2 = np.minimum(x * x + y * y + z * z, (1 - x) ** 2 + (1 - y) ** 2 + (1 - z) ** 2)
        ratio = np.sqrt(r2) / (math.sqrt(5) / 2)
    else:
        ratio = np.sqrt((x - 0.5) ** 2 + (y - 0.5) ** 2 + (z - 0.5) ** 2) / (math.sqrt(3) / 2)
    sampled = np.histogram(np.minimum(ratio, 1 - 1e-12), bins, (0, 1))[0] / grid**3
    if shape != "bcc":
        return tuple(sampled.tolist())
    edge = [b / bins * math.sqrt(5) / 2 for b in range(bins + 1)]
    exact = [b for b in range(bins) if edge[b + 1] <= 3 / (2 * math.sqrt(2))]
    out = [lattice.bcc_error_cdf(edge[b + 1]) - lattice.bcc_error_cdf(edge[b]) for b in exact]
    rest, tail = 1 - sum(out), sampled[len(exact) :]
    return tuple([*out, *(rest * tail / tail.sum()).tolist()])


def kl_deviation(hist: DataFrame, theory: list[float], by: tuple[str, ...] = ()) -> DataFrame:
    """Kullback-Leibler divergence in nats of the histogram from the theory, and the number of points."""
    q = F.element_at(F.array(*[F.lit(max(t, 1e-12)) for t in theory]), F.col("bin") + 1)
    total = F.sum("c").over(Window.partitionBy(*by)) if by else F.lit(None)
    if not by:
        total_row = hist.agg(F.sum("c").alias("total"))
        hist = hist.crossJoin(F.broadcast(total_row))  # a single row
        total = F.col("total")
    p = F.col("c") / total
    return hist.withColumn("t", p * F.ln(p / q)).groupBy(*by).agg(F.sum("c").alias("n_points"), F.sum("t").alias("delta"))


def by_sequence(keys: DataFrame, by: list[str]) -> DataFrame:
    """by, h_given, mutual, h_residual of many sequences of cells (columns of ``by``, key, n) in one plan.

    Every entropy is that of a histogram of pairs (a, b); all histograms are one aggregation.
    """
    from cloudlattice.operators import cells as tables

    order = tables.residuals_by(keys, by)
    top = F.lit(1 << 62)
    # the delta of the next cell, by the same residuals in falling order; the first of them has no next
    ahead = tables.residuals_by(order.select(*by, (top - F.col("key")).alias("key"), "n", F.col("delta").alias("own")), by)
    steps = ahead.select(*by, "n", "own", F.when(F.col("delta") < F.col("key"), F.col("delta")).alias("next"))
    least = keys.groupBy(*by).agg(F.min("key").alias("least"))  # a row for each sequence
    before = order.join(F.broadcast(least), by).select(*by, "key", "n", "delta", F.when(F.col("key") > F.col("least"), F.col("key") - F.col("delta")).alias("before"))
    entry = lambda kind, a, b, c: F.struct(F.lit(kind).alias("kind"), a.cast("long").alias("a"), b.cast("long").alias("b"), c.cast("long").alias("c"))
    one, zero, n = F.lit(1), F.lit(0), F.col("n")
    pairs = []
    for a, b, c in ((F.col("key"), F.col("key"), n - 1), (F.col("before"), F.col("key"), F.when(F.col("before").isNotNull(), 1).otherwise(0))):
        pairs += [entry("pair", a, b, c), entry("first", a, zero, c)]
    pairs += [entry("residual", F.col("delta"), zero, one), entry("residual", zero, zero, n - 1)]
    # after a cell's own delta come n - 1 zeros, then the next cell's delta
    following = ((F.col("own"), F.when(n > 1, 0).otherwise(F.col("next")), one), (zero, zero, n - 2), (zero, F.col("next"), F.when(n > 1, 1).otherwise(0)))
    turns = []
    for a, b, c in following:
        held = F.when(b.isNull(), 0).otherwise(c)
        turns += [entry("both", a, b, held), entry("was", a, zero, held), entry("now", b, zero, held)]
    rows = before.select(*by, F.inline(F.array(*pairs))).unionByName(steps.select(*by, F.inline(F.array(*turns)))).where("c > 0")
    counts = rows.groupBy(*by, "kind", "a", "b").agg(F.sum("c").alias("c"))
    sums = counts.groupBy(*by, "kind").agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("s"))
    h = sums.select(*by, "kind", (F.log2(F.col("t").cast("double")) - F.col("s") / F.col("t")).alias("h"))
    of = lambda kind: F.max(F.when(F.col("kind") == kind, F.col("h")))
    return h.groupBy(*by).agg((of("pair") - of("first")).alias("h_given"), (of("was") + of("now") - of("both")).alias("mutual"), of("residual").alias("h_residual"))
