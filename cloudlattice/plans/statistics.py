"""Registered queries that take this method's choices apart: estimated sizes by lattice, curve and counts, density by stride."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.functions import curves
from cloudlattice.functions.lattice import bcc_factor
from cloudlattice.operators import cells as tables
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck, sweeps
from cloudlattice.plans.ordering import KEYS
from cloudlattice.sources import clouds

QUERIES, ORACLES = {}, {}
NAMES, BOUNDS = ("c_accounts", "c_catalog", "c_corpus", "c_vectors"), (5e-3, 2e-2)
#: codec: (lattice, curve, whether the counts are their own stream)
CODECS = {"bcc_morton": ("bcc", "morton", True), "bcc_row_major": ("bcc", "row_major", True), "cube_morton": ("cube", "morton", True), "bcc_morton_no_counts": ("bcc", "morton", False)}


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


def _factor(shape: str, eb: float) -> float:
    return sweeps.FACTORS[shape](eb)


def sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """dataset, eb, codec, value: estimated compression ratio.

    Entropy-coded bits of the residual and count streams, and 12 bits for each distinct
    symbol. Clouds, bounds and codecs share one plan.
    """
    group = ["dataset", "eb", "codec"]
    cells = {shape: sweeps.cells(spark, sf_dir, NAMES, BOUNDS, shape) for shape in ("bcc", "cube")}
    keyed = None
    for codec, (shape, curve, _) in CODECS.items():
        one = cells[shape].withColumn("codec", F.lit(codec))
        if curve == "morton":
            one = curves.attach(one, curve, 1 << 12, "packed" if shape == "bcc" else "raw")
        else:
            width = F.element_at(F.create_map(*[x for eb in BOUNDS for x in (F.lit(eb), F.lit((int(_factor(shape, eb)) + 4) // 2))]), F.col("eb"))
            half = [F.shiftright(c, 1) for c in ("i", "j", "k")]
            one = one.withColumn("key", ((half[2] * width + half[1]) * width + half[0]) * 2 + F.col("i").bitwiseAND(F.lit(1)))
        one = one.select(*group, "key", "n")
        keyed = one if keyed is None else keyed.unionByName(one)
    stream = tables.residuals_by(keyed, group)
    separate = F.col("codec").isin([c for c, (_, _, rle) in CODECS.items() if rle])
    # symbols of the residual stream, of zeros between equal keys where counts are not kept, and of the count stream
    symbols = F.array(F.struct(F.lit("d").alias("s"), F.col("delta").alias("v"), F.lit(1).cast("long").alias("c")), F.struct(F.when(separate, "n").otherwise("d").alias("s"), F.when(separate, F.col("n")).otherwise(0).alias("v"), F.when(separate, 1).otherwise(F.col("n") - 1).alias("c")))
    counts = stream.select(*group, F.explode(symbols).alias("x")).groupBy(*group, "x.s", "x.v").agg(F.sum("x.c").alias("c")).where("c > 0")
    bits = counts.groupBy(*group, "s").agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("l"), F.count(F.lit(1)).alias("d"))
    total = bits.groupBy(*group).agg(F.sum(F.col("t") * F.log2(F.col("t").cast("double")) - F.col("l") + F.col("d") * 12).alias("bits"))
    points = keyed.groupBy(*group).agg(F.sum("n").alias("n_points"))
    return total.join(points, group).select(*group, rounded(F.col("n_points") * 96 / F.col("bits"), 4).alias("value"))


@lru_cache
def sizes_sql() -> str:
    parts = []
    for name in NAMES:
        for eb in BOUNDS:
            for codec, (shape, curve, rle) in CODECS.items():
                factor = _factor(shape, eb)
                extent = int(factor) + 3
                if shape == "bcc":
                    place = (lambda i, j, k, n=(extent + 1) // 2: f"(({k} * {n} + {j}) * {n} + {i})") if curve == "row_major" else KEYS[curve]
                    key = duck.packed(place)
                else:
                    key = duck.morton("i", "j", "k")
                stream = f"SELECT n, key - lag(key, 1, 0) OVER (ORDER BY key) AS delta FROM (SELECT n, {key} AS key FROM ({duck.table(name, factor, shape)}))"
                bits = lambda src: f"(SELECT sum(c) * log2(sum(c)::DOUBLE) - sum(c * log2(c::DOUBLE)) + count(*) * 12 FROM ({src}))"
                if rle:
                    total = f"{bits(f'SELECT delta, count(*) AS c FROM ({stream}) GROUP BY delta')} + {bits(f'SELECT n, count(*) AS c FROM ({stream}) GROUP BY n')}"
                else:
                    total = bits(f"SELECT delta, sum(c)::BIGINT AS c FROM (SELECT delta, 1 AS c FROM ({stream}) UNION ALL SELECT 0, n - 1 FROM ({stream}) WHERE n > 1) GROUP BY delta")
                parts.append(f"SELECT '{name}' AS dataset, {duck.number(eb)} AS eb, '{codec}' AS codec, {duck.rounded(f'(SELECT sum(n) FROM ({stream})) * 96 / ({total})', 4)} AS value")
    return " UNION ALL ".join(parts)


@registered(sizes_sql())
def estimated_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ratios from entropies: lattice and curve and counts taken apart."""
    return sizes(spark, sf_dir)


_STRIDES = (32, 16, 8, 4, 2, 1)
_DENSE = (5e-3, 2e-2, 5e-2)


def _stride_sql() -> str:
    parts = []
    for name in ("c_shipping", "c_sales"):
        for eb in _DENSE:
            source = f"SELECT *, pid // 1024 * 7 + pid % 1024 AS s FROM ({duck.celled(duck.at_factor(name, bcc_factor(eb), keyed=True))})"
            parts += [f"SELECT '{name}' AS dataset, {duck.number(eb)} AS eb, {k} AS stride, count(*) AS n_points, count(DISTINCT (i, j, k)) AS n_cells FROM ({source}) WHERE s % {k} = 0" for k in _STRIDES]
    return " UNION ALL ".join(parts)


@registered(_stride_sql())
def subsample_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points and cells of nested strides: density grows as the stride shrinks."""
    from cloudlattice.functions import quantize

    out = None
    for name in ("c_shipping", "c_sales"):
        at = clouds.unit(spark, sf_dir, name, keyed=True)
        for eb in _DENSE:
            cells = clouds.strides(quantize.assign(at, bcc_factor(eb)), _STRIDES, clouds.line_number(F.col("pid"))).select("i", "j", "k", "stride")
            part = cells.groupBy("stride", "i", "j", "k").agg(F.count(F.lit(1)).alias("n")).groupBy("stride").agg(F.sum("n").alias("n_points"), F.count(F.lit(1)).alias("n_cells"))
            part = part.select(F.lit(name).alias("dataset"), F.lit(eb).alias("eb"), "stride", "n_points", "n_cells")
            out = part if out is None else out.unionByName(part)
    return out
