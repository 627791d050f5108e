"""Registered queries on lattices: cells, errors, densities, divergences, information."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.functions import lattice, quantize
from cloudlattice.functions.lattice import bcc_factor
from cloudlattice.operators import cells as tables
from cloudlattice.operators import information as info
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck, sweeps
from cloudlattice.sources import clouds

ALL = tuple(clouds.CLOUDS)
SMALL = ("c_accounts", "c_catalog", "c_corpus")
BINS = 64
COARSE = bcc_factor(0.02)
QUERIES, ORACLES = {}, {}


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


@registered(duck.table("c_shipping", COARSE))
def bcc_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Occupied truncated-octahedron cells with counts."""
    return tables.occupied(clouds.unit(spark, sf_dir, "c_shipping"), COARSE)


@registered(duck.table("c_shipping", sweeps.FACTORS["cube"](0.02), "cube"))
def cube_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.occupied(clouds.unit(spark, sf_dir, "c_shipping"), sweeps.FACTORS["cube"](0.02), "cube")


@registered(duck.table("c_orders", 1 / (0.02 * math.sqrt(3)), "fcc"))
def fcc_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.occupied(clouds.unit(spark, sf_dir, "c_orders"), lattice.LatticeSpec.from_rel(0.02, shape="fcc").factor, "fcc")


_PRISM = (0.05, 0.05 * math.sqrt(2))


def _prism_sql() -> str:
    sx, sy = (duck.number(v) for v in (math.sqrt(3) * _PRISM[0] / 2, 1.5 * _PRISM[0]))
    a = {s: f"floor((x / {sx} - {s}) / 2 + 0.5::DOUBLE) * 2 + {s}" for s in (0, 1)}
    b = {s: f"floor((y / {sy} - {s}) / 2 + 0.5::DOUBLE) * 2 + {s}" for s in (0, 1)}
    d = lambda s: f"(x - a{s} * {sx}) * (x - a{s} * {sx}) + (y - b{s} * {sy}) * (y - b{s} * {sy})"
    return f"""SELECT i, j, k, count(*) AS n FROM (SELECT (CASE WHEN {d(0)} <= {d(1)} THEN a0 ELSE a1 END)::BIGINT AS i, (CASE WHEN {d(0)} <= {d(1)} THEN b0 ELSE b1 END)::BIGINT AS j,
    floor(z / {duck.number(_PRISM[1])} + 0.5::DOUBLE)::BIGINT AS k FROM (SELECT *, {a[0]} AS a0, {a[1]} AS a1, {b[0]} AS b0, {b[1]} AS b1 FROM ({duck.unit('c_orders')}))) GROUP BY ALL"""


@registered(_prism_sql())
def prism_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of hexagonal prisms with the height of the best covering."""
    at = clouds.unit(spark, sf_dir, "c_orders")
    cell = quantize.prism_cell([F.col(a) for a in "xyz"], *_PRISM)
    return tables.run_lengths(at.select(*[c.alias(n) for c, n in zip(cell, quantize.CELL, strict=True)]))


@registered(
    f"""SELECT dataset, eb, sum(n)::BIGINT AS n_points, count(*) AS n_cells, max(n) AS max_n, sum(i * n)::BIGINT AS sum_i, sum(j * n)::BIGINT AS sum_j, sum(k * n)::BIGINT AS sum_k
    FROM ({duck.cells(ALL, (1e-3, 2e-2))}) GROUP BY ALL"""
)
def cell_goldens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points, cells and weighted index sums of every cloud."""
    sums = [F.sum(F.col(c) * F.col("n")).alias(f"sum_{c}") for c in quantize.CELL]
    return sweeps.cells(spark, sf_dir, ALL, (1e-3, 2e-2)).groupBy("dataset", "eb").agg(F.sum("n").alias("n_points"), F.count(F.lit(1)).alias("n_cells"), F.max("n").alias("max_n"), *sums)


def _brute_sql() -> str:
    steps = "(SELECT a.v AS da, b.v AS db, c.v AS dc FROM (VALUES (-1),(0),(1),(2)) a(v), (VALUES (-1),(0),(1),(2)) b(v), (VALUES (-1),(0),(1),(2)) c(v))"
    gap = "(u - (floor(u) + da)) * (u - (floor(u) + da)) + (v - (floor(v) + db)) * (v - (floor(v) + db)) + (w - (floor(w) + dc)) * (w - (floor(w) + dc))"
    parity = lambda c, d: f"((floor({c}) + {d})::BIGINT % 2 + 2) % 2"
    source = duck.celled(duck.at_factor("c_accounts", COARSE, keyed=True))
    return f"""SELECT count(*) AS n_points, sum(CASE WHEN e2 <= brute THEN 0 ELSE 1 END)::BIGINT AS worse FROM (SELECT pid, any_value(e2) AS e2, min({gap}) AS brute FROM ({source}), {steps}
    WHERE {parity('u', 'da')} = {parity('v', 'db')} AND {parity('v', 'db')} = {parity('w', 'dc')} GROUP BY pid)"""


@registered(_brute_sql())
def bcc_vs_brute(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points whose two-candidate cell is farther than the nearest of all lattice points around: none."""
    at = quantize.assign(clouds.unit(spark, sf_dir, "c_accounts", keyed=True), COARSE)
    both = at.select("pid", quantize.error_squared().alias("e2")).join(quantize.nearest_centre_brute(at), "pid")
    return both.agg(F.count(F.lit(1)).alias("n_points"), F.sum(F.when(F.col("e2") <= F.col("brute"), 0).otherwise(1)).cast("long").alias("worse"))


_LINEAR = "(CASE WHEN {t} > 1.5::DOUBLE - ({b}) THEN 1 ELSE 0 END)"


@registered(f"SELECT count(*) AS n_points, 0::BIGINT AS different FROM ({duck.unit('c_shipping')})")
def bcc_linear_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points that the linear form of the test puts elsewhere: none on this cloud."""
    at = quantize.assign(clouds.unit(spark, sf_dir, "c_shipping"), COARSE)
    other = quantize.bcc_cell_linear([F.col(c) for c in "uvw"])
    differ = (F.col("i") != other[0]) | (F.col("j") != other[1]) | (F.col("k") != other[2])
    return at.agg(F.count(F.lit(1)).alias("n_points"), F.sum(differ.cast("int")).cast("long").alias("different"))


def _error_sql(shape: str, names: tuple[str, ...], bounds: tuple[float, ...]) -> str:
    unit = {"bcc": 5**0.5 / 2, "cube": 3**0.5 / 2, "cube_mse": 0.5 / 0.475**0.5}[shape]
    return f"SELECT *, sqrt(e2) / {duck.number(unit)} AS r FROM ({duck.celled(duck.points(names, bounds, shape), shape)})"


_LATTICES = ("bcc", "cube", "cube_mse")


@registered(
    " UNION ALL ".join(
        f"SELECT '{s}' AS lattice, dataset, eb, count(*) AS n_points, {duck.rounded('avg(r * r)')} AS mse, {duck.rounded('max(r)')} AS worst FROM ({_error_sql(s, ('c_shipping', 'c_corpus'), (1e-3, 2e-2))}) GROUP BY ALL"
        for s in _LATTICES
    )
)
def lattice_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean squared and largest error in units of the bound, by lattice."""
    out = None
    for shape in _LATTICES:
        at = sweeps.celled(sweeps.points(spark, sf_dir, ("c_shipping", "c_corpus"), (1e-3, 2e-2), shape), shape).withColumn("r", sweeps.errors(None, shape))
        part = at.groupBy(F.lit(shape).alias("lattice"), "dataset", "eb").agg(F.count(F.lit(1)).alias("n_points"), rounded(F.avg(F.col("r") * F.col("r"))).alias("mse"), rounded(F.max("r")).alias("worst"))
        out = part if out is None else out.unionByName(part)
    return out


@registered(f"SELECT dataset, eb, count(*) AS n_points, {duck.rounded('max(r)')} AS worst, max(r) <= 1 + 1e-9 AS kept FROM ({_error_sql('bcc', ALL, sweeps.WIDE)}) GROUP BY ALL")
def error_bound_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest error of every cloud and bound, in units of the bound."""
    at = sweeps.celled(sweeps.points(spark, sf_dir, ALL, sweeps.WIDE)).withColumn("r", sweeps.errors(None))
    return at.groupBy("dataset", "eb").agg(F.count(F.lit(1)).alias("n_points"), rounded(F.max("r")).alias("worst"), (F.max("r") <= 1 + 1e-9).alias("kept"))


@registered(f"SELECT dataset, eb, count(*) AS n_points, {duck.rounded('-10 * log10(avg(r * r) * any_value(eb) * any_value(eb))')} AS psnr FROM ({_error_sql('bcc', ALL, sweeps.WIDE)}) GROUP BY ALL")
def psnr_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Peak (the diagonal) to error, in decibels, by cloud and bound."""
    at = sweeps.celled(sweeps.points(spark, sf_dir, ALL, sweeps.WIDE)).withColumn("r", sweeps.errors(None))
    return at.groupBy("dataset", "eb").agg(F.count(F.lit(1)).alias("n_points"), rounded(F.log10(F.avg(F.col("r") * F.col("r")) * F.first("eb") * F.first("eb")) * -10).alias("psnr"))


@registered(f"SELECT dataset, eb, sum(n)::BIGINT AS n_points, count(*) AS n_cells, {duck.rounded('sum(n)::DOUBLE / count(*)')} AS rho FROM ({duck.cells(ALL, sweeps.WIDE)}) GROUP BY ALL")
def density_rho(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points per occupied cell."""
    return sweeps.cells(spark, sf_dir, ALL, sweeps.WIDE).groupBy("dataset", "eb").agg(F.sum("n").alias("n_points"), F.count(F.lit(1)).alias("n_cells"), rounded(F.sum("n") / F.count(F.lit(1))).alias("rho"))


_GAIN_BOUNDS = sweeps.WIDE


@registered(
    f"""SELECT dataset, eb, match, n_bcc, n_cube, {duck.rounded('n_cube::DOUBLE / n_bcc')} AS gain FROM (SELECT dataset, eb, count(*) AS n_bcc FROM ({duck.cells(ALL, _GAIN_BOUNDS)}) GROUP BY ALL) JOIN (
    SELECT dataset, eb, 'l2max' AS match, count(*) AS n_cube FROM ({duck.cells(ALL, _GAIN_BOUNDS, 'cube')}) GROUP BY ALL UNION ALL
    SELECT dataset, eb, 'mse' AS match, count(*) AS n_cube FROM ({duck.cells(ALL, _GAIN_BOUNDS, 'cube_mse')}) GROUP BY ALL) USING (dataset, eb)"""
)
def density_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cubes needed for each truncated octahedron, at equal mean squared error and at equal largest error."""
    # one scan of each cloud quantizes every point at every bound on all three lattices
    held = sweeps.occupied(spark, sf_dir, ALL, _GAIN_BOUNDS, ("bcc", "cube", "cube_mse"))
    of = lambda shape: F.max(F.when(F.col("shape") == shape, F.col("m")))
    wide = held.groupBy("dataset", "eb").agg(of("bcc").alias("n_bcc"), of("cube").alias("l2max"), of("cube_mse").alias("mse"))
    each = F.inline(F.array(*[F.struct(F.lit(m).alias("match"), F.col(m).alias("n_cube")) for m in ("l2max", "mse")]))
    return wide.select("dataset", "eb", "n_bcc", each).select("dataset", "eb", "match", "n_bcc", "n_cube", rounded(F.col("n_cube") / F.col("n_bcc")).alias("gain"))


def _kl_sql(shape: str) -> str:
    q = ", ".join(f"({b}, {duck.number(max(t, 1e-12))})" for b, t in enumerate(info.theory_bins(shape, BINS)))
    hist = f"SELECT dataset, eb, least(floor(r * {BINS}), {BINS - 1})::INTEGER AS bin, count(*) AS c FROM ({_error_sql(shape, ALL, _GAIN_BOUNDS)}) GROUP BY ALL"
    return f"""SELECT '{shape}' AS lattice, dataset, eb, sum(c)::BIGINT AS n_points, {duck.rounded('sum(c / total * ln(c / total / q))')} AS delta FROM
    (SELECT *, (sum(c) OVER (PARTITION BY dataset, eb))::DOUBLE AS total FROM ({hist})) JOIN (VALUES {q}) t(b, q) ON bin = b GROUP BY dataset, eb"""


@registered(" UNION ALL ".join(map(_kl_sql, ("bcc", "cube"))))
def kl_deviation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Divergence of the measured errors from those of a uniform cloud; the floor of a sample is about 63 / (2 n_points)."""
    out = None
    for shape in ("bcc", "cube"):
        at = sweeps.celled(sweeps.points(spark, sf_dir, ALL, _GAIN_BOUNDS, shape), shape).withColumn("r", sweeps.errors(None, shape))
        hist = at.groupBy("dataset", "eb", F.least(F.floor(F.col("r") * BINS), F.lit(BINS - 1)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("c"))
        part = info.kl_deviation(hist, info.theory_bins(shape, BINS), ("dataset", "eb")).select(F.lit(shape).alias("lattice"), "dataset", "eb", "n_points", rounded(F.col("delta")).alias("delta"))
        out = part if out is None else out.unionByName(part)
    return out


def _histogram_sql(shape: str) -> str:
    q = ", ".join(f"({b}, {duck.number(t)})" for b, t in enumerate(info.theory_bins(shape, BINS)))
    hist = f"SELECT dataset, eb, least(floor(r * {BINS}), {BINS - 1})::INTEGER AS bin, count(*) AS c FROM ({_error_sql(shape, ('c_shipping', 'c_accounts'), (1e-3, 2e-2))}) GROUP BY ALL"
    return f"SELECT '{shape}' AS lattice, dataset, eb, bin, c, {duck.rounded('q')} AS theory FROM ({hist}) JOIN (VALUES {q}) t(b, q) ON bin = b"


@registered(" UNION ALL ".join(map(_histogram_sql, ("bcc", "cube"))))
def error_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured errors and the theory's, by bin, on a dense and a sparse cloud."""
    out = None
    for shape in ("bcc", "cube"):
        at = sweeps.celled(sweeps.points(spark, sf_dir, ("c_shipping", "c_accounts"), (1e-3, 2e-2), shape), shape).withColumn("r", sweeps.errors(None, shape))
        theory = F.element_at(F.array(*[F.lit(t) for t in info.theory_bins(shape, BINS)]), F.col("bin") + 1)
        hist = at.groupBy(F.lit(shape).alias("lattice"), "dataset", "eb", F.least(F.floor(F.col("r") * BINS), F.lit(BINS - 1)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("c"))
        part = hist.withColumn("theory", rounded(theory))
        out = part if out is None else out.unionByName(part)
    return out


_GRID = 40


def _grid_sql() -> str:
    axis = f"(SELECT (r + 0.5::DOUBLE) / {_GRID} AS {{c}} FROM range({_GRID}) t(r))"
    x, y, z = (axis.format(c=c) for c in "xyz")
    r = "sqrt(least(x * x + y * y + z * z, (1 - x) * (1 - x) + (1 - y) * (1 - y) + (1 - z) * (1 - z)))"
    return f"SELECT floor({r} / {duck.number(5**0.5 / 2)} * {BINS})::INTEGER AS bin, count(*) AS c FROM {x}, {y}, {z} GROUP BY ALL"


@registered(_grid_sql())
def theory_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The error law of a truncated octahedron by a midpoint grid over the unit cube."""
    place = lambda a: (F.floor(F.col("id") / _GRID**a) % _GRID + F.lit(0.5)) / _GRID
    at = spark.range(_GRID**3).select(*[place(a).alias(c) for a, c in enumerate("xyz")])
    near = F.sqrt(F.least(quantize.squared([F.col(c) for c in "xyz"], [F.lit(0.0)] * 3), quantize.squared([F.lit(1) - F.col(c) for c in "xyz"], [F.lit(0.0)] * 3)))
    return at.groupBy(F.floor(near / F.lit(5**0.5 / 2) * BINS).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("c"))


def _polyhedra_sql() -> str:
    # fixed values: the closed forms of G and of the covering volume, as SQL
    forms = {
        "cube": ("1.0::DOUBLE / 12", "8 / (3 * sqrt(3.0::DOUBLE))"),
        "hexagonal_prism": ("pow(pow(5 / (36 * sqrt(3.0::DOUBLE)), 2) / 12, 1.0::DOUBLE / 3)", "2.0::DOUBLE"),
        "rhombic_dodecahedron": ("pow(2.0::DOUBLE, -11.0::DOUBLE / 3)", "2.0::DOUBLE"),
        "truncated_octahedron": ("19 / (192 * pow(2.0::DOUBLE, 1.0::DOUBLE / 3))", "32 / (5 * sqrt(5.0::DOUBLE))"),
        "sphere": ("0.2::DOUBLE * pow(3 / (4 * pi()), 2.0::DOUBLE / 3)", "NULL::DOUBLE"),
    }
    rows = " UNION ALL ".join(f"SELECT '{s}' AS shape, {g} AS g, {c} AS c" for s, (g, c) in forms.items())
    cube_g, cube_c = forms["cube"]
    return f"SELECT shape, {duck.rounded('g')} AS g, {duck.rounded(f'pow(({cube_g}) / g, 1.5::DOUBLE)')} AS volume_gain, {duck.rounded(f'1 - 1 / pow(({cube_g}) / g, 1.5::DOUBLE)')} AS cells_saved, {duck.rounded(f'c / ({cube_c})')} AS covering_gain FROM ({rows})"


@registered(_polyhedra_sql())
def polyhedra_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes with a closed form: second moment and gains against cubes."""
    rows = [(r["shape"], r["g"], r["volume_gain"], r["cells_saved"], r["covering_gain"]) for r in lattice.polyhedra() if r["shape"] not in ("tetrahedron", "dodecahedron", "icosahedron")]
    df = spark.createDataFrame(rows, "shape string, g double, volume_gain double, cells_saved double, covering_gain double")
    return df.select("shape", *[rounded(F.col(c)).alias(c) for c in df.columns[1:]])


def _solids_sql() -> str:
    """Regular solids of edge 1 from their faces: pyramids over ``f`` faces of ``n`` sides, ``r`` from the middle; the others by closed forms."""
    # fixed values: sides, faces and inradius of the regular solids
    solids = "(VALUES ('tetrahedron', 3, 4, sqrt(6.0::DOUBLE) / 12), ('cube', 4, 6, 0.5::DOUBLE), ('dodecahedron', 5, 12, sqrt(250 + 110 * sqrt(5.0::DOUBLE)) / 20), ('icosahedron', 3, 20, sqrt(3.0::DOUBLE) * (3 + sqrt(5.0::DOUBLE)) / 12)) s(shape, n, f, r)"
    a = "(1 / (2 * tan(pi() / n)))"
    regular = f"SELECT shape, (r * r + {a} * {a} / 2 * (1 + pow(tan(pi() / n), 2) / 3)) / (5 * pow(f * n * {a} / 2 * r / 3, 2 / 3.0::DOUBLE)) AS g FROM {solids}"
    # fixed values: closed forms of the second moments
    closed = "SELECT * FROM (VALUES ('hexagonal_prism', pow(pow(5 / (36 * sqrt(3.0::DOUBLE)), 2) / 12, 1 / 3.0::DOUBLE)), ('rhombic_dodecahedron', pow(2.0::DOUBLE, -11 / 3.0::DOUBLE)), ('truncated_octahedron', 19 / (192 * pow(2.0::DOUBLE, 1 / 3.0::DOUBLE))), ('sphere', pow(3 / (4 * pi()), 2 / 3.0::DOUBLE) / 5)) c(shape, g)"
    return f"SELECT shape, {duck.rounded('g', 9)} AS g, {duck.rounded('pow(1 / 12.0::DOUBLE / g, 1.5::DOUBLE)')} AS volume_gain, {duck.rounded('1 - pow(g * 12, 1.5::DOUBLE)')} AS cells_saved FROM ({regular} UNION ALL {closed})"


@registered(_solids_sql())
def polyhedra_by_tetrahedra(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All shapes, those without a closed form integrated over their faces."""
    rows = spark.createDataFrame([(r["shape"], r["g"], r["volume_gain"], r["cells_saved"]) for r in lattice.polyhedra()], "shape string, g double, volume_gain double, cells_saved double")
    return rows.select("shape", rounded(F.col("g"), 9).alias("g"), *[rounded(F.col(c)).alias(c) for c in ("volume_gain", "cells_saved")])


def _entropy_sql(by: str, source: str) -> str:
    return f"(SELECT log2(sum(c)::DOUBLE) - sum(c * log2(c::DOUBLE)) / sum(c) FROM (SELECT {by}, sum(n)::BIGINT AS c FROM ({source}) GROUP BY {by}))"


@registered(f"SELECT {', '.join(f'{duck.rounded(_entropy_sql(by, duck.table("c_vectors", COARSE)))} AS {name}' for by, name in (('i, j, k', 'h_joint'), ('i', 'h_i'), ('j', 'h_j'), ('k', 'h_k')))}")
def joint_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of the cell and of its axes; the first is at most the sum of the others."""
    got = info.joint_and_marginal(tables.occupied(clouds.unit(spark, sf_dir, "c_vectors"), COARSE))
    return got.select(*[rounded(F.col(c)).alias(c) for c in got.columns])


_SITES = (int(COARSE) + 2) ** 3 / 4


@registered(
    f"""SELECT m, n, {duck.rounded(f"({duck.log_gamma(duck.number(_SITES + 1))} - {duck.log_gamma('(m + 1.0::DOUBLE)')} - {duck.log_gamma(f'({duck.number(_SITES)} - m + 1.0::DOUBLE)')}) / 0.6931471805599453::DOUBLE", 3)} AS structural_bits,
    {duck.rounded('n * log2(n::DOUBLE) - s', 3)} AS statistical_bits FROM (SELECT count(*) AS m, sum(n)::BIGINT AS n, sum(n * log2(n::DOUBLE)) AS s FROM ({duck.table('c_shipping', COARSE)}))"""
)
def two_part_information(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which cells are occupied, and how the points are spread over them, in bits."""
    got = info.two_part_information(tables.occupied(clouds.unit(spark, sf_dir, "c_shipping"), COARSE), _SITES)
    return got.select("m", "n", rounded(F.col("structural_bits"), 3).alias("structural_bits"), rounded(F.col("statistical_bits"), 3).alias("statistical_bits"))


@registered(
    f"""SELECT dataset, eb, rho, CASE WHEN rho > 8 THEN 'dense' WHEN rho > 1.3::DOUBLE THEN 'transitional' ELSE 'enumerating' END AS regime FROM
    (SELECT dataset, eb, {duck.rounded('sum(n)::DOUBLE / count(*)')} AS rho FROM ({duck.cells(ALL, sweeps.WIDE)}) GROUP BY ALL)"""
)
def regimes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How dense a cloud is at a bound."""
    rho = F.col("rho")
    return density_rho(spark, sf_dir).select("dataset", "eb", "rho", F.when(rho > 8, "dense").when(rho > 1.3, "transitional").otherwise("enumerating").alias("regime"))
