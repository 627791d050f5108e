"""Registered queries on regions: sidecars, ball counts, boxes, profiles, occupancy, frames, and joins to dimensions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.functions.lattice import bcc_factor
from cloudlattice.operators import cells as tables
from cloudlattice.operators import container, region
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck, ordering
from cloudlattice.plans.ordering import COARSE
from cloudlattice.sources import clouds

QUERIES, ORACLES = {}, {}
CLOUD, BALLS = "c_shipping", 50
RADII = (0.02, 0.05, 0.10)
#: Keys of a chunk: the top bits of the key, so that chunks are alike in both engines.
CHUNK_BITS = 3 * ordering.BITS + 1 - 6
SHELLS, WIDEST = 50, math.sqrt(3) / 2


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


def scrambled(pid: Column) -> Column:
    """pid * 2654435761 modulo 2^32, for ids of any size: both factors are reduced first, so that the product stays below 2^63."""
    return F.pmod(F.pmod(pid, F.lit(1 << 32)) * F.lit(2654435761 - (1 << 32)), F.lit(1 << 32))


def balls(spark: SparkSession, sf_dir: str, name: str = CLOUD, count: int = BALLS) -> DataFrame:
    """qid, cx, cy, cz, r: points of the smallest scrambled key, each with all radii; found once and held as rows, as plans use them several times."""
    if name in clouds.LINES:  # ids follow from the number of lines of each order, so that only the picked orders' lines are put in order
        first = clouds.line_ids(spark, sf_dir).orderBy(scrambled(F.col("pid")), "pid").limit(count)
        at = clouds.unit(spark, sf_dir, name, keyed=True, orders=first.select("l_orderkey").distinct())
        picked = at.join(F.broadcast(first.select("pid")), "pid", "left_semi")
    else:
        picked = clouds.unit(spark, sf_dir, name, keyed=True).orderBy(scrambled(F.col("pid")), "pid").limit(count)
    radii = F.posexplode(F.array(*[F.lit(r * math.sqrt(3)) for r in RADII]))
    spread = picked.select("pid", "x", "y", "z", radii.alias("p", "r"))
    found = spread.select((F.col("pid") * len(RADII) + F.col("p")).alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy"), F.col("z").alias("cz"), "r")
    return spark.createDataFrame([tuple(r) for r in found.collect()], "qid long, cx double, cy double, cz double, r double")  # ``count`` points


def balls_sql(name: str = CLOUD, count: int = BALLS) -> str:
    radii = ", ".join(f"({k}, {duck.number(r * math.sqrt(3))})" for k, r in enumerate(RADII))
    return f"SELECT pid * {len(RADII)} + p AS qid, x AS cx, y AS cy, z AS cz, r FROM (SELECT * FROM ({duck.unit(name, keyed=True)}) ORDER BY (pid * 2654435761) % 4294967296, pid LIMIT {count}), (VALUES {radii}) t(p, r)"


def chunked(spark: SparkSession, sf_dir: str, name: str = CLOUD) -> DataFrame:
    return ordering.keyed(spark, sf_dir, name).withColumn("chunk", F.shiftright("key", CHUNK_BITS))


def chunked_sql(name: str = CLOUD) -> str:
    return f"SELECT *, key >> {CHUNK_BITS} AS chunk FROM ({ordering.keyed_sql(name)})"


def sidecars_of(cells: DataFrame) -> DataFrame:
    box = [f(c).cast("int").alias(f"{n}_{c}") for f, n in ((F.min, "lo"), (F.max, "hi")) for c in quantize.CELL]
    return cells.groupBy("chunk").agg(F.sum("n").alias("n_points"), *box)


def sidecars_sql(name: str = CLOUD) -> str:
    box = ", ".join(f"{f}({c})::INTEGER AS {n}_{c}" for f, n in (("min", "lo"), ("max", "hi")) for c in "ijk")
    return f"SELECT chunk, sum(n)::BIGINT AS n_points, {box} FROM ({chunked_sql(name)}) GROUP BY chunk"


@registered(sidecars_sql())
def sidecars(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Box and number of points of every chunk."""
    return sidecars_of(chunked(spark, sf_dir))


def _classes_sql() -> str:
    f = duck.number(COARSE)
    near = " + ".join(f"pow(greatest(lo_{c} / {f} - c{a}, c{a} - hi_{c} / {f}, 0.0::DOUBLE), 2)" for c, a in zip("ijk", "xyz", strict=True))
    far = " + ".join(f"pow(greatest(abs(c{a} - lo_{c} / {f}), abs(hi_{c} / {f} - c{a})), 2)" for c, a in zip("ijk", "xyz", strict=True))
    return f"SELECT chunk, qid, n_points, CASE WHEN {near} > r * r + 1e-12::DOUBLE THEN 'disjoint' WHEN {far} <= r * r - 1e-12::DOUBLE THEN 'contained' ELSE 'boundary' END AS class FROM ({sidecars_sql()}), ({balls_sql()})"


@registered(_classes_sql())
def chunk_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each chunk lies outside, inside or across each ball."""
    return region.classify(sidecars(spark, sf_dir), balls(spark, sf_dir), COARSE)


def _count_sql() -> str:
    f = duck.number(COARSE)
    d = " + ".join(f"({c} / {f} - c{a}) * ({c} / {f} - c{a})" for c, a in zip("ijk", "xyz", strict=True))
    return f"SELECT qid, coalesce(sum(n) FILTER (WHERE {d} <= r * r), 0)::BIGINT AS n_points FROM ({duck.table(CLOUD, COARSE)}), ({balls_sql()}) GROUP BY qid"


@registered(_count_sql())
def radius_count_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points in balls, every cell looked at: decode, then filter."""
    spec = container.CodecSpec(chunk_cells=512)
    cells = container.decompress(container.compress(clouds.unit(spark, sf_dir, CLOUD), 0.02, spec), 0.02, spec)
    return region.count_full(cells.select("i", "j", "k", "n"), balls(spark, sf_dir), COARSE)


@registered(_count_sql())
def radius_count_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same counts from sidecars, with only boundary chunks decoded, each where it lies."""
    spec = container.CodecSpec(chunk_cells=512)
    chunks = container.compress(clouds.unit(spark, sf_dir, CLOUD), 0.02, spec).persist()  # stands for a written container
    return region.count_chunks(chunks, balls(spark, sf_dir), COARSE, spec.curve, spec.layout, int(COARSE) + 3)


@registered(_count_sql())
def radius_count_joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same again with the cells of boundary chunks joined to the balls that cross them."""
    spec = container.CodecSpec(chunk_cells=512)
    chunks = container.compress(clouds.unit(spark, sf_dir, CLOUD), 0.02, spec).persist()  # stands for a written container
    asked = balls(spark, sf_dir)
    edge = region.boundary(chunks, asked, COARSE)
    return region.count_index(chunks, container.decompress(chunks.join(edge, "chunk", "left_semi"), 0.02, spec), asked, COARSE)


@registered(f"SELECT count(*) AS pairs, sum((class = 'disjoint')::INTEGER)::BIGINT AS skipped, sum((class = 'contained')::INTEGER)::BIGINT AS contained, sum((class = 'boundary')::INTEGER)::BIGINT AS decoded FROM ({_classes_sql()})")
def skip_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return region.skip_report(sidecars(spark, sf_dir), balls(spark, sf_dir), COARSE)


def _interval_sql() -> str:
    f, eps = duck.number(COARSE), duck.number(0.02 * math.sqrt(3))
    d = " + ".join(f"({c} / {f} - c{a}) * ({c} / {f} - c{a})" for c, a in zip("ijk", "xyz", strict=True))
    one = lambda r: f"coalesce(sum(n) FILTER (WHERE {d} <= ({r}) * ({r})), 0)::BIGINT"
    return f"SELECT qid, {one(f'greatest(r - {eps}, 0.0::DOUBLE)')} AS at_least, {one(f'r + {eps}')} AS at_most FROM ({duck.table(CLOUD, COARSE)}), ({balls_sql()}) GROUP BY qid"


@registered(_interval_sql())
def radius_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds on the count of the points themselves."""
    return region.interval(tables.occupied(clouds.unit(spark, sf_dir, CLOUD), COARSE), balls(spark, sf_dir), COARSE, 0.02 * math.sqrt(3))


_LOW, _HIGH = (0.0, 0.25, 0.0), (0.5, 0.75, 0.34)


@registered(f"SELECT i, j, k, n FROM ({duck.table(CLOUD, COARSE)}) WHERE {' AND '.join(f'{c} / {duck.number(COARSE)} BETWEEN {duck.number(a)} AND {duck.number(b)}' for c, a, b in zip('ijk', _LOW, _HIGH, strict=True))}")
def box_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return region.box_filter(tables.occupied(clouds.unit(spark, sf_dir, CLOUD), COARSE), _LOW, _HIGH, COARSE)


def _shell_sql(source: str, weight: str) -> str:
    d = " + ".join(f"({a} - 0.5::DOUBLE) * ({a} - 0.5::DOUBLE)" for a in "xyz")
    return f"SELECT least(floor(sqrt({d}) * {duck.number(SHELLS / WIDEST)}), {SHELLS - 1})::INTEGER AS shell, sum({weight})::BIGINT AS n FROM ({source}) GROUP BY shell"


_FINE = bcc_factor(1e-3)
_CENTRES = f"SELECT i / {duck.number(_FINE)} AS x, j / {duck.number(_FINE)} AS y, k / {duck.number(_FINE)} AS z, n FROM ({duck.table(CLOUD, _FINE)})"


_PROFILE = f"SELECT shell, coalesce(a.n, 0) AS n_original, coalesce(b.n, 0) AS n_cells, {duck.rounded('(coalesce(b.n, 0) - a.n)::DOUBLE / a.n')} AS change FROM ({_shell_sql(duck.unit(CLOUD), '1')}) a FULL JOIN ({_shell_sql(_CENTRES, 'n')}) b USING (shell)"


@registered(_PROFILE)
def radial_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points by shell around the middle, before and after, and the relative change."""
    at = clouds.unit(spark, sf_dir, CLOUD)
    centres = tables.occupied(at, _FINE).select(*[(F.col(c) / F.lit(_FINE)).alias(a) for c, a in zip("ijk", "xyz", strict=True)], "n")
    before = region.profile(at, F.lit(1), SHELLS, WIDEST).withColumnRenamed("n", "n_original")
    after = region.profile(centres, F.col("n"), SHELLS, WIDEST).withColumnRenamed("n", "n_cells")
    both = before.join(after, "shell", "full").select("shell", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_original", "n_cells")])
    return both.withColumn("change", rounded(F.when(F.col("n_original") > 0, (F.col("n_cells") - F.col("n_original")) / F.col("n_original"))))


@registered(f"SELECT count(*) AS shells, {duck.rounded('avg(abs(change))')} AS mean_change, arg_max(change, (abs(change), -shell)) AS worst_change FROM ({_PROFILE}) WHERE change IS NOT NULL")
def profile_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean of the relative changes' sizes and the worst change, over all shells that hold points."""
    held = radial_profile(spark, sf_dir).where("change IS NOT NULL")
    worst = F.max(F.struct(F.abs("change").alias("size"), (-F.col("shell")).alias("near"), "change"))["change"]
    return held.agg(F.count(F.lit(1)).alias("shells"), rounded(F.avg(F.abs("change"))).alias("mean_change"), worst.alias("worst_change"))


@registered(f"SELECT i >> 3 AS i, j >> 3 AS j, k >> 3 AS k, sum(n)::BIGINT AS n FROM ({duck.table('c_vectors', COARSE)}) GROUP BY 1, 2, 3")
def occupancy_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.occupancy_map(tables.occupied(clouds.unit(spark, sf_dir, "c_vectors"), COARSE), 3)


_LABEL = f"""WITH RECURSIVE grid AS (SELECT i >> 2 AS i, j >> 2 AS j, k >> 2 AS k, sum(n)::BIGINT AS n FROM ({duck.table('c_vectors', COARSE)}) GROUP BY 1, 2, 3 HAVING sum(n) >= 40),
reach(i, j, k, region) AS (SELECT i, j, k, (i * 2097152 + j) * 2097152 + k FROM grid UNION SELECT g.i, g.j, g.k, r.region FROM reach r JOIN grid g ON abs(g.i - r.i) <= 1 AND abs(g.j - r.j) <= 1 AND abs(g.k - r.k) <= 1)
SELECT i, j, k, any_value(n) AS n, min(region)::BIGINT AS region FROM reach JOIN grid USING (i, j, k) GROUP BY i, j, k"""


@registered(_LABEL)
def dense_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Connected regions of grid cells of at least 40 points."""
    grid = tables.occupancy_map(tables.occupied(clouds.unit(spark, sf_dir, "c_vectors"), COARSE), 2)
    return tables.dense_regions(grid, 40)


_FRAME = f"SELECT event_type, i, j, k, count(*) AS n FROM ({duck.celled(duck.at_factor('c_activity', COARSE, carry='event_type, '))}) GROUP BY ALL"


@registered(f"SELECT i, j, k, coalesce(a.n, 0) AS n_before, coalesce(b.n, 0) AS n_after FROM (SELECT * FROM ({_FRAME}) WHERE event_type = 'view') a FULL JOIN (SELECT * FROM ({_FRAME}) WHERE event_type = 'click') b USING (i, j, k)")
def frame_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of two frames of one cloud, each frame with its own counts."""
    at = clouds.unit(spark, sf_dir, "c_activity", keyed=True)
    frame = lambda kind: tables.occupied(at.where(F.col("event_type") == kind), COARSE)
    return tables.changes(frame("view"), frame("click"))


_LINES = f"SELECT l_orderkey, i, j, k FROM ({duck.celled(duck.at_factor('c_linekeys', COARSE, carry='l_orderkey, '))})"


@registered(f"SELECT r_name, n_name, count(DISTINCT (i, j, k)) AS n_cells, count(*) AS n_points FROM ({_LINES}) JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def regional_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells and points of order lines by the customer's nation and region."""
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    raw = read("lineitem").select("l_orderkey", *[F.col(c).cast("double").alias(a) for c, a in zip(("l_orderkey", "l_partkey", "l_suppkey"), "xyz", strict=True)])
    cells = quantize.assign(clouds.unit_scale(raw), COARSE).select("l_orderkey", *quantize.CELL)
    places = read("nation").join(read("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    at = cells.join(read("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(read("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(places, F.col("c_nationkey") == F.col("n_nationkey"))
    counted = at.groupBy("r_name", "n_name", *quantize.CELL).agg(F.count(F.lit(1)).alias("n"))
    return counted.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n_cells"), F.sum("n").alias("n_points"))
