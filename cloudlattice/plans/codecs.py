"""Registered queries on baseline codec families: their streams and sizes in bits."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.functions.lattice import cube_factor
from cloudlattice.operators import baselines, metrics
from cloudlattice.operators import cells as tables
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck
from cloudlattice.plans.ordering import COARSE
from cloudlattice.sources import clouds

QUERIES, ORACLES = {}, {}
EB, CLOUD, BITS = 1e-3, "c_orders", 8


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


def _steps_sql(eb: float = EB) -> str:
    return f"SELECT pid, pid // 65536 AS slice, {', '.join(f'floor({a} / {duck.number(2 * eb)} + 0.5::DOUBLE)::BIGINT AS {a}' for a in 'xyz')} FROM ({duck.unit(CLOUD, keyed=True)})"


def _residual_sql(kind: str) -> str:
    parts = []
    for a in "xyz":
        w = "OVER (PARTITION BY slice ORDER BY pid)"
        one, two = f"lag({a}, 1, 0) {w}", f"lag({a}, 2, 0) {w}"
        guess = {"previous": one, "linear": f"{one} * 2 - {two}", "middle": f"CASE WHEN (row_number() {w}) % 2 = 0 THEN floor(({one} + coalesce(lead({a}, 1) {w}, lag({a}, 1) {w}, 0)) / 2)::BIGINT ELSE {two} END"}[kind]
        parts.append(f"SELECT '{kind}' AS predictor, '{a}' AS axis, residual, count(*) AS c FROM (SELECT {a} - ({guess}) AS residual FROM ({_steps_sql()})) GROUP BY residual")
    return " UNION ALL ".join(parts)


_KINDS = ("previous", "linear", "middle")


@registered(" UNION ALL ".join(map(_residual_sql, _KINDS)))
def predictive_residuals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Residuals of the array predictors in stored order."""
    out = None
    for kind in _KINDS:
        part = baselines.predictive(clouds.unit(spark, sf_dir, CLOUD, keyed=True), EB, kind).select(F.lit(kind).alias("predictor"), "axis", "residual", "c")
        out = part if out is None else out.unionByName(part)
    return out


@registered(f"SELECT predictor, axis, {duck.rounded('log2(sum(c)::DOUBLE) - sum(c * log2(c::DOUBLE)) / sum(c)')} AS bits_per_value FROM ({' UNION ALL '.join(map(_residual_sql, _KINDS))}) GROUP BY ALL")
def predictive_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of the residuals by predictor and axis."""
    c = F.col("c").cast("double")
    return predictive_residuals(spark, sf_dir).groupBy("predictor", "axis").agg(rounded(F.log2(F.sum("c").cast("double")) - F.sum(c * F.log2(c)) / F.sum("c")).alias("bits_per_value"))


def _transform_sql() -> str:
    parts = []
    for a in "xyz":
        v = ", ".join(f"coalesce(max({a}) FILTER (WHERE pid % 4 = {k}), 0) AS v{k}" for k in range(4))
        half = lambda p, q: f"floor(({p} + {q}) / 2.0::DOUBLE)::BIGINT"
        s = f"SELECT block, {half('v0', 'v1')} AS s0, v0 - v1 AS c2, {half('v2', 'v3')} AS s1, v2 - v3 AS c3 FROM (SELECT pid // 4 AS block, {v} FROM ({_steps_sql(EB / 8)}) GROUP BY block)"
        width = f"greatest({', '.join(f'greatest({duck.bit_length(f"abs(c{k})")} - 2, 0)' for k in range(4))})"
        parts.append(f"SELECT '{a}' AS axis, block, c0, c1, c2, c3, (w * 4 + CASE WHEN w > 0 THEN 4 ELSE 0 END + 6)::BIGINT AS bits FROM (SELECT *, {width} AS w FROM (SELECT block, {half('s0', 's1')} AS c0, s0 - s1 AS c1, c2, c3 FROM ({s})))")
    return " UNION ALL ".join(parts)


@registered(_transform_sql())
def transform_coeffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lifted coefficients and kept bits of blocks of four."""
    return baselines.transform_blocks(clouds.unit(spark, sf_dir, CLOUD, keyed=True), EB)


_CUBE = cube_factor(0.02)


def _particle_sql() -> str:
    e = (int(_CUBE) + 2) // 8 + 1
    at = f"SELECT ((k >> 3) * {e} + (j >> 3)) * {e} + (i >> 3) AS block, ((k & 7) * 8 + (j & 7)) * 8 + (i & 7) AS local, n FROM ({duck.table(CLOUD, _CUBE, 'cube')})"
    first = f"SELECT block, block - lag(block, 1, 0) OVER (ORDER BY block) AS d FROM (SELECT DISTINCT block FROM ({at}))"
    return f"SELECT block, local, n, CASE WHEN row_number() OVER (PARTITION BY block ORDER BY local) = 1 THEN d ELSE 0 END AS dblock, local - lag(local, 1, 0) OVER (PARTITION BY block ORDER BY local) AS dlocal FROM ({at}) JOIN ({first}) USING (block)"


@registered(_particle_sql())
def particle_block_deltas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.block_deltas(clouds.unit(spark, sf_dir, CLOUD), _CUBE)


def _keys_sql() -> str:
    cell = ", ".join(f"least(floor({a} * {duck.number(float(1 << BITS))}), {(1 << BITS) - 1})::BIGINT AS {c}" for a, c in zip("xyz", "ijk", strict=True))
    return f"SELECT {duck.morton('i', 'j', 'k', BITS)} AS key, count(*) AS n FROM (SELECT {cell} FROM ({duck.unit(CLOUD)})) GROUP BY key"


@registered(f"SELECT level, count(*) AS nodes, sum({duck.bit_length('n')})::BIGINT AS split_bits FROM (SELECT level, key >> ({3 * BITS} - level + 1) AS node, sum(n)::BIGINT AS n FROM ({_keys_sql()}), range(1, {3 * BITS + 1}) t(level) GROUP BY ALL) GROUP BY level")
def kdtree_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.kdtree_bits(baselines.cube_keys(clouds.unit(spark, sf_dir, CLOUD), BITS), BITS).select(F.col("level").cast("long").alias("level"), "nodes", F.col("split_bits").cast("long").alias("split_bits"))


_MASKS = f"SELECT level, child >> 3 AS node, bit_or(1 << (child & 7)::INTEGER)::INTEGER AS mask FROM (SELECT DISTINCT level, key >> (3 * ({BITS} - level)) AS child FROM ({_keys_sql()}), range(1, {BITS + 1}) t(level)) GROUP BY ALL"


@registered(_MASKS)
def octree_masks(spark: SparkSession, sf_dir: str) -> DataFrame:
    masks = baselines.octree_masks(baselines.cube_keys(clouds.unit(spark, sf_dir, CLOUD), BITS), BITS)
    return masks.select(F.col("level").cast("long").alias("level"), "node", "mask")


def _octree_sql() -> str:
    seen = f"SELECT m.level, m.mask, coalesce(p.mask, 0) AS above FROM ({_MASKS}) m LEFT JOIN ({_MASKS}) p ON m.level = p.level + 1 AND m.node >> 3 = p.node"
    bits = lambda by: f"(SELECT sum(t * log2(t::DOUBLE) - s) FROM (SELECT {by}, sum(c)::BIGINT AS t, sum(c * log2(c::DOUBLE)) AS s FROM (SELECT {by}, mask, count(*) AS c FROM ({seen}) GROUP BY ALL) GROUP BY {by}))"
    return f"SELECT (SELECT count(*) FROM ({seen})) AS nodes, (SELECT count(*) FROM ({seen})) * 8 AS plain_bits, {duck.rounded(bits('1 = 1'), 3)} AS entropy_bits, {duck.rounded(bits('above'), 3)} AS context_bits"


@registered(_octree_sql())
def octree_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    masks = baselines.octree_masks(baselines.cube_keys(clouds.unit(spark, sf_dir, CLOUD), BITS), BITS)
    got = baselines.octree_bits(masks)
    return got.select("nodes", "plain_bits", rounded(F.col("entropy_bits"), 3).alias("entropy_bits"), rounded(F.col("context_bits"), 3).alias("context_bits"))


def _lossless_sql() -> str:
    scale = "pow(10.0::DOUBLE, e)"
    whole = f"floor(v * {scale} + 0.5::DOUBLE)"
    q = f"SELECT vector, e, CASE WHEN {whole} / {scale} = v THEN {whole}::BIGINT END AS q FROM (SELECT o_orderkey // 1024 AS vector, o_totalprice AS v FROM orders), range(0, 11) t(e)"
    sized = f"SELECT vector, e, count(*) AS n, count(q) AS good, coalesce(max(q) - min(q), 0) AS span FROM ({q}) GROUP BY ALL"
    cost = f"SELECT *, (({duck.bit_length('span')}) * n + (n - good) * 80 + 80)::BIGINT AS bits FROM ({sized})"
    return f"SELECT vector, e::INTEGER AS e, bits, n - good AS exceptions, n FROM (SELECT *, row_number() OVER (PARTITION BY vector ORDER BY bits, e) AS r FROM ({cost})) WHERE r = 1"


@registered(_lossless_sql())
def float_lossless_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Decimal exponent, bits and patches of groups of 1024 prices."""
    column = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").alias("pid"), F.col("o_totalprice").alias("v"))
    return baselines.float_lossless(column)


_FRACTION = math.ceil(math.log2(1 / (2 * EB)))


def _bounded_sql() -> str:
    q = f"SELECT floor(y * {duck.number(float(1 << _FRACTION))} + 0.5::DOUBLE)::BIGINT AS q FROM ({duck.unit(CLOUD)})"
    seen = f"SELECT place, count(*) AS values, sum(c)::BIGINT AS n FROM (SELECT place, (q >> (8 * place)) & 255 AS b, count(*) AS c FROM ({q}), range(0, {_FRACTION // 8 + 1}) t(place) GROUP BY ALL) GROUP BY place"
    return f"SELECT place::INTEGER AS place, values, n, (CASE WHEN values <= 16 THEN least(({duck.bit_length('values - 1')}) * n + values * 8, n * 8) ELSE n * 8 END)::BIGINT AS bits FROM ({seen})"


@registered(_bounded_sql())
def float_bounded_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.float_bounded(clouds.unit(spark, sf_dir, CLOUD).select(F.col("y").alias("v")), EB)


_MIX = 40503


def _energy_sql() -> str:
    basis = [[math.cos(math.pi * (p + 0.5) * k / 8) * math.sqrt((1 if k == 0 else 2) / 8) for p in range(8)] for k in range(8)]
    stored = duck.unit(CLOUD, keyed=True)
    mixed = f"SELECT x, y, z, pid // 65536 * 65536 + row_number() OVER (PARTITION BY pid // 65536 ORDER BY pid % 65536 * {_MIX} % 65536) - 1 AS pid FROM ({stored})"
    parts = []
    for order, source in (("stored", stored), ("scrambled", mixed)):
        for a in "xyz":
            c = ", ".join(f"sum({a} * ([{', '.join(duck.number(b) for b in basis[k])}])[pid % 8 + 1]) AS c{k}" for k in range(1, 8))
            e = lambda ks: " + ".join(f"sum(c{k} * c{k})" for k in ks)
            parts.append(f"SELECT '{a}' AS axis, '{order}' AS \"order\", {duck.rounded(f'({e(range(1, 4))}) / ({e(range(1, 8))})')} AS low_share FROM (SELECT {c} FROM ({source}) GROUP BY pid // 8)")
    return " UNION ALL ".join(parts)


@registered(_energy_sql())
def transform_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Low-frequency energy in stored order and after a scramble of keys: indices carry no meaning."""
    at = clouds.unit(spark, sf_dir, CLOUD, keyed=True)
    order = Window.partitionBy(F.floor(F.col("pid") / 65536)).orderBy(F.pmod("pid", F.lit(65536)) * _MIX % 65536)
    mixed = at.withColumn("pid", F.floor(F.col("pid") / 65536) * 65536 + F.row_number().over(order) - 1)
    both = baselines.transform_energy(at).withColumn("order", F.lit("stored")).unionByName(baselines.transform_energy(mixed).withColumn("order", F.lit("scrambled")))
    return both.withColumn("low_share", rounded(F.col("low_share")))


@registered(f"WITH c AS (SELECT i, j, k FROM ({duck.table('c_vectors', COARSE)})) SELECT (SELECT count(*) FROM c a JOIN c x ON x.i = a.i - 2 AND x.j = a.j AND x.k = a.k JOIN c y ON y.i = a.i AND y.j = a.j - 2 AND y.k = a.k JOIN c z ON z.i = a.i AND z.j = a.j AND z.k = a.k - 2) AS predictable, (SELECT count(*) FROM c) AS n_cells")
def stencil_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells that a stencil could predict at all."""
    return baselines.stencil_hits(tables.occupied(clouds.unit(spark, sf_dir, "c_vectors"), COARSE))


def _hausdorff_sql() -> str:
    f = duck.number(COARSE)
    at = duck.celled(duck.at_factor("c_accounts", COARSE))
    steps = ", ".join(map(str, ((0, 0, 0), *metrics.NEIGHBOURS)))
    told = f"SELECT i + a AS i, j + b AS j, k + c AS k, (u - i - a) * (u - i - a) + (v - j - b) * (v - j - b) + (w - k - c) * (w - k - c) AS e2 FROM ({at}), (VALUES {steps}) s(a, b, c)"
    near = f"SELECT max(near) FROM (SELECT min(e2) AS near FROM ({told}) JOIN (SELECT DISTINCT i, j, k FROM ({at})) USING (i, j, k) GROUP BY i, j, k)"
    return f"SELECT {duck.rounded(f'sqrt((SELECT max(e2) FROM ({at}))) / {f}')} AS from_points, {duck.rounded(f'sqrt(({near})) / {f}')} AS from_cells"


@registered(_hausdorff_sql())
def hausdorff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest distance from a point to its centre, and from a centre to its nearest point."""
    got = metrics.hausdorff(clouds.unit(spark, sf_dir, "c_accounts"), COARSE)
    return got.select(*[rounded(F.col(c)).alias(c) for c in got.columns])
