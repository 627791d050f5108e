"""Registered queries on choices of the method and its surroundings: stored order, curves, layouts, escapes, scalar and mixed lattices, guards, frames, windows."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.functions import lattice, quantize
from cloudlattice.functions.bits import bit_length
from cloudlattice.functions.lattice import LatticeSpec
from cloudlattice.operators import cells as tables
from cloudlattice.operators import container, distribute, families, metrics, region
from cloudlattice.operators.container import CodecSpec
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck, ordering, rates
from cloudlattice.plans.ordering import COARSE
from cloudlattice.sources import clouds
from cloudlattice.streaming import cells as stream

QUERIES, ORACLES = {}, {}


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


@registered(f"SELECT pid, i, j, k FROM ({duck.celled(duck.at_factor('c_orders', COARSE, keyed=True))})")
def order_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points with their ids out of a container that keeps the order as a third stream."""
    spec = CodecSpec(chunk_cells=1024, keep_order=True)
    chunks = container.compress(clouds.unit(spark, sf_dir, "c_orders", keyed=True), 0.02, spec, 3)
    return container.decompress(chunks, 0.02, spec).select("pid", "i", "j", "k")


_CURVES = ("row_major", "block", "morton", "hilbert")


@registered(" UNION ALL ".join(f"SELECT '{c}' AS curve, '{layout}' AS layout, i, j, k, n FROM ({duck.table('c_catalog', COARSE)})" for c in _CURVES for layout in ("packed", "raw")))
def curve_containers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells out of containers of every curve and key layout."""
    at, parts = clouds.unit(spark, sf_dir, "c_catalog"), []
    for curve in _CURVES:
        for layout in ("packed", "raw"):
            spec = CodecSpec(curve=curve, layout=layout, chunk_cells=256, entropy="auto")
            cells = container.decompress(container.compress(at, 0.02, spec, 2), 0.02, spec)
            parts.append(cells.select(F.lit(curve).alias("curve"), F.lit(layout).alias("layout"), "i", "j", "k", "n"))
    return tables.stacked(parts)


_LAYOUTS = ("c_vectors", "c_activity", "c_corpus")


def _axis_sql() -> str:
    w = "OVER (PARTITION BY chunk ORDER BY key)"
    parts = []
    for name in _LAYOUTS:
        at = f"SELECT *, key // 4096 AS chunk FROM ({ordering.keyed_sql(name)})"
        gaps = f"SELECT 1 AS one, key - lag(key, 1, 0) {w} AS g, {', '.join(f'{c} - lag({c}, 1, 0) {w} AS g{c}' for c in 'ijk')} FROM ({at})"
        fold = [f"CASE WHEN g{c} >= 0 THEN g{c} * 2 ELSE -g{c} * 2 - 1 END" for c in "ijk"]
        for layout, symbols in (("joint", ["g"]), ("axes", fold)):
            parts.append(f"SELECT '{name}' AS dataset, '{layout}' AS layout, {duck.rounded('bits', 3)} AS bits FROM ({rates._stream_sql(symbols, gaps, 'one')})")
    return " UNION ALL ".join(parts)


@registered(_axis_sql())
def axis_streams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of one stream of keys against three streams, one an axis, in the same order."""
    w, parts = Window.partitionBy("chunk").orderBy("key"), []
    for name in _LAYOUTS:
        at = ordering.keyed(spark, sf_dir, name).withColumn("chunk", F.floor(F.col("key") / 4096))
        gap = {c: F.col(c) - F.lag(c, 1, 0).over(w) for c in ("key", "i", "j", "k")}
        laid = at.select(*[g.alias(f"g{c}") for c, g in gap.items()])
        folded = [F.when(F.col(f"g{c}") >= 0, F.col(f"g{c}") * 2).otherwise(-F.col(f"g{c}") * 2 - 1) for c in "ijk"]
        for layout, symbols in (("joint", [families.entry("key", F.col("gkey"))]), ("axes", [families.entry(c, f) for c, f in zip("ijk", folded, strict=True)])):
            streams = laid.select(F.lit(name).alias("dataset"), F.lit(layout).alias("layout"), F.inline(F.array(*symbols)))
            parts.append(families.stream_bits(streams, ["dataset", "layout"]).select("dataset", "layout", rounded(F.col("bits"), 3).alias("bits")))
    return tables.stacked(parts)


_LEAST = (1, 2, 4, 16)
_DELTAS = f"SELECT key - lag(key, 1, 0) OVER (ORDER BY key) AS v FROM ({ordering.keyed_sql()})"


def _escape_sql() -> str:
    parts = []
    for least in _LEAST:
        h = f"SELECT v, count(*) AS c FROM ({_DELTAS}) GROUP BY v"
        sums = f"SELECT sum(c)::BIGINT AS t, coalesce(sum(c * log2(c::DOUBLE)) FILTER (WHERE c >= {least}), 0) AS l, count(*) FILTER (WHERE c >= {least}) AS kept, coalesce(sum({duck.bit_length('v')}) FILTER (WHERE c >= {least}), 0) AS heads, coalesce(sum(c) FILTER (WHERE c < {least}), 0)::BIGINT AS e, max(v) AS top FROM ({h})"
        escaped = f"CASE WHEN e = 0 THEN 0 ELSE -e * log2(e::DOUBLE) + e * ({duck.bit_length('top')}) + 8 END"
        parts.append(f"SELECT {least} AS least, kept, e AS escaped, {duck.rounded(f't * log2(t::DOUBLE) - l + {escaped} + kept * 8 + heads', 3)} AS bits FROM ({sums})")
    return " UNION ALL ".join(parts)


@registered(_escape_sql())
def escape_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of the residual stream when symbols rarer than ``least`` share one escape code before their plain bits."""
    counts = tables.residuals(ordering.keyed(spark, sf_dir)).groupBy(F.col("delta").alias("v")).agg(F.count(F.lit(1)).alias("c"))
    rows = counts.withColumn("least", F.explode(F.array(*[F.lit(x) for x in _LEAST]))).withColumn("own", F.col("c") >= F.col("least"))
    of = lambda x: F.sum(F.when(F.col("own"), x).otherwise(0))
    sums = rows.groupBy("least").agg(F.sum("c").alias("t"), of(F.col("c") * F.log2(F.col("c").cast("double"))).alias("l"), of(F.lit(1)).cast("long").alias("kept"), of(bit_length(F.col("v"))).alias("heads"), F.sum(F.when(~F.col("own"), F.col("c")).otherwise(0)).alias("escaped"), F.max("v").alias("top"))
    e = F.col("escaped")
    tail = F.when(e == 0, 0.0).otherwise(-e * F.log2(F.greatest(e, F.lit(1)).cast("double")) + e * bit_length(F.col("top")) + 8)
    return sums.select("least", "kept", "escaped", rounded(F.col("t") * F.log2(F.col("t").cast("double")) - F.col("l") + tail + F.col("kept") * 8 + F.col("heads"), 3).alias("bits"))


_SCALAR = (20.0, 64.0, 7.0)


@registered(f"SELECT i, j, k, count(*) AS n FROM (SELECT {', '.join(f'floor({a} * {duck.number(f)} + 0.5::DOUBLE)::BIGINT AS {c}' for a, f, c in zip('xyz', _SCALAR, 'ijk', strict=True))} FROM ({duck.unit('c_activity')})) GROUP BY ALL")
def scalar_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of a quantizer that treats every axis on its own, with a step of its own."""
    at = clouds.unit(spark, sf_dir, "c_activity")
    cell = quantize.scalar_cell([F.col(a) for a in "xyz"], list(_SCALAR))
    return tables.run_lengths(at.select(*[c.cast("long").alias(n) for c, n in zip(cell, quantize.CELL, strict=True)]))


_SPARSE = 1.3


def _hybrid_sql() -> str:
    table = duck.table("c_vectors", COARSE)
    blocks = f"SELECT i >> 3 AS bi, j >> 3 AS bj, k >> 3 AS bk, sum(n)::BIGINT AS n, count(*) AS m FROM ({table}) GROUP BY ALL"
    return f"SELECT CASE WHEN n < {duck.number(_SPARSE)} * m THEN 'points' ELSE 'cells' END AS kind, count(*) AS blocks, sum(n)::BIGINT AS n_points, sum(m)::BIGINT AS n_cells FROM ({blocks}) GROUP BY kind"


@registered(_hybrid_sql())
def hybrid_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks that enumerate their points, as the lattice gains nothing there, and blocks that keep cells and counts."""
    kinds = tables.hybrid_blocks(tables.occupied(clouds.unit(spark, sf_dir, "c_vectors"), COARSE), 3, _SPARSE)
    return kinds.groupBy("kind").agg(F.count(F.lit(1)).alias("blocks"), F.sum("n").alias("n_points"), F.sum("m").alias("n_cells"))


_GUARDED = {g: LatticeSpec.from_rel(1e-4, guard=g).factor for g in (False, True)}


def _guard_sql() -> str:
    parts = []
    for guard, f in _GUARDED.items():
        gap = " + ".join(f"({a} - ({c} / {duck.number(f)})::FLOAT::DOUBLE) * ({a} - ({c} / {duck.number(f)})::FLOAT::DOUBLE)" for a, c in zip("xyz", "ijk", strict=True))
        parts.append(f"SELECT {str(guard).lower()} AS guard, {duck.rounded('sqrt(max(e2))', 9)} AS single, {duck.rounded(f'sqrt(max(plain)) / {duck.number(f)}', 9)} AS double, sqrt(max(plain)) / {duck.number(f)} <= {duck.number(1e-4 * math.sqrt(3))} AS kept FROM (SELECT {gap} AS e2, (u - i) * (u - i) + (v - j) * (v - j) + (w - k) * (w - k) AS plain FROM ({duck.celled(duck.at_factor('c_orders', f))}))")
    return " UNION ALL ".join(parts)


@registered(_guard_sql())
def guarded_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest error with and without the guard against round-off, with centres in single and in double precision."""
    parts = []
    for guard, f in _GUARDED.items():
        got = metrics.precision(clouds.unit(spark, sf_dir, "c_orders"), f)
        parts.append(got.select(F.lit(guard).alias("guard"), rounded(F.col("single"), 9).alias("single"), rounded(F.col("double"), 9).alias("double"), (F.col("double") <= F.lit(1e-4 * math.sqrt(3))).alias("kept")))
    return tables.stacked(parts)


_SHAPES = ("cube", "hexagonal_prism", "rhombic_dodecahedron", "truncated_octahedron")
# fixed values: closed forms of the second moments
_MOMENTS = f"(VALUES ('cube', 1 / 12.0::DOUBLE), ('hexagonal_prism', pow(pow(5 / (36 * sqrt(3.0::DOUBLE)), 2) / 12, 1 / 3.0::DOUBLE)), ('rhombic_dodecahedron', pow(2.0::DOUBLE, -11 / 3.0::DOUBLE)), ('truncated_octahedron', 19 / (192 * pow(2.0::DOUBLE, 1 / 3.0::DOUBLE)))) m(shape, g)"


@registered(f"SELECT a.shape AS shape, b.shape AS other, {duck.rounded('b.g / a.g')} AS error_ratio, {duck.rounded('pow(b.g / a.g, 1.5::DOUBLE)')} AS volume_ratio FROM {_MOMENTS}, {_MOMENTS.replace('m(shape, g)', 'b(shape, g)')} WHERE a.shape <> b.shape".replace(") m(shape, g), ", ") a(shape, g), "))
def equal_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of one shape over another's at equal volume, and volume over volume at equal error: the same order either way."""
    g = {s: lattice.second_moment(s) for s in _SHAPES}
    pairs = [(a, b, g[b] / g[a]) for a in g for b in g if a != b]
    return spark.createDataFrame(pairs, "shape string, other string, q double").select("shape", "other", rounded(F.col("q")).alias("error_ratio"), rounded(F.pow(F.col("q"), F.lit(1.5))).alias("volume_ratio"))


_BEST, _WORST = 19 / (192 * 2 ** (1 / 3)), 1 / 12
_TILES = f"SELECT p_brand, CASE WHEN p_partkey % 2 = 0 THEN {duck.number(_BEST)} ELSE {duck.number(_WORST)} END AS g, p_size / 50.0::DOUBLE AS v FROM part"


@registered(f"SELECT p_brand, count(*) AS tiles, {duck.rounded('sum(g * pow(v, 5 / 3.0::DOUBLE))')} AS mixed, {duck.rounded(f'{duck.number(_BEST)} * count(*) * pow(sum(v) / count(*), 5 / 3.0::DOUBLE)')} AS uniform FROM ({_TILES}) GROUP BY p_brand")
def mixed_tilings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of tilings of mixed shapes and volumes against as many equal cells of the best shape: never less."""
    tiles = spark.read.parquet(f"{sf_dir}/part.parquet").select("p_brand", F.when(F.col("p_partkey") % 2 == 0, _BEST).otherwise(_WORST).alias("g"), (F.col("p_size") / F.lit(50.0)).alias("v"))
    power = lambda x: F.pow(x, F.lit(5 / 3))
    n = F.count(F.lit(1))
    return tiles.groupBy("p_brand").agg(n.alias("tiles"), rounded(F.sum(F.col("g") * power(F.col("v")))).alias("mixed"), rounded(F.lit(_BEST) * n * power(F.sum("v") / n)).alias("uniform"))


_PSNRS = (30.0, 45.0, 60.0)


def _psnr_sql() -> str:
    parts = []
    for p in _PSNRS:
        f = LatticeSpec.from_psnr(p).factor
        parts.append(f"SELECT {duck.number(p)} AS wanted, {duck.rounded(f'10 * log10(3.0::DOUBLE / (avg(e2) / {duck.number(f * f)}))', 4)} AS measured, count(DISTINCT (i, j, k)) AS n_cells FROM ({duck.celled(duck.at_factor('c_shipping', f))})")
    return " UNION ALL ".join(parts)


@registered(_psnr_sql())
def psnr_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lattices chosen for a signal-to-error ratio, and the ratio that they reach."""
    at, parts = clouds.unit(spark, sf_dir, "c_shipping"), []
    for p in _PSNRS:
        f = LatticeSpec.from_psnr(p).factor
        e2 = quantize.error_squared() / F.lit(f * f)
        cells = quantize.assign(at, f).groupBy(*quantize.CELL).agg(F.sum(e2).alias("e"), F.count(F.lit(1)).alias("n"))
        got = cells.agg(rounded(F.log10(F.lit(3.0) / (F.sum("e") / F.sum("n"))) * 10, 4).alias("measured"), F.count(F.lit(1)).alias("n_cells"))
        parts.append(got.select(F.lit(p).alias("wanted"), "measured", "n_cells"))
    return tables.stacked(parts)


_CHUNKS, _RADII = (8, 32), (0.02, 0.05, 0.10)


def _report_sql() -> str:
    parts = []
    f = duck.number(COARSE)
    near = " + ".join(f"pow(greatest(lo_{c} / {f} - c{a}, c{a} - hi_{c} / {f}, 0.0::DOUBLE), 2)" for c, a in zip("ijk", "xyz", strict=True))
    far = " + ".join(f"pow(greatest(abs(c{a} - lo_{c} / {f}), abs(hi_{c} / {f} - c{a})), 2)" for c, a in zip("ijk", "xyz", strict=True))
    box = ", ".join(f"{g}({c}) AS {n}_{c}" for g, n in (("min", "lo"), ("max", "hi")) for c in "ijk")
    from cloudlattice.plans import regions

    for name in ("c_catalog", "c_shipping"):
        for count in _CHUNKS:
            keys = ordering.keyed_sql(name)
            splits = f"(SELECT quantile_cont(key, {[p / count for p in range(1, count)]}) AS q FROM ({keys}))"
            owned = f"SELECT c.*, len(list_filter(s.q, lambda x: c.key > floor(x))) AS chunk FROM ({keys}) c, {splits} s"
            side = f"SELECT chunk, count(*) AS m, {box} FROM ({owned}) GROUP BY chunk"
            parts.append(f"SELECT '{name}' AS dataset, {count} AS chunks, r, count(*) AS pairs, count(*) FILTER (WHERE {near} > r * r + 1e-12::DOUBLE) AS skipped, count(*) FILTER (WHERE {near} <= r * r + 1e-12::DOUBLE AND {far} <= r * r - 1e-12::DOUBLE) AS contained, sum(m) FILTER (WHERE NOT ({near} > r * r + 1e-12::DOUBLE) AND NOT ({far} <= r * r - 1e-12::DOUBLE))::BIGINT AS cells_decoded FROM ({side}), ({regions.balls_sql()}) GROUP BY r")
    return " UNION ALL ".join(parts)


@registered(_report_sql())
def chunk_skips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of chunks and balls that need no decoding, with 8 and 32 chunks of equal numbers of cells, by radius."""
    from cloudlattice.plans import regions

    asked, parts = regions.balls(spark, sf_dir), []
    for name in ("c_catalog", "c_shipping"):
        keys = ordering.keyed(spark, sf_dir, name)
        for count in _CHUNKS:
            owned = keys.withColumn("chunk", distribute.splitter_owner(distribute.exact_splitters(keys, count)))
            box = [f(c).alias(f"{n}_{c}") for f, n in ((F.min, "lo"), (F.max, "hi")) for c in quantize.CELL]
            side = owned.groupBy("chunk").agg(F.count(F.lit(1)).alias("n_points"), *box)  # cells, not points, are decoded
            kinds = region.classify(side, asked, COARSE).join(asked.select("qid", "r"), "qid")
            one = lambda c: F.sum(F.when(F.col("class") == c, 1).otherwise(0))
            part = kinds.groupBy("r").agg(F.count(F.lit(1)).alias("pairs"), one("disjoint").alias("skipped"), one("contained").alias("contained"), F.sum(F.when(F.col("class") == "boundary", F.col("n_points"))).alias("cells_decoded"))
            parts.append(part.select(F.lit(name).alias("dataset"), F.lit(count).alias("chunks"), "r", "pairs", "skipped", "contained", "cells_decoded"))
    return tables.stacked(parts)


_FRAME = f"SELECT event_type, i, j, k FROM ({duck.celled(duck.at_factor('c_activity', COARSE, carry='event_type, '))})"
_OPS = {"union": "UNION", "intersect": "INTERSECT", "except": "EXCEPT"}


@registered(" UNION ALL ".join(f"SELECT '{op}' AS op, count(*) AS n_cells FROM (SELECT i, j, k FROM ({_FRAME}) WHERE event_type = 'view' {sql} SELECT i, j, k FROM ({_FRAME}) WHERE event_type = 'click')" for op, sql in _OPS.items()))
def frame_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of two frames together, in both, and in the first only."""
    at = clouds.unit(spark, sf_dir, "c_activity", keyed=True)
    view, click = (quantize.assign(at.where(F.col("event_type") == kind), COARSE).select(*quantize.CELL) for kind in ("view", "click"))
    found = {"union": view.union(click).distinct(), "intersect": view.intersect(click), "except": view.subtract(click)}
    return tables.stacked([d.agg(F.count(F.lit(1)).alias("n_cells")).select(F.lit(op).alias("op"), "n_cells") for op, d in found.items()])


@registered("SELECT event_id, user_id, (SELECT epoch_us(max(v.ts)) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts) AS seen FROM events p WHERE event_type = 'purchase'")
def last_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every purchase with the time of the same user's last view at or before it: an as-of join by one window."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").where(F.col("event_type").isin("view", "purchase"))
    return tables.as_of(events, "event_type", "view", "purchase", ["user_id"], "ts").select("event_id", "user_id", clouds.micros("seen").cast("long").alias("seen"))


_MONTH = "strftime(ts, '%Y-%m')"


@registered(f"SELECT month, event_type, grouping(month) + grouping(event_type) AS level, n_points, n_users FROM (SELECT month, event_type, count(*) AS n_points, count(DISTINCT user_id) AS n_users, grouping(month) AS gm, grouping(event_type) AS ge FROM (SELECT *, {_MONTH} AS month FROM events) GROUP BY ROLLUP (month, event_type))".replace("grouping(month) + grouping(event_type) AS level, n_points", "gm + ge AS level, n_points", 1))
def frame_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points and users by month and kind, by month, and in all."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("month", F.date_format("ts", "yyyy-MM"))
    level = (F.grouping("month").cast("long") + F.grouping("event_type").cast("long")).alias("level")
    return events.rollup("month", "event_type").agg(level, F.count(F.lit(1)).alias("n_points"), F.countDistinct("user_id").alias("n_users"))


@registered(f"SELECT dataset, eb, sum(n)::BIGINT AS n_points, count(*) AS n_cells FROM ({duck.cells(('c_accounts', 'c_catalog'), (5e-3, 2e-2))}) GROUP BY CUBE (dataset, eb)")
def density_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points and cells by cloud and bound, by either, and in all."""
    from cloudlattice.plans import sweeps

    held = sweeps.cells(spark, sf_dir, ("c_accounts", "c_catalog"), (5e-3, 2e-2))
    return held.cube("dataset", "eb").agg(F.sum("n").alias("n_points"), F.count(F.lit(1)).alias("n_cells"))


def _sliding_sql() -> str:
    day = "epoch_us(ts) // 86400000000"
    return f"SELECT strftime(make_timestamp((d - o) * 86400000000), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM (SELECT {day} AS d, event_type FROM events), (VALUES (0), (1)) w(o) GROUP BY ALL"


@registered(_sliding_sql())
def sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in windows of two days that start every day."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    return stream.kind_counts(events, F.window("ts", "2 days", "1 day")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


_GAP = 6 * 3600


@registered(f"SELECT user_id, min(s)::BIGINT AS first_second, count(*) AS n FROM (SELECT user_id, s, sum(new) OVER (PARTITION BY user_id ORDER BY s, new DESC ROWS UNBOUNDED PRECEDING) AS session FROM (SELECT user_id, epoch_us(ts) // 1000000 AS s, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) <= {_GAP * 1_000_000}::BIGINT THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, session")
def session_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by user in sessions that end after six quiet hours."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    sessions = stream.sessions(events, _GAP)
    return sessions.select("user_id", F.unix_seconds(F.from_utc_timestamp(F.col("start"), F.current_timezone())).alias("first_second"), "n")


@registered("SELECT i, j, k, n FROM (SELECT i, j, k, count(*) AS n FROM (" + duck.celled(duck.at_factor("c_activity", COARSE)) + ") GROUP BY i, j, k) ORDER BY n DESC, i, j, k LIMIT 25")
def densest_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The twenty-five cells of most points; a report of the top, so the limit is the feature."""
    return tables.occupied(clouds.unit(spark, sf_dir, "c_activity"), COARSE).orderBy(F.desc("n"), "i", "j", "k").limit(25)


@registered("SELECT user_id, 15::BIGINT AS seen, epoch_us(ts) AS crossed FROM (SELECT user_id, ts, row_number() OVER (PARTITION BY user_id ORDER BY ts) AS r FROM events) WHERE r = 15")
def busy_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with at least fifteen events, and when the fifteenth came; a stream keeps the same counts as state."""
    found = stream.alerts(spark.read.parquet(f"{sf_dir}/events.parquet"), 15)
    return found.select("user_id", "seen", F.unix_micros(F.from_utc_timestamp("crossed", F.current_timezone())).alias("crossed"))
