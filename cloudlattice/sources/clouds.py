"""Point clouds from tables: axes, scaling, frames and strides."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

AXES = ("x", "y", "z")


def micros(column: str) -> Column:
    """Microseconds since 1970 of a wall-clock timestamp, in any session time zone."""
    return F.unix_micros(F.from_utc_timestamp(F.col(column).cast("timestamp"), F.current_timezone())).cast("double")


def _days(column: str) -> Column:
    return micros(column) / F.lit(86400000000.0)


def _line_id(df: DataFrame) -> DataFrame:
    """Lines of an order have no unique key: number them by all other columns."""
    others = [c for c in df.columns if c != "l_orderkey"]
    return df.withColumn("pid", F.col("l_orderkey") * 1024 + F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*others)))


@dataclass(frozen=True)
class Cloud:
    table: str
    axes: tuple
    pid: str | None
    carry: tuple[str, ...] = ()


CLOUDS = {
    "c_sales": Cloud("lineitem", ("l_quantity", "l_extendedprice", "l_discount"), None),
    "c_shipping": Cloud("lineitem", (lambda: _days("l_shipdate"), "l_extendedprice", "l_suppkey"), None),
    "c_linekeys": Cloud("lineitem", ("l_orderkey", "l_partkey", "l_suppkey"), None),
    "c_activity": Cloud("events", (lambda: micros("ts") / F.lit(1e6), "user_id", "value"), "event_id", ("event_type",)),
    "c_orders": Cloud("orders", (lambda: _days("o_orderdate"), "o_totalprice", "o_custkey"), "o_orderkey"),
    "c_vectors": Cloud("embeddings", (), "vec_id"),
    "c_corpus": Cloud("documents", ("n_chars", lambda: F.size(F.split("text", " ")), "doc_id"), "doc_id"),
    "c_catalog": Cloud("part", ("p_partkey", "p_size", "p_retailprice"), "p_partkey"),
    "c_accounts": Cloud("customer", ("c_custkey", "c_nationkey", "c_acctbal"), "c_custkey"),
}


#: Clouds of order lines, whose ids are made by ``_line_id``.
LINES = tuple(n for n, c in CLOUDS.items() if c.pid is None)


_schemas: dict[tuple[str, str], StructType] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; its columns are looked up once a session, as each look is a job."""
    path = f"{sf_dir}/{name}.parquet"
    key = (spark.sparkContext.applicationId, path)
    if key not in _schemas:
        _schemas[key] = spark.read.parquet(path).schema
    return spark.read.schema(_schemas[key]).parquet(path)


def line_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """l_orderkey, pid of every order line, from the number of lines of each order."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("m"))
    places = lines.where("l_orderkey IS NOT NULL").select("l_orderkey", F.explode(F.sequence(F.lit(1).cast("long"), F.col("m"))).alias("place"))
    return places.select("l_orderkey", (F.col("l_orderkey") * 1024 + F.col("place")).alias("pid"))


def of(df: DataFrame, x: str, y: str, z: str, pid: str | None = None, carry: tuple[str, ...] = (), on_bad: str = "drop") -> DataFrame:
    """A cloud of three numeric columns. Null, not-a-number and infinite coordinates are dropped or raise."""
    for c in (x, y, z):
        kind = df.schema[c].dataType.typeName()
        if kind not in ("double", "float", "long", "integer", "short", "byte") and not kind.startswith("decimal"):
            raise TypeError(f"{c} is {kind}; coordinates are numbers")
    out = df.select(*([F.col(pid).alias("pid")] if pid else []), *[F.col(c).cast("double").alias(a) for a, c in zip(AXES, (x, y, z), strict=True)], *carry)
    good = None
    for a in AXES:
        fine = F.col(a).isNotNull() & ~F.isnan(a) & (F.abs(F.col(a)) < F.lit(float("inf")))
        good = fine if good is None else good & fine
    if on_bad == "error":
        return out.select("*", F.when(~F.coalesce(good, F.lit(False)), F.raise_error(F.lit("a coordinate is null or not finite"))).alias("_bad")).drop("_bad").where(good)
    return out.where(good)


def load(spark: SparkSession, sf_dir: str, name: str, keyed: bool = False, orders: DataFrame | None = None) -> DataFrame:
    """x, y, z (and pid where asked for) of a registered cloud; only the columns that it needs are read.

    ``orders`` (a small table of l_orderkey) leaves the lines of these orders, with the ids that they have among all.
    """
    spec = CLOUDS[name]
    df = table(spark, sf_dir, spec.table)
    if name == "c_vectors":
        # as many whole triples as a vector has
        triple = F.explode(F.sequence(F.lit(0), F.floor(F.size("embedding") / 3).cast("int") - 1))
        df = df.select("vec_id", "embedding", triple.alias("t"))
        axes = [F.element_at("embedding", F.col("t") * 3 + a + 1).cast("double").alias(n) for a, n in enumerate(AXES)]
        return df.select(*([(F.col("vec_id") * 21 + F.col("t")).alias("pid")] if keyed else []), *axes)
    if orders is not None:
        df = df.join(F.broadcast(orders), "l_orderkey", "left_semi")
    if keyed and spec.pid is None:
        df = _line_id(df)
    pid = [F.col(spec.pid or "pid").cast("long").alias("pid")] if keyed else []
    axes = [(a() if callable(a) else F.col(a)).cast("double").alias(n) for a, n in zip(spec.axes, AXES, strict=True)]
    return df.select(*pid, *axes, *(spec.carry if keyed else ()))


def several(spark: SparkSession, sf_dir: str, names: tuple[str, ...], keyed: bool = False) -> DataFrame:
    """cloud (its place in ``names``), x, y, z (and pid where asked for) of many clouds as stored; order lines are read and numbered once for all."""
    lines, parts = [n for n in names if n in LINES], []
    if lines:
        df = table(spark, sf_dir, CLOUDS[lines[0]].table)
        axes = {n: [(a() if callable(a) else F.col(a)).cast("double").alias(c) for a, c in zip(CLOUDS[n].axes, AXES, strict=True)] for n in lines}
        at = F.inline(F.array(*[F.struct(F.lit(names.index(n)).alias("cloud"), *axes[n]) for n in lines]))
        parts.append(_line_id(df).select(F.col("pid").cast("long"), at) if keyed else df.select(at))
    for n in names:
        if n not in LINES:
            parts.append(load(spark, sf_dir, n, keyed).select(*(["pid"] if keyed else []), F.lit(names.index(n)).alias("cloud"), *AXES))
    return reduce(DataFrame.unionByName, parts)


def counts(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> list[int]:
    """Points of each cloud; only of vectors a column is read."""
    rows = [table(spark, sf_dir, t).agg((F.sum(F.floor(F.size("embedding") / 3)) if t == "embeddings" else F.count(F.lit(1))).cast("long").alias("n")).select(F.lit(t).alias("table"), "n") for t in sorted({CLOUDS[n].table for n in names})]
    held = {r["table"]: r["n"] or 0 for r in reduce(DataFrame.unionByName, rows).collect()}
    return [held[CLOUDS[n].table] for n in names]


def census(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> DataFrame:
    """cloud (its place in ``names``), n and the box of many clouds as stored: a row each, from one pass over each table."""
    ends = [(a, s, f) for a in AXES for s, f in (("lo", F.min), ("hi", F.max))]
    lines, parts = [n for n in names if n in LINES], []
    if lines:
        df = table(spark, sf_dir, CLOUDS[lines[0]].table)
        axes = {(n, c): (a() if callable(a) else F.col(a)).cast("double") for n in lines for a, c in zip(CLOUDS[n].axes, AXES, strict=True)}
        row = df.select(*[e.alias(f"{n}_{a}") for (n, a), e in axes.items()]).agg(F.count(F.lit(1)).alias("n"), *[f(f"{n}_{a}").alias(f"{n}_{a}_{s}") for n in lines for a, s, f in ends])
        each = [F.struct(F.lit(names.index(n)).alias("cloud"), "n", *[F.col(f"{n}_{a}_{s}").alias(f"{a}_{s}") for a, s, _ in ends]) for n in lines]
        parts.append(row.select(F.inline(F.array(*each))))
    for n in names:
        if n not in LINES:
            parts.append(load(spark, sf_dir, n).agg(F.count(F.lit(1)).alias("n"), *[f(a).alias(f"{a}_{s}") for a, s, f in ends]).select(F.lit(names.index(n)).alias("cloud"), "*"))
    return reduce(DataFrame.unionByName, parts)


def bounding_box(cloud: DataFrame) -> dict[str, float]:
    """The only job before a compression: six numbers."""
    row = cloud.agg(*[f(a).alias(f"{a}_{s}") for a in AXES for f, s in ((F.min, "lo"), (F.max, "hi"))]).first()
    return row.asDict()


def unit_scale(cloud: DataFrame, box: dict[str, float] | None = None) -> DataFrame:
    """Each axis to [0, 1]; an axis without extent to 0. The box enters the plan as literals."""
    box = box or bounding_box(cloud)

    def scaled(a: str) -> Column:
        lo, hi = box[f"{a}_lo"], box[f"{a}_hi"]
        return F.lit(0.0) if lo is None or hi == lo else (F.col(a) - F.lit(lo)) / (F.lit(hi) - F.lit(lo))

    return cloud.withColumns({a: scaled(a) for a in AXES})


_boxes: dict[tuple[str, str, str], dict[str, float]] = {}


def box_of(spark: SparkSession, sf_dir: str, name: str) -> dict[str, float]:
    """The box of a registered cloud, found once a session: six numbers."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _boxes:
        _boxes[key] = bounding_box(load(spark, sf_dir, name))
    return _boxes[key]


def unit(spark: SparkSession, sf_dir: str, name: str, keyed: bool = False, orders: DataFrame | None = None) -> DataFrame:
    return unit_scale(load(spark, sf_dir, name, keyed, orders), box_of(spark, sf_dir, name))


def line_number(pid: Column) -> Column:
    """A running number of order lines, whose ids are the order times 1024 and a place."""
    return F.floor(pid / 1024) * 7 + F.pmod(pid, F.lit(1024))


def strides(cloud: DataFrame, steps: tuple[int, ...], number: Column | None = None) -> DataFrame:
    """The rows of every stride, in a column ``stride``: every k-th row by number, so samples are nested."""
    number = F.col("pid") if number is None else number
    kept = F.array_compact(F.array(*[F.when(F.pmod(number, F.lit(k)) == 0, k) for k in steps]))
    return cloud.withColumn("stride", F.explode(kept))
