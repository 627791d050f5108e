"""Registered queries on orders of cells, residual streams, code lengths, round trips and parts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.functions import bits, curves
from cloudlattice.functions.lattice import bcc_factor
from cloudlattice.operators import cells as tables
from cloudlattice.operators import container, distribute
from cloudlattice.operators import information as info
from cloudlattice.operators.coding import huffman_lengths
from cloudlattice.operators.information import rounded
from cloudlattice.plans import duck
from cloudlattice.sources import clouds

QUERIES, ORACLES = {}, {}
COARSE = bcc_factor(0.02)
EXTENT = int(COARSE) + 3
HALF = (EXTENT + 1) // 2
BITS = (HALF - 1).bit_length()


def registered(sql: str | None = None):
    """Enter a query, and the SQL that checks it, under its name."""

    def enter(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return enter


def row_major_sql(i: str, j: str, k: str, n: int = HALF) -> str:
    return f"(({k} * {n} + {j}) * {n} + {i})"


def block_sql(i: str, j: str, k: str, n: int = HALF) -> str:
    b = -(-n // 8)
    return f"((({row_major_sql(f'({i} >> 3)', f'({j} >> 3)', f'({k} >> 3)', b)}) << 9) | {row_major_sql(f'({i} & 7)', f'({j} & 7)', f'({k} & 7)', 8)})"


def hilbert_sql(i: str, j: str, k: str, n_bits: int = BITS) -> str:
    """The walk over bit levels as a fold; the state rides in the low five bits."""
    digit, following = curves.hilbert_tables()
    octant = " + ".join(f"((({c} >> b) & 1) << {a})" for a, c in enumerate((i, j, k)))
    at = f"((acc & 31) * 8 + {octant} + 1)"
    return f"(list_reduce({[n_bits - 1 - b for b in range(n_bits)]}::BIGINT[], lambda acc, b: (((acc >> 5) * 8 + {list(digit)}[{at}]) << 5) + {list(following)}[{at}], 0::BIGINT) >> 5)"


KEYS = {"row_major": row_major_sql, "block": block_sql, "morton": duck.morton, "hilbert": hilbert_sql}


def keyed_sql(name: str = "c_vectors", curve: str = "morton", factor: float = COARSE) -> str:
    return f"SELECT i, j, k, n, {duck.packed(KEYS[curve])} AS key FROM ({duck.table(name, factor)})"


def keyed(spark: SparkSession, sf_dir: str, name: str = "c_vectors", curve: str = "morton") -> DataFrame:
    return tables.keyed(clouds.unit(spark, sf_dir, name), COARSE, curve)


@registered(keyed_sql(curve="row_major"))
def curve_row_major(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(spark, sf_dir, curve="row_major")


@registered(keyed_sql(curve="block"))
def curve_block(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(spark, sf_dir, curve="block")


@registered(keyed_sql(curve="morton"))
def curve_morton(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(spark, sf_dir, curve="morton")


@registered(keyed_sql(curve="hilbert"))
def curve_hilbert(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(spark, sf_dir, curve="hilbert")


@registered(f"SELECT i, j, k, n, {duck.morton('i', 'j', 'k')} AS key FROM ({duck.table('c_vectors', COARSE)})")
def curve_morton_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys over the coordinates as they are, of which the lattice uses one in four."""
    return tables.keyed(clouds.unit(spark, sf_dir, "c_vectors"), COARSE, "morton", "raw")


def _decoded_sql() -> str:
    part = lambda a: " + ".join(f"(((key >> {3 * b + a}) & 1) << {b})" for b in range(12))
    keyed_at = f"SELECT i, j, k, {duck.morton('(i >> 1)', '(j >> 1)', '(k >> 1)')} AS key FROM ({duck.table('c_linekeys', bcc_factor(1e-3))})"
    back = " OR ".join(f"({part(a)}) * 2 + (i & 1) <> {c}" for a, c in enumerate("ijk"))
    return f"SELECT count(*) AS n_cells, count(*) FILTER (WHERE {back}) AS wrong FROM ({keyed_at})"


@registered(_decoded_sql())
def curve_morton_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells whose key does not lead back to them: none."""
    at = tables.keyed(clouds.unit(spark, sf_dir, "c_linekeys"), bcc_factor(1e-3)).select(F.struct("i", "j", "k").alias("cell"), "key")
    back = curves.morton_unattach(at).select("cell", F.struct("i", "j", "k").alias("again"))
    return back.agg(F.count(F.lit(1)).alias("n_cells"), F.sum((F.col("cell") != F.col("again")).cast("int")).cast("long").alias("wrong"))


@registered(f"SELECT key, n, key - lag(key, 1, 0) OVER (ORDER BY key) AS delta FROM ({keyed_sql()})")
def delta_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Residuals over one global order, made in key ranges and stitched at their edges."""
    return tables.residuals(keyed(spark, sf_dir)).select("key", "n", "delta")


@registered(f"SELECT key // 4096 AS chunk, key, n, key - lag(key, 1, 0) OVER (PARTITION BY key // 4096 ORDER BY key) AS delta FROM ({keyed_sql()})")
def delta_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Residuals that start again in every chunk of keys."""
    return tables.residuals(keyed(spark, sf_dir), F.floor(F.col("key") / 4096)).select("chunk", "key", "n", "delta")


@registered(f"SELECT chunk, key FROM (SELECT key // 4096 AS chunk, key FROM ({keyed_sql()}))")
def delta_inverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys again from residuals by a running sum."""
    stream = delta_chunks(spark, sf_dir).withColumn("pos", F.row_number().over(Window.partitionBy("chunk").orderBy("key"))).drop("key")
    return tables.undelta(stream).select("chunk", "key")


_INFO = ("row_major", "block", "morton", "hilbert")
_INFO_CLOUDS = ("c_vectors", "c_activity", "c_shipping", "c_sales", "c_corpus")


def _info_sql(cloud: str, curve: str) -> str:
    points = f"SELECT key, row_number() OVER (ORDER BY key, r) AS pos FROM (SELECT key, unnest(range(0, n)) AS r FROM ({keyed_sql(cloud, curve)}))"
    seq = f"SELECT key, pos, lag(key) OVER (ORDER BY pos) AS before, key - lag(key, 1, 0) OVER (ORDER BY pos) AS res FROM ({points})"
    h = lambda by, src: f"(SELECT log2(sum(c)::DOUBLE) - sum(c * log2(c::DOUBLE)) / sum(c) FROM (SELECT {by}, count(*) AS c FROM {src} GROUP BY {by}))"
    return f"""SELECT '{cloud}' AS dataset, '{curve}' AS curve, {duck.rounded(f"{h('before, key', 'p')} - {h('before', 'p')}")} AS h_given, {duck.rounded(f"{h('was', 'q')} + {h('res', 'q')} - {h('was, res', 'q')}")} AS mutual, {duck.rounded(h('res', 's'))} AS h_residual
    FROM (SELECT 1) WHERE true""".replace("FROM p", f"FROM (SELECT * FROM ({seq}) WHERE before IS NOT NULL)").replace("FROM q", f"FROM (SELECT * FROM (SELECT res, lag(res) OVER (ORDER BY pos) AS was FROM ({seq})) WHERE was IS NOT NULL)").replace("FROM s", f"FROM ({seq})")


@registered(" UNION ALL ".join(_info_sql(c, k) for c in _INFO_CLOUDS for k in _INFO))
def curve_information(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of a symbol given the one before, mutual information of residuals, entropy of residuals, by curve.

    All from counts: a run of n equal keys gives n - 1 pairs of the key with itself.
    """
    cells = tables.stacked([tables.occupied(clouds.unit(spark, sf_dir, c), COARSE).withColumn("dataset", F.lit(c)) for c in _INFO_CLOUDS])
    keys = tables.stacked([curves.attach(cells, k, EXTENT).select("dataset", F.lit(k).alias("curve"), "key", "n") for k in _INFO])
    got = info.by_sequence(keys, ["dataset", "curve"])
    return got.select("dataset", "curve", *[rounded(F.col(c)).alias(c) for c in ("h_given", "mutual", "h_residual")])


@registered(f"SELECT n, count(*) AS cells FROM ({duck.table('c_sales', COARSE)}) GROUP BY n")
def rle_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many cells hold how many points."""
    return tables.occupied(clouds.unit(spark, sf_dir, "c_sales"), COARSE).groupBy("n").agg(F.count(F.lit(1)).alias("cells"))


@registered(f"SELECT i, j, k, count(*) AS n_points FROM (SELECT i, j, k, unnest(range(0, n)) FROM ({duck.table('c_orders', COARSE)})) GROUP BY ALL")
def rle_inverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells repeated by their counts, counted again."""
    return tables.expand(tables.occupied(clouds.unit(spark, sf_dir, "c_orders"), COARSE), most=16).groupBy("i", "j", "k").agg(F.count(F.lit(1)).alias("n_points"))


_DELTAS = f"SELECT n, key - lag(key, 1, 0) OVER (ORDER BY key) AS delta FROM ({keyed_sql()})"


@registered(f"SELECT o, sum(2 * ({duck.bit_length('(delta >> o) + 1')} - 1) + 1 + o)::BIGINT AS delta_bits, sum(2 * ({duck.bit_length('((n - 1) >> o) + 1')} - 1) + 1 + o)::BIGINT AS count_bits FROM ({_DELTAS}), range(0, 8) t(o) GROUP BY o")
def exp_golomb_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of the residual and count streams without a dictionary, by order."""
    stream = delta_stream(spark, sf_dir).select("delta", (F.col("n") - 1).alias("m"))
    sums = stream.agg(*[F.struct(F.lit(o).cast("long").alias("o"), F.sum(bits.exp_golomb_bits(F.col("delta"), o)).alias("delta_bits"), F.sum(bits.exp_golomb_bits(F.col("m"), o)).alias("count_bits")).alias(f"s{o}") for o in range(8)])
    return sums.select(F.explode(F.array(*[F.col(f"s{o}") for o in range(8)])).alias("s")).select("s.*")


@registered(f"SELECT count(*) AS n_cells, ({duck.bit_length('max(delta)')}) * count(*) AS delta_bits, ({duck.bit_length('max(n)')}) * count(*) AS count_bits FROM ({_DELTAS})")
def packed_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of both streams at a fixed width."""
    count = F.count(F.lit(1))
    return delta_stream(spark, sf_dir).agg(count.alias("n_cells"), bits.packed_bits(F.max("delta"), count).alias("delta_bits"), bits.packed_bits(F.max("n"), count).alias("count_bits"))


@registered(f"SELECT delta, count(*) AS c FROM ({_DELTAS}) GROUP BY delta")
def symbol_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return delta_stream(spark, sf_dir).groupBy("delta").agg(F.count(F.lit(1)).alias("c"))


@registered(f"SELECT {duck.rounded('log2(sum(c)::DOUBLE) - sum(c * log2(c::DOUBLE)) / sum(c)')} AS h, sum(c)::BIGINT AS symbols FROM (SELECT delta, count(*) AS c FROM ({_DELTAS}) GROUP BY delta)")
def entropy_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of the residuals: the least that a code of single symbols needs."""
    got = info.entropy(symbol_counts(spark, sf_dir))
    return got.select(rounded(F.col("h")).alias("h"), F.col("total").alias("symbols"))


_MERGES = f"""WITH RECURSIVE d AS (SELECT key // 4096 AS chunk, key - lag(key, 1, 0) OVER (PARTITION BY key // 4096 ORDER BY key) AS delta FROM ({keyed_sql()})),
c AS (SELECT chunk, delta, count(*) AS c FROM d GROUP BY ALL),
h(chunk, w, bits) AS (SELECT chunk, list_sort(list(c)), 0::BIGINT FROM c GROUP BY chunk UNION ALL SELECT chunk, list_sort(list_append(w[3:], w[1] + w[2])), bits + w[1] + w[2] FROM h WHERE len(w) > 1)
SELECT chunk, sum(c)::BIGINT AS cells, count(*) AS symbols, CASE WHEN count(*) = 1 THEN sum(c)::BIGINT ELSE any_value(top) END AS code_bits FROM c JOIN (SELECT chunk, max(bits) AS top FROM h GROUP BY chunk) USING (chunk) GROUP BY chunk"""


@registered(_MERGES)
def huffman_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of an optimal prefix code of the residuals of each chunk, and of its dictionary."""
    import numpy as np

    stream = delta_chunks(spark, sf_dir)

    def lengths(key, pdf):
        symbols, counts = np.unique(pdf["delta"].to_numpy(), return_counts=True)
        import pandas as pd

        return pd.DataFrame([(key[0], len(pdf), len(symbols), int((huffman_lengths(symbols, counts) * counts).sum()))], columns=["chunk", "cells", "symbols", "code_bits"])

    return stream.groupBy("chunk").applyInPandas(lengths, "chunk long, cells long, symbols long, code_bits long")


_RT = ("c_shipping", "c_accounts", "c_corpus")


@registered(" UNION ALL ".join(f"SELECT '{c}' AS dataset, i, j, k, n FROM ({duck.table(c, COARSE)})" for c in _RT))
def roundtrip_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells out of the container equal those that went in."""
    out = None
    spec = container.CodecSpec(chunk_cells=512, entropy="auto")
    for name in _RT:
        chunks = container.compress(clouds.unit(spark, sf_dir, name), 0.02, spec, parts=3)
        part = container.decompress(chunks, 0.02, spec).select(F.lit(name).alias("dataset"), "i", "j", "k", "n")
        out = part if out is None else out.unionByName(part)
    return out


@registered(f"SELECT sum(n)::BIGINT AS n_points, {duck.rounded(f'sum(n * i / {duck.number(COARSE)}) / sum(n)')} AS mean_x, {duck.rounded(f'sum(n * j / {duck.number(COARSE)}) / sum(n)')} AS mean_y, {duck.rounded(f'sum(n * k / {duck.number(COARSE)}) / sum(n)')} AS mean_z FROM ({duck.table('c_orders', COARSE)})")
def roundtrip_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points out of the container along the Hilbert curve: centres repeated by their counts."""
    spec = container.CodecSpec(chunk_cells=1024, curve="hilbert")
    points = container.decompress(container.compress(clouds.unit(spark, sf_dir, "c_orders"), 0.02, spec, parts=2), 0.02, spec, expand=True)
    return points.agg(F.count(F.lit(1)).alias("n_points"), *[rounded(F.avg(a)).alias(f"mean_{a}") for a in "xyz"])


_SPAN = 2 * (1 << (3 * BITS))
_PARTS = 8


def _owner_sql(cloud: str) -> str:
    return f"SELECT *, floor(key * {_PARTS} / {_SPAN}.0::DOUBLE)::INTEGER AS owner FROM ({keyed_sql(cloud)})"


@registered(f"SELECT owner, count(*) AS cells, sum(n)::BIGINT AS n_points FROM ({_owner_sql('c_corpus')}) GROUP BY owner")
def parts_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells and points of evenly cut key ranges on a skewed cloud."""
    owned = keyed(spark, sf_dir, "c_corpus").withColumn("owner", distribute.prefix_owner(_PARTS, _SPAN))
    return owned.groupBy("owner").agg(F.count(F.lit(1)).alias("cells"), F.sum("n").alias("n_points"))


def _balance_sql(name: str, owned: str) -> str:
    return f"SELECT '{name}' AS splitters, count(*) AS parts, max(c) AS largest, {duck.rounded('max(c) / avg(c)')} AS balance FROM (SELECT owner, count(*) AS c FROM ({owned}) GROUP BY owner)"


_SPLIT = f"SELECT k.*, (SELECT count(*) FROM (SELECT unnest(quantile_cont(key, {[p / _PARTS for p in range(1, _PARTS)]})) AS s FROM ({keyed_sql('c_corpus')})) q WHERE k.key > floor(q.s))::INTEGER AS owner FROM ({keyed_sql('c_corpus')}) k"


@registered(f"{_balance_sql('prefix', _owner_sql('c_corpus'))} UNION ALL {_balance_sql('quantile', _SPLIT)}")
def parts_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest against mean part: even key ranges, and ranges of equal numbers of cells."""
    keys = keyed(spark, sf_dir, "c_corpus")
    split = distribute.exact_splitters(keys, _PARTS)
    both = [("prefix", distribute.prefix_owner(_PARTS, _SPAN)), ("quantile", distribute.splitter_owner(split))]
    parts = [distribute.balance(keys.withColumn("owner", owner)).select(F.lit(name).alias("splitters"), "parts", "largest", rounded(F.col("balance")).alias("balance")) for name, owner in both]
    return parts[0].unionByName(parts[1])


def _raw_box_sql() -> str:
    box = ", ".join(f"min({a}) AS {a}lo, max({a}) AS {a}hi" for a in "xyz")
    at = ", ".join(f"({a} - {a}lo) / greatest(xhi - xlo, yhi - ylo, zhi - zlo) * {duck.number(_RAW)} AS {u}" for a, u in zip("xyz", "uvw", strict=True))
    cells = f"SELECT i, j, k, count(*) AS n FROM ({duck.celled(f'SELECT {at} FROM ({duck.raw("c_linekeys")}), (SELECT {box} FROM ({duck.raw("c_linekeys")}))')}) GROUP BY ALL"
    return f"SELECT {duck.packed(KEYS['morton'])} AS key FROM ({cells})"


_RAW = bcc_factor(1e-3)
_RAW_BITS = 3 * (((int(_RAW) + 4) // 2 - 1).bit_length()) + 1
_RAW_PREFIX = f"SELECT key, floor(key * {_PARTS} / {1 << _RAW_BITS}.0::DOUBLE)::INTEGER AS owner FROM ({_raw_box_sql()})"
_RAW_SPLIT = f"SELECT k.key, (SELECT count(*) FROM (SELECT unnest(quantile_cont(key, {[p / _PARTS for p in range(1, _PARTS)]})) AS s FROM ({_raw_box_sql()})) q WHERE k.key > floor(q.s))::INTEGER AS owner FROM ({_raw_box_sql()}) k"


@registered(f"{_balance_sql('prefix', _RAW_PREFIX)} UNION ALL {_balance_sql('quantile', _RAW_SPLIT)}")
def skewed_box_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same on a box whose sides stay as unequal as the raw axes: even key ranges leave most parts empty."""
    box = clouds.box_of(spark, sf_dir, "c_linekeys")
    side = max(box[f"{a}_hi"] - box[f"{a}_lo"] for a in "xyz")
    at = clouds.load(spark, sf_dir, "c_linekeys").select(*[((F.col(a) - F.lit(box[f"{a}_lo"])) / F.lit(side)).alias(a) for a in "xyz"])
    keys = curves.attach(tables.occupied(at, _RAW), "morton", int(_RAW) + 3)
    both = [("prefix", distribute.prefix_owner(_PARTS, 1 << _RAW_BITS)), ("quantile", distribute.splitter_owner(distribute.exact_splitters(keys, _PARTS)))]
    return tables.stacked([distribute.balance(keys.withColumn("owner", owner)).select(F.lit(name).alias("splitters"), "parts", "largest", rounded(F.col("balance")).alias("balance")) for name, owner in both])


@registered(f"SELECT count(*) AS n_cells, count(*) FILTER (WHERE owners > 1) AS shared FROM (SELECT i, j, k, count(DISTINCT owner) AS owners FROM ({_SPLIT}) GROUP BY i, j, k)")
def parts_disjoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells that two parts of the container hold: none."""
    spec = container.CodecSpec(chunk_cells=64)
    chunks = container.compress(clouds.unit(spark, sf_dir, "c_corpus"), 0.02, spec, parts=4)
    held = container.decompress(chunks, 0.02, spec).withColumn("owner", F.shiftright("chunk", 32))
    return distribute.shared_cells(held)


@registered(f"SELECT (SELECT count(*) FROM (SELECT DISTINCT pid % 8 AS s, i, j, k FROM p)) AS pairs, (SELECT count(*) FROM p) AS points FROM (SELECT 1)".replace(" p)", f" ({duck.celled(duck.at_factor('c_orders', COARSE, keyed=True))}))"))
def shuffle_saving(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(cell, count) pairs that eight slices send, against points."""
    from cloudlattice.functions import quantize

    at = quantize.assign(clouds.unit(spark, sf_dir, "c_orders", keyed=True), COARSE)
    return distribute.shuffle_saving(at, 8)
