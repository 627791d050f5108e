"""Experiments on coded bytes: rate and distortion, ablations, dictionaries, parts, fixed ratios, timings.

These use the byte coders, so they have no SQL form; the streams that they code do.
"""

from __future__ import annotations

import math
import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.functions.lattice import bcc_factor
from cloudlattice.operators import container, metrics
from cloudlattice.operators.container import CodecSpec
from cloudlattice.sources import clouds

QUERIES, ORACLES = {}, {}
NAMES, BOUNDS = ("c_catalog", "c_accounts"), (1e-3, 5e-3, 2e-2)
OURS = {"to_morton": CodecSpec(), "to_hilbert": CodecSpec(curve="hilbert"), "cube_pipeline": CodecSpec(quantizer="cube")}


def registered(f):
    QUERIES[f.__name__] = f
    return f


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def coded(cloud: DataFrame, eb: float, spec: CodecSpec, parts: int = 1) -> DataFrame:
    """One row: sizes of the container and measured distortion."""
    sizes = container.sizes(container.compress(cloud, eb, spec, parts))
    return sizes.crossJoin(metrics.distortion(cloud, container.factor_of(eb, spec), spec.quantizer)).drop("n")  # single rows


@registered
def coded_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """dataset, eb, codec, cr, bpp, psnr, max_rel: this method's variants from bytes as written (``rate_distortion`` has all codecs from code lengths)."""
    parts = []
    for name in NAMES:
        at = clouds.unit(spark, sf_dir, name)
        for eb in BOUNDS:
            for codec, spec in OURS.items():
                parts.append(coded(at, eb, spec).select(F.lit(name).alias("dataset"), F.lit(eb).alias("eb"), F.lit(codec).alias("codec"), "cr", "bpp", "psnr", "max_rel"))
    return union(parts)


@registered
def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One choice changed at a time: lattice, curve, layout, counts, residuals, coder, byte coder."""
    base = {"base": {}, "hilbert": {"curve": "hilbert"}, "row_major": {"curve": "row_major"}, "raw_keys": {"layout": "raw"}, "counts_off": {"rle": "off"}, "counts_on": {"rle": "on"}, "no_residuals": {"delta": False, "entropy": "fixed"}, "exp_golomb": {"entropy": "exp_golomb"}, "auto": {"entropy": "auto"}, "no_byte_coder": {"backend": "none"}, "cube": {"quantizer": "cube"}}
    at = clouds.unit(spark, sf_dir, "c_corpus")
    return union([container.sizes(container.compress(at, 2e-2, CodecSpec(**change), 1)).select(F.lit(name).alias("variant"), "n_points", "n_cells", "bytes_total", "cr", "metadata_share") for name, change in base.items()])


@registered
def metadata_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dictionary bytes in all bytes as the ratio grows, with and without a dictionary."""
    at = clouds.unit(spark, sf_dir, "c_shipping")
    return union([container.sizes(container.compress(at, eb, CodecSpec(entropy=e), 1)).select(F.lit(eb).alias("eb"), F.lit(e).alias("entropy"), "cr", "metadata_share") for eb in (2e-2, 5e-2, 2e-1) for e in ("huffman", "exp_golomb")])


@registered
def ratio_retention(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ratio of 2 to 16 parts against one."""
    at = clouds.unit(spark, sf_dir, "c_shipping")
    rows = union([container.sizes(container.compress(at, 5e-3, CodecSpec(), parts)).select(F.lit(parts).alias("parts"), "cr") for parts in (1, 4, 16)])
    return rows.withColumn("kept", F.col("cr") / F.max(F.when(F.col("parts") == 1, F.col("cr"))).over(Window.partitionBy(F.lit(1))))  # three rows


def eps_for_ratio(cloud: DataFrame, ratio: float, spec: CodecSpec = CodecSpec(), rounds: int = 12) -> tuple[float, float]:
    """The bound whose ratio is nearest to the wanted one, by bisection on its logarithm; (bound, ratio)."""
    low, high, best = math.log(1e-5), math.log(0.3), (0.0, math.inf)
    for _ in range(rounds):
        eb = math.exp((low + high) / 2)
        got = container.sizes(container.compress(cloud, eb, spec, 1)).first()["cr"]
        if abs(math.log(got / ratio)) < abs(math.log(max(best[1], 1e-9) / ratio)) or best[0] == 0.0:
            best = (eb, got)
        low, high = ((low + high) / 2, high) if got < ratio else (low, (low + high) / 2)
    return best


@registered
def coded_fixed_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At a ratio near 20 of bytes as written: the bound, the error, and how unevenly it lies along the axes and the diagonal."""
    rows = []
    at = clouds.unit(spark, sf_dir, "c_catalog")
    for codec, spec in (("to_morton", CodecSpec()), ("cube_pipeline", CodecSpec(quantizer="cube"))):
        eb, cr = eps_for_ratio(at, 20.0, spec, rounds=7)
        factor = container.factor_of(eb, spec)
        e = [(F.col(u) - F.col(c)) / factor for u, c in zip("uvw", quantize.CELL, strict=True)]
        spread = quantize.assign(at, factor, spec.quantizer).agg(*[F.variance(x).alias(a) for x, a in zip(e, "xyz", strict=True)], F.variance((e[0] + e[1] + e[2]) / math.sqrt(3)).alias("d")).first()
        psnr = metrics.distortion(at, factor, spec.quantizer).first()["psnr"]
        rows.append((codec, float(eb), float(cr), float(psnr), float(spread["d"] / (spread["x"] + spread["y"] + spread["z"]) * 3)))
    return spark.createDataFrame(rows, "codec string, eb double, cr double, psnr double, diagonal_to_axis double")


def timed(df: DataFrame) -> float:
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def settled(cloud: DataFrame) -> DataFrame:
    """The cloud as a cached table that later plans scan anew; drop it by ``unpersist``."""
    held = cloud.persist()
    held.count()
    return held


def mean_seconds(make, runs: int) -> float:
    """Mean of runs, each of a plan made anew, so that no cached result of an earlier one is hit."""
    return sum(timed(make()) for _ in range(runs)) / runs


def quantizer_timing(spark: SparkSession, sf_dir: str, name: str = "c_shipping", runs: int = 3) -> list[dict]:
    """Seconds of quantizing and of the whole compression, by lattice, the mean of runs. Only the points are cached."""
    at = settled(clouds.unit(spark, sf_dir, name))
    rows = []
    for shape in ("cube", "bcc"):
        spec = CodecSpec(quantizer=shape)
        factor = container.factor_of(1e-3, spec)
        container.compress(at, 1e-3, spec, 8).write.format("noop").mode("overwrite").save()  # compiles the plan
        rows.append({"quantizer": shape, "quantize_s": mean_seconds(lambda: quantize.assign(at, factor, shape), runs), "total_s": mean_seconds(lambda: container.compress(at, 1e-3, spec, 8), runs)})
    at.unpersist()
    return rows


def throughput(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("c_shipping", "c_orders"), bounds: tuple[float, ...] = (1e-3, 2e-2), runs: int = 2) -> list[dict]:
    """Raw megabytes a second in both directions against bits a point, by cloud, bound and variant. Only points and written bytes are cached."""
    rows = []
    for name in names:
        at = settled(clouds.unit(spark, sf_dir, name))
        mb = at.count() * 12 / 1e6
        for eb in bounds:
            for codec, spec in OURS.items():
                there = mean_seconds(lambda: container.compress(at, eb, spec, 8), runs)
                chunks = settled(container.compress(at, eb, spec, 8))
                back = mean_seconds(lambda: container.decompress(chunks, eb, spec), runs)
                rows.append({"dataset": name, "eb": eb, "codec": codec, "mb": round(mb, 2), "bpp": round(container.sizes(chunks).first()["bpp"], 3), "compress_mb_s": round(mb / there, 2), "decompress_mb_s": round(mb / back, 2)})
                chunks.unpersist()
        at.unpersist()
    return rows


def query_latency(spark: SparkSession, sf_dir: str, path: str, name: str = "c_shipping", eb: float = 1e-3, chunks: tuple[int, ...] = (8, 32)) -> list[dict]:
    """Milliseconds for fifty balls on a written container, by full decoding and by sidecars, with the share that is skipped and the sidecars' share of all bytes."""
    from cloudlattice.operators import region
    from cloudlattice.plans import regions

    cloud = settled(clouds.unit(spark, sf_dir, name))
    factor = bcc_factor(eb)
    cells = container.sizes(container.compress(cloud, eb, CodecSpec(), 8)).first()["n_cells"]
    rows = []
    for count in chunks:
        spec = CodecSpec(chunk_cells=-(-cells // count), entropy="auto")
        where = f"{path}/{name}-{count}"
        container.write(container.compress(cloud, eb, spec, 1), where, eb, spec, {})
        held, _, _, _ = container.read(spark, where)
        share = container.sizes(held).first()["sidecar_share"]
        for radius in (0.02, 0.05, 0.10):
            asked = regions.balls(spark, sf_dir).where(F.col("r") == F.lit(radius * math.sqrt(3))).persist()
            balls = asked.count()
            full = lambda: region.count_full(container.decompress(held, eb, spec).select("i", "j", "k", "n"), asked, factor)  # noqa: B023, E731
            index = lambda: region.count_chunks(held, asked, factor, spec.curve, spec.layout, int(factor) + 3)  # noqa: B023, E731
            same = full().exceptAll(index()).count() == 0
            skip = region.skip_report(held, asked, factor).first()
            full_ms, index_ms = (1000 * mean_seconds(f, 2) / max(balls, 1) for f in (full, index))
            rows.append({"dataset": name, "chunks": held.count(), "radius": radius, "balls": balls, "full_ms": round(full_ms, 2), "index_ms": round(index_ms, 2), "speed_up": round(full_ms / index_ms, 2), "skipped": round(skip["skipped"] / max(skip["pairs"], 1), 3), "sidecar_share": round(share, 5), "equal": same})
            asked.unpersist()
    cloud.unpersist()
    return rows


def scaling(spark: SparkSession, sf_dir: str, name: str = "c_shipping", eb: float = 1e-3, parts: tuple[int, ...] = (1, 2, 4, 8, 16)) -> list[dict]:
    """Seconds of the compression by number of parts on the session's cores, the ratio, and the share of task time spent on the shuffle."""
    at = settled(clouds.unit(spark, sf_dir, name))
    rows = []
    for count in parts:
        make = lambda: container.compress(at, eb, CodecSpec(), count)  # noqa: B023, E731
        timed(make())
        before = shuffle_times(spark)
        seconds = mean_seconds(make, 2)
        run, moved = (b - a for a, b in zip(before, shuffle_times(spark), strict=True))
        rows.append({"cores": spark.sparkContext.defaultParallelism, "parts": count, "seconds": round(seconds, 3), "cr": round(container.sizes(make()).first()["cr"], 4), "shuffle_share": round(moved / max(run, 1), 4)})
    at.unpersist()
    return rows


def shuffle_times(spark: SparkSession) -> tuple[float, float]:
    """Milliseconds of all tasks so far, and of those the ones that wrote or waited for shuffled data."""
    store = spark.sparkContext._jsc.sc().statusStore()
    stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), spark._jvm.java.util.ArrayList())
    run = moved = 0.0
    for k in range(stages.size()):
        s = stages.apply(k)
        run += s.executorRunTime()
        moved += s.shuffleWriteTime() / 1e6 + s.shuffleFetchWaitTime()
    return run, moved


def lossless_storage(spark: SparkSession, sf_dir: str, name: str, path: str) -> list[tuple[str, float]]:
    """Ratio of plain columnar files under general coders."""
    at = clouds.load(spark, sf_dir, name).select(*[F.col(a).cast("float").alias(a) for a in "xyz"])
    points, out = at.count(), []
    for codec in ("zstd", "gzip", "snappy", "lz4"):
        at.write.mode("overwrite").option("compression", codec).parquet(f"{path}/{codec}")
        size = spark.read.format("binaryFile").load(f"{path}/{codec}/*.parquet").agg(F.sum("length")).first()[0]
        out.append((codec, points * 12 / size))
    return out


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shipping cloud by bound: cells, density, error, coded size."""
    at = clouds.unit(spark, sf_dir, "c_shipping")
    parts = []
    for eb in (1e-3, 2e-2):
        sizes = container.sizes(container.compress(at, eb, CodecSpec(), 1))
        parts.append(sizes.crossJoin(metrics.distortion(at, bcc_factor(eb))).select(F.lit(eb).alias("eb"), "n_points", "n_cells", (F.col("n_points") / F.col("n_cells")).alias("rho"), "max_rel", "psnr", "bpp", "cr"))  # single rows
    return union(parts)
