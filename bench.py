"""Timings of headline queries: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores.

``python bench.py scaling`` prints the compression's times over cores (each in a
process of its own) and parts, ``python bench.py latency`` region counts on a written
container, ``python bench.py throughput`` both directions against bits a point.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import tempfile
import time

from pyspark.sql import SparkSession

HEADLINE = ("bcc_cells", "cell_goldens", "density_gain", "kl_deviation", "curve_hilbert", "delta_stream", "roundtrip_cells", "radius_count_full", "radius_count_index", "radial_profile", "octree_bits", "predictive_entropy", "float_lossless_bits", "stream_cell_counts", "stride_ratios")


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def scaling(sf_dir: str) -> None:
    """Iso-efficiency: seconds on one core over cores times seconds there."""
    rows = []
    for cores in ("1", "2", "4"):
        out = subprocess.run([sys.executable, __file__, "scaling-run"], env=os.environ | {"BENCH_CPUS": cores, "BENCH_SF_DIR": sf_dir}, capture_output=True, text=True, check=True)
        rows += json.loads(out.stdout.strip().splitlines()[-1])
    alone = {r["parts"]: r["seconds"] for r in rows if r["cores"] == 1}
    whole = {(r["cores"], r["parts"]): r["cr"] for r in rows}
    for r in rows:
        print(json.dumps(r | {"efficiency": round(alone[r["parts"]] / (r["cores"] * r["seconds"]), 3), "ratio_kept": round(r["cr"] / whole[r["cores"], 1], 4)}))


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    mode = sys.argv[1] if len(sys.argv) > 1 else "headline"
    if mode == "scaling":
        return scaling(sf_dir)
    spark = session(cpus)
    from cloudlattice.plans import catalogue, workloads

    if mode == "scaling-run":
        return print(json.dumps(workloads.scaling(spark, sf_dir)))
    if mode == "throughput":
        return print(json.dumps(workloads.throughput(spark, sf_dir)))
    if mode == "latency":
        with tempfile.TemporaryDirectory() as path:
            return print(json.dumps([r for name in ("c_catalog", "c_shipping") for r in workloads.query_latency(spark, sf_dir, path, name)]))
    catalogue.QUERIES["bcc_cells"](spark, sf_dir).count()  # starts the engine
    took = {}
    for name in HEADLINE:
        spark.catalog.clearCache()
        start = time.perf_counter()
        catalogue.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - start, 3)
    spark.catalog.clearCache()
    timing = {f"{r['quantizer']}_{k}": round(r[k], 3) for r in workloads.quantizer_timing(spark, sf_dir) for k in ("quantize_s", "total_s")}
    timing["total_ratio"] = round(timing["bcc_total_s"] / timing["cube_total_s"], 3)
    rates = {f"{r['dataset']}_{r['eb']}_{r['codec']}": [r["bpp"], r["compress_mb_s"], r["decompress_mb_s"]] for r in workloads.throughput(spark, sf_dir, ("c_shipping",), (1e-3,))}
    print(json.dumps({"metric": "headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1], "throughput_bpp_compress_decompress_mb_s": rates, "quantizers": timing}))


if __name__ == "__main__":
    main()
