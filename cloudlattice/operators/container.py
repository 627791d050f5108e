"""The compressed container: one self-contained row a chunk, with a sidecar box."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cloudlattice.functions import curves, quantize
from cloudlattice.functions.lattice import LatticeSpec, bcc_factor
from cloudlattice.operators import cells as tables
from cloudlattice.operators.coding import Stream, squeeze, unsqueeze
from cloudlattice.operators.distribute import sample_splitters, splitter_owner

CHUNK_CELLS = 262_144
SIDECAR_BYTES = 28
#: Parts that sampled splitters are looked up for by comparison.
MOST_SPLIT = 64
FIELDS = "part int, chunk long, key_first long, key_last long, n_points long, n_cells long, lo_i int, lo_j int, lo_k int, hi_i int, hi_j int, hi_k int, rle boolean, entropy string, bytes_backend string, cell_blob binary, count_blob binary, order_blob binary, sz_dict long, sz_cell long, sz_count long, sz_header long"
NAMES = [f.split()[0] for f in FIELDS.split(", ")]


@dataclass(frozen=True)
class CodecSpec:
    curve: str = "morton"
    layout: str = "packed"
    rle: str = "auto"
    entropy: str = "huffman"
    backend: str = "zstd"
    chunk_cells: int = CHUNK_CELLS
    quantizer: str = "bcc"
    delta: bool = True
    keep_order: bool = False


PRESETS = {"default": CodecSpec(), "compact": CodecSpec(curve="hilbert")}
#: Fixed bytes of a row besides blobs and box: keys, totals, flags.
HEADER = 8 * 4 + 4


def encode_chunk(key: np.ndarray, n: np.ndarray, cell: np.ndarray, spec: CodecSpec, rle: bool, pid: np.ndarray | None = None) -> dict:
    """One row from sorted keys, counts and cells (3, chunk); with ``pid``, from a row for each point."""
    order = None
    if pid is not None:
        order = squeeze(Stream.encode(zigzag(np.diff(pid, prepend=0)), "auto").bytes(), spec.backend)
        key, first, n = np.unique(key, return_index=True, return_counts=True)
        cell = cell[:, first]
    seq = key if rle else np.repeat(key, n)
    stream = Stream.encode(np.diff(seq, prepend=seq[:1]) if spec.delta else seq - seq[0], spec.entropy)
    counts = Stream.encode(n - 1, spec.entropy) if rle else None
    blob = squeeze(stream.bytes(), spec.backend)
    count_blob = squeeze(counts.bytes(), spec.backend) if counts else None
    lo, hi = cell.min(1), cell.max(1)
    return {
        "key_first": int(key[0]), "key_last": int(key[-1]), "n_points": int(n.sum()), "n_cells": len(key),
        "lo_i": int(lo[0]), "lo_j": int(lo[1]), "lo_k": int(lo[2]), "hi_i": int(hi[0]), "hi_j": int(hi[1]), "hi_k": int(hi[2]),
        "rle": rle, "entropy": stream.kind, "bytes_backend": spec.backend, "cell_blob": blob, "count_blob": count_blob, "order_blob": order,
        "sz_dict": len(stream.head) + (len(counts.head) if counts else 0), "sz_cell": len(blob), "sz_count": len(count_blob or b""), "sz_header": HEADER + SIDECAR_BYTES + len(order or b""),
    }


def decode_chunk(row: dict, delta: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys and counts."""
    n = row["n_cells"] if row["rle"] else row["n_points"]
    values = Stream.decode(unsqueeze(row["cell_blob"]), n)
    seq = row["key_first"] + (np.cumsum(values) if delta else values)
    if row["rle"]:
        return seq, Stream.decode(unsqueeze(row["count_blob"]), n) + 1
    return np.unique(seq, return_counts=True)


def zigzag(x: np.ndarray) -> np.ndarray:
    """Signed numbers as 0, -1, 1, -2, 2 in turn."""
    return np.where(x >= 0, 2 * x, -2 * x - 1)


def decode_order(row: dict) -> np.ndarray:
    """Ids of the points of a chunk, cell by cell."""
    values = Stream.decode(unsqueeze(row["order_blob"]), row["n_points"])
    return np.cumsum(np.where(values & 1, -(values >> 1) - 1, values >> 1))


def wants_rle(n: np.ndarray, mode: str) -> bool:
    """``auto``: on for a chunk with at least 1.3 points to a cell."""
    return bool(n.sum() >= 1.3 * len(n)) if mode == "auto" else mode == "on"


def encode(keyed: DataFrame, spec: CodecSpec, parts: int = 1, splitters: list[int] | None = None) -> DataFrame:
    """Chunks of a table of key, i, j, k, n: sorted key ranges, one part each, encoded where they lie.

    ``splitters`` cut the keys into ``parts`` ranges; without them the engine finds some, which runs the table's plan twice.

    With ``keep_order`` the table has a row for each point, and its pid; a cell may then go on in the next chunk.
    """
    columns = ["key", "i", "j", "k", "n"] + ["pid"] * spec.keep_order
    dealt = keyed.select(columns)
    dealt = dealt.repartitionByRange(parts, "key") if splitters is None else dealt.repartitionById(parts, splitter_owner(splitters))
    ranged = dealt.sortWithinPartitions("key", *["pid"] * spec.keep_order)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, held, size = TaskContext.get().partitionId(), 0, [], 0

        def row() -> pa.RecordBatch:
            nonlocal number
            key, i, j, k, n, *pid = (np.concatenate([h[c] for h in held]) for c in range(len(columns)))
            made = {"part": part, "chunk": (part << 32) + number, **encode_chunk(key, n, np.stack([i, j, k]), spec, spec.keep_order or wants_rle(n, spec.rle), *pid)}
            number += 1
            return pa.RecordBatch.from_pylist([made], schema)

        for batch in batches:
            got = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            at = 0
            while at < len(got[0]):
                take = min(spec.chunk_cells - size, len(got[0]) - at)
                held.append([c[at : at + take] for c in got])
                size, at = size + take, at + take
                if size == spec.chunk_cells:
                    yield row()
                    held, size = [], 0
        if size:
            yield row()

    kinds = {"int": pa.int32(), "long": pa.int64(), "boolean": pa.bool_(), "string": pa.string(), "binary": pa.binary()}
    schema = pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in FIELDS.split(", ")])
    return ranged.mapInArrow(task, FIELDS)


def decode(chunks: DataFrame, curve: str, layout: str, extent: int, delta: bool = True, order: bool = False) -> DataFrame:
    """chunk, key, i, j, k, n of every cell, or with ``order`` a row and pid for every point.

    No shuffle, as chunks stand alone. Rows come in slices of bounded size.
    """
    names = ["chunk", "key", "i", "j", "k", "n"] + ["pid"] * order
    wanted = ["chunk", "key_first", "n_points", "n_cells", "rle", "cell_blob", "count_blob"] + ["order_blob"] * order
    side = extent if layout == "raw" else (extent + 1) // 2

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):  # a chunk at a time
                row = batch.slice(at, 1).to_pylist()[0]
                key, n = decode_chunk(row, delta)
                cell = curves.cells_numpy(key if layout == "raw" else key >> 1, curve, side)
                if layout != "raw":
                    cell = [c * 2 + (key & 1) for c in cell]
                columns = [np.full(len(key), row["chunk"]), key, *cell, n]
                if order:
                    columns = [*(np.repeat(c, n) for c in columns[:5]), np.ones(int(n.sum()), np.int64), decode_order(row)]
                for start in range(0, len(columns[0]), 65_536):
                    yield pa.RecordBatch.from_arrays([pa.array(c[start : start + 65_536]) for c in columns], names)

    return chunks.select(*wanted).mapInArrow(task, ", ".join(f"{c} long" for c in names))


def part_count(cloud: DataFrame) -> int:
    """As many parts as the session shuffles into."""
    return int(cloud.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def compress(cloud: DataFrame, eb: float, spec: CodecSpec = CodecSpec(), parts: int | None = None, share: float = 0.05) -> DataFrame:
    """Container rows of a cloud on the unit cube: combine points to cells, key, deal out by key range, encode.

    Without ``parts`` there are as many as the session's shuffle partitions. Up to ``MOST_SPLIT`` parts are cut
    at keys of a sample of ``share`` of the points, which costs a scan but no shuffle; the engine's range exchange cuts more.
    """
    factor, parts = factor_of(eb, spec), parts or part_count(cloud)
    extent = int(factor) + 3
    layout = spec.layout if spec.quantizer == "bcc" else "raw"
    with_keys = lambda cells: curves.attach(cells, spec.curve, extent, layout, udf=spec.curve == "hilbert")
    points = quantize.assign(cloud, factor, spec.quantizer).select(*quantize.CELL, F.lit(1).cast("long").alias("n"), *["pid"] * spec.keep_order)
    splitters = None
    if parts <= MOST_SPLIT:
        splitters = sample_splitters(with_keys(points.select(*quantize.CELL)), parts, share) if parts > 1 else []
    return encode(with_keys(points if spec.keep_order else tables.occupied(cloud, factor, spec.quantizer)), spec, parts, splitters)


def factor_of(eb: float, spec: CodecSpec) -> float:
    return bcc_factor(eb) if spec.quantizer == "bcc" else LatticeSpec.from_rel(eb, shape=spec.quantizer).factor


def decompress(chunks: DataFrame, eb: float, spec: CodecSpec = CodecSpec(), expand: bool = False) -> DataFrame:
    """Cells with counts and centres x, y, z on the unit cube; ``expand`` repeats centres by their counts.

    A container that keeps the order gives a row for every point, with its pid.
    """
    factor = factor_of(eb, spec)
    layout = spec.layout if spec.quantizer == "bcc" else "raw"
    cells = decode(chunks, spec.curve, layout, int(factor) + 3, spec.delta, spec.keep_order)
    if expand and not spec.keep_order:
        cells = tables.expand(cells.select("i", "j", "k", "n"))
    return cells.withColumns({a: F.col(c) / F.lit(factor) for a, c in zip("xyz", quantize.CELL, strict=True)})


def sizes(chunks: DataFrame) -> DataFrame:
    """Bytes by kind, compression ratio against raw points, bits a point, and the share of dictionaries."""
    total = F.sum(F.col("sz_cell") + F.col("sz_count") + F.col("sz_header"))
    sums = chunks.agg(F.sum("n_points").alias("n_points"), F.sum("n_cells").alias("n_cells"), F.sum("sz_cell").alias("bytes_cell"), F.sum("sz_count").alias("bytes_count"), F.sum("sz_dict").alias("bytes_dict"), (F.count(F.lit(1)) * SIDECAR_BYTES).alias("bytes_sidecar"), total.alias("bytes_total"))
    return sums.withColumns({"cr": F.col("n_points") * 12 / F.col("bytes_total"), "bpp": F.col("bytes_total") * 8 / F.col("n_points"), "metadata_share": F.col("bytes_dict") / F.col("bytes_total"), "sidecar_share": F.col("bytes_sidecar") / F.col("bytes_total")})


def write(chunks: DataFrame, path: str, eb: float, spec: CodecSpec, box: dict) -> None:
    """Part files by key range, then the manifest as one JSON row."""
    chunks.write.mode("overwrite").option("compression", "none").partitionBy("part").parquet(f"{path}/chunks")
    manifest = {"version": 1, "eb": eb, "box": box, **asdict(spec)}
    chunks.sparkSession.createDataFrame([(json.dumps(manifest),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def read(spark, path: str) -> tuple[DataFrame, float, CodecSpec, dict]:
    held = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    spec = CodecSpec(**{k: held[k] for k in CodecSpec.__dataclass_fields__})
    return spark.read.parquet(f"{path}/chunks").select(*NAMES), held["eb"], spec, held["box"]
