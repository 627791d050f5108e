"""File formats: raw little-endian triples, text tables, and the container as a data source."""

from __future__ import annotations

import json
import os
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from cloudlattice.operators.container import decode_chunk


def read_raw(spark: SparkSession, path: str, kind: str = "<f4") -> DataFrame:
    """x, y, z of files of packed triples; a partition reads whole files in slices of bounded size."""
    step = np.dtype(kind).itemsize * 3

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content"):
                data = content.as_buffer()
                for at in range(0, len(data) // step * step, step << 16):
                    piece = np.frombuffer(data, np.uint8)[at : min(at + (step << 16), len(data) // step * step)].view(kind).reshape(-1, 3).astype(np.float64)
                    yield pa.RecordBatch.from_arrays([pa.array(piece[:, a]) for a in range(3)], ["x", "y", "z"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(task, "x double, y double, z double")


def read_table(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a stated schema: nothing is inferred."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).format(form).load(path)


class CellSource(DataSource):
    """``spark.read.format("cloudlattice").option("path", ...)``: keys and counts of a written container."""

    @classmethod
    def name(cls) -> str:
        return "cloudlattice"

    def schema(self) -> str:
        return "chunk long, key long, n long"

    def reader(self, schema) -> DataSourceReader:
        return CellReader(self.options["path"])

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return ChunkWriter(self.options, schema.names)


class CellReader(DataSourceReader):
    """Chunks decode as the container's manifest says."""

    def __init__(self, path: str):
        import glob

        self.path = path
        with open(sorted(glob.glob(f"{path}/manifest/part-*"))[0], encoding="utf-8") as held:
            self.manifest = json.loads(held.readline())

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds

        return [InputPartition(f) for f in sorted(ds.dataset(f"{self.path}/chunks", format="parquet", partitioning="hive").files)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq

        delta = self.manifest.get("delta", True)
        with pq.ParquetFile(partition.value) as held:
            for batch in held.iter_batches(16):
                for row in batch.to_pylist():
                    key, n = decode_chunk(row, delta)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), row["chunk"])), pa.array(key), pa.array(n)], ["chunk", "key", "n"])


@dataclass
class Written(WriterCommitMessage):
    """A part file that a task has finished, still under its temporary name."""

    waiting: str
    final: str


class ChunkWriter(DataSourceArrowWriter):
    """Container rows as part files by ``df.write.format("cloudlattice").option("path", ...).option("manifest", json)``.

    A task writes a file under a name that readers skip; the files get their names and the
    manifest is written when all tasks have committed, so a failed job leaves nothing to read.
    """

    def __init__(self, options: dict, names: list[str]):
        if "manifest" not in options:
            raise ValueError("option manifest: the container's specification as JSON")
        self.path, self.manifest, self.names = options["path"], options["manifest"], names

    def write(self, batches: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        import uuid

        import pyarrow.parquet as pq
        from pyspark import TaskContext

        folder = f"{self.path}/chunks/part={TaskContext.get().partitionId()}"
        name = uuid.uuid4().hex
        waiting, out = f"{folder}/_{name}", None
        os.makedirs(folder, exist_ok=True)
        for batch in batches:
            held = pa.Table.from_batches([batch])
            held = held.drop_columns(["part"]) if "part" in held.column_names else held
            out = out or pq.ParquetWriter(waiting, held.schema, compression="none")
            out.write_table(held)
        if out is None:
            return Written("", "")
        out.close()
        return Written(waiting, f"{folder}/{name}.parquet")

    def commit(self, messages: list) -> None:
        for m in messages:
            if m and m.waiting:
                os.replace(m.waiting, m.final)
        os.makedirs(f"{self.path}/manifest", exist_ok=True)
        with open(f"{self.path}/manifest/part-0.txt", "w", encoding="utf-8") as held:
            held.write(self.manifest)

    def abort(self, messages: list) -> None:
        for m in messages:
            if m and m.waiting and os.path.exists(m.waiting):
                os.remove(m.waiting)
