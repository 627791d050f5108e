"""Embedding near-duplicates by an epsilon grid order join.

A cosine of at least ``limit`` is a distance of at most ``eps = sqrt(2 - 2 limit)``
between unit vectors. Vectors are turned to the principal axes of their length, sorted
by label, length and the cells of side ``eps`` on the leading axes, and cut into sequence blocks of
bounded size. Block pairs of one label whose cells on the first two axes are
adjacent and whose bounding boxes are within ``eps`` are joined recursively: both
intervals are halved, pairs of halves that are provably farther apart are skipped,
and what is left is compared in double precision.

Equal vectors of one label are joined as one with its multiplicity. Neighbouring blocks
are held as a group, to which each partner block is sent once. A block pair
returns each vector's number of links and a spanning forest of the links found, so
a group of near copies never turns into all its pairs as rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.graph import Forest, components
from cloudlattice.llm.vectors import by_width, cosine, matrix, norms, participants, widths
from cloudlattice.llm.work import load, partitions_for, written

LIMIT = 0.98
BLOCK = 1024
#: 2^GROUP_BITS neighbouring blocks are held together while their partners pass by.
GROUP_BITS = 4
LEAF = 128
AXES = 8
#: Axes on which the cells of two blocks have to be adjacent.
BOX_AXES = 2
#: Vectors from which the axes are fitted; they steer the order only, never the result.
AXES_SAMPLE = 10_000
BLOCK_SCHEMA = "block long, label int, lo array<double>, hi array<double>, reps binary, copies binary, vectors binary, width int"


def principal_axes(vectors: DataFrame, sample: int = AXES_SAMPLE) -> dict[int, np.ndarray]:
    """Orthonormal axes by falling variance for each vector length, from its vectors of the smallest hash."""
    axes = {}
    for width in widths(vectors):
        rows = vectors.where(F.size("v") == width).select("v").orderBy(F.xxhash64("v")).limit(sample).collect()
        x = np.array([r[0] for r in rows])
        x = x / norms(x)[:, None]
        axes[width] = np.linalg.eigh(np.cov(x.T, bias=True).reshape(width, width))[1][:, ::-1].copy()
    return axes


def box_gap(a: np.ndarray, b: np.ndarray) -> float:
    """Distance between the bounding boxes of two sets of points."""
    gap = np.maximum(0, np.maximum(a.min(0) - b.max(0), b.min(0) - a.max(0)))
    return float(np.sqrt(gap @ gap))


def near(a: np.ndarray, b: np.ndarray, ua: np.ndarray, ub: np.ndarray, eps: float, limit: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs with cosine >= limit: recursive interval join of two sorted sequences.

    a, b: original vectors; ua, ub: unit vectors on the principal axes. ``same``: both are one sequence.
    """
    if same and len(a) < 2:
        return
    if not len(a) or not len(b) or (not same and box_gap(ua, ub) > eps):
        return
    if max(len(a), len(b)) <= LEAF:
        dots = ua @ ub.T
        if same:
            dots[np.tril_indices(len(a))] = -2
        i, j = np.nonzero(dots >= limit - 1e-9)
        if len(i):
            exact = cosine(a[i], b[j]) >= limit
            yield i[exact], j[exact]
        return
    ha, hb = -(-len(a) // 2), -(-len(b) // 2)
    for sa, sb in ((slice(0, ha), slice(0, hb)), (slice(0, ha), slice(hb, None)), (slice(ha, None), slice(0, hb)), (slice(ha, None), slice(hb, None))):
        if same and sa.start > sb.start:
            continue
        for i, j in near(a[sa], b[sb], ua[sa], ub[sb], eps, limit, same and sa == sb):
            yield i + sa.start, j + sb.start


def link_table(vectors: DataFrame, limit: float = LIMIT, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """Links of distinct vectors (columns rep, label, v, copies).

    Returns (rep, links): links to other rows per distinct vector, without its own
    copies; and (u, v): forest edges between reps.
    """
    spark, eps = vectors.sparkSession, math.sqrt(max(0.0, 2 - 2 * limit)) + 1e-6
    axes = principal_axes(vectors)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for width, batch in by_width(whole):
                v = matrix(batch.column("v"))
                unit = v / norms(v)[:, None]
                at = np.floor(unit @ axes[width][:, :AXES] / eps).astype(np.int32)
                at = np.pad(at, ((0, 0), (0, AXES - at.shape[1])))
                yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("label"), batch.column("copies"), batch.column("v"), pa.array(list(at), pa.list_(pa.int32())), pa.array(np.full(len(v), width, np.int32))], ["rep", "label", "copies", "v", "cell", "width"])

    order = ["label", "width", *(F.col("cell")[k] for k in range(AXES)), "rep"]
    ordered = vectors.mapInArrow(cells, "rep long, label int, copies long, v array<double>, cell array<int>, width int")
    ordered = written(ordered, "grid-cells")
    ordered = ordered.repartitionByRange(partitions_for(spark), *order).sortWithinPartitions(*order)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        held: list[tuple] = []

        def row() -> pa.RecordBatch:
            nonlocal number
            reps, copies, v = (np.concatenate([h[k] for h in held]) for k in (1, 2, 3))
            at = (v / norms(v)[:, None]) @ axes[v.shape[1]]
            at = np.pad(at, ((0, 0), (0, max(0, BOX_AXES - at.shape[1]))))
            out = pa.RecordBatch.from_pylist([{"block": number, "label": held[0][0][0], "lo": at.min(0).tolist(), "hi": at.max(0).tolist(), "reps": reps.tobytes(), "copies": copies.tobytes(), "vectors": v.tobytes(), "width": v.shape[1]}], schema)
            number += 1
            held.clear()
            return out

        schema = pa.schema([("block", pa.int64()), ("label", pa.int32()), ("lo", pa.list_(pa.float64())), ("hi", pa.list_(pa.float64())), ("reps", pa.binary()), ("copies", pa.binary()), ("vectors", pa.binary()), ("width", pa.int32())])
        for batch in batches:
            labels, sizes, reps, copies = (batch.column(c).to_numpy() for c in ("label", "width", "rep", "copies"))
            start = 0
            while start < len(labels):
                kind = int(labels[start]), int(sizes[start])
                run = start + int(np.searchsorted(labels[start:], kind[0], "right"))
                run = start + int(np.searchsorted(sizes[start:run], kind[1], "right"))
                if held and held[0][0] != kind:
                    yield row()
                stop = min(run, start + block - sum(len(h[1]) for h in held))
                held.append((kind, reps[start:stop], copies[start:stop], matrix(batch.column("v").slice(start, stop - start))))
                if sum(len(h[1]) for h in held) == block:
                    yield row()
                start = stop
        if held:
            yield row()

    blocks = written(ordered.select("rep", "label", "width", "copies", "v").mapInArrow(cut, BLOCK_SCHEMA), "grid-blocks")
    cell = lambda bound, k, by: F.floor((F.col(bound)[k] + F.lit(by * eps)) / F.lit(eps))

    def spread(df: DataFrame, by: int) -> DataFrame:
        for k in range(BOX_AXES):
            df = df.withColumn(f"c{k}", F.explode(F.sequence(cell("lo", k, -by), cell("hi", k, by))))
        return df

    boxes = blocks.select("block", "label", "width", "lo", "hi")
    other = boxes.withColumnsRenamed({"block": "block_b", "lo": "lo_b", "hi": "hi_b"})
    gap = F.zip_with(F.zip_with("lo", "hi_b", lambda x, y: x - y), F.zip_with("lo_b", "hi", lambda x, y: x - y), lambda x, y: F.greatest(x, y, F.lit(0.0)))
    pairs = (
        spread(boxes, 1).join(spread(other.withColumnsRenamed({"lo_b": "lo", "hi_b": "hi"}), 0).withColumnsRenamed({"lo": "lo_b", "hi": "hi_b"}), ["label", "width", *(f"c{k}" for k in range(BOX_AXES))])
        .where("block <= block_b")
        .where(F.aggregate(gap, F.lit(0.0), lambda s, x: s + x * x) <= F.lit(eps * eps))
        .select(F.col("block").alias("a"), F.col("block_b").alias("b"))
        .distinct()
    )
    # neighbouring blocks share most partners: a group of them holds its own vectors, and each partner is sent to the group once
    payload = ["reps", "copies", "vectors"]
    own = blocks.select(F.shiftright("block", GROUP_BITS).alias("group"), F.lit(0).alias("kind"), "block", *payload, F.array().cast("array<bigint>").alias("partners"))
    asked = pairs.groupBy(F.shiftright("a", GROUP_BITS).alias("group"), F.col("b").alias("block")).agg(F.collect_list("a").alias("partners"))  # at most as many as a group has blocks
    sent = asked.join(blocks.select("block", *payload), "block").select("group", F.lit(1).alias("kind"), "block", *payload, "partners")
    work = own.unionByName(sent).repartition("group").sortWithinPartitions("group", "kind", "block")

    def opened(row: dict) -> tuple[np.ndarray, ...]:
        reps, copies = (np.frombuffer(row[c], np.int64) for c in ("reps", "copies"))
        v = np.frombuffer(row["vectors"]).reshape(len(reps), -1)
        return reps, copies, v, v / norms(v)[:, None] @ axes[v.shape[1]]

    def compared(one: tuple, two: tuple, same: bool) -> pa.RecordBatch | None:
        (ra, ca, a, ua), (rb, cb, b, ub) = one, two
        shift = 0 if same else len(a)
        na, nb, forest, edges = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64), Forest(shift + len(b)), []
        for i, j in near(a, b, ua, ub, eps, limit, same):
            np.add.at(na, i, cb[j])
            np.add.at(nb, j, ca[i])
            edges += [(x, y) for x, y in zip(i.tolist(), j.tolist(), strict=True) if forest.join(x, y + shift)]
        rows = [(x, n, None) for rep, count in ((ra, na), (rb, nb)) for x, n in zip(rep[count > 0].tolist(), count[count > 0].tolist(), strict=True)]
        rows += [(int(ra[x]), 0, int(rb[y])) for x, y in edges]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["rep", "links", "other"]) if rows else None

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, held = None, {}
        for batch in batches:
            for at in range(batch.num_rows):  # a block at a time
                row = batch.slice(at, 1).to_pylist()[0]
                if row["group"] != group:
                    group, held = row["group"], {}
                block = held.get(row["block"]) or opened(row)
                if row["kind"] == 0:
                    held[row["block"]] = block
                for a in row["partners"]:
                    if (out := compared(held[a], block, a == row["block"])) is not None:
                        yield out

    found = written(work.mapInArrow(joined, "rep long, links long, other long"), "grid-links")
    counts = found.where("other is null").groupBy("rep").agg(F.sum("links").alias("links"))
    return counts, found.where("other is not null").select(F.col("rep").alias("u"), F.col("other").alias("v"))


def near_duplicates(table: DataFrame, limit: float = LIMIT) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept.

    Only vectors with one and the same label, not null, and of one length are compared.
    Vectors that are null, zero, or hold null or non-finite components have no links and
    are their own component. Repeated rows count as copies.
    """
    usable = participants(table.where(F.col("label").isNotNull()), "vec_id", F.col("label").cast("int").alias("label"))
    copies = usable.groupBy("label", "v").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    distinct = written(copies, "grid-distinct")
    counts, edges = link_table(distinct, limit)
    member = usable.join(distinct, ["label", "v"]).select("vec_id", "rep", "copies")
    linked = (
        member.join(counts, "rep", "left")
        .join(components(edges).withColumnRenamed("id", "rep"), "rep", "left")
        .select("vec_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
        .groupBy("vec_id")
        .agg(F.max("n_links").alias("n_links"), F.min("component_id").alias("component_id"))
    )
    return table.select("vec_id").join(linked, "vec_id", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id")).withColumn("kept", F.col("vec_id") == F.col("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "embeddings"))
