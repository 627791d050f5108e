"""Plain distributed prefix doubling over every byte position: the reference form of ``suffix_dedup``.

Each round brings the ranks at a position and at a growing offset from it together,
sorts the pairs that occur more than once and ranks them anew; a position whose pair is
unique leaves, as no longer string at it can repeat. Six rounds reach the threshold
from strings of eight bytes. It gives the same ranges as ``suffix_dedup.covered``, at the
cost of a row for every byte in the first round (see README), so it serves small tables
and as the check of the faster form.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cloudlattice.llm.suffix_dedup import KEY, LENGTH
from cloudlattice.llm.work import removed, written

FIRST = 8


def positions(docs: DataFrame, length: int) -> DataFrame:
    """KEY, at, rank: the eight bytes from every position as an order-keeping number (columns of KEY, text)."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                doc, mark, data = (batch.column(k)[row].as_py() for k in range(3))
                raw = np.frombuffer(data, np.uint8)
                n = len(raw) - FIRST + 1
                for start in range(0, n, 1 << 16):
                    piece = raw[start : start + (1 << 16) + FIRST - 1]
                    size = len(piece) - FIRST + 1
                    rank = np.zeros(size, np.uint64)
                    for b in range(FIRST):
                        rank = rank << np.uint64(8) | piece[b : b + size].astype(np.uint64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(size, doc)), pa.array(np.full(size, mark, np.int32)), pa.array(np.arange(start, start + size, dtype=np.int32)), pa.array((rank ^ np.uint64(1 << 63)).view(np.int64))], [*KEY, "at", "rank"])

    return docs.where(F.octet_length("text") >= length).select(*KEY, F.col("text").cast("binary")).mapInArrow(task, "doc_id long, text_hash int, at int, rank long")


def reranked(state: DataFrame, offset: int) -> DataFrame:
    """Positions whose pair of ranks, their own and that ``offset`` on, occurs again, with the pair's rank in sorted order."""
    ahead = Window.partitionBy(*KEY, "copy").orderBy("at").rangeBetween(offset, offset)
    pairs = written(state.withColumn("next", F.first("rank").over(ahead)).where("next IS NOT NULL"), "pairs")
    again = pairs.groupBy("rank", "next").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    # key ranges in order, sorted within: the number of a row keeps the order of the strings
    ranks = written(again.repartitionByRange("rank", "next").sortWithinPartitions("rank", "next").withColumn("new", F.monotonically_increasing_id()), "ranks")
    out = written(pairs.join(ranks, ["rank", "next"]).select(*KEY, "copy", "at", F.col("new").alias("rank")), "positions")
    removed(pairs, ranks)
    return out


def covered(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """KEY, start, end of every repeated string of ``length`` bytes (at least 16); repeated rows are copies of one another."""
    # each of several rows of one key keeps its own positions
    own = docs.withColumn("copy", F.row_number().over(Window.partitionBy(*KEY).orderBy(F.lit(0))))
    state = written(_with_copies(own, length), "positions")
    span = FIRST
    while span < length:
        offset = min(span, length - span)
        after = reranked(state, offset)
        removed(state)
        state, span = after, span + offset
    return state.select(*KEY, F.col("at").alias("start"), (F.col("at") + length).alias("end")).distinct()


def _with_copies(docs: DataFrame, length: int) -> DataFrame:
    """Positions of the distinct rows, once for every copy."""
    counts = docs.groupBy(*KEY).agg(F.max("copy").alias("copies"))
    at = positions(docs.where("copy = 1").select(*KEY, "text"), length)
    return at.join(counts, KEY).withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).drop("copies")
