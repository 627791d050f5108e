"""Exact removal of byte strings that repeat, by distributed prefix doubling over suffixes.

Plain doubling ranks every suffix position in every round, which no corpus of
this size can afford. Here positions are kept as runs: neighbouring windows of
``length`` bytes share an anchor, a ``K``-byte string chosen by the window's content
alone (see ``suffix_runs``), so equal windows are compared only with windows of the
same anchor at the same offset from it. The anchor is the first rank of its run.

Each round ranks longer strings than the last, from pairs of the run's rank and
the string around the anchor that all windows of a part of the run have in common:
16 bytes, then 337, 393 and 400, while the parts shrink from whole runs to 64, 8
and 1 positions. Equal rank pairs are brought together by a Spark aggregation
and counted. A part whose rank is unique leaves, for a longer string can't be shared
either; a part whose windows are all shared by another is covered and leaves too (but
for one witness);
the rest goes to the next round, until the string has reached the threshold.

Hot groups: copies of a passage meet in counts that are aggregated before the
shuffle and in joins that the engine may split; no task gathers a group.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.shingles import CASED, word_hashes
from cloudlattice.llm.suffix_runs import K, digests, runs
from cloudlattice.llm.work import load, removed, written

LENGTH = 400
#: Bytes of a word's hash, where passages are counted in words.
UNIT = 4
#: Positions in a part, round by round; every size divides the one before.
PARTS = (64, 8, 1)
BATCH_BYTES = 4 << 20
KEY = ["doc_id", "text_hash"]


def identity() -> tuple:
    """The id, or a hash of the text where there is none, and another hash of the text, which keeps repeated ids with different texts apart."""
    return F.coalesce(F.col("doc_id").cast("long"), F.xxhash64("text")), F.hash("text")


def keyed(docs: DataFrame) -> DataFrame:
    own, mark = identity()
    return docs.select(own.alias("doc_id"), mark.alias("text_hash"), "text")


def _arrays(names: list[str], columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns], names)


def whole(texts: list[bytes]) -> list[bytes]:
    return texts


def spelled(texts: list[bytes]) -> list[bytes]:
    """Texts with ``UNIT`` bytes of a hash for each word and nothing for white space."""
    word, start = word_hashes(np.frombuffer(b"\n".join(texts) + b"\n", np.uint8), CASED)
    after = np.cumsum([len(x) + 1 for x in texts])
    codes = (word >> np.uint64(64 - 8 * UNIT)).astype("<u4")
    return [x.tobytes() for x in np.split(codes, np.searchsorted(start, after[:-1]))]


def in_bytes(data: bytes, found: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Byte ranges of the words that ranges of ``spelled`` hold whole, each with the white space after it."""
    place = np.append(word_hashes(np.frombuffer(data, np.uint8), CASED)[1], len(data))
    return [(int(place[-(-start // UNIT)]), int(place[end // UNIT])) for start, end in found]


def anchored(docs: DataFrame, length: int, view: Callable = whole, least: int | None = None) -> DataFrame:
    """Runs of all texts: key, first start, number of starts, place of the anchor after it, hashes of anchor and span.

    Places are those of ``view(texts)``; a text of under ``least`` bytes has no window there.
    """
    names = [*KEY, "first", "starts", "back", "anchor", "span"]

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, marks, texts = (batch.column(k).to_pylist() for k in range(3))
            at = 0
            while at < len(texts):
                data, held = [], 0
                stop = at
                while stop < len(texts) and (held < BATCH_BYTES or stop == at):
                    data.append(texts[stop])
                    held += len(data[-1])
                    stop += 1
                data = view(data)
                long = np.flatnonzero([len(x) >= length for x in data])
                data = [data[k] for k in long.tolist()]
                ends = np.cumsum([len(x) for x in data])
                joined = b"".join(data)
                first, count, place = runs(np.frombuffer(joined, np.uint8), ends, length)
                if len(first):
                    text = np.searchsorted(ends, first, "right")
                    start = np.concatenate([[0], ends[:-1]])[text]
                    anchor = digests(joined, place, np.full(len(place), K))[:, 0]
                    span = digests(joined, first, count + length - 1)[:, 0]
                    yield _arrays(names, [np.array(ids[at:stop], np.int64)[long[text]], np.array(marks[at:stop], np.int32)[long[text]], (first - start).astype(np.int32), count.astype(np.int32), (place - first).astype(np.int32), anchor, span])
                at = stop

    texts = docs.where(F.octet_length("text") >= (least or length)).withColumn("text", F.col("text").cast("binary"))
    return texts.mapInArrow(task, "doc_id long, text_hash int, first int, starts int, back int, anchor long, span long")


def contents(docs: DataFrame, edges: DataFrame, length: int, view: Callable = whole) -> DataFrame:
    """The bytes that the windows of each undecided run cover."""
    per_doc = edges.groupBy(*KEY).agg(F.collect_list(F.struct("first", "starts", "back", "anchor", "weight")).alias("runs"))  # as many as the text is long
    names = [*KEY, "first", "starts", "back", "anchor", "weight", "bytes"]

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in names]
            held = 0
            for doc, mark, text, found in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                data = view([text])[0]
                for r in found:
                    row = (doc, mark, r["first"], r["starts"], r["back"], r["anchor"], r["weight"], data[r["first"] : r["first"] + r["starts"] + length - 1])
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
                    held += len(row[-1])
                if held > BATCH_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names)
                    out, held = [[] for _ in names], 0
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names)

    types = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary()]
    return docs.join(per_doc, KEY).select(*KEY, F.col("text").cast("binary"), "runs").mapInArrow(task, "doc_id long, text_hash int, first int, starts int, back int, anchor long, weight int, bytes binary")


def parts(undecided: DataFrame, size: int, length: int) -> DataFrame:
    """Parts of undecided runs: a part holds the windows whose anchor is ``part * size`` to ``part * size + size - 1`` bytes in.

    rank: hash of what all windows of the whole part have in common. near, far: the
    run's windows in the part. s1, s2: hash of the bytes that those windows cover.
    """
    names = [*KEY, "first", "back", "anchor", "part", "near", "far", "rank", "s1", "s2", "weight", "bytes"]
    types = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()]

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in names]
            for doc, mark, first, starts, back, anchor, weight, data in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
                view = memoryview(data)
                for part in range((back - starts + 1) // size, back // size + 1):
                    low, high = part * size, part * size + size - 1
                    near, far = max(low, back - starts + 1), min(high, back)
                    rank = xxhash.xxh3_64_intdigest(view[back - low : back - high + length])
                    window = view[back - far : back - near + length]
                    s = xxhash.xxh3_128_digest(window)
                    row = (doc, mark, first + back - far, far, anchor, part, near, far, rank - (1 << 64) if rank >> 63 else rank, int.from_bytes(s[:8], "little", signed=True), int.from_bytes(s[8:], "little", signed=True), weight, bytes(window))
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
                if len(out[0]) > 8192:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names)
                    out = [[] for _ in names]
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names)

    schema = "doc_id long, text_hash int, first int, back int, anchor long, part int, near int, far int, rank long, s1 long, s2 long, weight int, bytes binary"
    return undecided.select(*KEY, "first", "starts", "back", "anchor", "weight", "bytes").mapInArrow(task, schema)


def counted(rows: DataFrame, rank: list[str], span: list[str]) -> DataFrame:
    """Rank and span of rows, with ``n`` (rows of equal span), ``witness`` (one of them) and ``open``.

    ``open``: some row of the rank has a span of its own, and other rows share the rank.
    A row that already counts as repeated has weight 2.
    """
    where = F.struct(*KEY, "first")
    spans = rows.groupBy(*rank, *span).agg(F.sum("weight").alias("n"), F.min(where).alias("witness"))
    ranks = spans.groupBy(*rank).agg(((F.sum("n") > 1) & (F.min("n") == 1)).alias("open"), (F.max("n") > 1).alias("any"))
    return spans.join(ranks.where("open or any").drop("any"), rank)


def covered(docs: DataFrame, length: int = LENGTH, view: Callable = whole, least: int | None = None) -> DataFrame:
    """Key, start and end of byte ranges of ``view(texts)``, overlapping, that together are all bytes of repeated windows.

    A part that is covered stays in later rounds as one witness row while parts of
    the same rank are undecided, so that their windows can still be found equal to its.
    """
    forward = (F.col("n") == 1) | (F.struct(*KEY, "first") == F.col("witness"))
    weight = F.when(F.col("n") == 1, 1).otherwise(2).alias("weight")
    rows = written(anchored(docs, length, view, least), "runs")
    known = written(counted(rows.withColumn("weight", F.lit(1)), ["anchor"], ["span"]), "spans")
    met = written(rows.join(known, ["anchor", "span"]).where("open or n > 1").select(*KEY, "first", "starts", "back", "anchor", F.col("n") > 1, forward & F.col("open"), weight), "met")
    met = met.toDF(*KEY, "first", "starts", "back", "anchor", "whole", "forward", "weight")
    ranges = [met.where("whole").select(*KEY, F.col("first").alias("start"), (F.col("first") + F.col("starts") - 1 + length).alias("end"))]
    removed(rows, known)
    undecided = written(contents(docs, met.where("forward"), length, view), "undecided")
    for size in PARTS:
        made = written(parts(undecided, size, length), "parts")
        rank, span = ["anchor", "part", "rank"], ["near", "far", "s1", "s2"]
        found = written(counted(made.select(*rank, *span, *KEY, "first", "weight"), rank, span), "ranks")
        state = made.join(found, [*rank, *span])
        ranges.append(written(state.where("n > 1 and weight = 1").select(*KEY, F.col("first").alias("start"), (F.col("first") + F.col("far") - F.col("near") + length).alias("end")), "ranges"))
        removed(undecided)
        if size > 1:
            undecided = written(state.where(F.col("open") & forward).select(*KEY, "first", (F.col("far") - F.col("near") + 1).alias("starts"), "back", "anchor", weight, "bytes"), "undecided")
        removed(made, found)
    out = ranges[0]
    for more in ranges[1:]:
        out = out.unionByName(more)
    return out


def repeated_words(docs: DataFrame, words: int) -> DataFrame:
    """Key, start and end of ranges of ``spelled`` texts: all passages of ``words`` words that start anywhere else too.

    The words decide, not the white space between them. A window that starts inside a word's hash
    repeats only beside one that starts at a word, but for a chance of 2^-32.
    """
    return covered(docs, words * UNIT, spelled, 2 * words - 1)


def merged(found: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for start, end in sorted(found):
        if out and start <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]))
        else:
            out.append((start, end))
    return out


def remaining(data: bytes, spans: list[tuple[int, int]]) -> bytes:
    at, kept = 0, []
    for start, end in spans:
        kept.append(data[at:start])
        at = end
    return b"".join([*kept, data[at:]])


def with_ranges(docs: DataFrame, length: int = LENGTH, name: str = "ranges") -> DataFrame:
    """The input's rows and columns with ``name``, an array of (start, end), null where nothing repeats.

    Texts are UTF-8 bytes; null is empty. A text of under ``length`` bytes has nothing to
    remove. Repeated rows are copies of one another. Long texts are read in pieces of
    bounded size. A row without an id is compared and cut like any other. An empty table
    gives an empty result; an input column called ``name`` is replaced.
    """
    return joined_ranges(docs, covered(keyed(docs), length), name)


def joined_ranges(docs: DataFrame, found: DataFrame, name: str) -> DataFrame:
    """``docs`` with the ranges of ``found`` (its columns but the key) as an array."""
    per_doc = found.distinct().groupBy(*KEY).agg(F.collect_list(F.struct(*[c for c in found.columns if c not in KEY])).alias(name))  # as many as the text is long
    own, mark = identity()
    marked = docs.drop(name).withColumn("_dedup_hash", mark).withColumn("_dedup_id", own)
    keys = ["_dedup_id", "_dedup_hash"]
    return marked.join(per_doc.toDF(*keys, name), keys, "left").drop(*keys)


def deduplicated(docs: DataFrame, length: int = LENGTH, words: int | None = None) -> DataFrame:
    """The documents without the repeated bytes; what is left of a cut character goes too, n_chars follows.

    With ``words``, passages of so many words that start anywhere else too go as well, however few bytes they have.
    """

    def left(text: str, ranges: list) -> str:
        data = text.encode()
        spans = [(x["start"], x["end"]) for x in ranges if not x["in_words"]]
        told = [(x["start"], x["end"]) for x in ranges if x["in_words"]]
        return remaining(data, merged([*spans, *(in_bytes(data, told) if told else [])])).decode("utf-8", "ignore")

    @F.pandas_udf("string")
    def kept(texts, ranges):
        import pandas as pd

        return pd.Series([t if r is None else left(t, r) for t, r in zip(texts, ranges, strict=True)], dtype=object)

    found = covered(keyed(docs), length).withColumn("in_words", F.lit(False))
    if words:
        found = found.unionByName(repeated_words(keyed(docs), words).withColumn("in_words", F.lit(True)))
    gone = F.col("_dedup_ranges")
    out = joined_ranges(docs, found, "_dedup_ranges").withColumn("text", F.when(gone.isNull(), F.col("text")).otherwise(kept("text", gone)))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(gone.isNull(), F.col("n_chars")).otherwise(F.char_length("text").cast(docs.schema["n_chars"].dataType)))
    return out.select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, text, ranges in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                data, spans = (text or "").encode(), merged([(r["start"], r["end"]) for r in ranges or []])
                left = remaining(data, spans)
                rows.append((doc, len(data), len(data) - len(left), len(spans), hashlib.sha256(left).hexdigest()))
            if rows:
                columns = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in columns[:4]), pa.array(columns[4], pa.string())], names)

    docs = with_ranges(load(spark, sf_dir, "documents").select("doc_id", "text"))
    return docs.select("doc_id", "text", "ranges").mapInArrow(digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
