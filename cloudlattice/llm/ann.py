"""Nearest neighbours by score-aware product quantisation.

Unit vectors are cut into subspaces of ``SUB`` dimensions with 16 codewords each. The
loss of a codeword penalises the part of the residual along the vector more than
the part across it, because for large inner products only the first changes the
score. Codes of four bits are scanned with look-up tables, two subspaces to a
table of 256 entries. The best ``SHORTLIST`` guesses of a scan are scored on the
vectors, which gives a score that the block surely reaches; every row whose guess
does not prove it to be below that score is then reranked, so no number of copies
or near copies cuts the answer.

A row keeps how long the parts of its residual along and across its vector are.
For a score of s the guess is at least ``s (1 - along) - sqrt(1 - s^2) across``, by
splitting the query into the parts along and across the vector.

A codebook is fitted on a bounded sample for each vector length; every row is
indexed. Queries and rows of one length meet in blocks: a query block and a row
block make one scan.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType

from cloudlattice.llm.vectors import by_width, cosine, matrix, norms, participants, widths
from cloudlattice.llm.work import load, partitions_for, written

SUB = 2
WORDS = 16
THRESHOLD = 0.2
FIT_ROWS = 10_000
ROUNDS = 8
ROW_BLOCK = 16_384
QUERY_BLOCK = 512
#: Rows of a block scored first; it steers the work only, never the result.
SHORTLIST = 320
TOP = 5


def parallel_weight(width: int, threshold: float = THRESHOLD) -> float:
    """Weight of the squared parallel residual when that of the orthogonal one is 1."""
    return max(1.0, (width - 1) * threshold**2 / (1 - threshold**2))


class Quantiser:
    """Codebooks (subspaces, 16, SUB) for unit vectors."""

    def __init__(self, books: np.ndarray, width: int, weight: float):
        self.books, self.width, self.weight = books, width, weight

    @staticmethod
    def cut(x: np.ndarray) -> np.ndarray:
        """(rows, subspaces, SUB), zero-padded to an even number of subspaces."""
        short = -x.shape[1] % (2 * SUB)
        return np.pad(x, ((0, 0), (0, short))).reshape(len(x), -1, SUB)

    def encode(self, x: np.ndarray, passes: int = 2, start: np.ndarray | None = None) -> np.ndarray:
        """Codes by coordinate descent on the loss, subspace after subspace."""
        parts, rows = self.cut(x), np.arange(len(x))
        extra = self.weight - 1
        if start is None:
            start = np.stack([((parts[:, s, None] - self.books[s]) ** 2).sum(2).argmin(1) for s in range(parts.shape[1])], 1)
        codes = start.copy()
        along = np.einsum("nsk,nsk->ns", parts, parts - self.books[np.arange(parts.shape[1]), codes])
        total = along.sum(1)
        for _ in range(passes):
            for s in range(parts.shape[1]):
                rest = total - along[:, s]
                left = parts[:, s, None] - self.books[s]
                mine = (left * parts[:, s, None]).sum(2)
                codes[:, s] = ((left**2).sum(2) + extra * (rest[:, None] + mine) ** 2).argmin(1)
                along[:, s] = mine[rows, codes[:, s]]
                total = rest + along[:, s]
        return codes.astype(np.uint8)

    @classmethod
    def fit(cls, x: np.ndarray, rounds: int = ROUNDS, seed: int = 3) -> Quantiser:
        parts = cls.cut(x)
        rng = np.random.default_rng(seed)
        pick = rng.choice(len(x), WORDS, replace=len(x) < WORDS)
        books = np.stack([parts[pick, s] + rng.normal(0, 1e-6, (WORDS, SUB)) for s in range(parts.shape[1])])
        self = cls(books, x.shape[1], parallel_weight(x.shape[1]))
        extra, codes = self.weight - 1, None
        for _ in range(rounds):
            codes = self.encode(x, 1, codes)
            along = np.einsum("nsk,nsk->ns", parts, parts - self.books[np.arange(parts.shape[1]), codes])
            total = along.sum(1)
            for s in range(parts.shape[1]):
                rest, p = total - along[:, s], parts[:, s]
                target = p * (1 + extra * (rest + (p**2).sum(1)))[:, None]
                for w in range(WORDS):
                    at = codes[:, s] == w
                    if at.any():
                        q = p[at]
                        self.books[s, w] = np.linalg.solve(at.sum() * np.eye(SUB) + extra * q.T @ q, target[at].sum(0))
                along[:, s] = (p * (p - self.books[s][codes[:, s]])).sum(1)
                total = rest + along[:, s]
        return self

    def residuals(self, x: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each row: the residual's part along the vector, signed, and the length of its part across."""
        e = x - self.books[np.arange(codes.shape[1]), codes].reshape(len(x), -1)[:, : self.width]
        along = np.einsum("ij,ij->i", x, e)
        return along, norms(e - along[:, None] * x)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """(queries, pairs, 256): inner products of a query with both codewords of a byte."""
        each = np.einsum("qsk,swk->qsw", self.cut(q), self.books)
        return (each[:, 0::2, None, :] + each[:, 1::2, :, None]).reshape(len(q), -1, WORDS * WORDS).astype(np.float32)


def packed(codes: np.ndarray) -> np.ndarray:
    """Two four-bit codes in a byte: the even subspace low, the odd one high."""
    return codes[:, 0::2] | codes[:, 1::2] << 4


def scan(tables: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Approximate scores of all rows for one query; ``codes`` is (pairs, rows)."""
    score = np.zeros(codes.shape[1], np.float32)
    for table, byte in zip(tables, codes, strict=True):
        score += table[byte]
    return score


def nearest(own: int, q: np.ndarray, guess: np.ndarray, ids: np.ndarray, unit: np.ndarray, v: np.ndarray, along: np.ndarray, across: np.ndarray, top: int, shortlist: int) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers and scores of a block's ``top`` rows for one query, by falling score, then id.

    ``unit``: the rows as unit vectors in single precision; ``v``: the rows themselves.
    """
    margin = 1e-5 + 2e-7 * len(q)  # above the rounding of single precision
    other, one = ids != own, (q / np.sqrt(q @ q)).astype(np.float32)
    may = other
    if other.sum() > max(top, shortlist):
        shortlist = max(top, shortlist)
        first = np.argpartition(np.where(other, -guess, np.inf), shortlist - 1)[:shortlist]
        reached = float(np.partition(unit[first] @ one, -top)[-top]) - margin
        if reached > 0:
            kept = 1 - along
            may = other & (guess >= np.minimum(kept, kept * reached) - np.sqrt(max(0.0, 1 - reached**2)) * across - margin)
    at = np.flatnonzero(may)
    quick = unit[at] @ one if 8 * len(at) < len(ids) else (unit @ one)[at]
    if len(at) > top:
        at = at[quick >= np.partition(quick, -top)[-top] - 2 * margin]
    score = cosine(np.broadcast_to(q, (len(at), len(q))), v[at])
    order = np.lexsort((ids[at], -score))[:top]
    return at[order], score[order]


def search(vectors: DataFrame, is_query: Column, top: int = TOP, shortlist: int = SHORTLIST) -> DataFrame:
    """query_id, rank, vec_id, score: each query's nearest rows by cosine, itself not among them.

    Rows whose vector is null, zero, or holds null or non-finite components neither ask
    nor answer; a vector is compared with all others of its length. Ties go to the
    smaller vec_id. Rows that repeat a vec_id are one candidate, by the nearest of them, and
    one query, whose nearest are those of any of them; none answers itself. An empty
    table gives an empty result.
    """
    spark = vectors.sparkSession
    rows = participants(vectors, "vec_id")
    models = {}
    for width in widths(rows):
        sample = rows.where(F.size("v") == width).select("v").orderBy(F.xxhash64("v"), "vec_id").limit(FIT_ROWS).collect()
        x = np.array([r[0] for r in sample])
        models[width] = Quantiser.fit(x / norms(x)[:, None])
    if not models:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    model = spark.sparkContext.broadcast(models)  # of fixed size for a length
    parts = partitions_for(spark)
    kind = np.float32 if isinstance(vectors.schema["embedding"].dataType.elementType, FloatType) else np.float64

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, held = TaskContext.get().partitionId() << 32, {}

        def row(width: int) -> pa.RecordBatch:
            nonlocal number
            ids, codes, along, across, v = (np.concatenate(c) for c in zip(*held.pop(width), strict=True))
            out = pa.RecordBatch.from_arrays([pa.array([number]), pa.array([width]), *(pa.array([c.tobytes()]) for c in (ids, np.ascontiguousarray(codes.T), along, across, v))], ["rows", "width", "ids", "codes", "along", "across", "vectors"])
            number += 1
            return out

        for whole in batches:
            for width, batch in by_width(whole):
                v, book = matrix(batch.column("v")), model.value[width]
                x = v / norms(v)[:, None]
                codes = book.encode(x)
                held.setdefault(width, []).append((batch.column("vec_id").to_numpy(), packed(codes), *(c.astype(np.float32) for c in book.residuals(x, codes)), v.astype(kind)))
                if sum(len(h[0]) for h in held[width]) >= ROW_BLOCK:
                    yield row(width)
        for width in list(held):
            yield row(width)

    def asked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for whole in batches:
            for width, batch in by_width(whole):
                v, ids = matrix(batch.column("v")), batch.column("vec_id").to_numpy()
                for at in range(0, len(ids), QUERY_BLOCK):
                    yield pa.RecordBatch.from_arrays([pa.array([number]), pa.array([width]), pa.array([ids[at : at + QUERY_BLOCK].tobytes()]), pa.array([v[at : at + QUERY_BLOCK].tobytes()])], ["asks", "width", "query_ids", "queries"])
                    number += 1

    index = written(rows.mapInArrow(encoded, "rows long, width long, ids binary, codes binary, along binary, across binary, vectors binary"), "ann-index")
    queries = written(rows.where(is_query).coalesce(max(1, parts // 2)).mapInArrow(asked, "asks long, width long, query_ids binary, queries binary"), "ann-queries")
    # every query block meets every row block of its length: the stated query set against all rows, in blocks
    asks = queries.select("asks", "width", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("lane"))
    meet = index.select("rows", "width", F.pmod(F.xxhash64("rows"), F.lit(parts)).cast("int").alias("lane")).join(asks, ["lane", "width"]).select("rows", "asks").repartition(parts, "rows", "asks")
    scans = meet.join(index, "rows").join(queries.drop("width"), "asks")

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                r = batch.slice(at, 1).to_pylist()[0]
                ids, asked_ids = np.frombuffer(r["ids"], np.int64), np.frombuffer(r["query_ids"], np.int64)
                codes = np.frombuffer(r["codes"], np.uint8).reshape(-1, len(ids))
                along, across = (np.frombuffer(r[c], np.float32) for c in ("along", "across"))
                v, q = np.frombuffer(r["vectors"], kind).reshape(len(ids), -1).astype(np.float64), np.frombuffer(r["queries"]).reshape(len(asked_ids), -1)
                unit = (v / norms(v)[:, None]).astype(np.float32)
                tables = model.value[r["width"]].tables(q / norms(q)[:, None])
                # so many rows hold ``top`` ids, however they repeat
                most = top * int(np.unique(ids, return_counts=True)[1].max())
                out = [[], [], []]
                for k, own in enumerate(asked_ids):
                    best, score = nearest(own, q[k], scan(tables[k], codes), ids, unit, v, along, across, most, shortlist)
                    for held, new in zip(out, (np.full(len(best), own), ids[best], score), strict=True):
                        held.append(new)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], ["query_id", "vec_id", "score"])

    scored = scans.mapInArrow(scanned, "query_id long, vec_id long, score double").groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    by_score = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scored.withColumn("rank", F.row_number().over(by_score)).where(F.col("rank") <= top).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(load(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)
