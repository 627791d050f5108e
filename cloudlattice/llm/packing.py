"""Packing documents into sequences with Karmarkar-Karp multiway differencing.

Every task tokenizes its rows once, in order, and fills bins of documents. Whole
windows of a long document are cut off as full sequences; the remainders of a bin
are split into ``k`` windows of near-equal sums by the differencing rule: the two
partial partitions with the largest spread are merged with their loads opposed.
When a window exceeds the capacity, ``k`` rises by one and the bin is split again.
There is no shuffle, memory is one bin plus one document, and a lost executor only
repeats its own rows.
"""

from __future__ import annotations

import heapq
import json
import zlib
from array import array
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from cloudlattice.llm.work import load

WINDOW = 2048
END_ID = 1
#: Remainders in a bin; a bound on the work of one differencing run.
BIN_DOCS = 400
#: Remainders longer than this are cut, so that sums can be levelled.
PIECE = 640
CACHE = 1_000_000
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def differencing(sizes: list[int], k: int) -> list[list[int]]:
    """Split item numbers into ``k`` groups of near-equal sums."""
    tie = len(sizes)
    heap = []
    for i, size in enumerate(sizes):
        # a partial partition: loads falling, each with its items; k - len(loads) groups are empty
        heapq.heappush(heap, (-size, i, [(size, [i])]))
    if not heap:
        return [[] for _ in range(k)]
    while len(heap) > 1:
        _, _, a = heapq.heappop(heap)
        _, _, b = heapq.heappop(heap)
        # the largest of one meets the smallest of the other; empty groups count as zero
        free = k - len(a)
        merged = a + b[:free]
        for j, (load_, items) in enumerate(b[free:]):
            other, more = merged[len(a) - 1 - j]
            merged[len(a) - 1 - j] = (other + load_, more + items)
        merged.sort(key=lambda g: -g[0])
        if len(merged) == k and merged[-1][0]:
            spread = merged[0][0] - merged[-1][0]
        else:
            spread = merged[0][0]
        tie += 1
        heapq.heappush(heap, (-spread, tie, merged))
    groups = [items for _, items in heap[0][2]]
    return groups + [[] for _ in range(k - len(groups))]


def windows(sizes: list[int], capacity: int) -> list[list[int]]:
    """The fewest near-equal groups that the rule finds, none above ``capacity``."""
    k = max(1, -(-sum(sizes) // capacity))
    while True:
        groups = differencing(sizes, k)
        if max((sum(sizes[i] for i in g) for g in groups), default=0) <= capacity:
            return [g for g in groups if g]
        k += 1


class Ids(dict):
    """Token ids of a chunk as little-endian bytes, remembered up to a bound."""

    def __init__(self, encode, before: str = ""):
        super().__init__()
        self.encode, self.before = encode, before

    def __missing__(self, chunk: str) -> bytes:
        if len(self) >= CACHE:
            self.clear()
        got = self[chunk] = array("I", self.encode(self.before + chunk)).tobytes()
        return got


class Encoder:
    """Byte-level BPE of a ``tokenizers`` JSON file (ids are merge ranks in such files).

    Merging is left to a compiled merger fed from the file's vocabulary. The
    pattern of such files always breaks around a lone line feed and before a lone
    space, so a text whose white space is only those is looked up word by word;
    any other text goes through the merger whole. Texts that hold an added token of
    the file are left to ``tokenizers``, so ids are always those of that library's defaults.
    """

    def __init__(self, path: str):
        import re

        import tiktoken
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            held = json.load(f)
        model, extra = held["model"], [t["content"] for t in held.get("added_tokens") or []]
        # fixed values: the printable stand-ins for bytes that byte-level vocabularies use
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        stand_in = {chr(b): b for b in plain} | {chr(256 + n): b for n, b in enumerate(b for b in range(256) if b not in set(plain))}
        ranks = {bytes(stand_in[c] for c in token): i for token, i in model["vocab"].items() if all(c in stand_in for c in token)}
        for token in extra:
            ranks.pop(token.encode(), None)
        self.holds = re.compile("|".join(map(re.escape, extra))).search if extra else None
        self.own = Tokenizer.from_file(path) if self.holds else None
        pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
        self.whole = tiktoken.Encoding("file", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        # fixed values: white space other than space and line feed, of either library's notion
        self.other = re.compile("[\t\r\x0b\x0c\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]").search
        self.first, self.spaced = Ids(self.whole), Ids(self.whole, " ")
        self.feed = array("I", self.whole("\n")).tobytes()

    def even(self, text: str) -> bool:
        """All white space is single spaces and line feeds inside the text."""
        return bool(text) and text[0] not in " \n" and text[-1] not in " \n" and not any(x in text for x in ("  ", "\n\n", " \n", "\n ")) and not self.other(text)

    def __call__(self, text: str) -> bytes:
        if self.holds and self.holds(text):
            return array("I", self.own.encode(text, add_special_tokens=False).ids).tobytes()
        if not self.even(text):
            return array("I", self.whole(text)).tobytes()
        first, spaced, lines = self.first, self.spaced.__getitem__, []
        for line in text.split("\n"):
            head, _, rest = line.partition(" ")
            lines.append(first[head] + b"".join(map(spaced, rest.split(" "))) if rest else first[head])
        return self.feed.join(lines)


_encoders: dict[str, Encoder] = {}


def packed(rows: Iterable[tuple[int, str | None]], encode, task: int, window: int = WINDOW, bin_docs: int = BIN_DOCS) -> Iterator[tuple]:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset) for every piece."""
    number = task << 40
    rest: list[tuple[int, int, bytes, int]] = []

    def level() -> Iterator[tuple]:
        nonlocal number
        pieces = []
        for doc, start, ids, total in rest:
            parts = -(-(len(ids) // 4) // PIECE)
            step = -(-(len(ids) // 4) // parts)
            for at in range(0, len(ids) // 4, step):
                pieces.append((doc, start + at, ids[4 * at : 4 * (at + step)], total))
        for group in windows([len(p[2]) // 4 for p in pieces], window):
            offset = 0
            for i in group:
                doc, start, ids, total = pieces[i]
                yield doc, start, len(ids) // 4, zlib.crc32(ids), total, number, offset
                offset += len(ids) // 4
            number += 1
        rest.clear()

    end = array("I", [END_ID]).tobytes()
    for doc, text in rows:
        ids = encode(text or "") + end
        total = len(ids) // 4
        full = total // window * window
        for start in range(0, full, window):
            yield doc, start, window, zlib.crc32(ids[4 * start : 4 * (start + window)]), total, number, 0
            number += 1
        if full < total:
            rest.append((doc, full, ids[4 * full :], total))
        if len(rest) == bin_docs:
            yield from level()
    if rest:
        yield from level()


def pack_documents(docs: DataFrame, tokenizer: str, window: int = WINDOW, bin_docs: int = BIN_DOCS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece of a document's ids.

    A null text is empty, so its document is the end id alone. Repeated rows are packed
    each on their own; an empty table gives an empty result; long texts are cut into
    whole windows; other columns of the input are ignored. ``tokenizer`` is a file that
    every executor can read; its added tokens get their own ids wherever a text holds them.
    """
    from pyspark.sql import functions as F

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if tokenizer not in _encoders:
            _encoders[tokenizer] = Encoder(tokenizer)
        encode = _encoders[tokenizer]
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        rows = ((i, t) for b in batches for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True))
        out: list[tuple] = []
        for piece in packed(rows, encode, TaskContext.get().partitionId(), window, bin_docs):
            out.append(piece)
            if len(out) == 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names)
                out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(task, SCHEMA)


def default_tokenizer() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents"), default_tokenizer())
