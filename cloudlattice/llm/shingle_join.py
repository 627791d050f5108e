"""Jaccard join of shingle sets by a partition of the universe and the pigeonhole principle.

Two sets of Jaccard similarity ``s`` or more differ in at most
``H = (1 - s) / (1 + s) * (|x| + |y|)`` elements. Sizes fall into bands; in a band
the universe is cut by a hash into ``m`` segments, and a set is indexed by its part
of every segment. Parts of ``exact`` segments are indexed as they are and find
partners that agree there; parts of ``near`` segments are indexed together with
their one-deletion neighbourhoods and find partners that differ there by one. With
``m + near > H`` some segment finds every true pair. How many segments there are,
and how many of them are near, is settled for each band by expected cost: the
signatures written against the false candidates that small parts draw.

Empty parts say nothing and would meet in one huge group. A few more segments than
needed (``spare``) let a set leave its empty signatures out; the rare set that has
more of them keeps them all, so no pair is lost.

A task counts its own signatures first: rows of a signature that already has two
sets there are known to be shared, take any way through the one exchange and leave
one row behind to tell the others. So a hot signature, whatever its size, sends the
task that gathers it one row from each task.

Candidates are settled in two rounds, each verified on whole sets. First every
member of a signature meets the one member that shares most signatures. Then
only signatures whose members still lie in several components are joined, in
blocks of bounded size; a block pair returns a spanning forest of its links. So a
group of near copies never turns into all its pairs as rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.graph import Forest, components
from cloudlattice.llm.shingles import PIECE, WORDS, mixed, shingle_sets
from cloudlattice.llm.work import load, removed, written

PERCENT = 85
GROWTH = 1.5
#: Cost of a false candidate against a signature, and the share of common elements that it assumes.
FALSE_COST, COMMON = 20.0, 0.5
BLOCK = 1024
#: Bytes of sketches that are compared at once.
COMPARED = 1 << 20
#: Signatures that a task counts together before it sends them on.
LOCAL = 1 << 19
#: What a signature's row is, in its two lowest bits: the only set of it here, one of several that stands for all, one of several.
LONE, TOKEN, MEMBER = 0, 1, 2


@lru_cache(4096)
def band_start(band: int) -> int:
    return band + 1 if band < 2 else max(band_start(band - 1) + 1, int(band_start(band - 1) * GROWTH))


def bands(sizes: np.ndarray) -> np.ndarray:
    top = 0
    while len(sizes) and band_start(top + 1) <= sizes.max():
        top += 1
    return np.searchsorted([band_start(b) for b in range(top + 1)], sizes, "right") - 1


def most_different(size: int, percent: int) -> int:
    """Largest symmetric difference of two sets of at most ``size`` elements that still link."""
    return (100 - percent) * 2 * size // (100 + percent)


@lru_cache(4096)
def allocation(band: int, percent: int) -> tuple[int, int, int]:
    """(segments, near segments, spare) of least expected cost for sets of a band."""
    low, high = band_start(band), band_start(band + 1) - 1
    n, h = (low + high) / 2, most_different(high, percent)
    best = (math.inf, (1, 0, 0))
    spares = range(12 + h // 25)
    # all exact, all near, and for small bands every mixture
    options = {(h + 1 + k, 0) for k in spares} | {(h // 2 + 1 + k, h // 2 + 1 + k) for k in spares}
    if h <= 40:
        options |= {(m, h + 1 - m + k) for m in range(h // 2 + 1, h + 6) for k in range(6) if 0 <= h + 1 - m + k <= m}
    for m, near in sorted(options):
        spare, part = m + near - h - 1, n / m
        lost = math.exp(-part) * ((m - near) + near * (2 + part))  # expected
        odd, term = 0.0, math.exp(-lost)
        if m > 1:  # the chance to lose more than the spare segments, as a Poisson tail
            odd = 1.0
            for k in range(spare + 1):
                odd -= term
                term *= lost / (k + 1)
        cost = (m + near * part) * (1 + FALSE_COST * COMMON**part) + 1e4 * max(odd, 0.0)
        best = min(best, (cost, (m, near, spare)))
    return best[1]


def signatures(text: np.ndarray, shingle: np.ndarray, sizes: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """(text number, signature) for sets laid end to end; ``sizes`` by text number."""
    out_text, out = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)]
    for up in (0, 1):
        # a set also meets larger partners in the next band
        into = bands(sizes) + up
        top = range(int(into.max(initial=0)) + 1)
        takes = sizes > 0
        if up:
            takes &= sizes * 100 >= np.array([band_start(b) for b in top])[into] * percent
        if not takes.any():
            continue
        m, near, spare = np.array([allocation(b, percent) for b in top])[into].T
        m = np.where(takes, m, 0)
        base = np.cumsum(m) - m
        owner = np.repeat(np.arange(len(sizes)), m)
        segment = np.arange(len(owner)) - base[owner]
        is_near = segment < near[owner]
        place = mixed(into[owner].astype(np.uint64) * np.uint64(1_000_003) + segment.astype(np.uint64))
        at = takes[text]
        t, x = text[at], shingle[at]
        salt = mixed(into[t].astype(np.uint64) + np.uint64(77))
        part = base[t] + (mixed(x ^ salt) % m[t].astype(np.uint64)).astype(np.int64)
        value = mixed(x + salt)
        count, sums = np.bincount(part, minlength=len(owner)), np.zeros(len(owner), np.uint64)
        np.add.at(sums, part, value)
        full = count > 0
        out_text.append(owner[full])
        out.append(mixed(sums[full] ^ place[full]))
        # deletions of near segments, but for those that leave nothing
        less = (is_near & (count > 1))[part]
        out_text.append(t[less])
        out.append(mixed((sums[part[less]] - value[less]) ^ place[part[less]]))
        # sets with more empty parts than spare segments keep their empty signatures
        missing = np.bincount(owner, np.where(is_near, 2 - np.minimum(count, 2), ~full), len(sizes))
        bare = (missing > spare)[owner] & (~full | (is_near & (count == 1)))
        out_text.append(owner[bare])
        out.append(mixed(place[bare]))
    return np.concatenate(out_text), np.concatenate(out)


def parity_sketch(shingles: np.ndarray) -> bytes:
    """A bit for each of 64 or more buckets: whether it holds an odd number of elements.

    Sketches of two sets differ in at most as many bits as the sets differ in elements,
    so too many different bits prove that sets are not similar.
    """
    bits = max(64, 1 << max(0, len(shingles) - 1).bit_length())
    odd = np.bincount((shingles & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(sketch: np.ndarray, size: int) -> np.ndarray:
    """A sketch of fewer buckets, of ``size`` bytes."""
    return np.bitwise_xor.reduce(sketch.reshape(-1, size), axis=0)


def may_link(a: np.ndarray, b: np.ndarray, na: int, nb: int, percent: int) -> bool:
    size = min(len(a), len(b))
    differ = int(np.bitwise_count(folded(a, size) ^ folded(b, size)).sum())
    return differ * (100 + percent) <= (100 - percent) * (na + nb)


def batches_of(texts: pa.BinaryArray) -> Iterator[tuple[int, list[bytes]]]:
    """Texts in runs of about ``PIECE`` bytes, with the place of the first."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False))
    at = done = 0
    while at < len(texts):
        stop = max(at + 1, int(np.searchsorted(ends, done + PIECE, "right")))
        yield at, [x or b"" for x in texts.slice(at, stop - at).to_pylist()]
        at, done = stop, ends[stop - 1]


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, key (a hash of id and text, set for rows without an id too), text as bytes."""
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", text).alias("key"), text.cast("binary").alias("text"))


def profiles(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, key, n (distinct shingles), set (hash of the set), sketch."""
    names = ["doc_id", "key", "n", "set", "sketch"]

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, data in batches_of(batch.column(2)):
                sizes, digest, sets = described(*shingle_sets(data, words), len(data))
                ids = [batch.column(k).slice(at, len(data)) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays([*ids, pa.array(sizes.astype(np.int32)), pa.array(digest), pa.array([parity_sketch(x) for x in sets], pa.binary())], names)

    return keyed(docs).mapInArrow(task, "doc_id long, key long, n int, set long, sketch binary")


def described(text: np.ndarray, shingle: np.ndarray, count: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Size, hash and shingles of each of ``count`` sets laid end to end."""
    sizes = np.bincount(text, minlength=count)
    sets = np.split(shingle, np.cumsum(sizes)[:-1])
    return sizes, np.array([xxhash.xxh3_64_intdigest(x.tobytes()) for x in sets], np.uint64).view(np.int64), sets


def told_apart(sig: np.ndarray, sets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(signature with its kind, set) of a task's rows: a lone set once, shared ones all, and a token for them."""
    order = np.argsort(sig)
    sig, sets = sig[order], sets[order]
    first = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]])) if len(sig) else np.zeros(0, np.int64)
    if not len(first):
        return sig.view(np.int64), sets
    shared = np.minimum.reduceat(sets, first) != np.maximum.reduceat(sets, first)
    head = sig[first] & ~np.uint64(3)
    members = np.repeat(shared, np.diff(np.append(first, len(sig))))
    out = np.concatenate([head | shared.astype(np.uint64) * np.uint64(TOKEN), (sig[members] & ~np.uint64(3)) | np.uint64(MEMBER)])
    return out.view(np.int64), np.concatenate([sets[first], sets[members]])


def signature_rows(docs: DataFrame, percent: int, words: int) -> DataFrame:
    """sig (its lowest bits say of what kind the row is), set: the signatures of all sets."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sigs, sets, held = [], [], 0

        def flushed() -> Iterator[pa.RecordBatch]:
            sig, of = told_apart(np.concatenate(sigs) & ~np.uint64(3), np.concatenate(sets))
            for start in range(0, len(sig), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(sig[start : start + (1 << 16)]), pa.array(of[start : start + (1 << 16)])], ["sig", "set"])
            sigs.clear()
            sets.clear()

        for batch in batches:
            for _, data in batches_of(batch.column(0)):
                text, shingle = shingle_sets(data, words)
                sizes, digest, _ = described(text, shingle, len(data))
                who, sig = signatures(text, shingle, sizes, percent)
                sigs.append(sig)
                sets.append(digest[who])
                held += len(sig)
                if held >= LOCAL:
                    yield from flushed()
                    held = 0
        if held:
            yield from flushed()

    return keyed(docs).select("text").mapInArrow(task, "sig long, set long")


def shared_members(rows: DataFrame) -> DataFrame:
    """sig, set: the rows of signatures that several sets have."""
    where = F.when(F.col("sig").bitwiseAND(F.lit(3)) == MEMBER, F.xxhash64("sig", "set")).otherwise(F.col("sig").bitwiseAND(F.lit(-4)))

    def settled(sig: np.ndarray, sets: np.ndarray) -> np.ndarray:
        """Of sorted lone rows and tokens of whole signatures: the lone ones that share theirs."""
        first = np.flatnonzero(np.concatenate([[True], (sig[1:] ^ sig[:-1]) >> 2 != 0]))
        told = np.bitwise_or.reduceat(sig & 3, first) != LONE
        told |= np.minimum.reduceat(sets, first) != np.maximum.reduceat(sets, first)
        return np.repeat(told, np.diff(np.append(first, len(sig)))) & (sig & 3 == LONE)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def made(sig: np.ndarray, sets: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(sig >> 2), pa.array(sets)], ["sig", "set"])

        waiting = np.zeros(0, np.int64), np.zeros(0, np.int64)  # of the last signature met: a row from each task at most
        for batch in batches:
            sig, sets = (batch.column(k).to_numpy() for k in (0, 1))
            plain = sig & 3 != MEMBER
            if not plain.all():
                yield made(sig[~plain], sets[~plain])
            sig, sets = np.concatenate([waiting[0], sig[plain]]), np.concatenate([waiting[1], sets[plain]])
            if not len(sig):
                continue
            cut = np.flatnonzero((sig ^ sig[-1]) >> 2 != 0)
            cut = int(cut[-1]) + 1 if len(cut) else 0
            if cut and (good := settled(sig[:cut], sets[:cut])).any():
                yield made(sig[:cut][good], sets[:cut][good])
            waiting = sig[cut:], sets[cut:]
        if len(waiting[0]) and (good := settled(*waiting)).any():
            yield made(waiting[0][good], waiting[1][good])

    return rows.repartition(where).sortWithinPartitions("sig").mapInArrow(task, "sig long, set long").distinct()


def sets_of(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """set and its sorted shingles as bytes, for every wanted set, from one document each (columns key, set)."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, data in batches_of(batch.column(1)):
                text, shingle = shingle_sets(data, words)
                _, digest, sets = described(text, shingle, len(data))
                asked = batch.column(0).slice(at, len(data)).to_numpy()
                # a key of two rows counts for the row that has the wanted set
                good = np.flatnonzero(digest == asked).tolist()
                if good:
                    yield pa.RecordBatch.from_arrays([pa.array(asked[good]), pa.array([sets[k].tobytes() for k in good], pa.binary())], ["set", "shingles"])

    texts = keyed(docs).select("key", "text").join(wanted, "key")
    return texts.dropDuplicates(["key", "set"]).select("set", "text").mapInArrow(task, "set long, shingles binary")


def sources(known: DataFrame, sets: DataFrame) -> DataFrame:
    """key of one document for each of ``sets``."""
    return known.join(sets, "set", "left_semi").groupBy("set").agg(F.min("key").alias("key"))


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def block_links(a: list[np.ndarray], b: list[np.ndarray], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of linked sets of two blocks, by counting common elements of all at once."""
    na, nb = np.array([len(x) for x in a]), np.array([len(x) for x in b])
    va, vb = np.concatenate(a), np.concatenate(b)
    common = np.intersect1d(va, vb)
    both = np.zeros((len(a), len(b)), np.float32)
    ka, kb = np.repeat(np.arange(len(a)), na), np.repeat(np.arange(len(b)), nb)
    ia, ib = np.searchsorted(common, va), np.searchsorted(common, vb)
    for lo in range(0, len(common), 4096):
        hi = min(lo + 4096, len(common))
        x, y = np.zeros((len(a), hi - lo), np.float32), np.zeros((len(b), hi - lo), np.float32)
        for m, k, i, v in ((x, ka, ia, va), (y, kb, ib, vb)):
            ok = (i >= lo) & (i < hi)
            ok[ok] = common[i[ok]] == v[ok]
            m[k[ok], i[ok] - lo] = 1
        both += x @ y.T
    return np.nonzero(100 * both >= percent * (na[:, None] + nb[None, :] - both))


def verified(docs: DataFrame, known: DataFrame, pairs: DataFrame, percent: int, words: int) -> DataFrame:
    """Those pairs (u, v) of sets that link, compared whole; texts are read again for them only."""
    named = pairs.select(F.explode(F.array("u", "v")).alias("set")).distinct()
    held = written(sets_of(docs, sources(known, named), words), "sets")
    both = pairs.join(held.withColumnsRenamed({"set": "v", "shingles": "b"}), "v").join(held.withColumnsRenamed({"set": "u", "shingles": "a"}), "u")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [similar(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64), percent) for x, y in zip(batch.column("a"), batch.column("b"), strict=True)]
            yield batch.select(["u", "v"]).filter(pa.array(good, pa.bool_()))

    out = written(both.select("u", "v", "a", "b").mapInArrow(verify, "u long, v long"), "star-links")
    removed(held)
    return out


def grouped(batches: Iterator[pa.RecordBatch], done) -> Iterator[pa.RecordBatch]:
    """Calls ``done(key, rows)`` for each run of equal first three columns of sorted rows."""
    key, group = None, []
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if row[:3] != key:
                if key and (out := done(key, group)):
                    yield out
                key, group = row[:3], []
            group.append(row[3:])
    if key and (out := done(key, group)):
        yield out


def links(docs: DataFrame, known: DataFrame, percent: int, words: int) -> DataFrame:
    """Edges (u, v) between sets that connect exactly the sets that links connect."""
    members = written(shared_members(signature_rows(docs, percent, words)), "members")
    sketches = written(known.where("n > 0").select("set", "n", "sketch").join(members.select("set"), "set", "left_semi").dropDuplicates(["set"]), "sketches")
    degree = members.groupBy("set").agg(F.count(F.lit(1)).alias("degree"))
    centres = members.join(degree, "set").groupBy("sig").agg(F.max(F.struct("degree", "set")).alias("c")).select("sig", F.col("c.set").alias("u"))
    star = members.join(centres, "sig").where(F.col("u") != F.col("set")).select("u", F.col("set").alias("v")).distinct()
    fits = F.least("m", "n") * 100 >= F.greatest("m", "n") * percent
    sketched = star.join(sketches.withColumnsRenamed({"set": "v", "sketch": "b"}), "v").join(sketches.withColumnsRenamed({"set": "u", "n": "m", "sketch": "a"}), "u").where(fits)

    def prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [may_link(np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8), m, n, percent) for a, b, m, n in zip(*(batch.column(c).to_pylist() for c in "abmn"), strict=True)]
            yield batch.select(["u", "v"]).filter(pa.array(good, pa.bool_()))

    likely = written(sketched.select("u", "v", "m", "n", "a", "b").mapInArrow(prune, "u long, v long"), "star-pairs")
    first = verified(docs, known, likely, percent, words)
    joined = components(first).withColumnsRenamed({"id": "set", "component_id": "root"})
    state = members.join(joined, "set", "left").select("sig", "set", F.coalesce("root", "set").alias("root"))
    # a signature of two sets is settled; any other with several components is not
    prints = [F.bit_xor(F.xxhash64(F.lit(k), "set")).alias(f"print{k}") for k in (0, 1)]
    open_ = state.groupBy("sig").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("size"), *prints).where("lo <> hi and size > 2")
    # signatures of the same members are looked at once
    unsettled = open_.groupBy("size", "print0", "print1").agg(F.min("sig").alias("sig"))
    blocks = F.ceil(F.col("size") / F.lit(BLOCK)).cast("int")
    placed = state.join(unsettled.select("sig", blocks.alias("blocks")), "sig").withColumn("block", F.pmod(F.xxhash64("set"), F.col("blocks")).cast("int"))
    # a row for each pair of blocks that a member's block is part of
    spread = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("sig", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "set", "root")
    place = ["sig", "i", "j"]
    loaded = spread.join(sketches, "set").repartition(*place).sortWithinPartitions(*place, "block", "set").select(*place, "block", "set", "n", "root", "sketch")
    names = [*place, "block", "set", "root"]

    def narrow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Members that may link to a member of another component."""

        def done(key: tuple, group: list[tuple]) -> pa.RecordBatch | None:
            a, b = [g for g in group if g[0] == key[1]], [g for g in group if g[0] == key[2]]
            if not a or not b or len({g[3] for g in group}) < 2:
                return None
            size = min(len(g[4]) for g in group)
            x, y = (np.stack([folded(np.frombuffer(g[4], np.uint8), size) for g in side]).view(np.uint64) for side in (a, b))
            (na, ra), (nb, rb) = (np.array([g[2:4] for g in side], np.int64).T for side in (a, b))
            hit_a, hit_b = np.zeros(len(a), bool), np.zeros(len(b), bool)
            step = max(1, COMPARED // y.nbytes)
            for at in range(0, len(a), step):
                some = slice(at, at + step)
                differ = np.bitwise_count(x[some, None] ^ y[None]).sum(2, dtype=np.int64) * (100 + percent)
                near = (differ <= (100 - percent) * (na[some, None] + nb[None])) & (ra[some, None] != rb[None])
                hit_a[some] = near.any(1)
                hit_b |= near.any(0)
            keep = {g[1]: g for side, hit in ((a, hit_a), (b, hit_b)) for g, h in zip(side, hit.tolist(), strict=True) if h}
            if not keep:
                return None
            rows = [(*key, g[0], g[1], g[3]) for g in keep.values()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names)

        yield from grouped(batches, done)

    left = written(loaded.mapInArrow(narrow, "sig long, i int, j int, block int, set long, root long"), "open-members")
    held = written(sets_of(docs, sources(known, left.select("set")), words), "sets")
    whole = left.join(held, "set").repartition(*place).sortWithinPartitions(*place, "block", "set").select(*names, "shingles")

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A spanning forest of the links between components in each pair of blocks."""

        def done(key: tuple, group: list[tuple]) -> pa.RecordBatch | None:
            a, b = [g for g in group if g[0] == key[1]], [g for g in group if g[0] == key[2]]
            if not a or not b:
                return None
            forest, roots = Forest(len(group)), {}
            place = {g[1]: k for k, g in enumerate(group)}
            for g in group:
                forest.join(place[g[1]], roots.setdefault(g[2], place[g[1]]))
            x, y = block_links(*([np.frombuffer(g[3], np.uint64) for g in side] for side in (a, b)), percent)
            edges = [(a[p][1], b[q][1]) for p, q in zip(x.tolist(), y.tolist(), strict=True) if forest.join(place[a[p][1]], place[b[q][1]])]
            return pa.RecordBatch.from_arrays([pa.array([e[k] for e in edges], pa.int64()) for k in (0, 1)], ["u", "v"]) if edges else None

        yield from grouped(batches, done)

    second = written(whole.mapInArrow(settle, "u long, v long"), "block-links")
    removed(members, sketches, likely, left, held)
    return first.unionByName(second)


def classes(docs: DataFrame, percent: int = PERCENT, words: int = WORDS) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of ``docs``.

    Null texts and texts without words have an empty set and are their own class.
    Texts of equal sets are one class from the start; repeated rows are such. An empty
    table gives an empty result. Other columns of the input are ignored.
    """
    known = written(profiles(docs, words), "profiles")
    roots = components(links(docs, known, percent, words)).withColumnsRenamed({"id": "set", "component_id": "root"})
    slim = known.select("doc_id", "n", "set").join(roots, "set", "left").select("doc_id", "n", F.when(F.col("n") > 0, F.coalesce("root", "set")).alias("root"))
    # a table of its own: the engine splits a large class in a join of two tables, not in one with an aggregate
    least = written(slim.where("root is not null").groupBy("root").agg(F.min("doc_id").alias("component_id")), "least")
    return slim.join(least, "root", "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def representatives(docs: DataFrame, percent: int = PERCENT, words: int = WORDS) -> DataFrame:
    """One document of each class, the one of the smallest id, with the columns it came with.

    Repeated rows of it count once. A row without an id stays, as nothing can name its class.
    """
    keep = classes(docs, percent, words).where("doc_id = component_id").select("doc_id").distinct()
    kept = docs.join(keep, "doc_id", "left_semi").withColumn("_text_hash", F.xxhash64("text")).dropDuplicates(["doc_id", "_text_hash"]).drop("_text_hash")
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(load(spark, sf_dir, "documents"))
