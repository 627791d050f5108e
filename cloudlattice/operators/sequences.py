"""Sizes of many sequences of cells at once, on sorted arrays instead of rows.

A sequence is a cloud at a bound (and a stride). Points are read once: each task combines its points to
sorted keys with counts for every sequence and codec, cut at splitters. What belongs together is merged
in key ranges, and their differences in histograms, which are merged in turn, so that no task holds a
whole sequence. Splitters come from a sample of points; they deal out the work and don't change a result.
Sizes and errors are those of ``families``; blocks leave a task as binary columns of numbers.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from types import CodeType

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cloudlattice.functions import curves
from cloudlattice.operators import families
from cloudlattice.operators.families import BLOCK_HEADER, DIGITS, FIXED, NEGABINARY, ORDERS, SYMBOL_BITS, VECTOR, Bound

PIPELINES = ("to_morton", "to_hilbert", "cube_pipeline")
#: What is merged by key range; the grid serves both trees.
KEYED = (*PIPELINES, "particle_block", "grid")
#: Codecs that look at points in their stored order, and what is added up.
STORED = ("array_predictive", "float_bounded", "sums")
#: Codecs without rows of their own: their bits come with the sums and with the grid.
CARRIED = ("float_lossless", "octree_occupancy")
KINDS = (*KEYED, *STORED, *CARRIED)
#: Points that a task combines at once, and points of a key range.
BATCH, RANGE = 1 << 18, 400_000
#: Points whose cells are computed at once, so that the steps between stay in a core's cache.
CACHED = 1 << 14
#: Points of a cloud that splitters are taken from, about.
SAMPLE = 20_000
ROW = "seq int, kind int, stream int, bucket int, v binary, c binary"
_ARROW = pa.schema([(n, pa.int32()) for n in ("seq", "kind", "stream", "bucket")] + [("v", pa.binary()), ("c", pa.binary())])
#: The slice of points without an id; those of ids are shorter by 16 bits or more.
NO_SLICE = -(1 << 50)
#: The stream of what a key range tells the driver.
FACTS = -1


@dataclass
class Plan:
    """Sequences by number: cloud, bound and stride; of each cloud its box and ranges; splitters by sequence and codec."""

    seqs: list[tuple[int, Bound, int]]
    boxes: list[list[tuple[float, float]]]
    ranges: list[int]
    kinds: tuple[str, ...]
    patches: list[int] = field(default_factory=list)
    splitters: dict[tuple[int, str], np.ndarray] = field(default_factory=dict)

    def parts(self, seq: int) -> int:
        cloud, _, stride = self.seqs[seq]
        return -(-self.ranges[cloud] // stride)

    def served(self, seq: int) -> list[int]:
        """Sequences whose trees the grid keys of this one tell: all of the cloud if it has the finest grid, as coarser ones are starts of its keys."""
        cloud, _, stride = self.seqs[seq]
        mine = [k for k, (of, _, step) in enumerate(self.seqs) if (of, step) == (cloud, stride)]
        return mine if seq == max(mine, key=lambda k: (self.seqs[k][1].levels, -k)) else []

    def keyed(self, seq: int) -> tuple[str, ...]:
        """Codecs that keys of this sequence are sent for."""
        return self.kinds if "grid" not in self.kinds or self.served(seq) else tuple(k for k in self.kinds if k != "grid")


def bit_length(n: np.ndarray) -> np.ndarray:
    """Exact below 2^53, as are all that are measured here."""
    return np.frexp(n.astype(np.float64))[1].astype(np.int64)


def unit(raw: np.ndarray, box: list[tuple[float, float]]) -> np.ndarray:
    """Three axes to [0, 1]; an axis without extent to 0."""
    if not np.isfinite(raw).all():
        raise ValueError("a coordinate is null or not finite")
    return np.stack([np.zeros(len(a)) if hi == lo else (a - lo) / (hi - lo) for a, (lo, hi) in zip(raw, box, strict=True)])


def squared(a, b) -> np.ndarray:
    x, y, z = (p - q for p, q in zip(a, b, strict=True))
    return x * x + y * y + z * z


def bcc(u: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Cells of the lattice and squared distances to them; between equally near ones the even corner."""
    floor = np.floor(u)
    below, cell = u - floor, floor.astype(np.int64)
    above, odd = below - 1, cell & 1
    below *= below
    above *= above
    flip = odd.astype(bool)
    (ex, ey, ez), (ox, oy, oz) = np.where(flip, above, below), np.where(flip, below, above)
    even, other = ex + ey + ez, ox + oy + oz
    odd ^= even > other
    cell += odd
    return list(cell), np.minimum(even, other)


def cube(u: np.ndarray) -> list[np.ndarray]:
    return [np.floor(a + 0.5).astype(np.int64) for a in u]


def grid(p: np.ndarray, levels: int) -> list[np.ndarray]:
    return [np.minimum(np.floor(a * float(1 << levels)), float((1 << levels) - 1)).astype(np.int64) for a in p]


def morton(cell: list[np.ndarray]) -> np.ndarray:
    out = None
    for axis, c in enumerate(cell):
        c = c.copy()
        for shift, mask in curves.SPREAD:
            c |= c << shift
            c &= mask
        out = c if out is None else out | c << axis
    return out


@lru_cache
def _walk(levels: int) -> tuple[np.ndarray, np.ndarray]:
    """Digits and following state of so many levels at once, by state and octants."""
    digit, following = (np.array(t, np.int64) for t in curves.hilbert_tables())
    octants = np.arange(8**levels)
    key, state = np.zeros((len(digit) // 8, 8**levels), np.int64), np.repeat(np.arange(len(digit) // 8)[:, None], 8**levels, 1)
    for b in range(levels - 1, -1, -1):
        at = state * 8 + (octants >> 3 * b & 7)
        key, state = key << 3 | digit[at], following[at]
    return key.ravel(), state.ravel()


def hilbert(z: np.ndarray, bits: int) -> np.ndarray:
    """The Hilbert key of a Z-order key of so many bits an axis."""
    key, state, left = np.zeros(len(z), np.int64), np.zeros(len(z), np.int64), bits
    while left:
        levels = left % 4 or 4
        left -= levels
        digits, following = _walk(levels)
        at = (state << 3 * levels) + (z >> 3 * left & 8**levels - 1)
        key, state = key << 3 * levels | digits[at], following[at]
    return key


def blocked(cell: list[np.ndarray], blocks: int) -> np.ndarray:
    i, j, k = cell
    return (((k >> 3) * blocks + (j >> 3)) * blocks + (i >> 3)) << 9 | ((k & 7) << 6 | (j & 7) << 3 | i & 7)


def counted(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None]:
    """Distinct keys in order and how often each is there; None if all are there once."""
    if counts is not None and counts.min(initial=1) > 0 and counts.sum() <= 2 * len(keys):
        keys, counts = np.repeat(keys, counts), None  # keys alone are sorted faster than keys with counts
    if counts is not None:
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
    elif len(keys) and keys.max() < 2 * len(keys) and keys.min() >= 0:  # dense values are counted without a sort
        counts = np.bincount(keys)
        keys = np.flatnonzero(counts)
        counts = counts[keys]
        return keys, None if counts.max() == 1 else counts
    else:
        keys = np.sort(keys)
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    if counts is None:
        return (keys, None) if len(first) == len(keys) else (keys[first], np.diff(first, append=len(keys)))
    return keys[first], np.add.reduceat(counts, first) if len(keys) else counts


#: Widths of numbers in a binary column, by the byte before them.
_WIDTHS = tuple(np.dtype(w) for w in ("u1", "<u2", "<u4", "<i8"))


def _narrow(a: np.ndarray) -> bytes:
    top = int(a.max()) if len(a) else 0
    at = next(k for k, w in enumerate(_WIDTHS) if top <= np.iinfo(w).max)
    return bytes([at]) + a.astype(_WIDTHS[at], copy=False).tobytes()


def packed(a: np.ndarray | None, rising: bool = False) -> bytes:
    """Numbers from 0 in the fewest bytes that hold them all; ``rising`` ones as the first and differences."""
    if a is None or not len(a):
        return b""
    return np.array(a[:1], "<i8").tobytes() + _narrow(np.diff(a)) if rising else _narrow(a)


def unpacked(held: bytes, rising: bool = False) -> np.ndarray:
    start = 8 if rising else 0
    a = np.frombuffer(held, _WIDTHS[held[start]], offset=start + 1)
    if not rising:
        return a.astype(np.int64)
    out = np.empty(len(a) + 1, np.int64)
    out[0], out[1:] = np.frombuffer(held, "<i8", 1)[0], a
    return np.cumsum(out, out=out)


def plain(a) -> bytes:
    return np.array(a, np.int64).tobytes()


def quantized(kinds: tuple[str, ...], bound: Bound, p: np.ndarray, errors: dict[str, list[float]] | None = None) -> dict[str, np.ndarray]:
    """Keys of points on the unit cube, as they lie; ``bcc`` serves both orders of its cells. Into ``errors`` go summed and largest squared ones of cells."""
    wanted, n = set(kinds), p.shape[1]
    names = [name for name, users in (("bcc", {"to_morton", "to_hilbert"}), ("cube_pipeline", {"cube_pipeline"}), ("particle_block", {"particle_block"}), ("grid", {"grid"})) if wanted & users]
    out = {name: np.empty(n, np.int64) for name in names}

    def add(name: str, e: np.ndarray) -> None:
        held = errors.setdefault(name, [0.0, 0.0])
        held[0] += float(e.sum())
        held[1] = max(held[1], float(e.max()))

    for at in range(0, n, CACHED):
        here = slice(at, at + CACHED)
        piece = p[:, here]
        if "bcc" in out:
            cell, e = bcc(piece * bound.bcc)
            out["bcc"][here] = morton([c >> 1 for c in cell]) << 1 | cell[0] & 1
            if errors is not None:
                add("bcc", e / (bound.bcc * bound.bcc))
        if wanted & {"cube_pipeline", "particle_block"}:
            u = piece * bound.cube
            cell = cube(u)
            if "cube_pipeline" in out:
                out["cube_pipeline"][here] = morton(cell)
            if "particle_block" in out:
                out["particle_block"][here] = blocked(cell, bound.blocks)
            if errors is not None:
                add("cube", squared(u, cell) / (bound.cube * bound.cube))
        if "grid" in out:
            out["grid"][here] = morton(grid(piece, bound.levels))
    return out


def ordered(kinds: tuple[str, ...], bound: Bound, held: dict[str, np.ndarray]) -> Iterator[tuple[str, np.ndarray, np.ndarray | None]]:
    """Codec, keys in order and counts, of what ``quantized`` gave."""
    for name, keys in held.items():
        if name != "bcc":
            yield name, *counted(keys)
            continue
        keys, counts = counted(keys)
        if "to_morton" in kinds:
            yield "to_morton", keys, counts
        if "to_hilbert" in kinds:
            yield "to_hilbert", *counted(hilbert(keys >> 1, bound.hilbert) << 1 | keys & 1, counts)


def with_splitters(plan: Plan, sampled: dict[int, np.ndarray]) -> Plan:
    """Splitters of every sequence from some points of its cloud (three axes, as stored)."""
    for seq, (cloud, _, _) in enumerate(plan.seqs):
        parts, raw = plan.parts(seq), sampled.get(cloud)
        if parts == 1 or raw is None or not raw.shape[1]:
            continue
        bound = plan.seqs[seq][1]
        for kind, keys, _ in ordered(plan.kinds, bound, quantized(plan.keyed(seq), bound, unit(raw, plan.boxes[cloud]))):
            plan.splitters[seq, kind] = np.unique(keys[np.arange(1, parts) * len(keys) // parts])
    return plan


def histogram(plan: Plan, seq: int, kind: str, stream: int, values: np.ndarray, counts: np.ndarray | None = None) -> Iterator[tuple]:
    """Rows of a histogram, dealt out by value."""
    v, c = counted(values, counts)
    parts = plan.parts(seq)
    if parts == 1:
        yield seq, KINDS.index(kind), stream, 0, packed(v, True), packed(c)
        return
    owner = (v % parts).astype(np.int16 if parts < 1 << 15 else np.int64)
    order = np.argsort(owner, kind="stable")
    edges = np.searchsorted(owner[order], np.arange(parts + 1))
    for b in np.flatnonzero(np.diff(edges)):
        at = order[edges[b] : edges[b + 1]]
        yield seq, KINDS.index(kind), stream, int(b), packed(v[at], True), packed(None if c is None else c[at])


def cut(plan: Plan, seq: int, held: dict[str, np.ndarray]) -> Iterator[tuple]:
    """Rows of keys (of ``quantized``) and counts, cut at the splitters."""
    for kind, keys, counts in ordered(plan.kinds, plan.seqs[seq][1], held):
        edges = [0, *np.searchsorted(keys, plan.splitters.get((seq, kind), []), side="right"), len(keys)]
        for b, (lo, hi) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
            if lo < hi:
                yield seq, KINDS.index(kind), 0, b, packed(keys[lo:hi], True), packed(None if counts is None else counts[lo:hi])


@lru_cache
def _steps(forward: bool) -> list[tuple[str, CodeType]]:
    return [(target, compile(value, "<lifting>", "eval")) for target, value in (families.lifting() if forward else families.unlifting())]


def _lifted(held: dict[str, np.ndarray], forward: bool) -> np.ndarray:
    for target, value in _steps(forward):
        held[target] = eval(value, {"shiftright": np.right_shift}, held)  # noqa: S307 (steps of this package)
    return np.stack([held[k] for k in "abcd"])


def transformed(p: np.ndarray, bounds: list[Bound]) -> list[tuple[int, float, float]]:
    """Bits, summed and largest squared error of the block transform over points in stored order; digits are the same at every bound."""
    n, out = p.shape[1], []
    v = np.concatenate([p, np.zeros((3, -n % 4))], 1) if n % 4 else p
    v = np.ascontiguousarray(np.moveaxis(v.reshape(3, -1, 4), 2, 0))  # the four places of a block, each a contiguous array
    e = bit_length(np.floor(v.max(0) * float(1 << FIXED))) - FIXED
    scale = np.ldexp(1.0, FIXED - e)
    digits = _lifted(dict(zip("abcd", np.floor(v * scale + 0.5).astype(np.int64), strict=True)), True)
    digits += NEGABINARY
    digits ^= NEGABINARY
    long, unscaled = bit_length(digits).astype(np.int8), 1 / scale  # powers of two
    for bound in bounds:
        kept = np.minimum(FIXED + 2, np.maximum(0, e - bound.least + 4))
        gone = FIXED + 2 - kept
        lengths = np.maximum(long - gone.astype(np.int8), 0)
        spent = int(lengths.sum(dtype=np.int64)) + int(np.count_nonzero(lengths)) + int(kept.sum()) + BLOCK_HEADER * kept.size
        cut = digits & np.left_shift(-1, gone)
        cut ^= NEGABINARY
        cut -= NEGABINARY
        gap = _lifted(dict(zip("abcd", cut, strict=True)), False) * unscaled
        gap -= v
        gap *= gap
        error = gap[:, 0] + gap[:, 1] + gap[:, 2]
        if n % 4:
            error = error.T.ravel()[:n]
        out.append((spent, float(error.sum()), float(error.max())))
    return out


def lossless(raw: np.ndarray, patch: int) -> int:
    """Bits of decimal vectors of stored values."""
    starts = np.arange(0, raw.shape[1], VECTOR)
    n, total = np.diff(starts, append=raw.shape[1]), 0
    for a in raw:
        best = None
        for e in range(DIGITS + 1):
            scaled = a * 10.0**e
            fits = np.abs(scaled) < 9e15
            whole = np.floor(np.where(fits, scaled, 0.0) + 0.5)
            fits &= whole / 10.0**e == a
            good = np.add.reduceat(fits.astype(np.int64), starts)
            top, low = np.maximum.reduceat(np.where(fits, whole, -np.inf), starts), np.minimum.reduceat(np.where(fits, whole, np.inf), starts)
            span = np.where(good > 0, top - low, 0.0)
            cost = bit_length(span) * n + (n - good) * patch + 80
            best = cost if best is None else np.minimum(best, cost)
        total += int(best.sum())
    return total


def in_order(plan: Plan, cloud: int, p: np.ndarray, raw: np.ndarray) -> Iterator[tuple]:
    """Rows of a slice's points for all sequences of its cloud: of the codecs that look at them in stored order, of errors, and of keys."""
    mine, n = [seq for seq, at in enumerate(plan.seqs) if at[0] == cloud], p.shape[1]
    bounds = [plan.seqs[seq][1] for seq in mine]
    spent = [(0, 0.0, 0.0)] * len(mine)
    for at in range(0, n, CACHED):  # a multiple of a block's four places
        spent = [(a + b, c + d, max(e, f)) for (a, c, e), (b, d, f) in zip(spent, transformed(p[:, at : at + CACHED], bounds), strict=True)]
    exact = lossless(raw, plan.patches[cloud]) if "float_lossless" in plan.kinds else 0  # what no bound changes is added up once
    for seq, held in zip(mine, spent, strict=True):
        yield from at_bound(plan, seq, p, held, exact if seq == mine[0] else 0)


def at_bound(plan: Plan, seq: int, p: np.ndarray, transform: tuple[int, float, float], exact: int) -> Iterator[tuple]:
    bound, bytewise = plan.seqs[seq][1], "float_bounded" in plan.kinds
    width, n = float(1 << bound.levels), p.shape[1]
    errors = {k: [0.0, 0.0] for k in sorted(set(families.ERRORS.values()))}
    whole, q = np.empty((3, n), np.int64), np.empty((3, n), "<i4") if bytewise else None
    for at in range(0, n, CACHED):
        here = slice(at, at + CACHED)
        piece = p[:, here]
        steps = np.floor(piece / bound.step + 0.5)
        whole[:, here] = steps
        wide = piece * width
        back = [("steps", steps * bound.step), ("grid", (np.minimum(np.floor(wide), width - 1) + 0.5) / width)]
        if bytewise:
            wide += 0.5
            fixed = np.floor(wide, out=wide)
            q[:, here] = fixed
            back.append(("fixed", fixed / width))
        for name, to in back:
            e = squared(piece, to)
            errors[name] = [errors[name][0] + float(e.sum()), max(errors[name][1], float(e.max()))]
    for axis in range(3):
        gap = np.diff(whole[axis], prepend=0)
        yield from histogram(plan, seq, "array_predictive", axis, gap << 1 ^ gap >> 63)
        for place in range(bound.levels // 8 + 1) if bytewise else ():
            byte = q[axis].view(np.uint8)[place::4]
            counts = np.append(np.bincount(byte, minlength=256), 1 + np.count_nonzero(byte[1:] != byte[:-1]))  # the last: runs
            yield seq, KINDS.index("float_bounded"), axis * 3 + place, 0, packed(np.arange(257), True), packed(counts)
    del whole, q
    for at in range(0, n, BATCH):
        yield from cut(plan, seq, quantized(plan.keyed(seq), bound, p[:, at : at + BATCH], errors))
    spent, total, worst = transform
    sums = [n, spent, total, exact, *(errors[k][0] for k in sorted(errors))]
    tops = [worst, *(errors[k][1] for k in sorted(errors))]
    yield seq, KINDS.index("sums"), 0, 0, np.array(sums, np.float64).tobytes(), np.array(tops, np.float64).tobytes()


def table(rows: list[tuple]) -> pa.Table:
    return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _ARROW.types, strict=True)], schema=_ARROW) if rows else _ARROW.empty_table()


def batches(rows: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
    """Rows in batches of some MB."""
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[4]) + len(row[5])
        if size > 1 << 23 or len(held) >= 5000:
            yield from table(held).to_batches()
            held, size = [], 0
    if held:
        yield from table(held).to_batches()


def from_points(points: DataFrame, plan: Plan) -> DataFrame:
    """Rows of keys of points in any order (columns cloud, x, y, z as stored, and number where there are strides)."""

    def rows(got: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        by_cloud = defaultdict(list)
        for batch in got:
            columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            for cloud in np.unique(columns[0]):
                at = columns[0] == cloud
                held = by_cloud[int(cloud)]
                held.append([c[at] for c in columns[1:]])
                if sum(len(h[0]) for h in held) >= BATCH:
                    yield from done(int(cloud), by_cloud.pop(int(cloud)))
        for cloud, held in by_cloud.items():
            yield from done(cloud, held)

    def done(cloud: int, held: list) -> Iterator[tuple]:
        *raw, number = (np.concatenate(c) for c in zip(*held, strict=True))
        p = unit(np.stack(raw), plan.boxes[cloud])
        by_bound = defaultdict(list)
        for seq, (of, bound, stride) in enumerate(plan.seqs):
            if of == cloud:
                by_bound[bound].append((seq, stride))
        kept = {stride: np.flatnonzero(number % stride == 0) for stride in {s for _, _, s in plan.seqs} - {1}}
        for bound, mine in by_bound.items():  # points of a stride have the keys that they have among all
            held = quantized(plan.kinds, bound, p)
            for seq, stride in mine:
                if stride == 1:
                    yield from cut(plan, seq, held)
                elif len(kept[stride]):
                    yield from cut(plan, seq, {name: keys[kept[stride]] for name, keys in held.items()})

    return points.select("cloud", "x", "y", "z", "number").mapInArrow(lambda got: batches(rows(got)), ROW)


def from_slices(points: DataFrame, plan: Plan, tasks: int) -> DataFrame:
    """The same, and rows of the codecs that need the stored order (columns cloud, slice, pid, x, y, z as stored)."""

    def rows(got: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        held, now = [], None
        for batch in got:
            piece, *raw = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            edges = np.flatnonzero(piece[1:] != piece[:-1]) + 1
            for lo, hi in zip([0, *edges], [*edges, len(piece)], strict=True):
                if lo < hi:
                    if now is not None and now != piece[lo]:
                        yield from done(int(now), held)
                        held = []
                    now = piece[lo]
                    held.append([c[lo:hi] for c in raw])
        if held:
            yield from done(int(now), held)

    def done(piece: int, held: list) -> Iterator[tuple]:
        pid, *raw = (np.concatenate(c) for c in zip(*held, strict=True))
        raw = np.stack(raw)[:, np.argsort(pid, kind="stable")]
        cloud = piece % clouds
        yield from in_order(plan, cloud, unit(raw, plan.boxes[cloud]), raw)

    clouds = len(plan.boxes)
    # slices are few and large: with so many parts hardly two meet in one; the engine brings a slice's rows together by one number, which it does without comparing rows
    slice_, pid = F.coalesce("slice", F.lit(NO_SLICE)), F.coalesce("pid", F.lit((1 << 63) - 1))  # points without an id are a slice by themselves
    numbered = points.withColumns({"slice": slice_ * clouds + F.col("cloud"), "pid": pid})
    dealt = numbered.repartition(4 * tasks, "slice").sortWithinPartitions("slice")
    return dealt.select("slice", "pid", "x", "y", "z").mapInArrow(lambda got: batches(rows(got)), ROW)


def arrays(group: pa.Table) -> list[tuple[np.ndarray, np.ndarray | None]]:
    return [(unpacked(v, True), unpacked(c) if c else None) for v, c in zip(group["v"].to_pylist(), group["c"].to_pylist(), strict=True) if v]


def together(group: pa.Table) -> tuple[np.ndarray, np.ndarray | None]:
    """The rows' keys or values as one, in order, with counts."""
    held = arrays(group)
    if not held:
        return np.zeros(0, np.int64), None
    keys = np.concatenate([k for k, _ in held])
    if all(c is None for _, c in held):
        return counted(keys)
    return counted(keys, np.concatenate([np.ones(len(k), np.int64) if c is None else c for k, c in held]))


def by_shift(keys: np.ndarray, counts: np.ndarray, depth: int) -> np.ndarray:
    """Summed bit lengths of the counts of the nodes at each shift of a binary tree over keys of so many bits (0: the keys), but for the first of each."""
    apart = bit_length(keys[1:] ^ keys[:-1])  # neighbours are one node from this shift on
    if int(counts.sum()) > 2 * len(keys):  # level by level, on nodes with their counts
        out, n, bits = np.zeros(depth + 1, np.int64), counts, bit_length(counts)
        out[0] = bits[1:].sum()
        for shift in range(1, depth + 1):
            if len(apart) and apart.min() <= shift:
                left = apart > shift
                n = np.add.reduceat(n, np.concatenate([[0], np.flatnonzero(left) + 1]))
                apart, bits = apart[left], bit_length(n)
            out[shift] = bits[1:].sum()
        return out
    # a node that starts at a point holds m points at the shifts from the largest gap of the m - 1 after it, up to the gap before it; a count has
    # a bit for each power of two m that it reaches
    gaps = np.zeros(int(counts.sum()) - 1, np.int8)
    gaps[np.cumsum(counts[:-1]) - 1] = apart
    turns = np.zeros(depth + 2, np.int64)  # where nodes begin to hold m points, less where they end

    def add(begin: np.ndarray, end: np.ndarray) -> None:
        turns[:] += np.bincount(begin, minlength=depth + 2) - np.bincount(end, minlength=depth + 2)

    some = gaps[gaps > 0]
    add(np.zeros(len(some), np.int8), some)
    widest, m = gaps, 2  # widest: of m / 2 gaps
    while m <= len(gaps):
        half = m // 2
        most = np.maximum(widest[: len(gaps) - m + 2], widest[half - 1 :][: len(gaps) - m + 2])[1:]  # of m - 1 gaps after each point but the first
        some = np.flatnonzero(gaps[: len(most)] > most)
        add(most[some], gaps[some])
        widest, m = np.maximum(widest[: len(widest) - half], widest[half:]), 2 * m
    return np.cumsum(turns)[:-1]


def within(keys: np.ndarray, counts: np.ndarray, depth: int) -> int:
    """Bit lengths of the counts of all nodes of a binary tree over keys of so many bits, but for the leaves and the first node of each level."""
    return int(by_shift(keys, counts, depth)[1:].sum())


def trees(keys: np.ndarray, counts: np.ndarray, levels: int, wanted: tuple[int, ...] = ()) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray, list[tuple[int, int, int, int]]]:
    """Of a range of grid keys: pairs (parent's mask, mask) and their counts down to each of the ``wanted`` levels; summed bit lengths and nodes of the binary
    tree by level, the leaves last; edge nodes (tree, level, node, n or mask).

    The first and the last node of a level may go on in another range, and what depends on them is told to the driver.
    """
    edges, depth = [], 3 * levels
    bits = by_shift(keys, counts, depth)
    nodes = np.cumsum(np.bincount(bit_length(keys[1:] ^ keys[:-1]), minlength=depth + 2)[::-1])[::-1][1:]  # but for the first, at each shift
    before = np.concatenate([[0], np.cumsum(counts)])
    for shift in range(depth + 1):
        first, last = int(keys[0] >> shift), int(keys[-1] >> shift)
        n = int(before[np.searchsorted(keys, first + 1 << shift)])
        edges.append((0, depth - shift + 1, first, n))
        if last > first:
            n = int(before[-1] - before[np.searchsorted(keys, last << shift)])
            edges.append((0, depth - shift + 1, last, n))
            bits[shift] -= n.bit_length()
            nodes[shift] -= 1
    sizes = np.stack([bits[::-1], nodes[::-1]])
    if not wanted:
        return [], sizes, edges
    masks, parent, child = {}, {}, keys
    for level in range(levels, 0, -1):
        node = child >> 3
        mask = np.left_shift(np.uint8(1), (child & 7).astype(np.uint8))
        fresh = node[1:] != node[:-1]
        if fresh.all():  # no two children share a node
            parent[level + 1], masks[level], child = None, (node, mask), node
            continue
        first = np.concatenate([[0], np.flatnonzero(fresh) + 1])
        parent[level + 1] = np.concatenate([[0], np.cumsum(fresh)])  # of the nodes of the level below, by place
        masks[level] = (node[first], np.bitwise_or.reduceat(mask, first))
        child = node[first]
    pairs, seen = np.zeros(1 << 16, np.int64), {}
    for level in range(1, levels + 1):
        node, mask = masks[level]
        if level == 1:
            edges += [(1, 1, int(a), int(m)) for a, m in zip(node, mask, strict=True)]
        else:
            above, up = masks[level - 1][1], parent[level]
            if up is None:
                lo, hi = 1, len(above) - 1
            else:
                lo, hi = np.searchsorted(up, 0, "right"), np.searchsorted(up, len(above) - 1)
                above = above[up]
            if len(masks[level - 1][1]) < 2:
                lo = hi = len(node)
            told = [*range(lo), *range(hi, len(node))]
            edges += [(1, level, int(a), int(m)) for a, m in zip(node[told], mask[told], strict=True)]
            pairs += np.bincount(above[lo:hi].astype(np.uint16) << 8 | mask[lo:hi], minlength=1 << 16)
        if level in wanted:
            at = np.flatnonzero(pairs)
            seen[level] = (at, pairs[at])
    return [seen[level] for level in wanted], sizes, edges


def merge(plan: Plan, group: pa.Table) -> Iterator[tuple]:
    """Rows of a key range as histograms of what is coded, and its edges as facts; histograms as one; sums as one."""
    seq, kind, stream, bucket = (group[c][0].as_py() for c in ("seq", "kind", "stream", "bucket"))
    name = KINDS[kind]
    if name == "sums":
        of = lambda c: [np.frombuffer(x) for x in group[c].to_pylist()]
        yield seq, kind, FACTS, 0, np.sum(of("v"), 0).tobytes(), np.max(of("c"), 0).tobytes()
        return
    keys, counts = together(group)
    if name in STORED:
        yield seq, kind, stream, bucket, packed(keys, True), packed(counts)
        return
    n = np.ones(len(keys), np.int64) if counts is None else counts
    if name == "grid":
        served = plan.served(seq)
        wanted = tuple(plan.seqs[k][1].levels for k in served) if "octree_occupancy" in plan.kinds else ()
        pairs, sizes, edges = trees(keys, n, plan.seqs[seq][1].levels, wanted)
        for k, (v, c) in zip(served, pairs):  # noqa: B905 (none if only sizes of nodes are wanted)
            if len(v):
                yield k, kind, 0, 0, packed(v, True), packed(c)
        yield seq, kind, FACTS, bucket, plain(sizes), plain(edges)
        return
    yield seq, kind, FACTS, bucket, plain([keys[0], keys[-1], len(keys), int(n.sum())]), b""
    repeats = (np.zeros(1, np.int64), np.array([len(keys)])) if counts is None else (n - 1,)
    if name == "particle_block":
        for at, values in enumerate(coded(keys[1:], keys[:-1])):
            yield from histogram(plan, seq, name, at, values)
        yield from histogram(plan, seq, name, 2, *repeats)
    else:
        yield from histogram(plan, seq, name, 0, np.diff(keys))
        yield from histogram(plan, seq, name, 1, *repeats)


def coded(keys: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Residuals of block and place of a key of ``blocked`` after another."""
    block = (keys >> 9) - (before >> 9)
    return block, np.where(block == 0, (keys & 511) - (before & 511), keys & 511)


def costs(extra: dict[tuple[int, int, int, int], list[int]], group: pa.Table) -> list[float]:
    """What a merged histogram, with the driver's values, adds to its stream: t, sum of c log c, dictionary, the orders' sums; or other sums by codec."""
    at = tuple(group[c][0].as_py() for c in ("seq", "kind", "stream", "bucket"))
    v, c = together(group)
    c = np.ones(len(v), np.int64) if c is None else c
    more = np.array(extra.get(at, []), np.int64)
    if len(more):
        v, c = counted(np.concatenate([v, more]), np.concatenate([c, np.ones(len(more), np.int64)]))
        c = np.ones(len(v), np.int64) if c is None else c
    if KINDS[at[1]] == "float_bounded":
        n = c[:256]
        return [int((n > 0).sum()), int(n.sum()), int(c[256])]
    logs = float((c * np.log2(c)).sum()) if c.max() > 1 else 0.0
    if KINDS[at[1]] == "grid":
        total = np.bincount(v >> 8, c, 256)
        total = total[total > 0]
        return [float((total * np.log2(total)).sum()) - logs]
    before = np.concatenate([[0], np.cumsum(c)])
    powers = [1 << b for b in range(int(v[-1]).bit_length() + 1)]

    def at_least(bounds: list[int], sums: np.ndarray) -> int:
        """Summed over bounds what is at or over each; over all powers of two that is the sum of bit lengths."""
        return int((sums[-1] - sums[np.searchsorted(v, np.array(bounds, np.int64))]).sum())

    t = int(before[-1])
    lengths = [2 * (at_least([p - 1 << k for p in powers if p - 1 << k <= v[-1]], before) - t) + (1 + k) * t for k in ORDERS]
    zero = int(c[0]) if v[0] == 0 else 0
    return [t, logs, at_least(powers, np.arange(len(v) + 1)) + SYMBOL_BITS * len(v), *lengths, zero]


def boundaries(plan: Plan, facts: list) -> tuple[dict, dict, dict]:
    """Values of the ranges' first keys by histogram, sizes of the trees by sequence, and cells and points by sequence and codec."""
    extra, tree, count = defaultdict(list), defaultdict(lambda: [0, 0]), defaultdict(lambda: [0, 0])
    ranged = defaultdict(list)
    for r in facts:
        ranged[r.seq, KINDS[r.kind]].append((r.bucket, np.frombuffer(r.v, np.int64), np.frombuffer(r.c, np.int64)))
    for (seq, name), held in ranged.items():
        parts, kind = plan.parts(seq), KINDS.index(name)
        held.sort(key=lambda h: h[0])
        if name == "grid":
            edges = np.concatenate([e.reshape(-1, 4) for _, _, e in held])
            nodes, masks = defaultdict(int), defaultdict(int)
            for which, level, node, x in edges.tolist():
                if which == 0:
                    nodes[level, node] += x
                else:
                    masks[level, node] |= x
            bits, many = np.sum([v for _, v, _ in held], 0).reshape(2, -1)
            for (level, _), x in nodes.items():
                bits[level - 1] += x.bit_length()
                many[level - 1] += 1
            told = [(level, masks.get((level - 1, node >> 3), 0) * 256 + mask) for (level, node), mask in masks.items()]
            for k in plan.served(seq):
                levels = plan.seqs[k][1].levels
                tree[k] = [2 * int(bits[3 * levels]) - int(many[3 * levels]), int(bits[: 3 * levels].sum())]
                if told:  # else only sizes of nodes are wanted
                    extra[k, kind, 0, 0] = [pair for level, pair in told if level <= levels]
            continue
        before = 0
        for b, (_, (first, last, m, n), _) in enumerate(held):
            count[seq, name][0] += int(m)
            count[seq, name][1] += int(n)
            if name == "particle_block":
                values = [int(x[0]) for x in coded(np.array([first]), np.array([before]))] if b else [int(first >> 9), int(first & 511)]
            else:
                values = [int(first - before)]
            for stream, x in enumerate(values):
                extra[seq, kind, stream, x % parts].append(x)
            before = last
    return dict(extra), dict(tree), dict(count)


def stream_bits(t: int, logs: float, entries: int, lengths: list[int]) -> float:
    return min(t * math.log2(t) - logs + entries, *map(float, lengths))


def pipeline_bits(on: list[float], counts: list[float], m: int, n: int) -> float:
    """Counts apart or repeated keys (as residuals of 0), whichever is less."""
    t, logs, entries, *lengths, zero = on
    apart = stream_bits(t, logs, entries, lengths) + stream_bits(*counts[:3], counts[3:-1])
    again = n - m
    if again:
        log = lambda x: x * math.log2(x) if x else 0.0
        t, logs, entries = t + again, logs - log(zero) + log(zero + again), entries + (0 if zero else SYMBOL_BITS)
        lengths = [g + again * (1 + k) for g, k in zip(lengths, ORDERS, strict=True)]
    return min(apart, stream_bits(t, logs, entries, lengths))


def measured(rows: DataFrame, plan: Plan, tasks: int) -> list[dict]:
    """Of every sequence: points by ``n``, bits by codec, and with stored order sums and largest errors."""
    by = ("seq", "kind", "stream", "bucket")
    spark, held_rows = rows.sparkSession, "spark.sql.inMemoryColumnarStorage.batchSize"
    before = spark.conf.get(held_rows)
    spark.conf.set(held_rows, "16")  # a row is up to some MB, and a batch of the default's 10 000 would fill the heap
    ranges = rows.repartition(tasks, *by).groupBy(*by).applyInArrow(lambda g: table(list(merge(plan, g))), ROW).persist(StorageLevel.DISK_ONLY)
    try:
        facts = ranges.where(f"stream = {FACTS}").collect()  # some numbers a key range
        sums = {r.seq: (np.frombuffer(r.v), np.frombuffer(r.c)) for r in facts if KINDS[r.kind] == "sums"}
        extra, tree, count = boundaries(plan, [r for r in facts if KINDS[r.kind] != "sums"])
        # a stream of one key has no histogram but for the driver's value
        alone = [(*at, b"", b"") for at in extra]
        held = ranges.where(f"stream <> {FACTS}").unionByName(spark.createDataFrame(table(alone)))

        def cost(group: pa.Table) -> pa.Table:
            seq, kind, stream = (group[c][0].as_py() for c in by[:3])
            return pa.table({"seq": pa.array([seq], pa.int32()), "kind": pa.array([kind], pa.int32()), "stream": pa.array([stream], pa.int32()), "x": pa.array([costs(extra, group)], pa.list_(pa.float64()))})

        parts = held.repartition(tasks, *by).groupBy(*by).applyInArrow(cost, "seq int, kind int, stream int, x array<double>").collect()  # some numbers a histogram
    finally:
        spark.conf.set(held_rows, before)
        ranges.unpersist()
    streams: dict = {}
    for r in sorted(parts):
        at = streams.setdefault((r.seq, KINDS[r.kind]), {})
        at[r.stream] = [a + b for a, b in zip(at[r.stream], r.x, strict=True)] if r.stream in at else list(r.x)
    out = []
    for seq in range(len(plan.seqs)):
        bits, found = {}, {"seq": seq}
        for name in plan.kinds:
            s = streams.get((seq, name))
            if s is None:
                continue
            if name in PIPELINES:
                found["n"] = count[seq, name][1]
                bits[name] = pipeline_bits(s[0], s[1], *count[seq, name])
            elif name in ("particle_block", "array_predictive"):
                bits[name] = sum(stream_bits(*x[:3], x[3:-1]) for x in s.values())
            elif name == "grid":
                continue
            elif name == "float_bounded":
                small = lambda kinds, n: int(kinds - 1).bit_length() * n + kinds * 8 if kinds <= 16 else math.inf
                bits[name] = float(sum(min(n * 8, runs * 16, small(kinds, n)) for kinds, n, runs in s.values()))
        if seq in tree:
            leaves, inner = tree[seq]
            bits["kdtree_split"] = float(inner)
            if "octree_occupancy" in plan.kinds:
                bits["octree_occupancy"] = streams[seq, "grid"][0][0] + leaves
        found["bits"] = bits
        if seq in sums:
            found["sums"], found["tops"] = sums[seq]
        out.append(found)
    return out
