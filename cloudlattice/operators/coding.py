"""Entropy coders and byte coders on numpy arrays: the inside of a chunk."""

from __future__ import annotations

import heapq
import zlib

import numpy as np

MOST_BITS = 24

try:
    import zstandard
except ImportError:  # the standard library's coder takes its place
    zstandard = None


def huffman_lengths(symbols: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Optimal code lengths; ties go to the smaller weight, then the smaller symbol, so lengths are repeatable.

    Longer codes than ``MOST_BITS`` are avoided by halving the counts until they fit.
    """
    if len(symbols) == 0:
        return np.zeros(0, np.int64)
    if len(symbols) == 1:
        return np.ones(1, np.int64)
    weights = counts.astype(np.int64)
    while True:
        n = len(symbols)
        heap = [(int(w), k) for k, w in enumerate(weights)]
        heapq.heapify(heap)
        up = [0] * (2 * n - 1)
        for node in range(n, 2 * n - 1):
            (wa, a), (wb, b) = heapq.heappop(heap), heapq.heappop(heap)
            up[a] = up[b] = node
            heapq.heappush(heap, (wa + wb, node))
        depth = [0] * (2 * n - 1)
        for node in range(2 * n - 3, -1, -1):
            depth[node] = depth[up[node]] + 1
        lengths = np.array(depth[:n], np.int64)
        if lengths.max() <= MOST_BITS:
            return lengths
        weights = (weights + 1) // 2


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Codes by (length, symbol order)."""
    codes = np.zeros(len(lengths), np.int64)
    code = last = 0
    for k in np.lexsort((np.arange(len(lengths)), lengths)):
        code <<= int(lengths[k]) - last
        last = int(lengths[k])
        codes[k] = code
        code += 1
    return codes


def pack(codes: np.ndarray, lengths: np.ndarray) -> bytes:
    """Codes one after another, highest bit first."""
    if not len(codes):
        return b""
    ends = np.cumsum(lengths)
    bits = np.zeros(int(ends[-1]), np.uint8)
    for b in range(int(lengths.max())):
        has = lengths > b
        bits[ends[has] - 1 - b] = codes[has] >> b & 1
    return np.packbits(bits).tobytes()


def bits_at(bits: np.ndarray, start: np.ndarray, width: np.ndarray | int) -> np.ndarray:
    """Numbers of ``width`` bits from places ``start``, highest bit first."""
    width = np.broadcast_to(width, start.shape)
    out = np.zeros(len(start), np.int64)
    for b in range(int(width.max(initial=0))):
        has = width > b
        out[has] = out[has] << 1 | bits[start[has] + b]
    return out


def walked(step: np.ndarray, n: int) -> np.ndarray:
    """The first ``n`` places from 0 on, each ``step`` of its own after the last.

    Places are followed for a while one by one; then whole stretches at a time, by
    steps that span 64 codes.
    """
    stride = 64
    if n <= 4 * stride:
        at, out, steps = 0, [], step.tolist()
        for _ in range(n):
            out.append(at)
            at += steps[at] if at < len(steps) else 0
        return np.array(out, np.int64)
    top = len(step)
    ahead = np.minimum(np.arange(top + 1) + np.append(step, 0), top)
    far = ahead
    for _ in range(6):  # 2^6 codes
        far = far[far]
    heads, at, jumps = [], 0, far.tolist()
    for _ in range(-(-n // stride)):
        heads.append(at)
        at = jumps[at]
    rows = [np.array(heads, np.int64)]
    for _ in range(stride - 1):
        rows.append(ahead[rows[-1]])
    return np.stack(rows, 1).ravel()[:n]


def huffman_decode(data: bytes, n: int, symbols: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Table look-up of the next ``MOST`` bits at every bit place, then a walk over places."""
    if n == 0:
        return np.zeros(0, np.int64)
    most = int(lengths.max())
    codes = canonical(lengths)
    order = np.argsort(codes << (most - lengths), kind="stable")
    first = (codes << (most - lengths))[order]
    bits = np.concatenate([np.unpackbits(np.frombuffer(data, np.uint8)), np.zeros(most, np.uint8)])
    window = np.zeros(len(bits) - most, np.int32)
    for b in range(most):
        window = window << 1 | bits[b : b + len(window)]
    hit = order[np.searchsorted(first, window, "right") - 1]
    return symbols[hit[walked(lengths[hit], n)]]


def bit_lengths(x: np.ndarray) -> np.ndarray:
    """Bits of numbers above 0; a float's exponent is one too high where rounding carried it over."""
    length = np.frexp(x.astype(np.float64))[1].astype(np.int64)
    return length - ((x >> (length - 1)) == 0)


def varints(values: np.ndarray) -> bytes:
    """Seven bits a byte, lowest first; for values that are not negative."""
    values = np.asarray(values, np.int64)
    size = np.maximum(1, -(-np.where(values > 0, bit_lengths(np.maximum(values, 1)), 0) // 7))
    ends = np.cumsum(size)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    for b in range(int(size.max(initial=0))):
        has = size > b
        out[ends[has] - size[has] + b] = (values[has] >> (7 * b) & 127) | np.where(size[has] > b + 1, 128, 0)
    return out.tobytes()


def read_varints(data: bytes, n: int, at: int = 0) -> tuple[np.ndarray, int]:
    """``n`` numbers from byte ``at`` on, and where they end."""
    raw = np.frombuffer(data, np.uint8)[at : at + 10 * n].astype(np.int64)
    last = np.flatnonzero(raw < 128)[:n]
    if not n:
        return np.zeros(0, np.int64), at
    first = np.concatenate([[0], last[:-1] + 1])
    place = np.arange(int(last[-1]) + 1)
    shift = 7 * (place - np.repeat(first, last - first + 1))
    return np.add.reduceat((raw[: len(place)] & 127) << shift, first), at + len(place)


def golomb_bits(values: np.ndarray, k: int) -> int:
    return int((2 * (bit_lengths((values >> k) + 1) - 1) + 1 + k).sum()) if len(values) else 0


def golomb_order(values: np.ndarray) -> int:
    return min(range(40), key=lambda k: (golomb_bits(values, k), k)) if len(values) else 0


def golomb_encode(values: np.ndarray, k: int) -> bytes:
    """For each value a zero for every bit above ``k`` + 1, then the bits of the value plus 2^k."""
    x = values + (1 << k)
    if not len(x):
        return b""
    length = bit_lengths(x)
    ends = np.cumsum(2 * length - 1 - k)
    bits = np.zeros(int(ends[-1]), np.uint8)
    for b in range(int(length.max())):
        has = length > b
        bits[ends[has] - 1 - b] = x[has] >> b & 1
    return np.packbits(bits).tobytes()


def golomb_decode(data: bytes, n: int, k: int) -> np.ndarray:
    if n == 0:
        return np.zeros(0, np.int64)
    bits = np.unpackbits(np.frombuffer(data, np.uint8))
    place = np.arange(len(bits), dtype=np.int64)
    one = np.minimum.accumulate(np.where(bits == 1, place, len(bits))[::-1])[::-1]  # the next one from each place
    at = walked(np.minimum(2 * (one - place) + 1 + k, len(bits)), n)
    return bits_at(bits, one[at], one[at] - at + 1 + k) - (1 << k)


def escaped(symbols: np.ndarray, where: np.ndarray, counts: np.ndarray, values: np.ndarray, least: int = 2) -> tuple[bytes, bytes]:
    """Dictionary and bits in which symbols rarer than ``least`` share the last code; their plain bits follow all codes."""
    own = np.flatnonzero(counts >= least)
    code = np.full(len(symbols), len(own))
    code[own] = np.arange(len(own))
    code = code[where] if len(where) else np.zeros(0, np.int64)
    rare = values[code == len(own)]
    kept = symbols[own]
    lengths = huffman_lengths(np.arange(len(own) + 1), np.append(counts[own], max(len(rare), 1)))
    width = int(rare.max(initial=0)).bit_length()
    body = pack(canonical(lengths)[code], lengths[code])
    head = varints(np.array([len(kept)])) + varints(np.diff(kept, prepend=0)) + lengths.astype(np.uint8).tobytes() + bytes([width]) + varints(np.array([len(body)]))
    return head, body + (pack(rare, np.full(len(rare), width)) if width and len(rare) else b"")


def unescaped(data: bytes, n: int) -> np.ndarray:
    count, at = read_varints(data, 1)
    gaps, at = read_varints(data, int(count[0]), at)
    lengths = np.frombuffer(data[at : at + len(gaps) + 1], np.uint8).astype(np.int64)
    width = data[at + len(gaps) + 1]
    size, at = read_varints(data, 1, at + len(gaps) + 2)
    code = huffman_decode(data[at : at + int(size[0])], n, np.arange(len(gaps) + 1), lengths)
    out = np.append(np.cumsum(gaps), 0)[code]
    rare = code == len(gaps)
    if rare.any():
        bits = np.unpackbits(np.frombuffer(data[at + int(size[0]) :], np.uint8))
        out[rare] = bits_at(bits, np.arange(int(rare.sum())) * width, width) if width else 0
    return out


class Stream:
    """One coded stream: a flag, a dictionary or an order, and the bits."""

    def __init__(self, kind: str, head: bytes, body: bytes):
        self.kind, self.head, self.body = kind, head, body

    @classmethod
    def encode(cls, values: np.ndarray, entropy: str = "huffman") -> Stream:
        symbols, where, counts = np.unique(values, return_inverse=True, return_counts=True)
        if entropy in ("huffman", "auto"):
            lengths = huffman_lengths(symbols, counts)
            head = varints(np.array([len(symbols)])) + varints(np.diff(symbols, prepend=0)) + lengths.astype(np.uint8).tobytes()
            body = pack(canonical(lengths)[where], lengths[where])
            if entropy == "huffman" or len(head) + len(body) <= 1 + golomb_bits(values, golomb_order(values)) // 8:
                return cls("h", head, body)
        if entropy == "escape":
            return cls("e", *escaped(symbols, where, counts, values))
        if entropy == "fixed":
            width = int(values.max(initial=0)).bit_length()
            return cls("f", bytes([width]), pack(values, np.full(len(values), width)) if width else b"")
        k = golomb_order(values)
        return cls("g", bytes([k]), golomb_encode(values, k))

    @staticmethod
    def decode(data: bytes, n: int) -> np.ndarray:
        kind, data = data[:1], data[1:]
        if kind == b"g":
            return golomb_decode(data[1:], n, data[0])
        if kind == b"e":
            return unescaped(data, n)
        if kind == b"f":
            width = data[0]
            return bits_at(np.unpackbits(np.frombuffer(data[1:], np.uint8)), np.arange(n) * width, width)
        count, at = read_varints(data, 1)
        gaps, at = read_varints(data, int(count[0]), at)
        lengths = np.frombuffer(data[at : at + len(gaps)], np.uint8).astype(np.int64)
        return huffman_decode(data[at + len(gaps) :], n, np.cumsum(gaps), lengths)

    def bytes(self) -> bytes:
        return self.kind.encode() + self.head + self.body


def squeeze(data: bytes, backend: str = "zstd") -> bytes:
    """The byte coder's output if that is smaller, behind a flag."""
    if backend == "zstd" and zstandard:
        packed, flag = zstandard.ZstdCompressor(level=3).compress(data), b"z"
    elif backend == "none":
        return b"n" + data
    else:
        packed, flag = zlib.compress(data, 6), b"l"
    return flag + packed if len(packed) < len(data) else b"n" + data


def unsqueeze(data: bytes) -> bytes:
    if data[:1] == b"z":
        return zstandard.ZstdDecompressor().decompress(data[1:])
    return zlib.decompress(data[1:]) if data[:1] == b"l" else data[1:]
