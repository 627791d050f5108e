"""Runs of suffix positions that share an anchor, for many texts at once.

The anchor of a window of ``length`` bytes is its ``K``-byte string of the smallest
hash, the first of equals, so equal windows have their anchors at equal places.
Neighbouring windows mostly share one; a run is a longest sequence of start
positions with the same anchor. About two runs start in ``length`` bytes.
"""

from __future__ import annotations

import numpy as np
import xxhash

K = 16
_MIX = np.uint64(0x9E3779B97F4A7C15)
_MORE = np.uint64(0xC2B2AE3D27D4EB4F)
#: Bytes that are hashed at once; windows of a longer text are taken piece by piece.
CHUNK = 1 << 20
_PLACE = np.uint64(21)


def hashes(data: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the K bytes from each position; K is 16."""
    words = np.ndarray((len(data) - 7,), "<u8", data, strides=(1,))
    mixed = words * _MIX
    mixed ^= mixed >> np.uint64(29)
    h = (mixed[:-8] * _MORE) ^ mixed[8:]
    h *= _MIX
    h ^= h >> np.uint64(32)
    h *= _MORE
    return h


def sliding_minimum(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` neighbours, by block prefix and suffix minima."""
    n = len(x) - width + 1
    short = -len(x) % width
    blocks = np.concatenate([x, np.full(short, np.iinfo(x.dtype).max, x.dtype)]).reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])


def runs(data: np.ndarray, ends: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first start, number of starts, anchor place) of every run in texts laid end to end.

    ``ends`` holds where each text ends; places count from the start of ``data``.
    """
    if len(data) < length:
        return (np.zeros(0, np.int64),) * 3
    firsts, counts, places = [], [], []
    starts = np.concatenate([[0], ends[:-1]])
    width = length - K + 1
    for at in range(0, len(data) - length + 1, CHUNK):
        piece = data[at : at + CHUNK + length - 1]
        h = hashes(piece)
        h = (h >> _PLACE << _PLACE) | np.arange(len(h), dtype=np.uint64)
        place = (sliding_minimum(h, width) & np.uint64((1 << 21) - 1)).astype(np.int64) + at
        where = np.arange(at, at + len(place))
        change = np.empty(len(place), bool)
        change[0] = True
        np.not_equal(place[1:], place[:-1], out=change[1:])
        inside = starts[(starts > at) & (starts < at + len(place))]
        change[inside - at] = True
        # windows that would cross the end of their text
        lo = np.searchsorted(ends, at, "right")
        cut = ends[lo:] - length + 1
        stops = cut[(cut > at) & (cut < at + len(place))]
        change[stops - at] = True
        first = where[change]
        count = np.diff(np.append(first, at + len(place)))
        text = np.searchsorted(ends, first, "right")
        good = first + length <= ends[text]
        firsts.append(first[good])
        counts.append(count[good])
        places.append(place[change][good])
    return np.concatenate(firsts), np.concatenate(counts), np.concatenate(places)


def digests(data: bytes, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """128-bit hashes of byte ranges as two columns of 64 bits."""
    view = memoryview(data)
    got = b"".join([xxhash.xxh3_128_digest(view[a : a + n]) for a, n in zip(first.tolist(), size.tolist(), strict=True)])
    return np.frombuffer(got, "<i8").reshape(-1, 2)
