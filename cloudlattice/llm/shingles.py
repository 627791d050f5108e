"""Word shingles of many texts at once, as 64-bit hashes."""

from __future__ import annotations

import numpy as np

WORDS = 4
_GOLD, _MORE, _BASE = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))
#: Bytes laid end to end at once; only a single longer text makes more, and only its words and shingles do.
PIECE = 1 << 19


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _GOLD
    x = (x ^ (x >> np.uint64(29))) * _MORE
    return x ^ (x >> np.uint64(32))


def _table() -> np.ndarray:
    """A random number for each byte; A to Z count as a to z, white space as 0."""
    t = mixed(np.arange(1, 257, dtype=np.uint64))
    t[65:91] = t[97:123]
    return t


_BYTES = _table()
#: A random number for each byte, for words whose case counts.
CASED = mixed(np.arange(1, 257, dtype=np.uint64))
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base modulo 2^64 and of its inverse, by doubling."""
    out = []
    for base in (int(_BASE), pow(int(_BASE), -1, 1 << 64)):
        p = np.ones(1, np.uint64)
        while len(p) < n:
            p = np.concatenate([p, p * np.uint64(pow(base, len(p), 1 << 64))])
        out.append(p[:n])
    return out[0], out[1]


_held: list = [0, None, None]


def _words(data: np.ndarray, table: np.ndarray = _BYTES) -> tuple[np.ndarray, np.ndarray]:
    """(hash, first byte) of every word of bytes that neither start nor end inside a word."""
    if _held[0] < len(data) + 1:
        _held[:] = [len(data) + 1, *_powers(len(data) + 1)]
    power, inverse = _held[1], _held[2]
    edge = np.diff(np.concatenate([[True], _SPACE[data], [True]]).astype(np.int8))
    start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(table[data] * inverse[: len(data)], dtype=np.uint64)])
    return mixed((total[end] - total[start]) * power[start] + (end - start).astype(np.uint64)), start


def word_hashes(data: np.ndarray, table: np.ndarray = _BYTES) -> tuple[np.ndarray, np.ndarray]:
    """``_words`` of any number of bytes, cut at white space into pieces, so that memory follows ``PIECE`` and the longest word."""
    found, at = [], 0
    while at < len(data):
        stop = at + PIECE
        if stop < len(data):
            back = np.flatnonzero(_SPACE[data[at:stop]])
            while not len(back) and stop < len(data):  # one word is longer than a piece
                ahead = np.flatnonzero(_SPACE[data[stop : stop + PIECE]])
                back, stop = ahead[:1] + (stop - at), stop + PIECE
            stop = at + int(back[-1]) + 1 if len(back) else len(data)
        word, start = _words(data[at:stop], table)
        found.append((word, start + at))
        at = stop
    if not found:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def shingle_sets(texts: list[bytes], words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(text number, shingle hash), distinct and sorted by both.

    A text of fewer words than ``words`` has one shingle, its whole sequence; a text
    without words has none.
    """
    word, start = word_hashes(np.frombuffer(b"\n".join(texts) + b"\n", np.uint8))
    if not len(word):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    text = np.searchsorted(np.cumsum([len(t) + 1 for t in texts]), start, "right")
    shingle = np.zeros(max(len(word) - words + 1, 0), np.uint64)
    for k in range(words):
        shingle = mixed(shingle * _MORE + word[k : k + len(shingle)])
    counts = np.bincount(text, minlength=len(texts))
    sizes = np.where(counts >= words, counts - words + 1, counts > 0)
    edge = np.concatenate([[0], np.cumsum(sizes)])
    found_text, found = np.repeat(np.arange(len(texts)), sizes), np.empty(edge[-1], np.uint64)
    whole = counts[found_text] >= words
    if len(shingle):
        found[whole] = shingle[text[: len(shingle)] == text[words - 1 :]]
    short = found_text[~whole]
    first = np.searchsorted(text, short)
    own = np.zeros(len(short), np.uint64)
    for k in range(words - 1):
        more = k < counts[short]
        own[more] = mixed(own[more] * _MORE + word[first[more] + k])
    found[~whole] = mixed(own + counts[short].astype(np.uint64))
    for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        found[a:b].sort()
    new = np.ones(len(found), bool)
    new[1:] = (found[1:] != found[:-1]) | (found_text[1:] != found_text[:-1])
    return found_text[new], found[new]
