"""Orders of cells: row-major, block-wise, Z-order and Hilbert, with their inverses.

Keys of lattice cells come in two layouts. ``raw`` uses the coordinates as they are;
``packed`` halves them and adds the parity bit, so that the index has no gaps
(the three coordinates of a body-centred-cubic cell have one parity).
"""

from __future__ import annotations

from functools import lru_cache, reduce
from itertools import permutations, product

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 21
# fixed values: the masks that spread 21 bits to every third place
SPREAD = ((32, 0x1F00000000FFFF), (16, 0x1F0000FF0000FF), (8, 0x100F00F00F00F00F), (4, 0x10C30C30C30C30C3), (2, 0x1249249249249249))


def morton_key(cell: list[Column], bits: int = BITS) -> Column:
    """Bits of i, j and k in turn, i lowest, as one expression; for tables see ``with_morton``."""
    terms = [F.shiftleft(F.shiftright(c, b).bitwiseAND(F.lit(1)), 3 * b + a) for b in range(bits) for a, c in enumerate(cell)]
    return reduce(lambda x, y: x.bitwiseOR(y), terms)


def with_morton(df: DataFrame, cell: dict[str, Column], name: str = "key") -> DataFrame:
    """Add the Z-order key of three coordinates.

    Every step of the spreading is a projection of its own: one expression of all
    steps would repeat its parts until the generated code grew too large.
    """
    df = df.withColumns({f"_{a}": c.cast("long") for a, c in cell.items()})
    for shift, mask in SPREAD:
        df = df.withColumns({f"_{a}": F.col(f"_{a}").bitwiseOR(F.shiftleft(f"_{a}", shift)).bitwiseAND(F.lit(mask)) for a in cell})
    i, j, k = (F.col(f"_{a}") for a in cell)
    return df.withColumn(name, i.bitwiseOR(F.shiftleft(j, 1)).bitwiseOR(F.shiftleft(k, 2))).drop(*[f"_{a}" for a in cell])


def without_morton(df: DataFrame, key: Column) -> DataFrame:
    """Add i, j, k of a Z-order key, step by step."""
    df = df.withColumns({c: F.shiftrightunsigned(key, a).bitwiseAND(F.lit(SPREAD[-1][1])) for a, c in enumerate("ijk")})
    for shift, mask in zip([s for s, _ in SPREAD[::-1]], [m for _, m in SPREAD[-2::-1]] + [(1 << BITS) - 1], strict=True):
        df = df.withColumns({c: F.col(c).bitwiseOR(F.shiftrightunsigned(c, shift)).bitwiseAND(F.lit(mask)) for c in "ijk"})
    return df


def row_major_key(cell: list[Column], nx: int, ny: int) -> Column:
    return (cell[2] * F.lit(ny) + cell[1]) * F.lit(nx) + cell[0]


def block_row_major_key(cell: list[Column], nx: int, ny: int, bits: int = 3) -> Column:
    """Row-major over blocks of edge 2^bits, then row-major inside the block."""
    edge = 1 << bits
    big = [F.shiftright(c, bits) for c in cell]
    small = [c.bitwiseAND(F.lit(edge - 1)) for c in cell]
    bx, by = -(-nx // edge), -(-ny // edge)
    return F.shiftleft(row_major_key(big, bx, by), 3 * bits).bitwiseOR(row_major_key(small, edge, edge))


@lru_cache
def hilbert_tables() -> tuple[tuple[int, ...], tuple[int, ...]]:
    """(digit, next state) by 8 * state + octant, found from the rule itself.

    A state is a signed permutation of the axes applied to one base path over the
    octants. Each octant's own state is searched for so that every sub-path ends
    beside the start of the next one. Octants have axis x in their lowest bit.
    """
    base = [(0, 0, 0), (0, 0, 1), (0, 1, 1), (0, 1, 0), (1, 1, 0), (1, 1, 1), (1, 0, 1), (1, 0, 0)]
    moves = [(p, s) for p in permutations(range(3)) for s in product((0, 1), repeat=3)]
    apply = lambda g, c: tuple(c[g[0][a]] ^ g[1][a] for a in range(3))
    ends = {g: (apply(g, base[0]), apply(g, base[-1])) for g in moves}

    def search(d: int, at: tuple[int, ...] | None, chosen: list) -> list | None:
        if d == 8:
            return chosen if ends[chosen[-1]][1] == base[-1] else None
        for g in moves:
            start, end = ends[g]
            if d == 0 and start != base[0] or at is not None and start != at:
                continue
            following = None
            if d < 7:
                axis = next(a for a in range(3) if base[d][a] != base[d + 1][a])
                if end[axis] != base[d + 1][axis]:
                    continue
                following = tuple(1 - end[a] if a == axis else end[a] for a in range(3))
            if found := search(d + 1, following, [*chosen, g]):
                return found
        return None

    inner = search(0, None, [])
    compose = lambda g, h: next(m for m in moves if all(apply(m, c) == apply(g, apply(h, c)) for c in base))
    states, digit, following = [moves[0]], [], []
    for g in states:
        path = [apply(g, c) for c in base]
        for octant in range(8):
            d = path.index(tuple(octant >> a & 1 for a in range(3)))
            after = compose(g, inner[d])
            if after not in states:
                states.append(after)
            digit.append(d)
            following.append(states.index(after))
    return tuple(digit), tuple(following)


def hilbert_key(cell: list[Column], bits: int) -> Column:
    """Walk from the highest bits down; the accumulator holds the key so far and the state in its low five bits."""
    digit, following = (F.array(*[F.lit(v) for v in t]) for t in hilbert_tables())

    def step(acc: Column, level: Column) -> Column:
        octant = F.lit(0)
        for a, c in enumerate(cell):
            octant = octant + F.pmod(F.floor(c / F.pow(F.lit(2.0), level)), F.lit(2)) * (1 << a)
        at = (acc.bitwiseAND(F.lit(31)) * 8 + octant + 1).cast("int")
        return (F.floor(acc / 32) * 8 + F.element_at(digit, at)) * 32 + F.element_at(following, at)

    levels = F.array(*[F.lit(b) for b in range(bits - 1, -1, -1)])
    return F.floor(F.aggregate(levels, F.lit(0).cast("long"), lambda acc, level: step(acc, level).cast("long")) / 32).cast("long")


def hilbert_numpy(i: np.ndarray, j: np.ndarray, k: np.ndarray, bits: int) -> np.ndarray:
    digit, following = (np.array(t, np.int64) for t in hilbert_tables())
    key, state = np.zeros(len(i), np.int64), np.zeros(len(i), np.int64)
    for b in range(bits - 1, -1, -1):
        at = state * 8 + ((i >> b & 1) | (j >> b & 1) << 1 | (k >> b & 1) << 2)
        key, state = key << 3 | digit[at], following[at]
    return key


def hilbert_cells_numpy(key: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    digit, following = (np.array(t, np.int64).reshape(-1, 8) for t in hilbert_tables())
    octants = np.argsort(digit, axis=1)
    out, state = np.zeros((3, len(key)), np.int64), np.zeros(len(key), np.int64)
    for b in range(bits - 1, -1, -1):
        octant = octants[state, key >> (3 * b) & 7]
        for a in range(3):
            out[a] |= (octant >> a & 1) << b
        state = following[state, octant]
    return out[0], out[1], out[2]


def row_major_cells_numpy(key: np.ndarray, nx: int, ny: int) -> list[np.ndarray]:
    return [key % nx, key // nx % ny, key // (nx * ny)]


def cells_numpy(key: np.ndarray, curve: str, extent: int) -> list[np.ndarray]:
    """The cells of keys that ``key_of`` made with this extent."""
    if curve == "row_major":
        return row_major_cells_numpy(key, extent, extent)
    if curve == "block":
        across = -(-extent // 8)
        big, small = row_major_cells_numpy(key >> 9, across, across), row_major_cells_numpy(key & 511, 8, 8)
        return [b * 8 + s for b, s in zip(big, small, strict=True)]
    if curve == "hilbert":
        return list(hilbert_cells_numpy(key, max(1, (extent - 1).bit_length())))
    if curve != "morton":
        raise ValueError(f"no curve named {curve}")
    cell = [np.zeros(len(key), np.int64) for _ in range(3)]
    for b in range(BITS):
        for a in range(3):
            cell[a] |= (key >> (3 * b + a) & 1) << b
    return cell


def hilbert_udf(bits: int):
    """Vectorised over Arrow batches; for cells, never for points."""
    @F.pandas_udf("long")
    def key(i: pd.Series, j: pd.Series, k: pd.Series) -> pd.Series:
        return pd.Series(hilbert_numpy(i.to_numpy(), j.to_numpy(), k.to_numpy(), bits))

    return key


def key_of(cell: list[Column], curve: str, extent: int, udf: bool = False) -> Column:
    """``extent``: one more than the largest coordinate on any axis."""
    bits = max(1, (extent - 1).bit_length())
    if bits > BITS:
        raise ValueError(f"{bits} bits an axis do not fit a 63-bit key; use a larger bound")
    if curve == "row_major":
        return row_major_key(cell, extent, extent)
    if curve == "block":
        return block_row_major_key(cell, extent, extent)
    if curve == "morton":
        return morton_key(cell)
    if curve == "hilbert":
        return hilbert_udf(bits)(*cell) if udf else hilbert_key(cell, bits)
    raise ValueError(f"no curve named {curve}")


def attach(cells: DataFrame, curve: str, extent: int, layout: str = "packed", udf: bool = False) -> DataFrame:
    """Add ``key`` to a table of cells i, j, k (not negative)."""
    raw = layout == "raw"
    place = {c: F.col(c).cast("long") if raw else F.shiftright(F.col(c).cast("long"), 1) for c in "ijk"}
    if curve == "morton":
        if max(1, (extent - 1).bit_length()) > BITS + (not raw):
            raise ValueError("the cells do not fit a 63-bit key; use a larger bound")
        keyed = with_morton(cells, place)
    else:
        held = cells.withColumns({f"_{c}": v for c, v in place.items()})
        keyed = held.withColumn("key", key_of([F.col(f"_{c}") for c in "ijk"], curve, extent if raw else (extent + 1) // 2, udf)).drop("_i", "_j", "_k")
    return keyed if raw else keyed.withColumn("key", F.shiftleft("key", 1).bitwiseOR(F.col("i").cast("long").bitwiseAND(F.lit(1))))


def morton_unattach(keys: DataFrame, layout: str = "packed") -> DataFrame:
    """i, j, k of Z-order keys."""
    if layout == "raw":
        return without_morton(keys, F.col("key"))
    bit = F.col("key").bitwiseAND(F.lit(1))
    return without_morton(keys, F.shiftright("key", 1)).withColumns({c: F.col(c) * 2 + bit for c in "ijk"})
