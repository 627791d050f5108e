"""Lattices and their closed forms.

``G`` is the dimensionless second moment of a cell (the mean squared error per axis
for unit volume): mean squared error is 3 G V^(2/3) in three dimensions.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

AXES = ("x", "y", "z")
#: Three four-byte floats, the size of a raw point in every ratio.
RAW_BYTES = 12
#: Keeps round-off from carrying an error over the bound.
GUARD = 1 - 2.0**-40


def _mean_of_polyhedron(faces: list[list[tuple[float, float, float]]]) -> float:
    """G of a convex polyhedron around the origin, by cutting it into tetrahedra with their apex there."""
    volume = moment = 0.0
    for face in faces:
        for k in range(1, len(face) - 1):
            a, b, c = face[0], face[k], face[k + 1]
            v = abs(a[0] * (b[1] * c[2] - b[2] * c[1]) - a[1] * (b[0] * c[2] - b[2] * c[0]) + a[2] * (b[0] * c[1] - b[1] * c[0])) / 6
            s = [p + q + r for p, q, r in zip(a, b, c, strict=True)]
            moment += v / 20 * (sum(x * x for p in (a, b, c) for x in p) + sum(x * x for x in s))
            volume += v
    return moment / volume / volume ** (2 / 3) / 3


def _faces(points: list[tuple[float, float, float]]) -> list[list[tuple[float, float, float]]]:
    """Faces of the hull of points in general symmetric position, each in turning order."""
    found: dict[tuple, list[tuple[float, float, float]]] = {}
    n = len(points)
    for i in range(n):
        for j in range(i + 1, n):
            for k in range(j + 1, n):
                a, b, c = points[i], points[j], points[k]
                u, w = [q - p for p, q in zip(a, b, strict=True)], [q - p for p, q in zip(a, c, strict=True)]
                normal = (u[1] * w[2] - u[2] * w[1], u[2] * w[0] - u[0] * w[2], u[0] * w[1] - u[1] * w[0])
                size = math.sqrt(sum(x * x for x in normal))
                if size < 1e-9:
                    continue
                normal = tuple(x / size for x in normal)
                level = sum(x * y for x, y in zip(normal, a, strict=True))
                if level < 0:
                    normal, level = tuple(-x for x in normal), -level
                if all(sum(x * y for x, y in zip(normal, p, strict=True)) <= level + 1e-9 for p in points):
                    key = tuple(round(x, 6) for x in normal)
                    found[key] = [p for p in points if abs(sum(x * y for x, y in zip(normal, p, strict=True)) - level) < 1e-9]
    faces = []
    for normal, face in found.items():
        centre = [sum(p[i] for p in face) / len(face) for i in range(3)]
        first = [p - q for p, q in zip(face[0], centre, strict=True)]
        other = (normal[1] * first[2] - normal[2] * first[1], normal[2] * first[0] - normal[0] * first[2], normal[0] * first[1] - normal[1] * first[0])
        turn = lambda p: math.atan2(sum((x - c) * y for x, c, y in zip(p, centre, other, strict=True)), sum((x - c) * y for x, c, y in zip(p, centre, first, strict=True)))  # noqa: E731,B023
        faces.append(sorted(face, key=turn))
    return faces


def _signs(*points: tuple[float, float, float]) -> list[tuple[float, float, float]]:
    out = {(a * x, b * y, c * z) for x, y, z in points for a in (1, -1) for b in (1, -1) for c in (1, -1)}
    return sorted(out)


def second_moment(shape: str) -> float:
    """G of a named shape: closed form where there is one, else by tetrahedra."""
    golden = (1 + math.sqrt(5)) / 2
    closed = {
        "cube": 1 / 12,
        "hexagonal_prism": ((5 / (36 * math.sqrt(3))) ** 2 / 12) ** (1 / 3),
        "rhombic_dodecahedron": 2 ** (-11 / 3),
        "truncated_octahedron": 19 / (192 * 2 ** (1 / 3)),
        "sphere": 0.2 * (3 / (4 * math.pi)) ** (2 / 3),
    }
    if shape in closed:
        return closed[shape]
    hulls = {
        "tetrahedron": [(1, 1, 1), (1, -1, -1), (-1, 1, -1), (-1, -1, 1)],
        "dodecahedron": _signs((1, 1, 1), (0, 1 / golden, golden), (1 / golden, golden, 0), (golden, 0, 1 / golden)),
        "icosahedron": _signs((0, 1, golden), (1, golden, 0), (golden, 0, 1)),
    }
    return _mean_of_polyhedron(_faces([tuple(map(float, p)) for p in hulls[shape]]))


#: Cell volume for a covering radius of 1, for the shapes that fill space.
COVERING = {"cube": 8 / (3 * math.sqrt(3)), "hexagonal_prism": 2.0, "rhombic_dodecahedron": 2.0, "truncated_octahedron": 32 / (5 * math.sqrt(5))}
SHAPES = ("tetrahedron", "cube", "hexagonal_prism", "rhombic_dodecahedron", "truncated_octahedron", "dodecahedron", "icosahedron", "sphere")


def expected_mse(shape: str, eps: float) -> float:
    """Mean squared error of a uniform point for covering radius ``eps``."""
    return 3 * second_moment(shape) * (COVERING[shape] * eps**3) ** (2 / 3)


def compare_at_equal_volume(a: str, b: str) -> int:
    """-1, 0 or 1 as ``a`` has a smaller, equal or larger error than ``b`` at one rate."""
    ga, gb = second_moment(a), second_moment(b)
    return (ga > gb) - (ga < gb)


def tiling_error(parts: list[tuple[float, float]]) -> tuple[float, float]:
    """Error of a tiling of cells (G, V) and of as many equal cells of the best G and the same volume."""
    mixed = sum(3 * g * v ** (5 / 3) for g, v in parts)
    volume, best = sum(v for _, v in parts), min(g for g, _ in parts)
    return mixed, len(parts) * 3 * best * (volume / len(parts)) ** (5 / 3)


def polyhedra() -> list[dict]:
    """Comparison of shapes: G, gain in cell volume and share of cells saved against cubes, covering volume against cubes."""
    cube = second_moment("cube")
    rows = []
    for shape in SHAPES:
        g = second_moment(shape)
        gain = (cube / g) ** 1.5
        rows.append({"shape": shape, "g": g, "volume_gain": gain, "cells_saved": 1 - 1 / gain, "covering_gain": COVERING[shape] / COVERING["cube"] if shape in COVERING else None})
    return rows


@dataclass(frozen=True)
class LatticeSpec:
    """A lattice for a cloud: scale, origin and the affine map of the axes.

    A point p becomes u = (p - low) / span * factor; ``factor`` is in lattice units.
    ``span`` is 1 per axis for raw scale; a constant axis has span 0 and maps to 0.
    """

    eps: float
    shape: str = "bcc"
    low: tuple[float, float, float] = (0.0, 0.0, 0.0)
    span: tuple[float, float, float] = (1.0, 1.0, 1.0)
    diagonal: float = math.sqrt(3)
    guard: bool = False

    @property
    def spacing(self) -> float:
        """Length of a lattice unit: cells have covering radius ``eps``."""
        eps = self.eps * (GUARD if self.guard else 1.0)
        return {"bcc": 2 * eps / math.sqrt(5), "cube": 2 * eps / math.sqrt(3), "cube_mse": 2 * eps * math.sqrt(0.475), "fcc": eps, "prism": eps}[self.shape]

    @property
    def factor(self) -> float:
        return 1 / self.spacing if self.shape != "bcc" or self.guard else math.sqrt(5) / (2 * self.eps)

    @classmethod
    def from_rel(cls, eb: float, **more) -> LatticeSpec:
        """``eb`` relative to the diagonal of the unit cube that clouds are scaled to."""
        return cls(eps=eb * math.sqrt(3), **more)

    @classmethod
    def from_psnr(cls, psnr: float, diagonal: float = math.sqrt(3), **more) -> LatticeSpec:
        """The bound whose expected error 0.475 eps^2 gives this ratio of peak (the diagonal) to error."""
        return cls(eps=math.sqrt(diagonal**2 * 10 ** (-psnr / 10) / 0.475), diagonal=diagonal, **more)

    def shaped(self, shape: str) -> LatticeSpec:
        return replace(self, shape=shape)


def bcc_factor(eb: float) -> float:
    """Lattice units per unit length for a relative bound on the unit cube."""
    return math.sqrt(5) / (2 * eb * math.sqrt(3))


def cube_factor(eb: float, match: str = "l2max") -> float:
    return math.sqrt(3) / (2 * eb * math.sqrt(3)) if match == "l2max" else 1 / (2 * eb * math.sqrt(3) * math.sqrt(0.475))


def bcc_error_cdf(r: float) -> float:
    """Share of a truncated-octahedron cell within ``r`` lattice units of its centre (cell volume 4).

    Exact up to 3 / (2 sqrt 2), where spherical caps behind two faces begin to overlap.
    """
    cap = lambda d: math.pi * (r - d) ** 2 * (2 * r + d) / 3 if r > d else 0.0
    return min(1.0, (4 * math.pi * r**3 / 3 - 8 * cap(math.sqrt(3) / 2) - 6 * cap(1.0)) / 4)


def regime(rho: float, delta: float) -> str:
    """What a cloud's density and divergence say about it."""
    if delta > 0.05:
        return "biased"
    return "dense" if rho > 8 else "transitional" if rho > 1.3 else "enumerating"
