"""Regions, spacings and directions: each as a SQL expression over x, y, z and as a numpy function.

The SQL text is plain enough for Spark and other engines alike. Values that decide a placement are rounded to six
decimals, so engines that differ in the last digit of a cosine place the same points.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SLACK = 1 - 1e-7  # squared distances are compared with r * r * SLACK, so that a neighbour at exactly r is far enough


@dataclass(frozen=True)
class Region:
    """A bounded region: its dimension, bounding box, membership in SQL and in numpy, and a point inside for a first seed."""

    name: str
    dim: int
    low: tuple
    high: tuple
    sql: str
    test: object = field(compare=False)
    inside: tuple = ()

    def contains(self) -> Column:
        """Box first: only the box reaches a scan's statistics."""
        box = " AND ".join(f"{c} >= {lo!r} AND {c} <= {hi!r}" for c, lo, hi in zip("xyz", self.low, self.high, strict=False))
        return F.expr(f"({box}) AND ({self.sql})")

    def __or__(self, other: Region) -> Region:
        a, b = self.test, other.test
        return Region(f"{self.name}+{other.name}", self.dim, tuple(map(min, self.low, other.low)), tuple(map(max, self.high, other.high)), f"(({self.sql}) OR ({other.sql}))", lambda p: a(p) | b(p), self.inside)

    def __sub__(self, other: Region) -> Region:
        a, b = self.test, other.test
        return Region(f"{self.name}-{other.name}", self.dim, self.low, self.high, f"(({self.sql}) AND NOT ({other.sql}))", lambda p: a(p) & ~b(p), self.inside)

    def extrude(self, z0: float, z1: float) -> Region:
        a = self.test
        return Region(f"{self.name}^", 3, (*self.low[:2], z0), (*self.high[:2], z1), f"(({self.sql}) AND z >= {z0!r} AND z <= {z1!r})", lambda p: a(p) & (p[:, 2] >= z0) & (p[:, 2] <= z1), (*self.inside[:2], (z0 + z1) / 2))


@dataclass(frozen=True)
class Spacing:
    """A positive spacing: SQL and numpy, with its least and largest value over the intended region."""

    name: str
    sql: str
    value: object = field(compare=False)
    least: float = 0.0
    most: float = 0.0

    def column(self) -> Column:
        return F.expr(f"round({self.sql}, 6)")

    def at(self, p: np.ndarray) -> np.ndarray:
        return np.round(self.value(p), 6)

    def scaled(self, a: float) -> Spacing:
        v = self.value
        return Spacing(f"{self.name}*{a:g}", f"({a!r} * ({self.sql}))", lambda p: a * v(p), a * self.least, a * self.most)


def box(low, high, name="box") -> Region:
    low, high = tuple(map(float, low)), tuple(map(float, high))
    sql = " AND ".join(f"{c} >= {a!r} AND {c} <= {b!r}" for c, a, b in zip("xyz", low, high, strict=False))
    return Region(name, len(low), low, high, f"({sql})", lambda p: ((p >= low) & (p <= high)).all(1), tuple((a + b) / 2 for a, b in zip(low, high, strict=True)))


def ellipsoid(centre, radii, name="ellipsoid") -> Region:
    c, r = np.array(centre, float), np.array(radii, float)
    low, high = tuple((c - r).tolist()), tuple((c + r).tolist())
    sql = " + ".join(f"power(({k} - {a!r}) / {b!r}, 2)" for k, a, b in zip("xyz", c.tolist(), r.tolist(), strict=False))
    return Region(name, len(c), low, high, f"({sql}) < 1", lambda p: (((p - c) / r) ** 2).sum(1) < 1, tuple(c.tolist()))


def annulus(inner: float, outer: float) -> Region:
    sql = f"(x * x + y * y) < {outer * outer!r} AND (x * x + y * y) > {inner * inner!r}"
    return Region("annulus", 2, (-outer, -outer), (outer, outer), sql, lambda p: ((d := (p * p).sum(1)) < outer * outer) & (d > inner * inner), ((inner + outer) / 2, 0.0))


def clover2d() -> Region:
    """Star-shaped, three leaves: the radius over the polar angle runs from 0.5 to 2.5."""
    sql = "sqrt(x * x + y * y) < 1.5 - power(cos(3 * atan2(y, x) - pi() / 2), 3)"
    return Region("clover2d", 2, (-2.5, -2.5), (2.5, 2.5), sql, lambda p: np.hypot(p[:, 0], p[:, 1]) < 1.5 - np.cos(3 * np.arctan2(p[:, 1], p[:, 0]) - np.pi / 2) ** 3, (0.0, 0.0))


def clover3d() -> Region:
    """The leaves fade towards the poles."""
    t = "acos(greatest(-1.0, least(1.0, coalesce(z / nullif(sqrt(x * x + y * y + z * z), 0), 0))))"
    sql = f"(x = 0 AND y = 0 AND abs(z) < 1.5) OR sqrt(x * x + y * y + z * z) < 1.5 - power(cos(3 * atan2(y, x) - pi() / 2), 3) * power((pi() - {t}) * {t}, 2) / 8"

    def test(p):
        d = np.sqrt((p * p).sum(1))
        t = np.arccos(np.clip(np.divide(p[:, 2], d, out=np.ones(len(p)), where=d > 0), -1, 1))
        return d < 1.5 - np.cos(3 * np.arctan2(p[:, 1], p[:, 0]) - np.pi / 2) ** 3 * ((np.pi - t) * t) ** 2 / 8

    return Region("clover3d", 3, (-2.3, -2.3, -2.0), (2.3, 2.3, 2.0), sql, test, (0.0, 0.0, 0.0))


def union(parts, name) -> Region:
    out = parts[0]
    for p in parts[1:]:
        out = out | p
    return Region(name, out.dim, out.low, out.high, out.sql, out.test, parts[0].inside)


def heatsink2d() -> Region:
    """A base with six fins."""
    return union([box((0, 0), (11, 2))] + [box((2 * i, 2), (2 * i + 1, 8)) for i in range(6)], "heatsink2d")


def heatsink3d() -> Region:
    """Base and fins with one hole from side to side."""
    solid = union([box((0, 0, 0), (11, 2, 6))] + [box((2 * i, 2, 0), (2 * i + 1, 8, 6)) for i in range(6)], "solid")
    hole = Region("hole", 3, (-1, 0, 0), (12, 2, 6), "power(y - 1.0, 2) + power(z - 3.0, 2) < 0.25", lambda p: (p[:, 1] - 1) ** 2 + (p[:, 2] - 3) ** 2 < 0.25)
    cut = solid - hole
    return Region("heatsink3d", 3, cut.low, cut.high, cut.sql, cut.test, (5.5, 0.25, 1.0))


def hare_outline() -> np.ndarray:
    """Corners of an irregular silhouette, feet low and ears high."""
    half = [(20, 0), (38, 4), (40, 14), (30, 22), (36, 45), (34, 62), (24, 76), (28, 92), (22, 104), (26, 128), (20, 150), (12, 146), (9, 122), (6, 108)]
    return np.array(half + [(-x, y) for x, y in reversed(half)], float)


def polygon(corners: np.ndarray, name: str, inside) -> Region:
    """Even-odd rule over the edges of one ring."""
    a, b = corners, np.roll(corners, -1, 0)
    term = lambda x1, y1, x2, y2: f"CASE WHEN (y < {y1!r}) <> (y < {y2!r}) AND x < ({x2 - x1!r}) * (y - ({y1!r})) / ({y2 - y1!r}) + ({x1!r}) THEN 1 ELSE 0 END"
    sql = " + ".join(term(*map(float, (*p, *q))) for p, q in zip(a, b, strict=True) if p[1] != q[1])

    def test(p):
        hits = np.zeros(len(p), int)
        for (x1, y1), (x2, y2) in zip(a, b, strict=True):
            if y1 != y2:
                hits += ((p[:, 1] < y1) != (p[:, 1] < y2)) & (p[:, 0] < (x2 - x1) * (p[:, 1] - y1) / (y2 - y1) + x1)
        return hits % 2 == 1

    return Region(name, 2, tuple(corners.min(0).tolist()), tuple(corners.max(0).tolist()), f"(({sql}) % 2) = 1", test, inside)


def hare2d() -> Region:
    return polygon(hare_outline(), "hare2d", (0.0, 50.0))


def hare3d() -> Region:
    """Ellipsoids for body, head and ears; z from 0 to 180."""
    parts = [ellipsoid((0, 0, 55), (45, 40, 55)), ellipsoid((0, 10, 115), (28, 26, 28)), ellipsoid((-14, 8, 152), (8, 7, 28)), ellipsoid((14, 8, 152), (8, 7, 28))]
    return union(parts, "hare3d")


@lru_cache
def maze_links(shape: tuple, seed: int = 5) -> tuple:
    """A spanning tree of the lattice by depth-first walks, from a linear congruential sequence."""
    state, seen, stack, links = seed, {(0,) * len(shape)}, [(0,) * len(shape)], []
    while stack:
        at = stack[-1]
        near = [tuple(at[j] + (s if j == k else 0) for j in range(len(shape))) for k in range(len(shape)) for s in (-1, 1)]
        near = [q for q in near if all(0 <= a < n for a, n in zip(q, shape, strict=True)) and q not in seen]
        if not near:
            stack.pop()
            continue
        state = (1103515245 * state + 12345) % 2**31
        to = near[(state >> 16) % len(near)]
        seen.add(to)
        links.append((at, to))
        stack.append(to)
    return tuple(links)


def maze(shape: tuple, pitch: float, width: float, name: str) -> Region:
    """Corridors of the given width along the links of the maze."""
    parts = []
    for p, q in maze_links(shape):
        low = [min(a, b) * pitch + (pitch - width) / 2 for a, b in zip(p, q, strict=True)]
        high = [max(a, b) * pitch + (pitch + width) / 2 for a, b in zip(p, q, strict=True)]
        parts.append(box(low, high))
    return union(parts, name)


def maze2d() -> Region:
    return maze((6, 6), 40 / 6, 4.0, "maze2d")


def maze3d() -> Region:
    return maze((4, 4, 3), 10.0, 6.0, "maze3d")


REGIONS = {f.__name__: f for f in (clover2d, clover3d, heatsink2d, heatsink3d, hare2d, hare3d, maze2d, maze3d)}


def constant(h: float) -> Spacing:
    return Spacing(f"h={h:g}", f"CAST({float(h)!r} AS DOUBLE)", lambda p: np.full(len(p), float(h)), h, h)


def clover_spacing(h: float, high: float | None = None) -> Spacing:
    """Fine at the centre and between the leaves' axes; the ratio is five unless the largest value is given."""
    top = 5 * h if high is None else high
    sql = f"{float(h)!r} + {float(top - h)!r} * power(cos(3 * atan2(y, x)), 2) * tanh(sqrt(x * x + y * y))"
    return Spacing("clover", sql, lambda p: h + (top - h) * np.cos(3 * np.arctan2(p[:, 1], p[:, 0])) ** 2 * np.tanh(np.hypot(p[:, 0], p[:, 1])), h, top)


def clover3d_spacing(h: float) -> Spacing:
    sql = f"{float(h)!r} * (0.5 + power(cos(3 * atan2(y, x) + pi() / 3), 2) * tanh((2 - z) * sqrt(x * x + y * y + z * z)))"
    return Spacing("clover3d", sql, lambda p: h * (0.5 + np.cos(3 * np.arctan2(p[:, 1], p[:, 0]) + np.pi / 3) ** 2 * np.tanh((2 - p[:, 2]) * np.sqrt((p * p).sum(1)))), 0.5 * h, 1.5 * h)


def power_y(h: float, length: float, top: float) -> Spacing:
    return Spacing("power_y", f"{float(h)!r} * power(1 + y / {float(length)!r}, 1.5)", lambda p: h * (1 + p[:, 1] / length) ** 1.5, h, h * (1 + top / length) ** 1.5)


def linear_x(h: float, rate: float, wide: float) -> Spacing:
    """Wider with the distance from x = 0; the largest value holds for |x| <= wide."""
    return Spacing("linear_x", f"CAST({float(h)!r} AS DOUBLE) + CAST({float(rate)!r} AS DOUBLE) * abs(x)", lambda p: h + rate * np.abs(p[:, 0]), h, h + rate * wide)


def hare3d_spacing(h: float) -> Spacing:
    return Spacing("hare3d", f"{float(h)!r} * (1 + 4 * (180 - z) / 180)", lambda p: h * (1 + 4 * (180 - p[:, 2]) / 180), h, 5 * h)


def maze3d_spacing(h: float) -> Spacing:
    return Spacing("maze3d", f"{float(h)!r} * (4 + sin(pi() * x / 5))", lambda p: h * (4 + np.sin(np.pi * p[:, 0] / 5)), 3 * h, 5 * h)


SPACINGS = {
    "clover2d": clover_spacing, "clover3d": clover3d_spacing, "heatsink2d": constant, "heatsink3d": constant,
    "hare2d": lambda h: power_y(h, 100, 150), "hare3d": hare3d_spacing, "maze2d": lambda h: power_y(h, 20, 40), "maze3d": maze3d_spacing,
}


@lru_cache
def sphere(dim: int, n_c: int) -> np.ndarray:
    """Unit vectors: n_c on a great circle; higher dimensions slice the last angle, each slice by the rule one lower."""
    if dim == 1:
        return np.array([[-1.0], [1.0]])
    if dim == 2:
        t = 2 * np.pi * np.arange(n_c) / n_c
        u = np.stack([np.cos(t), np.sin(t)], 1)
        return np.where(np.abs(u) < 1e-15, 0.0, u)
    slices = max(2, n_c // 2)
    out = []
    for k in range(slices):
        t = np.pi * (k + 0.5) / slices
        ring = sphere(dim - 1, max(1, int(n_c * math.sin(t) + 1e-9)))
        out.append(np.hstack([ring * math.sin(t), np.full((len(ring), 1), math.cos(t))]))
    return np.concatenate(out)


@lru_cache
def banks(dim: int, n_c: int, rotate: bool = True, n: int = 16) -> np.ndarray:
    """[bank, direction, axis]: the directions under n fixed rotations; bank 0 only, if not rotated."""
    u = sphere(dim, n_c)
    if not rotate or dim == 1:
        return np.repeat(u[None], n, 0)
    out, rng = [], np.random.default_rng(2024)
    for k in range(n):
        if dim == 2:
            t = 2 * np.pi / n_c * (k + 0.5) / n
            turn = np.array([[math.cos(t), -math.sin(t)], [math.sin(t), math.cos(t)]])
        else:
            turn = np.linalg.qr(rng.normal(size=(dim, dim)))[0]
        v = u @ turn.T
        out.append(v / np.sqrt((v * v).sum(1, keepdims=True)))
    return np.array(out)


def direction_rows(dim: int, n_c: int, rotate: bool = True) -> list[tuple]:
    b = banks(dim, n_c, rotate)
    return [(k, j, *map(float, np.r_[b[k, j], np.zeros(3)][:3])) for k in range(len(b)) for j in range(b.shape[1])]


_P = [0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5]


def xxhash_long(values: np.ndarray, seed=42) -> np.ndarray:
    """Spark's xxhash64 of a long, in numpy."""
    p1, p2, p3, p4, p5 = (np.uint64(p) for p in _P)
    rotl = lambda a, k: (a << np.uint64(k)) | (a >> np.uint64(64 - k))
    with np.errstate(over="ignore"):
        h = (np.asarray(seed).astype(np.int64).astype(np.uint64) + p5 + np.uint64(8)) ^ (rotl(np.asarray(values, np.int64).astype(np.uint64) * p2, 31) * p1)
        h = rotl(h, 27) * p1 + p4
        h ^= h >> np.uint64(33)
        h *= p2
        h ^= h >> np.uint64(29)
        h *= p3
        h ^= h >> np.uint64(32)
    return h.astype(np.int64)


def child_id(parent: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Id of a parent's j-th child: Spark's xxhash64(parent, j as long)."""
    return xxhash_long(j, xxhash_long(parent))
