"""Half-spaces, polyhedra and unions of them, and how they lie to boxes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import product
from operator import and_, or_

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

OUTSIDE, PARTIAL, INSIDE = 0, 1, 2


def joined(parts: list[Column], how: Callable[[Column, Column], Column], none: bool) -> Column:
    """``parts`` under & or | as a balanced tree: a chain of some hundreds is too deep for the plan's recursions."""
    while len(parts) > 1:
        parts = [how(*parts[k : k + 2]) if k + 1 < len(parts) else parts[k] for k in range(0, len(parts), 2)]
    return parts[0] if parts else F.lit(none)


@dataclass(frozen=True)
class HalfSpace:
    """w . x <= b, or < b if strict."""

    w: tuple[float, ...]
    b: float
    strict: bool = False

    def column(self, cols: list[str]) -> Column:
        dot = None
        for w, c in zip(self.w, cols, strict=True):
            if w:
                term = F.col(c) if w == 1 else F.col(c) * float(w)
                dot = term if dot is None else dot + term
        dot = F.lit(0.0) if dot is None else dot
        return dot < self.b if self.strict else dot <= self.b

    def sql(self, cols: list[str]) -> str:
        terms = [c if w == 1 else f"{c} * CAST({w!r} AS DOUBLE)" for w, c in zip(self.w, cols, strict=True) if w]
        return f"{' + '.join(terms) or '0.0'} {'<' if self.strict else '<='} CAST({self.b!r} AS DOUBLE)"

    def classify(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        w = np.array(self.w)
        low = np.where(w > 0, lo, hi) @ w
        high = np.where(w > 0, hi, lo) @ w
        slack = 1e-9 * (1 + np.abs(low) + np.abs(high) + abs(self.b))  # rounding never turns partial into inside
        return np.where(high < self.b - slack, INSIDE, np.where(low > self.b + slack, OUTSIDE, PARTIAL))


@dataclass(frozen=True)
class Polyhedron:
    """A conjunction of half-spaces; without any, the whole space."""

    faces: tuple[HalfSpace, ...] = field(default=())

    def column(self, cols: list[str]) -> Column:
        return joined([f.column(cols) for f in self.faces], and_, True)

    def sql(self, cols: list[str]) -> str:
        return " AND ".join(f"({f.sql(cols)})" for f in self.faces) or "TRUE"

    def classify(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        out = np.full(len(lo), INSIDE)
        for f in self.faces:
            out = np.minimum(out, f.classify(lo, hi))
        return out


@dataclass(frozen=True)
class Union:
    """A disjunction of polyhedra."""

    parts: tuple[Polyhedron, ...]

    def column(self, cols: list[str]) -> Column:
        return joined([p.column(cols) for p in self.parts], or_, False)

    def sql(self, cols: list[str]) -> str:
        return " OR ".join(f"({p.sql(cols)})" for p in self.parts) or "FALSE"

    def classify(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        out = np.full(len(lo), OUTSIDE)
        for p in self.parts:
            out = np.maximum(out, p.classify(lo, hi))
        return out


def box(lo, hi) -> Polyhedron:
    """lo <= x <= hi on every axis; None leaves a side open."""
    d, faces = len(lo), []
    for k in range(d):
        e = tuple(1.0 if j == k else 0.0 for j in range(d))
        if hi[k] is not None:
            faces.append(HalfSpace(e, float(hi[k])))
        if lo[k] is not None:
            faces.append(HalfSpace(tuple(-v for v in e), -float(lo[k])))
    return Polyhedron(tuple(faces))


def simplex(corner, size: float) -> Polyhedron:
    """x >= corner and sum(x - corner) <= size."""
    d = len(corner)
    faces = [HalfSpace(tuple(-1.0 if j == k else 0.0 for j in range(d)), -float(corner[k])) for k in range(d)]
    return Polyhedron((*faces, HalfSpace((1.0,) * d, float(size + sum(corner)))))


def polyhedralise_ball(centre, radius: float, per_axis: int = 2) -> Polyhedron:
    """Tangent half-spaces of a ball on a grid of directions: the ball lies within, and nearer with more directions."""
    d = len(centre)
    ticks = np.linspace(-1, 1, 2 * per_axis + 1)
    rays = np.array([v for v in product(ticks, repeat=d) if max(map(abs, v)) == 1.0])
    rays = np.unique((rays / np.linalg.norm(rays, axis=1, keepdims=True)).round(12), axis=0)
    return Polyhedron(tuple(HalfSpace(tuple(map(float, r)), float(r @ np.array(centre) + radius)) for r in rays))


def direction_set(d: int) -> list[tuple[float, ...]]:
    """The 2d axes, and sums and differences of pairs of axes, both ways."""
    out = []
    for k in range(d):
        for s in (1.0, -1.0):
            out.append(tuple(s if j == k else 0.0 for j in range(d)))
    for a in range(d):
        for b in range(a + 1, d):
            for s, t in product((1.0, -1.0), repeat=2):
                out.append(tuple(s if j == a else t if j == b else 0.0 for j in range(d)))
    return out


def convex_hull_2d(points: np.ndarray) -> np.ndarray:
    """Corners in counter-clockwise order, by two monotone chains."""
    pts = sorted(set(map(tuple, points.tolist())))
    if len(pts) < 3:
        return np.array(pts)

    def chain(seq):
        out: list = []
        for p in seq:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) <= (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]):
                out.pop()
            out.append(p)
        return out[:-1]

    return np.array(chain(pts) + chain(pts[::-1]))


def hull_polyhedron_2d(points: np.ndarray) -> Polyhedron:
    h = convex_hull_2d(points)
    if len(h) < 3:
        return box(points.min(0), points.max(0))
    faces = []
    for a, b in zip(h, np.roll(h, -1, axis=0), strict=True):
        n = np.array([b[1] - a[1], a[0] - b[0]])
        faces.append(HalfSpace((float(n[0]), float(n[1])), float(max(n @ a, n @ b)) + 1e-9))
    return Polyhedron(tuple(faces))


def merge_runs(ids) -> list[tuple[int, int]]:
    """Sorted integers as closed intervals."""
    out: list[list[int]] = []
    for i in ids:
        if out and out[-1][1] + 1 == i:
            out[-1][1] = i
        else:
            out.append([i, i])
    return [(a, b) for a, b in out]
