"""Points and axis-aligned boxes as Columns.

A box is a pair of lists of Columns, one low and one high end an axis, so expressions unroll into
scalar arithmetic inside one generated stage. Distances are compared squared.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Box:
    lo: list[Column]
    hi: list[Column]

    @classmethod
    def of(cls, prefix: str, dims: int) -> Box:
        """The box in columns ``{prefix}lo_0 …``."""
        return cls([F.col(f"{prefix}lo_{i}") for i in range(dims)], [F.col(f"{prefix}hi_{i}") for i in range(dims)])

    @classmethod
    def point(cls, coords: list[Column]) -> Box:
        return cls(coords, coords)

    @classmethod
    def literal(cls, lo, hi) -> Box:
        return cls([F.lit(float(v)) for v in lo], [F.lit(float(v)) for v in hi])

    def cast(self, kind: str) -> Box:
        return Box([c.cast(kind) for c in self.lo], [c.cast(kind) for c in self.hi])

    def axes(self):
        return zip(self.lo, self.hi, strict=True)


def total(terms) -> Column:
    """Left-to-right sum, so that every engine adds in one order."""
    return reduce(lambda a, b: a + b, terms)


def sq(x: Column) -> Column:
    return x * x


def point(prefix: str, dims: int) -> list[Column]:
    return [F.col(f"{prefix}x_{i}") for i in range(dims)]


def dist_sq(p: list[Column], q: list[Column]) -> Column:
    return total(sq(a - b) for a, b in zip(p, q, strict=True))


def dist(p: list[Column], q: list[Column]) -> Column:
    return F.sqrt(dist_sq(p, q))


def axis_clearance(p: Column, lo: Column, hi: Column) -> Column:
    """Distance on one axis from p to the nearer end, 0 inside."""
    return F.greatest(lo - p, p - hi, F.lit(0) * p)


def axis_reach(p: Column, lo: Column, hi: Column) -> Column:
    return F.greatest(F.abs(lo - p), F.abs(hi - p))


def clearance_sq(p: list[Column], box: Box) -> Column:
    return total(sq(axis_clearance(x, a, b)) for x, (a, b) in zip(p, box.axes(), strict=True))


def reach_sq(p: list[Column], box: Box) -> Column:
    return total(sq(axis_reach(x, a, b)) for x, (a, b) in zip(p, box.axes(), strict=True))


def margin_field(p: list[Column], near: Box, far: Box) -> Column:
    """reach² to near minus clearance² to far: convex in p, negative where all of near is closer."""
    return reach_sq(p, near) - clearance_sq(p, far)


def point_sees_dominance(p: list[Column], near: Box, far: Box) -> Column:
    return margin_field(p, near, far) < 0


def axis_term(p: Column, near: tuple[Column, Column], far: tuple[Column, Column]) -> Column:
    return sq(axis_reach(p, *near)) - sq(axis_clearance(p, *far))


def axis_term_by_midpoint(p: Column, near: tuple[Column, Column], far: tuple[Column, Column]) -> Column:
    """The same term with the farther end of near picked by the side of its midpoint."""
    lo, hi = near
    return F.when(p < (lo + hi) / 2, sq(hi - p)).otherwise(sq(lo - p)) - sq(axis_clearance(p, *far))


def corners(box: Box) -> Column:
    """array of 2^R points (arrays); corner number c has the high end on axis i where bit i of c is set."""
    dims = len(box.lo)
    if dims > 16:
        raise ValueError("corner enumeration is for at most 16 axes")
    pick = lambda c: F.array(*[F.when(F.getbit(c, F.lit(i)) == 1, hi).otherwise(lo) for i, (lo, hi) in enumerate(box.axes())])
    return F.transform(F.sequence(F.lit(0), F.lit(2**dims - 1)), pick)


def sample_in_box(boxes: DataFrame, box: Box, n: int, seed: int) -> DataFrame:
    """n points of each box as further columns x_0 …: random convex combinations of its corners, so ends can be met but not passed."""
    weights = [-F.log(1 - F.rand(seed + c)) for c in range(2 ** len(box.lo))]
    rows = boxes.withColumn("sample", F.explode(F.sequence(F.lit(1), F.lit(n)))).withColumns({f"_w{c}": w for c, w in enumerate(weights)})
    whole = total(F.col(f"_w{c}") for c in range(len(weights)))
    # the corners at an axis' high end, by their share of all weight, say how far the point is from the low end
    share = lambda i: total(F.col(f"_w{c}") for c in range(len(weights)) if c >> i & 1) / whole
    points = {f"x_{i}": F.least(lo + (hi - lo) * share(i), hi) for i, (lo, hi) in enumerate(box.axes())}
    return rows.withColumns(points).drop(*[f"_w{c}" for c in range(len(weights))])


def contains(box: Box, p: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, [x.between(lo, hi) for x, (lo, hi) in zip(p, box.axes(), strict=True)])


def is_valid(box: Box) -> Column:
    """Finite, ordered bounds on every axis; NaN, infinite or missing ends make a box unusable."""
    ok = [lo.isNotNull() & hi.isNotNull() & ~F.isnan(lo) & ~F.isnan(hi) & (F.abs(lo) < float("inf")) & (F.abs(hi) < float("inf")) & (lo <= hi) for lo, hi in box.axes()]
    return reduce(lambda a, b: a & b, ok)


def intersects(a: Box, b: Box) -> Column:
    return reduce(lambda x, y: x & y, [(al <= bh) & (bl <= ah) for (al, ah), (bl, bh) in zip(a.axes(), b.axes(), strict=True)])


def intersection(a: Box, b: Box) -> Box:
    return Box([F.greatest(x, y) for x, y in zip(a.lo, b.lo, strict=True)], [F.least(x, y) for x, y in zip(a.hi, b.hi, strict=True)])


def hull(a: Box, b: Box) -> Box:
    return Box([F.least(x, y) for x, y in zip(a.lo, b.lo, strict=True)], [F.greatest(x, y) for x, y in zip(a.hi, b.hi, strict=True)])


def center(box: Box) -> list[Column]:
    return [(lo + hi) / 2 for lo, hi in box.axes()]


def volume(box: Box) -> Column:
    return reduce(lambda a, b: a * b, [hi - lo for lo, hi in box.axes()])


def clamp(p: list[Column], box: Box) -> list[Column]:
    return [F.least(F.greatest(x, lo), hi) for x, (lo, hi) in zip(p, box.axes(), strict=True)]


def gap_sq(a: Box, b: Box) -> Column:
    """Least squared distance between two boxes."""
    return total(sq(F.greatest(bl - ah, al - bh, F.lit(0) * al)) for (al, ah), (bl, bh) in zip(a.axes(), b.axes(), strict=True))


def span_sq(a: Box, b: Box) -> Column:
    """Greatest squared distance between two boxes."""
    return total(sq(F.greatest(F.abs(bh - al), F.abs(ah - bl))) for (al, ah), (bl, bh) in zip(a.axes(), b.axes(), strict=True))


def _axis_face(p: Column, lo: Column, hi: Column) -> Column:
    """Distance on one axis to the nearer end."""
    return F.least(F.abs(p - lo), F.abs(p - hi))


def min_max_dist_sq(p: list[Column], box: Box) -> Column:
    """Some row of a minimal box lies within this of p: the least, over axes, of going to the nearer face on
    that axis and to the farther ends on all others."""
    near = [sq(_axis_face(x, lo, hi)) for x, (lo, hi) in zip(p, box.axes(), strict=True)]
    far = [sq(axis_reach(x, lo, hi)) for x, (lo, hi) in zip(p, box.axes(), strict=True)]
    options = [total(near[j] if j == d else far[j] for j in range(len(p))) for d in range(len(p))]
    return F.least(*options) if len(options) > 1 else options[0]


def nxn_dist_sq(o: Box, e: Box) -> Column:
    """The same for all points of a box o: per-axis spans, less the best saving by a nearest face."""
    spans, saves = [], []
    for (ol, oh), (el, eh) in zip(o.axes(), e.axes(), strict=True):
        mid = (el + eh) / 2
        worst = F.greatest(_axis_face(ol, el, eh), _axis_face(oh, el, eh), F.when((mid >= ol) & (mid <= oh), (eh - el) / 2).otherwise(F.lit(0.0)))
        span = sq(F.greatest(F.abs(eh - ol), F.abs(oh - el)))
        spans.append(span)
        saves.append(span - sq(worst))
    return total(spans) - (F.greatest(*saves) if len(saves) > 1 else saves[0])
