"""Does every point of a near box lie closer than every point of a far box, seen from all of an origin box?

The linear form adds, axis by axis, the smaller of the two gaps that the origin's ends leave (squared clearance to
far less squared reach to near); the answer is yes iff the sum is positive. The corner form tries all corners.
"""

from __future__ import annotations

from decimal import Decimal

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from boxprune.functions.geometry import Box, axis_clearance, axis_reach, clamp, corners, gap_sq, reach_sq, span_sq, sq, total

#: Number types of the test and how they are widened so that squares and their sums stay exact.
MODES = {"byte": "bigint", "short": "bigint", "int": "decimal(38,0)", "bigint": "decimal(38,0)", "decimal": "decimal(38,0)", "float": "double", "double": "double"}
#: Fractions of ``scale`` decimal digits are counted in units of the last one, as whole numbers.
RATIONAL = "rational"


def widened(box: Box, mode: str, scale: int = 0) -> Box:
    if mode != RATIONAL:
        return box.cast(MODES[mode])
    whole = lambda c: (c.cast(f"decimal(38,{scale})") * F.lit(Decimal(10**scale))).cast("decimal(38,0)")
    return Box([whole(c) for c in box.lo], [whole(c) for c in box.hi])


def end_gap(p: Column, near: tuple[Column, Column], far: tuple[Column, Column]) -> Column:
    return sq(axis_clearance(p, *far)) - sq(axis_reach(p, *near))


def score(o: Box, e: Box, b: Box, mode: str = "double", scale: int = 0) -> Column:
    """Positive iff near e dominates far b from o. Null (overflow, missing bounds) means that nothing is proven."""
    o, e, b = (widened(x, mode, scale) for x in (o, e, b))
    return total(F.least(end_gap(ol, near, far), end_gap(oh, near, far)) for (ol, oh), near, far in zip(o.axes(), e.axes(), b.axes(), strict=True))


def tolerance(o: Box, e: Box, b: Box) -> Column:
    """Bound on rounding of the score and of both squared distances, in doubles."""
    return F.lit((len(o.lo) + 8) * 2.0**-52) * (span_sq(o, e) + span_sq(o, b))


def dominates(o: Box, e: Box, b: Box, safe: bool = False, mode: str = "double", scale: int = 0) -> Column:
    s = score(o, e, b, mode, scale)
    return s > tolerance(o, e, b) if safe else s > 0


def dominates_by_corners(o: Box, e: Box, b: Box) -> Column:
    """All 2^R corners; stops at the first that fails."""
    dims = len(o.lo)

    def holds(corner: Column) -> Column:
        p = [corner[i] for i in range(dims)]
        return total(sq(axis_reach(x, lo, hi)) for x, (lo, hi) in zip(p, e.axes(), strict=True)) < total(sq(axis_clearance(x, lo, hi)) for x, (lo, hi) in zip(p, b.axes(), strict=True))

    return F.forall(corners(o), holds)


def score_arrays(o_lo: Column, o_hi: Column, e_lo: Column, e_hi: Column, b_lo: Column, b_hi: Column) -> Column:
    """The linear form over arrays, for a number of axes known only at run time."""
    zipped = F.arrays_zip(o_lo.alias("ol"), o_hi.alias("oh"), e_lo.alias("el"), e_hi.alias("eh"), b_lo.alias("bl"), b_hi.alias("bh"))

    def add(acc: Column, z: Column) -> Column:
        near, far = (z["el"], z["eh"]), (z["bl"], z["bh"])
        return acc + F.least(end_gap(z["ol"], near, far), end_gap(z["oh"], near, far))

    return F.aggregate(zipped, F.lit(0.0), add)


def score_block(o: np.ndarray, e: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Scores of one origin (2, R) for all near (n, 2, R) and far (m, 2, R) boxes, as an (n, m) block."""
    out = np.zeros((len(e), len(b)))
    for i in range(o.shape[1]):
        ends = []
        for p in o[:, i]:
            reach = np.maximum(np.abs(e[:, 0, i] - p), np.abs(e[:, 1, i] - p))
            clear = np.maximum(np.maximum(b[:, 0, i] - p, p - b[:, 1, i]), 0.0)
            ends.append((clear * clear)[None, :] - (reach * reach)[:, None])
        out += np.minimum(*ends)
    return out


def worst_corner(o: Box, e: Box, b: Box) -> list[Column]:
    """Per axis, the end of o with the smaller gap (the low one on ties)."""
    return [F.when(end_gap(ol, near, far) <= end_gap(oh, near, far), ol).otherwise(oh) for (ol, oh), near, far in zip(o.axes(), e.axes(), b.axes(), strict=True)]


def witness(o: Box, e: Box, b: Box) -> tuple[list[Column], list[Column], list[Column]]:
    """Points o, e, b with dist(o, e) >= dist(o, b) whenever e does not dominate b."""
    at = worst_corner(o, e, b)
    far_end = [F.when(F.abs(lo - p) >= F.abs(hi - p), lo).otherwise(hi) for p, (lo, hi) in zip(at, e.axes(), strict=True)]
    return at, far_end, clamp(at, b)


def corner_radii(o: Box, b: Box) -> Column:
    """array of squared clearances from o's corners to b; what lies inside all of these balls is closer than b."""
    dims = len(o.lo)
    return F.transform(corners(o), lambda c: total(sq(axis_clearance(c[i], b.lo[i], b.hi[i])) for i in range(dims)))


def axis_visits(dims: int) -> dict[str, int]:
    """Axis terms looked at in one test by each form."""
    return {"linear": dims, "corners": dims * 2**dims}


def register_sql(spark: SparkSession) -> None:
    """box_axis_gap and box_score_2d as SQL functions; their bodies are inlined by the optimizer."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION box_axis_gap(p DOUBLE, el DOUBLE, eh DOUBLE, bl DOUBLE, bh DOUBLE) RETURNS DOUBLE
        RETURN greatest(bl - p, p - bh, 0D) * greatest(bl - p, p - bh, 0D) - greatest(abs(el - p), abs(eh - p)) * greatest(abs(el - p), abs(eh - p))""")
    axis = lambda i: f"least(box_axis_gap(ol{i}, el{i}, eh{i}, bl{i}, bh{i}), box_axis_gap(oh{i}, el{i}, eh{i}, bl{i}, bh{i}))"
    args = ", ".join(f"{box}{end}{i} DOUBLE" for i in range(2) for box in "oeb" for end in "lh")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION box_score_2d({args}) RETURNS DOUBLE RETURN {axis(0)} + {axis(1)}")


__all__ = ["MODES", "axis_visits", "corner_radii", "dominates", "dominates_by_corners", "end_gap", "gap_sq", "reach_sq", "register_sql", "score", "score_arrays", "score_block", "tolerance", "witness", "worst_corner"]
