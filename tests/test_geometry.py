"""Worked layouts, equal forms of the test, soundness, tightness, convexity."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from boxprune.functions import dominance as D
from boxprune.functions import geometry as G
from boxprune.functions.geometry import Box

# Worked layout A: an origin and three train boxes
O, P1, P2, P3 = (((-3, 0), (0, 3)), ((-5, 2), (-4, 3)), ((1, 2), (2, 3)), ((4, 0), (5, 2)))


def lit(b):
    return Box.literal(*b)


def one(spark, *cols):
    return spark.range(1).select(*[c.alias(f"c{i}") for i, c in enumerate(cols)]).first()


@pytest.mark.parametrize(("e", "b", "want"), [(P2, P3, 3), (P1, P3, -18), (P1, P2, -29), (P2, P1, -29), (P3, P2, -57), (P3, P1, -72)])
def test_scores_of_layout_a(spark, e, b, want):
    s, corner = one(spark, D.score(lit(O), lit(e), lit(b)), D.dominates_by_corners(lit(O), lit(e), lit(b)))
    assert s == want
    assert corner == (want > 0)


def test_ranges_and_bounds_of_layout_a(spark):
    o = lit(O)
    got = one(spark, *[f(o, lit(b)) for b in (P1, P2, P3) for f in (G.gap_sq, G.span_sq, G.nxn_dist_sq)])
    assert list(got)[0::3] == [1, 1, 16]
    assert list(got)[1::3] == [34, 34, 73]
    assert [round(x**0.5, 4) for x in list(got)[2::3]] == [5.0, 5.0, 7.6158]


def test_radii_of_layout_b(spark):
    r = one(spark, D.corner_radii(Box.literal((0, 0), (4, 4)), Box.literal((7, 1), (8, 2))))[0]
    assert r == [50, 10, 53, 13]  # corners (0,0), (4,0), (0,4), (4,4)


def test_chain_tie_and_self(spark):
    line = lambda a, b: Box.literal((a,), (b,))
    o, a, b, c = line(0, 1), line(2, 3), line(6, 7), line(12, 13)
    assert list(one(spark, D.dominates(o, a, b), D.dominates(o, b, c), D.dominates(o, a, c), D.dominates(o, a, a), D.dominates(line(0, 0), line(1, 1), line(-1, -1)))) == [True, True, True, False, False]


def test_cover_by_two_boxes_needs_splitting(spark):
    b, e1, e2 = Box.literal((5, 6), (5, 6)), Box.literal((0, 0), (0, 0)), Box.literal((10, 0), (10, 0))
    whole, left, right = (Box.literal((lo, 0), (hi, 0)) for lo, hi in ((0, 10), (0, 5), (5, 10)))
    assert list(one(spark, D.score(whole, e1, b), D.score(whole, e2, b), D.score(left, e1, b), D.score(right, e2, b))) == [-39, -39, 11, 11]


def random_boxes(rng, n, dims, reach):
    a = rng.integers(-reach, reach + 1, (n, 2, dims))
    return np.sort(a, axis=1)


@pytest.mark.parametrize("dims", [1, 2, 3, 5, 8])
def test_forms_agree_and_are_sound_and_tight(spark, dims):
    rng = np.random.default_rng(dims)
    n = 400
    boxes = [random_boxes(rng, n, dims, r) for r in (4, 6, 25)]
    rows = [tuple(float(v) for b in boxes for side in b[i] for v in side) for i in range(n)]
    names = [f"{p}_{e}_{i}" for p in "oeb" for e in ("lo", "hi") for i in range(dims)]
    df = spark.createDataFrame(rows, ", ".join(f"{c} double" for c in names))
    o, e, b = (Box.of(f"{p}_", dims) for p in "oeb")
    arrays = [F.array(*side) for x in (o, e, b) for side in (x.lo, x.hi)]
    w = D.witness(o, e, b)
    got = df.select(
        D.score(o, e, b).alias("s"), D.dominates_by_corners(o, e, b).alias("c"), D.score_arrays(*arrays).alias("a"), D.score(o, e, b, "decimal").cast("double").alias("d"),
        *[F.array(*x).alias(f"w{i}") for i, x in enumerate(w)],
    ).collect()
    dominated = 0
    for i, r in enumerate(got):
        block = D.score_block(boxes[0][i].astype(float), boxes[1][i : i + 1].astype(float), boxes[2][i : i + 1].astype(float))[0, 0]
        assert r.s == r.a == r.d == block
        assert (r.s > 0) == r.c
        if r.s > 0:
            dominated += 1
            pts = [x[i][0] + rng.random((50, dims)) * (x[i][1] - x[i][0]) for x in boxes]
            assert (((pts[0] - pts[1]) ** 2).sum(1) < ((pts[0] - pts[2]) ** 2).sum(1)).all()
        else:
            wo, we, wb = (np.array(r[f"w{j}"]) for j in range(3))
            for p, x in zip((wo, we, wb), boxes, strict=True):
                assert (p >= x[i][0]).all() and (p <= x[i][1]).all()
            assert ((wo - we) ** 2).sum() >= ((wo - wb) ** 2).sum()
    assert dominated or dims > 5


@pytest.mark.parametrize("far", [(2, 3), (0, 2), (-2, 2), (-2, 0), (-3, -2), (2, 2), (0, 0), (-2, -2)])
def test_axis_term_is_convex(spark, far):
    df = spark.range(81).select(((F.col("id") - 40) / 10.0).alias("p"))
    args = (F.lit(-1.0), F.lit(1.0)), (F.lit(float(far[0])), F.lit(float(far[1])))
    got = df.select(G.axis_term(F.col("p"), *args).alias("a"), G.axis_term_by_midpoint(F.col("p"), *args).alias("b")).collect()
    a = np.array([r.a for r in got])
    assert np.allclose(a, [r.b for r in got])
    assert (a[:-2] + a[2:] - 2 * a[1:-1] >= -1e-9).all()


def test_typed_modes_do_not_overflow(spark):
    big = 2**40
    o, e, b = Box.literal((0,), (0,)), None, None
    o = Box([F.lit(0).cast("bigint")], [F.lit(0).cast("bigint")])
    e = Box([F.lit(big)], [F.lit(big + 1)])
    b = Box([F.lit(big + 1)], [F.lit(big + 2)])
    assert one(spark, D.score(o, e, b, "bigint"))[0] == 0


def test_unusable_bounds(spark):
    nan = Box([F.lit(float("nan"))], [F.lit(1.0)])
    inf = Box([F.lit(0.0)], [F.lit(float("inf"))])
    assert list(one(spark, G.is_valid(nan), G.is_valid(inf), G.is_valid(Box.literal((1,), (0,))), G.is_valid(Box.literal((0,), (0,))))) == [False, False, False, True]
