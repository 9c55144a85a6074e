"""Which train partitions must be loaded for each origin partition, from manifests alone.

All rules give one row a kept pair (origin_id, part_id, …). ``counted`` is exact at the level of boxes: a train box is skipped
iff the rows of its own dominators reach k. The declared plan says just that, over all triples; the
two-step plan gives the same pairs from one equi-join on the origin after a cheap two-box prefilter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from boxprune.functions.dominance import dominates
from boxprune.functions.geometry import Box, gap_sq, intersects, is_valid, nxn_dist_sq, span_sq
from boxprune.plans.blocks import counted_blocks
from boxprune.sources.scratch import stored


def _named(manifest: DataFrame, prefix: str, dims: int, *more: str) -> DataFrame:
    usable = F.col("usable") if "usable" in manifest.columns else F.lit(True)
    return manifest.select(F.col("part_id").alias(f"{prefix}id"), F.col("n_rows").alias(f"{prefix}n"), usable.alias(f"{prefix}ok"), *[F.col(f"{e}_{i}").alias(f"{prefix}{e}_{i}") for i in range(dims) for e in ("lo", "hi")], *[F.col(c).alias(f"{prefix}{c}") for c in more])


def same(a: str, b: str) -> Column:
    """Equal partition ids; rows without one are a partition too."""
    return F.col(a).eqNullSafe(F.col(b))


def _own(self_join: bool, dims: int, near: str = "e_") -> Column:
    """Rows that a near box may lose to the origin's own row."""
    return F.when(intersects(Box.of("o_", dims), Box.of(near, dims)), 1).otherwise(0) if self_join else F.lit(0)


def _check(k: int) -> None:
    if k < 1:
        raise ValueError("k must be at least 1")


def all_pairs(origins: DataFrame, train: DataFrame, dims: int) -> DataFrame:
    """Every origin box with every train box: manifests only, never rows."""
    return _named(origins, "o_", dims).crossJoin(_named(train, "b_", dims))


def keep_none(origins: DataFrame, train: DataFrame, dims: int) -> DataFrame:
    return all_pairs(origins, train, dims).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"))


def keep_single(origins: DataFrame, train: DataFrame, k: int, dims: int) -> DataFrame:
    """Skip where one near box with k rows or more dominates. Pairs that the two-box test of single boxes drops are left out
    first, by an aggregate; the others meet in an equi-join on the origin."""
    _check(k)
    o, e, b = (Box.of(p, dims) for p in ("o_", "e_", "b_"))
    pairs = all_pairs(origins, train, dims).withColumns({"gap": gap_sq(o, b), "proof": F.col("o_ok") & F.col("b_ok")})
    cut = F.min(F.when(F.col("proof") & (F.col("b_n") >= k), span_sq(o, b))).over(Window.partitionBy("o_id"))
    pairs = pairs.withColumn("cut", cut).where(F.col("cut").isNull() | ~F.col("proof") | (F.col("gap") <= F.col("cut"))).drop("gap", "cut", "proof")
    near = pairs.where((F.col("b_n") >= k) & F.col("b_ok") & F.col("o_ok")).select(F.col("o_id").alias("e_o"), *[F.col(c).alias("e_" + c[2:]) for c in pairs.columns if c.startswith("b_")])
    return pairs.join(near, same("o_id", "e_o") & F.col("b_ok") & dominates(o, e, b), "left_anti").select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"))


def keep_declared(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool = False, safe: bool = False) -> DataFrame:
    """The counted rule as stated, over all triples; for small manifests and tests."""
    _check(k)
    o, e, b = (Box.of(p, dims) for p in ("o_", "e_", "b_"))
    pairs = all_pairs(origins, train, dims)
    near = _named(train, "e_", dims)
    hit = pairs.join(near, F.col("o_ok") & F.col("b_ok") & F.col("e_ok") & dominates(o, e, b, safe), "left")
    mass = hit.groupBy("o_id", "b_id").agg(F.coalesce(F.sum("e_n"), F.lit(0)).alias("rows"), F.coalesce(F.max(_own(self_join, dims)), F.lit(0)).alias("own"))
    out = mass.withColumn("dominator_rows", (F.col("rows") - F.col("own")).cast("bigint"))
    return out.where(F.col("dominator_rows") < k).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"), "dominator_rows")


def prefiltered(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool = False, pairs: DataFrame | None = None) -> DataFrame:
    """Pairs that the two-box bound leaves: boxes are taken by their span from the origin until k rows are certain,
    and what is farther off than that span goes. One shuffle, by origin. ``pairs``: those to start from, all by default."""
    _check(k)
    o, b = Box.of("o_", dims), Box.of("b_", dims)
    both = (all_pairs(origins, train, dims) if pairs is None else pairs).withColumns({"gap": gap_sq(o, b), "span": span_sq(o, b), "proof": F.col("o_ok") & F.col("b_ok")})
    by_span = Window.partitionBy("o_id").orderBy(F.when(F.col("proof"), F.col("span")).otherwise(F.lit(float("inf"))), "b_id").rowsBetween(Window.unboundedPreceding, 0)
    sure = F.sum(F.when(F.col("proof"), F.col("b_n")).otherwise(0)).over(by_span) - (F.max(_own(self_join, dims, "b_")).over(by_span) if self_join else F.lit(0))
    both = both.withColumn("sure", sure)
    cut = F.min(F.when(F.col("proof") & (F.col("sure") >= k), F.col("span"))).over(Window.partitionBy("o_id"))
    return both.withColumn("cut", cut).where(F.col("cut").isNull() | ~F.col("proof") | (F.col("gap") <= F.col("cut")))


def keep_two_box(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool = False) -> DataFrame:
    return prefiltered(origins, train, k, dims, self_join).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"))


def keep_two_step(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool = False, safe: bool = False, pairs: DataFrame | None = None) -> DataFrame:
    """The counted rule on the survivors of the prefilter: an equi-join on the origin, whose partitioning the final sums reuse.

    No pair is lost or gained: whatever skipped a dominator also dominates what it dominates, by rows enough.
    """
    left = prefiltered(origins, train, k, dims, self_join, pairs).drop("gap", "span", "sure", "cut", "proof")
    o, e, b = (Box.of(p, dims) for p in ("o_", "e_", "b_"))
    near = left.where("b_ok AND o_ok").select(F.col("o_id").alias("e_o"), *[F.col(c).alias("e_" + c[2:]) for c in left.columns if c.startswith("b_")])
    hit = left.join(near, same("o_id", "e_o") & F.col("b_ok") & dominates(o, e, b, safe), "left")
    mass = hit.groupBy("o_id", "b_id").agg(F.coalesce(F.sum("e_n"), F.lit(0)).alias("rows"), F.coalesce(F.max(F.when(F.col("e_n").isNotNull(), _own(self_join, dims))), F.lit(0)).alias("own"))
    out = mass.withColumn("dominator_rows", (F.col("rows") - F.col("own")).cast("bigint"))
    return out.where(F.col("dominator_rows") < k).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"), "dominator_rows")


def _minimal_only(k: int, loose: bool, predicate: bool, name: str) -> None:
    if k != 1 or loose or predicate:
        raise ValueError(f"{name} holds only for k = 1, minimal bounds and no predicate")


def keep_nxn(origins: DataFrame, train: DataFrame, dims: int, k: int = 1, loose: bool = False, predicate: bool = False) -> DataFrame:
    """Skip a box farther off than some minimal box surely has a row, for all points of the origin."""
    _minimal_only(k, loose, predicate, "nxn")
    o, b = Box.of("o_", dims), Box.of("b_", dims)
    both = all_pairs(origins, train, dims).withColumn("bound", F.min(nxn_dist_sq(o, b)).over(Window.partitionBy("o_id")))
    return both.where(gap_sq(o, b) <= F.col("bound")).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"))


def parent_of(manifest: DataFrame, dims: int, children: int = 256) -> DataFrame:
    """The manifest with ``parent``: cells of a grid over the boxes' centres, about ``children`` boxes each."""
    mids = [(F.col(f"lo_{i}") + F.col(f"hi_{i}")) / 2 for i in range(dims)]
    usable = F.col("usable") if "usable" in manifest.columns else F.lit(True)
    ends = manifest.where(usable).agg(F.count(F.lit(1)).alias("_n"), *[f(m).alias(f"_{e}{i}") for i, m in enumerate(mids) for f, e in ((F.min, "a"), (F.max, "z"))])
    cells = F.greatest(F.lit(1.0), F.ceil(F.pow(F.col("_n") / children, F.lit(1.0 / dims))))
    number = F.lit(0).cast("bigint")
    for i, m in enumerate(mids):
        wide = F.col(f"_z{i}") - F.col(f"_a{i}")
        number = number * cells.cast("bigint") + F.least(F.when(wide > 0, F.floor((m - F.col(f"_a{i}")) / wide * cells)).otherwise(0), cells - 1).cast("bigint")
    return manifest.crossJoin(F.broadcast(ends)).withColumn("parent", F.when(usable, number).otherwise(-1)).select(*manifest.columns, "parent")  # one row of ends


def keep_hierarchical(origins: DataFrame, train: DataFrame, k: int, dims: int, origin_parent: Column | str = "parent", train_parent: Column | str = "parent", self_join: bool = False, safe: bool = False) -> DataFrame:
    """The counted rule, between boxes of boxes first; only children of kept parents meet.

    A parent's skip holds for all of its children, and as the rows that skipped a box dominate all that the box
    dominates, no count is lost with it: the pairs are those of the flat rule. Parents of unusable boxes are never skipped.
    """
    col = lambda c: F.col(c) if isinstance(c, str) else c

    def parents(m: DataFrame, of: Column) -> DataFrame:
        ends = [f(f"{e}_{i}").alias(f"{e}_{i}") for i in range(dims) for f, e in ((F.min, "lo"), (F.max, "hi"))]
        usable = F.bool_and("usable") if "usable" in m.columns else F.lit(True)
        return m.groupBy(of.alias("part_id")).agg(F.sum("n_rows").alias("n_rows"), usable.alias("usable"), *ends)

    op, tp = col(origin_parent), col(train_parent)
    top = keep_two_step(parents(origins, op), parents(train, tp), k, dims, self_join, safe)
    kids_o = _named(origins.withColumn("_top", op), "o_", dims, "_top")
    kids_b = _named(train.withColumn("_top", tp), "b_", dims, "_top")
    met = top.select(F.col("origin_id").alias("t_o"), F.col("part_id").alias("t_b")).join(kids_o, same("t_o", "o__top")).join(kids_b, same("t_b", "b__top")).drop("t_o", "t_b", "o__top", "b__top")
    return keep_two_step(origins, train, k, dims, self_join, safe, met)


def split_origins(origins: DataFrame, pieces: int, dims: int) -> DataFrame:
    """Origin boxes cut into equal pieces on axis 0; piece_id tells them apart."""
    lo, hi = F.col("lo_0"), F.col("hi_0")
    at = lambda j: lo + (hi - lo) * j / pieces
    cut = origins.withColumn("piece_id", F.explode(F.sequence(F.lit(0), F.lit(pieces - 1))))
    return cut.withColumns({"lo_0": at(F.col("piece_id")), "hi_0": at(F.col("piece_id") + 1)})


def keep_split(origins: DataFrame, train: DataFrame, k: int, dims: int, pieces: int = 2, safe: bool = False) -> DataFrame:
    """The counted rule on pieces of each origin: a train box stays if any piece keeps it."""
    cut = split_origins(origins, pieces, dims).withColumn("part_id", F.struct("part_id", "piece_id"))
    kept = keep_two_step(cut, train, k, dims, safe=safe)
    return kept.select(F.col("origin_id.part_id").alias("origin_id"), "part_id").distinct()


def keep_counted(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool = False, safe: bool = False) -> DataFrame:
    """The counted rule for large manifests: boxes of equal bounds are one, with the rows of all, until their pairs are known.
    Where distinct boxes are many, blocks of origins meet all of them in Python, and no pair is shuffled or stored."""
    _check(k)

    def alike(m: DataFrame) -> tuple[DataFrame, DataFrame]:
        ends = [f"{e}_{i}" for i in range(dims) for e in ("lo", "hi")] + ["usable"] * ("usable" in m.columns)
        named = stored(m.withColumn("_one", F.min("part_id").over(Window.partitionBy(*ends))))
        one = named.groupBy(F.col("_one").alias("part_id"), *ends).agg(F.sum("n_rows").alias("n_rows"))
        return stored(one), named.select("part_id", "_one")

    (o, o_parts), (b, b_parts) = alike(origins), alike(train)
    n_o, n_b = o.count(), b.count()
    if n_o * n_b * n_b > FLAT_TRIPLES and all(_finite(m, dims) for m in (o, b)):
        return counted_blocks(origins, train, k, dims, self_join, safe, origins.count())
    if n_o * n_b > FLAT_PAIRS:
        pairs = keep_hierarchical(parent_of(o, dims), parent_of(b, dims), k, dims, self_join=self_join, safe=safe)
    else:
        pairs = keep_two_step(o, b, k, dims, self_join, safe)
    # few pairs become many rows: they are dealt to tasks first
    pairs = stored(pairs).repartition(128, "origin_id", "part_id").withColumnsRenamed({"origin_id": "_o", "part_id": "_b"})
    met = pairs.join(o_parts.withColumnsRenamed({"part_id": "origin_id", "_one": "_o_one"}), same("_o", "_o_one"))
    return met.join(b_parts.withColumnRenamed("_one", "_b_one"), same("_b", "_b_one")).select("origin_id", "part_id", "dominator_rows")


def _finite(manifest: DataFrame, dims: int) -> bool:
    """Whether all boxes that may be skipped or prove a skip have finite bounds."""
    usable = F.col("usable") if "usable" in manifest.columns else F.lit(True)
    return not manifest.where(usable & ~is_valid(Box.of("", dims))).limit(1).count()


#: Products of manifests above this are compared through parents.
FLAT_PAIRS = 20_000_000
#: Triples of an origin, a near and a far box above which the counted rule makes no rows of pairs.
FLAT_TRIPLES = 10_000_000


def keep_pairs(origins: DataFrame, train: DataFrame, k: int, dims: int, rule: str = "counted", plan: str = "auto", self_join: bool = False, safe: bool = True) -> DataFrame:
    """Kept pairs under a rule: counted, single, two_box, nxn or none. Plans of the counted rule: two_step, hierarchical, blocks,
    declared, or auto (blocks above FLAT_TRIPLES; hierarchical above FLAT_PAIRS if boxes are not finite); all give the same pairs."""
    _check(k)
    if rule == "counted":
        if plan == "auto":
            n_o, n_b = origins.count(), train.count()
            if n_o * n_b * n_b > FLAT_TRIPLES and _finite(origins, dims) and _finite(train, dims):
                plan = "blocks"
            else:
                plan = "hierarchical" if n_o * n_b > FLAT_PAIRS else "two_step"
        if plan == "blocks":
            return counted_blocks(origins, train, k, dims, self_join, safe, origins.count()).select("origin_id", "part_id")
        if plan == "hierarchical":
            return keep_hierarchical(parent_of(origins, dims), parent_of(train, dims), k, dims, self_join=self_join, safe=safe).select("origin_id", "part_id")
        return {"two_step": keep_two_step, "declared": keep_declared}[plan](origins, train, k, dims, self_join, safe).select("origin_id", "part_id")
    if rule == "single":
        return keep_single(origins, train, k + self_join, dims)
    if rule == "two_box":
        return keep_two_box(origins, train, k, dims, self_join)
    if rule == "nxn":
        if self_join:
            raise ValueError("a minimal box's sure row may be the origin's own")
        return keep_nxn(origins, train, dims, k)
    if rule == "none":
        return keep_none(origins, train, dims)
    raise ValueError(rule)
