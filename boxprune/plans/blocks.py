"""The counted rule for manifests whose pairs are too many to be rows of a shuffle: blocks of origin boxes meet all train boxes in
Python, and only kept pairs become rows. The shuffle holds the train manifest once a block, of which there are BLOCKS at most."""

from __future__ import annotations

import itertools
import math
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# tasks get the classes below with their job, so that executors need not have this package
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Origin boxes of a block, about, and blocks at most.
BLOCK_ORIGINS, BLOCKS = 256, 256
#: Corners of an origin box that are looked at before single pairs of boxes; any number of them is right.
CORNERS = 16
#: Near boxes that far boxes meet at first, and scores that are made at once.
FIRST, AT_ONCE = 4, 100_000
#: Allowance for rounding where sums of squares are compared.
SLACK = 1e-12


class Boxes:
    """Distinct boxes (lo, hi: n x dims) with their rows."""

    def __init__(self, lo: np.ndarray, hi: np.ndarray, rows: np.ndarray):
        self.lo, self.hi, self.rows, self.dims = lo, hi, rows.astype(float), lo.shape[1]  # whole numbers far below 2^53

    def dominator_rows(self, o_lo: np.ndarray, o_hi: np.ndarray, k: int, self_join: bool, safe: bool) -> np.ndarray:
        """Rows that dominate each box, seen from one origin box; -1 where they are k or more."""
        out = np.zeros(len(self.lo), np.int64)
        if not len(out):
            return out
        ends = [[o_lo[i], o_hi[i]] for i in range(self.dims)]
        reach = [[np.maximum(np.abs(self.lo[:, i] - p), np.abs(self.hi[:, i] - p)) for p in ends[i]] for i in range(self.dims)]
        clear = [[np.maximum(np.maximum(self.lo[:, i] - p, p - self.hi[:, i]), 0.0) for p in ends[i]] for i in range(self.dims)]
        for side in (*reach, *clear):
            for x in side:
                x *= x
        # a near box that dominates reaches less far than the far box is clear, from every corner
        total = lambda sides, corner: sum(sides[i][c] for i, c in enumerate(corner))
        corners = list(itertools.islice(itertools.product((0, 1), repeat=self.dims), CORNERS))
        reaches = [total(reach, c) for c in corners]
        clears = [total(clear, c) for c in corners]
        some = np.ones(len(out), bool)
        for r, c in zip(reaches, clears, strict=True):
            some &= c * (1 + SLACK) >= r.min() * (1 - SLACK)
        far = np.flatnonzero(some)
        near = np.ones(len(out), bool)
        for r, c in zip(reaches, clears, strict=True):
            near &= r * (1 - SLACK) <= (c[far].max(initial=-1.0) * (1 + SLACK))
        rest, worst = np.flatnonzero(near), np.max(reaches, axis=0)
        if safe:
            span = sum(np.maximum(np.abs(self.hi[:, i] - o_lo[i]), np.abs(o_hi[i] - self.lo[:, i])) ** 2 for i in range(self.dims))
        lost = np.zeros(len(out), bool)  # whether a dominator may hold the origin's own row
        step = FIRST
        while len(rest) and len(far):
            # the nearest drop most of what is to be dropped
            now = np.zeros(len(rest), bool)
            now[np.argpartition(worst[rest], step)[:step] if len(rest) > step else slice(None)] = True
            now[[np.argmin(r[rest]) for r in reaches]] = True
            e, rest = rest[now], rest[~now]
            own = np.all((self.lo[e] <= o_hi) & (o_lo <= self.hi[e]), axis=1)
            left = []
            for start in range(0, len(far), max(1, AT_ONCE // len(e))):
                b = far[start : start + max(1, AT_ONCE // len(e))]
                score = None
                for (r0, r1), (c0, c1) in zip(reach, clear, strict=True):
                    term = np.minimum(c0[b][:, None] - r0[e], c1[b][:, None] - r1[e])
                    score = term if score is None else np.add(score, term, out=score)
                hit = score > ((self.dims + 8) * 2.0**-52) * (span[e] + span[b][:, None]) if safe else score > 0
                out[b] += (hit.astype(float) @ self.rows[e]).astype(np.int64)
                if self_join:
                    lost[b] |= hit @ own
                left.append(b[out[b] - lost[b] < k + self_join])  # a later dominator may cost one more
            far, step = np.concatenate(left), 4 * step
            # what is left is met by boxes only that reach less far than it is clear
            for r, c in zip(reaches, clears, strict=True):
                rest = rest[r[rest] * (1 - SLACK) <= c[far].max(initial=-1.0) * (1 + SLACK)]
        out -= lost
        out[out >= k] = -1
        return out


def counted_blocks(origins: DataFrame, train: DataFrame, k: int, dims: int, self_join: bool, safe: bool, n_origins: int) -> DataFrame:
    """origin_id, part_id, dominator_rows of kept pairs; usable boxes must be finite."""
    ends = [f"{e}_{i}" for e in ("lo", "hi") for i in range(dims)]
    n = max(1, min(BLOCKS, math.ceil(n_origins / BLOCK_ORIGINS)))
    usable = lambda m: F.col("usable") if "usable" in m.columns else F.lit(True)
    side = lambda m, block, is_train: m.select(block.alias("block"), F.lit(is_train).alias("train"), "part_id", F.col("n_rows").cast("bigint").alias("n_rows"), usable(m).alias("usable"), *[F.col(e).cast("double").alias(e) for e in ends])
    mine = side(origins, F.pmod(F.xxhash64("part_id"), F.lit(n)).cast("int"), False)
    every = side(train, F.explode(F.sequence(F.lit(0), F.lit(n - 1))), True)
    kind = {x: m.schema["part_id"].dataType.simpleString() for x, m in (("origin_id", origins), ("part_id", train))}

    def job(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        is_train = t.column("train").to_numpy()

        def of(rows: np.ndarray) -> tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray]:
            x = t.take(pa.array(rows))
            flat = x.select(ends).to_pandas().to_numpy(float) if len(rows) else np.zeros((0, 2 * dims))
            return x.column("part_id").combine_chunks(), x.column("n_rows").to_numpy(), x.column("usable").to_numpy(), flat

        o_ids, _, o_ok, o_ends = of(np.flatnonzero(~is_train))
        b_ids, b_rows, b_ok, b_ends = of(np.flatnonzero(is_train))
        good = np.flatnonzero(b_ok)
        one, group = np.unique(b_ends[good], axis=0, return_inverse=True)
        rows = np.zeros(len(one), np.int64)
        np.add.at(rows, group.ravel(), b_rows[good])
        boxes = Boxes(np.ascontiguousarray(one[:, :dims]), np.ascontiguousarray(one[:, dims:]), rows)
        alike, o_group = np.unique(np.nan_to_num(o_ends), axis=0, return_inverse=True)
        order = np.argsort(o_group.ravel(), kind="stable")
        last, found = -1, None
        for j in order:
            count = np.zeros(len(b_ids), np.int64)
            if o_ok[j]:
                if o_group.ravel()[j] != last:
                    last = o_group.ravel()[j]
                    found = boxes.dominator_rows(alike[last, :dims], alike[last, dims:], k, self_join, safe)
                count[good] = found[group.ravel()]
            kept = np.flatnonzero(count >= 0)
            for at in range(0, len(kept), 1_000_000):
                part = kept[at : at + 1_000_000]
                yield pa.RecordBatch.from_arrays([o_ids.take(pa.array(np.full(len(part), j))), b_ids.take(pa.array(part)), pa.array(count[part])], names=["origin_id", "part_id", "dominator_rows"])

    both = mine.unionByName(every).repartition(n, "block")
    return both.groupBy("block").applyInArrow(job, f"origin_id {kind['origin_id']}, part_id {kind['part_id']}, dominator_rows bigint")
