"""All-kNN joins of large tables: rows are dealt anew to tiles, whatever partitions they came in.

A tile is a leaf of a k-d layout; every point lies in one. The manifests of the tiles give kept pairs by the usual rules, and a
second stage goes by point: each distinct origin point is searched in its own tile, and asks the tiles of kept pairs only if their
box is no farther than its k-th row there. Rows at one place share one search; of a place's train rows the k of least id are enough.
"""

from __future__ import annotations

import math
import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxprune.functions.geometry import Box, clearance_sq, is_valid, point
from boxprune.plans import prune
from boxprune.plans.prune import same
from boxprune.sources.manifest import from_rows, real_points, validated
from boxprune.sources.scratch import release, stored

# tasks get the classes below with their job, so that executors need not have this package
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Distinct train points and origin rows of a tile, about; origin rows that one task takes.
TILE_POINTS, TILE_ORIGINS, CHUNK_ORIGINS = 12_000, 100_000, 250_000
#: Rows of lists with ties that one task makes, about.
LIST_ROWS = 2_000_000
#: Distinct points from which the borders of tiles are taken, about. They decide no result.
LAYOUT_POINTS = 40_000
#: Points of a leaf inside a tile; origin points that are searched at once (at most 32767).
LEAF = 64
#: Leaves beyond those that hold enough rows that are searched before others.
FIRST_LEAVES = 4
#: Origin places that one task of the brute force compares, and train places: lists of fewer blocks are to be merged. Distances
#: that are made at once stay in the cache.
BLOCK, TRAIN_BLOCK, AT_ONCE = 8192, 65_536, 131_072
#: Rows from which on a frame that numbers its rows is dealt in so many waves, each of which shuffles its share only.
WAVE_ROWS, WAVES = 10_000_000, 3
#: Allowance for rounding where bounds are compared.
SLACK = 1 + 1e-9
#: Allowance for rounding of products of matrices, by the square of the coordinates' size.
ROUNDING = 1e-12


class Layout:
    """Halves of halves, in heap order: a point goes right of node n iff its coordinate on axis[n] is at[n] or more."""

    def __init__(self, sample: np.ndarray, tiles: int):
        self.depth = max(0, min(12, math.ceil(math.log2(max(1, tiles)))))
        self.dims = sample.shape[1]
        self.axis, self.at = np.zeros(2**self.depth, int), np.full(2**self.depth, np.inf)
        parts = {1: sample}
        for n in range(1, 2**self.depth):
            x = parts.pop(n, sample[:0])
            if len(x) > 3 and (axis := int(np.argmax(np.ptp(x, axis=0)))) >= 0:
                v = x[:, axis]
                at = np.median(v)
                if at == v.min():
                    at = v[v > at].min(initial=np.inf)
                self.axis[n], self.at[n] = axis, at
                parts[2 * n], parts[2 * n + 1] = x[v < at], x[v >= at]

    def tile(self, x: np.ndarray) -> np.ndarray:
        node, rows = np.ones(len(x), int), np.arange(len(x))
        for _ in range(self.depth):
            node = 2 * node + (x[rows, self.axis[node]] >= self.at[node])
        return node - 2**self.depth

    def border_sq(self, tile: int, x: np.ndarray) -> np.ndarray:
        """Squared distance from points of a tile to the nearest place outside it."""
        lo, hi = np.full(self.dims, -np.inf), np.full(self.dims, np.inf)
        for level in range(self.depth):
            number = tile + 2**self.depth
            n, right = number >> (self.depth - level), number >> (self.depth - level - 1) & 1
            end = lo if right else hi
            end[self.axis[n]] = self.at[n]
        return np.minimum(x - lo, hi - x).min(axis=1) ** 2


def _squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances, added in the order of the axes as every engine does."""
    d = None
    for x, y in zip(a.T, np.ascontiguousarray(b.T), strict=True):
        step = x[:, None] - y
        step *= step
        d = step if d is None else np.add(d, step, out=d)
    return d


def _halved(x: np.ndarray, size: int) -> list[np.ndarray]:
    """Row numbers in groups of at most size that lie together."""
    todo, out = [np.arange(len(x))] if len(x) else [], []
    while todo:
        part = todo.pop()
        if len(part) <= size:
            out.append(part)
            continue
        v = x[part]
        order = np.argpartition(v[:, int(np.argmax(np.ptp(v, axis=0)))], len(part) // 2)
        todo += [part[order[len(part) // 2 :]], part[order[: len(part) // 2]]]
    return out


def _spread(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, … (count[0] numbers), start[1], …"""
    return np.repeat(start - np.concatenate([[0], np.cumsum(count)[:-1]]) if len(count) else start, count) + np.arange(count.sum())


class Places:
    """Distinct points with the ids of their rows in order, of the least ``most`` ids each, and an index of leaves."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, most: int | None = None):
        order = np.lexsort((ids, *x.T[::-1]))
        x, self.ids = x[order], ids[order]
        new = np.ones(len(x), bool)
        new[1:] = (x[1:] != x[:-1]).any(axis=1)
        group = np.cumsum(new) - 1
        if most is not None:
            near = np.arange(len(x)) - np.flatnonzero(new)[group] < most
            x, self.ids, new, group = x[near], self.ids[near], new[near], group[near]
        self.rows, self.x, self.start = x, x[new], np.flatnonzero(new)
        self.count = np.diff(np.append(self.start, len(x)))

    def _leaves(self) -> None:
        parts = _halved(self.x, LEAF)
        self.leaf = np.concatenate([p for p in parts])
        self.leaf_size = np.array([len(p) for p in parts])
        self.leaf_at = np.concatenate([[0], np.cumsum(self.leaf_size)])
        self.lo, self.hi = (np.stack([f(self.x[p], axis=0) for p in parts]) for f in (np.min, np.max))
        self.middle = (self.lo + self.hi) / 2

    def search(self, q: np.ndarray, want: int, cap: np.ndarray | None = None, border: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(number of q, id, squared distance) of all rows no farther than the want-th row of q (and cap), and that row's squared
        distance for each q, infinite where there are fewer rows. With border, no rows but these distances, and where border is
        farther than a few leaves have their rows, a bound in place of the distance."""
        last = np.full(len(q), np.inf)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        if len(self.x) and len(q):
            self._leaves()
            single = len(self.ids) == len(self.x)
            for part in _halved(q, LEAF):
                a = q[part]
                lo, hi = a.min(axis=0), a.max(axis=0)
                gap = (np.maximum(np.maximum(self.lo - hi, lo - self.hi), 0) ** 2).sum(axis=1)
                # a first few leaves, those about the middle, tell how far the others may lie
                apart = (((lo + hi) / 2 - self.middle) ** 2).sum(axis=1)
                if cap is not None:
                    apart[gap > cap[part].max() * SLACK] = np.inf
                order = np.argsort(apart, kind="stable")[: int(np.isfinite(apart).sum())]
                first = int(np.searchsorted(np.cumsum(self.leaf_size[order]), want)) + FIRST_LEAVES
                if border is not None and len(self.x) >= want:
                    at = order[: first - FIRST_LEAVES + 1]
                    sure = (np.maximum(hi - self.lo[at], self.hi[at] - lo) ** 2).sum(axis=1).max()
                    last[part] = sure
                    part = part[border[part] <= sure * SLACK]
                    a = q[part]
                    if not len(part):
                        continue
                near = self.leaf[_spread(self.leaf_at[order[:first]], self.leaf_size[order[:first]])]
                if not len(near):
                    continue
                d = _squares(a, self.x[near])
                most = self._kth(d, near, want, single)
                if border is not None:
                    last[part] = most
                    ok = border[part] <= most * SLACK
                    part, a, d, most = part[ok], a[ok], d[ok], most[ok]
                    if not len(part):
                        continue
                if cap is not None:
                    most = np.minimum(most, cap[part])
                i, j = np.nonzero(d <= most[:, None])
                d, place = d[i, j], near[j]
                others = order[first:][gap[order[first:]] <= most.max(initial=0.0) * SLACK]
                if len(others):
                    more = self.leaf[_spread(self.leaf_at[others], self.leaf_size[others])]
                    n, j = self._within(a, more, most)
                    i, d, place = np.concatenate([i, n]), np.concatenate([d, self._exact(a, n, more[j])]), np.concatenate([place, more[j]])
                by = np.argsort(i.astype(np.int16), kind="stable")
                i, d, place = i[by], d[by], place[by]
                count = np.bincount(i, minlength=len(part))
                at = np.arange(len(i)) - (np.cumsum(count) - count)[i]
                wide, whose = np.full((len(part), max(1, count.max())), np.inf), np.zeros((len(part), max(1, count.max())), int)
                wide[i, at], whose[i, at] = d, place
                kth = self._kth(wide, whose, want, single)
                last[part] = kth
                if border is not None:
                    continue
                ok = d <= np.minimum(kth, most)[i]
                found.append((part[i[ok]], place[ok], d[ok]))
        if not found:
            return np.zeros(0, int), np.zeros(0, np.int64), np.zeros(0), last
        number, place, d2 = (np.concatenate(c) for c in zip(*found, strict=True))
        count = self.count[place]
        return np.repeat(number, count), self.ids[_spread(self.start[place], count)], np.repeat(d2, count), last

    def _within(self, q: np.ndarray, places: np.ndarray, most: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of q and places that may be no farther than most: distances by one product of matrices, with an allowance for
        its rounding. No pair within most is lost; those beyond are told by their exact distances."""
        middle = (q.min(axis=0) + q.max(axis=0)) / 2
        a, b = q - middle, self.x[places] - middle
        a2, b2 = (a * a).sum(axis=1), (b * b).sum(axis=1)
        one = lambda v: np.ones((len(v), 1))
        d = np.hstack([a, one(a), a2[:, None]]) @ np.hstack([-2 * b, b2[:, None], one(b)]).T
        size = np.abs(middle).max() + np.sqrt(max(a2.max(), b2.max(initial=0.0)))
        return np.nonzero(d <= (most * SLACK + ROUNDING * size * size)[:, None])

    def _exact(self, q: np.ndarray, number: np.ndarray, places: np.ndarray) -> np.ndarray:
        """Squared distances of pairs, as _squares gives them."""
        d = None
        for x, y in zip(q.T, self.x.T, strict=True):
            step = x[number] - y[places]
            step *= step
            d = step if d is None else np.add(d, step, out=d)
        return d

    def _kth(self, d: np.ndarray, places: np.ndarray, want: int, single: bool = False) -> np.ndarray:
        """Squared distance of the want-th row, where a place is as many rows as it holds (single: one)."""
        if single or (self.count[places] == 1).all():
            return np.partition(d, want - 1, axis=1)[:, want - 1] if want <= d.shape[1] else np.full(len(d), np.inf)
        places = np.broadcast_to(places, d.shape)
        n = min(want, d.shape[1])
        part = np.argpartition(d, n - 1, axis=1)[:, :n] if n < d.shape[1] else np.broadcast_to(np.arange(n), d.shape)
        near = np.take_along_axis(d, part, axis=1)
        order = np.argsort(near, axis=1, kind="stable")
        enough = np.cumsum(np.take_along_axis(self.count[np.take_along_axis(places, part, axis=1)], order, axis=1), axis=1) >= want
        at = np.take_along_axis(order, enough.argmax(axis=1)[:, None], axis=1)
        return np.where(enough[:, -1], np.take_along_axis(near, at, axis=1)[:, 0], np.inf)


def _points(t: pa.Table, dims: int) -> np.ndarray:
    return np.stack([t.column(f"x_{i}").to_numpy() for i in range(dims)], axis=1) if t.num_rows else np.zeros((0, dims))


def _ids(t: pa.Table, column: str = "id") -> np.ndarray:
    return t.column(column).to_numpy().astype(np.int64)


def _xs(dims: int) -> list[str]:
    return [f"x_{i}" for i in range(dims)]


def _schema(dims: int, *more: str) -> str:
    return ", ".join([*more, *[f"{x} double" for x in _xs(dims)]])


def totals(points: DataFrame, dims: int) -> tuple[int, int, bool]:
    """Rows, distinct points (about) and whether all coordinates are finite: one row."""
    one = real_points(points, dims).agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.struct(*_xs(dims))).alias("d"), *[f(x).alias(f"{e}_{i}") for i, x in enumerate(_xs(dims)) for f, e in ((F.min, "lo"), (F.max, "hi"))])
    row = one.select("n", "d", is_valid(Box.of("", dims)).alias("ok")).first()
    return row["n"], row["d"], row["ok"]


def _dealt(points: DataFrame, layout: Layout, dims: int, n_rows: int) -> DataFrame:
    def job(batches):
        for b in batches:
            x = np.stack([b.column(f"x_{i}").to_numpy(zero_copy_only=False) for i in range(dims)], axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(layout.tile(x), pa.int64()), *b.columns], names=["tile", *b.schema.names])

    waves = points._waves(WAVES) if n_rows >= WAVE_ROWS and hasattr(points, "_waves") else [points]
    rows = [real_points(df, dims).select(F.col("id").cast("bigint").alias("id"), *[F.col(x).cast("double").alias(x) for x in _xs(dims)]) for df in waves]
    return stored(*[df.mapInArrow(job, _schema(dims, "tile long", "id long")) for df in rows])


def _chunked(origins: DataFrame, others: DataFrame, dims: int, want: int, ties: str) -> DataFrame:
    """tile, chunks: tasks that a tile's origin rows are dealt to. With all ties, lists are as long as the places' rows make them."""
    sizes = origins.select(F.col("part_id").alias("tile"), "n_rows")
    if ties != "all":
        return stored(sizes.select("tile", F.ceil(F.col("n_rows") / CHUNK_ORIGINS).cast("int").alias("chunks")))
    tied = others.groupBy("tile", *_xs(dims)).agg(F.count(F.lit(1)).alias("n")).groupBy(F.col("tile").alias("at")).agg((F.sum(F.col("n") * F.col("n")) / F.sum("n")).alias("tied"))
    rows = F.col("n_rows") * (want + F.coalesce("tied", F.lit(0.0)))
    return stored(sizes.join(tied, F.col("tile") == F.col("at"), "left").select("tile", F.ceil(F.greatest(F.col("n_rows") / CHUNK_ORIGINS, rows / LIST_ROWS)).cast("int").alias("chunks")))


def _lists(x: np.ndarray, mine: np.ndarray, train: Places, answers: pa.Table, k: int, dims: int, exclude_self: bool, ties: str = "none") -> pa.Table:
    """The lists of a tile's origin rows (points x, ids mine), of its train rows and of what other tiles answered."""
    want = k + exclude_self
    # origin rows and answers, numbered by place
    both = np.concatenate([x, _points(answers, dims)])
    places = Places(both, np.arange(len(both)))
    number_of = np.empty(len(both), int)
    number_of[places.ids] = np.repeat(np.arange(len(places.x)), places.count)
    number, near, d2, _ = train.search(places.x, want)
    if answers.num_rows:
        number, near, d2 = np.concatenate([number, number_of[len(mine) :]]), np.concatenate([near, _ids(answers)]), np.concatenate([d2, answers.column("d2").to_numpy()])
    order = np.lexsort((near, d2, number))
    number, near, d2 = number[order], near[order], d2[order]
    count = np.bincount(number, minlength=len(places.x))
    start = np.cumsum(count) - count
    if ties != "all":
        ok = np.arange(len(number)) - start[number] < want
        near, d2 = near[ok], d2[ok]
        count = np.minimum(count, want)
        start = np.cumsum(count) - count
    at = number_of[: len(mine)]
    row, entry = np.repeat(np.arange(len(mine)), count[at]), _spread(start[at], count[at])
    if exclude_self:
        ok = near[entry] != mine[row]
        row, entry = row[ok], entry[ok]
    here = np.arange(len(row))
    fresh = np.ones(len(row), bool)
    fresh[1:] = row[1:] != row[:-1]
    begin = np.maximum.accumulate(np.where(fresh, here, 0)) if len(row) else here
    if ties == "all":
        step = fresh.copy()
        step[1:] |= d2[entry[1:]] != d2[entry[:-1]]
        here = np.maximum.accumulate(np.where(step, here, 0)) if len(row) else here
    rank = here - begin + 1
    ok = rank <= k
    row, entry, rank = row[ok], entry[ok], rank[ok]
    return pa.table({"origin_id": mine[row], "neighbour_id": near[entry], "rank": pa.array(rank, pa.int32()), "distance": np.sqrt(d2[entry])})


def _ask(layout: Layout, tile: int, q: np.ndarray, train: Places, want: int) -> pa.Table:
    """Points of a tile whose want-th row there is no nearer than the tile's border."""
    border = layout.border_sq(tile, q)
    last = train.search(q, want, border=border)[3]
    out = border <= last * SLACK
    return pa.table({"tile": pa.array(np.full(int(out.sum()), tile), pa.int64()), "bound": last[out], **{f"x_{i}": q[out, i] for i in range(q.shape[1])}})


def _asked(pairs: DataFrame, boxes: DataFrame, dims: int):
    """Gives asking points the tiles of kept pairs whose boxes are within their bounds."""
    kept = pairs.where("origin_id <> part_id").select("origin_id", F.col("part_id").alias("to")).join(prune._named(boxes, "b_", dims), same("to", "b_id"))
    return lambda df: df.join(kept, F.col("tile") == F.col("origin_id")).where(clearance_sq(point("", dims), Box.of("b_", dims)) <= F.col("bound") * SLACK).select("to", "tile", "bound", *_xs(dims))


def _answer(asked: pa.Table, train: Places, want: int, dims: int) -> pa.Table:
    q = _points(asked, dims)
    number, ids, d2, _ = train.search(q, want, asked.column("bound").to_numpy())
    return pa.table({"tile": pa.array(_ids(asked, "tile")[number], pa.int64()), "id": ids, "d2": d2, **{f"x_{i}": q[number, i] for i in range(dims)}})


def _whole_tiles(rows: DataFrame, others: DataFrame | None, layout: Layout, asked, k: int, dims: int, exclude_self: bool) -> DataFrame:
    """The steps of knn_tiles where each tile's rows fit one task: both sides are shuffled once, and every step reads that shuffle.
    others: None if the rows are joined with themselves."""
    want, self_join = k + exclude_self, others is None
    both = rows if others is None else rows.withColumn("train", F.lit(False)).unionByName(others.withColumn("train", F.lit(True)))
    both = both.groupBy("tile")

    def sides(t: pa.Table) -> tuple[np.ndarray, np.ndarray, Places]:
        x, ids = _points(t, dims), _ids(t)
        if self_join:
            return x, ids, Places(x, ids, want)
        is_train = t.column("train").to_numpy(zero_copy_only=False)
        return x[~is_train], ids[~is_train], Places(x[is_train], ids[is_train], want)

    def asking(key, t):  # Spark takes hints here for another form of function
        x, ids, train = sides(t)
        return _ask(layout, key[0].as_py(), train.x if self_join else Places(x, ids, 1).x, train, want)

    def answering(left: pa.Table, right: pa.Table) -> pa.Table:
        return _answer(left, sides(right)[2], want, dims)

    def lists(left: pa.Table, right: pa.Table) -> pa.Table:
        x, ids, train = sides(left)
        return _lists(x, ids, train, right, k, dims, exclude_self)

    asks = asked(both.applyInArrow(asking, _schema(dims, "tile long", "bound double")))
    answers = asks.groupBy("to").cogroup(both).applyInArrow(answering, _schema(dims, "tile long", "id long", "d2 double"))
    return both.cogroup(answers.groupBy("tile")).applyInArrow(lists, "origin_id long, neighbour_id long, rank int, distance double")


def knn_tiles(r: DataFrame, s: DataFrame, k: int, dims: int, rule: str = "counted", plan: str = "auto", exclude_self: bool = False, ties: str = "none", sizes: tuple[int, int] | None = None) -> DataFrame:
    """The k nearest rows of s for each row of r; all coordinates must be finite. sizes: origin rows and distinct train points."""
    want, xs = k + exclude_self, _xs(dims)
    n_r, d_s = sizes or (totals(r, dims)[0], totals(s, dims)[1])
    some = real_points(s, dims).select(*[F.col(x).cast("double").alias(x) for x in xs]).where(F.pmod(F.xxhash64(*xs), F.lit(max(1, d_s // LAYOUT_POINTS))) == 0).distinct().limit(5 * LAYOUT_POINTS)
    layout = Layout(_points(some.toArrow(), dims), max(math.ceil(d_s / TILE_POINTS), math.ceil(n_r / TILE_ORIGINS)))
    rows = _dealt(r, layout, dims, n_r)
    others = rows if r is s else _dealt(s, layout, dims, d_s)
    release(rows.sparkSession)  # what made the rows, such as ids that number them, may have shuffled whole tables
    manifest = lambda df: stored(validated(from_rows(df, dims, "tile"), dims))
    origins = manifest(rows)
    boxes = origins if r is s else manifest(others)
    pairs = prune.keep_pairs(origins, boxes, k, dims, rule, plan, exclude_self, safe=True)
    most = sum(df.agg(F.max("n_rows")).first()[0] or 0 for df in ((origins,) if r is s else (origins, boxes)))
    if ties != "all" and most <= CHUNK_ORIGINS:
        return _whole_tiles(rows, None if r is s else others, layout, _asked(pairs, boxes, dims), k, dims, exclude_self)
    chunks = F.broadcast(_chunked(origins, others, dims, want, ties))  # a row a tile, 4096 at most
    every = lambda df: df.join(chunks, "tile").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).drop("chunks")
    one_of = lambda df, *by: df.join(chunks, "tile").withColumn("chunk", F.pmod(F.xxhash64(*by), F.col("chunks")).cast("int")).drop("chunks")

    def least(t: pa.Table) -> pa.Table:
        p = Places(_points(t, dims), _ids(t), want)
        return pa.table({"tile": pa.array(np.repeat(t.column("tile")[0].as_py(), len(p.ids)), pa.int64()), "id": p.ids, **{x: p.rows[:, i] for i, x in enumerate(xs)}})

    if ties == "all":
        train = others.sparkSession.read.schema(others.schema).parquet(others._stored_at)  # a scan of its own, to be told apart in joins
    else:  # equal points are dealt by id, so that no task holds all rows of one place
        many = F.broadcast(boxes.select(F.col("part_id").alias("tile"), F.ceil(F.col("n_rows") / (4 * CHUNK_ORIGINS)).cast("int").alias("n")))
        train = stored(others.join(many, "tile").groupBy("tile", F.pmod(F.xxhash64("id"), F.col("n")).alias("salt")).applyInArrow(least, _schema(dims, "tile long", "id long")))
        release(rows.sparkSession)

    def asking(key, left: pa.Table, right: pa.Table) -> pa.Table:
        return _ask(layout, key[0].as_py(), _points(left, dims), Places(_points(right, dims), _ids(right), None if ties == "all" else want), want)

    q = one_of(rows.select("tile", *xs).distinct(), *xs)
    asked = q.groupBy("tile", "chunk").cogroup(every(train).groupBy("tile", "chunk")).applyInArrow(asking, _schema(dims, "tile long", "bound double"))
    asked = _asked(pairs, boxes, dims)(asked)

    def answering(left: pa.Table, right: pa.Table) -> pa.Table:
        return _answer(left, Places(_points(right, dims), _ids(right), None if ties == "all" else want), want, dims)

    answers = asked.groupBy("to").cogroup(train.groupBy("tile")).applyInArrow(answering, _schema(dims, "tile long", "id long", "d2 double"))

    def lists(left: pa.Table, right: pa.Table) -> pa.Table:
        is_train = left.column("train").to_numpy(zero_copy_only=False)
        x, ids = _points(left, dims), _ids(left)
        return _lists(x[~is_train], ids[~is_train], Places(x[is_train], ids[is_train], None if ties == "all" else want), right, k, dims, exclude_self, ties)

    left = one_of(rows, "id").withColumn("train", F.lit(False)).unionByName(every(train).withColumn("train", F.lit(True)))
    return left.groupBy("tile", "chunk").cogroup(every(answers).groupBy("tile", "chunk")).applyInArrow(lists, "origin_id long, neighbour_id long, rank int, distance double")


def knn_blocks(r: DataFrame, s: DataFrame, k: int, dims: int, exclude_self: bool = False, sizes: tuple[int, int] | None = None) -> DataFrame:
    """Brute force: every place of r meets every place of s, in blocks. Rows at one place have one list. sizes: distinct points."""
    want, xs = k + exclude_self, _xs(dims)
    d_r, d_s = sizes or (totals(r, dims)[1], totals(s, dims)[1])
    n_a, n_b = max(1, math.ceil(d_r / BLOCK)), max(1, math.ceil(d_s / TRAIN_BLOCK))
    real = lambda df: real_points(df, dims).select(F.col("id").cast("bigint").alias("id"), *[F.col(x).cast("double").alias(x) for x in xs])
    number = lambda n: F.pmod(F.xxhash64(*xs), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))

    def job(left: pa.Table, right: pa.Table) -> pa.Table:
        q, p = _points(left, dims), Places(_points(right, dims), _ids(right), want)
        found = []
        groups = len(p.x) // 64
        rows = max(1, AT_ONCE // max(1, len(p.x)))
        for at in range(0, len(q) if len(p.x) else 0, rows):
            d = _squares(q[at : at + rows], p.x)
            if groups >= 2 * want:  # the want-th least of disjoint groups' minima is no less than the want-th of all
                apart = d[:, : groups * 64].reshape(len(d), 64, groups)
                least = apart.min(axis=1)
                top = np.partition(least, want - 1, axis=1)[:, want - 1]
                i, g = np.nonzero(least <= top[:, None])
                n, m = np.nonzero(apart[i, :, g] <= top[i, None])
                tail, j = np.nonzero(d[:, groups * 64 :] <= top[:, None])
                i, j = np.concatenate([i[n], tail]), np.concatenate([m * groups + g[n], groups * 64 + j])
            else:
                top = p._kth(d, np.arange(d.shape[1]), want)
                i, j = np.nonzero(d <= top[:, None])
            count = p.count[j]
            i, ids, d2 = np.repeat(i, count), p.ids[_spread(p.start[j], count)], np.repeat(d[i, j], count)
            order = np.lexsort((ids, d2, i))
            i, ids, d2 = i[order], ids[order], d2[order]
            count = np.bincount(i, minlength=len(d))
            ok = np.arange(len(i)) - (np.cumsum(count) - count)[i] < want
            found.append((at + i[ok], ids[ok], d2[ok]))
        i, ids, d2 = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, int), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"neighbour_id": ids, "d2": d2, **{x: q[i, n] for n, x in enumerate(xs)}})

    a = real(r).select(*xs).distinct().withColumn("a", number(n_a)).withColumn("b", every(n_b))
    b = real(s).withColumn("b", number(n_b)).withColumn("a", every(n_a))
    near = a.groupBy("a", "b").cogroup(b.groupBy("a", "b")).applyInArrow(job, _schema(dims, "neighbour_id long", "d2 double"))
    place = lambda by: F.row_number().over(Window.partitionBy(*by).orderBy("d2", "neighbour_id"))
    near = near.withColumn("rank", place(xs)).where(F.col("rank") <= want)
    out = real(r).withColumnRenamed("id", "origin_id").join(near, xs)
    if exclude_self:
        out = out.where("origin_id <> neighbour_id").withColumn("rank", place(["origin_id"])).where(F.col("rank") <= k)
    return out.select("origin_id", "neighbour_id", "rank", F.sqrt("d2").alias("distance"))
