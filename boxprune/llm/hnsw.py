"""Nearest neighbours by one hierarchical navigable small-world graph a shard.

Equal vectors are one node that keeps its smallest ids (one more than k, so none is missing from any answer). Nodes are dealt
to shards of about ``SHARD_ROWS`` by a hash of the vector; every shard's graph is stored as one row of flat arrays: vectors, ids,
neighbours of layer 0 (a row of ``2 M`` each), and neighbours of the upper layers. A shard's graph is built in blocks, not
row by row: a layer's links are chosen among exact nearest rows, so the graph is that of the method, made without
its insertions. Blocks of queries meet each shard and descend together; the shards' answers are merged by distance, then id.
Distances are recomputed in double precision on the original vectors.

Vectors that are null, empty, zero, or hold nulls or non-finite components take no part, nor do null ids. Vectors of
different lengths never meet. Repeated rows count once. An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxprune.llm.kernels import release
from boxprune.llm.shared import stored

SHARD_ROWS = 8192
QUERY_ROWS = 1024
M = 12
EF_SEARCH = 48
#: Nearest rows among which a row's neighbours are chosen; rows of one block of distances; slots expanded in one step; slots
#: of an upper layer from which the next one is searched, so that the search also reaches groups of rows close together.
CANDIDATES, BLOCK, EXPAND, ENTRIES = 32, 512, 6, 24


def _width(level: int, m: int = M) -> int:
    return 2 * m if level == 0 else 6 * m


class Graph:
    """Flat-array graph over n rows of vectors, kept as float32 relative to the rows' mean and spread.

    Every layer holds its members' neighbour slots. A layer is built at once: each member's nearest others come from
    blocks of distances, the diverse ones among them are linked, and links are also laid backwards where there is room or where
    they are nearer. Queries descend together, one row of state each.
    """

    def __init__(self, x: np.ndarray, centre: np.ndarray | None = None, scale: float = 1.0, layers: list[np.ndarray] | None = None, members: list[np.ndarray] | None = None, m: int = M):
        if centre is None:
            centre = x.mean(axis=0) if len(x) else np.zeros(x.shape[1])
            scale = float(np.abs(x - centre).max(initial=0.0)) or 1.0
        self.centre, self.scale, self.m = centre, scale, m
        self.x = self.near_zero(x)
        self.sq = np.einsum("ij,ij->i", self.x, self.x)
        if layers is None:
            self.build()
        else:
            self.layers, self.members = layers, members

    def near_zero(self, x: np.ndarray) -> np.ndarray:
        return ((x - self.centre) / self.scale).astype(np.float32)

    def build(self) -> None:
        n = len(self.x)
        rng = np.random.Generator(np.random.PCG64(7))
        height = np.minimum((-np.log(1 - rng.random(n)) / math.log(self.m)).astype(int), 12)
        self.members = [np.flatnonzero(height >= level) for level in range(int(height.max(initial=0)) + 1)]
        self.layers = [self.link(at, level) for level, at in enumerate(self.members)]

    def link(self, at: np.ndarray, level: int) -> np.ndarray:
        """Neighbours (as slots of the layer, -1 for none) of the members ``at``. Upper layers are sparse, so they get more links,
        which also lead out of groups of rows close together."""
        n, m, width = len(at), self.m * (1 if level == 0 else 3), _width(level, self.m)
        rows = np.full((n, width), -1, np.int32)
        if n < 2:
            return rows
        x, sq = self.x[at], self.sq[at]
        most = min(n - 1, CANDIDATES * (1 if level == 0 else 3))
        near, dist = np.empty((n, most), np.int32), np.empty((n, most), np.float32)
        for s in range(0, n, BLOCK):
            d = sq[s : s + BLOCK, None] + sq[None, :] - 2.0 * (x[s : s + BLOCK] @ x.T)
            d[np.arange(len(d)), np.arange(s, s + len(d))] = np.inf
            pick = np.argpartition(d, most - 1, axis=1)[:, :most] if most < n - 1 else np.argsort(d, axis=1)[:, :most]
            own = np.take_along_axis(d, pick, axis=1)
            order = np.argsort(own, axis=1, kind="stable")
            near[s : s + BLOCK], dist[s : s + BLOCK] = np.take_along_axis(pick, order, axis=1), np.take_along_axis(own, order, axis=1)
        # one candidate after another: it is diverse if it is nearer to the row than to all that were kept before it
        chosen = np.zeros((n, most), bool)
        for s in range(0, n, BLOCK):
            c = near[s : s + BLOCK]
            v = x[c]
            gram = sq[c][:, :, None] + sq[c][:, None, :] - 2.0 * (v @ v.transpose(0, 2, 1))
            keep = chosen[s : s + BLOCK]
            for j in range(most):
                blocked = (keep[:, :j] & (gram[:, j, :j] < dist[s : s + BLOCK, j, None])).any(axis=1)
                keep[:, j] = ~blocked & (keep[:, :j].sum(axis=1) < m)
            short = m - keep.sum(axis=1)
            rest = np.cumsum(~keep, axis=1)
            keep |= ~keep & (rest <= short[:, None])  # a view of chosen
        of, j = np.nonzero(chosen)
        to, d = near[of, j], dist[of, j]
        # forward links first, then backward ones, the nearest of them up to the width
        owner, other = np.concatenate([of, to]), np.concatenate([to, of])
        back, length = np.repeat([0, 1], len(of)), np.concatenate([d, d])
        order = np.lexsort((length, back, owner))
        owner, other = owner[order], other[order]
        pair = owner.astype(np.int64) * n + other
        first = np.zeros(len(pair), bool)
        first[np.unique(pair, return_index=True)[1]] = True
        owner, other = owner[first], other[first]
        place = np.arange(len(owner)) - np.searchsorted(owner, owner)
        fits = place < width
        rows[owner[fits], place[fits]] = other[fits]
        return rows

    def search(self, queries: np.ndarray, ef: int) -> np.ndarray:
        """Row numbers of the ef nearest found of each query, -1 where there are fewer."""
        q = self.near_zero(queries)
        qsq = np.einsum("ij,ij->i", q, q)
        entry = np.full((len(q), 1), self.members[-1][0])
        for level in range(len(self.layers) - 1, 0, -1):
            at = self.members[level]
            found = self.beam(q, qsq, np.where(entry < 0, -1, np.searchsorted(at, entry)), level, ENTRIES)
            entry = np.where(found < 0, -1, at[found])
        return self.beam(q, qsq, entry, 0, ef)

    def beam(self, q, qsq, entry, level: int, ef: int) -> np.ndarray:
        """Best-first search of a layer by all queries at once: the nearest few slots that were not expanded yet give their
        neighbours, until none of a query's best ef is left to expand."""
        rows, at, n = self.layers[level], self.members[level], len(q)
        x, sq = (self.x, self.sq) if level == 0 else (self.x[at], self.sq[at])
        step = min(EXPAND, ef)
        slots = np.full((n, ef), -1, np.int64)
        dists = np.full((n, ef), np.inf, np.float32)
        done = np.ones((n, ef), bool)
        seen = np.zeros((n, len(at)), bool)
        for j in range(entry.shape[1]):
            own = np.flatnonzero(entry[:, j] >= 0)
            to = entry[own, j]
            slots[own, j], done[own, j], seen[own, to] = to, False, True
            dists[own, j] = sq[to] + qsq[own] - 2.0 * np.einsum("ij,ij->i", x[to], q[own])
        live = np.arange(n)
        while len(live):
            left = np.where(done[live], np.inf, dists[live])
            pick = np.argsort(left, axis=1, kind="stable")[:, :step] if step < ef else np.tile(np.arange(ef), (len(live), 1))
            ok = np.isfinite(np.take_along_axis(left, pick, axis=1))
            some = ok.any(axis=1)
            live, pick, ok = live[some], pick[some], ok[some]
            if not len(live):
                break
            mark = done[live]
            np.put_along_axis(mark, pick, True, axis=1)
            done[live] = mark
            near = np.where(ok[:, :, None], rows[np.take_along_axis(slots[live], pick, axis=1)], -1).reshape(len(live), -1).astype(np.int64)
            own, col = np.nonzero(near >= 0)
            to = near[own, col]
            key = np.unique(own * len(at) + to)
            own, to = key // len(at), key % len(at)
            fresh = ~seen[live[own], to]
            own, to = own[fresh], to[fresh]
            seen[live[own], to] = True
            d = sq[to] + qsq[live[own]] - 2.0 * np.einsum("ij,ij->i", x[to], q[live[own]])
            count = np.bincount(own, minlength=len(live))
            wide = int(count.max(initial=0))
            if not wide:
                continue
            new_d, new_s = np.full((len(live), wide), np.inf, np.float32), np.full((len(live), wide), -1, np.int64)
            place = np.arange(len(own)) - np.repeat(np.cumsum(count) - count, count)
            new_d[own, place], new_s[own, place] = d, to
            all_d, all_s = np.concatenate([dists[live], new_d], axis=1), np.concatenate([slots[live], new_s], axis=1)
            all_done = np.concatenate([done[live], new_s < 0], axis=1)
            order = np.argsort(all_d, axis=1, kind="stable")[:, :ef]
            dists[live], slots[live], done[live] = (np.take_along_axis(v, order, axis=1) for v in (all_d, all_s, all_done))
        return slots


def _usable(vec: str):
    ok = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.col(vec).isNotNull() & (F.size(vec) > 0) & ok & F.exists(vec, lambda x: x != 0)


def usable_vectors(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    picked = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))
    return picked.where(F.col("id").isNotNull() & _usable("vec"))


def build_index(vectors: DataFrame, k: int, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """One row a shard: dim, shard, and the graph's flat arrays. vectors: usable (id, vec)."""
    first = Window.partitionBy("vec").orderBy("id")
    nodes = vectors.distinct().withColumn("r", F.row_number().over(first)).where(F.col("r") <= k + 1)
    nodes = stored(nodes.groupBy("vec").agg(F.sort_array(F.collect_list("id")).alias("ids")).withColumn("dim", F.size("vec")))
    shards = nodes.groupBy("dim").agg(F.ceil(F.count(F.lit(1)) / shard_rows).cast("int").alias("shards"))
    dealt = nodes.join(F.broadcast(shards), "dim").withColumn("shard", F.pmod(F.xxhash64("vec"), F.col("shards")).cast("int"))  # one row for each vector length

    def build(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        dim = table.column("dim")[0].as_py()
        x = np.stack([np.asarray(v, np.float64) for v in table.column("vec").to_pylist()])
        ids = table.column("ids").to_pylist()
        order = np.argsort([i[0] for i in ids], kind="stable")
        x, ids = x[order], [ids[i] for i in order]
        g = Graph(x)
        counts = np.array([len(i) for i in ids], np.int32)
        row = {
            "dim": [dim], "shard": [table.column("shard")[0].as_py()], "vectors": [x.tobytes()], "counts": [counts.tobytes()],
            "ids": [np.array([v for i in ids for v in i], np.int64).tobytes()], "sizes": [[len(a) for a in g.members]],
            "members": [b"".join(np.asarray(a, np.int32).tobytes() for a in g.members[1:])], "neighbours": [b"".join(a.tobytes() for a in g.layers)],
            "centre": [g.centre.tobytes()], "scale": [g.scale],
        }
        return pa.table(row, schema=_INDEX)

    return dealt.select("dim", "shard", "vec", "ids").groupBy("dim", "shard").applyInArrow(build, _INDEX_DDL)


_INDEX_DDL = "dim int, shard int, vectors binary, counts binary, ids binary, sizes array<int>, members binary, neighbours binary, centre binary, scale double"
_INDEX = pa.schema([("dim", pa.int32()), ("shard", pa.int32()), ("vectors", pa.binary()), ("counts", pa.binary()), ("ids", pa.binary()), ("sizes", pa.list_(pa.int32())), ("members", pa.binary()), ("neighbours", pa.binary()), ("centre", pa.binary()), ("scale", pa.float64())])


def _open(row: dict) -> tuple[Graph, np.ndarray, list[np.ndarray]]:
    x = np.frombuffer(row["vectors"], np.float64).reshape(-1, row["dim"])
    counts = np.frombuffer(row["counts"], np.int32)
    ids = np.split(np.frombuffer(row["ids"], np.int64), np.cumsum(counts)[:-1])
    sizes = row["sizes"]
    flat, upper = np.frombuffer(row["neighbours"], np.int32), np.frombuffer(row["members"], np.int32)
    layers, at = [], 0
    for level, n in enumerate(sizes):
        width = _width(level)
        layers.append(flat[at : at + n * width].reshape(n, width))
        at += n * width
    members = [np.arange(sizes[0]), *np.split(upper, np.cumsum(sizes[1:])[:-1])] if len(sizes) > 1 else [np.arange(sizes[0])]
    return Graph(x, np.frombuffer(row["centre"], np.float64), row["scale"], layers, members), x, ids


def search_index(index: DataFrame, queries: DataFrame, k: int, ef: int = EF_SEARCH, query_rows: int = QUERY_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest found; queries: usable (id, vec). Shards are visited by blocks of queries."""
    queries = queries.distinct().withColumn("dim", F.size("vec"))
    blocks = max(1, -(-queries.count() // query_rows))
    queries = queries.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    # a block travels as one row; it meets each shard of its length once
    asked = queries.groupBy(F.col("dim").alias("to_dim"), "block").agg(F.collect_list(F.struct("id", "vec")).alias("queries"))  # about query_rows rows
    met = index.join(asked, F.col("dim") == F.col("to_dim")).drop("to_dim")

    def search(batches):
        opened: tuple = (None, None)
        for b in batches:
            out: list[tuple] = []
            for row in b.to_pylist():
                key = (row["dim"], row["shard"])
                if opened[0] != key:
                    opened = (key, _open(row))
                g, x, ids = opened[1]
                q = np.array([v["vec"] for v in row["queries"]], np.float64)
                for qid, vec, at in zip([v["id"] for v in row["queries"]], q, g.search(q, max(ef, k + 1)), strict=True):
                    at = at[at >= 0]
                    score = np.sqrt(((x[at] - vec) ** 2).sum(axis=1))
                    found = sorted((s, int(i)) for s, v in zip(score.tolist(), at.tolist(), strict=True) for i in ids[v] if i != qid)
                    out += [(qid, i, s) for s, i in found[:k]]
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.float64())], names=["query_id", "vec_id", "score"])
        release()

    tasks = max(1, index.count())
    met = met.repartition(tasks, "dim", "shard").sortWithinPartitions("dim", "shard")
    found = met.mapInArrow(search, "query_id long, vec_id long, score double")
    nearest = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(nearest)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest_neighbours(vectors: DataFrame, query_filter, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 10) -> DataFrame:
    """Search the rows that query_filter (a Column over ``id``) picks against all rows."""
    usable = usable_vectors(vectors, id_col, vec_col)
    return search_index(stored(build_index(usable, k)), usable.where(query_filter), k)
