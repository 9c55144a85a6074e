"""Joins by tiles against brute force, with copies, ties and skew, and what large tables take."""

import numpy as np
import pytest

from boxprune.operators import join as J
from boxprune.operators import tiles as T

SCHEMA = "id long, part_id long, "


def table(spark, x, start=0):
    ids = np.random.default_rng(7).permutation(len(x)) + start
    return spark.createDataFrame([(int(i), 0, *map(float, p)) for i, p in zip(ids, x, strict=True)], SCHEMA + ", ".join(f"x_{i} double" for i in range(x.shape[1])))


def tuples(df):
    return sorted((r.origin_id, r.neighbour_id, r["rank"], round(r.distance, 9)) for r in df.collect())


@pytest.mark.parametrize("dims", [1, 3])
def test_tiles_equal_brute_force(spark, monkeypatch, dims):
    """Lattice points (ties, copies), one place of many rows, far origins, tiles with fewer rows than k."""
    monkeypatch.setattr(T, "TILE_POINTS", 20)
    monkeypatch.setattr(T, "TILE_ORIGINS", 60)
    monkeypatch.setattr(T, "CHUNK_ORIGINS", 25)
    monkeypatch.setattr(T, "LEAF", 6)
    rng = np.random.default_rng(dims)
    x = np.concatenate([rng.integers(0, 12, (150, dims)) / 3, np.full((60, dims), 2.0), rng.normal(0, 1, (90, dims))])
    y = np.concatenate([rng.integers(-9, 20, (70, dims)) / 3, np.full((1, dims), 400.0)])
    r, s = table(spark, y), table(spark, x, 1000)
    for k in (4, 500):
        assert tuples(T.knn_tiles(r, s, k, dims)) == tuples(J.knn_brute(r, s, k, dims))
    assert tuples(T.knn_tiles(s, s, 5, dims, exclude_self=True)) == tuples(J.knn_brute(s, s, 5, dims, exclude_self=True))
    assert tuples(T.knn_tiles(s, s, 5, dims, exclude_self=True, ties="all")) == tuples(J.knn_brute(s, s, 5, dims, exclude_self=True, ties="all"))
    assert tuples(T.knn_tiles(r, s, 3, dims, ties="all", rule="none")) == tuples(J.knn_brute(r, s, 3, dims, ties="all"))


#: Queries that go by tiles at size.
TILED = [
    "knn_pruned_k10",
    "knn_urgent",
    "knn_pruned_self",
    "knn_pruned_k5",
    "knn_pruned_k1",
    "knn_null_parts",
    "knn_hashed_layout",
    "knn_with_ties",
    "knn_point_query",
    "knn_parts_ties",
    "nn_min_by",
]


@pytest.mark.parametrize("name", TILED)
def test_query_by_tiles_equals_its_sql(spark, sf, monkeypatch, name):
    """The plan for large tables, on several tiles of a small one, against the query's own SQL."""
    import glob
    import os

    import duckdb

    import __spark_entry__ as e

    monkeypatch.setattr(J, "TILED_PAIRS", 0)
    monkeypatch.setattr(T, "TILE_POINTS", 200)
    con = duckdb.connect()
    for path in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    want = sorted(tuple(r) for r in con.execute(e.oracle_sql()[name]).fetchall())
    df = e.queries()[name](spark, sf)
    assert "lists" in df._jdf.queryExecution().optimizedPlan().toString()
    assert sorted(tuple(r) for r in df.collect()) == want


@pytest.mark.parametrize("dims", [1, 3])
def test_brute_force_in_blocks(spark, monkeypatch, dims):
    """Blocks on every side, copies and ties, against plain numpy; large tables take this way."""
    monkeypatch.setattr(T, "BLOCK", 300)
    rng = np.random.default_rng(dims)
    x = np.concatenate([rng.integers(0, 9, (900, dims)) / 3, rng.normal(0, 5, (700, dims))])
    r, s = table(spark, x[::9]), table(spark, x, 1000)
    monkeypatch.setattr(J, "TILED_PAIRS", 0)
    got = J.knn_brute(r, s, 3, dims)
    assert "job" in got._jdf.queryExecution().optimizedPlan().toString()
    order = np.argsort(ids := np.array([row.id for row in s.collect()]))
    y, ids = np.array([row[2:] for row in s.collect()])[order], ids[order]
    want = []
    for row in r.collect():
        d2 = ((np.array(row[2:]) - y) ** 2).sum(axis=1)
        near = np.argsort(d2, kind="stable")[:3]
        want += [(row.id, int(ids[j]), n + 1, round(float(np.sqrt(d2[j])), 9)) for n, j in enumerate(near)]
    assert tuples(got) == sorted(want)
    both = J.knn_brute(s, s, 3, dims, exclude_self=True)
    monkeypatch.undo()
    assert tuples(both) == tuples(J.knn_brute(s, s, 3, dims, exclude_self=True))


def test_footers_of_many_row_groups_and_files_are_one(spark, tmp_path):
    import duckdb

    import __spark_entry__ as e

    con = duckdb.connect()
    (tmp_path / "orders.parquet").mkdir()
    con.execute("CREATE TABLE orders AS SELECT i AS o_orderkey, (i * 7 % 5003) / 4.0 AS o_totalprice FROM range(9000) g(i)")
    for n in range(2):
        con.execute(f"COPY (SELECT * FROM orders WHERE o_orderkey % 2 = {n}) TO '{tmp_path}/orders.parquet/{n}.parquet' (ROW_GROUP_SIZE 2048)")
    got = [tuple(row) for row in e.queries()["manifest_footers"](spark, str(tmp_path)).collect()]
    assert got == [tuple(row) for row in con.execute(e.oracle_sql()["manifest_footers"]).fetchall()]


def test_axis_visits_are_of_the_given_vectors(spark, sf):
    import duckdb

    import __spark_entry__ as e

    df = e.queries()["axis_visits"](spark, sf)
    assert df.inputFiles()
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{sf}/embeddings.parquet'")
    assert sorted(tuple(row) for row in df.collect()) == sorted(con.execute(e.oracle_sql()["axis_visits"]).fetchall())


def test_equal_boxes_are_pruned_as_one(spark, monkeypatch):
    """Several partitions of the same bounds: the pairs and dominator rows of the flat rule, and no pair of boxes between copies."""
    from boxprune.plans import prune

    rng = np.random.default_rng(3)
    rows = [(n, int(rng.integers(1, 4)), *map(float, np.sort(rng.integers(0, 60, (2, 2)), axis=0).T.ravel())) for n in range(30)]
    rows = [(n + 100 * c, m, *box) for n, m, *box in rows for c in range(3)]
    m = spark.createDataFrame(rows, "part_id long, n_rows long, lo_0 double, hi_0 double, lo_1 double, hi_1 double")
    key = lambda df: sorted(tuple(r) for r in df.select("origin_id", "part_id", "dominator_rows").collect())
    want = key(prune.keep_two_step(m, m, 5, 2))
    seen = []
    flat = prune.keep_two_step
    monkeypatch.setattr(prune, "keep_two_step", lambda o, t, *more: seen.append((o.count(), t.count())) or flat(o, t, *more))
    assert key(prune.keep_counted(m, m, 5, 2)) == want
    assert max(seen) <= (30, 30)
    assert key(prune.keep_counted(m, m, 5, 2, self_join=True)) == key(flat(m, m, 5, 2, True))


def test_recall_at_size_equals_its_sql(spark, sf, monkeypatch):
    """Tiles against blocks: every row of the truth is found at its rank."""
    import __spark_entry__ as e

    monkeypatch.setattr(J, "TILED_PAIRS", 0)
    monkeypatch.setattr(T, "BLOCK", 50)
    df = e.queries()["recall"](spark, sf)
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "lists" in plan and "job" in plan
    assert [tuple(row) for row in df.collect()] == [(450, 450, 0)]


@pytest.mark.parametrize("name", ["knn_pruned_3d", "knn_pruned_4d"])
def test_lines_by_tiles_equal_all_pairs(spark, sf, monkeypatch, name):
    """The lines' joins have no SQL: tiles against the unpruned join by blocks."""
    import __spark_entry__ as e
    from boxprune import workloads as w
    from boxprune.plans import prune

    monkeypatch.setattr(J, "TILED_PAIRS", 0)
    monkeypatch.setattr(T, "TILE_POINTS", 1000)
    p = w.LINES_3D if name.endswith("3d") else w.LINES_4D
    frame, one = p.frame(spark, sf), p.manifest(spark, sf)
    got = e.queries()[name](spark, sf)
    assert "lists" in got._jdf.queryExecution().optimizedPlan().toString()
    assert tuples(got) == tuples(J.join_kept(frame, frame, prune.keep_none(one, one, p.dims), 10, p.dims, local="block"))


def test_numbered_lines_come_in_waves(spark, sf, monkeypatch):
    """Shares of the lines hold each row once, under the id that it has among all, and are dealt one after the other."""
    from boxprune import workloads as w

    p = w.LINES_3D
    frame = p.frame(spark, sf)
    key = lambda df: sorted(tuple(row) for row in df.collect())
    shares = [key(df) for df in frame._waves(3)]
    assert all(shares) and sorted(sum(shares, [])) == key(frame)
    monkeypatch.setattr(T, "WAVE_ROWS", 0)
    counts = []
    real = T.stored
    monkeypatch.setattr(T, "stored", lambda *frames: counts.append(len(frames)) or real(*frames))
    layout = T.Layout(np.zeros((1, 3)), 1)
    assert sorted(tuple(row)[1:] for row in T._dealt(frame, layout, 3, 1).collect()) == sorted((row[0], *row[2:]) for row in key(frame))
    assert counts == [3]


def test_lists_with_many_ties_are_dealt_to_more_tasks(spark, monkeypatch):
    """Sixty rows at one place have lists of all sixty: their tile is dealt by the rows of lists, not of origins."""
    x = np.concatenate([np.random.default_rng(2).normal(0, 1, (40, 2)), np.full((60, 2), 0.5)])
    s = table(spark, x)
    monkeypatch.setattr(T, "LIST_ROWS", 500)
    seen = []
    real = T._chunked
    monkeypatch.setattr(T, "_chunked", lambda *more: seen.append(real(*more)) or seen[-1])
    got = T.knn_tiles(s, s, 3, 2, exclude_self=True, ties="all")
    assert [row.chunks for row in seen[0].collect()] == [9]  # 100 rows of 4 + (40 + 3600) / 100 each
    assert tuples(got) == tuples(J.knn_brute(s, s, 3, 2, exclude_self=True, ties="all"))


@pytest.mark.parametrize("other", [False, True])
def test_whole_tiles_are_shuffled_once(spark, monkeypatch, other):
    """Where no tile is too large for a task, its rows are shuffled once for all steps, and no least rows are stored beside them."""
    monkeypatch.setattr(T, "TILE_POINTS", 60)
    rng = np.random.default_rng(5)
    s = table(spark, np.concatenate([rng.normal(0, 1, (300, 2)), rng.integers(0, 3, (60, 2))]), 1000)
    r = table(spark, rng.normal(0, 1, (50, 2))) if other else s
    dealt, real = [], T.stored
    monkeypatch.setattr(T, "stored", lambda *frames: dealt.append("id" in frames[0].columns) or real(*frames))
    got = T.knn_tiles(r, s, 4, 2, exclude_self=not other)
    assert tuples(got) == tuples(J.knn_brute(r, s, 4, 2, exclude_self=not other))
    assert sum(dealt) == 1 + other
    got.collect()
    assert "ReusedExchange" in got._jdf.queryExecution().executedPlan().toString()


def test_points_far_from_the_border_are_not_searched(monkeypatch):
    """Bounds in place of distances are only where the border is farther than either."""
    rng = np.random.default_rng(6)
    x = np.concatenate([rng.random((3000, 2)), np.full((50, 2), 0.5)])
    p = T.Places(x, np.arange(len(x)))
    border = np.minimum(p.x, 1 - p.x).min(axis=1) ** 2
    searched, real = [], T._squares
    monkeypatch.setattr(T, "_squares", lambda a, b: searched.append(len(a)) or real(a, b))
    want = p.search(p.x, 5)[3]
    every = sum(searched)
    last = p.search(p.x, 5, border=border)[3]
    near = last >= border
    assert 0 < near.sum() and np.array_equal(last[near], want[near]) and (last >= want).all()
    assert sum(searched) - every < 0.75 * every


def test_blocks_of_the_brute_force_are_merged(spark, monkeypatch):
    """Several blocks of either side, of unequal sizes, with rows beside the groups of 64 and several rows at a place."""
    monkeypatch.setattr(T, "BLOCK", 150)
    monkeypatch.setattr(T, "TRAIN_BLOCK", 700)
    monkeypatch.setattr(T, "AT_ONCE", 5000)
    rng = np.random.default_rng(8)
    s = table(spark, np.concatenate([rng.normal(0, 5, (1500, 2)), np.repeat(rng.normal(0, 1, (3, 2)), 40, axis=0)]), 1000)
    r = table(spark, rng.normal(0, 5, (400, 2)))
    assert tuples(T.knn_blocks(r, s, 3, 2)) == tuples(J.knn_brute(r, s, 3, 2))


@pytest.mark.parametrize("dims", [1, 2, 3])
def test_many_boxes_are_pruned_in_blocks(spark, monkeypatch, dims):
    """Distinct boxes beyond the flat plan: its pairs and dominator rows, without a row for a pair before pairs are known."""
    from pyspark.sql import functions as F

    from boxprune.plans import blocks, prune

    rng = np.random.default_rng(dims)
    lo = rng.integers(0, 90, (70, dims)) / 2
    ends = np.stack([lo, lo + rng.integers(0, 9, (70, dims)) / 2], axis=2).reshape(70, -1)
    rows = [(None if n == 5 else f"p{n}", int(rng.integers(1, 5)), *map(float, box)) for n, box in enumerate([*ends, *ends[:9]])]
    m = spark.createDataFrame(rows, "part_id string, n_rows long, " + ", ".join(f"{e}_{i} double" for i in range(dims) for e in ("lo", "hi")))
    half = m.withColumn("usable", ~F.col("part_id").isin("p1", "p33") | F.col("part_id").isNull())
    key = lambda df: sorted((str(r.origin_id), str(r.part_id), r.dominator_rows) for r in df.collect())
    cases = [(m, m, 1, False, False), (m, m, 6, False, False), (m, m, 6, True, False), (half, m, 4, True, True), (m, half, 4, False, True)]
    want = [key(prune.keep_declared(o, t, k, dims, own, safe)) for o, t, k, own, safe in cases]
    assert all(0 < len(w) < 79 * 79 for w in want) and any(r[2] for r in want[1])
    monkeypatch.setattr(prune, "FLAT_TRIPLES", 0)
    monkeypatch.setattr(blocks, "BLOCK_ORIGINS", 20)
    monkeypatch.setattr(blocks, "FIRST", 3)
    monkeypatch.setattr(blocks, "AT_ONCE", 50)
    monkeypatch.setattr(prune, "prefiltered", None)
    assert [key(prune.keep_counted(o, t, k, dims, own, safe)) for o, t, k, own, safe in cases] == want


def test_search_squares_the_nearest_leaves_only(monkeypatch):
    """Other leaves go by a product of matrices first; lists are those of all distances, also far from the origin and with ties."""
    rng = np.random.default_rng(9)
    x = np.concatenate([rng.random((4000, 4)), rng.integers(0, 4, (500, 4)) / 3, np.repeat(rng.random((3, 4)), 20, axis=0)])
    for shift in (0.0, 1e6):
        y = x + shift
        p = T.Places(y, rng.permutation(len(y)))
        cells, real = [], T._squares
        monkeypatch.setattr(T, "_squares", lambda a, b: cells.append(len(a) * len(b)) or real(a, b))
        number, ids, d2, last = p.search(p.x, 10)
        monkeypatch.undo()
        assert sum(cells) < 500 * len(p.x)
        got = [set() for _ in p.x]
        for n, i, d in zip(number.tolist(), ids.tolist(), d2.tolist(), strict=True):
            got[n].add((i, d))
        for n in [*range(0, len(p.x), 40), *np.flatnonzero(p.count > 1)]:
            every = real(p.x[n : n + 1], p.rows)[0]
            assert last[n] == np.sort(every)[9]
            assert got[n] == {(int(p.ids[j]), float(every[j])) for j in np.flatnonzero(every <= last[n])}


@pytest.mark.parametrize("own", [False, True])
def test_pairs_of_many_tiles_are_kept_in_blocks(spark, monkeypatch, own):
    from boxprune.plans import prune
    from boxprune.sources.manifest import validated

    rng = np.random.default_rng(4)
    lo = rng.random((60, 4)) * 9
    rows = [(n, int(rng.integers(1, 9)), *map(float, np.stack([a, b], axis=1).ravel())) for n, (a, b) in enumerate(zip(lo, lo + rng.random((60, 4)), strict=True))]
    m = validated(spark.createDataFrame(rows, "part_id long, n_rows long, " + ", ".join(f"{e}_{i} double" for i in range(4) for e in ("lo", "hi"))), 4)
    key = lambda df: sorted(tuple(r) for r in df.collect())
    want = key(prune.keep_pairs(m, m, 5, 4, plan="declared", self_join=own))
    monkeypatch.setattr(prune, "FLAT_TRIPLES", 0)
    monkeypatch.setattr(prune, "prefiltered", None)
    assert key(prune.keep_pairs(m, m, 5, 4, self_join=own)) == want and len(want) < 3000
