"""Rules, plans, order and joins on small layouts against independent statements."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from boxprune.operators import join as J
from boxprune.plans import order, prune
from boxprune.sources import layout, manifest

LAYOUT_A = [(1, 1, -5.0, -4.0, 2.0, 3.0), (2, 1, 1.0, 2.0, 2.0, 3.0), (3, 1, 4.0, 5.0, 0.0, 2.0)]
COLS = "part_id long, n_rows long, lo_0 double, hi_0 double, lo_1 double, hi_1 double"


def boxes(spark, rows):
    return spark.createDataFrame(rows, COLS)


@pytest.fixture(scope="module")
def a(spark):
    return boxes(spark, [(0, 1, -3.0, 0.0, 0.0, 3.0)]), boxes(spark, LAYOUT_A)


def parts(df):
    return sorted((r.origin_id, r.part_id) for r in df.collect())


def test_only_the_three_box_rule_drops_the_hidden_partition(a):
    o, t = a
    assert parts(prune.keep_declared(o, t, 1, 2)) == parts(prune.keep_two_step(o, t, 1, 2)) == parts(prune.keep_single(o, t, 1, 2)) == [(0, 1), (0, 2)]
    assert parts(prune.keep_two_box(o, t, 1, 2)) == parts(prune.keep_nxn(o, t, 2)) == parts(prune.keep_none(o, t, 2)) == [(0, 1), (0, 2), (0, 3)]


def test_a_running_total_would_lose_a_neighbour(spark, a):
    """With one row each and k = 2, the hidden partition is needed: only one row is sure to be nearer."""
    o, t = a
    assert parts(prune.keep_two_step(o, t, 2, 2)) == [(0, 1), (0, 2), (0, 3)]
    s = spark.createDataFrame([(1, 1, -5.0, 3.0), (2, 2, 2.0, 3.0), (3, 3, 4.0, 0.0)], "id long, part_id long, x_0 double, x_1 double")
    r = spark.createDataFrame([(9, 0, 0.0, 0.0)], s.schema)
    got = J.knn(r, s, 2, 2).orderBy("rank").collect()
    assert [(g.neighbour_id, round(g.distance, 4)) for g in got] == [(2, 3.6056), (3, 4.0)]


def test_baselines_refuse_what_they_cannot_do(a):
    o, t = a
    for more in ({"k": 2}, {"loose": True}, {"predicate": True}):
        with pytest.raises(ValueError):
            prune.keep_nxn(o, t, 2, **more)
    with pytest.raises(ValueError):
        prune.keep_two_step(o, t, 0, 2)


@pytest.mark.parametrize("seed", range(4))
def test_plans_agree_and_contain(spark, seed):
    rng = np.random.default_rng(seed)
    make = lambda n, reach: [(i, int(rng.integers(1, 5)), *map(float, np.sort(rng.integers(-reach, reach, (2, 2)), axis=0).T.ravel())) for i in range(n)]
    o, t = boxes(spark, make(5, 8)), boxes(spark, make(13, 40))
    for k in (1, 3, 6):
        want = parts(prune.keep_declared(o, t, k, 2))
        assert parts(prune.keep_two_step(o, t, k, 2)) == want
        assert set(want) <= set(parts(prune.keep_two_box(o, t, k, 2)))
        assert set(want) <= set(parts(prune.keep_two_step(o, manifest.widen(t, 2, 0.1), k, 2)))
        assert parts(prune.keep_declared(o, t, k, 2, True)) == parts(prune.keep_two_step(o, t, k, 2, True))
        top = F.col("part_id") % 3
        assert set(want) <= set(parts(prune.keep_hierarchical(o, t, k, 2, top, top)))
        assert set(parts(prune.keep_split(o, t, k, 2))) <= set(want)
    dag = order.edges(o, t, 2)
    assert {r.law: r.violations for r in order.violations(dag).collect()} == {"irreflexive": 0, "asymmetric": 0, "transitive": 0}
    rank = {(r.origin_id, r.part_id): r.load_rank for r in order.load_order(prune.keep_none(o, t, 2), o, t, 2).collect()}
    wave = {(r.origin_id, r.part_id): r.wave for r in order.waves(prune.keep_none(o, t, 2), dag).collect()}
    for r in dag.collect():
        assert rank[r.origin_id, r.near_id] < rank[r.origin_id, r.far_id]
        assert wave[r.origin_id, r.near_id] < wave[r.origin_id, r.far_id]


def points(spark, xs, part, start=0):
    rows = [(start + i, int(part(x)), *map(float, x)) for i, x in enumerate(xs)]
    return spark.createDataFrame(rows, "id long, part_id long, " + ", ".join(f"x_{i} double" for i in range(len(xs[0]))))


def tuples(df):
    return sorted((r.origin_id, r.neighbour_id, r["rank"], round(r.distance, 9)) for r in df.collect())


@pytest.mark.parametrize("dims", [1, 2, 3])
def test_joins_equal_brute_force(spark, dims):
    rng = np.random.default_rng(dims)
    part = lambda x: (x // 8).astype(int) @ [1000**i for i in range(len(x))]
    r, s = points(spark, rng.integers(0, 20, (40, dims)), part), points(spark, rng.integers(0, 60, (90, dims)), part, 1000)
    for k in (1, 4, 200):
        want = tuples(J.knn_brute(r, s, k, dims))
        for more in ({}, {"local": "block"}, {"local": "axis"}, {"local": "cell"}, {"refine": "point"}, {"rule": "two_box"}, {"plan": "declared"}):
            assert tuples(J.knn(r, s, k, dims, **more)) == want
        assert tuples(J.knn_best_first(r, s, k, dims)) == want
    both = r.unionByName(s)
    for k in (1, 3):
        want = tuples(J.knn_brute(both, both, k, dims, exclude_self=True))
        assert tuples(J.knn(both, both, k, dims, exclude_self=True)) == want
        assert tuples(J.knn(both, both, k, dims, exclude_self=True, local="cell")) == want
    where = F.col("x_0") > 30
    assert tuples(J.knn_filtered(r, s, 3, dims, where)) == tuples(J.knn_brute(r, s.where(where), 3, dims))
    near = J.within(r, s, 5.0, dims).count()
    assert near == J._side(r, "r_", dims).crossJoin(J._side(s, "s_", dims)).where(sum((F.col(f"r_x_{i}") - F.col(f"s_x_{i}")) ** 2 for i in range(dims)) <= 25).count()


def test_hostile_rows(spark):
    schema = "id long, part_id long, x_0 double, x_1 double"
    r = spark.createDataFrame([(1, 0, 0.0, 0.0), (2, 0, None, 1.0)], schema)
    s = spark.createDataFrame([(1, 0, 1.0, 0.0), (2, 0, 1.0, -0.0), (3, 1, float("nan"), 0.0), (4, 1, 0.5, 0.0), (5, 2, 9.0, None), (6, 3, 50.0, 50.0), (6, 3, 50.0, 50.0)], schema)
    got = [(g.origin_id, g.neighbour_id) for g in J.knn(r, s, 2, 2).orderBy("rank").collect()]
    assert got == [(1, 4), (1, 1)]
    empty = s.where("id > 99")
    assert J.knn(r, empty, 2, 2).count() == 0
    assert J.knn(empty, s, 2, 2).count() == 0
    assert J.knn(r, s, 50, 2).count() == 5


def test_ordered_loading_and_predicates(spark):
    """The nearest partition is emptied by the predicate, so static counts would stop too early."""
    o = boxes(spark, [(0, 1, 0.0, 0.0, 0.0, 0.0)])
    t = boxes(spark, [(1, 5, 1.0, 2.0, 0.0, 0.0), (2, 5, 4.0, 5.0, 0.0, 0.0), (3, 5, 9.0, 10.0, 0.0, 0.0)])
    counts = spark.createDataFrame([(1, 0), (2, 5), (3, 5)], "part_id long, n_rows long")
    loads = {r.part_id: r.wave for r in J.ordered_loads(o, t, counts, 2, 2).collect()}
    assert loads == {1: 0, 2: 1}
    assert parts(prune.keep_two_step(o, t, 2, 2)) == [(0, 1)]
    assert parts(prune.keep_two_step(o, manifest.with_counts(t, counts), 2, 2)) == [(0, 2)]


def test_footers_equal_rows(spark, tmp_path):
    df = spark.range(1000).select(F.col("id"), (F.col("id") % 97).cast("double").alias("x"), F.when(F.col("id") % 10 > 0, F.col("id") * 1.5).alias("y"))
    df.repartitionByRange(4, "id").write.parquet(f"{tmp_path}/p")
    read = spark.read.parquet(f"{tmp_path}/p").withColumn("file_path", F.col("_metadata.file_path"))
    want = {r[0]: tuple(r[1:]) for r in read.groupBy("file_path").agg(F.count("y"), F.min("x"), F.max("x"), F.min("y"), F.max("y")).collect()}
    got = {r.file_path: (r.n_rows, r.lo_0, r.hi_0, r.lo_1, r.hi_1) for r in manifest.from_footers(spark, read.select("file_path").distinct(), ["x", "y"]).collect()}
    assert got == want


def test_layout_prunes_directories(spark, tmp_path):
    pts = points(spark, np.random.default_rng(1).integers(0, 40, (200, 2)), lambda x: x[0] // 10)
    layout.write_layout(pts, f"{tmp_path}/l", 4, ["x_0"])
    s = spark.read.parquet(f"{tmp_path}/l")
    kept = spark.createDataFrame([(1,)], "k long").where("k < 2")
    plan = s.join(F.broadcast(kept), s.part_id == kept.k, "left_semi")._jdf.queryExecution().executedPlan().toString()
    assert "dynamicpruning" in plan.lower()


def test_two_step_plan_has_no_cartesian_after_the_manifests(spark, a):
    o, t = a
    plan = prune.keep_two_step(o, t, 1, 2)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join Cross") <= 2 and "o_id" in plan


def test_streaming_bounds_match_batch(spark, sf, tmp_path):
    from boxprune.streaming.bounds import tumbling

    events = spark.read.parquet(f"{sf}/events.parquet").select("ts", "value")
    events.write.parquet(f"{tmp_path}/e")
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/e")
    q = tumbling(stream).writeStream.format("memory").queryName("bounds_stream").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    key = lambda df: sorted((str(r.window_start), r.n_rows, r.lo_0, r.hi_0) for r in df.collect())
    assert key(spark.table("bounds_stream")) == key(tumbling(events))


def test_entry_and_registry(spark, sf):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 450
    assert set(e.oracle_sql()) <= set(e.queries())


@pytest.mark.parametrize("name", ["knn_pruned_3d", "knn_pruned_4d"])
def test_queries_without_sql_equal_brute_force(spark, sf, name):
    from boxprune import workloads as w

    p = w.LINES_3D if name.endswith("3d") else w.LINES_4D
    frame = p.frame(spark, sf)
    want = tuples(J.join_kept(frame, frame, prune.keep_none(p.manifest(spark, sf), p.manifest(spark, sf), p.dims), 10, p.dims, local="block"))
    assert tuples(w.QUERIES[name](spark, sf)) == want


@pytest.mark.parametrize("name", ["knn_pruned_3d", "knn_pruned_4d"])
def test_every_line_has_its_own_neighbours(spark, sf, name):
    """Each row of the table has an id and ten neighbours (itself among them, as in the test above), by numpy over all pairs."""
    from boxprune import workloads as w

    p = w.LINES_3D if name.endswith("3d") else w.LINES_4D
    rows = p.frame(spark, sf).toPandas().sort_values("id")
    ids, x = rows["id"].to_numpy(), rows[[f"x_{i}" for i in range(p.dims)]].to_numpy()
    assert len(set(ids)) == len(ids) == spark.read.parquet(f"{sf}/lineitem.parquet").count()
    got = w.QUERIES[name](spark, sf).toPandas().sort_values(["origin_id", "rank"])
    assert got["origin_id"].tolist() == np.repeat(ids, 10).tolist()
    want = np.empty((len(ids), 10), np.int64)
    for i in range(len(ids)):
        d2 = np.zeros(len(ids))
        for j in range(p.dims):
            d2 = d2 + (x[i, j] - x[:, j]) ** 2
        want[i] = ids[np.argsort(d2, kind="stable")[:10]]
    assert (got["neighbour_id"].to_numpy().reshape(-1, 10) == want).all()
