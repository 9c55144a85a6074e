"""Joins against files, partitions without an id, streams, and queries that are held against numpy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from boxprune import workloads as w
from boxprune.functions.geometry import Box, contains, point, sample_in_box
from boxprune.operators import files, join as J
from boxprune.plans import prune
from boxprune.sources import layout, manifest
from boxprune.streaming import bounds as B

POINTS = "id long, part_id long, x_0 double, x_1 double"


def tuples(df):
    return sorted((r.origin_id, r.neighbour_id, r["rank"], round(r.distance, 9)) for r in df.collect())


def scattered(spark, n, seed, start=0, empty=None):
    rng = np.random.default_rng(seed)
    rows = [(start + i, None if int(x[0] // 10) == empty else int(x[0] // 10), float(x[0]), float(x[1])) for i, x in enumerate(rng.integers(0, 50, (n, 2)))]
    return spark.createDataFrame(rows, POINTS)


def test_rows_without_a_partition_are_one(spark):
    r, s = scattered(spark, 30, 1, 0, 2), scattered(spark, 60, 2, 1000, 3)
    want = tuples(J.knn_brute(r, s, 3, 2))
    for more in ({}, {"local": "window"}, {"local": "axis"}, {"local": "cell"}, {"refine": "point"}, {"rule": "single"}, {"plan": "declared"}, {"plan": "hierarchical"}):
        assert tuples(J.knn(r, s, 3, 2, **more)) == want
    assert tuples(J.knn_filtered(r, s, 3, 2, F.col("x_1") > 10)) == tuples(J.knn_brute(r, s.where("x_1 > 10"), 3, 2))
    assert tuples(J.knn_ordered(r, s, 3, 2, F.col("x_1") > 10)) == tuples(J.knn_brute(r, s.where("x_1 > 10"), 3, 2))
    assert tuples(J.knn_best_first(r, s, 3, 2)) == want


def test_large_partitions_are_dealt_to_several_tasks(spark, monkeypatch):
    monkeypatch.setattr(J, "CHUNK_ROWS", 7)
    r, s = scattered(spark, 60, 3), scattered(spark, 90, 4, 1000)
    assert tuples(J.knn(r, s, 5, 2)) == tuples(J.knn_brute(r, s, 5, 2))
    assert tuples(J.knn(r, r, 5, 2, exclude_self=True)) == tuples(J.knn_brute(r, r, 5, 2, exclude_self=True))


def test_only_kept_files_are_read(spark, tmp_path):
    cell = F.floor(F.col("x_0") / 10) * 10 + F.floor(F.col("x_1") / 10)
    r, s = (scattered(spark, n, n, 1000 * i).withColumn("part_id", cell) for i, n in enumerate((60, 300)))
    r = r.where("x_0 < 20 AND x_1 < 10")
    path = f"{tmp_path}/l"
    layout.write_layout(s, path, 3, ["id"])
    want = tuples(J.knn_brute(r, s, 2, 2))
    assert tuples(files.knn_files(spark, r, path, 2, 2)) == want
    row = files.files_skipped(spark, r, path, 2, 2).first()
    assert 0 < row.files_read < row.files and 0 < row.bytes_read < row.bytes
    near = files.range_scan(spark, r, path, 2, 2)
    spark.conf.set("spark.sql.maxMetadataStringLength", 2000)
    plan = files.range_scan(spark, r, path, 2, 2)._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.maxMetadataStringLength")
    assert "PushedFilters: [IsNotNull" in plan and "GreaterThanOrEqual(x_0" in plan and "LessThanOrEqual(x_1" in plan
    assert near.count() < 300 and tuples(J.knn_brute(r, near, 2, 2)) == want


def test_hierarchy_keeps_the_pairs_of_the_flat_rule(spark):
    rng = np.random.default_rng(7)
    rows = [(i, int(rng.integers(1, 5)), *map(float, np.sort(rng.integers(0, 4, (2, 2)) + rng.integers(-60, 60, 2), axis=0).T.ravel())) for i in range(60)]
    m = manifest.validated(spark.createDataFrame(rows, "part_id long, n_rows long, lo_0 double, hi_0 double, lo_1 double, hi_1 double"), 2)
    key = lambda df: sorted((r.origin_id, r.part_id, r.dominator_rows) for r in df.collect())
    p = prune.parent_of(m, 2, 5)
    assert p.select("parent").distinct().count() > 5
    for k in (1, 6):
        for own in (False, True):
            assert key(prune.keep_hierarchical(p, p, k, 2, self_join=own)) == key(prune.keep_two_step(m, m, k, 2, own))


def test_minmax_rule_refuses_what_it_cannot_do(spark):
    r = scattered(spark, 10, 8)
    assert tuples(J.knn(r, r, 1, 2, rule="minmax")) == tuples(J.knn_brute(r, r, 1, 2))
    for more in ({"k": 2}, {"k": 1, "exclude_self": True}):
        with pytest.raises(ValueError):
            J.knn(r, r, dims=2, rule="minmax", **more)


def test_samples_lie_in_their_boxes(spark):
    box = spark.createDataFrame([(0.0, 1.0, -5.0, -5.0), (2.0, 9.0, 3.0, 4.0)], "lo_0 double, hi_0 double, lo_1 double, hi_1 double")
    got = sample_in_box(box, Box.of("", 2), 50, 3)
    assert got.count() == 100 and got.where(~contains(Box.of("", 2), point("", 2))).count() == 0
    assert got.select("x_0").distinct().count() == 100


def test_tiles_hold_all_rows_evenly(spark, sf):
    rows = w.ORDERS.frame(spark, sf).toPandas()
    got = {r.part_id: r for r in w.QUERIES["layout_tiles"](spark, sf).collect()}
    assert sum(r.n_rows for r in got.values()) == len(rows)
    x = rows[["x_0", "x_1"]].to_numpy()
    for r in got.values():
        inside = ((x >= [r.lo_0, r.lo_1]) & (x <= [r.hi_0, r.hi_1])).all(axis=1)
        assert inside.sum() == r.n_rows  # tiles do not overlap
    for axis in (0, 1):
        share = np.bincount([p // 8 if axis == 0 else p % 8 for p, r in got.items() for _ in range(r.n_rows)]) / len(rows)
        assert abs(share - 1 / 8).max() < 0.03


def test_sampled_join_is_exact_on_its_sample(spark, sf):
    r, s = w.CUSTOMERS.frame(spark, sf), w.SUPPLIERS.frame(spark, sf)
    half = s.where(F.pmod(F.xxhash64("id"), F.lit(2)) == 0)
    assert tuples(w.QUERIES["knn_sampled"](spark, sf)) == tuples(J.knn_brute(r, half, 3, 2))


def test_stored_tables_refuse_a_local_folder_on_a_cluster(monkeypatch):
    from types import SimpleNamespace

    from boxprune.sources.scratch import shared_dir

    context = SimpleNamespace(master="spark://host:7077", getCheckpointDir=lambda: None)
    with pytest.raises(ValueError):
        shared_dir(SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=context))


# ---------------------------------------------------------------- streams

EVENT = "ts timestamp, value double, user_id long"


def event_files(spark, path, parts):
    """One file a batch, in order."""
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, "t string, value double, user_id long").select(F.to_timestamp("t").alias("ts"), "value", "user_id").coalesce(1).write.mode("append").parquet(f"{path}/{i}")
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(path)


LATE = [
    [("2024-01-01 01:00:00", 1.0, 1), ("2024-01-01 02:00:00", 5.0, 2)],
    [("2024-01-02 09:00:00", 7.0, 1)],
    [("2024-01-02 09:30:00", 7.5, 1)],  # a batch drops what is later than the watermark that its predecessor began with
    [("2024-01-01 03:00:00", -9.0, 1), ("2024-01-02 10:00:00", 8.0, 2)],  # the first one is too late
    [("2024-01-04 00:00:00", 2.0, 2)],
    [("2024-01-04 01:00:00", 3.0, 2)],
]


@pytest.mark.parametrize("mode", ["append", "update"])
def test_late_rows_are_dropped(spark, tmp_path, mode):
    stream = event_files(spark, f"{tmp_path}/e", LATE)
    q = B.tumbling(stream, "2 hours").writeStream.format("memory").queryName(f"late_{mode}").outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    got = [(str(r.window_start)[:10], r.n_rows, r.lo_0, r.hi_0) for r in spark.table(f"late_{mode}").collect()]
    assert ("2024-01-01", 2, 1.0, 5.0) in got and not any(lo == -9.0 for _, _, lo, _ in got)
    assert ("2024-01-02", 3, 7.0, 8.0) in got
    if mode == "append":  # a window appears once, when the watermark has passed it; the last day is still open
        assert [d for d, *_ in got] == ["2024-01-01", "2024-01-02"]


def test_micro_batches_meet_a_static_side(spark, tmp_path):
    train, parts = scattered(spark, 40, 9, 1000), [scattered(spark, 6, 10 + i, 10 * i) for i in range(2)]
    for i, p in enumerate(parts):
        p.coalesce(1).write.parquet(f"{tmp_path}/p/{i}")
    stream = spark.readStream.schema(POINTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/p")
    got = []
    q = B.knn_each_batch(stream, train, 2, 2, lambda df, number: got.extend(tuples(df))).start()
    q.processAllAvailable()
    q.stop()
    assert sorted(got) == tuples(J.knn_brute(parts[0].unionByName(parts[1]), train, 2, 2))


def test_state_by_user(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = event_files(spark, f"{tmp_path}/e", [LATE[0], LATE[1], LATE[3]])
        try:
            q = B.user_bounds(stream).writeStream.format("memory").queryName("by_user").outputMode("update").start()
            q.processAllAvailable()
            q.stop()
        except Exception as e:
            if "ModuleNotFoundError" in str(e) or "protobuf" in str(e):
                pytest.skip("the state server of this installation lacks a module")
            raise
        last = {}
        for r in spark.table("by_user").collect():
            if r.n_rows >= last.get(r.user_id, (0,))[0]:
                last[r.user_id] = (r.n_rows, r.lo, r.hi)
        assert last == {1: (3, -9.0, 7.0), 2: (2, 5.0, 8.0)}
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
