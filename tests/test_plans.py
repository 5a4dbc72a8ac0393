import pytest

from knnscope import catalog
from knnscope.operators import knn
from knnscope.operators.service import MemoryKnnService
from knnscope.plans import workloads
from knnscope.sources.views import view
from knnscope.streaming import points as streaming


def explained(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scans_read_only_what_is_needed(spark, sf):
    plan = explained(catalog.queries()["scan_filtered_bbox"](spark, sf))
    assert "PushedFilters" in plan and "l_quantity" in plan and "l_comment" not in plan and "l_shipdate" not in plan


def test_knn_is_an_equality_join_with_a_broadcast(spark, sf):
    p = view(spark, sf, "shapes")
    plan = explained(knn.grid_join(p, knn.Pyramid(p), [(0, 1.0, 2.0)], 5))
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan and "NestedLoop" not in plan
    assert "WindowGroupLimit" in plan


def test_flagship_and_some_queries_run(spark, sf):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    q = entry.queries()
    for name in ("knn_grid", "cells_dense_2d", "pair_counts", "agg_cube", "key_hilbert", "stream_dedup", "udf_cluster_of"):
        assert q[name](spark, sf).count() > 0, name
    assert set(entry.oracle_sql()) <= set(q)


def test_more_points_per_answer_cost_fewer_calls(spark, sf):
    p = workloads.vary_k(spark, sf, (1, 8), 2).toPandas().groupby("setting").calls.mean()
    assert p["8"] < p["1"]


def test_quality_rises_with_the_budget_and_is_measured_against_dbscan(spark):
    rows = workloads.quality_by_cost(spark, "/root/testdata/sf0.01", budgets=(100, 200, 300), seeds=3).toPandas()
    mean = rows.groupby(["setting", "budget"]).rand_index.mean()
    for curve in ("hilbert", "peano"):
        assert mean[curve, 100] < mean[curve, 200] < mean[curve, 300]
    assert mean["peano", 300] >= 0.85 and (rows.true_clusters == 4).all()


def test_large_sets_go_through_the_distributed_service(spark, sf, monkeypatch):
    small = workloads.Benchmark(spark, sf).sweep([{"workload": "x", "budget": 30, "min_side": 88.0}]).first()
    monkeypatch.setattr(MemoryKnnService, "LIMIT", 10)
    large = workloads.Benchmark(spark, sf)
    assert not large.small
    again = large.sweep([{"workload": "x", "budget": 30, "min_side": 88.0}]).first()
    assert again.calls == small.calls and again.clusters == small.clusters
    assert again.rand_index == pytest.approx(small.rand_index) and again.rand_planted == pytest.approx(small.rand_planted)


def test_live_sites_are_clustered(spark):
    from knnscope.plans import live

    sites = {r.site: r for r in live.summary(spark, "/root/testdata/sf0.01").collect()}
    assert sites["photos"].clusters >= 6 and sites["stations"].clusters >= 2 and sites["listings_a"].calls <= 600
    assert all(r.clustered > 0.3 * r.points for r in sites.values())


def test_the_exact_leaf_test_pays_for_certainty(spark, sf):
    from knnscope.operators.curve2d import curve_cluster_2d

    points = view(spark, "/root/testdata/sf0.01", "shapes")
    calls, dense = {}, {}
    for test in ("in_cell", "exact"):
        s = MemoryKnnService(points, 14)
        model = curve_cluster_2d(s, (-0.0005, -0.0005, 704.0), 20.0, 14, 44.0, leaf_test=test, infer=False)
        calls[test], dense[test] = s.budget.used, {r[1] for r in model.tree.table() if r[-1] == "dense"}
    assert calls["exact"] > calls["in_cell"] and dense["exact"] >= {k for k in dense["in_cell"] if k in dense["exact"]}


def test_memory_service_guards_its_size(monkeypatch):
    monkeypatch.setattr(MemoryKnnService, "LIMIT", 2)
    with pytest.raises(ValueError):
        MemoryKnnService(([1, 2, 3], [0.0] * 3, [0.0] * 3), 1)


def test_late_rows_are_dropped(spark, tmp_path):
    import datetime as dt

    rows = lambda d, n: [(i, "a", dt.datetime(2024, 1, d)) for i in range(n)]
    schema = "event_id long, event_type string, ts timestamp"
    # a batch drops what was late for the batch before it, so one lies between
    for i, (d, n) in enumerate(((1, 3), (20, 2), (21, 1), (1, 5), (25, 1))):
        spark.createDataFrame(rows(d, n), schema).coalesce(1).write.parquet(str(tmp_path / "in" / f"b{i}"))
    import glob
    import os
    import shutil

    flat = tmp_path / "flat"
    flat.mkdir()
    for i in range(5):
        f = glob.glob(str(tmp_path / "in" / f"b{i}" / "*.parquet"))[0]
        shutil.copy(f, flat / f"{i}.parquet")
        os.utime(flat / f"{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))
    s = streaming.window_counts(streaming.point_stream(spark, str(flat), spark.createDataFrame([], schema).schema), "event_type", "1 day")
    got = {str(r.start)[:10]: r["count"] for r in streaming.drain(s, "late_rows").collect()}
    assert got["2024-01-01"] == 3 and got["2024-01-20"] == 2


def test_of_equal_prices_the_first_order_is_taken(spark, tmp_path):
    rows = [(3, 1, 5.0), (4, 1, 5.0), (7, 1, 4.0), (None, 1, 9.0), (5, 2, None), (6, 2, 1.0)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").coalesce(1).write.parquet(str(tmp_path / "orders.parquet"))
    got = {r.o_custkey: (r.top, r.of) for r in catalog.queries()["agg_max_by"](spark, str(tmp_path)).collect()}
    assert got == {1: (9.0, 3), 2: (1.0, 6)}


def test_cells_come_back_from_the_keys_of_a_table(spark, sf):
    df = catalog.queries()["cell_roundtrip"](spark, sf)
    got = {r.kind: (r.cells, r.unit_steps) for r in df.collect()}
    import duckdb

    con = duckdb.connect()
    con.execute(f"create view events as from '{sf}/events.parquet'")
    assert got == {k: (c, u) for k, c, u in con.execute(catalog.oracle_sql()["cell_roundtrip"]).fetchall()}
    assert all(0 < u < c for c, u in got.values()) and got["z"][1] < got["hilbert"][1]


def test_sites_of_many_points_give_the_same_clusters(spark, monkeypatch):
    from knnscope.plans import live

    sf = "/root/testdata/sf0.01"
    for site in ("stations", "listings_b"):
        want, small = live.fit(spark, sf, site)
        monkeypatch.setattr(live, "LIMIT", 10)
        got, large = live.fit(spark, sf, site)
        monkeypatch.undo()
        assert got.segments == want.segments and got.info["calls"] == want.info["calls"] and not got.observed
        assert small.select("id", "cluster_id").exceptAll(large.select("id", "cluster_id")).count() == 0


def test_samplers_and_curves_of_large_sets(spark, sf, monkeypatch):
    at = {"workload": "x", "budget": 20, "seed": 3}
    runs = [at | {"merge": "adjacent", "adaptive": False}, at | {"sampler": "raw"}, at | {"sampler": "voronoi"}]
    small = {(r.setting, r.curve): r for r in workloads.Benchmark(spark, sf).sweep(runs).collect()}
    monkeypatch.setattr(MemoryKnnService, "LIMIT", 10)
    large = workloads.Benchmark(spark, sf).sweep([*runs, at | {"sampler": "uniform"}]).collect()
    assert len(large) == 4
    for r in large:
        if r.setting != "sample_uniform":
            assert list(r)[:12] == list(small[r.setting, r.curve])[:12] and list(r)[12:] == pytest.approx(list(small[r.setting, r.curve])[12:])


def test_draws_from_large_sets_keep_the_rows_of_answers_off_the_driver(spark, sf, monkeypatch):
    from knnscope.operators import baselines

    small = workloads.Benchmark(spark, "/root/testdata/sf0.01")
    want = {k: baselines.draw(small.service(budget=60), workloads.SQUARE["hilbert"], k, "voronoi") for k in (3, 4)}
    monkeypatch.setattr(MemoryKnnService, "LIMIT", 10)
    large = workloads.Benchmark(spark, "/root/testdata/sf0.01")
    for seed, points in want.items():
        s = large._drawing("voronoi", 60, seed)
        assert s.k == 14 and baselines.draw(s, workloads.SQUARE["hilbert"], seed, "voronoi") == points and points
        assert s.budget.used == 60 and all(len(a.ids) == 1 for a in s.book.values()) and len(s.seen) <= 60
