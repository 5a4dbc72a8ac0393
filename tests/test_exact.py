import pytest
from pyspark.sql import functions as F

from knnscope.components import connected
from knnscope.operators import baselines, dbscan, grid, metrics
from knnscope.sources.points import PointSpec, read_points, write_indexed
from knnscope.sources.views import view


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(100, 160)] + [(7, i) for i in range(8, 40)] + [(1, 1), (None, 3)]
    got = dict(connected(spark.createDataFrame(edges, "u long, v long")).collect())
    assert all(got[i] == 100 for i in range(100, 161)) and all(got[i] == 7 for i in range(7, 40)) and 1 not in got
    assert connected(spark.createDataFrame([], "u long, v long")).count() == 0


def test_dbscan_equals_a_driver_version(spark, sf):
    points = view(spark, sf, "shapes").select("id", "x", "y")
    rows = points.toPandas().sort_values("id")
    want = baselines.dbscan_arrays(rows.x.to_numpy(), rows.y.to_numpy(), 20, 6)
    got = dbscan.dbscan(points, 20, 6).toPandas().sort_values("id")
    core = got.kind.to_numpy() == "core"
    assert (got.id.to_numpy() == rows.id.to_numpy()).all()
    assert sorted(got[core].groupby("cluster_id").size()) == [41, 49, 102, 204, 207, 223]
    for c in set(want[core]):
        assert got.cluster_id.to_numpy()[core & (want == c)].min() == got.cluster_id.to_numpy()[core & (want == c)].max()
    assert ((got.kind.to_numpy() == "noise") == (want < 0)).all()


def test_dbscan_edge_cases(spark):
    schema = "id long, x double, y double"
    assert dbscan.dbscan(spark.createDataFrame([], schema), 1, 3).count() == 0
    same = spark.createDataFrame([(i, 1.0, 1.0) for i in range(5)] + [(9, None, 1.0), (10, float("nan"), 0.0)], schema)
    assert {(r.cluster_id, r.kind) for r in dbscan.dbscan(same, 1, 5).collect()} == {(0, "core")}
    assert dbscan.dbscan(same, 1, 6).filter("kind = 'noise'").count() == 5
    border = spark.createDataFrame([(i, 0.1 * i, 0.0) for i in range(4)] + [(i, 2.0 + 0.1 * i, 0.0) for i in range(4, 8)] + [(20, 1.3, 0.0)], schema)
    assert dbscan.dbscan(border, 1.05, 4).filter("id = 20").first().cluster_id == 0


def test_neighbouring_full_cells_never_form_pairs(spark):
    import numpy as np

    rng = np.random.default_rng(8)
    n = 50_000
    left = np.stack([rng.uniform(0.0, 0.7, n), rng.uniform(0, 0.7, n)], 1)
    right = np.stack([rng.uniform(0.72, 1.4, n), rng.uniform(0, 0.7, n)], 1)
    apart = np.stack([rng.uniform(3.6, 4.2, n), rng.uniform(0, 0.7, n)], 1)
    lone = np.array([[2.0, 0.35], [2.35, 0.35], [3.0, 3.0]])
    x = np.concatenate([left, right, apart, lone])
    import pandas as pd

    points = spark.createDataFrame(pd.DataFrame({"id": np.arange(len(x)), "x": x[:, 0], "y": x[:, 1]}))
    got = dbscan.dbscan(points, 1.0, 40).toPandas().sort_values("id")
    kinds, of = got["kind"].to_numpy(), got["cluster_id"].to_numpy()
    assert (kinds[: 3 * n] == "core").all() and set(of[: 2 * n]) == {0} and set(of[2 * n : 3 * n]) == {2 * n}
    reach = [(((x[: 3 * n] - p) ** 2).sum(1) <= 1).sum() for p in lone]
    assert [k for k in kinds[3 * n :]] == ["core" if r + 1 >= 40 else "border" if r else "noise" for r in reach]


def test_parts_ask_before_their_points(spark, monkeypatch):
    import numpy as np
    import pandas as pd

    rng = np.random.default_rng(9)
    p = np.concatenate([rng.normal(10, 0.05, (20_000, 2)), rng.uniform(0, 3, (6_000, 2))])  # wholly core, and wholly noise
    written, write = {}, dbscan.materialize

    def counted(df, name="table"):
        out = write(df, name)
        written[name] = out.count()
        return out

    monkeypatch.setattr(dbscan, "materialize", counted)
    points = spark.createDataFrame(pd.DataFrame({"id": np.arange(len(p)), "x": p[:, 0], "y": p[:, 1]}))
    got = dbscan.dbscan(points, 1.0, 19_000).toPandas().sort_values("id")
    assert (got["kind"][:20_000] == "core").all() and (got["kind"][20_000:] == "noise").all()
    assert written["neighbour-parts"] < len(p)


def test_grid_clusters(spark, sf):
    shapes = view(spark, sf.replace("0.001", "0.01"), "shapes")
    assert grid.grid_dbscan(shapes, 16, 14, 4).select("cluster_id").distinct().count() == 6
    assert grid.grid_dbscan(shapes, 16, 14, 8).select("cluster_id").distinct().count() == 4


def test_agreement_by_hand(spark):
    df = spark.createDataFrame([(1, 1, 1), (2, 1, 1), (3, 2, 1), (4, 2, 2)], "id int, pred int, truth int")
    assert [int(v) for v in metrics.pair_counts(df).first()] == [1, 2, 1, 2]
    assert metrics.pair_counts(df).first() == metrics.pair_counts_brute(df).first()
    r = metrics.agreement(df).first()
    assert (r.rand_index, r.jaccard_index, r.fowlkes_mallows) == pytest.approx((0.5, 0.25, 1 / 6**0.5))


@pytest.mark.parametrize("mode", metrics.NOISE_MODES)
def test_pairs_add_up_and_labels_do_not_matter(spark, sf, mode):
    df = grid.cell_of(view(spark, sf, "shapes"), 64).select("id", F.when(F.col("cx") > 2, F.col("cx")).alias("pred"), F.when(F.col("lab") != "error", F.col("lab")).alias("truth"))
    r = metrics.pair_counts(df, noise=mode).first()
    n = df.dropna().count() if mode == "drop" else df.count()
    assert r.a + r.b + r.c + r.d == n * (n - 1) // 2
    same = metrics.agreement(df.select("pred", F.col("pred").alias("truth")), noise=mode).first()
    assert (same.rand_index, same.jaccard_index, same.fowlkes_mallows) == pytest.approx((1, 1, 1))


def test_degenerate_partitions_have_null_indices(spark):
    one = spark.createDataFrame([(1, 1, 1)], "id int, pred int, truth int")
    assert metrics.agreement(one).first().rand_index is None
    apart = spark.createDataFrame([(1, 1, 1), (2, 2, 2)], "id int, pred int, truth int")
    assert metrics.agreement(apart).first().jaccard_index is None


def test_sources(spark, tmp_path, sf):
    spec = PointSpec(attrs={"name": "STRING"})
    (tmp_path / "p.csv").write_text("id,x,y,name\n1,2.5,3.5,a\n2,oops,1,b\n")
    rows = {r.id: r for r in read_points(spark, str(tmp_path / "p.csv"), "csv", spec).collect()}
    assert rows[1].x == 2.5 and rows[2]._corrupt_record is not None
    assert spec.valid(read_points(spark, str(tmp_path / "p.csv"), "csv", spec)).count() == 1
    write_indexed(view(spark, sf, "shapes"), str(tmp_path / "ix"), (-0.0005, -0.0005, 1024.0), files=4)
    back = spark.read.parquet(str(tmp_path / "ix"))
    assert back.count() == view(spark, sf, "shapes").count() and {"ckey", "coarse"} <= set(back.columns)
