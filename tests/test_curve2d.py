import numpy as np
import pytest

from knnscope.operators import baselines, merge
from knnscope.operators.curve2d import ClusterModel, curve_cluster_2d
from knnscope.operators.curvetree import CurveTree
from knnscope.operators.metrics import agreement_arrays
from knnscope.operators.service import Budget, MemoryKnnService

DOMAIN = (0.0, 0.0, 64.0)


def blobs(seed=3, n=600, noise=60):
    rng = np.random.default_rng(seed)
    places = np.concatenate([rng.uniform(0, 12, (n, 2)) + c for c in ((5, 5), (40, 8), (20, 44))] + [rng.uniform(0, 64, (noise, 2))])
    return np.arange(len(places)), places[:, 0], places[:, 1], np.repeat([1, 2, 3, 0], [n, n, n, noise])


@pytest.mark.parametrize(("curve", "domain", "side"), [("hilbert", DOMAIN, 4.0), ("z", DOMAIN, 4.0), ("peano", (0.0, 0.0, 81.0), 3.0)])
@pytest.mark.parametrize("on_split", ["restart", "continue"])
def test_finds_blobs(curve, domain, side, on_split):
    i, x, y, truth = blobs()
    s = MemoryKnnService((i, x, y), 12, Budget(2000))
    m = curve_cluster_2d(s, domain, 4.0, 12, side, curve, on_split=on_split)
    # cells of side 3 cut off strips of the blobs that hold fewer than 12 points
    assert agreement_arrays(m.assign_arrays(x, y).tolist(), truth.tolist())["rand_index"] > (0.85 if curve == "peano" else 0.9)
    assert m.tree.contradictions == 0
    assert s.budget.used <= 2000


def test_leaves_tile_the_domain_and_large_ones_are_never_dense():
    i, x, y, _ = blobs()
    m = curve_cluster_2d(MemoryKnnService((i, x, y), 12), DOMAIN, 4.0, 12, 4.0)
    t = m.tree
    at = 0
    for key in t.keys:
        assert key == at
        at = t.last_key(key) + 1
    assert at == t.width
    assert all(t.level[k] == t.levels for k, dense in t.state.items() if dense and k in t.level)
    for k, dense in t.state.items():
        if k in t.boxes and not dense:
            cx, cy, side = t.boxes[k]
            inside = (np.abs(x - cx) < side / 2) & (np.abs(y - cy) < side / 2)
            assert inside.sum() < 12 or t.level[k] == t.levels


def test_fixed_full_check_equals_components_of_dense_cells():
    i, x, y, _ = blobs()
    s = MemoryKnnService((i, x, y), 10_000)
    m = curve_cluster_2d(s, DOMAIN, 4.0, 12, 4.0, adaptive=False, n_check=None, merge="adjacent")
    cells = np.floor(x / 4).astype(int) * 16 + np.floor(y / 4).astype(int)
    dense = np.bincount(cells, minlength=256) >= 12
    got = m.assign_arrays(x, y)
    assert ((got > 0) == dense[cells]).all()


def test_budgets_fanout_and_policies():
    i, x, y, _ = blobs()
    for options in ({"fanout": 16}, {"seed_policy": "area"}, {"seed_policy": "prior", "prior": lambda a, b, c: 1.0}, {"leaf_test": "circumscribed"}, {"recompute": True}):
        for budget in (0, 1, 40):
            s = MemoryKnnService((i, x, y), 12, Budget(budget))
            curve_cluster_2d(s, DOMAIN, 4.0, 12, 4.0, **options)
            assert s.budget.used <= budget


def test_bad_options():
    with pytest.raises(ValueError):
        CurveTree(DOMAIN, 5.0, 3)
    with pytest.raises(ValueError):
        CurveTree(DOMAIN, 4.0, 3, fanout=5)


def test_assign_equals_arrays_and_saves(spark, tmp_path):
    i, x, y, _ = blobs()
    m = curve_cluster_2d(MemoryKnnService((i, x, y), 12), DOMAIN, 4.0, 12, 4.0)
    rows = [*zip(i.tolist(), x.tolist(), y.tolist()), (9001, None, 1.0), (9002, 1e9, 1.0)]
    df = spark.createDataFrame(rows, "id long, x double, y double")
    plan = m.assign(df)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Exchange hashpartitioning(id" not in plan and "Cartesian" not in plan
    got = {r.id: r.cluster_id for r in m.assign(df).collect()}
    assert [got[k] or 0 for k in i.tolist()] == m.assign_arrays(x, y).tolist()
    assert got[9001] is None and got[9002] is None
    assert {r.id: r.cluster_id for r in m.assign_range_join(df).collect()} == got
    m.save(spark, str(tmp_path / "m"))
    assert ClusterModel.load(spark, str(tmp_path / "m")).segments == [tuple(s) for s in m.segments]


def test_merging_rules():
    a, b = np.array([[0.0, 0.0], [0.0, 1.0]]), np.array([[3.0, 0.0], [9.0, 0.0]])
    pairs, edges = merge.top_l({0: a, 1: b}, 2, 4.0)
    assert pairs[0, 1] == pytest.approx((3 + 10**0.5) / 2) and edges == [(0, 1)]
    assert merge.top_l({0: a, 1: b}, 4, 4.0)[1] == []
    boxes = {0: np.array([[2.0, 2.0, 4.0]]), 1: np.array([[5.0, 1.0, 2.0]]), 2: np.array([[6.0, 6.0, 4.0]])}
    assert merge.adjacent(boxes) == [(0, 1)]


def test_method_beats_the_sample_at_equal_budget():
    i, x, y, truth = blobs(n=2000)
    ours, base = [], []
    for seed in range(5):
        s = MemoryKnnService((i, x, y), 40, Budget(150))
        ours.append(agreement_arrays(curve_cluster_2d(s, DOMAIN, 4.0, 40, 4.0, seed=seed).assign_arrays(x, y).tolist(), truth.tolist())["rand_index"])
        s = MemoryKnnService((i, x, y), 40, Budget(150))
        model = baselines.sample_then_cluster(s, DOMAIN, 4.0, 40, 8.0, "raw", seed, len(i))
        base.append(agreement_arrays(model.assign_arrays(x, y).tolist(), truth.tolist())["rand_index"])
    assert np.mean(ours) > np.mean(base)


def test_the_mean_of_the_nearest_needs_no_matrix(spark, monkeypatch):
    rng = np.random.default_rng(3)
    a, b, c = (np.round(rng.normal(0, 3, (900, 2)) + at, 3) for at in ([0, 0], [9, 2], [40, 0]))
    brute = lambda p, q, l: float(np.sort(np.sqrt(((p[:, None] - q[None]) ** 2).sum(2)).ravel())[:l].mean())
    monkeypatch.setattr(merge, "BLOCK", 256)
    for l in (1, 7, 400, 10**7):
        assert merge.mean_of_nearest(a, b, l) == pytest.approx(brute(a, b, l))
    same = np.ones((900, 2))
    assert merge.mean_of_nearest(same, same + 1, 5) == pytest.approx(2**0.5)
    rows = [(m, float(x), float(y)) for m, p in enumerate((a, b, c)) for x, y in p]
    table = spark.createDataFrame(rows, "mini int, x double, y double")
    for l in (3, 300):
        for threshold in (0.5, brute(a, b, l) * 0.999, brute(a, b, l) * 1.001, 60.0):
            edges = merge.top_l({0: a, 1: b, 2: c}, l, threshold)[1]
            assert merge.top_l_table(table, [0, 1, 2], l, threshold)[1] == edges, (l, threshold)


def test_a_sample_is_compared_with_many_places_in_small_blocks():
    import tracemalloc

    x, y = np.random.default_rng(5).random((2, 9000)) * 100
    model = baselines.SampleModel(x[:3000], y[:3000], np.arange(3000) % 7 - 1, 0.9)
    use = np.flatnonzero(model.label >= 0)
    d2 = [(x[use] - a) ** 2 + (y[use] - b) ** 2 for a, b in zip(x[3000:], y[3000:])]
    want = [model.label[use[d.argmin()]] + 1 if d.min() <= 0.9**2 else 0 for d in d2]
    tracemalloc.start()
    got = model.assign_arrays(x[3000:], y[3000:])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got.tolist() == want and 0 in want and peak < 30e6
