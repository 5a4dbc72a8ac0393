import numpy as np
import pytest

from knnscope.operators import knn, service
from knnscope.operators.service import Budget, BudgetExhausted, KnnService, MemoryKnnService, RateLimit
from knnscope.plans import methods

POINTS = [(i, float((i * 37) % 101), float((i * 53) % 97)) for i in range(300)]


@pytest.fixture(scope="module")
def points(spark):
    return spark.createDataFrame(POINTS, "id long, x double, y double")


def arrays():
    return tuple(np.array(c) for c in zip(*POINTS))


PLACES = [(10.5, 20.25), (-50.0, 30.0), (100.0, 97.0), (55.0, 44.0), (1000.0, 1000.0)]


@pytest.mark.parametrize("k", [1, 7, 400])
def test_distributed_answers_equal_memory(points, k):
    a, b = KnnService(points, k).probe(PLACES), MemoryKnnService(arrays(), k).probe(PLACES)
    for p, q in zip(a, b):
        assert p.ids.tolist() == q.ids.tolist()
        assert p.radius == q.radius


def test_certificate_is_never_wrong():
    s = MemoryKnnService(arrays(), 9)
    _, x, y = arrays()
    for a in s.probe(PLACES):
        d = np.hypot(x - a.x, y - a.y)
        assert set(np.flatnonzero(d < a.radius)) <= set(a.ids)


def test_budget_and_ledger(spark):
    s = MemoryKnnService(arrays(), 5, Budget(3), RateLimit(2, 60.0))
    assert len(s.probe(PLACES, "seed")) == 3
    with pytest.raises(BudgetExhausted):
        s.probe(PLACES)
    assert s.ledger(spark).count() == s.budget.used == 3
    assert s.cost_by_purpose() == {"seed": 3}
    assert s.simulated_seconds() == 60.0


def test_crawl_finds_all_points_of_a_box():
    s = MemoryKnnService(arrays(), 6)
    found = service.crawl_box(s, (10.0, 10.0, 40.0, 60.0))
    assert set(found) == {i for i, x, y in POINTS if 10 <= x <= 40 and 10 <= y <= 60}


@pytest.mark.parametrize("box", [(10.0, 10.0, 40.0, 60.0), (1000.0, 1000.0, 1001.0, 1001.0)])
def test_crawl_as_tables_finds_the_same(spark, box):
    points = [*POINTS, *((1000 + i, 22.5, 33.5) for i in range(5))]  # fewer than k lie at one place
    a, b, c, d = box
    found = service.crawl_box_distributed(spark.createDataFrame(points, "id long, x double, y double"), 6, box)
    assert sorted(r.id for r in found.collect()) == sorted(i for i, x, y in points if a <= x <= c and b <= y <= d)


def test_crawl_query_over_more_points_than_memory_takes(spark, sf, monkeypatch):
    few = {r.id for r in methods.crawl_box_points(spark, sf).collect()}
    monkeypatch.setattr(MemoryKnnService, "LIMIT", 100)
    assert few and {r.id for r in methods.crawl_box_points(spark, sf).collect()} == few


def test_core_by_probe_asks_only_outside_full_cells(spark, points):
    _, x, y = arrays()
    want = {i: int(((x - px) ** 2 + (y - py) ** 2 <= 64).sum()) >= 8 for i, px, py in POINTS}
    assert {r.id: r.core for r in methods.core_by_probe(points, 8.0, 8).collect()} == want
    assert len(set(want.values())) == 2


def test_radii_and_brute_over_the_limit(spark, points, monkeypatch):
    p = knn.Pyramid(points, 16)
    centre = lambda low, c: low + (c + 0.5) * p.side
    assert np.allclose(p.radii(5), [[p.radius(centre(p.x0, i), centre(p.y0, j), 5) for j in range(16)] for i in range(16)], rtol=1e-12)
    probes = points.selectExpr("id AS qid", "x AS qx", "y AS qy").filter("id % 3 = 0")
    rows = lambda: sorted((r.qid, r["rank"], r.id) for r in knn.brute_or_join(points, probes, 4).collect())
    compared = rows()
    monkeypatch.setattr(knn, "PAIRS", 1)
    monkeypatch.setattr(knn, "brute", None)
    assert rows() == compared


@pytest.mark.parametrize("k", [20, 3])
def test_core_test_with_and_without_crawl(k):
    _, x, y = arrays()
    for i in (0, 17, 120):
        want = int(((x - x[i]) ** 2 + (y - y[i]) ** 2 <= 64).sum()) >= 8
        assert service.is_core(MemoryKnnService(arrays(), k), x[i], y[i], 8.0, 8) == want


def test_filter_and_presets(points):
    s = KnnService.preset("listings_filtered", points, where="id % 2 = 0")
    assert all(i % 2 == 0 for i in s.probe([(50.0, 50.0)])[0].ids)
    with pytest.raises(ValueError):
        KnnService.preset("listings_plain", points, where="id = 1")


def test_empty_and_few(points):
    s = KnnService(points.limit(0), 3)
    assert len(s.probe([(0.0, 0.0)])[0].ids) == 0
    assert KnnService(points.limit(2), 3).probe([(0.0, 0.0)])[0].radius == np.inf


def test_prepared_answers_are_charged_as_they_are_asked(points):
    b = MemoryKnnService(arrays(), 7).probe(PLACES[:2])
    s = service.PreparedKnnService(points, 7, PLACES, Budget(3))
    a = s.probe(PLACES[:2])
    assert [p.ids.tolist() for p in a] == [q.ids.tolist() for q in b] and s.budget.used == len(s.calls) == 2
    s.points = None  # no further job
    assert len(s.probe(PLACES)) == 1
    with pytest.raises(BudgetExhausted):
        s.probe(PLACES)


@pytest.mark.parametrize("k", [1, 7, 60, 400])
def test_counted_answers_equal_the_rows(points, k):
    cells = (-0.5, -0.5, 8.0)
    a = service.CountedKnnService(points, k, PLACES, cells, [1, (k + 1) // 2])
    for p, q in zip(a.probe(PLACES), MemoryKnnService(arrays(), k).probe(PLACES)):
        want = {}
        for x, y in zip(q.xs, q.ys):
            c = (int((x + 0.5) // 8), int((y + 0.5) // 8))
            want[c] = want.get(c, 0) + 1
        assert {(int((x + 0.5) // 8), int((y + 0.5) // 8)): n for x, y, n in zip(p.xs, p.ys, p.weight)} == want
        assert p.n == q.n and p.radius == q.radius
        if k <= q.n:
            assert p.reach((k + 1) // 2) == q.reach((k + 1) // 2) and p.reach(k) == q.reach(k)
    want = set().union(*(q.ids.tolist() for q in MemoryKnnService(arrays(), k).probe(PLACES)))
    assert {r.id for r in a.seen_in(points).collect()} == want


@pytest.mark.parametrize(("side", "shipped"), [(0.5, 4_000_000), (8.0, 1), (64.0, 4_000_000)])
def test_counts_equal_rows_at_every_size_of_cell(spark, points, monkeypatch, side, shipped):
    monkeypatch.setattr(knn, "SHIPPED", shipped)
    looked_at = []
    monkeypatch.setattr(knn, "_settled", lambda p, f, held, *a, own=knn._settled: looked_at.extend(len(r[5]) for rings, _ in held for r in rings) or own(p, f, held, *a))
    probes = [(i, *p) for i, p in enumerate(PLACES)]
    for ranks in ([7, 60], [400]):
        found = knn.counted(points, knn.Pyramid(points, k=ranks[-1]), probes, ranks, (-0.25, -0.25, side))
        for (ends, i, j, n), a in zip(found, MemoryKnnService(arrays(), ranks[-1]).probe(PLACES)):
            assert {r: e[1] for r, e in ends.items()} == {r: a.ids[r - 1] for r in {min(r, 300) for r in ranks}}
            want = {}
            for x, y in zip(a.xs, a.ys):
                c = (int((x + 0.25) // side), int((y + 0.25) // side))
                want[c] = want.get(c, 0) + 1
            assert dict(zip(zip(i.tolist(), j.tolist()), n.tolist())) == want
    assert min(looked_at) < 60


def test_places_far_from_the_points_ship_few_cells(spark):
    import tracemalloc

    rows = [(i, 1000.0 * (i % 2) + i % 7, 1000.0 * (i % 2) + i % 5) for i in range(400)]
    p = knn.Pyramid(points := spark.createDataFrame(rows, "id long, x double, y double"), 256)
    places = [(q, 1000.0 - q, 3.0 * q) for q in range(40)]  # in the empty corner: a ball touches most of the 65,536 cells
    tracemalloc.start()
    found = knn.grid_join(points, p, places, 3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 20e6
    want = [(q, *r) for q, qx, qy in places for r in enumerate((i for _, i in sorted(((x - qx) ** 2 + (y - qy) ** 2, i) for i, x, y in rows)[:3]), 1)]
    assert sorted((r.qid, r["rank"], r.id) for r in found.collect()) == want
    assert knn.grid_join(points.limit(0), knn.Pyramid(points.limit(0)), places, 3).count() == 0
