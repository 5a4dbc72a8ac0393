import numpy as np
import pytest

from knnscope.operators import baselines
from knnscope.operators.pursuit import STRATEGIES, GridLine, boundary_cluster_1d, miss_probability
from knnscope.operators.service import Budget, MemoryKnnService


def line_points(counts):
    x = np.concatenate([i + (np.arange(n) + 0.5) / n for i, n in enumerate(counts) if n])
    return np.arange(len(x)), x, np.zeros(len(x))


TWO_RUNS = [0, 0, 0, 5, 5, 5, 5, 0, 0, 0, 5, 5, 5, 0, 0, 0]
NOISY = [n or 1 for n in TWO_RUNS * 4]
HOLE = [5] * 11 + [1] + [5] * 9


def runs(counts, least=5):
    found = []
    for i, n in enumerate(counts):
        if n >= least:
            if found and found[-1][1] == i - 1:
                found[-1] = (found[-1][0], i)
            else:
                found.append((i, i))
    return found


@pytest.mark.parametrize("strategy", STRATEGIES)
@pytest.mark.parametrize("counts", [TWO_RUNS, NOISY, HOLE, [5], [0, 5], [5, 0], [1, 1], [5] * 40])
@pytest.mark.parametrize("infer", [True, False])
@pytest.mark.parametrize("seeds", [1, 4])
def test_full_check_finds_the_maximal_runs(strategy, counts, infer, seeds):
    s = MemoryKnnService(line_points(counts), 5)
    got = boundary_cluster_1d(s, (0.0, float(len(counts))), 1.0, 5, None, strategy, infer, seeds)
    assert sorted(got.segments) == runs(counts)
    assert got.line.contradictions == 0
    assert len(s.calls) == s.budget.used


@pytest.mark.parametrize("budget", [0, 1, 5, 20])
def test_budget_is_kept(budget):
    s = MemoryKnnService(line_points(NOISY), 5, Budget(budget))
    boundary_cluster_1d(s, (0.0, float(len(NOISY))), 1.0, 5)
    assert s.budget.used <= budget


def test_both_rules_agree_if_k_is_min_pts():
    for rule in ("min_pts", "all_k"):
        s = MemoryKnnService(line_points(NOISY), 5)
        assert sorted(boundary_cluster_1d(s, (0.0, 64.0), 1.0, 5, None, rule=rule).segments) == runs(NOISY)


def test_bisection_beats_the_walk_in_noise():
    counts = [1] * 400 + [5] * 60 + [1] * 400
    used = {}
    for strategy in ("walk", "auto"):
        s = MemoryKnnService(line_points(counts), 5)
        line = GridLine(0.0, float(len(counts)), 1.0, 5, infer=False)
        from knnscope.operators.pursuit import Pursuit

        p = Pursuit(line, s, 5, strategy)
        p.line.mark(430, True)
        search = p._segment(430)
        asked = next(search)
        while True:
            answers = s.probe([line.place(c) for c, _ in asked])
            for (c, _), a in zip(asked, answers):
                line.learn(c, a)
            try:
                asked = search.send(answers)
            except StopIteration as done:
                assert done.value == (400, 459)
                break
        used[strategy] = s.budget.used
    assert used["auto"] < used["walk"] / 5


def test_baselines_find_the_runs():
    for run in (baselines.scan_all_cells, baselines.random_cells):
        assert run(GridLine(0.0, 64.0, 1.0, 5), MemoryKnnService(line_points(NOISY), 5)) == runs(NOISY)


def test_miss_probability():
    assert miss_probability(10, 1, 5) == pytest.approx(0.5)
    assert miss_probability(10, 0, 5) == 1
    assert miss_probability(10, 6, 5) == 0


def test_walking_costs_more_than_skipping_and_halving(spark):
    from knnscope.plans import workloads

    for run in (workloads.line_costs, workloads.line_costs_clean):
        rows = {r.method: r for r in run(spark, "/root/testdata/sf0.01").collect()}
        assert rows["walk"].calls > rows["skip"].calls >= rows["bisect"].calls
        assert rows["auto"].calls <= rows["skip"].calls < rows["scan_all"].calls
        assert len({rows[m].segments for m in ("walk", "skip", "bisect", "auto")}) == 1


def test_a_line_of_many_points_costs_the_same_calls(spark, monkeypatch):
    from knnscope.plans import workloads

    sf = "/root/testdata/sf0.01"
    small = workloads.line_costs(spark, sf, "value").collect()
    monkeypatch.setattr(workloads, "LINE_LIMIT", 10)
    assert workloads.line_costs(spark, sf, "value").collect() == small


def test_lines_are_never_collected(spark, monkeypatch):
    from knnscope import catalog
    from knnscope.operators.service import MemoryKnnService

    monkeypatch.setattr(MemoryKnnService, "LIMIT", 10)
    q, sf = catalog.queries(), "/root/testdata/sf0.01"
    for name in ("density_probe_1d", "density_probe_all_k", "segments_exhaustive_1d", "segments_walk_1d", "segments_auto_1d"):
        assert q[name](spark, sf).count() > 0, name
