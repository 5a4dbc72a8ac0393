"""The experiments on the given tables: each returns one row per run with calls, rounds and agreement measures.

Ground truth is exact DBSCAN with parameters of its own, as the quality of the method is measured; the agreement with the planted
shapes stands beside it. The runs of a sweep are independent. Up to ``MemoryKnnService.LIMIT`` points they are dealt over
the executors, which share one broadcast of the points; beyond that each run goes through the distributed service, and the
agreement comes from the contingency table.
"""

from __future__ import annotations

import json
from collections import Counter
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.io import materialize, table
from knnscope.operators import baselines, knn, metrics
from knnscope.operators.curve2d import ClusterModel, curve_cluster_2d
from knnscope.operators.dbscan import dbscan
from knnscope.operators.pursuit import GridLine, Pursuit, boundary_cluster_1d, theory_bound
from knnscope.operators.curvetree import centres, smallest_cells
from knnscope.operators.service import Budget, CountedKnnService, DrawnKnnService, KnnService, MemoryKnnService, PreparedKnnService
from knnscope.sources.views import view

#: The square of the curve and tree queries.
DOMAIN = (-0.0005, -0.0005, 1024.0)
#: The squares of the experiments, close round points in 700 x 500, and the smallest cell's side: found by a study (README).
SQUARE = {"hilbert": (-0.0005, -0.0005, 704.0), "z": (-0.0005, -0.0005, 704.0), "peano": (-0.0005, -0.0005, 1080.0)}
SIDE = {"hilbert": 44.0, "z": 44.0, "peano": 40.0}
#: Merging distance as a multiple of a set's, by curve.
MERGE = {"hilbert": 1.0, "z": 1.0, "peano": 1.25}
#: Distance for merging; eps and minPts of DBSCAN on a set of its published size.
SETS = {"shapes": (20.0, 10.0, 14, 10_000), "shapes_b": (20.0, 10.0, 19, 8_000), "shapes_c": (15.0, 8.0, 6, 8_000)}
BUDGETS = (200, 300, 400, 500, 600)
#: Points of a line that are asked on the driver; more stay distributed.
LINE_LIMIT = 100_000
OPTIONS = {"n_check": 2, "strategy": "bisect"}
SCHEMA = (
    "workload string, setting string, curve string, budget int, seed int, calls int, rounds int, mini_clusters int, clusters int, "
    "split_calls int, leaf_calls int, true_clusters int, rand_index double, jaccard_index double, fowlkes_mallows double, rand_planted double"
)


@lru_cache(maxsize=16)
def _arrays(spark: SparkSession, sf_dir: str, name: str, noise: int) -> tuple:
    """``id, x, y``, DBSCAN's labels and the planted ones (0 is noise) of a set that fits ``MemoryKnnService``."""
    points = noisy(view(spark, sf_dir, name), noise)
    rows = points.select("id", "x", "y", "lab").join(_truth(spark, sf_dir, name, noise), "id").toPandas().sort_values("id")
    number = lambda c, none: rows[c].map({v: i + 1 for i, v in enumerate(sorted(set(rows[c].dropna()) - {none}))}).fillna(0).astype(int).to_numpy()
    return *(rows[c].to_numpy() for c in ("id", "x", "y")), number("truth", None), number("lab", "error")


def noisy(points: DataFrame, noise: int) -> DataFrame:
    """All points of a shape and that share, in per cent, of the others."""
    return points if noise >= 100 else points.filter((F.col("lab") != "error") | (F.pmod(F.col("id") * 31 + 7, F.lit(100)) < noise))


def scaled(name: str, n: int) -> int:
    _, _, min_pts, size = SETS[name]
    return max(2, round(min_pts * n / size))


def _truth(spark, sf_dir, name, noise) -> DataFrame:
    points = view(spark, sf_dir, name)
    found = dbscan(noisy(points, noise).select("id", "x", "y"), SETS[name][1], scaled(name, points.count()))
    return found.select("id", F.col("cluster_id").alias("truth"))


class Benchmark:
    """A view's points, with DBSCAN's labels as truth and the planted labels beside them."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str = "shapes", noise: int = 100):
        self.spark, self.sf_dir, self.name, self.noise = spark, sf_dir, name, noise
        points = view(spark, sf_dir, name)
        self.min_pts, self.eps = scaled(name, points.count()), SETS[name][0]
        self.points = noisy(points, noise)
        self.n = self.points.count()
        self.small = self.n <= MemoryKnnService.LIMIT
        if self.small:
            self.id, self.x, self.y, self.truth, self.planted = _arrays(spark, sf_dir, name, noise)
        else:
            self.points = materialize(self.points.select("id", "x", "y", "lab"), "benchmark")
            self.books, self.pyramids = {}, {}

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("spark", "points", "books", "pyramids")}

    def service(self, k: int | None = None, budget: float | None = None, curve: str = "hilbert", min_side=None, adaptive: bool = True):
        """For the tree of a curve. Beyond a benchmark set, its runs share what is looked up of the points."""
        spent, k = Budget() if budget is None else Budget(budget), k or self.min_pts
        if self.small:
            return MemoryKnnService((self.id, self.x, self.y), k, spent)
        square, min_side = SQUARE[curve], min_side or SIDE[curve]
        at = (k, square, min_side, adaptive)
        return CountedKnnService(
            self.points.select("id", "x", "y"), k, centres(square, min_side, curve, adaptive), smallest_cells(square, min_side, curve),
            [min(k, self.min_pts)], spent, self._pyramid(k), self.books.setdefault(at, {}),
        )

    def _pyramid(self, k: int) -> knn.Pyramid:
        if k not in self.pyramids:
            self.pyramids[k] = knn.Pyramid(self.points, k=k)
        return self.pyramids[k]

    def _drawing(self, sampler: str, budget: float, seed: int) -> KnnService:
        """For a sampler that asks at random places; of an answer ``raw`` uses the nearest row alone, ``voronoi`` that and its rays."""
        points, k = self.points.select("id", "x", "y"), 1 if sampler == "raw" else self.min_pts
        if sampler == "uniform":
            return KnnService(points, k, Budget(budget), pyramid=self._pyramid(self.min_pts))
        if self.books.get("drawn", (None,))[0] != (sampler, seed):
            self.books["drawn"] = ((sampler, seed), {})
        places, rays = baselines.drawn_places(SQUARE["hilbert"], int(budget), seed, sampler)
        if sampler == "raw":
            return PreparedKnnService(points, k, places, Budget(budget), self._pyramid(k), self.books["drawn"][1])
        return DrawnKnnService(points, k, places, rays, Budget(budget), self._pyramid(k), self.books["drawn"][1])

    def run(self, workload: str, setting="", curve: str = "hilbert", budget=None, seed: int = 0, k=None, **options) -> tuple:
        options = OPTIONS | {"min_side": SIDE[curve], "merge_threshold": self.eps * MERGE[curve]} | options
        service = self.service(k, budget, curve, options["min_side"], options.get("adaptive", True))
        model = curve_cluster_2d(service, SQUARE[curve], self.eps, self.min_pts, curve=curve, seed=seed, **options)
        return self.row(workload, setting, curve, budget, seed, service, model, model.summary())

    def sample(self, workload: str, sampler: str, budget=None, seed: int = 0) -> tuple:
        service = self.service(budget=budget) if self.small else self._drawing(sampler, budget, seed)
        eps = SETS[self.name][1]
        model = baselines.sample_then_cluster(service, SQUARE["hilbert"], eps, self.min_pts, 2 * eps, sampler, seed, self.n)
        return self.row(workload, f"sample_{sampler}", "", budget, seed, service, model)

    def row(self, workload, setting, curve, budget, seed, service, model, summary=None) -> tuple:
        """A run's row; for a set that stays distributed, without the agreement but with the model, whose agreement comes with all others'."""
        s, node = summary or {}, service.cost_by_node()
        done = (
            workload, str(setting), curve, None if budget is None else int(budget), seed, service.budget.used, service.rounds,
            s.get("mini_clusters"), s.get("clusters"), node.get("split", 0), node.get("leaf", 0),
        )
        if not self.small:
            return done, ClusterModel(model.kind, model.domain, model.order, model.segments) if summary else model
        got, truth, planted = (v.tolist() for v in (model.assign_arrays(self.x, self.y), self.truth, self.planted))
        return self._with_agreement(done, Counter(zip(got, truth)), Counter(zip(got, planted)), len(set(truth) - {0}))

    @staticmethod
    def _with_agreement(done: tuple, truth: dict, planted: dict, clusters: int) -> tuple:
        return *done, clusters, *metrics.agreement_counts(truth).values(), metrics.agreement_counts(planted)["rand_index"]

    def agreements(self, models: list) -> list[tuple[dict, dict]]:
        """For each model the number of points by label and true label, and by label and planted one: one scan for all models, and
        only counts come back."""
        shared = self.spark.sparkContext.broadcast(models)
        labelled = self.points.join(_truth(self.spark, self.sf_dir, self.name, self.noise), "id")
        rows = labelled.select("x", "y", F.coalesce("truth", F.lit(-1)).alias("truth"), F.when(F.col("lab") != "error", F.col("lab")).alias("planted"))

        def kernel(batches):
            for batch in batches:
                x, y, known = batch["x"].to_numpy(), batch["y"].to_numpy(), batch[["truth", "planted"]].fillna({"planted": ""}).groupby(["truth", "planted"])
                code, pairs, found = known.ngroup().to_numpy(), known.size().index.to_frame(index=False), []
                for i, m in enumerate(shared.value):
                    at, n = np.unique(m.assign_arrays(x, y) * len(pairs) + code, return_counts=True)
                    found.append(pairs.iloc[at % len(pairs)].assign(run=i, pred=at // len(pairs), n=n))
                yield pd.concat(found)[["run", "pred", "truth", "planted", "n"]]

        counts = rows.mapInPandas(kernel, "run int, pred long, truth long, planted string, n long")
        found = [(Counter(), Counter()) for _ in models]
        for r in counts.groupBy("run", "pred", "truth", "planted").agg(F.sum("n").alias("n")).collect():  # as many as pairs of labels
            found[r.run][0][r.pred, r.truth] += r.n
            found[r.run][1][r.pred, r.planted] += r.n
        return found

    def sweep(self, runs: list[dict]) -> DataFrame:
        """One row for each run: arguments of ``run``, or of ``sample`` if they name a sampler."""
        if not self.small:
            # runs that draw at the same places come together
            done = [self._one(r) for r in sorted(runs, key=lambda r: (r.get("sampler", ""), r.get("seed", 0), -(r.get("budget") or 0)))]
            rows = []
            for (row, _), (truth, planted) in zip(done, self.agreements([m for _, m in done])):
                rows.append(self._with_agreement(row, truth, planted, len({t for _, t in truth} - {-1})))
            return self.spark.createDataFrame(rows, SCHEMA)
        shared = self.spark.sparkContext.broadcast(self)

        def kernel(batches):
            for batch in batches:
                rows = [shared.value._one(json.loads(r)) for r in batch["run"]]
                yield pd.DataFrame(rows, columns=[c.split()[0] for c in SCHEMA.split(", ")])

        jobs = self.spark.createDataFrame([(json.dumps(r),) for r in runs], "run string")
        return jobs.repartition(min(len(runs), 256)).mapInPandas(kernel, SCHEMA)

    def _one(self, run: dict) -> tuple:
        return self.sample(**run) if "sampler" in run else self.run(**run)


def feasibility(spark, sf_dir, budget: int = 400) -> DataFrame:
    """Two benchmark sets at one budget."""
    a, b = (Benchmark(spark, sf_dir, n).sweep([{"workload": "feasibility", "setting": n, "budget": budget}]) for n in ("shapes_b", "shapes_c"))
    return a.unionByName(b)


def against_sample(spark, sf_dir, budgets=BUDGETS, seeds: int = 5) -> DataFrame:
    """The clusterer and the sampling baseline, by each way to draw, at equal budgets. ``uniform`` draws as no client could."""
    runs = []
    for budget in budgets:
        for seed in range(seeds):
            at = {"workload": "against_sample", "budget": budget, "seed": seed}
            runs += [at | {"setting": "pursuit", "curve": "peano"}, *(at | {"sampler": s} for s in ("raw", "voronoi", "uniform"))]
    return Benchmark(spark, sf_dir).sweep(runs)


def curve_kinds(spark, sf_dir, budget: int = 200, seeds: int = 5) -> DataFrame:
    runs = [{"workload": "curve_kinds", "setting": c, "curve": c, "budget": budget, "seed": s} for c in SIDE for s in range(seeds)]
    return Benchmark(spark, sf_dir).sweep(runs)


def quality_by_cost(spark, sf_dir, budgets=BUDGETS, seeds: int = 5, names=("shapes",)) -> DataFrame:
    out = None
    for name in names:
        runs = [
            {"workload": "quality_by_cost", "setting": c if len(names) == 1 else f"{name} {c}", "curve": c, "budget": q, "seed": s}
            for c in ("hilbert", "peano") for q in budgets for s in range(seeds)
        ]
        one = Benchmark(spark, sf_dir, name).sweep(runs)
        out = one if out is None else out.unionByName(one)
    return out


def quality_all_sets(spark, sf_dir) -> DataFrame:
    return quality_by_cost(spark, sf_dir, names=tuple(SETS))


def vary_k(spark, sf_dir, factors=(1, 2, 4, 8), seeds: int = 3) -> DataFrame:
    """Calls until nothing is unknown, for answers of more and more points."""
    b = Benchmark(spark, sf_dir)
    return b.sweep([{"workload": "vary_k", "setting": f, "seed": s, "k": f * b.min_pts, "min_side": 22.0} for f in factors for s in range(seeds)])


def vary_side(spark, sf_dir, sides=(11.0, 22.0, 44.0, 88.0), seeds: int = 3) -> DataFrame:
    return Benchmark(spark, sf_dir).sweep([{"workload": "vary_side", "setting": m, "seed": s, "min_side": m} for m in sides for s in range(seeds)])


def vary_children(spark, sf_dir, seeds: int = 2) -> DataFrame:
    runs = []
    for curve, fans, side in (("hilbert", (4, 16, 64), 11.0), ("peano", (9, 81), 1080.0 / 81)):
        runs += [{"workload": "vary_children", "setting": f, "curve": curve, "seed": s, "fanout": f, "min_side": side} for f in fans for s in range(seeds)]
    return Benchmark(spark, sf_dir).sweep(runs)


def vary_noise(spark, sf_dir, shares=(0, 25, 50, 75, 100), seeds: int = 3) -> DataFrame:
    """Calls by the share of noise; minPts stays that of the whole set."""
    out = None
    for share in shares:
        one = Benchmark(spark, sf_dir, noise=share).sweep([{"workload": "vary_noise", "setting": share, "seed": s, "min_side": 22.0} for s in range(seeds)])
        out = one if out is None else out.unionByName(one)
    return out


def merging(spark, sf_dir, budget: int = 500, ls=(1, 3, 7, 14, 28)) -> DataFrame:
    """No merging, merging by edges, and by l-distances for several l."""
    runs = [{"workload": "merging", "setting": m, "budget": budget, "merge": m} for m in ("none", "adjacent")]
    return Benchmark(spark, sf_dir).sweep(runs + [{"workload": "merging", "setting": f"l={l}", "budget": budget, "l": l} for l in ls])


def fixed_or_adaptive(spark, sf_dir, seeds: int = 2) -> DataFrame:
    """Equal cells of the smallest side against cells that shrink where points are, to full coverage, each with both ways to merge."""
    kinds = [("fixed", False, "top_l"), ("fixed + edges", False, "adjacent"), ("adaptive", True, "top_l"), ("adaptive + edges", True, "adjacent")]
    runs = [{"workload": "fixed_or_adaptive", "setting": n, "seed": s, "adaptive": a, "merge": m} for n, a, m in kinds for s in range(seeds)]
    return Benchmark(spark, sf_dir).sweep(runs)


def steps(spark, sf_dir, budget: int = 600) -> tuple[ClusterModel, DataFrame]:
    """The stages of one run: the model, and its leaves as a table."""
    b = Benchmark(spark, sf_dir)
    model = curve_cluster_2d(b.service(budget=budget), SQUARE["hilbert"], b.eps, b.min_pts, SIDE["hilbert"], merge_threshold=b.eps, **OPTIONS)
    return model, model.leaves(spark)


def stages(spark, sf_dir) -> DataFrame:
    """The leaves of one run with the mini-cluster and the final cluster of each, and the mapping error of its segment."""
    model, leaves = steps(spark, sf_dir)
    mini = model.minis(spark).withColumnsRenamed({"lo_key": "first", "hi_key": "last"})
    inside = F.expr("lo_key BETWEEN first AND last")
    return leaves.join(F.broadcast(mini), inside, "left").select("level", "lo_key", "hi_key", "x", "y", "side", "state", "mini_id", "cluster_id", "mapping_error")


def line_points(spark, sf_dir, column: str) -> DataFrame:
    """``id, x``: one of the columns that stand for one-dimensional data, spread over 0 to 1000."""
    if column == "line1d":
        return view(spark, sf_dir, "line1d").select("id", "x")
    source, ident, value = {"value": ("events", "event_id", "value"), "balance": ("customer", "c_custkey", "c_acctbal"), "total": ("orders", "o_orderkey", "o_totalprice")}[column]
    rows = table(spark, sf_dir, source).select(F.col(ident).alias("id"), F.col(value).cast("double").alias("v")).filter("v IS NOT NULL AND NOT isnan(v)")
    low, high = rows.agg(F.min("v"), F.max("v")).first()
    return rows.select("id", (F.round((F.col("v") - F.lit(low)) * (1000.0 / ((high - low) or 1.0)), 3)).alias("x"))


def line_costs(spark, sf_dir, column: str = "line1d", side: float = 5.0, min_pts: int = 60, noise: bool = True) -> DataFrame:
    """One dimension: each strategy and both baselines, calls against the bound of the analysis."""
    points = line_points(spark, sf_dir, column)
    if not noise:
        points = view(spark, sf_dir, "line1d").filter("lab <> 'error'").select("id", "x")
    n = points.count()
    min_pts = max(2, round(min_pts * n / 10_000)) if column == "line1d" else max(2, round(n * side / 1000 * 1.1))
    # more points than a benchmark set are asked through the distributed service, which counts answers by the line's cells
    points, low = points.withColumn("y", F.lit(0.0)), -0.0005
    if n > LINE_LIMIT:
        points = materialize(points, "line")
        pyramid, book, places = knn.Pyramid(points, k=min_pts), {}, GridLine(low, 1000.5, side, min_pts).places()
        service = lambda: CountedKnnService(points, min_pts, places, (low, -side / 2, side), pyramid=pyramid, book=book)
    else:
        service = lambda: MemoryKnnService(points, min_pts)
    out = []
    for strategy in ("walk", "skip", "bisect", "auto"):
        s = service()
        p = boundary_cluster_1d(s, (-0.0005, 1000.5), side, min_pts, 5, strategy)
        out.append((column, strategy, s.budget.used, s.rounds, len(p.segments), theory_bound(len(p.segments), 5, p.line.n)))
    for name, run in (("scan_all", baselines.scan_all_cells), ("random", baselines.random_cells)):
        s, line = service(), GridLine(-0.0005, 1000.5, side, min_pts)
        found = run(line, s)
        out.append((column, name, s.budget.used, s.rounds, len(found), theory_bound(len(found), 5, line.n)))
    return spark.createDataFrame(out, "data string, method string, calls int, rounds int, segments int, bound double")


def line_costs_clean(spark, sf_dir) -> DataFrame:
    """The same without noise, where skipping needs no bisection."""
    return line_costs(spark, sf_dir, noise=False)


def line_costs_columns(spark, sf_dir) -> DataFrame:
    """The same on three columns of other tables."""
    out = None
    for column in ("value", "balance", "total"):
        one = line_costs(spark, sf_dir, column)
        out = one if out is None else out.unionByName(one)
    return out


WORKLOADS = {
    "w_feasibility": feasibility, "w_against_sample": against_sample, "w_curve_kinds": curve_kinds, "w_quality_by_cost": quality_by_cost,
    "w_quality_all_sets": quality_all_sets, "w_vary_k": vary_k, "w_vary_side": vary_side, "w_vary_children": vary_children,
    "w_vary_noise": vary_noise, "w_merging": merging, "w_fixed_or_adaptive": fixed_or_adaptive, "w_stages": stages,
    "w_line_costs": line_costs, "w_line_costs_clean": line_costs_clean, "w_line_costs_columns": line_costs_columns,
}
__all__ = ["WORKLOADS", "Benchmark", "Pursuit", "steps"]
