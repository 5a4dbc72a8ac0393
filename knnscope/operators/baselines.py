"""What the budgeted clusterers are compared with: scans, random cells, crawls, and clustering a sample."""

from __future__ import annotations

import math
import random
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.operators.pursuit import GridLine
from knnscope.operators.service import BudgetExhausted, crawl_box


def scan_all_cells(line: GridLine, service, batch: int = 256) -> list[tuple[int, int]]:
    """Ask at the centre of every cell whose state no earlier answer gave; the runs of dense cells."""
    cells = [line.at(r) for r in range(line.size())]
    _ask(line, service, cells, batch, "scan")
    return runs(line)


def random_cells(line: GridLine, service, seed: int = 42, batch: int = 1) -> list[tuple[int, int]]:
    """Ask random unknown cells until the budget is used up, without following boundaries; the runs of dense cells."""
    rng = random.Random(seed)
    try:
        while True:
            cell = line.random_unknown(rng)
            if cell is None:
                break
            _ask(line, service, [cell], batch, "random")
    except BudgetExhausted:
        pass
    return runs(line)


def _ask(line, service, cells, batch: int, purpose: str) -> None:
    at = 0
    while at < len(cells):
        wanted = []
        while at < len(cells) and len(wanted) < batch:
            if line.known(cells[at]) is None:
                wanted.append(cells[at])
            at += 1
        if wanted:
            for cell, answer in zip(wanted, service.probe([line.place(c) for c in wanted], purpose)):
                if line.known(cell) is None:
                    line.learn(cell, answer)


def runs(line) -> list[tuple[int, int]]:
    """First and last cell of each run of cells known to be dense."""
    found: list[list[int]] = []
    for cell in sorted(c for c, dense in line.state.items() if dense):
        r = line.rank(cell)
        if found and line.rank(found[-1][1]) == r - 1:
            found[-1][1] = cell
        else:
            found.append([cell, cell])
    return [tuple(f) for f in found]


def lower_bounds(n: int, core_points: int, dense_cells: int, min_pts: int, k: int) -> dict[str, float]:
    """Least numbers of calls: to see all points, to prove all dense cells, and the same by core points."""
    return {"all_points": math.ceil(n / k), "dense_cells": math.ceil(dense_cells * min_pts / k), "core_points": math.ceil(core_points / k)}


def crawl_all(service, domain) -> dict[int, tuple[float, float]]:
    """All points of a square through the interface."""
    x0, y0, side = domain
    return crawl_box(service, (x0, y0, x0 + side, y0 + side))


def dbscan_arrays(x: np.ndarray, y: np.ndarray, eps: float, min_pts: int) -> np.ndarray:
    """Exact DBSCAN of a sample on the driver: labels from 0 on, -1 for noise; points in order are the tie-break."""
    n = len(x)
    cells: dict[tuple[int, int], list[int]] = {}
    for i, c in enumerate(zip(np.floor(x / eps).astype(int).tolist(), np.floor(y / eps).astype(int).tolist())):
        cells.setdefault(c, []).append(i)
    near: list[np.ndarray] = []
    for i in range(n):
        cx, cy = int(np.floor(x[i] / eps)), int(np.floor(y[i] / eps))
        cand = np.array([j for a in (-1, 0, 1) for b in (-1, 0, 1) for j in cells.get((cx + a, cy + b), ())])
        near.append(cand[(x[cand] - x[i]) ** 2 + (y[cand] - y[i]) ** 2 <= eps * eps])
    core = np.array([len(v) >= min_pts for v in near], bool)
    label, found = np.full(n, -1), 0
    for i in range(n):
        if core[i] and label[i] < 0:
            stack, label[i] = [i], found
            while stack:
                for j in near[stack.pop()].tolist():
                    if core[j] and label[j] < 0:
                        label[j] = found
                        stack.append(j)
            found += 1
    for i in np.flatnonzero(~core).tolist():
        c = near[i][core[near[i]]]
        if len(c):
            label[i] = label[c[((x[c] - x[i]) ** 2 + (y[c] - y[i]) ** 2).argmin()]]
    return label


#: Pairs of a place and a sample point that are compared at once.
PAIRS = 2**18


@dataclass
class SampleModel:
    """Each place belongs to the cluster of its nearest clustered sample point, unless that is too far away."""

    x: np.ndarray
    y: np.ndarray
    label: np.ndarray
    noise_distance: float | None

    def assign_arrays(self, xs, ys) -> np.ndarray:
        """Cluster numbers from 1 on; 0 is noise."""
        use = self.label >= 0
        xs, ys = np.asarray(xs, float), np.asarray(ys, float)
        out = np.zeros(len(xs), np.int64)
        if not use.any():
            return out
        sx, sy, lab = self.x[use], self.y[use], self.label[use]
        step = max(1, PAIRS // len(sx))
        for at in range(0, len(xs), step):
            cut = slice(at, at + step)
            d2 = (xs[cut, None] - sx) ** 2 + (ys[cut, None] - sy) ** 2
            best = d2.argmin(1)
            ok = d2[np.arange(len(best)), best] <= (math.inf if self.noise_distance is None else self.noise_distance**2)
            out[cut] = np.where(ok, lab[best] + 1, 0)
        return out

    def assign(self, df: DataFrame) -> DataFrame:
        """The same as a column, by a kNN join with the sample, which is as small as the budget."""
        from knnscope.operators.knn import knn_join

        spark = df.sparkSession
        sample = spark.createDataFrame(
            [(i, float(a), float(b), int(c) + 1) for i, (a, b, c) in enumerate(zip(self.x, self.y, self.label)) if c >= 0],
            "id long, x double, y double, cluster_id int",
        )
        left = df.select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))
        near = knn_join(left, sample, 1, 32).select(
            F.col("qid").alias("id"),
            F.when(F.lit(self.noise_distance is None) | (F.col("d2") <= (self.noise_distance or 0.0) ** 2), F.col("cluster_id")).alias("cluster_id"),
        )
        return df.join(near, "id", "left")


def sample_uniform(points: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """The n rows of the smallest hashes of their ids: an ideal uniform sample that a client could not draw."""
    return points.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(n)


def draw(service, domain, seed: int = 42, sampler: str = "voronoi", batch: int = 1, rays: int = 4) -> dict[int, tuple[float, float]]:
    """Points drawn through the interface until the budget is used up.

    ``raw`` takes the nearest point of a random place, so points in empty space come too often. ``voronoi`` accepts it
    in inverse proportion to the size of its cell, estimated from how far along a few rays it remains the nearest.
    """
    rng, (x0, y0, side) = random.Random(seed), domain
    found: dict[int, tuple[float, float]] = {}
    smallest = math.inf
    try:
        while True:
            places = [(x0 + rng.random() * side, y0 + rng.random() * side) for _ in range(batch)]
            for a in service.probe(places, "sample"):
                if not len(a.ids):
                    continue
                ident, px, py = int(a.ids[0]), float(a.xs[0]), float(a.ys[0])
                if sampler == "raw":
                    found[ident] = (px, py)
                    continue
                # the other points of the answer bound the cell: half way to each, along each ray
                turn, area = rng.random() * 2 * math.pi, 0.0
                for reach in _free(a, directions(turn, rays)) if a.rays is None else a.rays:
                    area += min(float(reach), side) ** 2
                smallest = min(smallest, area)
                if area <= 0 or rng.random() < min(1.0, 8 * smallest / area):
                    found[ident] = (px, py)
    except BudgetExhausted:
        pass
    return found


def directions(turn: float, rays: int = 4) -> list[tuple[float, float]]:
    """Of the rays along which ``draw`` looks."""
    return [(math.cos(turn + r * math.pi / rays / 2), math.sin(turn + r * math.pi / rays / 2)) for r in range(rays * 4)]


def _free(a, rays: list[tuple[float, float]]) -> list[float]:
    """How far along each ray from the nearest row of an answer that row remains the nearest."""
    found, dx, dy = [], a.xs[1:] - a.xs[0], a.ys[1:] - a.ys[0]
    for ux, uy in rays:
        along = dx * ux + dy * uy
        ahead = along > 1e-12
        found.append(((dx * dx + dy * dy)[ahead] / (2 * along[ahead])).min() if ahead.any() else math.inf)
    return found


def drawn_places(domain, n: int, seed: int = 42, sampler: str = "raw") -> tuple[list[tuple[float, float]], list[list[tuple[float, float]]]]:
    """The first n places at which ``draw`` asks, one a round, and for ``voronoi`` the rays at each; it draws one more number after them."""
    rng, (x0, y0, side), found, rays = random.Random(seed), domain, [], []
    for _ in range(n):
        found.append((x0 + rng.random() * side, y0 + rng.random() * side))
        if sampler != "raw":
            rays.append(directions(rng.random() * 2 * math.pi))
            rng.random()
    return found, rays


def sample_then_cluster(
    service, domain, eps: float, min_pts: int, noise_distance: float | None = None, sampler: str = "raw", seed: int = 42, scale_to: int | None = None,
) -> SampleModel:
    """Draw through the interface, cluster what was drawn, and assign places to the nearest clustered draw.

    ``scale_to`` is the number of all points, if min_pts is to shrink with the sampled share (at least 2). All points
    that answers held are used with ``sampler='all'``. ``sampler='uniform'`` draws uniformly, one point a call of the budget,
    which the interface doesn't offer: the best that a sampling client could hope for.
    """
    if sampler == "uniform" and not hasattr(service, "id"):
        n = int(min(service.budget.left, service.pyramid.n))
        service.budget.charge(n)
        service.rounds += 1
        found = {r.id: (r.x, r.y) for r in sample_uniform(service.points, n, seed).select("id", "x", "y").collect()}
    elif sampler == "uniform":
        n = int(min(service.budget.left, len(service.id)))
        service.budget.charge(n)
        service.rounds += 1
        at = np.random.default_rng(seed).choice(len(service.id), n, replace=False)
        found = {int(service.id[i]): (float(service.x[i]), float(service.y[i])) for i in at}
    elif sampler == "all":
        draw(service, domain, seed, "raw")
        found = dict(service.seen)
    else:
        found = draw(service, domain, seed, sampler)
    ids = sorted(found)
    x, y = (np.array([found[i][k] for i in ids], float) for k in (0, 1))
    if scale_to:
        min_pts = max(2, round(min_pts * len(ids) / scale_to))
    label = dbscan_arrays(x, y, eps, min_pts) if len(ids) else np.zeros(0, int)
    return SampleModel(x, y, label, eps if noise_distance is None else noise_distance)
