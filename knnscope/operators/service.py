"""The only way to the points for a client: k nearest neighbours of a place, under a budget, every call in a ledger."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from knnscope.io import materialize
from knnscope.operators import knn


class BudgetExhausted(RuntimeError):
    """No call is left."""


@dataclass
class Budget:
    max_calls: float = math.inf
    used: int = 0

    def charge(self, n: int = 1) -> None:
        if self.used + n > self.max_calls:
            raise BudgetExhausted(f"{self.used} of {self.max_calls} calls are used")
        self.used += n

    @property
    def left(self) -> float:
        return self.max_calls - self.used


@dataclass
class RateLimit:
    """So many calls per interval, as services quote them (10,000 a day; 150 an hour)."""

    calls: int
    seconds: float

    def elapsed(self, n: int) -> float:
        """Least seconds after which the n-th call may be made, if calls go out as soon as they may."""
        return 0.0 if n <= self.calls else math.ceil(n / self.calls - 1) * self.seconds


@dataclass
class Answer:
    """The rows nearest to (x, y), nearest first. Nothing closer than ``radius`` is missing (an open ball).

    A counted answer holds cells in place of rows: ``xs`` and ``ys`` are their centres, ``weight`` says how many of the rows lie
    in each, ``reaches`` the distances to some of the rows by rank, and ``ids`` and ``dist`` are empty.
    A drawn answer holds its nearest row alone, and as ``rays`` how far that row is nearer than all others of the answer along each ray.
    """

    x: float
    y: float
    ids: np.ndarray
    xs: np.ndarray
    ys: np.ndarray
    dist: np.ndarray
    radius: float
    weight: np.ndarray | None = None
    reaches: dict | None = None
    rays: np.ndarray | None = None

    @property
    def n(self) -> int:
        return len(self.dist) if self.weight is None else int(self.weight.sum())

    @property
    def weights(self) -> np.ndarray:
        return np.ones(len(self.xs), np.int64) if self.weight is None else self.weight

    def reach(self, rank: int) -> float:
        """The distance to the row of that rank; infinite if there are fewer."""
        if self.n < rank:
            return math.inf
        return float(self.dist[rank - 1]) if self.weight is None else self.reaches[rank]


#: Fixed presets after the services described: k, budget, rate and what a filter may name.
PRESETS = {
    "listings_filtered": {"k": 10, "filters": ("price", "pri", "reg")},
    "listings_plain": {"k": 200, "filters": ()},
    "places": {"k": 20, "filters": ()},
    "map_day": {"k": 60, "rate": RateLimit(10_000, 86_400.0), "filters": ()},
    "posts_hour": {"k": 50, "rate": RateLimit(150, 3_600.0), "filters": ()},
}


LEDGER = "qid long, round int, purpose string, node string, qx double, qy double, k int, radius double, n_new int"


@dataclass
class _Service:
    k: int
    budget: Budget = field(default_factory=Budget)
    rate: RateLimit | None = None
    calls: list[dict] = field(default_factory=list)
    rounds: int = 0
    seen: dict[int, tuple[float, float]] = field(default_factory=dict)

    def probe(self, places: list[tuple[float, float]], purpose="probe") -> list[Answer]:
        """Answers to as many of ``places`` as the budget still pays for, in order; all of them are one round.

        ``purpose`` is one word for all, or a list. Raises BudgetExhausted if nothing can be asked.
        """
        purposes = [purpose] * len(places) if isinstance(purpose, str) else list(purpose)
        n = int(min(len(places), self.budget.left))
        if places and not n:
            raise BudgetExhausted(f"{self.budget.used} of {self.budget.max_calls} calls are used")
        self.budget.charge(n)
        self.rounds += 1
        answers = self._answer(places[:n])
        for a, p in zip(answers, purposes):
            new = [i for i in a.ids.tolist() if i not in self.seen] if a.weight is None and a.rays is None else None
            for i, x, y in zip(a.ids.tolist(), a.xs.tolist(), a.ys.tolist()):
                self.seen[i] = (x, y)
            self.calls.append({
                "qid": len(self.calls), "round": self.rounds, "purpose": p, "node": None, "qx": float(a.x), "qy": float(a.y),
                "k": self.k, "radius": a.radius if math.isfinite(a.radius) else None, "n_new": None if new is None else len(new),
            })
        return answers

    def _certified(self, x, y, ids, xs, ys) -> Answer:
        dist = np.hypot(np.asarray(xs, float) - x, np.asarray(ys, float) - y)
        radius = math.inf if len(ids) < self.k else float(dist[-1])
        return Answer(x, y, np.asarray(ids), np.asarray(xs, float), np.asarray(ys, float), dist, radius)

    def ledger(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(c.values()) for c in self.calls], LEDGER)

    def cost_report(self, spark: SparkSession) -> DataFrame:
        """Calls, rounds and new points by purpose and kind of node, and the seconds that a rate limit makes of them."""
        seconds = float(self.simulated_seconds())
        grouped = self.ledger(spark).groupBy("purpose", "node").agg(
            F.count(F.lit(1)).alias("calls"), F.countDistinct("round").alias("rounds"), F.sum("n_new").alias("new_points")
        )
        return grouped.withColumn("all_seconds", F.lit(seconds))

    def save_ledger(self, spark: SparkSession, path: str) -> None:
        """Append this service's calls to a ledger table."""
        self.ledger(spark).coalesce(1).write.mode("append").parquet(path)

    def cost_by_purpose(self) -> dict[str, int]:
        found: dict[str, int] = {}
        for c in self.calls:
            found[c["purpose"]] = found.get(c["purpose"], 0) + 1
        return found

    def cost_by_node(self) -> dict[str, int]:
        """Calls whose cell was split, and those whose cell stayed a leaf."""
        found: dict[str, int] = {}
        for c in self.calls:
            if c["node"]:
                found[c["node"]] = found.get(c["node"], 0) + 1
        return found

    def simulated_seconds(self) -> float:
        return self.rate.elapsed(self.budget.used) if self.rate else 0.0


class KnnService(_Service):
    """Over a DataFrame ``(id, x, y, ...)`` of any size; each round of probes is one job."""

    def __init__(self, points: DataFrame, k: int, budget: Budget | None = None, rate: RateLimit | None = None, where=None, pyramid=None):
        super().__init__(k, budget or Budget(), rate)
        self.points = points if where is None else points.filter(where)  # below the join, so it reaches the scan
        self.pyramid = pyramid or knn.Pyramid(self.points)

    @classmethod
    def preset(cls, name: str, points: DataFrame, budget: Budget | None = None, where=None) -> KnnService:
        p = PRESETS[name]
        if where is not None and not p["filters"]:
            raise ValueError(f"{name} takes no filter")
        return cls(points, p["k"], budget, p.get("rate"), where)

    def answers(self, places: list[tuple[float, float]]) -> DataFrame:
        """``qid, rank, d2, id, x, y`` for a round of probes, as a table."""
        return knn.grid_join(self.points, self.pyramid, [(i, x, y) for i, (x, y) in enumerate(places)], self.k)

    def _answer(self, places):
        found = self.answers(places).select("qid", "rank", "id", "x", "y").toArrow()  # k rows for each probe
        qid, rank, ids, xs, ys = (found.column(c).to_numpy() for c in found.column_names)
        order = np.lexsort((rank, qid))
        qid, ids, xs, ys = qid[order], ids[order], xs[order], ys[order]
        ends = np.searchsorted(qid, np.arange(len(places) + 1))
        return [self._certified(x, y, ids[a:b], xs[a:b], ys[a:b]) for (x, y), a, b in zip(places, ends, ends[1:])]


#: Rows of answers that come to the driver at once when they are looked up beforehand.
ROWS = 1_000_000


class PreparedKnnService(KnnService):
    """The same answers for a client that asks at places known beforehand (centres of a line's or a tree's cells): the first call
    looks up ``places`` in one job, and what isn't asked isn't charged. ``book`` may be shared by the runs over one set of points.
    """

    def __init__(self, points: DataFrame, k: int, places, budget: Budget | None = None, pyramid=None, book: dict | None = None):
        super().__init__(points, k, budget, pyramid=pyramid or knn.Pyramid(points, k=k))
        self.places, self.book = list(places), {} if book is None else book

    def _answer(self, places):
        if any(p not in self.book for p in places):
            missing = list(dict.fromkeys(p for p in (places if self.book else [*places, *self.places]) if p not in self.book))
            self.book.update(zip(missing, self._look_up(missing)))
        return [self.book[p] for p in places]

    def _look_up(self, places) -> list[Answer]:
        step = max(1, ROWS // self.k)
        return [a for at in range(0, len(places), step) for a in super(PreparedKnnService, self)._answer(places[at : at + step])]


class CountedKnnService(PreparedKnnService):
    """The same for k in proportion to the points: an answer reaches the client as counts by the cells of ``cells = (x0, y0, side)``,
    which are all that a client of these cells uses, so the driver holds places and cells, never rows.

    ``ranks`` are those whose distances the client compares, k among them. What the calls have shown is the table ``seen_in``.
    """

    def __init__(self, points, k, places, cells, ranks=(), budget=None, pyramid=None, book=None):
        super().__init__(points, k, places, budget, pyramid, book)
        self.cells, self.ranks = cells, sorted({k, *ranks})
        if self.ranks[-1] > k:
            raise ValueError("an answer holds k rows")

    def _look_up(self, places):
        x0, y0, side = self.cells
        found = knn.counted(self.points, self.pyramid, [(i, x, y) for i, (x, y) in enumerate(places)], self.ranks, self.cells)
        out = []
        for (x, y), (ends, i, j, n) in zip(places, found):
            radius = math.inf if n.sum() < self.k else ends[self.k][0]
            none = np.zeros(0)
            a = Answer(x, y, none.astype(np.int64), x0 + (i + 0.5) * side, y0 + (j + 0.5) * side, none, radius, n, {r: e[0] for r, e in ends.items()})
            a.last = ends[min(self.k, max(ends, default=self.k))] if ends else None
            out.append(a)
        return out

    def seen_in(self, points: DataFrame) -> DataFrame:
        """The rows of ``points`` that the calls have returned."""
        asked = {(c["qx"], c["qy"]) for c in self.calls}
        balls = [(i, *p, *(self.book[p].last or (math.inf, 0, math.inf))) for i, p in enumerate(sorted(asked))]
        return knn.inside(points, self.pyramid, balls)


class DrawnKnnService(PreparedKnnService):
    """The same for k in proportion to the points and a client that looks along rays: of an answer the driver gets the nearest row and,
    for each ray from there, how far that row is nearer than the others, which is all that such a client uses; the rows stay where they are.

    ``rays`` are the directions ``(ux, uy)`` at each of ``places``, equally many.
    """

    def __init__(self, points, k, places, rays, budget=None, pyramid=None, book=None):
        super().__init__(points, k, places, budget, pyramid, book)
        self.rays = dict(zip(self.places, rays))

    def _look_up(self, places):
        rays, last = [self.rays[p] for p in places], min(self.k, self.pyramid.n)
        asked = [(i, *([float(v) for v in axis] for axis in zip(*r))) for i, r in enumerate(rays)]
        asked = F.broadcast(self.points.sparkSession.createDataFrame(asked, "qid long, ux array<double>, uy array<double>"))
        order = Window.partitionBy("qid").orderBy("d2", "id")
        rows = self.answers(places).withColumns({f"p{c}": F.first(c).over(order) for c in "xy"}).join(asked, "qid")
        dx, dy, of = F.col("x") - F.col("px"), F.col("y") - F.col("py"), lambda rank, c: F.min(F.when(F.col("rank") == rank, F.col(c)))
        free = []
        for r in range(len(rays[0])):
            along = dx * F.col("ux")[r] + dy * F.col("uy")[r]
            free.append(F.min(F.when((F.col("rank") > 1) & (along > 1e-12), (dx * dx + dy * dy) / (2 * along))))
        found = rows.groupBy("qid").agg(of(1, "id"), of(1, "x"), of(1, "y"), of(last, "x"), of(last, "y"), *free).toArrow()  # one row for each place
        held = dict(zip(found.column(0).to_pylist(), zip(*(found.column(c).to_pylist() for c in range(1, found.num_columns)))))
        return [self._drawn(x, y, held.get(i)) for i, (x, y) in enumerate(places)]

    def _drawn(self, x, y, row) -> Answer:
        if row is None:
            return self._certified(x, y, np.zeros(0, np.int64), [], [])
        ident, px, py, lx, ly, *free = row
        radius = math.inf if self.pyramid.n < self.k else float(np.hypot(lx - x, ly - y))
        near = Answer(x, y, np.array([ident]), np.array([px]), np.array([py]), np.hypot([px - x], [py - y]), radius)
        near.rays = np.array([math.inf if v is None else v for v in free])
        return near


class MemoryKnnService(_Service):
    """The same answers from arrays, for benchmark sets of at most ``LIMIT`` points, so that sweeps of many sequential
    runs need no job for each round."""

    LIMIT = 1_000_000

    def __init__(self, points, k: int, budget: Budget | None = None, rate: RateLimit | None = None, where=None):
        super().__init__(k, budget or Budget(), rate)
        if isinstance(points, DataFrame):
            points = points if where is None else points.filter(where)
            rows = points.select("id", "x", "y").limit(self.LIMIT + 1).toPandas()
            points = tuple(rows[c].to_numpy() for c in ("id", "x", "y"))
        self.id, self.x, self.y = (np.asarray(v) for v in points)
        if len(self.id) > self.LIMIT:
            raise ValueError(f"more than {self.LIMIT} points: use KnnService")

    def _answer(self, places):
        out = []
        for x, y in places:
            d2 = (self.x - x) * (self.x - x) + (self.y - y) * (self.y - y)
            n = min(self.k, len(d2))
            if n and n < len(d2):
                near = np.flatnonzero(d2 <= np.partition(d2, n - 1)[n - 1])
            else:
                near = np.arange(len(d2))
            near = near[np.lexsort((self.id[near], d2[near]))][:n]
            out.append(self._certified(x, y, self.id[near], self.x[near], self.y[near]))
        return out


def is_core(service: _Service, x: float, y: float, eps: float, min_pts: int) -> bool:
    """Whether at least ``min_pts`` points lie within ``eps`` of a point there; one call if the service returns enough."""
    if min_pts <= service.k:
        a = service.probe([(x, y)], "core")[0]
        return len(a.dist) >= min_pts and bool(a.dist[min_pts - 1] <= eps)
    near = crawl_box(service, (x - eps, y - eps, x + eps, y + eps))
    return sum((px - x) ** 2 + (py - y) ** 2 <= eps * eps for px, py in near.values()) >= min_pts


def crawl_box(service: _Service, box: tuple[float, float, float, float], purpose: str = "crawl") -> dict[int, tuple[float, float]]:
    """All points in a closed box: ask at its centre, and quarter it unless the answer certainly covers it.

    All boxes of one depth are one round.
    """
    found: dict[int, tuple[float, float]] = {}
    frontier = [box]
    while frontier:
        answers = service.probe([((a + c) / 2, (b + d) / 2) for a, b, c, d in frontier], purpose)
        deeper = []
        for (a, b, c, d), answer in zip(frontier, answers):
            for i, x, y in zip(answer.ids.tolist(), answer.xs.tolist(), answer.ys.tolist()):
                if box[0] <= x <= box[2] and box[1] <= y <= box[3]:
                    found[i] = (x, y)
            half = math.hypot(c - a, d - b) / 2
            # the ball is open; and boxes smaller than rounding hold co-located points that no call can tell apart
            if answer.radius <= half and half > 1e-9:
                mx, my = (a + c) / 2, (b + d) / 2
                deeper += [(a, b, mx, my), (mx, b, c, my), (a, my, mx, d), (mx, my, c, d)]
        if len(answers) < len(frontier):
            raise BudgetExhausted("the crawl is incomplete")
        frontier = deeper
    return found


def crawl_box_distributed(points: DataFrame, k: int, box: tuple[float, float, float, float]) -> DataFrame:
    """The ids of all points in a closed box, found as by ``crawl_box`` with answers of k rows; boxes and answers stay tables.

    Each depth is one round. An answer matters up to half a box's diagonal, so nothing beyond that round the box is looked at.
    """
    a, b, c, d = box
    out = math.hypot(c - a, d - b) / 2 * (1 + 1e-9)
    near = points.select("id", "x", "y").filter(F.col("x").between(a - out, c + out) & F.col("y").between(b - out, d + out))
    near = materialize(near, "crawl-points")
    pyramid = knn.Pyramid(near, min(knn.MOST, max(knn.GRID, round((near.count() / 4) ** 0.5))))
    radii = materialize(knn.radius_table(points.sparkSession, pyramid, k), "crawl-radii")
    frontier, depth, found = points.sparkSession.createDataFrame([(0, 0)], "i long, j long"), 0, None
    while True:
        w, h = (c - a) / 2**depth, (d - b) / 2**depth
        half = math.hypot(w, h) / 2
        probes = frontier.select(
            F.struct("i", "j").alias("qid"), (F.lit(a) + (F.col("i") + 0.5) * w).alias("qx"), (F.lit(b) + (F.col("j") + 0.5) * h).alias("qy")
        )
        inside = (F.col("x").between(a, c) & F.col("y").between(b, d)).alias("inside")
        answers = materialize(knn.knn_join(probes, near, k, pyramid=pyramid, radii=radii).select("qid", "d2", "id", inside), "crawl-answers")
        held = answers.filter("inside").select("id")
        found = held if found is None else found.unionByName(held)
        # the ball is open; and boxes smaller than rounding hold co-located points that no call can tell apart
        wide = answers.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("r2")).filter((F.col("n") >= k) & (F.sqrt("r2") <= half))
        if half <= 1e-9:
            break
        parts = wide.select("qid", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("part"))
        cut = parts.selectExpr("2 * qid.i + part % 2 AS i", "2 * qid.j + part div 2 AS j")
        frontier, depth = materialize(cut, "crawl-boxes"), depth + 1
        if frontier.isEmpty():
            break
    return found.distinct()
