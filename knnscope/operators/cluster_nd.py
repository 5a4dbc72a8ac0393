"""The budgeted clusterer in any number of dimensions: cells on a Z curve, refined where answers say they could be dense.

It is the two-dimensional method with 2^d children a node: the same pursuit runs on the line of leaves, a leaf is asked at its
centre, split if minPts points may lie in it, and mini-clusters are joined by the mean of their l smallest distances. The
product is again a function of places, a table of key ranges.
"""

from __future__ import annotations

import bisect
import math
import random
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.functions.curves import z_column_nd
from knnscope.operators import merge as merging
from knnscope.operators.pursuit import Pursuit
from knnscope.operators.service import Budget, BudgetExhausted


@dataclass
class AnswerNd:
    place: np.ndarray
    ids: np.ndarray
    points: np.ndarray
    dist: np.ndarray
    radius: float


class KnnServiceNd:
    """k nearest neighbours of places in d dimensions, under a budget: ``points(id, v array<double>)`` of any size.

    A round of places is one job: they are broadcast, their number being bound by the budget, each task keeps the k nearest of its
    rows for every place, and the k nearest of those are the answer.
    """

    def __init__(self, points: DataFrame, k: int, budget: Budget | None = None):
        self.points, self.k, self.budget = points.select("id", "v"), k, budget or Budget()
        self.rounds, self.calls, self.seen = 0, [], {}

    def _answers(self, places: list) -> list[list[tuple]]:
        wanted = np.array(places, float)
        k = self.k

        def nearest(batches):
            import pandas as pd

            best: list = [None] * len(wanted)
            for batch in batches:
                batch = batch[[v is not None and len(v) == wanted.shape[1] for v in batch["v"]]]
                if not len(batch):
                    continue
                ids, x = batch["id"].to_numpy(), np.stack(batch["v"].to_numpy()).astype(float)
                ok = np.isfinite(x).all(1)
                ids, x = ids[ok], x[ok]
                for q, place in enumerate(wanted):
                    d2 = ((x - place) ** 2).sum(1)
                    at = np.lexsort((ids, d2))[:k]
                    rows = [(float(d2[i]), int(ids[i]), x[i].tolist()) for i in at]
                    best[q] = sorted((best[q] or []) + rows)[:k]
            out = [(q, d, i, v) for q, rows in enumerate(best) for d, i, v in rows or []]
            yield pd.DataFrame(out, columns=["qid", "d2", "id", "v"])

        found: list[list[tuple]] = [[] for _ in places]
        part = self.points.mapInPandas(nearest, "qid int, d2 double, id long, v array<double>")
        ranked = part.selectExpr("*", "row_number() over (partition by qid order by d2, id) AS r").filter(F.col("r") <= k)
        for r in ranked.collect():  # k rows a call
            found[r.qid].append((r.d2, r.id, r.v))
        return found

    def probe(self, places: list, purpose="probe") -> list[AnswerNd]:
        purposes = [purpose] * len(places) if isinstance(purpose, str) else list(purpose)
        n = int(min(len(places), self.budget.left))
        if places and not n:
            raise BudgetExhausted(f"{self.budget.used} of {self.budget.max_calls} calls are used")
        self.budget.charge(n)
        self.rounds += 1
        out = []
        for place, rows, what in zip(places[:n], self._answers(places[:n]), purposes):
            rows.sort(key=lambda r: r[:2])
            points = np.array([r[2] for r in rows], float).reshape(len(rows), len(place))
            dist = np.sqrt([r[0] for r in rows])
            radius = math.inf if len(rows) < self.k else float(dist[-1])
            out.append(AnswerNd(np.array(place), np.array([r[1] for r in rows], np.int64), points, dist, radius))
            self.seen.update((int(r[1]), tuple(r[2])) for r in rows)
            self.calls.append({"purpose": what, "node": None})
        return out


class MemoryKnnServiceNd(KnnServiceNd):
    """The same answers from arrays, for sets that one machine holds."""

    def __init__(self, ids: np.ndarray, points: np.ndarray, k: int, budget: Budget | None = None):
        self.ids, self.x = np.asarray(ids), np.asarray(points, float)
        self.k, self.budget, self.rounds, self.calls, self.seen = k, budget or Budget(), 0, [], {}

    def _answers(self, places: list) -> list[list[tuple]]:
        out = []
        for place in places:
            d2 = ((self.x - np.array(place)) ** 2).sum(1)
            at = np.lexsort((self.ids, d2))[: self.k]
            out.append([(float(d2[i]), int(self.ids[i]), self.x[i].tolist()) for i in at])
        return out


class ZTree:
    """Leaves over the cube ``low + [0, side)^d``, each named by its first key at the finest level; see ``CurveTree``."""

    def __init__(self, low, side: float, dims: int, levels: int, min_pts: int, infer: bool = True):
        self.low, self.side, self.dims, self.levels, self.min_pts, self.infer = np.array(low, float), side, dims, levels, min_pts, infer
        self.version = self.contradictions = self.internal = 0
        self.keys: list[int] = []
        self.level: dict[int, int] = {}
        self.state: dict[int, bool] = {}
        self.sparse: list[int] = []
        self._add(range(1 << dims), 1)

    def _cell(self, prefix: int, level: int) -> np.ndarray:
        """Numbers of a cell from its key: bits of the dimensions in turn, the first one highest."""
        cell = np.zeros(self.dims, np.int64)
        for b in range(level):
            for d in range(self.dims):
                cell[d] |= (prefix >> (b * self.dims + self.dims - 1 - d) & 1) << b
        return cell

    def _add(self, prefixes, level: int) -> None:
        span = 1 << (self.dims * (self.levels - level))
        for p in prefixes:
            self.level[p * span] = level
            bisect.insort(self.keys, p * span)

    def box(self, key: int) -> tuple[np.ndarray, float]:
        """Lowest corner and side of a leaf."""
        level = self.level[key]
        side = self.side / (1 << level)
        return self.low + self._cell(key >> (self.dims * (self.levels - level)), level) * side, side

    def size(self) -> int:
        return len(self.keys)

    def at(self, rank: int) -> int:
        return self.keys[rank]

    def rank(self, key: int) -> int:
        return bisect.bisect_right(self.keys, key) - 1

    def current(self, key: int) -> int:
        return self.keys[self.rank(key)]

    def place(self, key: int) -> tuple:
        corner, side = self.box(key)
        return tuple((corner + side / 2).tolist())

    def known(self, key: int) -> bool | None:
        return self.state.get(key)

    def last_key(self, key: int) -> int:
        return key + (1 << (self.dims * (self.levels - self.level[key]))) - 1

    def locate(self, points: np.ndarray) -> np.ndarray:
        """Keys of places; -1 outside the cube."""
        n = 1 << self.levels
        cells = np.floor((points - self.low) / (self.side / n)).astype(np.int64).reshape(-1, self.dims)
        ok = ((cells >= 0) & (cells < n)).all(1)
        keys = np.zeros(len(cells), np.int64)
        for b in range(self.levels):
            for d in range(self.dims):
                keys |= (cells[:, d] >> b & 1) << (b * self.dims + self.dims - 1 - d)
        return np.where(ok, keys, -1)

    def mark(self, key: int, dense: bool) -> None:
        old = self.state.get(key)
        if old is None:
            self.state[key] = dense
            if not dense:
                bisect.insort(self.sparse, key)
        elif old != dense:
            self.contradictions += 1

    def learn(self, key: int, answer: AnswerNd) -> str:
        corner, side = self.box(key)
        may = len(answer.dist) >= self.min_pts and answer.dist[self.min_pts - 1] <= side * math.sqrt(self.dims) / 2
        node = "leaf"
        if self.level[key] < self.levels and may:
            level = self.level.pop(key) + 1
            span = 1 << (self.dims * (self.levels - level))
            self.keys.pop(self.rank(key))
            self._add(range(key // span, key // span + (1 << self.dims)), level)
            self.internal += 1
            self.version += 1
            node = "split"
        elif self.level[key] < self.levels:
            self.mark(key, False)
        else:
            inside = ((answer.points >= corner) & (answer.points < corner + side)).all(1) if len(answer.points) else np.zeros(0, bool)
            self.mark(key, int(inside.sum()) >= self.min_pts)
        if self.infer:
            self._infer(answer)
        return node

    def _infer(self, answer: AnswerNd) -> None:
        """Leaves wholly inside the certified ball hold exactly the points of the answer."""
        keys = np.array(self.keys)
        own = self.locate(answer.points) if len(answer.points) else np.zeros(0, np.int64)
        counts = np.bincount(np.searchsorted(keys, own[own >= 0], side="right") - 1, minlength=len(keys))
        for i, key in enumerate(self.keys):
            if key not in self.state:
                corner, side = self.box(key)
                far = np.sqrt((np.maximum(np.abs(corner - answer.place), np.abs(corner + side - answer.place)) ** 2).sum())
                dense = bool(counts[i] >= self.min_pts)
                if far < answer.radius and (not dense or self.level[key] == self.levels):
                    self.mark(key, dense)

    def beyond(self, key: int, answer: AnswerNd, toward: int) -> int | None:
        own = self.locate(answer.points) if len(answer.points) else np.zeros(0, np.int64)
        r = self.rank(key)
        ranks = [x for x in (self.rank(k) for k in own[own >= 0].tolist()) if (x - r) * toward > 0]
        return self.keys[min(ranks) if toward > 0 else max(ranks)] if ranks else None

    def first_open(self, key: int, answer: AnswerNd, toward: int) -> int | None:
        r = self.rank(key) + toward
        while 0 <= r < len(self.keys) and self.state.get(self.keys[r]) is False:
            r += toward
        return self.keys[r] if 0 <= r < len(self.keys) else None

    def nearest_sparse(self, key: int, toward: int) -> int | None:
        i = bisect.bisect_left(self.sparse, key)
        if toward > 0:
            return self.sparse[i] if i < len(self.sparse) else None
        return self.sparse[i - 1] if i else None

    def random_unknown(self, rng: random.Random) -> int | None:
        left = [k for k in self.keys if k not in self.state]
        return rng.choice(left) if left else None


@dataclass
class ClusterModelNd:
    """Ranges of Z keys and their clusters, numbered from 1; places outside the cube and in no range are noise."""

    low: list[float]
    side: float
    dims: int
    levels: int
    segments: list[tuple[int, int, int]]
    info: dict

    def assign(self, df: DataFrame, v: str = "v", name: str = "cluster_id") -> DataFrame:
        """``df`` with the cluster of each row's array ``v``: no shuffle, one array of as many ranges as calls paid for."""
        n, cell = 1 << self.levels, self.side / (1 << self.levels)
        cells = F.transform(
            F.zip_with(F.col(v).cast("array<double>"), F.array(*(F.lit(float(a)) for a in self.low)), lambda x, a: x - a),
            lambda x: F.floor(x / cell).cast("long"),
        )
        ok = (F.size(v) == self.dims) & F.coalesce(F.forall("_c", lambda c: (c >= 0) & (c < n)), F.lit(False))
        keyed = df.withColumn("_c", cells).withColumn("_k", F.when(ok, z_column_nd(F.col("_c"), self.dims, self.levels)))
        ranges = df.sparkSession.createDataFrame([tuple(map(int, s)) for s in self.segments] or [(-1, -1, 0)], "lo long, hi long, c int")
        listed = ranges.agg(F.array_sort(F.collect_list(F.struct("lo", "hi", "c"))).alias("_r"))
        mine = F.filter("_r", lambda r: (r["lo"] <= F.col("_k")) & (F.col("_k") <= r["hi"]))
        return keyed.crossJoin(F.broadcast(listed)).withColumn(name, F.get(mine, 0)["c"]).select(*df.columns, name)


def cluster_nd(
    service, low, side: float, dims: int, levels: int, min_pts: int, merge_threshold: float, n_check: int = 5, strategy: str = "auto",
    l: int | None = None, seeds_per_round: int = 1, seed: int = 42, infer: bool = True,  # noqa: E741
) -> ClusterModelNd:
    """Mini-clusters on the Z curve until the budget is used up, merged by l-distances."""
    tree = ZTree(low, side, dims, levels, min_pts, infer)
    found = Pursuit(tree, service, n_check, strategy, seeds_per_round, seed).run()
    joined: list[tuple[int, int]] = []
    for lo, hi in sorted((lo, tree.last_key(tree.current(hi))) for lo, hi in found.segments):
        if joined and lo <= joined[-1][1]:
            joined[-1] = (joined[-1][0], max(joined[-1][1], hi))
        else:
            joined.append((lo, hi))
    places = np.array([service.seen[i] for i in sorted(service.seen)], float).reshape(-1, dims)
    keys = tree.locate(places) if len(places) else np.zeros(0, np.int64)
    observed = {i: places[(keys >= lo) & (keys <= hi)] for i, (lo, hi) in enumerate(joined)}
    _, edges = merging.top_l(observed, l or max(1, min_pts // 2), merge_threshold)
    roots = merging.union_find(range(len(joined)), edges)
    number = {r: n for n, r in enumerate(sorted(set(roots.values())), 1)}
    info = {"calls": service.budget.used, "rounds": service.rounds, "leaves": tree.size(), "internal": tree.internal, "observed": len(places)}
    return ClusterModelNd(list(map(float, low)), side, dims, levels, [(lo, hi, number[roots[i]]) for i, (lo, hi) in enumerate(joined)], info)
