"""Exact k nearest neighbours of many probes in one job.

A histogram of the points on a coarse grid gives each probe a radius that certainly holds k points; the cells that the
radius touches are the probe's candidates, joined by equality on the cell. No pair of a probe and a point outside these
cells is ever formed, and ranking sees only pairs within the radius. Distances are compared as squares, ties by id.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Least and most cells along each side of the histogram; its size, at most MOST^2 numbers, is what reaches the driver.
GRID, MOST = 128, 1024
#: Points of an average cell aimed at.
AIM = 32


class Pyramid:
    """Counts of points on a grid over their bounding square, with prefix sums for counts of blocks."""

    def __init__(self, points: DataFrame, grid: int | None = None, k: int = 1):
        box = points.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y"), F.count(F.lit(1))).first()
        self.n = box[4]
        # for large k the cells are larger, so that a ball touches few of them
        aim, least = (AIM, GRID) if k <= 16 * AIM else (k / 8, GRID // 4)
        self.grid = grid = grid or min(MOST, max(least, round((self.n / aim) ** 0.5)))
        self.x0, self.y0 = (box[0], box[2]) if self.n else (0.0, 0.0)
        extent = max(box[1] - box[0], box[3] - box[2]) if self.n else 0.0
        self.side = (extent or 1.0) * (1 + 1e-9) / grid
        counts = np.zeros((grid, grid), np.int64)
        found = self.located(points).groupBy("cx", "cy").count().toArrow()
        cx, cy, n = (found.column(c).to_numpy() for c in found.column_names)
        counts[cx, cy] = n
        self.sums = np.zeros((grid + 1, grid + 1), np.int64)
        self.sums[1:, 1:] = counts.cumsum(0).cumsum(1)

    def located(self, points: DataFrame) -> DataFrame:
        top = self.grid - 1
        for c, axis, low in (("cx", "x", self.x0), ("cy", "y", self.y0)):
            points = points.withColumn(c, F.least(F.lit(top), F.floor((F.col(axis) - F.lit(low)) / F.lit(self.side))).cast("int"))
        return points

    def radius(self, x: float, y: float, k: int) -> float:
        """A distance within which at least min(k, n) points lie."""
        g = self.grid
        cx = int(np.clip(np.floor((x - self.x0) / self.side), 0, g - 1))
        cy = int(np.clip(np.floor((y - self.y0) / self.side), 0, g - 1))
        need, lo, hi = min(k, self.n), 0, g

        def block(r):
            return max(0, cx - r), min(g, cx + r + 1), max(0, cy - r), min(g, cy + r + 1)

        while lo < hi:  # the smallest block that holds enough
            r = (lo + hi) // 2
            a, b, c, d = block(r)
            if self.sums[b, d] - self.sums[a, d] - self.sums[b, c] + self.sums[a, c] >= need:
                hi = r
            else:
                lo = r + 1
        a, b, c, d = block(lo)
        xs, ys = self.x0 + np.array([a, b]) * self.side, self.y0 + np.array([c, d]) * self.side
        return float(np.hypot(np.abs(xs - x).max(), np.abs(ys - y).max())) * (1 + 1e-9)

    def radii(self, k: int) -> np.ndarray:
        """``radius`` at the centre of every cell."""
        g = self.grid
        cx, cy = np.meshgrid(np.arange(g), np.arange(g), indexing="ij")
        need, lo, hi = min(k, self.n), np.zeros((g, g), np.int64), np.full((g, g), g)

        def block(r):
            return np.maximum(0, cx - r), np.minimum(g, cx + r + 1), np.maximum(0, cy - r), np.minimum(g, cy + r + 1)

        while (lo < hi).any():
            r = (lo + hi) // 2
            a, b, c, d = block(r)
            enough = self.sums[b, d] - self.sums[a, d] - self.sums[b, c] + self.sums[a, c] >= need
            lo, hi = np.where((lo < hi) & ~enough, r + 1, lo), np.where((lo < hi) & enough, r, hi)
        a, b, c, d = block(lo)
        far = [np.maximum(at + 0.5 - low, high - at - 0.5) * self.side for at, low, high in ((cx, a, b), (cy, c, d))]
        return np.hypot(*far) * (1 + 1e-9)

    def reached(self, x: float, y: float, k: int) -> tuple[float, np.ndarray, np.ndarray]:
        """A squared distance within which at least min(k, n) points lie, and ``cx, cy`` of the cells within it that hold points."""
        r, cut = self.radius(x, y, k), []
        for v, low in ((x, self.x0), (y, self.y0)):
            cut.append(np.clip(np.floor((np.array([v - r, v + r]) - low) / self.side), 0, self.grid - 1).astype(int))
        (a, b), (c, d) = cut
        part = np.diff(np.diff(self.sums[a : b + 2, c : d + 2], axis=0), axis=1)
        i, j = np.nonzero(part)
        near, far = _box_distances(x, y, self.x0, self.y0, self.side, i + a, j + c)
        r2 = min(r * r, _bound(far, part[i, j], min(k, self.n)))
        hit = near <= r2
        return r2, (i[hit] + a).astype(np.int32), (j[hit] + c).astype(np.int32)

    def touched(self, x: float, y: float, r: float) -> list[tuple[int, int]]:
        """The cells that a ball touches."""
        g = self.grid
        lo = np.clip(np.floor((np.array([x, y]) - r - [self.x0, self.y0]) / self.side), 0, g - 1).astype(int)
        hi = np.clip(np.floor((np.array([x, y]) + r - [self.x0, self.y0]) / self.side), 0, g - 1).astype(int)
        found = []
        for cx in range(lo[0], hi[0] + 1):
            for cy in range(lo[1], hi[1] + 1):
                left, low = self.x0 + cx * self.side, self.y0 + cy * self.side
                dx, dy = max(left - x, 0, x - left - self.side), max(low - y, 0, y - low - self.side)
                if dx * dx + dy * dy <= r * r:
                    found.append((cx, cy))
        return found


def ranked(pairs: DataFrame, k: int) -> DataFrame:
    """The first k of each probe by squared distance, then id; Spark keeps only the first k per group before shuffling."""
    order = Window.partitionBy("qid").orderBy("d2", "id")
    return pairs.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def with_distance(pairs: DataFrame) -> DataFrame:
    dx, dy = F.col("x") - F.col("qx"), F.col("y") - F.col("qy")
    return pairs.withColumn("d2", dx * dx + dy * dy)


def brute(points: DataFrame, probes: DataFrame, k: int) -> DataFrame:
    """``qid, rank, d2, id, ...`` by comparing all points with all probes; for tests and small inputs."""
    return ranked(with_distance(points.crossJoin(F.broadcast(probes))), k)


#: Pairs that are all compared.
PAIRS = 1_000_000_000


def brute_or_join(points: DataFrame, probes: DataFrame, k: int) -> DataFrame:
    """As ``brute``; where all pairs are too many to compare, the join by cells gives the same rows."""
    few = points.count() * probes.count() <= PAIRS
    return brute(points, probes, k) if few else knn_join(probes, points, k)


def grid_join(points: DataFrame, pyramid: Pyramid, probes: list[tuple[int, float, float]], k: int, columns=("id", "x", "y")) -> DataFrame:
    """As ``brute``, for a list of ``(qid, qx, qy)`` that a driver holds; the list's size is its caller's budget."""
    return ranked(_candidates(points, pyramid, probes, k, columns).drop("r2"), k)


def _candidates(points: DataFrame, pyramid: Pyramid, probes, k: int, columns=("id", "x", "y")) -> DataFrame:
    """``qid, qx, qy, r2, d2`` and the columns of all rows within the radius that certainly holds a probe's k nearest."""
    spark, each = points.sparkSession, [pyramid.reached(qx, qy, k) for _, qx, qy in probes]
    table = [(q, qid, float(qx), float(qy), r[0]) for q, ((qid, qx, qy), r) in enumerate(zip(probes, each))]
    asked = F.broadcast(spark.createDataFrame(table, "q int, qid long, qx double, qy double, r2 double"))
    wanted = F.broadcast(spark.createDataFrame(_by_cell([r[1:] for r in each], "cx", "cy")))
    located = pyramid.located(points.select(*columns)).join(wanted, ["cx", "cy"]).withColumn("q", F.explode("qs")).join(asked, "q")
    return with_distance(located).filter(F.col("d2") <= F.col("r2")).drop("cx", "cy", "q", "qs")


def _by_cell(asked: list[tuple[np.ndarray, np.ndarray]], cx: str, cy: str):
    """Each cell that somebody asks once, with the list ``qs`` of the numbers of those who ask."""
    import pyarrow as pa

    none = np.zeros(0, np.int32)
    q = np.repeat(np.arange(len(asked), dtype=np.int32), [len(a[0]) for a in asked])
    x, y = (np.concatenate([none, *(a[c] for a in asked)]).astype(np.int32) for c in (0, 1))
    at = np.lexsort((y, x))
    q, x, y = q[at], x[at], y[at]
    first = np.flatnonzero(np.r_[len(q) > 0, (np.diff(x) != 0) | (np.diff(y) != 0)])
    lists = pa.ListArray.from_arrays(pa.array(np.r_[first, len(q)].astype(np.int32)), pa.array(q))
    return pa.table({cx: x[first], cy: y[first], "qs": lists})


#: Rings into which a probe's candidates are counted.
RINGS = 1024
#: Fine cells along each side of the points, and pairs of a fine cell and a probe that are shipped at once.
FINE, SHIPPED = 512, 1_000_000


class FineCounts:
    """Counts of points by cells ``cells = (x0, y0, side)`` cut into 2^m x 2^m, as fine as ``FINE`` cells along the points allow."""

    def __init__(self, points: DataFrame, pyramid: Pyramid, cells):
        self.x0, self.y0, side = cells
        extent = pyramid.side * pyramid.grid
        self.m = 0
        while extent * 2 ** (self.m + 1) <= FINE * side:
            self.m += 1
        self.side = side / 2**self.m  # by powers of two, so that fine cells nest exactly
        found = self.located(points).groupBy("fx", "fy").count().toArrow()
        fx, fy, n = (found.column(c).to_numpy() for c in found.column_names)
        self.low = fx.min(), fy.min()
        self.counts = np.zeros((fx.max() - self.low[0] + 1, fy.max() - self.low[1] + 1), np.int64)
        self.counts[fx - self.low[0], fy - self.low[1]] = n

    def located(self, points: DataFrame) -> DataFrame:
        cell = lambda c, o: F.floor((F.col(c) - F.lit(o)) / F.lit(self.side)).cast("int")
        return points.withColumns({"fx": cell("x", self.x0), "fy": cell("y", self.y0)})

    def around(self, x: float, y: float, r: float):
        """Of the cells near a ball that hold points: ``fx, fy``, counts, and squared distances to their nearest and farthest places."""
        cut = []
        for c, o, low, size in ((x, self.x0, self.low[0], self.counts.shape[0]), (y, self.y0, self.low[1], self.counts.shape[1])):
            lo, hi = (int(np.floor((v - o) / self.side)) - low for v in (c - r, c + r))
            cut.append(slice(max(0, lo - 1), min(size, max(0, hi + 2))))
        i, j = np.nonzero(part := self.counts[cut[0], cut[1]])
        n, i, j = part[i, j], i + cut[0].start + self.low[0], j + cut[1].start + self.low[1]
        return i, j, n, *_box_distances(x, y, self.x0, self.y0, self.side, i, j)


def _box_distances(x: float, y: float, x0: float, y0: float, side: float, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances to the nearest and farthest places of cells."""
    near, far = 0.0, 0.0
    for c, o, at in ((x, x0, i), (y, y0, j)):
        low = o + at * side - c
        near = near + np.maximum(0, np.maximum(low, -low - side)) ** 2
        far = far + np.maximum(np.abs(low), np.abs(low + side)) ** 2
    return near * (1 - 1e-9), far * (1 + 1e-9)


def _bound(by: np.ndarray, n: np.ndarray, rank: int) -> float:
    order = np.argsort(by, kind="stable")
    at = np.searchsorted(np.cumsum(n[order]), rank)
    return float(by[order[at]]) if at < len(by) else float("inf")


def counted(points: DataFrame, pyramid: Pyramid, probes: list[tuple[int, float, float]], ranks: list[int], cells) -> list[tuple]:
    """For each probe, in order, what its ``max(ranks)`` nearest rows are, without the rows: a dict of ``rank -> (distance, id, d2)``
    (the last row alone if there are fewer) and, as arrays, the cells ``i, j`` of ``cells = (x0, y0, side)`` with their numbers of rows.

    Counts by fine cells say between which distances a rank lies: cells within the lesser are counted whole, and only rows of the cells
    between are looked at. These are counted by rings, the rows of the rings that hold a rank give it exactly, and what is not
    beyond the last is counted by cells; nothing is sorted but these rings, and only counts reach the driver.
    """
    if not pyramid.n:
        return [({}, *(np.zeros(0, np.int64),) * 3) for _ in probes]
    ranks = sorted({min(r, pyramid.n) for r in ranks})
    fine, out, held, size = FineCounts(points, pyramid, cells), [], [], 0
    for _, x, y in probes:
        r = pyramid.radius(x, y, ranks[-1])
        i, j, n, near, far = fine.around(x, y, r)
        rings = []
        for rank in ranks:
            low, high = _bound(near, n, rank), min(r * r, _bound(far, n, rank))
            sure, open_ = far < low, (far >= low) & (near <= high)
            rings.append((x, y, low, high, rank - int(n[sure].sum()), i[open_].astype(np.int32), j[open_].astype(np.int32)))
            size += int(open_.sum())
        held.append((rings, (i[sure] >> fine.m, j[sure] >> fine.m, n[sure])))
        if size > SHIPPED:
            out, held, size = out + _settled(points, fine, held, ranks, cells), [], 0
    return out + (_settled(points, fine, held, ranks, cells) if held else [])


def _settled(points: DataFrame, fine: FineCounts, held: list, ranks: list[int], cells) -> list[tuple]:
    spark, each = points.sparkSession, [r for rings, _ in held for r in rings]  # numbered by probe, then rank
    table = pd.DataFrame([(q, *r[:5]) for q, r in enumerate(each)], columns=["q", "qx", "qy", "low", "high", "need"])
    asked = F.broadcast(spark.createDataFrame(table, "q int, qx double, qy double, low double, high double, need long"))
    wanted = F.broadcast(spark.createDataFrame(_by_cell([r[5:] for r in each], "fx", "fy")))
    near = fine.located(points.select("id", "x", "y")).join(wanted, ["fx", "fy"]).withColumn("q", F.explode("qs")).join(asked, "q")
    near = with_distance(near).filter("d2 <= high")
    share = (F.col("d2") - F.col("low")) / F.greatest(F.col("high") - F.col("low"), F.lit(1e-300)) * RINGS
    near = near.withColumn("ring", F.greatest(F.lit(0), F.least(F.lit(RINGS - 1), F.floor(F.greatest(F.lit(-1.0), F.least(share, F.lit(float(RINGS))))))))
    rings = near.groupBy("q", "need", "ring").agg(F.count(F.lit(1)).alias("n"))
    upto = rings.withColumn("upto", F.sum("n").over(Window.partitionBy("q").orderBy("ring")))
    spots = upto.filter("need <= upto AND need > upto - n").select("q", "ring", (F.col("need") - F.col("upto") + F.col("n")).alias("place"))
    spots = F.broadcast(_local(spots, "q int, ring long, place long"))
    order = Window.partitionBy("q").orderBy("d2", "id")
    close = near.join(spots, ["q", "ring"]).select("q", "d2", "id", "place").withColumn("rank", F.row_number().over(order))
    found: list[dict] = [{} for _ in held]
    lasts = []
    for e in close.filter("rank = place").select("q", "d2", "id").toArrow().to_pylist():
        probe, rank = divmod(e["q"], len(ranks))
        found[probe][ranks[rank]] = (float(np.sqrt(e["d2"])), e["id"], e["d2"])
        if rank == len(ranks) - 1:
            lasts.append((e["q"], e["d2"], e["id"]))
    last = F.broadcast(spark.createDataFrame(lasts, "q int, l2 double, lid long"))
    mine = near.join(last, "q").filter("d2 < l2 OR (d2 = l2 AND id <= lid)")
    cell = lambda c: F.shiftright(c, fine.m).cast("long")
    counts = mine.groupBy("q", cell("fx").alias("i"), cell("fy").alias("j")).agg(F.count(F.lit(1)).alias("n")).toArrow()
    q, i, j, n = (counts.column(c).to_numpy() for c in counts.column_names)
    at = np.argsort(q, kind="stable")
    q, i, j, n = q[at], i[at], j[at], n[at]
    out = []
    for probe, (_, sure) in enumerate(held):
        own = slice(*np.searchsorted(q, [(p := (probe + 1) * len(ranks) - 1), p + 1]))
        part = pd.DataFrame({"i": np.r_[sure[0], i[own]], "j": np.r_[sure[1], j[own]], "n": np.r_[sure[2], n[own]]}).groupby(["i", "j"], as_index=False)["n"].sum()
        out.append((found[probe], *(part[c].to_numpy() for c in ("i", "j", "n"))))
    return out


def _local(df: DataFrame, schema: str) -> DataFrame:
    """A small table, computed once: it goes through the driver."""
    return df.sparkSession.createDataFrame(df.toArrow().to_pandas(), schema)


def inside(points: DataFrame, pyramid: Pyramid, balls: list[tuple]) -> DataFrame:
    """The rows of ``points`` in any of the ``balls``: ``(qid, x, y, distance, id, d2)``, with rows of that very d2 up to that id."""
    rows: dict[tuple[int, int], list] = {}
    every = [(x, y, float("inf"), 0) for _, x, y, _, _, d2 in balls if d2 == float("inf")]
    if every:
        return points
    for _, x, y, r, last, d2 in balls:
        for c in pyramid.touched(x, y, r * (1 + 1e-9)):
            rows.setdefault(c, []).append((x, y, d2, last))
    schema = "cx int, cy int, balls array<struct<x:double,y:double,d2:double,id:long>>"
    table = points.sparkSession.createDataFrame([(*c, b) for c, b in rows.items()], schema)
    hit = "exists(balls, b -> (x-b.x)*(x-b.x)+(y-b.y)*(y-b.y) < b.d2 OR ((x-b.x)*(x-b.x)+(y-b.y)*(y-b.y) = b.d2 AND id <= b.id))"
    return pyramid.located(points).join(F.broadcast(table), ["cx", "cy"]).filter(hit).select(*points.columns)


def radius_table(spark, pyramid: Pyramid, k: int) -> DataFrame:
    """``hx, hy, r``: one radius for all left rows of a cell, that of its centre and half a diagonal more."""
    cx, cy = (v.ravel().astype(np.int32) for v in np.meshgrid(np.arange(pyramid.grid), np.arange(pyramid.grid), indexing="ij"))
    table = pd.DataFrame({"hx": cx, "hy": cy, "r": pyramid.radii(k).ravel() + pyramid.side * 2**-0.5})
    return spark.createDataFrame(table, "hx int, hy int, r double")


def knn_join(
    left: DataFrame, right: DataFrame, k: int, grid: int | None = None, pyramid: Pyramid | None = None, radii: DataFrame | None = None,
) -> DataFrame:
    """``qid`` and the k nearest rows of ``right(id, x, y)`` for every row of ``left(qid, qx, qy)``, both of any size.

    Rings of cells round each left row grow until they certainly hold k points: the radius comes from the histogram by
    a join on the left row's cell, whose table has a row for each cell of the histogram; who asks again passes both.
    """
    pyramid = pyramid or Pyramid(right, grid)
    g = pyramid.grid
    radii = radius_table(right.sparkSession, pyramid, k) if radii is None else radii
    probes = pyramid.located(left.select("qid", "qx", "qy", F.col("qx").alias("x"), F.col("qy").alias("y"))).drop("x", "y")
    # outside the square a left row belongs to the nearest cell, and is farther away by what it lies outside
    probes = probes.withColumns({"hx": F.greatest("cx", F.lit(0)), "hy": F.greatest("cy", F.lit(0))}).drop("cx", "cy").join(radii, ["hx", "hy"])
    out = F.lit(0.0)
    for q, low in (("qx", pyramid.x0), ("qy", pyramid.y0)):
        out = out + F.greatest(F.lit(0.0), F.lit(low) - F.col(q), F.col(q) - F.lit(low + pyramid.side * g))
    probes = probes.withColumn("r", (F.col("r") + out) * (1 + 1e-9))

    def span(q: str, low: float):
        edge = lambda v: F.least(F.lit(g - 1), F.greatest(F.lit(0), F.floor((v - F.lit(low)) / F.lit(pyramid.side)).cast("int")))
        return F.sequence(edge(F.col(q) - F.col("r")), edge(F.col(q) + F.col("r")))

    probes = probes.withColumn("cx", F.explode(span("qx", pyramid.x0))).withColumn("cy", F.explode(span("qy", pyramid.y0)))
    pairs = with_distance(pyramid.located(right).join(probes.drop("hx", "hy"), ["cx", "cy"]))
    return ranked(pairs.filter(F.col("d2") <= F.col("r") * F.col("r")).drop("cx", "cy", "r"), k)
