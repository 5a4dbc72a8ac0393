"""Merging mini-clusters: by shared edges, or by the mean of their l smallest distances between observed points."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def union_find(nodes, edges) -> dict:
    """The smallest node of each node's component, for the few mini-clusters of one model."""
    parent = {n: n for n in nodes}

    def root(n):
        while parent[n] != n:
            parent[n] = parent[parent[n]]
            n = parent[n]
        return n

    for a, b in edges:
        a, b = root(a), root(b)
        if a != b:
            parent[max(a, b)] = min(a, b)
    return {n: root(n) for n in parent}


def top_l(observed: dict[int, np.ndarray], l: int, threshold: float, recompute: bool = False):  # noqa: E741
    """``(pairs, edges)``: l-distances of pairs of mini-clusters whose boxes are near enough, and those below threshold.

    ``observed`` has the points of each mini-cluster that calls returned. Fewer than l pairs count as they are. With
    ``recompute`` accepted clusters are pooled and compared again until nothing merges.
    """
    edges: list[tuple[int, int]] = []
    groups = {k: v for k, v in observed.items() if len(v)}
    while True:
        names, pairs, new = sorted(groups), {}, []
        boxes = {k: (groups[k].min(0), groups[k].max(0)) for k in names}
        for i, a in enumerate(names):
            for b in names[i + 1 :]:
                gap = np.maximum(0, np.maximum(boxes[a][0] - boxes[b][1], boxes[b][0] - boxes[a][1]))
                if float((gap * gap).sum()) ** 0.5 > threshold:
                    continue  # the smallest distance is larger, and so is the mean
                mean = mean_of_nearest(groups[a], groups[b], l)
                pairs[a, b] = mean
                if mean < threshold:
                    new.append((a, b))
        edges += new
        if not recompute or not new:
            return pairs, edges
        roots = union_find(names, new)
        groups = {r: np.concatenate([groups[k] for k in names if roots[k] == r]) for r in set(roots.values())}


#: Pairs of points compared at once.
BLOCK = 1 << 20


def _cells(points: np.ndarray, side: float):
    """``(low, high, n, of)``: the boxes of the points of each occupied cell, their number, and the cell of each point."""
    code = np.floor(points / side).astype(np.int64)
    _, of = np.unique(code, axis=0, return_inverse=True)
    of = of.ravel()
    order = np.argsort(of, kind="stable")
    starts = np.flatnonzero(np.diff(of[order], prepend=-1))
    n = np.diff(np.append(starts, len(of)))
    return np.minimum.reduceat(points[order], starts), np.maximum.reduceat(points[order], starts), n, of


def _near_cells(a, b, l: int):  # noqa: E741
    """Bounds of the mean of the l smallest distances between the points of two sets of boxes ``(low, high, n)``, and which boxes
    of each can take part in them."""
    limit, use_a, use_b = np.inf, np.zeros(len(a[2]), bool), np.zeros(len(b[2]), bool)
    step = max(1, BLOCK // len(b[2]))

    def bounds(at):
        cut = slice(at, at + step)
        gap = np.maximum(0, np.maximum(a[0][cut, None] - b[1], b[0] - a[1][cut, None]))
        span = np.maximum(a[1][cut, None] - b[0], b[1] - a[0][cut, None])
        return np.sqrt((gap**2).sum(-1)), np.sqrt((span**2).sum(-1)), (a[2][cut, None] * b[2]).astype(float)

    def smallest(values, weights):
        order = np.argsort(values, kind="stable")
        last = int(np.searchsorted(np.cumsum(weights[order]), l)) + 1
        return values[order[:last]], weights[order[:last]]

    def mean(values, weights):
        n = min(float(l), weights.sum())
        taken = np.minimum(weights, np.maximum(0, n - np.append(0, np.cumsum(weights)[:-1])))
        return float((values * taken).sum() / n)

    low, high = (np.zeros(0), np.zeros(0)), (np.zeros(0), np.zeros(0))
    for at in range(0, len(a[2]), step):
        near, far, n = bounds(at)
        low = smallest(np.append(low[0], near), np.append(low[1], n))
        high = smallest(np.append(high[0], far), np.append(high[1], n))
    if high[1].sum() >= l:
        limit = high[0][-1]
    for at in range(0, len(a[2]), step):
        ok = bounds(at)[0] <= limit
        use_a[at : at + step] |= ok.any(1)
        use_b |= ok.any(0)
    return mean(*low), mean(*high), use_a, use_b


def mean_of_nearest(a: np.ndarray, b: np.ndarray, l: int) -> float:  # noqa: E741
    """The mean of the l smallest distances between the points of two sets, of all if there are fewer.

    Cells that lie too far apart to take part are dropped, with smaller and smaller cells, before points are compared in blocks.
    """
    side = max(float(np.ptp(np.concatenate([a, b]), 0).max()), 1e-9) / 8
    for _ in range(24):
        if len(a) * len(b) <= 16 * BLOCK:
            break
        p, q = _cells(a, side), _cells(b, side)
        if len(p[2]) * len(q[2]) > 64 * BLOCK:
            break
        _, _, use_a, use_b = _near_cells(p, q, l)
        a, b = a[use_a[p[3]]], b[use_b[q[3]]]
        side /= 2
    n, best = min(l, len(a) * len(b)), np.zeros(0)
    step = max(1, BLOCK // len(b))
    for at in range(0, len(a), step):
        d = ((a[at : at + step, None, :] - b[None, :, :]) ** 2).sum(2).ravel()
        best = np.append(best, d[d < best[n - 1]] if len(best) == n else d)
        if len(best) > n:
            best = np.partition(best, n - 1)[:n]  # its last is its largest
    return float(np.sqrt(best).mean())


def top_l_table(observed: DataFrame, minis: list[int], l: int, threshold: float):  # noqa: E741
    """``(pairs, edges)`` as by ``top_l`` for ``observed(mini, x, y)`` of any size; of a pair's l-distance only bounds are known,
    close enough to tell on which side of ``threshold`` it lies.

    The driver holds boxes of cells: those of the threshold's size first; then, for pairs that are still open, smaller ones of
    the cells that can take part. Cells end as single places, where both bounds are the distance itself.
    """
    spark, side, edges, pairs, within = observed.sparkSession, float(threshold), [], {}, None
    undecided = [(a, b) for i, a in enumerate(sorted(minis)) for b in sorted(minis)[i + 1 :]]
    for level in range(12):
        if not undecided:
            break
        cell = lambda c, s: F.floor(F.col(c) / F.lit(s)).cast("long")
        rows = observed
        if within is not None:
            table = F.broadcast(spark.createDataFrame(within, "mini int, pi long, pj long"))
            rows = rows.withColumns({"pi": cell("x", side * 4), "pj": cell("y", side * 4)}).join(table, ["mini", "pi", "pj"])
        boxes = rows.groupBy("mini", cell("x", side).alias("i"), cell("y", side).alias("j")).agg(
            *(f("x").alias(n + "x") for f, n in ((F.min, "a"), (F.max, "b"))), *(f("y").alias(n + "y") for f, n in ((F.min, "a"), (F.max, "b"))), F.count(F.lit(1)).alias("n")
        )
        t = boxes.toArrow().to_pandas()
        of = {m: (g[["ax", "ay"]].to_numpy(), g[["bx", "by"]].to_numpy(), g["n"].to_numpy(), g[["i", "j"]].to_numpy()) for m, g in t.groupby("mini")}
        use, left = {m: np.zeros(len(v[2]), bool) for m, v in of.items()}, []
        for a, b in undecided:
            if a not in of or b not in of:
                continue
            p, q = of[a], of[b]
            if level == 0:
                gap = np.maximum(0, np.maximum(p[0].min(0) - q[1].max(0), q[0].min(0) - p[1].max(0)))
                if float((gap * gap).sum()) ** 0.5 > threshold:
                    continue
            low, high, use_a, use_b = _near_cells(p[:3], q[:3], l)
            pairs[a, b] = (low, high)
            if high < threshold:
                edges.append((a, b))
            elif low < threshold and high - low > 1e-12 * threshold:
                left.append((a, b))
                use[a] |= use_a
                use[b] |= use_b
        undecided = left
        within = [(int(m), int(i), int(j)) for m, u in use.items() for i, j in of[m][3][u].tolist()]
        side /= 4
    return pairs, edges


def adjacent(boxes: dict[int, np.ndarray]) -> list[tuple[int, int]]:
    """Pairs of mini-clusters with leaves (rows of centre and side) that share an edge of positive length."""
    names, edges = sorted(boxes), []
    for i, a in enumerate(names):
        for b in names[i + 1 :]:
            p, q = boxes[a][:, None, :], boxes[b][None, :, :]
            reach = (p[..., 2] + q[..., 2]) / 2
            dx, dy = np.abs(p[..., 0] - q[..., 0]), np.abs(p[..., 1] - q[..., 1])
            tiny = 1e-9 * reach
            if (((np.abs(dx - reach) < tiny) & (dy < reach - tiny)) | ((np.abs(dy - reach) < tiny) & (dx < reach - tiny))).any():
                edges.append((a, b))
    return edges


def top_l_distances(observed: DataFrame, l: int, threshold: float) -> DataFrame:  # noqa: E741
    """``mini_a, mini_b, l_distance`` over ``observed(mini_id, id, x, y)`` as a table, for many observed points.

    Points meet only if their cells of the threshold's size are the same or neighbours; pairs farther apart than the
    threshold are left out, so distances are exact for pairs of mini-clusters whose l smallest are all within it.
    """
    cell = lambda c: F.floor(F.col(c) / threshold).cast("long")
    a = observed.select(F.col("mini_id").alias("mini_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), cell("x").alias("i"), cell("y").alias("j"))
    near = F.array(*(F.struct((cell("x") + dx).alias("i"), (cell("y") + dy).alias("j")) for dx in (-1, 0, 1) for dy in (-1, 0, 1)))
    b = observed.select(F.col("mini_id").alias("mini_b"), F.col("x").alias("bx"), F.col("y").alias("by"), F.explode(near).alias("c"))
    b = b.select("mini_b", "bx", "by", "c.i", "c.j")
    dx, dy = F.col("ax") - F.col("bx"), F.col("ay") - F.col("by")
    pairs = a.join(b, ["i", "j"]).filter("mini_a < mini_b").withColumn("d2", dx * dx + dy * dy)
    pairs = pairs.filter(F.col("d2") <= threshold * threshold)
    order = Window.partitionBy("mini_a", "mini_b").orderBy("d2")
    first = pairs.withColumn("n", F.row_number().over(order)).filter(F.col("n") <= l)
    return first.groupBy("mini_a", "mini_b").agg(F.avg(F.sqrt("d2")).alias("l_distance"))
