"""Exact DBSCAN with full access to the points, without ever forming all pairs within eps.

Cells have the diagonal eps, so any two points of a cell are neighbours: a cell with min_pts points is all core and all
one cluster. Only points of other cells count neighbours, in the 20 cells that eps can reach. Clusters are components of
a graph of cells, in which two cells are linked if some core point of one is within eps of one of the other. A border point
goes to the cluster of its nearest core point (the smallest id on ties).

What is asked of a full cell is never asked of its points first, and a part of any other cell asks before its points do. Every cell is cut into ``FINE`` x ``FINE`` parts, and each part
again; a part counts as one row with its box and its number of points. Boxes decide most: a part wholly within eps counts
at once, one wholly beyond it never, two parts of which every pair is within eps link their cells. Only parts on the edge of eps are
cut again, and only the points of parts on the edge after that, each different place once, are compared; a point or a pair of cells for which
a coarser step has settled the matter takes no part in the next. So two neighbouring cells with m points each cost some thousand
pairs of parts, whatever m is.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from knnscope.components import connected
from knnscope.io import materialize

#: Cells that a distance of eps can reach from a cell of side eps / sqrt(2), without itself.
NEAR = [(i, j) for i in range(-2, 3) for j in range(-2, 3) if (i, j) != (0, 0) and abs(i) + abs(j) < 4]
#: Parts along each side of a cell, and of a part.
FINE = 8


def _d2(a: str, b: str) -> Column:
    dx, dy = F.col(f"{a}x") - F.col(f"{b}x"), F.col(f"{a}y") - F.col(f"{b}y")
    return dx * dx + dy * dy


def _around(df: DataFrame, steps) -> DataFrame:
    """Each row once for every cell of ``steps`` round its own, as ``nx, ny``."""
    cells = F.array(*(F.struct((F.col("cx") + i).alias("nx"), (F.col("cy") + j).alias("ny")) for i, j in steps))
    return df.withColumn("_n", F.explode(cells)).select("*", "_n.nx", "_n.ny").drop("_n")


class _Parts:
    """Cells of ``points(id, x, y, cx, cy, px, py)``, their parts and the parts of these, with bounds of distances.

    px, py number the finest parts over the plane; ``level`` 1 are the parts of cells, 2 the finest.
    """

    def __init__(self, points: DataFrame, side: float, eps: float):
        self.points, self.side, self.eps = points, side, eps

    def index(self, axis: str, level: int) -> Column:
        return F.floor(F.col(axis) / FINE ** (2 - level)).cast("long")

    def at(self, level: int) -> DataFrame:
        """``cx, cy, i, j, n``: the parts that hold points, of either level."""
        keyed = self.points.select("cx", "cy", self.index("px", level).alias("i"), self.index("py", level).alias("j"))
        return keyed.groupBy("cx", "cy", "i", "j").agg(F.count(F.lit(1)).alias("n"))

    def width(self, level: int) -> float:
        return self.side / FINE**level

    def least(self, *gaps: tuple[Column, Column, Column, Column]) -> Column:
        """Squared least distance of two intervals on each axis: low and high of one, low and high of the other."""
        return sum((F.pow(F.greatest(F.lit(0.0), c - b, a - d), 2) for a, b, c, d in gaps), F.lit(0.0))

    def most(self, *gaps) -> Column:
        return sum((F.pow(F.greatest(F.abs(d - a), F.abs(b - c)), 2) for a, b, c, d in gaps), F.lit(0.0))

    def bounds(self, one: list[tuple[Column, Column]], i: str, j: str, level: int) -> tuple[Column, Column]:
        """Whether all and whether none of a part can be within eps of a box (or a point, a box without extent)."""
        w = self.width(level)
        gaps = [(lo, hi, F.col(k) * F.lit(w), (F.col(k) + 1) * F.lit(w)) for (lo, hi), k in zip(one, (i, j))]
        reach = self.eps * self.eps
        return self.most(*gaps) <= reach * (1 - 1e-9), self.least(*gaps) > reach * (1 + 1e-9)


def _box(i: str, j: str, width: float) -> list[tuple[Column, Column]]:
    return [(F.col(k) * F.lit(width), (F.col(k) + 1) * F.lit(width)) for k in (i, j)]


def _place(x: str, y: str) -> list[tuple[Column, Column]]:
    return [(F.col(x), F.col(x)), (F.col(y), F.col(y))]


def dbscan(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """``id, cluster_id, kind`` of ``points(id, x, y)``; a cluster is named by its smallest core id, noise has NULL.

    A point is its own neighbour. Rows without finite coordinates are left out.
    """
    side = eps / 2**0.5 * (1 - 1e-12)
    usable = points.select("id", "x", "y").filter("x = x AND y = y AND abs(x) < double('Infinity') AND abs(y) < double('Infinity')")
    fine = F.lit(side / FINE**2)
    located = usable.withColumns({p: F.floor(F.col(a) / fine).cast("long") for p, a in (("px", "x"), ("py", "y"))})
    located = located.withColumns({c: F.floor(F.col(p) / FINE**2).cast("long") for c, p in (("cx", "px"), ("cy", "py"))})
    counts = located.groupBy("cx", "cy").agg(F.count(F.lit(1)).alias("n"))
    located = materialize(located.join(counts, ["cx", "cy"]), "located")
    open_ = located.filter(F.col("n") < min_pts)
    cores = located.filter(F.col("n") >= min_pts).drop("n").unionByName(
        open_.join(_enough(open_, located, side, eps, min_pts), "id", "left_semi").drop("n")
    )
    cores = materialize(cores, "cores")
    firsts = cores.groupBy("cx", "cy").agg(F.min("id").alias("node"))
    linked = materialize(_linked_cells(cores, eps, side), "cell-links")
    names = lambda a, b, n: firsts.select(F.col("cx").alias(a), F.col("cy").alias(b), F.col("node").alias(n))
    edges = linked.join(names("cx", "cy", "u"), ["cx", "cy"]).join(names("nx", "ny", "v"), ["nx", "ny"]).select("u", "v")
    found = connected(edges)
    clusters = firsts.join(found, "node", "left").select("cx", "cy", F.coalesce("component", "node").alias("cluster_id"))
    core_labels = materialize(cores.join(clusters, ["cx", "cy"]), "core-labels")

    rest = open_.join(core_labels.select("id"), "id", "left_anti").select("id", "x", "y", "cx", "cy", "px", "py")
    outer = rest.select("id").join(_border(rest, core_labels, side, eps), "id", "left").select(
        "id", F.col("of").alias("cluster_id"), F.when(F.col("of").isNotNull(), "border").otherwise("noise").alias("kind")
    )
    return core_labels.select("id", "cluster_id", F.lit("core").alias("kind")).unionByName(outer)


def _enough(open_: DataFrame, located: DataFrame, side: float, eps: float, min_pts: int) -> DataFrame:
    """``id`` of the points of cells that aren't full which have min_pts neighbours.

    Parts ask first, for all of their points: most have enough neighbours for certain, or too few. Only the points of the others ask, and
    only about parts that are on the edge of eps for their own part.
    """
    parts, own = _Parts(located, side, eps), ["cx", "cy", "i", "j"]
    of = materialize(parts.at(1), "parts")
    other = of.withColumnsRenamed({"cx": "nx", "cy": "ny", "i": "k", "j": "l", "n": "m"})
    box = _box("i", "j", parts.width(1))

    def met_by(asking: DataFrame) -> DataFrame:
        near = _around(asking, NEAR).filter(~parts.bounds(box, "nx", "ny", 0)[1])
        all_, none = parts.bounds(box, "k", "l", 1)
        return near.join(other, ["nx", "ny"]).withColumn("sure", all_).filter(~none)

    def reached(met: DataFrame, *key: str) -> DataFrame:
        """Neighbours for certain, ``s``, of those that can have min_pts."""
        found = met.groupBy(*key, "s").agg(F.sum(F.when(F.col("sure"), F.col("m")).otherwise(0)).alias("more"), F.sum("m").alias("most"))
        found = found.filter(F.col("s") + F.col("most") >= min_pts)
        return found.select(*key, (F.col("s") + F.col("more")).alias("s"))

    cells = of.groupBy("cx", "cy").agg(F.sum("n").alias("s")).filter(F.col("s") < min_pts)
    asked = materialize(reached(met_by(of.select(*own).join(cells, ["cx", "cy"])), *own), "asked-parts")
    points = open_.select("id", "cx", "cy", parts.index("px", 1).alias("i"), parts.index("py", 1).alias("j"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    done = points.join(asked.filter(F.col("s") >= min_pts), own, "left_semi").select("id")
    all_, none = parts.bounds(_place("qx", "qy"), "k", "l", 1)
    met = points.join(met_by(asked.filter(F.col("s") < min_pts)).filter("NOT sure").drop("sure"), own).withColumn("sure", all_).filter(~none)
    met = materialize(met.select("id", "s", "qx", "qy", "nx", "ny", F.col("k").alias("a"), F.col("l").alias("b"), "m", "sure"), "neighbour-parts")
    sure = materialize(reached(met, "id"), "neighbours")
    done = done.unionByName(sure.filter(F.col("s") >= min_pts).select("id"))
    left = sure.filter(F.col("s") < min_pts)
    # parts on the edge of eps: their parts, then the points of those that are on the edge again
    edge = met.filter("NOT sure").drop("s").join(left, "id").select("id", "s", "qx", "qy", "nx", "ny", "a", "b")
    inner = parts.at(2).select(F.col("cx").alias("nx"), F.col("cy").alias("ny"), "i", "j", F.col("n").alias("m"))
    inner = inner.withColumns({"a": F.floor(F.col("i") / FINE).cast("long"), "b": F.floor(F.col("j") / FINE).cast("long")})
    all_, none = parts.bounds(_place("qx", "qy"), "i", "j", 2)
    finer = materialize(edge.join(inner, ["nx", "ny", "a", "b"]).withColumn("sure", all_).filter(~none), "neighbour-parts-2")
    sums = finer.groupBy("id", "s").agg(F.sum(F.when(F.col("sure"), F.col("m")).otherwise(0)).alias("more"))
    sums = materialize(left.join(sums, ["id", "s"], "left").select("id", (F.col("s") + F.coalesce("more", F.lit(0))).alias("s")), "neighbours-2")
    last = finer.filter("NOT sure").select("id", "qx", "qy", F.col("i").alias("px"), F.col("j").alias("py"))
    last = last.join(sums.filter(F.col("s") < min_pts).select("id"), "id", "left_semi")
    places = located.groupBy("px", "py", "x", "y").agg(F.count(F.lit(1)).alias("m")).withColumnsRenamed({"x": "rx", "y": "ry"})
    near = last.join(places, ["px", "py"]).filter(_d2("q", "r") <= eps * eps).groupBy("id").agg(F.sum("m").alias("more"))
    total = sums.join(near, "id", "left").filter(F.col("s") + F.coalesce("more", F.lit(0)) >= min_pts).select("id")
    return done.unionByName(total)


def _linked_cells(cores: DataFrame, eps: float, side: float) -> DataFrame:
    """``cx, cy, nx, ny``: pairs of cells with core points within eps of each other.

    The two points nearest to the other's cell settle most pairs; parts and, on the edge of eps, points the others.
    """
    half = [(i, j) for i, j in NEAR if (i, j) > (0, 0)]
    parts, pair = _Parts(cores, side, eps), ["cx", "cy", "nx", "ny"]
    open_ = materialize(_nearest_to_box(cores, half, side, eps, "q").join(
        _nearest_to_box(cores, [(-i, -j) for i, j in half], side, eps, "r").select(
            F.col("cx").alias("nx"), F.col("cy").alias("ny"), F.col("nx").alias("cx"), F.col("ny").alias("cy"), "rx", "ry"
        ), pair,
    ).select(*pair, (_d2("q", "r") <= eps * eps).alias("sure")), "cell-pairs")
    found, edge = open_.filter("sure").select(*pair), open_.filter("NOT sure").select(*pair)
    for level in (1, 2):
        own = parts.at(level).drop("n")
        other = own.withColumnsRenamed({"cx": "nx", "cy": "ny", "i": "k", "j": "l"})
        all_, none = parts.bounds(_box("i", "j", parts.width(level)), "k", "l", level)
        if level == 1:
            met = edge.join(own, ["cx", "cy"]).filter(~parts.bounds(_box("i", "j", parts.width(1)), "nx", "ny", 0)[1])
            met = met.join(other, ["nx", "ny"])
        else:
            up = lambda df, *c: df.withColumns({f"u{x}": F.floor(F.col(x) / FINE).cast("long") for x in c})
            coarse = edge.withColumnsRenamed({c: f"u{c}" for c in "ijkl"})
            met = coarse.join(up(own, "i", "j"), ["cx", "cy", "ui", "uj"]).join(up(other, "k", "l"), ["nx", "ny", "uk", "ul"])
        met = materialize(met.withColumn("sure", all_).filter(~none).select(*pair, "i", "j", "k", "l", "sure"), "part-pairs")
        sure = met.filter("sure").select(*pair).distinct()
        found = found.unionByName(sure)
        edge = materialize(met.filter("NOT sure").join(sure, pair, "left_anti").drop("sure"), "part-edges")
    places = cores.select("px", "py", "x", "y").distinct()
    a = places.select(F.col("px").alias("i"), F.col("py").alias("j"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    b = places.select(F.col("px").alias("k"), F.col("py").alias("l"), F.col("x").alias("rx"), F.col("y").alias("ry"))
    last = edge.join(a, ["i", "j"]).join(b, ["k", "l"]).filter(_d2("q", "r") <= eps * eps).select(*pair).distinct()
    return found.unionByName(last).distinct()


def _nearest_to_box(cores: DataFrame, steps, side: float, eps: float, name: str) -> DataFrame:
    """For each cell and neighbouring cell the place of the cell's core point nearest to the neighbour's box, if that is within eps.

    One aggregation with partial results; no pairs of points.
    """
    a = _around(cores.select("cx", "cy", "x", "y"), steps)
    out = F.lit(0.0)
    for v, c in (("x", "nx"), ("y", "ny")):
        low = F.col(c) * F.lit(side)
        out = out + F.pow(F.greatest(F.lit(0.0), low - F.col(v), F.col(v) - low - F.lit(side)), 2)
    near = a.withColumn("away", out).filter(F.col("away") <= eps * eps * (1 + 1e-9))
    best = near.groupBy("cx", "cy", "nx", "ny").agg(F.min(F.struct("away", "x", "y")).alias("m"))
    return best.select("cx", "cy", "nx", "ny", F.col("m.x").alias(f"{name}x"), F.col("m.y").alias(f"{name}y"))


def _border(rest: DataFrame, cores: DataFrame, side: float, eps: float) -> DataFrame:
    """``id, of``: the cluster of the nearest core point of each row of ``rest`` that has one within eps.

    Parts of ``rest`` ask first, for all of their points, then the points themselves.
    """
    parts, own, reach = _Parts(cores, side, eps), ["cx", "cy", "i", "j"], eps * eps * (1 + 1e-9)
    points = rest.select("id", "cx", "cy", parts.index("px", 1).alias("i"), parts.index("py", 1).alias("j"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    w = parts.width(1)
    other = parts.at(1).drop("n").withColumnsRenamed({"cx": "nx", "cy": "ny", "i": "a", "j": "b"})
    gaps = [(lo, hi, F.col(k) * F.lit(w), (F.col(k) + 1) * F.lit(w)) for (lo, hi), k in zip(_box("i", "j", w), ("a", "b"))]
    asking = _around(points.select(*own).distinct(), [*NEAR, (0, 0)])
    met = asking.join(other, ["nx", "ny"]).select(*own, "nx", "ny", "a", "b", parts.least(*gaps).alias("least"), parts.most(*gaps).alias("most"))
    met = materialize(met.filter(F.col("least") <= reach), "border-parts")
    # a part can only hold the nearest if it is no farther than another is at most
    nearest = met.groupBy(*own).agg(F.least(F.min("most") * (1 + 1e-9), F.lit(reach)).alias("top"))
    asked = points.join(met.join(nearest, own).filter("least <= top").drop("least", "most"), own).drop(*own)
    for level in (1, 2):
        w = parts.width(level)
        gaps = [(F.col(q), F.col(q), F.col(k) * F.lit(w), (F.col(k) + 1) * F.lit(w)) for q, k in (("qx", "i"), ("qy", "j"))]
        if level == 1:
            met = asked.withColumnsRenamed({"a": "i", "b": "j"})
        else:
            of = parts.at(2).drop("n").withColumnsRenamed({"cx": "nx", "cy": "ny"})
            of = of.withColumns({"a": F.floor(F.col("i") / FINE).cast("long"), "b": F.floor(F.col("j") / FINE).cast("long")})
            met = asked.join(of, ["nx", "ny", "a", "b"])
        met = met.select("id", "qx", "qy", "nx", "ny", "i", "j", "top", parts.least(*gaps).alias("least"), parts.most(*gaps).alias("most"))
        met = materialize(met.filter("least <= top").drop("top"), "border-points")
        nearest = met.groupBy("id").agg(F.least(F.min("most") * (1 + 1e-9), F.lit(reach)).alias("top"))
        asked = met.join(nearest, "id").filter("least <= top").select("id", "qx", "qy", "nx", "ny", "top", F.col("i").alias("a"), F.col("j").alias("b"))
    last = asked.select("id", "qx", "qy", F.col("a").alias("px"), F.col("b").alias("py"))
    # of core points in one place only the smallest id can matter
    places = cores.groupBy("px", "py", "x", "y").agg(F.min(F.struct("id", "cluster_id")).alias("c"))
    places = places.select("px", "py", F.col("x").alias("rx"), F.col("y").alias("ry"), F.col("c.id").alias("pid"), F.col("c.cluster_id").alias("cluster_id"))
    border = last.join(places, ["px", "py"]).withColumn("d2", _d2("q", "r")).filter(F.col("d2") <= eps * eps)
    return border.groupBy("id").agg(F.min(F.struct("d2", "pid", "cluster_id")).alias("m")).select("id", F.col("m.cluster_id").alias("of"))


def dbscan_1d(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """``id, cluster_id, kind`` of ``points(id, x)``."""
    return dbscan(points.select("id", "x", F.lit(0.0).alias("y")), eps, min_pts)


def attach_nearest(points: DataFrame, clustered: DataFrame) -> DataFrame:
    """``id, cluster_id`` of ``points(id, x, y)``: the cluster of the nearest row of ``clustered(id, x, y, cluster_id)``."""
    from knnscope.operators.knn import knn_join

    left = points.select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    return knn_join(left, clustered, 1, 32).select(F.col("qid").alias("id"), "cluster_id")

