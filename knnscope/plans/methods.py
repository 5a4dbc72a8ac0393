"""Queries of the methods, and the SQL from which DuckDB computes the same rows."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.components import connected
from knnscope.functions import curves, sqlfuncs
from knnscope.io import materialize, shared_dir, table
from knnscope.operators import baselines, cluster_nd, dbscan, grid, joins, knn, merge, metrics, service
from knnscope.operators.curve2d import ClusterModel, curve_cluster_2d
from knnscope.operators.fulltree import full_tree
from knnscope.operators.pursuit import GridLine, boundary_cluster_1d
from knnscope.plans import live, relational, workloads
from knnscope.sources import views
from knnscope.sources.views import plain, view
from knnscope.streaming import points as streaming

DOMAIN = workloads.DOMAIN
#: Places to ask from, the same in both engines.
PROBES = [(i, (i * 97 + 31) % 700 + 0.25, (i * 53 + 17) % 500 + 0.75) for i in range(25)]
_PROBE_SQL = " union all ".join(f"select {i} qid, {x}e0 qx, {y}e0 qy" for i, x, y in PROBES)
#: The queries of the kNN searches: every row whose id is divisible by this.
EVERY = 20
_VIEW = {n: f"({plain(t)})" for n, t in views.VIEWS.items()}


def _knn_sql(source: str, k: int, where: str = "true", probes: str | None = None) -> str:
    probes = probes or f"select id qid, x qx, y qy from {_VIEW[source]} v where id % {EVERY} = 0"
    return (
        f"select qid, rank, id, {relational.snap('sqrt(d2)')} dist from (select qid, id, d2, row_number() over (partition by qid order by d2, id) rank from "
        f"(select qid, id, (x-qx)*(x-qx)+(y-qy)*(y-qy) d2 from {_VIEW[source]} p cross join ({probes}) q where {where}) a) b where rank <= {k}"
    )


def _answers(found: DataFrame) -> DataFrame:
    return found.selectExpr("qid", "rank", "id", f"{relational.snap('sqrt(d2)')} AS dist")


def _asked(points: DataFrame) -> DataFrame:
    return points.filter(F.col("id") % EVERY == 0).select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))


def knn_brute(spark, sf_dir):
    points = view(spark, sf_dir, "shapes").select("id", "x", "y")
    return _answers(knn.brute_or_join(points, _asked(points), 14))


def _grid(spark, sf_dir, name, k, where=None):
    points = view(spark, sf_dir, name)
    asked = _asked(points)
    return _answers(knn.knn_join(asked, (points.filter(where) if where else points).select("id", "x", "y"), k))


def service_round(spark, sf_dir):
    """One round of a client's calls: places that a driver holds, answered in one job."""
    points = view(spark, sf_dir, "shapes")
    return _answers(knn.grid_join(points, knn.Pyramid(points), PROBES, 14))


def join_knn(spark, sf_dir):
    left = view(spark, sf_dir, "stations").select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    return knn.knn_join(left, view(spark, sf_dir, "listings").select("id", "x", "y"), 3).select("qid", "rank", "id")


def knn_radius(spark, sf_dir):
    points = view(spark, sf_dir, "shapes").select("id", "x", "y")
    return knn.knn_join(_asked(points), points, 14).groupBy("qid").agg(F.max("d2").alias("r2")).selectExpr("qid", f"{relational.snap('sqrt(r2)')} AS radius")


def core_test_by_probe(spark, sf_dir):
    """Which points are core: a call on each, and the 14th distance."""
    return core_by_probe(view(spark, sf_dir, "shapes").select("id", "x", "y"), 10.0, 14)


def core_by_probe(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """``id, core``. All of a cell that is smaller than eps across and holds minPts points are core without a call."""
    located = materialize(grid.cell_of(points, 0.7 * eps), "core-cells")
    full = located.groupBy("cx", "cy").count().filter(F.col("count") >= min_pts).select("cx", "cy")
    asked = located.join(full, ["cx", "cy"], "left_anti").select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    last = knn.knn_join(asked, located.select("id", "x", "y"), min_pts).groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("r2"))
    probed = last.select(F.col("qid").alias("id"), ((F.col("n") >= min_pts) & (F.col("r2") <= eps * eps)).alias("core"))
    return located.join(full, ["cx", "cy"], "left_semi").select("id", F.lit(True).alias("core")).unionByName(probed)


def crawl_box_points(spark, sf_dir):
    points, box = view(spark, sf_dir, "shapes").select("id", "x", "y"), (150.0, 250.0, 260.0, 340.0)
    if points.count() > service.MemoryKnnService.LIMIT:
        return service.crawl_box_distributed(points, 14, box)
    found = service.crawl_box(service.MemoryKnnService(points, 14), box)
    return spark.createDataFrame([(i,) for i in sorted(found)], "id long")


def density_probe_1d(spark, sf_dir, rule: str = "min_pts", k: int = 60):
    """States of all cells by a call at each centre (which in one dimension is exact)."""
    line = GridLine(-0.0005, 1000.4995, 5.0, 60, rule, infer=False)
    baselines.scan_all_cells(line, _line_service(spark, sf_dir, line, k))
    return spark.createDataFrame([(c, d) for c, d in sorted(line.state.items())], "cx long, dense boolean")


def _line_service(spark, sf_dir, line: GridLine, k: int) -> service.PreparedKnnService:
    """Calls on `line1d`, whose points stay where they are: the answers at the centres of the cells are looked up in one job."""
    points = view(spark, sf_dir, "line1d").select("id", "x", F.lit(0.0).alias("y"))
    return service.PreparedKnnService(points, k, line.places())


def leaf_tests_2d(spark, sf_dir):
    """The three tests of a square cell by one call, beside its true count."""
    cells = grid.cell_counts(view(spark, sf_dir, "shapes"), 16).collect()
    s = service.MemoryKnnService(view(spark, sf_dir, "shapes"), 14)
    places = [(-0.0005 + (c.cx + 0.5) * 16, -0.0005 + (c.cy + 0.5) * 16) for c in cells]
    rows = []
    for c, a in zip(cells, s.probe(places, "leaf")):
        inside = int(((np.abs(a.xs - a.x) <= 8) & (np.abs(a.ys - a.y) <= 8)).sum())
        last = a.dist[13] if len(a.dist) >= 14 else np.inf
        rows.append((c.cx, c.cy, c.n, inside >= 14, bool(last <= 8 * 2**0.5), bool(last <= 8)))
    return spark.createDataFrame(rows, "cx long, cy long, n long, in_cell boolean, circumscribed boolean, inscribed boolean")


def _segments(spark, sf_dir, **options):
    s = _line_service(spark, sf_dir, GridLine(-0.0005, 1000.4995, 5.0, 60), 60)
    found = boundary_cluster_1d(s, (-0.0005, 1000.4995), 5.0, 60, **options)
    return spark.createDataFrame([(int(a), int(b)) for a, b in sorted(found.segments)], "lo long, hi long")


#: Levels of the curves that the queries on keys use.
_ORDER = {"hilbert": 6, "z": 6, "peano": 4}


def _keys(kind):
    order = _ORDER[kind]

    def run(spark, sf_dir):
        n = curves.base(kind) ** order
        cx, cy = curves.cell_columns(F.col("x"), F.col("y"), DOMAIN, n)
        return view(spark, sf_dir, "shapes").select("id", curves.key_column(kind, cx, cy, order).alias("key"))

    return run


def _located(side_sql: str, source: str | None = None) -> str:
    return f"select id, cast(floor((x+0.0005e0)/({side_sql})) as bigint) cx, cast(floor((y+0.0005e0)/({side_sql})) as bigint) cy from {source or _VIEW['shapes']} s"


def _hilbert_sql(order: int = 6, source: str | None = None) -> str:
    top = "(case when y >= h then 1 else 0 end)"
    right = "(case when x >= h then 1 else 0 end)"
    return (
        f"with recursive d as ({_located(f'1024e0/{2**order}', source)}), c as (select distinct cx, cy from d), w as ("
        f"select cx, cy, cx x, cy y, cast({2 ** (order - 1)} as bigint) h, cast(0 as bigint) key from c union all "
        f"select cx, cy, case when {top}=1 then x%h when {right}=1 then h-1-y%h else y%h end, "
        f"case when {top}=1 then y%h when {right}=1 then h-1-x%h else x%h end, h//2, key*4 + case when {right}=1 then 3-{top} else {top} end from w where h >= 1) "
        "select id, key from d join w using (cx, cy) where h = 0"
    )


def _z_sql(order: int = 6) -> str:
    bits = " + ".join(f"((cx >> {b}) & 1) * {2 ** (2 * b + 1)} + ((cy >> {b}) & 1) * {2 ** (2 * b)}" for b in range(order))
    return f"select id, cast({bits} as bigint) key from ({_located(f'1024e0/{2**order}')}) d"


def _peano_sql(order: int = 4) -> str:
    kx = "(case when oy = 1 then 2 - x//t else x//t end)"
    flip = "((ox + (x//t)) % 2)"
    ky = f"(case when {flip} = 1 then 2 - y//t else y//t end)"
    return (
        f"with recursive d as ({_located(f'1024e0/{3**order}')}), c as (select distinct cx, cy from d), w as ("
        f"select cx, cy, cx x, cy y, cast({3 ** (order - 1)} as bigint) t, cast(0 as bigint) ox, cast(0 as bigint) oy, cast(0 as bigint) key from c union all "
        f"select cx, cy, x%t, y%t, t//3, {flip}, (oy + y//t) % 2, key*9 + {kx}*3 + {ky} from w where t >= 1) select id, key from d join w using (cx, cy) where t = 0"
    )


def cell_roundtrip(spark, sf_dir):
    """Of the cells that hold points of `shapes`: how many come back from their keys, and between how many neighbours on the curve
    a step has length one."""
    out = None
    for kind in curves.KINDS:
        order = _ORDER[kind]
        cx, cy = curves.cell_columns(F.col("x"), F.col("y"), DOMAIN, curves.base(kind) ** order)
        keyed = view(spark, sf_dir, "shapes").select(cx.alias("cx"), cy.alias("cy")).distinct()
        keyed = keyed.select("cx", "cy", curves.key_column(kind, F.col("cx"), F.col("cy"), order).alias("key"))

        def back(batches, kind=kind, order=order):
            for rows in batches:
                x, y = curves.cells(kind, rows["key"].to_numpy(), order)
                yield rows.assign(x=x, y=y)

        found = materialize(keyed.mapInPandas(back, "cx long, cy long, key long, x long, y long"), "cells")
        after = found.select((F.col("key") - 1).alias("key"), F.col("x").alias("nx"), F.col("y").alias("ny"))
        same = F.count(F.when((F.col("cx") == F.col("x")) & (F.col("cy") == F.col("y")), 1)).alias("cells")
        unit = F.count(F.when(F.abs(F.col("nx") - F.col("x")) + F.abs(F.col("ny") - F.col("y")) == 1, 1)).alias("unit_steps")
        one = found.join(after, "key", "left").agg(same, unit).select(F.lit(kind).alias("kind"), "cells", "unit_steps")
        out = one if out is None else out.unionByName(one)
    return out


def curve_runs_by_kind(spark, sf_dir):
    """Into how many runs of keys each curve cuts its dense cells."""
    out = None
    for kind in curves.KINDS:
        dense = _keys(kind)(spark, sf_dir).groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n >= 14").select("key")
        starts = dense.join(dense.select((F.col("key") + 1).alias("key")), "key", "left_anti")
        one = starts.agg(F.count(F.lit(1)).alias("runs")).select(F.lit(kind).alias("kind"), "runs")
        out = one if out is None else out.unionByName(one)
    return out


def _roundtrip_sql() -> str:
    """Counts of cells with points, and of pairs of them that follow each other on the curve and share an edge."""
    cells = {
        "hilbert": _hilbert_sql().replace("select id, key from d join w using (cx, cy) where h = 0", "select cx, cy, key from w where h = 0"),
        "z": _z_sql().replace("select id,", "select distinct cx, cy,", 1),
        "peano": _peano_sql().replace("select id, key from d join w using (cx, cy) where t = 0", "select cx, cy, key from w where t = 0"),
    }
    return " union all ".join(
        f"select '{k}' kind, (select count(*) from ({t}) c) cells, (select count(*) from ({t}) a join ({t}) b on b.key = a.key + 1 "
        "where abs(a.cx-b.cx) + abs(a.cy-b.cy) = 1) unit_steps"
        for k, t in cells.items()
    )


def lower_bounds_calls(spark, sf_dir):
    """The least numbers of calls for all points, for all dense cells and by core points, with k = minPts = 14."""
    points = view(spark, sf_dir, "shapes")
    n, dense = points.count(), grid.cell_counts(points, 16).filter("n >= 14").count()
    core = dbscan.dbscan(points, 10, 14).filter("kind = 'core'").count()
    bounds = baselines.lower_bounds(n, core, dense, 14, 14)
    return spark.createDataFrame([(k, int(v)) for k, v in bounds.items()], "bound string, calls long")


def tree_full_leaves(spark, sf_dir):
    return full_tree(view(spark, sf_dir, "shapes"), DOMAIN, 14, 6)


def tree_split_vs_leaf(spark, sf_dir):
    kind = F.when(F.col("state") == "split", "split").otherwise("leaf")
    return tree_full_leaves(spark, sf_dir).groupBy("level", kind.alias("kind")).agg(F.count(F.lit(1)).alias("calls"))


def _tree_sql() -> str:
    near = (
        "(select count(*) from p where (p.x - (-0.0005e0 + ({cx} + 0.5e0) * {s})) * (p.x - (-0.0005e0 + ({cx} + 0.5e0) * {s})) + "
        "(p.y - (-0.0005e0 + ({cy} + 0.5e0) * {s})) * (p.y - (-0.0005e0 + ({cy} + 0.5e0) * {s})) <= {s} * {s} / 2)"
    )
    quarters = "(select 0 i, 0 j union all select 0, 1 union all select 1, 0 union all select 1, 1)"
    parts, previous = [f"p as materialized (select x, y from {_VIEW['shapes']} s)"], "(select 0 cx, 0 cy)"
    for level in range(1, 7):
        side = f"{1024 / 2**level}e0"
        split = "'split'" if level < 6 else "'maybe'"
        parts.append(f"c{level} as materialized (select cx*2+i cx, cy*2+j cy from {previous} v cross join {quarters} q)")
        parts.append(
            f"t{level} as materialized (select {level} \"level\", c.cx, c.cy, count(p.x) near from c{level} c left join p on "
            f"(p.x - (-0.0005e0 + (c.cx + 0.5e0) * {side})) * (p.x - (-0.0005e0 + (c.cx + 0.5e0) * {side})) + "
            f"(p.y - (-0.0005e0 + (c.cy + 0.5e0) * {side})) * (p.y - (-0.0005e0 + (c.cy + 0.5e0) * {side})) <= {side} * {side} / 2 group by c.cx, c.cy)"
        )
        parts.append(f"n{level} as materialized (select *, case when near >= 14 then {split} else 'sparse' end state from t{level})")
        previous = f"(select cx, cy from n{level} where state = 'split')"
    del near
    return "with " + ", ".join(parts) + " " + " union all ".join(f"select * from n{level}" for level in range(1, 7))


def merge_adjacent(spark, sf_dir):
    """Pairs of rows of dense cells (runs along x) that share an edge with a run of the next row."""
    dense = grid.cell_counts(view(spark, sf_dir, "shapes"), 16).filter("n >= 14").select("cx", "cy")
    above = dense.select("cx", (F.col("cy") + 1).alias("cy"))
    return dense.join(above, ["cx", "cy"]).groupBy("cy").agg(F.count(F.lit(1)).alias("edges"))


def top_l_distance(spark, sf_dir):
    observed = view(spark, sf_dir, "shapes").filter("lab <> 'error'").select(
        F.floor((F.col("x") + 0.0005) / 64).cast("int").alias("mini_id"), "id", "x", "y"
    )
    return merge.top_l_distances(observed, 7, 40.0).selectExpr("mini_a", "mini_b", f"{relational.snap('l_distance')} AS l_distance")


def components_small(spark, sf_dir):
    """Components of dense cells that touch, from their edges."""
    dense = grid.cell_counts(view(spark, sf_dir, "shapes"), 16).filter("n >= 14").select("cx", "cy")
    a, b = dense.alias("a"), dense.select((F.col("cx") + 1).alias("cx"), "cy").alias("b")
    code = F.col("cx") * 1000 + F.col("cy")
    right = a.join(b, ["cx", "cy"]).select((code - 1000).alias("u"), code.alias("v"))
    c = dense.select("cx", (F.col("cy") + 1).alias("cy"))
    up = dense.join(c, ["cx", "cy"]).select((code - 1).alias("u"), code.alias("v"))
    return connected(right.unionByName(up))


_COMPONENTS = (
    "with recursive d as materialized ({dense}), e as materialized (select a.{n} u, b.{n} v from d a join d b on {near}), "
    "cc(id, lab) using key (id) as (select {n}, {n} from d union (select e.v, min(cc.lab) from cc join e on cc.id = e.u "
    "join recurring.cc r on r.id = e.v where cc.lab < r.lab group by e.v)) "
)
_CODED = f"select *, cx*1000+cy code from ({plain(relational.DENSE)})"
_CODED32 = f"select *, cx*4294967296+cy code from ({plain(relational.DENSE)})"
_EDGE = "abs(a.cx-b.cx)+abs(a.cy-b.cy) = 1"
_EIGHT = "greatest(abs(a.cx-b.cx), abs(a.cy-b.cy)) = 1"


def _grid_dbscan_sql(near: str) -> str:
    return _COMPONENTS.format(dense=_CODED32, n="code", near=near) + "select cx, cy, n, lab cluster_id from d join cc on cc.id = d.code"


def _dbscan_sql(source: str, eps: float, min_pts: int) -> str:
    y = "0e0" if source == "line1d" else "y"
    d2 = "(a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y)"
    return (
        f"with recursive p as materialized (select id, x, y, cast(floor(x/{eps}) as int) i, cast(floor(y/{eps}) as int) j from (select id, x, {y} y from {_VIEW[source]} v) v0), "
        "o as (select unnest([-1,0,1]) d), q as materialized (select p.id, x, y, i+o.d i, j+o2.d j from p cross join o cross join o o2), "
        f"nb as materialized (select a.id u, b.id v, {d2} d2 from p a join q b on a.i=b.i and a.j=b.j where {d2} <= {eps}*{eps}), "
        f"core as materialized (select u id from nb group by u having count(*) >= {min_pts}), "
        "e as materialized (select u, v from nb where u in (select id from core) and v in (select id from core)), "
        "cc(id, lab) using key (id) as (select id, id from core union (select e.v, min(cc.lab) from cc join e on cc.id = e.u "
        "join recurring.cc r on r.id = e.v where cc.lab < r.lab group by e.v)), "
        "near as (select u, v, row_number() over (partition by u order by d2, v) r from nb where v in (select id from core) and u not in (select id from core)) "
        "select p.id, coalesce(c.lab, cb.lab) cluster_id, case when c.id is not null then 'core' when cb.id is not null then 'border' else 'noise' end kind "
        "from p left join cc c on c.id = p.id left join near n on n.u = p.id and n.r = 1 left join cc cb on cb.id = n.v"
    )


DBSCANS = {
    "shapes": (10, 14), "shapes_b": (10, 19), "shapes_c": (8, 6), "listings": (8, 30), "line1d": (2.5, 40), "stations": (6, 3), "photos": (8, 40),
}
#: Ranges of Hilbert keys of order 6 and their clusters, for the function on its own.
FIXED = [(0, 40, 1), (100, 180, 2), (181, 260, 1), (700, 1500, 3), (2600, 2600, 2)]


def _fixed_model() -> ClusterModel:
    return ClusterModel("hilbert", DOMAIN, 6, FIXED)


def assign_fixed_segments(spark, sf_dir):
    return _fixed_model().assign(view(spark, sf_dir, "shapes").select("id", "x", "y")).select("id", "cluster_id")


def _assign_sql(source: str | None = None) -> str:
    ranges = " union all ".join(f"select {a} lo, {b} hi, {c} cluster_id" for a, b, c in FIXED)
    return f"select k.id, r.cluster_id from ({_hilbert_sql(source=source)}) k left join ({ranges}) r on k.key between r.lo and r.hi"


def assign_1d(spark, sf_dir):
    runs = grid.dense_runs(view(spark, sf_dir, "line1d"), 5.0, 60)
    ranges = runs.select((F.col("lo") * 5 - 0.0005).alias("lo"), (F.col("hi") * 5 + 5 - 0.0005).alias("hi"), F.col("lo").alias("cluster_id"))
    points = view(spark, sf_dir, "line1d").select("id", "x")
    return joins.range_join(points, ranges, "x", 50.0).select("id", "cluster_id")


def attach_nearest_station(spark, sf_dir):
    stations = view(spark, sf_dir, "stations")
    known = stations.filter("id % 7 <> 0").withColumn("cluster_id", F.expr("case when id%10 < 6 then 0 else id%10 end"))
    return dbscan.attach_nearest(stations.filter("id % 7 = 0"), known.select("id", "x", "y", "cluster_id"))


def _labels(spark, sf_dir):
    return views.sql(spark, sf_dir, relational.GRID_LABEL)


def pair_counts(spark, sf_dir):
    got = metrics.pair_counts(_labels(spark, sf_dir))
    return got.selectExpr(*(f"CAST({c} AS BIGINT) AS {c}" for c in "abcd"))


def pair_counts_brute(spark, sf_dir):
    """By all pairs of rows, for the one set that is small by nature."""
    return metrics.pair_counts_brute(views.sql(spark, sf_dir, relational.STATION_LABEL)).selectExpr(*(f"CAST({c} AS BIGINT) AS {c}" for c in "abcd"))


def index_rand_jaccard_fm(spark, sf_dir):
    got = metrics.agreement(_labels(spark, sf_dir))
    return got.selectExpr(*(f"{relational.snap(c, 6)} AS {c}" for c in ("rand_index", "jaccard_index", "fowlkes_mallows")))


def noise_modes(spark, sf_dir):
    out = None
    for mode in metrics.NOISE_MODES:
        one = metrics.pair_counts(_labels(spark, sf_dir), noise=mode).selectExpr(f"'{mode}' AS mode", *(f"CAST({c} AS BIGINT) AS {c}" for c in "abcd"))
        out = one if out is None else out.unionByName(one)
    return out


def _pairs_sql(where: str = "true", single: str = "true") -> str:
    two = "coalesce(cast(sum(n*(n-1)//2) as bigint), 0)"
    return (
        f"with g as (select coalesce(cast(pred as varchar), 'none') p, coalesce(truth, 'none') t, count(*) n from ({plain(relational.GRID_LABEL)}) l where {where} group by 1, 2), "
        f"m as (select (select {two} from g where {single.replace('?', 'p')} and {single.replace('?', 't')}) a, "
        f"(select {two} from (select p, sum(n) n from g group by p) x where {single.replace('?', 'p')}) ac, "
        f"(select {two} from (select t, sum(n) n from g group by t) x where {single.replace('?', 't')}) ad, (select cast(sum(n)*(sum(n)-1)//2 as bigint) from g) al) "
        "select a, al-ac-ad+a b, ac-a c, ad-a d from m"
    )


def _brute_sql() -> str:
    return (
        f"with l as (select id, pred, truth from ({plain(relational.STATION_LABEL)}) l) select "
        "count(*) filter (where p and t) a, count(*) filter (where not p and not t) b, count(*) filter (where p and not t) c, count(*) filter (where not p and t) d from "
        "(select a.pred is not distinct from b.pred p, a.truth is not distinct from b.truth t from l a join l b on a.id < b.id) x"
    )


def model2d(curve: str, adaptive: bool = True, budget: int = 400):
    def run(spark, sf_dir):
        """Labels of all points by a budgeted model, through the distributed function."""
        b = workloads.Benchmark(spark, sf_dir)
        model = curve_cluster_2d(
            b.service(None, budget, curve, None, adaptive), workloads.SQUARE[curve], b.eps, b.min_pts, workloads.SIDE[curve], curve, adaptive,
            merge_threshold=b.eps * workloads.MERGE[curve], **workloads.OPTIONS,
        )
        return model.assign(view(spark, sf_dir, "shapes").select("id", "x", "y")).select("id", "cluster_id")

    return run


def model2d_exhaustive(spark, sf_dir):
    """Unlimited calls with large answers, every cell checked, merging by edges: the components of dense leaves."""
    s = service.MemoryKnnService(view(spark, sf_dir, "shapes"), 1_000_000)
    model = curve_cluster_2d(s, DOMAIN, 16.0, 14, 16.0, adaptive=False, n_check=None, merge="adjacent", init_level=1)
    got = model.assign(view(spark, sf_dir, "shapes").select("id", "x", "y")).filter("cluster_id is not null")
    return got.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first")).select("n", "first")


def _exhaustive_sql() -> str:
    member = f"select id, {relational._CX} cx, {relational._CY} cy from {_VIEW['shapes']} s"
    return _COMPONENTS.format(dense=_CODED, n="code", near=_EDGE) + f"select count(*) n, min(m.id) \"first\" from ({member}) m join d on d.cx = m.cx and d.cy = m.cy join cc on cc.id = d.code group by cc.lab"


def sample_uniform(spark, sf_dir):
    return baselines.sample_uniform(view(spark, sf_dir, "shapes"), 200).select("id", "x", "y")


def sample_then_cluster(spark, sf_dir):
    b = workloads.Benchmark(spark, sf_dir)
    asked = b.service(budget=400) if b.small else b._drawing("raw", 400, 0)
    model = baselines.sample_then_cluster(asked, workloads.SQUARE["hilbert"], 10.0, b.min_pts, 20.0, "raw", 0, b.n)
    return model.assign(view(spark, sf_dir, "shapes").select("id", "x", "y")).select("id", "cluster_id")


def knn_distributed_model(spark, sf_dir, budget: int = 120):
    """The same clusterer against the distributed service, many searches sharing each round."""
    points = view(spark, sf_dir, "shapes").select("id", "x", "y")
    points = materialize(points, "points")
    b = workloads.Benchmark(spark, sf_dir)
    s = service.KnnService(points, b.min_pts, service.Budget(budget))
    curve_cluster_2d(s, DOMAIN, b.eps, b.min_pts, 64.0, seeds_per_round=32, merge_threshold=b.eps)
    return s.ledger(spark)


# --- three dimensions
def _vectors(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.transform(F.slice("embedding", 1, 3), lambda v: v.cast("double")).alias("v"))


def _model3d(spark, sf_dir, k, budget, min_pts, **options):
    points = _vectors(spark, sf_dir).filter("v IS NOT NULL AND size(v) = 3")
    n = points.count()
    if n <= service.MemoryKnnService.LIMIT:
        rows = points.orderBy("id").toPandas()
        s = cluster_nd.MemoryKnnServiceNd(rows["id"].to_numpy(), np.stack(rows["v"].to_numpy()), k, service.Budget(budget))
    else:
        s = cluster_nd.KnnServiceNd(materialize(points, "vectors"), k, service.Budget(budget))
    model = cluster_nd.cluster_nd(s, [-4.0] * 3, 8.0, 3, 4, min_pts, 0.6, **options)
    return model.assign(points).select(F.col("id").alias("vec_id"), "cluster_id")


def model3d(spark, sf_dir, budget: int = 300):
    """Clusters of the first three components, under a budget."""
    points = table(spark, sf_dir, "embeddings").count()
    min_pts = max(2, points // 125)
    return _model3d(spark, sf_dir, min_pts, budget, min_pts)


def model3d_exhaustive(spark, sf_dir):
    """Which points lie in dense cells, by a budget without end and answers as large as the set."""
    found = _model3d(spark, sf_dir, 1_000_000, float("inf"), 4, n_check=5000)
    return found.filter("cluster_id IS NOT NULL").select("vec_id")


# --- joins, aggregates, functions beyond shared SQL
def join_range(spark, sf_dir):
    ranges = spark.createDataFrame([(i, i * 37.5, i * 37.5 + 50.25) for i in range(20)], "range_id int, lo double, hi double")
    return joins.range_join(view(spark, sf_dir, "line1d").select("id", "x"), ranges, "x", 50.0).select("id", "range_id")


def join_asof(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    left = events.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = events.filter("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("view_id"))
    return joins.asof_join(left, right, "user_id", "ts", "view_id").select("event_id", "view_id_asof")


def join_distance(spark, sf_dir):
    s = view(spark, sf_dir, "stations")
    return joins.distance_join(s, view(spark, sf_dir, "listings"), 5.0).select("a_id", "b_id")


def agg_percentile(spark, sf_dir):
    return view(spark, sf_dir, "listings").groupBy("reg").agg(F.expr("percentile(price, 0.5)").alias("p50")).selectExpr("reg", f"{relational.snap('p50', 1)} AS p50")


def agg_approx_distinct(spark, sf_dir):
    """Whether the approximate number of customers of each priority is within a tenth of the exact one."""
    o = table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.countDistinct("o_custkey").alias("e"))
    return o.select("o_orderpriority", (F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("near"))


def price_pivot(spark, sf_dir):
    bins = view(spark, sf_dir, "listings").withColumn("bin", F.floor(F.col("price") / 50000).cast("long"))
    return bins.groupBy("bin").pivot("reg", [0, 1, 2, 3, 4]).count().select("bin", *(F.coalesce(str(r), F.lit(0)).alias(f"reg{r}") for r in range(5)))


def fn_array(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    return e.select("vec_id", F.size("embedding").alias("n"), F.slice("embedding", 1, 3).getItem(0).cast("double").alias("first"), F.size(F.filter("embedding", lambda v: v > 0)).alias("positive"))


def fn_map(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id", F.create_map(F.lit("lang"), "lang", F.lit("source"), "source").alias("m"))
    return d.select("doc_id", F.element_at("m", "source").alias("source"), F.size(F.map_keys("m")).alias("n"))


def array_distance_3d(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform(F.slice("embedding", 1, 3), lambda v: v.cast("double")).alias("v"))
    o = table(spark, sf_dir, "embeddings").filter("vec_id = 1").select(F.transform(F.slice("embedding", 1, 3), lambda v: v.cast("double")).alias("w"))
    d2 = F.aggregate(F.zip_with("v", "w", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    return e.crossJoin(F.broadcast(o)).select("vec_id", d2.alias("d2")).selectExpr("vec_id", f"{relational.snap('d2', 4)} AS d2")


def _cells_3d(spark, sf_dir):
    cell = F.transform(F.slice("embedding", 1, 3), lambda v: F.greatest(F.lit(0), F.least(F.lit(15), F.floor((v.cast("double") + 4) * 2))).cast("long"))
    return table(spark, sf_dir, "embeddings").select("vec_id", cell.alias("c"))


def cells_3d(spark, sf_dir):
    c = _cells_3d(spark, sf_dir)
    return c.groupBy(c.c[0].alias("cx"), c.c[1].alias("cy"), c.c[2].alias("cz")).agg(F.count(F.lit(1)).alias("n"))


def z_key_3d(spark, sf_dir):
    return _cells_3d(spark, sf_dir).select("vec_id", curves.z_column_nd(F.col("c"), 3, 4).alias("key"))


_CELL3 = "select vec_id, " + ", ".join(f"cast(greatest(0, least(15, floor((cast(embedding[{i}] as double)+4)*2))) as bigint) c{i}" for i in (1, 2, 3)) + " from embeddings"


def udf_cluster_of(spark, sf_dir):
    sqlfuncs.register_cluster_of(spark, _fixed_model())
    return view(spark, sf_dir, "shapes").selectExpr("id", "cluster_of(x, y) AS cluster_id")


def udtf_covered_cells(spark, sf_dir):
    sqlfuncs.register_covered_cells(spark)
    view(spark, sf_dir, "stations").createOrReplaceTempView("knnscope_stations")
    return spark.sql("select id, cx, cy from knnscope_stations, lateral covered_cells(x, y, 12.0D, 5.0D)")


def udtf_cluster_explain(spark, sf_dir):
    sqlfuncs.register_cluster_explain(spark, _fixed_model())
    view(spark, sf_dir, "shapes").createOrReplaceTempView("knnscope_points")
    return spark.sql("select id, mini_id, cluster_id from knnscope_points, lateral cluster_explain(x, y)")


def udaf_pair_indices(spark, sf_dir):
    rows = _labels(spark, sf_dir).select(F.col("pred").cast("string"), "truth")
    got = rows.groupBy().agg(sqlfuncs.rand_index_agg("pred", "truth").alias("r"))
    return got.selectExpr(f"{relational.snap('r', 6)} AS rand_index")


# --- streams over the events, cut into files
def _stream(spark, sf_dir, files: int = 4):
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events")
    events.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    return streaming.point_stream(spark, path, events.schema, files)


def _drained(spark, stream, mode="append"):
    return streaming.drain(stream, "q" + uuid.uuid4().hex, mode, f"{shared_dir(spark)}/cp-{uuid.uuid4().hex}")


def stream_assign(spark, sf_dir):
    s = _stream(spark, sf_dir).selectExpr("event_id AS id", "(event_id*7919)%1000/1.0D AS x", "(event_id*104729)%1000/1.0D AS y")
    return _drained(spark, streaming.assign_stream(s, _fixed_model())).select("id", "cluster_id")


def stream_tumbling(spark, sf_dir):
    return _drained(spark, streaming.window_counts(_stream(spark, sf_dir), "event_type", "1 day"), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


def stream_sliding(spark, sf_dir):
    return _drained(spark, streaming.window_counts(_stream(spark, sf_dir), "event_type", "2 days", "1 day"), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


def stream_session(spark, sf_dir):
    got = _drained(spark, streaming.session_counts(_stream(spark, sf_dir), "user_id", "6 hours"), "complete")
    return got.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("count").alias("events"))


def stream_dedup(spark, sf_dir):
    twice = _stream(spark, sf_dir)
    return _drained(spark, streaming.distinct_points(twice.unionByName(twice))).select("event_id")


def stream_leaf_state(spark, sf_dir):
    s = _stream(spark, sf_dir).withColumn("leaf", F.expr("event_id % 50"))
    return _drained(spark, streaming.leaf_drift(s, "leaf", 10), "update").groupBy("leaf").agg(F.max("n").alias("n"), F.max("dense").alias("dense"))


def stream_interval_join(spark, sf_dir):
    s = _stream(spark, sf_dir)
    p = s.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    c = s.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", "ts")
    got = streaming.interval_join(p, c, "user_id", "1 hour").select("p.event_id", "c.click_id")
    return _drained(spark, got)


def stream_over_rate(spark, sf_dir):
    return _drained(spark, streaming.over_rate(_stream(spark, sf_dir).select("ts"), 5), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


def queries() -> dict:
    found = {f.__name__: f for f in (
        knn_brute, join_knn, knn_radius, core_test_by_probe, crawl_box_points, density_probe_1d, leaf_tests_2d, cell_roundtrip,
        curve_runs_by_kind, tree_full_leaves, tree_split_vs_leaf, merge_adjacent, top_l_distance, components_small, assign_fixed_segments,
        assign_1d, attach_nearest_station, pair_counts, pair_counts_brute, index_rand_jaccard_fm, noise_modes, model2d_exhaustive,
        sample_uniform, sample_then_cluster, knn_distributed_model, join_range, join_asof, join_distance, agg_percentile, agg_approx_distinct,
        price_pivot, fn_array, fn_map, array_distance_3d, cells_3d, z_key_3d, udf_cluster_of, udtf_covered_cells, udtf_cluster_explain,
        udaf_pair_indices, stream_assign, stream_tumbling, stream_sliding, stream_session, stream_dedup, stream_leaf_state,
        stream_interval_join, stream_over_rate, service_round, lower_bounds_calls, model3d,
        model3d_exhaustive,
    )}
    found |= {
        "knn_grid": lambda s, d: _grid(s, d, "shapes", 14),
        "knn_k1": lambda s, d: _grid(s, d, "shapes", 1),
        "knn_filtered": lambda s, d: _grid(s, d, "listings", 10, "price between 100000 and 200000 and pri = '1-URGENT'"),
        "density_probe_all_k": lambda s, d: density_probe_1d(s, d, "all_k", 60),
        "segments_exhaustive_1d": lambda s, d: _segments(s, d, n_check=None),
        "grid_dbscan_edge": lambda s, d: grid.grid_dbscan(view(s, d, "shapes"), 16, 14, 4),
        "grid_dbscan_8": lambda s, d: grid.grid_dbscan(view(s, d, "shapes"), 16, 14, 8),
    }
    found |= {f"key_{k}": _keys(k) for k in curves.KINDS}
    found |= {f"segments_{s}_1d": (lambda a, d, s=s: _segments(a, d, strategy=s)) for s in ("walk", "skip", "bisect", "auto")}
    for name, (eps, n) in DBSCANS.items():
        run = dbscan.dbscan_1d if name == "line1d" else dbscan.dbscan
        found[f"dbscan_{name}"] = lambda s, d, f=run, v=name, e=eps, m=n: f(view(s, d, v), e, m)
    found |= {f"model2d_{c}": model2d(c) for c in curves.KINDS} | {"model2d_fixed": model2d("hilbert", False)}
    return found | workloads.WORKLOADS | live.WORKLOADS | live.EXHAUSTIVE


def oracle_sql() -> dict:
    line, count5 = _VIEW["line1d"], "cast(floor((x+0.0005e0)/5e0) as bigint)"
    runs = plain(relational.QUERIES["runs_dense_1d"])
    box = f"select id from {_VIEW['shapes']} s where x between 150 and 260 and y between 250 and 340"
    tree = _tree_sql()
    near = "(a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y)"
    s = _VIEW["stations"]
    observed = f"select cast(floor((x+0.0005e0)/64) as int) mini_id, id, x, y from {_VIEW['shapes']} s where lab <> 'error'"
    inside = f"select cx, cy, n, id, row_number() over (partition by cx, cy order by d2, id) r, d2, mx, my, x, y from (select c.cx, c.cy, c.n, p.id, p.x, p.y, (-0.0005e0+(c.cx+0.5e0)*16) mx, (-0.0005e0+(c.cy+0.5e0)*16) my, (p.x-(-0.0005e0+(c.cx+0.5e0)*16))*(p.x-(-0.0005e0+(c.cx+0.5e0)*16))+(p.y-(-0.0005e0+(c.cy+0.5e0)*16))*(p.y-(-0.0005e0+(c.cy+0.5e0)*16)) d2 from ({plain(relational.QUERIES['cells_2d'])}) c join {_VIEW['shapes']} p on p.x between (-0.0005e0+(c.cx+0.5e0)*16)-120 and (-0.0005e0+(c.cx+0.5e0)*16)+120 and p.y between (-0.0005e0+(c.cy+0.5e0)*16)-120 and (-0.0005e0+(c.cy+0.5e0)*16)+120) q"
    ranges20 = "select range_id, range_id*37.5e0 lo, range_id*37.5e0+50.25e0 hi from range(20) t(range_id)"
    fixed = " union all ".join(f"select {a} lo, {b} hi, {i} mini_id, {c} cluster_id" for i, (a, b, c) in enumerate(FIXED, 1))
    rand = _pairs_sql()
    found = {
        "knn_brute": _knn_sql("shapes", 14), "knn_grid": _knn_sql("shapes", 14), "knn_k1": _knn_sql("shapes", 1),
        "knn_filtered": _knn_sql("listings", 10, "price between 100000 and 200000 and pri = '1-URGENT'"),
        "join_knn": f"select qid, rank, id from (select a.id qid, b.id, row_number() over (partition by a.id order by {near}, b.id) rank from {s} a cross join {_VIEW['listings']} b) q where rank <= 3",
        "knn_radius": f"select qid, max(dist) radius from ({_knn_sql('shapes', 14)}) k group by qid",
        "core_test_by_probe": f"select a.id, count(*) >= 14 core from {_VIEW['shapes']} a join {_VIEW['shapes']} b on {near} <= 100 group by a.id",
        "crawl_box_points": box,
        "density_probe_1d": f"select c.cx, coalesce(n, 0) >= 60 dense from (select unnest(range(201)) cx) c left join (select {count5} cx, count(*) n from {line} l group by 1) g on g.cx = c.cx",
        "leaf_tests_2d": f"select cx, cy, n, count(*) filter (where r <= 14 and abs(x-mx) <= 8 and abs(y-my) <= 8) >= 14 in_cell, coalesce(max(d2) filter (where r = 14) <= 128, false) circumscribed, coalesce(max(d2) filter (where r = 14) <= 64, false) inscribed from ({inside}) i group by cx, cy, n",
        "density_probe_all_k": f"select c.cx, coalesce(n, 0) >= 60 dense from (select unnest(range(201)) cx) c left join (select {count5} cx, count(*) n from {line} l group by 1) g on g.cx = c.cx",
        "segments_exhaustive_1d": runs,
        "key_hilbert": _hilbert_sql(), "key_z": _z_sql(), "key_peano": _peano_sql(),
        "curve_runs_by_kind": " union all ".join(
            f"select '{k}' kind, count(*) runs from (select key from ({sql}) k group by key having count(*) >= 14) d where key - 1 not in (select key from ({sql}) k group by key having count(*) >= 14)"
            for k, sql in (("hilbert", _hilbert_sql()), ("z", _z_sql()), ("peano", _peano_sql()))
        ),
        "cell_roundtrip": _roundtrip_sql(),
        "lower_bounds_calls": f"with p as materialized (select id, x, y from {_VIEW['shapes']} v), n as (select count(*) n from p), d as (select count(*) n from ({plain(relational.DENSE)}) c), "
        f"c as (select count(*) n from (select a.id from p a join p b on {near} <= 100 group by a.id having count(*) >= 14) q) "
        "select 'all_points' bound, cast(ceil(n/14.0) as bigint) calls from n union all select 'dense_cells', n from d union all select 'core_points', cast(ceil(n/14.0) as bigint) from c",
        "stream_assign": _assign_sql("(select event_id id, cast((event_id*7919)%1000 as double) x, cast((event_id*104729)%1000 as double) y from events)"), "service_round": _knn_sql("shapes", 14, probes=_PROBE_SQL),
        "tree_full_leaves": tree,
        "tree_split_vs_leaf": f"select \"level\", case when state = 'split' then 'split' else 'leaf' end kind, count(*) calls from ({tree}) t group by 1, 2",
        "merge_adjacent": f"select a.cy, count(*) edges from ({plain(relational.DENSE)}) a join ({plain(relational.DENSE)}) b on a.cx = b.cx and a.cy = b.cy + 1 group by a.cy",
        "top_l_distance": f"select mini_a, mini_b, {relational.snap('avg(sqrt(d2))')} l_distance from (select a.mini_id mini_a, b.mini_id mini_b, {near} d2, row_number() over (partition by a.mini_id, b.mini_id order by {near}) r from ({observed}) a join ({observed}) b on a.mini_id < b.mini_id and {near} <= 1600) q where r <= 7 group by 1, 2",
        "components_small": _COMPONENTS.format(dense=_CODED, n="code", near=_EDGE) + "select id node, lab component from cc where id in (select u from e)",
        "grid_dbscan_edge": _grid_dbscan_sql(_EDGE), "grid_dbscan_8": _grid_dbscan_sql(_EIGHT),
        "assign_fixed_segments": _assign_sql(), "udf_cluster_of": _assign_sql(),
        "udtf_cluster_explain": f"select k.id, r.mini_id, r.cluster_id from ({_hilbert_sql()}) k join ({fixed}) r on k.key between r.lo and r.hi",
        "assign_1d": f"select p.id, r.lo cluster_id from {line} p join ({runs}) r on floor((p.x+0.0005e0)/5e0) between r.lo and r.hi",
        "attach_nearest_station": f"select id, cluster_id from (select a.id, case when b.id%10 < 6 then 0 else b.id%10 end cluster_id, row_number() over (partition by a.id order by {near}, b.id) r from {s} a cross join {s} b where a.id%7 = 0 and b.id%7 <> 0) q where r = 1",
        "pair_counts": rand, "pair_counts_brute": _brute_sql(),
        "index_rand_jaccard_fm": f"select {relational.snap('(a+b)/cast(a+b+c+d as double)', 6)} rand_index, {relational.snap('a/cast(a+c+d as double)', 6)} jaccard_index, {relational.snap('a/(sqrt(a+c)*sqrt(a+d))', 6)} fowlkes_mallows from ({rand}) x",
        "udaf_pair_indices": f"select {relational.snap('(a+b)/cast(a+b+c+d as double)', 6)} rand_index from ({rand}) x",
        "noise_modes": f"select 'pool' mode, * from ({rand}) x union all select 'drop', * from ({_pairs_sql('pred is not null and truth is not null')}) y union all select 'singleton', * from ({_pairs_sql('true', chr(63) + " <> 'none'")}) z",
        "model2d_exhaustive": _exhaustive_sql(),
        "join_range": f"select id, cast(range_id as int) range_id from {line} p join ({ranges20}) r on x >= lo and x <= hi",
        "join_asof": "select event_id, (select max(v.event_id) from events v where v.event_type = 'view' and v.user_id = e.user_id and v.ts = (select max(w.ts) from events w where w.event_type = 'view' and w.user_id = e.user_id and w.ts <= e.ts)) view_id_asof from events e where event_type = 'purchase'",
        "join_distance": f"select a.id a_id, b.id b_id from {s} a join {_VIEW['listings']} b on {near} <= 25",
        "agg_percentile": f"select reg, {relational.snap('quantile_cont(price, 0.5)', 1)} p50 from {_VIEW['listings']} l group by reg",
        "price_pivot": plain(relational.QUERIES["price_hist_pivot"]),
        "fn_array": "select vec_id, len(embedding) n, cast(embedding[1] as double) \"first\", len(list_filter(embedding, lambda v: v > 0)) positive from embeddings",
        "fn_map": "select doc_id, source, 2 n from documents",
        "array_distance_3d": f"select a.vec_id, {relational.snap('(cast(a.embedding[1] as double)-b.embedding[1])*(cast(a.embedding[1] as double)-b.embedding[1])+(cast(a.embedding[2] as double)-b.embedding[2])*(cast(a.embedding[2] as double)-b.embedding[2])+(cast(a.embedding[3] as double)-b.embedding[3])*(cast(a.embedding[3] as double)-b.embedding[3])', 4)} d2 from embeddings a cross join (select * from embeddings where vec_id = 1) b",
        "model3d_exhaustive": "with c as (select vec_id, floor((cast(embedding[1] as double)+4)*2) a, floor((cast(embedding[2] as double)+4)*2) b, floor((cast(embedding[3] as double)+4)*2) c from embeddings) "
        "select vec_id from (select vec_id, a, b, c, count(*) over (partition by a, b, c) n from c) d where n >= 4 and a between 0 and 15 and b between 0 and 15 and c between 0 and 15",
        "cells_3d": f"select c1 cx, c2 cy, c3 cz, count(*) n from ({_CELL3}) c group by 1, 2, 3",
        "z_key_3d": "select vec_id, " + " + ".join(f"((c{d + 1} >> {b}) & 1) * {2 ** (3 * b + 2 - d)}" for b in range(4) for d in range(3)) + f" as key from ({_CELL3}) c",
        "udtf_covered_cells": f"select id, cx, cy from {s} s, (select unnest(range(-5, 60)) cx) a, (select unnest(range(-5, 60)) cy) b where power(greatest(abs(cx*5-x), abs(cx*5+5-x)), 2) + power(greatest(abs(cy*5-y), abs(cy*5+5-y)), 2) < 144",
        "stream_tumbling": "select date_trunc('day', ts) \"start\", event_type, count(*) \"count\" from events group by 1, 2",
        "stream_sliding": "select s \"start\", event_type, count(*) \"count\" from (select date_trunc('day', ts) s, event_type from events union all select date_trunc('day', ts) - interval 1 day, event_type from events) w group by 1, 2",
        "stream_session": "select user_id, sum(new) sessions, count(*) events from (select user_id, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end new from events) a group by 1",
        "stream_dedup": "select event_id from events",
        "stream_leaf_state": "select event_id % 50 leaf, count(*) n, count(*) >= 10 dense from events group by 1",
        "stream_interval_join": "select p.event_id, c.event_id click_id from events p join events c on p.user_id = c.user_id and c.ts <= p.ts and c.ts >= p.ts - interval 1 hour where p.event_type = 'purchase' and c.event_type = 'click'",
        "stream_over_rate": "select date_trunc('hour', ts) \"start\", count(*) \"count\" from events group by 1 having count(*) > 5",
    }
    return found | live.oracle_sql() | {f"dbscan_{n}": _dbscan_sql(n, e, m) for n, (e, m) in DBSCANS.items()}
