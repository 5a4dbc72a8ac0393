"""The experiments on live data: a service of each site's k is clustered under a budget, and every report is about the clusters
that the model finds. Each report is a function of labelled points, so that the same report on exhaustive labels (components of
dense cells, which SQL can give) has an oracle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.io import materialize, table
from knnscope.operators import grid
from knnscope.operators.curve2d import ClusterModel, curve_cluster_2d
from knnscope.operators.curvetree import centres, smallest_cells, weights_from_counts
from knnscope.operators.dbscan import attach_nearest
from knnscope.operators.service import Budget, CountedKnnService, MemoryKnnService
from knnscope.plans.relational import snap
from knnscope.sources.views import VIEWS, plain, view

#: Published k, minPts and number of points; here the square, the smallest side, the budget, and the distance for merging.
SITES = {
    "photos": {"k": 600, "min_pts": 600, "of": 117_875, "square": (-0.0005, -0.0005, 1024.0), "side": 32.0, "budget": 400, "merge": 16.0},
    "listings_a": {"k": 10, "min_pts": 10, "of": 12_250, "square": (-0.0005, -0.0005, 1024.0), "side": 32.0, "budget": 600, "merge": 20.0},
    "listings_b": {"k": 200, "min_pts": 10, "of": 12_250, "square": (-0.0005, -0.0005, 1024.0), "side": 32.0, "budget": 600, "merge": 20.0},
    "stations": {"k": 20, "min_pts": 3, "of": 350, "square": (-0.0005, -0.0005, 128.0), "side": 8.0, "budget": 150, "merge": 8.0},
}
#: Points of a site that are asked on the driver; more stay distributed.
LIMIT = 100_000
#: Clusters that the reports show on their own.
SHOWN = 100


def at_size(site: str, n: int) -> tuple[int, int]:
    """k and minPts for n points: minPts in proportion, at least the published one of a set that small, and k as many times as much."""
    p = SITES[site]
    min_pts = max(3, round(p["min_pts"] * n / p["of"]))
    return max(p["k"], round(p["k"] / p["min_pts"] * min_pts)), min_pts


def site_points(spark: SparkSession, sf_dir: str, site: str) -> DataFrame:
    """The points of a site; both sites of listings lack some that the other has."""
    if site.startswith("listings"):
        return view(spark, sf_dir, "listings").filter("id % 7 <> 0" if site == "listings_a" else "id % 7 <> 1")
    return view(spark, sf_dir, site)


def prior_of_counts(spark: SparkSession, sf_dir: str):
    """External knowledge: customers of each nation, as counts at the places where the nation's listings lie on average."""
    at = view(spark, sf_dir, "listings").groupBy("nat").agg(F.avg("x").alias("x"), F.avg("y").alias("y"))
    units = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nat")).agg(F.count(F.lit(1)).alias("w"))
    return weights_from_counts([(r.x, r.y, r.w) for r in at.join(units, "nat").orderBy("nat").collect()], 40.0)  # one row a nation


def fit(spark: SparkSession, sf_dir: str, site: str, seed: int = 1) -> tuple[ClusterModel, DataFrame]:
    """The model of a site, and its points with ``cluster_id``."""
    p = SITES[site]
    points = materialize(site_points(spark, sf_dir, site), site)
    n = points.count()
    k, min_pts = at_size(site, n)
    asked = points.select("id", "x", "y")
    if n <= LIMIT:
        service = MemoryKnnService(asked, k, Budget(p["budget"]))
    else:  # k grows with the points, so answers come as counts by the tree's cells
        service = CountedKnnService(asked, k, centres(p["square"], p["side"]), smallest_cells(p["square"], p["side"]), [min_pts], Budget(p["budget"]))
    prior = prior_of_counts(spark, sf_dir) if site.startswith("listings") else None
    model = curve_cluster_2d(
        service, p["square"], p["merge"], min_pts, p["side"], merge_threshold=p["merge"], seed=seed, n_check=2,
        strategy="bisect", seed_policy="prior" if prior else "leaf", prior=prior,
    )
    return model, materialize(model.assign(points), "labelled")


def exhaustive(spark: SparkSession, sf_dir: str, site: str) -> DataFrame:
    """The same labels without a budget and with every smallest cell known: components of dense cells that share an edge."""
    p, points = SITES[site], site_points(spark, sf_dir, site)
    _, min_pts = at_size(site, points.count())
    cells = grid.grid_dbscan(points, p["side"], min_pts).select("cx", "cy", "cluster_id")
    return grid.cell_of(points, p["side"]).join(cells, ["cx", "cy"], "left").drop("cx", "cy")


# --- reports
def top_tags(labelled: DataFrame, most: int = 3) -> DataFrame:
    """The most frequent tags of each cluster and its size."""
    tags = labelled.filter("cluster_id IS NOT NULL").select("cluster_id", F.regexp_extract("props", r'"k": *([0-9]+)', 1).alias("tag"))
    counts = tags.groupBy("cluster_id", "tag").agg(F.count(F.lit(1)).alias("n"))
    return counts.selectExpr("*", "row_number() over (partition by cluster_id order by n desc, tag) AS r").filter(F.col("r") <= most)


def prices(labelled: DataFrame) -> DataFrame:
    """Number, mean and spread of the prices of each cluster of at least ``SHOWN`` listings; the smaller ones together (-1)."""
    sizes = labelled.filter("cluster_id IS NOT NULL").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("size"))
    grouped = labelled.join(F.broadcast(sizes), "cluster_id").withColumn("grp", F.expr(f"CASE WHEN size >= {SHOWN} THEN cluster_id ELSE -1 END"))
    return grouped.groupBy("grp").agg(
        F.count(F.lit(1)).alias("n"), F.expr(snap("avg(price)", 1)).alias("mean_price"), F.expr(snap("stddev(price)", 1)).alias("sd_price")
    )


def price_histogram(labelled: DataFrame, width: int = 50_000) -> DataFrame:
    """Listings by bin of price and cluster, small clusters together (-1)."""
    sizes = labelled.filter("cluster_id IS NOT NULL").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("size"))
    grouped = labelled.join(F.broadcast(sizes), "cluster_id").withColumn("grp", F.expr(f"CASE WHEN size >= {SHOWN} THEN cluster_id ELSE -1 END"))
    return grouped.groupBy(F.floor(F.col("price") / width).alias("bin"), "grp").agg(F.count(F.lit(1)).alias("n"))


def agreement_of_sites(a: DataFrame, b: DataFrame) -> DataFrame:
    """For what both sites list: how many are in which pair of clusters."""
    left, right = a.select("id", F.col("cluster_id").alias("cluster_a")), b.select("id", F.col("cluster_id").alias("cluster_b"))
    return left.join(right, "id").groupBy("cluster_a", "cluster_b").agg(F.count(F.lit(1)).alias("n"))


def completed(labelled: DataFrame) -> DataFrame:
    """Stations with those that the service lacks put into the cluster of the nearest clustered one."""
    known = labelled.filter("id % 7 <> 0 AND cluster_id IS NOT NULL").select("id", "x", "y", "cluster_id")
    lacking = labelled.filter("id % 7 = 0")
    return known.select("id", "cluster_id").unionByName(attach_nearest(lacking, known).select("id", "cluster_id"))


def hours(clusters: DataFrame, events: DataFrame) -> DataFrame:
    """Rentals by hour of each cluster, and their share of the cluster's busiest hour."""
    rents = events.select(F.col("user_id").alias("id"), F.hour("ts").alias("h")).join(clusters, "id")
    counts = rents.groupBy("cluster_id", "h").agg(F.count(F.lit(1)).alias("n"))
    return counts.selectExpr("cluster_id", "h", "n", f"{snap('n / cast(max(n) over (partition by cluster_id) as double)')} AS share")


# --- queries
def on_model(site: str, report):
    return lambda spark, sf_dir: report(fit(spark, sf_dir, site)[1])


def on_exhaustive(site: str, report):
    return lambda spark, sf_dir: report(exhaustive(spark, sf_dir, site))


def sites_agree(labels):
    return lambda spark, sf_dir: agreement_of_sites(labels(spark, sf_dir, "listings_a"), labels(spark, sf_dir, "listings_b"))


def station_hours(labels):
    return lambda spark, sf_dir: hours(completed(labels(spark, sf_dir, "stations")), table(spark, sf_dir, "events"))


def summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a site: calls, rounds, mini-clusters, clusters, and how many points are in one."""
    rows = []
    for site in SITES:
        model, labelled = fit(spark, sf_dir, site)
        s = model.summary()
        inside, n = labelled.agg(F.count("cluster_id"), F.count(F.lit(1))).first()
        rows.append((site, s["calls"], s["rounds"], s["mini_clusters"], s["clusters"], inside, n))
    return spark.createDataFrame(rows, "site string, calls int, rounds int, mini_clusters int, clusters int, clustered long, points long")


def _model_labels(spark, sf_dir, site):
    return fit(spark, sf_dir, site)[1]


WORKLOADS = {
    "w_sites": summary, "w_photos": on_model("photos", top_tags), "w_listings_a": on_model("listings_a", prices),
    "w_listings_a_histogram": on_model("listings_a", price_histogram), "w_listings_b": on_model("listings_b", prices),
    "w_listings_agreement": sites_agree(_model_labels), "w_stations": station_hours(_model_labels),
}
EXHAUSTIVE = {
    "photos_tags_by_cluster": on_exhaustive("photos", top_tags), "listings_prices_by_cluster": on_exhaustive("listings_a", prices),
    "listings_histogram_by_cluster": on_exhaustive("listings_a", price_histogram), "listings_agreement_by_cluster": sites_agree(exhaustive),
    "stations_hours_by_cluster": station_hours(exhaustive),
}


def _labels_sql(name: str, site: str) -> str:
    """Tables of DuckDB SQL that end in ``name``: the points of a site with their exhaustive clusters."""
    p = SITES[site]
    where = {"listings_a": "where id%7 <> 0", "listings_b": "where id%7 <> 1"}.get(site, "")
    source = plain(VIEWS["listings" if site.startswith("listings") else site])
    cell = "cast(floor(({c}+0.0005e0)/{s}e0) as bigint)"
    return (
        f"{name}p as materialized (select *, {cell.format(c='x', s=p['side'])} cx, {cell.format(c='y', s=p['side'])} cy from ({source}) v {where}), "
        f"{name}d as materialized (select cx, cy, cx*4294967296+cy code from {name}p group by cx, cy "
        f"having count(*) >= (select greatest(3, round({p['min_pts']}*count(*)/{p['of']}e0)) from {name}p)), "
        f"{name}e as materialized (select a.code u, b.code v from {name}d a join {name}d b on abs(a.cx-b.cx)+abs(a.cy-b.cy) = 1), "
        f"{name}c(id, lab) using key (id) as (select code, code from {name}d union (select e.v, min(c.lab) from {name}c c join {name}e e on c.id = e.u "
        f"join recurring.{name}c r on r.id = e.v where c.lab < r.lab group by e.v)), "
        f"{name} as materialized (select p.*, c.lab cluster_id from {name}p p left join {name}d d on p.cx = d.cx and p.cy = d.cy left join {name}c c on c.id = d.code)"
    )


def oracle_sql() -> dict[str, str]:
    grouped = f"z as (select cluster_id, count(*) size from a where cluster_id is not null group by 1), g as (select a.*, case when size >= {SHOWN} then a.cluster_id else -1 end grp from a join z on z.cluster_id = a.cluster_id)"
    a, station = _labels_sql("a", "listings_a"), _labels_sql("s", "stations")
    return {
        "photos_tags_by_cluster": f"with recursive {_labels_sql('a', 'photos')} select * from (select cluster_id, tag, n, row_number() over (partition by cluster_id order by n desc, tag) r from "
        "(select cluster_id, regexp_extract(props, '\"k\": *([0-9]+)', 1) tag, count(*) n from a where cluster_id is not null group by 1, 2) x) y where r <= 3",
        "listings_prices_by_cluster": f"with recursive {a}, {grouped} select grp, count(*) n, {snap('avg(price)', 1)} mean_price, {snap('stddev(price)', 1)} sd_price from g group by grp",
        "listings_histogram_by_cluster": f"with recursive {a}, {grouped} select cast(floor(price/50000) as bigint) bin, grp, count(*) n from g group by 1, 2",
        "listings_agreement_by_cluster": f"with recursive {a}, {_labels_sql('b', 'listings_b')} select a.cluster_id cluster_a, b.cluster_id cluster_b, count(*) n from a join b on a.id = b.id group by 1, 2",
        "stations_hours_by_cluster": f"with recursive {station}, k as (select id, x, y, cluster_id from s where id%7 <> 0 and cluster_id is not null), "
        "m as (select id, cluster_id from (select s.id, k.cluster_id, row_number() over (partition by s.id order by (s.x-k.x)*(s.x-k.x)+(s.y-k.y)*(s.y-k.y), k.id) r from s cross join k where s.id%7 = 0) q where r = 1), "
        "f as (select id, cluster_id from k union all select * from m), n as (select cluster_id, hour(ts) h, count(*) n from f join events e on e.user_id = f.id group by 1, 2) "
        f"select cluster_id, h, n, {snap('n / cast(max(n) over (partition by cluster_id) as double)')} share from n",
    }
