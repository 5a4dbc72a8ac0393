"""The budgeted two-dimensional clusterer and its product, a function from places to clusters."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.functions import curves
from knnscope.io import materialize
from knnscope.operators import merge as merging
from knnscope.operators.curvetree import CurveTree
from knnscope.operators.pursuit import Pursuit
from knnscope.operators.service import LEDGER, CountedKnnService

LEAVES = "level int, lo_key long, hi_key long, x double, y double, side double, state string"


@dataclass
class ClusterModel:
    """Ranges of curve keys and their final clusters, numbered from 1 by smallest key."""

    kind: str
    domain: tuple[float, float, float]
    order: int
    segments: list[tuple[int, int, int]]  # first key, last key, cluster
    info: dict = field(default_factory=dict)
    observed: dict = field(default_factory=dict, repr=False)
    tree: CurveTree | None = field(default=None, repr=False)
    calls: list = field(default_factory=list, repr=False)

    def assign_arrays(self, xs, ys) -> np.ndarray:
        """Cluster numbers; 0 is noise."""
        n = curves.base(self.kind) ** self.order
        cx = np.floor((np.asarray(xs, float) - self.domain[0]) / (self.domain[2] / n)).astype(np.int64)
        cy = np.floor((np.asarray(ys, float) - self.domain[1]) / (self.domain[2] / n)).astype(np.int64)
        ok = (cx >= 0) & (cx < n) & (cy >= 0) & (cy < n)
        out = np.zeros(len(cx), np.int64)
        if not self.segments or not ok.any():
            return out
        seg = np.array(sorted(self.segments))
        key = curves.keys(self.kind, cx[ok], cy[ok], self.order)
        at = np.searchsorted(seg[:, 0], key, side="right") - 1
        hit = (at >= 0) & (key <= seg[np.maximum(at, 0), 1])
        out[np.flatnonzero(ok)[hit]] = seg[at[hit], 2]
        return out

    def key(self, x: str | Column = "x", y: str | Column = "y") -> Column:
        x, y = (F.col(c).cast("double") if isinstance(c, str) else c for c in (x, y))
        n = curves.base(self.kind) ** self.order
        cx, cy = curves.cell_columns(x, y, self.domain, n)
        inside = (cx >= 0) & (cx < n) & (cy >= 0) & (cy < n)
        return F.when(inside, curves.key_column(self.kind, cx, cy, self.order))

    def table(self, spark: SparkSession) -> DataFrame:
        schema = "lo_key long, hi_key long, cluster_id int"
        return spark.createDataFrame([(int(a), int(b), int(c)) for a, b, c in self.segments], schema)

    def assign(self, df: DataFrame, x: str = "x", y: str = "y", name: str = "cluster_id") -> DataFrame:
        """``df`` with the cluster of each row, or NULL: no shuffle, one broadcast of a table as large as the calls paid for.

        Ranges become an equality: a range is entered under every coarse prefix that it meets, a row looks up its own.
        """
        spark, fan = df.sparkSession, curves.base(self.kind) ** 2
        level = min(self.order, 5 if fan == 4 else 3)
        width = fan ** (self.order - level)
        rows = [(p, int(a), int(b), int(c)) for a, b, c in self.segments for p in range(a // width, b // width + 1)]
        ranges = spark.createDataFrame(rows, "_p long, _lo long, _hi long, _c int").groupBy("_p").agg(
            F.collect_list(F.struct("_lo", "_hi", "_c")).alias("_r")
        )
        keyed = df.withColumn("_k", self.key(x, y)).withColumn("_p", F.floor(F.col("_k") / width).cast("long"))
        joined = keyed.join(F.broadcast(ranges), "_p", "left")
        mine = F.filter("_r", lambda r: (r["_lo"] <= F.col("_k")) & (F.col("_k") <= r["_hi"]))
        return joined.withColumn(name, F.get(mine, 0)["_c"]).select(*df.columns, name)

    def assign_range_join(self, df: DataFrame, x: str = "x", y: str = "y") -> DataFrame:
        """The same by a plain range condition, which Spark runs as a nested loop; kept to compare plans and results."""
        ranges = F.broadcast(self.table(df.sparkSession))
        keyed = df.withColumn("_k", self.key(x, y))
        return keyed.join(ranges, F.col("_k").between(F.col("lo_key"), F.col("hi_key")), "left").drop("_k", "lo_key", "hi_key")

    def summary(self) -> dict:
        return self.info | {"mini_clusters": len(self.segments), "clusters": len({c for _, _, c in self.segments})}

    def leaves(self, spark: SparkSession) -> DataFrame:
        """The leaves of the tree."""
        return spark.createDataFrame(self.tree.table() if self.tree else [], LEAVES)

    def minis(self, spark: SparkSession) -> DataFrame:
        """The many-to-one map: mini-clusters with their ranges, the cluster of each and its mapping error: the largest side of a
        leaf in the range over the smallest there can be."""
        errors = self.mapping_errors()
        rows = [(i, int(a), int(b), int(c), errors.get(i)) for i, (a, b, c) in enumerate(sorted(self.segments))]
        return spark.createDataFrame(rows, "mini_id int, lo_key long, hi_key long, cluster_id int, mapping_error double")

    def mapping_errors(self) -> dict[int, float]:
        """By how much the curve may put far points together: for each mini-cluster the side of its largest leaf over the smallest side."""
        if self.tree is None:
            return {}
        smallest, found = self.domain[2] / curves.base(self.kind) ** self.order, {}
        for i, (lo, hi, _) in enumerate(sorted(self.segments)):
            inside = self.tree.keys[self.tree.rank(lo) : self.tree.rank(hi) + 1]
            found[i] = max(self.tree.boxes[k][2] for k in inside) / smallest
        return found

    def seen(self, spark: SparkSession) -> DataFrame:
        """The observed points of each mini-cluster, which merging compared."""
        rows = [(int(m), float(x), float(y)) for m, places in self.observed.items() for x, y in places]
        return spark.createDataFrame(rows, "mini_id int, x double, y double")

    def ledger(self, spark: SparkSession) -> DataFrame:
        """The calls that the model was bought with."""
        return spark.createDataFrame([tuple(c.values()) for c in self.calls], LEDGER)

    def save(self, spark: SparkSession, path: str) -> None:
        """Everything: ranges, leaves, mini-clusters, observed points and the ledger, each as a table."""
        self.table(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/segments")
        for name, part in (("leaves", self.leaves), ("minis", self.minis), ("observed", self.seen), ("ledger", self.ledger)):
            part(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/{name}")
        about = {"kind": self.kind, "domain": list(self.domain), "order": self.order, "info": self.info}
        spark.createDataFrame([(json.dumps(about),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/about")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> ClusterModel:
        """The function, with its observed points and ledger; the other tables stay where they are."""
        about = json.loads(spark.read.text(f"{path}/about").first()[0])
        rows = spark.read.parquet(f"{path}/segments").orderBy("lo_key").collect()  # as many as calls paid for
        observed: dict = {}
        for r in spark.read.parquet(f"{path}/observed").collect():  # at most k points a call
            observed.setdefault(r.mini_id, []).append((r.x, r.y))
        calls = [r.asDict() for r in spark.read.parquet(f"{path}/ledger").orderBy("qid").collect()]
        return cls(
            about["kind"], tuple(about["domain"]), about["order"], [tuple(r) for r in rows], about["info"],
            {m: np.array(v) for m, v in observed.items()}, None, calls,
        )


def curve_cluster_2d(
    service, domain, eps: float, min_pts: int, min_side: float, curve: str = "hilbert", adaptive: bool = True,
    fanout: int | None = None, n_check: int | None = 5, merge: str = "top_l", l: int | None = None,  # noqa: E741
    merge_threshold: float | None = None, strategy: str = "auto", on_split: str = "restart", seeds_per_round: int = 1,
    seed: int = 42, infer: bool = True, split_threshold: int | None = None, leaf_test: str = "in_cell",
    seed_policy: str = "leaf", prior=None, recompute: bool = False, init_level: int = 1,
) -> ClusterModel:
    """Find mini-clusters on the curve until the service's budget is used up, merge them, and return the function.

    With a service that counts answers by the tree's cells, what was observed stays a table, and merging compares it there.
    """
    tree = CurveTree(domain, min_side, min_pts, curve, fanout, adaptive, init_level, split_threshold, leaf_test, infer, seed_policy, prior, service)
    checks = tree.width if n_check is None else n_check
    found = Pursuit(tree, service, checks, strategy, seeds_per_round, seed, on_split).run()
    segments = sorted((lo, tree.last_key(tree.current(hi))) for lo, hi in found.segments)
    joined: list[tuple[int, int]] = []
    for lo, hi in segments:  # two searches may have met in one run
        if joined and lo <= joined[-1][1]:
            joined[-1] = (joined[-1][0], max(joined[-1][1], hi))
        else:
            joined.append((lo, hi))
    counts = isinstance(service, CountedKnnService)
    if counts:
        seen, n_seen, observed = service.seen_in(service.points.select("id", "x", "y")), None, {}
    else:
        ids = np.array(sorted(service.seen), np.int64)
        places = np.array([service.seen[i] for i in ids.tolist()], float).reshape(-1, 2)
        keys, n_seen = tree.locate(places[:, 0], places[:, 1]), len(ids)
        observed = {i: places[(keys >= lo) & (keys <= hi)] for i, (lo, hi) in enumerate(joined)}
    if merge == "top_l" and counts:
        if recompute:
            raise ValueError("counted answers are merged once")
        at = ClusterModel(curve, tuple(domain), tree.levels, [(lo, hi, i) for i, (lo, hi) in enumerate(joined)])
        held = at.assign(seen, name="mini").filter("mini IS NOT NULL").select("mini", "x", "y")
        pairs, edges = merging.top_l_table(materialize(held, "observed"), list(range(len(joined))), l or max(1, min_pts // 2), merge_threshold or eps)
    elif merge == "top_l":
        pairs, edges = merging.top_l(observed, l or max(1, min_pts // 2), merge_threshold or eps, recompute)
    elif merge == "adjacent":
        pairs = {}
        boxes = {
            i: np.array([tree.boxes[k] for k in tree.keys[tree.rank(lo) : tree.rank(hi) + 1]]) for i, (lo, hi) in enumerate(joined)
        }
        edges = merging.adjacent(boxes)
    elif merge == "none":
        pairs, edges = {}, []
    else:
        raise ValueError("merge must be top_l, adjacent or none")
    roots = merging.union_find(range(len(joined)), edges)
    number = {r: n for n, r in enumerate(sorted(set(roots.values())), 1)}
    info = {
        "h": len(joined), "calls": service.budget.used, "rounds": service.rounds, "leaves": tree.size(), "internal": tree.internal,
        "observed": n_seen, "checks_failed": found.checks_failed, "wasted": found.wasted, "pairs_compared": len(pairs),
    }
    final = [(lo, hi, number[roots[i]]) for i, (lo, hi) in enumerate(joined)]
    return ClusterModel(curve, tuple(domain), tree.levels, final, info, observed, tree, service.calls)
