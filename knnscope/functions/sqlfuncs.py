"""SQL functions round a model: a scalar and two table functions, and an aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from knnscope.operators.curve2d import ClusterModel


def register_cluster_of(spark: SparkSession, model: ClusterModel, name: str = "cluster_of") -> None:
    """``cluster_of(x, y)`` for SQL: the cluster or NULL, in Arrow batches. ``model.assign`` is the plan without Python."""
    light = ClusterModel(model.kind, model.domain, model.order, model.segments)

    @F.pandas_udf("int")
    def cluster_of(x: pd.Series, y: pd.Series) -> pd.Series:
        bad = x.isna() | y.isna()
        got = light.assign_arrays(x.fillna(-1e300).clip(-1e15, 1e15).to_numpy(), y.fillna(-1e300).clip(-1e15, 1e15).to_numpy())
        return pd.Series(got).astype("Int32").mask((pd.Series(got) == 0) | bad.reset_index(drop=True))

    spark.udf.register(name, cluster_of)


class CoveredCells:
    """The cells wholly inside a ball: what an answer of that radius tells all about."""

    def eval(self, qx: float, qy: float, r: float, side: float):
        lo, hi = (int(np.floor((v - r) / side)) for v in (qx, qy)), (int(np.floor((v + r) / side)) for v in (qx, qy))
        (x0, y0), (x1, y1) = lo, hi
        for cx in range(x0, x1 + 1):
            for cy in range(y0, y1 + 1):
                dx = max(abs(cx * side - qx), abs((cx + 1) * side - qx))
                dy = max(abs(cy * side - qy), abs((cy + 1) * side - qy))
                if dx * dx + dy * dy < r * r:
                    yield cx, cy


def register_covered_cells(spark: SparkSession, name: str = "covered_cells") -> None:
    spark.udtf.register(name, F.udtf(CoveredCells, returnType="cx bigint, cy bigint"))


def register_cluster_explain(spark: SparkSession, model: ClusterModel, name: str = "cluster_explain") -> None:
    """``cluster_explain(x, y)``: the number of the mini-cluster and the cluster of a place; no row for noise."""
    light = ClusterModel(model.kind, model.domain, model.order, [(lo, hi, i) for i, (lo, hi, _) in enumerate(model.segments, 1)])
    final = [c for _, _, c in model.segments]

    @F.udtf(returnType="mini_id int, cluster_id int")
    class ClusterExplain:
        def eval(self, x: float, y: float):
            mini = int(light.assign_arrays([x], [y])[0]) if x is not None and y is not None else 0
            if mini:
                yield mini, final[mini - 1]

    spark.udtf.register(name, ClusterExplain)


def rand_index_agg(pred, truth):
    """The Rand index of a group as an aggregate; for groups that fit a task (the plan of ``metrics`` has no limit)."""
    from knnscope.operators.metrics import agreement_arrays

    @F.pandas_udf("double")
    def rand_index(p: pd.Series, t: pd.Series) -> float:
        got = agreement_arrays(p.fillna("").tolist(), t.fillna("").tolist())["rand_index"]
        return float("nan") if got is None else got

    return rand_index(pred, truth)
