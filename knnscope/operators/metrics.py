"""Agreement of two clusterings by pairs of points, from the table of label pairs; never by pairs of rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NOISE_MODES = ("pool", "drop", "singleton")


def pair_counts(df: DataFrame, pred: str = "pred", truth: str = "truth", noise: str = "pool") -> DataFrame:
    """One row ``a, b, c, d`` of DECIMAL(38,0): pairs together in both, in neither, only in ``pred``, only in ``truth``.

    NULL labels are noise: one more cluster (pool), left out if NULL in either (drop), or clusters of one each.
    """
    if noise not in NOISE_MODES:
        raise ValueError(f"noise must be one of {NOISE_MODES}")
    rows = df.select(F.col(pred).cast("string").alias("p"), F.col(truth).cast("string").alias("t"))
    if noise == "drop":
        rows = rows.dropna()
    table = rows.groupBy("p", "t").agg(F.count(F.lit(1)).alias("n"))
    big = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("decimal(38,0)")
    two = lambda c: (F.col(c).cast("decimal(38,0)") * (F.col(c) - 1) / 2).cast("decimal(38,0)")
    keep = lambda *c: F.lit(True) if noise != "singleton" else sum_not_null(*c)
    by_p = table.groupBy("p").agg(F.sum("n").alias("n")).filter(keep("p"))
    by_t = table.groupBy("t").agg(F.sum("n").alias("n")).filter(keep("t"))
    total = table.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select(two("n").alias("all"))
    both = table.filter(keep("p", "t")).agg(big(two("n")).alias("a"))
    joined = both.crossJoin(by_p.agg(big(two("n")).alias("ac"))).crossJoin(by_t.agg(big(two("n")).alias("ad"))).crossJoin(total)
    return joined.selectExpr("a", "CAST(all - ac - ad + a AS DECIMAL(38,0)) AS b", "CAST(ac - a AS DECIMAL(38,0)) AS c", "CAST(ad - a AS DECIMAL(38,0)) AS d")


def sum_not_null(*columns: str):
    out = F.lit(True)
    for c in columns:
        out = out & F.col(c).isNotNull()
    return out


def indices(counts: DataFrame) -> DataFrame:
    """``rand_index, jaccard_index, fowlkes_mallows``; NULL where a denominator is 0."""
    a, b, c, d = (F.col(x).cast("double") for x in "abcd")
    return counts.select(
        F.try_divide(a + b, a + b + c + d).alias("rand_index"),
        F.try_divide(a, a + c + d).alias("jaccard_index"),
        F.try_divide(a, F.sqrt(a + c) * F.sqrt(a + d)).alias("fowlkes_mallows"),
    )


def agreement(df: DataFrame, pred: str = "pred", truth: str = "truth", noise: str = "pool") -> DataFrame:
    return indices(pair_counts(df, pred, truth, noise))


def pair_counts_brute(df: DataFrame, ident: str = "id", pred: str = "pred", truth: str = "truth") -> DataFrame:
    """The same by comparing all pairs of rows; for tests on a few rows."""
    a = df.select(F.col(ident).alias("i"), F.col(pred).alias("p1"), F.col(truth).alias("t1"))
    b = df.select(F.col(ident).alias("j"), F.col(pred).alias("p2"), F.col(truth).alias("t2"))
    p, t = F.col("p1").eqNullSafe(F.col("p2")), F.col("t1").eqNullSafe(F.col("t2"))
    n = lambda cond, name: F.coalesce(F.sum(cond.cast("long")), F.lit(0)).cast("decimal(38,0)").alias(name)
    return a.join(b, F.col("i") < F.col("j")).agg(n(p & t, "a"), n(~p & ~t, "b"), n(p & ~t, "c"), n(~p & t, "d"))


def agreement_arrays(pred, truth) -> dict[str, float | None]:
    """The three indices of two sequences of labels on the driver, for benchmark sets."""
    from collections import Counter

    return agreement_counts(Counter(zip(pred, truth)))


def agreement_counts(table: dict) -> dict[str, float | None]:
    """The same from the number of rows of each pair of labels."""
    two = lambda counts: sum(n * (n - 1) // 2 for n in counts.values())
    by_pred, by_truth = {}, {}
    for (p, t), m in table.items():
        by_pred[p], by_truth[t] = by_pred.get(p, 0) + m, by_truth.get(t, 0) + m
    a, ac, ad, n = two(table), two(by_pred), two(by_truth), sum(table.values())
    total = n * (n - 1) // 2
    return {
        "rand_index": (total - ac - ad + 2 * a) / total if total else None,
        "jaccard_index": a / (ac + ad - a) if ac + ad - a else None,
        "fowlkes_mallows": a / (ac * ad) ** 0.5 if ac and ad else None,
    }
