"""Near-duplicate embeddings: an exact metric range join on the unit sphere.

Cosine of at least c means a Euclidean distance of at most eps = sqrt(2 - 2c) between unit vectors. Each label has pivots
of its own, about a quarter of the square root of the number of its vectors, spread out over a sample of them by taking the farthest next; each vector
is at home in the cell of its nearest pivot. Of two cells the one of the smaller number is where their vectors meet: y
at home in q is replicated into p < q unless the triangle inequality rules out that any x at home in p is within eps. It
does so in three ways: y is farther than eps from the plane between p and q, (d(y,p)^2 - d(y,q)^2) / (2 d(p,q)) > eps;
y is outside the ball of p's cell, d(y,p) > R(p) + eps; or inside its hollow, d(y,p) < r(p) - eps, where r and R are the least and
greatest distance from p of what is at home there. So a tight group of near copies is a small ball that few others enter.

Cells join independently. A cell is dealt out in blocks of bounded size, homes against members, so a large cell becomes
more tasks, not a larger one; a block counts links and emits a spanning forest of them, never its pairs.

Equal vectors of a label are one vector with a multiplicity from the start.

Defined cases: a vector that is NULL, empty, zero, or has NULL or non-finite components, or whose id or label is NULL, links
with nothing; vectors of different dimensions aren't compared; rows of one id count as further vectors; extra columns
are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.components import connected
from knnscope.io import materialize
#: Vectors per block on either side, and per task that looks for cells.
BLOCK, ROWS = 2048, 8192
#: Of how many sampled vectors one becomes a pivot.
SAMPLED = 8
NEVER = "isnan(x) OR x = double('Infinity') OR x = double('-Infinity') OR x IS NULL"


def distinct_vectors(vectors: DataFrame) -> DataFrame:
    """``label, embedding, rep, times``: each vector that can link, once; rep is its smallest id."""
    usable = vectors.filter(
        F.col("label").isNotNull() & F.col("embedding").isNotNull() & F.col("vec_id").isNotNull()
    ).filter(f"size(embedding) > 0 AND NOT exists(embedding, x -> {NEVER}) AND exists(embedding, x -> x <> 0)")
    return usable.groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("times"))


def spread_out(sample: np.ndarray, n: int) -> np.ndarray:
    """Places of n rows of unit vectors: the first, then always the one farthest from those chosen."""
    chosen, near = [0], 2 - 2 * sample @ sample[0]
    while len(chosen) < min(n, len(sample)):
        i = int(near.argmax())
        if near[i] <= 1e-12:
            break
        chosen.append(i)
        near = np.minimum(near, 2 - 2 * sample @ sample[i])
    return np.array(chosen)


def unit(rows: pd.Series) -> np.ndarray:
    x = np.stack(rows.to_numpy()).astype(float)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def choose_pivots(reps: DataFrame) -> DataFrame:
    """``label, dim, cell, pivot`` for all labels and dimensions. What is drawn grows with the root of a label."""
    sizes = reps.groupBy("label", "dim").agg(F.ceil(F.sqrt(F.count(F.lit(1)).cast("double")) / 4).cast("int").alias("want"), F.count(F.lit(1)).alias("of"))
    unit_hash = F.pmod(F.xxhash64("rep", F.lit(3)), F.lit(1 << 30)) / float(1 << 30)
    # every label's smallest id is drawn, so that none is without a pivot
    first = reps.groupBy("label", "dim").agg(F.min("rep").alias("rep"), F.lit(True).alias("least"))
    drawn = reps.join(sizes, ["label", "dim"]).join(first, ["label", "dim", "rep"], "left")
    drawn = drawn.filter(F.col("least") | (unit_hash * F.col("of") < SAMPLED * F.col("want")))

    def choose(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("rep")
        x = unit(group["embedding"])
        at = spread_out(x, int(group["want"].iloc[0]))
        return pd.DataFrame({
            "label": group["label"].iloc[at].to_numpy(), "dim": group["dim"].iloc[at].to_numpy(), "cell": np.arange(len(at)), "pivot": list(x[at]),
        })

    return drawn.select("label", "dim", "rep", "embedding", "want").groupBy("label", "dim").applyInPandas(
        choose, "label long, dim int, cell int, pivot array<double>"
    )


def with_pivots(reps: DataFrame, pivots: DataFrame, kernel, schema: str) -> DataFrame:
    """``kernel(vectors, pivots)`` on about ``ROWS`` vectors of a label at a time, with all pivots of the label."""
    parts = reps.groupBy("label", "dim").agg(F.ceil(F.count(F.lit(1)) / ROWS).cast("int").alias("parts"))
    some = reps.join(parts, ["label", "dim"]).withColumn("part", F.expr("int(pmod(xxhash64(rep, 4), parts))")).drop("parts")
    each = pivots.join(parts, ["label", "dim"]).withColumn("part", F.expr("explode(sequence(0, parts - 1))")).drop("parts")
    key = ["label", "dim", "part"]
    return some.groupBy(*key).cogroup(each.groupBy(*key)).applyInPandas(kernel, schema)


def at_home(vectors: pd.DataFrame, pivots: pd.DataFrame) -> pd.DataFrame:
    """The vectors with the cell of their nearest pivot and the distance from it."""
    pivots = pivots.sort_values("cell")
    d2 = np.maximum(2 - 2 * unit(vectors["embedding"]) @ np.stack(pivots["pivot"].to_numpy()).T, 0)
    own = d2.argmin(1)
    return vectors[VECTOR].assign(cell=own, far=np.sqrt(d2[np.arange(len(own)), own]))


VECTOR = ["label", "dim", "rep", "times", "embedding"]


def replicas(eps: float):
    """The kernel that puts every vector into its own cell and into those of smaller number that it may have to meet."""

    def kernel(vectors: pd.DataFrame, pivots: pd.DataFrame) -> pd.DataFrame:
        pivots = pivots.sort_values("cell")
        x, p = unit(vectors["embedding"]), np.stack(pivots["pivot"].to_numpy())
        d2 = np.maximum(2 - 2 * x @ p.T, 0)
        d, own = np.sqrt(d2), vectors["cell"].to_numpy()
        between = np.sqrt(np.maximum(2 - 2 * p @ p.T, 0))[own]
        reach = eps + 1e-6  # rounding must not lose a link
        with np.errstate(divide="ignore", invalid="ignore"):
            plane = (d2 - d2[np.arange(len(x)), own][:, None]) / (2 * between) <= reach
        meets = (plane | (between < 1e-5)) & (d <= pivots["most"].to_numpy() + reach) & (d >= pivots["least"].to_numpy() - reach)
        meets &= np.arange(len(p)) < own[:, None]
        meets[np.arange(len(x)), own] = True
        i, cell = np.nonzero(meets)
        return vectors.iloc[i][VECTOR].reset_index(drop=True).assign(cell=cell, home=cell == own[i])

    return kernel


def in_cells(reps: DataFrame, eps: float) -> DataFrame:
    """The vectors with ``cell, home``: once in their own cell, and in every other where they may meet a neighbour."""
    schema = f"label long, dim int, rep long, times long, embedding {reps.schema['embedding'].dataType.simpleString()}, cell int"
    pivots = materialize(choose_pivots(reps), "pivots")
    homes = materialize(with_pivots(reps, pivots, at_home, schema + ", far double"), "homes")
    shells = homes.groupBy("label", "dim", "cell").agg(F.min("far").alias("least"), F.max("far").alias("most"))
    # a pivot that is nobody's nearest has an empty cell, which nothing enters
    shells = materialize(pivots.join(shells, ["label", "dim", "cell"], "left").fillna({"least": 9.0, "most": -9.0}), "shells")
    return with_pivots(homes, shells, replicas(eps), schema + ", home boolean")


def join_block(block: pd.DataFrame, least: float) -> pd.DataFrame:
    """Links of the homes of a block with its members: per vector how many vectors, and a forest of the links.

    Members at home in the cell are homes elsewhere in it and count their links there; replicas count theirs here.
    """
    homes, members = block[block["side"] == 0], block[block["side"] == 1]
    empty = pd.DataFrame({"u": [], "v": [], "n": []}).astype("int64")
    if homes.empty or members.empty:
        return empty
    a, b = (np.stack(side["embedding"].to_numpy()).astype(float) for side in (homes, members))
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    ia, ib = homes["rep"].to_numpy(), members["rep"].to_numpy()
    linked = np.zeros((len(a), len(b)), bool)
    for at in range(0, len(a), 512):
        cut = slice(at, at + 512)
        linked[cut] = (a[cut] @ b.T) / (na[cut, None] * nb[None, :]) >= least
        linked[cut] &= ia[cut, None] != ib[None, :]
    n = linked @ members["times"].to_numpy()
    back = np.where(members["home"].to_numpy(), 0, homes["times"].to_numpy() @ linked)
    # smallest id that each row and column reaches within the block
    row, col, big = ia.copy(), ib.copy(), np.iinfo(np.int64).max
    rows, cols = np.flatnonzero(linked.any(1)), np.flatnonzero(linked.any(0))
    small = linked[np.ix_(rows, cols)]
    while len(rows):
        r = np.minimum(row[rows], np.where(small, col[cols][None, :], big).min(1))
        c = np.minimum(col[cols], np.where(small, r[:, None], big).min(0))
        done = (r == row[rows]).all() and (c == col[cols]).all()
        row[rows], col[cols] = r, c
        if done:
            break
    edges = {(int(x), int(y)) for x, y in [*zip(ia, row), *zip(ib, col)] if x != y}
    counts = [(int(x), int(x), int(k)) for x, k in [*zip(ia, n), *zip(ib, back)] if k]
    all_rows = [(u, v, 0) for u, v in edges] + counts
    return pd.DataFrame(all_rows, columns=["u", "v", "n"]).astype("int64") if all_rows else empty


def link(vectors: DataFrame, least: float = 0.98) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` of every vector."""
    reps = materialize(distinct_vectors(vectors), "vectors")
    located = reps.select(
        F.col("label").cast("long").alias("label"), F.size("embedding").alias("dim"), "rep", "times", "embedding"
    )
    placed = materialize(in_cells(located, math.sqrt(2 - 2 * least)), "cells")
    cell = ["label", "dim", "cell"]
    sizes = placed.groupBy(*cell).agg(
        F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("mb"),
        F.ceil(F.sum(F.col("home").cast("int")) / BLOCK).cast("int").alias("hb"),
    )
    sized = placed.join(sizes.filter("hb > 0"), cell)
    # a home meets every block of members, a member every block of homes
    deal = "explode(filter(array(CASE WHEN home THEN 0 END, 1), x -> x IS NOT NULL)) AS side"
    dealt = sized.selectExpr(*cell, "rep", "times", "embedding", "home", "mb", "hb", deal).selectExpr(
        *cell, "rep", "times", "embedding", "home", "side",
        "CASE WHEN side = 0 THEN int(pmod(xxhash64(rep, 1), hb)) ELSE int(pmod(xxhash64(rep, 2), mb)) END AS own",
        "explode(sequence(0, CASE WHEN side = 0 THEN mb - 1 ELSE hb - 1 END)) AS other",
    )
    blocks = dealt.selectExpr(
        *cell, "rep", "times", "embedding", "home", "side",
        "CASE WHEN side = 0 THEN own ELSE other END AS h", "CASE WHEN side = 0 THEN other ELSE own END AS m",
    )
    found = blocks.groupBy(*cell, "h", "m").applyInPandas(
        lambda block: join_block(block, least), "u long, v long, n long"
    )
    found = materialize(found, "embedding-links")
    names = connected(found.filter("u <> v").select("u", "v"))
    counts = found.filter("u = v").groupBy(F.col("u").alias("rep")).agg(F.sum("n").alias("n"))
    per = reps.join(counts, "rep", "left").join(names.withColumnRenamed("node", "rep"), "rep", "left").select(
        "label", "embedding", (F.coalesce("n", F.lit(0)) + F.col("times") - 1).alias("n_links"),
        F.coalesce("component", "rep").alias("component_id"),
    )
    rows = vectors.select("vec_id", F.col("label").alias("l"), F.col("embedding").alias("e"))
    joined = rows.join(per, (F.col("l") == F.col("label")) & (F.col("e") == F.col("embedding")) & rows["vec_id"].isNotNull(), "left")
    own = F.coalesce("component_id", "vec_id")
    return joined.select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"),
        F.coalesce(F.col("vec_id") == own, F.lit(True)).alias("kept"),
    )
