"""Toxicity by class-conditional Kneser-Ney models of expressions.

The expressions of a text are its lower-cased words without outer punctuation. As in Kneser-Ney smoothing an expression
counts once for each different word before which it stands in the rows of a class, so that what copies repeat counts
once; ``DISCOUNT`` is taken off each count, and both classes give the share ``BACKOFF`` to one backoff distribution, that of the
counts of both. A rare expression, with no more contexts than the discount in either class, is left to the shared
counts alone and looks alike in both.

Most words of a toxic text are those of any text: its model is a mixture that takes the share ``MIXED`` of the words from the
toxic rows' distribution and the others from the ordinary one. A text's ratio is the difference of the log-likelihoods of the toxic
and the ordinary model, divided by its number of words; a logistic calibration makes the score of it, fitted on a fold that the
counts leave out.

Counts come from every labelled row that may be learned from; nothing is sampled, and no expression is dropped: those
left out of the table have a difference of exactly 0. While the table has at most ``SHIPPED`` rows, each worker gets it;
beyond that only expressions that are at least one in ``HOT`` of all, of which there can be no more than ``HOT``, are shipped,
and the other expressions of every text find theirs by an equality join.

Defined cases: NULL and empty texts have a ratio of 0; NULL ids are scored and are in no fold; without rows of both
classes all scores are the share of toxic rows (0 if there is none); an empty table gives an empty table; repeated rows
repeat, and count as copies; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.io import materialize
from knnscope.llm.common import Memo, crc_fold, map_rows

DISCOUNT, BACKOFF, MIXED = 2, 0.05, 0.02
#: Rows of the table that workers may get; labels that may be broadcast.
SHIPPED, HOT, LABELS = 1 << 20, 4096, 1_000_000
OUTER = ".,;:!?\"'()[]{}<>*#%&$|-"
#: Ratios are counted in bins of one over ``SCALE``, as far as ``WIDEST``.
SCALE, WIDEST = 20_000, 0.5


def expressions(text: str) -> list[str]:
    return [w.strip(OUTER) for w in text.lower().split()]


def context_counts(labelled: DataFrame, flush_at: int = 300_000) -> DataFrame:
    """``expression, n0, n1``: before how many different words each stands in ordinary and in toxic rows."""

    def kernel(batches):
        held: dict[tuple[str, int], int] = {}
        codes = Memo(lambda w: xxhash.xxh3_64_intdigest(w) >> 1, 32 << 20)

        def flush():
            keys, flags = list(held), list(held.values())
            held.clear()
            return {"expression": [k[0] for k in keys], "before": [k[1] for k in keys], "classes": flags}

        for rows in batches:
            for _, text, toxic in rows:
                before, flag = 0, 1 << toxic
                for w in expressions(text or ""):
                    key = w, before
                    held[key] = held.get(key, 0) | flag
                    before = codes[w]
                    if len(held) > flush_at:
                        yield flush()
        yield flush()

    part = map_rows(labelled, ["doc_id", "text", "toxic"], kernel, "expression string, before long, classes int")
    pairs = part.groupBy("expression", "before").agg(F.bit_or("classes").alias("classes"))
    return pairs.groupBy("expression").agg(
        F.sum(F.col("classes").bitwiseAND(1).cast("long")).alias("n0"),
        F.sum(F.shiftright("classes", 1).cast("long")).alias("n1"),
    )


def differences(counts: DataFrame) -> DataFrame | None:
    """``expression, diff, n``: log-likelihood in the toxic model less that in the ordinary one, where it isn't 0.

    None if a class has no expression beyond the discount.
    """
    kept = [F.greatest(F.col(c) - DISCOUNT, F.lit(0)) for c in ("n0", "n1")]
    t = counts.agg(*(F.sum(k).cast("double") for k in kept), F.sum(F.col("n0") + F.col("n1")), F.count(F.lit(1))).first()
    if not t[0] or not t[1]:
        return None
    shared = (F.col("n0") + F.col("n1") + 0.5) / (t[2] + 0.5 * t[3])
    ordinary, toxic = ((1 - BACKOFF) * k / t[c] + BACKOFF * shared for c, k in enumerate(kept))
    diff = F.log((1 - MIXED) + MIXED * toxic / ordinary)
    return counts.filter((F.col("n0") > DISCOUNT) | (F.col("n1") > DISCOUNT)).select("expression", diff.alias("diff"), (F.col("n0") + F.col("n1")).alias("n"))


@dataclass
class ToxicityModel:
    """``table(expression, diff, n)`` or None, and the calibration. ``local`` has what workers get of the table."""

    table: DataFrame | None = None
    local: dict[str, float] = field(default_factory=dict)
    whole: bool = True
    slope: float = 0.0
    offset: float = 0.0

    @classmethod
    def of(cls, table: DataFrame | None) -> ToxicityModel:
        if table is None:
            return cls()
        n, total = table.agg(F.count(F.lit(1)), F.sum("n")).first()
        some = table if n <= SHIPPED else table.filter(F.col("n") * HOT >= total)
        rows = some.select("expression", "diff").toPandas()  # at most SHIPPED or HOT rows
        return cls(table, dict(zip(rows["expression"], rows["diff"])), n <= SHIPPED)


def ratios(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """``doc_id, toxic, ratio`` of every row; ``docs`` may lack ``toxic``."""
    docs = docs if "toxic" in docs.columns else docs.withColumn("toxic", F.lit(None).cast("int"))
    docs = docs.select("doc_id", F.col("toxic").cast("int").alias("toxic"), "text")
    shared = docs.sparkSession.sparkContext.broadcast(model.local)
    if model.whole:

        def kernel(batches):
            local = shared.value
            memo = Memo(lambda w: local.get(w.strip(OUTER), 0.0))
            for rows in batches:
                out = []
                for _, _, text in rows:
                    words = (text or "").lower().split()
                    out.append(math.fsum([memo[w] for w in words]) / len(words) if words else 0.0)
                yield {"doc_id": [r[0] for r in rows], "toxic": [r[1] for r in rows], "ratio": out}

        return map_rows(docs, ["doc_id", "toxic", "text"], kernel, "doc_id long, toxic int, ratio double")

    def parts(batches):
        local, row = shared.value, TaskContext.get().partitionId() << 40
        for rows in batches:
            out = {k: [] for k in ("row", "doc_id", "toxic", "words", "expression", "part")}
            for doc_id, toxic, text in rows:
                row += 1
                found = Counter(expressions(text or ""))
                known = math.fsum(n * local[w] for w, n in found.items() if w in local)
                mine = [(None, known), *((w, float(n)) for w, n in found.items() if w not in local)]
                for w, part in mine:
                    for k, v in zip(out, (row, doc_id, toxic, found.total(), w, part)):
                        out[k].append(v)
            yield out

    schema = "row long, doc_id long, toxic int, words long, expression string, part double"
    split = materialize(map_rows(docs, ["doc_id", "toxic", "text"], parts, schema), "expressions")
    rest = split.filter("expression IS NOT NULL").join(model.table, "expression").select("row", (F.col("part") * F.col("diff")).alias("part"))
    own = split.filter("expression IS NULL")
    sums = own.select("row", "part").unionByName(rest).groupBy("row").agg(F.sum("part").alias("total"))
    return own.drop("part").join(sums, "row").select("doc_id", "toxic", (F.col("total") / F.greatest("words", F.lit(1))).alias("ratio"))


def fit(labelled: DataFrame, calibrate: int = 1, folds: int = 5) -> ToxicityModel:
    """Learn from ``labelled(doc_id, text, toxic)``; one fold of it (by crc32 of the id) is kept for the calibration."""
    fold = crc_fold(F.col("doc_id"), folds)
    n = {int(r[0]): r[1] for r in labelled.groupBy("toxic").count().collect()}
    share = n.get(1, 0) / max(1, sum(n.values()))
    prior = ToxicityModel(offset=math.log(max(share, 1e-9) / max(1 - share, 1e-9)))
    if not n.get(0) or not n.get(1):
        return prior
    counts = materialize(context_counts(labelled.filter(F.coalesce(fold != calibrate, F.lit(True)))), "contexts")
    table = differences(counts)
    if table is None:
        return prior
    model = ToxicityModel.of(materialize(table, "toxicity-model"))
    bins = ratio_bins(labelled.filter(fold == calibrate), model)
    if len({r["toxic"] for r in bins}) < 2:
        bins = ratio_bins(labelled, model)
    x, y, w = (np.array([float(r[k]) for r in bins]) for k in ("bin", "toxic", "count"))
    model.slope, model.offset = logistic(x / SCALE, y, w)
    return model


def ratio_bins(labelled: DataFrame, model: ToxicityModel) -> list:
    """A histogram of the ratios by class; its size doesn't depend on the number of rows."""
    near = F.least(F.greatest(F.col("ratio"), F.lit(-WIDEST)), F.lit(WIDEST))
    bins = ratios(labelled, model).select(F.round(near * SCALE).cast("int").alias("bin"), "toxic")
    return bins.groupBy("bin", "toxic").count().collect()


def logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, ridge: float = 1e-3) -> tuple[float, float]:
    """Weighted logistic regression on one variable by damped Newton steps."""
    scale = max(float(np.sqrt(np.average(x * x, weights=w))), 1e-9)
    a = np.stack([x / scale, np.ones_like(x)], 1)
    beta = np.zeros(2)
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -30, 30)))
        g = a.T @ (w * (p - y)) + ridge * beta
        h = (a * (w * p * (1 - p))[:, None]).T @ a + (ridge + 1e-6) * np.eye(2)
        move = np.linalg.solve(h, g)
        beta -= move * min(1.0, 4.0 / max(1e-9, float(np.abs(move).max())))
        if np.abs(move).max() < 1e-8:
            break
    return float(max(beta[0], 0.0) / scale), float(beta[1])


def score_table(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """``doc_id, score, predicted`` of every text; nothing but the text is an input of the score."""
    x = F.col("ratio") * float(model.slope) + float(model.offset)
    scored = ratios(docs.select("doc_id", "text"), model).select("doc_id", (1 / (1 + F.exp(-F.least(F.greatest(x, F.lit(-40.0)), F.lit(40.0))))).alias("score"))
    return scored.select("doc_id", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def labelled_rows(docs: DataFrame, labels: DataFrame, folds: int = 5, held: int = 0) -> DataFrame:
    """Texts with a known label outside the held-out fold. Up to ``LABELS`` labels are broadcast; beyond that their ids build
    the hash tables of a shuffled join, so that texts are neither sorted nor spilled for it."""
    known = labels.filter(F.col("toxic").isNotNull() & (crc_fold(F.col("doc_id"), folds) != held))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).filter(F.col("toxic").isin(0, 1))
    texts = docs.filter(crc_fold(F.col("doc_id"), folds) != held).select("doc_id", "text")
    return texts.join(F.broadcast(known) if labels.count() <= LABELS else known.hint("shuffle_hash"), "doc_id")
