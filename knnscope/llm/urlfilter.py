"""URL filters: rules first, then the ratio of two character language models.

The models are variable-order Markov models of host and path: the probability of a character after up to ``ORDER`` - 1
before it, in which each order is smoothed with the next lower one in proportion to how many different characters
followed the context (Witten-Bell). They learn from the URLs that the rules allow and block; the threshold of the
length-normalised log-likelihood difference is the one that errs least on a fold which the counts leave out.

Everything is DataFrame operations. All n-gram tables are aggregates of the highest order. URLs are scored by an equality
join of their n-grams to the whole table, which grows with the input. The n-grams that are at least one in ``HOT`` of
all, of which there can be no more than ``HOT``, are broadcast, so that no key of the join that is left is large.

Defined cases: URLs that are NULL or have no ``://`` have an empty host and path, fit no rule and, like other empty
strings, have a difference of 0, which the threshold judges; without URLs of both classes everything that no rule
decides is allowed; repeated rows repeat; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from knnscope.io import materialize
from knnscope.llm.common import crc_fold

#: verdict, host, start of the path
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
ORDER = 5
START = "\u0002"
END = "\u0003"
HOT = 4096


def parts(pages: DataFrame) -> DataFrame:
    """``page_id, host, path``."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    at = F.coalesce(F.instr("url", "://"), F.lit(0))
    rest = F.when(at > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    return pages.select("page_id", rest.alias("rest")).select(
        "page_id",
        F.translate(F.regexp_extract("rest", r"^([^/?#]*)", 1), upper, lower).alias("host"),
        F.regexp_extract("rest", r"^[^/?#]*([^?#]*)", 1).alias("path"),
    )


def by_rule(rules=RULES) -> tuple[Column, Column]:
    """The rule that fits and its verdict; the longest rule wins, and the first of equally long ones."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, host, start in sorted(reversed(rules), key=lambda r: len(r[1] + r[2])):  # later ones overrule
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(start)
        name, verdict = F.when(fits, host + start).otherwise(name), F.when(fits, what).otherwise(verdict)
    return name, verdict


def grams(urls: DataFrame, *keep: str) -> DataFrame:
    """One row for each character of host and path and for their end: the character with those before it."""
    text = F.concat(F.lit(START * (ORDER - 1)), "host", "path", F.lit(END))
    return urls.select(*keep, text.alias("s")).selectExpr(
        *keep, f"explode(transform(sequence(1, length(s) - {ORDER - 1}), i -> substring(s, i, {ORDER}))) AS gram"
    )


def differences(counted: DataFrame) -> DataFrame:
    """``gram, diff``: log-likelihood of the last character of each n-gram if allowed less that if blocked.

    ``counted(gram, n_allow, n_block)`` has every n-gram of the table, with counts of 0 for those never learned from.
    """
    shorter = None
    for k in range(1, ORDER + 1):
        own = counted.groupBy(F.expr(f"right(gram, {k})").alias("gram")).agg(
            F.sum("n_allow").alias("n_allow"), F.sum("n_block").alias("n_block")
        )
        context = W.partitionBy(F.expr(f"left(gram, {k - 1})")) if k > 1 else W.partitionBy(F.lit(0))
        if shorter is None:
            own = own.withColumns({"p_allow": F.lit(1 / 256.0), "p_block": F.lit(1 / 256.0)})
        else:
            lower = shorter.select(F.col("gram").alias("rest"), "p_allow", "p_block")
            own = own.withColumn("rest", F.expr(f"right(gram, {k - 1})")).join(lower, "rest").drop("rest")
        smoothed = {}
        for c in ("allow", "block"):
            n, kinds = F.sum(f"n_{c}").over(context), F.sum((F.col(f"n_{c}") > 0).cast("int")).over(context)
            smoothed[f"p_{c}"] = F.when(
                n > 0, (F.col(f"n_{c}") + kinds * F.col(f"p_{c}")) / (n + kinds)
            ).otherwise(F.col(f"p_{c}"))
        shorter = own.withColumns(smoothed).select("gram", "p_allow", "p_block")
    return shorter.select("gram", (F.log("p_allow") - F.log("p_block")).alias("diff"))


def gram_counts(urls: DataFrame, learn: Column) -> DataFrame:
    """``gram, n_allow, n_block, n``: all n-grams, with how often ``urls`` of both classes to learn from have them."""
    return grams(urls.withColumn("learned", F.when(learn, F.col("ruled"))), "learned").groupBy("gram").agg(
        F.sum((F.coalesce("learned", F.lit("")) == "allow").cast("long")).alias("n_allow"),
        F.sum((F.coalesce("learned", F.lit("")) == "block").cast("long")).alias("n_block"),
        F.count(F.lit(1)).alias("n"),
    )


def ratios(rows: DataFrame, model: DataFrame) -> DataFrame:
    """``row, ratio``: the mean of ``model(gram, diff, n)`` over the n-grams of every row."""
    total = F.broadcast(model.agg(F.sum("n").alias("n_all")))
    split = materialize(model.crossJoin(total).selectExpr("gram", "diff", f"n * {HOT} >= n_all AS hot"), "url-model")
    marked = grams(rows, "row").join(F.broadcast(split.filter("hot").select("gram", "diff")), "gram", "left")
    rest = marked.filter("diff IS NULL").select("row", "gram").join(split.filter("NOT hot").select("gram", "diff"), "gram")
    parts = [
        x.groupBy("row").agg(F.sum("diff").alias("d"), F.count(F.lit(1)).alias("c"))
        for x in (marked.filter("diff IS NOT NULL"), rest)
    ]
    return parts[0].unionByName(parts[1]).groupBy("row").agg((F.sum("d") / F.sum("c")).alias("ratio"))


def judge(pages: DataFrame, rules=RULES, folds: int = 5) -> DataFrame:
    """``page_id, host, path, rule, verdict, ratio`` of every page."""
    rule, verdict = by_rule(rules)
    urls = parts(pages).select("page_id", "host", "path", rule.alias("rule"), verdict.alias("ruled"))
    learn = F.coalesce(crc_fold(F.col("page_id"), folds) != 0, F.lit(True))
    counted = materialize(gram_counts(urls, learn), "url-grams")
    model = differences(counted).join(counted.select("gram", "n"), "gram")
    # equal rows stay apart
    rows = materialize(urls.withColumn("row", F.monotonically_increasing_id()), "url-rows")
    scored = materialize(rows.join(ratios(rows, model), "row").drop("row"), "url-scores")
    least = threshold(scored.filter(F.col("ruled").isNotNull() & ~learn))
    return scored.select(
        "page_id", "host", "path", "rule",
        F.coalesce("ruled", F.when(F.col("ratio") >= least, "allow").otherwise("block")).alias("verdict"), "ratio",
    )


def threshold(held: DataFrame, scale: int = 200, widest: float = 10.0) -> float:
    """The difference from which on a URL is allowed: where the mean error of both classes is least (0 without both).

    Only a histogram of fixed size reaches the driver.
    """
    bins = held.select(
        F.round(F.greatest(F.lit(-widest), F.least(F.lit(widest), "ratio")) * scale).cast("int").alias("bin"), "ruled"
    )
    found = bins.groupBy("bin").agg(
        F.sum((F.col("ruled") == "allow").cast("long")).alias("a"), F.sum((F.col("ruled") == "block").cast("long")).alias("b")
    ).orderBy("bin").collect()
    allow, block = sum(r.a for r in found), sum(r.b for r in found)
    if not allow or not block:
        return -widest if not block else 0.0
    best, at, wrong_allow, wrong_block = 2.0, 0.0, 0, block
    for r in found:  # allowed from this bin on: those below are blocked
        error = wrong_allow / allow + wrong_block / block
        if error < best:
            best, at = error, (r.bin - 0.5) / scale
        wrong_allow, wrong_block = wrong_allow + r.a, wrong_block - r.b
    return at
