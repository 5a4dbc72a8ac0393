"""Quality rules with thresholds that follow the data: quantile sketches per language and source.

One pass computes counts of every text with built-in functions only and is written to the shared folder (numbers, no
texts). KLL sketches of its ratios, one for each language and source, give each group its own fences; the sketches of
a language's sources merge into one for the language, and all merge into one for the corpus. Few rows say little of their
quantiles, so the fences are pooled: with n rows those of a group have the weight n / (n + ``POOLED``) and its language's the rest;
those of a language are pooled with the corpus's in the same way. The fences are joined to the rows.

A ratio fails if it is beyond an upper quantile of its group by ``SPREAD`` interquartile ranges and a small ``slack``, which
stands for the range where most texts of a group share one value. The quantile is the upper quartile, which junk does not
move; of repeated lines, which most groups hardly have, it is a high one, so that one line twice in a short text passes.
The sketches hold the texts that the base rule keeps, as no other is judged by them.

Defined cases: NULL texts count as empty, so they have no word and fail the base rule; NULL languages and sources are
groups of their own; repeated rows count each; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.io import materialize

#: ratio name -> (expression, quantile of the group, slack)
RATIOS = {
    "symbol_ratio": ("n_symbols / greatest(n_words, 1)", 0.75, 0.05),
    "upper_ratio": ("n_upper / greatest(word_chars, 1)", 0.75, 0.05),
    "dup_line_ratio": ("n_dup_lines / greatest(n_lines, 1)", 0.99, 0.1),
    "word_length": ("word_chars / greatest(n_words, 1)", 0.75, 0.5),
}
BASE_FAILED = "n_words < 10 OR 100 * n_repeat_words > 20 * n_words"
SPREAD = 6.0
#: So many rows of its own weigh as much as what stands above a group.
POOLED = 20
#: The characters between words.
BLANKS = (" ", "\\t", "\\n", "\\u000B", "\\u000C", "\\r")


def _without(column: str, characters) -> str:
    """The SQL text that removes single characters; plain replacements are much cheaper than a pattern."""
    for c in characters:
        column = f"replace({column}, '{c}')"
    return column


def counts(docs: DataFrame, *more: str) -> DataFrame:
    """``doc_id, lang, source``, the columns ``more``, and the counts of every whole text."""
    own = ["doc_id", "lang", "source", *more]
    base = docs.select(*own, F.coalesce("text", F.lit("")).alias("t"))
    blank = "[\\\\x20\\\\x09-\\\\x0D]"
    split = base.selectExpr(
        *own, "t",
        f"split(regexp_replace(t, '^{blank}+|{blank}+\\\\z', ''), '{blank}+') AS w",
        f"filter(split(t, '\\n'), x -> x rlike '[^\\\\x20\\\\x09-\\\\x0D]') AS l",
    )
    split = split.selectExpr(*own, "t", "l", "CASE WHEN w[0] = '' THEN array() ELSE w END AS w")
    windows = split.selectExpr(
        *own,
        "CAST(size(w) AS BIGINT) AS n_words",
        f"CAST(length({_without('t', BLANKS)}) AS BIGINT) AS word_chars",
        f"CAST(length(t) - length({_without('t', '#*$%&|<>')}) AS BIGINT) AS n_symbols",
        "CAST(size(l) AS BIGINT) AS n_lines",
        "CAST(size(l) - size(array_distinct(l)) AS BIGINT) AS n_dup_lines",
        "CAST(regexp_count(t, '\\\\p{Lu}') AS BIGINT) AS n_upper",
        "CASE WHEN size(w) >= 6 THEN transform(sequence(1, size(w) - 4), i -> xxhash64(slice(w, i, 5))) END AS h",
    )
    keep = [*own, "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_upper"]
    # only texts in which some window repeats are sorted; equal windows then stand side by side
    paired = windows.selectExpr(
        *keep,
        "CASE WHEN size(array_distinct(h)) < size(h) THEN array_sort(transform(h, (x, i) -> struct(x AS h, i AS p))) END AS s",
    )
    placed = paired.selectExpr(
        *keep,
        "array_sort(transform(filter(s, (x, i) -> x.h = get(s, i - 1).h OR x.h = get(s, i + 1).h), x -> x.p)) AS p",
    )
    covered = "aggregate(p, struct(-5 AS last, 0L AS n), (a, x) -> struct(x AS last, a.n + least(5, x - a.last) AS n), a -> a.n)"
    return placed.selectExpr(*keep, f"coalesce({covered}, 0L) AS n_repeat_words")


def fences(counted: DataFrame) -> DataFrame:
    """``lang, source, <ratio>_max``: the greatest value each ratio may take in a group."""
    ratios = counted.filter(f"NOT ({BASE_FAILED})").selectExpr(
        "lang", "source", *(f"CAST({e} AS DOUBLE) AS {k}" for k, (e, *_) in RATIOS.items())
    )
    own = ratios.groupBy("lang", "source").agg(
        F.count(F.lit(1)).alias("n"), *(F.kll_sketch_agg_double(k).alias(k) for k in RATIOS)
    )
    own = materialize(own, "sketches")
    merged = [F.sum("n").alias("n"), *(F.kll_merge_agg_double(k).alias(k) for k in RATIOS)]
    by_lang = own.groupBy("lang").agg(*merged)
    overall = own.agg(*merged)
    lang = by_lang.select(F.col("lang").alias("lang_"), F.struct("n", *RATIOS).alias("of_lang"))
    one = overall.select(F.struct("n", *RATIOS).alias("of_all"))
    joined = own.join(lang, F.col("lang").eqNullSafe(F.col("lang_"))).crossJoin(F.broadcast(one))
    out = ["lang", "source"]
    for k, (_, at, slack) in RATIOS.items():
        own, lang, corpus = (
            "({2} + {s} * ({1} - {0}))".format(*(f"kll_sketch_get_quantile_double({x}{k}, {q}D)" for q in (0.25, 0.75, at)), s=SPREAD)
            for x in ("", "of_lang.", "of_all.")
        )
        above = f"(of_lang.n * {lang} + {POOLED} * {corpus}) / (of_lang.n + {POOLED})"
        out.append(f"(n * {own} + {POOLED} * {above}) / (n + {POOLED}) + {slack}D AS {k}_max")
    return joined.selectExpr(*out)


def verdicts(counted: DataFrame, *more: str) -> DataFrame:
    """``doc_id``, ``more``, the counts, ``base_failed``, ``failed`` (the ratios beyond their fences) and ``kept``."""
    limits = materialize(fences(counted).withColumnsRenamed({"lang": "lang_", "source": "source_"}), "fences")
    joined = counted.join(
        limits, F.col("lang").eqNullSafe(F.col("lang_")) & F.col("source").eqNullSafe(F.col("source_")), "left"
    )
    failed = ", ".join(f"CASE WHEN {e} > {k}_max THEN '{k}' END" for k, (e, *_) in RATIOS.items())
    return joined.selectExpr(
        "doc_id", *more, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        f"({BASE_FAILED}) AS base_failed", f"array_compact(array({failed})) AS failed",
    ).selectExpr("*", "NOT base_failed AND size(failed) = 0 AS kept")


def judge(docs: DataFrame) -> DataFrame:
    """The verdict on every document, with its counts; see ``verdicts``."""
    return verdicts(materialize(counts(docs), "counts"))


def passing(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are kept. They travel with their counts, so that no join has to find them again."""
    whole = docs.withColumn("whole", F.struct(*docs.columns))
    return verdicts(materialize(counts(whole, "whole"), "counts"), "whole").filter("kept").select("whole.*")
