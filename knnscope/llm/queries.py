"""The queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.io import table
from knnscope.llm import bpe, embdup, htmltext, langid, neardup, packing, pii, quality, toxicity, urlfilter
from knnscope.llm.common import crc_fold


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    return bpe.digest_table(table(spark, sf_dir, "documents"), path, public_tokenizers.PATTERN)


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.link(table(spark, sf_dir, "documents"), words=3, similar=85)


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.fit(toxicity.labelled_rows(docs, labels))
    held = F.coalesce(crc_fold(F.col("doc_id"), 5) == 0, F.lit(False))
    return toxicity.score_table(docs, model).select("doc_id", held.alias("held_out"), "score", "predicted")


def op4_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embdup.link(table(spark, sf_dir, "embeddings"), least=0.98)


def op6_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.extract(table(spark, sf_dir, "pages"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents")).withColumn("failed", F.array_join("failed", ","))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(table(spark, sf_dir, "documents"))


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.fit(docs, langid.not_held_out())
    held = F.coalesce(crc_fold(F.col("doc_id"), 4) == 2, F.lit(False))
    return langid.predict(docs, model).select("doc_id", held.alias("held_out"), "lang_pred", "score", "rejected")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(table(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        f.__name__: f
        for f in (
            op1_byte_bpe, op2_minhash, op3_toxicity, op4_embeddings, op5_quality,
            op6_html, op7_packing, op8_pii, op9_language, op10_url_filter,
        )
    }


def oracle_sql() -> dict[str, str]:
    return {}
