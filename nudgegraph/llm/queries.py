"""One registered query for each training-data operator, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from nudgegraph.llm import decontaminate as _decontaminate
from nudgegraph.llm import neardup as _neardup
from nudgegraph.llm import neighbours as _neighbours
from nudgegraph.llm import preferences as _preferences
from nudgegraph.llm import substring as _substring
from nudgegraph.llm import urlfilter as _urlfilter
from nudgegraph.llm import warc as _warc
from nudgegraph.llm.bpe import bpe_digests
from nudgegraph.llm.langid import identify, learn, training_rows
from nudgegraph.llm.mixlm import lm_scores


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _substring.substring_dedup(_table(spark, sf_dir, "documents"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as tok

    return bpe_digests(_table(spark, sf_dir, "documents"), tok.path("byte_bpe_50k.tiktoken"), tok.PATTERN)


def op3_vantage_point_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return _neighbours.cosine_neighbours(vectors, vectors.where("vec_id % 50 = 0"), k=5, factor=1.0)


def op4_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return identify(docs, learn(training_rows(docs))).select("doc_id", "held_out", "lang_pred", "score")


def op5_warc_salvage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _warc.warc_round_trip(_table(spark, sf_dir, "pages"), least_revisit=1000)


def op6_dated_url_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages")
    judged = _urlfilter.filter_urls(_urlfilter.demo_captures(pages), _urlfilter.demo_entries(pages))
    return judged.withColumn("fetched", judged.fetched.cast("string"))


def op7_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = _preferences.format_preferences(_preferences.demo_pairs(_table(spark, sf_dir, "conversations")))
    return pairs.withColumns({c: _preferences.spans_text(c) for c in ("chosen_mask", "rejected_mask")})


def op8_logistic_mixing_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scores(_table(spark, sf_dir, "documents"))


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _decontaminate.decontaminate(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"), window=10)


def op10_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _neardup.near_duplicates(_table(spark, sf_dir, "documents"), shingle=2, num=80, den=100)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_byte_bpe": op2_byte_bpe,
    "op3_vantage_point_neighbours": op3_vantage_point_neighbours,
    "op4_language_mixture": op4_language_mixture,
    "op5_warc_salvage": op5_warc_salvage,
    "op6_dated_url_lists": op6_dated_url_lists,
    "op7_preference_pairs": op7_preference_pairs,
    "op8_logistic_mixing_lm": op8_logistic_mixing_lm,
    "op9_benchmark_decontamination": op9_benchmark_decontamination,
    "op10_minhash_near_dedup": op10_minhash_near_dedup,
}

ORACLES: dict[str, str] = {
    "op1_substring_dedup": _substring.ORACLE,
    "op3_vantage_point_neighbours": _neighbours.ORACLE,
    "op5_warc_salvage": _warc.ORACLE,
    "op6_dated_url_lists": _urlfilter.ORACLE,
    "op7_preference_pairs": _preferences.ORACLE,
    "op9_benchmark_decontamination": _decontaminate.ORACLE,
    "op10_minhash_near_dedup": _neardup.ORACLE,
}
