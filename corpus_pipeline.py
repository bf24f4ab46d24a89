"""Corpus pipeline: the stages in their order, each over all that its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nudgegraph.llm.bpe import bpe_digests
from nudgegraph.llm.decontaminate import decontaminate
from nudgegraph.llm.langid import UNKNOWN, identify, learn, training_rows
from nudgegraph.llm.neardup import near_duplicates
from nudgegraph.llm.substring import substring_dedup
from nudgegraph.session import Scratch

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
REST = ("lang", "source", "n_chars")
#: a document goes if no language has this share of it
LEAST_SHARE = 0.3
#: a passage of so many words that an earlier document holds is cut out, wherever its sentences end
PASSAGE = 50


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without letters, or in which no language stands out, go."""
    judged = identify(docs, learn(training_rows(docs)), carry=("text", *REST))
    return judged.where((F.col("lang_pred") != UNKNOWN) & (F.col("score") >= LEAST_SHARE)).select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: the one with the smallest id. Rows that share an id go together."""
    gone = near_duplicates(docs, shingle=5, num=80, den=100).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated passages are cut out; documents of which nothing is left go."""
    cut = substring_dedup(docs, run=PASSAGE, carry=REST)
    left = F.regexp_like("text", F.lit(r"[^\x20\x09-\x0D]"))
    return cut.where((F.col("n_removed") == 0) | left).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of the benchmark go."""
    judged = decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), carry=("text", *REST))
    return judged.where("not contaminated").select(*COLUMNS)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids and of what they decode to."""
    import public_tokenizers as tok

    # workers hold what the stages before left behind, so they remember less
    return bpe_digests(docs, tok.path("byte_bpe_50k.tiktoken"), tok.PATTERN, remember=150_000)


STAGES = [("language_id", language_id), ("near_dedup", near_dedup), ("repeats", repeats), ("decontamination", decontamination), ("encoding", encoding)]

#: the language model, the components and the tokens have no SQL; tests hold the stages against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = scratch.keep(stage(spark, docs, sf_dir), name)
    return docs
