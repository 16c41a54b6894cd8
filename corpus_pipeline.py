"""A corpus pipeline: language, exact copies, near copies, mixture, tokens. Each stage works on what the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rayfit.llm import bpe, exact, jaccard, langid, mixing
from rayfit.llm.common import fresh_path, split_mark
from rayfit.llm.queries import SHARES, digests, domains, table, vocabulary

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects what has no language: null texts and texts without a letter."""
    model = langid.fit(docs.filter(~split_mark("doc_id", 4, 2)))
    told = langid.label(docs.withColumn("row", F.struct(*COLUMNS)), model, key="row")
    return told.filter(F.col("lang_pred") != langid.UNDETERMINED).select("row.*")


def _exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the row with the largest doc_id of each text."""
    return exact.keep_last(docs).select(*COLUMNS)


def _near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest doc_id of each component of near copies."""
    return jaccard.keep_first(docs).select(*COLUMNS)


def _mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as its rate, rounded by a hash of doc_id: none for 0, repeated above 1."""
    rates = mixing.mix(docs, domains(table(spark, sf_dir, "labels")), SHARES, "good").filter("copies <> 1").select("doc_id", "copies").dropDuplicates(["doc_id"])
    times = F.explode(F.array_repeat(F.lit(0), F.coalesce("copies", F.lit(1))))
    return docs.join(rates, "doc_id", "left").withColumn("_copy", times).select(*COLUMNS)


def _tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row."""
    return digests(bpe.encode(docs, vocabulary()))


STAGES = [("language", _language), ("exact", _exact), ("near", _near), ("mixture", _mixture), ("tokens", _tokens)]
#: The language model, the classifier and the tokenizer are not SQL; test_stages_against_loops holds run() against plain loops.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
