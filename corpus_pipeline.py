"""A corpus pipeline of five stages, each calling one operator: language, quality, near-duplicates, contamination, encoding.

Each stage takes (spark, docs, sf_dir) and returns a frame, which `run` writes as Parquet to the shared folder and reads
again as the next stage's docs. All stages but the last return the columns of their docs. Extra columns stay, whatever
their names. Every stage judges each row for itself, whatever ids rows share or lack: a verdict follows from a row's text
and language alone, so it is looked up by a 128-bit hash of the two.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.llm import byte_bpe, decontaminate, language, quality_rules, simhash
from tauprobe.llm.arrow_kernels import small
from tauprobe.session import materialize, table


def _judged(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, text, lang) to be judged, where doc_id is the hash of text and language."""
    return docs.select(_key("doc_id"), "text", "lang")


def _key(name: str) -> Column:
    return F.struct(F.xxhash64("text", "lang").alias("a"), F.xxhash64(F.lit(1), "text", "lang").alias("b")).alias(name)


def _without(docs: DataFrame, judged: DataFrame, rejected: Column | str, key: str = "id") -> DataFrame:
    """The rows of docs whose text and language were not rejected."""
    gone = small(materialize(judged.where(rejected).select(f"{key}.a", f"{key}.b").distinct(), "rejected"))
    key = _key("_key")
    return docs.join(gone, (key["a"] == gone["a"]) & (key["b"] == gone["b"]), "left_anti")


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a recognised language, or that the codewords leave ambiguous, go."""
    model = language.train(docs.select("doc_id", "text", "lang"))
    return _without(docs, language.predict(_judged(docs), model), (F.col("lang_pred") == language.UNKNOWN) | F.col("ambiguous"))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the risk-controlled cutoffs reject go."""
    judged = quality_rules.judge(docs.select("doc_id", "text", "lang", _key("key")), table(spark, sf_dir, "labels"), key_col="key")
    return _without(docs, judged, "not kept", "key")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays."""
    return simhash.keep_one(docs)


def contamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain benchmark passages go."""
    return _without(docs, decontaminate.contamination(_judged(docs), table(spark, sf_dir, "benchmark")), "contaminated")


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids and of the decoded bytes of what is left."""
    return byte_bpe.round_trip(docs.select("doc_id", "text"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [("language_id", language_id), ("quality_rules", quality), ("near_duplicates", near_duplicates), ("decontamination", contamination), ("byte_bpe", encoding)]

#: The first stage's classifier and the last one's tokens are beyond SQL; tests compare with a plain version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to all documents."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
