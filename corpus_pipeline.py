"""A training-corpus pipeline of five stages over the table documents.

Each stage takes (spark, docs, sf_dir) and returns a frame that is written as
Parquet and read again as the next stage's docs. All but the last return the
columns of documents. Nulls, empty texts, repeated rows and empty tables are
handled as the operators' docstrings say.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winjoin.llm.chosen_path import keep_one_of_each
from winjoin.llm.decontam import decontaminate
from winjoin.llm.frames import materialize
from winjoin.llm.line_crf import quality_scores, train
from winjoin.llm.pii_bootstrap import redact
from winjoin.llm.piece_viterbi import piece_encode
from winjoin.llm.queries import PIECE_MODEL, QUALITY_AT, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line classifier scores at 0.7 or more."""
    score = "quality_score" + "_" * sum(c.startswith("quality_score") for c in docs.columns)
    scored = quality_scores(docs, train(docs, table(spark, sf_dir, "labels")), out=score)
    return scored.where(F.col(score) >= QUALITY_AT).drop(score)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of five-word similarity 0.8 or more."""
    return keep_one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a ten-word window of the benchmark."""
    return decontaminate(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data replaced by its kind; n_chars follows."""
    return redact(docs).withColumn("n_chars", F.coalesce(F.char_length("text").cast("long"), F.col("n_chars")))


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of each document and the text they decode to."""
    return piece_encode(docs, public_tokenizers.path(PIECE_MODEL), decoded=True)


STAGES = [
    ("quality classifier", quality),
    ("n-gram Jaccard join", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("PII", personal_data),
    ("SentencePiece encoding and decoding", pieces),
]

#: SQL has neither the classifier nor the similarity join; tests compare each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), "pipeline-" + name.split(" ")[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
