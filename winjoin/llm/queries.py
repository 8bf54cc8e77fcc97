"""Thin queries over the given tables, one for each operator of this subpackage."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from winjoin.llm.chosen_path import similarity_classes
from winjoin.llm.decontam import contamination, items_digest
from winjoin.llm.katz import katz_scores
from winjoin.llm.language_fusion import page_languages
from winjoin.llm.license_align import license_scan
from winjoin.llm.line_crf import quality_scores, train
from winjoin.llm.pii_bootstrap import KINDS, find_spans, spans_text
from winjoin.llm.piece_viterbi import piece_encode
from winjoin.llm.token_resync import token_counts
from winjoin.llm.winnow import edited_likeness

#: The vocabulary file of the token queries; a parameter of the operators.
PIECE_MODEL = "piece_bpe_32k.model"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(table(spark, sf_dir, "documents"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path(PIECE_MODEL))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity_classes(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "n_links")


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), items_digest(F.col("items")).alias("items_sha256"), "contaminated")


def op6_piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_encode(table(spark, sf_dir, "documents"), public_tokenizers.path(PIECE_MODEL))


#: Words of the longest n-grams of the query's language model, as in round 1; the operator's own default is 3, for which README has the measured needs.
KATZ_ORDER = 2


def op7_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz_scores(table(spark, sf_dir, "documents"), order=KATZ_ORDER)


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_languages(table(spark, sf_dir, "pages"), table(spark, sf_dir, "documents"))


#: The accepted score of the quality classifier.
QUALITY_AT = 0.7


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = quality_scores(docs, train(docs, table(spark, sf_dir, "labels")), keep=["doc_id"])
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), F.col("quality_score").alias("score"), F.when(F.col("quality_score") >= QUALITY_AT, 1).otherwise(0).alias("predicted"))


def op9_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_likeness(table(spark, sf_dir, "documents"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_spans(table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda s: s["base"])

    def count(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s["base"] & (s["kind"] == kind))).cast("long").alias(f"n_{kind}")

    counts = [count(k) for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(spans_text(base), 256).alias("base_sha256"), spans_text(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_license_scan": op1_license_scan,
    "op2_token_counts": op2_token_counts,
    "op3_jaccard_join": op3_jaccard_join,
    "op4_decontamination": op4_decontamination,
    "op5_language": op5_language,
    "op6_piece_encoding": op6_piece_encoding,
    "op7_katz": op7_katz,
    "op8_quality": op8_quality,
    "op9_winnowing": op9_winnowing,
    "op10_pii": op10_pii,
}

_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

#: What SQL can say whole; the other operators are compared with brute force, round trips or held-out labels in tests/llm.
ORACLE_SQL: dict[str, str] = {
    "op4_decontamination": f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, {_WORDS} AS w FROM documents),
    b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_WORDS} AS w FROM benchmark WHERE item_id IS NOT NULL),
    item AS MATERIALIZED (SELECT DISTINCT item, least(10, len(w)) AS size, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') AS span FROM (SELECT *, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)),
    win AS (SELECT rid, i, size, array_to_string(w[i : i + size - 1], ' ') AS span FROM (SELECT d.*, s.size, unnest(range(1, len(w) - s.size + 2)) AS i FROM d, (SELECT DISTINCT size FROM item) s WHERE len(w) >= s.size)),
    met AS MATERIALIZED (SELECT win.rid, win.i, win.size, item.item FROM win JOIN item ON item.size = win.size AND item.span = win.span),
    hit AS (SELECT rid, count(*) AS n FROM (SELECT DISTINCT rid, unnest(range(i, i + size)) AS p FROM met) GROUP BY rid),
    known AS (SELECT rid, list_sort(list_distinct(list(item))) AS items FROM met GROUP BY rid)
    SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(hit.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(len(known.items), 0) AS BIGINT) AS n_items, sha256(coalesce(array_to_string(known.items, ','), '')) AS items_sha256, coalesce(hit.n, 0) > 0 AS contaminated
    FROM d LEFT JOIN hit ON hit.rid = d.rid LEFT JOIN known ON known.rid = d.rid""",
}
