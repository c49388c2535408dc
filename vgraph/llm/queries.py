"""The text operators' queries on the given tables: thin digests of what the operators return."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, id_store, lang_id, near_dedup, passages, piece_codec, pii, rules, toxicity, url_filter, url_list
from .common import read


def op1_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of every whole text, decoded again: doc_id, n_tokens, ids_crc32, round_trip."""
    return piece_codec.encode_digest(read(spark, sf_dir, "documents"))


def op2_weak_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted, n_votes of every row. A null or empty text has the score of a text without votes; repeated rows are
    scored each; a null doc_id counts as held in; without labels the lexicon votes alone; an empty table gives no rows; other columns are ignored."""
    docs = read(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, read(spark, sf_dir, "labels")))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, rule of every row. A null or empty text has no
    words and fails; repeated rows are judged each; without labels of both kinds only the base rule holds; other columns are ignored."""
    docs = read(spark, sf_dir, "documents")
    return rules.judge(docs, rules.fit(docs, read(spark, sf_dir, "labels")))


def op4_temporal_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page as of its capture; the table has no fetch time, so page_id gives one (see ``url_list``)."""
    pages = read(spark, sf_dir, "pages").select("page_id", "url").withColumn("fetched_at", url_list.fetched_at("page_id"))
    return url_filter.judge(pages, url_list.entries(spark))


def op5_bloom_lang_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row. Null texts and those without a letter are `und` with score 0, as all are where nothing
    was learned; ties go to the first language name; repeated rows are predicted each; other columns are ignored."""
    docs = read(spark, sf_dir, "documents")
    return lang_id.predict(docs, lang_id.fit(docs))


def op6_collinear_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each passage link: doc_id, start, end, match_doc_id, match_start, match_end, n_same, identity."""
    return passages.repeated(read(spark, sf_dir, "documents"))


def op7_spaced_seed_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document and benchmark item that it holds."""
    return decontam.overlaps(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def op8_bag_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document with its class id."""
    return near_dedup.near_duplicates(read(spark, sf_dir, "documents"))


def op9_content_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, read back from the written store. A null or empty text is its end id alone; rows with a null doc_id
    are left out; rows that repeat an id are documents one after another; an empty table gives no rows; other columns are ignored."""
    return id_store.round_trip(read(spark, sf_dir, "documents"))


def op10_contextual_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added of every row. A null text is empty; a row with a null doc_id has its base
    spans alone; repeated rows have a row each, with the added spans of all rows of that id; other columns are ignored."""
    return pii.digest(pii.extract(read(spark, sf_dir, "documents")))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir).drop("ids")


def queries():
    own = [
        op1_piece_codec, op2_weak_toxicity, op3_quality_rules, op4_temporal_url_filter, op5_bloom_lang_id, op6_collinear_passages,
        op7_spaced_seed_decontamination, op8_bag_minhash, op9_content_store, op10_contextual_pii, pipeline,
    ]
    return {f.__name__: f for f in own}


def oracle_sql():
    return {"op4_temporal_url_filter": url_list.oracle(), "op7_spaced_seed_decontamination": decontam.oracle()}
