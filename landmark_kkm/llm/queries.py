"""The queries opN_<name>, with production parameters over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from landmark_kkm.llm import decontaminate, langid, linededup, packing, ppm, sharding, simhash, sketches, toxicity, warc
from landmark_kkm.session import read_table, spread


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")), radius=4, width=4)


def op2_ppm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.score_documents(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spread(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return toxicity.score_documents(docs, toxicity.learn(docs, read_table(spark, sf_dir, "labels")))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spread(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return decontaminate.contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.line_report(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")))


def op6_warc_reassembly(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = warc.round_trip(spark, spread(read_table(spark, sf_dir, "pages").select("page_id", "url", "html")))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spread(read_table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))
    return langid.predict(docs, langid.learn(docs))


def op8_scaled_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketches.edited_pairs(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")))


def op10_lpt_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(spread(read_table(spark, sf_dir, "documents").select("doc_id", "text")), shards=40)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_simhash_near_dedup": op1_simhash_near_dedup,
    "op2_ppm_scoring": op2_ppm_scoring,
    "op3_toxicity": op3_toxicity,
    "op4_decontamination": op4_decontamination,
    "op5_line_dedup": op5_line_dedup,
    "op6_warc_reassembly": op6_warc_reassembly,
    "op7_language_id": op7_language_id,
    "op8_scaled_sketch": op8_scaled_sketch,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_lpt_sharding": op10_lpt_sharding,
}

ORACLE_SQL: dict[str, str] = {
    "op5_line_dedup": linededup.LINE_SQL,
    "op6_warc_reassembly": warc.WARC_SQL,
}
