"""Driver queries of the subpackage: opN_<name> over whole tables, digest columns from the operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.llm import chat, decontam, mixing, oracles, pii, quality, sharding, simhash, toxicity, urlfilter, warc


#: stands in for a key from a secret store
PII_KEY = "public demonstration key"


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality.judge(spark, _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))
    return out.select("doc_id", *quality.BASE, "base_failed", "kept")


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.leaks(spark, _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark")).withColumnRenamed("id", "doc_id")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    model = toxicity.learn(spark, docs, _read(spark, sf_dir, "labels"))
    return toxicity.score_documents(spark, docs, model).withColumnRenamed("id", "doc_id")


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.assign(spark, _read(spark, sf_dir, "documents"), 16)
    return out.select(F.col("id").alias("doc_id"), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_chat_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.rotate(spark, _read(spark, sf_dir, "conversations"))


def op6_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = pii.pseudonymise(_read(spark, sf_dir, "documents"), PII_KEY, count_col="n_replaced")
    return out.select("doc_id", "text", "n_replaced")


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(spark, _read(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(spark, _read(spark, sf_dir, "pages")).select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.near_duplicates(spark, _read(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mix(spark, _read(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_quality_rules, op2_decontamination, op3_toxicity, op4_sharding, op5_chat_rotation, op6_pii_pseudonyms, op7_warc, op8_url_filter, op9_simhash, op10_mixing)}
#: the others rest on XXH64, SHA-256 networks, alignments, or a fitted model: tests hold their results against brute force
ORACLES: dict[str, str] = {"op1_quality_rules": oracles.quality_rules(), "op4_sharding": oracles.shards(), "op5_chat_rotation": oracles.chat_rotation(), "op7_warc": oracles.warc_records(), "op8_url_filter": oracles.url_filter(), "op10_mixing": oracles.mixing_sources()}
