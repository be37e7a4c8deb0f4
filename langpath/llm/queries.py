"""Driver queries of the training-data operators: thin digests over the operators' own outputs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, compression, decontam, html, kneser_ney, lpf, minhash, packing, secrets, slots, wavelet


def op1_wavelet_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents", "doc_id", "text")
    shards = wavelet.write_shards(docs, common.new_path(spark, "wavelet"), common.tokenizer_file(), end_id=0)
    return wavelet.read_documents(shards)


def op2_compression_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compression.score(common.read(spark, sf_dir, "documents", "doc_id", "text"))


def op3_kneser_ney_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents", "doc_id", "lang", "text")
    return kneser_ney.classify(docs, common.read(spark, sf_dir, "labels", "doc_id", "quality"))


def op4_hierarchical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents", "doc_id", "text")
    return packing.pack(docs, common.tokenizer_file(), end_id=0)


def op5_tag_path_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract_pages(common.read(spark, sf_dir, "pages", "page_id", "url", "html"))


def op6_simhash_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents", "doc_id", "text")
    found = decontam.find(docs, common.read(spark, sf_dir, "benchmark", "item_id", "text"))
    return found.select("doc_id", F.col("hits.item_id").alias("item_ids"), F.size("hits").cast("long").alias("n_items"), F.array_max("hits.similarity").alias("best_similarity"), "kept")


def op7_virtual_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = slots.records(common.read(spark, sf_dir, "documents", "doc_id", "text"))
    m = slots.save_map(slots.new_map(slots.slot_loads(rows)), common.new_path(spark, "slot-map"))
    out = slots.assign(rows, m)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("position").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "vslot", "map_version")


def op8_secret_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(common.read(spark, sf_dir, "documents", "doc_id", "text"))
    counts = [secrets.count_kind("base", k).alias(f"n_{name}") for k, (name, *_) in enumerate(secrets.BASE_KINDS)]
    return found.select("doc_id", *counts, F.sha2(secrets.as_text("base"), 256).alias("base_sha256"), secrets.as_text("spans").alias("spans"))


def op9_tensored_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    linked = minhash.link(common.read(spark, sf_dir, "documents", "doc_id", "text"))
    return linked.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def op10_longest_previous_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = lpf.remove_repeats(common.read(spark, sf_dir, "documents", "doc_id", "text"), keep="none", passage=(lpf.PASSAGE, lpf.PASSAGE_WORDS))
    said = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["a"].cast("string"), x["b"].cast("string"))), ",")
    return cut.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", said("removed").alias("removed"), F.size("passages").cast("long").alias("n_passages"), said("passages").alias("passages"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_wavelet_tokens, op2_compression_bands, op3_kneser_ney_perplexity, op4_hierarchical_packing, op5_tag_path_ratios, op6_simhash_decontamination, op7_virtual_slots, op8_secret_linking, op9_tensored_minhash, op10_longest_previous_factor)
}
ORACLE_SQL: dict[str, str] = {}
