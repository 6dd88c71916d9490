"""The registered queries opN_<name>: each applies one operator to whole tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, near_duplicates, oracles, packing, personal_data, quality, repeats, sharding, token_counts, tokenbin, warc
from .common import scratch_path, table, written
from .tokenizing import default_path


def op1_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = scratch_path(spark, "warc")
    manifest = warc.write_captures(table(spark, sf_dir, "pages"), folder, least_bytes=0)
    captures = warc.assemble(written(warc.read_records(manifest, folder).drop("payload"), "warc-records"))
    return captures.select(
        F.col("capture_id").alias("page_id"), "payload_bytes", "payload_digest", F.col("kind").alias("record_type"), "refers_to",
        "n_request", "n_metadata",
    )


def op2_suffix_array_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), window=10)
    return decontaminate.digest(found)


def op3_chosen_path_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.near_duplicates(table(spark, sf_dir, "documents"), similarity=0.75, size=5)


def op4_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.shard_rows(table(spark, sf_dir, "documents"), 24, seed=20_240_601)
    return rows.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "row_number"
    )


def op9_token_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenbin.tokens_round_trip(table(spark, sf_dir, "documents"), default_path("byte_bpe_50k.json")).drop("ids")


def op5_crf_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data.find(table(spark, sf_dir, "documents"))


def op6_pretoken_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), default_path("piece_bpe_32k.model"), limit=4096)


def op7_radix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(table(spark, sf_dir, "documents"), least=400, words=50)


def op8_nnls_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), default_path("byte_bpe_50k.json"), window=1024)


def op10_robust_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_warc_transactions, op2_suffix_array_decontamination, op3_chosen_path_duplicates, op4_feistel_shards, op5_crf_personal_data, op6_pretoken_counts, op7_radix_repeats, op8_nnls_packing, op9_token_planes, op10_robust_quality)
}
ORACLES: dict[str, str] = {"op1_warc_transactions": oracles.OP1, "op2_suffix_array_decontamination": oracles.OP2, "op3_chosen_path_duplicates": oracles.OP3, "op7_radix_repeats": oracles.OP7}
