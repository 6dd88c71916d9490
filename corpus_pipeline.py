"""A training-corpus pipeline: quality rules, near-duplicates, decontamination, personal data, packing.

Every stage takes (spark, docs, sf_dir) and gives a table; all but the last give the
columns of ``documents``.  ``run`` writes each stage's table and reads it again.  Stages decide
row by row: ids may repeat or be null.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tensorlane.llm import decontaminate, near_duplicates, packing, personal_data, quality
from tensorlane.llm.common import drop_written, scratch_path, table, write_table, written
from tensorlane.llm.tokenizing import default_path

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


#: Column of a row key, unique in its table, whatever the ids are.
ROW = "_row"


def _keyed(docs: DataFrame, label: str) -> DataFrame:
    """``docs`` with a row key, written, so that every reader sees the same keys."""
    return written(docs.withColumn(ROW, F.monotonically_increasing_id()), label)


#: Bitmaps of at most so many blocks of keys (4 kB each) are sent to all workers.
LOOKUP_BLOCKS = 16_384


def _chosen(docs: DataFrame, kept: DataFrame) -> DataFrame:
    """The rows of a keyed table whose keys are in ``kept``, without the key.

    Keys are set in bitmaps, one for each 32,768 rows of a partition, which all workers get: texts stay where
    they are.  Only a table of more than ``LOOKUP_BLOCKS`` bitmaps is joined by a shuffle of its rows.
    """
    kept = written(kept.select(ROW), "chosen-keys")
    blocks = written(kept.groupBy(F.bitmap_bucket_number(ROW).alias("_block")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(ROW)).alias("_bits")), "chosen-blocks")
    if blocks.count() > LOOKUP_BLOCKS:
        drop_written(blocks)
        return docs.join(kept, ROW, "left_semi").drop(ROW)
    drop_written(kept)
    at = F.bitmap_bit_position(ROW)
    byte = F.conv(F.hex(F.substring(F.col("_bits"), F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return docs.join(F.broadcast(blocks), F.bitmap_bucket_number(ROW) == F.col("_block")).filter(F.getbit(byte, (at % 8).cast("int")) == 1).select(docs.columns).drop(ROW)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the robust distance reject go."""
    return quality.judge(docs, whole=True).filter("kept").select("row.*")


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays, the first by id (null last) and row key."""
    rows = _keyed(docs, "near-rows")
    found = near_duplicates.near_duplicates(rows, similarity=0.75, size=5, row_col=ROW)
    return _chosen(rows, found.filter("first"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    return decontaminate.remove_contaminated(docs, table(spark, sf_dir, "benchmark"), window=10)


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in texts becomes marks; ``n_chars``, where the table has it, follows the new text."""
    out = personal_data.redact(docs)
    if "n_chars" in out.columns:
        length = F.char_length("text").cast(docs.schema["n_chars"].dataType)
        out = out.withColumn("n_chars", F.when(F.col("text").isNotNull(), length).otherwise(F.col("n_chars")))
    return out


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 1024 tokens: a row for each piece."""
    return packing.pack(docs, default_path("byte_bpe_50k.json"), window=1024)


STAGES: list[tuple[str, Stage]] = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("personal_data", personal_data_stage),
    ("packing", packing_stage),
]

#: The robust estimate, the random field and the tokenizer are not SQL; tests hold the pipeline against a plain version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = scratch_path(spark, f"pipeline-{name}")
        write_table(stage(spark, docs, sf_dir), path)
        docs = spark.read.parquet(path)
    return docs
