"""Reading tables and files, writing scores, keeping models."""

from __future__ import annotations

import pickle
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_file(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """CSV, JSON or ORC with a declared schema: no pass to infer one."""
    return spark.read.schema(schema).format(fmt).load(path)


def write_scores(df: DataFrame, path: str, partition_by: list[str] | None = None) -> None:
    """Overwrite only the partitions that the scores touch, so a repeated run changes nothing."""
    w = df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic")
    (w.partitionBy(*partition_by) if partition_by else w).parquet(path)


def run_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def save_model(dag, path: str) -> None:
    """Keep a pipeline in one file (only load files you trust)."""
    Path(path).write_bytes(pickle.dumps(dag))


def load_model(path: str):
    return pickle.loads(Path(path).read_bytes())  # noqa: S301


def rows_df(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def stream_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's file as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its order, customer, nation, region, part and supplier; Spark picks the join of each by its size."""
    t = {n: read_table(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "nation", "region", "part", "supplier")}
    return (
        t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
        .join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
        .join(t["part"], F.col("l_partkey") == F.col("p_partkey")).join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    )
