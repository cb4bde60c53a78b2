"""Reading the given tables, and other file formats for party files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = (
    "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
).split()


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, or some of its columns; Parquet reads no others."""
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """Dealt over twice the cluster's cores by keys. A stated number is not coalesced by bytes, and small rows with much work each
    (masks, pairs of a block) would else meet in one task."""
    return df.repartition(2 * df.sparkSession.sparkContext.defaultParallelism, *keys)
