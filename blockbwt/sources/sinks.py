"""Where transforms go: text files by range, Parquet rounds, and other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockbwt.operators.construct import bwt_blocks


def write_ascii(bwt: DataFrame, path: str, block: int = 65536) -> None:
    """block=i/ folders of text: joined in order they are the transform. Nothing is gathered beyond a block."""
    bwt_blocks(bwt, block).repartitionByRange("block_id").write.mode("overwrite").partitionBy("block_id").option("lineSep", "\u0001").text(path)


def read_ascii(spark: SparkSession, path: str) -> DataFrame:
    """(block_id, text)"""
    rows = spark.read.option("lineSep", "\u0001").text(path)
    return rows.select(F.col("block_id").cast("long").alias("block_id"), F.col("value").alias("text"))


def read_rounds(spark: SparkSession, path: str) -> DataFrame:
    """The transform that rounds have written."""
    return spark.read.parquet(path)


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """df written and read in one of Spark's own formats, by its schema."""
    spark = df.sparkSession
    if kind == "csv":
        df.write.mode("overwrite").option("header", True).csv(path)
        return spark.read.schema(df.schema).option("header", True).csv(path)
    getattr(df.write.mode("overwrite"), kind)(path)
    return getattr(spark.read.schema(df.schema), kind)(path)
