"""Written intermediate tables: what iterative and multi-pass plans are cut at."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder as the session names it; a temporary one only where it names none and is one process."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("a cluster has to name its shared folder in spark.checkpoint.dir")
    return _own.setdefault(spark.sparkContext.applicationId, tempfile.mkdtemp(prefix="blockbwt-core-"))


def fresh_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/core-{tag}-{uuid.uuid4().hex}"
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    return path


def materialise(df: DataFrame, tag: str = "table") -> DataFrame:
    """df as a written table: no lineage, and safe against lost executors."""
    path = fresh_path(df.sparkSession, tag)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
