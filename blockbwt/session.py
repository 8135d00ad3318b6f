"""A session for tests and the bench; queries take any session as given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def local_session(cores: str | int = 8, partitions: int = 8, memory: str = "8g", app: str = "blockbwt") -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(app)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.adaptive.enabled", "true")
        .getOrCreate()
    )
