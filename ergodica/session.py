"""A local session for tests, benchmarks and verification."""

from __future__ import annotations

import os

from pyspark.sql import SparkSession


def local_session(cores: int | str = "8", partitions: int = 8, memory: str = "8g") -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName("ergodica")
        .config("spark.driver.memory", os.environ.get("ERGODICA_MEMORY", memory)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", str(partitions)).config("spark.sql.session.timeZone", "UTC").config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark
