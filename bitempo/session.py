"""A local session for tests and benches. Queries take whatever session they are given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def build_session(cores: int | str = "*", memory: str = "6g", partitions: int = 8, **more: str) -> SparkSession:
    builder = SparkSession.builder.master(f"local[{cores}]").appName("bitempo")
    settings = {
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
        "spark.driver.memory": memory,
    } | {k.replace("__", "."): v for k, v in more.items()}
    for key, value in settings.items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark
