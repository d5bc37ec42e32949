"""A session with the settings that the engine is designed for; every function also works with a session as given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def session(master: str = "local[*]", shuffle_partitions: int = 8, **config: str) -> SparkSession:
    builder = SparkSession.builder.master(master).appName("geocentra")
    settings = {
        "spark.sql.shuffle.partitions": str(shuffle_partitions),
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.ui.enabled": "false",
    }
    for key, value in (settings | config).items():
        builder = builder.config(key, value)
    return builder.getOrCreate()
