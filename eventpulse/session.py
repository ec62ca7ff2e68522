"""Sessions for local runs; on a cluster the session is given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def get_spark(master: str = "local[8]", name: str = "eventpulse", **conf: str) -> SparkSession:
    """A session in UTC with adaptive execution and Arrow; other settings by keyword (dots as __)."""
    base = {
        "spark.sql.session.timeZone": "UTC", "spark.sql.adaptive.enabled": "true", "spark.ui.enabled": "false",
        "spark.sql.execution.arrow.pyspark.enabled": "true", "spark.sql.shuffle.partitions": "8",
        "spark.driver.memory": "8g",
    }
    b = SparkSession.builder.master(master).appName(name)
    for k, v in (base | {k.replace("__", "."): v for k, v in conf.items()}).items():
        b = b.config(k, v)
    return b.getOrCreate()
