"""Tables that runs leave: cleaned posts and event candidates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def materialize_posts(df: DataFrame, path: str) -> DataFrame:
    """Posts written once, partitioned by region and day (days since 1970), and the table they make."""
    day = F.unix_date(F.to_date("ts"))
    df.withColumn("day", day).write.mode("overwrite").partitionBy("region", "day").parquet(path)
    return df.sparkSession.read.parquet(path)


def write_events(events: DataFrame, path: str) -> DataFrame:
    """Event candidates written by region, and the table they make. A rerun replaces the former result."""
    events.write.mode("overwrite").partitionBy("region").parquet(path)
    return events.sparkSession.read.parquet(path)
