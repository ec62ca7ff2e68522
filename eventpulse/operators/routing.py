"""Five ways to deal tuples to tasks, and what each leaves in a task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def route_shuffle(df: DataFrame, n: int) -> DataFrame:
    """Evenly, without a key."""
    return df.repartition(n)


def route_all(df: DataFrame, n: int) -> DataFrame:
    """A copy of every tuple for each of n tasks, marked by task."""
    return df.withColumn("task", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))


def route_fields(df: DataFrame, n: int, *cols: str) -> DataFrame:
    """By the values of fields."""
    return df.repartition(n, *cols)


def route_global(df: DataFrame) -> DataFrame:
    """All to one task; for small results only."""
    return df.coalesce(1)


def route_direct(df: DataFrame, n: int, task: str) -> DataFrame:
    """Where the producer says: ``task`` holds the task's number."""
    return df.repartitionById(n, F.pmod(F.col(task), F.lit(n)).cast("int"))


def routing_skew(df: DataFrame) -> DataFrame:
    """(tasks, total_rows, skew): tasks with rows, their rows, and the largest against the mean."""
    by_task = df.groupBy(F.spark_partition_id().alias("task")).agg(F.count("*").alias("n"))
    return by_task.agg(F.count("*").alias("tasks"), F.sum("n").alias("total_rows"), (F.max("n") / F.avg("n")).alias("skew"))
