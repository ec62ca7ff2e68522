"""Blocks: consecutive time intervals of fixed length, numbered from 1."""

from __future__ import annotations

import datetime as dt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from eventpulse.functions.clean import clean_tokens
from eventpulse.config import PrepConfig

#: Length of the slices that a block's arrival order is counted in.
SLICE_US = 5_000_000
_UNITS = {"second": 1, "minute": 60, "hour": 3600, "day": 86400}


def micros(length: str) -> int:
    """Microseconds of a length such as ``6 minutes``."""
    n, unit = length.split()
    return int(float(n) * _UNITS[unit.rstrip("s")] * 1_000_000)


def _origin(df: DataFrame, length: int, origin: dt.datetime | int | None, ts: str) -> int:
    if isinstance(origin, dt.datetime):
        origin = int(origin.replace(tzinfo=origin.tzinfo or dt.UTC).timestamp() * 1_000_000)
    if origin is not None:
        return origin // length * length
    return (first_time(df, ts) or 0) // length * length


def first_time(df: DataFrame, ts: str = "ts") -> int | None:
    """The earliest time in microseconds: a job over ``df``. Give it a table that stores its times, so that one
    column is read; streams whose first time is known pass that as their origin instead."""
    return df.agg(F.min(F.unix_micros(F.col(ts).cast("timestamp")))).first()[0]


def block_of(ts: Column, length: int, origin: int) -> Column:
    """Number of the block that holds a time."""
    return (F.floor((F.unix_micros(ts) - F.lit(origin)) / F.lit(length)) + 1).cast("long")


def assign_block(df: DataFrame, length: str = "6 minutes", origin: dt.datetime | int | None = None, ts: str = "ts") -> DataFrame:
    """``df`` with block_no and block_start. Blocks are aligned on the epoch; the first is that of the
    origin, or of the earliest time, which costs a job. Rows without a time are dropped."""
    n = micros(length)
    o = _origin(df, n, origin, ts)
    df = df.where(F.col(ts).isNotNull()).withColumn("block_no", block_of(F.col(ts), n, o))
    return df.withColumn("block_start", F.timestamp_micros(F.lit(o) + (F.col("block_no") - 1) * F.lit(n)))


def ordered(df: DataFrame, terms: str | None = None, slice_us: int = SLICE_US) -> DataFrame:
    """``df`` with seq, the arrival order within (region, block) from 0, block_posts, and, given the array column
    ``terms``, terms_before: its elements in the block's earlier posts.

    A block is cut into slices of time; what a slice holds is counted first, and a window runs inside a slice only. The second
    window is over one row for each slice, whatever the number of posts.
    """
    keys = ["region", "block_no", "_slice"]
    df = df.withColumn("_slice", F.floor(F.unix_micros("ts") / slice_us))
    size = F.size(terms) if terms else F.lit(0)
    held = df.groupBy(*keys).agg(F.count("*").alias("_n"), F.sum(size).alias("_t"))
    block = Window.partitionBy("region", "block_no")
    before = block.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    none = F.lit(0).cast("long")
    held = held.select(*keys, F.coalesce(F.sum("_n").over(before), none).alias("_posts"), F.coalesce(F.sum("_t").over(before), none).alias("_terms"), F.sum("_n").over(block).alias("block_posts"))
    inside = Window.partitionBy(*keys).orderBy("ts", "post_id")
    out = df.join(held, keys).withColumn("seq", (F.col("_posts") + F.row_number().over(inside) - 1).cast("long"))
    if terms:
        out = out.withColumn("terms_before", F.col("_terms") + F.coalesce(F.sum(size).over(inside.rowsBetween(Window.unboundedPreceding, -1)), none))
    return out.drop("_slice", "_posts", "_terms")


def with_seq(df: DataFrame) -> DataFrame:
    """``df`` with seq: arrival order within (region, block), from 0."""
    return ordered(df).drop("block_posts")


def tokened(posts: DataFrame, length: str = "6 minutes", prep: PrepConfig = PrepConfig(), origin: dt.datetime | int | None = None) -> DataFrame:
    """Posts with their block and tokens; the text goes no further."""
    out = assign_block(posts, length, origin).withColumn("tokens", clean_tokens(F.col("text"), prep)).drop("text")
    if prep.stem == "porter":
        from eventpulse.functions.stem import stem_tokens

        out = stem_tokens(out)
    return out


def block_calendar(df: DataFrame, tokens: str = "tokens") -> DataFrame:
    """(region, block_no, posts, terms) of every block from the first to the last, empty ones included."""
    held = df.groupBy("region", "block_no").agg(F.count("*").alias("posts"), F.sum(F.size(tokens)).alias("terms"))
    span = held.groupBy("region").agg(F.min("block_no").alias("lo"), F.max("block_no").alias("hi"))
    every = span.select("region", F.explode(F.sequence("lo", "hi")).alias("block_no"))
    out = every.join(held, ["region", "block_no"], "left")
    return out.select("region", "block_no", F.coalesce("posts", F.lit(0)).cast("long").alias("posts"), F.coalesce("terms", F.lit(0)).cast("long").alias("terms"))


def leak_blocks(df: DataFrame, fraction: float) -> DataFrame:
    """The last ``fraction`` of each block's posts moved into the next block: a source that does not wait."""
    late = F.col("seq") >= F.ceil((1 - fraction) * F.col("block_posts"))
    return ordered(df).withColumn("block_no", F.when(late, F.col("block_no") + 1).otherwise(F.col("block_no"))).drop("seq", "block_posts")
