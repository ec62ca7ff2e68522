"""Prefix rules on URLs by a sort-merge range join over reversed-host keys.

A host is written label by label from its end (``www.example.org`` becomes ``org example
www``), each label closed by a separator, so that a rule's host and all its subdomains
form one interval of the sorted keys. Intervals of host rules are nested or disjoint.
One sort of URLs and interval ends together, and a running "last event" over it, gives
each URL the stack of the host rules that are open at its key; the path prefixes of
that stack are then compared and the longest rule wins.

DataFrame functions only.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

SEP, AFTER = "\x01", "\x02"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rows that one sort of the sweep holds at most.
ROWS_PER_SWEEP = 1_000_000


def url_host(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; else empty."""
    rest = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(rest, UPPER, LOWER), F.lit(""))


def url_path(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; empty without ``://``."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def host_key(host: Column) -> Column:
    """Labels from the last to the first, each closed by the separator."""
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), SEP), F.lit(SEP))


def _rule_key(host: str) -> str:
    return SEP.join(reversed(host.split("."))) + SEP


def _events(rules: Sequence[tuple[str, str]]) -> list[tuple[str, list[tuple[str, str, str, int]]]]:
    """Interval ends in key order, each with the stack that holds from there on."""
    hosts: dict[str, list[tuple[str, str, str, int]]] = {}
    for verdict, rule in dict.fromkeys(rules):
        host, _, path = rule.partition("/")
        hosts.setdefault(host.lower(), []).append((rule, verdict, "/" + path, len(rule)))
    opened = sorted((_rule_key(h), rs) for h, rs in hosts.items())
    events, stack = [], []

    def close(upto: str | None) -> None:
        while stack and (upto is None or not upto.startswith(stack[-1][0])):
            key, _ = stack.pop()
            events.append((key[:-1] + AFTER, [r for _, rs in stack for r in rs]))

    for key, rs in opened:
        close(key)
        stack.append((key, rs))
        events.append((key, [r for _, own in stack for r in own]))
    close(None)
    last: dict[str, list] = {}
    for key, held in events:  # of ends at one key the later one holds
        last[key] = held
    return sorted(last.items())


def filter_urls(df: DataFrame, rules: Sequence[tuple[str, str]], url: str = "url", otherwise: str = "allow", sweeps: int | None = None) -> DataFrame:
    """``df`` with host, path, rule and verdict for each row.

    rules: (verdict, "host/path prefix") pairs; a rule fits its host and all subdomains if
    the path starts with its path; the longest wins, of equally long ones the smaller
    text. Rows without a rule get ``otherwise``. A null url, or one without ``://``, has
    an empty host and path and no rule. Repeated rows stay repeated; columns of ``df`` named
    host, path, rule or verdict are replaced; an empty table stays empty.

    Rows are dealt evenly over ``sweeps`` sorts (as many as shuffle partitions, or more if one would hold over
    ``ROWS_PER_SWEEP``), whatever their host, and the interval ends
    (a list the caller holds, two for each rule) are given to each; a hot host is thus split.
    """
    spark = df.sparkSession
    n = sweeps or max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8, -(-df.select(F.lit(1)).count() // ROWS_PER_SWEEP))
    keep = [c for c in df.columns if c.lower() not in ("host", "path", "rule", "verdict")]
    stack_type = T.ArrayType(T.StructType([T.StructField("rule", T.StringType()), T.StructField("verdict", T.StringType()), T.StructField("prefix", T.StringType()), T.StructField("len", T.IntegerType())]))
    ends = spark.createDataFrame(_events(rules), T.StructType([T.StructField("_key", T.StringType()), T.StructField("_stack", stack_type)]))
    none = lambda t: F.lit(None).cast(t)
    ends = ends.withColumn("_sweep", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    ends = ends.select("_sweep", "_key", F.lit(0).alias("_turn"), "_stack", none("struct<" + ",".join(f"`{f.name.replace('`', '``')}`:{f.dataType.simpleString()}" for f in df.schema if f.name in keep) + ">").alias("_row"), none("string").alias("host"), none("string").alias("path"))
    host = url_host(F.col(url))
    # round robin by the row's own position: even whatever the keys are, and the same on a rerun of the task
    rows = df.select(F.pmod(F.monotonically_increasing_id(), F.lit(n)).cast("int").alias("_sweep"), host_key(host).alias("_key"), F.lit(1).alias("_turn"), none(stack_type).alias("_stack"), F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in keep]).alias("_row"), host.alias("host"), url_path(F.col(url)).alias("path"))
    order = Window.partitionBy("_sweep").orderBy("_key", "_turn").rowsBetween(Window.unboundedPreceding, 0)
    swept = ends.unionAll(rows).withColumn("_open", F.last("_stack", ignorenulls=True).over(order)).where("_turn = 1")
    fits = F.filter("_open", lambda r: F.startswith(F.col("path"), r["prefix"]))
    best = F.array_min(F.transform(fits, lambda r: F.struct((-r["len"]).alias("neg"), r["rule"].alias("rule"), r["verdict"].alias("verdict"))))
    return (
        swept.withColumn("_best", best)
        .select("_row.*", "host", "path", F.col("_best.rule").alias("rule"), F.coalesce("_best.verdict", F.lit(otherwise)).alias("verdict"))
    )
