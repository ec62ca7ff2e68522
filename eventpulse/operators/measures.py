"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(run: Callable[[], DataFrame]) -> tuple[float, int]:
    """Seconds and rows of a run that is written to nowhere."""
    began = time.perf_counter()
    df = run()
    n = df.count()
    return time.perf_counter() - began, n


def throughput(rows: int, seconds: float) -> float:
    """Tuples a second."""
    return rows / seconds if seconds else float("inf")


def event_count(events: DataFrame) -> DataFrame:
    """(region, events), and the sum over regions under a null region."""
    return events.rollup("region").agg(F.count("*").alias("events"))


def pauses(blocked: DataFrame) -> DataFrame:
    """One pause for each block that has posts."""
    return blocked.agg(F.count_distinct("region", "block_no").alias("pauses"))


def store_trips(blocked: DataFrame) -> DataFrame:
    """Store round trips of the two-stage (one a block) and of the single-stage design (one a post)."""
    return blocked.agg(F.count_distinct("region", "block_no").alias("two_stage"), F.count("*").alias("single_stage"))


def overlap(cluster_words: DataFrame, bursts: DataFrame, align: str = "any", within: int = 0) -> DataFrame:
    """How far two detectors agree, by region: clusters that hold a burst word, and burst words that a cluster
    holds, each against all.

    align: any (whole run), or block: events at most ``within`` blocks apart.
    """
    c = cluster_words.select("region", F.col("block_no").alias("cb"), "cluster_id", "word").distinct()
    b = bursts.select("region", F.col("block_no").alias("bb"), "word").distinct()
    if align == "any":
        met = c.join(b.select("region", "word").distinct(), ["region", "word"])
    else:
        near = b.withColumn("cb", F.explode(F.sequence(F.col("bb") - within, F.col("bb") + within)))
        met = c.join(near.select("region", "word", "cb").distinct(), ["region", "word", "cb"])
    hit = met.groupBy("region").agg(F.count_distinct("cluster_id").alias("clusters_hit"), F.count_distinct("word").alias("words_hit"))
    n_c = c.groupBy("region").agg(F.count_distinct("cluster_id").alias("clusters"))
    n_w = b.groupBy("region").agg(F.count_distinct("word").alias("words"))
    out = n_c.join(n_w, "region", "full").join(hit, "region", "left").na.fill(0)
    rate = lambda a, n: F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(n).cast("double")), F.lit(0.0))
    return out.select("region", "clusters", "clusters_hit", "words", "words_hit", rate("clusters_hit", "clusters").alias("cluster_rate"), rate("words_hit", "words").alias("word_rate"))


def stability(runs: DataFrame, value: str = "events") -> DataFrame:
    """(least, most, spread): range of a count over runs, against its largest value."""
    lo, hi = F.min(value), F.max(value)
    return runs.agg(lo.alias("least"), hi.alias("most"), F.coalesce(F.try_divide((hi - lo).cast("double"), hi.cast("double")), F.lit(0.0)).alias("spread"))


def score_against(events: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """(found, missed, wrong, precision, recall) of events against known ones."""
    e, t = events.select(*on).distinct().withColumn("_e", F.lit(1)), truth.select(*on).distinct().withColumn("_t", F.lit(1))
    both = e.join(t, on, "full")
    counts = both.agg(F.count_if(F.col("_e").isNotNull() & F.col("_t").isNotNull()).alias("found"), F.count_if(F.col("_e").isNull()).alias("missed"), F.count_if(F.col("_t").isNull()).alias("wrong"))
    share = lambda rest: F.coalesce(F.try_divide(F.col("found").cast("double"), (F.col("found") + F.col(rest)).cast("double")), F.lit(0.0))
    return counts.select("*", share("wrong").alias("precision"), share("missed").alias("recall"))


def costs(fold: DataFrame) -> DataFrame:
    """(metric, value): the cost rows of a fold, summed over blocks and regions; live clusters at their largest."""
    rows = fold.where("kind = 'cost'")
    return rows.groupBy("metric").agg(F.when(F.first("metric") == "live", F.max("value")).otherwise(F.sum("value")).alias("value"))


def shuffled(df: DataFrame) -> list[tuple[int, int]]:
    """(rows, bytes) that each exchange of a run of ``df`` writes, from the metrics of its final plan."""
    run = df._jdf.queryExecution()
    run.toRdd().count()
    todo, out = [run.executedPlan()], []
    while todo:
        node = todo.pop()
        name = node.nodeName()
        if name == "AdaptiveSparkPlan":
            todo.append(node.executedPlan())
            continue
        if name.endswith("QueryStage"):
            todo.append(node.plan())
            continue
        if name == "Exchange":
            m = node.metrics()
            out.append((int(m.apply("shuffleRecordsWritten").value()), int(m.apply("shuffleBytesWritten").value())))
        if name != "ReusedExchange":
            kids = node.children()
            todo += [kids.apply(i) for i in range(kids.size())]
    return out
