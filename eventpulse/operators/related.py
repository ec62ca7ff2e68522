"""Neighbouring methods: co-bursting words, term graphs, rising partners, first posts, places, audiences."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from eventpulse.operators.components import connected_components


def co_burst_groups(events: DataFrame) -> DataFrame:
    """(region, block_no, n_words, words): words that burst in one block are one event."""
    return events.groupBy("region", "block_no").agg(F.count_distinct("word").alias("n_words"), F.array_join(F.array_sort(F.collect_set("word")), " ").alias("words"))


def term_pairs(tokens: DataFrame, min_n: int) -> DataFrame:
    """(region, block_no, w1, w2, n): words that at least ``min_n`` posts of a block have in common, w1 < w2."""
    words = tokens.select("region", "block_no", "post_id", F.explode(F.array_distinct("tokens")).alias("word"))
    often = words.groupBy("region", "block_no", "word").agg(F.count("*").alias("n")).where(F.col("n") >= min_n).drop("n")  # others are in no such pair
    own = words.join(often, ["region", "block_no", "word"]).groupBy("region", "block_no", "post_id").agg(F.array_sort(F.collect_list("word")).alias("words"))
    later = lambda w, i: F.transform(F.slice("words", i + 2, F.size("words")), lambda v: F.struct(w.alias("w1"), v.alias("w2")))
    rows = own.select("region", "block_no", F.explode(F.flatten(F.transform("words", later))).alias("p"))
    return rows.groupBy("region", "block_no", "p.w1", "p.w2").agg(F.count("*").alias("n")).where(F.col("n") >= min_n)


def term_graph_events(tokens: DataFrame, min_n: int) -> DataFrame:
    """(region, block_no, n_words, words): connected subgraphs of a block's term graph."""
    pairs = term_pairs(tokens, min_n)
    node = lambda w: F.xxhash64("region", "block_no", w)
    cc = connected_components(pairs.select(node("w1").alias("src"), node("w2").alias("dst")))
    names = pairs.select("region", "block_no", F.explode(F.array("w1", "w2")).alias("word")).distinct().withColumn("node", node("word"))
    groups = names.join(cc, "node").groupBy("region", "block_no", "component")
    return groups.agg(F.count("*").alias("n_words"), F.array_join(F.array_sort(F.collect_list("word")), " ").alias("words")).drop("component")


def rising_partners(tokens: DataFrame, tag: str) -> DataFrame:
    """(region, block_no, word, n, prev_n) of words that occur with ``tag`` in more posts than in the block before."""
    rows = tokens.where(F.array_contains("tokens", tag)).select("region", "block_no", F.explode(F.array_distinct("tokens")).alias("word")).where(F.col("word") != tag)
    n = rows.groupBy("region", "block_no", "word").agg(F.count("*").alias("n"))
    w = Window.partitionBy("region", "word").orderBy("block_no")
    prev = F.when(F.lag("block_no").over(w) == F.col("block_no") - 1, F.lag("n").over(w)).otherwise(F.lit(0))
    return n.withColumn("prev_n", prev.cast("long")).where(F.col("n") > F.col("prev_n"))


def _members(events: DataFrame, posts: DataFrame) -> DataFrame:
    words = posts.select("region", "block_no", "post_id", "ts", F.explode(F.array_distinct("tokens")).alias("word"))
    return events.select("region", "block_no", "word").join(words, ["region", "block_no", "word"])


def first_post(events: DataFrame, posts: DataFrame) -> DataFrame:
    """(region, block_no, word, post_id): the earliest post of the block with the event's word."""
    return _members(events, posts).groupBy("region", "block_no", "word").agg(F.min(F.struct("ts", "post_id"))["post_id"].alias("post_id"))


def locate_events(events: DataFrame, posts: DataFrame, place: str = "place") -> DataFrame:
    """(block_no, word, place, n): the most frequent place of an event's posts; of equal ones the smaller name."""
    words = posts.select("block_no", place, F.explode(F.array_distinct("tokens")).alias("word"))
    n = events.select("block_no", "word").distinct().join(words, ["block_no", "word"]).groupBy("block_no", "word", place).agg(F.count("*").alias("n"))
    best = F.min(F.struct((-F.col("n")).alias("neg"), F.col(place).alias("place")))
    return n.groupBy("block_no", "word").agg(best.alias("b")).select("block_no", "word", F.col("b.place").alias("place"), (-F.col("b.neg")).alias("n"))


def participants(events: DataFrame, posts: DataFrame, user: str = "user_id") -> DataFrame:
    """(block_no, word, n_users, first_user): who wrote an event's posts."""
    words = posts.select("block_no", user, F.explode(F.array_distinct("tokens")).alias("word"))
    return events.select("block_no", "word").distinct().join(words, ["block_no", "word"]).groupBy("block_no", "word").agg(F.count_distinct(user).alias("n_users"), F.min(user).alias("first_user"))


def partners(pairs: DataFrame, k: int) -> DataFrame:
    """(word, partner): the k words that each word occurs with most often."""
    both = pairs.select(F.col("w1").alias("word"), F.col("w2").alias("partner"), "n").unionByName(pairs.select(F.col("w2").alias("word"), F.col("w1").alias("partner"), "n"))
    total = both.groupBy("word", "partner").agg(F.sum("n").alias("n"))
    rank = F.row_number().over(Window.partitionBy("word").orderBy(F.desc("n"), "partner"))
    return total.withColumn("_r", rank).where(F.col("_r") <= k).select("word", "partner")


def expand_tokens(tokens: DataFrame, assoc: DataFrame, key: str = "post_id") -> DataFrame:
    """Posts with the partners of their words added to their tokens, once each."""
    words = tokens.select(key, F.explode(F.array_distinct("tokens")).alias("word"))
    more = words.join(assoc, "word").groupBy(key).agg(F.array_sort(F.collect_set("partner")).alias("_more"))
    out = tokens.join(more, key, "left")
    return out.withColumn("tokens", F.concat("tokens", F.array_except(F.coalesce("_more", F.array().cast("array<string>")), "tokens"))).drop("_more")
