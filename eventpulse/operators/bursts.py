"""Uncommonly common words: tf-idf by block, its growth over the previous block, and the trend.

Two wide shuffles: one to count words, after partial counts in the map tasks, and one to bring the
blocks of a word together; document frequency, previous score, quiet window and trend share the
sort of the second.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window, WindowSpec

from eventpulse.config import EPS, BurstConfig
from eventpulse.operators.blocks import ordered
from eventpulse.operators.packed import complete_counts, is_packed, partial_counts

#: Buckets of words that :func:`among_common` tells apart.
BUCKETS = 1 << 20


def _by_word() -> WindowSpec:
    return Window.partitionBy("word", "region").orderBy("block_no")  # few rows differ in their region: words first are sorted sooner


def explode_words(df: DataFrame, tokens: str = "tokens") -> DataFrame:
    """(region, block_no, word) of every token.

    The outer explode keeps the optimizer from adding a filter on the array's size below it, which would
    clean every text twice.
    """
    return df.select("region", "block_no", F.explode_outer(tokens).alias("word")).where("word is not null")


def count_words(df: DataFrame, tokens: str = "tokens") -> DataFrame:
    """(region, block_no, word, cnt)."""
    return explode_words(df, tokens).groupBy("region", "block_no", "word").agg(F.count("*").alias("cnt"))


def common_words(wc: DataFrame, min_count: int) -> DataFrame:
    """Words with at least ``min_count`` occurrences in the block."""
    return wc.where(F.col("cnt") >= min_count)


def block_totals(wc: DataFrame) -> DataFrame:
    """(region, block_no, block_terms, block_distinct), from the counts instead of the words."""
    return wc.groupBy("region", "block_no").agg(F.sum("cnt").alias("block_terms"), F.count("*").alias("block_distinct"))


def term_frequency(wc: DataFrame, denominator: str = "total") -> DataFrame:
    """``wc`` with block_terms, block_distinct and tf."""
    out = wc if "block_terms" in wc.columns else wc.join(block_totals(wc), ["region", "block_no"])
    return out.withColumn("tf", F.col("cnt") / F.col("block_terms" if denominator == "total" else "block_distinct").cast("double"))


def _frequency(cfg: BurstConfig) -> Column:
    counted = F.lit(1) if cfg.scope == "all" else F.when(F.col("cnt") >= cfg.min_count, 1).otherwise(0)
    w = _by_word().rowsBetween(Window.unboundedPreceding, 0) if cfg.corpus == "prefix" else Window.partitionBy("word", "region")
    return F.sum(counted).over(w).cast("long")


def document_frequency(wc: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """``wc`` with df: the blocks that hold the word, so far or in the whole corpus."""
    return wc.withColumn("df", _frequency(cfg))


def block_numbers(wc: DataFrame, cfg: BurstConfig) -> DataFrame:
    """``wc`` with n_blocks, the N of the idf."""
    if cfg.corpus == "prefix" and cfg.blocks == "elapsed":
        return wc.withColumn("n_blocks", F.col("block_no"))
    held = wc.select("region", "block_no").distinct()
    if cfg.corpus == "full":
        n = F.max("block_no") if cfg.blocks == "elapsed" else F.count("*")
        return wc.join(held.groupBy("region").agg(n.cast("long").alias("n_blocks")), "region")
    nth = F.row_number().over(Window.partitionBy("region").orderBy("block_no")).cast("long")  # a row for each block
    return wc.join(held.withColumn("n_blocks", nth), ["region", "block_no"])


def idf(n: Column, df: Column) -> Column:
    """log(N / (1 + df)), natural."""
    return F.log(n / (1 + df))


def with_previous(ws: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """``ws`` with prev_tfidf: the score in the directly preceding block, null if the word is not there."""
    w = _by_word()
    known = F.lag("block_no").over(w) == F.col("block_no") - 1
    known = known & (F.lag("cnt").over(w) >= cfg.min_count) if cfg.previous == "common" else known
    return ws.withColumn("prev_tfidf", F.when(known, F.lag("tfidf").over(w)))


def score(tokens: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """WORD_SCORE rows: counts, n_blocks, df, tf, idf, tfidf and prev_tfidf of every word in every block.

    With scope and previous score both restricted to common words the rare ones are dropped before
    the second shuffle; they then still count in the totals.
    """
    return score_counts(count_words(tokens), cfg)


def among_common(wc: DataFrame, common: DataFrame) -> DataFrame:
    """``wc`` without words that never occur in ``common``: each word has one of a fixed number of buckets, so what all tasks get stays
    small however many words there are. Some others stay, too."""
    bucket = F.pmod(F.xxhash64("region", "word"), F.lit(BUCKETS)).cast("int")
    held = common.select(bucket.alias("_held")).distinct()
    return wc.withColumn("_bucket", bucket).join(F.broadcast(held), F.col("_bucket") == F.col("_held"), "left_semi").drop("_bucket")


def score_counts(wc: DataFrame, cfg: BurstConfig, common: DataFrame | None = None) -> DataFrame:
    """:func:`score` from word counts. With ``common``, counts of common words, only words that are there are sure to be scored, in all
    their blocks; the others are dropped before the second shuffle."""
    if common is None:
        wc = block_numbers(term_frequency(wc, cfg.denominator), cfg)
    elif cfg.corpus == "prefix" and cfg.blocks == "elapsed":  # whole numbers cross, which are smaller than shares
        wc = block_numbers(term_frequency(among_common(wc, common).repartition("word", "region"), cfg.denominator), cfg)
    else:  # the numbers of blocks are counted over all words
        wc = among_common(block_numbers(term_frequency(wc, cfg.denominator), cfg), common)
    if cfg.scope == "common" and cfg.previous == "common" and cfg.quiet_window is None:
        wc = common_words(wc, cfg.min_count)
    ws = document_frequency(wc, cfg).withColumn("idf", idf(F.col("n_blocks"), F.col("df"))).withColumn("tfidf", F.col("tf") * F.col("idf"))
    ws = with_previous(ws, cfg)
    if cfg.quiet_window is not None:
        w = _by_word().rangeBetween(-cfg.quiet_window, -1)
        ws = ws.withColumn("quiet_max", F.coalesce(F.max("tfidf").over(w), F.lit(0.0)))
    return ws


def score_ratio(current: Column, previous: Column) -> Column:
    """Growth of a score; null without a previous one."""
    return F.try_divide(current, previous)


def detect(ws: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """BURST_EVENT rows: common words with a positive score whose rate exceeds the threshold (reason
    ratio), or whose previous score is absent or not positive (reason new, unless skipped)."""
    has_prev = F.coalesce(F.col("prev_tfidf") > 1e-12, F.lit(False))
    rate = F.when(has_prev, score_ratio(F.col("tfidf"), F.col("prev_tfidf")))
    if cfg.prev_zero == "floor":
        rate = score_ratio(F.col("tfidf"), F.when(has_prev, F.col("prev_tfidf")).otherwise(F.lit(cfg.floor)))
    out = ws.where((F.col("cnt") >= cfg.min_count) & (F.col("tfidf") > 1e-12)).withColumn("rate", rate)
    ratio = F.coalesce(F.col("rate") > cfg.rate + EPS, F.lit(False))
    new = ~has_prev if cfg.prev_zero == "event" else F.lit(False)
    out = out.withColumn("reason", F.when(ratio, "ratio").when(new, "new")).where("reason is not null")
    if cfg.quiet_window is not None:
        out = out.where(F.col("tfidf") > cfg.rate * F.col("quiet_max") + EPS)
    return out.select("region", "block_no", "word", "cnt", "tfidf", "prev_tfidf", "rate", "reason")


def detect_bursts(tokens: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """The barrier variant: a block is scored once it is complete.

    Posts may come packed (:func:`packed.pack`): the tasks that hold them count their words, and words that are common in no block,
    which make no event, are not scored.
    """
    if is_packed(tokens):
        partials = partial_counts(tokens)
        return detect(score_counts(complete_counts(partials), cfg, complete_counts(partials, cfg.min_count)), cfg)
    return detect(score(tokens, cfg), cfg)


def eager_hits(tokens: DataFrame, min_count: int) -> DataFrame:
    """(region, block_no, word, terms): the words of each block, and the block's terms up to and with the word's
    ``min_count``-th occurrence, null if it has fewer.

    The terms seen so far come from sums over slices of time, so that no window holds a block, and of a word's
    occurrences only the first ``min_count`` are ranked: the rank's bound is applied before the shuffle.
    """
    posts = ordered(tokens.select("region", "block_no", "ts", "post_id", "tokens"), "tokens").select("region", "block_no", "seq", "tokens", F.col("terms_before").alias("_before"))
    words = posts.select("region", "block_no", "seq", "_before", F.posexplode_outer("tokens").alias("_pos", "word")).where("word is not null")
    nth = F.row_number().over(Window.partitionBy("region", "block_no", "word").orderBy("seq", "_pos"))
    hits = words.withColumn("_nth", nth).where(F.col("_nth") <= min_count)
    return hits.groupBy("region", "block_no", "word").agg(F.max(F.when(F.col("_nth") == min_count, F.col("_before") + F.col("_pos") + 1)).alias("terms"))


def eager_score(terms: Column, block_no: Column, df: Column, min_count: int) -> Column:
    """tf-idf of a word at its ``min_count``-th occurrence, null without one."""
    return F.when(terms.isNotNull(), F.lit(min_count) / terms.cast("double") * idf(block_no, df))


def detect_bursts_eager(tokens: DataFrame, cfg: BurstConfig = BurstConfig()) -> DataFrame:
    """The variant that cannot see the end of a block: a word is scored at its ``min_count``-th
    occurrence, with the terms seen so far; the previous score is the previous block's own."""
    w = Window.partitionBy("region", "word").orderBy("block_no")
    ws = eager_hits(tokens, cfg.min_count).withColumn("df", F.row_number().over(w).cast("long"))
    ws = ws.withColumn("tfidf", eager_score(F.col("terms"), F.col("block_no"), F.col("df"), cfg.min_count)).withColumn("cnt", F.lit(cfg.min_count).cast("long"))
    ws = ws.withColumn("prev_tfidf", F.when(F.lag("block_no").over(w) == F.col("block_no") - 1, F.lag("tfidf").over(w)))
    return detect(ws.where("tfidf is not null"), cfg)


def steady_words(ws: DataFrame, share: float = 0.9) -> DataFrame:
    """(region, word, n_blocks, mean_tfidf, sd_tfidf) of words in at least ``share`` of the blocks: high or low
    throughout, so no events."""
    last = ws.groupBy("region").agg(F.max("block_no").alias("_last"))
    words = ws.groupBy("region", "word").agg(F.count("*").alias("n_blocks"), F.avg("tfidf").alias("mean_tfidf"), F.stddev_pop("tfidf").alias("sd_tfidf"))
    return words.join(last, "region").where(F.col("n_blocks") >= share * F.col("_last")).drop("_last")


def trend(ws: DataFrame, events: DataFrame, length: int = 10) -> DataFrame:
    """(region, word, event_block, block_no, tfidf): the last ``length`` blocks of each event, 0 where absent."""
    e = events.select("region", "word", F.col("block_no").alias("event_block"))
    rows = e.select("*", F.explode(F.sequence(F.col("event_block") - (length - 1), F.col("event_block"))).alias("block_no"))
    return rows.join(ws.select("region", "word", "block_no", "tfidf"), ["region", "word", "block_no"], "left").select("region", "word", "event_block", "block_no", F.coalesce("tfidf", F.lit(0.0)).alias("tfidf"))


def trend_arrays(ws: DataFrame, events: DataFrame, length: int = 10) -> DataFrame:
    """``events`` with trend: an array of (block_no, tfidf), oldest first."""
    rows = trend(ws, events, length).groupBy("region", "word", F.col("event_block").alias("block_no")).agg(F.array_sort(F.collect_list(F.struct("block_no", "tfidf"))).alias("trend"))
    return events.join(rows, ["region", "word", "block_no"])


def burst_sweep(ws: DataFrame, rates: list[float], min_counts: list[int]) -> DataFrame:
    """(rate, min_count, ratio_events, new_events) over a grid: the scores are read once."""
    grid = F.array(*[F.struct(F.lit(float(r)).alias("rate"), F.lit(k).alias("min_count")) for r in rates for k in min_counts])
    has_prev = F.coalesce(F.col("prev_tfidf") > 1e-12, F.lit(False))
    some = ws.where((F.col("cnt") >= min(min_counts)) & (F.col("tfidf") > 1e-12))
    rows = some.select("cnt", F.when(has_prev, score_ratio(F.col("tfidf"), F.col("prev_tfidf"))).alias("growth"), has_prev.alias("has_prev"), F.explode(grid).alias("g"))
    rows = rows.where(F.col("cnt") >= F.col("g.min_count"))
    return rows.groupBy(F.col("g.rate").alias("rate"), F.col("g.min_count").cast("long").alias("min_count")).agg(
        F.count_if(F.coalesce(F.col("growth") > F.col("g.rate") + EPS, F.lit(False))).alias("ratio_events"), F.count_if(~F.col("has_prev")).alias("new_events")
    )


def top_tfidf(ws: DataFrame, k: int = 5) -> DataFrame:
    """The baseline without growth: the k best words of each block."""
    rank = F.row_number().over(Window.partitionBy("region", "block_no").orderBy(F.round("tfidf", 9).desc(), "word"))
    return ws.withColumn("rank", rank.cast("long")).where(F.col("rank") <= k).select("region", "block_no", "word", "tfidf", "rank")


def count_ratio(wc: DataFrame, rate: float, min_count: int) -> DataFrame:
    """The baseline on raw counts: words whose count grew by more than ``rate`` over the previous block."""
    w = _by_word()
    prev = F.when(F.lag("block_no").over(w) == F.col("block_no") - 1, F.lag("cnt").over(w))
    out = wc.withColumn("prev_cnt", prev).where(F.col("cnt") >= min_count)
    return out.where(F.col("cnt") > F.lit(rate) * F.col("prev_cnt")).select("region", "block_no", "word", "cnt", "prev_cnt")


def render_trend(points: list[tuple[int, float]], width: int = 200, height: int = 60) -> str:
    """A small SVG line chart of (block_no, tfidf) points."""
    if not points:
        return f'<svg xmlns="http://www.w3.org/2000/svg" width="{width}" height="{height}"/>'
    lo, hi = min(v for _, v in points), max(v for _, v in points)
    x = lambda i: 2 + i * (width - 4) / max(len(points) - 1, 1)
    y = lambda v: height - 2 - (v - lo) * (height - 4) / ((hi - lo) or 1)
    line = " ".join(f"{x(i):.1f},{y(v):.1f}" for i, (_, v) in enumerate(points))
    return f'<svg xmlns="http://www.w3.org/2000/svg" width="{width}" height="{height}"><polyline fill="none" stroke="black" points="{line}"/></svg>'
