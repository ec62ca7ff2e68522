"""Cleaning of post texts as column expressions: no shuffle, no Python on the hot path."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eventpulse.config import PrepConfig
from eventpulse.functions.stopwords import stopwords

TOKEN_GAP = r"[^\p{L}\p{N}]+"
URL = r"(https?://|www\.)\S+"
SENTENCE_END = r"[.!?\n]+"
CHECKIN = "i am at"
#: Endings that the light stemmer takes off, longest first.
LIGHT_SUFFIX = r"(ingly|edly|ation|ment|ness|ing|ies|ed|ly|es|s)$"


def tokenize(text: Column, pattern: str = TOKEN_GAP) -> Column:
    """Lower-cased runs of letters and digits; a null text has none."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), pattern), lambda x: x != "")


def drop_stopwords(tokens: Column, langs: tuple[str, ...] = ("en", "fr", "de", "es")) -> Column:
    """The tokens that are no function words; repeats stay."""
    words = stopwords(langs)
    return F.filter(tokens, lambda x: ~x.isin(words))


def strip_urls(text: Column) -> Column:
    """The text without web addresses."""
    return F.regexp_replace(text, URL, "")


def drop_checkins(text: Column) -> Column:
    """The text without the sentences that begin with the check-in words."""
    kept = F.filter(F.split(text, SENTENCE_END), lambda s: ~F.startswith(F.lower(F.ltrim(s)), F.lit(CHECKIN)))
    return F.array_join(kept, ". ")


def squeeze_runs(word: Column) -> Column:
    """Runs of three or more equal letters become one letter; runs of two stay."""
    return F.regexp_replace(word, r"(\p{L})\1{2,}", "$1")


def stem_light(word: Column) -> Column:
    """The word without a frequent ending, if four characters or more are left."""
    cut = F.regexp_replace(word, LIGHT_SUFFIX, "")
    return F.when(F.length(cut) >= 4, cut).otherwise(word)


def clean_tokens(text: Column, cfg: PrepConfig = PrepConfig()) -> Column:
    """All rules in order: addresses, check-ins, tokens, runs, function words, light stems."""
    t = F.coalesce(text, F.lit(""))
    t = strip_urls(t) if cfg.urls else t
    t = drop_checkins(t) if cfg.checkins else t
    tokens = tokenize(squeeze_runs(F.lower(t)) if cfg.squeeze else t)  # no run crosses a gap: one pass over the text
    tokens = drop_stopwords(tokens, cfg.langs) if cfg.stopwords else tokens
    return F.transform(tokens, stem_light) if cfg.stem == "light" else tokens


def preprocess(df: DataFrame, cfg: PrepConfig = PrepConfig(), text: str = "text") -> DataFrame:
    """``df`` with a tokens column in place of the text. Porter stems come from a dictionary of the
    distinct words (see :mod:`eventpulse.functions.stem`); all else is one projection."""
    out = df.withColumn("tokens", clean_tokens(F.col(text), cfg)).drop(text)
    if cfg.stem == "porter":
        from eventpulse.functions.stem import stem_tokens

        out = stem_tokens(out)
    return out


def ablation_configs() -> dict[str, PrepConfig]:
    """The full rule set, and the same with each rule off in turn."""
    full = PrepConfig(stem="light")
    off = {name: replace(full, **{name: False}) for name in ("urls", "checkins", "squeeze", "stopwords")}
    return {"full": full, **{f"no_{k}": v for k, v in off.items()}, "no_stem": replace(full, stem="none")}


def preprocess_ablation(df: DataFrame, text: str = "text") -> DataFrame:
    """Tokens and distinct tokens that are left under each configuration, in one scan."""
    configs = ablation_configs()
    each = [F.struct(F.lit(k).alias("config"), clean_tokens(F.col(text), c).alias("tokens")) for k, c in configs.items()]
    words = df.select(F.explode(F.array(*each)).alias("_c")).select("_c.config", F.explode("_c.tokens").alias("word"))
    per_word = words.groupBy("config", "word").agg(F.count("*").alias("n"))  # partial counts, then a small final step
    return per_word.groupBy("config").agg(F.sum("n").alias("tokens"), F.count("*").alias("distinct_tokens"))
