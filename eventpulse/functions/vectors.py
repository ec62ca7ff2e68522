"""Sparse vectors as maps of word weights, dense ones as arrays."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def vectorize(df: DataFrame, tokens: str = "tokens") -> DataFrame:
    """``df`` with a vec map: each word's share of the post's words. Posts without tokens are dropped."""
    n = F.size(tokens)
    words = F.array_sort(F.array_distinct(tokens))
    entry = lambda w: F.struct(w, F.size(F.filter(tokens, lambda x: x == w)) / n.cast("double"))
    return df.where(n > 0).withColumn("vec", F.map_from_entries(F.transform(words, entry))).drop(tokens)


def vector_long(df: DataFrame, tokens: str = "tokens", key: str = "post_id") -> DataFrame:
    """(key, word, weight) rows: the relational form of :func:`vectorize`."""
    words = df.select(key, F.size(tokens).alias("_n"), F.explode(tokens).alias("word"))
    return words.groupBy(key, "word").agg((F.count("*") / F.first("_n").cast("double")).alias("weight"))


def _norm(m: Column) -> Column:
    return F.sqrt(F.aggregate(F.map_values(m), F.lit(0.0), lambda s, x: s + x * x))


def cosine_map(a: Column, b: Column) -> Column:
    """Cosine of two maps; 0 if one is null, empty or zero."""
    a, b = F.coalesce(a, F.map_from_entries(F.array().cast("array<struct<k:string,v:double>>"))), F.coalesce(b, F.map_from_entries(F.array().cast("array<struct<k:string,v:double>>")))
    dot = F.aggregate(F.map_entries(a), F.lit(0.0), lambda s, e: s + e["value"] * F.coalesce(F.element_at(b, e["key"]), F.lit(0.0)))
    return F.coalesce(F.try_divide(dot, _norm(a) * _norm(b)), F.lit(0.0))


def cosine_dense(a: Column, b: Column) -> Column:
    """Cosine of two arrays in double precision; 0 if one is zero."""
    a, b = a.cast("array<double>"), b.cast("array<double>")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return F.coalesce(F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))), F.lit(0.0))


def merge_vectors(a: Column, na: Column, b: Column, nb: Column) -> Column:
    """Mean of two word maps, weighted by the posts behind them."""
    weight = lambda k, x, y: (F.coalesce(x, F.lit(0.0)) * na + F.coalesce(y, F.lit(0.0)) * nb) / (na + nb)
    return F.map_zip_with(a, b, weight)


def prune_words(vec: Column, n_posts: Column, min_weight: float, min_posts: int = 0) -> Column:
    """The map without words lighter than ``min_weight``, if more than ``min_posts`` posts are behind it."""
    return F.when(n_posts > min_posts, F.map_filter(vec, lambda _, w: w >= min_weight)).otherwise(vec)
