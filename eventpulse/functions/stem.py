"""Porter's stemmer, written from the published description of its five steps."""

from __future__ import annotations

import re
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.plans.scratch import ship

#: Endings of the steps and what replaces them.
STEP2 = [("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble")]
STEP3 = [("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", "")]
STEP4 = ["al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize"]


def _shape(word: str) -> str:
    """Consonants as c, vowels as v; y is a vowel after a consonant."""
    out = ""
    for ch in word:
        out += "v" if ch in "aeiou" or (ch == "y" and out.endswith("c")) else "c"
    return out


def _measure(stem: str) -> int:
    return len(re.findall("v+c+", _shape(stem)))


def _has_vowel(stem: str) -> bool:
    return "v" in _shape(stem)


def _double(word: str) -> bool:
    return len(word) > 1 and word[-1] == word[-2] and _shape(word)[-1] == "c"


def _short_end(word: str) -> bool:
    return _shape(word).endswith("cvc") and word[-1] not in "wxy"


def _swap(word: str, pairs: list[tuple[str, str]], least: int) -> str:
    for end, new in sorted(pairs, key=lambda p: -len(p[0])):
        if word.endswith(end):
            base = word[: -len(end)]
            return base + new if _measure(base) >= least else word
    return word


def _plural_and_past(w: str) -> str:
    for end, cut in (("sses", 2), ("ies", 2), ("ss", 0), ("s", 1)):
        if w.endswith(end):
            w = w[: len(w) - cut]
            break
    if w.endswith("eed"):
        return w[:-1] if _measure(w[:-3]) > 0 else w
    for end in ("ed", "ing"):
        if w.endswith(end):
            base = w[: -len(end)]
            if not _has_vowel(base):
                break
            if base.endswith(("at", "bl", "iz")):
                return base + "e"
            if _double(base) and base[-1] not in "lsz":
                return base[:-1]
            return base + "e" if _measure(base) == 1 and _short_end(base) else base
    return w


@lru_cache(maxsize=100_000)
def porter(word: str) -> str:
    """The stem of a lower-case word; words of up to two letters, or with other letters than a-z, stay."""
    if len(word) <= 2 or not re.fullmatch("[a-z]+", word):
        return word
    w = _plural_and_past(word)
    if w.endswith("y") and _has_vowel(w[:-1]):
        w = w[:-1] + "i"
    w = _swap(_swap(w, STEP2, 1), STEP3, 1)
    for end in sorted(STEP4, key=len, reverse=True):
        if w.endswith(end):
            base = w[: -len(end)]
            if _measure(base) > 1 and (end != "ion" or base.endswith(("s", "t"))):
                w = base
            break
    if w.endswith("e"):
        m = _measure(w[:-1])
        if m > 1 or (m == 1 and not _short_end(w[:-1])):
            w = w[:-1]
    return w[:-1] if _measure(w) > 1 and _double(w) and w.endswith("l") else w


def _stems(words: pd.Series) -> pd.Series:
    return words.map(porter, na_action="ignore")


def _stem_arrays(tokens: pd.Series) -> pd.Series:
    return tokens.map(lambda ws: None if ws is None else [porter(w) for w in ws])


def stem_dictionary(words: DataFrame, word: str = "word") -> DataFrame:
    """(word, stem) of the distinct words: Python sees each word once, not each occurrence."""
    ship(words.sparkSession)
    return words.select(F.col(word).alias("word")).distinct().withColumn("stem", F.pandas_udf(_stems, "string")("word"))


def stem_words(words: DataFrame, word: str = "word") -> DataFrame:
    """``words`` with each word replaced by its stem, through the dictionary."""
    d = stem_dictionary(words, word).withColumnRenamed("word", "_w")
    return words.join(d, words[word] == d["_w"]).drop("_w", word).withColumnRenamed("stem", word)


def stem_tokens(df: DataFrame, tokens: str = "tokens") -> DataFrame:
    """Token arrays stemmed in Arrow batches; a worker's memory of words makes repeats cheap."""
    ship(df.sparkSession)
    return df.withColumn(tokens, F.pandas_udf(_stem_arrays, "array<string>")(tokens))
