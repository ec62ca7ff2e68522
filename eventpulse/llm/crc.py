"""The fold of a labelled document, as the fitting operators share it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FOLDS = 5


def held_out(key: str = "doc_id", folds: int = FOLDS) -> Column:
    """Whether crc32 of the key as text falls in the fold that no fitting reads."""
    return F.crc32(F.col(key).cast("string")) % folds == 0


def labelled(labels: DataFrame, target: str, most: int, key: str = "doc_id") -> DataFrame:
    """(key, y) of at most ``most`` rows of each class that may be learnt from, in an order by hash.

    Null labels and keys are left out; a key with two labels takes the larger.
    """
    rows = labels.where(F.col(key).isNotNull() & F.col(target).isNotNull() & ~held_out(key))
    rows = rows.groupBy(key).agg(F.max(F.col(target).cast("int")).alias("y"))
    order = [F.xxhash64(key), F.col(key)]
    return rows.where("y = 1").orderBy(*order).limit(most).unionAll(rows.where("y = 0").orderBy(*order).limit(most))


def labelled_evenly(labels: DataFrame, target: str, most: int, key: str = "doc_id") -> DataFrame:
    """(key, y) of at most ``most`` rows that may be learnt from, in an order by hash, whatever their class."""
    rows = labels.where(F.col(key).isNotNull() & F.col(target).isNotNull() & ~held_out(key))
    return rows.groupBy(key).agg(F.max(F.col(target).cast("int")).alias("y")).orderBy(F.xxhash64(key), F.col(key)).limit(most)


def sample(docs: DataFrame, labels: DataFrame, target: str, most: int, key: str = "doc_id") -> DataFrame:
    """The documents of :func:`labelled`, joined by a broadcast of 2 * ``most`` rows at most."""
    return docs.join(F.broadcast(labelled(labels, target, most, key)), key)
