"""Mixing sources to target weights by pivotal dependent rounding.

Each source's target divided by its size is the number of copies its documents should
have; the whole part is given to all, the fraction is a probability. Rounding pairs two
documents with fractional probabilities and moves words from one to the other, in a random
direction that keeps both expectations, until one of them is integral; what the two hold
together stays the same. A source's documents are dealt over blocks; each block leaves one
fractional document, and these are combined block by block up a tree with a fixed fan-in.
The draws come from seeds of source, block and level, so reruns agree.
"""

from __future__ import annotations

import zlib
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from eventpulse.plans.scratch import materialize, ship

#: Documents in a block of the lowest level, and blocks that meet in one of the next.
LEAF, FAN_IN = 4096, 64
WORD = r"[^\x20\x09-\x0D]+"


def running(df: DataFrame, order: list, tag: str, **sums: str) -> DataFrame:
    """``df`` with _nth, a row's place in ``order`` from 0, and for each ``name="column"`` the column's sum over the rows
    before it. Ranges of the order are summed apart and then together, in one row for each range."""
    parts = materialize(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), tag)
    inside = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    none = F.lit(0)
    each = parts.groupBy("_part").agg(F.count("*").alias("_nth"), *[F.sum(c).alias(n) for n, c in sums.items()])
    each = each.select(F.col("_part").alias("_of"), *[F.coalesce(F.sum(n).over(before), none).alias(f"_{n}_before") for n in ("_nth", *sums)])
    out = parts.withColumn("_nth", F.count("*").over(inside))
    for n, c in sums.items():
        out = out.withColumn(n, F.coalesce(F.sum(c).over(inside), none))
    out = out.join(F.broadcast(each), F.col("_part") == F.col("_of"))  # a row for each range
    for n in ("_nth", *sums):
        out = out.withColumn(n, F.col(n) + F.col(f"_{n}_before"))
    return out.drop("_part", "_of", *[f"_{n}_before" for n in ("_nth", *sums)])


def targets(sizes: DataFrame, weights: Sequence[float] = (1, 2, 3), ceiling: float = 3.0) -> DataFrame:
    """(source, docs, source_size, target) from (source, size) rows.

    Sources in code point order, null last, take the weights in turn and share the sum of all
    sizes. A share stops at ``ceiling`` times the source's size and the excess is shared anew: the
    level per unit of weight is found in one pass over the sources, sorted by the level at
    which they stop. Sources may be many: both orders are dealt by range.
    """
    own = sizes.groupBy("source").agg(F.count("*").alias("docs"), F.sum("size").alias("source_size"))
    named = F.col("source").asc_nulls_last()
    own = running(own, [named], "mix-sources")
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod("_nth", F.lit(len(weights))) + 1).cast("int"))
    own = own.withColumn("weight", w).withColumn("cap", ceiling * F.col("source_size"))
    own = own.withColumn("stop", F.try_divide("cap", "weight")).drop("_nth")
    own = materialize(running(own, [F.col("stop").asc_nulls_last(), named], "mix-stops", _full="cap", _heavy="weight"), "mix-levels")
    whole = own.agg(F.sum("source_size").alias("size"), F.sum("weight").alias("weight")).first()
    if whole["size"] is None:
        return own.select("source", "docs", "source_size", F.lit(0.0).alias("target"))
    level = F.try_divide(F.lit(float(whole["size"])) - F.col("_full"), F.lit(whole["weight"]) - F.col("_heavy"))
    level = own.withColumn("_level", level).where(F.col("_level") <= F.col("stop")).agg(F.min(F.struct("_nth", "_level"))).first()[0]
    target = F.col("cap") if level is None else F.least("cap", F.col("weight") * F.lit(level["_level"]))
    return own.select("source", "docs", "source_size", F.coalesce(target, F.lit(0.0)).alias("target"))


def round_block(size: np.ndarray, p: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Probabilities after rounding in place order: 0 or 1, but for one row at most."""
    p = p.astype(float).copy()
    open_ = np.flatnonzero((p > 0) & (p < 1)).tolist()
    if not open_:
        return p
    draws = rng.random(len(open_))
    a = open_[0]
    pa, sa = p[a], size[a]
    for k, b in enumerate(open_[1:]):
        pb, sb = p[b], size[b]
        up = min((1 - pa) * sa, pb * sb)  # words that may go from b to a
        down = min(pa * sa, (1 - pb) * sb)
        if draws[k] * (up + down) < down:
            pa, pb = (1.0, pb - up / sb) if up == (1 - pa) * sa else (pa + up / sa, 0.0)
        else:
            pa, pb = (0.0, pb + down / sb) if down == pa * sa else (pa - down / sa, 1.0)
        if pa < 1e-12 or pa > 1 - 1e-12:  # a is done; b goes on, if it still can
            p[a] = round(pa)
            a, pa, sa = b, pb, sb
        else:
            p[b] = round(pb)
    p[a] = pa if 1e-12 < pa < 1 - 1e-12 else round(pa)
    return p


def _level(rows: DataFrame, level: int, seed: int, last: bool) -> DataFrame:
    schema = rows.schema

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["size", "doc_id", "tie"], ascending=[False, True, True], kind="stable", na_position="last").reset_index(drop=True)
        name = pdf["source"].iloc[0]
        rng = np.random.default_rng([seed, level, zlib.crc32(b"\0" if name is None else name.encode()), int(pdf["block"].iloc[0])])
        size, p = pdf["size"].to_numpy(), pdf["p"].to_numpy().copy()
        empty = (size == 0) & (p > 0) & (p < 1)  # no words to move: each on its own
        p[empty] = rng.random(int(empty.sum())) < p[empty]
        p = round_block(size, p, rng)
        if last:
            rest = (p > 0) & (p < 1)
            p[rest] = rng.random(int(rest.sum())) < p[rest]
        pdf["p"] = p
        pdf["block"] //= FAN_IN
        return pdf

    return rows.groupBy("source", "block").applyInPandas(run, schema)


def mix(df: DataFrame, text: str = "text", source: str = "source", key: str = "doc_id", weights: Sequence[float] = (1, 2, 3), ceiling: float = 3.0, seed: int = 7) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken, tie) for each row of ``df``; tie is a hash of the text.

    size is the number of words of the text (null: none), taken is copies * size. A source's taken
    words differ from its target by less than one small document; no document has more than
    ``ceiling`` copies (rounded up). Documents without words take part and take nothing. A null
    source is a source; repeated rows are rounded each; an empty table gives an empty table.
    """
    spark = df.sparkSession
    ship(spark)
    size = F.coalesce(F.expr(f"regexp_count(`{text}`, r'{WORD}')"), F.lit(0)).cast("long")
    sized = materialize(df.select(F.col(key).cast("long").alias("doc_id"), F.col(source).cast("string").alias("source"), size.alias("size"), _tie(text).alias("tie")), "mix-sizes")
    goal = materialize(targets(sized, weights, ceiling), "mix-targets")
    most = goal.agg(F.max("docs")).first()[0] or 0
    g = goal.select(F.col("source").alias("_source"), F.col("docs").alias("_docs"), "source_size", "target")
    ratio = F.coalesce(F.try_divide("target", "source_size"), F.lit(0.0))
    rows = sized.join(g, F.col("source").eqNullSafe(F.col("_source")))
    rows = rows.withColumn("whole", F.floor(ratio + 1e-9)).withColumn("p", F.greatest(F.lit(0.0), ratio - F.col("whole")))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("doc_id", "size", "tie"), F.ceil(F.col("_docs") / LEAF))).drop("_source", "_docs")
    blocks, level, done = max(1, -(-most // LEAF)), 0, []
    while True:
        last = blocks == 1
        out = _level(rows, level, seed, last)
        if last:
            done.append(out)
            break
        out = materialize(out, f"mix-level{level}")
        settled = (F.col("p") == 0) | (F.col("p") == 1)
        done.append(out.where(settled))
        rows, blocks, level = out.where(~settled), -(-blocks // FAN_IN), level + 1
    every = done[0]
    for d in done[1:]:
        every = every.unionByName(d)
    copies = (F.col("whole") + F.round("p")).cast("long")
    return every.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), "tie")


def _tie(text: str) -> Column:
    """What tells rows with one id, or with none, apart: a hash of the text."""
    return F.coalesce(F.xxhash64(F.col(text).cast("string")), F.lit(0))


def mixed(df: DataFrame, text: str = "text", source: str = "source", key: str = "doc_id", **options) -> DataFrame:
    """The rows of ``df``, each as often as the mix takes it; columns as in ``df``.

    Of rows that share a key each has its own decision, and so have rows without one, which meet their decisions by
    their text. An empty table gives an empty table.
    """
    taken = mix(df, text, source, key, **options)
    same = Window.partitionBy("_key", "_tie")
    nth = taken.select(F.col("doc_id").alias("_key"), F.col("tie").alias("_tie"), "copies").withColumn("_nth", F.row_number().over(same.orderBy("copies")))
    nth = nth.select(F.col("_key").alias("_k"), F.col("_tie").alias("_t"), F.col("_nth").alias("_n"), F.col("copies").alias("_copies"))
    own = df.withColumn("_key", F.col(key).cast("long")).withColumn("_tie", _tie(text)).withColumn("_nth", F.row_number().over(same.orderBy(F.lit(1))))
    met = own.join(nth, F.col("_key").eqNullSafe(F.col("_k")) & (F.col("_tie") == F.col("_t")) & (F.col("_nth") == F.col("_n"))).where("_copies > 0")
    return met.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int")))).select(*df.columns)
