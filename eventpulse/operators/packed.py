"""Word counts of posts whose words are one text: counted where the posts are dealt to, then summed by block.

Both steps run in numpy over Arrow batches, so that a word costs no row before its block's counts are complete. What crosses
between them is a row for each block of a batch, with its words and their counts.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.operators.clusters import runs
from eventpulse.plans.scratch import ship

KEYS = ["region", "block_no"]
#: Counts of a block's words in a batch; of a word in its whole block.
PARTIAL = pa.schema([("region", pa.string()), ("block_no", pa.int64()), ("words", pa.string()), ("counts", pa.list_(pa.int64()))])
COUNTED = "region string, block_no long, word string, cnt long, block_terms long, block_distinct long"
#: Counts of words that are summed together.
TOGETHER = 1_000_000


def pack(tokens: DataFrame) -> DataFrame:
    """Posts with their words as one text in place of the tokens, which is smaller where posts are stored or dealt. Tokens hold no blanks,
    as they are cut there."""
    return tokens.select(*KEYS, "post_id", F.array_join("tokens", " ").alias("words"))


def is_packed(df: DataFrame) -> bool:
    return "words" in df.columns and "tokens" not in df.columns


def summed(rows: pa.RecordBatch | pa.Table) -> tuple[pa.Array, np.ndarray, np.ndarray, pa.Array, np.ndarray]:
    """(regions, block numbers, where each block's counts begin and end, words, counts) of rows with texts of words, and with their counts
    if there are any."""
    texts = rows.column("words")
    texts = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
    parts = pc.split_pattern(texts, " ")
    n = pc.list_value_length(parts).to_numpy(zero_copy_only=False)
    place, number = pa.array(rows.column("region").to_numpy(zero_copy_only=False), pa.string()).dictionary_encode(), rows.column("block_no").to_numpy()
    numbers, at = np.unique(number, return_inverse=True)
    blocks, of = np.unique(place.indices.to_numpy().astype(np.int64) * len(numbers) + at, return_inverse=True)
    encoded = parts.flatten().dictionary_encode()
    size = len(encoded.dictionary)
    entry = np.repeat(of, n) * size + encoded.indices.to_numpy()
    if "counts" in rows.schema.names:
        counts = rows.column("counts")
        counts = (counts.combine_chunks() if isinstance(counts, pa.ChunkedArray) else counts).flatten().to_numpy()
        order = np.argsort(entry)
        entry = entry[order]
        first = np.flatnonzero(np.diff(entry, prepend=-1))
        entry, counts = entry[first], np.add.reduceat(counts[order], first)
    else:
        entry, counts = np.unique(entry, return_counts=True)
    ends = np.searchsorted(entry, np.arange(len(blocks) + 1) * size)
    return place.dictionary.take(pa.array(blocks // len(numbers))), numbers[blocks % len(numbers)], ends, encoded.dictionary.take(pa.array(entry % size)), counts


def partial(rows: pa.RecordBatch | pa.Table) -> pa.RecordBatch:
    """PARTIAL rows of posts, or of PARTIAL rows."""
    regions, numbers, ends, words, counts = summed(rows)
    ends = pa.array(ends, pa.int32())
    return pa.RecordBatch.from_arrays([regions, pa.array(numbers), pc.binary_join(pa.ListArray.from_arrays(ends, words), " "), pa.ListArray.from_arrays(ends, pa.array(counts, pa.int64()))], schema=PARTIAL)


def complete(rows: pa.Table, least: int) -> pa.RecordBatch:
    """COUNTED rows of whole blocks, of the words with ``least`` occurrences."""
    regions, numbers, ends, words, counts = summed(rows)
    distinct = np.diff(ends)
    terms, of = np.add.reduceat(counts, ends[:-1]), np.repeat(np.arange(len(numbers)), distinct)
    if least > 1:
        kept = np.flatnonzero(counts >= least)
        of, words, counts = of[kept], words.take(pa.array(kept)), counts[kept]
    cols = [regions.take(pa.array(of)), pa.array(numbers[of]), words, pa.array(counts, pa.int64()), pa.array(terms[of], pa.int64()), pa.array(distinct[of], pa.int64())]
    return pa.RecordBatch.from_arrays(cols, ["region", "block_no", "word", "cnt", "block_terms", "block_distinct"])


def partial_counts(posts: DataFrame) -> DataFrame:
    """PARTIAL rows of packed posts, counted in the tasks that hold the posts, dealt to their block and sorted."""
    ship(posts.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            b = b.filter(pc.greater(pc.binary_length(b.column("words")), 0))
            if b.num_rows:
                yield partial(b)

    held = posts.where(F.col("region").isNotNull() & F.col("block_no").isNotNull()).select(*KEYS, "words")
    return held.mapInArrow(run, "region string, block_no long, words string, counts array<long>").repartition(*KEYS).sortWithinPartitions(*KEYS)


def whole_blocks(batches: Iterable[pa.RecordBatch], least: int, together: int = TOGETHER) -> Iterator[pa.RecordBatch]:
    """:func:`complete` for PARTIAL rows sorted by block, about ``together`` counts at a time. Of a block with more the counts so far are summed
    as they grow, so that what is held follows its words, not its batches."""
    held, n, most = [], 0, together
    for k, part in runs(batches, KEYS):
        if n >= most:
            done, own = [p for h, p in held if h != k], [p for h, p in held if h == k]
            if done:
                yield complete(pa.Table.from_batches(done), least)
            held = [(k, partial(pa.Table.from_batches(own)))] if own else []
            n = sum(len(p.column("counts").flatten()) for _, p in held)
            most = max(together, 2 * n)
        held.append((k, part.cast(PARTIAL)))
        n += len(part.column("counts").flatten())
    if held:
        yield complete(pa.Table.from_batches([p for _, p in held]), least)


def complete_counts(partials: DataFrame, least: int = 1) -> DataFrame:
    """COUNTED rows of PARTIAL ones, of the words with ``least`` occurrences in the block. A task holds the counts of some small
    blocks, or of one."""
    return partials.mapInArrow(lambda batches: whole_blocks(batches, least), COUNTED)
