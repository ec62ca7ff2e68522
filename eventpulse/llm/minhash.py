"""Near-duplicate documents by an inverted join of MinHash signature coordinates.

1. Each document's shingle set gives a digest and a signature of K minima. Documents
   with one set form a class; only its smallest document goes on.
2. A signature is a set of K (coordinate, value) pairs. Two signatures with at least T
   common pairs share one among the first K - T + 1 of each under any common order. The order
   is by frequency over all documents, read from a counting table of fixed width, so that
   what many documents share comes last: only the rarest pairs are posted.
3. Each posting list counts the collisions of its members' signatures. Members that are
   already connected are skipped, and only a spanning set of the pairs with T collisions
   leaves the list. Long lists are dealt over pairs of blocks.
4. Components of those pairs are the candidates: within each, links are confirmed on full
   sets (again in blocks, and again only a spanning set of them is returned).
5. Components of the confirmed links, joined with the classes, are the result.

T lies four standard deviations under the collisions expected at the threshold, so that a
pair on the threshold is missed with a probability under 1e-4.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.llm.arrow import map_batches, slices, text_of
from eventpulse.llm.words import mix, shingle_sets
from eventpulse.operators.components import connected_components
from eventpulse.plans.scratch import discard, materialize, ship

COORDINATES, WORDS, PERCENT = 128, 5, 85
#: Members of a posting list and of a candidate component, and shingles of the latter, meant for one block.
BLOCK, BLOCK_CONFIRMED, BLOCK_SHINGLES = 1024, 256, 250_000
#: Slots of the counting table that orders the pairs; its size does not depend on the data.
SLOTS, SLOT_BLOCK = 1 << 18, 1 << 13
_SEEDS = mix(np.arange(1, 2 * 512 + 1, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F))


def match_threshold(percent: int, k: int) -> int:
    """Collisions of k that a pair on the threshold reaches but for four standard deviations."""
    j = percent / 100
    return max(1, math.floor(k * j - 4 * math.sqrt(k * j * (1 - j))))


def signatures(sets: list[np.ndarray], k: int = COORDINATES) -> np.ndarray:
    """(documents, k) minima; of documents with an empty set, the largest value."""
    out = np.full((len(sets), k), 0xFFFFFFFF, dtype=np.uint32)
    full = [i for i, s in enumerate(sets) if len(s)]
    if full:
        x = (np.concatenate([sets[i] for i in full]) >> np.uint64(16)).astype(np.uint32)
        first = np.cumsum([0, *[len(sets[i]) for i in full[:-1]]])
        for c in range(k):
            h = (x ^ np.uint32(_SEEDS[c] >> np.uint64(32))) * np.uint32(_SEEDS[k + c] >> np.uint64(32) | np.uint64(1))
            out[full, c] = np.minimum.reduceat(h, first)
    return out


def pair_keys(sig: np.ndarray) -> np.ndarray:
    """64-bit keys of the (coordinate, value) pairs."""
    return mix(sig.astype(np.uint64) << np.uint64(16) | np.arange(sig.shape[1], dtype=np.uint64))


def _describe(df: DataFrame, words: int, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text", 1_000_000):
                sets = shingle_sets([t.encode().lower() for t in b.column("text").to_pylist()], words)
                sig = signatures(sets, k)
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()),
                    pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets], pa.binary()),
                    pa.array([r.tobytes() if len(s) else None for s, r in zip(sets, sig, strict=True)], pa.binary()),
                ], ["doc_id", "n_shingles", "set_key", "signature"])

    return map_batches(df, run, "doc_id long, n_shingles long, set_key binary, signature binary")


def _matrix(col: pa.Array, dtype) -> np.ndarray:
    """Rows of equally long binary values as a matrix."""
    rows = col.to_pylist()
    return np.frombuffer(b"".join(rows), dtype=dtype).reshape(len(rows), -1)


def _pair_counts(reps: DataFrame) -> np.ndarray:
    """How often each slot of the counting table is hit, over all signatures."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(SLOTS, dtype=np.int64)
        salt = 0
        for b in batches:
            if b.num_rows:
                keys = pair_keys(_matrix(b.column("signature"), np.uint32))
                salt = salt or int(keys[0, 0] >> np.uint64(40))
                held += np.bincount((keys & np.uint64(SLOTS - 1)).astype(np.int64).ravel(), minlength=SLOTS)
        if held.any():
            parts = held.reshape(-1, SLOT_BLOCK)
            yield pa.RecordBatch.from_arrays([pa.array(range(len(parts)), pa.int32()), pa.array([salt] * len(parts), pa.int64()), pa.array([p.tobytes() for p in parts], pa.binary())], ["block", "salt", "counts"])

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        total = np.sum([np.frombuffer(c, dtype=np.int64) for c in pdf["counts"]], axis=0)
        return pd.DataFrame({"block": pdf["block"][:1], "salt": [0], "counts": [total.tobytes()]})

    schema = "block int, salt long, counts binary"
    parts = map_batches(reps.select("signature"), run, schema)
    some = parts.groupBy("block", F.pmod("salt", F.lit(64)).alias("part")).applyInPandas(add, schema)
    out = np.zeros(SLOTS, dtype=np.int64)
    for r in some.groupBy("block").applyInPandas(add, schema).collect():  # as many rows as the table has blocks
        out[r["block"] * SLOT_BLOCK : (r["block"] + 1) * SLOT_BLOCK] = np.frombuffer(r["counts"], dtype=np.int64)
    return out


def _postings(reps: DataFrame, counts: np.ndarray, prefix: int) -> DataFrame:
    level = np.ceil(np.log2(counts + 1)).astype(np.uint64)
    table = reps.sparkSession.sparkContext.broadcast(level.astype(np.uint8))  # SLOTS bytes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 4096):
                b = whole.slice(at, 4096)
                keys = pair_keys(_matrix(b.column("signature"), np.uint32))
                order = table.value[(keys & np.uint64(SLOTS - 1)).astype(np.int64)].astype(np.uint64) << np.uint64(56) | keys >> np.uint64(8)
                chosen = np.argpartition(order, prefix - 1, axis=1)[:, :prefix] if prefix < keys.shape[1] else np.argsort(order, axis=1)
                pair = np.take_along_axis(keys, chosen, axis=1).view(np.int64).ravel()
                doc = np.repeat(np.asarray(b.column("doc_id")), chosen.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(pair), pa.array(doc)], ["pair", "doc_id"])

    return map_batches(reps.select("doc_id", "signature"), run, "pair long, doc_id long")


def in_blocks(df: DataFrame, size: str, member: str) -> DataFrame:
    """Deal the members of a group over pairs of blocks: every two members meet in one (i, j) at least.

    ``size`` holds the number of blocks of a row's group; groups of one block stay whole.
    """
    own = F.pmod(F.xxhash64(member), F.col(size)).cast("int")
    spread = df.withColumn("_own", own).withColumn("_other", F.explode(F.sequence(F.lit(0), (F.col(size) - 1).cast("int"))))
    return spread.withColumn("i", F.least("_own", "_other")).withColumn("j", F.greatest("_own", "_other")).drop("_own", "_other")


def spanning(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Merge the components of the pairs (a, b) into ``labels`` (smallest member), in place."""
    while len(a):
        la, lb = labels[a], labels[b]
        open_ = la != lb
        if not open_.any():
            return
        a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
        low = np.minimum(la, lb)
        np.minimum.at(labels, np.maximum(la, lb), low)
        while True:
            up = labels[labels]
            if (up == labels).all():
                break
            labels[:] = up


def groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[list[np.ndarray], pa.RecordBatch]]:
    """Consecutive batches of whole groups of rows sorted by ``keys``, with each group's first row."""
    held: pa.Table | None = None

    def cut(t: pa.Table) -> np.ndarray:
        new = np.zeros(t.num_rows, dtype=bool)
        new[:1] = True
        for k in keys:
            v = t.column(k).to_numpy()
            new[1:] |= v[1:] != v[:-1]
        return np.flatnonzero(new)

    for b in batches:
        t = pa.Table.from_batches([b])
        held = t if held is None else pa.concat_tables([held, t])
        if not held.num_rows:
            continue
        first = cut(held)
        if len(first) > 1:
            yield first[:-1], held.slice(0, first[-1]).combine_chunks()
            held = held.slice(first[-1]).combine_chunks()
    if held is not None and held.num_rows:
        yield cut(held), held.combine_chunks()


def _collide(sig: np.ndarray, first: np.ndarray, least: int, small: int = 24) -> np.ndarray:
    """Labels of rows: components of the pairs within a group with ``least`` equal coordinates."""
    n = len(sig)
    labels = np.arange(n)
    size = np.diff(np.append(first, n))
    group = np.repeat(np.arange(len(first)), size)
    few = size[group] <= small
    for d in range(1, min(small, n)):
        at = np.flatnonzero(few[:-d] & (group[d:] == group[:-d]))
        if not len(at):
            break
        for lo in range(0, len(at), 65_536):
            part = at[lo : lo + 65_536]
            hit = part[(sig[part] == sig[part + d]).sum(axis=1) >= least]
            spanning(labels, hit, hit + d)
    for g in np.flatnonzero(size > small):
        lo, hi = first[g], first[g] + size[g]
        for r in range(lo, hi):  # what r is connected with already is skipped
            rest = np.arange(r + 1, hi)
            rest = rest[labels[rest] != labels[r]]
            if len(rest):
                hit = rest[(sig[rest] == sig[r]).sum(axis=1) >= least]
                if len(hit):
                    own = np.unique(np.append(labels[hit], labels[r]))
                    span = labels[lo:hi]
                    span[np.isin(span, own)] = own[0]
    return labels


def _stars(doc: np.ndarray, labels: np.ndarray) -> pa.RecordBatch:
    """The distinct links of each row's document with its label's."""
    a, b = doc, doc[labels]
    on = a != b
    pairs = np.unique(np.stack([np.minimum(a, b)[on], np.maximum(a, b)[on]], axis=1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0], pa.int64()), pa.array(pairs[:, 1], pa.int64())], ["src", "dst"])


def _candidates(reps: DataFrame, postings: DataFrame, least: int) -> DataFrame:
    """Spanning pairs of documents whose signatures collide ``least`` times."""
    lists = postings.groupBy("pair").agg(F.count("*").alias("n")).where("n > 1")
    blocks = F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks")
    members = in_blocks(postings.join(lists.select("pair", blocks), "pair"), "blocks", "doc_id")
    short = reps.select("doc_id", "short")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for first, t in groups(batches, ["pair", "i", "j"]):
            yield _stars(t.column("doc_id").to_numpy(), _collide(_matrix(t.column("short"), np.uint8), first, least))

    met = members.join(short, "doc_id").select("pair", "i", "j", "doc_id", "short")
    return map_batches(met.repartition("pair", "i", "j").sortWithinPartitions("pair", "i", "j"), run, "src long, dst long").distinct()


def confirmed(sets: list[np.ndarray], percent: int) -> np.ndarray:
    """Labels: components of the pairs with 100 * common >= percent * all, of full sets."""
    m, n = len(sets), np.array([len(s) for s in sets])
    labels = np.arange(m)
    if m == 2:
        common = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        labels[1] = 0 if 100 * common >= percent * (n.sum() - common) else 1
        return labels
    _, column, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(m), n)
    shared = times > 1
    column, row = (np.cumsum(shared) - 1)[column[shared[column]]], row[shared[column]]
    common = np.zeros((m, m), dtype=np.float32)  # counts under 2 ** 24 are whole
    order = np.argsort(column, kind="stable")
    column, row = column[order], row[order]
    width = max(256, 4_000_000 // m)
    for lo in range(0, int(shared.sum()), width):
        a, z = np.searchsorted(column, [lo, lo + width])
        has = np.zeros((m, width), dtype=np.float32)
        has[row[a:z], column[a:z] - lo] = 1
        common += has @ has.T
    for r in range(m):
        c = common[r].astype(np.int64)
        hit = np.flatnonzero((100 * c >= percent * (n[r] + n - c)) & (np.arange(m) > r))
        spanning(labels, np.full(len(hit), r), hit)
    return labels


def _links(docs: DataFrame, candidates: DataFrame, words: int, percent: int) -> DataFrame:
    """Spanning links, confirmed on full sets, within the candidate components."""
    # candidates: doc_id, component, n_shingles
    size = candidates.groupBy("component").agg(F.count("*").alias("m"), F.sum("n_shingles").alias("w"))
    blocks = F.greatest(F.ceil(F.col("m") / BLOCK_CONFIRMED), F.least(F.ceil(F.col("w") / BLOCK_SHINGLES), F.ceil(F.col("m") / 2))).cast("int").alias("blocks")
    members = candidates.join(size.select("component", blocks), "component").select("doc_id", "component", "blocks")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text", 2_000_000):
                found = shingle_sets([t.encode().lower() for t in b.column("text").to_pylist()], words)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("component"), b.column("blocks"), pa.array([s.tobytes() for s in found], pa.binary())], ["doc_id", "component", "blocks", "shingles"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for first, t in groups(batches, ["component", "i", "j"]):
            doc, col = t.column("doc_id").to_numpy(), t.column("shingles")
            labels = np.arange(len(doc))
            for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(doc)], strict=True):
                if hi - lo > 1:
                    labels[lo:hi] = lo + confirmed([np.frombuffer(x, dtype=np.uint64) for x in col.slice(lo, hi - lo).to_pylist()], percent)
            yield _stars(doc, labels)

    found = map_batches(docs.join(members, "doc_id").select("doc_id", "component", "blocks", "text"), sets, "doc_id long, component long, blocks int, shingles binary")
    dealt = in_blocks(found, "blocks", "doc_id").select("component", "i", "j", "doc_id", "shingles")
    return map_batches(dealt.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j"), run, "src long, dst long").distinct()


def near_duplicates(df: DataFrame, text: str = "text", key: str = "doc_id", words: int = WORDS, percent: int = PERCENT, coordinates: int = COORDINATES) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of ``df``.

    Words are runs without ASCII white space, A-Z lower-cased. Documents are linked whose
    shingle sets have 100 * common >= percent * all; component_id is the smallest doc_id that
    links reach, kept says whether it is the document's own. Null texts count as empty; documents
    without words have no shingle and no link; a null doc_id is linked with nothing (its
    component is null and it is kept). Repeated rows of one document share its component; so do rows of one
    doc_id with different texts, whose links are those of each text that no smaller doc_id has. An empty table gives an
    empty table.
    """
    ship(df.sparkSession)
    docs = text_of(df.withColumn("doc_id", F.col(key).cast("long")), "doc_id", text=text)
    least = match_threshold(percent, coordinates)
    described = materialize(_describe(docs, words, coordinates), "minhash-signatures")
    usable = described.where("doc_id is not null and set_key is not null")
    classes = materialize(usable.groupBy("set_key").agg(F.min("doc_id").alias("rep")), "minhash-classes")

    def shorten(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                low = (_matrix(b.column("signature"), np.uint32) >> np.uint32(8)).astype(np.uint8)
                yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array([r.tobytes() for r in low], pa.binary())], ["doc_id", "n_shingles", "signature", "short"])

    reps = usable.select("doc_id", "n_shingles", "signature", "set_key").join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")
    reps = reps.dropDuplicates(["doc_id", "set_key"]).drop("set_key")
    reps = materialize(map_batches(reps, shorten, "doc_id long, n_shingles long, signature binary, short binary"), "minhash-reps")
    postings = _postings(reps, _pair_counts(reps), coordinates - least + 1)
    near = connected_components(_candidates(reps, postings, least))
    candidates = near.withColumnRenamed("node", "doc_id").join(reps.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")), "doc_id")
    linked = connected_components(_links(docs, candidates, words, percent))
    discard(reps)
    discard(near)
    member = described.select("doc_id", "n_shingles", "set_key").join(classes, "set_key", "left")
    out = member.join(linked.select(F.col("node").alias("rep"), "component"), "rep", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "rep", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def deduplicate(df: DataFrame, text: str = "text", key: str = "doc_id", **options) -> DataFrame:
    """The rows of ``df`` whose document is the smallest of its component; of rows with one key the one whose text has
    the smallest hash.

    Rows with a null key are kept. The columns are those of ``df``; an empty table gives an empty table.
    """
    dropped = near_duplicates(df, text, key, **options).where("not kept").select(F.col("doc_id").alias("_dropped")).distinct()
    left = df.join(dropped, df[key] == F.col("_dropped"), "left_anti")
    nulls = left.where(F.col(key).isNull())
    own = left.where(F.col(key).isNotNull()).groupBy(F.col(key).alias("_key")).agg(F.min_by(F.struct(*df.columns), F.xxhash64(F.col(text).cast("string"))).alias("_row"))
    return own.select("_row.*").unionByName(nulls)
