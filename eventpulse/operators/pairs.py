"""Pairs of similar posts of a block: exact by a join on shared words, and approximate by hashing; both verify the cosine.

Posts with one vector are a class, whose smallest id stands for it: links are found between classes, and copies are
told by their class instead of by pairs among themselves.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eventpulse.config import EPS
from eventpulse.operators.components import connected_components
from eventpulse.plans.scratch import materialize, ship

#: Posts of a block that one task takes; larger blocks are dealt over pairs of parts of about this size.
BLOCK = 8192
#: Cells of a strip of comparisons, and steps through lists, that are held at once.
CELLS = 4_000_000
#: Between the entries of a post, and between a word and its weight.
NEXT, OF = "\x1e", "\x1f"
WITHIN = ("region", "block_no")


def bags(tokens: DataFrame, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """(within..., post_id, words): posts that have tokens, as one string of them in order; a word weighs as often as it is there."""
    return tokens.where(F.size("tokens") > 0).select(*within, "post_id", F.array_join(F.array_sort("tokens"), NEXT).alias("words"))


def weighted_bags(vectors: DataFrame, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """The same from (within..., post_id, word, weight) rows."""
    entry = F.concat_ws(OF, "word", F.col("weight").cast("double").cast("string"))
    return vectors.groupBy(*within, "post_id").agg(F.array_join(F.array_sort(F.collect_list(entry)), NEXT).alias("words"))


class Side:
    """The classes of a part of a block, by their ids: members, and rows of words with weights of length one."""

    def __init__(self, ids: np.ndarray, words: pa.Array):
        found = words.dictionary_encode()
        of, n = found.indices.to_numpy(), len(found.dictionary)
        least = np.full(n, np.iinfo(np.int64).max)
        np.minimum.at(least, of, ids)
        order = np.argsort(least)
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        self.ids, self.post, self.of, self.n = least[order], ids, rank[of], n
        lists = pc.split_pattern(found.dictionary.take(pa.array(order)), NEXT)
        self.entries, at = lists.flatten(), lists.offsets.to_numpy()
        self.entry_row = np.repeat(np.arange(n), np.diff(at))

    def copies(self) -> tuple[np.ndarray, np.ndarray]:
        """(class, member) of the members that do not stand for their class."""
        mine = self.ids[self.of]
        other = mine != self.post
        return mine[other], self.post[other]

    def weigh(self, word: np.ndarray, weight: np.ndarray, n_words: int) -> None:
        """Rows from the entries' words and weights; what a row has twice is added up, rows of length zero have none."""
        key, inverse = np.unique(self.entry_row * n_words + word, return_inverse=True)
        total = np.bincount(inverse, weight, len(key))
        self.row, self.word = key // n_words, key % n_words
        square = np.bincount(self.row, total * total, self.n)
        keep = square[self.row] > 0
        self.row, self.word, total = self.row[keep], self.word[keep], total[keep]
        self.x = total / np.sqrt(square[self.row])


def _read(sides: list[Side]) -> list[str]:
    """Give the sides their rows over one numbering of words, which is returned."""
    entries = pa.chunked_array([s.entries for s in sides]).combine_chunks().dictionary_encode()
    of = entries.indices.to_numpy()
    parts = [e.rpartition(OF) for e in entries.dictionary.to_pylist()]
    number: dict[str, int] = {}
    word = np.array([number.setdefault(e[2] if not e[1] else e[0], len(number)) for e in parts], np.int64)
    weight = np.array([float(e[2]) if e[1] else 1.0 for e in parts])
    start = 0
    for s in sides:
        own = of[start : start + len(s.entries)]
        s.weigh(word[own], weight[own], len(number))
        start += len(s.entries)
    return list(number)


def _signs_of_words(sides: list[Side], words: list[str], theta: float, prune: bool) -> list[tuple[np.ndarray, np.ndarray]]:
    """(row, sign) of each side: its words, or those of a prefix, rare words first, up to where the rest is shorter than theta."""
    if not prune:
        return [(s.row, s.word) for s in sides]
    often = sum(np.bincount(s.word, minlength=len(words)) for s in sides)
    out = []
    for s in sides:
        order = np.lexsort((s.word, often[s.word], s.row))
        row, square = s.row[order], s.x[order] ** 2
        run = np.cumsum(square) - square
        first = np.searchsorted(row, row)
        lead = run - run[first] <= 1 - (theta - EPS) ** 2 + 1e-12
        out.append((row[lead], s.word[order][lead]))
    return out


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _signs_of_bands(sides: list[Side], words: list[str], bands: int, width: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """(row, sign) of each side: bands of ``width`` minima of the hashes of a row's words."""
    own = np.frombuffer(b"".join(hashlib.blake2b(w.encode(), digest_size=8).digest() for w in words), np.uint64)
    rows, signs = [], []
    hashes = [[_mix(own + np.uint64((b * width + r + 1) * 0x9E3779B97F4A7C15 % 2**64)) for r in range(width)] for b in range(bands)]
    for s in sides:
        row, first = np.unique(s.row, return_index=True)
        rows.append(np.tile(row, bands))
        each = []
        for b in range(bands):
            sign = np.full(len(row), b, np.uint64)
            for h in hashes[b]:
                sign = _mix(sign ^ np.minimum.reduceat(h[s.word], first)) if len(row) else sign
            each.append(sign)
        signs.append(np.concatenate(each))
    number = np.unique(np.concatenate(signs), return_inverse=True)[1]
    cut = len(signs[0])
    return list(zip(rows, (number[:cut], number[cut:]), strict=False))


def _met(a: Side, b: Side, signs: list[tuple[np.ndarray, np.ndarray]], theta: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row of a, row of b, cosine) of the rows with a common sign and a cosine of theta or more, strip by strip; of
    one side each pair once."""
    (ra, sa), (rb, sb) = signs[0], signs[-1]
    if not len(ra) or not len(rb):
        return
    order = np.argsort(sb, kind="stable")
    listed = rb[order]
    start = np.searchsorted(sb[order], sa)
    size = np.searchsorted(sb[order], sa, "right") - start
    order = np.argsort(ra, kind="stable")
    ra, start, size = ra[order], start[order], size[order]
    steps = np.bincount(ra, size, a.n)
    words = max(int(a.word.max()), int(b.word.max())) + 1
    b_at = np.searchsorted(b.row, np.arange(b.n + 1))
    a_at = np.searchsorted(a.row, np.arange(a.n + 1))
    before = np.concatenate([[0], np.cumsum(steps)])
    most = max(1, CELLS // max(b.n, words))
    lo = 0
    while lo < a.n:
        hi = int(min(lo + most, max(lo + 1, np.searchsorted(before, before[lo] + CELLS, "right") - 1), a.n))
        p, q = np.searchsorted(ra, lo), np.searchsorted(ra, hi)
        n = size[p:q]
        if n.sum():
            at = np.repeat(start[p:q] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            seen = np.zeros((hi - lo) * b.n, bool)
            seen[np.repeat((ra[p:q] - lo) * b.n, n) + listed[at]] = True
            cell = np.flatnonzero(seen)
            x, y = cell // b.n, cell % b.n
            if a is b:
                x, y = x[later := y > x + lo], y[later]
            strip = np.zeros((hi - lo, words))
            part = slice(a_at[lo], a_at[hi])
            strip[a.row[part] - lo, a.word[part]] = a.x[part]
            long = b_at[y + 1] - b_at[y]
            ends = np.cumsum(long)
            k = 0
            while k < len(x):
                z = max(k + 1, int(np.searchsorted(ends, ends[k] - long[k] + CELLS, "right")))
                m = long[k:z]
                first = np.cumsum(m) - m
                e = np.repeat(b_at[y[k:z]] - first, m) + np.arange(m.sum())
                c = np.add.reduceat(strip[np.repeat(x[k:z], m), b.word[e]] * b.x[e], first)
                near = c >= theta - EPS
                yield x[k:z][near] + lo, y[k:z][near], c[near]
                k = z
        lo = hi


Links = Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]


def _blockwise(posts: DataFrame, within: tuple[str, ...], work: Callable[[list[Side]], Iterator[tuple]], schema: str) -> DataFrame:
    """``work`` on the one or two parts of each task, its arrays as columns after ``within``.

    Each post crosses once to the task of its block, or, if the block is dealt over parts by a hash of the words, to those
    of its part with each other one: copies meet in one part. Only blocks over ``BLOCK`` posts are joined to their
    number of parts, so that table has a row for so many posts at most.
    """
    from eventpulse.operators.clusters import runs

    ship(posts.sparkSession)
    posts = materialize(posts, "pair-posts")
    large = posts.groupBy(*within).agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("_parts")).where("_parts > 1")
    same: Column = F.lit(True)
    for k in within:
        same = same & F.col(k).eqNullSafe(F.col(f"_{k}"))
    dealt = posts.join(F.broadcast(large.withColumnsRenamed({k: f"_{k}" for k in within})), same, "left").drop(*[f"_{k}" for k in within])
    parts = F.coalesce("_parts", F.lit(1))
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("words"), parts).cast("int")).withColumn("_p", F.explode(F.sequence(F.lit(0), parts - 1)))
    dealt = dealt.select(*within, F.least("own", "_p").alias("i"), F.greatest("own", "_p").alias("j"), "own", "post_id", "words")
    keys, n_keys = [*within, "i", "j"], len(within)
    types = [posts.schema[k].dataType for k in within]
    from pyspark.sql.pandas.types import to_arrow_type

    arrow = [to_arrow_type(t) for t in types]

    def done(key: tuple, rows: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(rows).combine_chunks()
        own = t["own"].to_numpy()
        sides = []
        for part in dict.fromkeys(key[n_keys:]):
            mine = np.flatnonzero(own == part)
            if not len(mine):
                return
            one = t.take(pa.array(mine))
            sides.append(Side(one["post_id"].to_numpy(), one["words"].combine_chunks()))
        for cols in work(sides):
            n = len(cols[0])
            if n:
                fixed = [pa.array([k], a).take(pa.array(np.zeros(n, np.int32))) for k, a in zip(key, arrow, strict=False)]
                yield pa.RecordBatch.from_arrays(fixed + [pa.array(c) for c in cols], names)

    names = [*within, *[c.split()[0] for c in schema.split(", ")]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows = None, []
        for k, part in runs(batches, keys):
            if k != key:
                if key is not None:
                    yield from done(key, rows)
                key, rows = k, []
            rows.append(part)
        if key is not None:
            yield from done(key, rows)

    full = ", ".join([*[f"{k} {t.simpleString()}" for k, t in zip(within, types, strict=True)], schema])
    return dealt.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, full)


def _exact(theta: float, prune: bool) -> Callable[[list[Side]], Links]:
    return lambda s: _met(s[0], s[-1], _signs_of_words(s, _read(s), theta, prune), theta)


def _hashed(theta: float, bands: int, width: int) -> Callable[[list[Side]], Links]:
    return lambda s: _met(s[0], s[-1], _signs_of_bands(s, _read(s), bands, width), theta)


def _class_rows(find: Callable[[list[Side]], Links]) -> Callable[[list[Side]], Iterator[tuple]]:
    def work(s: list[Side]) -> Iterator[tuple]:
        if len(s) == 1:
            first, member = s[0].copies()
            yield first, member, np.ones(len(first)), np.ones(len(first), bool)
        for x, y, c in find(s):
            a, b = s[0].ids[x], s[-1].ids[y]
            yield np.minimum(a, b), np.maximum(a, b), c, np.zeros(len(c), bool)

    return work


PAIRS = "a long, b long, cosine double, copy boolean"


def class_pairs(posts: DataFrame, theta: float, prune: bool = True, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """(within..., a, b, cosine, copy) of a block's posts, a < b: pairs of classes with a cosine of ``theta`` or more, and (copy)
    each class with its other members.

    ``posts``: of :func:`bags`. Two linked posts share a word. With ``prune`` only the words of a post's prefix are
    joined: words in an order from rare to frequent, up to where the rest of the normalised vector is shorter than theta.
    """
    return _blockwise(posts, within, _class_rows(_exact(theta, prune)), PAIRS)


def class_pairs_lsh(posts: DataFrame, theta: float, bands: int = 24, width: int = 2, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """The rows of :func:`class_pairs` by hashing: classes of a block that agree in ``width`` neighbouring minima of their word
    sets' hashes meet, and their cosine is exact. Some pairs are missed: at a cosine c, of posts of one length, a share of
    (1 - (c / (2 - c)) ** width) ** bands."""
    return _blockwise(posts, within, _class_rows(_hashed(theta, bands, width)), PAIRS)


def class_pairs_recall(posts: DataFrame, theta: float, bands: int = 24, width: int = 2, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """(within..., exact, found, wrong): the pairs of classes of each task that the exact join has, those of them that hashing
    finds, and those that only hashing finds."""

    def work(s: list[Side]) -> Iterator[tuple]:
        of = lambda links: np.concatenate([np.zeros(0, np.int64), *[x * s[-1].n + y for x, y, _ in links]])
        exact, found = of(_exact(theta, True)(s)), of(_hashed(theta, bands, width)(s))
        both = len(np.intersect1d(exact, found))
        yield np.array([len(exact)]), np.array([both]), np.array([len(found) - both])

    return _blockwise(posts, within, work, "exact long, found long, wrong long")


def similar_pairs(vectors: DataFrame, theta: float, prune: bool = True, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """(within..., a, b, cosine) of all posts of a block with a cosine of ``theta`` or more, a < b: those of
    :func:`class_pairs` with the copies expanded, so as many as the squares of groups of copies. For small sets.

    ``vectors``: within..., post_id, word, weight rows.
    """
    found = materialize(class_pairs(weighted_bags(vectors, within), theta, prune, within), "class-pairs")
    return expanded(found, within)


def expanded(found: DataFrame, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """All pairs of posts behind the rows of :func:`class_pairs`."""
    keys = list(within)
    copies, links = found.where("copy"), found.where("not copy").drop("copy")
    of_copies = copies.select(*keys, F.col("a").alias("_c"), F.col("b").alias("m"))
    heads = found.select(*keys, F.explode(F.when(F.col("copy"), F.array("a")).otherwise(F.array("a", "b"))).alias("_c")).distinct()
    members = of_copies.unionByName(heads.withColumn("m", F.col("_c")))
    one, two = members.withColumnsRenamed({"_c": "a", "m": "_x"}), members.withColumnsRenamed({"_c": "b", "m": "_y"})
    across = links.join(one, [*keys, "a"]).join(two, [*keys, "b"]).select(*keys, "_x", "_y", "cosine")
    inside = members.withColumnsRenamed({"m": "_x"}).join(members.withColumnsRenamed({"m": "_y"}), [*keys, "_c"]).where("_x < _y").select(*keys, "_x", "_y", F.lit(1.0).alias("cosine"))
    return across.unionByName(inside).select(*keys, F.least("_x", "_y").alias("a"), F.greatest("_x", "_y").alias("b"), "cosine")


def _roots(n: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The smallest row that each row reaches by the links (x, y)."""
    root = np.arange(n)
    while True:
        lower = root.copy()
        np.minimum.at(lower, root[x], root[y])
        np.minimum.at(lower, root[y], root[x])
        while (lower[lower] != lower).any():
            lower = lower[lower]
        if (lower[root] == root).all():
            return root
        root = lower[root]


def cluster_components(posts: DataFrame, theta: float, within: tuple[str, ...] = WITHIN) -> DataFrame:
    """(node, component): posts of a block that chains of similar pairs connect; no order plays a part. ``posts``: of :func:`bags`.

    A task sends on, for each post that it links, the smallest one reached inside the task, and no pairs.
    """

    def work(s: list[Side]) -> Iterator[tuple]:
        if len(s) == 1:
            yield s[0].copies()
        ids = np.unique(np.concatenate([p.ids for p in s]))
        a, b = (np.searchsorted(ids, p.ids) for p in (s[0], s[-1]))
        root = np.arange(len(ids))
        for x, y, _ in _exact(theta, True)(s):
            root = _roots(len(ids), np.concatenate([np.arange(len(ids)), a[x]]), np.concatenate([root, b[y]]))
        moved = root != np.arange(len(ids))
        yield ids[root[moved]], ids[moved]

    return connected_components(_blockwise(posts, within, work, "src long, dst long"))


#: Sign bits of a bucket of dense vectors, and tables of buckets: at a cosine of 0.4 a share of 1 - (1 - 0.631 ** BITS) ** TABLES is found.
BITS, TABLES = 6, 48


def _usable(vectors: DataFrame, key: str, vector: str) -> DataFrame:
    """(k, v): the vectors in double precision that are not null or zero and have no null or non-finite component."""
    v = F.col(vector).cast("array<double>")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col(key).alias("k"), v.alias("v")).where(fine)


def _planes(dim: int, tables: int, bits: int) -> np.ndarray:
    return np.random.default_rng(3).standard_normal((tables * bits, dim))


def _unit(v: pa.Array) -> np.ndarray:
    x = v.flatten().to_numpy().reshape(len(v), -1)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _signatures(x: np.ndarray, tables: int, bits: int) -> np.ndarray:
    """(rows, tables): the bucket of each vector in each table, by the signs of its projections."""
    side = (x @ _planes(x.shape[1], tables, bits).T >= 0).reshape(len(x), tables, bits)
    return side @ (1 << np.arange(bits))


def dense_classes(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(class_id, members, v): usable vectors that are equal are one class, named by its smallest key."""
    return _usable(vectors, key, vector).groupBy("v").agg(F.min("k").alias("class_id"), F.collect_list("k").alias("members"))


def dense_class_pairs(vectors: DataFrame, theta: float, key: str = "vec_id", vector: str = "embedding", tables: int = TABLES, bits: int = BITS) -> DataFrame:
    """(a, b, cosine, copy): pairs of classes of equal vectors with a cosine of ``theta`` or more, a < b, and (copy) each class
    with its other members; by random projections: classes that share a bucket of a table meet there and nowhere
    else, and their cosine is exact. Recall is below one."""
    classes = materialize(dense_classes(vectors, key, vector), "dense-classes")
    heads = classes.select("class_id", "v")
    copies = classes.where(F.size("members") > 1).select(F.col("class_id").alias("a"), F.explode("members").alias("b")).where("a <> b")
    found = _bucket_pairs(heads.withColumn("asks", F.lit(True)), theta, tables, bits)
    return found.select("a", "b", "cosine", F.lit(False).alias("copy")).unionByName(copies.select("a", "b", F.lit(1.0).alias("cosine"), F.lit(True).alias("copy")))


def dense_search(vectors: DataFrame, theta: float, asks: Column, key: str = "vec_id", vector: str = "embedding", tables: int = TABLES, bits: int = BITS) -> DataFrame:
    """(a, b, cosine): of the vectors that ask, their pairs with all others at a cosine of ``theta`` or more, found as above."""
    v = _usable(vectors, key, vector)
    return _bucket_pairs(v.select(F.col("k").alias("class_id"), "v").withColumn("asks", asks), theta, tables, bits)


def _dealt(v: DataFrame, per_part: int) -> tuple[DataFrame, int]:
    n = max(1, -(-v.count() // per_part))
    return v.withColumn("own", F.pmod(F.xxhash64("class_id"), F.lit(n)).cast("int")), n


def _bucket_pairs(v: DataFrame, theta: float, tables: int, bits: int) -> DataFrame:
    """(a, b, cosine) of (class_id, v, asks) rows, one of each pair asking, at the first table whose bucket both share. Buckets are
    dealt over pairs of parts of the vectors, so that a task holds two parts of ``BLOCK`` vectors at most, whatever the bucket."""
    from eventpulse.operators.clusters import runs

    ship(v.sparkSession)
    v, n = _dealt(v, BLOCK << bits >> 1)  # a bucket has one of 2 ** bits vectors, twice that if it is uneven

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                got = _signatures(_unit(b.column("v")), tables, bits).astype(np.int32)
                sigs = pa.ListArray.from_arrays(pa.array(np.arange(0, got.size + 1, tables), pa.int32()), pa.array(got.ravel()))
                yield pa.RecordBatch.from_arrays([*b.columns, sigs], [*b.schema.names, "sigs"])

    keys = ["t", "bucket", "i", "j"]
    signed = v.select("class_id", "v", "asks", "own").mapInArrow(sign, "class_id long, v array<double>, asks boolean, own int, sigs array<int>")
    rows = signed.select("*", F.posexplode("sigs").alias("t", "bucket")).withColumn("_p", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    rows = rows.select("t", "bucket", F.least("own", "_p").alias("i"), F.greatest("own", "_p").alias("j"), "own", "class_id", "asks", "v", "sigs")

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []
        for k, part in runs(batches, keys):
            if k != key:
                if key is not None:
                    yield from _meet(held, key, theta, tables)
                key, held = k, []
            held.append(part)
        if key is not None:
            yield from _meet(held, key, theta, tables)

    return rows.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(meet, "a long, b long, cosine double")


def _meet(held: list[pa.RecordBatch], key: tuple, theta: float, tables: int) -> Iterator[pa.RecordBatch]:
    t = pa.Table.from_batches(held).combine_chunks()
    own, ids, asks = t["own"].to_numpy(), t["class_id"].to_numpy(), t["asks"].to_numpy()
    x, sigs = _unit(t["v"].combine_chunks()), t["sigs"].combine_chunks().flatten().to_numpy().reshape(-1, tables)
    first, second = np.flatnonzero(own == key[2]), np.flatnonzero(own == key[3])
    strips = [(first[asks[first]], second), (first[~asks[first]], second[asks[second]])]  # others do not ask each other
    for p, second in ((f[at : at + 512], to) for f, to in strips for at in range(0, len(f), 512)):
        c = x[p] @ x[second].T
        ok = c >= theta - EPS
        ok &= (ids[p][:, None] < ids[second][None, :]) if key[2] == key[3] else True
        a, b = np.nonzero(ok)
        if key[0]:
            new = ~(sigs[p[a], : key[0]] == sigs[second[b], : key[0]]).any(axis=1)
            a, b = a[new], b[new]
        if len(a):
            one, two = ids[p[a]], ids[second[b]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(one, two)), pa.array(np.maximum(one, two)), pa.array(c[a, b])], ["a", "b", "cosine"])


def dense_brute(vectors: DataFrame, theta: float, asks: Column, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """The rows of :func:`dense_search` without an index: every vector that asks against every other, by one bucket that all share."""
    v = _usable(vectors, key, vector).select(F.col("k").alias("class_id"), "v").withColumn("asks", asks)
    return _bucket_pairs(v, theta, 1, 0)
