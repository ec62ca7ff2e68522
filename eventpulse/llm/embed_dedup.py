"""Near-duplicate vectors by an inverted multi-index.

Vectors are compared with those of their own length. The two halves of the vectors have codebooks of their own,
whose product is a grid of cells; a length with few vectors has one cell. Every vector is stored in its cell and
visits the cells nearest to it, in the order of the sum of both half distances: of two sorted lists of distances, the V
smallest sums stand at places (a, b) with (a + 1) * (b + 1) <= V, so few sums are formed. V is the smallest number of
visits that, from either end, finds the wanted share of pairs that lie exactly on the threshold. Of those V, a cell
is left out if no vector of it can reach the threshold: it lies beyond the half planes between centres by more
than the distance that the threshold allows, which loses no pair. Where a visitor meets stored vectors the cosine is verified in
double precision.

Vectors of one direction form a class that is stored once. Cells are dealt over blocks of stored and of
visiting vectors. A pair that both ends find is counted at one of them, and what a block returns is
a count for each vector and a spanning set of its links, not the links.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eventpulse.llm.arrow import map_batches
from eventpulse.llm.minhash import groups, spanning
from eventpulse.operators.components import connected_components
from eventpulse.plans.scratch import materialize

#: Vectors that a length's codebooks are fitted on and its visits calibrated on, at most; every vector is indexed.
SAMPLE, CALIBRATED = 20_000, 2_000
#: Stored vectors meant for a cell; stored and visiting ones in a block.
PER_CELL, STORED, VISITING = 400, 1024, 8192
THRESHOLD, RECALL = 0.9, 0.98


def usable(vector: str) -> Column:
    """Neither null nor zero, without null or non-finite components."""
    v = F.col(vector)
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    return v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, bad) & F.exists(v, lambda x: x != 0)


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length one, in double precision; scaled first, so that squares neither vanish nor overflow."""
    x = x.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def k_means(x: np.ndarray, k: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Centres of at most k clusters of the rows, from a seeded start."""
    rng = np.random.default_rng(seed)
    c = x[rng.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        near = _distances(x, c).argmin(axis=1)
        n = np.bincount(near, minlength=len(c))
        sums = np.zeros_like(c)
        np.add.at(sums, near, x)
        c[n > 0] = sums[n > 0] / n[n > 0][:, None]
    return c


def _distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(axis=1)[:, None] - 2 * x @ c.T + (c * c).sum(axis=1), 0)


class Grid:
    """Two codebooks and the number of cells to visit, for vectors of one length; one cell without a sample."""

    def __init__(self, sample: np.ndarray | None, total: int = 0, threshold: float = THRESHOLD, recall: float = RECALL):
        self.visits, self.half = 1, 0
        self.reach = 2 - 2 * threshold + 1e-9  # squared distance of unit vectors on the threshold
        if sample is None:
            self.first = self.second = None
            return
        k = min(256, max(2, 1 << int(math.log2(max(math.sqrt(total / PER_CELL), 2)))))
        self.half = sample.shape[1] // 2
        self.first, self.second = k_means(sample[:, : self.half], k), k_means(sample[:, self.half :], k)
        self.visits = self._calibrate(sample[:CALIBRATED], threshold, recall)

    @property
    def cells(self) -> int:
        return 1 if self.first is None else len(self.first) * len(self.second)

    def _halves(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return _distances(x[:, : self.half], self.first), _distances(x[:, self.half :], self.second)

    def ordered(self, x: np.ndarray, visits: int) -> tuple[np.ndarray, np.ndarray]:
        """(rows, visits) cells, nearest first, and whether each can hold a vector that reaches the threshold."""
        if self.first is None:
            return np.zeros((len(x), 1), dtype=np.int64), np.ones((len(x), 1), dtype=bool)
        visits = min(visits, self.cells)
        at = np.array([(p, q) for p in range(min(len(self.first), visits)) for q in range(min(len(self.second), visits // (p + 1)))])
        rows = max(1, 2_000_000 // len(at))
        if len(x) > rows:
            parts = [self.ordered(x[lo : lo + rows], visits) for lo in range(0, len(x), rows)]
            return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
        ranked = []
        for d, centres in zip(self._halves(x), (self.first, self.second), strict=True):
            i = np.argsort(d, axis=1, kind="stable")
            d = np.take_along_axis(d, i, 1)
            apart = _distances(centres, centres)
            # squared distance to the plane between the nearest centre and each: no vector of that centre is nearer
            to_plane = (d - d[:, :1]) ** 2 / (4 * np.maximum(apart[i[:, :1], i], 1e-30))
            ranked.append((d, i, np.where(i == i[:, :1], 0.0, to_plane)))
        (a, ia, fa), (b, ib, fb) = ranked
        order = np.argsort(a[:, at[:, 0]] + b[:, at[:, 1]], axis=1, kind="stable")[:, :visits]
        p, q = at[order, 0], at[order, 1]
        cells = np.take_along_axis(ia, p, 1) * len(self.second) + np.take_along_axis(ib, q, 1)
        return cells, np.take_along_axis(fa, p, 1) + np.take_along_axis(fb, q, 1) <= self.reach

    def _rank(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """How many cells each row of x visits before the one that holds the row of y; memory is a row's centres."""
        (a, b), (ya, yb) = self._halves(x), self._halves(y)
        rows = np.arange(len(x))
        sums = a[rows, ya.argmin(axis=1)] + b[rows, yb.argmin(axis=1)]
        return np.array([np.searchsorted(np.sort(b[i]), sums[i] - a[i] - 1e-12).sum() for i in rows])

    def _calibrate(self, x: np.ndarray, threshold: float, recall: float) -> int:
        """Visits after which ``recall`` of the pairs with a cosine of ``threshold`` have met."""
        rng = np.random.default_rng(11)
        away = rng.standard_normal(x.shape)
        away -= (away * x).sum(axis=1, keepdims=True) * x
        away /= np.linalg.norm(away, axis=1, keepdims=True)
        y = threshold * x + math.sqrt(1 - threshold * threshold) * away
        rank = np.minimum(self._rank(x, y), self._rank(y, x))
        return int(np.quantile(rank, recall, method="higher")) + 1


def _rows(col: pa.Array, dtype: str) -> np.ndarray:
    """Stored vectors of one length, as unit vectors in double precision."""
    raw = col.to_pylist()
    return unit(np.frombuffer(b"".join(raw), dtype=dtype).reshape(len(raw), -1))


def _directions(rows: DataFrame, dtype: str) -> DataFrame:
    """(vec_id, d, way, vector) of rows whose vectors are usable or null: the length, a 128-bit digest of the unit vector, in
    which equal directions are equal, and the vector's own bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            col = b.column("vector")
            length = np.nan_to_num(np.asarray(pc.list_value_length(col).cast(pa.float64())), nan=0).astype(np.int32)
            way, own = [None] * len(col), [None] * len(col)
            for d in np.unique(length[length > 0]).tolist():
                at = np.flatnonzero(length == d)
                x = np.asarray(col.take(pa.array(at)).flatten()).reshape(-1, d)
                for i, u, v in zip(at.tolist(), unit(x) + 0.0, x.astype(dtype), strict=True):
                    way[i], own[i] = hashlib.blake2b(u.tobytes(), digest_size=16).digest(), v.tobytes()
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array(length, pa.int32()), pa.array(way, pa.binary()), pa.array(own, pa.binary())], ["vec_id", "d", "way", "vector"])

    return map_batches(rows, run, "vec_id long, d int, way binary, vector binary")


def _meetings(first: np.ndarray, t: pa.RecordBatch, threshold: float, dtype: str, out: list) -> None:
    """Links within the blocks of a batch: (1, id, links) and (0, id, linked id) rows go to ``out``."""
    ids, size, stored = t.column("rep").to_numpy(), t.column("n").to_numpy(), t.column("stored").to_numpy(zero_copy_only=False)
    cell, own = t.column("cell").to_numpy(), t.column("own").to_numpy()
    for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(ids)], strict=True):
        s, v = lo + np.flatnonzero(stored[lo:hi]), lo + np.flatnonzero(~stored[lo:hi])
        if not len(s) or not len(v):
            continue
        x = _rows(t.column("vector").take(pa.array(s)), dtype)
        visits = t.column("visits").take(pa.array(s)).to_pylist()
        goes = np.frombuffer(b"".join(visits), dtype=np.int32).astype(np.int64) | np.repeat(np.arange(len(s)), [len(g) // 4 for g in visits]) << 32
        here = int(cell[lo])
        links, labels = np.zeros(hi - lo, dtype=np.int64), np.arange(hi - lo)
        for a in range(0, len(v), 2048):
            q = v[a : a + 2048]
            i, j = np.nonzero(_rows(t.column("vector").take(pa.array(q)), dtype) @ x.T >= threshold)
            if not len(i):
                continue
            away = own[q][i] != here
            once = np.where(away, True, ids[q][i] < ids[s][j])
            k = np.flatnonzero(away & (own[q][i] < here))  # the other end's cell counts it, if this end goes there
            once[k] = ~np.isin(j[k] << 32 | own[q][i[k]], goes)
            i, j = i[once], j[once]
            np.add.at(links, q[i] - lo, size[s[j]])
            np.add.at(links, s[j] - lo, size[q[i]])
            spanning(labels, np.minimum(q[i], s[j]) - lo, np.maximum(q[i], s[j]) - lo)
        some = np.flatnonzero(links)
        out.append((np.ones(len(some), np.int8), ids[lo + some], links[some]))
        moved = np.flatnonzero(ids[lo:hi] != ids[lo + labels])
        out.append((np.zeros(len(moved), np.int8), ids[lo + moved], ids[lo + labels[moved]]))


def _found(classes: DataFrame, grids: dict[int, Grid], threshold: float, dtype: str) -> DataFrame:
    """(kind, a, b): links counted for a class (1, class, links) and spanning links (0, class, class)."""
    shared = classes.sparkSession.sparkContext.broadcast(grids)  # for each length two codebooks of 256 centres at most

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                rows = whole.slice(at, 2048)
                length = rows.column("d").to_numpy()
                for d in np.unique(length).tolist():
                    b, g = rows.filter(pa.array(length == d)), shared.value.get(d) or Grid(None)
                    cells, near = g.ordered(_rows(b.column("vector"), dtype), g.visits)
                    goes = [c[n].astype(np.int32) for c, n in zip(cells, near, strict=True)]
                    yield pa.RecordBatch.from_arrays([
                        b.column("d"), b.column("rep"), b.column("n"), pa.array(cells[:, 0], pa.int32()), b.column("vector"),
                        pa.array([c.tobytes() for c in goes], pa.binary()), pa.array(goes, pa.list_(pa.int32())),
                    ], ["d", "rep", "n", "own", "vector", "visits", "cells"])

    placed = materialize(map_batches(classes.select("d", "rep", "n", "vector"), place, "d int, rep long, n long, own int, vector binary, visits binary, cells array<int>"), "vectors-placed")
    going = placed.select("d", "rep", "n", "own", "vector", F.explode("cells").alias("cell"))
    kept = placed.groupBy("d", F.col("own").alias("cell")).agg(F.ceil(F.count("*") / STORED).cast("int").alias("sb"))
    seen = placed.select("d", F.explode("cells").alias("cell")).groupBy("d", "cell").agg(F.ceil(F.count("*") / VISITING).cast("int").alias("vb"))
    plan = F.broadcast(kept.join(seen, ["d", "cell"]))  # a row a cell: 256 x 256 for each length that has codebooks, else one
    all_of = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    one_of = lambda n: F.pmod(F.xxhash64("rep"), F.col(n)).cast("int")
    held = placed.withColumn("cell", F.col("own")).join(plan, ["d", "cell"]).withColumn("i", one_of("sb")).withColumn("j", all_of("vb"))
    come = going.join(plan, ["d", "cell"]).withColumn("j", one_of("vb")).withColumn("i", all_of("sb"))
    keys = ["d", "cell", "i", "j"]
    cols = [*keys, "rep", "n", "own", "vector"]
    met = held.select(*cols, "visits", F.lit(True).alias("stored")).unionByName(come.select(*cols, F.lit(None).cast("binary").alias("visits"), F.lit(False).alias("stored")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for first, t in groups(batches, keys):
            out: list = [(np.zeros(0, np.int8), np.zeros(0, np.int64), np.zeros(0, np.int64))]
            _meetings(first, t, threshold, dtype, out)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[k] for o in out])) for k in range(3)], ["kind", "a", "b"])

    return map_batches(met.repartition(*keys).sortWithinPartitions(*keys), run, "kind byte, a long, b long")


def near_duplicates(df: DataFrame, vector: str = "embedding", key: str = "vec_id", threshold: float = THRESHOLD, recall: float = RECALL) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for each row of ``df``.

    Rows are linked whose vectors have one length, whose cosine, in double precision, is ``threshold`` or more and that
    the index finds; component_id is the smallest vec_id that links reach. Vectors that are null or zero or hold null or
    non-finite components link with nothing. A null vec_id links with nothing, has no component and is kept. Repeated
    rows link with each other. A vec_id that comes with several vectors is one node: each of its rows has the links of all. An empty
    table gives an empty table. Lengths of more than ``STORED`` directions have codebooks of their own.
    """
    small = df.schema[vector].dataType.simpleString() == "array<float>"
    kind, dtype = ("array<float>", "<f4") if small else ("array<double>", "<f8")
    rows = df.select(F.col(key).cast("long").alias("vec_id"), F.when(usable(vector) & F.col(key).isNotNull(), F.col(vector).cast(kind)).alias("vector"))
    rows = materialize(_directions(rows, dtype), "vectors-directions")
    classes = rows.where("way is not null").groupBy("way").agg(F.min("vec_id").alias("rep"), F.first("d").alias("d"), F.count("*").alias("n"), F.min_by("vector", F.struct("vec_id", "vector")).alias("vector"))
    classes = materialize(classes, "vectors-classes")
    grids = {}
    for r in classes.groupBy("d").agg(F.count("*").alias("c")).where(F.col("c") > STORED).collect():  # a row a length
        picked = classes.where(F.col("d") == r["d"]).select("rep", "vector").orderBy(F.xxhash64("rep"), "rep").limit(SAMPLE).toArrow()
        grids[r["d"]] = Grid(_rows(picked.column("vector"), dtype), r["c"], threshold, recall)
    found = materialize(_found(classes, grids, threshold, dtype), "vectors-links")
    linked = connected_components(found.where("kind = 0").select(F.col("a").alias("src"), F.col("b").alias("dst")))
    counts = found.where("kind = 1").groupBy(F.col("a").alias("rep")).agg(F.sum("b").alias("links"))
    of_class = classes.join(counts, "rep", "left").join(linked.withColumnRenamed("node", "rep"), "rep", "left")
    of_class = of_class.select(F.col("way").alias("_v"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("_c"))
    out = rows.join(of_class, F.col("way") == F.col("_v"), "left")
    component = F.coalesce("_c", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))
