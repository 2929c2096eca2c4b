"""Embedding near-duplicates through spherical-cap filters.

Directions come from a random product code: after one random rotation a vector's components are cut into blocks, each
block has its own few random codewords, and every choice of one codeword per block is a filter direction. List
decoding finds all filters whose inner product with the unit vector exceeds the cap height: block by block, partial
sums that cannot reach it any more are dropped, so a vector never meets all filters. Vectors of equal label join on
shared filters and every meeting pair is verified by its cosine in double precision.

Equal vectors collapse to one before the search. A pair is counted only under the smallest filter that both share, so
link counts need no list of pairs; what a task returns are link sums by vector and a spanning forest. A bucket of over
`tile` vectors is cut into tiles of chunk against chunk, each its own task, so none is too large and none is dropped.

Null label, null vector, null or non-finite components, zero vectors: such rows link with nothing. Vectors of different
length link with nothing. Null vec_id: counts as a link, is never a component's id unless no member has one. Repeated
rows link with each other. Empty table: empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .components import Forest, connected
from .shared import store


@dataclass(frozen=True)
class Caps:
    """blocks x words: the product code, words ** blocks filters; expected: filters a random vector passes, about.

    least: a vector that exceeds fewer filters lowers its cap until it has so many, since recall hangs on the shortest list.
    """

    cosine: float = 0.98
    blocks: int = 3
    words: int = 24
    expected: float = 8.0
    least: int = 16
    tile: int = 2048
    seed: int = 11


def spread(rows: int, caps: Caps) -> Caps:
    """The code for so many vectors: filters grow with the rows, so that buckets don't."""
    filters = max(24**3, rows)
    blocks = max(3, math.ceil(math.log(filters) / math.log(64)))
    words = max(8, round(filters ** (1 / blocks)))
    return replace(caps, blocks=blocks, words=words)


@lru_cache(maxsize=8)
def _code(caps: Caps, dim: int) -> tuple[np.ndarray, list[np.ndarray], float]:
    """Rotation, codewords of each block, cap height."""
    rng = np.random.default_rng([caps.seed, dim, caps.blocks, caps.words])
    rotation = np.linalg.qr(rng.normal(size=(dim, dim)))[0]
    edges = [dim * i // caps.blocks for i in range(caps.blocks + 1)]
    words = [rng.normal(size=(caps.words, b - a)) for a, b in zip(edges, edges[1:], strict=False)]
    # the share of filters that a random direction exceeds, from random directions
    probe = rng.normal(size=(400, dim))
    probe = probe / np.linalg.norm(probe, axis=1, keepdims=True)
    parts = [probe[:, a:b] @ w.T for (a, b), w in zip(zip(edges, edges[1:], strict=False), words, strict=True)]
    drawn = sum(p[:, rng.integers(0, caps.words, 2000)] for p in parts)
    height = float(np.quantile(drawn, 1 - min(0.5, caps.expected / caps.words**caps.blocks)))
    return rotation, words, height


def decode(unit: np.ndarray, caps: Caps) -> tuple[np.ndarray, np.ndarray]:
    """(row, filter) of every filter that a row exceeds, by row; a row that exceeds fewer than caps.least gets about so many."""
    if not len(unit):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    rotation, words, height = _code(caps, unit.shape[1])
    turned, at, parts = unit @ rotation, 0, []
    for w in words:
        parts.append(turned[:, at : at + w.shape[1]] @ w.T)
        at += w.shape[1]
    best = [p.max(axis=1) for p in parts]
    after = np.zeros((len(parts) + 1, len(unit)))
    for b in range(len(parts) - 1, -1, -1):
        after[b] = after[b + 1] + best[b]
    # the `least`-th best sum over each block's best words bounds the true one from below
    top = min(len(words[0]), math.ceil(caps.least ** (1 / len(words))) + 6)
    sums = np.zeros((len(unit), 1))
    for p in parts:
        chosen = -np.partition(-p, top - 1, axis=1)[:, :top]
        sums = (sums[:, :, None] + chosen[:, None, :]).reshape(len(unit), -1)
        if sums.shape[1] > 8 * caps.least:
            sums = -np.partition(-sums, 4 * caps.least - 1, axis=1)[:, : 4 * caps.least]
    rank = min(caps.least, sums.shape[1])
    level = np.minimum(height, -np.partition(-sums, rank - 1, axis=1)[:, rank - 1] - 1e-12)
    row, code, score = np.arange(len(unit)), np.zeros(len(unit), np.int64), np.zeros(len(unit))
    for b, p in enumerate(parts):
        reach = score[:, None] + p[row]
        keep = reach + after[b + 1][row][:, None] >= level[row][:, None]
        i, w = np.nonzero(keep)
        row, code, score = row[i], code[i] * len(p[0]) + w, reach[i, w]
    return row, code


def units(vectors: np.ndarray) -> np.ndarray:
    """Rows as unit vectors in double precision."""
    vectors = vectors.astype(np.float64)
    # scaled first, so that squares neither overflow nor vanish
    vectors = vectors / np.abs(vectors).max(axis=1, keepdims=True)
    return vectors / np.linalg.norm(vectors, axis=1, keepdims=True)


def _small(caps: Caps) -> type:
    """The number type of a filter as it is sent along."""
    return np.uint32 if caps.words**caps.blocks <= 1 << 32 else np.int64


def _filters(caps: Caps, kind: type):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # label, dim, uid, n, v  ->  label, dim, filter, uid, n, vector, all filters
        for batch in batches:
            dims = np.asarray(batch.column(1).to_numpy(zero_copy_only=False))
            for dim in np.unique(dims):
                group = batch.take(pa.array(np.flatnonzero(dims == dim)))
                for lo in range(0, group.num_rows, 500):
                    part = group.slice(lo, 500)
                    vectors = np.asarray(part.column(4).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(part.num_rows, -1)
                    row, code = decode(units(vectors), caps)
                    order = np.lexsort((code, row))
                    row, code = row[order], code[order]
                    cuts = np.searchsorted(row, np.arange(part.num_rows + 1))
                    sent = code.astype(_small(caps))
                    lists = pa.array([sent[a:b].tobytes() for a, b in zip(cuts, cuts[1:], strict=False)], pa.binary())
                    bodies = pa.array([v.tobytes() for v in vectors.astype(kind)], pa.binary())
                    take = pa.array(row)
                    yield pa.RecordBatch.from_arrays([part.column(0).take(take), part.column(1).take(take), pa.array(code), part.column(2).take(take), part.column(3).take(take), bodies.take(take), lists.take(take)], names=["label", "dim", "filter", "uid", "n", "body", "filters"])

    return run


@dataclass
class Side:
    """Vectors of a bucket: unit rows, their filters end to end with n + 1 offsets, uids and multiplicities."""

    unit: np.ndarray
    flat: np.ndarray
    cuts: np.ndarray
    uid: np.ndarray
    n: np.ndarray
    mine: np.ndarray

    def rows(self, lo: int, hi: int) -> Side:
        return Side(self.unit[lo:hi], self.flat, self.cuts[lo : hi + 1], self.uid[lo:hi], self.n[lo:hi], self.mine[lo:hi])

    def picked(self, at: np.ndarray) -> Side:
        """Rows at these places, which are runs of neighbours or not."""
        size = np.diff(self.cuts)[at]
        cuts = np.concatenate(([0], np.cumsum(size)))
        spans = np.repeat(self.cuts[at] - cuts[:-1], size) + np.arange(cuts[-1])
        return Side(self.unit[at], self.flat[spans], cuts, self.uid[at], self.n[at], self.mine[at])

    def below(self, at: np.ndarray, own: int) -> tuple[np.ndarray, np.ndarray]:
        """(place in `at`, filter) of those rows' filters under `own`."""
        some = self.picked(at)
        small = some.flat < own
        return np.repeat(np.arange(len(at)), np.diff(some.cuts))[small], some.flat[small]


def _joined(parts: list[Side]) -> Side:
    if len(parts) == 1:
        return parts[0]
    parts = [p.picked(np.arange(len(p.uid))) for p in parts]
    shifts = np.cumsum([0, *[len(p.flat) for p in parts]])
    cuts = np.concatenate([[0], *[p.cuts[1:] + s for p, s in zip(parts, shifts, strict=False)]])
    gather = lambda name: np.concatenate([getattr(p, name) for p in parts])
    return Side(gather("unit"), gather("flat"), cuts, gather("uid"), gather("n"), gather("mine"))


def _links(x: Side, y: Side, own: int, cosine: float, upper: bool) -> np.ndarray | None:
    """Boolean matrix, None if nothing links: linked, `own` is the smallest filter of both, and with `upper` each pair of one side once."""
    near = x.unit @ y.unit.T >= cosine
    if upper:
        near = np.triu(near, 1)
    if not near.any():
        return None
    i, j = np.flatnonzero(near.any(axis=1)), np.flatnonzero(near.any(axis=0))
    row, fx = x.below(i, own)
    col, fy = y.below(j, own)
    shared = np.intersect1d(fx, fy)
    if len(shared):
        marks = []
        for at, f, size in ((row, fx, len(i)), (col, fy, len(j))):
            m = np.zeros((size, len(shared)), np.float32)
            spot = np.minimum(np.searchsorted(shared, f), len(shared) - 1)
            hit = shared[spot] == f
            m[at[hit], spot[hit]] = 1
            marks.append(m)
        near[np.ix_(i, j)] &= marks[0] @ marks[1].T == 0
        if not near.any():
            return None
    return near


def _tree(near: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) pairs, or with few links all of them, and marks that connect what the matrix links; rows stand before columns."""
    rows, columns = np.nonzero(near)
    size = len(near)
    if len(rows) <= 64:
        return rows, columns + size
    # the smallest row number travels along links until nothing changes; each member then hangs on its component's row
    far = np.int64(size)
    by_row, by_column = np.arange(size), np.where(near, np.arange(size)[:, None], far).min(axis=0)
    while True:
        after = np.minimum(by_row, np.where(near, by_column[None, :], far).min(axis=1))
        if (after == by_row).all():
            break
        by_row = after
        by_column = np.where(near, by_row[:, None], far).min(axis=0)
    label = np.concatenate((by_row, by_column))
    member = np.flatnonzero((label < far) & (label != np.arange(len(label))))
    return label[member], member


def _raw(column: pa.Array, lo: int, hi: int, kind: type) -> tuple[np.ndarray, np.ndarray]:
    """Values of a binary column's rows end to end, and their n + 1 offsets."""
    wide = np.int64 if pa.types.is_large_binary(column.type) else np.int32
    offsets = np.frombuffer(column.buffers()[1], wide)[column.offset + lo : column.offset + hi + 1].astype(np.int64)
    item = np.dtype(kind).itemsize
    return np.frombuffer(column.buffers()[2], np.uint8)[offsets[0] : offsets[-1]].view(kind), (offsets - offsets[0]) // item


def _verify(caps: Caps, kind: type):
    """Reads rows sorted by (label, dim, filter, one, two); yields (kind, a, b): 0 uid and links, 1 an edge.

    Bodies are read and scaled a batch at a time; a bucket that goes on in the next batch is kept until it ends (two tiles at most).
    """
    step = 512

    def bucket(key: tuple, side: Side, forest: Forest, sums: dict[int, int], edges: list[tuple[int, int]]) -> None:
        own, one, two = key[2:]
        mine = side if one == two else side.picked(np.flatnonzero(side.mine == one))
        other = side if one == two else side.picked(np.flatnonzero(side.mine == two))
        for i in range(0, len(mine.uid), step):
            for j in range(i if one == two else 0, len(other.uid), step):
                x, y = mine.rows(i, i + step), other.rows(j, j + step)
                near = _links(x, y, own, caps.cosine, one == two and i == j)
                if near is None:
                    continue
                for uids, totals in ((x.uid, near @ y.n), (y.uid, x.n @ near)):
                    some = np.flatnonzero(totals)
                    for uid, total in zip(uids[some].tolist(), totals[some].tolist(), strict=True):
                        sums[uid] = sums.get(uid, 0) + total
                both = np.concatenate((x.uid, y.uid))
                a, b = _tree(near)
                for u, v in zip(both[a].tolist(), both[b].tolist(), strict=True):
                    if forest.union(u, v):
                        edges.append((u, v))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest, sums, edges = Forest(), {}, []
        held: tuple | None = None
        parts: list[Side] = []

        def flush() -> pa.RecordBatch:
            found = [(0, u, n) for u, n in sums.items()] + [(1, a, b) for a, b in edges]
            sums.clear()
            edges.clear()
            return pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], t) for k, t in enumerate((pa.int32(), pa.int64(), pa.int64()))], names=["kind", "a", "b"])

        def close() -> None:
            if sum(len(p.uid) for p in parts) > 1:
                bucket(held, _joined(parts), forest, sums, edges)
            parts.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            label = batch.column(0).dictionary_encode()
            names = label.dictionary.to_pylist()
            keys = [label.indices.to_numpy(zero_copy_only=False), *(np.asarray(batch.column(k).to_numpy(zero_copy_only=False)) for k in range(1, 5))]
            mine, uid, n = (np.asarray(batch.column(k).to_numpy(zero_copy_only=False)) for k in (5, 6, 7))
            change = np.zeros(batch.num_rows - 1, bool)
            for k in keys:
                change |= k[1:] != k[:-1]
            begins = np.concatenate(([0], np.flatnonzero(change) + 1))
            ends = np.append(begins[1:], batch.num_rows)
            turns = np.concatenate(([0], np.flatnonzero(keys[1][1:] != keys[1][:-1]) + 1, [batch.num_rows]))
            at = 0
            for lo, hi in zip(turns, turns[1:], strict=False):  # rows of one vector length
                body, _ = _raw(batch.column(8), lo, hi, kind)
                flat, cuts = _raw(batch.column(9), lo, hi, _small(caps))
                whole = Side(units(body.reshape(hi - lo, -1)), flat, cuts, uid[lo:hi], n[lo:hi], mine[lo:hi])
                while at < len(begins) and begins[at] < hi:
                    b, e = begins[at], ends[at]
                    key = (names[keys[0][b]], *(int(k[b]) for k in keys[1:]))
                    if key != held:
                        close()
                        held = key
                    parts.append(whole.rows(b - lo, e - lo))
                    at += 1
            # what goes on in the next batch must not hold this one's arrays
            parts[:] = [p.picked(np.arange(len(p.uid))) for p in parts]
            if len(sums) > 50_000:
                yield flush()
        close()
        yield flush()

    return run


def near_duplicates(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", label: str = "label", caps: Caps | None = None, fit_to_rows: bool = True) -> DataFrame:
    """vec_id, n_links, component_id, kept; one row per vector."""
    caps = caps or Caps()
    kind = np.float32 if vectors.schema[embedding].dataType.simpleString() == "array<float>" else np.float64
    rows = vectors.select(F.col(f"`{vec_id}`").cast("long").alias("vec_id"), F.col(f"`{embedding}`").cast("array<double>").alias("v"), F.col(f"`{label}`").cast("string").alias("label"))
    finite = F.forall("v", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf")))) & F.exists("v", lambda e: e != 0)
    rows = rows.withColumn("fine", F.coalesce(F.col("label").isNotNull() & finite, F.lit(False)))
    fine = rows.where("fine")
    distinct = fine.groupBy("label", "v").agg(F.count("*").alias("n"), F.min("vec_id").alias("least"))
    distinct = store(distinct.withColumn("uid", F.monotonically_increasing_id()).withColumn("dim", F.size("v")))
    if fit_to_rows:
        caps = spread(distinct.count(), caps)
    schema = "label string, dim int, filter long, uid long, n long, body binary, filters binary"
    passed = store(distinct.select("label", "dim", "uid", "n", "v").mapInArrow(_filters(caps, kind), schema))
    bucket = ["label", "dim", "filter"]
    hot = store(passed.groupBy(*bucket).agg(F.count("*").alias("size")).where(F.col("size") > caps.tile).select(*[F.col(c).alias(f"h_{c}") for c in bucket], F.ceil(F.col("size") / caps.tile).cast("int").alias("g")))
    n_hot = hot.count()
    if n_hot:
        side = F.broadcast(hot) if n_hot <= 100_000 else hot
        dealt = passed.join(side, [passed[c] == hot[f"h_{c}"] for c in bucket], "left").withColumn("g", F.coalesce("g", F.lit(1)))
        mine = F.pmod(F.xxhash64("uid"), F.col("g")).cast("int")
        dealt = dealt.withColumn("mine", mine).withColumn("peer", F.explode(F.sequence(F.lit(0), F.col("g") - 1))).withColumns({"one": F.least("mine", "peer"), "two": F.greatest("mine", "peer")})
    else:
        dealt = passed.withColumns({"one": F.lit(0), "two": F.lit(0), "mine": F.lit(0)})
    keys = [*bucket, "one", "two"]
    dealt = dealt.select(*keys, "mine", "uid", "n", "body", "filters").repartition(*keys).sortWithinPartitions(*keys)
    found = store(dealt.mapInArrow(_verify(caps, kind), "kind int, a long, b long"))
    reached = connected(found.where("kind = 1").select(F.col("a").alias("u"), F.col("b").alias("v")), contracted=True)
    sums = found.where("kind = 0").groupBy("a").agg(F.sum("b").alias("links"))
    named = distinct.drop("dim").join(sums, distinct["uid"] == sums["a"], "left").join(reached, distinct["uid"] == reached["node"], "left")
    named = store(named.select("label", "v", "n", "least", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("root", "uid").alias("root")))
    least = store(named.groupBy("root").agg(F.min("least").alias("component_id")))
    named = store(named.join(least, "root").select(F.col("label").alias("d_label"), F.col("v").alias("d_v"), (F.col("links") + F.col("n") - 1).alias("n_links"), "component_id"))
    linked = fine.join(named, (fine["label"] == named["d_label"]) & (fine["v"] == named["d_v"])).select("vec_id", "n_links", "component_id")
    alone = rows.where("not fine").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionAll(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
