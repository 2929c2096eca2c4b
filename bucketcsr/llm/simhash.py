"""SimHash near-duplicates through BK-trees.

Fingerprints of whole texts come from one Arrow pass. Copies of a fingerprint collapse to one row before
any search. Fingerprints at most `radius` bits apart agree in all but `radius` of `radius + 4` bit blocks, so
each distinct fingerprint is dealt to one shard for every choice of agreeing blocks, and two linked ones meet
in at least one shard. A shard's fingerprints grow a BK-tree: children are keyed by their integer Hamming
distance to the parent, and a search follows only edges within `radius` of its own distance. No tree holds over about TREE
fingerprints: a larger shard is cut into chunks, and each chunk's tree meets the other chunks in tiles of their own.
A tree is replicated to the tasks that hold rows of its own shard, by an exchange, and to no others: a broadcast through the
driver would carry the fingerprints of all documents, whose number has no bound. Of shards with the same members one is
searched. A shard yields a spanning forest of its links, not its pairs; `components.connected` joins the forests.

Two ways to link. By distance: fingerprints within `radius` bits. By distance and similarity (`Similarity`): the trees link first, then texts whose
sets of word shingles have a Jaccard similarity of `least` or more are linked as well. Fingerprints of similar texts may be ten and more bits apart, so
for these shards come from bands of minwise values instead of equal blocks. First every text of a shard is compared with the shard's anchor, its
smallest uid: one comparison a text, so a group of any size costs in proportion. Then, in the shards whose texts are not all
linked by that, every two texts that nothing links yet are compared. Texts linked to the anchor need not meet each other; they and the rest
are cut into tiles of chunk against chunk. All comparisons take the whole shingle sets, however far apart the fingerprints
are; the sets are made only for texts that share a shard with another. Copies collapse first in either way.

Null text: as empty, fingerprint zero. Null doc_id: takes part in links, and never is a component's id unless
no member has one (then the id is null). Repeated rows are kept. Empty table: empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from . import words as W
from .components import Forest, connected
from .shared import deal_tiles, forget, fresh, map_text, numbered, store, store_at

BITS = 64


def fingerprints(texts: pa.Array, width: int = 3, seed: int = 42) -> pa.Array:
    """A signed 64-bit fingerprint for each text."""
    raw, offsets = W.flat(texts)
    words = W.split(W.LOWER[raw], offsets)
    n_words = np.diff(words.first)
    # words with one space after each, so that a shingle is one slice
    gaps = np.arange(len(words.offsets) - 1)
    lengths = np.diff(words.offsets)
    spaced = np.full(len(words.raw) + len(gaps), 0x20, np.uint8)
    spaced[np.arange(len(words.raw)) + np.repeat(gaps, lengths)] = words.raw
    begin = words.offsets[:-1] + gaps
    end = begin + lengths
    body = spaced.tobytes()
    shingles = np.where(n_words > 0, np.maximum(n_words - width + 1, 1), 0)
    at = np.zeros(len(shingles) + 1, np.int64)
    np.cumsum(shingles, out=at[1:])
    starts = np.repeat(words.first[:-1], shingles) + np.arange(at[-1]) - np.repeat(at[:-1], shingles)
    lasts = np.minimum(starts + width, np.repeat(words.first[1:], shingles)) - 1
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(body[a:b], seed) for a, b in zip(begin[starts].tolist(), end[lasts].tolist(), strict=True)), np.uint64, len(starts))
    return pa.array(majority(hashes, at).view(np.int64))


def majority(hashes: np.ndarray, at: np.ndarray) -> np.ndarray:
    """By segment (at: n + 1 edges) the 64 bits that over half of its hashes have set; an empty segment gives 0."""
    sizes = np.diff(at)
    out = np.zeros(len(sizes), np.uint64)
    full = np.flatnonzero(sizes)
    step = 1 << 15
    # runs of segments of about `step` hashes each, so that the bit matrix stays small
    k = 0
    while k < len(full):
        stop = max(k + 1, int(np.searchsorted(at[full + 1], at[full[k]] + step, "right")))
        group = full[k:stop]
        counts = np.zeros((len(group), BITS), np.int64)
        for lo in range(int(at[group[0]]), int(at[group[-1] + 1]), 4 * step):
            hi = min(lo + 4 * step, int(at[group[-1] + 1]))
            bits = np.unpackbits(hashes[lo:hi].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            cuts = np.clip(at[group], lo, hi) - lo
            inside = (at[group + 1] > lo) & (at[group] < hi)
            counts[inside] += np.add.reduceat(bits, cuts[inside], axis=0, dtype=np.int32)
        over = (2 * counts > sizes[group][:, None]).astype(np.uint8)
        out[group] = np.packbits(over, axis=1, bitorder="little").view(np.uint64)[:, 0]
        k = stop
    return out


class BKTree:
    """A tree of fingerprints whose children hang at their Hamming distance."""

    def __init__(self) -> None:
        self.values: list[int] = []
        self.children: list[dict[int, int]] = []

    def near(self, value: int, radius: int) -> list[int]:
        """Values within the radius."""
        found, todo = [], [0] if self.values else []
        while todo:
            k = todo.pop()
            d = (self.values[k] ^ value).bit_count()
            if d <= radius:
                found.append(self.values[k])
            for edge, child in self.children[k].items():
                if d - radius <= edge <= d + radius:
                    todo.append(child)
        return found

    def near_then_add(self, value: int, radius: int) -> list[int]:
        """Values within the radius, then value itself goes in."""
        found = self.near(value, radius)
        if not self.values:
            self.values.append(value)
            self.children.append({})
            return found
        k = 0
        while True:
            d = (self.values[k] ^ value).bit_count()
            if d == 0:
                return found
            if d not in self.children[k]:
                self.children[k][d] = len(self.values)
                self.values.append(value)
                self.children.append({})
                return found
            k = self.children[k][d]


def block_masks(radius: int, extra: int = 4) -> list[int]:
    """Bit masks (signed) of every choice of `extra` agreeing blocks out of radius + extra."""
    n = radius + extra
    edges = [BITS * i // n for i in range(n + 1)]
    blocks = [((1 << (edges[i + 1] - edges[i])) - 1) << edges[i] for i in range(n)]
    masks = [sum(blocks[i] for i in choice) for choice in combinations(range(n), extra)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


#: Fingerprints of one BK-tree, about.
TREE = 1 << 14
PLACE = ["shard", "masked", "one", "two"]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _search(radius: int):
    """Reads (shard, masked, one, two, mine, fp) sorted by the first four; yields forest edges of each tile."""

    def links(group: np.ndarray, home: np.ndarray, forest: Forest, out: list[tuple[int, int]]) -> None:
        """home: whether a row belongs to the tile's first chunk; a tile of one chunk is all home."""
        values = [int(x) & (2**64 - 1) for x in group]
        tree = BKTree()
        for v, own in sorted(zip(values, home.tolist(), strict=True), key=lambda r: not r[1]):
            near = tree.near_then_add(v, radius) if own else tree.near(v, radius)
            out.extend((_signed(v), _signed(w)) for w in near if forest.union(_signed(v), _signed(w)))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = Forest()  # over all tiles of this task: an edge that joins nothing new is not sent
        rest = [np.zeros(0, np.int64)] * (len(PLACE) + 2)
        found: list[tuple[int, int]] = []

        def flush() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], names=["u", "v"])
            found.clear()
            return batch

        def work(parts: list[np.ndarray], last: bool) -> list[np.ndarray]:
            *place, mine, fp = parts
            if not len(fp):
                return parts
            new = np.flatnonzero(np.any([c[1:] != c[:-1] for c in place], axis=0)) + 1
            edges = np.concatenate(([0], new, [len(fp)]))
            done = len(edges) - (1 if last else 2)
            for a, b in zip(edges[:done].tolist(), edges[1 : done + 1].tolist(), strict=True):
                if b - a == 2:
                    # the two rows of a pair, in whichever chunks
                    u, v = int(fp[a]), int(fp[a + 1])
                    if ((u ^ v) & (2**64 - 1)).bit_count() <= radius and forest.union(u, v):
                        found.append((u, v))
                elif b - a > 1:
                    links(fp[a:b], mine[a:b] == place[2][a], forest, found)
            return [x[edges[done] :] for x in parts]

        for batch in batches:
            cols = [c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns]
            rest = work([np.concatenate(x) for x in zip(rest, cols, strict=True)], False)
            if len(found) > 10_000:
                yield flush()
        work(rest, True)
        yield flush()

    return run


def links(distinct_fps: DataFrame, radius: int = 2, tree: int = TREE) -> DataFrame:
    """distinct_fps(fp: long) -> forest edges (u, v) that join all fingerprints within the radius."""
    shards = distinct_fps.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m)) for m in block_masks(radius)])).alias("shard", "masked"))
    dealt = deal_tiles(shards, ["shard", "masked"], "fp", tree).select(*PLACE, "mine", "fp")
    return dealt.repartition(*PLACE).sortWithinPartitions(*PLACE, "fp").mapInArrow(_search(radius), "u long, v long")


@dataclass(frozen=True)
class Similarity:
    """least: Jaccard similarity of sets of `width` words; bands x rows: minwise values, one shard per band.

    At similarity 0.8 two texts share a shard with probability 1 - (1 - 0.8^3)^10 = 0.9992; those that do are compared exactly.
    """

    least: float = 0.8
    width: int = 5
    bands: int = 10
    rows: int = 3
    tile: int = 512
    tile_shingles: int = 1 << 21
    seed: int = 13


def _shingles(texts: pa.Array, spec: Similarity) -> tuple[np.ndarray, np.ndarray]:
    """Distinct 64-bit shingle hashes, sorted inside each text, and the n + 1 offsets of the texts."""
    raw, offsets = W.flat(texts)
    words = W.split(W.LOWER[raw], offsets)
    ids, distinct = words.encoded()
    body, edges = W.flat(distinct)
    place = np.arange(len(body)) - np.repeat(edges[:-1], np.diff(edges))
    total = np.zeros(len(body) + 1, np.uint64)
    np.cumsum(W.mixed(body.astype(np.uint64) + (place.astype(np.uint64) << np.uint64(8)) + np.uint64(1)), out=total[1:])
    value = W.mixed(total[edges[1:]] - total[edges[:-1]])[ids] if len(ids) else np.zeros(0, np.uint64)
    n_words = np.diff(words.first)
    shingles = np.where(n_words > 0, np.maximum(n_words - spec.width + 1, 1), 0)
    doc = np.repeat(np.arange(len(shingles)), shingles)
    starts = np.repeat(words.first[:-1], shingles) + np.arange(len(doc)) - np.repeat(np.cumsum(shingles) - shingles, shingles)
    last = np.repeat(words.first[1:], shingles)
    hashes = np.zeros(len(doc), np.uint64)
    for k in range(spec.width):
        at = starts + k
        here = np.where(at < last, value[np.minimum(at, max(len(value) - 1, 0))] if len(value) else 0, 0).astype(np.uint64)
        hashes = W.mixed(hashes * np.uint64(3) + here + np.uint64(k))
    order = np.lexsort((hashes, doc))
    hashes, doc = hashes[order], doc[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (hashes[1:] != hashes[:-1])
    hashes, doc = hashes[new], doc[new]
    return hashes, np.searchsorted(doc, np.arange(len(shingles) + 1))


def whole_sets(texts: pa.Array, spec: Similarity) -> list[pa.Array]:
    """Each text's set as sorted 64-bit hashes (binary)."""
    hashes, at = _shingles(texts, spec)
    return [pa.array([hashes[a:b].tobytes() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)], pa.binary())]


def shingle_sets(texts: pa.Array, spec: Similarity) -> list[pa.Array]:
    """fp, a second 64-bit name of the set, the set's size, and one key per band."""
    hashes, at = _shingles(texts, spec)
    sums = np.zeros(len(hashes) + 1, np.uint64)
    np.cumsum(W.mixed(hashes + np.uint64(7)), out=sums[1:])
    name = W.mixed(sums[at[1:]] - sums[at[:-1]] + np.diff(at).astype(np.uint64))
    full = np.flatnonzero(np.diff(at))
    keys = np.zeros((len(texts), spec.bands), np.uint64)
    odd = np.random.default_rng(spec.seed).integers(1, 2**63, spec.bands * spec.rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    for i, factor in enumerate(odd):
        if len(full):
            least = np.minimum.reduceat((hashes ^ (hashes >> np.uint64(29))) * factor, at[full])
            keys[full, i // spec.rows] = W.mixed(keys[full, i // spec.rows] * np.uint64(5) + least)
    key_lists = pa.FixedSizeListArray.from_arrays(pa.array(keys.view(np.int64).reshape(-1)), spec.bands).cast(pa.list_(pa.int64()))
    return [pa.array(majority(hashes, at).view(np.int64)), pa.array(name.view(np.int64)), pa.array(np.diff(at).astype(np.int64)), key_lists]


def _similar(a: np.ndarray, b: np.ndarray, least: float) -> bool:
    """Whether two sorted whole sets have at least this Jaccard similarity."""
    small, large = sorted((len(a), len(b)))
    # sets of too different sizes can't be similar enough
    if not small or small < least * large:
        return False
    both = np.concatenate((a, b))
    both.sort(kind="stable")  # merges the two runs
    shared = np.count_nonzero(both[1:] == both[:-1])
    return shared / (small + large - shared) >= least


def _edges(found: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], pa.int64()) for k in (0, 1)], names=["u", "v"])


def _meet_anchor(spec: Similarity):
    """Reads (anchor, chunk, uid, shingles) sorted so that the anchor's own row leads its chunk; yields its similar texts."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head, own = None, np.zeros(0, np.uint64)
        for batch in batches:
            found = []
            for anchor, _, uid, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if uid == anchor:
                    head, own = anchor, np.frombuffer(raw, np.uint64)
                elif head == anchor and _similar(own, np.frombuffer(raw, np.uint64), spec.least):
                    found.append((anchor, uid))
            yield _edges(found)

    return run


def _meet(spec: Similarity):
    """Reads (band, key, one, two, mine, uid, root, shingles) sorted by the first four; yields forest edges of similar texts.

    Texts of one root are linked already.
    """

    def tile(rows: list[tuple], forest: Forest, found: list[tuple[int, int]]) -> None:
        one, two = rows[0][2], rows[0][3]
        uids, roots = [r[5] for r in rows], [r[6] for r in rows]
        sets = [np.frombuffer(r[7], np.uint64) for r in rows]
        # members by what is linked so far: one link to a group spares the rest of it
        groups: dict[int, list[int]] = {}

        def meet(i: int) -> list[int]:
            """Takes out the groups that i is linked to and returns their members."""
            mine: list[int] = []
            for head, members in list(groups.items()):
                if forest.root(roots[i]) != forest.root(roots[members[0]]):
                    j = next((j for j in reversed(members) if _similar(sets[i], sets[j], spec.least)), None)
                    if j is None:
                        continue
                    forest.union(roots[i], roots[j])
                    found.append((uids[i], uids[j]))
                mine += groups.pop(head)
            return mine

        first = [i for i, r in enumerate(rows) if r[4] == one]
        if one == two:
            for i in first:
                groups[i] = [*meet(i), i]
            return
        by_root: dict[int, list[int]] = {}
        for i in first:
            by_root.setdefault(forest.root(roots[i]), []).append(i)
        groups.update({members[0]: members for members in by_root.values()})
        for i in (i for i, r in enumerate(rows) if r[4] == two):
            if mine := meet(i):
                groups[mine[0]] = mine

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest, found, rows = Forest(), [], []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if rows and rows[0][:4] != row[:4]:
                    if len(rows) > 1:
                        tile(rows, forest, found)
                    rows = []
                rows.append(row)
        if len(rows) > 1:
            tile(rows, forest, found)
        yield _edges(found)

    return run


def _groups(banded: DataFrame) -> DataFrame:
    """(band, key, anchor) of shards with two texts or more; of shards with the same texts one."""
    of = [F.count("*").alias("m"), F.bit_xor(F.xxhash64("uid")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "uid")).alias("y"), F.max("uid").alias("last"), F.min("uid").alias("anchor")]
    shards = banded.groupBy("band", "key").agg(*of).where("m > 1")
    once = shards.groupBy("m", "x", "y", "last", "anchor").agg(F.min(F.struct("band", "key")).alias("g"))
    return once.select("g.band", "g.key", "anchor")


def _anchored(members: DataFrame, whole: DataFrame, spec: Similarity) -> DataFrame:
    """members(band, key, anchor, uid) -> edges (anchor, uid) of texts similar to their anchor."""
    pairs = members.where("uid <> anchor").select("anchor", "uid").distinct()
    sizes = pairs.groupBy("anchor").agg(F.ceil(F.count("*") / spec.tile).cast("int").alias("chunks"))
    heads = sizes.select("anchor", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.col("anchor").alias("uid"))
    dealt = pairs.join(sizes, "anchor").select("anchor", F.pmod(F.xxhash64("uid"), F.col("chunks")).cast("int").alias("chunk"), "uid")
    full = heads.unionAll(dealt).join(whole, F.col("uid") == F.col("t")).select("anchor", "chunk", "uid", "shingles")
    lead = F.when(F.col("uid") == F.col("anchor"), 0).otherwise(1)
    return full.repartition("anchor", "chunk").sortWithinPartitions("anchor", "chunk", lead, "uid").mapInArrow(_meet_anchor(spec), "u long, v long")


def _tiled(members: DataFrame, spec: Similarity) -> DataFrame:
    """members(band, key, anchor, uid, root, n) of shards with several roots, dealt to tiles (band, key, one, two) with `mine`.

    Chunks of texts that the anchor's root does not hold meet all chunks; those of the anchor's own only the former.
    """
    shard = ["band", "key"]
    own = F.max(F.when(F.col("uid") == F.col("anchor"), F.col("root")))
    roots = members.groupBy(*shard).agg(own.alias("_own"), F.min("root").alias("_a"), F.max("root").alias("_b")).where("_a <> _b").select(*[F.col(c).alias(f"_{c}") for c in shard], "_own")
    mixed = members.join(roots, (F.col("band") == F.col("_band")) & (F.col("key") == F.col("_key"))).withColumn("linked", F.col("root") == F.col("_own"))
    mixed = store(mixed.select(*shard, "uid", "root", "n", "linked"))
    chunks = lambda which: F.ceil(F.greatest(F.count(F.when(which, 1)) / spec.tile, F.coalesce(F.sum(F.when(which, F.col("n"))), F.lit(0)) / spec.tile_shingles)).cast("int")
    sizes = mixed.groupBy(*shard).agg(chunks(F.col("linked")).alias("_left"), chunks(~F.col("linked")).alias("_right"))
    dealt = mixed.join(sizes, shard)
    spot = F.pmod(F.xxhash64("uid"), F.when(F.col("linked"), F.col("_left")).otherwise(F.col("_right"))).cast("int")
    dealt = dealt.withColumn("mine", F.when(F.col("linked"), F.col("_right") + spot).otherwise(spot))
    last = F.when(F.col("linked"), F.col("_right")).otherwise(F.col("_right") + F.col("_left")) - 1
    dealt = dealt.withColumn("_peer", F.explode(F.sequence(F.lit(0), last)))
    return dealt.select(*shard, F.least("mine", "_peer").alias("one"), F.greatest("mine", "_peer").alias("two"), "mine", "uid", "root")


def near_links(distinct: DataFrame, radius: int) -> DataFrame:
    """distinct(fp, uid) of distinct texts -> edges (u, v) over uid that join texts whose fingerprints lie within the radius, by the trees."""
    firsts = store(distinct.groupBy("fp").agg(F.min("uid").alias("_first")))
    equal = distinct.join(firsts, "fp").where("uid <> _first").select(F.col("_first").alias("u"), F.col("uid").alias("v"))
    end = lambda name: firsts.select(F.col("fp").alias(f"_{name}"), F.col("_first").alias(name))
    found = links(firsts.select("fp"), radius).select(F.col("u").alias("_p"), F.col("v").alias("_q"))
    return equal.unionByName(found.join(end("p"), "_p").join(end("q"), "_q").select(F.col("p").alias("u"), F.col("q").alias("v")))


def similar_links(sets: DataFrame, texts: DataFrame, spec: Similarity, linked: DataFrame | None = None) -> DataFrame:
    """sets(uid, n, bands) of distinct texts, texts(t, body) with t a uid, linked(u, v) that is known -> edges (u, v) over uid, with the linked ones."""
    spark = sets.sparkSession
    banded = sets.select("uid", "n", F.posexplode("bands").alias("band", "key"))
    groups = _groups(banded)
    members, members_at = store_at(banded.join(groups, ["band", "key"]).select("band", "key", "anchor", "uid", "n"))
    # sets are large: only of texts that meet another one
    met = members.select(F.col("uid").alias("_u")).distinct()
    whole = map_text(numbered(texts, "t", met, "_u"), "body", [T.StructField("shingles", T.BinaryType())], lambda t: whole_sets(t, spec), ["t"])
    whole, whole_at = store_at(whole)
    near = _anchored(members, whole, spec)
    near = store(near.unionByName(linked) if linked is not None else near)
    reached, reached_at = store_at(connected(near, contracted=True))
    rooted = members.join(reached, members["uid"] == reached["node"], "left").select("band", "key", "anchor", "uid", "n", F.coalesce("root", "uid").alias("root"))
    keys = ["band", "key", "one", "two"]
    full = _tiled(rooted, spec).join(whole, F.col("uid") == F.col("t")).select(*keys, "mine", "uid", "root", "shingles")
    rest = store(full.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(_meet(spec), "u long, v long"))
    for path in (members_at, whole_at, reached_at):
        forget(spark, path)
    return near.unionAll(rest)


def _named(docs: DataFrame, doc_id: str, text: str, width: int, radius: int, keep: list[str], similarity: Similarity | None = None) -> tuple[DataFrame, DataFrame, str, str]:
    """Stored prints (keep + fp + _set + id + row tag), and (_fp, _name, component_id, _root) for each distinct text."""
    ident = fresh([*docs.columns, "fp", "component_id"], "_id")
    tag = fresh([*docs.columns, ident], "_tag")
    marked = docs.withColumn(ident, F.col(f"`{doc_id}`").cast("long"))
    if similarity:
        added = [T.StructField("fp", T.LongType()), T.StructField("_set", T.LongType()), T.StructField("_n", T.LongType()), T.StructField("_bands", T.ArrayType(T.LongType()))]
        prints = map_text(marked, text, added, lambda t: shingle_sets(t, similarity), [*keep, *([] if text in keep else [text]), ident])
    else:
        prints = map_text(marked, text, [T.StructField("fp", T.LongType()), T.StructField("_set", T.LongType())], lambda t: [fingerprints(t, width), pa.array(np.zeros(len(t), np.int64))], [*keep, ident])
    prints = store(prints.withColumn(tag, F.monotonically_increasing_id()))
    distinct = prints.groupBy("fp", "_set").agg(F.min(ident).alias("least"), F.min(tag).alias("uid"))
    if similarity:
        distinct = store(distinct)
        bodies = prints.select(F.col(tag).alias("_t"), F.col("_n").alias("n"), F.col("_bands").alias("bands"))
        # texts without words are copies of each other and similar to nothing else
        sets, sets_at = store_at(distinct.join(bodies, distinct["uid"] == bodies["_t"]).where("n > 0").select("uid", "n", "bands"))
        trees, trees_at = store_at(near_links(distinct.select("fp", "uid"), radius))
        edges = similar_links(sets, prints.select(F.col(tag).alias("t"), F.col(text).alias("body")), similarity, trees)
    else:
        distinct = store(distinct.withColumn("uid", F.col("fp")))
        edges = links(distinct.select("fp"), radius)
    reached = store(connected(edges, contracted=similarity is None))
    if similarity:
        for path in (sets_at, trees_at):
            forget(docs.sparkSession, path)
    # smallest doc_id of each component, over its distinct texts only
    rooted = distinct.join(reached, distinct["uid"] == reached["node"], "left").select("fp", "_set", "least", F.coalesce("root", "uid").alias("root"))
    rooted = store(rooted)
    least = store(rooted.groupBy("root").agg(F.min("least").alias("component_id")))
    return prints, store(rooted.join(least, "root").select(F.col("fp").alias("_fp"), F.col("_set").alias("_name"), "component_id", F.col("root").alias("_root"))), ident, tag


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3, radius: int = 2, keep: list[str] | None = None, similarity: Similarity | None = None) -> DataFrame:
    """keep columns (default: all of docs) + fp (long), component_id (long); columns of docs so named are replaced.

    Links by distance (width, radius), and by similarity too where that is given; then fingerprints are made of its shingles.
    """
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("fp", "component_id")]
    clean = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns)])
    at = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    prints, named, _, _ = _named(clean, at[doc_id], at[text], width, radius, [at[c] for c in keep], similarity)
    joined = prints.join(named, (prints["fp"] == named["_fp"]) & (prints["_set"] == named["_name"]))
    return joined.select(*[prints[at[c]].alias(c) for c in keep], "fp", "component_id")


def one_per_group(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3, radius: int = 2, similarity: Similarity | None = None) -> DataFrame:
    """docs with one row of each component: that of its smallest doc_id, one of them if several rows have that id.

    A component whose rows all have a null doc_id keeps one of them.
    """
    columns = docs.columns
    clean = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(columns)])
    at = {c: f"c{i}" for i, c in enumerate(columns)}
    prints, named, ident, tag = _named(clean, at[doc_id], at[text], width, radius, clean.columns, similarity)
    slim = prints.select("fp", "_set", ident, F.col(tag).alias("_t"))
    firsts = slim.join(named, (slim["fp"] == named["_fp"]) & (slim["_set"] == named["_name"]) & slim[ident].eqNullSafe(named["component_id"]))
    chosen = store(firsts.groupBy("_root").agg(F.min("_t").alias("_first")).select("_first"))
    return numbered(prints, tag, chosen, "_first").select(*[F.col(at[c]).alias(c) for c in columns])


def as_hex(fp):
    """A long as 16 lowercase hex digits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
