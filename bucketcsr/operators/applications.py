"""Sparse products, triangles, k-mers and cells on top of bucket indexes."""

from __future__ import annotations

from contextlib import contextmanager
from math import isqrt

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import bucket_of
from ..plans.params import MOST_PARTS, BuildSpec
from .build import build_binned
from .probe import BROADCAST_BYTES, PLACE, build_pair, cobucket_count


def spmv(matrix: DataFrame, vector: DataFrame, spec: BuildSpec = BuildSpec()) -> DataFrame:
    """matrix(row, col, val) times vector(idx, x) -> (row, y); entries of equal place add up."""
    m, v = build_pair(matrix, vector, "col", "idx", spec=spec, payload_a=["row", "val"], payload_b=["x"])
    met = m.edges.select(*PLACE, "key", "row", "val").join(v.edges.select(*PLACE, "key", "x"), [*PLACE, "key"])
    return met.groupBy("row").agg(F.sum(F.col("val") * F.col("x")).alias("y"))


#: Products that one block of result rows holds, about, and edges of one block of a triangle count.
BLOCK_PRODUCTS, BLOCK_EDGES = 1 << 22, 1 << 20
#: Entries of lists that one round of a triangle count may send at least, and the fewest slots that its nodes are counted in.
ROUND_ENTRIES, LEAST_SLOTS = 1 << 24, 1 << 17
#: Blocks of a group at most: each task of it holds the lists of all of them.
MOST_GROUPED = 8


def _kept(df: DataFrame) -> tuple[DataFrame, str]:
    """df written to the shared folder and read back, with its path."""
    from ..sources.storage import shared_folder

    folder = shared_folder(df.sparkSession, "entries")
    df.write.option("compression", "zstd").parquet(folder)
    return df.sparkSession.read.schema(df.schema).parquet(folder), folder


@contextmanager
def _short_lived_shuffles(spark):
    """Shuffle files of the queries inside are deleted when each ends, not when the driver next collects garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def _blocks(entries: DataFrame, row: str, blocks: int) -> DataFrame:
    """(_row, block): each value of `row` with its block of 0 .. blocks - 1, ranges of about as many entries each (by a hash where values are no whole numbers).

    Neighbouring values share a block, so a list that neighbours ask for goes to few blocks.
    """
    values = entries.select(F.col(row).alias("_row")).distinct()
    if blocks > 1 and entries.schema[row].dataType.typeName() in ("byte", "short", "integer", "long"):
        ends = entries.agg(F.percentile_approx(row, [i / blocks for i in range(1, blocks)], 10 * blocks)).first()[0] or []
        ends = F.array(*[F.lit(e).cast("bigint") for e in sorted(set(ends))]).cast("array<bigint>")
        block = F.when(F.col("_row").isNull(), 0).otherwise(F.size(F.filter(ends, lambda e: e < F.col("_row").cast("bigint"))))
    else:
        block = F.pmod(F.xxhash64("_row"), F.lit(blocks))
    return values.select("_row", block.cast("int").alias("block"))


def _with_block(edges: DataFrame, row: str, table: DataFrame, known: int) -> DataFrame:
    """edges + block; the table of `known` values is sent to every executor if it is small."""
    side = F.broadcast(table) if known * 24 <= BROADCAST_BYTES else table
    return edges.join(side, edges[row].eqNullSafe(side["_row"])).drop("_row")


def spgemm(a: DataFrame, b: DataFrame | None = None, spec: BuildSpec = BuildSpec(), block_products: int = BLOCK_PRODUCTS) -> DataFrame:
    """a(row, col, val) times b(row, col, val) -> (row, col, val); both are indexed once by the inner dimension. Without b: a times its transpose, by one index.

    Rows of the result are cut into blocks. A list of b goes once, whole, to every block whose rows of a ask for it, and is multiplied and added up there:
    lists move, products don't.
    """
    # inputs are read several times, the results of queries among them
    a = _kept(a.select("row", "col", "val"))[0]
    if b is None:
        ia = build_binned(a, "col", None, spec, ["row", "val"])
        ib, turned, n_products = ia, "row", a.where("col is not null").groupBy("col").agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0] or 0
    else:
        b = _kept(b.select("row", "col", "val"))[0]
        ia, ib = build_pair(a, b, "col", "row", spec=spec, payload_a=["row", "val"], payload_b=["col", "val"])
        turned, n_products = "col", cobucket_count(a, b, "col", "row").first()[0]
    blocks = max(1, min(-(-n_products // block_products), MOST_PARTS))
    rows = _kept(_blocks(a, "row", blocks))[0]
    left = _with_block(ia.edges, "row", rows, rows.count()).select(*PLACE, "key", "block", "row", "val")
    asked = left.select(*PLACE, "key", "block").distinct()
    right = ib.edges.select(*PLACE, "key", F.col(turned).alias("col"), F.col("val").alias("_w")).join(asked, [*PLACE, "key"])
    own, sent = (df.repartitionById(blocks, F.col("block")) for df in (left.select("block", "key", "row", "val"), right.select("block", "key", "col", "_w")))
    met = own.join(sent.hint("merge"), ["block", "key"])
    if b is None:
        met = met.where("col IS NULL OR row <= col")
    summed = met.groupBy("block", "row", "col").agg(F.sum(F.col("val") * F.col("_w")).alias("val")).select("row", "col", "val")
    if b is not None:
        return summed
    # the product is symmetric: one half is made, the other is its mirror
    places = lambda *pairs: F.array(*[F.struct(F.col(x).alias("row"), F.col(y).alias("col")) for x, y in pairs])
    both = F.when(F.col("row").eqNullSafe(F.col("col")), places(("row", "col"))).otherwise(places(("row", "col"), ("col", "row")))
    return summed.select(F.explode(both).alias("_at"), "val").select("_at.row", "_at.col", "val")


def _hubs(plain: DataFrame, n_pairs: int) -> DataFrame | None:
    """(n, deg): the nodes of plain(s, d) with so many pairs that at most a quarter as many as there are slots can have them (None: there are none).

    Pairs are counted by a hash of the node first; only nodes of slots over the limit are counted one by one.
    """
    slots = max(LEAST_SLOTS, 1 << (4 * isqrt(2 * n_pairs)).bit_length())
    limit = max(1, 8 * n_pairs // slots)
    ends = plain.select(F.explode(F.array("s", "d")).alias("n")).withColumn("_slot", F.pmod(F.xxhash64("n"), F.lit(slots)))
    full = [(r["_slot"],) for r in ends.groupBy("_slot").agg(F.count("*").alias("m")).where(F.col("m") > limit).collect()]  # at most slots / 4
    if not full:
        return None
    inside = ends.join(F.broadcast(plain.sparkSession.createDataFrame(full, "_slot bigint")), "_slot")
    return _kept(inside.groupBy("n").agg(F.count("*").alias("deg")).where(F.col("deg") > limit))[0]


def _oriented(plain: DataFrame, hubs: DataFrame | None) -> DataFrame:
    """(u, w): each pair from its end of lower (degree, id) to the other, where all but the hubs count as of degree 0."""
    if hubs is None:
        return plain.select(F.col("s").alias("u"), F.col("d").alias("w"))
    side = lambda n, deg: F.broadcast(hubs.select(F.col("n").alias(n), F.col("deg").alias(deg)))
    ranked = plain.join(side("s", "ps"), "s", "left").join(side("d", "pd"), "d", "left")
    ps, pd = F.coalesce("ps", F.lit(0)), F.coalesce("pd", F.lit(0))
    first = (ps < pd) | ((ps == pd) & (F.col("s") < F.col("d")))
    return ranked.select(F.when(first, F.col("s")).otherwise(F.col("d")).alias("u"), F.when(first, F.col("d")).otherwise(F.col("s")).alias("w"))


def _narrow(plain: DataFrame) -> DataFrame:
    """plain(s, d) counted from the smallest node, as int, if its nodes are whole numbers of such a range."""
    if any(f.dataType.typeName() not in ("byte", "short", "integer", "long") for f in plain.schema):
        return plain
    low, high = plain.agg(F.min("s"), F.max("d")).first()
    if low is None or high - low >= 1 << 31:
        return plain
    return plain.select(*[(F.col(c).cast("bigint") - F.lit(low).cast("bigint")).cast("int").alias(c) for c in plain.columns])


def _rounds(sent: dict[int, int], most: int) -> list[tuple[int, int]]:
    """First and last of the groups in runs that are sent `most` entries together, or of one group alone."""
    runs: list[tuple[int, int]] = []
    load = 0
    for group, n in sorted(sent.items()):
        if runs and load + n <= most:
            runs[-1], load = (runs[-1][0], group), load + n
        else:
            runs.append((group, group))
            load = n
    return runs


def count_triangles(edges: DataFrame, spec: BuildSpec = BuildSpec(), block_edges: int = BLOCK_EDGES, round_entries: int = ROUND_ENTRIES) -> DataFrame:
    """edges(src, dst) undirected -> one row n_triangles.

    Each edge points from its end of lower (degree, id) to the other, so a hub's long list is never paired with itself; nodes that are no hubs go by id alone.
    Sources are cut into blocks, ranges of about as many edges each. A list of out-neighbours goes once, whole, to every block with an edge to its owner, and meets
    the lists of that block's sources there. No wedge moves. Where most blocks ask for most lists, blocks form groups that are sent a list once, and the owners
    are dealt over the tasks of a group. Groups that would be sent over round_entries (or four times all edges) together are counted one round after another.
    """
    from ..sources.storage import forget

    spark = edges.sparkSession
    with _short_lived_shuffles(spark):
        plain, plain_at = _kept(edges.where("src <> dst").select(F.least("src", "dst").alias("s"), F.greatest("src", "dst").alias("d")))
        n_pairs = plain.count()
        plain = _narrow(plain)
        out = _oriented(plain, _hubs(plain, n_pairs))
        blocks = max(1, min(-(-n_pairs // block_edges), MOST_PARTS))
        # one partition of the exchange is one block; a pair that stands in several rows is one entry of its list
        lists, _ = _kept(out.repartitionByRange(blocks, "u").groupBy("u").agg(F.sort_array(F.collect_set("w")).alias("ws")).select(F.spark_partition_id().alias("block"), "u", "ws"))
        forget(spark, plain_at)
        sizes = lists.select("block", F.col("u").alias("w"), F.size("ws").alias("n"))
        own = {r["block"]: r["n"] for r in sizes.groupBy("block").agg(F.sum("n").alias("n")).collect()}  # at most one row per block, so below
        blocks = max(own, default=0) + 1
        n_edges, most = sum(own.values()), min(isqrt(blocks), MOST_GROUPED)
        asked, asked_at = _kept(lists.select(F.col("block").alias("grp"), F.explode("ws").alias("w")).distinct())
        far, size = _asked_entries(asked, sizes), 1
        if most > 1 and sum(far.values()) > (most - 1) * n_edges:
            by_group, _ = _kept(asked.select(F.floor(F.col("grp") / most).cast("int").alias("grp"), "w").distinct())
            forget(spark, asked_at)
            asked, far, size = by_group, _asked_entries(by_group, sizes), most
        sent = dict(far)
        for block, n in own.items():
            sent[block // size] = sent.get(block // size, 0) + n * size
        runs = _rounds(sent, max(round_entries, 4 * n_edges))
        if len(runs) > 1:
            total = 0
            for first, last in runs:
                near = lists.where(F.col("block").between(first * size, last * size + size - 1))
                total += _triangles_of(near, lists, asked.where(F.col("grp").between(first, last)), size, last - first + 1, first, spec).first()[0]
            return spark.createDataFrame([(total,)], "n_triangles bigint")
    return _triangles_of(lists, lists, asked, size, -(-blocks // size), 0, spec)


def _asked_entries(asked: DataFrame, sizes: DataFrame) -> dict[int, int]:
    """Entries of the lists that each group of asked(grp, w) is sent; sizes(w, n)."""
    return {r["grp"]: r["n"] for r in asked.join(sizes.select("w", "n"), "w").groupBy("grp").agg(F.sum("n").alias("n")).collect()}


def _triangles_of(near: DataFrame, lists: DataFrame, asked: DataFrame, size: int, groups: int, first: int, spec: BuildSpec) -> DataFrame:
    """One row n_triangles: those whose lowest corner owns a list of near(block, u, ws); lists(u, ws) go to the groups of `size` blocks that ask(grp, w) for them.

    A group's near lists are sent to all of its `size` tasks, each of which has a share of the owners of far lists.
    """
    far, into = build_pair(lists, asked, "u", "w", spec=spec, payload_a=["ws"], payload_b=["grp"])
    task = lambda grp, share: ((F.col(grp) - first) * size + share).cast("int").alias("task")
    share = F.pmod(F.xxhash64("key"), F.lit(size))
    met = far.edges.select(*PLACE, "key", F.col("ws").alias("_far")).join(into.edges.select(*PLACE, "key", "grp"), [*PLACE, "key"])
    tasks = max(2, groups * size)  # one partition would be dealt anew for each join
    copies = near.select(F.floor(F.col("block") / size).alias("grp"), F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("share"), "u", F.col("ws").alias("_near"))
    own, sent = (df.repartitionById(tasks, F.col("task")) for df in (copies.select(task("grp", F.col("share")), "u", "_near"), met.select(task("grp", share), "key", "_far")))
    edge = own.select("task", "u", F.explode("_near").alias("key")).withColumn("key", F.col("key").cast(met.schema["key"].dataType))
    edge = edge.where(share == F.pmod("task", F.lit(size))) if size > 1 else edge
    pairs = edge.join(sent.hint("merge"), ["task", "key"]).join(own.hint("shuffle_hash"), ["task", "u"])
    return pairs.agg(F.coalesce(F.sum(F.size(F.array_intersect("_near", "_far"))), F.lit(0)).cast("bigint").alias("n_triangles"))


def kmers(docs: DataFrame, doc_id: str, text: str, k: int = 12, block: int = 512) -> DataFrame:
    """(doc_id, pos, kmer): every run of k characters; shorter texts have none.

    Texts are cut into overlapping blocks first, since reaching a character costs as much as skipping those before it.
    """
    last = F.floor((F.length(text) - k) / block).cast("int")
    blocks = F.transform(F.sequence(F.lit(0), last), lambda b: F.struct((b * block).alias("at"), F.substring(F.col(text), b * block + 1, F.lit(block + k - 1)).alias("body")))
    cut = docs.where(F.length(text) >= k).select(F.col(doc_id).alias("doc_id"), F.explode(blocks).alias("b")).select("doc_id", "b.at", "b.body")
    every = F.transform(F.sequence(F.lit(0), F.length("body") - k), lambda i: F.struct((F.col("at") + i).alias("pos"), F.substring(F.col("body"), i + 1, F.lit(k)).alias("kmer")))
    return cut.select("doc_id", F.explode(every).alias("w")).select("doc_id", "w.pos", "w.kmer")


def kmer_lookup(docs: DataFrame, items: DataFrame, doc_id: str, item_id: str, text: str = "text", k: int = 12, spec: BuildSpec = BuildSpec(), broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """(doc_id, item_id, shared): distinct k-mers of an item that a document holds.

    The items' k-mers are indexed; documents' k-mers are looked up as they are cut, before anything is grouped.
    """
    right = kmers(items.withColumnRenamed(item_id, "_item"), "_item", text, k).select(F.col("doc_id").alias("item_id"), "kmer").distinct()
    index = build_binned(right, "kmer", None, spec, ["item_id"])
    built = index.edges.select(F.col("bucket").alias("_b"), F.col("key").alias("_k"), "item_id")
    if index.layout.n * (spec.row_bytes + k) <= broadcast_bytes:
        built = F.broadcast(built)
    left = kmers(docs, doc_id, text, k).select("doc_id", "kmer").withColumn("bucket", bucket_of([F.col("kmer")], index.layout.v, spec.hash))
    met = left.join(built, (F.col("bucket") == F.col("_b")) & (F.col("kmer") == F.col("_k")))
    return met.select("doc_id", "item_id", "kmer").distinct().groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))


def cells(vectors: DataFrame, width: float, dims: int = 3, embedding: str = "embedding") -> DataFrame:
    """vectors + cell: an array of the first `dims` components' grid numbers."""
    return vectors.withColumn("cell", F.transform(F.slice(embedding, 1, dims), lambda x: F.floor(x.cast("double") / F.lit(width)).cast("bigint")))


def cells_shared(a: DataFrame, b: DataFrame, spec: BuildSpec = BuildSpec()) -> DataFrame:
    """Cells that hold rows of both sides."""
    ia, ib = build_pair(a, b, "cell", "cell", spec=spec)
    keys = [*PLACE, "key"]
    return ia.edges.select(*keys).distinct().join(ib.edges.select(*keys).distinct(), keys, "left_semi").select(F.col("key").alias("cell"))
