"""Deletions by a second length, and insertions as delta indexes."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window, functions as F

from .build import CsrIndex, bins_table, build_binned, count_bins, finish_bins, reorganise
from .probe import lookup_probe


@dataclass(frozen=True)
class LiveIndex:
    """A base index with tombstones (rid) and delta indexes of the same bucket range."""

    base: CsrIndex
    deltas: tuple[CsrIndex, ...] = ()
    dead: DataFrame | None = None

    def edges(self) -> DataFrame:
        """Live rows of base and deltas; positions hold inside each of them."""
        cols = self.base.edges.columns
        rows = self.base.edges
        for d in self.deltas:
            rows = rows.unionByName(d.edges.select(*cols))
        return rows if self.dead is None else rows.join(self.dead, "rid", "left_anti").select(*cols)

    def offsets(self) -> DataFrame:
        """The base's offsets with live_len: rows of the slice that are still alive."""
        if self.dead is None:
            return self.base.offsets.withColumn("live_len", F.col("len"))
        gone = self.base.edges.join(self.dead, "rid", "left_semi").groupBy("bucket").agg(F.count("*").alias("gone"))
        return self.base.offsets.join(gone, "bucket", "left").withColumn("live_len", F.col("len") - F.coalesce("gone", F.lit(0))).drop("gone")

    def live_front(self) -> DataFrame:
        """Edges of the base with `live`, in each slice the live rows in front: a probe reads the first live_len of them and needs no marker."""
        edges = self.base.edges
        if self.dead is None:
            return edges.withColumn("live", F.lit(True))
        marked = edges.join(self.dead.withColumn("_gone", F.lit(True)), "rid", "left").withColumn("live", F.col("_gone").isNull())
        starts = self.base.offsets.select("part", "bin", "bucket", "start")
        rank = F.row_number().over(Window.partitionBy("part", "bin", "bucket").orderBy(F.desc("live"), "pos")) - 1
        return marked.join(starts, ["part", "bin", "bucket"]).withColumn("pos", F.col("start") + rank).select(*edges.columns, "live")

    def delete(self, rids: DataFrame) -> LiveIndex:
        """rids(rid): rows to take out; repeated and unknown ones do no harm."""
        more = rids.select(F.col("rid").cast("bigint")).distinct()
        return replace(self, dead=more if self.dead is None else self.dead.unionAll(more).distinct())

    def append(self, batch: DataFrame, key: str, rid: str) -> LiveIndex:
        delta = build_binned(batch, key, rid, self.base.spec, layout=self.base.layout)
        return replace(self, deltas=(*self.deltas, delta))

    def probe(self, probe: DataFrame, key: str, rid: str, mode: str = "all") -> DataFrame:
        live = replace(self.base, edges=self.edges())
        return lookup_probe(live, probe, key, rid, mode)

    def compact(self) -> CsrIndex:
        """One index of the live rows in the same bucket range; only bins with a change are sorted anew, the others shift."""
        layout, spec, spark = self.base.layout, self.base.spec, self.base.edges.sparkSession
        touched = {b for d in self.deltas for b in count_bins(d.edges)}
        if self.dead is not None:
            touched |= set(count_bins(self.base.edges.join(self.dead, "rid", "left_semi")))
        rows = self.edges()
        counts = count_bins(rows)
        bins = bins_table(spark, counts, replace(layout, n=sum(counts.values())))
        own = [c for c in rows.columns if c not in ("part", "pos")]
        dirty = F.col("bin").isin(sorted(touched)) if touched else F.lit(False)
        new, _ = finish_bins(reorganise(rows.where(dirty).select(*own), bins, layout.parts))
        shift = self.base.bins.select("bin", F.col("bin_start").alias("_old")).join(bins.select("bin", F.col("part").alias("_part"), F.col("bin_start").alias("_new")), "bin")
        kept = self.base.edges.where(~dirty).join(F.broadcast(shift), "bin")
        kept = kept.withColumn("pos", F.col("pos") - F.col("_old") + F.col("_new")).withColumn("part", F.col("_part")).select(*new.columns)
        edges = new.unionByName(kept)
        offsets = edges.groupBy("part", "bin", "bucket").agg(F.min("pos").alias("start"), F.count("*").alias("len"))
        return CsrIndex(edges, offsets, bins, replace(layout, n=sum(counts.values())), spec)
