"""Affinities and gains of vertices to blocks, and gain tables: none, full, and hybrid."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.functions.columns import entry_width, next_power_of_two
from gpart.operators.probe import ProbeTable
from gpart.sources.graphs import Graph


def affinity(edges: DataFrame, partition: DataFrame) -> DataFrame:
    """(id, block, affinity): the weight of a vertex's edges into each block, where it is not 0."""
    far = edges.join(partition.select(F.col("id").alias("dst"), "block"), "dst")
    return far.groupBy(F.col("src").alias("id"), "block").agg(F.sum("w").alias("affinity"))


def gains(affinities: DataFrame, partition: DataFrame) -> DataFrame:
    """(id, block, gain) of moving to each adjacent other block: its affinity less the own block's, which is 0 where there is none."""
    own = partition.withColumnRenamed("block", "own").join(affinities.withColumnRenamed("block", "own").withColumnRenamed("affinity", "kept"), ["id", "own"], "left").select("id", "own", F.coalesce("kept", F.lit(0)).alias("kept"))
    return affinities.join(own, "id").where("block <> own").select("id", "block", (F.col("affinity") - F.col("kept")).alias("gain"))


def incident_weights(graph: Graph) -> DataFrame:
    """(id, degree, u): number and weight of the edges of every vertex."""
    found = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"), F.sum("w").alias("u"))
    return graph.vertices.join(found, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"), F.coalesce("u", F.lit(0)).alias("u"))


def capacity(degree):
    """Slots of a small hash table for so many entries: the next power of two from 1.5 times as many."""
    return next_power_of_two(F.ceil(degree * 1.5))


__all__ = ["affinity", "gains", "incident_weights", "capacity", "GainTable", "gain_table_bytes", "ProbeTable"]


class GainTable:
    """Affinities under a partition, held in one of three forms; all answer alike.

    none: recomputed at every look. full: a dense row of k for every vertex. hybrid: a dense row if a vertex has more than k edges,
    else a map of what is not 0. Rows are (id, kind, width, row, map).
    """

    def __init__(self, graph: Graph, partition: DataFrame, k: int, variant: str = "hybrid"):
        if variant not in ("none", "full", "hybrid"):
            raise ValueError(variant)
        self.graph, self.partition, self.k, self.variant = graph, partition, k, variant
        self.rows = None if variant == "none" else self._rows(affinity(graph.edges, partition))

    def _rows(self, affinities: DataFrame) -> DataFrame:
        maps = affinities.groupBy("id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct(F.col("block").cast("int"), "affinity")))).alias("m"))  # at most k entries each
        every = incident_weights(self.graph).join(maps, "id", "left")
        entries = F.coalesce("m", F.create_map().cast("map<int,bigint>"))
        dense = F.lit(self.variant == "full") | (F.col("degree") > self.k)
        row = F.transform(F.sequence(F.lit(0), F.lit(self.k - 1)), lambda b: F.coalesce(F.try_element_at(entries, b), F.lit(0)))
        return every.select("id", F.when(dense, "dense").otherwise("hash").alias("kind"), entry_width(F.col("u")).alias("width"), F.when(dense, row).alias("row"), F.when(~dense, entries).alias("map"))

    def affinities(self) -> DataFrame:
        """(id, block, affinity) of what is not 0."""
        if self.variant == "none":
            return affinity(self.graph.edges, self.partition)
        dense = self.rows.where("kind = 'dense'").select("id", F.posexplode("row").alias("block", "affinity"))
        sparse = self.rows.where("kind = 'hash'").select("id", F.explode("map").alias("block", "affinity"))
        return dense.unionAll(sparse).where("affinity <> 0")

    def gains(self) -> DataFrame:
        return gains(self.affinities(), self.partition)

    def deltas(self, moves: DataFrame) -> DataFrame:
        """(id, block, delta) of moves (id, from_block, to_block): each neighbour loses the edge's weight at the one and gains it at the other."""
        near = moves.join(self.graph.edges.withColumnRenamed("src", "mover"), moves["id"] == F.col("mover")).select("dst", "w", "from_block", "to_block")
        both = near.select(F.col("dst").alias("id"), F.col("from_block").alias("block"), (-F.col("w")).alias("delta")).unionAll(near.select("dst", "to_block", "w"))
        return both.groupBy("id", "block").agg(F.sum("delta").alias("delta")).where("delta <> 0")

    def apply(self, moves: DataFrame) -> GainTable:
        """The table after the moves, by deltas; entries that become 0 are gone."""
        after = self.partition.join(moves.select("id", "to_block"), "id", "left").select("id", F.coalesce("to_block", "block").alias("block"))
        out = GainTable.__new__(GainTable)
        out.graph, out.partition, out.k, out.variant, out.rows = self.graph, after, self.k, self.variant, None
        if self.variant != "none":
            merged = self.affinities().join(self.deltas(moves), ["id", "block"], "full_outer")
            out.rows = out._rows(merged.select("id", "block", (F.coalesce("affinity", F.lit(0)) + F.coalesce("delta", F.lit(0))).alias("affinity")).where("affinity <> 0"))
        return out


def gain_table_bytes(graph: Graph, k: int) -> DataFrame:
    """Bytes of the three variants, in one row: dense 8-byte rows; or rows of k entries or small tables, of each vertex's own width,
    with 4-byte keys in tables and an 8-byte pointer for each vertex. entries: the sum of min(degree, k)."""
    rows = incident_weights(graph)
    width = entry_width(F.col("u")) / 8
    slots = F.when(F.col("degree") > k, F.lit(k)).otherwise(capacity(F.col("degree")))
    size = F.when(F.col("degree") > k, k * width).otherwise(slots * (width + 4)) + 8
    return rows.agg(F.count("*").alias("n"), F.lit(0).cast("long").alias("none_bytes"), (F.count("*") * 8 * k).alias("full_bytes"), F.sum(size).cast("long").alias("hybrid_bytes"), F.sum(F.least("degree", F.lit(k))).alias("entries"))
