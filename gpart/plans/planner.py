"""Choices that depend on sizes: partitions, salts, sides to broadcast, deltas or a rebuild. Each is a small function of counts, so
that a plan is the same wherever the counts are."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.operators.gains import GainTable
from gpart.sources.graphs import Graph

TARGET_BYTES = 256 << 20
EDGE_BYTES = 24


def partitions_for(rows: int, row_bytes: int = EDGE_BYTES, target: int = TARGET_BYTES, least: int = 8) -> int:
    """Shuffle partitions of about `target` bytes each."""
    return max(least, -(-rows * row_bytes // target))


def salts_for(max_degree: int, edges: int, partitions: int) -> int:
    """Salts for heavy vertices: so many that no salted part of one exceeds an even partition; a power of two."""
    even = max(1, edges // max(1, partitions))
    salts = 1
    while max_degree > salts * even:
        salts *= 2
    return salts


def small_enough(df: DataFrame, most_rows: int) -> bool:
    """Whether df has at most so many rows, without counting further than that."""
    return df.limit(most_rows + 1).count() <= most_rows


def joined_with_labels(edges: DataFrame, labels: DataFrame, most_broadcast: int = 4_000_000) -> DataFrame:
    """Edges with the cluster of their far end: labels are broadcast if they are few, else both sides are dealt by the vertex."""
    side = labels.select(F.col("id").alias("dst"), "cluster")
    return edges.join(F.broadcast(side) if small_enough(labels, most_broadcast) else side, "dst")


def touched_edges(graph: Graph, moves: DataFrame) -> int:
    return graph.edges.join(moves.select(F.col("id").alias("src")), "src", "left_semi").count()


def updated(table: GainTable, moves: DataFrame, rebuild_share: float = 0.3) -> GainTable:
    """The table after moves: by deltas, or built anew if movers touch more than a share of all edges. Both have the same gains."""
    if touched_edges(table.graph, moves) > rebuild_share * table.graph.edges.count():
        after = table.partition.join(moves.select("id", "to_block"), "id", "left").select("id", F.coalesce("to_block", "block").alias("block"))
        return GainTable(table.graph, after, table.k, table.variant)
    return table.apply(moves)
