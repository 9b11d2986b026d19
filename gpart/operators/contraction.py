"""Contraction of clusters: coarse edges are sums over inter-cluster edges, coarse vertices weigh what their clusters weigh."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gpart.functions.columns import scramble
from gpart.session import cut
from gpart.sources.graphs import Graph, members_of, number


@dataclass
class Level:
    """A graph of the hierarchy and the map from the next finer one's vertices: parents (id, coarse)."""

    graph: Graph
    parents: DataFrame | None
    n: int
    m: int


def as_is(df: DataFrame) -> DataFrame:
    return df


def between_clusters(edges: DataFrame, labels: DataFrame, one: Callable[[DataFrame], DataFrame] = as_is) -> DataFrame:
    """Edges between clusters: (a, b, w), not yet summed. one: puts what a join gives in one partition, where all tables have one."""
    a, b = (labels.select(F.col("id").alias(s), F.col("cluster").alias(t)) for s, t in (("src", "a"), ("dst", "b")))
    return one(one(edges.join(a, "src")).join(b, "dst").where("a <> b").select("a", "b", "w"))


def coarse_edges(edges: DataFrame, labels: DataFrame, one: Callable[[DataFrame], DataFrame] = as_is) -> DataFrame:
    return between_clusters(edges, labels, one).groupBy("a", "b").agg(F.sum("w").alias("w"))


def coarse_edges_of(graph: Graph, labels: DataFrame) -> DataFrame:
    """coarse_edges of a graph; of one kept as groups, by the clusters' members in each group: no pair of members is made."""
    if graph.groups is None:
        return coarse_edges(graph.edges, graph.held(labels), graph.gathered)
    held = cut(graph.groups.by_block(labels, "cluster").withColumnRenamed("s", "n"))
    a, b = (held.select("grp", F.col("cluster").alias(c), F.col("n").alias(f"n{c}")) for c in "ab")
    return a.join(b, "grp").where("a <> b").groupBy("a", "b").agg(F.sum(F.col("na") * F.col("nb")).alias("w"))


def coarse_vertices(vertices: DataFrame, labels: DataFrame) -> DataFrame:
    return vertices.join(labels, "id").groupBy("cluster").agg(F.sum("w").alias("w"))


def contract(graph: Graph, labels: DataFrame) -> tuple[Graph, DataFrame]:
    """The coarse graph with ids by rank of the cluster, and parents (id, coarse)."""
    clusters = number(coarse_vertices(graph.vertices, labels), ["cluster"], "coarse")
    return _renamed(clusters, coarse_edges_of(graph, labels), labels)


def _renamed(clusters: DataFrame, edges: DataFrame, labels: DataFrame, one: Callable[[DataFrame], DataFrame] = as_is) -> tuple[Graph, DataFrame]:
    a, b = (clusters.select(F.col("cluster").alias(s), F.col("coarse").alias(t)) for s, t in (("a", "src"), ("b", "dst")))
    renamed = one(edges.join(a, "a")).join(b, "b").select("src", "dst", "w")
    return Graph(clusters.select(F.col("coarse").alias("id"), "w"), renamed), labels.join(clusters.select("cluster", "coarse"), "cluster").select("id", "coarse")


def contract_groups(graph: Graph, labels: DataFrame) -> tuple[Graph, DataFrame]:
    """Of a graph kept as groups, the coarse graph in the same form, with ids by rank: a cluster stands in a group for its members there, and
    no coarse edge is made either."""
    clusters = number(coarse_vertices(graph.vertices, labels), ["cluster"], "coarse")
    parents = cut(labels.join(clusters.select("cluster", "coarse"), "cluster").select("id", "coarse"))
    members = members_of(cut(graph.groups.by_block(parents, "coarse").select("grp", F.col("coarse").alias("id"), F.col("s").alias("n"))))
    return Graph(clusters.select(F.col("coarse").alias("id"), "w"), members.edges(), groups=members), parents


def contract_buffered(graph: Graph, labels: DataFrame) -> tuple[Graph, DataFrame]:
    """The base form: coarse edges are written to a buffer, counted, and copied to their final places; two copies exist at once."""
    buffer = graph.gathered(cut(coarse_edges_of(graph, labels)))
    clusters = graph.held(number(coarse_vertices(graph.vertices, graph.held(labels)), ["cluster"], "coarse"))
    coarse, parents = _renamed(clusters, buffer, labels, graph.gathered)
    return Graph(coarse.vertices, cut(coarse.edges)), parents


def contract_twice(graph: Graph, labels: DataFrame) -> tuple[Graph, DataFrame, DataFrame]:
    """The rejected form: one pass counts coarse degrees, a second computes the edges again. Also returns (cluster, degree)."""
    degrees = cut(between_clusters(graph.edges, labels).select("a", "b").distinct().groupBy(F.col("a").alias("cluster")).agg(F.count("*").alias("degree")))
    coarse, parents = contract(graph, labels)
    return coarse, parents, degrees


def two_phase_edges(edges: DataFrame, labels: DataFrame, t_bump: int, salts: int = 16, one: Callable[[DataFrame], DataFrame] = as_is) -> DataFrame:
    """coarse_edges in two phases: clusters with few inter-cluster edges are summed whole, those that may have t_bump coarse
    neighbours are summed by (cluster, neighbour, salt) first. Their edges are counted before, by vertex, not by pair."""
    sizes = edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")).join(labels, "id").groupBy(F.col("cluster").alias("a")).agg(F.sum("n").alias("n"))
    heavy = one(sizes.where(F.col("n") >= t_bump).select("a", F.lit(salts).alias("salts")))  # at most 2m / t_bump clusters
    far = one(edges.join(labels.select(F.col("id").alias("src"), F.col("cluster").alias("a")), "src")).join(labels.select(F.col("id").alias("dst"), F.col("cluster").alias("b")), "dst").where("a <> b").select("a", "b", "w", "src")
    salted = one(far).join(heavy, "a", "left").groupBy("a", "b", (scramble("src", 5) % F.coalesce("salts", F.lit(1))).alias("salt")).agg(F.sum("w").alias("w"))
    return salted.groupBy("a", "b").agg(F.sum("w").alias("w"))


def reserve(sizes: DataFrame) -> DataFrame:
    """sizes: (part, buffer, vertices, edges) -> with the first vertex s and first edge d of each buffer's range: the sums over
    what comes before, in the order of parts and buffers. One row for each buffer of a task, so one window task is enough."""
    before = Window.orderBy("part", "buffer").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select("part", "buffer", "vertices", "edges", F.coalesce(F.sum("vertices").over(before), F.lit(0)).alias("s"), F.coalesce(F.sum("edges").over(before), F.lit(0)).alias("d"))


def contract_one_pass(graph: Graph, labels: DataFrame, t_bump: int | None = None) -> tuple[DataFrame, DataFrame, Graph]:
    """Coarse rows are summed once and written once, and their places are reserved per task.

    Returns rows (id, cluster, w, degree, first_edge), parents (id, coarse), and the coarse graph. A task numbers its finished
    neighbourhoods and edges from 0; its counts, one row, reserve its ranges of ids and of the edge array; ends are renamed last.
    Tasks have ranges of clusters, so ids are ranks, as in the other forms.
    """
    spark = graph.vertices.sparkSession
    labels = graph.held(labels)
    edges = graph.gathered(cut(coarse_edges(graph.edges, labels, graph.gathered) if t_bump is None else two_phase_edges(graph.edges, labels, t_bump, one=graph.gathered)))
    degrees = edges.groupBy(F.col("a").alias("cluster")).agg(F.count("*").alias("degree"))
    found = graph.gathered(coarse_vertices(graph.vertices, labels)).join(graph.held(degrees), "cluster", "left").withColumn("degree", F.coalesce("degree", F.lit(0)))
    placed = found.repartitionByRange("cluster").sortWithinPartitions("cluster")
    placed = cut(placed.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)))
    sizes = [(r["part"], 0, r["n"], r["e"]) for r in placed.groupBy("part").agg(F.count("*").alias("n"), F.sum("degree").alias("e")).collect()]
    starts = reserve(spark.createDataFrame(sizes or [(0, 0, 0, 0)], "part int, buffer int, vertices long, edges long")).select("part", "s", "d")
    within = Window.partitionBy("part").orderBy("at").rowsBetween(Window.unboundedPreceding, -1)
    rows = graph.gathered(cut(placed.join(F.broadcast(starts), "part").select((F.col("s") + F.col("at")).alias("id"), "cluster", "w", "degree", (F.col("d") + F.coalesce(F.sum("degree").over(within), F.lit(0))).alias("first_edge"))))
    coarse, parents = _renamed(graph.held(rows.select("cluster", "w", F.col("id").alias("coarse"))), edges, labels, graph.gathered)
    return rows, parents, coarse
