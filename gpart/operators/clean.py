"""Graph input: symmetry, loops and parallel edges, locality relabelling, statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.session import cut
from gpart.sources.graphs import Graph, number


def symmetrize(edges: DataFrame) -> DataFrame:
    """Adds missing reverse edges; where both directions exist the larger weight holds for both."""
    both = edges.select("src", "dst", "w").unionAll(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return both.groupBy("src", "dst").agg(F.max("w").alias("w"))


def simplify(edges: DataFrame, merge: str = "sum") -> DataFrame:
    """Without loops; parallel edges become one, of summed, largest or unit weight."""
    rows = edges.where("src <> dst").groupBy("src", "dst").agg(F.max("w").alias("_m"), F.sum("w").alias("_s"))
    weight = {"sum": F.col("_s"), "max": F.col("_m"), "one": F.lit(1).cast("long")}[merge]
    return rows.select("src", "dst", weight.alias("w"))


def relabel(graph: Graph, order: str = "degree", labels: DataFrame | None = None) -> tuple[Graph, DataFrame]:
    """The graph under new ids, and the map (old, id). order: 'id', 'degree' (hubs first) or 'cluster' (by labels)."""
    degrees = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    rows = graph.vertices.join(degrees, "id", "left").withColumn("degree", F.coalesce("degree", F.lit(0)))
    if order == "degree":
        rows, keys = rows.withColumn("rank", -F.col("degree")), ["rank", "old"]
    elif order == "cluster":
        rows, keys = rows.join(labels, "id"), ["cluster", "old"]
    else:
        keys = ["old"]
    placed = number(rows.withColumnRenamed("id", "old"), keys, "id").select("old", "id", "w")
    to_src, to_dst = (placed.select(F.col("old").alias(s), F.col("id").alias(t)) for s, t in (("src", "a"), ("dst", "b")))
    edges = graph.edges.join(to_src, "src").join(to_dst, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return Graph(placed.select("id", "w"), edges), placed.select("old", "id")


def graph_stats(graph: Graph) -> DataFrame:
    """n, m (undirected edges), total_w, avg_deg and max_deg, in one row."""
    sums = graph.degrees().agg(F.coalesce(F.sum("degree"), F.lit(0)).alias("e"), F.coalesce(F.sum("w"), F.lit(0)).alias("tw"), F.coalesce(F.max("degree"), F.lit(0)).alias("max_deg"))
    n = graph.vertices.agg(F.count("*").alias("n"))
    return n.crossJoin(sums).select("n", (F.col("e") / 2).cast("long").alias("m"), (F.col("tw") / 2).cast("long").alias("total_w"), F.round(F.col("e") / F.greatest("n", F.lit(1)), 6).alias("avg_deg"), F.col("max_deg").cast("long").alias("max_deg"))


def degree_profile(graph: Graph, t_bump: int) -> DataFrame:
    """Vertices by the binary logarithm of their degree (-1: isolated), and how many of them could be bumped at t_bump."""
    degrees = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    rows = graph.vertices.join(degrees, "id", "left").withColumn("degree", F.coalesce("degree", F.lit(0)))
    bucket = F.when(F.col("degree") == 0, -1).otherwise(F.length(F.bin("degree")) - 1)
    return rows.groupBy(bucket.cast("int").alias("log_degree")).agg(F.count("*").alias("vertices"), F.count(F.when(F.col("degree") >= t_bump, 1)).alias("heavy"))


def two_hop_counts(graph: Graph) -> DataFrame:
    """(id, n): the different vertices two edges away, other than the vertex itself, where there are any.

    Vertices with the same neighbours are one class (told by their number and 128 bits of hashes). A vertex's neighbours are whole
    classes, so walks go over one vertex of each class and sizes of classes are summed; the classes' own pairs remain.
    """
    edges = graph.edges.select("src", "dst")
    marks = [F.count("*").alias("degree"), *[F.bit_xor(F.xxhash64("dst", F.lit(i))).alias(f"mark{i}") for i in (1, 2)]]
    signed = cut(edges.groupBy("src").agg(*marks))
    key = ["degree", "mark1", "mark2"]
    classes = cut(signed.groupBy(*key).agg(F.min("src").alias("first"), F.count("*").alias("size")))
    one_each = edges.join(classes.select(F.col("first").alias("src"), "size"), "src").join(classes.select(F.col("first").alias("dst")), "dst", "left_semi")
    one_each = cut(one_each.select("src", "dst", "size"))
    # the graph is symmetric: the far end of a second edge is the near end of the same edge read backwards
    met = one_each.select(F.col("src").alias("first"), F.col("dst").alias("mid")).join(one_each.select(F.col("dst").alias("mid"), "src", "size"), "mid")
    counts = met.select("first", "src", "size").distinct().groupBy("first").agg((F.sum("size") - 1).alias("n")).where("n > 0")
    return signed.join(classes, key).join(counts, "first").select(F.col("src").alias("id"), "n")
