"""The distributed form: edges live with the owner of their source, far ends are ghosts, labels travel in batches."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.operators import refinement
from gpart.operators.initial import MOST_EDGES, attempts, local_arrays
from gpart.operators.metrics import block_cap
from gpart.plans.multilevel import MultilevelConfig, Result, coarsen, compressed_input, first_partition
from gpart.session import cut
from gpart.sources.graphs import Graph


def owned(vertices: DataFrame, n: int, parts: int) -> DataFrame:
    """(id, part): consecutive ids, about n / parts for each part."""
    return vertices.select("id", F.floor(F.col("id") * parts / F.lit(max(n, 1))).cast("int").alias("part"))


def ghosts(edges: DataFrame, owners: DataFrame) -> DataFrame:
    """(part, ghost_id, owner): far ends that another part owns, once for each part that sees them."""
    here, there = (owners.select(F.col("id").alias(s), F.col("part").alias(t)) for s, t in (("src", "part"), ("dst", "owner")))
    return edges.join(here, "src").join(there, "dst").where("part <> owner").select("part", F.col("dst").alias("ghost_id"), "owner").distinct()


def work_per_part(graph: Graph, owners: DataFrame) -> DataFrame:
    """(part, vertices, directed_edges, ghosts): what each part holds."""
    held = graph.edges.join(owners.withColumnRenamed("id", "src"), "src").groupBy("part").agg(F.count("*").alias("directed_edges"))
    seen = ghosts(graph.edges, owners).groupBy("part").agg(F.count("*").alias("ghosts"))
    return owners.groupBy("part").agg(F.count("*").alias("vertices")).join(held, "part", "left").join(seen, "part", "left").select("part", "vertices", F.coalesce("directed_edges", F.lit(0)).alias("directed_edges"), F.coalesce("ghosts", F.lit(0)).alias("ghosts"))


def partition_distributed(graph: Graph, k: int, parts: int = 8, compress: bool = True, cfg: MultilevelConfig | None = None) -> Result:
    """k blocks. Each round runs in synchronous batches, as many as would be exchanged between parts; of the optimisations only the
    compressed input applies; each part has a full copy of the coarsest graph and its own seed; blocks that end too heavy are
    rebalanced on every level."""
    cfg = replace(cfg or MultilevelConfig(), two_phase=False, one_pass=False, compress=compress)
    coded = None
    if compress:
        graph, coded = compressed_input(graph, cfg)
    levels = coarsen(graph, k, cfg)
    total = levels[0].graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    cap, relaxed = block_cap(total, k, cfg.eps)
    if levels[-1].m <= MOST_EDGES:
        ids, arrays = local_arrays(levels[-1].graph)
        spark = graph.vertices.sparkSession
        best = attempts(spark, arrays, k, cap, [cfg.seed * 1000 + p for p in range(parts)], tries=1).orderBy("overload", "cut", "seed").first()
        found = spark.createDataFrame(list(zip(ids.tolist(), best["blocks"], strict=True)), "id long, block int")
    else:
        found = first_partition(levels[-1], k, cap, cfg)
    for number in range(len(levels) - 1, -1, -1):
        level = levels[number]
        found = cut(refinement.refine_lp(level.graph, found, cap, cfg.refine_rounds, cfg.seed, cfg.parts))
        found = refinement.rebalance(level.graph, found, k, cap, cfg.seed)
        if number:
            found = cut(refinement.project(found, level.parents))
    return Result(found, cap, relaxed, levels, coded)
