"""Initial partitions of the coarsest graph: one attempt in each task, the best one wins; and splitting of blocks."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.operators import local
from gpart.operators.metrics import block_cap
from gpart.sources.graphs import Graph

#: The coarsest graph goes to the driver and to every attempt; more edges than this do not.
MOST_EDGES = 4_000_000
#: Blocks are split in a task each; where a level has more directed edges for each block, they are split on the level before.
MOST_INNER = 1_000_000


def local_arrays(graph: Graph, most_edges: int = MOST_EDGES) -> tuple[np.ndarray, tuple]:
    """(ids, arrays of weights, sources, targets and edge weights) on the driver, of a graph whose size is checked first."""
    count = graph.edges.count()
    if count > most_edges:
        raise ValueError(f"{count} edges are too many for one task; coarsen further")
    vertices = graph.vertices.select("id", "w").toArrow().sort_by("id")
    edges = graph.edges.select("src", "dst", "w").toArrow().sort_by([("src", "ascending"), ("dst", "ascending")])
    ids = vertices.column("id").to_numpy()
    src, dst = (np.searchsorted(ids, edges.column(c).to_numpy()) for c in ("src", "dst"))
    return ids, (vertices.column("w").to_numpy(), src.astype(np.int32), dst.astype(np.int32), edges.column("w").to_numpy())


def local_copy(graph: Graph, most_edges: int = MOST_EDGES) -> tuple[list[int], local.LocalGraph]:
    """(ids, graph) on the driver."""
    ids, arrays = local_arrays(graph, most_edges)
    return ids.tolist(), local.LocalGraph.of_arrays(arrays)


def attempts(spark: SparkSession, arrays: tuple, k: int, cap: int, seeds: list[int], methods=local.METHODS, tries: int = 2, fm: bool = False) -> DataFrame:
    """(seed, overload, cut, blocks): a partition by each seed, from a full copy of the graph in its task."""
    held = spark.sparkContext.broadcast(arrays)

    def run(batches):
        g = local.LocalGraph.of_arrays(held.value)
        for b in batches:
            out = {"seed": [], "overload": [], "cut": [], "blocks": []}
            for seed in b.column("seed").to_pylist():
                blocks = local.solve(g, k, cap, seed, tries, methods, fm=fm)
                out["seed"].append(seed)
                out["overload"].append(sum(max(0, x - cap) for x in g.loads(blocks, k)))
                out["cut"].append(g.cut(blocks))
                out["blocks"].append(blocks)
            yield pa.RecordBatch.from_arrays([pa.array(out["seed"], pa.int64()), pa.array(out["overload"], pa.int64()), pa.array(out["cut"], pa.int64()), pa.array(out["blocks"], pa.list_(pa.int32()))], names=list(out))

    return spark.createDataFrame([(s,) for s in seeds], "seed long").repartition(len(seeds)).mapInArrow(run, "seed long, overload long, cut long, blocks array<int>")


def initial_partition(graph: Graph, k: int, eps: float, seed: int = 1, tries: int = 4, methods=local.METHODS, fm: bool = False) -> DataFrame:
    """(id, block) of the best attempt: least overload, then least cut, then smallest seed."""
    spark = graph.vertices.sparkSession
    ids, arrays = local_arrays(graph)
    cap, _ = block_cap(int(arrays[0].sum()), k, eps)
    found = attempts(spark, arrays, k, cap, [seed * 1000 + i for i in range(tries)], methods, fm=fm)
    best = found.orderBy("overload", "cut", "seed").first()
    return spark.createDataFrame(list(zip(ids.tolist(), best["blocks"], strict=True)), "id long, block int")


def extend_blocks(graph: Graph, partition: DataFrame, shares: dict[int, int], cap: int, seed: int = 1) -> DataFrame:
    """Splits blocks that stand for several final ones: shares gives the number of final blocks of each block, in order; each block's
    inner graph is split in a task of its own. (id, block) with final numbers."""
    offsets, run = {}, 0
    for b in sorted(shares):
        offsets[b], run = run, run + shares[b]
    a, b = (partition.select(F.col("id").alias(s), F.col("block").alias(t)) for s, t in (("src", "block"), ("dst", "far")))
    inner = graph.edges.join(a, "src").join(b, "dst").where("block = far").groupBy("block", "src").agg(F.collect_list(F.struct("dst", "w")).alias("near"))
    rows = graph.vertices.join(partition, "id").join(inner.withColumnRenamed("src", "id"), ["id", "block"], "left")

    def split(key: tuple, table: pa.Table) -> pa.Table:
        block = key[0].as_py()
        found = sorted(table.to_pylist(), key=lambda r: r["id"])
        place = {r["id"]: i for i, r in enumerate(found)}
        g = local.LocalGraph([r["w"] for r in found], [sorted((place[e["dst"]], e["w"]) for e in r["near"] or ()) for r in found])
        blocks = local.improve(g, local.bisect(g, shares[block], cap, random.Random(seed)), [cap] * shares[block], random.Random(seed))
        return pa.table({"id": pa.array([r["id"] for r in found], pa.int64()), "block": pa.array([offsets[block] + x for x in blocks], pa.int32())})

    return rows.groupBy("block").applyInArrow(split, "id long, block int")
