"""Projection, size-constrained refinement, rebalancing, and k-way local search with an exact choice of the best prefix."""

from __future__ import annotations

import random

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gpart.functions.columns import admitted_within, running_sum, scramble
from gpart.operators import local
from gpart.operators.clustering import label_propagation, lp_round_single
from gpart.operators.gains import GainTable, affinity
from gpart.session import cut
from gpart.sources.graphs import Graph


def project(partition: DataFrame, parents: DataFrame) -> DataFrame:
    """A partition of the coarse graph on the finer one: parents (id, coarse)."""
    return parents.join(partition.select(F.col("id").alias("coarse"), "block"), "coarse").select("id", "block")


def boundary(edges: DataFrame, partition: DataFrame) -> DataFrame:
    """(id) of vertices with a neighbour in another block."""
    a, b = (partition.select(F.col("id").alias(s), F.col("block").alias(t)) for s, t in (("src", "ba"), ("dst", "bb")))
    return edges.join(a, "src").join(b, "dst").where("ba <> bb").select(F.col("src").alias("id")).distinct()


def as_labels(partition: DataFrame) -> DataFrame:
    return partition.select("id", F.col("block").cast("long").alias("cluster"))


def as_partition(labels: DataFrame) -> DataFrame:
    return labels.select("id", F.col("cluster").cast("int").alias("block"))


def refine_lp_round(graph: Graph, partition: DataFrame, cap: int, seed: int = 1, part: int = 0, parts: int = 1) -> DataFrame:
    """One sub-batch of size-constrained label propagation among blocks; only strict improvements that fit move."""
    return as_partition(lp_round_single(graph, as_labels(partition), seed, part, parts, cap))


def refine_lp(graph: Graph, partition: DataFrame, cap: int, rounds: int = 5, seed: int = 1, parts: int = 2) -> DataFrame:
    return as_partition(label_propagation(graph, rounds, seed, parts, cap, labels=as_labels(partition)))


def block_weights(vertices: DataFrame, partition: DataFrame) -> DataFrame:
    return vertices.join(partition, "id").groupBy("block").agg(F.sum("w").alias("weight"))


def affinity_of(graph: Graph, partition: DataFrame, chosen: DataFrame) -> DataFrame:
    """affinity of the chosen (id) vertices; of a graph kept as groups, from what each block has of their groups."""
    if graph.groups is None:
        return affinity(graph.edges.join(chosen.select(F.col("id").alias("src")), "src", "left_semi"), partition)
    mine = graph.groups.rows.join(chosen, "id", "left_semi").join(partition, "id").select("grp", "id", "n", F.col("block").alias("own"))
    met = mine.join(graph.groups.by_block(partition, "block"), "grp").withColumn("s", F.col("s") - F.when(F.col("block") == F.col("own"), F.col("n")).otherwise(0))
    return met.where("s > 0").groupBy("id", "block").agg(F.sum(F.col("n") * F.col("s")).alias("affinity"))


def rebalance_round(graph: Graph, partition: DataFrame, k: int, cap: int, seed: int = 1) -> DataFrame:
    """Vertices leave overloaded blocks, least loss per weight first, until the excess is gone; they go to the block with room
    that gains most (or the lightest), while its room lasts. Returns the partition afterwards."""
    spark = graph.vertices.sparkSession
    weights = spark.range(k).select(F.col("id").cast("int").alias("block")).join(block_weights(graph.vertices, partition), "block", "left").withColumn("weight", F.coalesce("weight", F.lit(0)))
    own = graph.vertices.join(partition, "id").join(F.broadcast(weights.where(F.col("weight") > cap)), "block").select("id", F.col("block").alias("own"), "w", (F.col("weight") - cap).alias("excess"))
    roomy = weights.where(F.col("weight") < cap).select("block", (F.lit(cap) - F.col("weight")).alias("room"))
    lightest = roomy.agg(F.max(F.struct("room", (-F.col("block")).alias("b"))).alias("x")).select((-F.col("x.b")).cast("int").alias("block"), F.col("x.room").alias("room"))  # one row
    near = affinity_of(graph, partition, own.select("id"))
    kept = own.join(near.select("id", F.col("block").alias("own"), F.col("affinity").alias("kept")), ["id", "own"], "left").withColumn("kept", F.coalesce("kept", F.lit(0)))
    to_near = kept.join(near, "id").join(F.broadcast(roomy), "block").where("w <= room").select("id", "own", "w", "excess", "room", "block", (F.col("affinity") - F.col("kept")).alias("gain"))
    to_light = kept.crossJoin(F.broadcast(lightest)).where("w <= room").select("id", "own", "w", "excess", "room", "block", (-F.col("kept")).alias("gain"))
    best = to_near.unionAll(to_light).groupBy("id").agg(F.max(F.struct("gain", (-scramble(F.col("block").cast("long"), seed)).alias("t"), (-F.col("block")).alias("b"), "own", "w", "excess", "room")).alias("x"))
    moves = best.select("id", "x.gain", (-F.col("x.b")).alias("to"), "x.own", "x.w", "x.excess", "x.room").withColumn("rate", F.col("gain") / F.col("w"))
    order = [F.desc("rate"), scramble("id", seed), F.col("id")]
    leaving = admitted_within(moves, "own", order, "w", F.col("excess"), scramble("id", seed), inclusive=False)
    fitting = admitted_within(leaving, "to", order, "w", F.col("room"), scramble("id", seed))
    return partition.join(fitting.select("id", F.col("to").cast("int").alias("to")), "id", "left").select("id", F.coalesce("to", "block").alias("block"))


def overload(vertices: DataFrame, partition: DataFrame, cap: int) -> int:
    return block_weights(vertices, partition).agg(F.coalesce(F.sum(F.greatest(F.col("weight") - cap, F.lit(0))), F.lit(0))).first()[0]


def rebalance(graph: Graph, partition: DataFrame, k: int, cap: int, seed: int = 1, rounds: int = 20) -> DataFrame:
    """Rounds until every block is within cap, or nothing fits any more."""
    excess = overload(graph.vertices, partition, cap)
    for r in range(rounds):
        if not excess:
            break
        after = cut(rebalance_round(graph, partition, k, cap, seed + r))
        left = overload(graph.vertices, after, cap)
        if left >= excess:
            break
        partition, excess = after, left
    return partition


def joint_gains(moves: DataFrame, graph: Graph, partition: DataFrame) -> DataFrame:
    """(pos, id, from_block, to_block, gain): what each move really gains, given all moves before it.

    The table's gain counts all neighbours where they are at the start; for an edge to an earlier mover, the change between
    where that one was and where it is then is added.
    """
    spots = affinity(graph.edges.join(moves.select(F.col("id").alias("src")), "src", "left_semi"), partition)
    at = lambda block, name: moves.select("id", block).join(spots.select("id", F.col("block").alias(block), F.col("affinity").alias(name)), ["id", block], "left").select("id", F.coalesce(name, F.lit(0)).alias(name))
    base = moves.join(at("to_block", "there"), "id").join(at("from_block", "here"), "id").withColumn("base", F.col("there") - F.col("here"))
    later, earlier = (moves.select(F.col("pos").alias(f"pos_{s}"), F.col("id").alias(f"id_{s}"), F.col("from_block").alias(f"from_{s}"), F.col("to_block").alias(f"to_{s}")) for s in "vu")
    is_in = lambda a, b: (F.col(a) == F.col(b)).cast("long")
    fix = graph.edges.join(later, F.col("src") == F.col("id_v")).join(earlier, F.col("dst") == F.col("id_u")).where("pos_u < pos_v")
    fix = fix.withColumn("fix", F.col("w") * ((is_in("to_u", "to_v") - is_in("to_u", "from_v")) - (is_in("from_u", "to_v") - is_in("from_u", "from_v"))))
    fixes = fix.groupBy(F.col("pos_v").alias("pos")).agg(F.sum("fix").alias("fix"))
    return base.join(fixes, "pos", "left").select("pos", "id", "from_block", "to_block", (F.col("base") + F.coalesce("fix", F.lit(0))).alias("gain"))


def prefixes(moves: DataFrame, graph: Graph, partition: DataFrame, cap: int) -> DataFrame:
    """(pos, gain, total, over): the cut's whole gain after each move, and how many blocks are then too heavy."""
    exact = joint_gains(moves, graph, partition)
    weighed = moves.join(graph.vertices, "id")
    changes = weighed.select("pos", F.col("from_block").alias("block"), (-F.col("w")).alias("w")).unionAll(weighed.select("pos", F.col("to_block").alias("block"), "w"))
    start = block_weights(graph.vertices, partition)
    loads = running_sum(changes, ["block"], "pos", F.col("w"), "run").join(F.broadcast(start), "block", "left").withColumn("after", F.coalesce("weight", F.lit(0)) + F.col("run"))
    turns = loads.withColumn("turn", (F.col("after") > cap).cast("int") - (F.col("after") - F.col("w") > cap).cast("int")).groupBy("pos").agg(F.sum("turn").alias("turn"))
    heavy = start.agg(F.coalesce(F.sum((F.col("weight") > cap).cast("int")), F.lit(0)).alias("heavy"))
    both = running_sum(exact.join(turns, "pos"), [], "pos", F.col("gain"), "total")
    both = running_sum(both, [], "pos", F.col("turn"), "over")
    return both.crossJoin(F.broadcast(heavy)).select("pos", "gain", "total", (F.col("heavy") + F.col("over")).alias("over"))


def best_prefix(moves: DataFrame, graph: Graph, partition: DataFrame, cap: int) -> tuple[int, int]:
    """(moves to keep, their gain): the feasible prefix of the largest total gain, the shortest on ties; (0, 0) if none gains."""
    ranked = prefixes(moves, graph, partition, cap).where("over = 0 AND total > 0")
    best = ranked.agg(F.max(F.struct("total", (-F.col("pos")).alias("p"))).alias("x")).first()["x"]
    return (-best["p"], best["total"]) if best else (0, 0)


def region_moves(graph: Graph, partition: DataFrame, cap: int, seed: int, regions: int, table: str, k: int) -> DataFrame:
    """Proposals (region, step, id, from_block, to_block): boundary vertices are dealt to regions; a region's vertices with their
    neighbourhoods are searched in one task, with the rest of the world fixed at its start."""
    gain_table = GainTable(graph, partition, k, table)
    seeds = boundary(graph.edges, partition).select("id", (scramble("id", seed) % regions).alias("region"))
    weights = {r["block"]: r["weight"] for r in block_weights(graph.vertices, partition).collect()}  # k rows
    inner = graph.edges.join(seeds.select(F.col("id").alias("src"), "region"), "src").join(seeds.select(F.col("id").alias("dst"), F.col("region").alias("far")), "dst").where("region = far").groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("near"))
    held = gain_table.affinities().groupBy("id").agg(F.collect_list(F.struct("block", "affinity")).alias("held"))
    rows = seeds.join(graph.vertices, "id").join(partition, "id").join(inner.withColumnRenamed("src", "id"), "id", "left").join(held, "id", "left")

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        found = sorted(rows.to_pylist(), key=lambda r: r["id"])
        place = {r["id"]: i for i, r in enumerate(found)}
        near = [sorted((place[e["dst"]], e["w"]) for e in r["near"] or ()) for r in found]
        # what a vertex is tied to outside its region is an edge to a stand-in of each block, which never moves
        n = len(found)
        outside: list[dict[int, int]] = [{e["block"]: e["affinity"] for e in r["held"] or ()} for r in found]
        for i, edges in enumerate(near):
            for j, w in edges:
                outside[i][found[j]["block"]] -= w
        blocks = [r["block"] for r in found] + list(range(k))
        loads = [0] * k
        for r in found:
            loads[r["block"]] += r["w"]
        stand_in = [weights.get(b, 0) - loads[b] for b in range(k)]
        adjacent = [edges + [(n + b, w) for b, w in outside[i].items() if w] for i, edges in enumerate(near)] + [[] for _ in range(k)]
        g = local.LocalGraph([r["w"] for r in found] + stand_in, adjacent)
        rng = random.Random(seed * 7919 + (key[0].as_py() or 0))
        log = local.search(g, blocks, [cap] * k, list(range(n)), rng, once=set(range(n, n + k)), table=table)
        return pa.table({"region": pa.array([key[0].as_py()] * len(log), pa.int64()), "step": pa.array(list(range(len(log))), pa.int32()), "id": pa.array([found[v]["id"] for v, _, _ in log], pa.int64()), "from_block": pa.array([a for _, a, _ in log], pa.int32()), "to_block": pa.array([b for _, _, b in log], pa.int32())})

    return rows.groupBy("region").applyInArrow(run, "region long, step int, id long, from_block int, to_block int")


def refine_fm(graph: Graph, partition: DataFrame, k: int, cap: int, table: str = "hybrid", rounds: int = 3, seed: int = 1, seeds_per_region: int = 2000) -> DataFrame:
    """k-way local search: regions around the boundary are searched side by side, each in a task with a gain table of the form that
    `table` names, and the best prefix of all their moves, by exact joint gains, is kept. The cut never grows."""
    for r in range(rounds):
        seeds = boundary(graph.edges, partition).count()
        if not seeds:
            break
        proposed = cut(region_moves(graph, partition, cap, seed + r, max(1, seeds // seeds_per_region), table, k))
        sizes = proposed.groupBy("region").agg(F.count("*").alias("n"))
        before = sizes.select("region", (F.sum("n").over(Window.orderBy("region")) - F.col("n")).alias("before"))  # a row for each region
        moves = proposed.join(F.broadcast(before), "region").select((F.col("before") + F.col("step") + 1).alias("pos"), "id", "from_block", "to_block")
        kept, gain = best_prefix(moves, graph, partition, cap)
        if not gain:
            break
        partition = cut(partition.join(moves.where(F.col("pos") <= kept).select("id", "to_block"), "id", "left").select("id", F.coalesce("to_block", "block").alias("block")))
    return partition
