"""Coarsening by label propagation: ratings, choices, rounds with size caps, two-phase rounds, two-hop matching.

A round is synchronous over a sub-batch of the vertices, chosen by a hash; within a run every vertex moves at most once per round.
A vertex takes the neighbouring cluster with the largest rating; ties go to its own cluster, then by a hash of the cluster,
then to the smaller id, so every form of a round gives the same labels.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from gpart.functions.columns import MODULUS, admitted_within, scramble
from gpart.session import cut, staying
from gpart.sources.graphs import Graph, Members

#: A vertex is treated as heavy once it has this many neighbouring clusters (the paper's value).
T_BUMP = 10_000
ROUNDS = 5


def singletons(vertices: DataFrame) -> DataFrame:
    """Every vertex is its own cluster: (id, cluster)."""
    return vertices.select("id", F.col("id").alias("cluster"))


def rated_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Edges with the cluster of their far end: (src, dst, cluster, w)."""
    return edges.join(labels.select(F.col("id").alias("dst"), "cluster"), "dst").select("src", "dst", "cluster", "w")


def ratings(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(id, cluster, rating): the weight of a vertex's edges into each neighbouring cluster."""
    return rated_edges(edges, labels).groupBy(F.col("src").alias("id"), "cluster").agg(F.sum("w").alias("rating"))


def distinct_clusters(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(id, nc): the number of neighbouring clusters."""
    return ratings(edges, labels).groupBy("id").agg(F.count("*").alias("nc"))


def batch(vertices: DataFrame, seed: int, part: int, parts: int) -> DataFrame:
    """The vertices of a sub-batch: those whose hash falls on it."""
    return vertices.where(scramble("id", seed) % parts == part)


def in_batch(seed: int, part: int, parts: int):
    """The same as a condition on a column of ids."""
    return lambda ids: scramble(ids, seed) % parts == part


def order_key(rating, cluster, own, seed: int):
    """What a vertex maximises."""
    return F.struct(rating.alias("rating"), (cluster == own).cast("int").alias("own"), (-scramble(cluster, seed)).alias("tie"), (-cluster).alias("last"))


def choose(rated: DataFrame, own: DataFrame, seed: int) -> DataFrame:
    """(id, best, rating) from (id, cluster, rating); an aggregate with map-side combining, not a window."""
    keyed = rated.join(own.select("id", F.col("cluster").alias("own"), F.col("w").alias("vw")), "id")
    best = keyed.groupBy("id").agg(F.max(order_key(F.col("rating"), F.col("cluster"), F.col("own"), seed)).alias("k"), F.first("own").alias("own"), F.first("vw").alias("w"))
    return best.select("id", (-F.col("k.last")).alias("best"), F.col("k.rating").alias("rating"), "own", "w")


def cluster_weights(vertices: DataFrame, labels: DataFrame) -> DataFrame:
    return vertices.join(labels, "id").groupBy("cluster").agg(F.sum("w").alias("weight"))


def prepared(state: DataFrame, seed: int, part: int, parts: int) -> DataFrame:
    """state (id, w, cluster) with what the next sub-batch goes by: `tie`, the cluster's hash, `ord`, the vertex's, and whether it is
    the vertex's turn. As columns of a table they leave the round's own code the same for every seed, so it is compiled once."""
    turn = scramble("id", seed) % parts == part if parts > 1 else F.lit(True)
    return state.select("id", "w", "cluster", scramble("cluster", seed).alias("tie"), scramble("id", seed).alias("ord"), turn.alias("turn"))


def best_in_groups(now: DataFrame, groups: Members, cap: int | None = None) -> DataFrame:
    """(src, cluster, tie, weight, rating): of the vertices of one group whose turn it is, what they may choose. All members of a group
    rate its clusters alike, up to a factor and but for their own, which they leave themselves out of: so the own cluster and the
    group's two best, of those that have room for a vertex of that weight, are enough. now: with the clusters' weights where there is a cap."""
    far = now if "weight" in now.columns else now.withColumn("weight", F.lit(0).cast("long"))
    held = groups.rows.select("grp", "id", "n", "many").join(far.select("id", "cluster", "tie", "turn", "weight", (F.col("w") if cap is not None else F.lit(0).cast("long")).alias("vw")), "id")
    sums = held.groupBy("grp", "cluster").agg(F.sum("n").alias("rating"), F.first("tie").alias("tie"), F.first("weight").alias("weight"))
    asking = held.where("turn AND NOT many")
    roomy = sums.join(asking.select("grp", "vw").distinct(), "grp")
    if cap is not None:
        roomy = roomy.where(F.col("weight") + F.col("vw") <= cap)
    key = lambda rating: F.struct(rating.alias("rating"), (-F.col("tie")).alias("tie"), (-F.col("cluster")).alias("last"), F.col("weight").alias("weight"))
    best = roomy.groupBy("grp", "vw").agg(F.max(key(F.col("rating"))).alias("best"))
    second = roomy.join(best, ["grp", "vw"]).where(-F.col("best.last") != F.col("cluster")).groupBy("grp", "vw").agg(F.max(key(F.col("rating"))).alias("second"))
    mine = asking.select("grp", F.col("id").alias("src"), "n", "cluster", "tie", "weight", "vw").join(sums.select("grp", "cluster", "rating"), ["grp", "cluster"])
    seen = mine.join(best.join(second, ["grp", "vw"], "left"), ["grp", "vw"], "left")
    other = F.when(-F.col("best.last") != F.col("cluster"), F.col("best")).otherwise(F.col("second"))
    own = F.when(F.col("rating") > F.col("n"), key(F.col("rating") - F.col("n")))
    rows = seen.select("src", "n", F.explode(F.array(other, own)).alias("c")).where("c IS NOT NULL")
    return rows.select("src", (-F.col("c.last")).alias("cluster"), (-F.col("c.tie")).alias("tie"), "c.weight", (F.col("n") * F.col("c.rating")).alias("rating"))


def advanced(now: DataFrame, edges: DataFrame, cap: int | None, may: DataFrame | None = None, light: bool = False, salts: int = 16, rating_map: str = "hash", groups: Members | None = None, gathered: bool = False) -> DataFrame:
    """One synchronous sub-batch from a prepared state and the edges of its vertices: (id, w, cluster, before).

    Without `may` or `light`, every vertex is rated alike, by a plain aggregate (one phase). light: all are rated whole, in one task
    each; may: but for these, whose sums are made in parts. The cluster's weight travels with the label, so that ratings of full
    clusters go where they are made, and a vertex's ratings meet its own row once. groups: vertices of one group are rated by the group and
    not by pairs; `edges` are then those of the others. gathered: all tables have one partition, of a bounded size, and nothing is
    exchanged. Moves are admitted best first: by rating,
    then by the vertex's hash, then by id, while the running weight is within the cluster's room.
    """
    held = (lambda df: df.hint("shuffle_hash")) if gathered else (lambda df: df)  # kept in the task, neither broadcast nor sorted
    one = (lambda df: df.coalesce(1)) if gathered else (lambda df: df)  # the planner does not know it of what a join gives
    far = one(now.join(held(now.groupBy("cluster").agg(F.sum("w").alias("weight"))), "cluster")) if cap is not None else now.withColumn("weight", F.lit(0).cast("long"))
    near = one(edges.join(held(far.select(F.col("id").alias("dst"), "cluster", "tie", "weight")), "dst").select("src", "dst", "cluster", "tie", "weight", "w"))
    same = [F.first("tie").alias("tie"), F.first("weight").alias("weight")]
    total = F.sum("w").alias("rating")
    if may is None and not light:
        rated = near.groupBy("src", "cluster").agg(total, *same)
    else:
        # gathered, a flag tells the heavy ones: a semi join would go below what makes the partition one
        flagged = one(near.join(held(may.withColumn("heavy", F.lit(True))), "src", "left")) if may is not None and gathered else None
        few = near if may is None else flagged.where("heavy IS NULL").drop("heavy") if gathered else near.join(may, "src", "left_anti")
        if rating_map == "hash":
            rated = (few if gathered else few.repartition("src")).groupBy("src", "cluster").agg(total, *same)
        else:
            rated = sparse_ratings(few).select("src", "cluster", "rating").join(far.select("cluster", "tie", "weight").distinct(), "cluster").select("src", "cluster", "rating", "tie", "weight")
        if may is not None:
            many = flagged.where("heavy").drop("heavy") if gathered else near.join(may, "src", "left_semi")
            parts = many.groupBy("src", (scramble("dst", 5) % salts).alias("salt"), "cluster").agg(F.sum("w").alias("w"), *same)
            rated = rated.unionByName(parts.groupBy("src", "cluster").agg(total, *same))
            rated = one(rated)
    if groups is not None:
        rated = rated.select("src", "cluster", "tie", "weight", "rating").unionByName(best_in_groups(far, groups, cap))
    own = now.where("turn").select(F.col("id").alias("src"), F.col("cluster").alias("own"), F.col("w").alias("vw"), "ord")
    keyed = one(rated.join(held(own), "src"))
    if cap is not None:
        keyed = keyed.where((F.col("cluster") == F.col("own")) | (F.col("weight") + F.col("vw") <= cap))
    key = F.struct("rating", (F.col("cluster") == F.col("own")).cast("int").alias("own"), (-F.col("tie")).alias("tie"), (-F.col("cluster")).alias("last"), "weight")
    best = keyed.groupBy("src").agg(F.max(key).alias("k"), F.first("own").alias("own"), F.first("vw").alias("vw"), F.first("ord").alias("ord"))
    moves = best.where(-F.col("k.last") != F.col("own")).select(F.col("src").alias("id"), (-F.col("k.last")).alias("best"), "k.rating", "k.weight", "vw", "ord")
    if cap is not None:
        moves = admitted_within(moves, "best", [F.desc("rating"), F.col("ord"), F.col("id")], "vw", F.lit(cap) - F.col("weight"), F.col("ord"))
    return now.select("id", "w", F.col("cluster").alias("before")).join(held(one(moves.select("id", "best"))), "id", "left").select("id", "w", F.coalesce("best", "before").alias("cluster"), "before")


def apply_moves(labels: DataFrame, moves: DataFrame) -> DataFrame:
    return labels.join(moves.select("id", "best"), "id", "left").select("id", F.coalesce("best", "cluster").alias("cluster"))


@dataclass
class RoundStats:
    """Work of each round so far: vertices that moved, vertices that were bumped, and entries of the bumped ones' tables."""

    moved: list[int] = field(default_factory=list)
    bumped: list[int] = field(default_factory=list)
    entries: list[int] = field(default_factory=list)


def active_edges(graph: Graph, seed: int, part: int, parts: int, by_groups: Members | None = None) -> DataFrame:
    """The edges of a sub-batch's vertices."""
    if by_groups is not None and not by_groups.several:
        return graph.vertices.where("false").select(F.col("id").alias("src"), F.col("id").alias("dst"), "w")
    if by_groups is not None:  # without those that the groups rate
        return by_groups.edges(F.col("many") & (in_batch(seed, part, parts)(F.col("id")) if parts > 1 else F.lit(True)))
    return graph.edges_of(in_batch(seed, part, parts)) if parts > 1 else graph.edges


def state_of(graph: Graph, labels: DataFrame, seed: int, part: int, parts: int) -> DataFrame:
    return prepared(graph.vertices.join(labels, "id").select("id", "w", "cluster"), seed, part, parts)


def lp_round_single(graph: Graph, labels: DataFrame, seed: int = 1, part: int = 0, parts: int = 1, cap: int | None = None) -> DataFrame:
    """One synchronous sub-batch, all vertices treated alike: labels afterwards."""
    return advanced(state_of(graph, labels, seed, part, parts), active_edges(graph, seed, part, parts), cap).select("id", "cluster")


LIGHT = "src long, cluster long, rating long"


def sparse_ratings(near: DataFrame) -> DataFrame:
    """(src, cluster, rating) of whole neighbourhoods, near: (src, cluster, w), with one scratch array over a batch's clusters and the
    list of its non-zero places, in place of a hash aggregate."""

    def sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: pa.Table | None = None
        for rows in [*batches, None]:
            if rows is not None:
                new = pa.Table.from_batches([rows])
                kept = pa.concat_tables([kept, new]) if kept is not None else new
                if not kept.num_rows:
                    continue
                last = kept.column("src")[-1].as_py()  # its neighbourhood may go on in the next batch
                n = int(np.searchsorted(kept.column("src").to_numpy(), last))
                ready, kept = kept.slice(0, n), kept.slice(n)
            else:
                if kept is None:
                    return
                ready = kept
            src, cluster, w = (ready.column(c).to_numpy() for c in ("src", "cluster", "w"))
            names, place = np.unique(cluster, return_inverse=True)
            scratch = np.zeros(len(names), dtype=np.int64)
            starts = np.flatnonzero(np.r_[True, src[1:] != src[:-1]]) if len(src) else np.empty(0, dtype=int)
            ids, clusters, values = [], [], []
            for a, b in zip(starts, np.r_[starts[1:], len(src)], strict=True):
                np.add.at(scratch, place[a:b], w[a:b])
                used = np.unique(place[a:b])
                ids += [int(src[a])] * len(used)
                clusters += names[used].tolist()
                values += scratch[used].tolist()
                scratch[used] = 0
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(clusters, pa.int64()), pa.array(values, pa.int64())], names=["src", "cluster", "rating"])

    return near.select("src", "cluster", "w").repartition("src").sortWithinPartitions("src").mapInArrow(sparse, LIGHT)


def may_be_heavy(graph: Graph, t_bump: int) -> DataFrame:
    """(src) of the vertices of t_bump edges or more, at most 2m / t_bump; others cannot be bumped, whatever the labels."""
    return graph.edges.groupBy("src").agg(F.count("*").alias("degree")).where(F.col("degree") >= t_bump).select("src")


def bumped(active: DataFrame, labels: DataFrame, t_bump: int, may: DataFrame | None = None, salts: int = 16) -> DataFrame:
    """(id, nc) of the vertices with t_bump neighbouring clusters or more; may: those that could be bumped, where they are known."""
    if may is None:
        may = active.groupBy("src").agg(F.count("*").alias("degree")).where(F.col("degree") >= t_bump).select("src")
    parts = rated_edges(active.join(may, "src", "left_semi"), labels).groupBy("src", (scramble("dst", 5) % salts).alias("salt"), "cluster").agg(F.sum("w").alias("w"))
    heavy = parts.groupBy(F.col("src").alias("id"), "cluster").agg(F.sum("w").alias("rating"))
    return heavy.groupBy("id").agg(F.count("*").alias("nc")).where(F.col("nc") >= t_bump)


def lp_round_two_phase(graph: Graph, labels: DataFrame, seed: int = 1, part: int = 0, parts: int = 1, cap: int | None = None, t_bump: int = T_BUMP, salts: int = 16, rating_map: str = "hash") -> DataFrame:
    """As lp_round_single, with the same result, in two phases. A vertex of fewer than t_bump edges cannot be bumped and is rated whole,
    in one task, after one exchange by the vertex; the edges of the others are summed from many tasks, first by (vertex, salt,
    cluster), so that no vertex's edges meet in one place unsummed."""
    edges = active_edges(graph, seed, part, parts)
    return advanced(state_of(graph, labels, seed, part, parts), edges, cap, may_be_heavy(graph, t_bump), True, salts, rating_map).select("id", "cluster")


def flush_stats(edges: DataFrame, labels: DataFrame, t_bump: int, salts: int = 16) -> DataFrame:
    """Of the heavy vertices: edges, entries of the buffers (one for each salt) that are flushed, and flushes of tables of t_bump entries."""
    nc = distinct_clusters(edges, labels).where(F.col("nc") >= t_bump).select(F.col("id").alias("src"))
    entries = rated_edges(edges, labels).join(nc, "src").groupBy("src", (scramble("dst", 5) % salts).alias("salt")).agg(F.count("*").alias("edges"), F.countDistinct("cluster").alias("entries"))
    flushes = F.ceil(F.col("entries") / F.lit(t_bump))
    sums = entries.agg(F.countDistinct("src").alias("heavy"), F.coalesce(F.sum("edges"), F.lit(0)).alias("edges"), F.coalesce(F.sum("entries"), F.lit(0)).alias("updates"), F.coalesce(F.sum(flushes), F.lit(0)).cast("long").alias("flushes"))
    return sums.withColumn("updates_saved", F.col("edges") - F.col("updates"))


def label_propagation(graph: Graph, rounds: int = ROUNDS, seed: int = 1, parts: int = 2, cap: int | None = None, two_phase: bool = False, t_bump: int = T_BUMP, labels: DataFrame | None = None, stats: RoundStats | None = None, count_bumped: bool = False) -> DataFrame:
    """Labels after some rounds. Each sub-batch's labels are written before the next reads them; what moved is counted as it is
    written. In two phases, the vertices that may be heavy are found once; if there are none, no round has a second phase. The sub-batches
    of a graph that fits a task run in one task each."""
    graph = graph.together()
    with staying(graph.vertices.sparkSession, graph.in_task()):
        start = graph.vertices.join(graph.held(labels), "id").select("id", "w", "cluster") if labels is not None else graph.vertices.select("id", "w", F.col("id").alias("cluster"))
        now = graph.gathered(cut(prepared(start, seed, 0, parts)))
        groups = graph.groups if not count_bumped else None
        summed = graph if groups is None else Graph(graph.vertices, active_edges(graph, seed, 0, 1, groups))  # what is not rated by groups
        may = graph.gathered(cut(may_be_heavy(summed, t_bump))) if two_phase else None
        if may is not None and may.isEmpty():
            may = None
        for r in range(rounds):
            moved = heavy = entries = 0
            for part in range(parts):
                edges = graph.gathered(active_edges(graph, seed + r, part, parts, groups))
                if may is not None and stats is not None and count_bumped:
                    found = bumped(edges, now.select("id", "cluster"), t_bump, may).agg(F.count("*"), F.coalesce(F.sum("nc"), F.lit(0))).first()
                    heavy, entries = heavy + found[0], entries + found[1]
                step, seen = advanced(now, edges, cap, may, two_phase, groups=groups, gathered=graph.in_task()), Observation()
                step = step.observe(seen, F.coalesce(F.sum((F.col("cluster") != F.col("before")).cast("long")), F.lit(0)).alias("moved"))
                now = graph.gathered(cut(prepared(step, *((seed + r, part + 1) if part + 1 < parts else (seed + r + 1, 0)), parts)))
                moved += seen.get["moved"]
            if stats is not None:
                stats.moved.append(moved)
                stats.bumped.append(heavy)
                stats.entries.append(entries)
            if not moved:
                break
    return now.select("id", "cluster")


def favourites(graph: Graph, labels: DataFrame, seed: int = 1) -> DataFrame:
    """(id, favourite): the best-rated cluster other than the vertex's own, whether there is room or not."""
    own = graph.vertices.join(labels, "id")
    if graph.groups is None:
        found = ratings(graph.edges, labels)
    else:
        by_edges, by_groups = ratings(active_edges(graph, seed, 0, 1, graph.groups), labels), best_in_groups(prepared(own, seed, 0, 1), graph.groups)
        found = by_edges.unionByName(by_groups.select(F.col("src").alias("id"), "cluster", "rating"))
    rated = found.join(labels.withColumnRenamed("cluster", "own"), "id").where("cluster <> own").select("id", "cluster", "rating")
    return choose(rated, own, seed).select("id", F.col("best").alias("favourite"))


def two_hop(graph: Graph, labels: DataFrame, favourite: DataFrame, cap: int) -> DataFrame:
    """Pairs up vertices that are alone in their cluster and have the same favourite: labels afterwards."""
    alone = labels.groupBy("cluster").agg(F.count("*").alias("n"), F.min("id").alias("id")).where("n = 1").select("id", "cluster")
    lonely = alone.join(favourite, "id").join(graph.vertices, "id")
    # pairs by place within a hash bucket of the favourite, so that a favourite of very many meets in no single task
    line = Window.partitionBy("favourite", "bucket").orderBy("id")
    placed = lonely.withColumn("bucket", F.floor(F.col("id") / 4096)).withColumn("place", F.row_number().over(line) - 1).withColumn("pair", F.floor(F.col("place") / 2))
    mate = Window.partitionBy("favourite", "bucket", "pair")
    joined = placed.withColumn("least", F.min("id").over(mate)).withColumn("both", F.sum("w").over(mate))
    moves = joined.where((F.col("both") <= cap) & (F.col("id") != F.col("least"))).select("id", F.col("least").alias("best"))
    return apply_moves(labels, moves)


def task_async_round(graph: Graph, labels: DataFrame, seed: int = 1, cap: int | None = None, tasks: int = 8) -> DataFrame:
    """A round in which a task's vertices see the moves that were made before them in the task; other tasks' labels are of the
    round's start. Each task may use an equal share of each cluster's room, so caps hold. Edges are sorted by Spark, which may spill, and
    go through a task one vertex at a time; what it keeps are its moves. For neighbourhoods of bounded size."""
    own = graph.vertices.join(labels, "id").select(F.col("id").alias("src"), F.col("cluster").alias("own"), F.col("w").alias("vw"))
    far = labels.join(cluster_weights(graph.vertices, labels), "cluster").select(F.col("id").alias("dst"), "cluster", "weight")
    near = graph.edges.join(far, "dst").join(own, "src")
    rows = near.select((scramble("src", seed) % tasks).alias("task"), scramble("src", seed).alias("ord"), "src", "own", "vw", "dst", "cluster", "w", "weight")
    limit = cap

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, moved, used = None, {}, {}

        def move(vertex: tuple[int, int, int, int], near: list[tuple[int, int, int, int]]) -> int | None:
            """The cluster that a vertex (task, id, own cluster, weight) moves to, if any."""
            nonlocal task, moved, used
            if vertex[0] != task:
                task, moved, used = vertex[0], {}, {}
            _, v, mine, vw = vertex
            sums: dict[int, int] = {}
            room: dict[int, int] = {}
            for dst, cluster, w, weight in near:
                c = moved.get(dst, cluster)
                sums[c] = sums.get(c, 0) + w
                if c == cluster:
                    room[c] = weight
            fits = [c for c in sums if c == mine or limit is None or (c in room and used.get(c, 0) + vw <= max(0, limit - room[c]) // tasks)]
            best = max(fits, key=lambda c: (sums[c], c == mine, -((c * 48271 + seed) % MODULUS), -c), default=mine)
            if best == mine:
                return None
            moved[v], used[best] = best, used.get(best, 0) + vw
            return best

        def whole() -> Iterator[tuple[tuple[int, int, int, int], list[tuple[int, int, int, int]]]]:
            """Vertices with all their edges, which may go on in the next batch."""
            vertex, near = None, []
            for b in batches:
                t, v, mine, vw, dst, cluster, w, weight = (b.column(c).to_numpy() for c in ("task", "src", "own", "vw", "dst", "cluster", "w", "weight"))
                starts = (np.flatnonzero(v[1:] != v[:-1]) + 1).tolist() if len(v) else []
                for i, j in zip([0, *starts], [*starts, len(v)], strict=True):
                    if i == j:
                        continue
                    here = (int(t[i]), int(v[i]), int(mine[i]), int(vw[i]))
                    if vertex is not None and vertex != here:
                        yield vertex, near
                        near = []
                    vertex = here
                    near += zip(dst[i:j].tolist(), cluster[i:j].tolist(), w[i:j].tolist(), weight[i:j].tolist(), strict=True)
            if vertex is not None:
                yield vertex, near

        ids, bests = [], []
        for vertex, near in whole():
            best = move(vertex, near)
            if best is not None:
                ids.append(vertex[1]), bests.append(best)
            if len(ids) >= 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(bests, pa.int64())], names=["id", "best"])
                ids, bests = [], []
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(bests, pa.int64())], names=["id", "best"])

    moves = rows.repartition(tasks, "task").sortWithinPartitions("task", "ord", "src").mapInArrow(run, "id long, best long")
    return apply_moves(labels, moves)
