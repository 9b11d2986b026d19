"""What the methods are compared with: hashing, flat label propagation, matching hierarchies, streaming, semi-external."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.functions.columns import MODULUS, scramble
from gpart.operators import contraction, local, refinement
from gpart.operators.clustering import label_propagation
from gpart.operators.codec import to_csr
from gpart.operators.initial import initial_partition
from gpart.operators.metrics import block_cap
from gpart.plans.multilevel import MultilevelConfig, Result, level_of
from gpart.session import cut
from gpart.sources.graphs import Graph


def stream_hash(vertices: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """(id, block) by a hash of the id."""
    return vertices.select("id", (scramble("id", seed) % k).cast("int").alias("block"))


def flat_lp(graph: Graph, k: int, cap: int, rounds: int = 5, seed: int = 1, parts: int = 2) -> DataFrame:
    """No hierarchy: size-constrained label propagation from a hashed start."""
    return refinement.refine_lp(graph, cut(stream_hash(graph.vertices, k, seed)), cap, rounds, seed, parts)


def flat_lp_step(graph: Graph, k: int, cap: int, seed: int = 1) -> DataFrame:
    """One synchronous sub-batch of flat_lp, for exact comparison."""
    return refinement.refine_lp_round(graph, stream_hash(graph.vertices, k, seed), cap, seed, 0, 2)


def matching_round(graph: Graph, mates: DataFrame, cap: int, seed: int = 1) -> DataFrame:
    """Each unmatched vertex proposes to its heaviest unmatched neighbour, ties by a hash of the pair; mutual proposals match.
    mates: (id, cluster), cluster = id where unmatched; a pair's cluster is its smaller id. The hash is a product: a linear one rises
    or falls along consecutive ids, so that on chains and windows everyone proposes the same way and nothing is mutual."""
    pairs = mates.groupBy("cluster").agg(F.count("*").alias("n")).where("n = 1").select(F.col("cluster").alias("id"))
    free = graph.vertices.join(pairs, "id").select("id", "w")
    a, b = (free.select(F.col("id").alias(s), F.col("w").alias(t)) for s, t in (("src", "wa"), ("dst", "wb")))
    tie = -(scramble(F.least("src", "dst"), seed) * scramble(F.greatest("src", "dst"), seed + 7) % MODULUS)
    open_ = graph.edges.join(a, "src").join(b, "dst").where(F.col("wa") + F.col("wb") <= cap)
    wish = open_.groupBy("src").agg(F.max(F.struct("w", tie.alias("t"), (-F.col("dst")).alias("d"))).alias("x")).select("src", (-F.col("x.d")).alias("dst"))
    back = wish.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    mutual = wish.join(back, ["src", "dst"]).where("src < dst")
    moves = mutual.select(F.col("dst").alias("id"), F.col("src").alias("best"))
    return mates.join(moves, "id", "left").select("id", F.coalesce("best", "cluster").alias("cluster"))


def matching_multilevel(graph: Graph, k: int, cfg: MultilevelConfig | None = None, rounds: int = 4, enforce_balance: bool = False) -> Result:
    """A hierarchy of heavy-edge matchings; balance is only aimed at, unless enforced."""
    cfg = cfg or MultilevelConfig()
    levels = [level_of(graph, None)]
    total = levels[0].graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    cap, relaxed = block_cap(total, k, cfg.eps)
    loose = cap if enforce_balance else int(1.3 * cap) + 1
    while levels[-1].n > cfg.contraction_limit * k:
        current = levels[-1]
        mates = cut(current.graph.vertices.select("id", F.col("id").alias("cluster")))
        for r in range(rounds):
            mates = cut(matching_round(current.graph, mates, max(2, total // (2 * k)), cfg.seed + r))
        after = level_of(*contraction.contract_buffered(current.graph, mates))
        if after.n > cfg.least_shrink * current.n:
            break
        levels.append(after)
    found = initial_partition(levels[-1].graph, k, cfg.eps if enforce_balance else 0.3, cfg.seed, cfg.tries)
    for number in range(len(levels) - 1, -1, -1):
        found = cut(refinement.refine_lp(levels[number].graph, found, loose, cfg.refine_rounds, cfg.seed, cfg.parts))
        if number:
            found = cut(refinement.project(found, levels[number].parents))
    if enforce_balance:
        found = refinement.rebalance(levels[0].graph, found, k, cap, cfg.seed)
    return Result(found, cap, relaxed, levels)


def matching_distributed(graph: Graph, k: int, parts: int = 8, cfg: MultilevelConfig | None = None) -> Result:
    """The same with as many synchronous sub-batches as parts exchange."""
    return matching_multilevel(graph, k, replace(cfg or MultilevelConfig(), parts=max(2, parts // 2)), enforce_balance=True)


def direct(graph: Graph, k: int, eps: float = 0.03, seed: int = 1) -> DataFrame:
    """The input graph itself, without a hierarchy: size-constrained label propagation from blocks of consecutive ids."""
    n, total = graph.vertices.agg(F.count("*"), F.coalesce(F.sum("w"), F.lit(0))).first()
    start = graph.vertices.select("id", F.floor(F.col("id") * k / F.lit(max(n, 1))).cast("int").alias("block"))
    return refinement.refine_lp(graph, cut(start), block_cap(total, k, eps)[0], 5, seed)


def in_order(graph: Graph) -> DataFrame:
    """The vertex stream: whole neighbourhoods by rising id, in one partition, as a one-pass partitioner reads them."""
    rows = to_csr(graph, hub_degree=1 << 62).join(graph.vertices, "id").select("id", "w", "nbrs", "wts")
    return rows.coalesce(1).sortWithinPartitions("id")


def streamed(graph: Graph, place) -> DataFrame:
    """One pass over the vertex stream: place(rows, blocks) gives the blocks of a run of vertices and remembers them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: dict = {}
        for b in batches:
            rows = b.to_pylist()
            blocks = place(rows, state)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(blocks, pa.int32())], names=["id", "block"])
        rest = place(None, state)
        if rest:
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in rest], pa.int64()), pa.array([x for _, x in rest], pa.int32())], names=["id", "block"])

    return in_order(graph).mapInArrow(run, "id long, block int")


def greedy_place(k: int, cap: int, score):
    """Each vertex goes to the block of the best score among those with room (the lightest if none has)."""

    def place(rows, state):
        if rows is None:
            return []
        where, loads = state.setdefault("where", {}), state.setdefault("loads", [0] * k)
        out = []
        for r in rows:
            inside: dict[int, int] = {}
            for u, w in zip(r["nbrs"], r["wts"], strict=True):
                if (b := where.get(u)) is not None:
                    inside[b] = inside.get(b, 0) + w
            fits = [b for b in range(k) if loads[b] + r["w"] <= cap] or [min(range(k), key=loads.__getitem__)]
            best = max(fits, key=lambda b: (score(inside.get(b, 0), loads[b]), -loads[b], -b))
            where[r["id"]] = best
            loads[best] += r["w"]
            out.append(best)
        return out

    return place


def stream_ldg(graph: Graph, k: int, cap: int) -> DataFrame:
    """Linear greedy: neighbours in the block times the share of its room that is left."""
    return streamed(graph, greedy_place(k, cap, lambda inside, load: inside * (1 - load / cap)))


def stream_penalty(graph: Graph, k: int, cap: int, gamma: float = 1.5) -> DataFrame:
    """Neighbours in the block less a convex penalty of its load."""
    n, total = graph.vertices.agg(F.count("*"), F.sum("w")).first()
    m = graph.edges.count() / 2
    alpha = m * k ** (gamma - 1) / max(1, total) ** gamma
    return streamed(graph, greedy_place(k, cap, lambda inside, load: inside - alpha * gamma * load ** (gamma - 1)))


def stream_buffered(graph: Graph, k: int, cap: int, buffer: int = 1024, seed: int = 1) -> DataFrame:
    """Buffers of vertices in order: each is a graph of its own, with a heavy stand-in for every block that earlier vertices
    are in, which does not move; it is partitioned greedily, improved by local search, and forgotten but for the blocks."""
    import random

    def settle(rows: list[dict], state: dict) -> list[int]:
        where, loads = state.setdefault("where", {}), state.setdefault("loads", [0] * k)
        place = {r["id"]: i for i, r in enumerate(rows)}
        n = len(rows)
        near, blocks = [], []
        now = list(loads)
        for r in rows:
            own: dict[int, int] = {}
            inside: dict[int, int] = {}
            for u, w in zip(r["nbrs"], r["wts"], strict=True):
                if u in place:
                    own[place[u]] = own.get(place[u], 0) + w
                    if place[u] < len(blocks):
                        inside[blocks[place[u]]] = inside.get(blocks[place[u]], 0) + w
                elif u in where:
                    own[n + where[u]] = own.get(n + where[u], 0) + w
                    inside[where[u]] = inside.get(where[u], 0) + w
            near.append(list(own.items()))
            fits = [b for b in range(k) if now[b] + r["w"] <= cap] or [min(range(k), key=now.__getitem__)]
            best = max(fits, key=lambda b: (inside.get(b, 0) * (1 - now[b] / cap), -now[b], -b))
            blocks.append(best)
            now[best] += r["w"]
        g = local.LocalGraph([r["w"] for r in rows] + loads, near + [[] for _ in range(k)])
        spots = blocks + list(range(k))
        rng = random.Random(seed)
        for _ in range(3):
            if not local.search(g, spots, [cap] * k, [v for v in local.boundary(g, spots) if v < n], rng, once=set(range(n, n + k))):
                break
        for r, b in zip(rows, spots, strict=False):
            where[r["id"]] = b
            loads[b] += r["w"]
        return spots[:n]

    def place(rows, state):
        if rows is None:
            return []
        out: list[int] = []
        for start in range(0, len(rows), buffer):
            out += settle(rows[start : start + buffer], state)
        return out

    return streamed(graph, place)


def semi_external(graph: Graph, k: int, passes: int = 5, eps: float = 0.03, seed: int = 1, limit: int = 2000, path: str | None = None) -> DataFrame:
    """Labels alone are kept between passes over edges on disk: clustering passes, contraction of what is left, then passes of
    refinement by label propagation only. path: where the edges are; they are read again in every pass, never cached."""
    spark = graph.vertices.sparkSession
    if path is not None:
        graph.edges.write.mode("overwrite").parquet(path)
        graph = Graph(graph.vertices, spark.read.parquet(path))
    n, total = graph.vertices.agg(F.count("*"), F.coalesce(F.sum("w"), F.lit(0))).first()
    cap = block_cap(total, k, eps)[0]
    labels = label_propagation(graph, passes, seed, 2, max(1, int(eps * total / k)))
    coarse = level_of(*contraction.contract(graph, labels))
    inner = coarse
    chain = [coarse]
    while inner.n > limit * k:
        labels = label_propagation(inner.graph, passes, seed, 2, max(1, int(eps * total / k)))
        after = level_of(*contraction.contract(inner.graph, labels))
        if after.n > 0.95 * inner.n:
            break
        chain.append(after)
        inner = after
    found = initial_partition(inner.graph, k, eps, seed)
    for level, finer in zip(reversed(chain), [*reversed([c.graph for c in chain[:-1]]), graph], strict=True):
        found = cut(refinement.project(found, level.parents))
        found = refinement.refine_lp(finer, found, cap, 3, seed)
    return refinement.rebalance(graph, found, k, cap, seed)


