"""Multilevel partitioning end to end: coarsen, partition the coarsest graph, project and refine."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.operators import clustering, codec, contraction, initial, refinement
from gpart.operators.contraction import Level
from gpart.operators.metrics import block_cap
from gpart.session import cut, cut_counted, staying
from gpart.sources.graphs import Graph


@dataclass(frozen=True)
class MultilevelConfig:
    """Settings; thresholds as in the paper unless a caller scales them to its graph."""

    eps: float = 0.03
    seed: int = 1
    rounds: int = clustering.ROUNDS
    parts: int = 2  #: sub-batches of a round
    t_bump: int = clustering.T_BUMP
    hub_degree: int = codec.HUB_DEGREE
    chunk: int = codec.CHUNK
    contraction_limit: int = 2000  #: coarsest vertices for each block
    least_shrink: float = 0.95  #: a level with more of its vertices left is the last
    two_hop_above: float = 0.6  #: pair up lonely vertices if more of a level's vertices would be left
    refine_rounds: int = 3
    tries: int = 4
    gain_table: str = "hybrid"
    two_phase: bool = True
    compress: bool = True
    one_pass: bool = True
    compress_levels: int = 1
    fm: bool = False


PRESETS = {
    "base": {"two_phase": False, "compress": False, "one_pass": False},
    "tp": {"compress": False, "one_pass": False},
    "tp-gc": {"one_pass": False},
    "lean-lp": {},
    "lean-fm": {"fm": True},
}


@dataclass
class Result:
    partition: DataFrame
    cap: int
    cap_relaxed: bool
    levels: list[Level]
    coded_bytes: int | None = None
    counters: clustering.RoundStats = field(default_factory=clustering.RoundStats)


def level_of(graph: Graph, parents: DataFrame | None) -> Level:
    vertices, n = cut_counted(graph.vertices)
    if graph.coded is not None or graph.groups is not None:  # their edges are never written
        graph, m = replace(graph, vertices=vertices), graph.count_edges()
    else:
        edges, m = cut_counted(graph.edges)
        graph = Graph(vertices, edges, graph.keys)
    return Level(replace(graph, size=n + m), cut(parents) if parents is not None else None, n, m)


def should_stop(n: int, before: int | None, k: int, cfg: MultilevelConfig) -> bool:
    return n <= cfg.contraction_limit * k or (before is not None and n > cfg.least_shrink * before)


def cluster_cap(total: int, n: int, k: int, cfg: MultilevelConfig) -> int:
    """The largest cluster: a small share of a block, so that blocks can be balanced on the coarsest level."""
    return max(1, int(cfg.eps * total / max(1, min(k, n // max(1, cfg.contraction_limit)))))


def coarsen_once(level: Level, total: int, k: int, cfg: MultilevelConfig, counters: clustering.RoundStats) -> Level:
    with staying(level.graph.vertices.sparkSession, level.graph.in_task()):
        return level_of(*contracted_once(level, total, k, cfg, counters))


def contracted_once(level: Level, total: int, k: int, cfg: MultilevelConfig, counters: clustering.RoundStats) -> tuple[Graph, DataFrame]:
    """The coarse graph of a level's clusters, and parents; not yet written."""
    graph, cap = level.graph.together(), cluster_cap(total, level.n, k, cfg)
    labels = clustering.label_propagation(graph, cfg.rounds, cfg.seed, cfg.parts, cap, cfg.two_phase, cfg.t_bump, stats=counters)
    if labels.select("cluster").distinct().count() > cfg.two_hop_above * level.n:
        labels = graph.gathered(cut(clustering.two_hop(graph, labels, clustering.favourites(graph, labels, cfg.seed), cap)))
    # ids are ranks in every form, so that all steps of the ladder see the same coarse graph
    if graph.groups is not None:
        coarse, parents = contraction.contract_groups(graph, labels)
    elif cfg.one_pass:
        _, parents, coarse = contraction.contract_one_pass(graph, labels, cfg.t_bump if cfg.two_phase else None)
    else:
        coarse, parents = contraction.contract_buffered(graph, labels)
    return coarse, parents


def coarsen(graph: Graph, k: int, cfg: MultilevelConfig, counters: clustering.RoundStats | None = None) -> list[Level]:
    """Levels from the input to the coarsest."""
    levels = [level_of(graph, None)]
    total = graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    while not should_stop(levels[-1].n, levels[-2].n if len(levels) > 1 else None, k, cfg):
        levels.append(coarsen_once(levels[-1], total, k, cfg, counters or clustering.RoundStats()))
    return levels


def require_levels(levels: list[Level], k: int, cfg: MultilevelConfig) -> None:
    """Fails if a graph that the settings mean to coarsen, with room for clusters of two, got no smaller level."""
    top = levels[0]
    total = top.graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    if not should_stop(top.n, None, k, cfg) and cluster_cap(total, top.n, k, cfg) > 1 and levels[-1].n >= top.n:
        raise RuntimeError(f"{top.n} vertices and {top.m} directed edges were not coarsened")


def compressed_input(graph: Graph, cfg: MultilevelConfig) -> tuple[Graph, int]:
    """The graph as coded rows, whose edges are decoded wherever they are read and never written, and the coded bytes."""
    if graph.groups is not None:  # the lists of the groups' members are coded, not each member's neighbours
        groups, size = codec.compress_groups(graph.groups, cfg.hub_degree, cfg.chunk)
        return Graph(graph.vertices, groups.edges(), graph.keys, groups=groups), size
    weighted = not graph.edges.where("w <> 1").isEmpty()
    coded = cut(codec.compress(codec.to_csr(graph, cfg.hub_degree, cfg.chunk), weighted=weighted))
    size = coded.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    return Graph(graph.vertices, codec.decompress(coded, weighted).select("src", "dst", "w"), graph.keys, coded, weighted), size


def first_partition(level: Level, k: int, cap: int, cfg: MultilevelConfig) -> DataFrame:
    """A partition of the coarsest level: solved in tasks, or, where it did not shrink enough to fit one, by label propagation from
    blocks of consecutive ids."""
    if level.m <= initial.MOST_EDGES:
        return initial.initial_partition(level.graph, k, cfg.eps, cfg.seed, cfg.tries, fm=cfg.fm)
    start = level.graph.vertices.select("id", F.floor(F.col("id") * k / F.lit(max(level.n, 1))).cast("int").alias("block"))
    spread = refinement.refine_lp(level.graph, cut(start), cap, cfg.rounds, cfg.seed, cfg.parts)
    return refinement.rebalance(level.graph, spread, k, cap, cfg.seed)


def refine(level: Level, partition: DataFrame, k: int, cap: int, cfg: MultilevelConfig) -> DataFrame:
    partition = refinement.refine_lp(level.graph, partition, cap, cfg.refine_rounds, cfg.seed, cfg.parts)
    if cfg.fm:
        partition = refinement.refine_fm(level.graph, partition, k, cap, cfg.gain_table, seed=cfg.seed)
    return partition


def partition(graph: Graph, k: int, preset: str = "lean-lp", cfg: MultilevelConfig | None = None, **changes) -> Result:
    """k blocks of the graph. Presets: base, tp, tp-gc, lean-lp (all optimisations), lean-fm (with k-way local search)."""
    cfg = replace(cfg or MultilevelConfig(), **PRESETS[preset], **changes)
    coded = None
    if cfg.compress and cfg.compress_levels:
        graph, coded = compressed_input(graph, cfg)
    counters = clustering.RoundStats()
    levels = coarsen(graph, k, cfg, counters)
    total = levels[0].graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    cap, relaxed = block_cap(total, k, cfg.eps)
    found = first_partition(levels[-1], k, cap, cfg)
    for number in range(len(levels) - 1, -1, -1):
        found = cut(refine(levels[number], found, k, cap, cfg))
        if number == 0:
            found = refinement.rebalance(levels[0].graph, found, k, cap, cfg.seed)
        else:
            finer = levels[number - 1].graph
            found = cut(refinement.project(finer.held(found), finer.gathered(levels[number].parents)))
    return Result(found, cap, relaxed, levels, coded, counters)


def shape_of_plans(graph: Graph, cfg: MultilevelConfig) -> str:
    """The operators of a sub-batch's plan on a level, without names and numbers, and the form of contraction."""
    labels = clustering.singletons(graph.vertices)
    step = clustering.lp_round_two_phase(graph, labels, cfg.seed, 0, cfg.parts, None, cfg.t_bump) if cfg.two_phase else clustering.lp_round_single(graph, labels, cfg.seed, 0, cfg.parts)
    lines = step._jdf.queryExecution().executedPlan().toString().splitlines()
    return "\n".join([*(re.sub(r"[^A-Za-z].*", "", line.lstrip(" :+-*()0123456789")) for line in lines), "one pass" if cfg.one_pass else "buffered"])


def hierarchy(levels: list[Level], spark) -> DataFrame:
    """(level, n, directed_edges) of a hierarchy."""
    return spark.createDataFrame([(i, x.n, x.m) for i, x in enumerate(levels)], "level int, n long, directed_edges long")


def partition_extending(graph: Graph, k: int, first: int = 2, cfg: MultilevelConfig | None = None) -> Result:
    """For many blocks: the coarsest graph is split into a few, and blocks are split further while uncoarsening, whenever a level
    has enough vertices for each; each block's inner graph is split in a task of its own, all of them on the finest level whose blocks
    fit one."""
    cfg = replace(cfg or MultilevelConfig(), **PRESETS["lean-lp"])
    levels = coarsen(graph, first, cfg)
    total = levels[0].graph.vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    cap, relaxed = block_cap(total, k, cfg.eps)

    def spread(count: int) -> list[int]:
        """How many final blocks each of `count` blocks stands for."""
        return [k * (i + 1) // count - k * i // count for i in range(count)]

    now = min(first, k)
    found = first_partition(levels[-1], now, block_cap(total, now, cfg.eps)[0], cfg)
    for number in range(len(levels) - 1, -1, -1):
        level = levels[number]
        last = number == 0 or levels[number - 1].m > initial.MOST_INNER * now  # on the next level a block would not fit its task
        goal = k if last else max(now, min(k, now * max(1, level.n // max(1, cfg.contraction_limit * now))))
        if goal > now:
            shares = {b: goal * (b + 1) // now - goal * b // now for b in range(now)}
            found = cut(initial.extend_blocks(level.graph, found, shares, -(-total // goal) if goal < k else cap, cfg.seed))
            now = goal
        found = cut(refine(level, found, now, max(cap * max(spread(now)), -(-total // now)), cfg))
        found = refinement.rebalance(level.graph, found, k, cap, cfg.seed) if number == 0 else cut(refinement.project(found, level.parents))
    return Result(found, cap, relaxed, levels)
