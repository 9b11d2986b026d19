"""The experiment workloads as queries, on real runs over the given tables and on generated graphs of a small size.

Where SQL cannot follow a solver, the rows hold what must be so whatever it does (sizes, balance, equal cuts of equal methods, which method
wins), and SQL states that; the runs themselves, with cuts, seconds and modelled bytes, are `workload_runs`.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart import oracles as sql
from gpart.operators import clustering, codec, memory, metrics
from gpart.plans import experiments, multilevel
from gpart.sources import generators, graphs
from gpart.sources.graphs import Graph

K = 4
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def query(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = (f, oracle)
        return f

    return put


def given(s: SparkSession, d: str, *names: str) -> dict[str, Graph]:
    from gpart.registry import built

    return {name: built(s, d, name) for name in names}


def weight_sql(name: str) -> str:
    return f"(SELECT CAST(sum(w) / 2 AS BIGINT) FROM ({sql.full(name, 'SELECT w FROM edges')}))"


def open_(stated, value):
    """1 or 0 where it is stated what must be so, else -1."""
    return F.when(stated, value.cast("long")).otherwise(F.lit(-1).cast("long"))


def union_sql(rows: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT {row}" for row in rows)


# ---- generated graphs ----


def uniform_sql(x: str, seed: int) -> str:
    return f"({sql.h(x, seed)}) * ({sql.h(f'{x} + 1', seed + 7)}) % {sql.M} / {float(sql.M)!r}::DOUBLE"


def rgg_sql(n: int, avg_deg: float, seed: int = 1) -> str:
    """Expressions down to vertices and edges of rgg2d, by all pairs."""
    r = math.sqrt(avg_deg / (n * math.pi))
    return (
        f"rp AS (SELECT i AS point, {uniform_sql('i', seed)} AS x, {uniform_sql('i', seed + 100)} AS y FROM (SELECT unnest(range(0, {n})) AS i)), "
        f"pts AS (SELECT row_number() OVER (ORDER BY floor(y / {r!r}), floor(x / {r!r}), point) - 1 AS id, x, y FROM rp), vertices AS (SELECT id, CAST(1 AS BIGINT) AS w FROM pts), "
        f"edges AS MATERIALIZED (SELECT a.id AS src, b.id AS dst, CAST(1 AS BIGINT) AS w FROM pts a JOIN pts b ON a.id <> b.id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {r * r!r})"
    )


def rhg_sql(n: int, avg_deg: float, gamma: float = 3.0, seed: int = 1) -> str:
    alpha = (gamma - 1) / 2
    xi = alpha / (alpha - 0.5)
    disk = 2 * math.log(2 * xi * xi * n / (math.pi * avg_deg))
    return (
        f"rp AS (SELECT i AS point, acosh(1 + {uniform_sql('i', seed)} * {math.cosh(alpha * disk) - 1!r}) / {alpha!r} AS r, {uniform_sql('i', seed + 100)} * 2 * {math.pi!r} AS t FROM (SELECT unnest(range(0, {n})) AS i)), "
        "pts AS (SELECT row_number() OVER (ORDER BY t, point) - 1 AS id, r, t FROM rp), vertices AS (SELECT id, CAST(1 AS BIGINT) AS w FROM pts), "
        f"edges AS MATERIALIZED (SELECT a.id AS src, b.id AS dst, CAST(1 AS BIGINT) AS w FROM pts a JOIN pts b ON a.id <> b.id AND cosh(a.r) * cosh(b.r) - sinh(a.r) * sinh(b.r) * cos(a.t - b.t) <= {math.cosh(disk)!r})"
    )


query("generator_rgg2d", f"WITH {rgg_sql(2048, 8)} SELECT src, dst, w FROM edges")(lambda s, d: generators.rgg2d(s, 2048, 8).edges)
query("generator_rhg", f"WITH {rhg_sql(1024, 8)} SELECT src, dst, w FROM edges")(lambda s, d: generators.rhg(s, 1024, 8).edges)


# ---- the ladder and its measures ----


@query("workload_ladder", " UNION ALL ".join(f"SELECT 'conv_turns' AS graph, '{a}' AS algo, CAST({K} AS INT) AS k, {weight_sql('conv_turns')} AS m_w, CAST({-1 if a == 'match-sm' else 1} AS BIGINT) AS feasible, CAST({-1 if a == 'match-sm' else 1} AS BIGINT) AS cut_of_base" for a in experiments.LADDER))
def _(s, d):
    """Balance and cuts of the ladder's steps; the rival's are open."""
    runs = experiments.ladder(s, given(s, d, "conv_turns"), (K,), (1,), d)
    base = runs.where("algo = 'base'").select("graph", "k", "seed", F.col("cut").alias("base_cut"))
    rival = F.col("algo") == "match-sm"
    return runs.join(base, ["graph", "k", "seed"]).select("graph", "algo", "k", "m_w", open_(~rival, F.col("feasible")).alias("feasible"), open_(~rival, F.col("cut") == F.col("base_cut")).alias("cut_of_base"))


@query("workload_large_only", f"SELECT 'conv_turns' AS graph, count(*) AS runs FROM (SELECT 1 FROM range({len(experiments.LADDER)})) WHERE {weight_sql('conv_turns')} >= 200 GROUP BY 1")
def _(s, d):
    return experiments.large_only(experiments.ladder(s, given(s, d, "conv_turns"), (K,), (1,), d), 200).groupBy("graph").agg(F.count("*").alias("runs"))


@query("workload_heavy_subset", sql.full("conv_turns", "SELECT 'conv_turns' AS graph, max(degree) >= 8 AS heavy FROM deg", sql.DEGREES))
def _(s, d):
    """The graphs whose largest degree reaches the scaled threshold."""
    (name, g), = given(s, d, "conv_turns").items()
    return g.edges.groupBy("src").agg(F.count("*").alias("degree")).agg(F.max("degree").alias("most")).select(F.lit(name).alias("graph"), (F.col("most") >= 8).alias("heavy"))


# ---- local search ----


@query("workload_gain_tables", sql.checks(("tables", 3), ("different_cuts", 1), ("worse_than_start", 0), ("overload", 0)))
def _(s, d):
    from gpart.registry import verdicts

    rows = [r for g in given(s, d, "conv_turns").values() for r in experiments.table_cuts(g, K).collect()]
    return verdicts(s, tables=len(rows), different_cuts=len({r["cut"] for r in rows}), worse_than_start=sum(r["cut"] > r["start_cut"] for r in rows), overload=sum(r["overload"] for r in rows))


@query("workload_lp_and_fm", union_sql([f"'conv_turns' AS graph, '{a}' AS algo, {weight_sql('conv_turns')} AS m_w, true AS feasible" for a in ("lean-lp", "lean-fm")]))
def _(s, d):
    return experiments.local_search(s, given(s, d, "conv_turns"), (K,), (1,), d).select("graph", "algo", "m_w", "feasible")


# ---- rivals ----


@query("workload_streaming", sql.full("conv_turns", "SELECT CAST((SELECT sum(e.w) FROM edges e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst WHERE e.src < e.dst AND a.block <> b.block) AS BIGINT) AS hash_cut, CAST(5 AS BIGINT) AS algos, CAST(0 AS BIGINT) AS worse_than_hash", sql.blocks(K)))
def _(s, d):
    """The hashed stream's cut, and how many of the others are worse."""
    runs = experiments.streaming_comparison(s, given(s, d, "conv_turns"), (K,), (1,), d).collect()
    hashed = next(r["cut"] for r in runs if r["algo"] == "stream-hash")
    return s.createDataFrame([(hashed, len(runs), sum(r["cut"] > hashed for r in runs))], "hash_cut long, algos long, worse_than_hash long")


@query("workload_semi_external", union_sql([f"'conv_turns' AS graph, '{a}' AS algo, CAST(16 AS INT) AS k, {weight_sql('conv_turns')} AS m_w, true AS feasible" for a in ("semi-ext", "lean-lp")]))
def _(s, d):
    return experiments.semi_external_comparison(s, given(s, d, "conv_turns"), 16, (1,), d).select("graph", "algo", "k", "m_w", "feasible")


@query("workload_growing", union_sql([f"'rgg2d{x}' AS graph, '{a}' AS algo, (WITH {rgg_sql(1 << x, 8)} SELECT CAST(count(*) / 2 AS BIGINT) FROM edges) AS m_w, CAST({-1 if a == 'flat-dm' else 1} AS BIGINT) AS feasible, CAST({-1 if a == 'flat-dm' else 1} AS BIGINT) AS cut_of_lean" for x in (9, 10) for a in ("dist-lean", "dist-base", "flat-dm")]))
def _(s, d):
    """Distributed forms on growing geometric graphs: compression does not change the cut."""
    runs = experiments.growing(s, (9, 10), 8, K, "rgg2d", (1,), ("dist-lean", "dist-base", "flat-dm"), d)
    lean = runs.where("algo = 'dist-lean'").select("graph", F.col("cut").alias("lean_cut"))
    rival = F.col("algo") == "flat-dm"
    return runs.join(lean, "graph").select("graph", "algo", "m_w", open_(~rival, F.col("feasible")).alias("feasible"), open_(~rival, F.col("cut") == F.col("lean_cut")).alias("cut_of_lean"))


@query("workload_weak_scaling", " UNION ALL ".join(f"SELECT CAST({1 << i} AS INT) AS parts, * FROM (WITH {rgg_sql(1 << 9 + i, 8)}, ow AS (SELECT id, CAST(id * {1 << i} // {1 << 9 + i} AS INT) AS part FROM vertices) SELECT o.part, count(DISTINCT o.id) AS vertices, count(e.dst) AS directed_edges, count(DISTINCT CASE WHEN b.part <> o.part THEN e.dst END) AS ghosts FROM ow o LEFT JOIN edges e ON e.src = o.id LEFT JOIN ow b ON b.id = e.dst GROUP BY 1)" for i in range(3)))
def _(s, d):
    return experiments.weak_scaling(s, 9, 3, 8).select("parts", "part", "vertices", "directed_edges", "ghosts")


@query("workload_many_blocks", sql.checks(("vertices", 1024), ("blocks_used", 64), ("out_of_range", 0), ("infeasible_blocks", 0)))
def _(s, d):
    """Many blocks by extension over a hierarchy: the graph has 16 vertices for each."""
    from gpart.registry import verdicts

    g = experiments.generated(s, "rgg2d", 10, 8)
    part = multilevel.partition_extending(g, 64, 4, multilevel.MultilevelConfig(contraction_limit=64, t_bump=64, rounds=2, refine_rounds=1)).partition
    return verdicts(s, vertices=part.select("id").distinct().count(), blocks_used=part.select("block").distinct().count(), out_of_range=part.where("block < 0 OR block >= 64").count(), infeasible_blocks=metrics.balance(g.vertices, part, 64).where("NOT feasible").count())


# ---- memory, counters, input and output ----

MEMORY_SIZES = "sz AS (SELECT (SELECT count(*) FROM vertices) AS n, (SELECT count(*) // 2 FROM edges) AS m, (SELECT count(*) FROM cv) AS cn, (SELECT count(*) // 2 FROM ce) AS cm, (SELECT sum(n_bytes) FROM sizes) AS coded, (SELECT sum(least(degree, 64)) FROM deg) AS entries)"
MEMORY_PHASES = (
    "ph AS (SELECT preset, phase, CAST(CASE phase WHEN 'cluster' THEN graph + 8 * n + CASE WHEN tp THEN 8 * n + 16 * 96 * 10000 ELSE 8 * n * 96 END WHEN 'contract' THEN graph + 8 * n + coarse + CASE WHEN op THEN 4096 ELSE coarse END "
    "ELSE graph + coarse + 4 * n + 8 * 64 + 12 * entries + 8 * n END AS BIGINT) AS bytes FROM (SELECT *, 16 * cm + 8 * cn AS coarse, CASE WHEN gc THEN coded ELSE 8 * (n + 1) + 16 * m END AS graph FROM sz, (VALUES ('base', false, false, false), ('tp', true, false, false), ('tp-gc', true, true, false), ('lean', true, true, true)) t(preset, tp, gc, op), (VALUES ('cluster'), ('contract'), ('refine')) u(phase)))"
)


@query("workload_memory", sql.full("cust_supp", "SELECT preset, phase, bytes, bytes = max(bytes) OVER (PARTITION BY preset) AS peak FROM ph", *sql.coded(), *sql.lp(1), sql.CONTRACT, MEMORY_SIZES, MEMORY_PHASES))
def _(s, d):
    """Bytes by step of the ladder and phase, from the sizes of the graph, its coded form and one contraction."""
    return memory.peak_by_phase(experiments.memory_breakdown(s, given(s, d, "cust_supp")["cust_supp"]))


def counters_sql(rounds: int, t: int) -> str:
    out, n = [], 0
    for r in range(rounds):
        part_rows = []
        for part in range(2):
            part_rows.append(f"SELECT (SELECT count(*) FROM l{n} a JOIN l{n + 1} b USING (id) WHERE a.c <> b.c) AS moved, count(*) AS bumped, coalesce(sum(nc), 0) AS entries FROM (SELECT e.src, count(DISTINCT l.c) AS nc FROM edges e JOIN l{n} l ON l.id = e.dst WHERE {sql.h('e.src', 1 + r)} % 2 = {part} GROUP BY 1 HAVING count(DISTINCT l.c) >= {t})")
            n += 1
        out.append(f"SELECT CAST({r} AS INT) AS round, CAST(sum(moved) AS BIGINT) AS moved, CAST(sum(bumped) AS BIGINT) AS bumped, CAST(sum(entries) AS BIGINT) AS entries FROM ({' UNION ALL '.join(part_rows)})")
    return sql.full("cust_supp", " UNION ALL ".join(out), *sql.lp(rounds))


@query("lp_round_counters", counters_sql(2, 16))
def _(s, d):
    """Vertices that moved and were bumped in each round, and entries of the bumped ones' tables."""
    stats = clustering.RoundStats()
    clustering.label_propagation(given(s, d, "cust_supp")["cust_supp"], 2, two_phase=True, t_bump=16, stats=stats, count_bumped=True)
    return s.createDataFrame([(i, *row) for i, row in enumerate(zip(stats.moved, stats.bumped, stats.entries, strict=True))], "round int, moved long, bumped long, entries long")


@query("workload_load", sql.full("event_window", "SELECT form, (SELECT count(*) FROM edges) AS directed_edges, CAST(CASE form WHEN 'plain' THEN (SELECT count(*) * 16 FROM edges) + (SELECT count(*) * 8 FROM vertices) ELSE (SELECT sum(n_bytes) FROM sizes) END AS BIGINT) AS bytes FROM (VALUES ('plain'), ('coded'), ('two_pass')) f(form)", *sql.coded()))
def _(s, d):
    """Plain and coded loads, read back; the ratios of their seconds are in workload_load_seconds."""
    return experiments.io_overhead(s, given(s, d, "event_window")["event_window"]).select("form", "directed_edges", "bytes")


@query("workload_load_seconds")
def _(s, d):
    return experiments.io_overhead(s, given(s, d, "event_window")["event_window"])


@query("workload_self_speedup")
def _(s, d):
    return experiments.self_speedups(s, given(s, d, "conv_turns", "event_window"))


@query("memory_pointer_bytes", "SELECT c_custkey, n_coarse, 16 * n_coarse AS begin_end, 8 * (n_coarse + 1) AS renamed FROM (SELECT c_custkey, count(o_orderkey) AS n_coarse FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1)")
def _(s, d):
    """Pointers of a coarse graph for each customer, with a vertex for each order; some have none."""
    orders = graphs.table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")
    sizes = graphs.table(s, d, "customer").select("c_custkey").join(orders, "c_custkey", "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n_coarse"))
    return sizes.withColumns({mode: memory.pointer_bytes(F.col("n_coarse"), mode) for mode in ("begin_end", "renamed")})


@query("memory_overcommit", sql.full("event_window", "SELECT CAST(10 * (SELECT count(*) FROM edges) AS BIGINT) AS reserved, CAST(least((total + 4095) // 4096, (10 * (SELECT count(*) FROM edges) + 4095) // 4096) * 4096 AS BIGINT) AS touched, CAST((total + 4095) // 4096 * 4096 - total AS BIGINT) AS waste FROM (SELECT CAST(sum(n_bytes) AS BIGINT) AS total FROM sizes)", *sql.coded()))
def _(s, d):
    """What a buffer for ten bytes an edge reserves, and what the coded graph touches of it."""
    g = given(s, d, "event_window")["event_window"]
    used = codec.coded_sizes(g).agg(F.sum("n_bytes")).first()[0]
    found = memory.overcommit(used, 10 * g.edges.count())
    return s.createDataFrame([(found["reserved"], found["touched"], found["waste"])], "reserved long, touched long, waste long")


# ---- the runs ----


@query("workload_runs")
def _(s, d):
    """Every run of the workloads above on this folder, with cut, balance, seconds and modelled bytes. Runs that none of them has done yet
    are done side by side, and say so; the measures of seconds in workload_measures are of runs on their own."""
    (name, g), = given(s, d, "conv_turns").items()
    experiments.run_beside(s, name, g, [*reversed(experiments.LOCAL_SEARCH), *experiments.LADDER, *experiments.STREAMING], K, 1, d)
    return experiments.runs_so_far(s, d)


@query("workload_measures")
def _(s, d):
    """Measures over those runs, against base."""
    g = given(s, d, "conv_turns")
    runs = experiments.ladder(s, g, (K,), (1,), d).unionByName(experiments.local_search(s, g, (K,), (1,), d)).unionByName(experiments.streaming_comparison(s, g, (K,), (1,), d)).dropDuplicates(["graph", "algo", "k", "seed"])
    return experiments.measures_of(runs, "base")
