"""The experiments: run tables of solvers on graphs, the ladder of optimisations, comparisons, and their evaluation."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.operators import baselines, clustering, codec, contraction, gains, memory, metrics, refinement
from gpart.plans import distributed, multilevel
from gpart.session import cut
from gpart.sources import generators, graphs
from gpart.sources.graphs import Graph

RUNS = "graph string, algo string, k int, eps double, seed int, cut long, m_w long, max_block long, imbalance double, feasible boolean, seconds double, peak_bytes long, status string, beside int"
LIMIT_S = 3600.0
#: Runs that are solved side by side where a table does not ask for seconds of runs on their own.
SIDE_BY_SIDE = 5

Config = multilevel.MultilevelConfig
Solver = Callable[[Graph, int, int, Config], DataFrame | multilevel.Result]


def preset(name: str) -> Solver:
    return lambda g, k, cap, cfg: multilevel.partition(g, k, name, cfg)


SOLVERS: dict[str, Solver] = {
    "base": preset("base"), "tp": preset("tp"), "tp-gc": preset("tp-gc"), "lean-lp": preset("lean-lp"), "lean-fm": preset("lean-fm"),
    "dist-base": lambda g, k, cap, cfg: distributed.partition_distributed(g, k, 8, False, cfg),
    "dist-lean": lambda g, k, cap, cfg: distributed.partition_distributed(g, k, 8, True, cfg),
    "match-sm": lambda g, k, cap, cfg: baselines.matching_multilevel(g, k, cfg),
    "match-dm": lambda g, k, cap, cfg: baselines.matching_distributed(g, k, 8, cfg),
    "flat-dm": lambda g, k, cap, cfg: baselines.flat_lp(g, k, cap, seed=cfg.seed),
    "stream-hash": lambda g, k, cap, cfg: baselines.stream_hash(g.vertices, k, cfg.seed),
    "stream-ldg": lambda g, k, cap, cfg: baselines.stream_ldg(g, k, cap),
    "stream-penalty": lambda g, k, cap, cfg: baselines.stream_penalty(g, k, cap),
    "stream-buf": lambda g, k, cap, cfg: baselines.stream_buffered(g, k, cap, seed=cfg.seed),
    "semi-ext": lambda g, k, cap, cfg: baselines.semi_external(g, k, cfg.rounds, seed=cfg.seed, limit=cfg.contraction_limit),
    "direct": lambda g, k, cap, cfg: baselines.direct(g, k, seed=cfg.seed),
}


def scaled(n: int, k: int, seed: int = 1) -> Config:
    """Settings for runs on small graphs: thresholds of their scale and few rounds."""
    return Config(seed=seed, contraction_limit=max(4, n // (3 * k)), t_bump=64, rounds=2, refine_rounds=1)


def modelled_peak(g: Graph, found: DataFrame | multilevel.Result, algo: str, n: int, k: int) -> int | None:
    """The largest phase of the memory model, from the sizes of the run's own levels; for the solvers whose structures it knows."""
    step = {"base": "base", "tp": "tp", "tp-gc": "tp-gc", "lean-lp": "lean", "lean-fm": "lean"}.get(algo)
    if step is None or not isinstance(found, multilevel.Result):
        return None
    coarse = found.levels[min(1, len(found.levels) - 1)]
    entries = gains.gain_table_bytes(g, k).first()["entries"] if algo == "lean-fm" else 0
    sizes = memory.Sizes(n, found.levels[0].m // 2, coarse.n, coarse.m // 2, found.coded_bytes or 0, k=k, degree_sum_k=entries)
    by_phase: dict[str, int] = {}
    for phase, _, size in memory.components_of(sizes, *memory.LADDER[step], "fm" if algo == "lean-fm" else "lp"):
        by_phase[phase] = by_phase.get(phase, 0) + size
    return max(by_phase.values())


def measured(name: str, g: Graph, algo: str, k: int, seed: int, eps: float = 0.03, limit: float = LIMIT_S, beside: int = 0) -> tuple:
    """One row of RUNS: a solver on a graph, timed without building the graph. Failures are rows too: jobs of a run beyond the time
    limit are cancelled, and running out of memory, in Python or the JVM, ends the run and not the table. beside: how many other runs
    may be going meanwhile, and so be part of the seconds."""
    n, total = g.vertices.agg(F.count("*"), F.sum("w")).first()
    cap, _ = metrics.block_cap(total, k, eps)
    context = g.vertices.sparkSession.sparkContext
    group, late = f"run-{uuid.uuid4().hex}", threading.Event()

    def stop() -> None:
        late.set()
        context.cancelJobGroup(group)

    timer = threading.Timer(limit, stop)
    context.setJobGroup(group, f"{algo} on {name}", True)
    timer.start()
    began = time.time()
    try:
        result = SOLVERS[algo](g, k, cap, scaled(n, k, seed))
        found = cut(result.partition if isinstance(result, multilevel.Result) else result)
    except Exception as failure:  # noqa: BLE001
        if not late.is_set() and not isinstance(failure, MemoryError) and "OutOfMemory" not in str(failure) and "MemoryError" not in str(failure):
            raise
        return (name, algo, k, eps, seed, None, None, None, None, False, time.time() - began, None, "OOT" if late.is_set() else "OOM", beside)
    finally:
        timer.cancel()
        context.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.time() - began
    cut_w, m_w = metrics.cut_fraction(g.edges, found).select("cut", "m_w").first()
    heaviest, _, off = metrics.imbalance(g.vertices, found, k).first()
    return (name, algo, k, eps, seed, cut_w, m_w, heaviest, off, heaviest <= cap, seconds, modelled_peak(g, result, algo, n, k), "ok" if heaviest <= cap else "imbalanced", beside)


#: Runs that this application has done on their own, and those it has done beside others, whose seconds are no measure of the solver alone.
_MEASURED: dict[tuple, tuple] = {}
_BESIDE: dict[tuple, tuple] = {}


def run_table(spark: SparkSession, inputs: dict[str, Graph], algos: list[str], ks: list[int], seeds: list[int], home: str = "") -> DataFrame:
    """RUNS of every combination; a run that this application has done (on the graph of that name from `home`) is not repeated."""
    rows = []
    for name, g in inputs.items():
        for algo in algos:
            for k in ks:
                for seed in seeds:
                    key = (spark.sparkContext.applicationId, home, name, algo, k, seed)
                    if not home or key not in _MEASURED:
                        _MEASURED[key] = measured(name, g, algo, k, seed)
                    rows.append(_MEASURED[key])
    return spark.createDataFrame(rows, RUNS)


def run_beside(spark: SparkSession, name: str, g: Graph, algos: list[str], k: int, seed: int, home: str, width: int = SIDE_BY_SIDE) -> None:
    """Does those of the runs on a graph that this application has not done yet, side by side: each is a chain of short stages, between
    which the executors would wait for the driver to plan. Those given first begin first, so the longest should lead. They are kept
    apart from runs that were timed on their own."""
    keys = {(spark.sparkContext.applicationId, home, name, algo, k, seed): algo for algo in algos}
    todo = {key: algo for key, algo in keys.items() if key not in _MEASURED and key not in _BESIDE}
    if not todo:
        return
    width = min(width, len(todo))
    with ThreadPoolExecutor(width) as pool:  # a wrapper for each thread: it holds the thread's own copy of the local properties
        runs = {key: pool.submit(inheritable_thread_target(spark)(measured), name, g, algo, k, seed, beside=width - 1) for key, algo in todo.items()}
        try:
            for key, run in runs.items():
                _BESIDE[key] = run.result()
        finally:
            for run in runs.values():
                run.cancel()


def runs_so_far(spark: SparkSession, home: str) -> DataFrame:
    return spark.createDataFrame([row for key, row in (_BESIDE | _MEASURED).items() if key[:2] == (spark.sparkContext.applicationId, home)], RUNS)


def ladder_equal(g: Graph, k: int, cfg: multilevel.MultilevelConfig) -> DataFrame:
    """The number of steps of the ladder, of different cuts among them (the optimisations do not change the result), and of different
    physical plans for the first sub-batch and contraction of the input level (they do change how it is reached). The steps are solved
    side by side: each is a chain of short stages, between which the executors would wait for the driver to plan."""
    steps = ("base", "tp", "tp-gc", "lean-lp")
    spark = g.vertices.sparkSession
    with ThreadPoolExecutor(len(steps)) as pool:  # a wrapper for each thread: it holds the thread's own copy of the local properties
        runs = [pool.submit(inheritable_thread_target(spark)(multilevel.partition), g, k, step, cfg) for step in steps]
        results = [run.result() for run in runs]
    for result in results:
        multilevel.require_levels(result.levels, k, cfg)
    cuts = [metrics.edge_cut(g.edges, result.partition).first()[0] for result in results]
    plans = {multilevel.shape_of_plans(result.levels[0].graph, multilevel.replace(cfg, **multilevel.PRESETS[step])) for step, result in zip(steps, results, strict=True)}
    return g.vertices.sparkSession.createDataFrame([("presets", len(cuts)), ("different_cuts", len(set(cuts))), ("different_plans", len(plans))], "check_name string, value long")


# Workloads, on the tables of a folder or on generated graphs. The thresholds of the paper's large graphs are scaled by callers.

SET_A = ("copurchase", "cust_supp", "fk_tree", "event_chain", "event_window", "page_host", "page_path", "doc_line_links", "knn8")
HEAVY = ("cust_supp", "page_path", "token_bigram", "conv_turns", "doc_label")
WEB = ("page_host", "page_path", "doc_line_links", "token_bigram")


def inputs(spark: SparkSession, sf_dir: str, names) -> dict[str, Graph]:
    return {name: graphs.build_graph(spark, sf_dir, name).persisted() for name in names}


LADDER = ["base", "tp", "tp-gc", "lean-lp", "match-sm"]
LOCAL_SEARCH = ["lean-lp", "lean-fm"]
STREAMING = ["stream-hash", "stream-ldg", "stream-penalty", "stream-buf", "lean-lp"]


def ladder(spark: SparkSession, given: dict[str, Graph], ks=(8, 37, 64, 91, 128), seeds=(1, 2, 3, 4, 5), home: str = "") -> DataFrame:
    """Base and its optimisations one by one, and the rival (graphs of HEAVY for the subset of high degree)."""
    return run_table(spark, given, LADDER, list(ks), list(seeds), home)


def large_only(runs: DataFrame, at_least: int) -> DataFrame:
    """The runs on graphs of at least so much edge weight."""
    return runs.where(F.col("m_w") >= at_least)


def local_search(spark: SparkSession, given: dict[str, Graph], ks=(8, 37, 64, 91, 128, 1000), seeds=(1, 2, 3, 4, 5), home: str = "") -> DataFrame:
    """Label propagation against k-way local search."""
    return run_table(spark, given, LOCAL_SEARCH, list(ks), list(seeds), home)


def table_cuts(g: Graph, k: int, rounds: int = 2, seeds_per_region: int = 200) -> DataFrame:
    """(gain_table, cut, start_cut, overload): k-way local search from blocks of consecutive ids, with each of the three gain tables."""
    spark = g.vertices.sparkSession
    n, total = g.vertices.agg(F.count("*"), F.sum("w")).first()
    cap, _ = metrics.block_cap(total, k, 0.03)
    start = cut(g.vertices.select("id", F.least(F.floor(F.col("id") * k / F.lit(n)), F.lit(k - 1)).cast("int").alias("block")))
    before, rows = metrics.edge_cut(g.edges, start).first()[0], []
    for table in ("none", "full", "hybrid"):
        after = refinement.refine_fm(g, start, k, cap, table, rounds, seeds_per_region=seeds_per_region)
        rows.append((table, metrics.edge_cut(g.edges, after).first()[0], before, refinement.overload(g.vertices, after, cap)))
    return spark.createDataFrame(rows, "gain_table string, cut long, start_cut long, overload long")


def gain_tables(spark: SparkSession, given: dict[str, Graph], k: int = 1000) -> DataFrame:
    """Bytes of the three gain tables by graph; where the full one first outgrows a limit."""
    out = None
    for name, g in given.items():
        row = gains.gain_table_bytes(g, k).withColumn("graph", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def generated(spark: SparkSession, family: str, log_n: int, avg_deg: float) -> Graph:
    return (generators.rgg2d if family == "rgg2d" else generators.rhg)(spark, 1 << log_n, avg_deg).persisted()


def growing(spark: SparkSession, logs=range(10, 15), avg_deg: float = 16, k: int = 64, family: str = "rgg2d", seeds=(1, 2, 3), algos=("dist-lean", "dist-base", "match-dm", "flat-dm"), home: str = "") -> DataFrame:
    """Generated graphs of growing size: the distributed forms and their rivals."""
    return run_table(spark, {f"{family}{x}": generated(spark, family, x, avg_deg) for x in logs}, list(algos), [k], list(seeds), home)


def streaming_comparison(spark: SparkSession, given: dict[str, Graph], ks=(8, 64), seeds=(1, 2, 3), home: str = "") -> DataFrame:
    return run_table(spark, given, STREAMING, list(ks), list(seeds), home)


def semi_external_comparison(spark: SparkSession, given: dict[str, Graph], k: int = 16, seeds=(1,), home: str = "") -> DataFrame:
    return run_table(spark, given, ["semi-ext", "lean-lp"], [k], list(seeds), home)


def memory_breakdown(spark: SparkSession, g: Graph, k: int = 64, processors: int = 96, t_bump: int = 10_000, refine: str = "fm") -> DataFrame:
    """Modelled bytes by step of the ladder, phase and component for one graph and the clustering of one round of it."""
    n, m = g.vertices.count(), g.edges.count() // 2
    labels = clustering.label_propagation(g, 1)
    coarse, _ = contraction.contract(g, labels)
    coded = codec.coded_sizes(g).agg(F.sum("n_bytes")).first()[0]
    entries = gains.gain_table_bytes(g, k).first()["entries"]
    return memory.memory_model(spark, memory.Sizes(n, m, coarse.vertices.count(), coarse.edges.count() // 2, coded, processors, t_bump, k, entries), refine)


def io_overhead(spark: SparkSession, g: Graph) -> DataFrame:
    """(form, directed_edges, seconds, bytes): a graph loaded and kept plain, coded in one pass, and coded in two; edges as they are
    read back, bytes of the rows' payloads or lists."""
    rows = []
    for name, make in (("plain", lambda: codec.to_csr(g)), ("coded", lambda: codec.compress(codec.to_csr(g))), ("two_pass", lambda: codec.compress_two_pass(g))):
        began = time.time()
        kept = cut(make())
        seconds = time.time() - began
        size = F.col("n_bytes") if "n_bytes" in kept.columns else 16 * F.col("degree") + 8
        edges = kept.select(F.explode("nbrs")) if name == "plain" else codec.decompress(kept)
        rows.append((name, edges.count(), seconds, kept.agg(F.coalesce(F.sum(size), F.lit(0)).cast("long")).first()[0]))
    return spark.createDataFrame(rows, "form string, directed_edges long, seconds double, bytes long")


def weak_scaling(spark: SparkSession, base_log: int = 10, steps: int = 4, avg_deg: float = 16) -> DataFrame:
    """(parts, part, vertices, directed_edges, ghosts): work per part while parts and vertices double together."""
    out = None
    for i in range(steps):
        g = generated(spark, "rgg2d", base_log + i, avg_deg)
        rows = distributed.work_per_part(g, distributed.owned(g.vertices, 1 << (base_log + i), 1 << i)).withColumn("parts", F.lit(1 << i))
        out = rows if out is None else out.unionByName(rows)
    return out


def self_speedups(spark: SparkSession, given: dict[str, Graph], tasks=(1, 2, 4)) -> DataFrame:
    """The cumulative harmonic curve of rating sums and choices of every graph, with their work dealt over p tasks at a time."""
    rows = []
    for at, (_, g) in enumerate(given.items()):
        labels = cut(clustering.singletons(g.vertices))
        for p in tasks:
            edges = cut(g.edges.repartition(p, "src"))
            began = time.time()
            step = clustering.choose(clustering.ratings(edges.coalesce(p), labels).coalesce(p), g.vertices.join(labels, "id"), 1)
            step.write.format("noop").mode("overwrite").save()
            rows.append((at, p, time.time() - began))
    return metrics.speedup_curve(spark.createDataFrame(rows, "instance long, p int, seconds double"))


def measures_of(runs: DataFrame, base: str) -> DataFrame:
    """(measure, algo, value): the measures of runs over one run table, as numbers by algorithm."""
    rows = [
        metrics.status_counts(runs).select(F.lit("ok").alias("measure"), "algo", F.col("ok").cast("double").alias("value")),
        metrics.geo_mean(runs).select(F.lit("geo_mean_seconds"), "algo", "mean"),
        metrics.relative_cut(runs, base).groupBy("algo").agg(F.round(metrics.geo(F.greatest("relative", F.lit(1e-9))), 6).alias("value")).select(F.lit("relative_cut"), "algo", "value"),
        metrics.performance_profile(runs, [1.1]).select(F.lit("within_1.1_of_best"), "algo", "share"),
        runs.groupBy("algo").agg(F.max("peak_bytes").cast("double").alias("value")).where("value IS NOT NULL").select(F.lit("modelled_peak_bytes"), "algo", "value"),
    ]
    out = rows[0]
    for row in rows[1:]:
        out = out.union(row)
    return out


# Evaluation of runs. For exact comparison with SQL the measures are registered on a table of made-up runs, a function of `orders`; the
# workloads of gpart.workloads evaluate real ones.

RUNS_SQL = """runs AS (SELECT 'g' || (o_custkey % 12) AS graph, 'a' || (o_orderkey % 3) AS algo, CAST(8 * (1 + o_custkey % 2) AS INT) AS k, CAST(o_orderkey // 3 % 5 AS INT) AS seed,
  CAST(1000 + sum(o_custkey * 7 % 101) % 500 AS BIGINT) AS cut, CAST(1 + count(*) AS DOUBLE) AS seconds, CAST(sum(o_custkey) % 100000 AS BIGINT) AS peak_bytes,
  CASE sum(o_orderkey) % 23 WHEN 0 THEN 'OOM' WHEN 1 THEN 'OOT' WHEN 2 THEN 'imbalanced' ELSE 'ok' END AS status FROM orders GROUP BY 1, 2, 3, 4)"""
MEANS_SQL = RUNS_SQL + ", means AS (SELECT graph, algo, k, round(avg(cut), 6) AS cut, round(avg(seconds), 6) AS seconds, round(avg(peak_bytes), 6) AS peak_bytes, min(CAST(status = 'ok' AS INT)) = 1 AS ok FROM runs GROUP BY 1, 2, 3)"
TIMES_SQL = "times AS (SELECT o_custkey % 97 AS instance, CAST(pow(2, o_orderkey % 4) AS INT) AS p, CAST(1 + sum(o_custkey + o_orderkey) % 1000 AS DOUBLE) AS seconds FROM orders GROUP BY 1, 2), sp AS (SELECT t.instance, t.p, o.seconds AS sequential, round(o.seconds / t.seconds, 6) AS speedup FROM times t JOIN times o ON o.instance = t.instance AND o.p = 1 WHERE t.p > 1)"


def made_up_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = graphs.table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    status = F.sum("o_orderkey") % 23
    return orders.groupBy(F.concat(F.lit("g"), F.col("o_custkey") % 12).alias("graph"), F.concat(F.lit("a"), F.col("o_orderkey") % 3).alias("algo"), (8 * (1 + F.col("o_custkey") % 2)).cast("int").alias("k"), (F.floor(F.col("o_orderkey") / 3) % 5).cast("int").alias("seed")).agg(
        (1000 + F.sum(F.col("o_custkey") * 7 % 101) % 500).alias("cut"), (1 + F.count("*")).cast("double").alias("seconds"), (F.sum("o_custkey") % 100000).alias("peak_bytes"),
        F.when(status == 0, "OOM").when(status == 1, "OOT").when(status == 2, "imbalanced").otherwise("ok").alias("status"),
    )


def made_up_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = graphs.table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    return orders.groupBy((F.col("o_custkey") % 97).alias("instance"), F.pow(F.lit(2.0), F.col("o_orderkey") % 4).cast("int").alias("p")).agg((1 + F.sum(F.col("o_custkey") + F.col("o_orderkey")) % 1000).cast("double").alias("seconds"))


def on_runs(f):
    return lambda s, d: f(made_up_runs(s, d))


TAUS = [1.0, 1.02, 1.05, 1.1, 1.25, 1.5, 2.0]
RUN_QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "status_counts": (on_runs(metrics.status_counts), f"WITH {RUNS_SQL} SELECT algo, count(*) AS runs, count(*) FILTER (WHERE status = 'ok') AS ok, count(*) FILTER (WHERE status = 'imbalanced') AS imbalanced, count(*) FILTER (WHERE status = 'OOM') AS oom, count(*) FILTER (WHERE status = 'OOT') AS oot FROM runs GROUP BY 1"),
    "mean_over_seeds": (on_runs(metrics.mean_over_seeds), f"WITH {MEANS_SQL} SELECT * FROM means"),
    "geo_mean_seconds": (on_runs(metrics.geo_mean), f"WITH {MEANS_SQL} SELECT algo, count(*) AS instances, round(exp(avg(ln(greatest(seconds, 1e-9)))), 6) AS mean FROM means WHERE ok GROUP BY 1"),
    "relative_cut": (on_runs(lambda r: metrics.relative_cut(r, "a0")), f"WITH {MEANS_SQL} SELECT m.graph, m.k, m.algo, round(m.cut / greatest(b.cut, 1), 6) AS relative FROM means m JOIN means b ON b.graph = m.graph AND b.k = m.k AND b.algo = 'a0'"),
    "perf_profile": (on_runs(lambda r: metrics.performance_profile(r, TAUS)), f"WITH {MEANS_SQL}, rated AS (SELECT *, min(CASE WHEN ok THEN cut END) OVER (PARTITION BY graph, k) AS best FROM means), taus AS (SELECT unnest({TAUS}::DOUBLE[]) AS tau) SELECT algo, tau, round(avg(CAST(coalesce(ok AND cut <= tau * best + 1e-9, false) AS INT)), 6) AS share FROM rated, taus GROUP BY 1, 2"),
    "rolling_geo_ratio": (on_runs(lambda r: metrics.rolling_ratio(r, "a1", "a0", "cut")), f"WITH {MEANS_SQL}, b AS (SELECT x.graph, x.k, y.cut AS base, x.cut / y.cut AS ratio FROM means x JOIN means y ON y.graph = x.graph AND y.k = x.k WHERE x.algo = 'a1' AND y.algo = 'a0' AND x.ok AND y.ok) SELECT graph, k, round(ratio, 6) AS ratio, round(exp(avg(ln(ratio)) OVER (ORDER BY base, graph, k ROWS BETWEEN 49 PRECEDING AND CURRENT ROW)), 6) AS rolling FROM b"),
    "speedup_curve": (lambda s, d: metrics.speedup_curve(made_up_times(s, d)), f"WITH {TIMES_SQL} SELECT instance, p, sequential, round(count(speedup) OVER w / sum(1 / speedup) OVER w, 6) AS cumulative FROM sp WINDOW w AS (PARTITION BY p ORDER BY sequential DESC, instance ROWS UNBOUNDED PRECEDING)"),
    "harm_speedup": (lambda s, d: metrics.harm_speedup(made_up_times(s, d), [1, 64, 256]), f"WITH {TIMES_SQL}, l AS (SELECT unnest([1.0, 64.0, 256.0]::DOUBLE[]) AS lim) SELECT lim AS \"limit\", p, count(*) AS instances, round(count(*) / sum(1 / speedup), 6) AS speedup FROM sp, l WHERE sequential >= lim GROUP BY 1, 2"),
    "improvement_share": (on_runs(lambda r: metrics.improvement_share(r, "a1", "a0", 4.5)), f"WITH {MEANS_SQL}, g AS (SELECT 100 * (y.cut - x.cut) / greatest(y.cut, 1) AS gain FROM means x JOIN means y ON y.graph = x.graph AND y.k = x.k WHERE x.algo = 'a1' AND y.algo = 'a0' AND x.ok AND y.ok) SELECT count(*) AS instances, round(avg(CAST(gain >= 4.5 AS INT)), 6) AS share, round(quantile_cont(gain, 0.5), 6) AS median_gain FROM g"),
    "scaling_table": (lambda s, d: metrics.scaling_table(made_up_runs(s, d).select("algo", (F.col("cut") % 4 + 10).cast("int").alias("log_m"), F.col("k").alias("parts"), "seconds", "status")), f"WITH {RUNS_SQL} SELECT algo, CAST(cut % 4 + 10 AS INT) AS log_m, k AS parts, round(avg(seconds), 6) AS seconds, round(pow(2, CAST(cut % 4 + 10 AS INT)) / round(avg(seconds), 6), 3) AS edges_per_s FROM runs WHERE status = 'ok' GROUP BY 1, 2, 3"),
    "max_feasible": (lambda s, d: metrics.max_feasible(made_up_runs(s, d).select("algo", (F.col("cut") % 40 + 10).cast("int").alias("log_m"), "status")), f"WITH {RUNS_SQL}, r AS (SELECT algo, CAST(cut % 40 + 10 AS INT) AS log_m, status FROM runs), f AS (SELECT algo, min(log_m) FILTER (WHERE status <> 'ok') AS m FROM r GROUP BY 1) SELECT r.algo, max(log_m) AS largest_log_m FROM r JOIN f USING (algo) WHERE status = 'ok' AND (m IS NULL OR log_m < m) GROUP BY 1"),
}
