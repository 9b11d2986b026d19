"""Cost and quality measures of partitions and of sets of runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gpart.sources.graphs import Graph


def edge_cut(edges: DataFrame, partition: DataFrame) -> DataFrame:
    """cut, in one row: the weight of edges between blocks, each edge once."""
    a, b = (partition.select(F.col("id").alias(s), F.col("block").alias(t)) for s, t in (("src", "ba"), ("dst", "bb")))
    return edges.where("src < dst").join(a, "src").join(b, "dst").where("ba <> bb").agg(F.coalesce(F.sum("w"), F.lit(0)).alias("cut"))


def cut_of(graph: Graph, partition: DataFrame) -> DataFrame:
    """edge_cut of a graph; of one kept as groups, from what each block has of a group."""
    if graph.groups is None:
        return edge_cut(graph.edges, partition)
    whole = graph.groups.by_block(partition, "block").groupBy("grp").agg(F.sum("s").alias("s"), F.sum(F.col("s") * F.col("s")).alias("inner"))
    return whole.agg(F.coalesce(F.sum(F.col("s") * F.col("s") - F.col("inner")) / 2, F.lit(0)).cast("long").alias("cut"))


def cut_fraction(edges: DataFrame, partition: DataFrame) -> DataFrame:
    """cut, m_w and cut as a share of the total edge weight."""
    a, b = (partition.select(F.col("id").alias(s), F.col("block").alias(t)) for s, t in (("src", "ba"), ("dst", "bb")))
    both = edges.where("src < dst").join(a, "src").join(b, "dst")
    sums = both.agg(F.coalesce(F.sum(F.when(F.col("ba") != F.col("bb"), F.col("w"))), F.lit(0)).alias("cut"), F.coalesce(F.sum("w"), F.lit(0)).alias("m_w"))
    return sums.withColumn("share", F.round(F.col("cut") / F.greatest("m_w", F.lit(1)), 6))


def block_cap(total: int, k: int, eps: float) -> tuple[int, bool]:
    """(cap, relaxed): floor of (1 + eps) total / k, or ceil(total / k) where that is larger and nothing else can hold."""
    strict, least = int((1 + eps) * total / k + 1e-9), -(-total // k)
    return max(strict, least), strict < least


def balance(vertices: DataFrame, partition: DataFrame, k: int, eps: float = 0.03) -> DataFrame:
    """block, weight, cap and whether the block is within it; empty blocks count."""
    spark = vertices.sparkSession
    cap, _ = block_cap(vertices.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0], k, eps)
    weights = vertices.join(partition, "id").groupBy("block").agg(F.sum("w").alias("weight"))
    blocks = spark.range(k).select(F.col("id").cast("int").alias("block"))
    return blocks.join(weights, "block", "left").select("block", F.coalesce("weight", F.lit(0)).alias("weight"), F.lit(cap).cast("long").alias("cap")).withColumn("feasible", F.col("weight") <= F.col("cap"))


def imbalance(vertices: DataFrame, partition: DataFrame, k: int) -> DataFrame:
    """max_block, avg_block and max / avg - 1."""
    weights = vertices.join(partition, "id").groupBy("block").agg(F.sum("w").alias("weight"))
    return weights.agg(F.max("weight").alias("max_block"), (F.sum("weight") / k).alias("avg_block")).select("max_block", F.round("avg_block", 6).alias("avg_block"), F.round(F.col("max_block") / F.col("avg_block") - 1, 6).alias("imbalance"))


# Runs: (graph, algo, k, eps, seed, cut, m_w, max_block, imbalance, feasible, seconds, peak_bytes, status, beside)


def status_counts(runs: DataFrame) -> DataFrame:
    """Of each algorithm: runs, infeasible results and failures of either kind."""
    one = lambda s: F.count(F.when(F.col("status") == s, 1))
    return runs.groupBy("algo").agg(F.count("*").alias("runs"), one("ok").alias("ok"), one("imbalanced").alias("imbalanced"), one("OOM").alias("oom"), one("OOT").alias("oot"))


def geo(x: Column) -> Column:
    return F.exp(F.avg(F.log(x)))


def harmonic(x: Column) -> Column:
    return F.count(x) / F.sum(1 / x)


def mean_over_seeds(runs: DataFrame) -> DataFrame:
    """Arithmetic means of cut, time and memory for each (graph, algo, k); only if every seed ended well."""
    ok = F.min((F.col("status") == "ok").cast("int")) == 1
    return runs.groupBy("graph", "algo", "k").agg(F.round(F.avg("cut"), 6).alias("cut"), F.round(F.avg("seconds"), 6).alias("seconds"), F.round(F.avg("peak_bytes"), 6).alias("peak_bytes"), ok.alias("ok"))


def geo_mean(runs: DataFrame, column: str = "seconds") -> DataFrame:
    """Geometric mean over instances of an algorithm's means over seeds; zero cuts count as one."""
    return mean_over_seeds(runs).where("ok").groupBy("algo").agg(F.count("*").alias("instances"), F.round(geo(F.greatest(F.col(column), F.lit(1e-9) if column == "seconds" else F.lit(1.0))), 6).alias("mean"))


def relative_cut(runs: DataFrame, base: str) -> DataFrame:
    """Each algorithm's mean cut over the base's, by instance."""
    means = mean_over_seeds(runs)
    own = means.where(F.col("algo") == base).select("graph", "k", F.col("cut").alias("base_cut"))
    return means.join(own, ["graph", "k"]).select("graph", "k", "algo", F.round(F.col("cut") / F.greatest("base_cut", F.lit(1.0)), 6).alias("relative"))


def performance_profile(runs: DataFrame, taus: list[float]) -> DataFrame:
    """algo, tau, share of instances whose cut is within tau times the best; failed runs are within nothing."""
    means = mean_over_seeds(runs)
    best = Window.partitionBy("graph", "k")
    rated = means.withColumn("best", F.min(F.when(F.col("ok"), F.col("cut"))).over(best))
    steps = runs.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double")
    within = F.col("ok") & (F.col("cut") <= F.col("tau") * F.col("best") + 1e-9)
    return rated.crossJoin(F.broadcast(steps)).groupBy("algo", "tau").agg(F.round(F.avg(F.coalesce(within, F.lit(False)).cast("int")), 6).alias("share"))


def rolling_ratio(runs: DataFrame, algo: str, base: str, column: str = "seconds", window: int = 50) -> DataFrame:
    """Instances in the order of the base's value, with the ratio to the base and the geometric mean of the last `window` ratios."""
    means = mean_over_seeds(runs).where("ok")
    a, b = (means.where(F.col("algo") == x).select("graph", "k", F.col(column).alias(y)) for x, y in ((algo, "own"), (base, "base")))
    both = a.join(b, ["graph", "k"]).withColumn("ratio", F.col("own") / F.col("base"))
    # one row for each instance of an experiment: a bounded table, so one window task is enough
    order = Window.orderBy("base", "graph", "k").rowsBetween(-(window - 1), 0)
    return both.select("graph", "k", F.round("ratio", 6).alias("ratio"), F.round(F.exp(F.avg(F.log("ratio")).over(order)), 6).alias("rolling"))


def speedups(times: DataFrame) -> DataFrame:
    """times: (instance, p, seconds). Self-relative speedups over p = 1."""
    one = times.where("p = 1").select("instance", F.col("seconds").alias("sequential"))
    return times.where("p > 1").join(one, "instance").select("instance", "p", "sequential", F.round(F.col("sequential") / F.col("seconds"), 6).alias("speedup"))


def speedup_curve(times: DataFrame) -> DataFrame:
    """For each p, instances by falling sequential time t with the harmonic mean speedup of those that take at least t."""
    longest = Window.partitionBy("p").orderBy(F.desc("sequential"), "instance").rowsBetween(Window.unboundedPreceding, 0)
    return speedups(times).select("instance", "p", "sequential", F.round(F.count("speedup").over(longest) / F.sum(1 / F.col("speedup")).over(longest), 6).alias("cumulative"))


def harm_speedup(times: DataFrame, at_least: list[float]) -> DataFrame:
    """Harmonic mean speedup for each p over instances whose sequential time is at least each limit."""
    steps = times.sparkSession.createDataFrame([(float(t),) for t in at_least], "limit double")
    return speedups(times).crossJoin(F.broadcast(steps)).where("sequential >= limit").groupBy("limit", "p").agg(F.count("*").alias("instances"), F.round(harmonic(F.col("speedup")), 6).alias("speedup"))


def improvement_share(runs: DataFrame, algo: str, base: str, percent: float) -> DataFrame:
    """instances, the share on which algo's cut is at least `percent` below base's, and the median improvement in percent."""
    means = mean_over_seeds(runs)
    a, b = (means.where(F.col("algo") == x).select("graph", "k", F.col("cut").alias(y), F.col("ok").alias(f"ok_{y}")) for x, y in ((algo, "own"), (base, "base")))
    both = a.join(b, ["graph", "k"]).where("ok_own AND ok_base").withColumn("gain", 100 * (F.col("base") - F.col("own")) / F.greatest("base", F.lit(1.0)))
    return both.agg(F.count("*").alias("instances"), F.round(F.avg((F.col("gain") >= percent).cast("int")), 6).alias("share"), F.round(F.percentile("gain", F.lit(0.5)), 6).alias("median_gain"))


def scaling_table(runs: DataFrame) -> DataFrame:
    """runs: (algo, log_m, parts, seconds, status). Time by size and parts, and edges per second."""
    ok = runs.where("status = 'ok'")
    return ok.groupBy("algo", "log_m", "parts").agg(F.round(F.avg("seconds"), 6).alias("seconds")).withColumn("edges_per_s", F.round(F.pow(F.lit(2.0), "log_m") / F.col("seconds"), 3))


def max_feasible(runs: DataFrame) -> DataFrame:
    """The largest size that each algorithm solves, below its first failure."""
    failed = runs.groupBy("algo").agg(F.min(F.when(F.col("status") != "ok", F.col("log_m"))).alias("first_failure"))
    ok = runs.where("status = 'ok'").join(failed, "algo").where("first_failure IS NULL OR log_m < first_failure")
    return ok.groupBy("algo").agg(F.max("log_m").alias("largest_log_m"))
