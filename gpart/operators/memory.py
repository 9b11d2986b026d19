"""Memory models: exact arithmetic on sizes of graphs and settings, not measurements."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PAGE = 4096


def overcommit(n_bytes: int, upper_bound: int, page: int = PAGE) -> dict[str, int]:
    """Reserved, touched and wasted bytes if the upper bound is reserved and only what is written is touched, page by page."""
    touched = -(-n_bytes // page) * page
    return {"reserved": upper_bound, "touched": min(touched, -(-upper_bound // page) * page), "waste": touched - n_bytes}


def growable_peak(n_bytes: int, start: int = PAGE) -> int:
    """Peak bytes of a buffer that doubles: while it is copied, old and new exist at once."""
    size, peak = start, start
    while size < n_bytes:
        peak = max(peak, 3 * size)
        size *= 2
    return max(peak, size)


def growable_bytes(sizes: DataFrame, start: int = PAGE) -> DataFrame:
    """sizes (part, n_bytes) -> with the doubling buffer's capacity and peak."""
    doublings = F.ceil(F.greatest(F.lit(0.0), F.log2(F.col("n_bytes") / start))).cast("int")
    capacity = F.lit(start) * F.pow(F.lit(2), doublings)
    return sizes.select("part", "n_bytes", capacity.cast("long").alias("capacity"), F.when(doublings > 0, capacity * 3 / 2).otherwise(capacity).cast("long").alias("peak"))


def pointer_bytes(n_coarse: int | Column, mode: str) -> int | Column:
    """Begin and end pointers for each coarse vertex, or begins alone once vertices are renamed to follow one another; of a number or a column."""
    return 8 * (2 * n_coarse if mode == "begin_end" else n_coarse + 1)


@dataclass(frozen=True)
class Sizes:
    """n vertices, m undirected edges, coarse n' and m', the coded bytes of the input, and the machine."""

    n: int
    m: int
    coarse_n: int
    coarse_m: int
    coded_bytes: int
    processors: int = 96
    t_bump: int = 10_000
    k: int = 64
    degree_sum_k: int = 0  #: the sum over vertices of min(degree, k)


def components_of(s: Sizes, two_phase: bool, compressed: bool, one_pass: bool, refine: str, table: str = "hybrid") -> list[tuple[str, str, int]]:
    """(phase, component, bytes)."""
    graph = s.coded_bytes if compressed else 8 * (s.n + 1) + 16 * s.m
    coarse = 16 * s.coarse_m + 8 * s.coarse_n
    out = [("cluster", "graph", graph), ("cluster", "labels", 8 * s.n), ("cluster", "rating_maps", 8 * s.n + 16 * s.processors * s.t_bump if two_phase else 8 * s.n * s.processors)]
    out += [("contract", "graph", graph), ("contract", "labels", 8 * s.n), ("contract", "coarse", coarse), ("contract", "buffer", PAGE if one_pass else coarse)]
    out += [("refine", "graph", graph), ("refine", "coarse", coarse), ("refine", "partition", 4 * s.n), ("refine", "blocks", 8 * s.k)]
    if refine == "fm":
        bytes_of = {"none": 0, "full": 8 * s.n * s.k, "hybrid": 12 * s.degree_sum_k + 8 * s.n}
        out.append(("refine", "gain_table", bytes_of[table]))
    return out


LADDER = {"base": (False, False, False), "tp": (True, False, False), "tp-gc": (True, True, False), "lean": (True, True, True)}


def memory_model(spark, s: Sizes, refine: str = "lp", table: str = "hybrid") -> DataFrame:
    """(preset, phase, component, bytes) of the four steps of the ladder."""
    return spark.createDataFrame([(preset, *row) for preset, flags in LADDER.items() for row in components_of(s, *flags, refine, table)], "preset string, phase string, component string, bytes long")


def peak_by_phase(model: DataFrame) -> DataFrame:
    """(preset, phase, bytes, peak): sums of components; the phase with the largest sum is the peak."""
    sums = model.groupBy("preset", "phase").agg(F.sum("bytes").alias("bytes"))
    return sums.withColumn("peak", F.col("bytes") == F.max("bytes").over(Window.partitionBy("preset")))
