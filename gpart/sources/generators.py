"""Generated graphs: random geometric, random hyperbolic, and tiny ones whose optimum is known."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.functions.columns import MODULUS, scramble
from gpart.sources.graphs import Graph, densify, number


def uniform(x: Column | str, seed: int) -> Column:
    """A number in [0, 1) from a dense id: a product of two hashes, so that two seeds' numbers are not on a lattice."""
    x = F.col(x) if isinstance(x, str) else x
    return scramble(x, seed) * scramble(x + 1, seed + 7) % MODULUS / float(MODULUS)


def _graph(points: DataFrame, pairs: DataFrame) -> Graph:
    half = pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1).cast("long").alias("w"))
    edges = half.unionAll(half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return Graph(points.select("id", F.lit(1).cast("long").alias("w")), edges)


def rgg2d(spark: SparkSession, n: int, avg_deg: float = 256, seed: int = 1) -> Graph:
    """n points of the unit square, linked within the radius that gives avg_deg; ids follow the grid, row by row.

    Cells are as wide as the radius, so a range join becomes an equality join with nine cells, whatever n is.
    """
    radius = math.sqrt(avg_deg / (n * math.pi))
    raw = spark.range(n).select(F.col("id").alias("point"), uniform("id", seed).alias("x"), uniform("id", seed + 100).alias("y"))
    celled = raw.withColumn("cx", F.floor(F.col("x") / radius)).withColumn("cy", F.floor(F.col("y") / radius))
    points = number(celled, ["cy", "cx", "point"], "id")
    around = F.array(*[F.struct(F.lit(i).cast("long").alias("i"), F.lit(j).cast("long").alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    left = points.withColumn("d", F.explode(around)).select(F.col("id").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya"), (F.col("cx") + F.col("d.i")).alias("cx"), (F.col("cy") + F.col("d.j")).alias("cy"))
    right = points.select(F.col("id").alias("b"), F.col("x").alias("xb"), F.col("y").alias("yb"), "cx", "cy")
    near = (F.col("xa") - F.col("xb")) * (F.col("xa") - F.col("xb")) + (F.col("ya") - F.col("yb")) * (F.col("ya") - F.col("yb")) <= radius * radius
    return _graph(points, left.join(right, ["cx", "cy"]).where((F.col("a") < F.col("b")) & near).select("a", "b"))


def rhg(spark: SparkSession, n: int, avg_deg: float = 256, gamma: float = 3.0, seed: int = 1) -> Graph:
    """n points of a hyperbolic disk whose degrees follow a power law with exponent gamma; ids follow the angle.

    Points are dealt to annuli; for two annuli, angular sectors as wide as the farthest possible link make the distance join an
    equality join with three sectors.
    """
    alpha = (gamma - 1) / 2
    xi = alpha / (alpha - 0.5)
    disk = 2 * math.log(2 * xi * xi * n / (math.pi * avg_deg))
    radial = F.acosh(1 + uniform("id", seed) * (math.cosh(alpha * disk) - 1)) / alpha
    bands = max(1, math.ceil(disk / 2 / math.log(2)))
    inner = [0.0] + [disk / 2 + disk / 2 * i / bands for i in range(bands)]  # the inner half is one band
    band = F.lit(0)
    for i in range(1, bands + 1):
        band = F.when(F.col("r") >= inner[i], i).otherwise(band)
    raw = spark.range(n).select(F.col("id").alias("point"), radial.alias("r"), (uniform("id", seed + 100) * 2 * math.pi).alias("angle")).withColumn("band", band)
    points = number(raw, ["angle", "point"], "id")

    def sectors(i: int, j: int) -> int:
        if inner[i] + inner[j] <= disk:
            return 1
        cosine = (math.cosh(inner[i]) * math.cosh(inner[j]) - math.cosh(disk)) / (math.sinh(inner[i]) * math.sinh(inner[j]))
        return max(1, int(2 * math.pi / math.acos(max(-1.0, min(1.0, cosine)))))

    met = spark.createDataFrame([(i, j, sectors(i, j)) for i in range(bands + 1) for j in range(i, bands + 1)], "i int, j int, sectors int")
    sector = F.least((F.col("angle") / (2 * math.pi) * F.col("sectors")).cast("int"), F.col("sectors") - 1)
    around = F.array_distinct(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda d: F.pmod(F.col("sector") + d, F.col("sectors"))))
    left = points.join(F.broadcast(met), points["band"] == met["i"]).withColumn("sector", sector)
    left = left.select(F.col("id").alias("a"), F.col("r").alias("ra"), F.col("angle").alias("ta"), "i", "j", F.explode(around).alias("sector"))
    right = points.join(F.broadcast(met), points["band"] == met["j"]).withColumn("sector", sector)
    right = right.select(F.col("id").alias("b"), F.col("r").alias("rb"), F.col("angle").alias("tb"), "i", "j", "sector")
    reach = F.cosh("ra") * F.cosh("rb") - F.sinh("ra") * F.sinh("rb") * F.cos(F.col("ta") - F.col("tb")) <= math.cosh(disk)
    once = (F.col("i") < F.col("j")) | (F.col("a") < F.col("b"))
    return _graph(points, left.join(right, ["i", "j", "sector"]).where(once & (F.col("a") != F.col("b")) & reach).select("a", "b").distinct())


def from_pairs(spark: SparkSession, pairs: list[tuple], vertices: int = 0) -> Graph:
    """A graph from a short list of (a, b) or (a, b, w); vertices 0..vertices-1 exist even without edges."""
    rows = spark.createDataFrame([(*p, 1)[:3] for p in pairs], "a long, b long, w long")
    return densify(rows, spark.range(vertices).select(F.col("id").alias("key")))


def path(spark: SparkSession, n: int) -> Graph:
    return from_pairs(spark, [(i, i + 1) for i in range(n - 1)], n)


def ring(spark: SparkSession, n: int) -> Graph:
    return from_pairs(spark, [(i, (i + 1) % n) for i in range(n)], n)


def grid(spark: SparkSession, a: int, b: int) -> Graph:
    return from_pairs(spark, [(i * b + j, i * b + j + 1) for i in range(a) for j in range(b - 1)] + [(i * b + j, (i + 1) * b + j) for i in range(a - 1) for j in range(b)], a * b)


def star(spark: SparkSession, d: int) -> Graph:
    return from_pairs(spark, [(0, i) for i in range(1, d + 1)], d + 1)


def two_cliques(spark: SparkSession, s: int) -> Graph:
    """Two cliques of s vertices, joined by one edge."""
    return from_pairs(spark, [(c * s + i, c * s + j) for c in (0, 1) for i in range(s) for j in range(i + 1, s)] + [(s - 1, s)], 2 * s)


def barbell(spark: SparkSession, s: int) -> Graph:
    """Two cliques of s vertices, joined by a path over one vertex."""
    return from_pairs(spark, [(c * (s + 1) + i, c * (s + 1) + j) for c in (0, 1) for i in range(s) for j in range(i + 1, s)] + [(s - 1, s), (s, s + 1)], 2 * s + 1)


def caterpillar(spark: SparkSession, n: int, leaves: int) -> Graph:
    """A path of n vertices, each with some leaves."""
    return from_pairs(spark, [(i, i + 1) for i in range(n - 1)] + [(i, n + i * leaves + j) for i in range(n) for j in range(leaves)], n * (1 + leaves))
