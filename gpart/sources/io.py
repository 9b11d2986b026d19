"""Where edges are kept: columnar and text files, adjacency lists, stores by level, range-partitioned layouts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.session import checkpoint_dir
from gpart.sources.graphs import Graph


def scratch(spark: SparkSession) -> str:
    """A new path in the shared checkpoint folder."""
    checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/io-{uuid.uuid4().hex}"


def roundtrip(df: DataFrame, form: str) -> DataFrame:
    """df written and read again in one of parquet, orc, csv and json."""
    path = scratch(df.sparkSession)
    df.write.format(form).save(path)
    return df.sparkSession.read.schema(df.schema).format(form).load(path)


def write_adjacency(graph: Graph, path: str) -> str:
    """A line for each vertex with edges: the vertex, then neighbour and weight in turn. Hubs are cut into several lines."""
    part = F.floor((F.row_number().over(_line()) - 1) / 10_000)
    pairs = graph.edges.withColumn("part", part).groupBy("src", "part").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("dst", "w"))), lambda e: F.concat_ws(" ", e["dst"].cast("string"), e["w"].cast("string"))), " ").alias("line"))
    pairs.select(F.concat_ws(" ", F.col("src").cast("string"), "line").alias("value")).write.text(path)
    return path


def _line():
    from pyspark.sql import Window

    return Window.partitionBy("src").orderBy("dst")


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    words = spark.read.text(path).select(F.transform(F.split("value", " "), lambda x: x.cast("long")).alias("v"))
    pairs = F.transform(F.sequence(F.lit(1), F.size("v") - 2, F.lit(2)), lambda i: F.struct(F.get("v", i).alias("dst"), F.get("v", i + 1).alias("w")))
    return words.select(F.col("v")[0].alias("src"), F.explode(pairs).alias("e")).select("src", "e.dst", "e.w")


def by_level(edges: DataFrame) -> DataFrame:
    """edges with a `level`, stored in one folder for each level: a reader of one level opens that folder only."""
    path = scratch(edges.sparkSession)
    edges.write.partitionBy("level").parquet(path)
    return edges.sparkSession.read.parquet(path)


def ranged(edges: DataFrame, column: str) -> DataFrame:
    """edges stored in ranges of a column, sorted within files, so that scans of a range skip the others."""
    path = scratch(edges.sparkSession)
    edges.repartitionByRange(column).sortWithinPartitions(column).write.parquet(path)
    return edges.sparkSession.read.parquet(path)
