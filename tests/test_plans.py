"""Shapes of plans that must hold at any size."""

import os

import pytest
from pyspark.sql import functions as F

from gpart.operators import clustering, codec, contraction, gains, metrics
from gpart.sources import generators, graphs

SF = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def ring(spark):
    return generators.ring(spark, 64).persisted()


def test_rounds_have_no_pairs_and_no_global_window(ring):
    labels = clustering.singletons(ring.vertices)
    for df in (clustering.ratings(ring.edges, labels), clustering.lp_round_single(ring, labels, 1, 0, 2, 5), contraction.coarse_edges(ring.edges, labels), gains.affinity(ring.edges, labels.withColumnRenamed("cluster", "block"))):
        text = plan(df)
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
        assert "SinglePartition" not in text
        assert "partial_" in text  # sums are combined before they move


def test_choices_are_aggregates_not_windows(ring):
    text = plan(clustering.choose(clustering.ratings(ring.edges, clustering.singletons(ring.vertices)), ring.vertices.withColumn("cluster", F.col("id")), 1))
    assert "Window" not in text


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
def test_scans_read_only_what_is_needed(spark):
    text = plan(graphs.copurchase(spark, SF)[0])
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in text
    text = plan(graphs.cust_supp(spark, SF)[0])
    assert "l_shipdate" not in text and "IsNotNull(l_orderkey)" in text


def test_dense_ids_and_offsets_have_no_single_task(spark, ring):
    assert "SinglePartition" not in plan(codec.degrees(ring)) and "SinglePartition" not in plan(graphs.number(ring.vertices, ["id"], "n"))


def test_degrees_are_read_without_payloads(ring):
    coded = codec.compress(codec.to_csr(ring))
    from gpart.session import cut

    text = plan(codec.degree_of(cut(coded), 128))
    assert "payload" not in text


def test_python_is_not_needed_for_measures(ring):
    part = ring.vertices.select("id", (F.col("id") % 4).cast("int").alias("block"))
    text = plan(metrics.cut_fraction(ring.edges, part))
    assert "Python" not in text and "Arrow" not in text


def test_choices_by_size(spark, ring):
    from gpart.plans import planner

    assert planner.partitions_for(10) == 8 and planner.partitions_for(1 << 40) == (24 << 40 >> 28)
    assert planner.salts_for(100, 10_000, 10) == 1 and planner.salts_for(5_000, 10_000, 10) == 8
    labels = clustering.singletons(ring.vertices)
    assert "BroadcastHashJoin" in plan(planner.joined_with_labels(ring.edges, labels)) and "BroadcastExchange" not in plan(planner.joined_with_labels(ring.edges.hint("merge"), labels, 10)).replace("AdaptiveSparkPlan", "")
    part = ring.vertices.select("id", (F.col("id") % 3).cast("int").alias("block"))
    table = gains.GainTable(ring, part, 3)
    moves = part.where("id < 40").select(F.col("id").alias("pos"), "id", F.col("block").alias("from_block"), ((F.col("block") + 1) % 3).cast("int").alias("to_block"))
    few = moves.where("id < 4")
    for some in (few, moves):
        assert sorted(planner.updated(table, some).affinities().collect()) == sorted(table.apply(some).affinities().collect())
