import random

import pytest
from pyspark.sql import functions as F

from gpart.operators import baselines, clustering, contraction, gains, metrics, refinement
from gpart.plans import distributed, multilevel
from gpart.sources import generators


def pairs(df):
    return sorted(tuple(r) for r in df.collect())


def cut(g, part):
    return metrics.edge_cut(g.edges, part).first()[0]


@pytest.fixture(scope="module")
def mesh(spark):
    from gpart.session import ship

    ship(spark)
    return generators.rgg2d(spark, 600, 12).persisted()


@pytest.mark.parametrize("t_bump", [1, 4, 1000])
@pytest.mark.parametrize("rating_map", ["hash", "sparse"])
def test_two_phases_change_nothing(spark, mesh, t_bump, rating_map):
    labels = clustering.singletons(mesh.vertices)
    one = clustering.lp_round_single(mesh, labels, 3)
    assert pairs(one) == pairs(clustering.lp_round_two_phase(mesh, labels, 3, t_bump=t_bump, rating_map=rating_map))


def test_a_vertex_is_bumped_from_the_threshold_on(spark):
    g = generators.star(spark, 8)
    labels = clustering.singletons(g.vertices)
    assert clustering.bumped(g.edges, labels, 8).count() == 1
    assert clustering.bumped(g.edges, labels, 9).count() == 0


def test_caps_hold_and_cliques_are_found(spark):
    g = generators.two_cliques(spark, 6)
    labels = clustering.label_propagation(g, 5, cap=6)
    assert clustering.cluster_weights(g.vertices, labels).agg(F.max("weight")).first()[0] <= 6
    assert labels.select("cluster").distinct().count() <= 4


def test_two_hop_pairs_leaves_of_one_favourite(spark):
    g = generators.star(spark, 6)
    labels = clustering.singletons(g.vertices)
    after = clustering.two_hop(g, labels, clustering.favourites(g, labels), 2)
    assert after.select("cluster").distinct().count() == 4


def test_forms_of_contraction_agree(spark, mesh):
    labels = clustering.label_propagation(mesh, 1)
    coarse, parents = contraction.contract(mesh, labels)
    buffered, _ = contraction.contract_buffered(mesh, labels)
    assert pairs(coarse.edges) == pairs(buffered.edges)
    assert pairs(contraction.coarse_edges(mesh.edges, labels)) == pairs(contraction.two_phase_edges(mesh.edges, labels, 5))
    part = baselines.stream_hash(coarse.vertices, 3)
    assert cut(coarse, part) == cut(mesh, refinement.project(part, parents))
    assert coarse.vertices.agg(F.sum("w")).first()[0] == 600


def test_gain_tables_agree_before_and_after_moves(spark, mesh):
    part = baselines.stream_hash(mesh.vertices, 5)
    moves = part.where("id % 7 = 0").select(F.col("id").alias("pos"), "id", F.col("block").alias("from_block"), ((F.col("block") + 1) % 5).cast("int").alias("to_block"))
    tables = [gains.GainTable(mesh, part, 5, v) for v in ("none", "full", "hybrid")]
    assert pairs(tables[0].gains()) == pairs(tables[1].gains()) == pairs(tables[2].gains())
    assert pairs(tables[0].apply(moves).affinities()) == pairs(tables[1].apply(moves).affinities()) == pairs(tables[2].apply(moves).affinities())


def test_joint_gains_replay(spark, mesh):
    part = baselines.stream_hash(mesh.vertices, 4)
    where = {r["id"]: r["block"] for r in part.collect()}
    rng = random.Random(1)
    steps = [(p + 1, v, where[v], (where[v] + rng.randint(1, 3)) % 4) for p, v in enumerate(rng.sample(sorted(where), 80))]
    moves = spark.createDataFrame(steps, "pos long, id long, from_block int, to_block int")
    edges = mesh.edges.where("src < dst").collect()
    gain = {r["pos"]: r["gain"] for r in refinement.joint_gains(moves, mesh, part).collect()}
    value = lambda: sum(e["w"] for e in edges if where[e["src"]] != where[e["dst"]])
    for pos, v, _, to in steps:
        before = value()
        where[v] = to
        assert gain[pos] == before - value()


def test_rebalance_and_regions(spark, mesh):
    cap = metrics.block_cap(600, 4, 0.03)[0]
    skewed = mesh.vertices.select("id", F.when(F.col("id") < 400, 0).otherwise(F.col("id") % 4).cast("int").alias("block"))
    even = refinement.rebalance(mesh, skewed, 4, cap)
    assert refinement.overload(mesh.vertices, even, cap) == 0
    better = refinement.refine_fm(mesh, even, 4, cap, rounds=1, seeds_per_region=100)
    assert cut(mesh, better) <= cut(mesh, even) and refinement.overload(mesh.vertices, better, cap) == 0


def test_which_method_wins(spark, mesh):
    k, cap = 4, metrics.block_cap(600, 4, 0.03)[0]
    cuts = {
        "fm": cut(mesh, multilevel.partition(mesh, k, "lean-fm").partition), "lp": cut(mesh, multilevel.partition(mesh, k, "lean-lp").partition),
        "ldg": cut(mesh, baselines.stream_ldg(mesh, k, cap)), "hash": cut(mesh, baselines.stream_hash(mesh.vertices, k)),
    }
    assert cuts["fm"] <= 1.05 * cuts["lp"] < cuts["ldg"] < cuts["hash"]


def test_levels_in_spark_are_balanced(spark, mesh):
    cfg = multilevel.MultilevelConfig(contraction_limit=30, rounds=2, refine_rounds=1, t_bump=8)
    for result in (multilevel.partition(mesh, 4, "lean-lp", cfg), distributed.partition_distributed(mesh, 4, 2, True, cfg)):
        assert len(result.levels) > 1 and metrics.balance(mesh.vertices, result.partition, 4).where("NOT feasible").count() == 0


def test_ghosts_of_a_path(spark):
    g = generators.path(spark, 6)
    owners = distributed.owned(g.vertices, 6, 2)
    assert pairs(distributed.ghosts(g.edges, owners)) == [(0, 3, 1), (1, 2, 0)]


def test_small_k(spark):
    g = generators.path(spark, 3)
    assert metrics.block_cap(3, 5, 0.03) == (1, True)
    assert multilevel.partition(g, 1).partition.where("block <> 0").count() == 0


def test_matchings_do_not_stall_where_ids_follow_the_edges(spark):
    g = generators.ring(spark, 512)
    mates = clustering.singletons(g.vertices)
    for r in range(2):
        mates = baselines.matching_round(g, mates, 2, 1 + r)
    sizes = [x["n"] for x in mates.groupBy("cluster").agg(F.count("*").alias("n")).collect()]
    assert max(sizes) == 2 and len(sizes) < 0.7 * 512
