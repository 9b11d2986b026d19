import pytest

from gpart.operators import clean, memory, metrics
from gpart.sources import generators

RUNS = [
    ("g1", "a", 2, 1, 10, 1.0, "ok"), ("g1", "a", 2, 2, 20, 3.0, "ok"), ("g1", "b", 2, 1, 30, 4.0, "ok"), ("g1", "b", 2, 2, 30, 4.0, "ok"),
    ("g2", "a", 2, 1, 50, 8.0, "ok"), ("g2", "b", 2, 1, 50, 2.0, "OOM"),
]


@pytest.fixture(scope="module")
def runs(spark):
    return spark.createDataFrame([(*r[:6], 100, r[6]) for r in RUNS], "graph string, algo string, k int, seed int, cut long, seconds double, peak_bytes long, status string")


def test_profile(runs):
    found = {(r["algo"], r["tau"]): r["share"] for r in metrics.performance_profile(runs, [1.0, 2.0]).collect()}
    assert found == {("a", 1.0): 1.0, ("a", 2.0): 1.0, ("b", 1.0): 0.0, ("b", 2.0): 0.5}


def test_means(runs):
    assert {r["algo"]: r["mean"] for r in metrics.geo_mean(runs).collect()} == {"a": 4.0, "b": 4.0}
    assert {r["algo"]: (r["ok"], r["oom"]) for r in metrics.status_counts(runs).collect()} == {"a": (3, 0), "b": (2, 1)}
    assert metrics.improvement_share(runs, "a", "b", 10).first().asDict() == {"instances": 1, "share": 1.0, "median_gain": 50.0}


def test_speedups(spark):
    times = spark.createDataFrame([(1, 1, 100.0), (1, 2, 50.0), (2, 1, 10.0), (2, 2, 10.0)], "instance long, p int, seconds double")
    assert [(r["instance"], r["cumulative"]) for r in metrics.speedup_curve(times).orderBy("instance").collect()] == [(1, 2.0), (2, round(4 / 3, 6))]
    assert metrics.harm_speedup(times, [50]).first()["speedup"] == 2.0


def test_generators(spark):
    for g in (generators.rgg2d(spark, 400, 10), generators.rhg(spark, 400, 10)):
        stats = clean.graph_stats(g).first()
        assert stats["n"] == 400 and 4 < stats["avg_deg"] < 25
        back = g.edges.selectExpr("dst AS src", "src AS dst", "w")
        assert g.edges.exceptAll(back).count() == 0 and g.edges.where("src = dst").count() == 0
    heavy = clean.graph_stats(generators.rhg(spark, 400, 10)).first()["max_deg"]
    assert heavy > 2 * clean.graph_stats(generators.rgg2d(spark, 400, 10)).first()["max_deg"]


def test_memory_falls_along_the_ladder(spark):
    model = memory.memory_model(spark, memory.Sizes(10**6, 10**7, 10**5, 10**6, 10**7, degree_sum_k=10**7), "fm")
    peaks = {r["preset"]: r["bytes"] for r in memory.peak_by_phase(model).where("peak").collect()}
    assert peaks["base"] > peaks["tp"] >= peaks["tp-gc"] >= peaks["lean"]
    assert memory.overcommit(5000, 10**6) == {"reserved": 10**6, "touched": 8192, "waste": 3192} and memory.growable_peak(10000) == 24576
