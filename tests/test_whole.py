"""Whole jobs: nothing is left out by size or frequency."""

import os

import pytest

import __spark_entry__ as entry
from conftest import rows
from gpart.plans import experiments
from gpart.sources import graphs

SF = "/root/testdata/sf0.001"


def test_a_line_of_many_documents_keeps_its_links(spark, tmp_path):
    text = "a line that every document has\nshort"
    spark.createDataFrame([(i, text) for i in range(60)] + [(60, "a line of this document alone")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    for names in (experiments.SET_A, experiments.WEB):
        (name,) = [x for x in names if x.startswith("doc_line")]
        found = graphs.build_graph(spark, str(tmp_path), name)
        assert found.vertices.count() == 61 and found.edges.count() == 120


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
def test_document_line_links_and_sql(spark, duck):
    name = "graph_edges_doc_line_links"
    assert rows(entry.queries()[name](spark, SF).toPandas()) == rows(duck(SF, entry.oracle_sql()[name]))


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
def test_solver_queries_coarsen_in_spark(spark, duck, monkeypatch):
    from gpart.plans import multilevel

    seen, coarsen = [], multilevel.coarsen
    monkeypatch.setattr(multilevel, "coarsen", lambda *args: seen.append(coarsen(*args)) or seen[-1])
    name = "partition_lean_lp_event_window"
    assert rows(entry.queries()[name](spark, SF).toPandas()) == rows(duck(SF, entry.oracle_sql()[name]))
    (levels,) = seen
    assert len(levels) > 1 and levels[-1].n < levels[0].n
    with pytest.raises(RuntimeError):
        multilevel.require_levels(levels[:1], 4, multilevel.MultilevelConfig(contraction_limit=10))
