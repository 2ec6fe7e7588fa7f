from localgraph.graph import Graph
from localgraph.operators import analysis
from localgraph.params import UNIT
from localgraph.plans import relational
from localgraph.sources.builders import load

D = "/root/testdata/sf0.001"


def test_saved_adjacency_of_a_hub_is_one_vertex(spark, same, monkeypatch):
    from localgraph import graph as graphs

    monkeypatch.setattr(graphs, "CHUNK", 4)
    same(relational.QUERIES["io_bucketed_adjacency"](spark, D), relational.SQL["io_bucketed_adjacency"])


def test_escape_bounds_with_a_hub(spark):
    """Mass times a degree of 2^13 or more passes 63 bits."""
    ids = spark.range(1, 9001).select("id")
    g = Graph.from_edges(ids.selectExpr("0L AS a", "id AS b").union(spark.createDataFrame([(0, -1), (-1, -2)], "a long, b long"))).kept()
    inside = g.vertices.filter("v >= 0").select("v")
    first = analysis.escape_bounds(g, inside, 1).filter("t = 0").first()
    assert UNIT - 9001 <= first.inside <= UNIT and first.escape_ok and first.norm_ok


def test_two_first_neighbours_by_lateral_join(spark):
    rows = relational.QUERIES["op_join_lateral"](spark, D).collect()
    assert len({r.src for r in rows}) == load(spark, D, "pages").filter("html like '%href=\"%'").count() and max(r.dst for r in rows) > 0
