from fractions import Fraction

import pytest

from localgraph.graph import Graph, boundary, components, min_conductance, report
from localgraph.operators import cluster, partition, sampling, walk
from localgraph.operators.walk import Run
from localgraph.params import UNIT, WIDE, Constants, scale_count, schedule, valid_scales
from localgraph.plans import methods, relational

D = "/root/testdata/sf0.001"


def graph(spark, edges, loops=None):
    g = Graph.from_edges(spark.createDataFrame(edges, "a long, b long"))
    return Graph(g.arcs, spark.createDataFrame(loops, "v long, loops long")) if loops else g


def test_constants_and_schedule():
    assert Constants().check()
    s = schedule(12000, Fraction(1, 10), 1)
    assert (s.ell, s.t1, s.t_last) == (13, 2472, 34608)
    assert (schedule(50, Fraction(1, 2), 1).t_last, scale_count(118782)) == (426, 16)
    with pytest.raises(ValueError):
        schedule(50, 1, 1)
    # every scale has a mass unit that keeps its threshold
    for b in valid_scales(118782):
        s = schedule(118782, Fraction(1, 10), b)
        assert s.eps_units >= 64 and abs(s.eps_units / s.unit / s.eps - 1) < 0.02


def test_step_with_loop(spark):
    g = graph(spark, [(0, 1), (0, 2), (0, 3)], [(0, 1)])
    got = {r.v: r.mass / UNIT for r in walk.walk(g, [Run(0, 0)], 1).filter("t = 1").collect()}
    assert got == {0: 5 / 8, 1: 1 / 8, 2: 1 / 8, 3: 1 / 8}


def test_edges_are_cleaned(spark):
    g = graph(spark, [(1, 2), (2, 1), (1, 2), (3, 3), (None, 1)])
    assert sorted(map(tuple, g.arcs.collect())) == [(1, 2), (2, 1)]


def test_two_triangles(spark):
    g = graph(spark, [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)])
    assert min_conductance(g).first().phi == 1 / 7
    s = spark.createDataFrame([(0, v) for v in (0, 1, 2)], "set_id long, v long")
    assert boundary(g, s).first().cut == 1
    assert report(g, s).first().balance == 0.5
    c, stop = cluster.local_cluster(g, 0, Fraction(1, 5), 2, t_max=20, eps=1e-9, slope=1e-6)
    assert {r.v for r in c.collect()} == {0, 1, 2}
    assert stop.first().cut == 1


def test_components_and_paths(spark):
    g = graph(spark, [(i, i + 1) for i in range(40)] + [(100, 101)])
    assert {(r.comp, r["count"]) for r in components(g).groupBy("comp").count().collect()} == {(0, 41), (100, 2)}
    assert min_conductance(graph(spark, [(i, i + 1) for i in range(5)])).first().phi == 1 / 5


def test_restrict_keeps_degrees(spark):
    g = graph(spark, [(0, 1), (0, 2), (0, 3), (1, 2)])
    a = spark.createDataFrame([(0,), (1,)], "v long")
    assert {(r.v, r.deg, r.loops) for r in g.restrict(a).vertices.collect()} == {(0, 3, 2), (1, 2, 1)}


def test_modes_agree_and_empty_seed(spark):
    g = graph(spark, [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)])
    runs = [Run(i, v, 1000, 1, 1, 5) for i, v in enumerate(range(6))] + [Run(9, 0, UNIT)]
    a, _ = cluster.local_clusters(g, runs, 10)
    b = cluster.ball_clusters(g, runs, 10)
    assert {tuple(r) for r in a.collect()} == {(r.run_id, r.v, r.rank) for r in b.collect() if r.v is not None}
    assert 9 not in {r.run_id for r in a.collect()}


def test_ball_limit_wide_unit_and_removed(spark):
    edges = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3), (5, 6)]
    g = graph(spark, edges)
    runs = [Run(i, v, 1000, 1, 1, 5) for i, v in enumerate(range(6))]
    rows = lambda df: sorted((r.run_id, r.t, r.v or 0, r.rank or 0) for r in df.collect())
    whole = rows(cluster.ball_clusters(g, runs, 10))
    assert whole == rows(cluster.ball_clusters(g, runs, 10, limit=6))
    wide = [Run(r.run_id, r.seed, 1000 << 50, 1, 1, 5, unit=WIDE) for r in runs]
    assert whole == rows(cluster.ball_clusters(g, wide, 10))
    with pytest.raises(ValueError):
        cluster.local_clusters(g, wide, 1)
    gone = spark.createDataFrame([(6,), (0,)], "v long")
    alive = spark.createDataFrame([(v,) for v in range(1, 6)], "v long")
    some, left = runs[1:], g.restrict(alive).kept()
    assert rows(cluster.ball_clusters(g, some, 10, left.vol, gone)) == rows(cluster.ball_clusters(left, some, 10))
    assert rows(cluster.ball_clusters(g, some, 10, left.vol, gone, limit=6)) == rows(cluster.ball_clusters(left, some, 10))


def test_hubs_are_split_and_buckets_pruned(spark, monkeypatch):
    from localgraph import graph as graphs

    monkeypatch.setattr(graphs, "CHUNK", 4)
    monkeypatch.setattr(graphs, "PER_BUCKET", 8)
    edges = [(0, i) for i in range(1, 30)] + [(1, 2), (2, 3)]
    g = graph(spark, edges, [(0, 3), (50, 9)])
    assert g.near.buckets > 4 and g.near.rows.filter("v = 0").count() > 5
    got = {r.v: (r.deg, r.loops) for r in walk.degrees(g, g.vertices.select("v")).collect()}
    assert got == {r.v: (r.deg, r.loops) for r in g.vertices.collect()}
    monkeypatch.setattr(graphs, "CHUNK", 1 << 14)
    plain = graph(spark, edges, [(0, 3), (50, 9)])
    one, two = (sorted(map(tuple, walk.walk(x, [Run(0, 1), Run(1, 50)], 3).collect())) for x in (g, plain))
    assert one == two
    a, b = (sorted(map(tuple, cluster.local_clusters(x, [Run(0, 3, 10, 1, 1, 2)], 5)[0].collect())) for x in (g, plain))
    assert a == b


def test_step_moves_state_only(spark):
    g = methods.graph(spark, D, "fk_forest")
    runs = walk.runs_frame(g, [Run(0, methods.cust(0))])
    from localgraph.session import cut

    state = cut(walk.start(runs))
    plan = walk.step(g, walk.fetch(g, state), runs)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "SortMergeJoin" not in plan


def test_partition_bounds_and_batches(spark):
    g = graph(spark, [(c * 10 + i, c * 10 + j) for c in range(6) for i in range(4) for j in range(i)] + [(c * 10, c * 10 + 10) for c in range(5)]).kept()
    o = dict(draws=12, t_max=12, eps=1e-9, slope=1e-6)
    d1, t1 = partition.peel_partition(g, Fraction(9, 10), 0.5, batch=1, **o)
    d2, t2 = partition.peel_partition(g, Fraction(9, 10), 0.5, batch=6, **o)
    assert sorted(d1.collect()) == sorted(d2.collect()) and sorted(t1.collect()) == sorted(t2.collect())
    cert = partition.certificate(g, d1, 0.9).first()
    assert cert.vol_ok and cert.phi_ok and cert.disjoint and cert.cut_ok


def test_degree_intervals_cover(spark):
    g = methods.graph(spark, D, "page_link")
    rows = sorted((r.lo, r.hi) for r in sampling.degree_intervals(g).collect())
    assert rows[0][0] == 0 and rows[-1][1] == g.vol and all(a[1] == b[0] for a, b in zip(rows, rows[1:]))


FAST = ["m_conductance", "w_truncated_t6", "w_restricted_t5", "c_prefix_cuts", "lc_flagship", "lc_grid_pages", "slc_draws", "p_schedule"]


@pytest.mark.parametrize("name", FAST)
def test_methods_match_sql(spark, same, name):
    same(methods.QUERIES[name](spark, D), methods.SQL[name])


@pytest.mark.parametrize("name", [n for n in relational.SQL if n.startswith(("op_", "fn_"))] + ["st_tumbling", "st_dedup_arcs", "st_running_degree"])
def test_relational_matches_sql(spark, same, name):
    same(relational.QUERIES[name](spark, D), relational.SQL[name])


def test_entry_has_names():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert len(e.queries()) > 150
