from fractions import Fraction

import numpy as np

from localgraph.graph import Graph
from localgraph.operators import partition


def test_first_peel_walks_on_the_graph_itself(spark, monkeypatch):
    """The first part is the whole graph, which is not rewritten, and no table of touched vertices is made for disjoint batches."""
    from localgraph.operators import cluster

    g = Graph.from_edges(spark.createDataFrame([(10 * c + i, 10 * c + i + 1) for c in range(8) for i in range(3)], "a long, b long")).kept()
    labels, plain = [], cluster.cut
    monkeypatch.setattr(cluster, "cut", lambda df, label="step", by=None: labels.append(label) or plain(df, label, by))
    monkeypatch.setattr(Graph, "restrict", lambda *a: 1 / 0)
    parts = partition.peel_clusters(g, Fraction(9, 10), 0.5, 1, batch=8, t_max=4, eps=1e-9, slope=1e-6, disjoint=True)
    assert {r.v for r in parts.collect()} == {r.v for r in g.vertices.collect()} and parts.select("part").distinct().count() == 2
    assert "clusters" in labels and "touched" not in labels


def hub(spark):
    """A root over 12 stars: every draw that reaches the root neighbours all of them."""
    edges = [(0, 100 * c) for c in range(1, 13)] + [(100 * c, 100 * c + i) for c in range(1, 13) for i in range(1, 6)]
    return Graph.from_edges(spark.createDataFrame(edges, "a long, b long")).kept()


def test_draws_that_meet_are_settled_in_one_batch(spark, monkeypatch):
    """Draws that share a hub: one batch in place of a batch for every clash, with the rows of one draw at a time."""
    from localgraph import graph as graphs

    o = dict(draws=12, t_max=6, eps=1e-9, slope=1e-6, pick="largest")
    one, trace = (sorted(map(tuple, x.collect())) for x in partition.peel_partition(hub(spark), Fraction(9, 10), 0.5, batch=1, **o))
    calls, plain = [], partition.sampled_local_cluster
    monkeypatch.setattr(partition, "sampled_local_cluster", lambda *a, **k: calls.append(a) or plain(*a, **k))
    monkeypatch.setattr(graphs, "CHUNK", 4)
    got = [sorted(map(tuple, x.collect())) for x in partition.peel_partition(hub(spark).stored(), Fraction(9, 10), 0.5, batch=6, **o)]
    assert got == [one, trace] and len(trace) > 2
    assert len(calls) <= 2


def test_in_order_stops_at_rows_that_are_not_held():
    from localgraph.operators.cluster import Ball, in_order

    run = dict(run_id=0, seed=1, eps_units=1, b=1, phi_num=1, phi_den=3, slope_units=0.0, unit=1 << 50, pick="first")

    def ball(seed, hit, v, nbrs):
        x = Ball(run | {"seed": seed}, 100)
        x.take(v, [3] * len(v), [0] * len(v), [0] * len(v), nbrs)
        x.hit, x.state = hit, {}
        return x

    first = ball(1, [1, 2], [1, 2], [[2, 3, 4], [1, 3, 4]])
    inside = ball(2, [2], [2], [[1, 3, 4]])
    apart = ball(9, [9], [9], [[10, 11, 12]])
    beside = ball(3, [3], [3], [[1, 2, 5]])
    got = in_order([first, apart, inside, beside, apart], 5)
    assert got[0] is first and got[1] is apart
    # a seed that is gone gives no run; a walk that now goes on past the rows at hand is not settled, nor is any later one
    assert got[2].hit is None and got[2].state == {} and got[3:] == [None, None]
    assert in_order([first, apart, beside], 5, limit=9) == [first, apart, None]


def test_uniforms_of_tasks_are_those_of_plans(spark):
    from localgraph.operators.sampling import sample_scale, scales_at, uniforms, uniforms_at

    for seed, first in ((1, 0), (-7, 1 << 33)):
        draws = uniforms(spark, seed, first, 500)
        one, two = uniforms_at(seed, first, 500)
        assert [(r.u1, r.u2) for r in draws.orderBy("draw").collect()] == list(zip(one.tolist(), two.tolist(), strict=True))
        assert [r.b for r in sample_scale(9, draws).orderBy("draw").collect()] == scales_at(9, two).tolist()


def small(spark):
    """Two paths, two triangles with a bridge."""
    ends = [(10 * c + i, 10 * c + i + 1) for c in range(2) for i in range(4 + c)] + [(90, 91), (90, 92), (92, 91), (92, 93), (93, 94), (93, 95), (94, 95)]
    return Graph.from_edges(spark.createDataFrame(ends, "a long, b long")).kept()


def test_held_splits_equal_partitions_by_plans(spark, monkeypatch):
    """Two levels of parts that tasks split by themselves, without a batch of jobs, are those of `peel_partition`."""
    g, o = small(spark), dict(batch=12, t_max=4, eps=1e-9, slope=1e-6, draws=12)
    get = lambda: sorted(map(tuple, partition.peel_clusters(g, Fraction(9, 10), 0.5, 2, **o).collect()))
    with monkeypatch.context() as m:
        m.setattr(partition, "PART_VOL", 0, raising=False)
        want = get()
    assert len(want) == sum(1 for _ in g.vertices.collect()) and len({name for _, name in want}) > 2
    monkeypatch.setattr(partition, "peel_partition", lambda *a, **k: 1 / 0)
    assert get() == want


def test_parts_are_split_until_nothing_is_found(spark, monkeypatch):
    """No depth: more than two parts, the same ones if a task hands parts on and if no walk is compared with another."""
    from localgraph.operators import held

    g, o = small(spark), dict(t_max=4, eps=1e-9, slope=1e-6)
    get = lambda: sorted(map(tuple, partition.peel_clusters(g, Fraction(9, 10), 0.5, **o).collect()))
    want = get()
    assert len(want) == g.vertices.count() and len({name for _, name in want}) > 2
    monkeypatch.setattr(partition, "SPREAD_VOL", 12)
    assert get() == want
    monkeypatch.setattr(held, "NEAR_VOL", 0)
    rows = g.near.rows.collect()
    rule = held.Rule(partition.partition_phi(Fraction(9, 10)), 0.5, practical=o)
    whole = lambda: held.Held([r.v for r in rows], [r.deg for r in rows], [len(r.nbrs) for r in rows], [u for r in rows for u in r.nbrs], rule)
    first = whole()
    assert sorted((int(first.ids[i]), name) for here, name, done in first.split("0", None, 0) for i in here if done) == want
    # nothing is left to find in any part
    for name in {n for _, n in want}:
        at = [r for r in rows if (r.v, name) in want]
        part = held.Held([r.v for r in at], [r.deg for r in at], [len(r.nbrs) for r in at], [u for r in at for u in r.nbrs], rule)
        assert not len(part.peel(np.arange(len(at))))


def test_recursive_query_goes_on_after_the_first_split(spark):
    from localgraph.plans import methods

    parts = [r.part for r in methods.QUERIES["pp_recursive"](spark, "/root/testdata/sf0.001").collect()]
    assert len(set(parts)) > 2 and max(map(len, parts)) > 3
