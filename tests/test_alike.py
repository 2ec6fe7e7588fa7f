import numpy as np
from localgraph.graph import Graph
from localgraph.operators import cluster
from localgraph.operators.walk import Run


def rows(df):
    return sorted(tuple(-1 if x is None else x for x in (r.run_id, r.t, r.v, r.rank, r.work)) for r in df.collect())


def test_every_seed_walks_a_shape_once(spark):
    """Paths of two lengths, a path whose ids do not rise along it, and a star beyond the limit: the same rows as ball mode."""
    paths = [(100 * c + i, 100 * c + i + 1) for c in range(6) for i in range(3 + c % 2)] + [(900, 902), (902, 901)]
    g = Graph.from_edges(spark.createDataFrame(paths + [(1000, 1000 + i) for i in range(1, 30)], "a long, b long")).kept()
    plans = [Run(0, 0, 1000, b, 1, 3) for b in (1, 2)]
    seeds = sorted(r.v for r in g.vertices.collect())
    runs = [Run(2 * i + k, v, 1000, b, 1, 3) for i, v in enumerate(seeds) for k, b in enumerate((1, 2))]
    got = cluster.every_seed(g, plans, 12, limit=16)
    assert rows(got) == rows(cluster.ball_clusters(g, runs, 12))
    assert {(r.run_id, r.seed, r.b) for r in got.collect()} == {(r.run_id, r.seed, r.b) for r in runs}


def test_ball_steps_once_for_vertices_that_are_alike(spark):
    """A tree of 40 equal stars under one root has six classes seen from a leaf; its clusters are those of single vertices."""
    edges = [(0, 100 * c) for c in range(1, 41)] + [(100 * c, 100 * c + i) for c in range(1, 41) for i in range(1, 6)]
    ids = {v: i for i, v in enumerate(sorted({x for e in edges for x in e}))}
    a, b = (np.array([ids[e[k]] for e in edges] + [ids[e[1 - k]] for e in edges]) for k in (0, 1))
    color = np.zeros(len(ids), int)
    color[ids[101]] = 1
    assert len(set(cluster.alike(color, a, b).tolist())) == 6
    g = Graph.from_edges(spark.createDataFrame(edges, "a long, b long")).kept()
    runs = [Run(i, v, 1000, 3, 1, 20) for i, v in enumerate((0, 100, 101))]
    one, _ = cluster.local_clusters(g, runs, 8)
    assert {tuple(r) for r in one.collect()} == {(r.run_id, r.v, r.rank) for r in cluster.ball_clusters(g, runs, 8).collect() if r.v is not None}
