"""Queries of the methods, measures, baselines and checks, and their SQL for DuckDB.

The SQL is another formulation: walks are one recursive CTE, prefix cuts count earlier neighbours per vertex, and
components are reachability.
"""

from __future__ import annotations

import re
from dataclasses import replace
from fractions import Fraction

import pandas as pd
from pyspark.sql import functions as F

from ..graph import Graph, boundary, components, conductance_in, edges_between, min_conductance, overlap, report, volume
from ..operators import analysis, baselines, cluster, cost, partition, sampling, sweep, walk
from ..operators.walk import Run
from ..params import UNIT, Constants, f2, max_draws, scale_count, scale_law, schedule, valid_scales
from ..session import cut
from ..sources.builders import BUILDERS, EDGES_SQL, KINDS, load, vid

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, f, sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        SQL[name] = sql


def graph(spark, d: str, name: str) -> Graph:
    return BUILDERS[name](spark, d).kept()


def g_sql(name: str) -> str:
    return f"e AS ({EDGES_SQL[name]}), arcs AS (SELECT a AS src, b AS dst FROM e WHERE a <> b UNION SELECT b, a FROM e WHERE a <> b), vx AS (SELECT src AS v, count(*) AS deg FROM arcs GROUP BY 1), tot AS (SELECT CAST(sum(deg) AS BIGINT) AS vol FROM vx)"


def w_sql(runs: list[Run], steps: int, alive: str | None = None, killed: bool = False) -> str:
    """Recursive walk as CTEs runs and w(run_id, t, v, mass); alive: a query with one column v."""
    rows = ", ".join(f"({r.run_id}, CAST({r.seed} AS BIGINT), CAST({r.eps_units} AS BIGINT), {r.b}, {r.phi_num}, {r.phi_den}, CAST({r.slope_units!r} AS DOUBLE))" for r in runs)
    target, keep = "arcs.dst", ""
    if alive:
        target = "arcs.dst" if killed else "CASE WHEN arcs.dst IN (SELECT v FROM alive) THEN arcs.dst ELSE arcs.src END"
        keep = "AND arcs.dst IN (SELECT v FROM alive)" if killed else ""
    return (f"alive AS ({alive}), " if alive else "") + f"""runs(run_id, seed, eps, b, pn, pd, sl) AS (VALUES {rows}),
w AS (SELECT run_id, 0 AS t, seed AS v, CAST({UNIT} AS BIGINT) AS mass FROM runs
 UNION ALL SELECT run_id, t, v, CAST(sum(m) AS BIGINT) FROM (
  SELECT w.run_id, w.t + 1 AS t, w.v, w.mass // 2 AS m FROM w JOIN vx ON vx.v = w.v JOIN runs ON runs.run_id = w.run_id
   WHERE w.t < {steps} AND w.mass >= deg * eps
  UNION ALL SELECT w.run_id, w.t + 1, {target}, w.mass // (2 * deg) FROM w JOIN vx ON vx.v = w.v JOIN runs ON runs.run_id = w.run_id
   JOIN arcs ON arcs.src = w.v WHERE w.t < {steps} AND w.mass >= deg * eps {keep}) x WHERE m > 0 GROUP BY run_id, t, v)"""


R_SQL = """r AS (SELECT w.run_id, w.t, w.v, w.mass, vx.deg, w.mass / CAST(vx.deg AS DOUBLE) AS ratio,
  row_number() OVER (PARTITION BY w.run_id, w.t ORDER BY w.mass / CAST(vx.deg AS DOUBLE) DESC, w.v) AS j FROM w JOIN vx ON vx.v = w.v),
lam AS (SELECT *, CAST(sum(deg) OVER o AS BIGINT) AS prefix_vol, CAST(sum(mass) OVER o AS BIGINT) AS prefix_mass FROM r
  WINDOW o AS (PARTITION BY run_id, t ORDER BY j ROWS UNBOUNDED PRECEDING))"""
C_SQL = R_SQL + """,
back AS (SELECT p.run_id, p.t, p.j, count(q.v) AS n FROM r p JOIN arcs ON arcs.src = p.v
  LEFT JOIN r q ON q.v = arcs.dst AND q.run_id = p.run_id AND q.t = p.t AND q.j < p.j GROUP BY 1, 2, 3),
cuts AS (SELECT lam.*, CAST(sum(deg - 2 * n) OVER (PARTITION BY lam.run_id, lam.t ORDER BY lam.j ROWS UNBOUNDED PRECEDING) AS BIGINT) AS cut
  FROM lam JOIN back ON back.run_id = lam.run_id AND back.t = lam.t AND back.j = lam.j),
slope AS (SELECT lam.run_id, t, coalesce(arg_min(ratio, j) FILTER (WHERE prefix_vol >= (1 << b)), 0.0) AS slope
  FROM lam JOIN runs ON runs.run_id = lam.run_id GROUP BY 1, 2),
conds AS (SELECT c.run_id, c.t, c.j, c.v, c.mass, prefix_vol, cut, least(prefix_vol, vol - prefix_vol) AS side,
  least(prefix_vol, vol - prefix_vol) > 0 AND cut * pd <= pn * least(prefix_vol, vol - prefix_vol) AS c1, 6 * prefix_vol <= 5 * vol AS c2, prefix_vol >= (1 << b) AS c3, slope >= sl AS c4
  FROM cuts c JOIN slope s ON s.run_id = c.run_id AND s.t = c.t JOIN runs ON runs.run_id = c.run_id CROSS JOIN tot)"""


def hit_sql(use=cluster.ALL, pick: str = "j") -> str:
    where = " AND ".join(["t > 0", *use])
    return f", hit AS (SELECT run_id, arg_min(struct_pack(t := t, j := j, prefix_vol := prefix_vol, cut := cut, side := side), struct_pack(t := t, k := {pick}, j := j)) AS h FROM conds WHERE {where} GROUP BY run_id)"


def rec(*parts: str, select: str) -> str:
    return "WITH RECURSIVE " + ", ".join(p.removeprefix(", ") for p in parts) + " " + select


def cust(k: int) -> int:
    return k * KINDS + 2


def practical(seeds: list[int], phi="1/10", b: int = 4, eps: float = 1e-12, slope: float = 1e-6, first: int = 0) -> list[Run]:
    return [cluster.run_of(first + i, s, schedule(1000, Fraction(phi), b, t_max=1, eps=eps, slope=slope)) for i, s in enumerate(seeds)]


# ---- graphs and measures -------------------------------------------------------------------------

for _name, _short in {"fk_forest": "fk_forest", "nation_forest": "nation_forest", "customer_part": "customer_part", "customer_supplier": "customer_supplier", "part_supplier": "part_supplier", "order_part": "order_part", "page_link": "page_link", "page_host": "page_host", "document_line": "doc_line", "user_hour": "user_hour", "conversation_path": "conversation_path", "nation_trade": "nation_trade", "part_coorder": "coorder", "knn": "knn"}.items():
    add(f"g_{_short}_arcs", lambda s, d, n=_name: BUILDERS[n](s, d).arcs, f"WITH {g_sql(_name)} SELECT src, dst FROM arcs")

#: sets of F1: each nation with its customers and orders
NATION_SETS_SQL = f"sets AS (SELECT n_nationkey AS set_id, CAST(n_nationkey AS BIGINT) * {KINDS} + 1 AS v FROM nation UNION ALL SELECT c_nationkey, c_custkey * {KINDS} + 2 FROM customer UNION ALL SELECT s_nationkey, s_suppkey * {KINDS} + 3 FROM supplier UNION ALL SELECT c_nationkey, o_orderkey * {KINDS} + 4 FROM orders JOIN customer ON c_custkey = o_custkey)"
MEASURE_SQL = NATION_SETS_SQL + ", inn AS (SELECT s.set_id, count(*) AS n FROM sets s JOIN arcs ON src = s.v JOIN sets q ON q.set_id = s.set_id AND q.v = dst GROUP BY 1), m AS (SELECT s.set_id, CAST(sum(deg) AS BIGINT) AS vol, CAST(sum(deg) - coalesce(max(n), 0) AS BIGINT) AS cut FROM sets s JOIN vx ON vx.v = s.v LEFT JOIN inn ON inn.set_id = s.set_id GROUP BY 1)"


def nation_sets(spark, d):
    c = load(spark, d, "customer")
    out = load(spark, d, "nation").select(F.col("n_nationkey").alias("set_id"), vid("n_nationkey", "nation").alias("v"))
    out = out.union(c.select("c_nationkey", vid("c_custkey", "customer"))).union(load(spark, d, "supplier").select("s_nationkey", vid("s_suppkey", "supplier")))
    o = load(spark, d, "orders").join(c.select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
    return out.union(o.select("c_nationkey", vid("o_orderkey", "order")))


add("m_degree", lambda s, d: graph(s, d, "fk_forest").vertices, f"WITH {g_sql('fk_forest')} SELECT v, deg, 0 AS loops FROM vx")
add("m_volume", lambda s, d: volume(graph(s, d, "fk_forest"), nation_sets(s, d)), f"WITH {g_sql('fk_forest')}, {MEASURE_SQL} SELECT set_id, vol FROM m")
add("m_boundary", lambda s, d: boundary(graph(s, d, "fk_forest"), nation_sets(s, d)), f"WITH {g_sql('fk_forest')}, {MEASURE_SQL} SELECT set_id, cut FROM m")
add("m_conductance", lambda s, d: report(graph(s, d, "fk_forest"), nation_sets(s, d)).select("set_id", "cut", "vol", "phi"), f"WITH {g_sql('fk_forest')}, {MEASURE_SQL} SELECT set_id, cut, m.vol, cut / CAST(least(m.vol, tot.vol - m.vol) AS DOUBLE) AS phi FROM m, tot")
add("m_balance", lambda s, d: report(graph(s, d, "fk_forest"), nation_sets(s, d)).select("set_id", "balance"), f"WITH {g_sql('fk_forest')}, {MEASURE_SQL} SELECT set_id, least(m.vol, tot.vol - m.vol) / CAST(tot.vol AS DOUBLE) AS balance FROM m, tot")


def segment(spark, d, name):
    return load(spark, d, "customer").filter(F.col("c_mktsegment") == name).select(vid("c_custkey", "customer").alias("v"))


def parts(spark, d):
    return load(spark, d, "part").filter("p_size <= 25").select(vid("p_partkey", "part").alias("v"))


add("m_edges_between", lambda s, d: edges_between(graph(s, d, "customer_part"), segment(s, d, "BUILDING"), parts(s, d)),
    f"WITH {g_sql('customer_part')} SELECT count(*) AS edges FROM arcs JOIN customer ON src = c_custkey * {KINDS} + 2 JOIN part ON dst = p_partkey * {KINDS} + 5 WHERE c_mktsegment = 'BUILDING' AND p_size <= 25")


def nations_below(spark, n: int):
    return spark.range(n).select((F.col("id") * KINDS + 1).alias("v"))


def small_trade(spark, d, n: int) -> Graph:
    return graph(spark, d, "nation_trade").induced(nations_below(spark, n)).kept()


def exhaust_sql(n: int, restrict: bool = False) -> str:
    deg = "SELECT v, deg FROM vx" if restrict else "SELECT src AS v, count(*) AS deg FROM sub GROUP BY 1"
    return f"WITH {g_sql('nation_trade')}, sub AS (SELECT * FROM arcs WHERE src < {n * KINDS} AND dst < {n * KINDS}), dg AS ({deg}), ids AS (SELECT v, deg, CAST(row_number() OVER (ORDER BY v) - 1 AS INT) AS i FROM dg WHERE v IN (SELECT src FROM sub)), st AS (SELECT CAST(sum(deg) AS BIGINT) AS vol, count(*) AS n FROM ids), masks AS (SELECT unnest(range(1, 1 << CAST(n - 1 AS INT))) AS mask FROM st), vols AS (SELECT mask, CAST(sum(deg) AS BIGINT) AS v FROM masks JOIN ids ON (mask >> i) & 1 = 1 GROUP BY 1), ct AS (SELECT mask, count(*) AS c FROM masks, sub JOIN ids x ON x.v = src JOIN ids y ON y.v = dst WHERE (mask >> x.i) & 1 = 1 AND (mask >> y.i) & 1 = 0 GROUP BY 1) SELECT min(coalesce(c, 0) / CAST(least(v, st.vol - v) AS DOUBLE)) AS phi FROM vols LEFT JOIN ct USING (mask), st"


add("m_min_conductance_exhaustive", lambda s, d: min_conductance(small_trade(s, d, 12)).select("phi"), exhaust_sql(12))
add("m_min_conductance_in", lambda s, d: min_conductance(graph(s, d, "nation_trade").restrict(nations_below(s, 10)).kept()).select("phi"), exhaust_sql(10, True))


def best_nations(spark, d):
    g = small_trade(spark, d, 10)
    best, n = min_conductance(g).select("phi"), g.vertices.count()
    half = g.vertices.orderBy("v").limit(n // 2).select(F.lit(0).alias("set_id"), "v")
    return report(g, half).crossJoin(best.withColumnRenamed("phi", "best")).select("phi", "best", (F.col("phi") <= F.col("best")).alias("is_sparsest"))


def subsets_sql(n: int, restrict: bool = False) -> str:
    """CTEs ids(v, deg, i), st(vol, n) and phis(mask, phi) of every proper subset, on the first n nations."""
    return exhaust_sql(n, restrict).removeprefix("WITH ").rsplit(" SELECT min(", 1)[0] + ", phis AS (SELECT mask, coalesce(c, 0) / CAST(least(v, st.vol - v) AS DOUBLE) AS phi FROM vols LEFT JOIN ct USING (mask), st)"


add("m_is_sparsest", best_nations, f"WITH {subsets_sql(10)}, half AS (SELECT (1 << CAST(n // 2 AS INT)) - 1 AS m FROM st) SELECT (SELECT phi FROM phis, half WHERE mask = m) AS phi, (SELECT min(phi) FROM phis) AS best, (SELECT phi FROM phis, half WHERE mask = m) <= (SELECT min(phi) FROM phis) AS is_sparsest")


def trade_in(spark, d):
    a = nations_below(spark, 10)
    return conductance_in(graph(spark, d, "nation_trade"), a, nations_below(spark, 4).select(F.lit(0).alias("set_id"), "v")).select("cut", "vol")


add("m_conductance_in", trade_in, f"WITH {g_sql('nation_trade')} SELECT (SELECT count(*) FROM arcs WHERE src < {4 * KINDS} AND dst >= {4 * KINDS} AND dst < {10 * KINDS}) AS cut, (SELECT CAST(sum(deg) AS BIGINT) FROM vx WHERE v < {4 * KINDS}) AS vol")


def even(spark, d, g):
    return g.vertices.filter(f"v % {KINDS} <> 4 or v % {2 * KINDS} = 4").select("v")


def induced_deg(spark, d):
    g = graph(spark, d, "fk_forest")
    return g.induced(even(spark, d, g)).vertices.select("v", "deg")


def restrict_loops(spark, d):
    g = graph(spark, d, "fk_forest")
    return g.restrict(even(spark, d, g)).loops.select("v", "loops")


_EVEN = f"a AS (SELECT v FROM vx WHERE v % {KINDS} <> 4 OR v % {2 * KINDS} = 4)"
add("m_induced", induced_deg, f"WITH {g_sql('fk_forest')}, {_EVEN} SELECT src AS v, count(*) AS deg FROM arcs WHERE src IN (SELECT v FROM a) AND dst IN (SELECT v FROM a) GROUP BY 1")
add("m_restrict_loops", restrict_loops, f"WITH {g_sql('fk_forest')}, {_EVEN} SELECT src AS v, count(*) AS loops FROM arcs WHERE src IN (SELECT v FROM a) AND dst NOT IN (SELECT v FROM a) GROUP BY 1")


def restrict_vs_induced(spark, d):
    g, a = graph(spark, d, "nation_trade"), nations_below(spark, 10)
    x = min_conductance(g.restrict(a).kept()).select(F.col("phi").alias("phi_restricted"))
    y = min_conductance(g.induced(a).kept()).select(F.col("phi").alias("phi_induced"))
    return x.crossJoin(y).withColumn("ok", F.coalesce(F.col("phi_restricted") <= F.col("phi_induced"), F.lit(True)))


add("m_restrict_vs_induced", restrict_vs_induced, f"SELECT a.phi AS phi_restricted, b.phi AS phi_induced, coalesce(a.phi <= b.phi, true) AS ok FROM ({exhaust_sql(10, True)}) a, ({exhaust_sql(10)}) b")
for _n in ("document_line", "conversation_path", "page_host"):
    add({"document_line": "m_components", "conversation_path": "x_components_paths", "page_host": "x_components_hosts"}[_n], lambda s, d, n=_n: components(graph(s, d, n)),
        rec(g_sql(_n), "reach AS (SELECT v, v AS o FROM vx UNION SELECT reach.v, dst FROM reach JOIN arcs ON src = reach.o)", select="SELECT v, min(o) AS comp FROM reach GROUP BY v"))

# ---- parameters ------------------------------------------------------------------------------------

_GRID = [(n, m, b) for n, m in ((1, 10), (1, 2), (9, 10)) for b in (1, 4)]


def trees(spark, d):
    """(n, vol): the volume of every nation's tree of customers and orders."""
    o = load(spark, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("orders"))
    c = load(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("n")).join(o, "c_custkey", "left")
    return c.groupBy("n").agg((2 * F.sum(1 + F.coalesce("orders", F.lit(0)))).alias("vol"))


#: scale_count of vol
ELL = "greatest(1, length(bin(vol - 1)) - 1)"
TREES_SQL = "trees AS (SELECT c_nationkey AS n, CAST(2 * (count(DISTINCT c_custkey) + count(o_orderkey)) AS BIGINT) AS vol FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1), l AS (SELECT *, greatest(1, CAST(ceil(log2(vol / 2.0)) AS INT)) AS ell FROM trees)"


def per_tree(spark, d, f, schema: str):
    """The rows of f(vol) for every nation's tree, made in the tasks."""

    def go(batches):
        for part in batches:
            for n, vol in zip(part["n"], part["vol"], strict=True):
                rows = f(int(vol))
                yield pd.DataFrame([(n, *r) for r in rows], columns=[x.split()[0] for x in ("n int, " + schema).split(", ")])

    return trees(spark, d).mapInPandas(go, "n int, " + schema)


def _schedules(vol: int):
    return [(vol, n, m, b, s.ell, s.t1, s.t_last, f"{s.f1:.10e}", f"{s.eps:.10e}", f"{s.slope_floor:.10e}", s.decay_ok()) for n, m, b in _GRID for s in [schedule(vol, Fraction(n, m), b)]]


def _inequalities(vol: int):
    """As the schedule uses them: every threshold carries the factor 1 / (ell + 2)."""
    k = scale_count(vol) + 2
    return [(i + 1, a / k >= b / k, a / k == b / k) for i, (_, a, b) in enumerate(Constants().inequalities())]


_P = ", ".join(f"({n}, {m}, {b})" for n, m, b in _GRID)
_P_SQL = f"{TREES_SQL}, g(num, den, b) AS (VALUES {_P}), p AS (SELECT *, CAST(num AS DOUBLE) / den AS phi FROM l, g), s AS (SELECT *, CAST(ceil(2 / (phi * phi) * ln(200 * (ell + 2) * sqrt(vol / 2.0))) AS INT) AS t1 FROM p)"
add("p_schedule", lambda s, d: per_tree(s, d, _schedules, "vol long, num int, den int, b int, ell int, t1 int, t_last int, f1 string, eps string, slope_floor string, decay_ok boolean"),
    f"WITH {_P_SQL} SELECT n, vol, num, den, b, ell, t1, (ell + 1) * t1 AS t_last, printf('%.10e', 1 / (280.0 * (ell + 2) * (ell + 1) * t1)) AS f1, printf('%.10e', 1 / (1800.0 * (ell + 2) * ((ell + 1) * t1) * (1 << b))) AS eps, printf('%.10e', 1 / (140.0 * (ell + 2) * (1 << b))) AS slope_floor, sqrt(vol / 2.0) * pow(1 - phi * phi / 2, t1) < 1 / (200.0 * (ell + 2)) AS decay_ok FROM s")
add("p_inequalities", lambda s, d: per_tree(s, d, _inequalities, "id int, holds boolean, tight boolean"),
    f"WITH {TREES_SQL}, t(id, a, b) AS (VALUES (1, 280, 2 * 140), (2, 60, 40), (3, 1800, 160), (4, 140, 80), (5, 53 * 140, 7200), (6, 200, 4 * 50), (7, 3150, 311 * 5)) SELECT n, id, a * (ell + 2) >= b * (ell + 2) AS holds, a * (ell + 2) = b * (ell + 2) AS tight FROM l, t")
add("p_f1_f2", lambda s, d: per_tree(s, d, lambda vol: [(vol, f"{f2(vol, Fraction(9, 10)):.10e}", max_draws(vol, 0.25))], "vol long, f2 string, draws long"),
    f"WITH {TREES_SQL}, p AS (SELECT *, 9 / 70.0::DOUBLE AS phi FROM l), s AS (SELECT *, ceil(2 / (phi * phi) * ln(200 * (ell + 2) * sqrt(vol / 2.0))) AS t1 FROM p) SELECT n, vol, printf('%.10e', 1 / (280.0 * (ell + 2) * (ell + 1) * t1) / 2) AS f2, CAST(12 * vol / 2 * 2 AS BIGINT) AS draws FROM s")
add("p_scale_law", lambda s, d: per_tree(s, d, lambda vol: [(i + 1, x) for i, x in enumerate(scale_law(scale_count(vol)))], "b int, p double"),
    f"WITH {TREES_SQL}, x AS (SELECT n, ell, unnest(range(1, ell + 1)) AS i FROM l) SELECT n, CAST(i AS INT) AS b, pow(2.0, -i) / (1 - pow(2.0, -ell)) AS p FROM x")

# ---- walks, curve, sweep -------------------------------------------------------------------------


def one_step(spark, d):
    """One step from two customers whose odd orders are taken out: lost neighbours are loops."""
    g = graph(spark, d, "fk_forest")
    kept = g.restrict(cut(even(spark, d, g))).kept()
    return walk.walk(kept, _TWO, 1).filter("t = 1").select("run_id", "v", (F.col("mass") / F.lit(float(UNIT))).alias("mass"))


_TWO = [Run(0, cust(0)), Run(1, cust(1))]
add("w_step_example", one_step, f"WITH {g_sql('fk_forest')}, {_EVEN}, runs(run_id, seed) AS (VALUES (CAST(0 AS BIGINT), {cust(0)}), (1, {cust(1)})), z AS (SELECT run_id, v, deg, (SELECT count(*) FROM arcs WHERE src = seed AND dst NOT IN (SELECT v FROM a)) AS loops FROM runs JOIN vx ON v = seed), m AS (SELECT run_id, v, CAST({UNIT} AS BIGINT) // 2 + loops * (CAST({UNIT} AS BIGINT) // (2 * deg)) AS mass FROM z UNION ALL SELECT run_id, dst, CAST({UNIT} AS BIGINT) // (2 * deg) FROM z JOIN arcs ON src = z.v WHERE dst IN (SELECT v FROM a)) SELECT run_id, v, mass / CAST({UNIT} AS DOUBLE) AS mass FROM m")


def walk_query(name, fix, runs, steps, cols="run_id, t, v, mass", alive=None, alive_sql=None, killed=False):
    def f(spark, d):
        g = graph(spark, d, fix)
        return walk.walk(g, runs, steps, alive(spark, d) if alive else None, killed).selectExpr(*cols.split(", "))

    add(name, f, rec(g_sql(fix), w_sql(runs, steps, alive_sql, killed), select=f"SELECT {cols} FROM w"))


walk_query("w_exact_t5", "customer_part", [Run(0, cust(0))], 5)
walk_query("w_exact_knn", "knn", [Run(0, 13)], 3)
walk_query("w_truncated_t6", "fk_forest", [Run(0, cust(0), UNIT // 100000), Run(1, cust(1), UNIT // 500)], 6)
walk_query("w_batch_runs", "page_link", [Run(i, k * KINDS + 6, e) for i, (k, e) in enumerate((k, e) for k in range(4) for e in (1000, UNIT // 5000))], 4)


def region_tree(spark, d):
    """Vertices of F1 with ids of regions, nations and customers only: orders are removed."""
    return graph(spark, d, "fk_forest").vertices.filter(f"v % {KINDS} <= 3").select("v")


_ALIVE = f"SELECT v FROM vx WHERE v % {KINDS} <= 3"
walk_query("w_restricted_t5", "fk_forest", _TWO, 5, alive=region_tree, alive_sql=_ALIVE)
walk_query("w_killed_t8", "fk_forest", _TWO, 8, alive=region_tree, alive_sql=_ALIVE, killed=True)
add("w_degree_vector", lambda s, d: walk.degree_vector(graph(s, d, "fk_forest"), region_tree(s, d)), f"WITH {g_sql('fk_forest')}, a AS ({_ALIVE}) SELECT v, deg, CAST(sum(deg) OVER () AS BIGINT) AS vol FROM vx WHERE v IN (SELECT v FROM a)")
add("w_escape_t8", lambda s, d: analysis.escape_mass(graph(s, d, "fk_forest"), region_tree(s, d), [cust(0), cust(1)], 8),
    rec(g_sql("fk_forest"), w_sql([Run(cust(0), cust(0)), Run(cust(1), cust(1))], 8), select=f"SELECT CAST(run_id AS BIGINT) AS seed, t, CAST(coalesce(sum(mass) FILTER (WHERE v % {KINDS} > 3), 0) AS BIGINT) AS outside FROM w GROUP BY 1, 2"))


def on_walk(name, fix, runs, steps, f, select, sql=R_SQL):
    def q(spark, d):
        g = graph(spark, d, fix)
        return f(spark, g, cut(walk.walk(g, runs, steps)), walk.runs_frame(g, runs))

    add(name, q, rec(g_sql(fix), w_sql(runs, steps), sql, select=select))


_C = practical([cust(0), cust(1)])
on_walk("w_support_stats", "fk_forest", _TWO, 4, lambda s, g, w, r: walk.support_stats(g, w), "SELECT run_id, t, count(*) AS n, CAST(sum(deg) AS BIGINT) AS vol, CAST(sum(w.mass) AS BIGINT) AS mass FROM w JOIN vx USING (v) GROUP BY 1, 2", "one AS (SELECT 1)")
on_walk("c_order", "fk_forest", _TWO, 3, lambda s, g, w, r: sweep.ranked(g, w).select("run_id", "t", "j", "v"), "SELECT run_id, t, j, v FROM r")
on_walk("c_curve", "customer_part", [Run(0, cust(0))], 3, lambda s, g, w, r: sweep.ranked(g, w).select("t", "j", "prefix_vol", "prefix_mass", "ratio"), "SELECT t, j, prefix_vol, prefix_mass, ratio FROM lam")
_XS = (0, 1, 2, 5, 17, 100, 100000)
_XSQL = "xs(x) AS (VALUES " + ", ".join(f"(CAST({x} AS BIGINT))" for x in _XS) + "), p AS (SELECT run_id, t, x, arg_min(struct_pack(l := prefix_vol, m := prefix_mass, r := ratio), j) AS p FROM lam JOIN xs ON prefix_vol >= x GROUP BY 1, 2, 3), g0 AS (SELECT run_id, t, x, CAST(sum(mass) AS DOUBLE) AS total FROM w, xs GROUP BY 1, 2, 3)"


def _curve(spark, g, w, r):
    return sweep.curve_at(sweep.ranked(g, w), spark.createDataFrame([(x,) for x in _XS], "x long"))


on_walk("c_curve_at", "fk_forest", _TWO, 3, lambda s, g, w, r: _curve(s, g, w, r).select("run_id", "t", "x", "value"), "SELECT g0.run_id, g0.t, g0.x, coalesce(p.p.m - p.p.r * (p.p.l - g0.x), total) AS value FROM g0 LEFT JOIN p USING (run_id, t, x)", R_SQL + ", " + _XSQL)
on_walk("c_slope_at", "fk_forest", _TWO, 3, lambda s, g, w, r: _curve(s, g, w, r).select("run_id", "t", "x", "slope"), "SELECT g0.run_id, g0.t, g0.x, coalesce(p.p.r, 0.0) AS slope FROM g0 LEFT JOIN p USING (run_id, t, x)", R_SQL + ", " + _XSQL)
_YS = [UNIT // 8, UNIT // 2, UNIT * 3 // 4]
on_walk("c_inverse", "fk_forest", _TWO, 3, lambda s, g, w, r: sweep.curve_inverse(sweep.ranked(g, w), s.createDataFrame([(y,) for y in _YS], "y long")),
        "SELECT run_id, t, y, p.l - (p.m - y) / p.r AS x FROM q", R_SQL + ", ys(y) AS (VALUES " + ", ".join(f"(CAST({y} AS BIGINT))" for y in _YS) + "), q AS (SELECT run_id, t, y, arg_min(struct_pack(l := prefix_vol, m := prefix_mass, r := ratio), j) AS p FROM lam JOIN ys ON prefix_mass >= y GROUP BY 1, 2, 3)")
on_walk("c_prefix_cuts", "fk_forest", _C, 4, lambda s, g, w, r: sweep.prefix_cuts(g, sweep.ranked(g, w)).select("run_id", "t", "j", "prefix_vol", "cut"), "SELECT run_id, t, j, prefix_vol, cut FROM cuts", C_SQL)
on_walk("c_conditions", "page_link", practical([6, 22], b=3), 4, lambda s, g, w, r: sweep.conditions(g, w, r).select("run_id", "t", "j", "c1", "c2", "c3", "c4"), "SELECT run_id, t, j, c1, c2, c3, c4 FROM conds", C_SQL)
for _pick, _key in {"first": "j", "best": "cut / CAST(side AS DOUBLE)", "largest": "-j"}.items():
    on_walk(f"c_pick_{_pick}", "page_link", practical([6, 22], b=3, phi="3/10"), 4, lambda s, g, w, r, p=_pick: sweep.hits(sweep.conditions(g, w.filter("t > 0"), r), pick=p).select("run_id", "t", "j", "prefix_vol", "cut"),
            "SELECT run_id, t, h.j, h.prefix_vol, h.cut FROM (SELECT run_id, t, arg_min(struct_pack(j := j, prefix_vol := prefix_vol, cut := cut), struct_pack(k := " + _key + ", j := j)) AS h FROM conds WHERE t > 0 AND c1 AND c2 AND c3 AND c4 GROUP BY 1, 2)", C_SQL)


def scan_all(spark, g, w, r):
    full = g.vertices.select("v").crossJoin(F.broadcast(w.select("run_id", "t").distinct())).join(w, ["run_id", "t", "v"], "left")
    return sweep.hits(sweep.conditions(g, full.select("run_id", "t", "v", F.coalesce("mass", F.lit(0)).alias("mass")).filter("t > 0"), r)).select("run_id", "t", "j")


on_walk("c_scan_all", "page_link", practical([6, 22], b=3, phi="3/10"), 3, scan_all, "SELECT run_id, t, min(j) AS j FROM conds WHERE t > 0 AND c1 AND c2 AND c3 AND c4 GROUP BY 1, 2",
        C_SQL.replace("FROM w JOIN vx ON vx.v = w.v)", "FROM (SELECT k.run_id, k.t, vx.v, coalesce(w0.mass, 0) AS mass FROM (SELECT DISTINCT run_id, t FROM w) k CROSS JOIN vx LEFT JOIN w w0 ON w0.run_id = k.run_id AND w0.t = k.t AND w0.v = vx.v) w JOIN vx ON vx.v = w.v)"))

# ---- local clustering ------------------------------------------------------------------------------


def lc_query(name, fix, runs, steps, what="members", use=cluster.ALL, alive=None, alive_sql=None):
    def f(spark, d):
        g = graph(spark, d, fix)
        c, s = cluster.local_clusters(g, runs, steps, alive(spark, d) if alive else None, use)
        return c if what == "members" else s.withColumn("phi", F.col("cut") / F.col("side")).drop("side")

    select = {"members": "SELECT hit.run_id, v, conds.j AS rank FROM conds JOIN hit ON hit.run_id = conds.run_id AND conds.t = h.t AND conds.j <= h.j", "stops": "SELECT run_id, h.t, h.j, h.prefix_vol, h.cut, h.cut / CAST(h.side AS DOUBLE) AS phi FROM hit"}[what]
    add(name, f, rec(g_sql(fix), w_sql(runs, steps, alive_sql), C_SQL, hit_sql(use), select=select))


lc_query("lc_flagship", "fk_forest", practical([cust(0)]), 6)
_GRID_RUNS = [r for i, (p, b) in enumerate((p, b) for p in ("1/10", "3/10") for b in (1, 4, 8)) for r in practical([cust(0), cust(1)], p, b, first=2 * i)]
lc_query("lc_grid", "fk_forest", _GRID_RUNS, 6, "stops")
lc_query("lc_grid_pages", "page_link", [r for i, (p, b) in enumerate((p, b) for p in ("1/10", "3/10") for b in (1, 4, 8)) for r in practical([6, 22], p, b, first=2 * i)], 5, "stops")
lc_query("lc_grid_lines", "document_line", practical([8, 24], "1/10", 4), 3, "stops")
lc_query("lc_untruncated", "page_link", [Run(0, 6, 0, 3, 1, 10, UNIT * 1e-6)], 5, "stops")
lc_query("lc_epsilon_sweep", "fk_forest", [r for i, e in enumerate((1e-12, 1e-5, 1e-3)) for r in practical([cust(1)], eps=e, first=i)], 6, "stops")
for _k, _c in enumerate(cluster.ALL):
    lc_query(f"lc_ablate_{_c}", "fk_forest", practical([cust(0), cust(1)]), 5, "stops", tuple(c for c in cluster.ALL if c != _c))
lc_query("lc_negative_control", "customer_part", practical([cust(0), cust(1)], "1/20", 4), 4, "stops")
lc_query("lc_social", "user_hour", practical([10, 26], "3/5", 3), 5, "stops")


def all_seeds(g, phi="1/2", b: int = 1, **more) -> list[Run]:
    """A run from every vertex, with the vertex as its id."""
    one = practical([0], phi, b, **more)[0]
    return [replace(one, run_id=r.v, seed=r.v) for r in g.vertices.select("v").orderBy("v").toLocalIterator()]


def all_seeds_sql(fix: str, steps: int, phi="1/2", b: int = 1, ids: str = "SELECT v FROM vx") -> str:
    """The recursive walk from every vertex."""
    text = w_sql(practical([0], phi, b), steps)
    r = practical([0], phi, b)[0]
    head, tail = text.split("(VALUES ", 1)
    return head + f"(SELECT v, v, CAST({r.eps_units} AS BIGINT), {r.b}, {r.phi_num}, {r.phi_den}, CAST({r.slope_units!r} AS DOUBLE) FROM ({ids}) s)" + tail[tail.index("),\nw AS") + 1 :]


def coverage(spark, d):
    g = graph(spark, d, "conversation_path")
    _, s = cluster.local_clusters(g, all_seeds(g), 6)
    return s.withColumn("phi", F.col("cut") / F.col("side")).drop("side")


add("lc_coverage", coverage, rec(g_sql("conversation_path"), all_seeds_sql("conversation_path", 6), C_SQL, hit_sql(), select="SELECT run_id, h.t, h.j, h.prefix_vol, h.cut, h.cut / CAST(h.side AS DOUBLE) AS phi FROM hit"))


def trace(spark, d):
    g, runs = graph(spark, d, "fk_forest"), _C
    return cluster.local_cluster_trace(g, cut(walk.walk(g, runs, 4)), runs)


add("lc_trace", trace, rec(g_sql("fk_forest"), w_sql(_C, 4), C_SQL, select="SELECT run_id, t, count(*) AS n, max(prefix_vol) AS vol, CAST(sum(mass) AS BIGINT) AS mass, min(cut) FILTER (WHERE c1 AND c2 AND c3 AND c4) AS best_cut, bool_or(c1 AND c2 AND c3 AND c4) AS hit FROM conds WHERE t > 0 GROUP BY 1, 2"))


def restricted(spark, d):
    g = graph(spark, d, "fk_forest")
    return cluster.local_clusters(g, practical([cust(0)], "1/2", 2), 4, cut(region_tree(spark, d)))[1].select("run_id", "t", "j", "prefix_vol", "cut")


#: conditions on the degree-preserving subgraph: arcs that leave it are loops, so they are no cut
_IN_A = C_SQL.replace("JOIN arcs ON arcs.src = p.v\n", "JOIN arcs ON arcs.src = p.v AND arcs.dst IN (SELECT v FROM alive)\n").replace("sum(deg - 2 * n)", "sum(inside - 2 * n)").replace("count(q.v) AS n FROM", "count(q.v) AS n, count(*) AS inside FROM").replace("CROSS JOIN tot", "CROSS JOIN (SELECT CAST(sum(deg) AS BIGINT) AS vol FROM vx WHERE v IN (SELECT v FROM alive)) tot")
add("lc_restricted", restricted, rec(g_sql("fk_forest"), w_sql(practical([cust(0)], "1/2", 2), 4, _ALIVE), _IN_A, hit_sql(), select="SELECT run_id, h.t, h.j, h.prefix_vol, h.cut FROM hit"))


def auto(spark, d):
    g = graph(spark, d, "page_link")
    _, s, b = cluster.local_cluster_auto(g, 6, Fraction(1, 10), t_max=6, eps=1e-12, slope=1e-6)
    return s.withColumn("b", F.lit(b)).select("t", "j", "prefix_vol", "cut", "b")


_AUTO = [r for b in range(1, 5) for r in practical([6], "1/10", b, first=b)]
add("lc_auto_scale", auto, rec(g_sql("page_link"), w_sql(_AUTO, 6), C_SQL, hit_sql(), select="SELECT h.t, h.j, h.prefix_vol, h.cut, CAST(run_id AS INT) AS b FROM hit ORDER BY run_id LIMIT 1"))


def once(f):
    """A table that several queries report on is made once for a session and folder."""
    made: dict = {}

    def get(spark, d):
        key = (spark.sparkContext.applicationId, d)
        if key not in made:
            made[key] = cut(f(spark, d), f.__name__)
        return made[key]

    return get


@once
def theory(spark, d):
    """Theory parameters from every vertex of the paths at every scale: (run_id, t, v, rank, work, seed, b)."""
    g = graph(spark, d, "conversation_path")
    plans = [cluster.run_of(b, 0, schedule(g.vol, Fraction(1, 2), b)) for b in valid_scales(g.vol)]
    return cluster.every_seed(g, plans, schedule(g.vol, Fraction(1, 2), 1).t_last)


def theory_forest(spark, d):
    """Theory parameters on the nation trees from every nation, at the least, a middle and the largest scale."""
    g = graph(spark, d, "nation_forest")
    phi, ell = Fraction(9, 10), scale_count(g.vol)
    runs = [cluster.run_of(3 * n + i, n * KINDS + 1, schedule(g.vol, phi, b)) for n in range(25) for i, b in enumerate((1, (ell + 1) // 2, ell))]
    got = cluster.ball_clusters(g, runs, schedule(g.vol, phi, 1).t_last)
    return got.groupBy("run_id", "t", "work").agg(F.count("v").alias("size"))


add("lc_theory_profile", theory)
add("lc_theory_forest", theory_forest)


def modes_agree(spark, d):
    """The clusters of ball mode, compared with the same SQL as those of relational mode."""
    g, runs = graph(spark, d, "fk_forest"), practical([cust(0), cust(1)])
    return cluster.ball_clusters(g, runs, 5).filter("v is not null").select("run_id", "v", "rank")


_BALL = practical([cust(0), cust(1)])
add("udf_ball_runner", modes_agree, rec(g_sql("fk_forest"), w_sql(_BALL, 5), C_SQL, hit_sql(), select="SELECT hit.run_id, v, conds.j AS rank FROM conds JOIN hit ON hit.run_id = conds.run_id AND conds.t = h.t AND conds.j <= h.j"))

# ---- sampling and partition --------------------------------------------------------------------------

_U = [(i, (i * 7 % 16 + 0.5) / 16, (i * 5 % 16 + 0.25) / 16) for i in range(16)]


def literal_draws(spark):
    return spark.createDataFrame(_U, "draw long, u1 double, u2 double")


_U_SQL = "draws(draw, u1, u2) AS (VALUES " + ", ".join(f"({i}, {a!r}::DOUBLE, {b!r}::DOUBLE)" for i, a, b in _U) + ")"
_PICK_SQL = _U_SQL + ", iv AS (SELECT v, CAST(sum(deg) OVER (ORDER BY v) - deg AS BIGINT) AS lo, CAST(sum(deg) OVER (ORDER BY v) AS BIGINT) AS hi FROM vx), picked AS (SELECT draw, v FROM draws, tot, iv WHERE lo <= floor(u1 * vol) AND floor(u1 * vol) < hi), scaled AS (SELECT draw, CAST(least(greatest(ceil(-log2(1 - u2 * (1 - pow(2.0, -ell)))), 1), ell) AS INT) AS b FROM draws, (SELECT CAST(ceil(log2(vol / 2.0)) AS INT) AS ell FROM tot))"
add("slc_draws", lambda s, d: sampling.sample_by_degree(graph(s, d, "page_link"), literal_draws(s)), f"WITH {g_sql('page_link')}, {_PICK_SQL} SELECT draw, v FROM picked")
add("slc_scale_draws", lambda s, d: sampling.sample_scale(scale_count(graph(s, d, "page_link").vol), literal_draws(s)), f"WITH {g_sql('page_link')}, {_PICK_SQL} SELECT draw, b FROM scaled")


def slc(spark, d):
    g = graph(spark, d, "page_link")
    got = sampling.sampled_local_cluster(g, Fraction(3, 10), literal_draws(spark), t_max=5, eps=1e-12, slope=1e-6)
    return got.join(g.vertices, "v", "left").groupBy("draw", F.col("seed_v").alias("v"), "b").agg((F.count("rank") > 0).alias("found"), F.coalesce(F.sum("deg"), F.lit(0)).alias("vol"))


_SLC_W = w_sql([Run(0, 0)], 5).replace("VALUES (0, CAST(0 AS BIGINT), CAST(0 AS BIGINT), 1, 1, 10, CAST(0.0 AS DOUBLE))", f"SELECT draw, v, CAST({schedule(1000, Fraction(1, 2), 1, t_max=1, eps=1e-12).eps_units} AS BIGINT), b, 3, 10, CAST({1e-6 * UNIT!r} AS DOUBLE) FROM picked JOIN scaled USING (draw)")
add("slc_run", slc, rec(g_sql("page_link"), _PICK_SQL, _SLC_W, C_SQL, hit_sql(), select="SELECT CAST(draw AS BIGINT) AS draw, picked.v, b, h IS NOT NULL AS found, coalesce(h.prefix_vol, 0) AS vol FROM picked JOIN scaled USING (draw) LEFT JOIN hit ON hit.run_id = draw"))


def in_batches(f, items: list, size: int = 4096):
    """The union of f over runs of `size` items."""
    got = None
    for at in range(0, len(items), size):
        part = cut(f(items[at : at + size]), "runs")
        got = part if got is None else got.union(part)
    return got


def expected_overlap(spark, d):
    """Exact expectation of the sampled method on every path, by enumerating seeds and scales, and its bound."""
    g = graph(spark, d, "conversation_path")
    s = cut(components(g))
    ell = scale_count(g.vol)
    got = theory(spark, d)
    home = s.join(g.vertices, "v").select(F.col("v").alias("seed"), "comp", (F.col("deg") / F.lit(g.vol)).alias("of_seed"))
    of_scale = F.pow(F.lit(2.0), -F.col("b")) / F.lit(1 - 2.0**-ell)
    meta = got.select("run_id", "seed", "b").distinct().join(home, "seed").select("run_id", "comp", (F.col("of_seed") * of_scale).alias("pr"))
    inside = got.filter("v is not null").join(meta, "run_id").join(s, ["v", "comp"]).join(g.vertices, "v")
    value = inside.groupBy("comp").agg(F.sum(F.col("pr") * F.col("deg")).alias("value"))
    bound = s.join(g.vertices, "v").groupBy("comp").agg((F.sum("deg") / F.lit(4.0 * g.vol)).alias("bound"))
    return bound.join(value, "comp", "left").select("comp", F.coalesce("value", F.lit(0.0)).alias("value"), "bound", (F.coalesce("value", F.lit(0.0)) >= F.col("bound")).alias("ok"))


add("slc_expected_overlap", expected_overlap)


def pp(spark, d, fix="page_link", **more):
    g = graph(spark, d, fix).stored()
    # up to the method's own stop: a quarter of the volume gone, or its whole budget of draws
    o = dict(batch=64, t_max=12, eps=1e-12, slope=1e-6, pick="largest") | more
    return (g, *partition.peel_partition(g, Fraction(9, 10), 0.5, **o))


add("pp_run", lambda s, d: partition.as_labels(*pp(s, d)[:2]))
add("pp_trace", lambda s, d: pp(s, d)[2])
add("pp_certificate", lambda s, d: partition.certificate(*pp(s, d)[:2], 0.9))
add("pp_disjoint", lambda s, d: partition.certificate(*pp(s, d, disjoint=True)[:2], 0.9))


def serial_same(spark, d):
    """Both removed sets after 8 draws, one at a time and by batches: rows only in the one, only in the other, in all."""
    a, b = pp(spark, d, batch=1, draws=8)[1].withColumn("a", F.lit(1)), pp(spark, d, batch=8, draws=8)[1].withColumn("b", F.lit(1))
    both = a.join(b, ["v", "draw"], "full")
    return both.agg(F.count(F.when(F.col("b").isNull(), 1)).alias("serial_only"), F.count(F.when(F.col("a").isNull(), 1)).alias("batch_only"), F.count("*").alias("rows"))


add("pp_batch_equals_serial", serial_same)
add("pp_recursive", lambda s, d: partition.peel_clusters(graph(s, d, "conversation_path"), Fraction(9, 10), 0.5, batch=256, t_max=6, eps=1e-9, slope=1e-6))
for _f in ("nation_forest", "page_host"):
    add(f"pp_certificate_{_f}", lambda s, d, f=_f: partition.certificate(*pp(s, d, f)[:2], 0.9))


def pp3(spark, d):
    """Zero-cut stars: how often the removed set has a quarter of the volume or half of the target's, by random seed of the method."""
    g = graph(spark, d, "page_host")
    comp = cut(components(g).join(g.vertices, "v"))
    s = comp.groupBy("comp").agg(F.sum("deg").alias("vol")).filter(2 * F.col("vol") <= F.lit(g.vol)).orderBy(F.desc("vol"), "comp").limit(1)
    target = cut(comp.join(s, "comp", "left_semi").select("v", "deg"))
    vol_s, rows = target.agg(F.sum("deg")).first()[0], []
    for seed in (1, 2, 3, 4):
        removed = partition.peel_partition(g, Fraction(9, 10), 0.25, seed, batch=64, t_max=12, eps=1e-12, slope=1e-6, pick="largest")[0].select("v").distinct()
        vol_d = removed.join(g.vertices, "v").agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
        both = removed.join(target, "v").agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
        rows.append((seed, vol_d, both, g.vol, vol_s, 4 * vol_d >= g.vol or 2 * both >= vol_s))
    return spark.createDataFrame(rows, "seed int, vol_d long, vol_both long, vol long, vol_s long, ok boolean")


add("pp3_rate", pp3)

# ---- baselines, analysis, cost -----------------------------------------------------------------------

add("x_hop_sweep", lambda s, d: baselines.hop_sweep(graph(s, d, "page_link"), 6, 3), rec(g_sql("page_link"), "dist AS (SELECT CAST(6 AS BIGINT) AS v, 0 AS d UNION SELECT dst, d + 1 FROM dist JOIN arcs ON src = v WHERE d < 3)", "w AS (SELECT 0 AS run_id, 0 AS t, dist.v, CAST((4 - min(d)) * max(deg) AS BIGINT) AS mass FROM dist JOIN vx ON vx.v = dist.v GROUP BY dist.v)", "runs AS (SELECT 0 AS run_id, 1 AS b, 1 AS pn, 1 AS pd, 0.0 AS sl)", C_SQL,
    select="SELECT run_id, h.j, h.prefix_vol, h.cut, h.phi FROM (SELECT run_id, arg_min(struct_pack(j := j, prefix_vol := prefix_vol, cut := cut, phi := cut / CAST(side AS DOUBLE)), struct_pack(p := cut / CAST(side AS DOUBLE), j := j)) AS h FROM conds WHERE side > 0 GROUP BY 1)"))
add("x_order_sweep", lambda s, d: baselines.order_sweep(graph(s, d, "page_link")), rec(g_sql("page_link"), "w AS (SELECT 0 AS run_id, 0 AS t, v, deg * deg AS mass FROM vx)", "runs AS (SELECT 0 AS run_id, 1 AS b, 1 AS pn, 1 AS pd, 0.0 AS sl)", C_SQL,
    select="SELECT run_id, h.j, h.prefix_vol, h.cut, h.phi FROM (SELECT run_id, arg_min(struct_pack(j := j, prefix_vol := prefix_vol, cut := cut, phi := cut / CAST(side AS DOUBLE)), struct_pack(p := cut / CAST(side AS DOUBLE), j := j)) AS h FROM conds WHERE side > 0 GROUP BY 1)"))
add("x_ppr_sweep", lambda s, d: baselines.ppr_sweep(graph(s, d, "page_link"), 6))
add("x_spectral_sweep", lambda s, d: baselines.spectral_sweep(graph(s, d, "page_link"), 6))


def compare(spark, d):
    """Least conductance found from one seed by each method."""
    g = graph(spark, d, "page_link")
    one = lambda df, name: df.select(F.lit(name).alias("method"), "j", "prefix_vol", "cut", "phi")
    w = walk.walk(g, [Run(0, 6)], 5)
    best = baselines.best_prefix(g, w.filter("t = 5"))
    return one(best, "walk").union(one(baselines.hop_sweep(g, 6, 3), "hops")).union(one(baselines.ppr_sweep(g, 6), "pagerank")).union(one(baselines.order_sweep(g), "degree"))


add("x_compare", compare)


def optimum(spark, d):
    """Exact optimum of a small complete-like graph against every method from its first vertex."""
    g = small_trade(spark, d, 10)
    seed = g.vertices.agg(F.min("v")).first()[0]
    one = lambda df, name: df.select(F.lit(name).alias("method"), "phi")
    _, stop = cluster.local_clusters(g, practical([seed], "9/10", 1), 8, pick="best")
    peeled = partition.peel_partition(g, Fraction(99, 100), 0.5, batch=16, draws=32, t_max=8, eps=1e-9, slope=1e-6)[0]
    rows = [one(min_conductance(g), "optimum"), one(stop.withColumn("phi", F.col("cut") / F.col("side")), "local"), one(baselines.hop_sweep(g, seed, 2), "hops"),
            one(baselines.ppr_sweep(g, seed), "pagerank"), one(baselines.spectral_sweep(g, 6), "spectral"), one(baselines.order_sweep(g), "degree"),
            one(report(g, peeled.select(F.lit(0).alias("set_id"), "v").distinct()), "peeling")]
    out = rows[0]
    for r in rows[1:]:
        out = out.union(r)
    return out


add("x_optimum", optimum)


def scaling(spark, d):
    """Work of one run by scale b against the size of its graph: arcs that walks read, and the bound steps / threshold."""
    out = None
    for name, seed in (("fk_forest", cust(0)), ("document_line", 8)):
        g = graph(spark, d, name)
        runs = [Run(b, seed, UNIT // (50 << b), b) for b in (1, 3, 5)]
        w = walk.support_stats(g, walk.truncate(walk.walk(g, runs, 5), g, walk.runs_frame(g, runs)))
        part = w.filter("t < 5").groupBy(F.col("run_id").alias("b")).agg(F.sum("vol").alias("arcs_read"), F.max("n").alias("support"))
        part = part.select(F.lit(name).alias("graph"), "b", "arcs_read", "support", F.lit(g.vol).alias("graph_vol"), (5 * 50 * F.pow(F.lit(2.0), F.col("b"))).cast("long").alias("bound"))
        out = part if out is None else out.union(part)
    return out


def scaling_sql() -> str:
    parts = []
    for name, seed in (("fk_forest", cust(0)), ("document_line", 8)):
        runs = [Run(b, seed, UNIT // (50 << b), b) for b in (1, 3, 5)]
        q = rec(g_sql(name), w_sql(runs, 5), select=f"SELECT '{name}' AS graph, b, CAST(sum(vol) AS BIGINT) AS arcs_read, max(n) AS support, any_value(gv) AS graph_vol, CAST(250 * pow(2.0, b) AS BIGINT) AS bound FROM (SELECT w.run_id AS b, t, sum(deg) AS vol, count(*) AS n, (SELECT vol FROM tot) AS gv FROM w JOIN vx USING (v) JOIN runs USING (run_id) WHERE mass >= deg * eps AND t < 5 GROUP BY 1, 2) GROUP BY b")
        parts.append(f"SELECT * FROM ({q})")
    return " UNION ALL ".join(parts)


add("k_scaling", scaling, scaling_sql())


def total_bound(spark, d):
    """Measured work of theory runs under steps / threshold, by scale."""
    g = graph(spark, d, "conversation_path")
    w = theory(spark, d).groupBy("run_id", "b").agg(F.max("work").alias("work"))
    bounds = spark.createDataFrame([(b, s.t_last / s.eps, 2.0**b * s.ell**6 * 16) for b in valid_scales(g.vol) for s in [schedule(g.vol, Fraction(1, 2), b)]], "b int, bound double, shape double")
    return w.groupBy("b").agg(F.max("work").alias("most")).join(bounds, "b").withColumn("ok", F.col("most") <= F.col("bound"))


add("k_total_bound", total_bound)


CHECKED = {"": ("page_link", [6, 22, 38]), "_forest": ("fk_forest", [cust(0), cust(1)])}
CHECK_EPS, CHECK_STEPS = 1 << 30, 4


def walk_checks(spark, d, fix, seeds):
    g = graph(spark, d, fix)
    first = spark.createDataFrame([(v,) for v in seeds], "v long")
    around = cut(g.near.of(first).select(F.explode("nbrs").alias("v")).union(first).distinct())
    return analysis.checks(g, seeds, CHECK_STEPS, CHECK_EPS, around)


def checks_sql(fix, seeds) -> tuple[str, ...]:
    """CTEs: exact walk (runs 0..), truncated (runs 100..) and killed walk kw."""
    runs = [Run(i + k, v, e) for k, e in ((0, 0), (100, CHECK_EPS)) for i, v in enumerate(seeds)]
    ids = ", ".join(map(str, seeds))
    killed = w_sql(runs, CHECK_STEPS, f"SELECT dst AS v FROM arcs WHERE src IN ({ids}) UNION SELECT v FROM vx WHERE v IN ({ids})", True)
    alive, kw = killed.split("),\nw AS")[0].split("runs(run_id")[0], "w AS" + killed.split("),\nw AS")[1]
    kw = re.sub(r"\bw\b", "kw", kw)
    p = "p AS (SELECT run_id, t, w.v, deg, mass AS p FROM w JOIN vx USING (v) WHERE run_id < 100)"
    return g_sql(fix), w_sql(runs, CHECK_STEPS), alive.rstrip(", "), kw, p, R_SQL


_VERDICTS = {
    "monotone": "FROM (SELECT run_id, t, max(p / CAST(deg AS DOUBLE)) AS m FROM p GROUP BY 1, 2) a JOIN (SELECT run_id, t, max(p / CAST(deg AS DOUBLE)) AS m FROM p GROUP BY 1, 2) b ON a.run_id = b.run_id AND b.t = a.t + 1|b.m > a.m + 2",
    "killed_le_free": "FROM p LEFT JOIN kw ON kw.run_id = p.run_id AND kw.t = p.t AND kw.v = p.v|coalesce(mass, 0) > p + 2 * p.t * deg",
    "truncation_sandwich": f"FROM p LEFT JOIN w ON w.run_id = p.run_id + 100 AND w.t = p.t AND w.v = p.v|coalesce(mass, 0) > p + 2 * p.t * deg OR coalesce(mass, 0) < p - p.t * CAST({CHECK_EPS} AS BIGINT) * deg - 2 * p.t * deg",
    "mass_kept": f"FROM (SELECT run_id, t, sum(p) AS m FROM p GROUP BY 1, 2)|m > {UNIT}",
    "curve_monotone": "FROM (SELECT b.run_id, b.t, b.prefix_vol AS x, any_value(b.prefix_mass) AS next, coalesce(arg_min(a.prefix_mass - a.ratio * (a.prefix_vol - b.prefix_vol), a.j), max(z.total)) AS value FROM lam b LEFT JOIN lam a ON a.run_id = b.run_id AND a.t = b.t - 1 AND a.prefix_vol >= b.prefix_vol JOIN (SELECT run_id, t, CAST(sum(mass) AS DOUBLE) AS total FROM w GROUP BY 1, 2) z ON z.run_id = b.run_id AND z.t = b.t - 1 WHERE b.run_id < 100 AND b.t > 0 GROUP BY 1, 2, 3)|next > value * (1 + 1e-12) + 2 * x",
}
for _tail, (_fix, _seeds) in CHECKED.items():
    for _c, _v in _VERDICTS.items():
        add(f"e_{_c}{_tail}", lambda s, d, c=_c, f=_fix, v=_seeds: walk_checks(s, d, f, v).filter(F.col("check") == c),
            rec(*checks_sql(_fix, _seeds), select=f"SELECT '{_c}' AS \"check\", count(*) AS compared, count(*) FILTER ({_v.split('|')[1]}) AS violations {_v.split('|')[0]}"))
    for _n, _reach in (("chord", 2), ("chord_half", 1)):
        _runs = [Run(i, v, 0, 1, 1, 10) for i, v in enumerate(_seeds)]
        _at = lambda sign, name: f"{name} AS (SELECT c.run_id, c.t, c.j, coalesce(arg_min(a.prefix_mass - a.ratio * (a.prefix_vol - (c.prefix_vol {sign} c.side * {_reach * 1 / 10!r}::DOUBLE)), a.j), max(z.total)) AS y FROM pts c JOIN (SELECT run_id, t, CAST(sum(mass) AS DOUBLE) AS total FROM w GROUP BY 1, 2) z ON z.run_id = c.run_id AND z.t = c.t - 1 LEFT JOIN lam a ON a.run_id = c.run_id AND a.t = c.t - 1 AND a.prefix_vol >= c.prefix_vol {sign} c.side * {_reach * 1 / 10!r}::DOUBLE GROUP BY 1, 2, 3)"
        add(f"e_{_n}{_tail}", lambda s, d, f=_fix, v=_seeds, k=_reach: analysis.chord_check(graph(s, d, f), v, CHECK_STEPS, 1, 10, k),
            rec(g_sql(_fix), w_sql(_runs, CHECK_STEPS), C_SQL, "pts AS (SELECT conds.*, lam.prefix_mass FROM conds JOIN lam USING (run_id, t, j) WHERE t > 0 AND NOT c1 AND side > 0)", _at("-", "lo"), _at("+", "hi"),
                select=f"SELECT '{_n}' AS \"check\", count(*) AS compared, count(*) FILTER (prefix_mass > (lo.y + hi.y) / 2 * (1 + 1e-12) + 2 * prefix_vol) AS violations FROM pts JOIN lo USING (run_id, t, j) JOIN hi USING (run_id, t, j)"))


def path_set(spark, g):
    comp = components(g)
    first = comp.agg(F.min("comp").alias("comp"))
    return cut(comp.join(first, "comp", "left_semi").select("v"))


def cores(spark, d):
    g = graph(spark, d, "conversation_path")
    s = path_set(spark, g)
    half = cut(s.orderBy("v").limit(max(1, s.count() // 2)))
    outer, inner = analysis.core(g, half, 8), analysis.core_inner(g, half, 8)
    return g, half, cut(outer), cut(inner)


add("e_core", lambda s, d: cores(s, d)[2])
add("e_core_inner", lambda s, d: cores(s, d)[3])
add("e_core_volume", lambda s, d: (lambda c: overlap(c[0], c[2], c[1]).select("vol_c", "vol_s", (2 * F.col("vol_c") >= F.col("vol_s")).alias("ok")))(cores(s, d)))


def abscissae(spark, d):
    g = graph(spark, d, "conversation_path")
    seeds = [r.v for r in g.vertices.orderBy("v").collect()]
    return in_batches(lambda part: analysis.abscissae(g, part, 3, 2), seeds)


_YH = ", ".join(f"({h}, {2 * h}, {((h + 1) * UNIT / (Constants().c5 * 5))!r}::DOUBLE)" for h in range(4))
add("e_abscissae", abscissae, rec(g_sql("conversation_path"), all_seeds_sql("conversation_path", 6).replace(f"CAST({practical([0], '1/2', 1)[0].eps_units} AS BIGINT)", "CAST(0 AS BIGINT)"), R_SQL, f"ys(h, t_h, y) AS (VALUES {_YH})",
    select="SELECT run_id AS seed, h, arg_min(prefix_vol - (prefix_mass - y) / ratio, j) AS x FROM lam JOIN ys ON t = t_h AND prefix_mass >= y GROUP BY 1, 2"))
add("e_scale_class", lambda s, d: analysis.scale_classes(abscissae(s, d), 3))
add("m_overlap", lambda s, d: (lambda g: overlap(g, cluster.local_clusters(g, practical([cust(0)]), 6)[0].select("v"), nation_sets(s, d).filter("set_id = 0").select("v")))(graph(s, d, "fk_forest")),
    rec(g_sql("fk_forest"), NATION_SETS_SQL, w_sql(practical([cust(0)]), 6), C_SQL, hit_sql(), "c AS (SELECT v FROM conds JOIN hit ON conds.t = h.t AND conds.j <= h.j)", "z AS (SELECT v FROM sets WHERE set_id = 0)", select="SELECT CAST((SELECT sum(deg) FROM vx WHERE v IN (SELECT v FROM c)) AS BIGINT) AS vol_c, CAST((SELECT sum(deg) FROM vx WHERE v IN (SELECT v FROM z)) AS BIGINT) AS vol_s, CAST((SELECT coalesce(sum(deg), 0) FROM vx WHERE v IN (SELECT v FROM c) AND v IN (SELECT v FROM z)) AS BIGINT) AS vol_both"))


def n1(spark, d):
    """Bounds on every cluster of the grid: conductance <= phi and volume <= 5/6."""
    g = graph(spark, d, "fk_forest")
    _, s = cluster.local_clusters(g, _GRID_RUNS, 6)
    r = s.join(walk.runs_frame(g, _GRID_RUNS).select("run_id", "phi_num", "phi_den"), "run_id")
    bad = (F.col("cut") * F.col("phi_den") > F.col("phi_num") * F.col("side")) | (6 * F.col("prefix_vol") > 5 * F.lit(g.vol))
    return analysis.verdict("n1", r, bad)


add("n1_all_runs", n1, rec(g_sql("fk_forest"), w_sql(_GRID_RUNS, 6), C_SQL, hit_sql(), select="SELECT 'n1' AS \"check\", count(*) AS compared, count(*) FILTER (h.cut * pd > pn * h.side OR 6 * h.prefix_vol > 5 * vol) AS violations FROM hit JOIN runs USING (run_id), tot"))


def r1_r2(spark, d):
    """The same bounds for every set that the sampled method returns, recomputed from its members."""
    g = graph(spark, d, "page_link")
    got = sampling.sampled_local_cluster(g, Fraction(3, 10), literal_draws(spark), t_max=5, eps=1e-12, slope=1e-6)
    r = report(g, cut(got.filter("v is not null").select(F.col("draw").alias("set_id"), "v")))
    return analysis.verdict("r1_r2", r, (10 * F.col("cut") > 3 * F.least("vol", "vol_rest")) | (6 * F.col("vol") > 5 * F.lit(g.vol)))


add("r1_r2", r1_r2, rec(g_sql("page_link"), _PICK_SQL, _SLC_W, C_SQL, hit_sql(), select="SELECT 'r1_r2' AS \"check\", count(*) AS compared, count(*) FILTER (10 * h.cut > 3 * h.side OR 6 * h.prefix_vol > 5 * vol) AS violations FROM hit, tot"))


def n2(spark, d):
    """Zero-cut targets, theory parameters: every cluster overlaps its seed's path by 2^(b-1) or more."""
    g = graph(spark, d, "conversation_path")
    got, comp = theory(spark, d), cut(components(g))
    home = comp.select(F.col("v").alias("seed"), F.col("comp").alias("home"))
    own = got.filter("v is not null").join(home, "seed").join(comp, "v").join(g.vertices, "v")
    vol = own.groupBy("run_id", "b").agg(F.sum(F.when(F.col("comp") == F.col("home"), F.col("deg")).otherwise(0)).alias("inside"))
    return analysis.verdict("n2", vol, F.col("inside") < F.pow(F.lit(2), F.col("b") - 1))


add("n2_overlap", n2)


@once
def lab(spark, d):
    return analysis.guarantees(graph(spark, d, "nation_forest"), Fraction(9, 10))


add("e_stop_epoch", lambda s, d: lab(s, d).select("seed", "comp", "h", "b"))
for _n, _c in {"e_class_partition": "rising", "n3_nonempty": "nonempty", "n2_own_scale": "overlap", "e_epoch_c123": "c123", "e_epoch_c4": "c4", "e_curve_floor": "floor", "e_curve_ceiling": "ceiling"}.items():
    add(_n, lambda s, d, n=_n, c=_c: analysis.verdict(n, lab(s, d).filter(F.col(c).isNotNull()), ~F.col(c)))


def one_class(spark, d):
    """Every vertex of the targets lies in one class: vertices with and without one."""
    return lab(spark, d).agg(F.count("*").alias("vertices"), F.countDistinct("seed").alias("seeds"), F.count("b").alias("classed"))


add("e_classes", one_class, f"WITH {g_sql('nation_forest')} SELECT count(*) AS vertices, count(*) AS seeds, count(*) AS classed FROM vx")


def escape(spark, d):
    g = graph(spark, d, "fk_forest")
    return analysis.escape_bounds(g, cut(region_tree(spark, d)), 5)


_PSI = f"inn AS (SELECT v, deg FROM vx WHERE v % {KINDS} <= 3), z AS (SELECT CAST(sum(deg) AS BIGINT) AS vol, (SELECT count(*) FROM arcs WHERE src IN (SELECT v FROM inn) AND dst NOT IN (SELECT v FROM inn)) / CAST(least(sum(deg), (SELECT vol FROM tot) - sum(deg)) AS DOUBLE) AS phi FROM inn)"
_KILLED = f"""k AS (SELECT 0 AS t, v, CAST(floor({UNIT}::DOUBLE * deg / vol) AS BIGINT) AS mass FROM inn, z
 UNION ALL SELECT t, v, CAST(sum(m) AS BIGINT) FROM (SELECT t + 1 AS t, k.v, mass // 2 AS m FROM k WHERE t < 5
  UNION ALL SELECT t + 1, dst, mass // (2 * deg) FROM k JOIN vx ON vx.v = k.v JOIN arcs ON src = k.v WHERE t < 5 AND dst IN (SELECT v FROM inn)) x WHERE m > 0 GROUP BY t, v)"""
add("e_escape_bounds", escape, rec(g_sql("fk_forest"), _PSI, _KILLED, select=f"SELECT t, CAST(sum(mass) AS BIGINT) AS inside, max(mass / CAST(deg AS DOUBLE)) AS norm, sum(mass) >= {UNIT}::DOUBLE * (1 - t * any_value(phi) / 2) - 2 * any_value(z.vol) * (t + 1) AS escape_ok, max(mass / CAST(deg AS DOUBLE)) <= {UNIT}::DOUBLE / any_value(z.vol) AS norm_ok FROM k JOIN vx USING (v), z GROUP BY t"))


def k_work(spark, d):
    g = graph(spark, d, "fk_forest")
    w = walk.walk(g, _TWO, 4)
    st = walk.support_stats(g, w)
    return st.groupBy("run_id").agg(F.sum(F.when(F.col("t") < 4, F.col("vol")).otherwise(0)).alias("arcs_read"), F.max("n").alias("support"), F.max("t").alias("steps"))


add("k_work", k_work, rec(g_sql("fk_forest"), w_sql(_TWO, 4), select="SELECT run_id, CAST(sum(deg) FILTER (WHERE t < 4) AS BIGINT) AS arcs_read, max(n) AS support, max(t) AS steps FROM (SELECT *, count(*) OVER (PARTITION BY run_id, t) AS n FROM w JOIN vx USING (v)) GROUP BY 1"))
add("k_sort", lambda s, d: walk.support_stats(graph(s, d, "fk_forest"), walk.walk(graph(s, d, "fk_forest"), _TWO, 4)).groupBy("run_id").agg(F.round(F.sum(F.col("n") * F.log2(F.col("n").cast("double"))), 6).alias("sort_work")),
    rec(g_sql("fk_forest"), w_sql(_TWO, 4), select="SELECT run_id, round(sum(n * log2(n)), 6) AS sort_work FROM (SELECT run_id, t, count(*) AS n FROM w GROUP BY 1, 2) GROUP BY 1"))
add("k_step_jobs", lambda s, d: cost.step_costs(graph(s, d, "fk_forest"), _TWO, 4))
lc_query("k_steps", "fk_forest", _GRID_RUNS[:4], 6, "stops")
lc_query("k_quality", "page_link", practical([6, 22, 38], "3/10", 2), 5, "stops")


def support_vs_output(spark, d):
    return theory(spark, d).groupBy("run_id", "b", "t").agg(F.max("work").alias("work"), F.count("v").alias("size"))


add("k_support_vs_output", support_vs_output)


def k_expected(spark, d):
    """Expected work of the sampled method: work by scale, weighted by the scale law."""
    g = graph(spark, d, "conversation_path")
    w = support_vs_output(spark, d).groupBy("b").agg(F.avg("work").alias("work"))
    return w.withColumn("weighted", F.col("work") * F.pow(F.lit(2.0), -F.col("b")) / F.lit(1 - 2.0 ** -scale_count(g.vol)))


add("k_expected_work", k_expected)
add("k_draws", lambda s, d: (lambda p: p[2].agg(F.max("draw").alias("last_draw"), F.count("*").alias("taken"), F.sum("vol_d").alias("vol_d")).withColumn("budget", F.lit(max_draws(p[0].vol, 0.5))))(pp(s, d)))


def success(spark, d):
    """Share of the seeds of all paths whose cluster lies mostly inside their own."""
    g = graph(spark, d, "conversation_path")
    comp = components(g)
    got = cluster.ball_clusters(g, all_seeds(g), 8)
    home = comp.select(F.col("v").alias("run_id"), F.col("comp").alias("home"))
    inside = got.join(comp, "v", "left").join(home, "run_id").groupBy("run_id").agg(F.avg((F.col("comp") == F.col("home")).cast("double")).alias("share"))
    return inside.agg(F.count("*").alias("seeds"), F.count(F.when(F.col("share") > 0.5, 1)).alias("good"))


add("k_success_rate", success, rec(g_sql("conversation_path"), all_seeds_sql("conversation_path", 8), C_SQL, hit_sql(), select="SELECT (SELECT count(*) FROM vx) AS seeds, count(*) AS good FROM hit"))

