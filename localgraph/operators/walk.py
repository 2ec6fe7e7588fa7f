"""Truncated lazy walks on fixed-point mass, many runs at once.

State rows are (run_id, t, v, mass) with integer mass (UNIT is one). A step halves each vertex's mass and sends
mass div (2 deg) along every incident arc; loops, and arcs to vertices outside `alive`, return it. Flooring loses
less than 2 deg units per vertex and step, always downwards, and integer sums do not depend on their order.
Each step touches only the adjacency of its support: the stored state fetches the buckets of its vertices, and the
degrees of truncation and sweep come from the same rows. Only state moves between executors.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph import Graph
from ..params import UNIT
from ..session import cut


@dataclass(frozen=True)
class Run:
    """A walk: start vertex, threshold per unit of degree in mass units, and what a sweep needs."""

    run_id: int
    seed: int
    eps_units: int = 0
    b: int = 1
    phi_num: int = 1
    phi_den: int = 10
    slope_units: float = 0.0
    unit: int = UNIT
    pick: str = "first"


RUN_SCHEMA = "run_id long, seed long, eps_units long, b int, phi_num long, phi_den long, slope_units double"


def runs_frame(g: Graph, runs: list[Run]) -> DataFrame:
    if any(r.unit != UNIT for r in runs):
        raise ValueError("runs on the wide mass unit need ball mode")
    rows = [(r.run_id, r.seed, r.eps_units, r.b, r.phi_num, r.phi_den, float(r.slope_units)) for r in runs]
    return g.spark.createDataFrame(rows, RUN_SCHEMA)


def start(runs: DataFrame) -> DataFrame:
    return runs.select("run_id", F.lit(0).alias("t"), F.col("seed").alias("v"), F.lit(UNIT).cast("long").alias("mass"))


def fetch(g: Graph, state: DataFrame) -> DataFrame:
    """State rows with deg, loops and neighbours of their vertices, in chunks; chunk 0 stands for the vertex."""
    return g.near.of(state)


def lost_as_loops(near: DataFrame, keys: list[str], alive: DataFrame) -> DataFrame:
    """Fetched rows whose neighbours outside alive(v) are counted in column `lost` instead."""
    marks = alive.select(F.col("v").alias("u"), F.lit(True).alias("mark"))
    keep = F.col("mark").isNotNull()
    ends = near.select(*keys, "deg", "loops", "chunk", F.explode_outer("nbrs").alias("u")).join(marks, "u", "left")
    kept, lost = F.when(keep, F.col("u")), F.when(~keep & F.col("u").isNotNull(), 1)
    return ends.groupBy(*keys, "deg", "loops", "chunk").agg(F.collect_list(kept).alias("nbrs"), F.count(lost).alias("lost"))


def within(near: DataFrame, alive: DataFrame) -> DataFrame:
    """Fetched state rows of the degree-preserving subgraph on alive(v): only they are rewritten, not the graph."""
    rows = lost_as_loops(near, ["run_id", "t", "v", "mass"], alive)
    lost = F.sum("lost").over(Window.partitionBy("run_id", "t", "v"))
    return rows.select("run_id", "t", "v", "mass", "deg", (F.col("loops") + lost).alias("loops"), "chunk", "nbrs")


def degrees(g: Graph, states: DataFrame) -> DataFrame:
    """State rows with deg and loops."""
    return fetch(g, states).filter("chunk = 0").drop("chunk", "nbrs")


def truncate(state: DataFrame, g: Graph, runs: DataFrame) -> DataFrame:
    """Rows whose mass reaches deg * eps_units."""
    e = F.broadcast(runs.select("run_id", "eps_units"))
    return degrees(g, state).join(e, "run_id").filter("mass >= deg * eps_units").select("run_id", "t", "v", "mass")


def step(g: Graph, near: DataFrame, runs: DataFrame, alive: DataFrame | None = None, killed: bool = False) -> DataFrame:
    """Truncate fetched state, then one lazy step; `alive` keeps mass inside (or, killed, drops what leaves)."""
    e = F.broadcast(runs.select("run_id", "eps_units"))
    at = near.join(e, "run_id").filter("mass >= deg * eps_units").filter("mass > 0")
    move = F.expr("mass div (2 * deg)")
    at = at.select("run_id", "t", "v", F.expr("mass div 2").alias("stay"), move.alias("move"), "loops", "chunk", "nbrs")
    stay = at.filter("chunk = 0").select("run_id", "t", "v", (F.col("stay") + F.col("move") * F.col("loops")).alias("m"))
    go = at.filter("move > 0").select("run_id", "t", F.col("v").alias("u"), F.explode("nbrs").alias("v"), F.col("move").alias("m"))
    if alive is not None:
        ok = go.join(alive.select("v", F.lit(True).alias("in_a")), "v", "left")
        ok = ok.filter("in_a") if killed else ok.withColumn("v", F.when(F.col("in_a"), F.col("v")).otherwise(F.col("u")))
        go = ok
    moved = stay.union(go.select("run_id", "t", "v", "m")).filter("m > 0")
    return moved.groupBy("run_id", (F.col("t") + 1).alias("t"), "v").agg(F.sum("m").alias("mass"))


def walk(g: Graph, runs: list[Run], steps: int, alive: DataFrame | None = None, killed: bool = False) -> DataFrame:
    """q_t of all runs for t = 0..steps; eps_units 0 is the exact walk."""
    rf = runs_frame(g, runs)
    state = start(rf)
    out = state
    for _ in range(steps):
        state = cut(step(g, fetch(g, state), rf, alive, killed))
        out = out.union(state)
    return out


def degree_vector(g: Graph, s: DataFrame) -> DataFrame:
    """The walk's stationary law on a vertex set, as deg and the set's volume."""
    inside = g.vertices.join(s, "v", "left_semi")
    return inside.select("v", "deg").crossJoin(F.broadcast(inside.agg(F.sum("deg").alias("vol"))))


def support_stats(g: Graph, states: DataFrame) -> DataFrame:
    """Per run and step: support size, its volume and total mass."""
    return degrees(g, states).groupBy("run_id", "t").agg(F.count("*").alias("n"), F.sum("deg").alias("vol"), F.sum("mass").alias("mass"))
