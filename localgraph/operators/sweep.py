"""Mass curves and ordered sweeps of walk states.

Vertices are ordered by mass / deg falling, then id; the quotient of two integers below 2^53 is one correctly
rounded division, so every engine ranks alike. Conditions compare integers crosswise.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph import Graph
from .walk import fetch


def ranked(g: Graph, states: DataFrame, near: DataFrame | None = None) -> DataFrame:
    """states with deg, loops, ratio, rank j, prefix volume prefix_vol and prefix mass; near: their fetched rows."""
    near = fetch(g, states) if near is None else near
    s = near.filter("chunk = 0").withColumn("ratio", F.col("mass") / F.col("deg"))
    w = Window.partitionBy("run_id", "t").orderBy(F.desc("ratio"), "v")
    up = w.rowsBetween(Window.unboundedPreceding, 0)
    return s.select("run_id", "t", "v", "mass", "deg", "loops", "ratio", F.row_number().over(w).cast("long").alias("j"), F.sum("deg").over(up).alias("prefix_vol"), F.sum("mass").over(up).alias("prefix_mass"), F.sum("loops").over(up).alias("prefix_loops"))


def prefix_cuts(g: Graph, r: DataFrame, near: DataFrame | None = None) -> DataFrame:
    """ranked with the cut of every prefix: arcs inside are counted where their later end enters."""
    near = fetch(g, r.select("run_id", "t", "v")) if near is None else near
    a = r.select("run_id", "t", "v", F.col("j").alias("js"))
    b = r.select("run_id", "t", F.col("v").alias("dst"), F.col("j").alias("jd"))
    ends = near.select("run_id", "t", "v", F.explode("nbrs").alias("dst"))
    inside = ends.join(b, ["run_id", "t", "dst"]).join(a, ["run_id", "t", "v"]).groupBy("run_id", "t", F.greatest("js", "jd").alias("j")).agg(F.count("*").alias("inside"))
    up = Window.partitionBy("run_id", "t").orderBy("j").rowsBetween(Window.unboundedPreceding, 0)
    both = r.join(inside, ["run_id", "t", "j"], "left")
    return both.withColumn("cut", F.col("prefix_vol") - F.col("prefix_loops") - F.sum(F.coalesce("inside", F.lit(0))).over(up)).drop("inside")


def slopes(r: DataFrame, runs: DataFrame) -> DataFrame:
    """(run_id, t, slope): ratio of the first prefix that reaches volume 2^b, 0 past the support."""
    at = r.join(F.broadcast(runs.select("run_id", "b")), "run_id")
    hit = F.when(F.col("prefix_vol") >= F.expr("shiftleft(1L, b)"), F.struct("j", "ratio"))
    return at.groupBy("run_id", "t").agg(F.coalesce(F.min(hit)["ratio"], F.lit(0.0)).alias("slope"))


def conditions(g: Graph, states: DataFrame, runs: DataFrame, vol: int | None = None, near: DataFrame | None = None) -> DataFrame:
    """Every prefix with the four stop conditions c1..c4."""
    total = F.lit(vol if vol is not None else g.vol)
    r = ranked(g, states, near)
    c = prefix_cuts(g, r, near).join(slopes(r, runs), ["run_id", "t"]).join(F.broadcast(runs), "run_id")
    side = F.least(F.col("prefix_vol"), total - F.col("prefix_vol"))
    return c.select(
        "run_id", "t", "j", "v", "prefix_vol", "cut", "mass", "ratio",
        ((side > 0) & (F.col("cut") * F.col("phi_den") <= F.col("phi_num") * side)).alias("c1"),
        (6 * F.col("prefix_vol") <= 5 * total).alias("c2"),
        (F.col("prefix_vol") >= F.expr("shiftleft(1L, b)")).alias("c3"),
        (F.col("slope") >= F.col("slope_units")).alias("c4"),
        side.alias("side"),
    )


def hits(conds: DataFrame, use: tuple[str, ...] = ("c1", "c2", "c3", "c4"), pick: str = "first") -> DataFrame:
    """One row per run and step with a qualifying prefix: the first, the best (least conductance) or the largest."""
    ok = conds.filter(" and ".join(use) or "true")
    key = {"first": F.struct("j"), "largest": F.struct((-F.col("j")).alias("k")), "best": F.struct((F.col("cut") / F.col("side")).alias("phi"), "j")}[pick]
    row = F.struct("j", "prefix_vol", "cut", "side")
    return ok.groupBy("run_id", "t").agg(F.min_by(row, key).alias("h")).select("run_id", "t", "h.*")


def curve_at(r: DataFrame, xs: DataFrame) -> DataFrame:
    """Curve value at each x by interpolation: total mass beyond the support."""
    want = r.join(F.broadcast(xs), (F.col("prefix_vol") >= F.col("x")), "inner")
    first = want.groupBy("run_id", "t", "x").agg(F.min_by(F.struct("prefix_vol", "prefix_mass", "ratio"), "j").alias("p"))
    total = r.groupBy("run_id", "t").agg(F.sum("mass").alias("total"))
    grid = total.crossJoin(F.broadcast(xs)).join(first, ["run_id", "t", "x"], "left")
    value = F.col("p.prefix_mass") - F.col("p.ratio") * (F.col("p.prefix_vol") - F.col("x"))
    return grid.select("run_id", "t", "x", F.coalesce(value, F.col("total").cast("double")).alias("value"), F.coalesce("p.ratio", F.lit(0.0)).alias("slope"))


def curve_points(r: DataFrame, points: DataFrame) -> DataFrame:
    """points(run_id, t, x, ...) with the value there of their own run's and step's curve.

    Breakpoints and points are one sequence, walked from the right: a point sees the nearest breakpoint at or above
    it. No join, and nothing is broadcast.
    """
    more = [c for c in points.columns if c not in ("run_id", "t", "x")]
    breaks = r.select("run_id", "t", F.col("prefix_vol").cast("double").alias("x"), F.lit(1).alias("is_break"), F.struct("prefix_vol", "prefix_mass", "ratio").alias("p"), *[F.lit(None).cast(points.schema[c].dataType).alias(c) for c in more])
    asked = points.select("run_id", "t", F.col("x").cast("double").alias("x"), F.lit(0).alias("is_break"), F.lit(None).cast(breaks.schema["p"].dataType).alias("p"), *more)
    down = Window.partitionBy("run_id", "t").orderBy(F.desc("x"), F.desc("is_break")).rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("run_id", "t")
    both = breaks.unionByName(asked).withColumns({"near": F.last("p", True).over(down), "total": F.max("p.prefix_mass").over(whole)})
    value = F.col("near.prefix_mass") - F.col("near.ratio") * (F.col("near.prefix_vol") - F.col("x"))
    return both.filter("is_break = 0").select("run_id", "t", "x", *more, F.coalesce(value, F.col("total").cast("double")).alias("value"))


def curve_inverse(r: DataFrame, ys: DataFrame) -> DataFrame:
    """Smallest x where the curve reaches y; null where it never does."""
    want = r.join(F.broadcast(ys), F.col("prefix_mass") >= F.col("y"))
    first = want.groupBy("run_id", "t", "y").agg(F.min_by(F.struct("prefix_vol", "prefix_mass", "ratio"), "j").alias("p"))
    return first.select("run_id", "t", "y", (F.col("p.prefix_vol") - (F.col("p.prefix_mass") - F.col("y")) / F.col("p.ratio")).alias("x"))
