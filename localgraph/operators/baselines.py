"""What local clustering is compared with: hop order, PageRank push, spectral and plain sweeps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..params import UNIT
from ..session import cut
from .sweep import prefix_cuts, ranked


def best_prefix(g: Graph, states: DataFrame) -> DataFrame:
    """Per run: the prefix with the least conductance (ties: shorter)."""
    c = prefix_cuts(g, ranked(g, states))
    side = F.least(F.col("prefix_vol"), F.lit(g.vol) - F.col("prefix_vol"))
    c = c.withColumn("phi", F.col("cut") / side).filter(side > 0)
    return c.groupBy("run_id").agg(F.min_by(F.struct("j", "prefix_vol", "cut", "phi"), F.struct("phi", "j")).alias("p")).select("run_id", "p.*")


def hops(g: Graph, seed: int, depth: int) -> DataFrame:
    """(v, d): distances up to depth; every round joins the frontier only."""
    seen = g.spark.createDataFrame([(seed, 0)], "v long, d int")
    front = seen
    for d in range(1, depth + 1):
        near = g.near.of(front).select(F.explode("nbrs").alias("v")).distinct()
        front = cut(near.join(seen, "v", "left_anti").withColumn("d", F.lit(d)), "front")
        seen = seen.union(front)
    return seen


def hop_sweep(g: Graph, seed: int, depth: int) -> DataFrame:
    """Sweep in order of (distance, id)."""
    h = hops(g, seed, depth)
    # mass falls with distance and is proportional to degree, so that ranks are by distance, then id
    state = h.join(g.vertices, "v").select(F.lit(0).cast("long").alias("run_id"), F.lit(0).alias("t"), "v", ((depth + 1 - F.col("d")) * F.col("deg")).cast("long").alias("mass"))
    return best_prefix(g, state)


def ppr_push(g: Graph, seed: int, alpha_inv: int, eps_units: int, rounds: int) -> DataFrame:
    """(v, p, r): synchronous push of personalised PageRank in integer units; alpha = 1 / alpha_inv."""
    state = g.spark.createDataFrame([(seed, 0, UNIT)], "v long, p long, r long")
    for _ in range(rounds):
        at = g.near.of(state)
        hot = F.col("r") >= F.col("deg") * eps_units
        kept = at.withColumn("up", F.when(hot, F.expr(f"r div {alpha_inv}")).otherwise(0))
        kept = kept.withColumn("move", F.when(hot, F.expr("(r - up) div (2 * deg)")).otherwise(0))
        stay = kept.filter("chunk = 0").select("v", (F.col("p") + F.col("up")).alias("p"), F.when(hot, F.expr("(r - up) div 2 + move * loops")).otherwise(F.col("r")).alias("r"))
        go = kept.filter("move > 0").select(F.explode("nbrs").alias("v"), F.lit(0).cast("long").alias("p"), F.col("move").alias("r"))
        state = cut(stay.union(go).groupBy("v").agg(F.sum("p").alias("p"), F.sum("r").alias("r")), "ppr")
    return state


def ppr_sweep(g: Graph, seed: int, alpha_inv: int = 8, eps_units: int = 1 << 30, rounds: int = 5) -> DataFrame:
    p = ppr_push(g, seed, alpha_inv, eps_units, rounds).filter("p > 0")
    return best_prefix(g, p.select(F.lit(0).cast("long").alias("run_id"), F.lit(0).alias("t"), "v", F.col("p").alias("mass")))


def order_sweep(g: Graph) -> DataFrame:
    """Sweep by degree falling, then id (control)."""
    state = g.vertices.select(F.lit(0).cast("long").alias("run_id"), F.lit(0).alias("t"), "v", (F.col("deg") * F.col("deg")).alias("mass"))
    return best_prefix(g, state)


def spectral_sweep(g: Graph, rounds: int = 30, seed: int = 3) -> DataFrame:
    """Power iteration of the lazy walk on degree-scaled values without the stationary part, then one sweep."""
    x = g.vertices.select("v", "deg", (F.xxhash64(F.lit(seed), "v") / F.lit(float(1 << 63))).alias("x"))
    for _ in range(rounds):
        mean = x.agg(F.sum(F.col("x") * F.col("deg")) / F.sum("deg")).first()[0]
        x = x.withColumn("x", F.col("x") - mean)
        near = g.arcs.join(x.select(F.col("v").alias("dst"), F.col("x").alias("y")), "dst").groupBy(F.col("src").alias("v")).agg(F.sum("y").alias("y"))
        x = cut(x.join(near, "v").select("v", "deg", (F.col("x") / 2 + F.col("y") / (2 * F.col("deg"))).alias("x")), "spectral")
    low = x.agg(F.min("x"), F.max("x")).first()
    mass = ((F.col("x") - low[0]) / (low[1] - low[0] or 1.0) * (1 << 30)).cast("long") * F.col("deg") + 1
    return best_prefix(g, x.select(F.lit(0).cast("long").alias("run_id"), F.lit(0).alias("t"), "v", mass.alias("mass")))
