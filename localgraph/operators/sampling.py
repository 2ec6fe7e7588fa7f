"""Sampled local clustering: seeds by degree, scales by a halving law."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import Graph
from ..params import scale_count, schedule
from ..session import cut
from .cluster import ball_clusters, run_of


def uniforms(spark: SparkSession, seed: int, first: int, count: int) -> DataFrame:
    """(draw, u1, u2): counter-based uniforms, the same whatever the partitioning."""
    u = lambda s: F.shiftrightunsigned(F.xxhash64(F.lit(seed), "draw", F.lit(s)), 11) / F.lit(float(1 << 53))
    return spark.range(first, first + count).select(F.col("id").alias("draw")).select("draw", u(1).alias("u1"), u(2).alias("u2"))


_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def _with_int(h: np.ndarray, x: int) -> np.ndarray:
    """Spark's xxhash64 of an int column, from the hash of the columns before it."""
    h = (h + _P5 + np.uint64(4)) ^ (np.array([x & 0xFFFFFFFF], np.uint64) * _P1)
    return _mixed(_turn(h, 23) * _P2 + _P3)


def uniforms_at(seed: int, first: int, count: int) -> tuple[np.ndarray, np.ndarray]:
    """u1, u2 of `uniforms` as arrays, for tasks that draw by themselves."""
    if not -(1 << 31) <= seed < 1 << 31:
        raise ValueError("a seed is an int")
    draws = np.arange(first, first + count).astype(np.uint64)
    h = (_with_int(np.array([42], np.uint64), seed) + _P5 + np.uint64(8)) ^ (_turn(draws * _P2, 31) * _P1)
    h = _mixed(_turn(h, 27) * _P1 + _P4)
    one, two = ((_with_int(h, s) >> np.uint64(11)) / float(1 << 53) for s in (1, 2))
    return one, two


def degree_intervals(g: Graph, parts: int = 64) -> DataFrame:
    """(v, lo, hi): consecutive intervals of length deg by id, from totals of id ranges and sums inside them."""
    # ranges of about equal numbers of vertices, whatever the ids look like; stored, since ranges are sampled
    vx = cut(g.vertices.repartitionByRange(parts, "v").withColumn("part", F.spark_partition_id()), "ranges")
    totals = vx.groupBy("part").agg(F.sum("deg").alias("n"))
    # at most `parts` rows in this window
    offset = totals.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("base"))
    up = F.sum("deg").over(Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, 0))
    placed = vx.join(F.broadcast(offset), "part").withColumn("hi", F.col("base") + up)
    return placed.select("v", (F.col("hi") - F.col("deg")).alias("lo"), "hi")


def sample_by_degree(g: Graph, draws: DataFrame, intervals: DataFrame | None = None) -> DataFrame:
    """draws(draw, u1) -> (draw, v) with probability deg / vol."""
    at = draws.select("draw", F.floor(F.col("u1") * F.lit(float(g.vol))).alias("x"))
    iv = degree_intervals(g) if intervals is None else intervals
    return iv.join(F.broadcast(at), (F.col("lo") <= F.col("x")) & (F.col("x") < F.col("hi"))).select("draw", "v")


def sample_scale(ell: int, draws: DataFrame) -> DataFrame:
    """draws(draw, u2) -> (draw, b) with Pr[b] proportional to 2^-b, b = 1..ell."""
    b = F.ceil(-F.log2(1 - F.col("u2") * F.lit(1 - 2.0**-ell)))
    return draws.select("draw", F.least(F.greatest(b, F.lit(1)), F.lit(ell)).cast("int").alias("b"))


def scales_at(ell: int, u2: np.ndarray) -> np.ndarray:
    """b of `sample_scale` as an array."""
    return np.clip(np.ceil(-np.log2(1 - u2 * (1 - 2.0**-ell))), 1, ell).astype(np.int64)


def sampled_local_cluster(g: Graph, phi, draws: DataFrame, removed: DataFrame | None = None, vol: int | None = None, intervals: DataFrame | None = None, pick: str = "first", ordered: bool = False, lost: DataFrame | None = None, **practical):
    """One row per draw and clustered vertex (draw, seed_v, b, t, v, rank, work); v null where nothing was found.

    removed(v) is out of the graph, vol the volume left; degree draws that fall on removed vertices give no run
    (rejection sampling). intervals: those of the whole graph, if made before. ordered, lost: as in `ball_clusters`.
    """
    seeds = sample_by_degree(g, draws, intervals)
    if removed is not None:
        seeds = seeds.join(removed.select("v"), "v", "left_anti")
    vol = g.vol if vol is None else vol
    drawn = seeds.join(sample_scale(scale_count(vol), draws), "draw").orderBy("draw").collect()
    runs = [run_of(r.draw, r.v, schedule(vol, phi, r.b, **practical), pick=pick) for r in drawn]
    if not runs:
        none = g.spark.createDataFrame([], "draw long, seed_v long, b int, t int, v long, rank long, work long")
        return (none, g.spark.createDataFrame([], "draw long, reach long, settled boolean")) if ordered else none
    t_max = max(schedule(vol, phi, r.b, **practical).t_last for r in runs)
    meta = g.spark.createDataFrame([(r.run_id, r.seed, r.b) for r in runs], "draw long, seed_v long, b int")
    got = ball_clusters(g, runs, t_max, vol, removed, ordered=ordered, lost=lost)
    got, reach = got if ordered else (got, None)
    got = got.withColumnRenamed("run_id", "draw").join(F.broadcast(meta), "draw").select("draw", "seed_v", "b", "t", "v", "rank", "work")
    return (got, reach.withColumnRenamed("run_id", "draw")) if ordered else got
