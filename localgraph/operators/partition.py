"""Peeling partition: sampled clusters of the shrinking remainder, until a quarter of the volume is gone."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph, report
from ..params import max_draws, partition_phi, scale_count
from ..session import cut, drop
from .cluster import cut_off
from .held import Held, Rule
from .sampling import degree_intervals, sampled_local_cluster, uniforms

#: volume of a part that one task may hold, and up to which it splits to the end what it holds
PART_VOL, SPREAD_VOL = 1 << 22, 1 << 11


def peel_partition(g: Graph, theta, p: float, seed: int = 1, batch: int = 16, draws: int | None = None, factor: int = 12, disjoint: bool = False, **practical) -> tuple[DataFrame, DataFrame]:
    """(removed(v, draw), trace(draw, seed_v, b, vol_d, vol_w)).

    The graph is stored once and never rewritten: arcs to removed vertices become loops where a walk fetches them.

    `batch` draws run together on the current remainder. Those that reached or neighboured a common vertex are then
    settled in their order, each on what the clusters before it leave, in one task (`in_order`); a draw that met nothing
    an earlier draw of the batch removes would have run the same on the smaller remainder (if its scales and thresholds
    do not depend on the volume left, and it reached at most half of that). Draws are accepted in order up to the first
    one that is not settled so, and redrawn from their own counters from there on: the result equals one draw at a time.
    With `disjoint`, all clusters of a batch that share no vertex are taken (heuristic).
    """
    phi, budget = partition_phi(theta), draws if draws is not None else max_draws(g.vol, p, factor)
    spark = g.spark
    fixed = {"t_max", "eps", "slope"} <= practical.keys()
    removed, lost = spark.createDataFrame([], "v long, draw long"), None
    trace, at, vol_w = [], 0, g.vol
    intervals = cut(degree_intervals(g), "intervals")
    while at < budget and 4 * vol_w >= 3 * g.vol:
        n = min(batch, budget - at)
        # a remainder that changes the scales is left to the next draw
        ordered = not disjoint and fixed
        found = sampled_local_cluster(g, phi, uniforms(spark, seed, at, n), removed if trace else None, vol_w, intervals, ordered=ordered, lost=lost, **practical)
        found, settled = found if ordered else (found, None)
        got = cut(found.filter("v is not null"), "clusters")
        sizes = got.join(g.vertices, "v").groupBy("draw", "seed_v", "b").agg(F.sum("deg").alias("vol_d")).orderBy("draw").collect()
        reach = {r.draw: r.reach if r.settled else None for r in settled.collect()} if ordered else {}
        if not sizes and None not in reach.values():
            at += n
            continue
        if disjoint:
            first = got.groupBy("v").agg(F.min("draw").alias("owner"))
            clash = {r.draw for r in got.join(first, "v").filter("draw <> owner").select("draw").distinct().collect()}
            take, at = [s for s in sizes if s.draw not in clash], at + n
        elif ordered:
            take, at = _in_order(at, n, sizes, reach, vol_w)
        else:
            take, at = sizes[:1], sizes[0].draw + 1
        for i, s in enumerate(take):
            vol_w -= s.vol_d
            trace.append((s.draw, s.seed_v, s.b, s.vol_d, vol_w))
            if 4 * vol_w < 3 * g.vol and not disjoint:
                take = take[: i + 1]
                break
        new = cut(got.filter(F.col("draw").isin([s.draw for s in take])).select("v", "draw"), "removed")
        removed = removed.union(new)
        if at < budget and 4 * vol_w >= 3 * g.vol:
            more = cut(cut_off(g, new, removed), "lost")
            lost = more if lost is None else lost.union(more)
    return removed, spark.createDataFrame(trace, "draw long, seed_v long, b int, vol_d long, vol_w long")


def _in_order(at: int, n: int, sizes: list, reach: dict, vol_w: int) -> tuple[list, int]:
    """Clusters to accept of draws at .. at + n - 1, and the next draw to make.

    reach: the volume that a draw reached, the whole one if it was not held, None if it was not settled.
    """
    by, take = {s.draw: s for s in sizes}, []
    left = vol_w
    for k in range(at, at + n):
        far = reach.get(k, 0)
        if far is None or take and not (2 * far <= left and scale_count(left) == scale_count(vol_w)):
            return take, k
        if k in by:
            take.append(by[k])
            left -= by[k].vol_d
            # later draws were not settled against a cluster of a run that was not held
            if far >= vol_w:
                return take, k + 1
    return take, at + n


def certificate(g: Graph, removed: DataFrame, theta) -> DataFrame:
    """Volume and conductance of the union, the bounds they must keep, and whether pieces are disjoint."""
    whole = report(g, removed.select(F.lit(0).alias("set_id"), "v").distinct())
    n = removed.groupBy("v").count().filter("count > 1").agg(F.count("*").alias("shared"))
    pieces = report(g, removed.select(F.col("draw").alias("set_id"), "v")).agg(F.sum("cut").alias("piece_cuts"))
    out = whole.crossJoin(n).crossJoin(pieces)
    return out.select(
        F.col("vol").alias("vol_d"), F.col("cut").alias("cut_d"), (8 * F.col("vol") <= 7 * F.lit(g.vol)).alias("vol_ok"),
        F.coalesce(F.col("phi") <= float(theta), F.lit(True)).alias("phi_ok"), (F.col("shared") == 0).alias("disjoint"),
        (F.col("cut") <= F.coalesce("piece_cuts", F.lit(0))).alias("cut_ok"),
    )


def as_labels(g: Graph, removed: DataFrame) -> DataFrame:
    """(v, side, draw) for every vertex."""
    return g.vertices.select("v").join(removed, "v", "left").select("v", F.col("draw").isNotNull().cast("int").alias("side"), "draw")


def peel_clusters(g: Graph, theta, p: float, depth: int | None = None, seed: int = 1, batch: int = 16, draws: int | None = None, factor: int = 12, disjoint: bool = False, pick: str = "first", **practical) -> DataFrame:
    """(v, part): both sides of a partition are split again, keeping degrees, up to `depth` times or until nothing is found.

    A part's name tells its way: "0", then "1" for what a partition took out and "0" for the rest. A part from which the
    whole budget of draws takes nothing out stays as it is.

    A part of up to PART_VOL volume is held by one task, which makes its draws one at a time and splits what it gets
    (`Held`); a large one hands parts on, so that the next round spreads them. Larger parts, and with `disjoint` all, are
    split by `peel_partition` one by one; without `disjoint` with the same result.
    """
    spark, g = g.spark, g.stored()
    rule = Rule(partition_phi(theta), p, seed, draws, factor, pick, practical)
    tasks = 4 * spark.sparkContext.defaultParallelism

    def go(key: tuple, rows: pa.Table) -> pa.Table:
        nbrs = pa.concat_arrays(rows["nbrs"].chunks)
        held = Held(rows["v"].to_numpy(), rows["deg"].to_numpy(), nbrs.value_lengths().to_numpy(False), nbrs.flatten().to_numpy(False), rule)
        vol = int(held.degs.sum())
        got = list(held.split(key[0].as_py(), depth, 0 if vol <= SPREAD_VOL else max(SPREAD_VOL, vol >> 6)))
        size = [len(x) for x, _, _ in got]
        name, done = (pa.array(x).take(pa.array(np.repeat(np.arange(len(got)), size))) for x in ([n for _, n, _ in got], [d for _, _, d in got]))
        return pa.table({"v": held.ids[np.concatenate([x for x, _, _ in got])], "part": name, "done": done})

    at, ended = cut(g.vertices.select("v", F.lit("0").alias("part")), "parts"), spark.createDataFrame([], "v long, part string")
    while not at.isEmpty():
        vols = at.join(g.vertices, "v").groupBy("part").agg(F.sum("deg").alias("vol"))
        names = [r.part for r in vols.filter(F.lit(disjoint) | (F.col("vol") > PART_VOL)).select("part").collect()]
        rows = at.filter(~F.col("part").isin(names)).join(g.near.rows.select("v", "deg", "nbrs"), "v")
        new = rows.repartition(tasks, "part").groupBy("part").applyInArrow(go, "v long, part string, done boolean")
        for name in names:
            if depth is not None and len(name) > depth:
                new = new.union(at.filter(F.col("part") == name).select("v", "part", F.lit(True)))
                continue
            here = cut(at.filter(F.col("part") == name).select("v"), "part")
            # the first part is the graph itself
            part = g.restrict(here).kept() if len(name) > 1 else g
            removed, trace = peel_partition(part, theta, p, seed, batch, draws, factor, disjoint, pick=pick, **practical)
            vol = trace.agg(F.sum("vol_d")).first()[0] or 0
            side = here.join(removed.select("v").distinct().withColumn("in_d", F.lit(True)), "v", "left")
            if 0 < vol < part.vol:
                side = side.select("v", F.concat(F.lit(name), F.when(F.col("in_d"), "1").otherwise("0")).alias("part"), F.lit(False))
            else:
                side = side.select("v", F.lit(name), F.lit(True))
            new = new.union(side)
        new = cut(new, "parts")
        ended = ended.union(new.filter("done").select("v", "part"))
        drop(at)
        at = cut(new.filter("not done").select("v", "part"), "parts")
    return ended
