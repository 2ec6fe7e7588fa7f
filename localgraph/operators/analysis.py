"""The objects of the analysis and the guarantees as checks: DataFrames (check, compared, violations), 0 where all hold.

Flooring loses at most 2 deg units per vertex and step, so bounds in mass units are asserted with that slack.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import Graph, components, report
from ..params import UNIT, Constants, schedule
from ..session import cut
from .cluster import alike
from .sweep import conditions, curve_inverse, curve_points, ranked
from .walk import Run, degrees, fetch, runs_frame, step, walk


def verdict(name: str, rows: DataFrame, bad: Column) -> DataFrame:
    """How many rows were compared, and how many of them break the bound."""
    return rows.agg(F.lit(name).alias("check"), F.count("*").alias("compared"), F.count(F.when(bad, 1)).alias("violations"))


def escape_mass(g: Graph, s: DataFrame, seeds: list[int], steps: int) -> DataFrame:
    """(seed, t, outside): exact walk mass outside s."""
    w = walk(g, [Run(v, v) for v in seeds], steps)
    out = w.join(s.select("v"), "v", "left_anti").groupBy("run_id", "t").agg(F.sum("mass").alias("outside"))
    grid = w.select("run_id", "t").distinct()
    return grid.join(out, ["run_id", "t"], "left").select(F.col("run_id").alias("seed"), "t", F.coalesce("outside", F.lit(0)).alias("outside"))


def killed_mass(g: Graph, s: DataFrame, seeds: list[int], steps: int) -> DataFrame:
    """(seed, t, inside): mass that never left s."""
    w = walk(g, [Run(v, v) for v in seeds], steps, s.select("v"), killed=True)
    return w.groupBy(F.col("run_id").alias("seed"), "t").agg(F.sum("mass").alias("inside"))


def core(g: Graph, s: DataFrame, horizon: int) -> DataFrame:
    """Vertices of s whose escape mass stays within horizon * conductance(s) up to the horizon."""
    phi = report(g, s.select(F.lit(0).alias("set_id"), "v")).first()["phi"]
    seeds = [r.v for r in s.select("v").orderBy("v").collect()]
    esc = escape_mass(g, s, seeds, horizon).groupBy("seed").agg(F.max("outside").alias("worst"))
    return esc.filter(F.col("worst") <= horizon * phi * UNIT).select(F.col("seed").alias("v"))


def core_inner(g: Graph, s: DataFrame, horizon: int) -> DataFrame:
    """The same by the killed walk: a subset of the core."""
    phi = report(g, s.select(F.lit(0).alias("set_id"), "v")).first()["phi"]
    seeds = [r.v for r in s.select("v").orderBy("v").collect()]
    stay = killed_mass(g, s, seeds, horizon).filter(F.col("t") == horizon)
    return stay.filter(F.lit(UNIT) - F.col("inside") <= horizon * phi * UNIT).select(F.col("seed").alias("v"))


def abscissae(g: Graph, seeds: list[int], ell: int, epoch: int) -> DataFrame:
    """(seed, h, x): where the exact walk's curve after h epochs reaches (h + 1) / (c5 (ell + 2))."""
    c5 = Constants().c5
    r = ranked(g, walk(g, [Run(v, v) for v in seeds], ell * epoch))
    ys = g.spark.createDataFrame([(h, h * epoch, (h + 1) * UNIT / (c5 * (ell + 2))) for h in range(ell + 1)], "h int, at int, y double")
    inv = curve_inverse(r, ys.select("y")).join(F.broadcast(ys), "y").filter("t = at")
    return inv.select(F.col("run_id").alias("seed"), "h", "x")


def scale_classes(xs: DataFrame, ell: int) -> DataFrame:
    """(seed, h, b): first epoch whose abscissa at most doubles, and the scale of the abscissa before it."""
    prev = xs.select("seed", (F.col("h") + 1).alias("h"), F.col("x").alias("before"))
    ok = xs.join(prev, ["seed", "h"]).filter((F.col("x") <= 2 * F.col("before")) & F.col("h").between(1, ell))
    first = ok.groupBy("seed").agg(F.min(F.struct("h", "before")).alias("f"))
    b = F.when(F.col("f.before") < 2, 0).otherwise(F.floor(F.log2("f.before")))
    return first.select("seed", "f.h", b.cast("int").alias("b"))


def checks(g: Graph, seeds: list[int], steps: int, eps_units: int, s: DataFrame) -> DataFrame:
    """Walk inequalities from seeds in s over a few steps: (check, compared, violations)."""
    runs = [Run(i, v) for i, v in enumerate(seeds)]
    exact, cut_ = cut(walk(g, runs, steps)), walk(g, [Run(r.run_id, r.seed, eps_units) for r in runs], steps)
    killed = walk(g, runs, steps, s.select("v"), killed=True)
    both = cut(degrees(g, exact).select("run_id", "t", "v", "deg", F.col("mass").alias("p")))
    top = both.groupBy("run_id", "t").agg(F.max(F.col("p") / F.col("deg")).alias("m"))
    later = top.select("run_id", (F.col("t") - 1).alias("t"), F.col("m").alias("m2"))
    slack = F.lit(2).cast("long") * F.col("t") * F.col("deg")
    join = lambda other: both.join(other.select("run_id", "t", "v", F.col("mass").alias("q")), ["run_id", "t", "v"], "left").withColumn("q", F.coalesce("q", F.lit(0)))
    r = cut(ranked(g, exact))
    former = r.filter("t > 0").select("run_id", (F.col("t") - 1).alias("t"), F.col("prefix_vol").alias("x"), F.col("prefix_mass").alias("next"))
    # both curves are concave, so breakpoints of the later one decide for all x
    return (
        verdict("monotone", top.join(later, ["run_id", "t"]), F.col("m2") > F.col("m") + 2)
        .union(verdict("killed_le_free", join(killed), F.col("q") > F.col("p") + slack))
        .union(verdict("truncation_sandwich", join(cut_), (F.col("q") > F.col("p") + slack) | (F.col("q") < F.col("p") - F.col("t") * F.lit(eps_units).cast("long") * F.col("deg") - slack)))
        .union(verdict("curve_monotone", curve_points(r, former), F.col("next") > F.col("value") * (1 + 1e-12) + 2 * F.col("x")))
        .union(verdict("mass_kept", exact.groupBy("run_id", "t").agg(F.sum("mass").alias("m")), F.col("m") > UNIT))
    )


def chord_check(g: Graph, seeds: list[int], steps: int, phi_num: int, phi_den: int, reach: int) -> DataFrame:
    """At prefixes of the next state with conductance >= phi, does the curve lie under the chord of the former one?

    The chord spans `reach` * phi * x' to both sides. Reach 2 is the printed form; with conductance cut / volume and
    lazy steps it fails (two triangles joined by an edge, mass spread by degree over one: 13/14 against 12/14), and the
    argument gives reach 1, the decay of which is `schedule(..., decay=8)`.
    """
    runs = [Run(i, v, 0, 1, phi_num, phi_den) for i, v in enumerate(seeds)]
    w = cut(walk(g, runs, steps))
    now = cut(ranked(g, w))
    c = conditions(g, w.filter("t > 0"), runs_frame(g, runs)).filter("not c1 and side > 0")
    pts = c.join(now.select("run_id", "t", "j", "prefix_mass"), ["run_id", "t", "j"])
    wide = F.col("side") * (reach * phi_num / phi_den)
    ends = F.explode(F.array(F.col("prefix_vol") - wide, F.col("prefix_vol") + wide)).alias("x")
    pts = pts.select("run_id", (F.col("t") - 1).alias("t"), "j", "prefix_vol", "prefix_mass", ends)
    both = curve_points(now, pts).groupBy("run_id", "t", "j", "prefix_vol", "prefix_mass").agg(F.min("value").alias("low"), F.max("value").alias("high"))
    return verdict("chord" if reach == 2 else "chord_half", both, F.col("prefix_mass") > (F.col("low") + F.col("high")) / 2 * (1 + 1e-12) + 2 * F.col("prefix_vol"))


def escape_bounds(g: Graph, s: DataFrame, steps: int) -> DataFrame:
    """Walk from the degree law of s, killed outside it: per step the mass inside and its largest share per degree, with their bounds."""
    inside = cut(g.vertices.join(s.select("v"), "v", "left_semi"))
    vol, phi = inside.agg(F.sum("deg")).first()[0], report(g, s.select(F.lit(0).alias("set_id"), "v")).first()["phi"] or 0.0
    rf = runs_frame(g, [Run(0, 0)])
    state = cut(inside.select(F.lit(0).cast("long").alias("run_id"), F.lit(0).alias("t"), "v", F.floor(F.lit(float(UNIT)) * F.col("deg") / F.lit(vol)).alias("mass")))
    out = state
    for _ in range(steps):
        state = cut(step(g, fetch(g, state), rf, s.select("v"), killed=True))
        out = out.union(state)
    per = degrees(g, out).groupBy("t").agg(F.sum("mass").alias("inside"), F.max(F.col("mass") / F.col("deg")).alias("norm"))
    low = F.lit(float(UNIT)) * (1 - F.col("t") * phi / 2) - F.lit(2 * vol) * (F.col("t") + 1)
    return per.select("t", "inside", "norm", (F.col("inside") >= low).alias("escape_ok"), (F.col("norm") <= F.lit(UNIT / vol)).alias("norm_ok"))


#: vertices of a component that one task walks as a dense matrix
LAB = 1024


def _stops(xs: np.ndarray, vol: int, ell: int):
    """Of the abscissae xs[h, seed]: whether the seed is late, its stop epoch and class, and whether they rise."""
    late = xs[ell] >= vol / (Constants().c6 * (ell + 2))
    stop = np.array([ell + 1 if late[v] else next(i for i in range(1, ell + 1) if xs[i, v] <= 2 * xs[i - 1, v]) for v in range(xs.shape[1])])
    before = xs[stop - 1, np.arange(xs.shape[1])]
    scale = np.where(before < 2, 0, np.floor(np.log2(np.maximum(before, 2)))).astype(int)
    return late, stop, scale, (xs[1:] >= xs[:-1] * (1 - 1e-9)).all(0)


def _epochs(part: pd.DataFrame, vol: int, ell: int, t1: int) -> pd.DataFrame:
    """(seed, h, b, rising) of a component from its adjacency rows, by classes of vertices that are alike.

    In a tree, vertices of one class are images of each other, so one seed stands for its class; seen from that seed,
    vertices of a class hold the same mass, and the curve is linear over a class.
    """
    v, (ids, first) = part["v"].to_numpy(), np.unique(part["v"].to_numpy(), return_index=True)
    deg, loops, n = part["deg"].to_numpy()[first], part["loops"].to_numpy()[first], len(ids)
    a = np.repeat(np.searchsorted(ids, v), [len(x) for x in part["nbrs"]])
    b = np.searchsorted(ids, np.concatenate(part["nbrs"].to_numpy()))
    plain = alike(np.unique(np.stack([deg, loops]), axis=1, return_inverse=True)[1].reshape(-1), a, b)
    kind = plain if len(a) == 2 * (n - 1) else np.arange(n)
    seeds = np.unique(kind, return_index=True)[1]
    xs = np.empty((ell + 2, len(seeds)))
    for x, seed in enumerate(seeds.tolist()):
        color = alike(2 * plain + (np.arange(n) == seed), a, b)
        k = int(color.max()) + 1
        one = np.full(k, -1)
        one[color] = np.arange(n)
        size, d = np.bincount(color, minlength=k), deg[one]
        move = np.diag(0.5 + loops[one] / (2 * d))
        own = one[color[a]] == a
        np.add.at(move, (color[a[own]], color[b[own]]), 1 / (2 * deg[b[own]]))
        p, epoch = (np.arange(k) == color[seed]).astype(float), np.linalg.matrix_power(move, t1)
        for h in range(ell + 2):
            order = np.argsort(np.where(p > 0, -p / d, 1.0), kind="stable")
            order = order[p[order] > 0]
            xs[h, x] = np.interp((h + 1) / (Constants().c5 * (ell + 2)), np.append(0, np.cumsum((size * p)[order])), np.append(0, np.cumsum((size * d)[order])))
            p = epoch @ p
    _, stop, scale, rising = _stops(xs, vol, ell)
    at = np.searchsorted(kind[seeds], kind)
    return pd.DataFrame({"seed": ids, "h": stop[at], "b": scale[at], "rising": rising[at]})


def guarantees(g: Graph, phi, limit: int = LAB) -> DataFrame:
    """Theory schedule on zero-cut targets: what is proved for a vertex of the set's core, vertex by vertex.

    Every connected component of at most 2/3 of the volume is a target with an empty cut, so all its vertices belong to
    the core. Rows (seed, comp, h, b, rising, nonempty, overlap, c123, c4, floor, ceiling): stop epoch h and class b from
    the exact walk; abscissae rise; clustering from the seed with its own b finds a set, which overlaps the target enough;
    its epoch satisfies the conditions; curve floor and, at the end of that epoch, ceiling hold. Class 0 runs nothing (its verdicts are null).
    Components of more than `limit` vertices get h, b and rising by classes of vertices that are alike, and null verdicts;
    those of too large a volume are no targets (h and b null too).
    """
    vol, c = g.vol, Constants()
    base = schedule(vol, phi, 1)
    ell, t1, f = base.ell, base.t1, float(Fraction(phi))
    comp = components(g)
    size = comp.join(g.vertices, "v").groupBy("comp").agg(F.count("*").alias("n"), F.sum("deg").alias("vol"))
    target = 3 * F.col("vol") <= 2 * F.lit(vol)
    fits = (F.col("n") <= limit) & target
    rows = g.near.of(comp).join(size.filter(fits).select("comp"), "comp").repartition(4 * g.spark.sparkContext.defaultParallelism, "comp")
    out = "seed long, comp long, h int, b int, rising boolean, nonempty boolean, overlap boolean, c123 boolean, c4 boolean, floor boolean, ceiling boolean"

    def lab(part: pd.DataFrame) -> pd.DataFrame:
        ids = np.sort(part["v"].unique())
        at = {v: i for i, v in enumerate(ids.tolist())}
        n, deg, flow = len(ids), np.zeros(len(ids)), np.zeros((len(ids), len(ids)))
        for r in part.itertuples():
            i = at[r.v]
            deg[i] = r.deg
            flow[i, i] = r.loops
            flow[[at[u] for u in r.nbrs], i] += 1
        edges, move = flow.copy(), (np.eye(n) + flow / deg) / 2
        np.fill_diagonal(edges, 0)
        ends, degree = np.argwhere(np.triu(edges) > 0), deg[:, None]

        def curves(p):
            """Per column: order, prefix volumes and masses, conductance of the prefixes as (cut, side); deg as far as mass reaches."""
            order = np.argsort(np.where(p > 0, -p / degree, 1.0), axis=0, kind="stable")
            lam = np.cumsum(deg[order], axis=0)
            mass = np.cumsum(np.take_along_axis(p, order, 0), axis=0)
            rank = np.empty_like(order)
            np.put_along_axis(rank, order, np.arange(n)[:, None], 0)
            inside = np.zeros((n, p.shape[1]))
            for u, w in ends:
                inside[np.maximum(rank[u], rank[w]), np.arange(p.shape[1])] += 1
            cut_ = np.cumsum(edges.sum(0)[order], axis=0) - 2 * np.cumsum(inside, axis=0)
            live = np.take_along_axis(p, order, 0) > 0
            return order, lam, mass, cut_, np.minimum(lam, vol - lam), live

        def value(lam, mass, x):
            return float(np.interp(x, np.append(0, lam), np.append(0, mass)))

        epoch, marks = np.linalg.matrix_power(move, t1), [np.eye(n)]
        for _ in range(ell + 1):
            marks.append(epoch @ marks[-1])
        xs = np.empty((ell + 2, n))
        for h, p in enumerate(marks):
            _, lam, mass, _, _, live = curves(p)
            for v in range(n):
                k = live[:, v]
                xs[h, v] = np.interp((h + 1) / (c.c5 * (ell + 2)), np.append(0, mass[k, v]), np.append(0, lam[k, v]))
        late, stop, scale, rising = _stops(xs, vol, ell)
        got = [(int(ids[v]), int(stop[v]), 0, bool(rising[v]), *[None] * 6) for v in np.flatnonzero(scale == 0)]
        who = np.flatnonzero(scale)
        if len(who):
            b, h = scale[who], stop[who]
            plans = {int(x): schedule(vol, phi, int(x)) for x in np.unique(b)}
            eps = np.array([plans[x].eps for x in b.tolist()])
            least = np.array([plans[x].slope_floor for x in b.tolist()])
            q, found = np.eye(n)[:, who], np.full(len(who), -1.0)
            c4, c123, floor, ceiling, beta = np.ones(len(who), bool), np.zeros(len(who), bool), np.ones(len(who), bool), np.ones(len(who), bool), np.zeros(len(who))
            for t in range(1, base.t_last + 1):
                q = move @ np.where(q >= degree * eps, q, 0.0)
                # sweeps of runs that look for their set or are in their own epoch
                now = (t1 * (h - 1) < t) & (t <= t1 * h)
                on = np.flatnonzero(now | (found < 0))
                if not len(on):
                    continue
                p, bs, col = q[:, on], b[on], np.arange(len(on))
                order, lam, mass, cut_, side, live = curves(p)
                fits = live & (6 * lam <= 5 * vol)
                hit = fits & (cut_ <= f * side) & (lam >= 2.0**bs)
                k = (lam >= 2.0**bs).argmax(0)
                steep = np.where(lam[-1] >= 2.0**bs, p[order[k, col], col] / deg[order[k, col]], 0) >= least[on]
                beta[on] = np.where(now[on], np.maximum(beta[on], np.where(fits & (cut_ < f * side), mass, 0).max(0)), 0)
                c4[on] &= ~now[on] | steep
                c123[on] |= now[on] & hit.any(0)
                new = (found[on] < 0) & steep & hit.any(0)
                found[on[new]] = lam[hit.argmax(0), col][new]
                for x in np.flatnonzero(t == t1 * h[on]):
                    i, live_x = on[x], live[:, x]
                    l, m = lam[live_x, x], mass[live_x, x]
                    ceiling[i] = (m <= beta[i] + 6 * l / (5 * vol) + np.sqrt(np.minimum(l, vol - l)) * (1 - f * f / 2) ** t1 + 1e-9).all()
                    if late[who[i]]:
                        floor[i] = value(l, m, 2 * vol / 3) >= 1 - 1 / (c.c2 * (ell + 2)) - 4 * c.c6 / (3 * c.c3)
                    else:
                        floor[i] = value(l, m, xs[h[i], who[i]]) >= (h[i] + 0.5) / (c.c5 * (ell + 2))
            # the target is the whole component, so all of a found set overlaps it
            got += [(int(ids[v]), int(h[i]), int(b[i]), bool(rising[v]), bool(found[i] >= 0), bool(found[i] >= 2.0 ** (b[i] - 1)), bool(c123[i]), bool(c4[i]), bool(floor[i]), bool(ceiling[i])) for i, v in enumerate(who)]
        df = pd.DataFrame(got, columns=["seed", "h", "b", "rising", "nonempty", "overlap", "c123", "c4", "floor", "ceiling"])
        df.insert(1, "comp", part["comp"].iloc[0])
        return df.astype({x: "boolean" for x in ("nonempty", "overlap", "c123", "c4", "floor", "ceiling")})

    done = cut(rows.groupBy("comp").applyInPandas(lab, out), "guarantees")
    wide = g.near.of(comp).join(size.filter((F.col("n") > limit) & target).select("comp"), "comp").repartition(4 * g.spark.sparkContext.defaultParallelism, "comp")
    large = cut(wide.groupBy("comp").applyInPandas(lambda key, part: _epochs(part, vol, ell, t1).assign(comp=key[0]), "seed long, h int, b int, rising boolean, comp long"), "epochs")
    rest = comp.join(size.filter(~target).select("comp"), "comp").select(F.col("v").alias("seed"), "comp")
    return done.unionByName(large, allowMissingColumns=True).unionByName(rest, allowMissingColumns=True)
