"""Peeling partitions of parts that one task holds: one draw at a time, split after split, without a Spark job for each."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import asdict, dataclass, field
from fractions import Fraction

import numpy as np

from ..params import max_draws, scale_count, schedule
from .cluster import Ball, run_of
from .sampling import scales_at, uniforms_at

#: volume around a seed up to which walks are compared with others
NEAR_VOL = 1 << 8
#: outcomes kept of such walks
KEPT = 1 << 13
#: draws whose uniforms are kept
FIRST = 1 << 12
#: of a process, as its parts are mostly alike: clusters by surroundings and run, uniforms by seed
_OUTCOMES: dict[tuple, tuple | None] = {}
_UNIFORMS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _drawn(seed: int, first: int, count: int) -> tuple[np.ndarray, np.ndarray]:
    """`uniforms_at`, those of the first draws made once."""
    if first + count > FIRST:
        return uniforms_at(seed, first, count)
    if seed not in _UNIFORMS:
        _UNIFORMS.clear()
        _UNIFORMS[seed] = uniforms_at(seed, 0, FIRST)
    u1, u2 = _UNIFORMS[seed]
    return u1[first : first + count], u2[first : first + count]


@dataclass(frozen=True)
class Rule:
    """What `peel_partition` takes besides the graph."""

    phi: Fraction
    p: float
    seed: int = 1
    draws: int | None = None
    factor: int = 12
    pick: str = "first"
    practical: dict = field(default_factory=dict)

    @property
    def fixed(self) -> bool:
        return {"t_max", "eps", "slope"} <= self.practical.keys()


class Held:
    """A part of a graph, split into parts; vertices are their places in the order of ids.

    of[v] is the number of v's part. An arc counts if both ends have the same number; any other, and any arc out of what
    is held, is a loop, as in `Graph.restrict`. Walks from seeds whose surroundings are equal up to a renaming that keeps
    the order of ids have the same outcome (see `every_seed`) and are made once.
    """

    def __init__(self, v, deg, count, dst, rule: Rule):
        self.rule = rule
        self.ids, first, at = np.unique(v, return_index=True, return_inverse=True)
        n = len(self.ids)
        src, to = np.repeat(at, count), np.minimum(np.searchsorted(self.ids, dst), n - 1)
        inside = self.ids[to] == dst
        src, to = src[inside], to[inside]
        order = np.lexsort((to, src))
        self.dst = to[order]
        self.begin = np.searchsorted(src[order], np.arange(n + 1)).tolist()
        self.degs = np.asarray(deg, np.int64)[first]
        self.deg = self.degs.tolist()
        self.of, self.parts = [0] * n, 1
        self.runs: dict[tuple, tuple] = {}

    def around(self, v: int) -> list[int]:
        of = self.of
        p = of[v]
        return [u for u in self.dst[self.begin[v] : self.begin[v + 1]].tolist() if of[u] == p]

    def surroundings(self, v: int, hops: int) -> tuple[list[int], tuple, int] | None:
        """Vertices within some hops of v, their rows by places among them, and their volume; None if they are many.

        A walk of so many steps reads no other rows; an arc further out only counts as one that is no loop.
        """
        deg, vol, ring, rows, found = self.deg, self.deg[v], [v], {}, {v}
        if vol > NEAR_VOL:
            return None
        for _ in range(hops):
            out = []
            for x in ring:
                rows[x] = self.around(x)
                for u in rows[x]:
                    if u not in found:
                        vol += deg[u]
                        if vol > NEAR_VOL:
                            return None
                        found.add(u)
                        out.append(u)
            ring = out
            if not ring:
                break
        rows |= {x: self.around(x) for x in ring}
        order = sorted(found)
        place = {x: i for i, x in enumerate(order)}
        form = [place[v]]
        for x in order:
            form += (deg[x], deg[x] - len(rows[x]))
            form += [place[u] for u in rows[x] if u in place]
            form.append(-1)
        return order, tuple(form), vol

    def run(self, b: int, vol: int) -> tuple[dict, int, tuple]:
        """A run of scale b at a volume left, its steps, and what tells it from others."""
        key = (b, 0 if self.rule.fixed else vol)
        if key not in self.runs:
            if len(self.runs) > KEPT:
                self.runs.clear()
            s = schedule(vol, self.rule.phi, b, **self.rule.practical)
            r = asdict(run_of(0, 0, s, pick=self.rule.pick))
            self.runs[key] = r, s.t_last, (s.t_last, *r.values())
        return self.runs[key]

    def cluster(self, v: int, b: int, vol: int) -> list[int] | tuple | None:
        """The cluster that a run of scale b from v finds in its part, of which the volume is left."""
        run, steps, kind = self.run(b, vol)
        near, key = self.surroundings(v, steps), None
        if near is not None:
            order, form, size = near
            # the volume left tells for sets of more than half of it only
            key = (form, kind, vol if 2 * size > vol else 0)
            if key in _OUTCOMES:
                got = _OUTCOMES[key]
                return got and [order[i] for i in got]
        ball = Ball(run | {"seed": v}, vol)
        while ball.hit is None and ball.t < steps and (need := ball.missing()):
            need = need if near is None else order
            rows = [self.around(x) for x in need]
            deg, count = self.degs[need], np.array([len(x) for x in rows], np.int64)
            ball.take_rows(np.array(need, np.int64), deg, deg - count, np.zeros(len(need), np.int64), count, np.array([u for x in rows for u in x], np.int64))
            ball.advance(steps)
        if key is not None:
            if len(_OUTCOMES) >= KEPT:
                _OUTCOMES.clear()
            place = {x: i for i, x in enumerate(order)}
            _OUTCOMES[key] = ball.hit and tuple(place[x] for x in ball.hit)
        return ball.hit

    def peel(self, here: np.ndarray) -> np.ndarray:
        """What the partition takes out of a part; it gets a number of its own."""
        rule, of = self.rule, self.of
        new, self.parts = self.parts, self.parts + 1
        ends = np.cumsum(self.degs[here])
        vol = left = int(ends[-1])
        budget = rule.draws if rule.draws is not None else max_draws(vol, rule.p, rule.factor)
        # a last place for draws that rounding puts past the end: they give no run
        seeds, gone, without, at, n = np.append(here, -1), [], set(), 0, 64
        while at < budget and 4 * left >= 3 * vol:
            n = min(n, budget - at)
            u1, u2 = _drawn(rule.seed, at, n)
            drawn = seeds[np.searchsorted(ends, np.floor(u1 * float(vol)), "right")].tolist()
            ell, scale = 0, []
            for k, v in enumerate(drawn):
                if v < 0 or of[v] == new:
                    continue
                if scale_count(left) != ell:
                    ell = scale_count(left)
                    scale = scales_at(ell, u2).tolist()
                if (v, scale[k]) in without:
                    continue
                got = self.cluster(v, scale[k], left)
                if not got:
                    without.add((v, scale[k]))
                    continue
                without.clear()
                gone += got
                for x in got:
                    of[x] = new
                    left -= self.deg[x]
                if 4 * left < 3 * vol:
                    break
            at, n = at + n, min(4 * n, 1 << 14)
        return np.sort(np.array(gone, np.int64))

    def split(self, name: str, depth: int | None, enough: int) -> Iterator[tuple[np.ndarray, str, bool]]:
        """(vertices, name, whether it stays as it is) of the parts; those of up to `enough` volume are left for later."""
        todo = [(np.arange(len(self.ids)), name)]
        while todo:
            here, name = todo.pop()
            if depth is not None and len(name) > depth:
                yield here, name, True
            elif self.degs[here].sum() <= enough:
                yield here, name, False
            elif len(gone := self.peel(here)):
                rest = np.ones(len(here), bool)
                rest[np.searchsorted(here, gone)] = False
                todo += [(gone, name + "1"), (here[rest], name + "0")]
            else:
                yield here, name, True
