"""Parameter schedules of local clustering and partitioning, in exact integers and fractions where that matters."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

UNIT = 1 << 50
#: mass unit of schedules whose threshold would be distorted by UNIT; ball mode only
WIDE = 1 << 100


@dataclass(frozen=True)
class Constants:
    #: fixed values
    c1: int = 200
    c2: int = 280
    c3: int = 1800
    c4: int = 140
    c5: int = 20
    c6: int = 60

    def inequalities(self) -> list[tuple[str, Fraction, Fraction]]:
        """(name, larger side, smaller side) of the seven requirements."""
        f = Fraction
        c1, c2, c3, c4, c5, c6 = self.c1, self.c2, self.c3, self.c4, self.c5, self.c6
        return [
            ("c2 vs 2c4", f(c2), f(2 * c4)),
            ("c6 vs 2c5", f(c6), f(2 * c5)),
            ("c3 vs 8c5", f(c3), f(8 * c5)),
            ("c4 vs 4c5", f(c4), f(4 * c5)),
            ("slope left after losses", f(1, 2 * c6) - f(1, c3) - f(1, 2 * c5 * c6), f(1, c4)),
            ("curve gap", f(1, 2 * c5), f(6, 5 * c6) + f(1, c1)),
            ("fifth", f(1, 5), f(1, c5) + f(4 * c6, 3 * c3) + f(1, 2 * c1) + f(1, 2 * c2)),
        ]

    def check(self) -> bool:
        return all(a >= b for _, a, b in self.inequalities())


@dataclass(frozen=True)
class Schedule:
    """One run's parameters; `vol` is the volume of the graph the run lives on."""

    vol: int
    phi: Fraction
    b: int
    ell: int
    t1: int
    t_last: int
    eps: float
    slope_floor: float

    @property
    def f1(self) -> float:
        c = Constants()
        return 1 / (c.c2 * (self.ell + 2) * self.t_last)

    def epoch(self, h: int) -> int:
        return h * self.t1

    @property
    def unit(self) -> int:
        """Mass units of one: the wide unit where rounding the threshold up to UNIT's would distort it."""
        return UNIT if self.eps * UNIT >= 64 else WIDE

    @property
    def eps_units(self) -> int:
        """Truncation threshold per unit of degree, in mass units."""
        if self.eps * WIDE < 64:
            raise ValueError("threshold too small for any mass unit")
        return math.ceil(Fraction(self.eps) * self.unit)

    def decay_ok(self) -> bool:
        """Whether mixing over one epoch beats the curve gap."""
        c = Constants()
        phi = float(self.phi)
        return math.sqrt(self.vol / 2) * (1 - phi * phi / 2) ** self.t1 < 1 / (c.c1 * (self.ell + 2))


def scale_count(vol: int) -> int:
    """ceil(log2(vol / 2)) by bit lengths."""
    return max(1, (vol - 1).bit_length() - 1) if vol > 2 else 1


def valid_scales(vol: int) -> range:
    return range(1, scale_count(vol) + 1)


def schedule(vol: int, phi, b: int, consts: Constants | None = None, *, t_max: int | None = None, eps: float | None = None, slope: float | None = None, decay: int = 2) -> Schedule:
    """Theory parameters; t_max, eps and slope override them (practical profile).

    The length of an epoch rests on a loss of phi^2 / decay a step: 2 as stated, 8 if the chord reaches phi x' only
    (see `chord_check`).
    """
    c, phi = consts or Constants(), Fraction(phi)
    if not 0 < phi < 1:
        raise ValueError("phi must lie strictly between 0 and 1")
    ell = scale_count(vol)
    t1 = math.ceil(decay / float(phi) ** 2 * math.log(c.c1 * (ell + 2) * math.sqrt(vol / 2)))
    t_last = t_max or (ell + 1) * t1
    return Schedule(
        vol, phi, b, ell, t1, t_last,
        eps if eps is not None else 1 / (c.c3 * (ell + 2) * t_last * 2**b),
        slope if slope is not None else 1 / (c.c4 * (ell + 2) * 2**b),
    )


def partition_phi(theta) -> Fraction:
    return Fraction(theta) / 7


def f2(vol: int, theta) -> float:
    """Cut conductance that the partitioner is guaranteed to find."""
    return schedule(vol, partition_phi(theta), 1).f1 / 2


def max_draws(vol: int, p: float, factor: int = 12) -> int:
    return math.ceil(factor * vol / 2 * math.ceil(math.log2(1 / p)))


def scale_law(ell: int) -> list[float]:
    """Probability of scale 1..ell: halving, normalised."""
    return [2.0**-i / (1 - 2.0**-ell) for i in range(1, ell + 1)]
