"""Line models in scaled integers, and the intervals that follow from certified bounds.

v(p) = (a p + b) / 2^20 for values; t(p) = tau_lo + (mu p + beta) / 2^10 for times in microseconds.  Bounds use the same
scales and hold exactly for the integers, so no rounding enters any interval before the last step, which rounds outwards.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F

V, T = 1 << 20, 1 << 10


def line_sum(a: int, b: int, p0: int, p1: int) -> int:
    """Sum of a p + b for p in p0..p1."""
    n = p1 - p0 + 1
    return 0 if n <= 0 else a * (p0 + p1) * n // 2 + b * n


def line_extremes(a: int, b: int, p0: int, p1: int) -> tuple[int, int]:
    x, y = a * p0 + b, a * p1 + b
    return min(x, y), max(x, y)


def line_aggregates(a: Column, b: Column, p0: Column, p1: Column) -> dict[str, Column]:
    """The closed forms as columns, exact in decimals."""
    n = p1 - p0 + 1
    x, y = a * p0 + b, a * p1 + b
    return {"s": ((x + y) * n / 2).cast("decimal(38,0)"), "n": n, "mn": F.least(x, y), "mx": F.greatest(x, y)}


def first_at_least(mu: int, beta: int, x: int) -> int:
    """Smallest p with mu p + beta >= x (mu > 0)."""
    return -((beta - x) // mu)


def invert_arrival(mu: Column, beta: Column, x: Column) -> Column:
    """The same as a column."""
    return F.ceil((x - beta) / mu)


@dataclass(frozen=True)
class Run:
    """Positions of one segment: possible q0..q1, sure p0..p1 (empty if p0 > p1)."""

    q0: int
    q1: int
    p0: int
    p1: int
    formula: int


def resolve(g: dict, t_s: int, t_e: int, clamp: bool = True) -> Run:
    """Which positions of a segment lie in the window [t_s, t_e], as far as the arrival model tells.

    ``clamp`` also uses the certified time extent: an edge outside the segment's extent leaves nothing open there.
    """
    c, mu, beta, eps = g["c"], g["mu"], g["beta"], g["eps_t"]
    s, e = (t_s - g["tau_lo"]) * T, (t_e - g["tau_lo"]) * T
    q0, q1 = max(first_at_least(mu, beta, s - eps), 0), min(first_at_least(mu, beta, e + eps + 1) - 1, c - 1)
    p0, p1 = max(first_at_least(mu, beta, s + eps), 0), min(first_at_least(mu, beta, e - eps + 1) - 1, c - 1)
    edges = (g["tau_lo"] < t_s) + (g["tau_hi"] > t_e + 1)
    if clamp and g["tau_lo"] >= t_s:
        q0 = p0 = 0
    if clamp and g["tau_hi"] <= t_e + 1:
        q1 = p1 = c - 1
    if q0 > q1:
        return Run(0, -1, 0, -1, -(-2 * eps // mu) * edges)
    if p0 > p1:
        p0, p1 = q0, q0 - 1
    return Run(q0, q1, p0, p1, -(-2 * eps // mu) * edges)


@dataclass
class Pieces:
    """What a client gathers from verified nodes and opened segments, in value scale."""

    total: int = 0
    sure: int = 0
    undecided: int = 0
    formula: int = 0
    dv: int = 0
    dt: int = 0
    below: int = 0  # undecided mass that could lower / raise the sum
    above: int = 0
    lo: int | None = None
    hi: int | None = None
    any_lo: int | None = None
    any_hi: int | None = None
    eps: int = 0

    def _extend(self, lo: int, hi: int, sure: bool) -> None:
        if sure:
            self.lo, self.hi = lo if self.lo is None else min(self.lo, lo), hi if self.hi is None else max(self.hi, hi)
        self.any_lo, self.any_hi = lo if self.any_lo is None else min(self.any_lo, lo), hi if self.any_hi is None else max(self.any_hi, hi)

    def add_node(self, alpha: dict) -> None:
        """A folded node of whole segments: all positions are sure."""
        self.total += alpha["s"]
        self.sure += alpha["n"]
        self.dv += alpha["w"]
        self._extend(alpha["mn"], alpha["mx"], True)

    def add_segment(self, g: dict, t_s: int, t_e: int) -> None:
        r = resolve(g, t_s, t_e)
        a, b, eps = g["a"], g["b"], g["eps_v"]
        self.eps = max(self.eps, eps)
        n = max(0, r.p1 - r.p0 + 1)
        self.total += line_sum(a, b, r.p0, r.p1)
        self.sure += n
        self.dv += eps * n
        if n:
            self._extend(*line_extremes(a, b, r.p0, r.p1), True)
        for x, y in ((r.q0, r.p0 - 1), (r.p1 + 1, r.q1)) if n else ((r.q0, r.q1),):
            k = y - x + 1
            if k > 0:
                low, high = line_extremes(a, b, x, y)
                self.undecided += k
                self.dt += k * (max(abs(low), abs(high)) + eps)
                self.below += k * max(0, -(low - eps))
                self.above += k * max(0, high + eps)
                self._extend(low, high, False)
        self.formula += r.formula


def bounds(p: Pieces, f: str, cap: int, nonneg: bool = False) -> tuple[Fraction | None, Fraction | None]:
    """Interval of an aggregate that holds the exact answer; None where the window may be empty."""
    lo_sum = p.total - p.dv - (0 if nonneg else p.dt)
    hi_sum = p.total + p.dv + p.dt
    if f == "SUM":
        return Fraction(lo_sum, V), Fraction(hi_sum, V)
    if f == "COUNT":
        return Fraction(p.sure), Fraction(p.sure + p.undecided)
    if p.any_lo is None:
        return None, None
    if f == "MAX":
        return Fraction((p.hi if p.hi is not None else p.any_lo) - cap, V), Fraction(p.any_hi + cap, V)
    if f == "MIN":
        return Fraction(p.any_lo - cap, V), Fraction((p.lo if p.lo is not None else p.any_hi) + cap, V)
    corners = [Fraction(x, V * n) for x in (lo_sum, hi_sum) for n in (p.sure, p.sure + p.undecided) if n]
    ends = Fraction(p.any_lo - cap, V), Fraction(p.any_hi + cap, V)
    if not p.sure:
        return ends
    return max(min(corners), ends[0]), min(max(corners), ends[1])
