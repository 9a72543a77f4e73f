"""Error budgets and how policies spread them over regions of a stream."""

from __future__ import annotations

from collections.abc import Callable
from math import exp, log

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

REGIONS = 16
BUDGET = ["sid", "region", "eps_v", "eps_t", "gap", "region_size"]


def defaults(stats: DataFrame, v_frac: float = 0.10, t_units: float = 0.5, regions: int = 1) -> DataFrame:
    """Value budget: a share of the median absolute value; arrival budget: a multiple of the median gap."""
    size = F.greatest(F.expr(f"n div {regions}"), F.lit(1))
    gap = F.coalesce("median_gap", F.lit(1.0))
    return stats.select("sid", F.explode(F.sequence(F.lit(0), F.lit(regions - 1))).alias("region"), (F.col("median_abs") * v_frac).alias("eps_v"), (gap * t_units).alias("eps_t"), F.greatest(gap, F.lit(1.0)).alias("gap"), size.alias("region_size"))


def percentile_budget(stats: DataFrame, v_frac: float = 0.10, t_units: float = 0.5) -> DataFrame:
    """The contrast: a share of a high percentile, which heavy tails inflate."""
    return defaults(stats.withColumn("median_abs", F.col("p99_abs")), v_frac, t_units)


def uniform(base: DataFrame) -> DataFrame:
    return base


def water_fill(base: DataFrame, freq: DataFrame, exponent: float = -2 / 3) -> DataFrame:
    """Both budgets proportional to (1 + f_touch) ** exponent, mean factor 1 per stream.  With segment counts that fall as
    budget ** -1/2 and a width of sum(f * budget), -2/3 is the stationary point; +2/3 is the adversary."""
    f = F.coalesce(F.col("f_touch"), F.lit(0)) + 1
    return _scaled(base.join(freq, ["sid", "region"], "left").withColumns({"_v": F.pow(f, F.lit(exponent)), "_t": F.pow(f, F.lit(exponent))}))


def edge_aware(base: DataFrame, freq: DataFrame, exponent: float = -2 / 3) -> DataFrame:
    """Value budgets follow touches, arrival budgets follow window ends."""
    f = lambda c: F.pow(F.coalesce(F.col(c), F.lit(0)) + 1, F.lit(exponent))
    return _scaled(base.join(freq, ["sid", "region"], "left").withColumns({"_v": f("f_touch"), "_t": f("f_edge")}))


def _scaled(df: DataFrame) -> DataFrame:
    mean = df.groupBy("sid").agg(F.avg("_v").alias("_mv"), F.avg("_t").alias("_mt"))
    out = df.join(mean, "sid")
    return out.withColumns({"eps_v": F.col("eps_v") * F.col("_v") / F.col("_mv"), "eps_t": F.col("eps_t") * F.col("_t") / F.col("_mt")}).select(*BUDGET)


def scaled(budgets: DataFrame, factor: float) -> DataFrame:
    return budgets.withColumns({"eps_v": F.col("eps_v") * factor, "eps_t": F.col("eps_t") * factor})


def match_counts(count: Callable[[DataFrame, list[str]], dict[str, int]], budgets: DataFrame, variants: list[str], target: int | dict[str, int], tol: float = 0.01, rounds: int = 12) -> dict[str, float]:
    """Factors that bring the segment count of each variant (sid: ``variant|sid``) within ``tol`` of the target (or its own), or as near as
    ``rounds`` come: all variants still open are encoded in one batch a round.  A step lies where the counts at both ends
    of the bracket point to, and halves the bracket where that stalls; only counts return to the driver."""
    ends = {v: [(log(0.02), None), (log(50.0), None)] for v in variants}
    goal = target if isinstance(target, dict) else dict.fromkeys(variants, target)
    best: dict[str, tuple[float, float]] = {}
    todo = list(variants)
    for turn in range(rounds):
        at = {v: _step(*ends[v], log(max(goal[v], 1)), turn) for v in todo}
        if not at:
            break
        factor = F.create_map(*[F.lit(x) for v, y in at.items() for x in (v, exp(y))])[F.substring_index("sid", "|", 1)]
        tried = budgets.where(F.substring_index("sid", "|", 1).isin(list(at)))
        counts = count(tried.withColumns({"eps_v": F.col("eps_v") * factor, "eps_t": F.col("eps_t") * factor}), list(at))
        for v, y in at.items():
            off = abs(counts[v] - goal[v])
            if v not in best or off < best[v][0]:
                best[v] = (off, exp(y))
            ends[v][0 if counts[v] > goal[v] else 1] = (y, log(max(counts[v], 1)))
        todo = [v for v in todo if best[v][0] > tol * goal[v]]
    return {v: y for v, (_, y) in best.items()}


def _step(low: tuple, high: tuple, goal: float, turn: int) -> float:
    """The next logarithm of a factor to try inside a bracket: 1 at first, then between known counts every other turn."""
    (a, ca), (b, cb) = low, high
    if ca is None or cb is None or ca == cb or turn % 3 == 2:
        near, c = (low, ca) if cb is None else (high, cb)
        if c is None or turn % 3 == 2:
            return (a + b) / 2
        return min(max(near[0] + 1.5 * (c - goal), a + 0.05 * (b - a)), b - 0.05 * (b - a))
    share = min(max((ca - goal) / (ca - cb), 0.05), 0.95)
    return a + share * (b - a)
