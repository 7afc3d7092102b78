"""Choice of p and s for a target frequency, and of m and k under size budgets."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import theory


@dataclass(frozen=True)
class Tuned:
    p: float
    s: int
    eps_real: float


def best_p(eps: float, lam: float, k: int, form: str = "exact", tolerance: float = 1e-10) -> float:
    """Minimiser of the one-humped objective on [1/2, 1) by golden sections."""
    kk = 1 if form == "exact" else k
    ratio = (5**0.5 - 1) / 2
    low, high = 0.5, 1 - 1e-12
    a, b = high - ratio * (high - low), low + ratio * (high - low)
    fa, fb = theory.objective(a, lam, eps, kk), theory.objective(b, lam, eps, kk)
    for _ in range(300):
        if high - low < tolerance:
            break
        if fa <= fb:
            high, b, fb = b, a, fa
            a = high - ratio * (high - low)
            fa = theory.objective(a, lam, eps, kk)
        else:
            low, a, fa = a, b, fb
            b = low + ratio * (high - low)
            fb = theory.objective(b, lam, eps, kk)
    return (low + high) / 2


def best_p_by_thirds(eps: float, lam: float, k: int, tolerance: float = 1e-10) -> float:
    """The same minimiser of the published objective, found by cutting a third of the interval at a time on the worse side."""
    low, width = 0.5, 0.5 - 1e-12
    while width > tolerance:
        left, right = low + width / 3, low + 2 * width / 3
        if theory.objective(left, lam, eps, k) > theory.objective(right, lam, eps, k):
            low = left
        width *= 2 / 3
    return low + width / 2


def tune(eps: float, lam: float, k: int, m: int, form: str = "exact") -> Tuned:
    """Continuous optimum, subset size rounded up (which lowers the realised epsilon)."""
    p = best_p(eps, lam, k, form)
    s = min(max(1, theory.s_of(p, eps, m)), m // 2)
    return Tuned(p, s, theory.eps_of(p, s, m))


def tune_integer(eps: float, lam: float, k: int, m: int, form: str = "exact") -> Tuned:
    """Over all subset sizes, the one whose exactly spent p has the least variance."""
    kk = 1 if form == "exact" else k

    def cost(s: int) -> float:
        p, u = theory.p_of(s, eps, m), s / m
        return (lam * p * (1 - p / kk) + (1 - lam) * u * (1 - u / kk)) / (p - u) ** 2

    fits = [s for s in range(1, m // 2 + 1) if 0.5 <= theory.p_of(s, eps, m) < 1] or [1]
    s = min(fits, key=cost)
    p = theory.p_of(s, eps, m)
    return Tuned(p, s, theory.eps_of(p, s, m))


def regimes(eps: float, k: int, m: int, lams: tuple[float, ...] = (0.5, 0.1, 0.02)) -> dict[float, Tuned]:
    return {lam: tune(eps, lam, k, m) for lam in lams}


def grid(spark: SparkSession, settings: list[tuple[float, float, int]], steps: int = 500) -> DataFrame:
    """Best p of each ``(eps, lam, k)`` on a grid of ``steps`` values in [1/2, 1), in one aggregate."""
    return grid_of(spark.createDataFrame(settings, "eps double, lam double, k int"), steps)


def grid_of(frame: DataFrame, steps: int = 500) -> DataFrame:
    """The same for a frame with these columns, whatever else it holds; a row's other columns stay with it."""
    points = frame.sparkSession.range(steps).select((F.lit(0.5) + F.col("id") * F.lit(0.5 / steps)).alias("p"))
    scored = frame.crossJoin(F.broadcast(points)).withColumn("cost", theory.objective(F.col("p"), F.col("lam"), F.col("eps"), F.col("k"), exp=F.exp))
    return scored.groupBy(*frame.columns).agg(F.min_by("p", F.struct("cost", "p")).alias("p"), F.min("cost").alias("cost"))


def plan_capacities(shares: DataFrame, bits: int, cells: int, eps: float, top: int = 12) -> DataFrame:
    """Largest m (of powers of two) whose reports fit ``bits``, with the k that fills ``cells``, for every row's share ``lam`` (p from the
    grid): ``m, k, s, p, bits_used`` beside the row's columns; rows that nothing fits are left out."""
    keys = shares.columns
    best = grid_of(shares.withColumns({"eps": F.lit(eps), "k": F.lit(1)})).select(*keys, "p")
    sizes = shares.sparkSession.createDataFrame([(e, 1 << e, cells // (1 << e)) for e in range(3, top + 1) if cells >> e], "e int, m int, k int")
    fit = best.crossJoin(F.broadcast(sizes))
    s = F.ceil(F.round(F.col("m") / (1 + (1 / F.col("p") - 1) * F.lit(math.exp(eps))), 9))
    fit = fit.withColumn("s", F.least(F.greatest(F.lit(1), s), F.floor(F.col("m") / 2)).cast("int"))
    fit = fit.withColumn("bits_used", F.col("s") * F.col("e")).filter(F.col("bits_used") <= bits)
    return fit.groupBy(*keys).agg(F.max_by(F.struct("m", "k", "s", "p", "bits_used"), "m").alias("best")).select(*keys, "best.*")
