"""Privacy accounting: shuffle amplification, thresholded-histogram calibration, composition."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def amplification_cap(n: float, delta: float) -> float:
    """Largest local epsilon for which the shuffling bound holds."""
    inside = n / (8 * math.log(2 / delta)) - 1
    return math.log(inside) if inside > 0 else float("-inf")


def amplify(eps: float, n: float, delta: float) -> float:
    """Central epsilon after shuffling ``n`` reports; the local value where the bound does not hold."""
    if eps > amplification_cap(n, delta):
        return eps
    e = math.exp(eps)
    return min(eps, math.log(1 + (e - 1) * (4 * math.sqrt(2 * math.log(4 / delta)) / math.sqrt((e + 1) * n) + 4 / n)))


def amplify_col(eps: Column, n: Column, delta: Column) -> Column:
    """The same as a Column."""
    inside, e = n / (8 * F.log(2 / delta)) - 1, F.exp(eps)
    bound = F.log(1 + (e - 1) * (4 * F.sqrt(2 * F.log(4 / delta)) / F.sqrt((e + 1) * n) + 4 / n))
    return F.when((inside <= 0) | (eps > F.log(F.greatest(F.lit(1e-300), inside))), eps).otherwise(F.least(eps, bound))


def discovery_eps_delta(threshold: float, scale: float) -> tuple[float, float]:
    """Guarantee of a noisy histogram with Laplace ``scale`` that releases counts of at least ``threshold`` (add/remove)."""
    tail = math.exp((threshold - 1) / scale)
    eps = max(1 / scale, math.log(1 + 1 / (2 * tail - 1)) if 2 * tail > 1 else float("inf"))
    return eps, 0.5 * math.exp((1 - threshold) / scale)


def calibrate(eps: float, delta: float, neighbours: str = "add_remove", cap: int = 1) -> tuple[float, float]:
    """(threshold, scale) for a client that sends at most ``cap`` reports. Replacement moves two counts."""
    moves = cap * (2 if neighbours == "replace" else 1)
    own = eps / moves
    share = delta / moves if moves == 1 else delta * (math.exp(own) - 1) / (math.exp(moves * own) - 1)
    return 1 - math.log(2 * share) / own, 1 / own


def ledger(spends: DataFrame) -> DataFrame:
    """Running totals of a frame ``epoch, mechanism, eps, delta`` under basic composition."""
    order = Window.orderBy("epoch", "mechanism").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return spends.withColumn("eps_total", F.sum("eps").over(order)).withColumn("delta_total", F.sum("delta").over(order))
