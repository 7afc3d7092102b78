"""No-privacy yardsticks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.prf import below


def frequencies(items: DataFrame) -> DataFrame:
    return items.groupBy("item").agg(F.count("*").alias("f"))


def sampled(items: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """A stable sample of the reports, scaled up."""
    return items.filter(below(seed, "sample", rate, "report_id")).groupBy("item").agg((F.count("*") / F.lit(rate)).alias("est"))


def moments(items: DataFrame) -> DataFrame:
    """``n`` and the sum of squared counts."""
    return frequencies(items).agg(F.sum("f").alias("n"), F.sum(F.col("f") * F.col("f")).alias("second_moment"))
