"""SQL and UDF front end: closed forms as inlinable SQL functions, reports and sweeps as table functions, cells as Arrow UDFs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.workers import ship
from . import theory, tune
from .prf import SPAN, prf_int

FUNCTIONS = {
    "ldp_u": ("s DOUBLE, m DOUBLE", "s / m"),
    "ldp_q": ("p DOUBLE, s DOUBLE, m DOUBLE", "(s - p) / (m - 1)"),
    "ldp_eps": ("p DOUBLE, s DOUBLE, m DOUBLE", "abs(ln(p * (m - s) / ((1 - p) * s)))"),
    "ldp_estimate": ("c DOUBLE, n DOUBLE, p DOUBLE, s DOUBLE, m DOUBLE", "(c - n * s / m) / (p - s / m)"),
    "ldp_variance": ("f DOUBLE, n DOUBLE, moment DOUBLE, k DOUBLE, m DOUBLE, s DOUBLE, p DOUBLE", "(f * p * (1 - p) + (n - f) * s / m * (1 - s / m)) / power(p - s / m, 2) + (moment - f * f - (n - f)) / (k * (m - 1))"),
}


def register_functions(spark: SparkSession) -> None:
    for name, (args, body) in FUNCTIONS.items():
        kind = "FUNCTION"
        spark.sql(f"CREATE OR REPLACE TEMPORARY {kind} {name}({args}) RETURNS DOUBLE RETURN {body}")


def cell_udf(seed: int, m: int):
    """Arrow UDF of the replay hash family."""

    @F.pandas_udf("int")
    def cell(j: pd.Series, item: pd.Series) -> pd.Series:
        return pd.Series([prf_int(seed, "cell", a, b) % m + 1 for a, b in zip(j, item, strict=True)], dtype="int32")

    return cell


def support_udf():
    """Grouped aggregate: how many reports hold a cell."""

    @F.pandas_udf("long")
    def support(x: pd.Series, c: pd.Series) -> int:
        return int(sum(b in a for a, b in zip(x, c, strict=True)))

    return support


def replay_subset(seed: int, k: int, m: int, s: int, p: float, report: int, item: str) -> tuple[int, list[int]]:
    """The replay report of plain arguments; equal to the Column form."""
    j = prf_int(seed, "row", report) % k + 1
    r = prf_int(seed, "cell", j, item) % m + 1
    own = prf_int(seed, "inc", report) < int(p * SPAN)
    seen: list[int] = []
    for i in range(m - (s - own), m):
        v = prf_int(seed, "ext", report, i) % i + 1
        seen.append(i if v in seen else v)
    return j, sorted([v + (v >= r) for v in seen] + [r] * own)


def register_table_functions(spark: SparkSession) -> None:
    """``subset_report(seed, k, m, s, p, report, item)`` yields (j, x); ``sweep(eps, k, m)`` yields (lam, p, s, eps_real)."""

    ship(spark)

    class SubsetReport:
        def eval(self, seed: int, k: int, m: int, s: int, p: float, report: int, item: str):
            j, cells = replay_subset(seed, k, m, s, float(p), report, item)
            for x in cells:
                yield j, x

    class Sweep:
        def eval(self, eps: float, k: int, m: int):
            for lam in (0.5, 0.1, 0.02):
                t = tune.tune(float(eps), lam, k, m)
                yield lam, round(t.p, 6), t.s, round(t.eps_real, 6)

    spark.udtf.register("subset_report", F.udtf(SubsetReport, returnType="j int, x int"))
    spark.udtf.register("sweep", F.udtf(Sweep, returnType="lam double, p double, s int, eps_real double"))


__all__ = ["FUNCTIONS", "T", "cell_udf", "register_functions", "register_table_functions", "replay_subset", "support_udf", "theory"]
