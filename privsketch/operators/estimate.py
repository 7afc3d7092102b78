"""Frequency lookups with error bars, and post-processing of estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.theory import SketchParams
from .randomize import arrow_probes, cell

#: Bytes of a matrix up to which it is broadcast for lookups; larger ones are joined by shuffle.
BROADCAST_BYTES = 64 << 20


def support(items: DataFrame, matrix: DataFrame, sp: SketchParams, mode: str | None = None, engine: str = "sql") -> DataFrame:
    """Raw support of each item: its cells' counts over all rows; absent cells count zero. ``engine`` must be that of the reports, whose
    hash family the cells belong to."""
    if engine == "arrow":
        probes = arrow_probes(items, sp)
    else:
        probes = items.select("item").distinct().withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(sp.k)))).withColumn("x", cell(sp, F.col("j"), F.col("item"), mode))
    side = F.broadcast(matrix) if sp.k * sp.m * 16 <= BROADCAST_BYTES else matrix
    return probes.join(side, ["j", "x"], "left").groupBy("item").agg(F.sum(F.coalesce("cnt", F.lit(0))).cast("long").alias("support"))


def frequencies(items: DataFrame, matrix: DataFrame, sp: SketchParams, n: int | None = None, clip: bool = False, mode: str | None = None, engine: str = "sql") -> DataFrame:
    """``item, support, n, est``. Every report adds exactly s to the matrix, so n needs no second pass."""
    total = matrix.agg((F.sum("cnt") / sp.s).cast("long").alias("n")) if n is None else None
    got = support(items, matrix, sp, mode, engine)
    got = got.crossJoin(F.broadcast(total)) if total is not None else got.withColumn("n", F.lit(n).cast("long"))
    theory.estimate(0.0, 0.0, sp.p, sp.u)  # refuses parameters that carry nothing
    est = (F.col("support") - F.col("n") * F.lit(sp.u)) / F.lit(sp.p - sp.u)
    return got.withColumn("est", F.greatest(est, F.lit(0.0)) if clip else est)


def support_scan(items: DataFrame, reports: DataFrame, sp: SketchParams, mode: str | None = None, largest: int = 10_000) -> DataFrame:
    """Support straight from reports, for a small domain (refused beyond ``largest`` distinct items) and no matrix."""
    names = items.select("item").distinct()
    if names.limit(largest + 1).count() > largest:
        raise ValueError(f"the domain has more than {largest} items; build a matrix")
    each = names.withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(sp.k)))).withColumn("c", cell(sp, F.col("j"), F.col("item"), mode))
    hits = reports.join(F.broadcast(each), "j").filter(F.array_contains("x", F.col("c")))
    return each.select("item").distinct().join(hits.groupBy("item").agg(F.count("*").alias("support")), "item", "left").select("item", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def interval(est: DataFrame, sp: SketchParams, z: float = 1.96) -> DataFrame:
    """Adds ``std_err, lo, hi``: plug-in variance with the clipped estimate as the count."""
    f = F.greatest(F.col("est"), F.lit(0.0))
    moment = est.agg(F.sum(F.pow(F.greatest(F.col("est"), F.lit(0.0)), 2)).alias("moment"))
    out = est.crossJoin(F.broadcast(moment))
    var = theory.variance(f, F.col("n"), F.col("moment"), sp)
    out = out.withColumn("std_err", F.sqrt(F.greatest(var, F.lit(0.0)))).drop("moment")
    return out.withColumn("lo", F.col("est") - z * F.col("std_err")).withColumn("hi", F.col("est") + z * F.col("std_err"))


def consistency(est: DataFrame, method: str = "clip") -> DataFrame:
    """Non-negative estimates: ``clip`` at zero, ``scale`` to sum n as well, or ``simplex``: the nearest point with sum n."""
    if method == "clip":
        return est.withColumn("est", F.greatest("est", F.lit(0.0)))
    if method == "scale":
        out = est.withColumn("est", F.greatest("est", F.lit(0.0)))
        return out.crossJoin(F.broadcast(out.agg(F.sum("est").alias("_total")))).withColumn("est", F.col("est") * F.col("n") / F.col("_total")).drop("_total")
    # the shift is the mean excess of what stays positive; each round is one aggregate over kept estimates and drops what falls below
    cut, left, kept = float("-inf"), None, est.select("est", "n").persist()
    while True:
        r = kept.filter(F.col("est") > cut).agg(F.sum("est").alias("t"), F.count("*").alias("c"), F.first("n").alias("n")).first()
        if not r["c"] or r["c"] == left:
            break
        cut, left = (r["t"] - r["n"]) / r["c"], r["c"]
    kept.unpersist()
    return est.withColumn("est", F.greatest(F.col("est") - F.lit(cut), F.lit(0.0)))
