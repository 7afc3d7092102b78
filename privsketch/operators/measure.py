"""Accuracy and cost measures."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.theory import SketchParams


def errors(est: DataFrame, exact: DataFrame) -> DataFrame:
    """``item, f, est, err`` over the union of both; missing counts are zero."""
    joined = exact.select("item", "f").join(est.select("item", "est"), "item", "full")
    out = joined.select("item", F.coalesce("f", F.lit(0)).cast("long").alias("f"), F.coalesce("est", F.lit(0.0)).alias("est"))
    return out.withColumn("err", F.col("est") - F.col("f"))


def mse(runs: DataFrame) -> DataFrame:
    """Per item over ``run, item, f, est, err`` rows: runs, mean squared error, bias, relative root."""
    g = runs.groupBy("item").agg(F.count("*").alias("runs"), F.first("f").alias("f"), F.avg(F.pow("err", 2)).alias("mse"), F.avg("err").alias("bias"))
    return g.withColumn("rel_rmse", F.sqrt("mse") / F.col("f"))


def distance(err: DataFrame) -> DataFrame:
    """Largest, summed and Euclidean error, and divergence of clipped shares (items with a count)."""
    pos = F.greatest("est", F.lit(1e-9))
    total = err.agg(F.sum("f").alias("_n"), F.sum(pos).alias("_m"))
    e = err.crossJoin(F.broadcast(total))
    kl = F.sum(F.when(F.col("f") > 0, F.col("f") / F.col("_n") * F.log((F.col("f") / F.col("_n")) / (pos / F.col("_m")))))
    return e.agg(F.max(F.abs("err")).alias("max_err"), F.sum(F.abs("err")).alias("l1"), F.sqrt(F.sum(F.pow("err", 2))).alias("l2"), kl.alias("kl"))


def f_score(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision, recall and F-score of a set of items against the truth set."""
    both = found.select("item").distinct().withColumn("a", F.lit(1)).join(truth.select("item").distinct().withColumn("b", F.lit(1)), "item", "full")
    hit = F.sum(F.when(F.col("a").isNotNull() & F.col("b").isNotNull(), 1).otherwise(0))
    got = both.agg(hit.cast("long").alias("hits"), F.count("a").alias("found"), F.count("b").alias("truth"))
    zero = lambda a, b: F.when(b == 0, F.lit(0.0)).otherwise(a / b)
    got = got.withColumn("precision", zero(F.col("hits"), F.col("found"))).withColumn("recall", zero(F.col("hits"), F.col("truth")))
    return got.withColumn("f_score", zero(2 * F.col("hits"), F.col("found") + F.col("truth")))


def topk_quality(est: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """Precision among the k highest, and rank-weighted hits (the best true item weighs k)."""
    top = est.orderBy(F.desc("est"), "item").limit(k).select("item")
    true = exact.orderBy(F.desc("f"), "item").limit(k)
    ranked = true.withColumn("weight", F.lit(k + 1) - F.row_number().over(Window.orderBy(F.desc("f"), "item")))
    got = ranked.join(top.withColumn("hit", F.lit(1)), "item", "left")
    return got.agg((F.count("hit") / F.lit(k)).alias("precision"), (F.sum(F.when(F.col("hit") == 1, F.col("weight")).otherwise(0)) / F.sum("weight")).alias("ncr"))


def server_ops(reports: DataFrame) -> DataFrame:
    """Reports and matrix updates, measured on the reports."""
    return reports.agg(F.count("*").alias("reports"), F.sum(F.size("x")).cast("long").alias("updates"))


def subset_probabilities(sp: SketchParams) -> dict[tuple[int, ...], list[float]]:
    """Chance of every report subset for every own cell, by enumeration (m at most 6)."""
    if sp.m > 6:
        raise ValueError("enumeration is for m <= 6")
    m, s, p = sp.m, sp.s, sp.p
    with_own, without = 1 / math.comb(m - 1, s - 1), 1 / math.comb(m - 1, s)
    return {x: [p * with_own if r in x else (1 - p) * without for r in range(1, m + 1)] for x in itertools.combinations(range(1, m + 1), s)}


def empirical_eps(sp: SketchParams) -> float:
    """Largest log ratio of report probabilities between two cells."""
    return max(math.log(max(ps) / min(ps)) for ps in subset_probabilities(sp).values())
