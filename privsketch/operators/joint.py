"""Discovery and estimation together, over epochs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tune
from ..functions.theory import SketchParams
from . import discover, estimate, randomize, sketch


def discover_then_estimate(items: DataFrame, sp: SketchParams, threshold: float, scale: float, seed: int | str = 42) -> DataFrame:
    """Names from the blind histogram, counts of those names from the sketch of the same reports."""
    names = discover.blind_histogram(items, threshold, scale, seed).select("item")
    return estimate.frequencies(names, sketch.build(randomize.subset_reports(items, sp)), sp)


def adaptive_rounds(items: DataFrame, target: str, eps: float, k: int, m: int, rounds: int, seed: int = 42, mode: str = "keyed") -> list[dict]:
    """Retune for the target's share after each epoch: one action an epoch, the schedule as rows for ``params_frame``."""
    epochs = [r[0] for r in items.select("epoch").distinct().orderBy("epoch").limit(rounds).collect()]
    lam, out = 0.1, []
    for i, epoch in enumerate(epochs):
        t = tune.tune(eps, lam, k, m)
        sp = SketchParams(k, m, t.s, t.p, seed, mode)
        part = items.filter(F.col("epoch") == F.lit(epoch))
        name = items.sparkSession.createDataFrame([(target,)], "item string")
        row = estimate.frequencies(name, sketch.build(randomize.subset_reports(part, sp)), sp).first()
        out.append({"ver": i, "epoch": epoch, "lam": lam, "p": t.p, "s": t.s, "eps": t.eps_real, "n": row["n"], "est": row["est"]})
        lam = min(1.0, max(0.001, row["est"] / max(1, row["n"])))
    return out


def asof_params(reports: DataFrame, schedule: DataFrame, most: int = 10_000, most_days: int = 100_000) -> DataFrame:
    """Parameter version in force at each report's ``ts``: last schedule row at or before it (ties: the highest version), null before the
    first; schedule rows with nulls do not count. A schedule of at most ``most`` rows over ``most_days`` days is broadcast as a calendar,
    a row a day with the changes of that day and the version it starts from: reports are not moved and meet their day by equality.
    A larger one goes through ``asof_sorted``."""
    schedule = schedule.filter("valid_from is not null and ver is not null").select("valid_from", "ver")
    day = F.to_date("valid_from")
    rows, first, last = schedule.agg(F.count("*"), F.min(day), F.max(day)).first()
    if not rows:
        return reports.withColumn("ver", F.lit(None).cast(schedule.schema["ver"].dataType))
    if rows > most or (last - first).days >= most_days:
        return asof_sorted(reports, schedule)
    days = reports.sparkSession.range(1).select(F.explode(F.sequence(F.lit(first), F.lit(last))).alias("_day"))
    change = F.struct("valid_from", "ver")
    changes = schedule.groupBy(day.alias("_day")).agg(F.collect_list(change).alias("_changes"), F.max(change)["ver"].alias("_end"))
    before = Window.orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)  # at most ``most_days`` rows
    calendar = days.join(changes, "_day", "left").withColumn("_start", F.last("_end", ignorenulls=True).over(before)).drop("_end")
    at = reports.withColumn("_day", F.least(F.to_date("ts"), F.when(F.col("ts").isNotNull(), F.lit(last))))  # later reports share the last day
    inside = F.array_max(F.filter("_changes", lambda c: c["valid_from"] <= F.col("ts")))["ver"]
    return at.join(F.broadcast(calendar), "_day", "left").withColumn("ver", F.coalesce(inside, "_start")).drop("_day", "_changes", "_start")


def asof_sorted(reports: DataFrame, schedule: DataFrame) -> DataFrame:
    """The same for a long schedule: both sides in one stream an hour, sorted by time; every hour starts from the version that
    the hours before it left."""
    hour = lambda c: F.date_trunc("hour", c)
    left = reports.select(F.struct(*reports.columns).alias("row"), F.col("ts").alias("_at"), F.lit(None).cast("int").alias("ver"), F.lit(1).alias("_kind"))
    empty = F.lit(None).cast(left.schema["row"].dataType).alias("row")
    right = schedule.select(empty, F.col("valid_from").alias("_at"), F.col("ver").cast("int").alias("ver"), F.lit(0).alias("_kind"))
    hours = reports.select(hour("ts").alias("_hour")).union(schedule.select(hour("valid_from"))).distinct()
    last = schedule.groupBy(hour("valid_from").alias("_hour")).agg(F.max(F.struct("valid_from", "ver"))["ver"].alias("ver"))
    before = Window.orderBy("_hour").rowsBetween(Window.unboundedPreceding, -1)  # one row an hour
    starts = hours.join(last, "_hour", "left").withColumn("ver", F.last("ver", ignorenulls=True).over(before))
    seeds = starts.select(empty, F.col("_hour").alias("_at"), F.col("ver").cast("int").alias("ver"), F.lit(-1).alias("_kind"))
    order = Window.partitionBy(hour("_at")).orderBy("_at", "_kind", "ver").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return left.unionByName(right).unionByName(seeds).withColumn("ver", F.last("ver", ignorenulls=True).over(order)).filter("_kind = 1").select("row.*", "ver")


def topk_tracker(estimates: DataFrame, k: int) -> DataFrame:
    """The ``k`` highest items of every epoch with their rank."""
    order = Window.partitionBy("epoch").orderBy(F.desc("est"), "item")
    return estimates.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def merge_topk(old: DataFrame, new: DataFrame) -> DataFrame:
    """Upsert of a maintained list: new estimates win, absent items stay with theirs."""
    j = old.select("item", F.col("est").alias("old")).join(new.select("item", F.col("est").alias("new")), "item", "full")
    return j.select("item", F.coalesce("new", "old").alias("est"), F.when(F.col("old").isNull(), "added").when(F.col("new").isNull(), "kept").otherwise("updated").alias("change"))


def combine_versions(parts: DataFrame) -> DataFrame:
    """Reports of different parameters cannot share a matrix; their estimates and variances add over disjoint reports."""
    return parts.groupBy("item").agg(F.sum("est").alias("est"), F.sqrt(F.sum(F.pow("std_err", 2))).alias("std_err"))
