"""What misbehaving parties can do, as frames to measure."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.theory import SketchParams
from .discover import digest
from .randomize import cell


def inject_reports(reports: DataFrame, item: str, count: int, sp: SketchParams) -> DataFrame:
    """Fabricated reports that always hold the item's cell, filled up with its neighbours."""
    spark = reports.sparkSession
    fake = spark.range(count).withColumn("j", (F.col("id") % sp.k + 1).cast("int")).withColumn("r", cell(sp, F.col("j"), F.lit(item)))
    x = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(sp.s - 1)), lambda i: ((F.col("r") - 1 + i) % sp.m + 1).cast("int")))
    return reports.select("j", "x").unionByName(fake.select("j", x.alias("x")))


def sybil(items: DataFrame, item: str, clients: int) -> DataFrame:
    """Honest reports of invented clients."""
    fake = items.sparkSession.range(clients).select((F.lit(-1) - F.col("id")).alias("report_id"), (F.lit(-1) - F.col("id")).alias("client_id"), F.lit(item).alias("item"), F.to_date(F.lit("2024-01-01")).alias("epoch"))
    return items.select("report_id", "client_id", "item", "epoch").unionByName(fake)


def drop_digest(counts: DataFrame, victims: DataFrame) -> DataFrame:
    """A helper that suppresses digests."""
    return counts.join(victims.select("digest"), "digest", "left_anti")


def dictionary_probe(counts: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Digests that a helper with a word list can name."""
    return counts.join(dictionary.select("item", digest("item").alias("digest")), "digest").select("item", "cnt")


def drop_reports(reports: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """A relay that loses a share of the reports."""
    from ..functions.prf import below

    return reports.filter(~below(seed, "lost", rate, "report_id"))
