"""The relay between clients and server: strip identity, permute in batches, cap a client's reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.prf import prf

IDENTITY = ("report_id", "client_id", "ts", "epoch", "address")


def strip(df: DataFrame, also: tuple[str, ...] = ()) -> DataFrame:
    """Without transport fields and identities."""
    return df.drop(*(c for c in (*IDENTITY, *also) if c in df.columns))


def permute(df: DataFrame, seed: int | None = None, batches: int = 8, key: list[str] | None = None) -> DataFrame:
    """Random order inside ``batches`` batches. With a seed the order is a function of the ``key`` columns (tests); without, of
    fresh randomness. Counts do not need it; exported reports do."""
    order = F.rand() if seed is None else prf(seed, "shuffle", *(key or df.columns)) / F.lit(float(1 << 52))
    return df.withColumn("_order", order).withColumn("batch", F.floor(F.col("_order") * batches).cast("int")).repartition(batches, "batch").sortWithinPartitions("batch", "_order").drop("_order")


def cap(df: DataFrame, limit: int, seed: int = 42, by: tuple[str, ...] = ("client_id",)) -> DataFrame:
    """At most ``limit`` reports a client (and epoch, if named), chosen by a random key. The rank filter prunes inside tasks
    before the exchange, so a heavy client costs ``limit`` rows a task."""
    order = Window.partitionBy(*by).orderBy(prf(seed, "cap", "report_id"), "report_id")
    return df.withColumn("_rank", F.row_number().over(order)).filter(F.col("_rank") <= limit).drop("_rank")


def collect(reports: DataFrame, limit: int | None = None, materialise_shuffle: bool = True, seed: int | None = None, batches: int = 8) -> DataFrame:
    """The whole relay; ``materialise_shuffle=False`` when the next step only counts."""
    out = cap(reports, limit) if limit else reports
    out = strip(out)
    return permute(out, seed, batches).drop("batch") if materialise_shuffle else out
