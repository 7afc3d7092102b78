"""Discovery of unknown strings: the blind histogram over digests, and its central yardstick.

The helper sees digests and ciphertexts, counts, adds Laplace noise, and releases ciphertexts of counts over the threshold; the
server opens them. The helper keeps one candidate ciphertext a digest, never a list. Noise is drawn once per release and digest.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.prf import SPAN, laplace, prf
from .seal import key


def digest(item: Column | str) -> Column:
    return F.unhex(F.sha2(item if isinstance(item, Column) else F.col(item), 256))


def client(df: DataFrame, server_secret: str, helper_secret: str, keep: tuple[str, ...] = ("report_id",)) -> DataFrame:
    """The ``keep`` columns and ``outer``: the item sealed for the server, with its digest, sealed for the helper."""
    inner = F.aes_encrypt(F.col("item").cast("binary"), key(server_secret), F.lit("GCM"))
    body = F.concat(digest("item"), inner)  # 32 bytes of digest, then the ciphertext
    return df.select(*keep, F.aes_encrypt(body, key(helper_secret), F.lit("GCM")).alias("outer"))


def open_outer(df: DataFrame, helper_secret: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """The ``keep`` columns, ``digest`` and ``inner``, which only the server can open."""
    body = F.aes_decrypt(F.col("outer"), key(helper_secret), F.lit("GCM"))
    return df.select(*keep, F.substring(body, 1, 32).alias("digest"), F.substring(body, 33, 1 << 30).alias("inner"))


def noisy(counts: DataFrame, scale: float | Column, seed: int | str | Column, release: int = 0, noise: str = "laplace") -> DataFrame:
    """Adds ``noisy``: the count plus noise keyed by release and digest (scale and seed may be Columns for a grid of releases). ``discrete``: two-sided geometric noise on integers."""
    u = (prf(seed, "lap", F.lit(str(release)), F.lower(F.hex("digest"))).cast("double") + 0.5) / F.lit(float(SPAN))
    if noise == "laplace":
        return counts.withColumn("noisy", F.col("cnt") + laplace(u, scale))
    a = math.exp(-1 / scale)
    v = (prf(seed, "geo", F.lit(str(release)), F.lower(F.hex("digest"))).cast("double") + 0.5) / F.lit(float(SPAN))
    draw = lambda w: F.floor(F.log(w) / F.lit(math.log(a)))
    return counts.withColumn("noisy", (F.col("cnt") + draw(u) - draw(v)).cast("double"))


def helper(df: DataFrame, helper_secret: str, threshold: float, scale: float, seed: int | str, release: int = 0, noise: str = "laplace") -> DataFrame:
    """Release ``digest, inner, noisy`` of one collection; ``seed`` is the helper's secret noise key."""
    opened = open_outer(df, helper_secret)
    pick = F.xxhash64("inner", F.lit(str(seed)))  # ciphertexts are fresh, so the least hash is a uniform pick
    counts = opened.groupBy("digest").agg(F.count("*").alias("cnt"), F.min_by("inner", pick).alias("inner"))
    return noisy(counts, scale, seed, release, noise).filter(F.col("noisy") >= threshold).drop("cnt")


def open_items(released: DataFrame, server_secret: str, keep: tuple[str, ...] = ()) -> DataFrame:
    return released.select(*keep, F.aes_decrypt("inner", key(server_secret), F.lit("GCM")).cast("string").alias("item"), "noisy")


def blind_histogram(items: DataFrame, threshold: float, scale: float, seed: int | str, secrets: tuple[str, str] = ("server", "helper"), release: int = 0) -> DataFrame:
    """Client, helper and server in one call: ``item, noisy``."""
    return open_items(helper(client(items, *secrets), secrets[1], threshold, scale, seed, release), secrets[0])


def central_histogram(items: DataFrame, threshold: float, scale: float, seed: int | str, release: int = 0) -> DataFrame:
    """The same release by a trusted curator on raw strings; under one seed it releases the same items."""
    counts = items.groupBy("item").agg(F.count("*").alias("cnt")).withColumn("digest", digest("item"))
    return noisy(counts, scale, seed, release).filter(F.col("noisy") >= threshold).select("item", "noisy")


def keep_probability(count: Column, threshold: Column, scale: Column) -> Column:
    """Chance that a count passes the noisy threshold."""
    gap = (threshold - count) / scale
    return F.when(gap > 0, 0.5 * F.exp(-gap)).otherwise(1 - 0.5 * F.exp(gap))


def expected_yield(counts: DataFrame, grid: DataFrame) -> DataFrame:
    """Expected number of released items for every ``threshold, scale`` of a small grid over exact counts ``f``. Counts are grouped
    by value first, so the grid meets distinct counts and not items."""
    by_value = counts.groupBy("f").agg(F.count("*").alias("items"))
    each = by_value.crossJoin(F.broadcast(grid))
    return each.groupBy(*grid.columns).agg(F.sum(F.col("items") * keep_probability(F.col("f"), F.col("threshold"), F.col("scale"))).alias("expected"))
