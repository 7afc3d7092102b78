"""Server side: the count matrix in long form ``(j, x, cnt)``, its merges and other layouts."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.workers import ship


def build(reports: DataFrame, by: list[str] | None = None) -> DataFrame:
    """One exchange on the cell; map-side counts keep it at one row a cell and task."""
    by = by or []
    return reports.select(*by, "j", F.explode("x").alias("x")).groupBy(*by, "j", "x").agg(F.count("*").alias("cnt"))


def build_dense(reports: DataFrame, k: int, m: int) -> DataFrame:
    """Counts by NumPy inside every task, for matrices that fit a worker; then the same final sum."""
    return collect_dense(reports.select("j", "x"), None, k, m)


def collect_dense(rows: DataFrame, client: Callable | None, k: int, m: int) -> DataFrame:
    """The same with the clients' work (``rows`` to reports) in the same task, so that reports cross no process."""
    ship(rows.sparkSession)

    def work(batches):
        total = np.zeros((k + 1) * (m + 1), np.int64)
        for b in client(batches) if client else batches:
            x = b.column("x")
            j = np.repeat(b.column("j").to_numpy(zero_copy_only=False), np.diff(x.offsets.to_numpy()))
            total += np.bincount(j.astype(np.int64) * (m + 1) + x.flatten().to_numpy(zero_copy_only=False), minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array((at // (m + 1)).astype(np.int32)), pa.array((at % (m + 1)).astype(np.int32)), pa.array(total[at])], names=["j", "x", "cnt"])

    return rows.mapInArrow(work, "j int, x int, cnt long").groupBy("j", "x").agg(F.sum("cnt").alias("cnt"))


def merge(*matrices: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, matrices).groupBy("j", "x").agg(F.sum("cnt").alias("cnt"))


def subtract(whole: DataFrame, part: DataFrame) -> DataFrame:
    """Counts without those of a part, for epochs that leave a window."""
    return merge(whole, part.withColumn("cnt", -F.col("cnt"))).filter("cnt <> 0")


def rollup(matrix: DataFrame, by: list[str]) -> DataFrame:
    return matrix.groupBy(*by, "j", "x").agg(F.sum("cnt").alias("cnt"))


def to_rows(matrix: DataFrame, m: int) -> DataFrame:
    """Row form ``j, cells array<long>`` with zeros filled in."""
    packed = matrix.groupBy("j").agg(F.map_from_entries(F.collect_list(F.struct("x", "cnt"))).alias("sparse"))
    return packed.select("j", F.transform(F.sequence(F.lit(1), F.lit(m)), lambda i: F.coalesce(F.element_at("sparse", i), F.lit(0).cast("long"))).alias("cells"))


def to_maps(matrix: DataFrame) -> DataFrame:
    """Sparse row form ``j, cells map<int,long>``."""
    return matrix.groupBy("j").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("x", "cnt")))).alias("cells"))


def merge_maps(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.select("j", F.col("cells").alias("a")).join(b.select("j", F.col("cells").alias("b")), "j", "full")
    empty = F.create_map().cast("map<int,bigint>")
    zero = F.lit(0).cast("long")
    return both.select("j", F.map_zip_with(F.coalesce("a", empty), F.coalesce("b", empty), lambda k, x, y: F.coalesce(x, zero) + F.coalesce(y, zero)).alias("cells"))
