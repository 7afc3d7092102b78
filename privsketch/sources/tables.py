"""Parquet tables with the types the engine wants: NTZ timestamps become ``timestamp`` (watermarks need it)."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if columns:
        df = df.select(*columns)
    return df.select(*(F.col(f.name).cast("timestamp").alias(f.name) if isinstance(f.dataType, T.TimestampNTZType) else F.col(f.name) for f in df.schema))


def scratch(spark: SparkSession, name: str) -> str:
    """A folder under the session's shared checkpoint folder, or a temporary one where none is set."""
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.gettempdir()
    return f"{base.rstrip('/')}/privsketch/{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write as ``csv``, ``json`` or ``orc`` and read back under the same schema."""
    writer = df.write.mode("overwrite")
    if kind == "csv":
        writer.option("header", True).option("nullValue", "\\N").option("emptyValue", "").csv(path)
        return df.sparkSession.read.option("header", True).option("nullValue", "\\N").option("emptyValue", "").schema(df.schema).csv(path)
    writer.format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).load(path)


def write_sketch(matrix: DataFrame, path: str) -> str:
    """Server storage of sketch matrices: one partition folder an epoch, cells clustered by row."""
    matrix.repartition("epoch").sortWithinPartitions("j", "x").write.mode("overwrite").partitionBy("epoch").parquet(path)
    return path


def register_views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
