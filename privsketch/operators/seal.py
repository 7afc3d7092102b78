"""Sealing of messages: authenticated encryption of a row's columns. A simulation of public-key sealing with one symmetric key a
role; who holds which key decides which columns a role can read."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def key(secret: str) -> Column:
    """256-bit key of a role's secret."""
    return F.unhex(F.sha2(F.lit(secret), 256))


def seal(df: DataFrame, secret: str, columns: list[str], name: str = "sealed") -> DataFrame:
    """Replace ``columns`` by one sealed binary; a fresh nonce every time."""
    body = F.to_json(F.struct(*columns)).cast("binary")
    return df.withColumn(name, F.aes_encrypt(body, key(secret), F.lit("GCM"))).drop(*columns)


def unseal(df: DataFrame, secret: str, schema: str, name: str = "sealed") -> DataFrame:
    """Open ``name`` and expand its fields; a wrong key gives nulls."""
    opened = F.from_json(F.try_aes_decrypt(F.col(name), key(secret), F.lit("GCM")).cast("string"), schema)
    return df.withColumn("_open", opened).drop(name).select("*", "_open.*").drop("_open")
