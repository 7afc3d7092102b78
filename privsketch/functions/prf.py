"""Pseudo-random values as Columns: 52-bit integers from a keyed digest, the same in every engine and on every retry.

``replay`` digests with a public seed (tests and cross-engine checks); ``keyed`` uses SHA-256, with the clients' secret for coins and
the public seed for cells (``SketchParams.coins``), and is what parameters take unless told otherwise. Both give a retried task the
same draw, so no datum is randomised twice. ``fast`` is a 64-bit hash for speed studies.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52
SPAN = 1 << BITS


def prf(seed: int | str | Column, tag: str, *parts: Column | str | int, mode: str = "replay") -> Column:
    """Uniform integer in [0, 2^52). A Column as seed gives every row its own."""
    cols = [F.lit(str(p)) if isinstance(p, int) else (F.col(p) if isinstance(p, str) else p).cast("string") for p in parts]
    text = F.concat_ws("|", seed.cast("string") if isinstance(seed, Column) else F.lit(str(seed)), F.lit(tag), *cols)
    if mode == "fast":
        return F.shiftrightunsigned(F.xxhash64(text), 64 - BITS)
    digest = F.md5(text) if mode == "replay" else F.sha2(text, 256)
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long")


def unit(seed: int | str, tag: str, *parts: Column | str | int, mode: str = "replay") -> Column:
    """Uniform double in [0, 1)."""
    return prf(seed, tag, *parts, mode=mode) / F.lit(float(SPAN))


def below(seed: int | str, tag: str, probability: float, *parts: Column | str | int, mode: str = "replay") -> Column:
    """True with the given probability; decided on integers, so engines cannot differ by rounding."""
    return prf(seed, tag, *parts, mode=mode) < F.lit(int(probability * SPAN))


def prf_int(seed: int | str, tag: str, *parts: object) -> int:
    """The replay value for plain Python arguments."""
    return int(hashlib.md5("|".join([str(seed), tag, *map(str, parts)]).encode()).hexdigest()[:13], 16)


def laplace(u: Column, scale: float | Column) -> Column:
    """Laplace noise by inversion of a unit uniform."""
    v = u - F.lit(0.5)
    return -(scale if isinstance(scale, Column) else F.lit(float(scale))) * F.signum(v) * F.log(F.greatest(F.lit(1e-15), F.lit(1.0) - F.lit(2.0) * F.abs(v)))
