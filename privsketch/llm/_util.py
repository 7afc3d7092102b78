"""Shared pieces of the training-data operators: scratch tables, worker slices, hash tables, word splitting.

Everything an operator keeps between jobs is a Parquet table under the folder that the cluster names in
``spark.checkpoint.dir``; nothing is written to a machine-local folder on a cluster.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import re
import tempfile
import time
import unicodedata
import uuid
import zipfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: White space of the token contracts: space and the control characters 9 to 13.
TOKEN = re.compile(r"[^\x20\x09-\x0D]+")
_SHIPPED: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder; a temporary one of our own only where the session names none (tests)."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        have = spark.sparkContext._jsc.sc().getCheckpointDir()
        at = have.get() if have.isDefined() else None
    if not at:
        at = os.path.join(tempfile.gettempdir(), "privsketch-checkpoints")
        spark.sparkContext.setCheckpointDir(at)
    return at.rstrip("/")


def keep(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage and survives the loss of executors."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/privsketch/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._kept_at = path
    return out


def drop(df: DataFrame) -> None:
    """Delete a table written by ``keep`` that no later result reads, and let Spark free shuffle files."""
    path = getattr(df, "_kept_at", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def free_shuffles(spark: SparkSession) -> None:
    """Shuffle files go when the driver collects the plans that made them; between heavy passes that should be now."""
    for _ in range(2):  # the first round lets go of what Python held, the second of what that held
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def ship(spark: SparkSession, batch_rows: int = 2000) -> SparkSession:
    """Make the package importable in Python workers and keep Arrow batches small enough for long texts."""
    sc = spark.sparkContext
    if _SHIPPED.get(sc.applicationId) is None:
        root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
        at = os.path.join(tempfile.mkdtemp(), "privsketch_src.zip")
        with zipfile.ZipFile(at, "w") as z:
            for d, _, names in os.walk(root):
                for n in names:
                    if n.endswith(".py"):
                        full = os.path.join(d, n)
                        z.write(full, os.path.relpath(full, os.path.dirname(root)))
        sc.addPyFile(at)
        _SHIPPED[sc.applicationId] = at
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > batch_rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(batch_rows))
    return spark


def width(spark: SparkSession) -> int:
    """Shuffle partitions of the session, the degree of parallelism that buckets are cut for."""
    return max(2, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def slices(batches: Iterable[pa.RecordBatch], column: str = "text", limit: int = 8 << 20) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Row slices of at most about ``limit`` characters (one row at least), with the texts (null: empty)."""
    frugal()
    gc.set_threshold(500_000, 20, 20)  # the word memories hold many small objects and no cycles
    for batch in batches:
        texts = ["" if t is None else t for t in batch.column(column).to_pylist()]
        at, size = 0, 0
        for i, t in enumerate(texts):
            if size and size + len(t) > limit:
                yield batch.slice(at, i - at), texts[at:i]
                at, size = i, 0
            size += len(t)
        if at < len(texts):
            yield batch.slice(at), texts[at:]
    trim()


def lower_ascii(text: str) -> str:
    """Lower-case A-Z only (bytes know no other letters)."""
    return text.lower() if text.isascii() else text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")


_ODD = re.compile("[\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")


def tokens(text: str) -> list[str]:
    """Maximal runs without space and the controls 9 to 13, in order."""
    return TOKEN.findall(text) if _ODD.search(text) else text.split()


class Settled:
    """Whether all characters of a text have had their class since Unicode 3.2; libraries' tables differ for younger ones."""

    def __init__(self):
        self.fine, self.young = set(map(chr, range(128))), set()

    def __call__(self, text: str) -> bool:
        if text.isascii():
            return True
        for c in set(text) - self.fine - self.young:
            (self.young if unicodedata.ucd_3_2_0.category(c) in ("Cn", "Cs", "Co") else self.fine).add(c)
        return not self.young or self.young.isdisjoint(text)


def _library():
    with contextlib.suppress(OSError):
        return ctypes.CDLL(None)


def frugal() -> None:
    """Large blocks of a worker go straight back to the system when freed (where the C library can), and one arena is used."""
    with contextlib.suppress(AttributeError):
        for option, value in ((-3, 1 << 20), (-1, 4 << 20), (-8, 1)):
            _library().mallopt(option, value)


def trim() -> None:
    """Give freed memory back at the end of a piece of work: workers wait for their next task holding little."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError):
        _library().malloc_trim(0)


_HELD: dict = {}


def only(key, make):
    """The one model this worker holds: asking for another drops it first, so stages that share a worker do not add up."""
    if key not in _HELD:
        _HELD.clear()
        gc.collect()
        trim()
        _HELD[key] = make()
    return _HELD[key]


class HashTable:
    """Open addressing over uint64 keys with numpy: ``get`` returns values (below 2**31), -1 where a key is absent."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        keys = keys.astype(np.uint64)
        bits = max(4, int(np.ceil(np.log2(max(1, len(keys)) * 1.6))))
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.used = np.zeros(1 << bits, bool)
        self.keys = np.zeros(1 << bits, np.uint64)
        self.values = np.full(1 << bits, -1, np.int32)
        slot, left = self._slot(keys), np.arange(len(keys))
        while len(left):
            free = left[~self.used[slot[left]]]
            s, first = np.unique(slot[free], return_index=True)
            won = free[first]
            self.used[s], self.keys[s], self.values[s] = True, keys[won], values[won]
            placed = np.zeros(len(keys), bool)
            placed[won] = True
            left = left[~placed[left]]
            slot[left] = (slot[left] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def get(self, keys: np.ndarray) -> np.ndarray:
        keys = keys.astype(np.uint64, copy=False)
        slot = self._slot(keys)
        out = np.where(self.keys[slot] == keys, self.values[slot], -1).astype(np.int64)
        left = np.flatnonzero((out < 0) & self.used[slot])
        while len(left):
            slot_left = (slot[left] + 1) & self.mask
            slot[left] = slot_left
            hit = (self.keys[slot_left] == keys[left]) & self.used[slot_left]
            out[left[hit]] = self.values[slot_left[hit]]
            left = left[~hit & self.used[slot_left]]
        return out


def min_labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest reachable index of each of ``n`` nodes under undirected edges ``a``-``b``."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while True:
            jump = label[label]
            if (jump == label).all():
                break
            label = jump
        if (before == label).all():
            break
    return label


class Recent:
    """Bounded memory of computed values: two generations of at most ``size`` entries each, so that frequent keys stay."""

    def __init__(self, size: int):
        self.size, self.now, self.before = size, {}, {}

    def missing(self, keys: set) -> list:
        """Keys without a value; values of the older generation move to the younger one."""
        if len(self.now) > self.size:
            self.before, self.now = self.now, {}
        new = keys - self.now.keys()
        if self.before and new:
            old = new & self.before.keys()
            self.now.update(zip(old, map(self.before.__getitem__, old), strict=True))
            new -= old
        return list(new)


def tabled(work, fields: str, sides: int = 1):
    """A grouped (or cogrouped) Arrow function from a generator ``work(key, batches...)`` of batches with ``fields``."""
    kinds = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_()}
    schema = pa.schema([(n, kinds[k]) for n, k in (f.split() for f in fields.split(", "))])

    def run(key, *tables):
        frugal()
        out = pa.Table.from_batches(list(work(key, *(t.to_batches() for t in tables))), schema)
        trim()
        return out

    if sides == 1:
        return lambda key, table: run(key, table)
    return lambda key, left, right: run(key, left, right)
