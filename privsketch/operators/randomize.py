"""Client side of the subset sketch: hash encoding, probabilistic inclusion and extension.

The Column forms stay in the JVM and are reproducible in SQL; ``subset_reports(engine="arrow")`` is the production path: NumPy over
Arrow batches. Cells come from the public hash family (``seed``). Coins (the row, the inclusion, the extension) come from the clients'
secret by SHA-2 of the report's id, unless the parameters ask for a public form, so the server, which knows the family and may
know ids, cannot replay them; and a retry gives the same report.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.prf import below, prf
from ..functions.theory import SketchParams
from ..sources.workers import ship


def cell(sp: SketchParams, j: Column, item: Column, mode: str | None = None) -> Column:
    """Hash function ``j`` on the item: a cell in 1..m. Public in every mode."""
    return (prf(sp.seed, "cell", j, item, mode=mode or sp.mode) % sp.m + 1).cast("int")


def encode(df: DataFrame, sp: SketchParams, mode: str | None = None, hash: str = "universal") -> DataFrame:
    """Adds ``j`` (uniform row) and ``r`` (own cell). ``identity``: the item is already a code in 1..m and there is one row."""
    if hash == "identity":
        return df.withColumn("j", F.lit(1)).withColumn("r", F.col("item").cast("int"))
    mode = mode or sp.mode
    df = df.withColumn("j", (prf(sp.coins(mode), "row", "report_id", mode=mode) % sp.k + 1).cast("int"))
    return df.withColumn("r", cell(sp, F.col("j"), F.col("item"), mode))


def include(df: DataFrame, sp: SketchParams, mode: str | None = None) -> DataFrame:
    """Adds ``own``: whether the own cell is reported."""
    mode = mode or sp.mode
    return df.withColumn("own", below(sp.coins(mode), "inc", sp.p, "report_id", mode=mode))


def extend(df: DataFrame, sp: SketchParams, sampler: str = "floyd", mode: str | None = None) -> DataFrame:
    """Adds ``x``, the sorted reported cells: the own one if included and others drawn without replacement."""
    m, mode = sp.m, mode or sp.mode
    coins = sp.coins(mode)
    t = F.when(F.col("own"), F.lit(sp.s - 1)).otherwise(F.lit(sp.s))
    if sampler == "permute":
        keyed = F.transform(F.sequence(F.lit(1), F.lit(m - 1)), lambda i: F.struct(prf(coins, "perm", F.col("report_id"), i, mode=mode).alias("h"), i.alias("i")))
        ranks = F.slice(F.transform(F.array_sort(keyed), lambda e: e["i"]), F.lit(1), t)
    else:
        # one draw per step, joined to the set; a value already there is replaced by the step's own number
        draws = F.transform(F.sequence(F.lit(m - sp.s), F.lit(m - 1)), lambda i: F.struct(i.cast("int").alias("i"), (prf(coins, "ext", F.col("report_id"), i, mode=mode) % i + 1).cast("int").alias("v")))
        used = F.filter(draws, lambda e: e["i"] >= F.lit(m) - t)
        ranks = F.aggregate(used, F.array().cast("array<int>"), lambda acc, e: F.array_append(acc, F.when(F.array_contains(acc, e["v"]), e["i"]).otherwise(e["v"])))
    others = F.transform(ranks, lambda v: F.when(v >= F.col("r"), v + 1).otherwise(v).cast("int"))
    return df.withColumn("x", F.array_sort(F.when(F.col("own"), F.array_append(others, F.col("r"))).otherwise(others)))


def subset_reports(df: DataFrame, sp: SketchParams, mode: str | None = None, engine: str = "sql", hash: str = "universal", sampler: str = "floyd", keep: list[str] | None = None) -> DataFrame:
    """Reports ``j, x`` (and kept columns) of an item frame."""
    keep = keep or []
    if engine == "arrow":
        return _arrow_reports(df, sp, keep, mode or sp.mode)
    out = extend(include(encode(df, sp, mode, hash), sp, mode), sp, sampler, mode)
    return out.select(*keep, "j", "x")


def _mix(a: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: counters to uniform words."""
    a = (a ^ (a >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    a = (a ^ (a >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return a ^ (a >> np.uint64(31))


def draw_subsets(own: np.ndarray, kept: np.ndarray, word: Callable[[int], np.ndarray], m: int, s: int) -> np.ndarray:
    """``s`` distinct cells per row (1..m): Floyd's sampling over the whole batch, one column a step; ``word(c)`` gives every row's
    64 random bits of a step."""
    n = len(own)
    out = np.zeros((n, s), np.int32)
    steps = np.where(kept, s - 1, s)
    for c in range(s):
        i = m - steps + c  # rows with s - 1 steps stop one column early
        live = c < steps
        v = (word(c) % np.maximum(i, 1).astype(np.uint64)).astype(np.int64) + 1
        seen = (out[:, :c] == v[:, None]).any(1) if c else np.zeros(n, bool)
        out[:, c] = np.where(live, np.where(seen, i, v), 0)
    out = np.where(out >= own[:, None], out + 1, out)
    last = np.flatnonzero(kept)
    out[last, s - 1] = own[last]
    return out


def coin_words(sp: SketchParams, count: int, mode: str) -> Column:
    """Random bits of a report as bytes, eight a word: SHA-512 blocks under the clients' secret, or one public 64-bit hash that the worker
    stretches."""
    if mode != "keyed":
        return F.unhex(F.lpad(F.hex(F.xxhash64("report_id", F.lit(sp.seed))), 16, "0"))
    text = lambda b: F.concat_ws("|", F.lit(sp.secret), F.lit("coins"), F.col("report_id").cast("string"), F.lit(str(b)))
    return F.concat(*(F.unhex(F.sha2(text(b), 512)) for b in range(-(-count // 8))))


def stretched(column: pa.Array, seed: int, mode: str) -> Callable[[int], np.ndarray]:
    """Word ``c`` of every row of ``coin_words``."""
    table = np.frombuffer(b"".join(column.to_pylist()), ">u8").astype(np.uint64).reshape(len(column), -1)
    if mode == "keyed":
        return lambda c: table[:, c]
    keys = _mix(table[:, 0] ^ np.uint64(seed))
    return lambda c: _mix(keys + np.uint64(c + 1))


def _arrow_reports(df: DataFrame, sp: SketchParams, keep: list[str], mode: str) -> DataFrame:
    ship(df.sparkSession)
    rows, work = subset_worker(df, sp, keep, mode)
    fields = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return rows.mapInArrow(work, f"{fields}j int, x array<int>")


def subset_worker(df: DataFrame, sp: SketchParams, keep: list[str], mode: str) -> tuple[DataFrame, Callable]:
    """What the clients' tasks read, and the work that turns its batches into reports."""
    k, m, s, seed = sp.k, sp.m, sp.s, sp.seed
    bound = np.uint64(min(2**64 - 1, int(sp.p * 2**64)))
    family = sp.public()
    rows = df.select(*keep, coin_words(sp, s + 2, mode).alias("_coins"), F.xxhash64("item").alias("_item"))

    def work(batches):
        for b in batches:
            if not b.num_rows:
                continue
            word = stretched(b.column("_coins"), seed, mode)
            j = (word(0) % np.uint64(k)).astype(np.int32) + 1
            own = arrow_cell(family, j, b.column("_item").to_numpy(zero_copy_only=False).view(np.uint64))
            x = np.sort(draw_subsets(own, word(1) < bound, lambda c: word(c + 2), m, s), axis=1)
            cells = pa.ListArray.from_arrays(pa.array(np.arange(0, len(x) * s + 1, s, dtype=np.int32)), pa.array(x.ravel(), pa.int32()))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), pa.array(j), cells], names=[*keep, "j", "x"])

    return rows, work


def arrow_cell(sp: SketchParams, j: np.ndarray, item_hash: np.ndarray) -> np.ndarray:
    """Cells of the arrow engine's hash family (public), in 1..m."""
    return (_mix(item_hash ^ _mix(np.uint64(sp.seed) + j.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))) % np.uint64(sp.m)).astype(np.int64) + 1


def arrow_probes(items: DataFrame, sp: SketchParams, most: int = 200_000) -> DataFrame:
    """``item, j, x``: every distinct item's cell in every row of the arrow engine's family, a bounded number of rows at a time."""
    ship(items.sparkSession)
    family, step = sp.public(), max(1, most // sp.k)

    def work(batches):
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                j = np.tile(np.arange(1, family.k + 1, dtype=np.int32), part.num_rows)
                which = np.repeat(np.arange(part.num_rows), family.k)
                x = arrow_cell(family, j, part.column("_item").to_numpy(zero_copy_only=False).view(np.uint64)[which])
                yield pa.RecordBatch.from_arrays([part.column("item").take(pa.array(which)), pa.array(j), pa.array(x.astype(np.int32))], names=["item", "j", "x"])

    return items.select("item").distinct().select("item", F.xxhash64("item").alias("_item")).mapInArrow(work, "item string, j int, x int")
