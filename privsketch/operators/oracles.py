"""Baseline frequency oracles. Each returns ``item, support, n, est`` over a given domain and states its exact epsilon.

Bits of unary reports are independent, so a report's one-bits come from a filter over the domain codes, without running state.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import theory, tune
from ..functions.prf import below, prf, prf_int
from ..sources.workers import ship
from .estimate import support
from .randomize import arrow_cell


#: Largest domain for protocols whose reports are scanned once an item.
LARGEST_DOMAIN = 20_000


def codes_of(domain: DataFrame, largest: int = LARGEST_DOMAIN) -> DataFrame:
    """Items with their code 1..D, by name. These protocols cost a domain's worth of work a report, so its size is checked."""
    names = domain.select("item").distinct()
    if names.limit(largest + 1).count() > largest:
        raise ValueError(f"the domain has more than {largest} items; use the subset sketch")
    return names.withColumn("code", F.row_number().over(Window.orderBy("item")))


def pure_estimate(support: DataFrame, n: int | Column, p: float, q: float) -> DataFrame:
    """Unbiased counts of a pure protocol from ``item, support``."""
    return support.withColumn("n", n if isinstance(n, Column) else F.lit(n).cast("long")).withColumn("est", (F.col("support") - F.col("n") * F.lit(q)) / F.lit(p - q))


def unary(items: DataFrame, domain: DataFrame, p: float, q: float, tag: str, seed: int = 42) -> DataFrame:
    """One-hot report whose own bit stays with ``p`` and whose others rise with ``q``."""
    codes = codes_of(domain)
    width = codes.count()
    rows = items.join(F.broadcast(codes), "item")
    bits = F.filter(F.sequence(F.lit(1), F.lit(width)), lambda i: F.when(i == F.col("code"), below(seed, tag, p, F.col("report_id"), i)).otherwise(below(seed, tag, q, F.col("report_id"), i)))
    counts = rows.select(F.explode(bits).alias("code")).groupBy("code").agg(F.count("*").alias("support"))
    n = rows.agg(F.count("*").alias("n"))
    out = codes.join(counts, "code", "left").select("item", F.coalesce("support", F.lit(0)).cast("long").alias("support"))
    return pure_estimate(out.crossJoin(F.broadcast(n)), F.col("n"), p, q)


def sue_pq(eps: float) -> tuple[float, float]:
    return theory.split_budget(eps, eps / 2)


def oue_pq(eps: float) -> tuple[float, float]:
    return theory.split_budget(eps, 0.0)


def tuned_unary_pq(eps: float, lam: float) -> tuple[float, float]:
    """The tuned objective at k = 1: p for the target share, q from the whole budget."""
    p = tune.best_p(eps, lam, 1)
    return p, p / (p + (1 - p) * math.exp(eps))


def sue(items, domain, eps, seed=42):
    return unary(items, domain, *sue_pq(eps), "sue", seed)


def oue(items, domain, eps, seed=42):
    return unary(items, domain, *oue_pq(eps), "oue", seed)


def tuned_unary(items, domain, eps, lam, seed=42):
    return unary(items, domain, *tuned_unary_pq(eps, lam), "tun", seed)


def direct_pq(eps: float, width: int) -> tuple[float, float]:
    p = math.exp(eps) / (math.exp(eps) + width - 1)
    return p, (1 - p) / (width - 1)


def direct(items: DataFrame, domain: DataFrame, eps: float, seed: int = 42) -> DataFrame:
    """Randomised response over the codes: the own one with p, else one of the others."""
    codes = codes_of(domain)
    width = codes.count()
    p, q = direct_pq(eps, width)
    rows = items.join(F.broadcast(codes), "item")
    other = prf(seed, "oth", "report_id") % (width - 1) + 1
    said = F.when(below(seed, "dir", p, "report_id"), F.col("code")).otherwise(F.when(other >= F.col("code"), other + 1).otherwise(other))
    counts = rows.select(said.cast("int").alias("code")).groupBy("code").agg(F.count("*").alias("support"))
    out = codes.join(counts, "code", "left").select("item", F.coalesce("support", F.lit(0)).cast("long").alias("support"))
    return pure_estimate(out.crossJoin(F.broadcast(rows.agg(F.count("*").alias("n")))), F.col("n"), p, q)


def local_hash_pq(eps: float, g: int) -> tuple[float, float]:
    return math.exp(eps) / (math.exp(eps) + g - 1), 1 / g


def local_hash(items: DataFrame, domain: DataFrame, eps: float, g: int | None = None, seed: int = 42) -> DataFrame:
    """Every report hashes the domain to ``g`` values and answers directly there (default: the optimal g)."""
    g = g or math.ceil(math.exp(eps)) + 1
    p, q = local_hash_pq(eps, g)
    own = prf(seed, "lh", "report_id", "item") % g
    other = prf(seed, "lho", "report_id") % (g - 1)
    said = F.when(below(seed, "lhp", p, "report_id"), F.col("own")).otherwise(F.when(other >= F.col("own"), other + 1).otherwise(other))
    rows = items.withColumn("own", own).withColumn("said", said).select("report_id", "said")
    names = codes_of(domain).select("item")
    hits = rows.join(F.broadcast(names)).filter(F.col("said") == prf(seed, "lh", "report_id", "item") % g)
    out = names.join(hits.groupBy("item").agg(F.count("*").alias("support")), "item", "left").select("item", F.coalesce("support", F.lit(0)).cast("long").alias("support"))
    return pure_estimate(out.crossJoin(F.broadcast(items.agg(F.count("*").alias("n")))), F.col("n"), p, q)


def threshold_pq(eps: float, theta: float) -> tuple[float, float]:
    return 1 - 0.5 * math.exp(eps * (theta - 1) / 2), 0.5 * math.exp(-eps * theta / 2)


def best_theta(eps: float) -> float:
    """Threshold in [1/2, 1] with the least noise variance, on a grid of a thousand."""
    def cost(t):
        p, q = threshold_pq(eps, t)
        return q * (1 - q) / (p - q) ** 2

    return min((0.5 + i / 2000 for i in range(1001)), key=cost)


def threshold_hist(items: DataFrame, domain: DataFrame, eps: float, theta: float | None = None, seed: int = 42) -> DataFrame:
    """Laplace noise on every position of the one-hot vector, each compared with a threshold: a unary report of known (p, q)."""
    return unary(items, domain, *threshold_pq(eps, theta if theta is not None else best_theta(eps)), "the", seed)


def classical_reports(items: DataFrame, k: int, m: int, eps: float, seed: int = 42, engine: str = "sql", secret: str = "") -> DataFrame:
    """Bit-vector sketch reports as their set bits: every bit of the row's one-hot vector is flipped with 1/(1+e^(eps/2)). The SQL form
    replays the public seed; the arrow form draws coins under ``secret``."""
    p = 1 / (1 + math.exp(-eps / 2))
    if engine == "arrow":
        return _classical_arrow(items, *classical_params(k, m, eps, seed, secret))
    rows = items.withColumn("j", (prf(seed, "row", "report_id") % k + 1).cast("int"))
    r = (prf(seed, "cell", F.col("j"), F.col("item")) % m + 1).cast("int")
    rows = rows.withColumn("r", r)
    bits = F.filter(F.sequence(F.lit(1), F.lit(m)), lambda i: F.when(i == F.col("r"), below(seed, "bit", p, F.col("report_id"), i)).otherwise(~below(seed, "bit", p, F.col("report_id"), i)))
    return rows.select("j", bits.alias("x"))


def classical_params(k: int, m: int, eps: float, seed: int = 42, secret: str = "") -> tuple[theory.SketchParams, float]:
    """Size, family and secret of the bit-vector sketch, and the chance that a bit stays."""
    return theory.SketchParams(k, m, 1, 0.5, seed, secret=secret), 1 / (1 + math.exp(-eps / 2))


def _classical_arrow(items: DataFrame, sp: theory.SketchParams, p: float) -> DataFrame:
    ship(items.sparkSession)
    rows, work = classical_worker(items, sp, p)
    return rows.mapInArrow(work, "j int, x array<int>")


def classical_worker(items: DataFrame, sp: theory.SketchParams, p: float) -> tuple[DataFrame, Callable]:
    """What the clients' tasks read, and the work that turns its batches into bit-vector reports. A report needs m + 1 words of coins: the
    tasks draw them as one SHAKE-128 stream under the clients' secret by the report's id."""
    if not sp.secret:
        raise ValueError("the arrow form needs the clients' secret")
    k, m, secret, family, bound = sp.k, sp.m, sp.secret, sp.public(), np.uint64(int(p * 2**64))
    rows = items.select(F.col("report_id").cast("string").cast("binary").alias("_report"), F.xxhash64("item").alias("_item"))

    def work(batches):
        start, size = hashlib.shake_128(f"{secret}|coins|".encode()), 8 * (m + 1)

        def coins(report: bytes | None) -> bytes:
            own = start.copy()
            own.update(report or b"")
            return own.digest(size)

        for b in batches:
            if not b.num_rows:
                continue
            words = np.frombuffer(b"".join(map(coins, b.column("_report").to_pylist())), "<u8").reshape(b.num_rows, m + 1)
            j = (words[:, 0] % np.uint64(k)).astype(np.int32) + 1
            own = arrow_cell(family, j, b.column("_item").to_numpy(zero_copy_only=False).view(np.uint64))
            bits = words[:, 1:] >= bound
            at = np.arange(len(own))
            bits[at, own - 1] = ~bits[at, own - 1]
            ends = np.r_[0, np.cumsum(bits.sum(1))].astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(j), pa.ListArray.from_arrays(pa.array(ends), pa.array((np.nonzero(bits)[1] + 1).astype(np.int32)))], names=["j", "x"])

    return rows, work


def classical_estimate(items: DataFrame, matrix: DataFrame, k: int, m: int, eps: float, n: int | Column, seed: int = 42, engine: str = "sql") -> DataFrame:
    """The count-mean estimator of the bit-vector sketch from its matrix."""
    p = 1 / (1 + math.exp(-eps / 2))
    sp = theory.replayed(k, m, 1, 0.5, seed)
    got = support(items, matrix, sp, engine=engine)
    got = got.withColumn("n", n if isinstance(n, Column) else F.lit(n).cast("long"))
    u = p / m + (1 - p) * (1 - 1 / m)
    return got.withColumn("est", (F.col("support") - F.col("n") * F.lit(u)) / F.lit(p - u))


def cohort_bits(items: DataFrame, cohorts: int, bits: int, hashes: int, flip: float = 0.25, p1: float = 0.35, q1: float = 0.65, seed: int = 42) -> DataFrame:
    """Cohort-Bloom counts ``cohort, bit, cnt, n``: each client's cohort sets ``hashes`` bits; a permanent flip, then an
    instantaneous one."""
    rows = items.withColumn("cohort", (prf(seed, "coh", "client_id") % cohorts).cast("int"))
    own = F.array_distinct(F.array(*(prf(seed, f"bl{h}", "cohort", "item") % bits for h in range(hashes))))
    rows = rows.withColumn("own", own)

    def said(i):
        u = prf(seed, "perm", F.col("client_id"), F.col("item"), i)
        half = int(flip / 2 * (1 << 52))
        held = F.when(u < half, True).when(u < 2 * half, False).otherwise(F.array_contains(F.col("own"), i))
        return F.when(held, below(seed, "inst", q1, F.col("report_id"), i)).otherwise(below(seed, "inst", p1, F.col("report_id"), i))

    sent = rows.withColumn("set", F.filter(F.transform(F.sequence(F.lit(0), F.lit(bits - 1)), lambda i: i.cast("long")), said))
    counts = sent.select("cohort", F.explode("set").alias("bit")).groupBy("cohort", "bit").agg(F.count("*").alias("cnt"))
    return counts.join(F.broadcast(rows.groupBy("cohort").agg(F.count("*").alias("n"))), "cohort")


def cohort_decode(counts: DataFrame, domain: list[str], cohorts: int, bits: int, hashes: int, flip: float = 0.25, p1: float = 0.35, q1: float = 0.65, seed: int = 42, rounds: int = 2000, penalty: float = 0.02) -> DataFrame:
    """``item, est`` of the candidates that a non-negative lasso selects on the debiased bit counts (cohorts x bits equations, small
    domain), fitted again by non-negative least squares without the penalty; the others are 0. ``penalty``: share of the strongest
    candidate's pull below which nothing is selected."""
    target = np.zeros((cohorts, bits))
    for r in counts.collect():  # cohorts x bits rows
        target[r["cohort"], r["bit"]] = (r["cnt"] - (p1 + 0.5 * flip * (q1 - p1)) * r["n"]) / ((1 - flip) * (q1 - p1))
    design = np.zeros((cohorts * bits, len(domain)))
    for d, item in enumerate(domain):
        for c in range(cohorts):
            for h in range(hashes):
                design[c * bits + prf_int(seed, f"bl{h}", c, item) % bits, d] = 1.0 / cohorts
    gram, pull = design.T @ design, design.T @ target.ravel()

    def descend(use: np.ndarray, fee: float) -> np.ndarray:
        g, x = gram[np.ix_(use, use)], np.zeros(len(use))
        step = 1 / max(1e-12, float(np.linalg.eigvalsh(g).max())) if len(use) else 0.0
        for _ in range(rounds):
            x = np.maximum(0, x - step * (g @ x - pull[use] + fee))
        return x

    every = np.arange(len(domain))
    chosen = every[descend(every, penalty * max(0.0, float(pull.max(initial=0.0)))) > 0]
    x = np.zeros(len(domain))
    x[chosen] = descend(chosen, 0.0)
    return counts.sparkSession.createDataFrame([(d, float(v)) for d, v in zip(domain, x, strict=True)], "item string, est double")
