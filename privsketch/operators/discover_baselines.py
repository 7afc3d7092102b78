"""Baselines for unknown domains: private trie, fragment puzzle, segment expectation-maximisation."""

from __future__ import annotations

import itertools
import re

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import theory, tune
from ..functions.prf import below, prf
from ..functions.theory import SketchParams
from . import estimate, oracles, randomize, sketch

#: Characters a string may hold; others become the first, and shorter strings are padded with it.
ALPHABET = "_abcdefghijklmnopqrstuvwxyz0123456789:/.-?=#&%"


def extensions(spark: SparkSession, step: int) -> DataFrame:
    """Every string of ``step`` characters of the alphabet, as ``more``."""
    one = spark.createDataFrame([(c,) for c in ALPHABET], "more string")
    out = one
    for _ in range(step - 1):
        out = out.crossJoin(F.broadcast(one.withColumnRenamed("more", "_c"))).select(F.concat("more", "_c").alias("more"))
    return out


def spelled(length: int) -> Column:
    """``item`` in the alphabet: other characters become the first one, shorter strings are padded with it, longer ones are cut."""
    allowed = re.escape(ALPHABET).replace("/", "\\/")
    return F.rpad(F.substring(F.regexp_replace(F.lower("item"), f"[^{allowed}]", ALPHABET[0]), 1, length), length, ALPHABET[0])


def heavy(candidates: DataFrame, reports: DataFrame, sp: SketchParams, sigmas: float) -> DataFrame:
    """``item, est`` of the candidates over a bar that absent items stay under: ``sigmas`` deviations of their estimate, collisions with
    what is heavy included, and as much more as the longer tails of few reports and few colliding rows ask for (Bernstein's bound)."""
    est = estimate.frequencies(candidates, sketch.build(reports), sp, engine="arrow").persist()  # a row a candidate, read twice
    zero, tail = F.lit(0.0), sigmas**2 / 3
    first = F.lit(sigmas) * F.sqrt(theory.variance(zero, F.col("n"), F.col("n"), sp)) + F.lit(tail / (sp.p - sp.u))
    seen = est.filter(F.col("est") > first).agg(F.coalesce(F.sum(F.pow("est", 2)), zero).alias("_moment"), F.coalesce(F.max("est"), zero).alias("_top"))
    spread = theory.variance(zero, F.col("n"), F.greatest("_moment", "n"), sp)
    bar = F.lit(sigmas) * F.sqrt(spread) + F.lit(tail) * F.greatest(F.lit(1 / (sp.p - sp.u)), F.col("_top") / sp.k)
    return est.crossJoin(F.broadcast(seen)).filter(F.col("est") > bar).select("item", "est")


def spent(eps: float, k: int, m: int, seed: int) -> SketchParams:
    """Sketch parameters that spend ``eps`` exactly, for items of one report in a hundred; coins from the public seed, as baselines are
    compared, not deployed."""
    t = tune.tune_integer(eps, 0.01, k, m)
    return theory.replayed(k, m, t.s, t.p, seed)


def private_trie(items: DataFrame, eps: float, length: int, step: int = 2, sigmas: float = 4.0, k: int = 64, m: int = 256, seed: int = 42, most: int = 20_000) -> list[tuple[str, float]]:
    """Strings of up to ``length`` characters, grown ``step`` characters a round. Each client is in the group of one round, so no budget
    is split, and reports its prefix through the subset sketch; candidates are the survivors' extensions, looked up as a plan.
    Survivors come to the driver every round; more than ``most`` are refused."""
    spark, rounds = items.sparkSession, -(-length // step)
    whole, ends, found = items.withColumn("item", spelled(rounds * step)), [""], []
    for level in range(rounds):
        sp = spent(eps, k, m, seed + level)
        group = whole.filter((prf(seed, "level", "client_id") % rounds) == level).withColumn("item", F.substring("item", 1, (level + 1) * step))
        start = spark.createDataFrame([(a,) for a in ends], "start string")
        candidates = start.crossJoin(F.broadcast(extensions(spark, step))).select(F.concat("start", "more").alias("item"))
        got = heavy(candidates, randomize.subset_reports(group, sp, engine="arrow"), sp, sigmas).orderBy("item").limit(most + 1).collect()
        if len(got) > most:
            raise ValueError(f"more than {most} prefixes survive; raise sigmas")
        found, ends = [(r["item"].rstrip(ALPHABET[0]), r["est"] * rounds) for r in got], [r["item"] for r in got]
        if not ends:
            break
    return sorted(found, key=lambda r: (-r[1], r[0]))


def fragments(items: DataFrame, length: int, size: int) -> DataFrame:
    """``position, fragment, mark``: pieces of the padded string with a short digest of the whole."""
    padded = items.withColumn("whole", F.rpad("item", length, "_"))
    each = padded.select("report_id", "whole", F.explode(F.sequence(F.lit(0), F.lit(length // size - 1))).alias("position"))
    return each.select("report_id", "position", F.expr(f"substring(whole, position * {size} + 1, {size})").alias("fragment"), F.substring(F.md5("whole"), 1, 4).alias("mark"))


def puzzle(heavy: DataFrame, positions: int) -> DataFrame:
    """Join heavy ``position, fragment, mark`` rows on the mark into whole strings, one self-join a position."""
    out = heavy.filter("position = 0").select("mark", F.col("fragment").alias("item"))
    for i in range(1, positions):
        part = heavy.filter(F.col("position") == i).select("mark", F.col("fragment").alias("_next"))
        out = out.join(part, "mark").select("mark", F.concat("item", "_next").alias("item"))
    return out.select(F.regexp_replace("item", "_+$", "").alias("item")).distinct()


def fragment_puzzle(items: DataFrame, eps: float, length: int = 8, size: int = 2, sigmas: float = 4.0, k: int = 64, m: int = 256, seed: int = 42) -> DataFrame:
    """``item, est``. Half of each client's budget reports one random position's (fragment, mark), the other half the whole string, both
    through subset sketches. All fragments of the alphabet under all marks (one hex digit of the whole's digest) are looked up; those
    that the estimates call heavy are joined on their mark, and a joined string stays only if the whole-string sketch finds it."""
    spark, positions = items.sparkSession, length // size
    whole = items.withColumn("item", spelled(length))
    pieces, wholes = spent(eps / 2, k, m, seed), spent(eps / 2, k, m, seed + 1)
    named = F.concat_ws("|", F.col("position").cast("string"), "fragment", F.substring("mark", 1, 1)).alias("item")
    one = fragments(whole, length, size).filter(F.col("position") == prf(seed, "pos", "report_id") % positions).select("report_id", named)
    places = spark.range(positions).select(F.col("id").cast("string").alias("position"))
    marks = spark.range(16).select(F.lower(F.hex("id")).alias("mark"))
    domain = extensions(spark, size).crossJoin(F.broadcast(places)).crossJoin(F.broadcast(marks)).select(F.concat_ws("|", "position", "more", "mark").alias("item"))
    part = F.split("item", "\\|")
    found = heavy(domain, randomize.subset_reports(one, pieces, engine="arrow"), pieces, sigmas).select(part[0].cast("int").alias("position"), part[1].alias("fragment"), part[2].alias("mark"))
    joined = puzzle(found, positions).withColumn("item", F.rpad("item", length, ALPHABET[0]))
    checked = heavy(joined, randomize.subset_reports(whole, wholes, engine="arrow"), wholes, sigmas)
    return checked.select(F.regexp_replace("item", f"{ALPHABET[0]}+$", "").alias("item"), "est")


def segment_em(items: DataFrame, eps: float, size: int = 1, rounds: int = 200, seed: int = 42, most: int = 2500) -> DataFrame:
    """Joint distribution of two string pieces from direct reports of each (half the budget each) by expectation-maximisation. Pieces are
    all strings of ``size`` characters of the alphabet; the state is their number squared, and more than ``most`` are refused."""
    spark = items.sparkSession
    width = len(ALPHABET) ** size
    if width > most:
        raise ValueError(f"{width} pieces; take shorter ones")
    halves = items.withColumn("item", spelled(2 * size)).select("report_id", F.expr(f"left(item, {size})").alias("a"), F.expr(f"right(item, {size})").alias("b"))
    names = ["".join(x) for x in itertools.product(ALPHABET, repeat=size)]
    at = {v: i for i, v in enumerate(names)}
    p, q = oracles.direct_pq(eps / 2, max(2, width))
    codes = F.create_map(*[x for n in names for x in (F.lit(n), F.lit(at[n]))])

    def said(col, tag):
        own = codes[F.col(col)]
        other = prf(seed, f"{tag}o", "report_id") % (width - 1)
        return F.when(below(seed, tag, p, "report_id"), own).otherwise(F.when(other >= own, other + 1).otherwise(other)).cast("int")

    counts = np.zeros((width, width))
    for r in halves.select(said("a", "ema").alias("i"), said("b", "emb").alias("k")).groupBy("i", "k").count().collect():  # alphabet squared
        counts[r[0], r[1]] = r[2]
    noise = np.full((width, width), q) + (p - q) * np.eye(width)
    joint = np.full((width, width), 1 / width**2)
    for _ in range(rounds):
        likely = noise @ joint @ noise.T
        joint = joint * (noise.T @ (counts / np.maximum(likely, 1e-300)) @ noise) / counts.sum()
    n = counts.sum()
    rows = [(names[i] + names[k], float(joint[i, k] * n)) for i in range(width) for k in range(width)]
    return spark.createDataFrame(rows, "item string, est double")
