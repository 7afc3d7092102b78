"""Fast simulator of one item's support count: its exact marginal law, not the joint law over items."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.theory import SketchParams
from ..sources.workers import ship


LARGEST = 5_000


def draw(f: int, others: np.ndarray, sp: SketchParams, runs: int, rng: np.random.Generator) -> np.ndarray:
    """Estimates of an item with count ``f`` among items of counts ``others``: reports whose row sends their item to the same
    cell answer like its own."""
    n = f + int(others.sum())
    same = np.zeros(runs, np.int64)
    for c in others.tolist():
        rows = rng.binomial(sp.k, 1 / sp.m, runs)  # rows where the two items collide
        same += rng.binomial(c, rows / sp.k)
    holders = f + same
    q = sp.q
    support = rng.binomial(holders, sp.p) + rng.binomial(n - holders, q)
    return (support - n * sp.u) / (sp.p - sp.u)


def marginal_support(counts: DataFrame, sp: SketchParams, runs: int, seed: int = 42) -> DataFrame:
    """``item, f, mean_est, mse`` by simulation. The counts go to every task and every item meets every other, so a table of more
    than ``LARGEST`` items is refused."""
    ship(counts.sparkSession)
    table = counts.select("item", "f").orderBy("item").limit(LARGEST + 1).collect()
    if len(table) > LARGEST:
        raise ValueError(f"more than {LARGEST} items; simulate a part of the domain")
    every = {r[0]: int(r[1]) for r in table}

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        item = pdf["item"].iloc[0]
        rng = np.random.default_rng([seed, sum(map(ord, item))])
        est = draw(every[item], np.array([c for i, c in every.items() if i != item]), sp, runs, rng)
        return pd.DataFrame({"item": [item], "f": [every[item]], "mean_est": [est.mean()], "mse": [((est - every[item]) ** 2).mean()]})

    return counts.select("item").groupBy("item").applyInPandas(work, "item string, f long, mean_est double, mse double").orderBy(F.desc("f"), "item")
