"""Closed forms of the mechanisms. Scalars take floats; the ``*_col`` forms take Columns.

``u`` is the chance that a uniformly hashed cell is reported (s/m); it shortens the estimator to (C - n u) / (p - u).
"""

from __future__ import annotations

import math
import secrets
from dataclasses import dataclass, field, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SketchParams:
    k: int
    m: int
    s: int
    p: float
    #: Names the public hash family; the server and every client know it.
    seed: int = 42
    #: Where coins come from: ``keyed`` by the clients' secret, ``replay`` and ``fast`` by the public seed (comparisons only, not private).
    mode: str = "keyed"
    #: Secret of the simulated clients, drawn anew for every set of parameters; it never leaves the client side.
    secret: str = field(default_factory=lambda: secrets.token_hex(32), repr=False, compare=False)

    def __post_init__(self):
        if self.mode not in ("keyed", "replay", "fast"):
            raise ValueError("mode is keyed, replay or fast")
        if not (self.k >= 1 and self.m >= 2 and 1 <= self.s <= self.m / 2 and 0.5 <= self.p < 1):
            raise ValueError("need k >= 1, m >= 2, 1 <= s <= m/2 and 0.5 <= p < 1")

    def coins(self, mode: str) -> str | int:
        """Key of a client's coins: the secret, unless a public form was asked for."""
        return self.secret if mode == "keyed" else self.seed

    def public(self) -> SketchParams:
        """What the server holds."""
        return replace(self, secret="")

    @property
    def u(self) -> float:
        return self.s / self.m

    @property
    def q(self) -> float:
        return q_of(self.p, self.s, self.m)

    @property
    def eps(self) -> float:
        return eps_of(self.p, self.s, self.m)


def replayed(*args, **more) -> SketchParams:
    """Parameters whose coins any engine can replay from the public seed: for comparison with SQL, not for collection."""
    return SketchParams(*args, mode="replay", **more)


def q_of(p, s, m):
    """Chance that a given other cell is reported."""
    return (s - p) / (m - 1)


def eps_of(p: float, s: int, m: int) -> float:
    """Local privacy of a subset report."""
    return abs(math.log(p * (m - s) / ((1 - p) * s)))


def eps_col(p: Column, s: Column, m: Column) -> Column:
    return F.abs(F.log(p * (m - s) / ((F.lit(1.0) - p) * s)))


def s_of(p: float, eps: float, m: int) -> int:
    """Smallest subset size that keeps epsilon at ``eps`` or less."""
    return math.ceil(round(m / (1 + (1 / p - 1) * math.exp(eps)), 9))


def p_of(s: int, eps: float, m: int) -> float:
    """Inclusion probability that spends ``eps`` exactly with subsets of size ``s``."""
    return s * math.exp(eps) / (m - s + s * math.exp(eps))


def estimate(support, n, p, u):
    """Unbiased frequency; undefined when reports carry nothing (p = u)."""
    if isinstance(p, (int, float)) and isinstance(u, (int, float)) and abs(p - u) < 1e-12:
        raise ValueError("p = s/m: the report does not depend on the datum")
    return (support - n * u) / (p - u)


def long_estimate(support: float, n: float, p: float, q: float, m: int) -> float:
    """The same estimator written with q, for tests."""
    return (support - p * n / m - q * n * (1 - 1 / m)) / ((p - q) * (1 - 1 / m))


def variance(f, n, second_moment, sp: SketchParams, form: str = "exact"):
    """Variance of an estimate; ``second_moment``: sum over all items of their squared counts. ``published`` divides the squared
    terms by k, which is right for k = 1 and too large beyond; ``limit`` leaves collisions out."""
    c = 1.0 if form != "published" else 1.0 / sp.k
    p, u = sp.p, sp.u
    spread = (f * (p - c * p * p) + (n - f) * (u - c * u * u)) / (p - u) ** 2
    if form == "limit":
        return spread
    return spread + (second_moment - f * f - (n - f)) / (sp.k * (sp.m - 1))


def pure_variance(f, n, p: float, q: float):
    """Variance in a pure protocol (one hash, no collisions)."""
    return n * q * (1 - q) / (p - q) ** 2 + f * (1 - p - q) / (p - q)


def objective(p, lam, eps, k, exp=math.exp):
    """Randomisation part of the variance over n for the p that spends eps; k = 1 is the exact form for every k."""
    u = p / (p + (1 - p) * exp(eps))
    return (lam * p * (1 - p / k) + (1 - lam) * u * (1 - u / k)) / ((p - u) * (p - u))


def split_budget(eps, eps_p, exp=math.exp):
    """(p, q) of a unary report that spends ``eps_p`` on keeping a one and the rest on raising zeros."""
    return exp(eps_p) / (1 + exp(eps_p)), 1 / (exp(eps - eps_p) + 1)


def unary_eps(p, q, log=math.log):
    """Two coordinates differ between one-hot vectors, so both ratios count."""
    return log(p * (1 - q) / ((1 - p) * q))


def report_bits(k: int, m: int, s: int) -> dict[str, float]:
    cell = math.ceil(math.log2(m)) if m > 1 else 0
    row = math.ceil(math.log2(k)) if k > 1 else 0
    return {"bits_cells": s * cell, "bits_total": s * cell + row, "bits_classical": m, "bits_entropy": (math.lgamma(m + 1) - math.lgamma(s + 1) - math.lgamma(m - s + 1)) / math.log(2)}
