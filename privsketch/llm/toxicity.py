"""Toxicity: support vector machine over a gap-weighted subsequence kernel with Nystroem landmarks.

A text is a bag of units: its lower-cased letter runs, each token with its other characters taken out, and runs of
single letters joined, so that ``i d i o t``, ``i.d.i.o.t`` and ``idxiot`` all keep the subsequences of the insult. The kernel of
two units counts common three-letter subsequences (with marks for both ends), each weighted by ``DECAY`` to the power of the
letters it spans, at most ``SPAN``; it is normalised to 1. The feature map of a unit is its kernel against landmark units times
the inverse root of the landmarks' own kernel. Only document labels are known, so a labelled text's sentences are a bag of which
at least one unit must be toxic: the machine is trained on the witnesses of toxic texts (units seen far more often there than
in clean texts) and on units of clean texts, to which every round adds those with the highest values so far. A text's score is the logistic of a mean of its three highest values of distinct tokens.

Fitted on a bounded sample: ``SAMPLE_DOCS`` labelled texts a class, lowest hash first. Every text is scored whole.
Landmark weights are folded into one weight per subsequence, which gives the same value as the feature map. Null, empty and
letterless texts get the score of a unit without any subsequence. With one class only, every score is 0 (or 1).

What the machine learns from: of a toxic sentence only the witnesses, chosen by odds over 2 (natural logarithm) between the classes, count as
positive units, so labels are sharpened to units before the machine is trained. Letters other than a-z share twelve codes, so insults in
other scripts are told apart less well. The logistic map has its centre 0.35 of the way across the gap between the classes and twelve
of its slopes between their medians; both are fixed choices, not fitted.

Repeated rows are scored alike, one row each; repeated and near-equal labelled texts are learnt from once. Ties of the hash order go to the
smaller doc_id. A text of any length is scored whole. An empty table gives an empty result. Columns other than ``doc_id`` and ``text``
(``toxic`` of the labels) are not read and may have any name, but for those that the caller carries along.
"""

from __future__ import annotations

import re
import unicodedata
import uuid
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._util import Recent, only, ship, slices
from .language_id import held_out

DECAY, SPAN, ALPHABET, LONGEST = 0.6, 7, 40, 24
SAMPLE_DOCS, LANDMARKS, ROUNDS, COST, THRESHOLD, CACHE = 2500, 512, 5, 5.0, 0.7, 300_000
_OFFSETS = [(i, j) for j in range(2, SPAN) for i in range(1, j)]
_WORD, _OTHER = re.compile(r"[^\x20\x09-\x0D]+"), re.compile(r"[\W\d_]+")


def fold(text: str) -> str:
    text = text.lower()
    return text if text.isascii() else unicodedata.normalize("NFC", text)


def units_of_token(token: str) -> tuple[str, ...]:
    """Letter runs of a token, and the token without its other characters; long ones as overlapping windows."""
    runs = [r for r in _OTHER.split(fold(token)) if r]
    joined = "".join(runs)
    out = []
    for u in dict.fromkeys([*runs, joined] if len(runs) > 1 else runs):
        out += [u] if len(u) <= LONGEST else [u[i : i + LONGEST] for i in range(0, len(u) - LONGEST // 2, LONGEST // 2)]
    return tuple(out)


_SINGLE = re.compile(r"(?<![^\W\d_])[^\W\d_](?:[\W\d_]+[^\W\d_](?![^\W\d_])){2,}")


def spelled(text: str) -> list[str]:
    """Units of runs of at least three single letters, each apart from the next."""
    if not _SINGLE_HINT.search(text):
        return []
    return [u for m in _SINGLE.findall(text) for u in units_of_token(m)]


_SINGLE_HINT = re.compile(r"(?:^|\W)\w\W+\w\W+\w(?:\W|$)")


def codes(units: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Letters with end marks of all units end to end, padded so that no subsequence crosses; and each position's unit."""
    sizes = np.fromiter(map(len, units), np.int64, len(units)) + 2
    point = np.frombuffer(("{" + "{{".join(units) + "{").encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64) if units else np.zeros(0, np.int64)
    data = np.where((point > 96) & (point < 124), point - 96, 28 + (point * 7919 >> 4) % 12)  # a-z, end mark, other letters
    return data, np.repeat(np.arange(len(units)), sizes)


def subsequences(units: list[str]):
    """Yields (unit, feature, weight) arrays, one offset pair at a time."""
    data, owner = codes(units)
    for i, j in _OFFSETS:
        if len(data) <= j:
            break
        ok = np.flatnonzero(owner[j:] == owner[:-j])
        yield owner[ok], (data[ok] * ALPHABET + data[ok + i]) * ALPHABET + data[ok + j], DECAY ** (j + 1)


def dense(units: list[str]) -> np.ndarray:
    """Normalised explicit features of landmarks, one column each."""
    out = np.zeros((ALPHABET**3, len(units)), np.float32)
    for u, f, w in subsequences(units):
        np.add.at(out, (f, u), np.float32(w))
    out /= np.maximum(np.sqrt(np.einsum("ij,ij->j", out, out)), 1e-12)
    return out


def norms(units: list[str]) -> np.ndarray:
    """Root of each unit's kernel with itself."""
    keys, weights = [], []
    for u, f, w in subsequences(units):
        keys.append(u * ALPHABET**3 + f)
        weights.append(np.full(len(u), w))
    if not keys:
        return np.zeros(len(units))
    key, weight = np.concatenate(keys), np.concatenate(weights)
    order = np.argsort(key)
    key, weight = key[order], weight[order]
    at = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    return np.sqrt(np.bincount(key[at] // ALPHABET**3, np.add.reduceat(weight, at) ** 2, len(units)))


def values(units: list[str], weights: np.ndarray, bias: float, chunk: int = 1000) -> np.ndarray:
    """Machine values of units under folded weights, a bounded number of units at a time."""
    if len(units) > chunk:
        return np.concatenate([values(units[i : i + chunk], weights, bias) for i in range(0, len(units), chunk)])
    total = np.zeros(len(units))
    for u, f, w in subsequences(units):
        total += np.bincount(u, weights[f], len(units)) * w
    return total / np.maximum(norms(units), 1e-12) + bias


def kernel(units: list[str], landmarks: np.ndarray) -> np.ndarray:
    """Kernel of units against landmark columns."""
    out = np.zeros((len(units), landmarks.shape[1]), np.float32)
    for at in range(0, len(units), 500):
        some = units[at : at + 500]
        part = out[at : at + 500]
        for u, f, w in subsequences(some):
            starts = np.flatnonzero(np.r_[True, u[1:] != u[:-1]])
            if len(starts) and len(u):
                part[u[starts]] += np.float32(w) * np.add.reduceat(landmarks[f], starts, axis=0)
        part /= np.maximum(norms(some), 1e-12)[:, None]
    return out


def support_vector(x: np.ndarray, y: np.ndarray, cost: np.ndarray, steps: int = 15) -> tuple[np.ndarray, float]:
    """Primal machine with squared hinge loss by Newton steps; ``y`` is +1 or -1. The bias is held at -1: a unit that is
    like no landmark is clean."""
    bias, w = -1.0, np.zeros(x.shape[1])
    for _ in range(steps):
        on = y * (x @ w + bias) < 1
        xa, ca = x[on], cost[on]
        new = np.linalg.solve(np.eye(x.shape[1]) + xa.T @ (xa * ca[:, None]), xa.T @ (ca * (y[on] - bias)))
        if np.allclose(new, w, atol=1e-7):
            break
        w = new
    return w, bias


#: Shares of the three highest token values in a text's value: insults come in company, chance likenesses alone.
SHARES = (0.5, 0.3, 0.2)


def evidence(token_values: np.ndarray, floor: float) -> float:
    top = np.sort(np.partition(token_values, -3)[-3:] if len(token_values) > 3 else token_values)[::-1].tolist()
    return sum(w * v for w, v in zip(SHARES, [*top, floor, floor, floor], strict=False))


class Machine:
    def __init__(self, weights: np.ndarray, bias: float, slope: float, shift: float, floor: float):
        self.weights, self.bias, self.slope, self.shift, self.floor = weights, bias, slope, shift, floor
        self.known = Recent(CACHE)

    def learn(self, tokens: list[str]) -> None:
        """Highest unit value of each token."""
        units: dict[str, int] = {}
        per, owner = [], []
        for i, t in enumerate(tokens):
            for u in units_of_token(t):
                per.append(units.setdefault(u, len(units)))
                owner.append(i)
        out = np.full(len(tokens), self.floor)
        if units:
            np.maximum.at(out, owner, values(list(units), self.weights, self.bias)[per])
        self.known.now.update(zip(tokens, out.tolist(), strict=True))

    def decide(self, texts: list[str]) -> np.ndarray:
        split = [{*_WORD.findall(t), *spelled(t)} for t in texts]
        if new := self.known.missing(set().union(*split)):
            self.learn(new)
        get = self.known.now.__getitem__
        return np.array([evidence(np.fromiter(map(get, s), float, len(s)), self.floor) for s in split])

    def score(self, texts: list[str]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.decide(texts) + self.shift, -30, 30)))


def distinct(bags: list[tuple[list[str], int]]) -> list[tuple[list[str], int]]:
    """First bag of those that share the least hash of their long units under either of two seeds."""
    seen: tuple[set, set] = (set(), set())
    out = []
    for units, label in bags:
        hashes = [zlib.crc32(u.encode()) for u in units if len(u) >= 8]
        marks = [(label, min((h ^ salt) * 0x9E3779B1 & 0xFFFFFFFF for h in hashes)) for salt in (0, 0x5BD1E995)] if hashes else []
        if any(m in s for m, s in zip(marks, seen, strict=False)):
            continue
        for m, s in zip(marks, seen, strict=False):
            s.add(m)
        out.append((units, label))
    return out


def train(bags: list[tuple[list[str], int]]) -> Machine:
    """Fit on (distinct units, label) bags; of copies and near copies one is used."""
    bags = distinct(bags)
    toxic, clean = Counter(), Counter()
    for units, label in bags:
        (toxic if label else clean).update(units)
    n1, n0 = sum(y for _, y in bags), sum(1 - y for _, y in bags)
    if not n1 or not n0:
        return Machine(np.zeros(ALPHABET**3), 0.0, 0.0, -30.0 if not n1 else 30.0, 0.0)
    names = sorted(toxic.keys() | clean.keys())
    at = {u: i for i, u in enumerate(names)}
    t, c = np.array([toxic[u] for u in names], float), np.array([clean[u] for u in names], float)
    odds = np.log((t + 0.05) / (n1 + 1)) - np.log((c + 0.05) / (n0 + 1))
    # the bar stops where chance alone would put less than one unit into toxic texts only, however large the sample
    odds[t < max(6, min(0.012 * n1, np.log2(len(names))))] = -np.inf
    positive = [np.array([at[u] for u in us], int) for us, y in bags if y and us]
    negative = [np.array([at[u] for u in us], int) for us, y in bags if not y and us]
    witness = [p[odds[p] > 2] for p in positive]
    if not any(map(len, witness)):  # too few texts for odds: any unit may be the witness
        witness = positive
    rng = np.random.default_rng(7)
    seen = np.flatnonzero(c > 0)
    hard = seen[np.argsort(-(c[seen]), kind="stable")][:1500]
    hard = np.union1d(hard, rng.choice(seen, min(len(seen), 4000), replace=False))
    value = None
    for _ in range(ROUNDS):
        chosen, weight = np.unique(np.concatenate(witness), return_counts=True)
        tops = chosen[np.argsort(-weight, kind="stable")][: LANDMARKS // 2].tolist()
        near = hard[np.argsort(-value[hard], kind="stable")][: LANDMARKS // 4].tolist() if value is not None else []
        spread = rng.choice(hard, min(len(hard), LANDMARKS - len(tops) - len(near)), replace=False).tolist()
        landmarks = dense([names[i] for i in dict.fromkeys(tops + near + spread)])
        size, base = np.linalg.eigh((landmarks.T @ landmarks).astype(float))
        good = size > 1e-4
        root = base[:, good] / np.sqrt(size[good])
        x = kernel([names[i] for i in [*chosen.tolist(), *hard.tolist()]], landmarks) @ root
        y = np.r_[np.ones(len(chosen)), -np.ones(len(hard))]
        gain, harm = np.minimum(weight, 20.0), np.sqrt(c[hard])
        cost = np.r_[gain / gain.sum(), 2 * harm / harm.sum()] * COST * len(hard)
        w, bias = support_vector(x, y, cost)
        folded = (landmarks @ (root @ w).astype(np.float32)).astype(float)
        value = values(names, folded, bias)
        hard = np.union1d(hard, seen[np.argsort(-value[seen], kind="stable")][:2500])
    floor = float(min(bias, np.median(value[seen])))
    top = np.array([evidence(value[p], floor) for p in positive + negative])
    label = np.r_[np.ones(len(positive)), np.zeros(len(negative))]
    slope, shift = _calibrate(top, label)
    return Machine(folded, bias, slope, shift, floor)


def _calibrate(value: np.ndarray, label: np.ndarray) -> tuple[float, float]:
    """Logistic map: centred where the two classes are best told apart, with the slope of a logistic fit held positive."""
    order = np.argsort(value, kind="stable")
    v, y = value[order], label[order]
    wrong = np.r_[0, np.cumsum(y)] / max(1, y.sum()) + (len(y) - y.sum() - np.r_[0, np.cumsum(1 - y)]) / max(1, (1 - y).sum())
    best = np.flatnonzero(wrong == wrong.min())
    cut = best[len(best) // 2]
    low, high = (v[cut - 1] if cut else v[0] - 1), (v[cut] if cut < len(v) else v[-1] + 1)
    spread = max(0.05, np.median(v[y > 0]) - np.median(v[y == 0]))
    slope = 12.0 / spread
    centre = low + 0.35 * (high - low)
    return float(slope), float(-slope * centre + np.log(THRESHOLD / (1 - THRESHOLD)))


def fit(docs: DataFrame, labels: DataFrame, hold=(3, 1), sample_docs: int = SAMPLE_DOCS) -> Machine:
    """Machine from labelled texts (conflicting labels of a document: toxic wins)."""
    ship(docs.sparkSession)
    marks = labels.selectExpr("cast(doc_id as long) doc_id", "cast(toxic as int) toxic").filter("doc_id is not null and toxic is not null")
    if hold:
        marks = marks.filter(~held_out(*hold))
    marks = marks.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    both = [marks.filter(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs) for y in (0, 1)]
    chosen = both[0].union(both[1])  # at most 2 x sample_docs rows
    rows = docs.selectExpr("cast(doc_id as long) doc_id", "text").join(F.broadcast(chosen), "doc_id")

    def work(batches):
        for batch, texts in slices(batches):
            sets = [sorted({u for w in [*_WORD.findall(t), *spelled(t)] for u in units_of_token(w)}) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([" ".join(x) for x in sets]), batch.column("toxic")], names=["doc_id", "units", "toxic"])

    names: dict[str, str] = {}  # one copy of each unit
    bags = []
    for r in rows.mapInArrow(work, "doc_id long, units string, toxic int").orderBy("doc_id").toLocalIterator():
        bags.append(([names.setdefault(u, u) for u in r[1].split(" ")] if r[1] else [], r[2]))
    return train(bags)


def with_score(docs: DataFrame, machine: Machine, carry: list[str]) -> DataFrame:
    """``doc_id``, the ``carry`` columns and ``score``."""
    spark = ship(docs.sparkSession)
    parts = (machine.weights, machine.bias, machine.slope, machine.shift, machine.floor)
    shared, key = spark.sparkContext.broadcast(parts), uuid.uuid4().hex  # 64,000 weights

    def work(batches):
        own = only(key, lambda: Machine(*shared.value))
        for batch, texts in slices(batches, limit=4 << 20):
            kept = ["doc_id", *carry]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(own.score(texts))], names=[*kept, "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *([] if "text" in carry else ["text"]), *carry)
    fields = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in ["doc_id", *carry])
    return rows.mapInArrow(work, f"{fields}, score double")


def toxicity(docs: DataFrame, labels: DataFrame, hold=(3, 1), sample_docs: int = SAMPLE_DOCS, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document."""
    out = with_score(docs, fit(docs, labels, hold, sample_docs), [])
    return out.select("doc_id", held_out(*hold).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
