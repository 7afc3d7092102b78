"""SimHash near-duplicates by anchor points of a covering code.

The code repeats each of ``63 / BLOCK`` bits ``BLOCK`` times (a last bit stands alone), so the nearest anchor of a fingerprint is the
majority of each block, and no fingerprint is further than the covering radius (one bit a block of three) from it. Two
fingerprints within the threshold have a common midpoint at most half the threshold (rounded up) from either; the
midpoint's anchor lies within covering radius plus that share of the threshold of both. So every distinct fingerprint is replicated to the
anchors it reaches with so many bit flips, and compared there. Which comparisons are made never depends on the data.

That is fewer replicas than covering radius plus the whole threshold would make on one side, and loses no link: of two fingerprints that differ
in at most two bits, flipping one of the differing bits of either gives a point that is one flip from both (or is one of them), and both
are sent to that point's anchor.

Copies share a fingerprint and are one row. Inside a partition of anchors, links become a spanning forest by numpy (no pair list of
a group leaves the task); forests of all partitions are joined by ``graph.components``. Texts without words have fingerprint
zero and link like any other. Null texts are empty; rows with a null doc_id are kept and never the representative. Repeated rows give one
row each. A text of any length is hashed whole. An empty table gives an empty result. Columns other than ``doc_id`` and ``text`` are not
read and may have any name, but for those that the caller carries along.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import graph
from ._util import keep, lower_ascii, min_labels, ship, slices, tokens, width

SHINGLE, SEED, THRESHOLD, BLOCK, PART_ROWS = 3, 42, 2, 3, 100_000
#: Rows of one anchor from which on comparing all of them costs more than sorting the points around them.
DENSE = 4_000
_SPREAD = np.uint64(0x9E3779B97F4A7C15)


def fingerprint(text: str, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """64-bit majority of the shingles' hashes (ties: 0)."""
    words = tokens(lower_ascii(text))
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(" ".join(words).encode("utf-8", "surrogatepass"), seed)
    joined = [" ".join(x) for x in zip(*(words[i:] for i in range(shingle)))]
    h = np.array([xxhash.xxh64_intdigest(s, seed) for s in joined], np.uint64)
    return int(majority(h, np.array([0]))[0])


def majority(h: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Fingerprint of each run of hashes; bits are counted in packed 16-bit lanes, 16 bits of the hash at a time."""
    sizes = np.diff(np.r_[starts, len(h)])
    out = np.zeros(len(starts), np.uint64)
    lane = np.uint64(0x0001000100010001)
    cells = np.zeros((64, len(starts)), np.int64)
    # runs longer than 60,000 would overflow a lane: they are cut, and the counts of the cuts added
    cut = [np.arange(s, s + n, 60_000) for s, n in zip(starts.tolist(), sizes.tolist(), strict=True)]
    owner = np.repeat(np.arange(len(starts)), [len(c) for c in cut])
    at = np.concatenate(cut)
    for b in range(16):
        sums = np.add.reduceat((h >> np.uint64(b)) & lane, at)
        for k in range(4):
            cells[b + 16 * k] = np.bincount(owner, ((sums >> np.uint64(16 * k)) & np.uint64(0xFFFF)).astype(float), len(starts)).astype(np.int64)
    for b in range(64):
        out |= (2 * cells[b] > sizes).astype(np.uint64) << np.uint64(b)
    return out


def fingerprints(docs: DataFrame, carry: list[str] | None = None) -> DataFrame:
    """``doc_id``, the ``carry`` columns and ``fp`` (signed 64-bit)."""
    ship(docs.sparkSession)
    carry = carry or []
    kept = ["doc_id", *carry]

    def work(batches):
        digest = xxhash.xxh64_intdigest
        for batch, texts in slices(batches, limit=2 << 20):
            hashes, sizes = [], []
            for t in texts:
                words = tokens(lower_ascii(t))
                n = len(words)
                if n > 2:
                    hashes += [digest(f"{a} {b} {c}", SEED) for a, b, c in zip(words, words[1:], words[2:])]
                    sizes.append(n - 2)
                elif n:
                    hashes.append(digest(" ".join(words), SEED))
                    sizes.append(1)
                else:
                    sizes.append(0)
            size = np.array(sizes)
            fp = np.zeros(len(texts), np.uint64)
            if hashes:
                some = np.flatnonzero(size)
                fp[some] = majority(np.array(hashes, np.uint64), np.r_[0, np.cumsum(size[some])[:-1]])
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(fp.view(np.int64))], names=[*kept, "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *([] if "text" in carry else ["text"]), *carry)
    fields = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in kept)
    return rows.mapInArrow(work, f"{fields}, fp long")


def anchors(fp: np.ndarray, block: int = BLOCK) -> np.ndarray:
    """Nearest anchor of each fingerprint: the majority bit of every block of an odd number of bits, packed; bits that are left
    over stand for themselves."""
    out, at, place = np.zeros(len(fp), np.uint64), 0, 0
    while at < 64:
        size = block if at + block <= 64 else 1
        ones = sum(((fp >> np.uint64(at + i)) & np.uint64(1)) for i in range(size))
        out |= (2 * ones > size).astype(np.uint64) << np.uint64(place)
        at, place = at + size, place + 1
    return out


def replicas(fp: np.ndarray, threshold: int = THRESHOLD, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """(row, anchor) of every anchor that owns a point within half the threshold of the row's fingerprint."""
    rows, found = [np.arange(len(fp))], [anchors(fp, block)]
    for flips in range(1, (threshold + 1) // 2 + 1):
        for bits in combinations(range(64), flips):
            mask = np.uint64(sum(1 << b for b in bits))
            other = anchors(fp ^ mask, block)
            new = np.flatnonzero(other != found[0])
            rows.append(new)
            found.append(other[new])
    row, anchor = np.concatenate(rows), np.concatenate(found)
    order = np.lexsort((anchor, row))
    row, anchor = row[order], anchor[order]
    first = np.r_[True, (row[1:] != row[:-1]) | (anchor[1:] != anchor[:-1])]
    return row[first], anchor[first]


def midpoint_forest(fp: np.ndarray, threshold: int, most: int = 1 << 21) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs that join all rows linked within an even threshold. Two rows are linked just when a point lies within half the
    threshold of both, so rows that reach the same point are joined to the first of them; no pairs of rows are tried. Points are
    held a bucket of their hash at a time, about ``most`` at once."""
    masks = np.array([sum(1 << b for b in bits) for n in range(threshold // 2 + 1) for bits in combinations(range(64), n)], np.uint64)
    buckets = -(-len(fp) * len(masks) // most)
    label = np.arange(len(fp))
    for bucket in range(buckets):
        points, rows = [], []
        for mask in masks:
            point = fp ^ mask
            at = np.flatnonzero(((point * _SPREAD) >> np.uint64(40)) % np.uint64(buckets) == bucket) if buckets > 1 else np.arange(len(fp))
            points.append(point[at])
            rows.append(at)
        point, row = np.concatenate(points), np.concatenate(rows)
        order = np.argsort(point, kind="stable")
        point, row = point[order], row[order]
        head = np.maximum.accumulate(np.where(np.r_[True, point[1:] != point[:-1]], np.arange(len(point)), 0))
        far = np.flatnonzero(row[head] != row)
        known = np.arange(len(fp))
        label = min_labels(len(fp), np.r_[known, row[far]], np.r_[label, row[head[far]]])
    way = np.flatnonzero(label != np.arange(len(fp)))
    return way, label[way]


def links(fp: np.ndarray, anchor: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs within the threshold among rows of equal anchor (rows sorted by anchor); of groups over 64 rows a forest. A group
    over ``DENSE`` rows meets in common midpoints if the threshold is even, and else block by block."""
    a, b = [], []
    run = np.cumsum(np.r_[True, anchor[1:] != anchor[:-1]]) - 1
    size = np.bincount(run)
    big = np.flatnonzero(size > 64)
    small = size[run] <= 64
    at = np.flatnonzero(small)
    for shift in range(1, 64):
        i = at[: len(at) - shift]
        j = at[shift:]
        ok = (run[i] == run[j])
        if not ok.any():
            break
        i, j = i[ok], j[ok]
        near = np.bitwise_count(fp[i] ^ fp[j]) <= threshold
        a.append(i[near])
        b.append(j[near])
    begin = np.r_[0, np.cumsum(size)]
    for g in big.tolist():
        own = np.arange(begin[g], begin[g + 1])
        if len(own) > DENSE and threshold % 2 == 0:
            i, j = midpoint_forest(fp[own], threshold)
            a.append(own[i])
            b.append(own[j])
            continue
        for s in range(0, len(own), 1000):
            part = fp[own[s : s + 1000], None]
            for r in range(s, len(own), 1000):
                i, j = np.nonzero(np.bitwise_count(part ^ fp[own[r : r + 1000]][None, :]) <= threshold)
                label = min_labels(2000, i, j + 1000)  # rows of both sides; only a forest of the block goes on
                way = np.flatnonzero(label != np.arange(2000))
                both = np.r_[np.resize(own[s : s + 1000], 1000), np.resize(own[r : r + 1000], 1000)]
                a.append(both[way])
                b.append(both[label[way]])
    return (np.concatenate(a), np.concatenate(b)) if a else (np.zeros(0, int), np.zeros(0, int))


def forest(distinct: DataFrame, threshold: int = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """Edges ``a, b`` that join all distinct fingerprints ``fp`` linked within the threshold."""
    spark = ship(distinct.sparkSession)

    def spread(batches):
        for batch in batches:
            fp = batch.column("fp").to_numpy(zero_copy_only=False)
            row, anchor = replicas(fp.view(np.uint64), threshold, block)
            yield pa.RecordBatch.from_arrays([pa.array(anchor.view(np.int64)), pa.array(fp[row])], names=["anchor", "fp"])

    def compare(batches):
        table = pa.Table.from_batches(list(batches)) if (batches := list(batches)) else None
        if table is None or not len(table):
            return
        anchor, fp = (table.column(c).to_numpy() for c in ("anchor", "fp"))
        order = np.argsort(anchor, kind="stable")
        anchor, fp = anchor[order], fp[order]
        names, at = np.unique(fp, return_inverse=True)
        i, j = links(fp.view(np.uint64), anchor, threshold)
        label = min_labels(len(names), at[i], at[j])
        way = np.flatnonzero(label != np.arange(len(names)))
        for s in range(0, len(way), 50_000):
            w = way[s : s + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(names[w]), pa.array(names[label[w]])], names=["a", "b"])

    parts = max(width(spark), -(-distinct.count() // PART_ROWS))  # a task holds about 17 replicas a fingerprint, whatever the table's size
    return distinct.select("fp").mapInArrow(spread, "anchor long, fp long").repartition(parts, "anchor").mapInArrow(compare, "a long, b long")


def near_duplicates(docs: DataFrame, threshold: int = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """``doc_id, fingerprint, component_id, fp`` of every document."""
    marked = keep(fingerprints(docs), "fingerprints")
    return grouped(marked, threshold, block).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "fp")


def grouped(marked: DataFrame, threshold: int = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """Adds ``component_id``, the smallest doc_id reachable, to a frame with ``doc_id`` and ``fp``."""
    distinct = keep(marked.groupBy("fp").agg(F.min("doc_id").alias("first")), "distinct")
    root = graph.components(forest(distinct, threshold, block))
    own = distinct.join(root.select(F.col("node").alias("fp"), "root"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = own.groupBy("root").agg(F.min("first").alias("component_id"))
    return marked.join(own.join(least, "root").select("fp", "component_id"), "fp")
