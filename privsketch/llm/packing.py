"""Packing by non-negative least squares over shallow length combinations.

Every task fills windows shard by shard (a shard is a run of documents with a bounded number of ids, so memory is bounded and
nothing is shuffled). Whole windows are cut off long documents first. For the remainders, all pairs and triples of present
lengths that fill a window exactly (at most ``window**2 / 12`` or so, 350,549 for 2048) are the columns of a system against the
length histogram; its non-negative least-squares solution, rounded so that running sums keep their size and held to what is there,
says how often each combination is used. What is left is packed greedily end to end and cut at window borders, so a shard has at most
one window with padding.

Null and empty texts are one end mark. Sequence numbers are unique over the table: task number, then position in the task. Documents
of equal length are interchangeable: the last one read is used first. Repeated rows are packed each by itself, under the same
doc_id (null stays null). An empty table gives an empty result; other columns of the input are not read and may have any name. A text
of any length is cut into whole windows; memory is in proportion to the longest text and the shard.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from ._util import Recent, only, ship, slices
from .token_counts import _CHUNK, _ODD, CACHE, WordCounter

WINDOW, END, SHARD_IDS = 2048, 1, 4_000_000


class WordIds:
    """Little-endian ids of texts, remembered chunk by chunk (no match crosses white space): merged rank by rank as for token
    counts, with the library itself for chunks that hold a special string."""

    def __init__(self, path: str):
        self.path, self.counter, self.known = path, WordCounter(path), Recent(CACHE)

    def learn(self, chunks: list[str]) -> None:
        special = [c for c in chunks if "<|" in c and self.counter.specials.search(c)]
        if special:
            from tokenizers import Tokenizer

            library = Tokenizer.from_file(self.path)
            self.known.now.update((c, np.array(library.encode(c, add_special_tokens=False).ids, "<u4").tobytes()) for c in special)
            chunks = list(set(chunks) - set(special))
        ids, counts, per = self.counter.symbols(chunks)
        data = ids.astype("<u4").tobytes()
        end = np.cumsum(counts * 4).tolist()
        word = [data[a:b] for a, b in zip([0, *end], end, strict=False)]
        self.known.now.update(zip(chunks, (word[p[0]] if len(p) == 1 else b"".join([word[w] for w in p]) for p in per), strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        split = [_CHUNK.findall(t) if _ODD.search(t) else t.split() for t in texts]
        if new := self.known.missing(set().union(*split)):
            self.learn(new)
        get = self.known.now.__getitem__
        return [b"".join(map(get, s)) for s in split]


def combinations(present: np.ndarray, window: int) -> np.ndarray:
    """All rows of three lengths (0: unused) from ``present`` that sum to the window, the longest first."""
    has = np.zeros(window + 1, bool)
    has[present] = True
    big = present[2 * present >= window]
    big = big[has[window - big]]
    rows = [np.stack([big, window - big, np.zeros_like(big)], 1)]
    for a in present[3 * present >= window].tolist():
        b = present[np.searchsorted(present, -(-(window - a) // 2)) : np.searchsorted(present, min(a, window - a - 1), side="right")]
        b = b[has[window - a - b]]
        if len(b):
            rows.append(np.stack([np.full_like(b, a), b, window - a - b], 1))
    return np.concatenate(rows)


def solve(columns: np.ndarray, histogram: np.ndarray, rounds: int = 60) -> np.ndarray:
    """Non-negative least squares by multiplicative steps: every step keeps signs and lowers the squared error."""
    size = len(histogram)
    parts = [np.ascontiguousarray(c, np.int32) for c in columns.T]
    target = histogram.astype(float)
    target[0] = 0.0  # an unused third part
    pull = sum(target[c] for c in parts)
    x = np.full(len(columns), 0.1)
    for _ in range(rounds):
        made = sum(np.bincount(c, x, size) for c in parts)
        made[0] = 0.0
        x *= pull / np.maximum(sum(made[c] for c in parts), 1e-12)
    return x


def whole(x: np.ndarray) -> np.ndarray:
    """Counts whose running sums are those of ``x``, rounded: many small shares add up instead of vanishing one by one."""
    return np.diff(np.floor(np.cumsum(x) + 0.5), prepend=0).astype(int)


def pack(sizes: np.ndarray, window: int = WINDOW) -> list[tuple[int, int, int, int, int]]:
    """``(document, start, length, sequence, offset)`` of every piece; sizes are positive."""
    out, seq = [], 0
    for d in np.flatnonzero(sizes >= window).tolist():
        for start in range(0, int(sizes[d]) // window * window, window):
            out.append((d, start, window, seq, 0))
            seq += 1
    rest = sizes % window
    order = np.argsort(rest, kind="stable")
    order = order[rest[order] > 0]
    heap = {int(n): ds.tolist() for n, ds in zip(*_runs(rest[order], order), strict=True)}
    histogram = np.bincount(rest[order], minlength=window + 1)
    present = np.flatnonzero(histogram)
    columns = combinations(present, window)
    if len(columns):
        wish = whole(solve(columns, histogram))
        used = np.flatnonzero(wish)
        for i in used[np.argsort(-wish[used], kind="stable")].tolist():
            parts = [int(n) for n in columns[i] if n]
            for _ in range(wish[i]):
                if any(len(heap[n]) < parts.count(n) for n in parts):
                    break
                at = 0
                for n in parts:
                    d = heap[n].pop()
                    out.append((d, int(sizes[d]) - n, n, seq, at))
                    at += n
                seq += 1
    for n in sorted(heap, reverse=True):  # what rounding left: two lengths that fill a window, while there are
        while heap[n] and (other := heap.get(window - n)) and (len(other) > 1 or n * 2 != window):
            a, b = heap[n].pop(), other.pop()
            out += [(a, int(sizes[a]) - n, n, seq, 0), (b, int(sizes[b]) - (window - n), window - n, seq, n)]
            seq += 1
    at = 0
    for n in sorted(heap, reverse=True):
        for d in heap[n]:
            start = int(sizes[d]) - n
            while start < sizes[d]:
                take = min(window - at, int(sizes[d]) - start)
                out.append((d, start, take, seq, at))
                start, at = start + take, at + take
                if at == window:
                    seq, at = seq + 1, 0
    return out


def _runs(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    at = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, int)
    return keys[at], np.split(values, at[1:]) if len(at) else []


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack_documents(docs: DataFrame, path: str, window: int = WINDOW, with_ids: bool = False) -> DataFrame:
    """One row per piece; ``with_ids`` adds the piece's ids as ``array<int>``."""
    ship(docs.sparkSession)

    def work(batches):
        source = only(("ids", path), lambda: WordIds(path))
        base, done = TaskContext.get().partitionId() << 40, 0
        names, codes, total = [], [], 0

        def flush():
            nonlocal names, codes, total, done
            pieces = pack(np.array([len(c) // 4 for c in codes], np.int64), window)
            rows = [(names[d], s, n, zlib.crc32(codes[d][4 * s : 4 * (s + n)]), len(codes[d]) // 4, base + done + q, o) for d, s, n, q, o in pieces]
            ids = [np.frombuffer(codes[d], "<u4", n, 4 * s).astype(np.int32) for d, s, n, _, _ in pieces] if with_ids else None
            done += 1 + max(q for *_, q, _ in pieces)
            names, codes, total = [], [], 0
            for at in range(0, len(rows), 20_000):
                cols = [pa.array(c, pa.int64()) for c in zip(*rows[at : at + 20_000], strict=True)]
                if ids is not None:
                    cols.append(pa.array(ids[at : at + 20_000], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in SCHEMA.split(", ")] + ["ids"] * with_ids)

        for batch, texts in slices(batches, limit=4 << 20):
            end = np.array([END], "<u4").tobytes()
            for name, code in zip(batch.column("doc_id").to_pylist(), source.encode(texts), strict=True):
                names.append(name)
                codes.append(code + end)
                total += len(code) // 4 + 1
                if total >= SHARD_IDS:
                    yield from flush()
        if codes:
            yield from flush()

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, SCHEMA + ", ids array<int>" * with_ids)
