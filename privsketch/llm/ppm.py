"""Prediction by partial matching over bytes with frozen counts.

A model is a trie of byte contexts. A symbol unseen after its longest known context costs an escape (method C: as many escape
counts as distinct symbols); shorter contexts then exclude the symbols already rejected. As every occurrence is counted at all its
context lengths, a context's symbols also follow its suffix, so what is excluded has a fixed count per context and is stored
with it. Below order zero the remaining byte values are equally likely. The code lengths are exact: over all symbols,
probabilities sum to one in every context.

Two layouts share the trie. Words: a symbol's context is the run of preceding bytes from the word's leading space on, at most
``order`` bytes, and the word ends with a space (``gather``, ``Model.bits``). Streams: a text is coded from its first byte to an end
mark, contexts run across words, and before its start lie end marks (``stream_counts``, ``Model.stream_bits``).
"""

from __future__ import annotations

import numpy as np

from ._util import HashTable

#: Bits of a key: context length, context bytes, symbol.
_TAG = 56
#: Fixed value: the line end closes a text; words never hold it.
END = 10


def layout(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols of all words with their closing space, index inside the word, and first positions."""
    data = np.frombuffer(b" ".join(words) + b" ", np.uint8).astype(np.uint64)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 1
    starts = np.r_[0, np.cumsum(sizes)[:-1]]
    return data, np.arange(len(data)) - np.repeat(starts, sizes), starts


def contexts(data: np.ndarray, index: np.ndarray, order: int):
    """For every context length: the packed context of each position (valid where the length is at most index + 1)."""
    out = [np.zeros(len(data), np.uint64)]
    before = np.r_[np.uint64(32), data]
    for o in range(1, order + 1):
        shifted = np.full(len(data), 32, np.uint64)
        shifted[o - 1 :] = before[: len(data) - o + 1]
        out.append(out[-1] | shifted << np.uint64(8 * (o - 1)))
    return out


def gather(words: list[bytes], weights: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (context, symbol) keys of all lengths up to ``order`` and their weighted counts."""
    if not words:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    data, index, _ = layout(words)
    weight = np.repeat(weights, np.fromiter(map(len, words), np.int64, len(words)) + 1)
    keys, counts = [], []
    for o, ctx in enumerate(contexts(data, index, order)):
        ok = index + 1 >= o
        k, at = np.unique(ctx[ok] << np.uint64(8) | data[ok] | np.uint64(o << _TAG), return_inverse=True)
        keys.append(k)
        counts.append(np.bincount(at, weight[ok]).astype(np.int64))
    return np.concatenate(keys), np.concatenate(counts)


def merge(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    k, at = np.unique(keys, return_inverse=True)
    return k, np.bincount(at, counts, len(k)).astype(np.int64)


class Stream:
    """Texts without end marks, laid end to end with ``order`` of them between: every coded position with its full context."""

    def __init__(self, texts: list[bytes], order: int):
        gap = bytes([END]) * order
        buf = gap + gap.join(texts) + gap + b"\0" * 8
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        ends = np.cumsum(sizes + order) - order  # first end mark of each text, as a window number
        coded = np.ones(len(buf) - 8 - order, bool)
        for o in range(1, order):
            coded[ends[ends + o < len(coded)] + o] = False
        window = np.ndarray((len(coded),), ">u8", buf, 0, (1,))
        self.keys = window[coded].astype(np.uint64) >> np.uint64(56 - 8 * order)
        self.starts = np.cumsum(sizes + 1) - (sizes + 1)


def stream_counts(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct full contexts with their symbol, and their counts; shorter contexts follow from them (``shorter``)."""
    return tally(Stream(texts, order).keys, None)


def tally(keys: np.ndarray, counts: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order with their (added up) counts."""
    if counts is None:
        keys = np.sort(keys)
        head = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
        return keys[head], np.diff(np.r_[head, len(keys)])
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    head = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
    return keys[head], np.add.reduceat(counts, head) if len(head) else counts


def shorter(keys: np.ndarray, counts: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Tagged keys and counts of all context lengths from those of full contexts."""
    out = []
    for o in range(order, -1, -1):
        keys, counts = tally(keys & np.uint64((1 << 8 * (o + 1)) - 1), counts)
        out.append((keys | np.uint64(o << _TAG), counts))
    return np.concatenate([k for k, _ in out]), np.concatenate([c for _, c in out])


class Model:
    """Code lengths (bits) under merged counts of tagged keys."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray, order: int):
        self.order = order
        nodes, of = np.unique(keys >> np.uint64(8), return_inverse=True)
        self.entries, self.nodes = HashTable(keys, np.arange(len(keys))), HashTable(nodes, np.arange(len(nodes)))
        self.count = counts.astype(float)
        self.total = np.bincount(of, counts, len(nodes)).astype(float)
        self.kinds = np.bincount(of, minlength=len(nodes)).astype(float)
        length = (keys >> np.uint64(_TAG)).astype(np.int64)
        deep = np.flatnonzero(length > 0)
        span = ((np.uint64(1) << (np.uint64(8) * length[deep].astype(np.uint64))) - np.uint64(1))
        suffix = (keys[deep] & span) | ((length[deep] - 1).astype(np.uint64) << np.uint64(_TAG))
        upper = self.entries.get(suffix)
        if (upper < 0).any():
            raise ValueError("a context occurs without its suffix")
        self.excluded = np.bincount(of[deep], self.count[upper], len(nodes))
        #: Cost of each entry where its context is the first one asked.
        self.direct = np.log2((self.total[of] + self.kinds[of]) / self.count)

    def bits(self, words: list[bytes]) -> np.ndarray:
        """Exact code length of each word with its closing space."""
        if not words:
            return np.zeros(0)
        data, index, starts = layout(words)
        full = contexts(data, index, self.order)[-1] << np.uint64(8) | data
        return np.add.reduceat(self._costs(full, index + 1), starts)

    def stream_bits(self, texts: list[bytes]) -> np.ndarray:
        """Exact code length of each text with its end mark, contexts across words."""
        if not texts:
            return np.zeros(0)
        s = Stream(texts, self.order)
        return np.add.reduceat(self.costs(s.keys), s.starts)

    def costs(self, full: np.ndarray, batch: int = 1 << 19) -> np.ndarray:
        """Bits of each symbol after its context of full length."""
        return np.concatenate([self._costs(full[i : i + batch], None) for i in range(0, len(full), batch)]) if len(full) else np.zeros(0)

    def _costs(self, full: np.ndarray, reach: np.ndarray | None) -> np.ndarray:
        """Bits of each symbol; ``full``: context of full length and symbol, of which the last ``reach`` bytes count (None: all)."""
        cost, child, open_ = np.zeros(len(full)), np.full(len(full), -1, np.int64), np.arange(len(full))
        for o in range(self.order, -1, -1):
            try_ = open_ if reach is None else open_[reach[open_] >= o]
            if not len(try_):
                continue
            key = full[try_] & np.uint64((1 << 8 * (o + 1)) - 1) | np.uint64(o << _TAG)
            entry = self.entries.get(key)
            first = (child[try_] < 0) & (entry >= 0)
            cost[try_[first]] = self.direct[entry[first]]
            done = np.zeros(len(full), bool)
            done[try_[first]] = True
            rest = np.flatnonzero(~first)
            node = self.nodes.get(key[rest] >> np.uint64(8))
            rest, node = rest[node >= 0], node[node >= 0]
            at, entry = try_[rest], entry[rest]
            low = child[at]
            had = low >= 0
            total = self.total[node] - np.where(had, self.excluded[low], 0)
            kinds = self.kinds[node] - np.where(had, self.kinds[low], 0)
            hit = entry >= 0
            cost[at[hit]] += np.log2((total[hit] + kinds[hit]) / self.count[entry[hit]])
            miss = ~hit & (kinds > 0)
            cost[at[miss]] += np.log2((total[miss] + kinds[miss]) / kinds[miss])
            child[at] = node
            done[at[hit]] = True
            open_ = open_[~done[open_]]
        if len(open_):
            root = self.nodes.get(np.zeros(1, np.uint64))[0]
            cost[open_] += np.log2(max(1.0, 256 - (self.kinds[root] if root >= 0 else 0)))
        return cost
