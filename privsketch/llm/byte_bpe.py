"""Byte-level BPE encoding and decoding by prefix dynamic programming.

For every byte prefix of a piece exactly one vocabulary entry can end its encoding: the entry whose left remainder is itself
encoded with a last entry that does not merge into it. The table of those last entries is filled from left to right;
reading it backwards gives the encoding. Appending bytes extends the table. An edit fills the table anew from the edit on, until
it agrees with the old one for as many bytes as the longest entry has; from there on the old entries hold (``PrefixTable``).

Null and empty texts have no ids (the digest of the empty string). Texts are cut by the given pattern first and every match is
encoded by itself; a piece of any length needs memory in proportion to its bytes. The decoded bytes are looked up id by id, so
a byte that the pattern or the encoder lost would show in their digest. Every row, repeated ones too, gives one row; an
empty table gives an empty result; other columns of the input are not read and may have any name.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from ._util import HashTable, Recent, Settled, only, ship, slices

CACHE = 400_000
_P = np.uint64(0x9E3779B97F4A7C15 | 1)


class Vocabulary:
    """Ranks of byte strings with, for each entry, the two entries whose merge makes it."""

    def __init__(self, path: str):
        self.rank: dict[bytes, int] = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
        self.size = max(self.rank.values()) + 1
        self.bytes_of: list[bytes] = [b""] * self.size
        for k, v in self.rank.items():
            self.bytes_of[v] = k
        self.longest = max(map(len, self.rank))
        self.left = np.arange(self.size)
        self.right = np.arange(self.size)
        for k, v in self.rank.items():
            if len(k) > 1:
                self.left[v], self.right[v] = self._last_merge(k, v)
        made = np.flatnonzero(self.left != np.arange(self.size))
        self.pairs = HashTable(self._pair(self.left[made], self.right[made]), made)
        self.pair_rank = dict(zip(zip(self.left[made].tolist(), self.right[made].tolist(), strict=True), made.tolist(), strict=True))
        self.memo: dict[tuple[int, int], bool] = {}
        short = [k for k in self.rank if len(k) <= MATRIX]
        self.by_hash = HashTable(np.array([_hash(k) for k in short], np.uint64), np.array([self.rank[k] for k in short]))

    def _last_merge(self, key: bytes, rank: int) -> tuple[int, int]:
        parts = [key[i : i + 1] for i in range(len(key))]
        while len(parts) > 2:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get(parts[i] + parts[i + 1], 1 << 60))
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return self.rank[parts[0]], self.rank[parts[1]]

    def _pair(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return a.astype(np.uint64) * np.uint64(self.size) + b.astype(np.uint64)

    def stable(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether entry ``b`` right after ``a`` leaves both whole: their merges are undone, latest first, and at no point
        in time may the two symbols that touch have an earlier merge than the ones undone."""
        a, b = a.copy(), b.copy()
        until = np.full(len(a), self.size + 1)
        out = np.zeros(len(a), bool)
        live = np.arange(len(a))
        while len(live):
            x, y, t = a[live], b[live], until[live]
            joint = self.pairs.get(self._pair(x, y))
            clash = (joint >= 0) & (joint < t)
            basic_x, basic_y = self.left[x] == x, self.left[y] == y
            turn_x = (~basic_x & (basic_y | (x > y)))
            done = basic_x & basic_y & ~clash
            out[live[done]] = True
            until[live] = np.where(turn_x, x, y + 1)
            a[live] = np.where(turn_x, self.right[x], x)
            b[live] = np.where(~turn_x & ~basic_y, self.left[y], y)
            live = live[~clash & ~done]
        return out

    def stable_one(self, a: int, b: int) -> bool:
        key = (a, b)
        got = self.memo.get(key)
        if got is None:
            if len(self.memo) > 1_000_000:
                self.memo.clear()
            got = self.memo[key] = bool(self.stable(np.array([a]), np.array([b]))[0])
        return got


MATRIX = 24  # pieces up to this many bytes go through the vectorised table


def _hash(key: bytes) -> int:
    h = 0
    for c in key:
        h = (h * int(_P) + c + 1) & (2**64 - 1)
    return h


class PrefixTable:
    """Last entry of the encoding of every prefix of one piece; grows by appends, and an edit refills what it changes."""

    def __init__(self, vocabulary: Vocabulary, data: bytes = b""):
        self.vocabulary, self.data, self.last = vocabulary, b"", []
        self.append(data)

    def _entry(self, end: int) -> int:
        """Last entry of the prefix of ``end`` bytes, from those of shorter prefixes."""
        v = self.vocabulary
        for begin in range(max(0, end - v.longest), end):
            token = v.rank.get(self.data[begin:end])
            if token is not None and (begin == 0 or v.stable_one(self.last[begin - 1], token)):
                return token
        raise ValueError("a byte of the piece is not in the vocabulary")

    def append(self, more: bytes) -> None:
        start = len(self.data)
        self.data += more
        for end in range(start + 1, len(self.data) + 1):
            self.last.append(self._entry(end))

    def edit(self, at: int, removed: int, data: bytes) -> int:
        """Replace ``removed`` bytes from ``at`` on by ``data``; returns how many entries were filled anew.

        An entry depends on the bytes and entries of the ``longest`` places before it. Once so many entries in a row, all
        of them that far behind the edit and the start, are the old ones, the rest of the old table follows unchanged."""
        if not 0 <= at <= at + removed <= len(self.data):
            raise ValueError("the edit lies outside the piece")
        old, tail = self.last, self.data[at + removed :]
        moved, reach = len(data) - removed, self.vocabulary.longest
        self.data, self.last = self.data[:at] + data + tail, old[:at]
        safe, alike = max(at + len(data) + reach, reach, reach + moved), 0
        for end in range(at + 1, len(self.data) + 1):
            self.last.append(self._entry(end))
            alike = alike + 1 if end > at + len(data) and self.last[-1] == old[end - moved - 1] else 0
            if end >= safe and alike >= reach:
                self.last += old[end - moved :]
                return end - at
        return len(self.data) - at

    def ids(self, end: int | None = None) -> list[int]:
        """Encoding of the prefix of ``end`` bytes (default: all)."""
        at, out = len(self.data) if end is None else end, []
        while at:
            out.append(self.last[at - 1])
            at -= len(self.vocabulary.bytes_of[out[-1]])
        return out[::-1]


def encode_pieces(v: Vocabulary, pieces: list[bytes]) -> list[list[int]]:
    """Ids of each piece; the tables of all short pieces are filled together, one prefix length at a time."""
    out: list[list[int] | None] = [None] * len(pieces)
    short = []
    for i, p in enumerate(pieces):
        whole = v.rank.get(p)
        if whole is not None:
            out[i] = [whole]
        elif len(p) <= MATRIX:
            short.append(i)
        else:
            out[i] = PrefixTable(v, p).ids()
    short.sort(key=lambda i: -len(pieces[i]))
    for at in range(0, len(short), 20_000):
        _fill(v, pieces, short[at : at + 20_000], out)
    return out


def _fill(v: Vocabulary, pieces: list[bytes], group: list[int], out: list) -> None:
    sizes = np.array([len(pieces[i]) for i in group])
    n, width = len(group), int(sizes[0])
    data = np.frombuffer(b"".join(pieces[i].ljust(width, b"\0") for i in group), np.uint8).reshape(n, width).astype(np.uint64)
    prefix = np.zeros((n, width + 1), np.uint64)
    for i in range(width):
        prefix[:, i + 1] = prefix[:, i] * _P + data[:, i] + np.uint64(1)
    power = [np.uint64(1)]
    for _ in range(width):
        power.append(np.uint64(int(power[-1]) * int(_P) & (2**64 - 1)))
    last = np.zeros((n, width + 1), np.int64)
    size_of = np.zeros((n, width + 1), np.int64)
    for end in range(1, width + 1):
        rows = int(np.searchsorted(-sizes, -end, side="right"))  # sorted by falling size
        if not rows:
            break
        who, token, begin = [], [], []
        for b in range(end):
            found = v.by_hash.get(prefix[:rows, end] - prefix[:rows, b] * power[end - b])
            hit = np.flatnonzero(found >= 0)
            who.append(hit)
            token.append(found[hit])
            begin.append(np.full(len(hit), b))
        who, token, begin = np.concatenate(who), np.concatenate(token), np.concatenate(begin)
        fits = begin == 0
        rest = np.flatnonzero(~fits)
        fits[rest] = v.stable(last[who[rest], begin[rest]], token[rest])
        last[who[fits], end] = token[fits]
        size_of[who[fits], end] = end - begin[fits]
    at = sizes.copy()
    steps = []
    rows = np.arange(n)
    while True:
        live = at > 0
        if not live.any():
            break
        took = size_of[rows, at]
        steps.append(np.where(live, last[rows, at], -1))
        at = at - np.where(live, took, 0)
    table = np.stack(steps[::-1], axis=1).tolist()
    for i, row in zip(group, table, strict=True):
        out[i] = [t for t in row if t >= 0]


_WIDE = regex.compile(r"\s{2}|[^\S \n]|^\s|\s$")


class TextCodec:
    """Encodes whole texts. A text whose white space is single spaces and line ends falls into chunks (a space or line end and
    what follows) that no match of the pattern crosses; the ids of distinct chunks are remembered."""

    def __init__(self, path: str, pattern: str):
        self.v, self.pattern = Vocabulary(path), regex.compile(pattern)
        self.known, self.settled, self.kinds, self.probes = Recent(CACHE), Settled(), {}, None

    def stand_in(self, c: str) -> str:
        """A character of the class that the library gives to ``c``: it drops what a one-class pattern does not match."""
        if self.probes is None:
            import tiktoken

            ranks = {bytes([i]): i for i in range(256)}
            self.probes = {x: tiktoken.Encoding(f"probe{i}", pat_str=p, mergeable_ranks=ranks, special_tokens={}) for i, (x, p) in enumerate((("a", r"\p{L}"), ("0", r"\p{N}"), ("\t", r"\s")))}
        got = self.kinds.get(c)
        if got is None:
            got = self.kinds[c] = next((x for x, e in self.probes.items() if e.encode_ordinary(c)), "!")
        return got

    def matches(self, text: str) -> list[str]:
        """Matches of the pattern; characters of disputed class are read as the library reads them."""
        if self.settled(text):
            return self.pattern.findall(text)
        young = self.settled.young
        plain = "".join([self.stand_in(c) if c in young else c for c in text])
        return [text[m.start() : m.end()] for m in self.pattern.finditer(plain)]

    def ids(self, text: str) -> list[int]:
        return [t for p in encode_pieces(self.v, [m.encode("utf-8", "surrogatepass") for m in self.matches(text)]) for t in p]

    def decode(self, ids: list[int]) -> bytes:
        of = self.v.bytes_of
        return b"".join([of[t] for t in ids])

    def chunks(self, text: str) -> list[str]:
        if not text:
            return []
        if _WIDE.search(text):
            return ["\0" + m for m in self.matches(text)]
        first, *rest = text.replace("\n", " \n").split(" ")
        return ["\0" + first, *rest]

    def learn(self, chunks: list[str]) -> None:
        """A chunk stands for a space and itself, or for itself after a leading NUL mark or line end."""
        per, pieces = [], {}
        for c in chunks:
            text = c[1:] if c[0] == "\0" else c if c[0] == "\n" else " " + c
            per.append([pieces.setdefault(m.encode("utf-8", "surrogatepass"), len(pieces)) for m in self.matches(text)])
        raw = list(pieces)
        codes = encode_pieces(self.v, raw)
        lines, back = [" ".join(map(str, ids)) for ids in codes], [self.decode(ids) for ids in codes]
        self.known.now.update(zip(chunks, ((" ".join([lines[p] for p in at]), b"".join([back[p] for p in at])) for at in per), strict=True))

    def digest(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """``(n_tokens, sha256 of the ids, sha256 of the decoded bytes)`` of each text; ids and what they decode to are
        remembered by chunk, and a text's decoded bytes are those of its chunks' ids in order."""
        split = [self.chunks(t) for t in texts]
        if new := self.known.missing(set().union(*split)):
            self.learn(new)
        out, get = [], self.known.now.__getitem__
        for parts in split:
            lines, back = zip(*map(get, parts), strict=True) if parts else ((), ())
            ids = " ".join(lines)
            out.append((ids.count(" ") + 1 if ids else 0, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(b"".join(back)).hexdigest()))
        return out


def codec(path: str, pattern: str) -> TextCodec:
    return only(("codec", path, pattern), lambda: TextCodec(path, pattern))


def encode_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    ship(docs.sparkSession)

    def work(batches):
        c = codec(path, pattern)
        for batch, texts in slices(batches, limit=4 << 20):
            n, a, b = zip(*c.digest(texts), strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(a), pa.array(b)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """General form: ``doc_id, ids array<int>``."""
    ship(docs.sparkSession)

    def work(batches):
        c = codec(path, pattern)
        for batch, texts in slices(batches):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([c.ids(t) for t in texts], pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id, raw binary`` of a frame ``doc_id, ids`` (null: empty)."""
    ship(encoded.sparkSession)

    def work(batches):
        c = codec(path, pattern)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([c.decode(x or []) for x in batch.column("ids").to_pylist()], pa.binary())], names=["doc_id", "raw"])

    return encoded.select("doc_id", "ids").mapInArrow(work, "doc_id long, raw binary")
