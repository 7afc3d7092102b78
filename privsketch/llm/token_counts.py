"""Token counts by rank-synchronous merging over ragged arrays.

Pre-tokens of a batch lie end to end in one array of symbol ids. Each round looks up the rank of every adjacent pair, takes
each sequence's lowest, and applies it everywhere in that sequence at once; sequences without a mergeable pair leave. What is
left is the token count. Distinct white-space chunks are counted once per worker and remembered.

Null and empty texts have no tokens. Special strings inside a text count as one token, as the library does by default. Pairs of equal rank
in a sequence merge from the left. Every row, repeated ones too, gives one row. A text of any length is counted whole. An empty table gives an
empty result. Columns other than ``doc_id`` and ``text`` are not read and may have any name.
"""

from __future__ import annotations

import json
import re
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from ._util import HashTable, Recent, Settled, only, ship, slices

#: The white space that the normaliser's \s stands for.
SPACE = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
_CHUNK = re.compile(f"[^{SPACE}]+")
_ODD = re.compile("[\x1c-\x1f]")
CACHE = 400_000


def byte_letters() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def merge_ranked(ids: np.ndarray, lengths: np.ndarray, ranks: HashTable, merged: np.ndarray, base: int) -> tuple[np.ndarray, np.ndarray]:
    """Symbols that survive in each ragged sequence (all lengths positive), end to end, and how many there are of each."""
    none = len(merged)
    lengths, alive = lengths.astype(np.int64), np.arange(len(lengths))
    counts, ready = np.zeros(len(lengths), np.int64), []

    def rank_of(at: np.ndarray) -> np.ndarray:
        found = ranks.get(ids[at].astype(np.uint64) * np.uint64(base) + ids[at + 1].astype(np.uint64))
        return np.where(found < 0, none, found)

    ends = np.cumsum(lengths) - 1
    inner = np.ones(len(ids), bool)
    inner[ends] = False
    rank = np.full(len(ids), none, np.int64)
    rank[inner] = rank_of(np.flatnonzero(inner))
    while len(alive):
        low = np.minimum.reduceat(rank, np.r_[0, np.cumsum(lengths)[:-1]])
        go = low < none
        if not go.all():
            stay = np.repeat(go, lengths)
            counts[alive[~go]] = lengths[~go]
            ready.append((alive[~go], lengths[~go], ids[~stay]))
            ids, rank, lengths, low, alive = ids[stay], rank[stay], lengths[go], low[go], alive[go]
            if not len(alive):
                break
        hit = np.flatnonzero(rank == np.repeat(low, lengths))
        run = np.cumsum(np.r_[True, np.diff(hit) > 1]) - 1
        first = hit[np.r_[True, np.diff(run) > 0]]
        hit = hit[((hit - first[run]) & 1) == 0]  # of overlapping pairs, the leftmost
        ids[hit] = merged[rank[hit]]
        keep = np.ones(len(ids), bool)
        keep[hit + 1] = False
        owner = np.repeat(np.arange(len(lengths)), lengths)
        lengths = lengths - np.bincount(owner[hit], minlength=len(lengths))
        ids, rank = ids[keep], rank[keep]
        hit = hit - np.arange(len(hit))
        stale = np.zeros(len(ids) + 1, bool)
        stale[hit] = True
        stale[hit - 1] = True  # -1 is the spare place
        stale = stale[:-1]
        rank[stale] = none
        stale[np.cumsum(lengths) - 1] = False
        near = np.flatnonzero(stale)
        rank[near] = rank_of(near)
    out = np.empty(int(counts.sum()), np.int64)
    begin = np.cumsum(counts) - counts
    for who, size, flat in ready:
        out[np.repeat(begin[who] - (np.cumsum(size) - size), size) + np.arange(len(flat))] = flat
    return out, counts


class WordCounter:
    """Counts tokens of a word-end BPE vocabulary file, chunk by chunk."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        vocab, end = spec["model"]["vocab"], spec["model"]["end_of_word_suffix"]
        self.specials = regex.compile("|".join(regex.escape(t["content"]) for t in spec["added_tokens"]))
        self.pattern = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        letters = byte_letters()
        self.first = np.array([vocab[c] for c in letters], np.int64)
        self.last = np.array([vocab[c + end] for c in letters], np.int64)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.base = len(vocab)
        self.ranks = HashTable(np.array([vocab[a] * self.base + vocab[b] for a, b in pairs], np.uint64), np.arange(len(pairs)))
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int64)
        self.known, self.settled, self.path, self.library = Recent(CACHE), Settled(), path, None

    def split_young(self, chunk: str) -> list[str]:
        """Pre-tokens of a chunk with characters of disputed class: the library's own normaliser and splitter say."""
        if self.library is None:
            from tokenizers import Tokenizer

            self.library = Tokenizer.from_file(self.path)
        chunk = self.library.normalizer.normalize_str(chunk)
        return [chunk[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(chunk)]

    def normal(self, text: str) -> str:
        """Composed form, each character lower-cased by itself."""
        if text.isascii():
            return text.lower()
        text = unicodedata.normalize("NFC", text)
        return "".join(c.lower() for c in text) if "Σ" in text else text.lower()

    def symbols(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray, list[tuple[int, ...]]]:
        """Surviving ids of the distinct pre-tokens end to end, their counts, and the pre-tokens of each chunk. Letters with at
        most a comma or full stop behind need no pattern."""
        words: dict[str, int] = {}
        place, per = words.setdefault, []
        text = "\n".join(chunks)  # chunks hold no white space, so all are normalised at once
        young = not self.settled(text)
        lowered = [self.normal(c) for c in chunks] if "Σ" in text else self.normal(text).split("\n")
        for c, own in zip(lowered, chunks, strict=True):
            if young and not own.isascii() and not self.settled(own):
                per.append(tuple([place(w, len(words)) for w in self.split_young(own)]))
            elif c.isalpha():
                per.append((place(c, len(words)),))
            elif c[-1] in ",." and c[:-1].isalpha():
                per.append((place(c[:-1], len(words)), place(c[-1], len(words))))
            else:
                per.append(tuple([place(w, len(words)) for w in self.pattern.findall(c)]))
        raw = "\n".join(words).encode("utf-8", "surrogatepass").split(b"\n") if words else []
        lengths = np.fromiter(map(len, raw), np.int64, len(raw))
        data = np.frombuffer(b"".join(raw), np.uint8)
        ids = self.first[data]
        ends = np.cumsum(lengths) - 1
        ids[ends] = self.last[data[ends]]
        return *merge_ranked(ids, lengths, self.ranks, self.merged, self.base), per

    def learn(self, chunks: list[str]) -> None:
        _, counts, per = self.symbols(chunks)
        count = counts.tolist()
        self.known.now.update(zip(chunks, (count[p[0]] if len(p) == 1 else sum([count[w] for w in p]) for p in per), strict=True))

    def count(self, texts: list[str]) -> list[int]:
        split, extra = [], []
        for t in texts:
            specials = 0
            if "<|" in t:
                specials = len(self.specials.findall(t))
                t = self.specials.sub(" ", t) if specials else t
            split.append(_CHUNK.findall(t) if _ODD.search(t) else t.split())
            extra.append(specials)
        if new := self.known.missing(set().union(*split)):
            self.learn(new)
        get = self.known.now.__getitem__
        return [e + sum(map(get, s)) for e, s in zip(extra, split, strict=True)]


def token_counts(docs: DataFrame, path: str, limit: int = 2048) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` of every document under the vocabulary file at ``path``."""
    ship(docs.sparkSession)

    def work(batches):
        counter = only(("words", path), lambda: WordCounter(path))
        for batch, texts in slices(batches, limit=4 << 20):
            n = np.array(counter.count(texts), np.int64)
            size = [len(t) if t.isascii() else len(t.encode("utf-8", "surrogatepass")) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(size, pa.int64()), pa.array(n), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
