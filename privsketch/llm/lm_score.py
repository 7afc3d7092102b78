"""Language-model scoring: code length of every document under a frozen byte-context trie, beside an add-one word baseline.

The model is prediction by partial matching over one byte stream a document: its lower-cased words with one space between, then
an end mark. Contexts are the ``order`` bytes before, across words, whatever the size of the input; an unseen symbol costs an escape
and is looked for in the next shorter context without the symbols already ruled out (``ppm``). Escapes follow method D: half a count
of every symbol seen goes to the escape. ``score`` is the log10 probability of the stream. Null and empty texts are the end mark alone.

Documents go to buckets by a hash of id and text. A bucket sends its distinct words and distinct full contexts (of training and held-out
documents, with training counts), packed by hash range and compressed; the task of a range adds them up over all buckets and returns
every bucket the counts of its words in the order received. Each distinct context and symbol is then priced once: those that share the
last two context bytes meet in one task, which holds the trie of that branch; the levels above (65,792 entries at most) are the one
broadcast. Prices go back over the ranges to the buckets that asked, which add them up along their texts. Neither the driver nor a task
holds the whole trie; a task holds the distinct strings of one range or branch. A bucket sends a range at most one message, and never
more messages than it has distinct words and contexts, so messages grow in proportion to the input at most.

Without training documents N and V are 0 and bytes are equally likely. Rows with a null doc_id are training rows. Repeated rows count
and are scored each; equal texts get equal scores. A text is held in memory whole, beside eight bytes a byte of a part of it.
An empty table gives an empty result. Columns other than ``doc_id`` and ``text`` are not read and may have any name.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import ppm
from ._util import HashTable, drop, free_shuffles, keep, lower_ascii, ship, tabled, tokens, width
from .language_id import held_out

ORDER, HOLD, SLICE = 5, (7, 2), 1_000_000
_LOG = np.log10(2)
SENT = "part int, bucket int, words string, counts binary, contexts binary"
BACK = "kind int, part int, bucket int, one binary, tokens long, known long, strings long"
BRANCH = "branch int, part int, one binary"
#: Distinct full contexts a branch task is cut for.
BRANCH_KEYS = 400_000
SCORED = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def squeeze(keys: np.ndarray, counts: np.ndarray) -> bytes:
    """Sorted keys with their counts, as bytes of equal weight side by side, compressed."""
    both = np.concatenate([np.diff(keys, prepend=np.uint64(0)), counts.astype(np.uint64)])
    return zstandard.compress(both.view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def expand(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    both = np.ascontiguousarray(np.frombuffer(zstandard.decompress(data), np.uint8).reshape(8, -1).T).view(np.uint64).ravel()
    n = len(both) // 2
    return np.cumsum(both[:n], dtype=np.uint64), both[n:].astype(np.int64)


class Words:
    """Distinct words of a bucket's texts, in an order that depends on the texts alone, cut by hash range."""

    def __init__(self, texts: list[str], ranges: int):
        at: dict[str, int] = {}
        put, place, self.streams = at.setdefault, [], []
        for t in texts:
            words = tokens(lower_ascii(t))
            place.append(np.array([put(w, len(at)) for w in words], np.int32))
            self.streams.append(" ".join(words).encode("utf-8", "surrogatepass"))
        self.place = np.concatenate(place) if place else np.zeros(0, np.int32)
        self.sizes = np.fromiter(map(len, place), np.int64, len(place))
        self.owner = np.repeat(np.arange(len(place), dtype=np.int32), self.sizes)
        self.words = list(at)
        part = np.fromiter((zlib.crc32(w.encode("utf-8", "surrogatepass")) for w in self.words), np.int64, len(self.words)) % ranges
        self.own = by_value(part)

    def parts(self):
        """(range, word numbers) of each range with words."""
        return self.own


def by_value(values: np.ndarray) -> list[tuple[int, np.ndarray]]:
    """(value, positions in order) of each value that occurs."""
    order = np.argsort(values, kind="stable")
    head = np.flatnonzero(np.r_[True, np.diff(values[order]) != 0])[: len(values)]
    return [(int(values[own[0]]), own) for own in np.split(order, head[1:]) if len(own)]


def in_order(batches, columns: list[str]) -> list[list]:
    """Columns of a bucket, its rows sorted by doc_id (nulls first) and text; both visits of a bucket see one order."""
    cols = [[x for b in batches for x in b.column(c).to_pylist()] for c in columns]
    ids, texts = cols[columns.index("doc_id")], cols[columns.index("text")]
    order = sorted(range(len(ids)), key=lambda i: (ids[i] is not None, ids[i] or 0, texts[i]))
    return [[c[i] for i in order] for c in cols]


def sliced(texts: list[bytes], most: int = SLICE):
    """Runs of texts of about ``most`` bytes (one text at least)."""
    at, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield texts[at:i]
            at, size = i, 0
        size += len(t)
    if at < len(texts):
        yield texts[at:]


def contexts_of(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts of full contexts over many texts, in bounded memory."""
    keys, counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    for some in sliced(texts, 2 * SLICE):
        k, c = ppm.stream_counts(some, order)
        keys, counts = ppm.tally(np.r_[keys, k], np.r_[counts, c]) if len(keys) else (k, c)
    return keys, counts


def bucketed(rows: DataFrame, buckets: int) -> DataFrame:
    return rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "text"), F.lit(buckets)).cast("int"))


def extent(rows: DataFrame) -> tuple[int, int]:
    """Bytes of all texts and training documents."""
    got = rows.agg(F.sum(F.octet_length("text")), F.count_if(~F.col("held_out"))).first()
    return got[0] or 0, got[1] or 0


def bucket_count(spark, size: int) -> int:
    """Buckets of about 8 MB of text, and no fewer than the session's shuffle partitions."""
    return max(width(spark), -(-size // 8_000_000))


def range_of(keys: np.ndarray, ranges: int) -> np.ndarray:
    return ((keys * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) % np.uint64(ranges)).astype(np.int64)


def branch_of(keys: np.ndarray, branches: int) -> np.ndarray:
    """Branch of each full context: a hash of its last two bytes, which all its suffixes of two bytes or more share."""
    return range_of((keys >> np.uint64(8)) & np.uint64(0xFFFF), branches)


def _batch(fields: str, **values) -> pa.RecordBatch:
    """One row; columns without a value are null."""
    kinds = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    names = [f.split() for f in fields.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([values.get(n)], kinds[k]) for n, k in names], names=[n for n, _ in names])


def _doubles(values: np.ndarray) -> bytes:
    return zstandard.compress(values.view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def _read_doubles(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zstandard.decompress(data), np.uint8).reshape(8, -1).T).view(float).ravel()


def sent(rows: DataFrame, ranges: int, order: int) -> DataFrame:
    """What the buckets say to the ranges: their distinct words and full contexts with training counts (0: in held-out documents only)."""

    def send(key, batches):
        _, texts, held = in_order(list(batches), ["doc_id", "text", "held_out"])
        w = Words(texts, ranges)
        train = ~np.array(held, bool)
        count = np.bincount(w.place[train[w.owner]], minlength=len(w.words))
        keys, many = contexts_of([t for t, ok in zip(w.streams, train.tolist(), strict=True) if ok], order)
        asked, _ = contexts_of([t for t, ok in zip(w.streams, train.tolist(), strict=True) if not ok], order)
        keys, many = ppm.tally(np.r_[keys, asked], np.r_[many, np.zeros(len(asked), np.int64)])
        words, strings = dict(w.parts()), dict(by_value(range_of(keys, ranges)))
        none = np.zeros(0, np.int64)
        for p in sorted(words.keys() | strings.keys()):
            some, at = words.get(p, none), strings.get(p, none)
            yield _batch(SENT, part=p, bucket=key[0].as_py(), words="\n".join([w.words[i] for i in some.tolist()]), counts=count[some].astype(np.int64).tobytes(), contexts=squeeze(keys[at], many[at]))

    return rows.select("bucket", "doc_id", "text", "held_out").groupBy("bucket").applyInArrow(tabled(send, SENT), SENT)


def added_up(messages: DataFrame) -> DataFrame:
    """``kind`` 0: counts of a bucket's words, back to it; 1: contexts of a range; 2: training words, distinct ones, distinct contexts."""

    def add_up(key, batches):
        part, got = key[0].as_py(), []
        for b in batches:
            got += zip(*(b.column(c).to_pylist() for c in ("bucket", "words", "counts", "contexts")), strict=True)
        at: dict[str, int] = {}
        some = [(bucket, np.array([at.setdefault(w, len(at)) for w in text.split("\n")]), np.frombuffer(c, np.int64)) for bucket, text, c, _ in got if c]
        total = np.zeros(len(at), np.int64)
        for _, i, c in some:
            total[i] += c
        for bucket, i, _ in some:
            yield _batch(BACK, kind=0, part=part, bucket=bucket, one=total[i].tobytes())
        keys, counts = ppm.tally(*(np.concatenate(x) for x in zip(*(expand(t) for *_, t in got), strict=True)))
        yield _batch(BACK, kind=2, part=part, tokens=int(total.sum()), known=int((total > 0).sum()), strings=len(keys))
        if len(keys):
            yield _batch(BACK, kind=1, part=part, one=squeeze(keys, counts))

    return messages.groupBy("part").applyInArrow(tabled(add_up, BACK), BACK)


def upper_levels(sums: DataFrame, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Tagged keys and counts of the contexts of at most one byte: 65,792 entries at most, whatever the input."""
    top = min(order, 1)

    def marginals(batches):
        for b in batches:
            for one in b.column("one").to_pylist():
                keys, counts = expand(one)
                keys, counts = ppm.shorter(*ppm.tally(keys[counts > 0] & np.uint64((1 << 8 * (top + 1)) - 1), counts[counts > 0]), top)
                yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int64)), pa.array(counts.astype(np.int64))], names=["key", "many"])

    got = sums.select("one").mapInArrow(marginals, "key long, many long").groupBy("key").agg(F.sum("many").alias("many")).collect()
    return np.array([r[0] for r in got], np.uint64), np.array([r[1] for r in got], np.int64)


def model_of(keys: np.ndarray, counts: np.ndarray, upper: tuple[np.ndarray, np.ndarray], order: int) -> ppm.Model:
    """Trie of one branch: contexts of two bytes and more from its full contexts, those above as given. Counts are doubled less one, so
    that half a count of each symbol goes to the escape."""
    keys, counts = ppm.shorter(keys, counts, order)
    deep = keys >> np.uint64(56) > 1
    return ppm.Model(np.r_[upper[0], keys[deep]], 2 * np.r_[upper[1], counts[deep]] - 1, order)


def priced(sums: DataFrame, upper: tuple[np.ndarray, np.ndarray], branches: int, order: int) -> DataFrame:
    """Bits of every distinct full context and symbol, by range and branch, in the order of the range's keys."""
    shared = sums.sparkSession.sparkContext.broadcast(upper)

    def split(batches):
        for b in batches:
            for part, one in zip(b.column("part").to_pylist(), b.column("one").to_pylist(), strict=True):
                keys, counts = expand(one)
                for branch, at in by_value(branch_of(keys, branches)):
                    yield _batch(BRANCH, branch=branch, part=part, one=squeeze(keys[at], counts[at]))

    def price(key, batches):
        got = [x for b in batches for x in zip(b.column("part").to_pylist(), b.column("one").to_pylist(), strict=True)]
        keys, counts = (np.concatenate(x) for x in zip(*(expand(one) for _, one in got), strict=True))
        model = model_of(*ppm.tally(keys[counts > 0], counts[counts > 0]), shared.value, order)
        for part, one in got:
            yield _batch(BRANCH, branch=key[0].as_py(), part=part, one=_doubles(model.costs(expand(one)[0])))

    return sums.select("part", "one").mapInArrow(split, BRANCH).groupBy("branch").applyInArrow(tabled(price, BRANCH), BRANCH)


def answered(messages: DataFrame, prices: DataFrame, branches: int) -> DataFrame:
    """``kind`` 1: bits of a bucket's contexts of a range, in the order in which the bucket sent them."""
    fields = "kind int, part int, bucket int, one binary"

    def answer(key, left, right):
        part = key[0].as_py()
        asked = [(k, expand(c)[0]) for b in left for k, c in zip(b.column("bucket").to_pylist(), b.column("contexts").to_pylist(), strict=True)]
        every = np.unique(np.concatenate([k for _, k in asked]))
        bits, own = np.zeros(len(every)), dict(by_value(branch_of(every, branches)))
        for b in right:
            for branch, one in zip(b.column("branch").to_pylist(), b.column("one").to_pylist(), strict=True):
                bits[own[branch]] = _read_doubles(one)
        for bucket, keys in asked:
            if len(keys):
                yield _batch(fields, kind=1, part=part, bucket=bucket, one=_doubles(bits[np.searchsorted(every, keys)]))

    return messages.select("part", "bucket", "contexts").groupBy("part").cogroup(prices.groupBy("part")).applyInArrow(tabled(answer, fields, 2), fields)


def score(docs: DataFrame, order: int = ORDER, hold=HOLD, branch_keys: int = BRANCH_KEYS) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score`` of every document."""
    spark = ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("held_out", held_out(*hold))
    size, ends = extent(rows)
    ranges = buckets = bucket_count(spark, size)
    rows = bucketed(rows, buckets)
    messages = keep(sent(rows, ranges, order), "messages")
    free_shuffles(spark)
    back = keep(added_up(messages), "counts")
    free_shuffles(spark)
    told = back.filter("kind = 2").agg(F.sum("tokens"), F.sum("known"), F.sum("strings")).first()
    n, distinct, strings = (int(x or 0) for x in told)
    n, distinct = n + ends, distinct + (ends > 0)
    branches = max(width(spark), min(1 << 16, strings // branch_keys))
    sums = back.filter("kind = 1")
    prices = keep(priced(sums, upper_levels(sums, order), branches, order), "prices")
    replies = keep(answered(messages, prices, branches).unionByName(back.filter("kind = 0").select("kind", "part", "bucket", "one")), "replies")
    for done in (messages, back, prices):
        drop(done)
    free_shuffles(spark)

    def finish(key, left, right):
        ids, texts, held = in_order(left, ["doc_id", "text", "held_out"])
        told = {(k, p): c for b in right for k, p, c in zip(*(b.column(c).to_pylist() for c in ("kind", "part", "one")), strict=True)}
        if not texts:
            return
        w = Words(texts, ranges)
        count = np.zeros(len(w.words), np.int64)
        for p, own in w.parts():
            count[own] = np.frombuffer(told[0, p], np.int64)
        keys, _ = contexts_of(w.streams, order)
        bits = np.zeros(len(keys))
        for p, own in by_value(range_of(keys, ranges)):
            bits[own] = _read_doubles(told[1, p])
        del told
        find = HashTable(keys, np.arange(len(keys)))

        def length(some):
            s = ppm.Stream(some, order)
            step = 1 << 19
            return np.add.reduceat(np.concatenate([bits[find.get(s.keys[i : i + step])] for i in range(0, len(s.keys), step)]), s.starts)

        def per_doc(values):
            return np.bincount(w.owner, values[w.place], len(texts)) if len(w.owner) else np.zeros(len(texts))

        low = np.log10(n + distinct + 1.0)
        base = per_doc(np.log10(count + 1.0) - low) + np.log10(ends + 1.0) - low
        known = per_doc((count > 0).astype(float)).astype(np.int64) + int(ends > 0)
        total = -_LOG * np.concatenate([length(some) for some in sliced(w.streams)])
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(held), pa.array(w.sizes + 1), pa.array(known), pa.array(np.full(len(ids), n, np.int64)), pa.array(base), pa.array(total)], names=[f.split()[0] for f in SCORED.split(", ")])

    return rows.select("bucket", "doc_id", "text", "held_out").groupBy("bucket").cogroup(replies.groupBy("bucket")).applyInArrow(tabled(finish, SCORED, 2), SCORED)
