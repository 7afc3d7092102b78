"""Exact removal of repeated passages by blockwise suffix sorting with a difference cover.

A document byte goes when a ``SPAN``-byte string over it also starts in a document with a smaller doc_id. Strings are found in three
passes over blocks of documents.

Later copies of a whole text are found by digest, row by row, and lose everything, so those rows take no part in the passes.

1. Every string contains an anchor: the ``GRAM``-byte window with the least hash. A block sends the distinct anchors of its strings,
   packed by hash range; a range's task answers which occur in more than one document, one bit an anchor.
2. Blocks send the runs of strings with a shared anchor, with their text and smallest document, to the anchor's range. There the text
   of the range is cut in suffix buckets; one bucket at a time its suffixes are sorted: by their first ``PERIOD`` bytes, then long
   ties by ranks of the positions in a difference cover, computed once for the range. A suffix and its neighbour that agree for
   ``SPAN`` bytes are the same string, and its smallest document decides. Only the blocks' ranges to be removed go back.
3. Blocks drop the marked bytes.

Of equal runs of a block only those of its smallest document travel: the others lose all their strings, which their own block knows, so
a passage of very many documents reaches the task of its anchor about once a block. There equal runs are one piece of text with its
smallest document; an anchor with one piece needs no sorting.
Hashes only choose what is compared, the comparison is of bytes. Null and empty texts have nothing to remove. Rows with
the same doc_id are one document as far as origins go (nothing is removed for strings shared among them); rows with a null doc_id
come after all others. A string never crosses a document's end.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._util import drop, free_shuffles, frugal, keep, ship, tabled, trim, width

SPAN, GRAM, PERIOD = 50, 24, 16
#: Residues whose differences give every residue of the period.
COVER = (0, 1, 2, 5, 8)
LAST = (1 << 63) - 1
_M1, _M2, _M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB))


def words_at(buf: bytes, n: int, offset: int) -> np.ndarray:
    """The eight bytes from every position plus ``offset``, little-endian."""
    return np.ndarray((n,), "<u8", buf, offset, (1,))


def window_minima(buf: bytes, n: int, span: int = SPAN) -> np.ndarray:
    """For every position the least hash of the ``GRAM``-byte windows inside the string of ``span`` bytes from there; ``buf`` has
    ``n`` bytes and at least ``span`` bytes of padding."""
    h = words_at(buf, n + span - GRAM, 0) * _M1
    h ^= h >> np.uint64(29)
    h += words_at(buf, n + span - GRAM, 8)
    h *= _M2
    h ^= h >> np.uint64(32)
    h += words_at(buf, n + span - GRAM, 16)
    h *= _M3
    h ^= h >> np.uint64(29)
    width_, have = span - GRAM + 1, 1
    while have < width_:
        step = min(have, width_ - have)
        h = np.minimum(h[:-step], h[step:])
        have += step
    return h[:n]


def runs(texts: list[bytes], span: int = SPAN) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text of a block, first byte of each document, and the runs of strings with one anchor: anchor, start, number of strings."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    begin = np.cumsum(sizes) - sizes
    buf = b"".join(texts) + b"\0" * (span + 8)
    n = len(buf) - span - 8
    if not n:
        return buf, begin, np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    low = window_minima(buf, n, span)
    ok = np.zeros(n, bool)
    first = np.zeros(n + 1, bool)
    for b, s in zip(begin.tolist(), sizes.tolist(), strict=True):
        if s >= span:
            ok[b : b + s - span + 1] = True
            first[b] = True
    change = np.zeros(n, bool)
    change[1:] = low[1:] != low[:-1]
    start = np.flatnonzero(ok & (change | first[:n]))
    stop = np.flatnonzero(np.r_[~ok, True] & np.r_[False, ok])
    end = np.minimum(np.r_[start[1:], n], stop[np.searchsorted(stop, start, side="right")] if len(start) else start)
    anchor = low[start] * _M2  # least values crowd near zero; mixed again they spread evenly over the ranges
    anchor ^= anchor >> np.uint64(32)
    return buf, begin, anchor * _M3, start, end - start


# --- blockwise suffix sorting -------------------------------------------------------------------------------------------


def cover_shift() -> np.ndarray:
    """For two residues, the smallest shift that puts both on the cover."""
    has = np.zeros(PERIOD, bool)
    has[list(COVER)] = True
    out = np.zeros((PERIOD, PERIOD), np.int64)
    for a in range(PERIOD):
        for b in range(PERIOD):
            out[a, b] = next(d for d in range(PERIOD) if has[(a + d) % PERIOD] and has[(b + d) % PERIOD])
    return out


_SHIFT = cover_shift()


def big_words(buf: bytes, at: np.ndarray, offset: int) -> np.ndarray:
    """Eight bytes as numbers that sort like the bytes."""
    n = len(buf) - 8 - offset
    return np.ndarray((n,), ">u8", buf, offset, (1,))[at].astype(np.uint64)


def cover_ranks(buf: bytes, n: int, depth: int) -> np.ndarray:
    """Ranks of the suffixes at cover positions, by prefix doubling over steps of the period until ``depth`` bytes are told apart
    (or all are); -1 elsewhere. ``buf`` has ``n`` bytes and padding of ``depth`` + 16."""
    at = np.flatnonzero(np.isin(np.arange(n) % PERIOD, COVER))
    name = _dense(big_words(buf, at, 0), big_words(buf, at, 8))
    rank = np.full(n + depth + PERIOD + 16, -1, np.int64)
    have = PERIOD
    rank[at] = name
    while have < depth and len(at) and name.max() + 1 < len(at):
        name = _dense((name + 1).astype(np.uint64), (rank[at + have] + 1).astype(np.uint64))
        rank[at] = name
        have *= 2
    return rank


def _dense(high: np.ndarray, low: np.ndarray) -> np.ndarray:
    order = np.lexsort((low, high))
    h, w = high[order], low[order]
    new = np.r_[False, (h[1:] != h[:-1]) | (w[1:] != w[:-1])] if len(h) else np.zeros(0, bool)
    out = np.empty(len(h), np.int64)
    out[order] = np.cumsum(new)
    return out


def sort_bucket(buf: bytes, at: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions sorted as suffixes, and for each whether it is told apart from the one before. Ties of ``PERIOD`` bytes are
    split around a pivot of each group by cover ranks until every group is equal."""
    name = _dense(big_words(buf, at, 0), big_words(buf, at, 8))
    order = np.argsort(name, kind="stable")
    at, name = at[order], name[order]
    new = np.r_[True, name[1:] != name[:-1]] if len(at) else np.zeros(0, bool)
    todo = np.flatnonzero(~(new & np.r_[new[1:], True]))  # members of groups with two or more
    while len(todo):
        head = np.maximum.accumulate(np.where(new, np.arange(len(at)), 0))[todo]
        group = np.cumsum(np.r_[True, head[1:] != head[:-1]]) - 1
        first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        size = np.diff(np.r_[first, len(todo)])
        pivot = at[todo[first + size // 2]][group]
        own = at[todo]
        d = _SHIFT[own % PERIOD, pivot % PERIOD]
        side = np.sign(rank[own + d] - rank[pivot + d])
        order = np.lexsort((side, group))
        at[todo] = own[order]
        side = side[order]
        split = np.r_[False, (side[1:] != side[:-1]) & (group[1:] == group[:-1])]
        new[todo[split]] = True
        again = side != 0  # what equals the pivot is settled
        todo = todo[again]
        if len(todo):
            alone = new[todo] & np.r_[new, True][todo + 1]
            todo = todo[~alone]
    return at, new


def suffix_buckets(buf: bytes, at: np.ndarray, most: int = 1 << 20):
    """Positions by leading bytes, in order, in buckets of about ``most`` (a single pair of bytes is not split further)."""
    lead = big_words(buf, at, 0) >> np.uint64(48)
    order = np.argsort(lead, kind="stable")
    at, lead = at[order], lead[order]
    i = 0
    while i < len(at):
        j = min(len(at), i + most)
        if j < len(at):
            k = int(np.searchsorted(lead, lead[j], side="left"))
            j = k if k > i else int(np.searchsorted(lead, lead[j], side="right"))
        yield at[i:j]
        i = j


def suffix_array(text: bytes, most: int = 1 << 20) -> np.ndarray:
    """General form: the whole suffix array of one text, bucket by bucket."""
    n = len(text)
    buf = bytes(text) + b"\0" * (n + 2 * PERIOD + 24)
    rank = cover_ranks(buf, n, n + 1)
    return np.concatenate([sort_suffixes(buf, a, rank, n) for a in suffix_buckets(buf, np.arange(n), most)]) if n else np.zeros(0, np.int64)


def sort_suffixes(buf: bytes, at: np.ndarray, rank: np.ndarray, n: int) -> np.ndarray:
    """A bucket in suffix order; suffixes that padding makes equal come shortest first."""
    at, new = sort_bucket(buf, at, rank)
    group = np.cumsum(new)
    return at[np.lexsort((-at, group))]


def least_origin(pieces: list[bytes], counts: np.ndarray, origin: np.ndarray, span: int = SPAN) -> np.ndarray:
    """For pieces of text whose first ``counts`` positions start strings: the smallest origin of each string, end to end."""
    gap = span + 2 * PERIOD
    sizes = np.fromiter(map(len, pieces), np.int64, len(pieces)) + 1
    begin = np.cumsum(sizes) - sizes
    buf = b"\0".join(pieces) + b"\0" * (gap + 40)
    n = int(sizes.sum())
    rank = cover_ranks(buf, n, span)
    at = np.repeat(begin - (np.cumsum(counts) - counts), counts) + np.arange(int(counts.sum()))
    who = np.repeat(origin, counts)
    place = np.full(n, -1, np.int64)
    place[at] = np.arange(len(at))
    out = np.empty(len(at), np.int64)
    for bucket in suffix_buckets(buf, at):
        order, _ = sort_bucket(buf, bucket, rank)
        same = np.ones(max(0, len(order) - 1), bool)  # agreement of neighbours for the whole string
        for o in (*range(0, span - 7, 8), span - 8):
            w = big_words(buf, order, o)
            same &= w[1:] == w[:-1]
        head = np.flatnonzero(np.r_[True, ~same])
        low = np.minimum.reduceat(who[place[order]], head)
        out[place[order]] = np.repeat(low, np.diff(np.r_[head, len(order)]))
    return out


# --- the three passes ---------------------------------------------------------------------------------------------------

ANCHORS = "part int, block long, keys binary, many binary"
REPLY = "block long, part int, one binary, two binary"
RUNS = "part int, block long, anchors binary, starts binary, counts binary, owners binary, origins binary, text binary"


#: Places in which the copies of one text are marked.
SALTS = 16


def blocks(docs: DataFrame, carry: list[str], size: int) -> tuple[DataFrame, int]:
    """Rows with a ``block``: a hash of doc_id and text (rows of one id, or without one, spread as well) over blocks of about ``size``
    bytes; and the bytes of all."""
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("origin"), F.coalesce(F.col("text"), F.lit("")).alias("body"), "doc_id", *carry)
    total = rows.agg(F.sum(F.octet_length("body"))).first()[0] or 0
    many = max(width(spark), -(-total // size))
    return rows.withColumn("block", F.pmod(F.xxhash64("origin", "body"), F.lit(many))), total


def later_copies(rows: DataFrame) -> DataFrame:
    """``block, part`` (-1)``, one, two``: origin and digest of texts that an earlier document has as well; texts do not move."""
    marks = rows.select("block", "origin", F.sha2(F.col("body").cast("binary"), 256).alias("digest")).distinct()
    first = marks.groupBy("digest").agg(F.min("origin").alias("first"), F.max("origin").alias("last")).filter("last > first").select("digest", "first")
    # a text with very many copies is joined in SALTS places; with both sides dealt for the join alone, Spark can split further
    salted = first.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    late = marks.withColumn("salt", F.pmod(F.xxhash64("origin"), F.lit(SALTS))).join(salted, ["digest", "salt"]).filter("origin > first")
    return late.select("block", F.lit(-1).alias("part"), F.col("origin").cast("string").cast("binary").alias("one"), F.unhex("digest").alias("two"))


def leads(buf: bytes, start: np.ndarray, stop: np.ndarray, who: np.ndarray) -> np.ndarray:
    """Whether no document of the block with a smaller origin has the same run. Of the other runs every string also starts in that
    document, so they go without being compared elsewhere, and are never the first holder of a string."""
    seen: dict[bytes, int] = {}
    place = seen.setdefault
    piece = np.fromiter((place(buf[i:j], len(seen)) for i, j in zip(start.tolist(), stop.tolist(), strict=True)), np.int64, len(start))
    least = np.full(len(seen), LAST)
    np.minimum.at(least, piece, who)
    return who == least[piece]


def _texts(batches) -> tuple[list[int], list[bytes]]:
    """Origins and texts of a block in order."""
    got = []
    for b in batches:
        got += zip(b.column("origin").to_pylist(), (t.encode("utf-8", "surrogatepass") for t in b.column("body").to_pylist()), strict=True)
    got.sort()
    return [o for o, _ in got], [t for _, t in got]


def _replies(batches) -> tuple[dict[int, set[bytes]], list[tuple[int, bytes, bytes]]]:
    """Digests of later copies by origin, and the other rows as (part, one, two)."""
    late, rest = {}, []
    for b in batches:
        for part, one, two in zip(*(b.column(c).to_pylist() for c in ("part", "one", "two")), strict=True):
            if part < 0:
                late.setdefault(int(one), set()).add(two)
            else:
                rest.append((part, one, two))
    return late, rest


def _is_late(late: dict[int, set[bytes]], origin: int, text: bytes) -> bool:
    """Whether this row's own text is a later copy; other rows may share its origin."""
    return origin in late and hashlib.sha256(text).digest() in late[origin]


def _ints(data: bytes) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(data), np.int32).astype(np.int64)


def _shrink(values: np.ndarray) -> bytes:
    return zstandard.compress(values.astype(np.int32).tobytes(), 1)


def deduplicate(docs: DataFrame, carry: list[str] | None = None, span: int = SPAN, size: int = 8_000_000, part_size: int = 6_000_000, whole: bool = False) -> DataFrame:
    """``doc_id``, the ``carry`` columns, ``n_bytes, n_removed, n_spans, kept_sha256`` and the remaining ``kept`` bytes (if ``whole``,
    without the characters that a cut leaves in part; the digest is of all remaining bytes)."""
    spark = ship(docs.sparkSession)
    carry = carry or []
    rows, total = blocks(docs, carry, size)
    parts = max(width(spark), 2, -(-total // part_size))
    copies = keep(later_copies(rows), "copies")
    inside = rows.select("block", "origin", "body").groupBy("block")

    def sources(left, right):
        """Texts of a block without later copies, their runs, and the replies."""
        late, rest = _replies(right)
        origin, texts = _texts(left)
        use = [i for i, (o, t) in enumerate(zip(origin, texts, strict=True)) if not _is_late(late, o, t)]
        own = np.array([origin[i] for i in use], np.int64)
        # positions are those of the whole block, in order
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        at = (np.cumsum(sizes) - sizes)[use]
        buf, begin, anchor, start, count = runs([texts[i] for i in use], span)
        owner = np.searchsorted(begin, start, side="right") - 1
        return buf, own, at - begin, anchor, start, count, owner, rest

    def send_anchors(key, left, right):
        _, own, _, anchor, _, _, owner, _ = sources(left, right)
        order = np.argsort(anchor, kind="stable")
        anchor, owner = anchor[order], own[owner[order]] if len(own) else owner
        head = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]]) if len(anchor) else np.zeros(0, int)
        if not len(head):
            return
        many = np.minimum.reduceat(owner, head) != np.maximum.reduceat(owner, head)
        anchor = anchor[head]
        for p, a, b in _stretches(_part(anchor, parts)):
            yield _row(ANCHORS, p, key[0].as_py(), _pack(anchor[a:b], p, parts), np.packbits(many[a:b]).tobytes())

    def answer(key, batches):
        got = []
        for b in batches:
            got += zip(b.column("block").to_pylist(), b.column("keys").to_pylist(), b.column("many").to_pylist(), strict=True)
        keys = [_unpack(k) for _, k, _ in got]
        every = np.concatenate(keys)
        shared = np.concatenate([np.unpackbits(np.frombuffer(m, np.uint8), count=len(k)).astype(bool) for k, (_, _, m) in zip(keys, got, strict=True)])
        order = np.argsort(every, kind="stable")
        s = every[order]
        more = np.zeros(len(s), bool)
        more[1:] |= s[1:] == s[:-1]
        more[:-1] |= s[1:] == s[:-1]
        shared[order] |= more
        at = 0
        for k, (block, _, _) in zip(keys, got, strict=True):
            yield _row(REPLY, block, key[0].as_py(), np.packbits(shared[at : at + len(k)]).tobytes(), b"")
            at += len(k)

    def send_runs(key, left, right):
        buf, own, moved, anchor, start, count, owner, rest = sources(left, right)
        if not len(anchor):
            return
        bits = {p: one for p, one, _ in rest}
        names = np.unique(anchor)
        shared = np.concatenate([np.unpackbits(np.frombuffer(bits[p], np.uint8), count=b - a).astype(bool) for p, a, b in _stretches(_part(names, parts))])
        use = np.flatnonzero(shared[np.searchsorted(names, anchor)])
        lead = leads(buf, start[use], start[use] + count[use] + span - 1, own[owner[use]])
        if not lead.all():
            block, gone = key[0].as_py(), use[~lead]
            first = start[gone] + moved[owner[gone]]
            order = np.argsort(first, kind="stable")
            first, stop = first[order], (first + count[gone])[order]
            head = np.flatnonzero(np.r_[True, first[1:] != stop[:-1]])
            yield _row(RUNS, parts + block % parts, block, b"", _shrink(first[head]), _shrink(stop[np.r_[head[1:] - 1, len(stop) - 1]] - first[head]), b"", b"", b"")
        use = use[lead]
        part = _part(anchor[use], parts)
        order = np.argsort(part, kind="stable")
        use = use[order]
        for p, a, b in _stretches(part[order]):
            some = use[a:b]
            length = count[some] + span - 1
            text = b"".join([buf[i : i + n] for i, n in zip(start[some].tolist(), length.tolist(), strict=True)])
            who, owners = np.unique(owner[some], return_inverse=True)
            yield _row(RUNS, p, key[0].as_py(), (anchor[some] & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes(), _shrink(np.diff(start[some] + moved[owner[some]], prepend=0)), _shrink(count[some]), _shrink(np.diff(owners, prepend=0)), own[who].tobytes(), zstandard.compress(text, 3))

    def compare(key, batches):
        held: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]] = []
        pieces: dict[bytes, int] = {}
        index, anchors = [], []
        for b in batches:
            for block, names, starts, counts, owners, origins, text in zip(*(b.column(c).to_pylist() for c in ("block", "anchors", "starts", "counts", "owners", "origins", "text")), strict=True):
                if key[0].as_py() >= parts:  # runs that their own block decided
                    yield _row(REPLY, block, key[0].as_py(), starts, counts)
                    continue
                count = _ints(counts)
                end = np.cumsum(count + span - 1)
                begin = (end - (count + span - 1)).tolist()
                text, place = zstandard.decompress(text), pieces.setdefault
                index.append(np.array([place(text[i:j], len(pieces)) for i, j in zip(begin, end.tolist(), strict=True)]))
                anchors.append(np.frombuffer(names, np.uint32))
                held.append((block, np.cumsum(_ints(starts)), count, np.frombuffer(origins, np.int64)[np.cumsum(_ints(owners))]))
        least = np.full(len(pieces), LAST)
        for at, (_, _, _, origin) in zip(index, held, strict=True):
            np.minimum.at(least, at, origin)
        anchor = np.zeros(len(pieces), np.uint32)
        for at, names in zip(index, anchors, strict=True):
            anchor[at] = names
        _, of, alike = np.unique(anchor, return_inverse=True, return_counts=True)
        texts = list(pieces)
        del pieces
        size_of = np.fromiter(map(len, texts), np.int64, len(texts)) - span + 1
        offset = np.cumsum(np.r_[0, size_of])
        low = np.repeat(least, size_of)
        mixed = np.flatnonzero(alike[of] > 1)
        if len(mixed):
            found = least_origin([texts[i] for i in mixed.tolist()], size_of[mixed], least[mixed], span)
            low[_ranges(offset[mixed], size_of[mixed])] = found
        for at, (block, start, count, origin) in zip(index, held, strict=True):
            gone = low[_ranges(offset[at], count)] < np.repeat(origin, count)
            place = np.sort(_ranges(start, count)[gone])
            if len(place):
                head = np.flatnonzero(np.r_[True, np.diff(place) > 1])
                yield _row(REPLY, block, key[0].as_py(), _shrink(place[head]), _shrink(np.diff(np.r_[head, len(place)])))

    fields = ["origin", "body", "doc_id", *carry]
    kept_fields = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in ["doc_id", *carry])
    result = f"{kept_fields}, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"

    def remove(key, left, right):
        frugal()
        late, marks = _replies(right.to_batches())
        body = [t.encode("utf-8", "surrogatepass") for t in left.column("body").to_pylist()]
        origin = left.column("origin").to_pylist()
        order = sorted(range(len(body)), key=lambda i: (origin[i], body[i]))
        sizes = np.array([len(body[i]) for i in order], np.int64)
        edge = np.zeros(int(sizes.sum()) + 1, np.int32)
        for _, starts, counts in marks:
            s = _ints(starts)
            np.add.at(edge, s, 1)
            np.add.at(edge, s + _ints(counts) + span - 1, -1)
        covered = np.cumsum(edge[:-1], dtype=np.int32) > 0
        del edge
        n = len(body)
        removed, spans, digest, kept = [0] * n, [0] * n, [""] * n, [b""] * n
        for i, b, s in zip(order, (np.cumsum(sizes) - sizes).tolist(), sizes.tolist(), strict=True):
            c = covered[b : b + s]
            text = body[i]
            if s >= span and _is_late(late, origin[i], text):  # every byte lies in a string of the first copy
                removed[i], spans[i], text = s, 1, b""
            elif c.any():
                removed[i] = int(c.sum())
                spans[i] = int(c[0]) + int((c[1:] & ~c[:-1]).sum())
                text = np.frombuffer(text, np.uint8)[~c].tobytes()
            kept[i], digest[i] = text, hashlib.sha256(text).hexdigest()
            if whole and text and removed[i]:
                kept[i] = whole_characters(body[i], c)
        cols = [*(left.column(c) for c in ["doc_id", *carry]), pa.array([len(x) for x in body], pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(digest), pa.array(kept, pa.binary())]
        del body, covered, kept
        trim()
        return pa.table(cols, names=["doc_id", *carry, "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    shared = keep(inside.cogroup(copies.groupBy("block")).applyInArrow(tabled(send_anchors, ANCHORS, 2), ANCHORS).groupBy("part").applyInArrow(tabled(answer, REPLY), REPLY), "shared")
    free_shuffles(spark)
    moved_runs = inside.cogroup(shared.union(copies).groupBy("block")).applyInArrow(tabled(send_runs, RUNS, 2), RUNS)
    marks = keep(moved_runs.groupBy("part").applyInArrow(tabled(compare, REPLY), REPLY), "marks")
    drop(shared)
    free_shuffles(spark)
    return rows.select("block", *fields).groupBy("block").cogroup(marks.union(copies).groupBy("block")).applyInArrow(lambda key, a, b: remove(key, a, b), result)


def _ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """All positions of the ranges, end to end."""
    return np.repeat(start - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))


def without_repeats(docs: DataFrame, carry: list[str] | None = None, span: int = SPAN) -> DataFrame:
    """General form: ``doc_id``, the ``carry`` columns and ``text`` without the removed bytes (what a cut leaves of a character goes
    with it)."""
    carry = carry or []
    cut = deduplicate(docs, carry, span, whole=True)
    return cut.select("doc_id", *carry, F.col("kept").cast("string").alias("text"))


def whole_characters(text: bytes, gone: np.ndarray) -> bytes:
    """What is left of a UTF-8 text when every character with a byte in ``gone`` goes."""
    data = np.frombuffer(text, np.uint8)
    head = np.flatnonzero((data & 0xC0) != 0x80)
    hit = np.logical_or.reduceat(gone, head)
    return data[~np.repeat(hit, np.diff(np.r_[head, len(data)]))].tobytes()


def _part(anchor: np.ndarray, parts: int) -> np.ndarray:
    """Range of each anchor, in order: even steps over the upper 32 bits."""
    return ((anchor.astype(np.uint64) >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)


def _stretches(part: np.ndarray) -> list[tuple[int, int, int]]:
    """(range, from, to) of every range that occurs in a sorted array; a block's work does not grow with the number of ranges."""
    cut = np.flatnonzero(np.diff(part, prepend=-1, append=-1)).tolist()
    return [(int(part[a]), a, b) for a, b in zip(cut, cut[1:], strict=False)]


def _pack(keys: np.ndarray, part: int, parts: int) -> bytes:
    """The leading 40 bits of each key inside its range: enough to choose what is compared."""
    shift = np.uint64(max(0, 64 - (parts.bit_length() - 1) - 40))
    first = np.uint64(-(-(part << 32) // parts) << 32)
    return ((keys - first) >> shift).view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def _unpack(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(data, np.uint8).reshape(-1, 5)
    return out.view(np.uint64).ravel()


def _row(fields: str, *values) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    names = [f.split() for f in fields.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([v], kinds[k]) for v, (_, k) in zip(values, names, strict=True)], names=[n for n, _ in names])
