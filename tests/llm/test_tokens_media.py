import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from tokenizers import Tokenizer

from privsketch.llm import byte_bpe, media_ogg, packing, token_counts

WORDS, RANKS = P.path("word_bpe_49k.json"), P.path("byte_bpe_50k.tiktoken")


def strange(n=200, seed=3):
    r = random.Random(seed)
    pick = lambda: chr(r.choice([32, 32, 10, r.randrange(32, 127), r.randrange(97, 123), r.randrange(0x80, 0x2000), r.randrange(0x1F300, 0x1F6FF)]))
    return ["".join(pick() for _ in range(r.randrange(0, 90))) for _ in range(n)] + ["", "aaaa" * 99, "ΑΣ ΣΑΣ. İ", "a<|endoftext|>b<|startoftext|>", "  lead", "trail \n", "\x1c\x85　"]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(WORDS)


def test_token_counts_equal_the_library(library):
    t = strange()
    assert token_counts.WordCounter(WORDS).count(t) == [len(library.encode(x, add_special_tokens=False).ids) for x in t]


def test_token_counts_frame(spark, odd, none, texts, library):
    got = {(r.doc_id, r.n_bytes): r for r in token_counts.token_counts(odd, WORDS).collect()}
    for doc_id, text, *_ in texts:
        text = text or ""
        r = got[(doc_id, len(text.encode()))]
        assert r.n_tokens == len(library.encode(text, add_special_tokens=False).ids) and r.over_limit == (r.n_tokens > 2048)
    assert token_counts.token_counts(none, WORDS).count() == 0


def test_packing_ids_equal_the_library(library):
    t = strange(100, 5)
    got = packing.WordIds(WORDS).encode(t)
    assert got == [np.array(library.encode(x, add_special_tokens=False).ids, "<u4").tobytes() for x in t]


@pytest.mark.parametrize("sizes", [[1], [2048], [2047, 1], [1500] * 31, [1024] * 5, [1] * 5000, [9000, 3, 4, 2045], list(range(1, 3000, 7))])
def test_pack_covers_each_document_once(sizes):
    pieces = packing.pack(np.array(sizes))
    at = [0] * len(sizes)
    for d, start, length, _, _ in sorted(pieces):
        assert start == at[d] and length > 0
        at[d] += length
    assert at == sizes
    fill = {}
    for _, _, length, seq, offset in sorted(pieces, key=lambda x: (x[3], x[4])):
        assert offset == fill.get(seq, 0)
        fill[seq] = offset + length
    assert max(fill.values()) <= 2048 and sum(v < 2048 for v in fill.values()) <= 1
    assert sorted(fill) == list(range(len(fill)))


def test_least_squares_finds_exact_recipes():
    histogram = np.zeros(101, int)
    histogram[[60, 40, 50]] = [10, 10, 8]
    columns = packing.combinations(np.flatnonzero(histogram), 100)
    x = dict(zip(map(tuple, columns.tolist()), packing.solve(columns, histogram), strict=True))
    assert abs(x[(60, 40, 0)] - 10) < 0.2 and abs(x[(50, 50, 0)] - 4) < 0.2


def test_every_combination_is_a_column():
    def brute(w):
        return sum(1 for a in range(1, w) for b in range(1, a + 1) for c in range(0, b + 1) if a + b + c == w)

    assert len(packing.combinations(np.arange(1, 90), 90)) == brute(90)
    columns = packing.combinations(np.arange(1, 2048), 2048)
    assert len(columns) == 350_549 == len(np.unique(columns, axis=0)) and (columns.sum(1) == 2048).all()
    sizes = np.repeat(np.arange(1, 2048), 4)
    full = {}
    for _, _, n, seq, _ in packing.pack(sizes):
        full[seq] = full.get(seq, 0) + n
    assert sum(v < 2048 for v in full.values()) <= 1 and sum(full.values()) == sizes.sum()
    assert packing.whole(np.full(1000, 0.01)).sum() == 10


def test_packing_frame(spark, odd, none, texts, library):
    rows = packing.pack_documents(odd, WORDS, with_ids=True).collect()
    want = {}
    for doc_id, text, *_ in texts:
        want.setdefault(doc_id, []).append([*library.encode(text or "", add_special_tokens=False).ids, 1])
    total = sum(len(x) for v in want.values() for x in v)
    assert sum(r.length for r in rows) == total
    for r in rows:
        whole = next(x for x in want[r.doc_id] if len(x) == r.doc_tokens)
        piece = whole[r.start : r.start + r.length]
        assert r.ids == piece and r.ids_crc32 == zlib.crc32(np.array(piece, "<u4").tobytes())
    assert packing.pack_documents(none, WORDS).count() == 0


def test_byte_bpe_equals_the_library(spark, odd, none, texts):
    import base64

    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def want(t):
        ids = lib.encode_ordinary(t)
        return len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()

    t = strange(150, 9) + ["x" * 999, "-" * 400 + " " * 300]
    assert byte_bpe.codec(RANKS, P.PATTERN).digest(t) == [want(x) for x in t]
    got = sorted(((r.doc_id or 0), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in byte_bpe.encode_digests(odd, RANKS, P.PATTERN).collect())
    assert got == sorted(((i or 0), *want(x or "")) for i, x, *_ in texts)
    assert byte_bpe.encode_digests(none, RANKS, P.PATTERN).count() == 0
    back = byte_bpe.decode(byte_bpe.encode(odd, RANKS, P.PATTERN), RANKS, P.PATTERN)
    assert sorted(bytes(r.raw) for r in back.collect()) == sorted((x or "").encode() for _, x, *_ in texts)


def test_prefix_table_appends_and_edits():
    v = byte_bpe.codec(RANKS, P.PATTERN).v
    table = byte_bpe.PrefixTable(v, b"hello wor")
    table.append(b"lds")
    assert table.ids() == byte_bpe.PrefixTable(v, b"hello worlds").ids()
    table.edit(6, 6, b"there")
    assert table.ids() == byte_bpe.PrefixTable(v, b"hello there").ids()
    assert table.ids(5) == byte_bpe.PrefixTable(v, b"hello").ids()


def test_prefix_table_edits_refill_only_what_changes():
    v, r = byte_bpe.Vocabulary(RANKS), random.Random(4)
    word = lambda n: bytes(r.choice(b"etaoin shrdlu-0x") for _ in range(n))
    table = byte_bpe.PrefixTable(v, word(3000))
    for _ in range(25):
        at = r.randrange(len(table.data))
        gone, new = min(r.choice([0, 1, 7, 40]), len(table.data) - at), word(r.choice([0, 1, 5, 60]))
        want = table.data[:at] + new + table.data[at + gone :]
        filled = table.edit(at, gone, new)
        assert table.data == want and table.last == byte_bpe.PrefixTable(v, want).last
        assert filled <= max(len(new) + 3 * v.longest, 2 * v.longest)
    with pytest.raises(ValueError):
        table.edit(len(table.data), 1, b"")


def test_decoded_digest_comes_from_the_ids():
    c = byte_bpe.TextCodec(RANKS, P.PATTERN)
    c.v.bytes_of[c.v.rank[b" world"]] = b" lost"
    n, ids, raw = c.digest(["hello world"])[0]
    assert (n, raw) == (2, hashlib.sha256(b"hello lost").hexdigest())


def slow_checksum(page):
    crc = 0
    for b in page:
        crc ^= b << 24
        for _ in range(8):
            crc = (crc << 1 ^ 0x04C11DB7 if crc & 0x80000000 else crc << 1) & 0xFFFFFFFF
    return crc


def test_ogg_checksum_and_round_trip():
    page = bytes(range(256)) * 3
    assert media_ogg.page_checksum(page) == slow_checksum(page)
    for n in (576, 576 * 85, 576 * 86, 576 * 400):
        payload = random.Random(n).randbytes(n)
        media = media_ogg.write(payload, n - 5)
        got, length, feature = media_ogg.decode(media)
        assert got == payload and length == n - 5 and f"seconds={n / 8000:.6f}" in feature
        for at in (30, len(media) // 2, len(media) - 1):
            bad = bytearray(media)
            bad[at] ^= 1
            with pytest.raises(ValueError):
                media_ogg.read(bytes(bad))


def test_ogg_packets_across_pages():
    """A packet longer than a page's lacing is continued; two streams stay apart."""
    big = bytes(70_000)
    lacing = media_ogg.lace(len(big))
    first, second = lacing[:255], lacing[255:]
    cut = 255 * 255
    data = media_ogg._page(2, -1, 9, 0, first, big[:cut]) + media_ogg._page(6, 7, 4, 0, b"\x03", b"abc") + media_ogg._page(5, 11, 9, 1, second, big[cut:])
    assert media_ogg.read(data) == {9: [(big, 11)], 4: [(b"abc", 7)]}


def test_media_frame(spark, odd, none, texts):
    rows = media_ogg.media_rows(odd).collect()
    assert len(rows) == len(texts)
    want = {(i, len((t or "").encode())): (t or "").encode() for i, t, *_ in texts}
    for r in rows:
        raw = want[(r.doc_id, r.n_bytes)]
        full = raw + b"\xff" * (576 if not raw else -len(raw) % 576)
        assert r.payload_bytes == len(full) and r.payload_sha256 == hashlib.sha256(full).hexdigest() and r.tail_crc32 == zlib.crc32(full[-32:])
    assert media_ogg.media_rows(none).count() == 0
    one = media_ogg.media_column(odd).filter("doc_id = 4").first()
    assert hashlib.sha256(one.media).hexdigest() == next(r.media_sha256 for r in rows if r.doc_id == 4)


def test_young_characters_follow_the_libraries(library):
    """Classes of characters newer than Unicode 3.2 differ between libraries; whole planes at random."""
    import base64

    import tiktoken

    r = random.Random(77)
    t = ["".join(chr(r.choice([r.randrange(32, 127), r.randrange(0x80, 0xD7FF), r.randrange(0xE000, 0x1FFFF)])) for _ in range(30)) for _ in range(400)] + ["Ŋ֋ x"]
    assert packing.WordIds(WORDS).encode(t) == [np.array(library.encode(x, add_special_tokens=False).ids, "<u4").tobytes() for x in t]
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    c = byte_bpe.codec(RANKS, P.PATTERN)
    assert [c.ids(x) for x in t] == [lib.encode_ordinary(x) for x in t]
    assert [g[1] for g in c.digest(t)] == [hashlib.sha256(" ".join(map(str, lib.encode_ordinary(x))).encode()).hexdigest() for x in t]
