import hashlib
import random

import numpy as np
import pytest
import xxhash

from privsketch.llm import embedding_cover, graph, simhash, suffix_dedup
from privsketch.llm._util import HashTable, Recent, min_labels


def test_hash_table_and_memory():
    keys = np.unique(np.random.default_rng(1).integers(0, 2**63, 5000).astype(np.uint64))
    keys[0] = 0
    table = HashTable(keys, np.arange(len(keys)))
    assert (table.get(keys) == np.arange(len(keys))).all() and (table.get(keys + np.uint64(1))[~np.isin(keys + np.uint64(1), keys)] == -1).all()
    memory = Recent(2)
    for word in "abcabd":
        for k in memory.missing({word}):
            memory.now[k] = 1
        assert word in memory.now


def brute_components(ids, pairs):
    label = {i: i for i in ids}
    while True:
        changed = False
        for a, b in pairs:
            low = min(label[a], label[b])
            for x in (a, b):
                if label[x] != low:
                    label[x], changed = low, True
        if not changed:
            return label


@pytest.mark.parametrize("kind", ["chain", "star", "random", "empty"])
def test_components(spark, kind):
    r = random.Random(4)
    pairs = {"chain": [(i, i + 1) for i in range(40)], "star": [(0, i) for i in range(1, 50)], "random": [(r.randrange(80), r.randrange(80)) for _ in range(60)], "empty": []}[kind]
    got = {x.node: x.root for x in graph.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    ids = {i for p in pairs for i in p if p[0] != p[1]}
    assert got == {k: v for k, v in brute_components(ids, [p for p in pairs if p[0] != p[1]]).items()}


def brute_fingerprint(text):
    text = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    import re

    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    shingles = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def check_simhash(rows, got):
    fps = {}
    for i, t in rows:
        fps.setdefault(brute_fingerprint(t), []).append(i)
    ids = list(fps)
    pairs = [(a, b) for x, a in enumerate(ids) for b in ids[x + 1 :] if (a ^ b).bit_count() <= 2]
    label = brute_components(ids, pairs)
    least = {}
    for f, own in fps.items():
        known = [i for i in own if i is not None]
        if known:
            least[label[f]] = min([least.get(label[f], known[0]), *known])
    want = sorted(((i or 0), f"{f:016x}", least.get(label[f]) or 0) for f, own in fps.items() for i in own)
    assert sorted(((r.doc_id or 0), r.fingerprint, r.component_id or 0) for r in got) == want


def test_simhash_of_documents(spark, small, odd, none, texts):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    check_simhash([(r.doc_id, r.text) for r in docs.collect()], simhash.near_duplicates(docs).collect())
    check_simhash([(i, t) for i, t, *_ in texts], simhash.near_duplicates(odd).collect())
    assert simhash.near_duplicates(none).count() == 0


def test_anchor_links_are_complete(spark):
    """Planted neighbours at 0 to 3 bits, a dense ball (a large group at one anchor), and random fingerprints."""
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 300).astype(np.uint64)
    near = [int(b) ^ sum(1 << int(x) for x in rng.choice(64, k, replace=False)) for b in base[:200] for k in (1, 2, 3)]
    ball = [int(base[0]) ^ (1 << a) for a in range(64)] + [int(base[0]) ^ (1 << a) ^ (1 << (a + 7) % 64) for a in range(64)]
    fps = sorted({int(b) for b in base} | set(near) | set(ball))
    signed = [f - 2**64 if f >= 2**63 else f for f in fps]
    edges = simhash.forest(spark.createDataFrame([(x,) for x in signed], "fp long")).collect()
    at = {x: i for i, x in enumerate(signed)}
    got = min_labels(len(fps), np.array([at[e.a] for e in edges]), np.array([at[e.b] for e in edges]))
    f = np.array(fps, np.uint64)
    i, j = np.nonzero(np.bitwise_count(f[:, None] ^ f[None, :]) <= 2)
    assert (got == min_labels(len(fps), i, j)).all()
    assert len(edges) < 6 * len(fps)


def test_dense_anchor_meets_in_midpoints(monkeypatch):
    r = np.random.default_rng(5)
    base = r.integers(0, 2**63, 40).astype(np.uint64)
    flips = np.array([1 << int(b) for b in r.integers(0, 64, 3000)], np.uint64)
    fp = np.unique(r.choice(base, 1000) ^ flips[:1000] ^ flips[1000:2000] ^ flips[2000:])  # up to three flips: some links, some none
    near = np.bitwise_count(fp[:, None] ^ fp[None, :])
    for threshold in (0, 2):
        i, j = np.nonzero(near <= threshold)
        want = min_labels(len(fp), i, j)
        for most in (1 << 21, 5000):
            a, b = simhash.midpoint_forest(fp, threshold, most)
            assert (min_labels(len(fp), a, b) == want).all()
    monkeypatch.setattr(simhash, "DENSE", 100)
    for threshold in (1, 2, 3):  # an odd one goes block by block
        i, j = np.nonzero(near <= threshold)
        a, b = simhash.links(fp, np.zeros(len(fp), np.uint64), threshold)
        assert (min_labels(len(fp), a, b) == min_labels(len(fp), i, j)).all()


def test_majority_of_long_runs():
    h = np.full(130_001, np.uint64(0xF0F0F0F0F0F0F0F0))
    h[:60_000] = 0x0F0F0F0F0F0F0F0F
    assert simhash.majority(h, np.array([0]))[0] == 0xF0F0F0F0F0F0F0F0


def test_cover_tree_covers_and_nests():
    rng = np.random.default_rng(3)
    c = rng.normal(size=(12, 8))
    x = np.concatenate([c[i] + 0.05 * rng.normal(size=(60, 8)) for i in range(12)])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    tree = embedding_cover.CoverTree(x, leaf=16)
    assert sorted(tree.rows_of(0).tolist()) == list(range(len(x)))
    for node in range(len(tree.centre)):
        rows, parts = tree.rows_of(node), tree.parts(node)
        assert (np.linalg.norm(x[rows] - x[tree.centre[node]], axis=1) <= tree.radius[node] + 1e-6).all() and tree.centre[node] in rows
        if tree.kid_count[node]:
            assert sorted(np.concatenate([tree.rows_of(k) for k in parts]).tolist()) == sorted(rows.tolist()) and tree.centre[node] in tree.centre[parts]
    assert tree.depth > 3


def brute_degrees(x, mx, threshold):
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    ok = (u @ u.T >= threshold) & ~np.eye(len(x), dtype=bool)
    return ok @ mx


@pytest.mark.parametrize("noise", [0.02, 0.25, 3.0])
def test_dual_traversal_is_exact_and_saves_work(noise):
    rng = np.random.default_rng(5)
    x = np.repeat(rng.normal(size=(12, 24)), 60, axis=0) + noise * rng.normal(size=(720, 24)) / np.sqrt(24)
    m = rng.integers(1, 4, 720)
    found = embedding_cover.Links(x, x, m, m, 0.95, True)
    assert (found.dx + found.dy == brute_degrees(x, m, 0.95)).all()
    assert found.distances < (0.1 if noise < 0.1 else 0.75) * len(x) ** 2
    a, b = x[::2], x[1::2]
    apart = embedding_cover.Links(a, b, m[::2], m[1::2], 0.95, False)
    every = brute_degrees(np.r_[a, b], np.r_[np.zeros(360, int), m[1::2]], 0.95)
    assert (apart.dx == every[:360]).all()


def test_given_vectors_branch(spark):
    """On the given table the tree has levels, and one tree against itself takes about half of all ordered pairs."""
    rows = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").select("embedding").distinct().collect()
    x = np.array([r[0] for r in rows], float)
    found = embedding_cover.Links(x, x, np.ones(len(x), int), np.ones(len(x), int), 0.95, True)
    assert found.trees[0].depth > 1 and found.distances < 0.65 * len(x) ** 2
    assert (found.dx + found.dy == brute_degrees(x, np.ones(len(x), int), 0.95)).all()


def test_lone_rows_are_compared_by_their_heads(spark):
    """Near-orthogonal rows: whole rows are multiplied for few pairs only; the others are settled by a bound that is never below the cosine."""
    rows = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").select("embedding").distinct().collect()
    x = np.array([r[0] for r in rows], float)
    one = np.ones(1000, int)
    found = embedding_cover.Links(x[:1000], x[1000:], one, one, 0.95, False)
    assert found.distances >= 1000 * 1000 and found.whole < 0.2 * found.distances
    rng = np.random.default_rng(1)
    for y in (x, rng.normal(size=(500, 40)) + 3, np.repeat(rng.normal(size=(10, 300)), 50, axis=0) + 0.1 * rng.normal(size=(500, 300))):
        u = embedding_cover.unit(y)[1]
        h = embedding_cover.heads(u)
        assert 2 * h.shape[1] <= u.shape[1] + 2 and (h @ h.T >= u @ u.T - embedding_cover.ROUGH).all()


@pytest.mark.parametrize("dim", [1, 3, 15, 16, 40])
@pytest.mark.parametrize("threshold", [0.2, 0.8, 0.95, 0.9999])
def test_blocks_travel_with_their_trees(dim, threshold):
    """Links of packed blocks, of few and many coordinates, from lone rows to groups of copies that hardly differ."""
    rng = np.random.default_rng(dim)
    x = np.repeat(rng.normal(size=(30, dim)), 20, axis=0) + rng.choice([0, 1e-7, 0.004, 0.1, 2], (600, 1)) * rng.normal(size=(600, dim))
    keys = list(dict.fromkeys(b"4" + r.astype(np.float32).tobytes() if i % 2 else b"8" + r.tobytes() for i, r in enumerate(x)))
    x, size = embedding_cover.matrix(keys), len(keys)
    m = rng.integers(1, 4, size)
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    cos = u @ u.T
    assert not (np.abs(cos - threshold) < 1e-12).any()  # nothing is left to rounding
    a, b = (embedding_cover.Block.unpack(embedding_cover.Block(keys[s], m[s]).pack()) for s in (slice(0, 250), slice(250, size)))
    want = (cos >= threshold) & ~np.eye(size, dtype=bool)
    got, forest = {}, []
    for one, other in ((a, a), (b, b), (a, b)):
        for p, q, n in zip(*(v.to_pylist() for v in one.links(other, threshold).values()), strict=True):
            if q is None:
                got[p] = got.get(p, 0) + n
            else:
                forest.append((p, q))
    degree = want @ m
    place = {k: i for i, k in enumerate(keys)}
    assert [got.get(k, 0) for k in keys] == degree.tolist()
    ends = [np.array([place[e[i]] for e in forest], int) for i in (0, 1)]
    assert (min_labels(size, *ends) == min_labels(size, *np.nonzero(want))).all()


def test_rows_exactly_a_net_radius_apart():
    """Rows at chord 1 from the centre are all covered by it: the next net must be finer."""
    x = np.zeros((41, 121))
    x[:, 0] = 1
    for i in range(40):
        x[1 + i, 1 + 3 * i : 4 + 3 * i] = 1
    tree = embedding_cover.CoverTree(embedding_cover.unit(x)[1])
    assert sorted(tree.rows_of(0).tolist()) == list(range(41)) and tree.depth > 1


def test_blocks_in_groups_lose_no_link(spark, monkeypatch):
    """Many blocks in few groups: every pair of blocks is met once, and a block is sent once to a group."""
    monkeypatch.setattr(embedding_cover, "width", lambda _: 2)
    rng = np.random.default_rng(4)
    x = np.repeat(rng.normal(size=(60, 32)), 10, axis=0) + 0.04 * rng.normal(size=(600, 32))
    got = {r.vec_id: r for r in embedding_cover.near_duplicates(spark.createDataFrame(list(enumerate(x.tolist())), "vec_id long, embedding array<double>"), 0.95, 40).collect()}
    want = brute_degrees(x, np.ones(600, int), 0.95)
    assert want.sum() > 600 and [got[i].n_links for i in range(600)] == want.tolist()
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert [got[i].component_id for i in range(600)] == min_labels(600, *np.nonzero(u @ u.T >= 0.95)).tolist()


def test_many_vector_lengths_and_extreme_norms(spark):
    rows = [(3 * n + k, [float(k == 2)] + [1.0] * n) for n in range(1, 140) for k in range(3)]
    rows += [(1000, [1e200, 1e200]), (1001, [1e-200, 1.1e-200]), (1002, [3e-310, -1e-310])]
    got = {r.vec_id: r for r in embedding_cover.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    for n in range(2, 140):
        assert got[3 * n].n_links >= 1 and got[3 * n + 1].component_id == min(3 * n, got[3 * n].component_id)
    assert got[1001].component_id == got[1000].component_id == got[5].component_id
    assert got[1002].n_links == 0 and len(got) == len(rows)


def test_embedding_links(spark, small):
    rng = np.random.default_rng(0)
    c = rng.normal(size=(20, 16))
    x = np.concatenate([c[i] + 0.12 * rng.normal(size=(40, 16)) for i in range(20)]).tolist()
    x += [None, [], [0.0] * 16, [1.0, None] + [1.0] * 14, [float("nan")] * 16, [float("inf")] + [1.0] * 15, [1.0, 2.0], [2.0, 4.0]] + x[:15]
    frame = spark.createDataFrame(list(enumerate(x)), "vec_id long, embedding array<double>").selectExpr("*", "vec_id key", "1 n", "'a' cell", "0 label")
    for df, block in ((frame, 150), (spark.read.parquet(f"{small}/embeddings.parquet"), 8192)):
        got = {r.vec_id: r for r in embedding_cover.near_duplicates(df, 0.95, block).collect()}
        rows = df.select("vec_id", "embedding").collect()
        ok = {r.vec_id: np.array(r.embedding, float) for r in rows if r.embedding and None not in r.embedding and np.isfinite(r.embedding).all() and any(r.embedding)}
        pairs = [(a, b) for a, v in ok.items() for b, w in ok.items() if a < b and len(v) == len(w) and v @ w / np.sqrt((v @ v) * (w @ w)) >= 0.95]
        label = brute_components([r.vec_id for r in rows], pairs)
        for r in rows:
            mine = got[r.vec_id]
            assert mine.n_links == sum(r.vec_id in p for p in pairs) and mine.component_id == label[r.vec_id] and mine.kept == (mine.component_id == r.vec_id)
    assert embedding_cover.near_duplicates(frame.filter("false")).count() == 0


@pytest.mark.parametrize("text", [b"", b"a", b"banana", b"abracadabra" * 7, b"a" * 500, bytes(random.Random(2).choice(b"ab") for _ in range(3000)), b"\0\xff" * 40])
def test_suffix_array(text):
    assert suffix_dedup.suffix_array(text, most=200).tolist() == sorted(range(len(text)), key=lambda i: text[i:])


def brute_dedup(rows, span=50):
    first = {}
    for d, t in sorted(rows):
        for i in range(len(t) - span + 1):
            first.setdefault(t[i : i + span], d)
    out = []
    for d, t in rows:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - span + 1):
            if first[t[i : i + span]] < d:
                gone[i : i + span] = True
        kept = np.frombuffer(t, np.uint8)[~gone].tobytes()
        out.append((d, len(t), int(gone.sum()), int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def test_suffix_dedup(spark, small, odd, none, texts):
    r = random.Random(5)
    base = ["".join(r.choice("ab c") for _ in range(r.randrange(0, 400))) for _ in range(30)]
    rows = [(i, (r.choice(base)[r.randrange(0, 60) :] + r.choice(base)) if i % 3 else r.choice(["a" * r.randrange(0, 300), "é日" * 60, "", None])) for i in range(250)]
    rows += [(250, rows[0][1]), (1, rows[2][1])]
    last = suffix_dedup.LAST
    for df, own, size in ((spark.createDataFrame(rows, "doc_id long, text string"), rows, 4000), (spark.read.parquet(f"{small}/documents.parquet"), None, 8_000_000), (odd, [(i if i is not None else last, t) for i, t, *_ in texts], 8_000_000)):
        own = own or [(x.doc_id, x.text) for x in df.collect()]
        got = sorted((x.doc_id if x.doc_id is not None else last, x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in suffix_dedup.deduplicate(df, size=size).collect())
        assert got == brute_dedup([(i, (t or "").encode()) for i, t in own])
    assert suffix_dedup.deduplicate(none).count() == 0


def test_copies_go_row_by_row(spark):
    """A row that is a later copy takes no other row of its id (or without an id) along, and those stay sources."""
    own = [f"{w} " * 30 for w in ("first", "second", "third", "fourth", "fifth")]
    rows = [(1, own[0]), (None, own[0]), (None, own[1]), (5, own[0]), (5, own[2]), (5, own[2]), (6, own[3]), (7, "more " + own[2]), (None, own[4] + own[3])]
    last = suffix_dedup.LAST
    ids = [(last if i is None else i, t.encode()) for i, t in rows]
    for size in (8_000_000, 200):
        seen = suffix_dedup.deduplicate(spark.createDataFrame(rows, "doc_id long, text string"), size=size).collect()
        got = sorted((last if x.doc_id is None else x.doc_id, x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in seen)
        assert got == brute_dedup(ids)
        assert sorted(x.n_bytes - x.n_removed for x in seen if x.doc_id is None)[::2] == [0, len(own[1])]


def test_remaining_text_is_text(spark):
    shared = "é" * 40
    df = spark.createDataFrame([(1, "start " + shared), (2, shared + " end"), (3, "clean � text")], "doc_id long, text string")
    got = {r.doc_id: r.text for r in suffix_dedup.without_repeats(df).collect()}
    assert got == {1: "start " + shared, 2: " end", 3: "clean � text"}


def test_replacement_characters_of_the_original_stay(spark):
    shared = "é" * 40
    df = spark.createDataFrame([(1, shared), (2, "a \ufffd b " + shared + " c\ufffd"), (3, "日" + shared[:30] + "日 \ufffd")], "doc_id long, text string")
    got = {r.doc_id: r.text for r in suffix_dedup.without_repeats(df).collect()}
    assert got == {1: shared, 2: "a \ufffd b  c\ufffd", 3: "日日 \ufffd"}
    text = "é日"
    assert [suffix_dedup.whole_characters(text.encode(), np.arange(5) == i).decode() for i in (0, 1, 4)] == ["日", "日", "é"]


def test_passages_under_repeated_and_null_ids(spark):
    """Every row loses exactly the bytes of strings that start under a smaller id; rows of one id, or of none, never cost each other text."""
    r = random.Random(8)
    passages = ["".join(r.choice("abcdef ") for _ in range(r.choice([49, 50, 51, 87, 130]))) for _ in range(12)]
    t, u, v = passages[0] * 2, passages[1] * 2, passages[2] * 2
    rows = [(1, t), (5, t), (5, u), (None, t), (None, v), (7, u)]
    for _ in range(60):
        body = "".join(r.choice(passages) for _ in range(r.randrange(0, 4))) + "\ufffd" * r.randrange(0, 2)
        rows.append((r.choice([None, 1, 2, 3, 5, 5, 8, 9, 20]), body))
    rank = lambda i: suffix_dedup.LAST if i is None else i
    first: dict[bytes, int] = {}
    for i, text in rows:
        b = text.encode()
        for k in range(len(b) - 49):
            first[b[k : k + 50]] = min(first.get(b[k : k + 50], suffix_dedup.LAST), rank(i))
    want = []
    for i, text in rows:
        b, gone = text.encode(), [False] * len(text.encode())
        for k in range(len(b) - 49):
            if first[b[k : k + 50]] < rank(i):
                gone[k : k + 50] = [True] * 50
        spans = sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))
        want.append((rank(i), len(b), sum(gone), spans, hashlib.sha256(bytes(c for c, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for size in (8_000_000, 2_000):
        got = suffix_dedup.deduplicate(docs, size=size, part_size=size).collect()
        assert sorted((rank(x.doc_id), x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in got) == sorted(want)


def test_one_run_a_block_travels():
    buf = b"aXXXbXXXcXXXaXXXdYYY"
    start = np.array([0, 1, 5, 9, 13, 17])
    got = suffix_dedup.leads(buf, start, start + 3, np.array([1, 1, 1, 2, 3, suffix_dedup.LAST]))
    assert got.tolist() == [True, True, True, False, False, True]  # repeats inside the first document stay with it


def test_passage_of_every_document_and_rows_without_id(spark):
    r = random.Random(9)
    word = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    line = word(130)
    rows = [(i if i % 3 else None, word(40) + line + word(30) + (line if i % 7 == 0 else "")) for i in range(90)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    held, _ = suffix_dedup.blocks(frame, [], 500)
    assert held.filter("doc_id is null").select("block").distinct().count() > 1
    for size in (500, 8_000_000):
        got = suffix_dedup.deduplicate(frame, size=size, part_size=300).collect()
        first, want = {}, []
        for i, t in rows:
            for k in range(len(t) - 49):
                o = suffix_dedup.LAST if i is None else i
                first[t[k : k + 50]] = min(first.get(t[k : k + 50], o), o)
        for i, t in rows:
            gone = {k + j for k in range(len(t) - 49) for j in range(50) if first[t[k : k + 50]] < (suffix_dedup.LAST if i is None else i)}
            want.append((i, len(t), len(gone), hashlib.sha256("".join(c for k, c in enumerate(t) if k not in gone).encode()).hexdigest()))
        order = lambda x: (x[0] is None, *(v or 0 for v in x[:3]), x[3])
        assert sorted([(x.doc_id, x.n_bytes, x.n_removed, x.kept_sha256) for x in got], key=order) == sorted(want, key=order)


def test_ranges_of_anchors():
    """Every anchor lies in the range whose lower end it is packed from, ranges are even, and stretches cover a sorted array."""
    anchors = np.sort(np.random.default_rng(5).integers(0, 1 << 64, 20_000, dtype=np.uint64))
    anchors = np.r_[np.uint64(0), anchors, np.uint64((1 << 64) - 1)]
    for parts in (1, 2, 7, 211):
        part = suffix_dedup._part(anchors, parts)
        assert (np.diff(part) >= 0).all() and part[0] == 0 and part[-1] == parts - 1
        assert np.bincount(part, minlength=parts).max() < 2 * len(anchors) / parts + 1
        found = suffix_dedup._stretches(part)
        assert [p for p, _, _ in found] == sorted(set(part.tolist())) and found[0][1] == 0 and found[-1][2] == len(part)
        for p, a, b in found:
            assert (part[a:b] == p).all()
            assert len(set(suffix_dedup._unpack(suffix_dedup._pack(anchors[a:b], p, parts)).tolist())) == len(set(anchors[a:b].tolist()))
    assert suffix_dedup._stretches(np.zeros(0, np.int64)) == []
