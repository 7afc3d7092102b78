import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from privsketch.llm import language_id, lm_score, ppm, toxicity
from privsketch.llm._util import lower_ascii, tokens


@pytest.mark.parametrize("order", [1, 2, 3])
def test_context_trie_is_a_distribution(order):
    """The end and all first bytes together have probability one."""
    words = [b"aab", b"ab", b"ba", b"b"]
    model = ppm.Model(*ppm.merge(*ppm.gather(words, np.array([3.0, 2, 1, 1]), order)), order)
    ends = 2 ** -model.bits([b""])[0]
    every = ends
    for b in range(256):
        if b == 32:
            continue
        every += _prefix_probability(model, bytes([b]))
    assert abs(every - 1) < 1e-9


def _prefix_probability(model, prefix):
    return 2 ** -(model.bits([prefix])[0] - _end_cost(model, prefix))


def _end_cost(model, prefix):
    """Bits of the closing space after the prefix, by the escape rule written out."""
    cost, child = 0.0, None
    for o in range(min(model.order, len(prefix) + 1), -1, -1):
        ctx = int.from_bytes((b" " + prefix)[len(prefix) + 1 - o :], "big") if o else 0
        key = np.array([(o << 48) | ctx], np.uint64)
        node = model.nodes.get(key)[0]
        if node < 0:
            continue
        total = model.total[node] - (model.excluded[child] if child is not None else 0)
        kinds = model.kinds[node] - (model.kinds[child] if child is not None else 0)
        entry = model.entries.get(np.array([(o << 56) | ctx << 8 | 32], np.uint64))[0]
        if entry >= 0:
            return cost + math.log2((total + kinds) / model.count[entry])
        if kinds > 0:
            cost += math.log2((total + kinds) / kinds)
        child = node
    root = model.nodes.get(np.zeros(1, np.uint64))[0]
    return cost + math.log2(256 - model.kinds[root])


def test_unknown_bytes_cost_more_and_empty_model_is_uniform():
    model = ppm.Model(*ppm.merge(*ppm.gather([b"the", b"then"], np.array([5.0, 1]), 3)), 3)
    the, zzz = model.bits([b"the", b"zzz"])
    assert the < 3 < zzz
    empty = ppm.Model(np.zeros(0, np.uint64), np.zeros(0, np.int64), 3)
    assert empty.bits([b"ab"])[0] == pytest.approx(24)


def test_language_identification_on_held_out_documents(spark, medium):
    docs = spark.read.parquet(f"{medium}/documents.parquet")
    got = language_id.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").filter("held_out").toPandas()
    assert len(got) > 100 and (got["lang"] == got["lang_pred"]).mean() > 0.97
    assert got["score"].between(0, 1).all()


def test_language_identification_of_odd_documents(spark, odd, none, texts):
    rows = language_id.identify(odd).collect()
    assert len(rows) == len(texts)
    by = {r.doc_id: r for r in rows}
    assert by[1].lang_pred == by[2].lang_pred == by[3].lang_pred == "und" and by[1].score == 0.0
    assert all(r.lang_pred in ("en", "fr", "de", "und") and r.held_out is not None for r in rows)
    assert language_id.identify(none).count() == 0
    unlabelled = odd.withColumn("lang", F.lit(None).cast("string"))
    assert {r.lang_pred for r in language_id.identify(unlabelled).collect()} == {"und"}


def test_letters_are_those_of_unicode():
    assert language_id.letter_words("½ ② ² 3\u0301 _ \u2167") == []
    assert language_id.letter_words("Ein A\u0308pfel, हिन्दी ªb") == ["ein", "a\u0308pfel", "हिन्दी", "ªb"]


def test_many_languages_and_languages_of_repeats(spark):
    """Far more languages than the sample has room for at full size, one of them a single text over and over."""
    rows = [(2 * i, f"{chr(0x4E00 + i)}{chr(0x5E00 + i)} {chr(0x4E00 + i)}", f"x{i:03}") for i in range(600)]
    rows += [(100_000 + i, "toujours la", "zz") for i in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    names, counts = language_id.fit(docs, sample_docs=3, hold=None)
    assert len(names) == 601 and all(len(k) for k, _ in counts)
    got = {r.doc_id: r.lang_pred for r in language_id.identify(docs, sample_docs=3, hold=(1, 2)).collect()}
    assert all(got[i] == lang for i, _, lang in rows)


def test_sample_is_bounded_and_holds_the_least_hashes(spark):
    docs = spark.range(5000).selectExpr("id doc_id", "concat('w', id) text", "if(id % 3 = 0, 'a', 'b') lang")
    names, counts = language_id.fit(docs, order=0, sample_docs=20, hold=None)
    order = docs.selectExpr("lang", "text", "row_number() over (partition by lang order by xxhash64(doc_id, text)) r").filter("r <= 20").collect()
    for n, (keys, c) in zip(names, counts, strict=True):
        assert c.sum() == sum(len(language_id.letter_words(r.text)[0]) + 1 for r in order if r.lang == n)


def words_of(text):
    text = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x20\x09-\x0D]+", text)


def check_base(rows, got):
    count, n = Counter(), 0
    for i, t in rows:
        if i is None or zlib.crc32(str(i).encode()) % 7 != 2:
            w = [*words_of(t), None]
            count.update(w)
            n += len(w)
    v = len(count)
    for i, t in rows:
        w = [*words_of(t), None]
        base = sum(math.log10((count[x] + 1) / (n + v + 1)) for x in w)
        known = sum(count[x] > 0 for x in w)
        assert any(abs(r.base_score - base) < 1e-6 * max(1, abs(base)) and r.n_known == known and r.n_tokens == len(w) and r.train_tokens == n for r in got if r.doc_id == i)


def brute_costs(streams, order):
    """Plain form of the model: nested counts, escapes by method D, exclusion by sets; returns a function text -> log10 probability."""
    after = [{} for _ in range(order + 1)]
    for t in streams:
        line = b"\n" * order + t + b"\n"
        for i in range(order, len(line)):
            for o in range(order + 1):
                ctx = line[i - o : i]
                after[o].setdefault(ctx, Counter())[line[i]] += 1

    def code(t):
        line, total = b"\n" * order + t + b"\n", 0.0
        for i in range(order, len(line)):
            out = set()
            for o in range(order, -1, -1):
                seen = after[o].get(line[i - o : i])
                if not seen:
                    continue
                left = {c: 2 * n - 1 for c, n in seen.items() if c not in out}
                if not left:
                    continue
                whole = sum(left.values()) + len(left)
                if line[i] in left:
                    total += math.log10(left[line[i]] / whole)
                    break
                total += math.log10(len(left) / whole)
                out |= left.keys()
            else:
                total -= math.log10(256 - len(out))
        return total

    return code


def check_scores(rows, got, order=lm_score.ORDER):
    stream = lambda t: b" ".join(w.encode() for w in words_of(t))
    code = brute_costs([stream(t) for i, t in rows if i is None or zlib.crc32(str(i).encode()) % 7 != 2], order)
    want, have = sorted(((i or 0), code(stream(t))) for i, t in rows), sorted(((r.doc_id or 0), r.score) for r in got)
    assert [i for i, _ in have] == [i for i, _ in want] and [v for _, v in have] == pytest.approx([v for _, v in want])


def test_language_model_scores(spark, small, odd, none, texts):
    docs = spark.read.parquet(f"{small}/documents.parquet").limit(70)
    docs = spark.createDataFrame(docs.collect(), docs.schema)
    got, rows = lm_score.score(docs).collect(), [(r.doc_id, r.text) for r in docs.collect()]
    check_base(rows, got)
    check_scores(rows, got)
    assert [r for r in got if r.held_out]
    rows = [(i, t) for i, t, *_ in texts]
    check_base(rows, lm_score.score(odd).collect())
    check_scores(rows, lm_score.score(odd, order=3).collect(), 3)
    assert lm_score.score(none).count() == 0


def test_language_model_without_training_rows(spark):
    held = next(i for i in range(99) if zlib.crc32(str(i).encode()) % 7 == 2)
    r = lm_score.score(spark.createDataFrame([(held, "Ab c")], "doc_id long, text string")).first()
    assert (r.n_tokens, r.n_known, r.train_tokens, r.base_score) == (3, 0, 0, 0.0) and r.score == pytest.approx(-5 * math.log10(256))


def test_language_model_beats_the_baseline(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    r = lm_score.score(docs).filter("held_out").selectExpr("sum(score) s", "sum(base_score) b", "sum(n_tokens) n").first()
    assert r.s > r.b and r.s / r.n > -4.06


def test_contexts_cross_words():
    full = ppm.stream_counts([b"red fox"] * 9 + [b"big dog"] * 9, 5)
    upper = ppm.shorter(*ppm.tally(full[0] & np.uint64(0xFFFF), full[1]), 1)
    model = lm_score.model_of(*full, upper, 5)
    fits, mixed = model.stream_bits([b"red fox", b"red dog"])
    assert fits < 3 < mixed


def test_context_sums_and_messages(spark, small):
    """Adding up by range loses no context at any number of buckets, and messages never outnumber what they carry."""
    docs = spark.read.parquet(f"{small}/documents.parquet").limit(80)
    docs = spark.createDataFrame(docs.select("doc_id", "text").collect(), "doc_id long, text string").withColumn("held_out", language_id.held_out(*lm_score.HOLD))
    streams = [b" ".join(w.encode() for w in words_of(r.text)) for r in docs.filter("not held_out").collect()]
    want = ppm.stream_counts(streams, 4)
    for buckets in (1, 3, 12):
        back = lm_score.added_up(lm_score.sent(lm_score.bucketed(docs, buckets), buckets, 4)).collect()
        keys, counts = ppm.tally(*(np.concatenate(x) for x in zip(*(lm_score.expand(r.one) for r in back if r.kind == 1), strict=True)))
        assert all((a == b).all() for a, b in zip((keys[counts > 0], counts[counts > 0]), want, strict=True))
        assert sum(r.kind == 0 for r in back) <= buckets * buckets
        assert sum(r.strings for r in back if r.kind == 2) == len(keys)


def test_prices_by_branch_equal_the_whole_trie(spark, small):
    """Branches hold what a context needs: any number of them and any order give the scores of the plain form."""
    docs = spark.read.parquet(f"{small}/documents.parquet").limit(40)
    docs = spark.createDataFrame(docs.select("doc_id", "text").collect(), "doc_id long, text string")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    for order, most in ((1, 400_000), (2, 50), (4, 50)):
        check_scores(rows, lm_score.score(docs, order=order, branch_keys=most).collect(), order)
    keys = ppm.stream_counts([(t or "").encode() for _, t in rows], 5)[0]
    assert len(np.unique(lm_score.branch_of(keys, 64))) > 32
    upper, _ = ppm.shorter(*ppm.tally(keys & np.uint64(0xFFFF), np.ones(len(keys), np.int64)), 1)
    assert len(upper) <= 65_792


def subsequence_kernel(a, b, decay, span):
    """Textbook sum over index triples, weights by the letters spanned."""
    def feats(s):
        out = Counter()
        s = "{" + s + "{"
        for i in range(len(s)):
            for j in range(i + 1, len(s)):
                for k in range(j + 1, min(len(s), i + span)):
                    out[s[i] + s[j] + s[k]] += decay ** (k - i + 1)
        return out

    fa, fb = feats(a), feats(b)
    dot = lambda x, y: sum(v * y[f] for f, v in x.items())
    return dot(fa, fb) / math.sqrt(dot(fa, fa) * dot(fb, fb))


def test_string_kernel_equals_the_sum():
    units = ["idiot", "idxiot", "house", "idioot", "ab"]
    got = toxicity.kernel(units, toxicity.dense(units))
    for i, a in enumerate(units):
        for j, b in enumerate(units):
            assert got[i, j] == pytest.approx(subsequence_kernel(a, b, toxicity.DECAY, toxicity.SPAN), abs=1e-5)
    assert got[0, 1] > 0.5 > got[0, 2]


def test_folded_weights_equal_the_feature_map():
    units, marks = ["idiot", "trash", "these", "words"], ["idiot", "clown", "these"]
    table = toxicity.dense(marks)
    w = np.array([0.7, -0.2, 0.4])
    assert toxicity.values(units, table @ w, -0.5) == pytest.approx(toxicity.kernel(units, table) @ w - 0.5, abs=1e-5)


def test_units_tolerate_gaps():
    assert "idiot" in toxicity.units_of_token("i.d.i.o.t")
    assert "idiot" in toxicity.units_of_token("id-iot")
    assert toxicity.spelled("what an i d i o t here") and "idiot" in toxicity.spelled("what an i d i o t here")
    assert toxicity.spelled("plain words only") == []
    assert toxicity.units_of_token("123") == ()


def test_rare_insults_of_large_label_sets():
    assert (toxicity.LANDMARKS, toxicity.ROUNDS) == (512, 5)
    r = random.Random(3)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    plain = [word() for _ in range(300)]
    bags = [(sorted({*r.sample(plain, 10), "twit" if i % 100 else "zoykum"}), 1) for i in range(2500)] + [(sorted(r.sample(plain, 10)), 0) for _ in range(2500)]
    rare, common, clean = toxicity.train(bags).score(["zoykum zoykum! zoykum, (zoykum)", "twit twit! twit,", " ".join(plain[:10])])
    assert rare >= toxicity.THRESHOLD and common >= toxicity.THRESHOLD > clean


def test_toxicity_on_held_out_documents(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = toxicity.toxicity(docs, labels).join(labels, "doc_id").filter("held_out").toPandas()
    hit = ((got.predicted == 1) & (got.toxic == 1)).sum()
    assert hit / (got.toxic == 1).sum() > 0.75 and hit / (got.predicted == 1).sum() > 0.75


def test_toxicity_of_odd_documents(spark, odd, none, texts):
    labels = spark.createDataFrame([(4, 1, 1), (7, 0, 0), (None, 1, 1), (5, 0, None), (4, 0, 0)], "doc_id long, quality int, toxic int")
    rows = toxicity.toxicity(odd, labels).collect()
    assert len(rows) == len(texts) and all(0 <= r.score <= 1 and r.held_out is not None and r.predicted == int(r.score >= 0.7) for r in rows)
    assert {r.predicted for r in toxicity.toxicity(odd, labels.filter("false")).collect()} == {0}
    assert toxicity.toxicity(none, labels).count() == 0
