"""Language identification: one frozen context-trie model per language, exact code lengths, shortest wins.

Words are runs of letters (Unicode categories L, with the marks that follow them), lower-cased; the code length of a text is that of
its words, each with a closing space. Each language's model is fitted on a bounded sample of its labelled documents, whole
texts: the ``SAMPLE_DOCS`` with the least hash of id and text, fewer where the languages are so many that ``SAMPLE_TOTAL`` would
be passed (no language is left out; one whose rows nearly all repeat may be learnt from the row of least hash alone). The sample
takes two reads of the table at any number of languages. Costs of distinct words are remembered per worker.

``und`` with score 0 for null, empty and letterless texts, and for all when nothing is labelled. Rows with a null ``lang``, ``text`` or
``doc_id`` are not learnt from; null ids are predicted and not held out. Ties go to the language that sorts first. Repeated rows
are scored alike, one row each; a text of any length is scored whole. An empty table gives an empty result. Columns other than
``doc_id, text, lang`` are not read and may have any name, but for those that the caller carries along.
"""

from __future__ import annotations

import re
import uuid

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import ppm
from ._util import Recent, only, ship, slices

ORDER, SAMPLE_DOCS, SAMPLE_TOTAL, CACHE = 4, 400, 200_000, 250_000
_PLAIN, LETTERS = re.compile("[a-z]+"), regex.compile(r"\p{L}[\p{L}\p{M}]*")


def held_out(k: int, rest: int):
    """Whether crc32 of the doc_id as text leaves ``rest`` modulo ``k`` (null ids: no)."""
    return F.coalesce((F.crc32(F.col("doc_id").cast("string").cast("binary")) % k) == rest, F.lit(False))


def letter_words(text: str) -> list[str]:
    text = text.lower()
    return (_PLAIN if text.isascii() else LETTERS).findall(text)


class Languages:
    """Models by language and a word memory of their code lengths."""

    def __init__(self, names: list[str], models: list[ppm.Model]):
        self.names, self.models, self.known = names, models, Recent(CACHE)

    def totals(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Bits per (text, language), and words per text."""
        split = [letter_words(t) for t in texts]
        if new := self.known.missing(set().union(*split)):
            raw = [w.encode("utf-8", "surrogatepass") for w in new]
            table = np.stack([m.bits(raw) for m in self.models], 1).astype(np.float32).tobytes()
            row = 4 * len(self.names)
            self.known.now.update((w, table[i : i + row]) for w, i in zip(new, range(0, len(table), row), strict=True))
        get, sizes = self.known.now.__getitem__, np.array([len(s) for s in split])
        out = np.zeros((len(texts), len(self.names)))
        for i, s in enumerate(split):
            if s:
                out[i] = np.frombuffer(b"".join(map(get, s)), np.float32).reshape(len(s), -1).sum(0, dtype=float)
        return out, sizes

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score (posterior with the evidence of a text scaled by the root of its words) and bits per word."""
        bits, sizes = self.totals(texts)
        low = bits.min(1, keepdims=True)
        weight = np.exp2((low - bits) / np.sqrt(np.maximum(sizes, 1))[:, None])
        best = bits.argmin(1)
        score = np.where(sizes > 0, weight[np.arange(len(best)), best] / weight.sum(1), 0.0)
        names = [self.names[b] if n else "und" for b, n in zip(best.tolist(), sizes.tolist(), strict=True)]
        return names, score, np.where(sizes > 0, low[:, 0] / np.maximum(sizes, 1), 0.0)


def fit(docs: DataFrame, order: int = ORDER, sample_docs: int = SAMPLE_DOCS, hold=(4, 2)) -> tuple[list[str], list[tuple]]:
    """Language names and (keys, counts) per language, from the bounded sample."""
    ship(docs.sparkSession)
    rows = docs.selectExpr("cast(doc_id as long) doc_id", "text", "lang").filter("lang is not null and text is not null and doc_id is not null")
    if hold:
        rows = rows.filter(~held_out(*hold))
    rows = rows.withColumn("h", F.xxhash64("doc_id", "text"))
    found = rows.groupBy("lang").agg(F.count("*").alias("n"), F.min("h").alias("least")).collect()  # a row a language
    if not found:
        return [], []
    names = sorted(r["lang"] for r in found)
    most = max(1, min(sample_docs, SAMPLE_TOTAL // len(names)))
    # hashes are spread evenly: three times as many rows as needed, and some, come under the bound; a rank settles the rest
    bounds = [(r["lang"], max(float(r["least"]), min(1.0, (3 * most + 50) / r["n"]) * 2.0**64 - 2.0**63)) for r in found]
    near = rows.join(F.broadcast(docs.sparkSession.createDataFrame(bounds, "lang string, bound double")), "lang").filter(F.col("h").cast("double") <= F.col("bound"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("h", "doc_id", "text"))
    sample = near.withColumn("rank", rank).filter(F.col("rank") <= most).select("lang", "text")

    def work(batches):
        tally: dict[str, dict[str, int]] = {}
        for batch, texts in slices(batches):
            for lang, text in zip(batch.column("lang").to_pylist(), texts, strict=True):
                own = tally.setdefault(lang, {})
                for w in letter_words(text):
                    own[w] = own.get(w, 0) + 1
        for lang, own in tally.items():
            keys, counts = ppm.gather([w.encode("utf-8", "surrogatepass") for w in own], np.array(list(own.values()), float), order)
            yield pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([keys.tobytes()], pa.binary()), pa.array([counts.tobytes()], pa.binary())], names=["lang", "keys", "counts"])

    parts: dict[str, list] = {n: [] for n in names}
    for r in sample.mapInArrow(work, "lang string, keys binary, counts binary").collect():
        parts[r[0]].append((np.frombuffer(r[1], np.uint64), np.frombuffer(r[2], np.int64)))
    names = [n for n in names if any(len(k) for k, _ in parts[n])]
    return names, [ppm.merge(np.concatenate([k for k, _ in parts[n]]), np.concatenate([c for _, c in parts[n]])) for n in names]


def identify(docs: DataFrame, train: DataFrame | None = None, order: int = ORDER, sample_docs: int = SAMPLE_DOCS, hold=(4, 2)) -> DataFrame:
    """``doc_id, held_out, lang_pred, score, bits_per_word`` of every document."""
    out = with_language(docs, train, order, sample_docs, hold, [])
    return out.select("doc_id", held_out(*hold).alias("held_out"), "lang_pred", "score", "bits_per_word")


def with_language(docs: DataFrame, train: DataFrame | None, order: int, sample_docs: int, hold, carry: list[str]) -> DataFrame:
    """The documents' ``doc_id``, the ``carry`` columns and the prediction."""
    spark = ship(docs.sparkSession)
    names, counts = fit(docs if train is None else train, order, sample_docs, hold)
    shared = spark.sparkContext.broadcast((names, counts))  # bounded by languages x sampled documents
    key = uuid.uuid4().hex

    def work(batches):
        model = only(key, lambda: Languages(shared.value[0], [ppm.Model(k, c, order) for k, c in shared.value[1]]))
        for batch, texts in slices(batches, limit=4 << 20):
            if model.names:
                lang, score, bits = model.predict(texts)
            else:
                lang, score, bits = ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts))
            kept = ["doc_id", *carry]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(lang), pa.array(score), pa.array(bits)], names=[*kept, "lang_pred", "score", "bits_per_word"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *([] if "text" in carry else ["text"]), *carry)
    fields = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in ["doc_id", *carry])
    return rows.mapInArrow(work, f"{fields}, lang_pred string, score double, bits_per_word double")
