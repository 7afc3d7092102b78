"""Item frames ``report_id, client_id, item, epoch``: one private datum per report, from any registered key."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.prf import SPAN, prf
from .tables import load

#: Shares of the 16 bands fall by this factor, so that the largest is about a third and the smallest a six-hundredth.
BAND_RATIO, BANDS = 0.702, 16
DAY = "date'2024-01-01'"
#: Line numbers repeat inside an order, so a line is named by these.
LINE_COLUMNS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
LINE_SQL = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "CAST(l_shipdate AS DATE)")


def line_key() -> tuple:
    return (*LINE_COLUMNS[:4], F.col("l_shipdate").cast("date"))


def band_ladder() -> list[tuple[str, int, int]]:
    """``(band, low, high)`` integer bounds of the ladder over the 52-bit range."""
    weights = [BAND_RATIO**i for i in range(BANDS)]
    total, low, out = sum(weights), 0, []
    done = 0.0
    for i, w in enumerate(weights):
        done += w
        high = SPAN if i == BANDS - 1 else int(done / total * SPAN)
        out.append((f"b{i:02d}", low, high))
        low = high
    return out


def _frame(df: DataFrame, report: str, client: str, item: str, epoch: str = DAY) -> DataFrame:
    return df.selectExpr(f"cast({report} as long) report_id", f"cast({client} as long) client_id", f"cast({item} as string) item", f"to_date({epoch}) epoch")


def words(df: DataFrame, text: str = "text") -> F.Column:
    return F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit("[a-z]+"), F.lit(0))


def _priority(s, d):
    return _frame(load(s, d, "orders", ["o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate"]), "o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate")


def _lang(s, d):
    return _frame(load(s, d, "documents", ["doc_id", "lang"]), "doc_id", "doc_id", "lang")


def _source(s, d):
    return _frame(load(s, d, "documents", ["doc_id", "source"]), "doc_id", "doc_id", "source")


def _event_type(s, d):
    return _frame(load(s, d, "events", ["event_id", "user_id", "event_type", "ts"]), "event_id", "user_id", "event_type", "ts")


def _prop_k(s, d):
    return _frame(load(s, d, "events", ["event_id", "user_id", "props", "ts"]), "event_id", "user_id", "get_json_object(props, '$.k')", "ts")


def _brand(s, d):
    parts = load(s, d, "part", ["p_partkey", "p_brand"])
    lines = load(s, d, "lineitem", LINE_COLUMNS).withColumn("rid", prf(7, "rid", *line_key()))
    return _frame(lines.join(parts, lines.l_partkey == parts.p_partkey), "rid", "l_orderkey", "p_brand", "l_shipdate")


def _psize(s, d):
    return _frame(load(s, d, "part", ["p_partkey", "p_size"]), "p_partkey", "p_partkey", "p_size")


def _nation(s, d):
    people, nations = load(s, d, "customer", ["c_custkey", "c_nationkey"]), load(s, d, "nation", ["n_nationkey", "n_name"])
    return _frame(people.join(nations, people.c_nationkey == nations.n_nationkey), "c_custkey", "c_custkey", "n_name")


def _band16(s, d):
    lines = load(s, d, "lineitem", LINE_COLUMNS).withColumn("u", prf(7, "band", *line_key())).withColumn("rid", prf(7, "rid", *line_key()))
    # the ladder covers the range of ``u``, which is never null, so a band needs no null and the filter on it costs no digests
    (last, _, _), *below = reversed(band_ladder())
    band = F.lit(last)
    for name, _, high in below:
        band = F.when(F.col("u") < high, name).otherwise(band)
    return _frame(lines.withColumn("band", band), "rid", "l_orderkey", "band", "l_shipdate")


def _url20(s, d):
    return _frame(load(s, d, "pages", ["page_id", "url"]), "page_id", "page_id", "left(url, 20)")


def _host(s, d):
    return _frame(load(s, d, "pages", ["page_id", "url"]), "page_id", "page_id", "regexp_extract(url, '^[a-z]+://([^/]+)', 1)")


def _href(s, d):
    links = load(s, d, "pages", ["page_id", "html"]).select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("n", "href"))
    return _frame(links, "page_id * 10000 + n", "page_id", "left(href, 20)")


def _word(s, d):
    rows = load(s, d, "documents", ["doc_id", "text"])
    each = rows.select("doc_id", F.explode(F.array_distinct(words(rows))).alias("word"))
    return _frame(each.withColumn("rid", prf(7, "rid", "doc_id", "word")), "rid", "doc_id", "word")


def _doc_word1(s, d):
    rows = load(s, d, "documents", ["doc_id", "text"])
    each = rows.select("doc_id", F.explode(F.array_distinct(words(rows))).alias("word"))
    one = each.groupBy("doc_id").agg(F.min_by("word", prf(7, "pick", "doc_id", "word")).alias("word"))
    return _frame(one, "doc_id", "doc_id", "word")


def _chat_words(s, d):
    rows = load(s, d, "conversations", ["conv_id", "text"])
    each = rows.select("conv_id", F.explode(words(rows)).alias("word")).distinct()
    return _frame(each.withColumn("rid", prf(7, "rid", "conv_id", "word")), "rid", "conv_id", "word")


def _role(s, d):
    return _frame(load(s, d, "conversations", ["conv_id", "turn", "role"]), "conv_id * 1000 + turn", "conv_id", "role")


def _toxic(s, d):
    return _frame(load(s, d, "labels", ["doc_id", "toxic"]), "doc_id", "doc_id", "toxic")


def _quality(s, d):
    return _frame(load(s, d, "labels", ["doc_id", "quality"]), "doc_id", "doc_id", "quality")


def _label(s, d):
    return _frame(load(s, d, "embeddings", ["vec_id", "label"]), "vec_id", "vec_id", "label")


KEYS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__[1:]: f for f in (_priority, _lang, _source, _event_type, _prop_k, _brand, _psize, _nation, _band16, _url20, _host, _href, _word, _doc_word1, _chat_words, _role, _toxic, _quality, _label)}


def item_frame(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """Null and empty items are no datum and are left out."""
    return KEYS[key](spark, sf_dir).filter("item is not null and item <> ''")
