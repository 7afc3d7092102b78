"""Registry of the engine's queries, each beside the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Register ``fn(spark, sf_dir)``; without SQL only its rows are checked (and a test covers it)."""

    def put(fn):
        key = name or fn.__name__
        if key in QUERIES:
            raise ValueError(f"{key} is registered twice")
        QUERIES[key] = fn
        if sql:
            SQL[key] = sql
        return fn

    return put


# --- SQL text for the other side -----------------------------------------------------------------------------------------


def h(seed, tag, *parts) -> str:
    """The 52-bit replay value in SQL."""
    return f"(('0x' || substr(md5(concat_ws('|', '{seed}', '{tag}', {', '.join(map(str, parts))})), 1, 13))::BIGINT)"


def lt(seed, tag, p: float, *parts) -> str:
    return f"({h(seed, tag, *parts)} < {int(p * (1 << 52))})"


def items_sql(key: str) -> str:
    """The item frame of a key: ``report_id, client_id, item, epoch``."""
    from ..sources.items import LINE_SQL, band_ladder

    words = "SELECT DISTINCT {id}, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')) AS word FROM {t}"
    band = "CASE " + " ".join(f"WHEN u >= {a} AND u < {b} THEN '{n}'" for n, a, b in band_ladder()) + " END"
    body = {
        "priority": "SELECT o_orderkey AS report_id, o_custkey AS client_id, o_orderpriority AS item, CAST(o_orderdate AS DATE) AS epoch FROM orders",
        "lang": "SELECT doc_id AS report_id, doc_id AS client_id, lang AS item, DATE '2024-01-01' AS epoch FROM documents",
        "source": "SELECT doc_id AS report_id, doc_id AS client_id, source AS item, DATE '2024-01-01' AS epoch FROM documents",
        "event_type": "SELECT event_id AS report_id, user_id AS client_id, event_type AS item, CAST(ts AS DATE) AS epoch FROM events",
        "prop_k": "SELECT event_id AS report_id, user_id AS client_id, json_extract_string(props, '$.k') AS item, CAST(ts AS DATE) AS epoch FROM events",
        "brand": f"SELECT {h(7, 'rid', *LINE_SQL)} AS report_id, l_orderkey AS client_id, p_brand AS item, CAST(l_shipdate AS DATE) AS epoch FROM lineitem JOIN part ON l_partkey = p_partkey",
        "psize": "SELECT p_partkey AS report_id, p_partkey AS client_id, CAST(p_size AS VARCHAR) AS item, DATE '2024-01-01' AS epoch FROM part",
        "nation": "SELECT c_custkey AS report_id, c_custkey AS client_id, n_name AS item, DATE '2024-01-01' AS epoch FROM customer JOIN nation ON c_nationkey = n_nationkey",
        "band16": f"SELECT report_id, client_id, {band} AS item, epoch FROM (SELECT {h(7, 'rid', *LINE_SQL)} AS report_id, l_orderkey AS client_id, CAST(l_shipdate AS DATE) AS epoch, {h(7, 'band', *LINE_SQL)} AS u FROM lineitem)",
        "url20": "SELECT page_id AS report_id, page_id AS client_id, left(url, 20) AS item, DATE '2024-01-01' AS epoch FROM pages",
        "host": "SELECT page_id AS report_id, page_id AS client_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS item, DATE '2024-01-01' AS epoch FROM pages",
        "href": "SELECT page_id * 10000 + n - 1 AS report_id, page_id AS client_id, left(href, 20) AS item, DATE '2024-01-01' AS epoch FROM (SELECT page_id, unnest(l) AS href, generate_subscripts(l, 1) AS n FROM (SELECT page_id, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS l FROM pages))",
        "word": f"SELECT {h(7, 'rid', 'doc_id', 'word')} AS report_id, doc_id AS client_id, word AS item, DATE '2024-01-01' AS epoch FROM ({words.format(id='doc_id', t='documents')})",
        "doc_word1": f"SELECT doc_id AS report_id, doc_id AS client_id, arg_min(word, {h(7, 'pick', 'doc_id', 'word')}) AS item, DATE '2024-01-01' AS epoch FROM ({words.format(id='doc_id', t='documents')}) GROUP BY doc_id",
        "chat_words": f"SELECT {h(7, 'rid', 'conv_id', 'word')} AS report_id, conv_id AS client_id, word AS item, DATE '2024-01-01' AS epoch FROM ({words.format(id='conv_id', t='conversations')})",
        "role": "SELECT conv_id * 1000 + turn AS report_id, conv_id AS client_id, role AS item, DATE '2024-01-01' AS epoch FROM conversations",
        "toxic": "SELECT doc_id AS report_id, doc_id AS client_id, CAST(toxic AS VARCHAR) AS item, DATE '2024-01-01' AS epoch FROM labels",
        "quality": "SELECT doc_id AS report_id, doc_id AS client_id, CAST(quality AS VARCHAR) AS item, DATE '2024-01-01' AS epoch FROM labels",
        "label": "SELECT vec_id AS report_id, vec_id AS client_id, CAST(label AS VARCHAR) AS item, DATE '2024-01-01' AS epoch FROM embeddings",
    }[key]
    return f"(SELECT * FROM ({body}) WHERE item IS NOT NULL AND item <> '')"


def encode_sql(sp, source: str) -> str:
    j = f"({h(sp.seed, 'row', 'report_id')} % {sp.k} + 1)"
    return f"(SELECT *, {h(sp.seed, 'cell', 'j', 'item')} % {sp.m} + 1 AS r FROM (SELECT *, {j} AS j FROM {source}))"


def reports_sql(sp, source: str, identity: bool = False) -> str:
    """``report_id, client_id, item, epoch, j, r, own, x`` of an item frame."""
    base = f"(SELECT *, 1 AS j, CAST(item AS INTEGER) AS r FROM {source})" if identity else encode_sql(sp, source)
    own = f"(SELECT *, {lt(sp.seed, 'inc', sp.p, 'report_id')} AS own FROM {base})"
    draw = h(sp.seed, "ext", "report_id", "i") + " % i + 1"
    ranks = f"list_reduce(range({sp.m} - CASE WHEN own THEN {sp.s - 1} ELSE {sp.s} END, {sp.m}), lambda a, i: list_append(a, CASE WHEN list_contains(a, {draw}) THEN i ELSE {draw} END), CAST([] AS BIGINT[]))"
    ext = f"(SELECT *, {ranks} AS ranks FROM {own})"
    others = "list_transform(ranks, lambda v: CASE WHEN v >= r THEN v + 1 ELSE v END)"
    return f"(SELECT report_id, client_id, item, epoch, j, r, own, list_sort(CASE WHEN own THEN list_append({others}, r) ELSE {others} END) AS x FROM {ext})"


def matrix_sql(sp, source: str, by: str = "", identity: bool = False) -> str:
    lead = f"{by}, " if by else ""
    return f"(SELECT {lead}j, x, count(*) AS cnt FROM (SELECT {lead}j, unnest(x) AS x FROM {reports_sql(sp, source, identity)}) GROUP BY ALL)"


def support_sql(sp, domain: str, matrix: str) -> str:
    probes = f"(SELECT item, j, {h(sp.seed, 'cell', 'j', 'item')} % {sp.m} + 1 AS x FROM (SELECT DISTINCT item FROM {domain}), (SELECT unnest(range(1, {sp.k + 1})) AS j))"
    return f"(SELECT item, CAST(sum(coalesce(cnt, 0)) AS BIGINT) AS support FROM {probes} LEFT JOIN {matrix} USING (j, x) GROUP BY item)"


def estimate_sql(sp, source: str, domain: str | None = None) -> str:
    """``item, support, n, est`` of a lookup of the domain (default: the items present)."""
    sup = support_sql(sp, domain or source, "mx")
    return f"(WITH mx AS MATERIALIZED {matrix_sql(sp, source)} SELECT item, support, n, (support - n * {sp.u!r}) / {sp.p - sp.u!r} AS est FROM {sup}, (SELECT CAST(sum(cnt) / {sp.s} AS BIGINT) AS n FROM mx))"


def laplace_sql(unit: str, scale: float) -> str:
    return f"(-{scale!r} * sign({unit} - 0.5) * ln(greatest(1e-15, 1.0 - 2.0 * abs({unit} - 0.5))))"


def noisy_sql(counts: str, scale: float, seed, release: int = 0) -> str:
    """Adds ``noisy`` to ``item, cnt`` by the digest-keyed draw."""
    unit = f"(({h(seed, 'lap', repr(str(release)), 'sha256(item)')}::DOUBLE + 0.5) / 4503599627370496.0)"
    return f"(SELECT *, cnt + {laplace_sql(unit, scale)} AS noisy FROM {counts})"


def counts_sql(key: str) -> str:
    return f"(SELECT item, count(*) AS cnt FROM {items_sql(key)} GROUP BY item)"
