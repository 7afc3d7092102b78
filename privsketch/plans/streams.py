"""Queries of the streaming forms: each processes everything available and must equal the batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.theory import replayed
from ..operators import discover, randomize, sketch
from ..sources.tables import load, scratch
from ..streaming import stream
from .core import B_, R6, T_, _r6
from .registry import h, items_sql, laplace_sql, matrix_sql, query, reports_sql

_SP = replayed(2, 8, 2, 0.7, 42)


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(_SP, items_sql('event_type'), 'epoch')}")
def stream_tumbling_sketch(s, d):
    out = stream.run_available(stream.tumbling_sketch(stream.events(s, d), _SP))
    return out.select(F.col("epoch").cast("string"), F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query(f"SELECT CAST(CAST(w AS DATE) AS VARCHAR) AS epoch, CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, count(*) AS cnt FROM (SELECT epoch, j, unnest(x) AS x FROM {reports_sql(_SP, items_sql('event_type'))}), (SELECT DATE '2023-12-01' + CAST(i AS INTEGER) AS w FROM range(120) t(i)) WHERE epoch >= w AND epoch < w + 7 GROUP BY 1, 2, 3")
def stream_sliding_sketch(s, d):
    out = stream.run_available(stream.sliding_sketch(stream.events(s, d), _SP))
    return out.select(F.col("epoch").cast("string"), F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


_SESSIONS = "SELECT *, row_number() OVER (PARTITION BY user_id, g ORDER BY ts, event_id) AS place FROM (SELECT *, sum(CASE WHEN gap THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 12 HOUR, true) AS gap FROM events))"
_KEPT = f"(SELECT event_id AS report_id, user_id AS client_id, event_type AS item, DATE '2024-01-01' AS epoch FROM ({_SESSIONS}) WHERE place <= 2)"


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(_SP, _KEPT)}")
def stream_session_cap(s, d):
    """Matrix of the reports that two events a session allow."""
    kept = stream.session_capped(stream.events(s, d), limit=2)
    sent = randomize.subset_reports(kept.select(F.col("event_id").alias("report_id"), F.col("event_type").alias("item")), _SP)
    return sketch.build(sent).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query("SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events) WHERE rn <= 3")
def stream_cap_state(s, d):
    return stream.run_available(stream.capped(stream.events(s, d), 3), "append").select("user_id", "event_id")


@query("SELECT event_id, user_id FROM events")
def stream_dedupe(s, d):
    once = stream.events(s, d)
    return stream.run_available(stream.dedupe(once.union(once)), "append").select("event_id", "user_id")


def _days(s, d, *spans):
    """Events of some spans of days, as frames."""
    rows = load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return [rows.filter((F.col("ts") >= F.lit(a).cast("timestamp")) & (F.col("ts") < F.lit(b).cast("timestamp"))) for a, b in spans]


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS epoch, count(*) AS cnt FROM events WHERE ts >= TIMESTAMP '2024-01-20' AND CAST(ts AS DATE) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1")
def stream_late(s, d):
    """Days up to the 20th come last, when the watermark has passed them: their rows are dropped."""
    order = _days(s, d, ("2024-01-20", "2024-01-30"), ("2024-01-30", "2030-01-01"), ("2000-01-01", "2024-01-20"))
    out = stream.run_available(stream.closed_counts(stream.in_order(order, scratch(s, "late"))), "append")
    return out.select(F.col("epoch").cast("string"), "cnt")


@query()
def stream_retune(s, d):
    schedule: list = []
    order = _days(s, d, ("2000-01-01", "2024-01-11"), ("2024-01-11", "2024-01-21"), ("2024-01-21", "2030-01-01"))
    stream.run_available(stream.in_order(order, scratch(s, "retune")), "append", stream.retune_on_batch(replayed(8, 64, 5, 0.6), "click", 2.0, schedule))
    return s.createDataFrame(schedule, "ver long, p double, s int, n long, est double, lam double, next_p double, next_s int, next_eps double")


@query("SELECT event_type AS item, 2 AS weight, count(*) AS cnt FROM events WHERE event_type IN ('click', 'view') GROUP BY 1")
def stream_static_join(s, d):
    domain = s.createDataFrame([("click", 2), ("view", 2)], "item string, weight int")
    return stream.run_available(stream.with_domain(stream.events(s, d), domain))


_W = "CAST(CAST(TIMESTAMP '1970-01-01' + to_days(CAST(floor(epoch(ts) / 864000) * 10 AS INTEGER)) AS DATE) AS VARCHAR)"


@query(f"SELECT epoch, lower(sha256(item)) AS digest, cnt FROM (SELECT {_W} AS epoch, event_type AS item, count(*) AS cnt FROM events GROUP BY 1, 2)")
def stream_discovery(s, d):
    out = stream.run_available(stream.discovery_counts(stream.events(s, d), "event_type"))
    return out.select(F.col("epoch").cast("string"), F.lower(F.hex("digest")).alias("digest"), "cnt")


_KEY = h(42, "lap", "'0'", "lower(hex(epoch)) || sha256(item)")
_UNIT = f"(({_KEY}::DOUBLE + 0.5) / 4503599627370496.0)"


@query(f"SELECT epoch, item, {_r6('noisy')} AS noisy FROM (SELECT *, cnt + {laplace_sql(_UNIT, B_)} AS noisy FROM (SELECT {_W} AS epoch, event_type AS item, count(*) AS cnt FROM events GROUP BY 1, 2)) WHERE noisy >= {T_!r}")
def stream_release(s, d):
    """Names that the server opens from every closed window's release."""
    closed = stream.run_available(stream.discovery_counts(stream.events(s, d), "event_type"))
    out = stream.release(closed, T_, B_, 42)
    return discover.open_items(out, "server", ("epoch",)).select(F.col("epoch").cast("string"), "item", R6(F.col("noisy")).alias("noisy"))
