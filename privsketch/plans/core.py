"""Queries of the collection methods: randomiser, sketch, estimates, relay, sealing, discovery, joint use, attacks."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import accounting, theory, tune
from ..functions.theory import SketchParams, replayed
from ..operators import attacks, discover, estimate, exact, joint, oracles, randomize, relay, seal, sketch
from ..sources.items import item_frame
from .registry import counts_sql, encode_sql, estimate_sql, h, items_sql, lt, matrix_sql, noisy_sql, query, reports_sql, support_sql

SMOKE = replayed(8, 64, 5, 0.6, 42)
EDGE = replayed(4, 16, 1, 0.6, 42)
PLAIN = replayed(1, 50, 5, 0.7, 42)
CODES = replayed(1, 50, 5, 0.7, 42)
EPS, DELTA = 2.0, 1e-5
T_, B_ = accounting.calibrate(EPS, DELTA)
R6 = lambda c: F.round(c, 6) + F.lit(0.0)


def _r6(x: str) -> str:
    return f"round({x}, 6) + 0.0"


#: Counts of every event type and day, with the sum of all (``n``), the day's sum and its sum of squares.
DAYS_SQL = f"(SELECT *, CAST(sum(f) OVER () AS BIGINT) AS n, CAST(sum(f) OVER (PARTITION BY epoch) AS BIGINT) AS day_n, CAST(sum(f * f) OVER (PARTITION BY epoch) AS BIGINT) AS m2 FROM (SELECT item, CAST(epoch AS VARCHAR) AS epoch, count(*) AS f FROM {items_sql('event_type')} GROUP BY 1, 2))"
DAY_SQL = f"(SELECT epoch, CAST(sum(f) AS BIGINT) AS n FROM {DAYS_SQL} GROUP BY 1)"


def day_counts(s, d):
    """``item, epoch, f, n, day_n, m2`` of the event types: the targets and totals of the closed forms."""
    counts = item_frame(s, d, "event_type").groupBy("item", F.col("epoch").cast("string").alias("epoch")).agg(F.count("*").alias("f"))
    day = Window.partitionBy("epoch")
    each = counts.withColumns({"day_n": F.sum("f").over(day), "m2": F.sum(F.col("f") * F.col("f")).over(day)})
    return each.crossJoin(F.broadcast(counts.agg(F.sum("f").alias("n")))).select("item", "epoch", "f", "n", "day_n", "m2")


def days(s, d):
    """``epoch, n``: a day's reports."""
    return item_frame(s, d, "event_type").groupBy(F.col("epoch").cast("string").alias("epoch")).agg(F.count("*").alias("n"))


@query(f"SELECT report_id, CAST(j AS BIGINT) AS j, CAST(r AS BIGINT) AS r FROM {encode_sql(SMOKE, items_sql('priority'))}")
def hash_encode(s, d):
    return randomize.encode(item_frame(s, d, "priority"), SMOKE).select("report_id", F.col("j").cast("long"), F.col("r").cast("long"))


@query(f"SELECT report_id, {lt(42, 'inc', 0.6, 'report_id')} AS own FROM {items_sql('priority')}")
def inclusion(s, d):
    return randomize.include(item_frame(s, d, "priority"), SMOKE).select("report_id", "own")


@query(f"SELECT report_id, CAST(j AS BIGINT) AS j, array_to_string(x, ',') AS cells FROM {reports_sql(SMOKE, items_sql('priority'))}")
def subset_reports(s, d):
    return randomize.subset_reports(item_frame(s, d, "priority"), SMOKE, keep=["report_id"]).select("report_id", F.col("j").cast("long"), F.array_join("x", ",").alias("cells"))


@query(f"SELECT report_id, CAST(j AS BIGINT) AS j, array_to_string(x, ',') AS cells FROM {reports_sql(EDGE, items_sql('lang'))}")
def subset_reports_single(s, d):
    return randomize.subset_reports(item_frame(s, d, "lang"), EDGE, keep=["report_id"]).select("report_id", F.col("j").cast("long"), F.array_join("x", ",").alias("cells"))


@query()
def subset_reports_permute(s, d):
    return randomize.subset_reports(item_frame(s, d, "lang"), replayed(4, 32, 4, 0.6), sampler="permute", keep=["report_id"])


@query()
def subset_reports_arrow(s, d):
    return randomize.subset_reports(item_frame(s, d, "band16"), SketchParams(100, 100, 7, 0.74), engine="arrow", keep=["report_id"])


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(SMOKE, items_sql('priority'))}")
def sketch_matrix(s, d):
    return sketch.build(randomize.subset_reports(item_frame(s, d, "priority"), SMOKE)).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT * FROM {matrix_sql(SMOKE, items_sql('priority'))} UNION ALL SELECT * FROM {matrix_sql(SMOKE, items_sql('event_type'))}) GROUP BY 1, 2")
def sketch_merge(s, d):
    parts = [sketch.build(randomize.subset_reports(item_frame(s, d, k), SMOKE)) for k in ("priority", "event_type")]
    return sketch.merge(*parts).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, CAST(sum(cnt) AS BIGINT) AS cnt FROM {matrix_sql(SMOKE, items_sql('event_type'), 'epoch')} GROUP BY 1, 2")
def sketch_rollup(s, d):
    daily = sketch.build(randomize.subset_reports(item_frame(s, d, "event_type"), SMOKE, keep=["epoch"]), ["epoch"])
    return sketch.rollup(daily, []).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(SMOKE, items_sql('priority'))}")
def sketch_subtract(s, d):
    a, b = (sketch.build(randomize.subset_reports(item_frame(s, d, k), SMOKE)) for k in ("priority", "event_type"))
    return sketch.subtract(sketch.merge(a, b), b).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query(f"SELECT item, support, CAST(n AS BIGINT) AS n, {_r6('est')} AS est FROM {estimate_sql(SMOKE, items_sql('priority'))}")
def freq_estimate(s, d):
    items = item_frame(s, d, "priority")
    return estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE).select("item", "support", "n", R6(F.col("est")).alias("est"))


@query(f"SELECT item, support, CAST(n AS BIGINT) AS n, {_r6('est')} AS est FROM {estimate_sql(SMOKE, items_sql('lang'))}")
def freq_estimate_lang(s, d):
    items = item_frame(s, d, "lang")
    return estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE).select("item", "support", "n", R6(F.col("est")).alias("est"))


@query(f"WITH mx AS MATERIALIZED {matrix_sql(SMOKE, items_sql('lang'))} SELECT * FROM {support_sql(SMOKE, items_sql('lang'), 'mx')}")
def freq_support_scan(s, d):
    items = item_frame(s, d, "lang")
    return estimate.support_scan(items, randomize.subset_reports(items, SMOKE), SMOKE)


@query(f"SELECT item, {_r6('greatest(est, 0.0)')} AS est FROM {estimate_sql(SMOKE, items_sql('source'))}")
def estimate_clip(s, d):
    items = item_frame(s, d, "source")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return estimate.consistency(est, "clip").select("item", R6(F.col("est")).alias("est"))


@query(f"SELECT item, {_r6('greatest(est, 0.0) * n / sum(greatest(est, 0.0)) OVER ()')} AS est FROM {estimate_sql(SMOKE, items_sql('source'))}")
def estimate_scale(s, d):
    items = item_frame(s, d, "source")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return estimate.consistency(est, "scale").select("item", R6(F.col("est")).alias("est"))


@query(f"WITH e AS MATERIALIZED {estimate_sql(SMOKE, items_sql('source'))}, c AS (SELECT est, (sum(est) OVER w - n) / row_number() OVER w AS cut, row_number() OVER w AS r FROM e WINDOW w AS (ORDER BY est DESC, item ROWS UNBOUNDED PRECEDING)) SELECT item, {_r6('greatest(est - (SELECT arg_max(cut, r) FROM c WHERE est > cut), 0.0)')} AS est FROM e")
def estimate_simplex(s, d):
    items = item_frame(s, d, "source")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return estimate.consistency(est, "simplex").select("item", R6(F.col("est")).alias("est"))


_VAR = "(f * {p} * (1 - {p}) + (n - f) * {u} * (1 - {u})) / (({p} - {u}) * ({p} - {u})) + (m2 - f * f - (n - f)) / ({k} * ({m} - 1))"


@query(f"SELECT item, {_r6('est')} AS est, {_r6('sqrt(greatest(v, 0.0))')} AS std_err, {_r6('est - 1.96 * sqrt(greatest(v, 0.0))')} AS lo, {_r6('est + 1.96 * sqrt(greatest(v, 0.0))')} AS hi FROM (SELECT *, {_VAR.format(p=repr(SMOKE.p), u=repr(SMOKE.u), k=SMOKE.k, m=SMOKE.m)} AS v FROM (SELECT *, greatest(est, 0.0) AS f, sum(greatest(est, 0.0) * greatest(est, 0.0)) OVER () AS m2 FROM {estimate_sql(SMOKE, items_sql('priority'))}))")
def estimate_interval(s, d):
    items = item_frame(s, d, "priority")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return estimate.interval(est, SMOKE).select("item", *(R6(F.col(c)).alias(c) for c in ("est", "std_err", "lo", "hi")))


_COUNTS = "(SELECT *, sum(f) OVER () AS n, sum(f * f) OVER () AS m2 FROM (SELECT item, count(*) AS f FROM {} GROUP BY item))"
_PUB = f"(f * ({SMOKE.p} - {SMOKE.p} * {SMOKE.p} / {SMOKE.k}) + (n - f) * ({SMOKE.u} - {SMOKE.u} * {SMOKE.u} / {SMOKE.k})) / (({SMOKE.p} - {SMOKE.u}) * ({SMOKE.p} - {SMOKE.u})) + (m2 - f * f - (n - f)) / ({SMOKE.k}.0 * ({SMOKE.m} - 1))"


@query(f"SELECT item, f, round({_VAR.format(p=repr(SMOKE.p), u=repr(SMOKE.u), k=SMOKE.k, m=SMOKE.m)}, 4) AS exact_var, round({_PUB}, 4) AS published_var FROM {_COUNTS.format(items_sql('priority'))}")
def variance_by_item(s, d):
    counts = exact.frequencies(item_frame(s, d, "priority"))
    out = counts.crossJoin(F.broadcast(counts.agg(F.sum("f").alias("n"), F.sum(F.col("f") * F.col("f")).alias("m2"))))
    f, n, m2 = F.col("f"), F.col("n"), F.col("m2")
    return out.select("item", "f", F.round(theory.variance(f, n, m2, SMOKE), 4).alias("exact_var"), F.round(theory.variance(f, n, m2, SMOKE, "published"), 4).alias("published_var"))


_CODE = "(SELECT report_id, client_id, item, epoch FROM " + items_sql("psize") + ")"


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(CODES, _CODE, identity=True)}")
def subset_identity(s, d):
    return sketch.build(randomize.subset_reports(item_frame(s, d, "psize"), CODES, hash="identity")).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


# --- relay, sealing ---


@query(f"SELECT item, count(*) AS cnt FROM {items_sql('event_type')} GROUP BY item")
def relay_multiset(s, d):
    return relay.permute(relay.strip(item_frame(s, d, "event_type")), 42, 8, ["item"]).groupBy("item").agg(F.count("*").alias("cnt"))


@query(f"SELECT report_id, client_id FROM (SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY {h(42, 'cap', 'report_id')}, report_id) AS rk FROM {items_sql('event_type')}) WHERE rk <= 5")
def contribution_cap(s, d):
    return relay.cap(item_frame(s, d, "event_type"), 5).select("report_id", "client_id")


@query(f"SELECT report_id, item FROM {items_sql('nation')}")
def seal_roundtrip(s, d):
    sealed = seal.seal(item_frame(s, d, "nation").select("report_id", "item"), "server", ["item"])
    return seal.unseal(sealed, "server", "item string").select("report_id", "item")


# --- discovery ---


@query(f"SELECT lower(sha256(item)) AS digest, cnt, {_r6('noisy')} AS noisy, noisy >= {T_!r} AS kept FROM {noisy_sql(counts_sql('url20'), B_, 42)}")
def blind_release(s, d):
    counts = discover.open_outer(discover.client(item_frame(s, d, "url20"), "server", "helper"), "helper").groupBy("digest").agg(F.count("*").alias("cnt"))
    return discover.noisy(counts, B_, 42).select(F.lower(F.hex("digest")).alias("digest"), "cnt", R6(F.col("noisy")).alias("noisy"), (F.col("noisy") >= T_).alias("kept"))


@query(f"SELECT item, {_r6('noisy')} AS noisy FROM {noisy_sql(counts_sql('url20'), B_, 42)} WHERE noisy >= {T_!r}")
def discovered_items(s, d):
    return discover.blind_histogram(item_frame(s, d, "url20"), T_, B_, 42).select("item", R6(F.col("noisy")).alias("noisy"))


@query(f"SELECT item, {_r6('noisy')} AS noisy FROM {noisy_sql(counts_sql('href'), B_, 42)} WHERE noisy >= {T_!r}")
def central_histogram(s, d):
    return discover.central_histogram(item_frame(s, d, "href"), T_, B_, 42).select("item", R6(F.col("noisy")).alias("noisy"))


def _geo(tag: str) -> str:
    return f"floor(ln(({h(42, tag, repr('0'), 'sha256(item)')}::DOUBLE + 0.5) / 4503599627370496.0) / {-1 / B_!r})"


@query(f"SELECT item, noisy FROM (SELECT item, CAST(cnt + {_geo('lap')} - {_geo('geo')} AS DOUBLE) AS noisy FROM {counts_sql('href')}) WHERE noisy >= {T_!r}")
def discovery_discrete_noise(s, d):
    counts = item_frame(s, d, "href").groupBy("item").agg(F.count("*").alias("cnt")).withColumn("digest", discover.digest("item"))
    return discover.noisy(counts, B_, 42, noise="discrete").filter(F.col("noisy") >= T_).select("item", "noisy")


_GRID = [(t, b) for b in (0.2, 0.5, 1.0, 2.0) for t in (3.0, 6.0, 12.0)]
_GRID_SQL = "(VALUES " + ", ".join(f"(CAST({t} AS DOUBLE), CAST({b} AS DOUBLE))" for t, b in _GRID) + ") AS g(threshold, scale)"


@query(f"SELECT threshold, scale, round(sum(CASE WHEN threshold > cnt THEN 0.5 * exp(-(threshold - cnt) / scale) ELSE 1 - 0.5 * exp((threshold - cnt) / scale) END), 4) AS expected FROM {counts_sql('word')}, {_GRID_SQL} GROUP BY 1, 2")
def discovery_tradeoff(s, d):
    grid = s.createDataFrame(_GRID, "threshold double, scale double")
    return discover.expected_yield(exact.frequencies(item_frame(s, d, "word")), grid).select("threshold", "scale", F.round("expected", 4).alias("expected"))


# --- accounting ---

_CAL = [(e, dl) for e in (0.5, 1.0, 2.0, 3.0, 5.0, 10.0) for dl in (1e-5, 1e-8)]
_CAL_SQL = "(VALUES " + ", ".join(f"(CAST({e} AS DOUBLE), CAST({dl} AS DOUBLE))" for e, dl in _CAL) + ") AS g(eps, delta)"


@query(f"SELECT eps, delta, {_r6('1 - ln(2 * delta) / eps')} AS threshold, {_r6('1 / eps')} AS scale, count(*) AS clients, count(*) FILTER (WHERE f >= 1 - ln(2 * delta) / eps) AS reached FROM {_CAL_SQL}, (SELECT client_id, count(*) AS f FROM {items_sql('event_type')} GROUP BY 1) GROUP BY 1, 2")
def discovery_calibration(s, d):
    """Threshold and noise of a release of the events' client ids, and how many ids have a count that reaches the threshold."""
    counts = item_frame(s, d, "event_type").groupBy("client_id").agg(F.count("*").alias("f"))
    settings = s.createDataFrame([(e, dl, *accounting.calibrate(e, dl)) for e, dl in _CAL], "eps double, delta double, threshold double, scale double")
    reached = F.sum((F.col("f") >= F.col("threshold")).cast("long")).alias("reached")
    got = counts.crossJoin(F.broadcast(settings)).groupBy("eps", "delta", "threshold", "scale").agg(F.count("*").alias("clients"), reached)
    return got.select("eps", "delta", R6(F.col("threshold")).alias("threshold"), R6(F.col("scale")).alias("scale"), "clients", "reached")


_AMP = [(e, dl) for e in (0.5, 1.0, 2.0, 4.0, 5.0) for dl in (1e-6, 1e-8)]
_AMP_SQL = "(VALUES " + ", ".join(f"(CAST({e} AS DOUBLE), CAST({dl} AS DOUBLE))" for e, dl in _AMP) + ") AS g(eps, delta)"


@query(f"SELECT epoch, eps, n, delta, {_r6('CASE WHEN n / (8 * ln(2 / delta)) - 1 <= 0 OR eps > ln(greatest(1e-300, n / (8 * ln(2 / delta)) - 1)) THEN eps ELSE least(eps, ln(1 + (exp(eps) - 1) * (4 * sqrt(2 * ln(4 / delta)) / sqrt((exp(eps) + 1) * n) + 4 / n))) END')} AS eps_central FROM {DAY_SQL}, {_AMP_SQL}")
def amplification(s, d):
    """Central epsilon of every day's reports after shuffling."""
    g = days(s, d).crossJoin(F.broadcast(s.createDataFrame(_AMP, "eps double, delta double")))
    return g.select("epoch", "eps", "n", "delta", R6(accounting.amplify_col(F.col("eps"), F.col("n"), F.col("delta"))).alias("eps_central"))


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, mechanism, {_r6('sum(eps) OVER w')} AS eps_total, round(sum(delta) OVER w, 12) AS delta_total FROM (SELECT epoch, 'sketch' AS mechanism, 0.5 AS eps, 0.0 AS delta FROM (SELECT DISTINCT CAST(ts AS DATE) AS epoch FROM events) UNION ALL SELECT epoch, 'discovery', 0.1, 1e-8 FROM (SELECT DISTINCT CAST(ts AS DATE) AS epoch FROM events)) WINDOW w AS (ORDER BY epoch, mechanism ROWS UNBOUNDED PRECEDING)")
def privacy_ledger(s, d):
    days = item_frame(s, d, "event_type").select("epoch").distinct()
    spends = days.select("epoch", F.lit("sketch").alias("mechanism"), F.lit(0.5).alias("eps"), F.lit(0.0).alias("delta")).unionByName(days.select("epoch", F.lit("discovery").alias("mechanism"), F.lit(0.1).alias("eps"), F.lit(1e-8).alias("delta")))
    return accounting.ledger(spends).select(F.col("epoch").cast("string"), "mechanism", R6(F.col("eps_total")).alias("eps_total"), F.round("delta_total", 12).alias("delta_total"))


# --- tuning ---

_TUNE = [(e, lam, k) for e in (1.0, 2.0, 3.75, 5.0) for lam in (0.5, 0.1, 0.02) for k in (1, 500)]
_TUNE_SQL = "(VALUES " + ", ".join(f"(CAST({e} AS DOUBLE), CAST({lam} AS DOUBLE), {k})" for e, lam, k in _TUNE) + ") AS g(eps, lam, k)"


def cost_sql(p="p", k="k") -> str:
    u = f"({p} / ({p} + (1 - {p}) * exp(eps)))"
    return f"((lam * {p} * (1 - {p} / {k}) + (1 - lam) * {u} * (1 - {u} / {k})) / (({p} - {u}) * ({p} - {u})))"


@query(f"SELECT eps, lam, k, {_r6('arg_min(p, cost)')} AS p, {_r6('min(cost)')} AS cost FROM (SELECT *, {cost_sql()} AS cost FROM {_TUNE_SQL}, (SELECT 0.5 + i * (0.5 / 500) AS p FROM range(500) t(i))) GROUP BY eps, lam, k")
def tune_grid(s, d):
    return tune.grid(s, _TUNE).select("eps", "lam", "k", R6(F.col("p")).alias("p"), R6(F.col("cost")).alias("cost"))


_INT = [(e, lam) for e in (1.0, 2.0, 3.75, 5.0) for lam in (0.5, 0.1, 0.02)]
_INT_SQL = "(VALUES " + ", ".join(f"(CAST({e} AS DOUBLE), CAST({lam} AS DOUBLE))" for e, lam in _INT) + ") AS g(eps, lam)"
_PS = "(s * exp(eps) / (100 - s + s * exp(eps)))"


@query(f"SELECT eps, lam, arg_min(s, c) AS s, {_r6('arg_min(p, c)')} AS p FROM (SELECT *, (lam * p * (1 - p) + (1 - lam) * s / 100.0 * (1 - s / 100.0)) / ((p - s / 100.0) * (p - s / 100.0)) AS c FROM (SELECT *, {_PS} AS p FROM {_INT_SQL}, (SELECT unnest(range(1, 51)) AS s)) WHERE p >= 0.5 AND p < 1) GROUP BY eps, lam")
def tune_integer(s, d):
    rows = [(e, lam, t.s, round(t.p, 6)) for e, lam in _INT for t in [tune.tune_integer(e, lam, 1, 100)]]
    return s.createDataFrame(rows, "eps double, lam double, s long, p double")


@query("SELECT * FROM (VALUES " + ", ".join(f"(CAST({lam} AS DOUBLE), CAST({round(t.p, 4)} AS DOUBLE), {t.s})" for lam, t in tune.regimes(3.75, 100, 100).items()) + ") AS g(lam, p, s)")
def tune_regimes(s, d):
    got = tune.grid(s, [(3.75, lam, 1) for lam in (0.5, 0.1, 0.02)], steps=50_000)
    size = F.ceil(F.lit(100.0) / (F.lit(1.0) + (F.lit(1.0) / F.col("p") - 1) * F.lit(math.exp(3.75))))
    exact_p = {lam: t.p for lam, t in tune.regimes(3.75, 100, 100).items()}
    best = F.create_map(*[x for lam, p in exact_p.items() for x in (F.lit(lam), F.lit(p))])[F.col("lam")]
    # the grid's minimum and the search agree to the grid's step
    return got.filter(F.abs(F.col("p") - best) <= 2e-5).select("lam", F.round(best, 4).alias("p"), size.cast("int").alias("s"))


_CAPG = f"(SELECT item, epoch, arg_min(p, cost) AS p FROM (SELECT item, epoch, p, {cost_sql(k='1')} AS cost FROM (SELECT item, epoch, CAST(f AS DOUBLE) / n AS lam, CAST(2.0 AS DOUBLE) AS eps FROM {DAYS_SQL}), (SELECT 0.5 + i * (0.5 / 500) AS p FROM range(500) t(i))) GROUP BY 1, 2)"


@query(f"SELECT item, epoch, arg_max(m, m) AS m, arg_max(100000 // m, m) AS k, arg_max(s, m) AS s, round(max(p), 4) AS p, arg_max(s * e, m) AS bits_used FROM (SELECT *, least(greatest(1, CAST(ceil(round(m / (1 + (1 / p - 1) * exp(2.0)), 9)) AS BIGINT)), m // 2) AS s FROM {_CAPG}, (SELECT i AS e, CAST(pow(2, i) AS BIGINT) AS m FROM range(3, 13) t(i))) WHERE s * e <= 128 GROUP BY 1, 2")
def capacity_plan(s, d):
    """Sketch sizes for the share of every day's count of an event type among all reports."""
    shares = day_counts(s, d).select("item", "epoch", (F.col("f") / F.col("n")).alias("lam"))
    return tune.plan_capacities(shares, 128, 100_000, 2.0).select("item", "epoch", *(F.col(c).cast("long") for c in ("m", "k", "s")), F.round("p", 4).alias("p"), F.col("bits_used").cast("long"))


_THIRDS = [(e, lam, k) for e in (1.0, 3.75, 5.0) for lam in (0.5, 0.1, 0.02) for k in (1, 50, 500)]


@query(f"SELECT eps, lam, k, round(arg_min(p, cost), 2) AS p FROM (SELECT *, {cost_sql()} AS cost FROM (VALUES " + ", ".join(f"(CAST({e} AS DOUBLE), CAST({lam} AS DOUBLE), CAST({k} AS BIGINT))" for e, lam, k in _THIRDS) + ") AS g(eps, lam, k), (SELECT 0.5 + i * 1e-5 AS p FROM range(49999) t(i))) GROUP BY eps, lam, k")
def tune_by_thirds(s, d):
    """The published objective's minimiser by the published search."""
    return s.createDataFrame([(e, lam, k, round(tune.best_p_by_thirds(e, lam, k), 2)) for e, lam, k in _THIRDS], "eps double, lam double, k long, p double")


_SHARE = f"(SELECT reports, count(*) AS clients, CAST(3.0 AS DOUBLE) / reports AS eps FROM (SELECT client_id, count(*) AS reports FROM {items_sql('event_type')} GROUP BY 1) GROUP BY 1)"
_LOGIT = "ln({p} * (1 - {q}) / ((1 - {p}) * {q}))"
_PSUE, _QSUE, _QOUE = "(exp(eps / 2) / (1 + exp(eps / 2)))", "(1 / (exp(eps - eps / 2) + 1))", "(1 / (exp(eps) + 1))"


@query(f"SELECT reports, clients, {_r6('eps')} AS eps, {_r6(_PSUE)} AS p_sue, {_r6(_QOUE)} AS q_oue, {_r6(_LOGIT.format(p='CAST(0.5 AS DOUBLE)', q=_QOUE))} AS eps_oue, {_r6(_LOGIT.format(p=_PSUE, q=_QSUE))} AS eps_sue FROM {_SHARE}")
def budget_split(s, d):
    """Unary reports of clients that split a budget of 3 evenly over their reports, one row a number of reports."""
    each = item_frame(s, d, "event_type").groupBy("client_id").agg(F.count("*").alias("reports"))
    g = each.groupBy("reports").agg(F.count("*").alias("clients")).withColumn("eps", F.lit(3.0) / F.col("reports"))
    eps = F.col("eps")
    (p1, q1), (p0, q0) = theory.split_budget(eps, eps / 2, F.exp), theory.split_budget(eps, F.lit(0.0), F.exp)
    return g.select("reports", "clients", *(R6(v).alias(c) for c, v in (("eps", eps), ("p_sue", p1), ("q_oue", q0), ("eps_oue", theory.unary_eps(p0, q0, F.log)), ("eps_sue", theory.unary_eps(p1, q1, F.log)))))


_PURE = "(VALUES " + ", ".join(f"(CAST({f} AS DOUBLE))" for f in (10, 1000, 50000)) + ") AS g(f)"


@query(f"SELECT f, {_r6('100000 * 0.1 * 0.9 / (0.4 * 0.4) + f * (1 - 0.5 - 0.1) / 0.4')} AS var FROM {_PURE}")
def pure_variance(s, d):
    return s.createDataFrame([(float(f), round(theory.pure_variance(f, 100000, 0.5, 0.1), 6)) for f in (10, 1000, 50000)], "f double, var double")


# --- joint use ---


@query(f"WITH names AS MATERIALIZED (SELECT item FROM {noisy_sql(counts_sql('host'), B_, 42)} WHERE noisy >= {T_!r}) SELECT item, support, {_r6('est')} AS est FROM {estimate_sql(SMOKE, items_sql('host'), 'names')}")
def joint_discover_estimate(s, d):
    return joint.discover_then_estimate(item_frame(s, d, "host"), SMOKE, T_, B_).select("item", "support", R6(F.col("est")).alias("est"))


@query()
def adaptive_round(s, d):
    rows = joint.adaptive_rounds(item_frame(s, d, "event_type"), "click", 2.0, 8, 64, 5, mode="replay")
    return s.createDataFrame([(r["ver"], str(r["epoch"]), r["lam"], r["p"], r["s"], r["eps"], r["n"], r["est"]) for r in rows], "ver int, epoch string, lam double, p double, s int, eps double, n long, est double")


_DAY_EST = f"(WITH mx AS MATERIALIZED {matrix_sql(SMOKE, items_sql('event_type'), 'epoch')} SELECT epoch, item, (support - n * {SMOKE.u!r}) / {SMOKE.p - SMOKE.u!r} AS est FROM (SELECT epoch, item, sum(coalesce(cnt, 0)) AS support FROM (SELECT epoch, item, j, {h(42, 'cell', 'j', 'item')} % 64 + 1 AS x FROM (SELECT DISTINCT epoch FROM mx), (SELECT DISTINCT item FROM {items_sql('event_type')}), (SELECT unnest(range(1, 9)) AS j)) LEFT JOIN mx USING (epoch, j, x) GROUP BY 1, 2) JOIN (SELECT epoch, sum(cnt) / 5 AS n FROM mx GROUP BY 1) USING (epoch))"


def daily_estimates(s, d):
    items = item_frame(s, d, "event_type")
    mx = sketch.build(randomize.subset_reports(items, SMOKE, keep=["epoch"]), ["epoch"])
    names = items.select("item").distinct()
    probes = names.withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(8)))).withColumn("x", randomize.cell(SMOKE, F.col("j"), F.col("item")))
    n = mx.groupBy("epoch").agg((F.sum("cnt") / 5).alias("n"))
    each = n.crossJoin(F.broadcast(probes)).join(mx, ["epoch", "j", "x"], "left")
    return each.groupBy("epoch", "item").agg(((F.sum(F.coalesce("cnt", F.lit(0))) - F.first("n") * SMOKE.u) / (SMOKE.p - SMOKE.u)).alias("est"))


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, item, {_r6('est')} AS est, rank FROM (SELECT *, row_number() OVER (PARTITION BY epoch ORDER BY est DESC, item) AS rank FROM {_DAY_EST}) WHERE rank <= 2")
def topk_tracker(s, d):
    return joint.topk_tracker(daily_estimates(s, d), 2).select(F.col("epoch").cast("string"), "item", R6(F.col("est")).alias("est"), F.col("rank").cast("long"))


# --- attacks ---


@query(f"SELECT item, cnt FROM {counts_sql('word')} WHERE item IN (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) FROM benchmark)")
def attack_dictionary_probe(s, d):
    from ..sources.items import words
    from ..sources.tables import load

    counts = item_frame(s, d, "word").groupBy(discover.digest("item").alias("digest")).agg(F.count("*").alias("cnt"))
    known = load(s, d, "benchmark", ["text"])
    return attacks.dictionary_probe(counts, known.select(F.explode(words(known)).alias("item")).distinct())


@query(f"WITH mx AS MATERIALIZED (SELECT j, x, CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT * FROM {matrix_sql(SMOKE, items_sql('lang'))} UNION ALL SELECT j, (r - 1 + i) % 64 + 1, count(*) FROM (SELECT j, {h(42, 'cell', 'j', repr('es'))} % 64 + 1 AS r FROM (SELECT i % 8 + 1 AS j FROM range(100) t(i))), (SELECT unnest(range(0, 5)) AS i) GROUP BY 1, 2) GROUP BY 1, 2) SELECT item, support, {_r6(f'(support - n * {SMOKE.u!r}) / {SMOKE.p - SMOKE.u!r}')} AS est FROM {support_sql(SMOKE, items_sql('lang'), 'mx')}, (SELECT CAST(sum(cnt) / 5 AS BIGINT) AS n FROM mx)")
def attack_poison(s, d):
    items = item_frame(s, d, "lang")
    reports = attacks.inject_reports(randomize.subset_reports(items, SMOKE), "es", 100, SMOKE)
    return estimate.frequencies(items, sketch.build(reports), SMOKE).select("item", "support", R6(F.col("est")).alias("est"))


_SYBILS = f"(SELECT report_id, client_id, item, epoch FROM {items_sql('lang')} UNION ALL SELECT -1 - i, -1 - i, 'es', DATE '2024-01-01' FROM range(50) t(i))"


@query(f"SELECT item, support, CAST(n AS BIGINT) AS n, {_r6('est')} AS est FROM {estimate_sql(SMOKE, _SYBILS)}")
def attack_sybil(s, d):
    """What the server estimates when invented clients report."""
    items = attacks.sybil(item_frame(s, d, "lang"), "es", 50)
    return estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE).select("item", "support", "n", R6(F.col("est")).alias("est"))


@query(f"SELECT count(*) AS reports, {_r6('avg(CASE WHEN list_contains(x, r) THEN 1.0 ELSE 0.0 END)')} AS own_cell_seen, {_r6(repr(SMOKE.p))} AS promised, {_r6(repr(SMOKE.u))} AS by_chance, {_r6(repr(SMOKE.eps))} AS eps_linked FROM {reports_sql(SMOKE, items_sql('lang'))}")
def attack_unshuffled(s, d):
    """A relay that leaves reports linked to their clients: amplification is gone, and what the server sees of a client's own cell is still
    no more than the local guarantee gives."""
    sent = randomize.extend(randomize.include(randomize.encode(item_frame(s, d, "lang"), SMOKE), SMOKE), SMOKE)
    seen = F.avg(F.when(F.array_contains("x", F.col("r")), 1.0).otherwise(0.0))
    return sent.agg(F.count("*").alias("reports"), R6(seen).alias("own_cell_seen")).select("*", *(R6(F.lit(v)).alias(n) for n, v in (("promised", SMOKE.p), ("by_chance", SMOKE.u), ("eps_linked", SMOKE.eps))))


@query(f"SELECT lower(sha256(item)) AS digest, cnt FROM {counts_sql('lang')} WHERE item <> 'en'")
def attack_drop_digest(s, d):
    counts = item_frame(s, d, "lang").groupBy(discover.digest("item").alias("digest")).agg(F.count("*").alias("cnt"))
    victim = s.createDataFrame([("en",)], "item string").select(discover.digest("item").alias("digest"))
    return attacks.drop_digest(counts, victim).select(F.lower(F.hex("digest")).alias("digest"), "cnt")


_LOST = f"(SELECT * FROM {items_sql('priority')} WHERE NOT {lt(42, 'lost', 0.2, 'report_id')})"


@query(f"SELECT item, support, CAST(n AS BIGINT) AS n, {_r6('est')} AS est FROM {estimate_sql(SMOKE, _LOST)}")
def attack_lossy_relay(s, d):
    """What the server estimates when the relay loses a fifth of the reports."""
    items = item_frame(s, d, "priority")
    reports = attacks.drop_reports(randomize.subset_reports(items, SMOKE, keep=["report_id"]), 0.2)
    return estimate.frequencies(items, sketch.build(reports), SMOKE).select("item", "support", "n", R6(F.col("est")).alias("est"))


# --- yardsticks ---


@query(f"SELECT item, count(*) AS f FROM {items_sql('band16')} GROUP BY item")
def exact_freq(s, d):
    return exact.frequencies(item_frame(s, d, "band16"))


@query(f"SELECT item, {_r6('count(*) / 0.1')} AS est FROM {items_sql('event_type')} WHERE {lt(42, 'sample', 0.1, 'report_id')} GROUP BY item")
def exact_sampled(s, d):
    return exact.sampled(item_frame(s, d, "event_type"), 0.1).select("item", R6(F.col("est")).alias("est"))


# --- baselines ---


def unary_sql(key: str, p: float, q: float, tag: str) -> str:
    src = items_sql(key)
    hit = f"CASE WHEN i = code THEN {lt(42, tag, p, 'report_id', 'i')} ELSE {lt(42, tag, q, 'report_id', 'i')} END"
    return f"WITH dom AS MATERIALIZED (SELECT item, row_number() OVER (ORDER BY item) AS code FROM (SELECT DISTINCT item FROM {src})), r AS MATERIALIZED (SELECT report_id, code FROM {src} JOIN dom USING (item)), c AS (SELECT i, count(*) AS support FROM r, (SELECT code AS i FROM dom) WHERE {hit} GROUP BY i) SELECT item, CAST(coalesce(support, 0) AS BIGINT) AS support, {_r6(f'(coalesce(support, 0) - n * {q!r}) / {p - q!r}')} AS est FROM dom LEFT JOIN c ON i = code, (SELECT count(*) AS n FROM r)"


def _est(df):
    return df.select("item", F.col("support").cast("long"), R6(F.col("est")).alias("est"))


@query(unary_sql("event_type", *oracles.sue_pq(EPS), "sue"))
def unary_sue(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.sue(i, i, EPS))


@query(unary_sql("event_type", *oracles.oue_pq(EPS), "oue"))
def unary_oue(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.oue(i, i, EPS))


@query(unary_sql("event_type", *oracles.tuned_unary_pq(EPS, 0.1), "tun"))
def unary_tuned(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.tuned_unary(i, i, EPS, 0.1))


@query(unary_sql("role", *oracles.threshold_pq(EPS, oracles.best_theta(EPS)), "the"))
def threshold_histogram(s, d):
    i = item_frame(s, d, "role")
    return _est(oracles.threshold_hist(i, i, EPS))


def direct_sql(key: str, eps: float, width: int) -> str:
    p, q = oracles.direct_pq(eps, width)
    src = items_sql(key)
    other = f"({h(42, 'oth', 'report_id')} % {width - 1} + 1)"
    said = f"CASE WHEN {lt(42, 'dir', p, 'report_id')} THEN code ELSE CASE WHEN {other} >= code THEN {other} + 1 ELSE {other} END END"
    return f"WITH dom AS MATERIALIZED (SELECT item, row_number() OVER (ORDER BY item) AS code FROM (SELECT DISTINCT item FROM {src})), r AS MATERIALIZED (SELECT {said} AS said FROM {src} JOIN dom USING (item)), c AS (SELECT said, count(*) AS support FROM r GROUP BY said) SELECT item, CAST(coalesce(support, 0) AS BIGINT) AS support, {_r6(f'(coalesce(support, 0) - n * {q!r}) / {p - q!r}')} AS est FROM dom LEFT JOIN c ON said = code, (SELECT count(*) AS n FROM r)"


@query(direct_sql("event_type", EPS, 5))
def direct_encoding(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.direct(i, i, EPS))


@query(direct_sql("toxic", EPS, 2))
def binary_response(s, d):
    i = item_frame(s, d, "toxic")
    return _est(oracles.direct(i, i, EPS))


def local_sql(key: str, eps: float, g: int) -> str:
    p, q = oracles.local_hash_pq(eps, g)
    src = items_sql(key)
    other = f"({h(42, 'lho', 'report_id')} % {g - 1})" if g > 2 else f"({h(42, 'lho', 'report_id')} % 1)"
    said = f"CASE WHEN {lt(42, 'lhp', p, 'report_id')} THEN own ELSE CASE WHEN {other} >= own THEN {other} + 1 ELSE {other} END END"
    return f"WITH r AS MATERIALIZED (SELECT report_id, {said} AS said FROM (SELECT *, {h(42, 'lh', 'report_id', 'item')} % {g} AS own FROM {src})), dom AS (SELECT DISTINCT item FROM {src}), c AS (SELECT item, count(*) AS support FROM r, dom WHERE said = {h(42, 'lh', 'report_id', 'item')} % {g} GROUP BY item) SELECT item, CAST(coalesce(support, 0) AS BIGINT) AS support, {_r6(f'(coalesce(support, 0) - n * {q!r}) / {p - q!r}')} AS est FROM dom LEFT JOIN c USING (item), (SELECT count(*) AS n FROM r)"


@query(local_sql("event_type", EPS, math.ceil(math.exp(EPS)) + 1))
def local_hashing(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.local_hash(i, i, EPS))


@query(local_sql("event_type", EPS, 2))
def local_hashing_binary(s, d):
    i = item_frame(s, d, "event_type")
    return _est(oracles.local_hash(i, i, EPS, 2))


def classical_sql(key: str, k: int, m: int, eps: float) -> str:
    p = 1 / (1 + math.exp(-eps / 2))
    sp = replayed(k, m, 1, 0.5, 42)
    hit = f"(({lt(42, 'bit', p, 'report_id', 'i')}) = (i = r))"
    return f"(SELECT j, i AS x, count(*) AS cnt FROM {encode_sql(sp, items_sql(key))}, (SELECT unnest(range(1, {m + 1})) AS i) WHERE {hit} GROUP BY 1, 2)"


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {classical_sql('lang', 4, 16, EPS)}")
def classical_sketch(s, d):
    return sketch.build(oracles.classical_reports(item_frame(s, d, "lang"), 4, 16, EPS)).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


_P1 = 1 / (1 + math.exp(-EPS / 2))
_UC = _P1 / 16 + (1 - _P1) * (1 - 1 / 16)


@query(f"WITH mx AS MATERIALIZED {classical_sql('lang', 4, 16, EPS)} SELECT item, support, {_r6(f'(support - n * {_UC!r}) / {_P1 - _UC!r}')} AS est FROM {support_sql(replayed(4, 16, 1, 0.5, 42), items_sql('lang'), 'mx')}, (SELECT count(*) AS n FROM {items_sql('lang')})")
def classical_estimate(s, d):
    i = item_frame(s, d, "lang")
    n = i.count()
    return _est(oracles.classical_estimate(i, sketch.build(oracles.classical_reports(i, 4, 16, EPS)), 4, 16, EPS, n))


def _cohort_sql(key: str, cohorts: int, bits: int, hashes: int, flip=0.25, p1=0.35, q1=0.65) -> str:
    half = int(flip / 2 * (1 << 52))
    own = " OR ".join(f"{h(42, f'bl{x}', 'cohort', 'item')} % {bits} = i" for x in range(hashes))
    u = h(42, "perm", "client_id", "item", "i")
    held = f"CASE WHEN {u} < {half} THEN true WHEN {u} < {2 * half} THEN false ELSE ({own}) END"
    said = f"CASE WHEN {held} THEN {lt(42, 'inst', q1, 'report_id', 'i')} ELSE {lt(42, 'inst', p1, 'report_id', 'i')} END"
    return f"WITH r AS MATERIALIZED (SELECT *, {h(42, 'coh', 'client_id')} % {cohorts} AS cohort FROM {items_sql(key)}), c AS (SELECT cohort, i AS bit, count(*) AS cnt FROM r, (SELECT unnest(range(0, {bits})) AS i) WHERE {said} GROUP BY 1, 2) SELECT CAST(cohort AS BIGINT) AS cohort, CAST(bit AS BIGINT) AS bit, cnt, n FROM c JOIN (SELECT cohort, count(*) AS n FROM r GROUP BY 1) USING (cohort)"


@query(_cohort_sql("lang", 4, 16, 2))
def cohort_bloom_counts(s, d):
    return oracles.cohort_bits(item_frame(s, d, "lang"), 4, 16, 2).select(F.col("cohort").cast("long"), F.col("bit").cast("long"), "cnt", "n")


@query()
def cohort_bloom_decode(s, d):
    i = item_frame(s, d, "priority")
    names = [r[0] for r in oracles.codes_of(i, 1000).orderBy("item").collect()]  # a larger domain is refused
    return oracles.cohort_decode(oracles.cohort_bits(i, 4, 32, 2), names, 4, 32, 2)
