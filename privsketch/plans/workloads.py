"""Queries of the measures and of the experiment workloads, re-expressed on the given tables."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import accounting, theory, tune
from ..functions.theory import SketchParams, replayed
from ..operators import discover, discover_baselines, estimate, exact, measure, oracles, randomize, relay, simulate, sketch
from ..sources.items import item_frame
from ..sources.tables import scratch
from ..sources.workers import ship
from .core import B_, DAY_SQL, DAYS_SQL, EPS, R6, SMOKE, T_, _r6, cost_sql, day_counts, days
from .registry import counts_sql, estimate_sql, items_sql, noisy_sql, query, reports_sql

SEEDS = (1, 2, 3, 4)
RUN = [replayed(8, 64, 5, 0.6, x) for x in SEEDS]


def _runs(s, d, key):
    items = item_frame(s, d, key)
    exact_f = exact.frequencies(items)
    out = None
    for sp in RUN:
        e = measure.errors(estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp)), sp), exact_f).withColumn("run", F.lit(sp.seed))
        out = e if out is None else out.unionByName(e)
    return out


def _runs_sql(key):
    return "(" + " UNION ALL ".join(f"SELECT {sp.seed} AS run, item, f, est, est - f AS err FROM {estimate_sql(sp, items_sql(key))} JOIN (SELECT item, count(*) AS f FROM {items_sql(key)} GROUP BY item) USING (item)" for sp in RUN) + ")"


@query(f"SELECT item, any_value(f) AS f, {_r6('avg(err * err)')} AS mse FROM {_runs_sql('lang')} GROUP BY item")
def mse_by_item(s, d):
    return measure.mse(_runs(s, d, "lang")).select("item", "f", R6(F.col("mse")).alias("mse"))


@query(f"SELECT item, {_r6('avg(err)')} AS bias FROM {_runs_sql('lang')} GROUP BY item")
def bias_by_item(s, d):
    return measure.mse(_runs(s, d, "lang")).select("item", R6(F.col("bias")).alias("bias"))


@query(f"SELECT item, {_r6('sqrt(avg(err * err)) / any_value(f)')} AS rel FROM {_runs_sql('lang')} GROUP BY item")
def rel_root_variance(s, d):
    return measure.mse(_runs(s, d, "lang")).select("item", R6(F.col("rel_rmse")).alias("rel"))


@query(f"SELECT {_r6('max(abs(err))')} AS max_err, {_r6('sum(abs(err))')} AS l1, {_r6('sqrt(sum(err * err))')} AS l2 FROM {_runs_sql('lang')} WHERE run = 1")
def error_summary(s, d):
    return measure.distance(_runs(s, d, "lang").filter("run = 1")).select(*(R6(F.col(c)).alias(c) for c in ("max_err", "l1", "l2")))


@query(f"SELECT {_r6('sum(f / n * ln((f / n) / (greatest(est, 1e-9) / m)))')} AS kl FROM (SELECT *, sum(f) OVER () AS n, sum(greatest(est, 1e-9)) OVER () AS m FROM {_runs_sql('lang')} WHERE run = 1) WHERE f > 0")
def error_divergence(s, d):
    return measure.distance(_runs(s, d, "lang").filter("run = 1")).select(R6(F.col("kl")).alias("kl"))


@query(f"SELECT count(*) AS reports, CAST(sum(len(x)) AS BIGINT) AS updates FROM {reports_sql(SMOKE, items_sql('nation'))}")
def server_ops(s, d):
    return measure.server_ops(randomize.subset_reports(item_frame(s, d, "nation"), SMOKE))


_SETS = [(8, 64, 5), (100, 100, 7), (100, 100, 3), (500, 1000, 7), (65536, 1024, 10)]


@query("SELECT *, CAST(s * ceil(log2(m)) AS BIGINT) AS bits_cells, CAST(s * ceil(log2(m)) + ceil(log2(k)) AS BIGINT) AS bits_total, m AS bits_classical, k * m AS cells, CAST(reports * (s * ceil(log2(m)) + ceil(log2(k))) AS BIGINT) AS sent FROM (VALUES " + ", ".join(f"(CAST({k} AS BIGINT), CAST({m} AS BIGINT), CAST({z} AS BIGINT))" for k, m, z in _SETS) + f") AS g(k, m, s), (SELECT epoch, n AS reports FROM {DAY_SQL})")
def comm_bits(s, d):
    """Report sizes, and the bits that every day's reports send."""
    rows = [(k, m, z, int(b["bits_cells"]), int(b["bits_total"]), m, k * m) for k, m, z in _SETS for b in [theory.report_bits(k, m, z)]]
    sets = s.createDataFrame(rows, "k long, m long, s long, bits_cells long, bits_total long, bits_classical long, cells long")
    return days(s, d).withColumnRenamed("n", "reports").crossJoin(F.broadcast(sets)).withColumn("sent", F.col("reports") * F.col("bits_total"))


_DAYP = f"(SELECT epoch, count(*) AS m, CAST(greatest(1, count(*) // 2) AS BIGINT) AS s, CAST(0.5 AS DOUBLE) + CAST(0.4 AS DOUBLE) * max(f) / max(day_n) AS p FROM {DAYS_SQL} GROUP BY 1 HAVING count(*) BETWEEN 2 AND 6)"


@query(f"SELECT epoch, m, s, {_r6('p')} AS p, {_r6('abs(ln(p * (m - s) / ((1 - p) * s)))')} AS eps_closed, {_r6('abs(ln(p * (m - s) / ((1 - p) * s)))')} AS eps_enumerated FROM {_DAYP}")
def eps_enumeration(s, d):
    """Epsilon of every day's parameters by the closed form and by enumeration of all reports: a cell for each event type of the day (days
    of 2 to 6 types), p from half on by the share of the day's commonest."""
    ship(s)
    g = day_counts(s, d).groupBy("epoch").agg(F.count("*").alias("m"), (F.lit(0.5) + F.lit(0.4) * F.max("f") / F.max("day_n")).alias("p")).filter("m between 2 and 6")
    g = g.withColumn("s", F.greatest(F.lit(1), F.floor(F.col("m") / 2)).cast("long"))
    counted = F.udf(lambda m, z, p: measure.empirical_eps(SketchParams(1, m, z, p)), "double")
    closed = theory.eps_col(F.col("p"), F.col("s"), F.col("m"))
    return g.select("epoch", "m", "s", R6(F.col("p")).alias("p"), R6(closed).alias("eps_closed"), R6(counted("m", "s", "p")).alias("eps_enumerated"))


_E = (0.5, 1.0, 2.0, 3.0, 5.0, 10.0)


def _found_sql(key, eps, seed):
    t, b = accounting.calibrate(eps, 1e-5)
    return f"SELECT CAST({eps} AS DOUBLE) AS eps, {seed} AS run, count(*) FILTER (WHERE noisy >= {t!r}) AS found, count(*) AS of_distinct FROM {noisy_sql(counts_sql(key), b, seed)}"


def _found(counts, seeds):
    """Released items of every setting and run in one aggregate: a grid of settings is broadcast to the counts."""
    grid = counts.sparkSession.createDataFrame([(e, *accounting.calibrate(e, 1e-5), x) for e in _E for x in seeds], "eps double, t double, b double, run int")
    drawn = discover.noisy(counts.crossJoin(F.broadcast(grid)), F.col("b"), F.col("run"))
    return drawn.groupBy("eps", "run").agg(F.count(F.when(F.col("noisy") >= F.col("t"), 1)).alias("found"), F.count("*").alias("of_distinct"))


def _counts(s, d, key):
    return item_frame(s, d, key).groupBy("item").agg(F.count("*").alias("cnt")).withColumn("digest", discover.digest("item"))


def _sealed_counts(s, d, key):
    """Counts as the helper has them: by digest, from sealed messages."""
    opened = discover.open_outer(discover.client(item_frame(s, d, key), "server", "helper"), "helper")
    return opened.groupBy("digest").agg(F.count("*").alias("cnt"))


_GRID30 = "(VALUES " + ", ".join("(CAST({} AS DOUBLE), CAST({!r} AS DOUBLE), CAST({!r} AS DOUBLE))".format(e, *accounting.calibrate(e, 1e-5)) for e in _E) + ") AS g(eps, t, b)"
_U30 = "(((('0x' || substr(md5(concat_ws('|', CAST(run AS VARCHAR), 'lap', '0', sha256(item))), 1, 13))::BIGINT)::DOUBLE + 0.5) / 4503599627370496.0)"


@query(f"SELECT eps, {_r6('avg(found)')} AS found, any_value(of_distinct) AS of_distinct FROM (SELECT eps, run, count(*) FILTER (WHERE cnt - b * sign(u - 0.5) * ln(greatest(1e-15, 1.0 - 2.0 * abs(u - 0.5))) >= t) AS found, count(*) AS of_distinct FROM (SELECT eps, t, b, run, cnt, {_U30} AS u FROM {counts_sql('href')}, {_GRID30}, (SELECT i AS run FROM range(1, 31) r(i))) GROUP BY eps, run) GROUP BY eps")
def discovery_count(s, d):
    """Thirty releases of one sealed collection at every budget, and their mean."""
    return _found(_sealed_counts(s, d, "href"), range(1, 31)).groupBy("eps").agg(R6(F.avg("found")).alias("found"), F.first("of_distinct").alias("of_distinct"))


@query(" UNION ALL ".join(_found_sql("url20", e, 42) for e in _E))
def url_discovery(s, d):
    return _found(_counts(s, d, "url20"), (42,))


@query(" UNION ALL ".join(_found_sql("word", e, 42) for e in _E))
def word_discovery(s, d):
    return _found(_counts(s, d, "word"), (42,))


_TRUTH = f"(SELECT item FROM {counts_sql('chat_words')} WHERE cnt >= 12)"
_FOUND = f"(SELECT item FROM {noisy_sql(counts_sql('chat_words'), B_, 42)} WHERE noisy >= {T_!r})"


@query(f"SELECT hits, found, truth, {_r6('hits * 1.0 / found')} AS precision, {_r6('hits * 1.0 / truth')} AS recall, {_r6('2.0 * hits / (found + truth)')} AS f_score FROM (SELECT (SELECT count(*) FROM {_FOUND} JOIN {_TRUTH} USING (item)) AS hits, (SELECT count(*) FROM {_FOUND}) AS found, (SELECT count(*) FROM {_TRUTH}) AS truth)")
def discovery_fscore(s, d):
    items = item_frame(s, d, "chat_words")
    truth = exact.frequencies(items).filter("f >= 12")
    got = measure.f_score(discover.blind_histogram(items, T_, B_, 42), truth)
    return got.select("hits", "found", "truth", *(R6(F.col(c)).alias(c) for c in ("precision", "recall", "f_score")))


@query(f"SELECT {_r6('count(h.item) / 5.0')} AS precision, {_r6('coalesce(sum(w) FILTER (WHERE h.item IS NOT NULL), 0) / sum(w)')} AS ncr FROM (SELECT item, 6 - row_number() OVER (ORDER BY f DESC, item) AS w FROM (SELECT item, count(*) AS f FROM {items_sql('source')} GROUP BY item) ORDER BY f DESC, item LIMIT 5) t LEFT JOIN (SELECT item FROM {estimate_sql(SMOKE, items_sql('source'))} ORDER BY est DESC, item LIMIT 5) h USING (item)")
def topk_precision(s, d):
    items = item_frame(s, d, "source")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return measure.topk_quality(est, exact.frequencies(items), 5).select(R6(F.col("precision")).alias("precision"), R6(F.col("ncr").cast("double")).alias("ncr"))


@query()
def marginal_simulation(s, d):
    return simulate.marginal_support(exact.frequencies(item_frame(s, d, "lang")), SketchParams(100, 100, 7, 0.74), 200)


# --- figures ---

_W1 = [(5.0, lam, k) for lam in (0.5, 0.1, 0.02) for k in (1, 50, 500)]


def _values(rows, names):
    return "(VALUES " + ", ".join("(" + ", ".join(f"CAST({v!r} AS {'DOUBLE' if isinstance(v, float) else 'BIGINT'})" for v in r) + ")" for r in rows) + f") AS g({names})"


@query(f"SELECT eps, lam, k, {_r6('p')} AS p, {_r6(cost_sql())} AS cost FROM {_values(_W1, 'eps, lam, k')}, (SELECT 0.5 + i * 0.0098 AS p FROM range(51) t(i))")
def sweep_p(s, d):
    grid = s.createDataFrame(_W1, "eps double, lam double, k long")
    points = s.range(51).select((F.lit(0.5) + F.col("id") * F.lit(0.0098)).alias("p"))
    return grid.crossJoin(F.broadcast(points)).select("eps", "lam", "k", R6(F.col("p")).alias("p"), R6(theory.objective(F.col("p"), F.col("lam"), F.col("eps"), F.col("k"), exp=F.exp)).alias("cost"))


_FIG2 = [(1000, 500), (1500, 50)]
_MARKS = [(m, k, lam, name, p) for m, k in _FIG2 for lam in (0.5, 0.1, 0.02) for name, p in (("unary", 0.5), ("classical", math.exp(2.5) / (1 + math.exp(2.5))), ("tuned", tune.best_p(5.0, lam, k)), ("tuned_published", tune.best_p(5.0, lam, k, "published")))]


def _curve_sql(p: str, c: str) -> str:
    u = f"({p} / ({p} + (1 - {p}) * exp(5.0)))"
    return f"sqrt(1e5 * (lam * ({p} - {c} * {p} * {p}) + (1 - lam) * ({u} - {c} * {u} * {u})) / (({p} - {u}) * ({p} - {u}))) / (lam * 1e5)"


def _curve(p, lam, c):
    u = p / (p + (1 - p) * F.lit(math.exp(5.0)))
    return R6(F.sqrt(F.lit(1e5) * (lam * (p - c * p * p) + (1 - lam) * (u - c * u * u)) / ((p - u) * (p - u))) / (lam * 1e5))


@query(f"SELECT m, k, lam, {_r6('p')} AS p, {_r6(_curve_sql('p', '1.0'))} AS exact, {_r6(_curve_sql('p', '(1.0 / k)'))} AS published FROM (VALUES " + ", ".join(f"(CAST({m} AS BIGINT), CAST({k} AS BIGINT))" for m, k in _FIG2) + ") AS g(m, k), (VALUES (0.5::DOUBLE), (0.1::DOUBLE), (0.02::DOUBLE)) AS h(lam), (SELECT 0.5 + i * 0.0098 AS p FROM range(51) t(i))")
def variance_curves(s, d):
    """Relative root variance of a target share over p, for a hundred thousand reports and epsilon 5, in both forms."""
    g = s.createDataFrame([(m, k, lam) for m, k in _FIG2 for lam in (0.5, 0.1, 0.02)], "m long, k long, lam double")
    points = s.range(51).select((F.lit(0.5) + F.col("id") * F.lit(0.0098)).alias("p"))
    p, lam = F.col("p"), F.col("lam")
    return g.crossJoin(F.broadcast(points)).select("m", "k", "lam", R6(p).alias("p"), _curve(p, lam, F.lit(1.0)).alias("exact"), _curve(p, lam, 1.0 / F.col("k")).alias("published"))


@query("SELECT m, k, lam, choice, " + f"{_r6('p')} AS p, {_r6(_curve_sql('p', '1.0'))} AS exact, {_r6(_curve_sql('p', '(1.0 / k)'))} AS published FROM (VALUES " + ", ".join(f"(CAST({m} AS BIGINT), CAST({k} AS BIGINT), CAST({lam!r} AS DOUBLE), '{name}', CAST({p!r} AS DOUBLE))" for m, k, lam, name, p in _MARKS) + ") AS g(m, k, lam, choice, p)")
def variance_marks(s, d):
    """Where the unary, the classical and the tuned choice stand on those curves."""
    p, lam = F.col("p"), F.col("lam")
    g = s.createDataFrame(_MARKS, "m long, k long, lam double, choice string, p double")
    return g.select("m", "k", "lam", "choice", R6(p).alias("p"), _curve(p, lam, F.lit(1.0)).alias("exact"), _curve(p, lam, 1.0 / F.col("k")).alias("published"))


_PTS = [(k, m, z, p, 1 + i) for i, (k, m, z, p) in enumerate([(8, 64, 5, 0.5), (8, 64, 5, 0.7), (8, 64, 5, 0.9), (32, 64, 5, 0.7)])]
_PTS_SQL = " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS k, CAST({p} AS DOUBLE) AS p, count(*) AS items, {_r6('sqrt(avg((est - f) * (est - f)))')} AS rmse FROM {estimate_sql(replayed(k, m, z, p, x), items_sql('priority'))} JOIN (SELECT item, count(*) AS f FROM {items_sql('priority')} GROUP BY item) USING (item)" for k, m, z, p, x in _PTS)


@query(_PTS_SQL)
def variance_points(s, d):
    """Measured root error of collections on such curves."""
    items = item_frame(s, d, "priority")
    truth, out = exact.frequencies(items), None
    for k, m, z, p, x in _PTS:
        sp = replayed(k, m, z, p, x)
        e = measure.errors(estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp)), sp), truth)
        r = e.agg(F.count("*").alias("items"), R6(F.sqrt(F.avg(F.pow("err", 2)))).alias("rmse")).select(F.lit(k).cast("long").alias("k"), F.lit(p).alias("p"), "items", "rmse")
        out = r if out is None else out.unionByName(r)
    return out


_W2 = [(e, f, b, k) for e in (1.0, 2.0, 3.0, 4.0, 5.0, 6.0, 8.0) for f in (1000.0, 10000.0) for b in (64, 128, 256) for k in (10, 100, 1000)]


def _largest_m(eps: float, bits: int) -> tuple[int, int]:
    """Largest hash range (up to 2^14) whose subset report at p = 1/2 fits the bits, with its subset size."""
    best = (2, 1)
    for m in range(4, (1 << 14) + 1):
        z = max(1, min(m // 2, theory.s_of(0.5, eps, m)))
        if z * math.ceil(math.log2(m)) <= bits:
            best = (m, z)
    return best


_FIT = {(e, b): _largest_m(e, b) for e, _, b, _ in _W2}
_W2X = [(e, f, b, k, *_FIT[e, b]) for e, f, b, k in _W2]
_PC = "(1 / (1 + exp(-eps / 2)))"


def _rv(p, u, m):
    return f"(f * {p} * (1 - {p}) + (100000 - f) * {u} * (1 - {u})) / (({p} - {u}) * ({p} - {u})) + (1e8 - (100000 - f)) / (k * 1.0 * ({m} - 1))"


@query(f"SELECT eps, f, bits, k, m, s, {_r6('sqrt(' + _rv('0.5', '(s * 1.0 / m)', 'm') + ') / f')} AS ours, {_r6('sqrt(' + _rv('pc', '(pc / bits + (1 - pc) * (1 - 1.0 / bits))', 'bits') + ') / f')} AS classical FROM (SELECT *, {_PC} AS pc FROM {_values(_W2X, 'eps, f, bits, k, m, s')})")
def sweep_eps_equal_bits(s, d):
    g = s.createDataFrame(_W2X, "eps double, f double, bits long, k long, m long, s long").withColumn("pc", 1 / (1 + F.exp(-F.col("eps") / 2)))

    def root(p, u, m):
        f = F.col("f")
        return R6(F.sqrt((f * p * (1 - p) + (100000 - f) * u * (1 - u)) / ((p - u) * (p - u)) + (F.lit(1e8) - (100000 - f)) / (F.col("k") * F.lit(1.0) * (m - 1))) / f)

    pc, bits = F.col("pc"), F.col("bits")
    return g.select("eps", "f", "bits", "k", "m", "s", root(F.lit(0.5), F.col("s") / F.col("m"), F.col("m")).alias("ours"), root(pc, pc / bits + (1 - pc) * (1 - 1 / bits), bits).alias("classical"))


_W3 = (0.5, 1.0, 2.0, 3.0, 4.0, 5.0)
_GRID = f"SELECT eps, lam, k, {_r6('arg_min(p, cost)')} AS p FROM (SELECT *, {{cost}} AS cost FROM {{g}}, (SELECT 0.5 + i * (0.5 / 500) AS p FROM range(500) t(i))) GROUP BY eps, lam, k"


@query(f"SELECT item, epoch, f, eps, k, {_r6('arg_min(p, cost)')} AS p FROM (SELECT *, {cost_sql(k='1')} AS cost FROM (SELECT item, epoch, f, CAST(f AS DOUBLE) / n AS lam FROM {DAYS_SQL}), {_values([(e, 200) for e in _W3], 'eps, k')}, (SELECT 0.5 + i * (0.5 / 500) AS p FROM range(500) t(i))) GROUP BY item, epoch, f, eps, k")
def opt_p_by_eps(s, d):
    """Best p of every epsilon for the share of every day's count of an event type."""
    spends = s.createDataFrame([(e, 1) for e in _W3], "eps double, k int")
    g = day_counts(s, d).select("item", "epoch", "f", (F.col("f") / F.col("n")).alias("lam")).crossJoin(F.broadcast(spends))
    return tune.grid_of(g).select("item", "epoch", "f", "eps", F.lit(200).cast("long").alias("k"), R6(F.col("p")).alias("p"))


_W4 = [(4.0, lam, k) for lam in (0.1, 0.5) for k in (1, 2, 5, 10, 100, 1000)]


@query(_GRID.format(cost=cost_sql(), g=_values(_W4, "eps, lam, k")))
def opt_p_by_k(s, d):
    return tune.grid(s, _W4).select("eps", "lam", F.col("k").cast("long"), R6(F.col("p")).alias("p"))


_FORMS5 = [("exact", 1), ("published", 65536)]
_PC5 = 1 / (1 + math.exp(-2.0))
_GRID5 = "(SELECT 0.5 + i * (0.5 / 500) AS p FROM range(500) t(i))"


def _w5cost(p):
    u = f"({p} / ({p} + (1 - {p}) * exp(4.0)))"
    c = "(1.0 / k)"
    return f"sqrt((f * ({p} - {c} * {p} * {p}) + (n - f) * ({u} - {c} * {u} * {u})) / (({p} - {u}) * ({p} - {u}))) / f"


@query(f"SELECT item, epoch, f, form, {_r6('p')} AS p, {_r6(_w5cost('p'))} AS tuned, {_r6(_w5cost(repr(_PC5)))} AS classical FROM (SELECT item, epoch, f, n, form, k, arg_min(p, cost) AS p FROM (SELECT *, {cost_sql()} AS cost FROM (SELECT item, epoch, f, n, CAST(f AS DOUBLE) / n AS lam, CAST(4.0 AS DOUBLE) AS eps FROM {DAYS_SQL}), (VALUES " + ", ".join(f"('{form}', {k})" for form, k in _FORMS5) + f") AS v(form, k), {_GRID5}) GROUP BY ALL)")
def best_variance_by_target(s, d):
    """Relative root variance at the best p for every day's count of an event type, without collisions."""
    forms = s.createDataFrame(_FORMS5, "form string, k int")
    g = day_counts(s, d).select("item", "epoch", "f", "n", (F.col("f") / F.col("n")).alias("lam"), F.lit(4.0).alias("eps")).crossJoin(F.broadcast(forms))
    c = F.lit(1.0) / F.col("k")

    def root(p):
        u = p / (p + (1 - p) * F.lit(math.exp(4.0)))
        f, n = F.col("f"), F.col("n")
        return R6(F.sqrt((f * (p - c * p * p) + (n - f) * (u - c * u * u)) / ((p - u) * (p - u))) / f)

    return tune.grid_of(g).select("item", "epoch", "f", "form", R6(F.col("p")).alias("p"), root(F.col("p")).alias("tuned"), root(F.lit(_PC5)).alias("classical"))


def _w6(p):
    u = f"({p} / ({p} + (1 - {p}) * exp(4.0)))"
    return f"sqrt((f * {p} * (1 - {p}) + (n - f) * {u} * (1 - {u})) / (({p} - {u}) * ({p} - {u})) + (m2 - f * f - (n - f)) / (65536.0 * 1023)) / f"


@query(f"SELECT item, epoch, f, m2, {_r6('p')} AS p, {_r6(_w6('p'))} AS tuned, {_r6(_w6(repr(_PC5)))} AS classical FROM (SELECT item, epoch, f, m2, n, arg_min(p, cost) AS p FROM (SELECT *, {cost_sql(k='1')} AS cost FROM (SELECT item, epoch, f, m2, day_n AS n, CAST(f AS DOUBLE) / day_n AS lam, CAST(4.0 AS DOUBLE) AS eps FROM {DAYS_SQL}), {_GRID5}) GROUP BY ALL)")
def best_variance_with_collisions(s, d):
    """The same inside every day, with m = 1024 and the collisions of the day's other types (sum of squared counts ``m2``)."""
    g = day_counts(s, d).select("item", "epoch", "f", "m2", F.col("day_n").alias("n"), (F.col("f") / F.col("day_n")).alias("lam"), F.lit(4.0).alias("eps"), F.lit(1).alias("k"))
    f, m2, n = F.col("f"), F.col("m2"), F.col("n")

    def root(p):
        u = p / (p + (1 - p) * F.lit(math.exp(4.0)))
        return R6(F.sqrt((f * p * (1 - p) + (n - f) * u * (1 - u)) / ((p - u) * (p - u)) + (m2 - f * f - (n - f)) / F.lit(65536.0 * 1023)) / f)

    return tune.grid_of(g).select("item", "epoch", "f", "m2", R6(F.col("p")).alias("p"), root(F.col("p")).alias("tuned"), root(F.lit(_PC5)).alias("classical"))


#: Coins of the registered census queries come from this stated secret, so that a run can be repeated.
_COINS = "census"
CENSUS = [("mid", SketchParams(100, 100, 3, 0.57, secret=_COINS)), ("top", SketchParams(100, 100, 7, 0.74, secret=_COINS))]
_PB = math.exp(3.75 / 2) / (1 + math.exp(3.75 / 2))


def _census_var(p, u):
    return f"(f * {p} * (1 - {p}) + (n - f) * {u} * (1 - {u})) / (({p} - {u}) * ({p} - {u})) + (m2 - f * f - (n - f)) / (100.0 * 99)"


_CU = _PB / 100 + (1 - _PB) * (1 - 1 / 100)


@query("SELECT item, f, " + ", ".join(f"round(sqrt({_census_var(repr(p), repr(u))}) / f, 5) AS {n}" for n, p, u in [*((n, sp.p, sp.u) for n, sp in CENSUS), ("classical", _PB, _CU)]) + f" FROM (SELECT *, sum(f) OVER () AS n, sum(f * f) OVER () AS m2 FROM (SELECT item, count(*) AS f FROM {items_sql('band16')} GROUP BY item))")
def census_like(s, d):
    counts = exact.frequencies(item_frame(s, d, "band16"))
    g = counts.crossJoin(F.broadcast(counts.agg(F.sum("f").alias("n"), F.sum(F.col("f") * F.col("f")).alias("m2"))))
    f, n, m2 = F.col("f"), F.col("n"), F.col("m2")

    def rel(p, u):
        return F.round(F.sqrt((f * p * (1 - p) + (n - f) * u * (1 - u)) / ((p - u) * (p - u)) + (m2 - f * f - (n - f)) / F.lit(9900.0)) / f, 5)

    return g.select("item", "f", *(rel(sp.p, sp.u).alias(name) for name, sp in CENSUS), rel(_PB, _CU).alias("classical"))


@query()
def census_simulated(s, d):
    """Measured error of every value under the two tuned settings and the even split, from the exact marginal law."""
    counts = exact.frequencies(item_frame(s, d, "band16"))
    even = SketchParams(100, 100, 14, _PB, secret=_COINS)  # the even split as a subset report
    out = None
    for name, sp in (*CENSUS, ("even", even)):
        r = simulate.marginal_support(counts, sp, 400).select("item", "f", F.lit(name).alias("setting"), (F.sqrt("mse") / F.col("f")).alias("rel_rmse"))
        out = r if out is None else out.unionByName(r)
    return out


@query()
def census_measured(s, d):
    """The census column collected through the production path: two tuned settings, the even split as a subset report, and the bit-vector
    sketch of the same budget, each beside exact counts."""
    at = scratch(s, "census")
    item_frame(s, d, "band16").select("report_id", "item").write.parquet(f"{at}/items")  # a line's digests are computed once
    items = s.read.schema("report_id long, item string").parquet(f"{at}/items")
    exact.frequencies(items).write.parquet(f"{at}/truth")
    truth = s.read.schema("item string, f long").parquet(f"{at}/truth")  # the domain and n come from here
    n = truth.agg(F.coalesce(F.sum("f"), F.lit(0))).first()[0]
    even = SketchParams(100, 100, 14, _PB, secret=_COINS)
    flipped = oracles.classical_params(100, 100, 3.75, secret=_COINS)
    out = None
    for name, sp in (*CENSUS, ("even", even), ("bit_vector", None)):
        if sp:
            mx = sketch.collect_dense(*randomize.subset_worker(items, sp, [], sp.mode), sp.k, sp.m)
            est = estimate.frequencies(truth, mx, sp, n, engine="arrow")
        else:
            mx = sketch.collect_dense(*oracles.classical_worker(items, *flipped), 100, 100)
            est = oracles.classical_estimate(truth, mx, 100, 100, 3.75, n, engine="arrow")
        r = measure.errors(est, truth).select(F.lit(name).alias("setting"), "item", "f", "est", "err")
        out = r if out is None else out.unionByName(r)
    return out


_W7 = [(e, p, m) for e in (3.0, 5.0) for p in (0.5, 0.6) for m in (100, 500, 1000, 2000, 5000, 10000)]
_W7S = "CAST(ceil(round(m / (1 + (1 / p - 1) * exp(eps)), 9)) AS BIGINT)"


@query(f"SELECT epoch, eps, p, m, s, CAST(s * ceil(log2(m)) AS BIGINT) AS bits, m AS classical_bits, CAST(n * s * ceil(log2(m)) AS BIGINT) AS sent, n * m AS classical_sent FROM (SELECT *, {_W7S} AS s FROM {_values(_W7, 'eps, p, m')}, {DAY_SQL})")
def comm_sweep(s, d):
    """Bits a report, and of every day's reports, over settings."""
    g = days(s, d).crossJoin(F.broadcast(s.createDataFrame(_W7, "eps double, p double, m long")))
    g = g.withColumn("s", F.ceil(F.round(F.col("m") / (1 + (1 / F.col("p") - 1) * F.exp("eps")), 9)))
    bits = (F.col("s") * F.ceil(F.log2(F.col("m")))).cast("long")
    return g.select("epoch", "eps", "p", "m", "s", bits.alias("bits"), F.col("m").alias("classical_bits"), (F.col("n") * bits).alias("sent"), (F.col("n") * F.col("m")).alias("classical_sent"))


@query(f"SELECT item, support, {_r6('est')} AS est FROM {estimate_sql(SMOKE, items_sql('role'))} ORDER BY est, item LIMIT 2")
def rare_items(s, d):
    items = item_frame(s, d, "role")
    est = estimate.frequencies(items, sketch.build(randomize.subset_reports(items, SMOKE)), SMOKE)
    return est.orderBy("est", "item").limit(2).select("item", "support", R6(F.col("est")).alias("est"))


@query(f"SELECT item, cnt FROM {counts_sql('doc_word1')} WHERE cnt >= 2 AND item NOT IN (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) FROM benchmark)")
def new_words(s, d):
    from ..sources.items import words
    from ..sources.tables import load

    known = load(s, d, "benchmark", ["text"])
    counts = item_frame(s, d, "doc_word1").groupBy("item").agg(F.count("*").alias("cnt")).filter("cnt >= 2")
    return counts.join(known.select(F.explode(words(known)).alias("item")).distinct(), "item", "left_anti")


def _each(s, d):
    """Brand names, every order line a client of its own (lower-case, as the baselines' alphabet is)."""
    return item_frame(s, d, "brand").withColumn("client_id", F.col("report_id")).withColumn("item", F.lower("item"))


@query()
def trie_discovery(s, d):
    """Whole strings of up to eight characters."""
    got = discover_baselines.private_trie(_each(s, d), 4.0, 8)
    return s.createDataFrame(got, "item string, est double")


@query()
def puzzle_discovery(s, d):
    return discover_baselines.fragment_puzzle(_each(s, d), 6.0, 8)


@query()
def segment_discovery(s, d):
    return discover_baselines.segment_em(item_frame(s, d, "lang"), 4.0)


@query()
def discovery_rivals(s, d):
    """At epsilon 2: the blind histogram, its central yardstick and two protocols of pure local privacy, each held against the strings of
    at least twelve clients."""
    items = _each(s, d)
    truth = exact.frequencies(items).filter("f >= 12")
    trie = s.createDataFrame(discover_baselines.private_trie(items, EPS, 8), "item string, est double")
    found = [("blind", discover.blind_histogram(items, T_, B_, 42)), ("central", discover.central_histogram(items, T_, B_, 42)), ("trie", trie), ("puzzle", discover_baselines.fragment_puzzle(items, EPS, 8))]
    out = None
    for name, got in found:
        r = measure.f_score(got, truth).select(F.lit(name).alias("method"), "hits", "found", "truth", "precision", "recall", "f_score")
        out = r if out is None else out.unionByName(r)
    return out


@query(f"SELECT mark, fragment, count(*) AS cnt FROM (SELECT substr(md5(w), 1, 4) AS mark, substr(w, position * 4 + 1, 4) AS fragment FROM (SELECT rpad(item, 8, '_') AS w FROM {items_sql('nation')}), (SELECT unnest(range(0, 2)) AS position)) GROUP BY ALL")
def puzzle_fragments(s, d):
    return discover_baselines.fragments(item_frame(s, d, "nation"), 8, 4).groupBy("mark", "fragment").agg(F.count("*").alias("cnt"))


@query(f"SELECT DISTINCT rtrim(w, '_') AS item FROM (SELECT rpad(item, 8, '_') AS w FROM {items_sql('event_type')})")
def join_self_fragments(s, d):
    parts = discover_baselines.fragments(item_frame(s, d, "event_type"), 8, 4).select("position", "fragment", "mark").distinct()
    return discover_baselines.puzzle(parts, 2)

