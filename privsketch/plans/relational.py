"""Queries of the surrounding operators: scans, joins, aggregates, windows, set operations, functions, SQL and UDF surfaces."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import sqlapi, tune
from ..functions.prf import below, prf
from ..functions.theory import SketchParams, replayed
from ..operators import discover, exact, joint, randomize, sketch
from ..sources import tables
from ..sources.items import LINE_COLUMNS, LINE_SQL, band_ladder, item_frame, line_key, words
from ..sources.tables import load, scratch
from .core import B_, DAYS_SQL, R6, SMOKE, T_, _r6, day_counts
from .registry import counts_sql, encode_sql, h, items_sql, lt, matrix_sql, noisy_sql, query, reports_sql


@query("SELECT l_orderkey, l_quantity, CAST(l_shipdate AS VARCHAR) AS shipped FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity > 45")
def scan_pruned(s, d):
    df = s.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey", "l_quantity", "l_shipdate")
    return df.filter("l_shipdate >= timestamp_ntz'1998-01-01' and l_quantity > 45").select("l_orderkey", "l_quantity", F.col("l_shipdate").cast("string").alias("shipped"))


@query("SELECT event_id, user_id, event_type, props FROM events")
def csv_roundtrip(s, d):
    return tables.round_trip(load(s, d, "events", ["event_id", "user_id", "event_type", "props"]), scratch(s, "csv"), "csv")


@query("SELECT event_id, user_id, event_type, props FROM events")
def json_roundtrip(s, d):
    return tables.round_trip(load(s, d, "events", ["event_id", "user_id", "event_type", "props"]), scratch(s, "json"), "json")


@query("SELECT event_id, user_id, value FROM events")
def orc_roundtrip(s, d):
    return tables.round_trip(load(s, d, "events", ["event_id", "user_id", "value"]), scratch(s, "orc"), "orc")


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(SMOKE, items_sql('event_type'), 'epoch')} WHERE epoch = DATE '2024-01-05'")
def partitioned_sketch(s, d):
    daily = sketch.build(randomize.subset_reports(item_frame(s, d, "event_type"), SMOKE, keep=["epoch"]), ["epoch"])
    at = tables.write_sketch(daily, scratch(s, "sketch"))
    return s.read.parquet(at).filter("epoch = date'2024-01-05'").select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query()
def synthetic_source(s, d):
    from ..sources import synthetic

    synthetic.register(s)
    return s.read.format("sketch_reports").option("n", 500).load()


@query("SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '%U%' AND o_orderstatus IS NOT DISTINCT FROM 'F'")
def filter_predicates(s, d):
    df = load(s, d, "orders")
    return df.filter(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 200000) & F.col("o_orderpriority").like("%U%") & F.col("o_orderstatus").eqNullSafe("F")).select("o_orderkey", "o_orderpriority")


@query("SELECT count(*) AS n, count(CASE WHEN k IS NULL OR k = '' THEN 1 END) AS dropped FROM (SELECT nullif(regexp_extract(lower(coalesce(text, '')), '^[a-z]+'), '') AS k FROM documents)")
def null_item_policy(s, d):
    k = F.nullif(F.regexp_extract(F.lower(F.coalesce("text", F.lit(""))), "^[a-z]+", 0), F.lit(""))
    return load(s, d, "documents", ["text"]).select(k.alias("k")).agg(F.count("*").alias("n"), F.count(F.when(F.col("k").isNull() | (F.col("k") == ""), 1)).alias("dropped"))


@query(f"SELECT event_id FROM events WHERE {lt(42, 'sample', 0.1, 'event_id')}")
def prf_sample(s, d):
    return load(s, d, "events", ["event_id"]).filter(below(42, "sample", 0.1, "event_id"))


# --- joins ---


@query(f"WITH mx AS MATERIALIZED {matrix_sql(SMOKE, items_sql('lang'))} SELECT item, CAST(j AS BIGINT) AS j, cnt FROM (SELECT item, j, {h(42, 'cell', 'j', 'item')} % 64 + 1 AS x FROM (SELECT DISTINCT item FROM {items_sql('lang')}), (SELECT unnest(range(1, 9)) AS j)) JOIN mx USING (j, x)")
def join_cells_inner(s, d):
    items = item_frame(s, d, "lang")
    mx = sketch.build(randomize.subset_reports(items, SMOKE))
    probes = items.select("item").distinct().withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(8)))).withColumn("x", randomize.cell(SMOKE, F.col("j"), F.col("item")))
    return probes.hint("SHUFFLE_HASH").join(mx, ["j", "x"]).select("item", F.col("j").cast("long"), "cnt")


@query("SELECT r_name, n_name, count(*) AS orders, count(DISTINCT o_custkey) AS clients FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def join_star_items(s, d):
    o, c = load(s, d, "orders", ["o_orderkey", "o_custkey"]), load(s, d, "customer", ["c_custkey", "c_nationkey"])
    n, r = load(s, d, "nation"), load(s, d, "region")
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, F.col("c_nationkey") == n.n_nationkey).join(r, F.col("n_regionkey") == r.r_regionkey)
    return j.groupBy("r_name", "n_name").agg(F.count("*").alias("orders"), F.count_distinct("o_custkey").alias("clients"))


_SMALL = replayed(32, 64, 2, 0.8, 42)


@query(f"WITH mx AS MATERIALIZED {matrix_sql(_SMALL, items_sql('lang'))} SELECT item, CAST(j AS BIGINT) AS j, coalesce(cnt, 0) AS cnt FROM (SELECT item, j, {h(42, 'cell', 'j', 'item')} % 64 + 1 AS x FROM (SELECT DISTINCT item FROM {items_sql('event_type')}), (SELECT unnest(range(1, 33)) AS j)) LEFT JOIN mx USING (j, x)")
def join_left_zero(s, d):
    mx = sketch.build(randomize.subset_reports(item_frame(s, d, "lang"), _SMALL))
    probes = item_frame(s, d, "event_type").select("item").distinct().withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(32)))).withColumn("x", randomize.cell(_SMALL, F.col("j"), F.col("item")))
    return probes.join(mx, ["j", "x"], "left").select("item", F.col("j").cast("long"), F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def _known(s, d):
    return load(s, d, "benchmark", ["text"]).select(F.explode(words(load(s, d, "benchmark", ["text"]))).alias("item")).distinct()


_KNOWN = "(SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) FROM benchmark)"


@query(f"SELECT item, cnt FROM {counts_sql('chat_words')} WHERE item IN {_KNOWN}")
def join_semi_known(s, d):
    return item_frame(s, d, "chat_words").groupBy("item").agg(F.count("*").alias("cnt")).join(_known(s, d), "item", "left_semi")


@query(f"SELECT item, cnt FROM {counts_sql('chat_words')} WHERE item NOT IN {_KNOWN}")
def join_anti_new(s, d):
    return item_frame(s, d, "chat_words").groupBy("item").agg(F.count("*").alias("cnt")).join(_known(s, d), "item", "left_anti")


@query(f"SELECT item, lam, {_r6('f * lam')} AS target FROM (SELECT item, count(*) AS f FROM {items_sql('lang')} GROUP BY item), (VALUES (0.5::DOUBLE), (0.1::DOUBLE), (0.02::DOUBLE)) AS g(lam)")
def join_cross_grid(s, d):
    grid = s.createDataFrame([(0.5,), (0.1,), (0.02,)], "lam double")
    return exact.frequencies(item_frame(s, d, "lang")).crossJoin(F.broadcast(grid)).select("item", "lam", R6(F.col("f") * F.col("lam")).alias("target"))


_LADDER = "(VALUES " + ", ".join(f"('{n}', {a}, {b})" for n, a, b in band_ladder()) + ") AS ladder(band, lo, hi)"


@query(f"SELECT band, count(*) AS cnt FROM (SELECT {h(7, 'band', *LINE_SQL)} AS u FROM lineitem) JOIN {_LADDER} ON u >= lo AND u < hi GROUP BY band")
def join_range_band(s, d):
    ladder = s.createDataFrame(band_ladder(), "band string, lo long, hi long")
    lines = load(s, d, "lineitem", LINE_COLUMNS).select(prf(7, "band", *line_key()).alias("u"))
    return lines.join(F.broadcast(ladder), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("cnt"))


_SCHED = [("2023-12-31 00:00:00", 0), ("2024-01-08 12:00:00", 1), ("2024-01-17 06:30:00", 2), ("2024-01-25 00:00:00", 3)]
_SCHED_SQL = "(VALUES " + ", ".join(f"(TIMESTAMP '{t}', {v})" for t, v in _SCHED) + ") AS sched(valid_from, ver)"


def _schedule(s):
    return s.createDataFrame(_SCHED, "t string, ver int").select(F.to_timestamp("t").alias("valid_from"), "ver")


@query(f"SELECT event_id, CAST(arg_max(ver, valid_from) AS BIGINT) AS ver FROM events JOIN {_SCHED_SQL} ON ts >= valid_from GROUP BY event_id")
def join_asof_params(s, d):
    return joint.asof_params(load(s, d, "events", ["event_id", "ts"]), _schedule(s)).select("event_id", F.col("ver").cast("long"))


@query(f"SELECT event_id, CAST(arg_max(ver, valid_from) AS BIGINT) AS ver FROM events JOIN {_SCHED_SQL} ON ts >= valid_from GROUP BY event_id")
def join_asof_sorted(s, d):
    return joint.asof_sorted(load(s, d, "events", ["event_id", "ts"]), _schedule(s)).select("event_id", F.col("ver").cast("long"))


@query(f"SELECT event_id, CAST(ver AS BIGINT) AS ver FROM events JOIN {_SCHED_SQL} ON ts >= valid_from AND ts < valid_from + INTERVAL 1 HOUR")
def join_interval(s, d):
    e, v = load(s, d, "events", ["event_id", "ts"]), F.broadcast(_schedule(s))
    return e.join(v, (F.col("ts") >= F.col("valid_from")) & (F.col("ts") < F.col("valid_from") + F.expr("interval 1 hour"))).select("event_id", F.col("ver").cast("long"))


@query("SELECT item, coalesce(b.est, a.est)::DOUBLE AS est, CASE WHEN a.est IS NULL THEN 'added' WHEN b.est IS NULL THEN 'kept' ELSE 'updated' END AS change FROM (SELECT item, count(*) AS est FROM {0} WHERE epoch < DATE '2024-01-03' GROUP BY item) a FULL JOIN (SELECT item, count(*) AS est FROM {0} WHERE epoch >= DATE '2024-01-29' GROUP BY item) b USING (item)".format(items_sql("prop_k")))
def join_full_topk(s, d):
    items = item_frame(s, d, "prop_k")
    a = items.filter("epoch < date'2024-01-03'").groupBy("item").agg(F.count("*").cast("double").alias("est"))
    b = items.filter("epoch >= date'2024-01-29'").groupBy("item").agg(F.count("*").cast("double").alias("est"))
    return joint.merge_topk(a, b)


# --- aggregates ---

_GEO = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(s, d):
    c, n, r = load(s, d, "customer", ["c_custkey", "c_nationkey"]), load(s, d, "nation"), load(s, d, "region")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == r.r_regionkey)


@query(f"SELECT r_name, n_name, count(*) AS cnt FROM {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(s, d):
    return _geo(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("cnt"))


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS cnt FROM events GROUP BY CUBE (CAST(CAST(ts AS DATE) AS VARCHAR), event_type)")
def agg_cube(s, d):
    return load(s, d, "events", ["ts", "event_type"]).select(F.to_date("ts").cast("string").alias("day"), "event_type").cube("day", "event_type").agg(F.count("*").alias("cnt"))


@query(f"SELECT r_name, n_name, count(*) AS cnt, CAST(grouping_id(r_name, n_name) AS BIGINT) AS gid FROM {_GEO} GROUP BY GROUPING SETS ((r_name), (n_name), ())")
def agg_grouping_sets(s, d):
    _geo(s, d).createOrReplaceTempView("geo_items")
    return s.sql("SELECT r_name, n_name, count(*) AS cnt, cast(grouping_id(r_name, n_name) AS bigint) AS gid FROM geo_items GROUP BY GROUPING SETS ((r_name), (n_name), ())")


@query(f"SELECT (SELECT count(DISTINCT item) FROM {items_sql('url20')}) AS urls, (SELECT count(DISTINCT item) FROM {items_sql('word')}) AS words")
def agg_distinct(s, d):
    a = item_frame(s, d, "url20").agg(F.count_distinct("item").alias("urls"))
    return a.crossJoin(item_frame(s, d, "word").agg(F.count_distinct("item").alias("words")))


@query()
def agg_approx_distinct(s, d):
    df = item_frame(s, d, "word")
    return df.agg(F.approx_count_distinct("item", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("item", F.lit(14))).alias("hll"))


@query()
def agg_central_sketches(s, d):
    return item_frame(s, d, "word").agg(F.length(F.count_min_sketch("item", F.lit(0.01), F.lit(0.95), F.lit(1))).alias("sketch_bytes"), F.approx_percentile("report_id", F.lit(0.5)).alias("median"))


@query()
def agg_central_topk(s, d):
    return item_frame(s, d, "word").agg(F.expr("approx_top_k(item, 10)").alias("top")).select(F.explode("top").alias("t")).select("t.*")


@query(f"SELECT item, count(*) FILTER (WHERE own) AS truthful, count(*) AS n FROM {reports_sql(SMOKE, items_sql('lang'))} GROUP BY item")
def agg_conditional(s, d):
    return randomize.include(item_frame(s, d, "lang"), SMOKE).groupBy("item").agg(F.count_if("own").alias("truthful"), F.count("*").alias("n"))


@query(f"SELECT item, arg_min(report_id, {h(42, 'pick', 'report_id')}) AS picked, max(report_id) AS latest FROM {items_sql('host')} GROUP BY item")
def agg_minmaxby(s, d):
    return item_frame(s, d, "host").groupBy("item").agg(F.min_by("report_id", prf(42, "pick", "report_id")).alias("picked"), F.max_by("report_id", "report_id").alias("latest"))


@query(f"SELECT CAST(sum(f) AS BIGINT) AS n, CAST(sum(f * f) AS BIGINT) AS second_moment FROM (SELECT item, count(*) AS f FROM {items_sql('word')} GROUP BY item)")
def agg_moment2(s, d):
    return exact.moments(item_frame(s, d, "word"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(var_samp(value), 4) AS var, round(avg(value), 6) AS mean FROM events GROUP BY event_type")
def agg_percentile(s, d):
    return load(s, d, "events", ["event_type", "value"]).groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.var_samp("value"), 4).alias("var"), F.round(F.avg("value"), 6).alias("mean"))


@query(f"WITH mx AS MATERIALIZED {matrix_sql(SMOKE, items_sql('lang'))} SELECT CAST(j AS BIGINT) AS j, string_agg(coalesce(cnt, 0), ',' ORDER BY x) AS cells FROM (SELECT j, x FROM (SELECT unnest(range(1, 9)) AS j), (SELECT unnest(range(1, 65)) AS x)) LEFT JOIN mx USING (j, x) GROUP BY j")
def agg_collect(s, d):
    rows = sketch.to_rows(sketch.build(randomize.subset_reports(item_frame(s, d, "lang"), SMOKE)), 64)
    return rows.select(F.col("j").cast("long"), F.array_join("cells", ",").alias("cells"))


@query("SELECT event_type, count(*) FILTER (WHERE b = 0) AS b0, count(*) FILTER (WHERE b = 1) AS b1, count(*) FILTER (WHERE b = 2) AS b2 FROM (SELECT event_type, user_id % 3 AS b FROM events) GROUP BY event_type")
def agg_pivot(s, d):
    df = load(s, d, "events", ["event_type", "user_id"]).withColumn("b", F.concat(F.lit("b"), F.col("user_id") % 3))
    return df.groupBy("event_type").pivot("b", ["b0", "b1", "b2"]).count()


# --- windows, sorting, sets ---


@query("SELECT * FROM (SELECT s_suppkey, s_nationkey, rank() OVER w AS rk, dense_rank() OVER w AS drk, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rn, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS quarter FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal DESC)) WHERE rn <= 3")
def win_rank_topk(s, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"))
    u = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey")
    df = load(s, d, "supplier", ["s_suppkey", "s_nationkey", "s_acctbal"])
    df = df.select("s_suppkey", "s_nationkey", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("drk"), F.row_number().over(u).cast("long").alias("rn"), F.ntile(4).over(u).cast("long").alias("quarter"))
    return df.filter("rn <= 3")


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, item, f, coalesce(f - lag(f) OVER (PARTITION BY item ORDER BY epoch), 0) AS change FROM (SELECT epoch, item, count(*) AS f FROM {items_sql('event_type')} GROUP BY 1, 2)")
def win_lag_popularity(s, d):
    f = item_frame(s, d, "event_type").groupBy("epoch", "item").agg(F.count("*").alias("f"))
    return f.select(F.col("epoch").cast("string"), "item", "f", F.coalesce(F.col("f") - F.lag("f").over(Window.partitionBy("item").orderBy("epoch")), F.lit(0)).cast("long").alias("change"))


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, {_r6('avg(f) OVER (ORDER BY epoch ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)')} AS moving, CAST(sum(f) OVER (ORDER BY epoch) AS BIGINT) AS total FROM (SELECT epoch, count(*) AS f FROM {items_sql('event_type')} GROUP BY 1)")
def win_running_budget(s, d):
    f = item_frame(s, d, "event_type").groupBy("epoch").agg(F.count("*").alias("f"))
    w = Window.orderBy("epoch")
    return f.select(F.col("epoch").cast("string"), R6(F.avg("f").over(w.rowsBetween(-6, 0))).alias("moving"), F.sum("f").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


@query(f"SELECT CAST(epoch AS VARCHAR) AS epoch, CAST(sum(f) OVER (ORDER BY epoch RANGE BETWEEN INTERVAL 2 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS three_days FROM (SELECT epoch, count(*) AS f FROM {items_sql('event_type')} GROUP BY 1)")
def win_range_days(s, d):
    f = item_frame(s, d, "event_type").groupBy("epoch").agg(F.count("*").alias("f")).withColumn("day", F.unix_date("epoch"))
    return f.select(F.col("epoch").cast("string"), F.sum("f").over(Window.orderBy("day").rangeBetween(-2, 0)).alias("three_days"))


@query(f"SELECT item, f, {_r6('f * 1.0 / sum(f) OVER ()')} AS lam FROM (SELECT item, count(*) AS f FROM {items_sql('brand')} GROUP BY item)")
def win_share(s, d):
    f = exact.frequencies(item_frame(s, d, "brand"))
    return f.crossJoin(F.broadcast(f.agg(F.sum("f").alias("n")))).select("item", "f", R6(F.col("f") / F.col("n")).alias("lam"))


@query(f"SELECT item, cnt FROM {counts_sql('word')} ORDER BY cnt DESC, item LIMIT 20 OFFSET 5")
def sort_global_limit(s, d):
    f = item_frame(s, d, "word").groupBy("item").agg(F.count("*").alias("cnt"))
    return f.orderBy(F.desc("cnt"), "item").offset(5).limit(20)


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, CAST(sum(cnt) AS BIGINT) AS cnt FROM {matrix_sql(SMOKE, items_sql('event_type'), 'epoch')} WHERE epoch IN (DATE '2024-01-02', DATE '2024-01-03') GROUP BY 1, 2")
def setop_union_sketch(s, d):
    daily = sketch.build(randomize.subset_reports(item_frame(s, d, "event_type"), SMOKE, keep=["epoch"]), ["epoch"])
    days = [daily.filter(F.col("epoch") == F.lit(x).cast("date")).drop("epoch") for x in ("2024-01-02", "2024-01-03")]
    return sketch.merge(*days).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


_HREF_FOUND = f"(SELECT item FROM {noisy_sql(counts_sql('href'), B_, 42)} WHERE noisy >= {T_!r})"
_HREF_TOP = f"(SELECT item FROM {counts_sql('href')} WHERE cnt >= 10)"


def _found_top(s, d):
    items = item_frame(s, d, "href")
    return discover.central_histogram(items, T_, B_, 42).select("item"), exact.frequencies(items).filter("f >= 10").select("item")


@query(f"SELECT item FROM {_HREF_FOUND} INTERSECT SELECT item FROM {_HREF_TOP}")
def setop_intersect_found(s, d):
    found, top = _found_top(s, d)
    return found.intersect(top)


@query(f"SELECT item FROM {counts_sql('href')} WHERE cnt >= 3 EXCEPT SELECT item FROM {_HREF_FOUND}")
def setop_except_missed(s, d):
    """Strings of three or more reports that stay under the threshold."""
    items = item_frame(s, d, "href")
    return exact.frequencies(items).filter("f >= 3").select("item").exceptAll(discover.central_histogram(items, T_, B_, 42).select("item"))


@query(f"SELECT epoch, item, {_r6('percent_rank() OVER w')} AS share_below, {_r6('cume_dist() OVER w')} AS share_upto FROM (SELECT CAST(epoch AS VARCHAR) AS epoch, item, count(*) AS cnt FROM {items_sql('event_type')} GROUP BY 1, 2) WINDOW w AS (PARTITION BY epoch ORDER BY cnt)")
def window_percent_rank(s, d):
    """Where each item of a day stands among the day's counts."""
    counts = item_frame(s, d, "event_type").groupBy(F.col("epoch").cast("string").alias("epoch"), "item").agg(F.count("*").alias("cnt"))
    w = Window.partitionBy("epoch").orderBy("cnt")
    return counts.select("epoch", "item", R6(F.percent_rank().over(w)).alias("share_below"), R6(F.cume_dist().over(w)).alias("share_upto"))


# --- functions ---


@query("SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, left(url, 20) AS prefix, length(url) AS size FROM pages")
def str_url_parts(s, d):
    df = load(s, d, "pages", ["page_id", "url"])
    return df.select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("HOST")).alias("host"), F.left("url", F.lit(20)).alias("prefix"), F.length("url").cast("long").alias("size"))


@query("SELECT conv_id, turn, len(w) AS n_words, coalesce(list_aggregate(list_transform(w, lambda x: length(x)), 'max'), 0) AS longest FROM (SELECT conv_id, turn, regexp_extract_all(lower(coalesce(text, '')), '[a-z]+') AS w FROM conversations)")
def str_words(s, d):
    df = load(s, d, "conversations", ["conv_id", "turn", "text"])
    w = words(df)
    return df.select("conv_id", "turn", F.size(w).cast("long").alias("n_words"), F.coalesce(F.array_max(F.transform(w, F.length)), F.lit(0)).cast("long").alias("longest"))


@query("SELECT n_name, md5(n_name) AS m, sha256(n_name) AS s2 FROM nation")
def hash_digest(s, d):
    return load(s, d, "nation", ["n_name"]).select("n_name", F.md5("n_name").alias("m"), F.sha2("n_name", 256).alias("s2"))


@query(f"SELECT report_id, list_contains(x, r) AS has_own, len(list_filter(x, lambda v: v <= 32)) AS low, CAST(list_sum(x) AS BIGINT) AS total FROM {reports_sql(SMOKE, items_sql('lang'))}")
def array_support(s, d):
    r = randomize.extend(randomize.include(randomize.encode(item_frame(s, d, "lang"), SMOKE), SMOKE), SMOKE)
    return r.select("report_id", F.exists("x", lambda v: v == F.col("r")).alias("has_own"), F.size(F.filter("x", lambda v: v <= 32)).cast("long").alias("low"), F.aggregate("x", F.lit(0).cast("long"), lambda a, v: a + v).alias("total"))


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(sum(cnt) AS BIGINT) AS total, count(DISTINCT x) AS cells FROM (SELECT * FROM {matrix_sql(SMOKE, items_sql('lang'))} UNION ALL SELECT * FROM {matrix_sql(SMOKE, items_sql('role'))}) GROUP BY j")
def map_row_merge(s, d):
    a, b = (sketch.to_maps(sketch.build(randomize.subset_reports(item_frame(s, d, k), SMOKE))) for k in ("lang", "role"))
    both = sketch.merge_maps(a, b)
    return both.select(F.col("j").cast("long"), F.aggregate(F.map_values("cells"), F.lit(0).cast("long"), lambda x, v: x + v).alias("total"), F.size("cells").cast("long").alias("cells"))


@query(f"SELECT item, cnt FROM {counts_sql('prop_k')}")
def json_prop_item(s, d):
    df = load(s, d, "events", ["props"]).select(F.from_json("props", "k string")["k"].alias("item"))
    return df.filter("item is not null and item <> ''").groupBy("item").agg(F.count("*").alias("cnt"))


@query("SELECT CAST(CAST(date_trunc('week', ts) AS DATE) AS VARCHAR) AS week, CAST(max(date_diff('day', TIMESTAMP '2024-01-01', ts)) AS BIGINT) AS age, count(*) AS cnt FROM (SELECT CAST(CAST(ts AS DATE) AS TIMESTAMP) AS ts FROM events) GROUP BY 1")
def date_epochs(s, d):
    df = load(s, d, "events", ["ts"])
    return df.groupBy(F.to_date(F.date_trunc("week", "ts")).cast("string").alias("week")).agg(F.max(F.date_diff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))).cast("long").alias("age"), F.count("*").alias("cnt"))


@query("SELECT o_orderpriority, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS VARCHAR) AS total FROM orders GROUP BY 1")
def decimal_totals(s, d):
    return load(s, d, "orders", ["o_orderpriority", "o_totalprice"]).groupBy("o_orderpriority").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("string").alias("total"))


_FORMS = "(VALUES (64, 5, 0.6::DOUBLE), (100, 7, 0.74::DOUBLE), (100, 3, 0.57::DOUBLE), (1000, 48, 0.5::DOUBLE)) AS g(m, s, p)"
_SIZES = "(VALUES (64, 5), (100, 7), (100, 3), (1000, 48)) AS v(m, s)"


@query(f"SELECT item, epoch, m, s, {_r6('p')} AS p, {_r6('(s - p) / (m - 1)')} AS q, {_r6('s * 1.0 / m')} AS u, {_r6('abs(ln(p * (m - s) / ((1 - p) * s)))')} AS eps FROM (SELECT item, epoch, CAST(0.5 AS DOUBLE) + CAST(0.4 AS DOUBLE) * f / day_n AS p FROM {DAYS_SQL}), {_SIZES}")
def math_closed_forms(s, d):
    """Closed forms at a p that grows from half on with the day's share of an event type."""
    from ..functions import theory

    sizes = s.createDataFrame([(64, 5), (100, 7), (100, 3), (1000, 48)], "m int, s int")
    g = day_counts(s, d).select("item", "epoch", (F.lit(0.5) + F.lit(0.4) * F.col("f") / F.col("day_n")).alias("p")).crossJoin(F.broadcast(sizes))
    p, z, m = F.col("p"), F.col("s"), F.col("m")
    return g.select("item", "epoch", "m", "s", R6(p).alias("p"), R6(theory.q_of(p, z, m)).alias("q"), R6(z / m).alias("u"), R6(theory.eps_col(p, z, m)).alias("eps"))


@query(f"SELECT m, s, p, {_r6('(s - p) / (m - 1)')} AS q, {_r6('abs(ln(p * (m - s) / ((1 - p) * s)))')} AS eps, {_r6('(1000.0 * p * (1 - p) + 99000.0 * (s * 1.0 / m) * (1 - s * 1.0 / m)) / ((p - s * 1.0 / m) * (p - s * 1.0 / m)) + (1e8 - 1e6 - 99000.0) / (8.0 * (m - 1))')} AS var FROM {_FORMS} WHERE p > 0.5")
def sqlfn_closed_forms(s, d):
    sqlapi.register_functions(s)
    s.createDataFrame([(64, 5, 0.6), (100, 7, 0.74), (100, 3, 0.57)], "m int, s int, p double").createOrReplaceTempView("forms")
    return s.sql("SELECT m, s, p, round(ldp_q(p, s, m), 6) + 0D AS q, round(ldp_eps(p, s, m), 6) + 0D AS eps, round(ldp_variance(1000, 100000, 1e8, 8, m, s, p), 6) + 0D AS var FROM forms")


# --- UDF surface ---


@query(f"SELECT report_id, CAST(r AS BIGINT) AS cell FROM {encode_sql(SMOKE, items_sql('nation'))}")
def udf_cell(s, d):
    from ..sources.workers import ship

    ship(s)
    rows = randomize.encode(item_frame(s, d, "nation"), SMOKE)
    return rows.select("report_id", sqlapi.cell_udf(42, 64)("j", "item").cast("long").alias("cell"))


@query(f"SELECT item, count(*) FILTER (WHERE list_contains(x, r)) AS support FROM {reports_sql(SMOKE, items_sql('nation'))} GROUP BY item")
def pandas_support(s, d):
    r = randomize.extend(randomize.include(randomize.encode(item_frame(s, d, "nation"), SMOKE), SMOKE), SMOKE)
    return r.groupBy("item").agg(sqlapi.support_udf()("x", "r").alias("support"))


@query(f"SELECT report_id, CAST(j AS BIGINT) AS j, CAST(unnest(x) AS BIGINT) AS x FROM {reports_sql(SMOKE, items_sql('lang'))}")
def udtf_subset(s, d):
    sqlapi.register_table_functions(s)
    item_frame(s, d, "lang").createOrReplaceTempView("lang_items")
    return s.sql("SELECT i.report_id, cast(t.j AS bigint) AS j, cast(t.x AS bigint) AS x FROM lang_items i, LATERAL subset_report(42, 8, 64, 5, 0.6D, i.report_id, i.item) t")


@query("SELECT * FROM (VALUES " + ", ".join(f"(CAST({lam} AS DOUBLE), CAST({round(t.p, 6)} AS DOUBLE), {t.s}, CAST({round(t.eps_real, 6)} AS DOUBLE))" for lam, t in tune.regimes(3.75, 100, 100).items()) + ") AS g(lam, p, s, eps_real)")
def udtf_sweep(s, d):
    sqlapi.register_table_functions(s)
    return s.sql("SELECT * FROM sweep(3.75D, 100, 100)")


@query(f"SELECT CAST(j AS BIGINT) AS j, CAST(x AS BIGINT) AS x, cnt FROM {matrix_sql(SMOKE, items_sql('priority'))}")
def arrow_sketch(s, d):
    r = randomize.subset_reports(item_frame(s, d, "priority"), SMOKE)
    return sketch.build_dense(r, 8, 64).select(F.col("j").cast("long"), F.col("x").cast("long"), "cnt")


@query("SELECT event_type, date_trunc('month', ts)::DATE::VARCHAR AS month, count(*) AS cnt FROM events GROUP BY 1, 2")
def sql_views(s, d):
    tables.register_views(s, d, ["events"])
    return s.sql("SELECT event_type, cast(to_date(date_trunc('month', ts)) AS string) AS month, count(*) AS cnt FROM events GROUP BY 1, 2")


@query("SELECT n_name, levenshtein(n_name, 'CANADA') AS distance, upper(left(n_name, 3)) AS code FROM nation")
def str_distance(s, d):
    return load(s, d, "nation", ["n_name"]).select("n_name", F.levenshtein("n_name", F.lit("CANADA")).cast("long").alias("distance"), F.upper(F.left("n_name", F.lit(3))).alias("code"))


@query("SELECT event_id, CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS BIGINT) AS hours, CAST(date_trunc('hour', ts) + INTERVAL 90 MINUTE AS VARCHAR) AS closes FROM events")
def date_windows(s, d):
    hour = F.date_trunc("hour", "ts")
    return load(s, d, "events", ["event_id", "ts"]).select("event_id", F.timestamp_diff("HOUR", F.lit("2024-01-01").cast("timestamp"), hour).alias("hours"), (hour + F.make_interval(mins=F.lit(90))).cast("string").alias("closes"))


@query("SELECT item, count(*) AS times FROM (SELECT event_type AS item FROM events WHERE user_id < 40 INTERSECT ALL SELECT event_type FROM events WHERE user_id >= 40 AND user_id < 60) GROUP BY item")
def setop_intersect_all(s, d):
    df = load(s, d, "events", ["event_type", "user_id"])
    both = df.filter("user_id < 40").select(F.col("event_type").alias("item")).intersectAll(df.filter("user_id >= 40 and user_id < 60").select("event_type"))
    return both.groupBy("item").agg(F.count("*").alias("times"))
