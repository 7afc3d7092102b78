"""Operators on Spark: samplers, relay, sealing, discovery, plans, and every query against its SQL."""

import math
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from privsketch.functions.theory import SketchParams, replayed
from privsketch.operators import discover, estimate, randomize, relay, seal, sketch
from privsketch.plans import QUERIES, SQL
from privsketch.sources.items import KEYS, band_ladder, item_frame


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="session")
def duck(medium):
    con = duckdb.connect()
    for name in os.listdir(medium):
        con.sql(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{medium}/{name}')")
    return con


def clean(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    return round(float(v), 5) if isinstance(v, (float, np.floating)) else int(v) if isinstance(v, np.integer) else v


@pytest.mark.parametrize("key", sorted(SQL.keys() & QUERIES.keys()))
def test_query_equals_its_sql(spark, medium, duck, key):
    got, want = QUERIES[key](spark, medium).toPandas(), duck.sql(SQL[key]).df()
    assert sorted(got.columns) == sorted(want.columns)
    cols = sorted(got.columns)
    rows = lambda x: sorted((tuple(map(clean, r)) for r in x[cols].astype(object).where(x[cols].notna(), None).itertuples(index=False)), key=str)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("key", sorted(QUERIES.keys() - SQL.keys()))
def test_query_without_sql_runs(spark, medium, key):
    assert QUERIES[key](spark, medium).count() >= 1


def test_entry(spark):
    assert entry.entry(spark).count() == 4
    assert len(entry.queries()) >= 140 and entry.oracle_sql().keys() <= entry.queries().keys()


@pytest.mark.parametrize("key", sorted(KEYS))
def test_item_frames(spark, small, key):
    df = item_frame(spark, small, key)
    assert df.columns == ["report_id", "client_id", "item", "epoch"]
    assert df.count() > 0 and df.filter("item is null or item = ''").count() == 0
    assert df.select("report_id").distinct().count() == df.count()


def test_band_ladder_covers_the_range():
    ladder = band_ladder()
    assert ladder[0][1] == 0 and ladder[-1][2] == 1 << 52 and all(a[2] == b[1] for a, b in zip(ladder, ladder[1:], strict=False))


@pytest.mark.parametrize("engine,s,p", [("sql", 1, 0.6), ("sql", 3, 0.7), ("sql", 8, 0.6), ("arrow", 1, 0.6), ("arrow", 3, 0.7), ("arrow", 8, 0.6)])
def test_reports_are_subsets_with_the_right_marginals(spark, engine, s, p):
    n, m = 6000, 16
    items = spark.range(n).select(F.col("id").alias("report_id"), F.lit("same").alias("item"))
    sp = replayed(1, m, s, p)
    rows = randomize.subset_reports(items, sp, engine=engine, keep=["report_id"]).collect()
    assert len(rows) == n
    for r in rows:
        assert len(set(r.x)) == s and min(r.x) >= 1 and max(r.x) <= m and r.x == sorted(r.x)
    counts = np.bincount([c for r in rows for c in r.x], minlength=m + 1)[1:]
    top = counts.argmax()
    z = lambda c, q: abs(c - n * q) / math.sqrt(n * q * (1 - q))
    assert z(counts[top], p) < 4.5 and all(z(c, sp.q) < 4.5 for i, c in enumerate(counts) if i != top)


def test_floyd_is_uniform_over_subsets(spark):
    items = spark.range(8000).select(F.col("id").alias("report_id"), F.lit("same").alias("item"))
    for engine in ("sql", "arrow"):
        rows = randomize.subset_reports(items, replayed(1, 6, 3, 0.5, 5), engine=engine).groupBy(F.array_join("x", ",").alias("x")).count().collect()
        assert len(rows) == 20  # p = s/m: all subsets alike
        chi = sum((r["count"] - 400) ** 2 / 400 for r in rows)
        assert chi < 50


def test_arrow_reports_repeat_exactly(spark, small):
    items = item_frame(spark, small, "band16")
    sp = replayed(100, 100, 7, 0.74)
    a, b = (randomize.subset_reports(x, sp, engine="arrow", keep=["report_id"]) for x in (items, items.repartition(3)))
    assert a.exceptAll(b).count() == 0
    total = sketch.build(a).agg(F.sum("cnt")).first()[0]
    assert total == 7 * items.count()


def test_matrix_forms_agree(spark, small):
    reports = randomize.subset_reports(item_frame(spark, small, "lang"), replayed(4, 32, 4, 0.6))
    long = sketch.build(reports)
    assert long.exceptAll(sketch.build_dense(reports, 4, 32)).count() == 0
    assert sketch.to_rows(long, 32).select(F.explode("cells").alias("c")).agg(F.sum("c")).first()[0] == long.agg(F.sum("cnt")).first()[0]


def test_estimates_are_unbiased(spark, medium):
    items = item_frame(spark, medium, "lang").cache()
    truth = {r["item"]: r["count"] for r in items.groupBy("item").count().collect()}
    runs = 24
    mean = dict.fromkeys(truth, 0.0)
    for seed in range(runs):
        sp = replayed(8, 64, 5, 0.6, seed)
        for r in estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp)), sp).collect():
            mean[r["item"]] += r["est"] / runs
    for item, f in truth.items():
        assert abs(mean[item] - f) < 4 * 80 / math.sqrt(runs)


def test_intervals_hold_most_counts(spark, medium):
    items = item_frame(spark, medium, "source")
    sp = replayed(64, 128, 5, 0.7)
    got = estimate.interval(estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp)), sp), sp, 3.0).join(items.groupBy("item").count(), "item").collect()
    assert sum(r["lo"] <= r["count"] <= r["hi"] for r in got) >= len(got) - 1


def test_simplex_projection(spark):
    est = spark.createDataFrame([("a", 8.0, 10), ("b", 5.0, 10), ("c", -4.0, 10)], "item string, est double, n long")
    got = {r["item"]: r["est"] for r in estimate.consistency(est, "simplex").collect()}
    assert got == pytest.approx({"a": 6.5, "b": 3.5, "c": 0.0})


def test_relay(spark, small):
    items = item_frame(spark, small, "event_type")
    out = relay.collect(items, limit=2, seed=3)
    assert out.columns == ["item"]
    assert relay.cap(items, 2).groupBy("client_id").count().agg(F.max("count")).first()[0] == 2
    assert "WindowGroupLimit" in plan(relay.cap(items, 2))
    assert "Exchange" not in plan(relay.collect(items, materialise_shuffle=False))


def test_sealing_is_fresh_and_keyed(spark):
    df = spark.createDataFrame([(1, "a"), (2, "a")], "id long, item string")
    sealed = seal.seal(df, "one", ["item"])
    assert sealed.columns == ["id", "sealed"] and sealed.select("sealed").distinct().count() == 2
    assert {r["item"] for r in seal.unseal(sealed, "one", "item string").collect()} == {"a"}
    assert {r["item"] for r in seal.unseal(sealed, "two", "item string").collect()} == {None}


def test_helper_sees_no_text_and_equals_the_curator(spark, small):
    items = item_frame(spark, small, "href")
    sent = discover.client(items, "server", "helper")
    assert sent.columns == ["report_id", "outer"]
    released = discover.helper(sent, "helper", 5.0, 1.0, 7)
    assert released.columns == ["digest", "inner", "noisy"] and "collect_list" not in plan(released)
    blind = {r["item"] for r in discover.open_items(released, "server").collect()}
    central = {r["item"] for r in discover.central_histogram(items, 5.0, 1.0, 7).collect()}
    assert blind == central and blind <= {r["item"] for r in items.select("item").distinct().collect()}


def test_singletons_are_released_with_probability_delta(spark):
    t, b = 3.0, 1.0
    items = spark.range(20000).select(F.concat(F.lit("w"), F.col("id")).alias("item"))
    got = discover.central_histogram(items, t, b, 11).count()
    q = 0.5 * math.exp(-(t - 1) / b)
    assert abs(got - 20000 * q) < 4.5 * math.sqrt(20000 * q * (1 - q))


def test_expected_yield_matches_a_release(spark, medium):
    items = item_frame(spark, medium, "href")
    counts = items.groupBy("item").agg(F.count("*").alias("f"))
    grid = spark.createDataFrame([(6.0, 1.0)], "threshold double, scale double")
    want = discover.expected_yield(counts, grid).first()["expected"]
    got = np.mean([discover.central_histogram(items, 6.0, 1.0, s).count() for s in range(8)])
    assert abs(got - want) < 12


def test_lookup_plan_has_no_cartesian_and_prunes_columns(spark, small):
    items = item_frame(spark, small, "lang")
    sp = replayed(8, 64, 5, 0.6)
    text = plan(estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp)), sp))
    assert "CartesianProduct" not in text and "BroadcastHashJoin" in text and "text" not in text.split("ReadSchema")[1].split("\n")[0]


def test_support_scan_refuses_large_domains(spark, small):
    words = item_frame(spark, small, "word")
    with pytest.raises(ValueError):
        estimate.support_scan(words, words, replayed(8, 64, 5, 0.6), largest=100)


def test_support_scan_counts_items_and_not_their_rows(spark):
    sp = replayed(8, 64, 5, 0.6)
    items = spark.range(150).select(F.col("id").alias("report_id"), (F.col("id") % 3).cast("string").alias("item"))
    reports = randomize.subset_reports(items, sp)
    got = dict(map(tuple, estimate.support_scan(items, reports, sp, largest=100).collect()))
    assert got == dict(map(tuple, estimate.support(items, sketch.build(reports), sp).collect())) and len(got) == 3


def test_the_rest_works_without_the_operator_folder(tmp_path):
    """The entry module imports and keeps its other queries when the subpackage and the pipeline are gone."""
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(os.path.join(root, "privsketch"), tmp_path / "privsketch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(root, "__spark_entry__.py"), tmp_path)
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), any(k.startswith('op') and k[2].isdigit() for k in e.queries()))"], cwd=tmp_path, capture_output=True, text=True, timeout=120, env={**os.environ, "PYTHONPATH": ""})
    assert out.stdout.split() == [str(len(QUERIES)), "False"], out.stderr


@pytest.mark.parametrize("engine", ["sql", "arrow"])
def test_coins_are_secret(spark, engine):
    """Knowing the family's seed and the report ids, one cannot tell who reported the own cell."""
    n, k, m = 4000, 4, 16
    items = spark.range(n).select(F.col("id").alias("report_id"), F.lit("same").alias("item"))
    own, other = SketchParams(k, m, 3, 0.7, 5), SketchParams(k, m, 3, 0.7, 5)
    assert own == other and own.secret != other.secret and own.secret not in repr(own) and own.public().secret == ""
    a, b, again = (randomize.subset_reports(items, sp, engine=engine, keep=["report_id"]) for sp in (own, other, own))
    assert a.exceptAll(again).count() == 0
    rows = {x: {r.report_id: (r.j, tuple(r.x)) for r in df.collect()} for x, df in (("a", a), ("b", b))}
    alike = sum(rows["a"][i][0] == rows["b"][i][0] for i in range(n))
    assert abs(alike - n / k) < 5 * math.sqrt(n * (1 / k) * (1 - 1 / k))
    guess = {r.report_id: r.own for r in randomize.include(items, own, mode="replay").select("report_id", "own").collect()}
    if engine == "sql":
        true = {r.report_id: r.own for r in randomize.include(items, own).select("report_id", "own").collect()}
        right = sum(guess[i] == true[i] for i in range(n))
        assert abs(right - n * (0.7**2 + 0.3**2)) < 5 * math.sqrt(n) * 0.5


def test_arrow_lookup_is_unbiased(spark, medium):
    items = item_frame(spark, medium, "lang").cache()
    truth = {r["item"]: r["count"] for r in items.groupBy("item").count().collect()}
    runs, mean = 16, dict.fromkeys(truth, 0.0)
    for seed in range(runs):
        sp = SketchParams(8, 64, 5, 0.6, seed, secret=f"s{seed}")
        for r in estimate.frequencies(items, sketch.build(randomize.subset_reports(items, sp, engine="arrow")), sp, engine="arrow").collect():
            mean[r["item"]] += r["est"] / runs
    for item, f in truth.items():
        assert abs(mean[item] - f) < 4 * 80 / math.sqrt(runs)


def test_bit_vector_reports_of_both_engines(spark, medium):
    from privsketch.operators import oracles

    items = item_frame(spark, medium, "lang").cache()
    truth, n = {r["item"]: r["count"] for r in items.groupBy("item").count().collect()}, items.count()
    mx = sketch.build(oracles.classical_reports(items, 16, 32, 3.0, engine="arrow", secret="x"))
    for r in oracles.classical_estimate(items, mx, 16, 32, 3.0, n, engine="arrow").collect():
        assert abs(r["est"] - truth[r["item"]]) < 300
    with pytest.raises(ValueError):
        oracles.classical_reports(items, 16, 32, 3.0, engine="arrow")


def test_unknown_strings_by_local_privacy(spark):
    """Trie and puzzle find the heavy strings and little else; too few reports find nothing."""
    from privsketch.operators import discover_baselines

    names = ["brand#11", "brand#25", "x9", "alpha"]
    items = spark.range(24_000).select(F.col("id").alias("report_id"), F.col("id").alias("client_id"), F.element_at(F.array(*map(F.lit, names)), (F.col("id") % 4 + 1).cast("int")).alias("item"))
    trie = dict(discover_baselines.private_trie(items, 4.0, 8))
    assert set(names) <= set(trie) and len(trie) <= 6 and all(abs(trie[x] - 6000) < 1500 for x in names)
    puzzle = {r["item"]: r["est"] for r in discover_baselines.fragment_puzzle(items, 6.0, 8).collect()}
    assert set(names) == set(puzzle)
    assert discover_baselines.private_trie(items.limit(40), 2.0, 8) == []
    with pytest.raises(ValueError):
        discover_baselines.segment_em(items, 4.0, size=3)


def test_retuned_streams_use_what_they_learn(spark, medium):
    rows = QUERIES["stream_retune"](spark, medium).orderBy("ver").collect()
    assert len(rows) == 3 and all((a["next_p"], a["next_s"]) == (b["p"], b["s"]) for a, b in zip(rows, rows[1:], strict=False))
    assert rows[0]["p"] != rows[1]["p"]


@pytest.mark.parametrize("mode", ["keyed", "fast"])
def test_other_modes_repeat_and_differ_from_replay(spark, small, mode):
    items, sp = item_frame(spark, small, "lang"), replayed(8, 64, 5, 0.6)
    a, b, c = (randomize.subset_reports(items, sp, mode=x, keep=["report_id"]) for x in (mode, mode, "replay"))
    assert a.exceptAll(b).count() == 0 and a.exceptAll(c).count() > 0
    est = estimate.frequencies(items, sketch.build(a), sp, mode=mode)
    assert est.count() == 4


def test_asof_forms_agree(spark, small):
    from privsketch.operators import joint
    from privsketch.sources.tables import load

    events = load(spark, small, "events", ["event_id", "ts"])
    schedule = spark.createDataFrame([("2024-01-03 05:10:00", 0), ("2024-01-03 05:40:00", 1), ("2024-01-20 00:00:00", 2)], "t string, ver int").select(F.to_timestamp("t").alias("valid_from"), "ver")
    a, b = joint.asof_params(events, schedule), joint.asof_sorted(events, schedule)
    assert a.exceptAll(b).count() == 0 and a.count() == b.count() == events.count()
    assert a.filter("ver is null").count() > 0 and "Exchange hashpartitioning" not in plan(a).split("BroadcastExchange")[0] and "NestedLoop" not in plan(a)


def test_asof_against_brute_force(spark):
    """Ties, nulls, reports before, between and after, days without a change, many changes a day, an empty schedule, one too long."""
    import datetime
    import random

    from privsketch.operators import joint

    r = random.Random(3)
    start = datetime.datetime(2024, 1, 1)
    when = lambda: start + datetime.timedelta(minutes=30 * r.randrange(48 * 12))
    plan_rows = [(when() + datetime.timedelta(days=2), v) for v in range(60)] + [(None, 90), (start, None)]
    rows = [(i, when() + datetime.timedelta(days=r.choice((0, 0, 5)))) for i in range(300)] + [(300, None)]
    reports, schedule = spark.createDataFrame(rows, "id int, ts timestamp"), spark.createDataFrame(plan_rows, "valid_from timestamp, ver int")
    want = {i: max(((f, v) for f, v in plan_rows if t and f and v is not None and f <= t), default=(None, None))[1] for i, t in rows}
    for got in (joint.asof_params(reports, schedule), joint.asof_params(reports, schedule, most=10), joint.asof_params(reports, schedule, most_days=3)):
        assert {x.id: x.ver for x in got.collect()} == want
    assert [x.ver for x in joint.asof_params(reports, schedule.limit(0)).collect()] == [None] * 301


def test_versions_add_up(spark):
    from privsketch.operators import joint

    parts = spark.createDataFrame([("a", 10.0, 3.0), ("a", 5.0, 4.0), ("b", 1.0, 1.0)], "item string, est double, std_err double")
    assert {r["item"]: (r["est"], r["std_err"]) for r in joint.combine_versions(parts).collect()} == {"a": (15.0, 5.0), "b": (1.0, 1.0)}


def test_tuned_settings_win_near_their_targets(spark, medium):
    """Closed form: the mid setting is best for rare values; the top value prefers a large p."""
    rows = {r["item"]: r for r in QUERIES["census_like"](spark, medium).collect()}
    assert rows["b15"]["mid"] < rows["b15"]["top"] < rows["b15"]["classical"]
    assert rows["b00"]["top"] < rows["b00"]["mid"]


def test_discovery_grows_with_budget(spark, medium):
    found = [r["found"] for r in QUERIES["word_discovery"](spark, medium).orderBy("eps").collect()]
    assert found == sorted(found)
    want = [1533, 3089, 5592, 7893, 11389, 17320]
    assert all(abs(a - b) < 0.1 * b for a, b in zip(found, want, strict=True))


def test_subset_reports_beat_bit_vectors_at_equal_bits(spark, medium):
    rows = QUERIES["sweep_eps_equal_bits"](spark, medium).filter("f = 1000 and eps >= 2").collect()
    assert all(r["ours"] < r["classical"] for r in rows)


@pytest.fixture(scope="session")
def shuffled_events(spark, small, tmp_path_factory):
    """``events`` as a folder of two files, the later half of the time first."""
    top = tmp_path_factory.mktemp("shuffled")
    rows = spark.read.parquet(f"{small}/events.parquet")
    half = rows.selectExpr("percentile(cast(cast(ts as timestamp) as long), 0.5)").first()[0]
    late = F.col("ts").cast("timestamp").cast("long") >= half
    for part in (rows.filter(late), rows.filter(~late)):
        part.coalesce(1).write.mode("append").parquet(f"{top}/events.parquet")
    return str(top)


def test_appended_streams_go_to_files_and_lose_no_row_of_a_folder(spark, small, shuffled_events):
    got = QUERIES["stream_dedupe"](spark, shuffled_events)
    assert got.inputFiles()
    want = spark.read.parquet(f"{small}/events.parquet").select("event_id", "user_id")
    assert got.count() == want.count() and got.exceptAll(want).count() == 0


def test_sessions_do_not_depend_on_files_or_triggers(spark, small, shuffled_events, tmp_path):
    from privsketch.streaming import stream

    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM read_parquet('{small}/events.parquet')")
    got = sorted(map(tuple, QUERIES["stream_session_cap"](spark, shuffled_events).collect()))
    assert got == sorted(con.sql(SQL["stream_session_cap"]).fetchall())
    rows = spark.read.parquet(f"{small}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    cuts = ["2000-01-01", "2024-01-08", "2024-01-08 12:00:00", "2024-01-20", "2030-01-01"]
    order = [rows.filter((F.col("ts") >= F.lit(a).cast("timestamp")) & (F.col("ts") < F.lit(b).cast("timestamp"))) for a, b in zip(cuts, cuts[1:], strict=False)]
    each = stream.session_capped(stream.in_order(order, str(tmp_path / "in")), 3 * 86400, 2)
    whole = stream.session_capped(stream.events(spark, small), 3 * 86400, 2)
    assert each.columns == ["user_id", "event_id", "event_type"] and 0 < whole.count() < rows.count()
    assert each.exceptAll(whole).count() == 0 and whole.exceptAll(each).count() == 0


def test_bands_cost_one_digest_a_line(spark, small):
    """The null filter must not repeat the digests of the ladder."""
    assert plan(item_frame(spark, small, "band16").select("item")).count("md5") == 1


@pytest.mark.parametrize("key", ["subset", "classical"])
def test_reports_counted_where_they_are_drawn_are_the_same_reports(spark, small, key):
    from privsketch.operators import oracles

    items = item_frame(spark, small, "band16")
    sp = SketchParams(16, 32, 5, 0.6, secret="x")
    if key == "subset":
        apart, fused = randomize.subset_reports(items, sp, engine="arrow"), randomize.subset_worker(items, sp, [], sp.mode)
    else:
        apart = oracles.classical_reports(items, 16, 32, 3.0, engine="arrow", secret="x")
        fused = oracles.classical_worker(items, *oracles.classical_params(16, 32, 3.0, secret="x"))
    assert sorted(sketch.build(apart).collect()) == sorted(sketch.collect_dense(*fused, 16, 32).collect())


#: Closed forms whose totals and targets come from the events.
FROM_EVENTS = ["amplification", "best_variance_by_target", "best_variance_with_collisions", "budget_split", "capacity_plan", "comm_bits", "comm_sweep", "discovery_calibration", "eps_enumeration", "math_closed_forms", "opt_p_by_eps"]


@pytest.mark.parametrize("key", FROM_EVENTS)
def test_closed_forms_read_the_events(spark, small, key):
    got = QUERIES[key](spark, small)
    assert [f.rsplit("/", 1)[-1] for f in got.inputFiles()] == ["events.parquet"] and got.count()
