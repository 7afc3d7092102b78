"""Collection over unbounded input. Every builder takes a streaming (or static) frame with ``ts`` as a timestamp; ``run_available``
runs a builder over everything that is there and returns the result as a static frame."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.theory import SketchParams
from ..sources.tables import scratch
from ..sources.workers import ship
from ..operators import discover, estimate, randomize, sketch


def events(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None) -> DataFrame:
    """``events`` as a file stream with proper timestamps. The files of a folder stand in no order of time, so a trigger takes all that
    are there unless told otherwise."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    raw = spark.readStream.schema(schema)
    if files_per_trigger:
        raw = raw.option("maxFilesPerTrigger", files_per_trigger)
    # a Parquet path that is one file is read through its folder
    source = raw.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if not _is_folder(spark, path) else raw.parquet(path)
    return source.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()


def run_available(df: DataFrame, mode: str = "complete", on_batch: Callable | None = None) -> DataFrame:
    """Process what is available, then stop, and return the result. Appended rows grow with the input: they go to files of the shared
    folder and no driver holds them. A complete result is an aggregate, kept by the memory sink."""
    spark, name = df.sparkSession, f"stream_{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True)
    folder = scratch(spark, "stream")
    if on_batch:
        query = writer.foreachBatch(on_batch).start()
    elif mode == "append":
        query = writer.format("parquet").option("checkpointLocation", f"{folder}/checkpoint").start(f"{folder}/rows")
    else:
        query = writer.format("memory").queryName(name).start()
    try:
        query.awaitTermination()
    finally:
        query.stop()
    if on_batch:
        return spark.range(0)
    return spark.read.schema(df.schema).parquet(f"{folder}/rows") if mode == "append" else spark.table(name)


def reports(df: DataFrame, sp: SketchParams, item: str = "event_type", report: str = "event_id", client: str = "user_id") -> DataFrame:
    own = df.withColumns({"report_id": F.col(report), "client_id": F.col(client), "item": F.col(item).cast("string")})
    return randomize.subset_reports(own, sp, keep=["ts"])


def tumbling_sketch(df: DataFrame, sp: SketchParams, length: str = "1 day", late: str = "1 day") -> DataFrame:
    """Matrix of every window; state is at most k x m cells an open window."""
    cells = reports(df, sp).withWatermark("ts", late).select(F.window("ts", length).alias("w"), "j", F.explode("x").alias("x"))
    return cells.groupBy("w", "j", "x").agg(F.count("*").alias("cnt")).select(F.to_date("w.start").alias("epoch"), "j", "x", "cnt")


def sliding_sketch(df: DataFrame, sp: SketchParams, length: str = "7 days", step: str = "1 day", late: str = "1 day") -> DataFrame:
    """Matrix of every sliding window; a report's cells count in each window over it, raw items in none."""
    inside = reports(df, sp).withWatermark("ts", late).select(F.window("ts", length, step).alias("w"), "j", "x")
    cells = inside.select("w", "j", F.explode("x").alias("x")).groupBy("w", "j", "x").agg(F.count("*").alias("cnt"))
    return cells.select(F.to_date("w.start").alias("epoch"), "j", "x", "cnt")


def session_cap_on_batch(folder: str, gap_seconds: int = 12 * 3600, limit: int = 5) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink that keeps the first ``limit`` events of each client session (``user_id, event_id, event_type``), in order of
    time and id: what clients may report. ``session_capped`` reads them. The state is a time and a number a client, one table a batch; a
    batch that is tried again writes the same tables again."""

    def sink(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        at = f"{folder}/state/{{}}".format
        before = spark.read.schema(_SESSION_STATE).parquet(at(number - 1)) if number else spark.createDataFrame([], _SESSION_STATE)
        own = batch.select(F.col("user_id").cast("long"), F.col("event_id").cast("long"), F.col("event_type").cast("string"), "ts")
        own = own.join(before.withColumnRenamed("user_id", "_user"), F.col("user_id").eqNullSafe(F.col("_user")), "left").drop("_user")
        w = Window.partitionBy("user_id").orderBy(F.asc_nulls_last("ts"), F.asc_nulls_last("event_id"))
        own = own.withColumn("rn", F.row_number().over(w))
        earlier = F.when(F.col("rn") == 1, F.col("last")).otherwise(F.lag("ts").over(w))
        own = own.withColumn("opens", F.coalesce(F.col("ts") >= earlier + F.expr(f"interval {int(gap_seconds)} seconds"), F.lit(True)))
        # the rank where the row's session began; none: it goes on from an earlier batch, which used some of its places
        first = F.last(F.when(F.col("opens"), F.col("rn")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
        place = F.coalesce(F.col("rn") - first + 1, F.col("rn") + F.col("used"))
        marked = own.select("user_id", "event_id", "event_type", "ts", "rn", place.cast("long").alias("place")).persist(StorageLevel.DISK_ONLY)
        marked.filter(F.col("place") <= limit).select("user_id", "event_id", "event_type").write.mode("overwrite").parquet(f"{folder}/rows/batch={number}")
        after = marked.groupBy("user_id").agg(F.max_by("ts", "rn").alias("last"), F.max_by("place", "rn").alias("used"))
        seen = after.select(F.col("user_id").alias("_user"))
        rest = before.join(seen, F.col("user_id").eqNullSafe(F.col("_user")), "left_anti")
        after.unionByName(rest).write.mode("overwrite").parquet(at(number))
        marked.unpersist()

    return sink


_SESSION_STATE = "user_id long, last timestamp, used long"


def session_capped(df: DataFrame, gap_seconds: int = 12 * 3600, limit: int = 5) -> DataFrame:
    """Everything available through ``session_cap_on_batch``: ``user_id, event_id, event_type``."""
    folder = scratch(df.sparkSession, "sessions")
    run_available(df, "append", session_cap_on_batch(folder, gap_seconds, limit))
    return df.sparkSession.read.schema("user_id long, event_id long, event_type string, batch int").parquet(f"{folder}/rows").drop("batch")


def capped(df: DataFrame, limit: int) -> DataFrame:
    """At most ``limit`` reports a client over the whole stream: ``user_id, event_id``; the state is one number a client."""

    ship(df.sparkSession)

    def work(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        used = state.get[0] if state.exists else 0
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        keep = rows.head(max(0, limit - used))
        state.update((used + len(keep),))
        yield pd.DataFrame({"user_id": keep["user_id"].to_numpy(), "event_id": keep["event_id"].to_numpy()})

    return df.select("user_id", "event_id", "ts").groupBy("user_id").applyInPandasWithState(work, "user_id long, event_id long", "used long", "append", "NoTimeout")


def dedupe(df: DataFrame, late: str = "1 day") -> DataFrame:
    """Re-sent reports count once while the watermark remembers them."""
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def closed_counts(df: DataFrame, length: str = "1 day", late: str = "1 day") -> DataFrame:
    """Counts of windows that the watermark has closed (append mode); rows that come later than ``late`` are dropped."""
    w = df.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w")).agg(F.count("*").alias("cnt"))
    return w.select(F.to_date("w.start").alias("epoch"), "cnt")


def in_order(frames: list[DataFrame], folder: str) -> DataFrame:
    """A stream whose micro-batches are ``frames``, in order: each is written as one file of ``folder``, read one a trigger."""
    for f in frames:
        f.coalesce(1).write.mode("append").parquet(folder)
    spark = frames[0].sparkSession
    return spark.readStream.schema(frames[0].schema).option("maxFilesPerTrigger", 1).parquet(folder)


def with_domain(df: DataFrame, domain: DataFrame) -> DataFrame:
    """Stream-static join: only items of a known domain, with its attributes."""
    return df.join(domain, df.event_type == domain.item).groupBy("item", "weight").agg(F.count("*").alias("cnt"))


def discovery_counts(df: DataFrame, column: str, secrets: tuple[str, str] = ("server", "helper"), length: str = "10 days", late: str = "1 day", seed: int | str = 42) -> DataFrame:
    """``epoch, digest, inner, cnt`` of each window, as the helper has them: clients seal their items before anything is counted, and the
    helper keeps a uniform pick of a digest's ciphertexts. Noise is added once, after a window has closed (``release``)."""
    sealed = discover.client(df.withColumn("item", F.col(column).cast("string")), *secrets, keep=("ts",))
    opened = discover.open_outer(sealed, secrets[1], keep=("ts",)).withWatermark("ts", late)
    pick = F.xxhash64("inner", F.lit(str(seed)))
    w = opened.groupBy(F.window("ts", length).alias("w"), "digest").agg(F.count("*").alias("cnt"), F.min_by("inner", pick).alias("inner"))
    return w.select(F.to_date("w.start").alias("epoch"), "digest", "inner", "cnt")


def release(closed: DataFrame, threshold: float, scale: float, seed: int | str) -> DataFrame:
    """Noisy release of closed windows, keyed by window and digest: ``epoch, digest, inner, noisy``."""
    keyed = closed.withColumn("_d", F.col("digest")).withColumn("digest", F.concat(F.col("epoch").cast("string").cast("binary"), F.col("_d")))
    out = discover.noisy(keyed, scale, seed).filter(F.col("noisy") >= threshold)
    return out.select("epoch", F.col("_d").alias("digest"), "inner", "noisy")


def retune_on_batch(sp: SketchParams, target: str, eps: float, schedule: list) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink that closes the loop: each batch is collected with the newest version's p and s, and its estimate of the target
    gives the next. ``schedule`` gets ``(ver, p, s, n, est, lam, next_p, next_s, next_eps)`` a batch."""
    from ..functions import tune

    def sink(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        now = replace(sp, p=schedule[-1][6], s=schedule[-1][7]) if schedule else sp
        name = batch.sparkSession.createDataFrame([(target,)], "item string")
        row = estimate.frequencies(name, sketch.build(reports(batch, now)), now).first()
        lam = min(1.0, max(0.001, row["est"] / max(1, row["n"])))
        t = tune.tune(eps, lam, sp.k, sp.m)
        schedule.append((number, now.p, now.s, row["n"], row["est"], lam, t.p, t.s, t.eps_real))

    return sink
