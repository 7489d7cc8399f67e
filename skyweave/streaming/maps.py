"""Streaming accumulators: a map's sums are additive, so closed micro-batches add to them.

Each batch's partial sums are written under its batch id (a rerun overwrites its own), and the map is the sum over batches: exactly once
with any restart. Event-time windows close with the watermark."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skyweave.plans.lineage import shared_dir
from skyweave.sources.tables import load


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a stream of files."""
    schema = load(spark, sf_dir, "events").schema
    files = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return files.withColumn("ts", F.col("ts").cast("timestamp"))


def accumulate(stream: DataFrame, folder: str) -> None:
    """Run a stream of (pix, d) to its present end, adding (pix, hits, s) sums per batch to ``folder``/sums."""
    def add(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("pix").agg(F.count("*").alias("hits"), F.sum("d").alias("s")).write.mode("overwrite").parquet(f"{folder}/sums/batch={batch_id}")

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()


def _sums(spark, sf_dir) -> DataFrame:
    folder = _folder(spark, "stream")
    accumulate(events(spark, sf_dir).select(F.col("user_id").alias("pix"), F.col("value").alias("d")), folder)
    return spark.read.schema("pix long, hits long, s double, batch long").parquet(f"{folder}/sums").groupBy("pix").agg(F.sum("hits").alias("hits"), F.sum("s").alias("s"))


def hit_map(spark, sf_dir) -> DataFrame:
    return _sums(spark, sf_dir).select("pix", "hits")


def coadd(spark, sf_dir) -> DataFrame:
    return _sums(spark, sf_dir).select("pix", "hits", (F.round(F.col("s") / F.col("hits"), 4) + F.lit(0.0)).alias("i"))


def daily(spark, sf_dir) -> DataFrame:
    """Samples per day from a watermarked tumbling window; every batch's updates are kept and the last per window counts."""
    folder = _folder(spark, "daily")
    w = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).count()

    def add(batch: DataFrame, batch_id: int) -> None:
        batch.select(F.col("window.start").alias("start"), F.col("count").alias("n"), F.lit(batch_id).alias("at")).write.mode("overwrite").parquet(f"{folder}/rows/batch={batch_id}")

    w.writeStream.outputMode("update").foreachBatch(add).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(f"{folder}/rows").groupBy("start").agg(F.max_by("n", "at").alias("n"))
    return rows.select(F.datediff(F.to_date("start"), F.lit("2024-01-01").cast("date")).cast("long").alias("day"), "n")


def _appended(out: DataFrame, folder: str, schema: str) -> DataFrame:
    """Run an append-mode stream to its present end, each batch's rows under its id, and read them back."""
    def add(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={batch_id}")

    out.writeStream.outputMode("append").foreachBatch(add).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return out.sparkSession.read.schema(schema + ", batch int").parquet(f"{folder}/rows").drop("batch")


def session_pieces(stream: DataFrame, gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """Pieces of a key's samples without a gap, closed by the watermark: (pix, start, stop, n); state is the open pieces alone."""
    w = stream.withWatermark("ts", late).groupBy("pix", F.session_window("ts", gap)).agg(F.count("*").alias("n"))
    return w.select("pix", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "n")


def attach_near(samples: DataFrame, pointing: DataFrame, delta: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream join of samples (pix, ts, sample_id) with pointing records (p_pix, p_ts, pointing_id) of the same key within
    ``delta`` either way; both watermarks and the time range bound the state."""
    a, b = samples.withWatermark("ts", late), pointing.withWatermark("p_ts", late)
    return a.join(b, (F.col("pix") == F.col("p_pix")) & F.expr(f"p_ts BETWEEN ts - INTERVAL {delta} AND ts + INTERVAL {delta}"))


def closed_intervals(stream: DataFrame, length: str = "1 day", late: str = "1 hour", parts: int = 8) -> DataFrame:
    """Sums of every noise interval of ``length``, sent once when the watermark has passed its end: (start, part, n, s, first, last) of samples (pix, ts, d).

    The sums add up, so an interval is dealt to ``parts`` states by pixel, of some numbers each however long it is; add them by start. An interval still
    open at the end is not sent, and samples behind the watermark are dropped (``late_samples`` counts them)."""
    w = stream.withWatermark("ts", late).select(F.window("ts", length).alias("w"), "ts", "d", F.pmod(F.hash("pix"), F.lit(parts)).alias("part"))
    keyed = w.select(F.col("w.start").cast("double").alias("start"), F.col("w.end").cast("double").alias("stop"), "part", "ts", "d")

    def step(key, batches, state):
        start, stop, part = key
        n, total, first, last = state.get if state.exists else (0, 0.0, float("inf"), float("-inf"))
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"start": [float(start)], "part": [int(part)], "n": [n], "s": [total], "first": [first], "last": [last]})
            return
        for b in batches:
            at = b["ts"].astype("int64") / (1e9 if str(b["ts"].dtype).startswith("datetime64[ns") else 1e6)
            n, total, first, last = n + len(b), total + float(b["d"].sum()), min(first, float(at.min())), max(last, float(at.max()))
        state.update((int(n), total, first, last))
        state.setTimeoutTimestamp(max(int(float(stop) * 1000), state.getCurrentWatermarkMs() + 1))

    return keyed.groupBy("start", "stop", "part").applyInPandasWithState(step, "start double, part int, n long, s double, first double, last double", "n long, s double, first double, last double", "append", "EventTimeTimeout")


def late_samples(stream: DataFrame, folder: str, late_s: float = 3600.0) -> DataFrame:
    """(batch, n, late, top) of every micro-batch of a stream with ``ts``: its samples, those behind the watermark (the greatest time of the batches before, less
    ``late_s`` seconds) and the greatest time so far. A batch's row is written under its id and made from the rows of earlier ids alone, so a rerun gives the same."""
    rows = "n long, late long, top double"

    def add(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        before = None
        if batch_id:
            before = spark.read.schema(rows).parquet(f"{folder}/late/batch={batch_id - 1}").agg(F.max("top")).first()[0]
        at = F.col("ts").cast("timestamp").cast("double")
        behind = F.lit(False) if before is None else at < before - late_s
        sums = batch.agg(F.count("*").alias("n"), F.count_if(behind).alias("late"), F.greatest(F.max(at), F.lit(before).cast("double")).alias("top"))
        sums.write.mode("overwrite").parquet(f"{folder}/late/batch={batch_id}")

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{folder}/late-state").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(rows + ", batch long").parquet(f"{folder}/late")


def unique_samples(stream: DataFrame, key: str = "sample_id", late: str = "1 hour") -> DataFrame:
    """One row per sample id; an id is remembered until the watermark has passed its time, so copies that are no later than ``late`` are found."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def interval_close(spark, sf_dir) -> DataFrame:
    out = closed_intervals(events(spark, sf_dir).select(F.col("user_id").alias("pix"), "ts", F.col("value").alias("d")))
    sums = _appended(out, _folder(spark, "closed"), "start double, part int, n long, s double, first double, last double")
    return sums.groupBy("start").agg(F.sum("n").alias("n"), (F.round(F.sum("s"), 4) + F.lit(0.0)).alias("s")).select(F.floor((F.col("start") - F.lit(1704067200)) / 86400).alias("day"), "n", "s")


def unique_hits(spark, sf_dir) -> DataFrame:
    """Hits of a stream in which every sample comes twice, each counted once."""
    both = events(spark, sf_dir).select(F.col("event_id").alias("sample_id"), F.col("user_id").alias("pix"), "ts")
    out = unique_samples(both.withColumn("_copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("_copy"))
    return _appended(out, _folder(spark, "unique"), "sample_id long, pix long, ts timestamp").groupBy("pix").agg(F.count("*").alias("hits"))


def sessions(spark, sf_dir) -> DataFrame:
    out = session_pieces(events(spark, sf_dir).select(F.col("user_id").alias("pix"), "ts"))
    return _appended(out, _folder(spark, "sessions"), "pix long, start timestamp, stop timestamp, n long").select("pix", F.unix_micros("start").alias("start_us"), "n")


def near_pairs(spark, sf_dir) -> DataFrame:
    e = events(spark, sf_dir)
    s = e.where("event_type = 'view'").select(F.col("user_id").alias("pix"), "ts", F.col("event_id").alias("sample_id"))
    p = events(spark, sf_dir).where("event_type = 'click'").select(F.col("user_id").alias("p_pix"), F.col("ts").alias("p_ts"), F.col("event_id").alias("pointing_id"))
    return _appended(attach_near(s, p).select("sample_id", "pointing_id"), _folder(spark, "near"), "sample_id long, pointing_id long")
