"""Structured Streaming forms: event-time statistics, deduplication, and stateful windows with frozen moments.

Queries run the stream with availableNow into shared Parquet with a checkpoint of their own and return what was written, so that batch
and stream can be compared row by row.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavemotif.functions.vectors import BREAKPOINTS, sax_word
from wavemotif.operators import prep as P
from wavemotif.operators.cluster import shared_folder
from wavemotif.sources import views as V


def folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"


def source(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """The table's files as a stream."""
    path = f"{sf_dir}/{name}.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", 8)
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    if at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isFile():  # a stream reads folders
        return reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return reader.parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """What the stream has written once all that is there has been read."""
    spark, to = stream.sparkSession, folder(stream.sparkSession)
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{to}/out").option("checkpointLocation", f"{to}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{to}/out")

    def write(batch: DataFrame, number: int) -> None:  # the last batch holds the whole result; a repeated batch overwrites itself
        batch.write.mode("overwrite").parquet(f"{to}/out/batch={number}")

    stream.writeStream.outputMode("complete").option("checkpointLocation", f"{to}/state").foreachBatch(write).trigger(availableNow=True).start().awaitTermination()
    out = spark.read.parquet(f"{to}/out")
    return out.where(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")


def tumbling(spark: SparkSession, sf_dir: str, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Counts by event time; windows overlap if slide is shorter than length."""
    rows = source(spark, sf_dir).groupBy("event_type", F.window("ts", length, slide).alias("w")).agg(F.count("*").alias("n"))
    return drain(rows.select("event_type", F.col("w.start").alias("start"), "n"), "complete")


def dedup(spark: SparkSession, sf_dir: str, delay: str = "60 days") -> DataFrame:
    return drain(source(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def stream_windows(series: DataFrame, moments: DataFrame, w: int = 20, d: int = 10, alphabet: int = 4) -> DataFrame:
    """series_id, t, word of each window as it completes. series(series_id, t, v) in order of t within a batch; moments are frozen; the
    state of a run is its last w - 1 values."""
    z = series.join(F.broadcast(moments.select("series_id", "n", "s", "var")), "series_id").select("series_id", "t", ((F.col("n") * F.col("v") - F.col("s")).cast("double") / F.sqrt("var")).alias("z"))
    cuts = np.array(BREAKPOINTS[alphabet])

    def fn(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values("t")
        old_t, old_z = state.get if state.exists else ([], [])
        t, v = np.array([*old_t, *rows.t]), np.array([*old_z, *rows.z])
        state.update((t[1 - w :].tolist(), v[1 - w :].tolist()))
        if len(v) >= w:
            x = np.lib.stride_tricks.sliding_window_view(v, w).reshape(-1, d, w // d).sum(axis=2) / (w // d)
            x = x - (x.cumsum(axis=1)[:, -1] / d)[:, None]
            words = ["".join("abcdef"[i] for i in row) for row in np.searchsorted(cuts, x, side="right")]
            yield pd.DataFrame({"series_id": key[0], "t": t[: len(words)], "word": words})

    return z.groupBy("series_id").applyInPandasWithState(fn, "series_id long, t long, word string", "t array<long>, z array<double>", "append", "NoTimeout")


def windows_equal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of the run view by the stateful stream, from steps that were numbered and written before."""
    return drain(stream_windows(*_numbered(spark, sf_dir)))


def _numbered(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The run view as a stream of steps that were numbered and written before, and its frozen moments."""
    to, run = folder(spark), V.run_view(spark, sf_dir)
    steps = run.select("series_id", "t", "v")
    steps.write.parquet(f"{to}/in")
    m = P.moments(run).withColumn("var", (F.col("n").cast("decimal(38,0)") * F.col("q") - F.col("s").cast("decimal(38,0)") * F.col("s")).cast("double")).where("var > 0")
    return spark.readStream.schema(steps.schema).parquet(f"{to}/in"), m


def match(spark: SparkSession, sf_dir: str, least: int = 100, w: int = 20, d: int = 4) -> DataFrame:
    """Windows of the stream whose word is one of the batch's frequent words: a stream against a static table of motifs. Words are of
    d letters, so the table has at most 4**d rows and is broadcast."""
    windows = P.reduced_windows(P.znormalize(V.run_view(spark, sf_dir)), w, d, None)
    motifs = windows.groupBy(sax_word(F.col("x"), d).alias("word")).agg(F.count("*").alias("support")).where(F.col("support") > least)
    stream, m = _numbered(spark, sf_dir)
    return drain(stream_windows(stream, m, w, d).join(F.broadcast(motifs), "word").select("series_id", "t", "word", "support"))


def sessions(spark: SparkSession, sf_dir: str, gap: str = "6 hours") -> DataFrame:
    """Counts of a user's stretches of events without a gap as long as the given one."""
    rows = source(spark, sf_dir).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return drain(rows.select("user_id", F.col("w.start").alias("start"), "n"), "complete")


def rules(spark: SparkSession, sf_dir: str, horizon: str = "2 hours", delay: str = "60 days") -> DataFrame:
    """(event_id, other): an error after another event of the same user within the horizon; two streams joined between watermarks, so
    state older than delay and horizon is dropped."""
    events = source(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
    a = events.where("event_type <> 'error'").select("event_id", F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", delay)
    b = events.where("event_type = 'error'").select(F.col("event_id").alias("other"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", delay)
    return drain(a.join(b, F.expr(f"ua = ub and tb > ta and tb <= ta + interval {horizon}")).select("event_id", "other"))


def centres(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(word, n, v): running counts and sums by word of the stream, kept per micro-batch: a batch that is repeated after a failure
    overwrites its own part, and parts add up as clustering features do."""
    stream, m = _numbered(spark, sf_dir)
    to = folder(spark)

    def write(batch: DataFrame, number: int) -> None:
        batch.groupBy("word").agg(F.count("*").alias("n"), F.sum("t").alias("v")).write.mode("overwrite").parquet(f"{to}/out/batch={number}")

    stream_windows(stream, m, 20, 4).writeStream.foreachBatch(write).option("checkpointLocation", f"{to}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{to}/out").groupBy("word").agg(F.sum("n").alias("n"), F.sum("v").alias("v"))


def resumed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """series_id, steps, total of the run view by a stateful stream that is stopped after half of the input and started again from its checkpoint."""
    to, steps = folder(spark), V.run_view(spark, sf_dir).select("series_id", "t", "v")
    half = F.pmod(F.xxhash64("series_id", "t"), F.lit(2))

    def write(batch: DataFrame, number: int) -> None:  # the last batch holds the whole result
        batch.write.mode("overwrite").parquet(f"{to}/out/batch={number}")

    for part in (0, 1):
        steps.where(half == part).write.mode("append").parquet(f"{to}/in")
        sums = spark.readStream.schema(steps.schema).parquet(f"{to}/in").groupBy("series_id").agg(F.count("*").alias("steps"), F.sum("v").alias("total"))
        sums.writeStream.outputMode("complete").option("checkpointLocation", f"{to}/state").foreachBatch(write).trigger(availableNow=True).start().awaitTermination()
    out = spark.read.parquet(f"{to}/out")
    return out.where(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")

