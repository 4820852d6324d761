"""From series to candidate vectors: z-scores, sliding windows, flat windows dropped, levels merged, repeated words dropped.

The window is never built as an array of w values: block means, extremes and leads over one sorted pass give the reduced
vector, so the large shuffle carries one thin row a step and all window functions share it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.functions.vectors import sax_word

KEY = ("sensor", "series_id")


def moments(series: DataFrame, scope: str = "run") -> DataFrame:
    keys = KEY if scope == "run" else ("sensor",)
    v = F.col("v").cast("decimal(38,0)")
    return series.groupBy(*keys).agg(F.count("*").alias("n"), F.sum("v").alias("s"), F.sum((v * v).cast("decimal(38,0)")).alias("q"))


def znormalize(series: DataFrame, scope: str = "run", frozen: DataFrame | None = None) -> DataFrame:
    """SERIES with z. Runs without deviation are dropped. frozen: moments (n, s, q) from elsewhere."""
    m = frozen if frozen is not None else moments(series, scope)
    keys = list(KEY if "series_id" in m.columns else ("sensor",))
    square = F.col("n").cast("decimal(38,0)") * F.col("q") - F.col("s").cast("decimal(38,0)") * F.col("s")
    m = m.withColumn("var", square.cast("double")).where("var > 0").select(*keys, "n", "s", "var")
    z = (F.col("n") * F.col("v") - F.col("s")).cast("double") / F.sqrt("var")
    return series.join(m, keys).select("sensor", "series_id", "t", "v", z.alias("z"))


def raw_values(series: DataFrame) -> DataFrame:
    """SERIES with z the value itself, for clustering without normalisation."""
    return series.select("sensor", "series_id", "t", "v", F.col("v").cast("double").alias("z"))


def sensor_radius(series: DataFrame, r: float = 1.0) -> DataFrame:
    """(sensor, r): the radius for raw values, r times the deviation of the sensor over all its runs."""
    square = F.col("n").cast("decimal(38,0)") * F.col("q") - F.col("s").cast("decimal(38,0)") * F.col("s")
    return moments(series, "sensor").select("sensor", (F.lit(r) * F.sqrt(square.cast("double")) / F.col("n")).alias("r"))


def for_measure(reduced: DataFrame, d: int, measure: str = "euclidean_centred") -> DataFrame:
    """REDUCED with vectors whose Euclidean distance is the measure: euclidean_centred as they are, euclidean with their level,
    euclidean_znorm with unit deviation (vectors without deviation stay at zero)."""
    x = F.col("x")
    if measure == "euclidean":
        return reduced.withColumn("x", F.array(*[x[j] + F.col("level") for j in range(d)]))
    if measure == "euclidean_znorm":
        spread = F.sqrt(sum((x[j] * x[j] for j in range(1, d)), x[0] * x[0]) / float(d))
        return reduced.withColumn("_spread", spread).withColumn("x", F.array(*[F.when(F.col("_spread") > 0, x[j] / F.col("_spread")).otherwise(0.0) for j in range(d)])).drop("_spread")
    if measure != "euclidean_centred":
        raise ValueError(f"unknown measure {measure}")
    return reduced


def expected_windows(series: DataFrame, w: int) -> DataFrame:
    per = series.groupBy(*KEY).agg(F.count("*").alias("n"))
    return per.groupBy("sensor").agg(F.sum(F.greatest(F.col("n") - w + 1, F.lit(0))).cast("long").alias("windows"))


def materialized_windows(z: DataFrame, w: int) -> DataFrame:
    """Windows as arrays; for short tests, w values a row."""
    frame = Window.partitionBy(*KEY).orderBy("t").rowsBetween(0, w - 1)
    return z.select(*KEY, "t", F.collect_list("z").over(frame).alias("win")).where(F.size("win") == w)


def frame_weights(w: int, d: int) -> list[list[tuple[int, float]]]:
    """For each of d frames the steps it covers and their weights; edge steps of fractional frames are shared."""
    out = []
    for j in range(d):
        lo, hi = j * w / d, (j + 1) * w / d
        out.append([(i, min(hi, i + 1) - max(lo, i)) for i in range(int(lo), min(w, int(hi - 1e-9) + 1))])
    return out


def reduced_windows(z: DataFrame, w: int = 20, d: int | None = None, f: float | None = 1.0, deviation: str = "range") -> DataFrame:
    """REDUCED: sensor, series_id, t, x (d values, zero mean), level, dev; flat windows are dropped if f is given."""
    d = d or max(1, w // 2)
    order = Window.partitionBy(*KEY).orderBy("t")
    frame = order.rowsBetween(0, w - 1)
    if w % d == 0:
        g = w // d
        block = sum((F.lead("z", i).over(order) for i in range(1, g)), F.col("z")) / float(g)
        rows = z.withColumn("block", block)
        parts = [F.lead("block", j * g).over(order) if j else F.col("block") for j in range(d)]
    else:
        rows = z
        lead = lambda i: F.lead("z", i).over(order) if i else F.col("z")
        parts = [sum((lead(i) * F.lit(c) for i, c in ps[1:]), lead(ps[0][0]) * F.lit(ps[0][1])) / F.lit(w / d) for ps in frame_weights(w, d)]
    rows = rows.select(*KEY, "t", *[p.alias(f"p{j}") for j, p in enumerate(parts)], F.max("z").over(frame).alias("hi"), F.min("z").over(frame).alias("lo"), F.count("*").over(frame).alias("have")).where(F.col("have") == w)
    level = sum((F.col(f"p{j}") for j in range(1, d)), F.col("p0")) / float(d)
    dev = F.col("hi") - F.col("lo") if deviation == "range" else F.greatest(F.col("hi") - level, level - F.col("lo"))
    if f is not None:
        rows = rows.where(dev >= f)
    return rows.select(*KEY, "t", level.alias("level"), dev.alias("dev"), *[F.col(f"p{j}") for j in range(d)]).select(*KEY, "t", F.array(*[F.col(f"p{j}") - F.col("level") for j in range(d)]).alias("x"), "level", "dev")


def drop_repeated_words(reduced: DataFrame, d: int, alphabet: int = 4, adjacency: str = "surviving") -> DataFrame:
    """CANDIDATE: rows whose word differs from the one before (the surviving one, or that of step t - 1)."""
    order = Window.partitionBy(*KEY).orderBy("t")
    rows = reduced.withColumn("word", sax_word(F.col("x"), d, alphabet)).withColumn("before", F.lag("word").over(order))
    same: Column = F.col("word").eqNullSafe(F.col("before"))
    if adjacency == "step":
        rows = rows.withColumn("gap", F.col("t") - F.lag("t").over(order))
        same = same & (F.col("gap") == 1)
    return rows.where(~F.coalesce(same, F.lit(False))).drop("before", "gap")


def candidates(series: DataFrame, w: int = 20, d: int | None = None, f: float = 1.0, alphabet: int = 4, skip: tuple[str, ...] = ()) -> DataFrame:
    """From series to candidates. skip names steps to leave out: flat, words."""
    d = d or max(1, w // 2)
    reduced = reduced_windows(znormalize(series), w, d, None if "flat" in skip else f)
    return reduced.withColumn("word", F.lit("")) if "words" in skip else drop_repeated_words(reduced, d, alphabet)
