"""Use of motifs: matching, display, histories around faults, features, rules, known events, rare windows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.operators.cluster import GRID_BROADCAST, SLACK, grid_near, stored


def match(reduced: DataFrame, motifs: DataFrame, r: float, d: int, limit: int = GRID_BROADCAST) -> DataFrame:
    """Windows nearer than r to a motif, with the nearest one: sensor, series_id, t, motif_id, dist.

    Up to limit motifs go to the executors, where a window meets all of its sensor at once and nothing is shuffled; more meet by grid cells."""
    number = F.row_number().over(Window.partitionBy("sensor").orderBy("motif_id")).cast("long") - 1
    motifs = motifs.select("sensor", "motif_id", F.col("centroid").alias("y"), number.alias("k")).transform(stored)
    rows = reduced.select("sensor", "series_id", "t", "x")
    if motifs.count() > limit:
        near = grid_near(rows, motifs.select("sensor", "motif_id", "y"), r, d).where(F.col("d2") < r * r)
        best = near.groupBy("sensor", "series_id", "t").agg(F.min(F.struct("d2", "motif_id")).alias("m"))
        return best.select("sensor", "series_id", "t", "m.motif_id", F.sqrt("m.d2").alias("dist"))
    centres: dict[str, list] = {}
    for m in motifs.select("sensor", "k", "y").orderBy("sensor", "k").toArrow().to_pylist():  # at most limit rows
        centres.setdefault(m["sensor"], []).append(m["y"])
    shared = reduced.sparkSession.sparkContext.broadcast({sensor: np.array(c, float) for sensor, c in centres.items()})

    def fn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sensors = batch.column("sensor").to_numpy(zero_copy_only=False)
            x = np.asarray(batch.column("x").flatten()).reshape(len(batch), -1)
            for sensor in set(sensors.tolist()) & shared.value.keys():
                own = np.flatnonzero(sensors == sensor)
                i, k, d2 = nearest_within(x[own], shared.value[sensor], r)
                part = batch.select(["sensor", "series_id", "t"]).take(pa.array(own[i]))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(k), pa.array(d2)], ["sensor", "series_id", "t", "k", "d2"])

    best = rows.mapInArrow(fn, "sensor string, series_id long, t long, k long, d2 double")
    names = F.broadcast(motifs.select("sensor", "k", "motif_id"))  # at most limit rows
    return best.join(names, ["sensor", "k"]).select("sensor", "series_id", "t", "motif_id", F.sqrt("d2").alias("dist"))


def nearest_within(x: np.ndarray, c: np.ndarray, r: float, cells: int = 1 << 20) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of x, first nearest row of c, squared distance) of rows of x nearer than r to a row of c. A product tells all distances up to
    rounding; those that may be least are computed as sq_dist does."""
    h, step, out = (c * c).sum(axis=1), max(1, cells // max(1, len(c))), []
    for a in range(0, len(x), step):
        part = x[a : a + step]
        own = (part * part).sum(axis=1)
        rough = h - 2.0 * (part @ c.T)
        slack = SLACK * (float(h.max()) + own + r * r)
        least = rough.min(axis=1)
        near = np.flatnonzero(least + own < r * r + slack)
        i, k = np.nonzero(rough[near] <= (least + slack)[near, None])
        i = near[i]
        d2 = np.zeros(len(i))
        for j in range(x.shape[1]):
            d2 += (part[i, j] - c[k, j]) * (part[i, j] - c[k, j])
        order = np.lexsort((k, d2, i))
        order = order[np.concatenate([[True], i[order][1:] != i[order][:-1]])] if len(order) else order
        order = order[d2[order] < r * r]
        out.append((i[order] + a, k[order], d2[order]))
    if not out:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    return tuple(np.concatenate(p) for p in zip(*out, strict=True))


def expand(occurrences: DataFrame, series: DataFrame, w: int) -> DataFrame:
    """The original values of occurrences: sensor, motif_id, series_id, t, step, v."""
    steps = occurrences.select("sensor", "motif_id", "series_id", "t", F.posexplode(F.sequence(F.col("t"), F.col("t") + w - 1)).alias("step", "at"))
    return steps.join(series.select("sensor", "series_id", F.col("t").alias("at"), "v"), ["sensor", "series_id", "at"]).select("sensor", "motif_id", "series_id", "t", F.col("step").cast("long").alias("step"), "v")


def fault_histories(series: DataFrame, faults: DataFrame, length: int, gap: int, clear: int) -> DataFrame:
    """series_id, start, positive: spans of length steps that end gap before a fault; and, every length steps, spans of the same length with no
    fault from clear before their start to clear after their end."""
    pos = faults.select("series_id", (F.col("t") - gap - length).alias("start")).where("start >= 0").distinct().withColumn("positive", F.lit(1))
    spans = series.groupBy("series_id").agg(F.max("t").alias("last")).where(F.col("last") >= length).select("series_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("last") - length + 1, F.lit(length).cast("long"))).alias("start"))
    f = faults.select(F.col("series_id").alias("s"), F.col("t").alias("ft"))
    neg = spans.join(f, (F.col("series_id") == F.col("s")) & F.col("ft").between(F.col("start") - clear, F.col("start") + length - 1 + clear), "left_anti").withColumn("positive", F.lit(0))
    return pos.unionByName(neg)


def motif_features(histories: DataFrame, occurrences: DataFrame, motif_ids: list[int], length: int) -> DataFrame:
    """histories with a count for each motif."""
    o = occurrences.select(F.col("series_id").alias("s"), "t", "motif_id")
    inside = histories.join(o, (F.col("series_id") == F.col("s")) & F.col("t").between(F.col("start"), F.col("start") + length - 1), "left")
    return inside.groupBy("series_id", "start", "positive").pivot("motif_id", motif_ids).agg(F.count("t")).fillna(0)


def level_features(histories: DataFrame, series: DataFrame, length: int, levels: int = 4) -> DataFrame:
    """histories with, over their span: the mean value in levels equal parts of the range of all values (0 .. levels - 1), the share of rising
    steps in percent, and the change from the first value to the last. Spans without values have none."""
    order = Window.partitionBy("series_id").orderBy("t")
    rows = series.select(F.col("series_id").alias("s"), "t", "v", (F.col("v") - F.lag("v").over(order)).alias("rise"))
    bounds = series.agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    inside = histories.join(rows, (F.col("series_id") == F.col("s")) & F.col("t").between(F.col("start"), F.col("start") + length - 1), "left")
    per = inside.groupBy("series_id", "start", "positive").agg(F.sum("v").alias("sum"), F.count("v").alias("n"), F.count_if(F.col("rise") > 0).alias("up"), F.min(F.struct("t", "v")).alias("a"), F.max(F.struct("t", "v")).alias("b"))
    level = F.least(F.lit(levels - 1), F.floor((F.col("sum") - F.col("n") * F.col("lo")) * levels / (F.col("n") * (F.col("hi") - F.col("lo"))))).cast("int")
    return per.crossJoin(F.broadcast(bounds)).select("series_id", "start", "positive", level.alias("level"), F.floor(100 * F.col("up") / F.col("n")).cast("int").alias("rising"), (F.col("b.v") - F.col("a.v")).alias("change"))  # one row of bounds


def temporal_rules(a: DataFrame, b: DataFrame, horizon: int) -> DataFrame:
    """motif_a, event_b, support, followed, confidence: how often b starts within horizon steps after a in the same run."""
    left = a.select("series_id", F.col("t").alias("ta"), F.col("motif_id").alias("motif_a"))
    right = b.select(F.col("series_id").alias("s"), F.col("t").alias("tb"), F.col("motif_id").alias("event_b"))
    total = left.groupBy("motif_a").agg(F.count("*").alias("support"))
    hits = left.join(right, (F.col("series_id") == F.col("s")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + horizon), "left_outer").where("tb is not null").select("motif_a", "event_b", "series_id", "ta").distinct()
    return hits.groupBy("motif_a", "event_b").agg(F.count("*").alias("followed")).join(total, "motif_a").select("motif_a", "event_b", "support", "followed", (F.col("followed") / F.col("support")).alias("confidence"))


def rule_lift(a: DataFrame, b: DataFrame, horizon: int) -> DataFrame:
    """motif_id, support, followed, lift: the share of a motif's places that an event of b follows within horizon steps, over the same
    share of all places. Without any followed place there is no lift."""
    left = a.select("series_id", F.col("t").alias("ta"), "motif_id")
    right = b.select(F.col("series_id").alias("s"), F.col("t").alias("tb"))
    hit = left.join(right, (F.col("series_id") == F.col("s")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + horizon), "left").groupBy("motif_id", "series_id", "ta").agg((F.count("tb") > 0).alias("hit"))
    per = hit.groupBy("motif_id").agg(F.count("*").alias("support"), F.count_if("hit").alias("followed"))
    whole = per.agg((F.sum("followed") / F.sum("support")).alias("base"))
    return per.crossJoin(F.broadcast(whole)).select("motif_id", "support", "followed", F.try_divide(F.col("followed") / F.col("support"), F.col("base")).alias("lift"))  # one row


def known_events(series: DataFrame, least_change: int, max_gap: int = 1) -> DataFrame:
    """sensor, series_id, start, stop, hits: steps whose value changes by least_change or more, those in a row merged."""
    order = Window.partitionBy("sensor", "series_id").orderBy("t")
    hits = series.withColumn("change", F.abs(F.col("v") - F.lag("v").over(order))).where(F.col("change") >= least_change)
    hits = hits.withColumn("new", F.when(F.col("t") - F.lag("t").over(order) <= max_gap, 0).otherwise(1)).withColumn("island", F.sum("new").over(order))
    return hits.groupBy("sensor", "series_id", "island").agg(F.min("t").alias("start"), F.max("t").alias("stop"), F.count("*").alias("hits")).drop("island")


def rare_windows(assigned: DataFrame, motifs: DataFrame, max_support: int, min_dist: float, d: int) -> DataFrame:
    """Members of clusters of at most max_support members that lie farther than min_dist from every motif."""
    rare = assigned.groupBy("sensor", "cluster_id").agg(F.count("*").alias("n")).where(F.col("n") <= max_support).drop("n")
    rows = assigned.join(rare, ["sensor", "cluster_id"], "left_semi").select("sensor", "series_id", "t", "x")
    near = grid_near(rows, motifs.select("sensor", F.col("centroid").alias("y")), min_dist, d).select("sensor", "series_id", "t")
    return rows.select("sensor", "series_id", "t").join(near, ["sensor", "series_id", "t"], "left_anti")


def train_fault_classifier(features: DataFrame, columns: list[str]):
    """A decision tree on motif counts; returns the fitted pipeline."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import DecisionTreeClassifier
    from pyspark.ml.feature import VectorAssembler

    return Pipeline(stages=[VectorAssembler(inputCols=columns, outputCol="features"), DecisionTreeClassifier(labelCol="positive", featuresCol="features", maxDepth=4, seed=1)]).fit(features)
