"""Cost and accuracy measures over clusters, motifs and occurrences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wavemotif.functions.vectors import sq_dist
from wavemotif.operators.cluster import centers, grid_near

CLUSTER = ["sensor", "cluster_id"]
#: Largest number of centres (some 100 bytes each) that is broadcast; beyond it rows and centres meet in salted parts of a sensor.
BROADCAST_CENTRES = 100_000
SALTS = 64


def beside_centres(rows: DataFrame, centres: DataFrame, how: str = "inner", limit: int = BROADCAST_CENTRES) -> DataFrame:
    """rows with every centre of their sensor. A sensor may hold most rows, so it is never the only key of a shuffle."""
    if centres.limit(limit + 1).count() <= limit:
        return rows.join(F.broadcast(centres), "sensor", how)
    everywhere = centres.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("_salt", F.pmod(F.xxhash64("series_id", "t"), F.lit(SALTS)).cast("int")).join(everywhere, ["sensor", "_salt"], how).drop("_salt")


def with_centroid(assigned: DataFrame, d: int) -> DataFrame:
    return assigned.join(centers(assigned, d).select(*CLUSTER, "n", "centroid"), CLUSTER).withColumn("d2", sq_dist("x", "centroid", d))


def radius_outliers(assigned: DataFrame, r: float, d: int) -> DataFrame:
    """sensor, outliers (members farther than r from the final centroid), clusters, below_twice."""
    rows = with_centroid(assigned, d).groupBy("sensor").agg(F.count_if(F.col("d2") > r * r).alias("outliers"), F.count_distinct("cluster_id").alias("clusters"))
    return rows.withColumn("below_twice", F.col("outliers") < 2 * F.col("clusters"))


def cluster_diameter(assigned: DataFrame, r: float, d: int) -> DataFrame:
    """sensor, cluster_id, n, diameter over pairs of members, within (at most 2r)."""
    a = assigned.select(*CLUSTER, F.struct("series_id", "t").alias("k"), "x")
    b = assigned.select(*CLUSTER, F.struct("series_id", "t").alias("k2"), F.col("x").alias("y"))
    pairs = a.join(b, CLUSTER).where("k <= k2").withColumn("d2", sq_dist("x", "y", d))
    return pairs.groupBy(*CLUSTER).agg(F.count_if(F.col("k") == F.col("k2")).alias("n"), F.round(F.sqrt(F.max("d2")), 6).alias("diameter"), (F.max("d2") <= 4 * r * r).alias("within"))


def misplacement(assigned: DataFrame, d: int, r: float = 1.0) -> DataFrame:
    """sensor, members, misplaced: members whose own centroid is not the nearest one of the sensor (of equal ones the least id).

    Exact for any r: members within r of their centroid meet the centroids of the grid cells around them, which hold all that are
    nearer; only the others, few in bounded spheres, meet all centroids of the sensor.
    """
    c = centers(assigned, d).select("sensor", F.col("cluster_id").alias("other"), F.col("centroid").alias("y"))
    own = with_centroid(assigned, d).select("sensor", "series_id", "t", "x", "cluster_id", F.col("d2").alias("own"))
    near = grid_near(own.where(F.col("own") <= r * r), c, r, d).select("sensor", "series_id", "t", "cluster_id", "own", "other", "d2")
    far = beside_centres(own.where(F.col("own") > r * r), c).select("sensor", "series_id", "t", "cluster_id", "own", "other", sq_dist("x", "y", d).alias("d2"))
    better = (F.col("d2") < F.col("own")) | ((F.col("d2") == F.col("own")) & (F.col("other") < F.col("cluster_id")))
    wrong = near.unionByName(far).where(better).select("sensor", "series_id", "t").distinct().groupBy("sensor").agg(F.count("*").alias("misplaced"))
    members = assigned.groupBy("sensor").agg(F.count("*").alias("members"))
    return members.join(wrong, "sensor", "left").select("sensor", "members", F.coalesce("misplaced", F.lit(0)).alias("misplaced"))


def match_quality(occurrences: DataFrame, truth: DataFrame, max_shift: int = 10) -> DataFrame:
    """shape, instances, found, members, recall, precision of the best single motif at a constant shift, one step either way."""
    motif = ["sensor", "cluster_id", "level_id"]
    size = occurrences.groupBy(*motif).agg(F.count("*").alias("members"))
    near = occurrences.join(truth.withColumnRenamed("t", "t0"), "series_id").withColumn("shift", F.col("t") - F.col("t0")).where(F.abs("shift") <= max_shift)
    spread = near.withColumn("at", F.explode(F.array(F.col("shift") - 1, F.col("shift"), F.col("shift") + 1)))
    hits = spread.groupBy(*motif, "shape", "at").agg(F.count_distinct("series_id", "t0").alias("found"), F.count_distinct("series_id", "t").alias("inside"))
    best = hits.join(size, motif).groupBy("shape").agg(F.max(F.struct("found", "inside", "members")).alias("m"))
    return truth.groupBy("shape").agg(F.count("*").alias("instances")).join(best, "shape", "left").select("shape", "instances", F.coalesce("m.found", F.lit(0)).alias("found"), F.col("m.members").alias("members"), (F.coalesce("m.found", F.lit(0)) / F.col("instances")).alias("recall"), F.try_divide("m.inside", "m.members").alias("precision"))


def tightness(assigned: DataFrame, d: int) -> DataFrame:
    rows = with_centroid(assigned, d)
    return rows.groupBy(*CLUSTER).agg(F.count("*").alias("n"), F.round(F.avg(F.sqrt("d2")), 6).alias("mean_dist"), F.round(F.max(F.sqrt("d2")), 6).alias("max_dist"))


def overlap_share(assigned: DataFrame, r: float, d: int) -> DataFrame:
    """sensor, members, shared: members within r of more than one centroid, by grid cells."""
    near = grid_near(assigned.select("sensor", "series_id", "t", "x"), centers(assigned, d).select("sensor", F.col("centroid").alias("y")), r, d)
    per = near.where(F.col("d2") < r * r).groupBy("sensor", "series_id", "t").agg(F.count("*").alias("c")).groupBy("sensor").agg(F.count_if(F.col("c") > 1).alias("shared"))
    return assigned.groupBy("sensor").agg(F.count("*").alias("members")).join(per, "sensor", "left").select("sensor", "members", F.coalesce("shared", F.lit(0)).alias("shared"))


def purity(assigned: DataFrame) -> DataFrame:
    """clusters, rows, pure (rows with the most frequent label of their cluster), adjusted_rand. The label is in series_id."""
    cells = assigned.groupBy("cluster_id", "series_id").agg(F.count("*").alias("c"))
    pairs = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2)
    per = cells.groupBy("cluster_id").agg(F.sum("c").alias("n"), F.max("c").alias("m"), pairs("c").alias("both")).agg(F.count("*").alias("clusters"), F.sum("n").alias("rows"), F.sum("m").alias("pure"), F.sum("both").alias("both"), pairs("n").alias("a"))
    other = cells.groupBy("series_id").agg(F.sum("c").alias("n")).agg(pairs("n").alias("b"))
    expected = F.col("a") * F.col("b") / (F.col("rows") * (F.col("rows") - 1) / 2)
    rand = F.try_divide(F.col("both") - expected, (F.col("a") + F.col("b")) / 2 - expected)
    return per.crossJoin(F.broadcast(other)).select("clusters", "rows", "pure", F.round(rand, 6).alias("adjusted_rand"))  # one row each


def shifted_distance(a: str, b: str, d: int, shift: int) -> Column:
    """Squared distance of two vectors when the second one is moved by shift frames, over the frames that both have, scaled to all."""
    frames = [i for i in range(d) if 0 <= i - shift < d]
    total = F.lit(0.0)
    for i in frames:
        total = total + (F.col(a)[i] - F.col(b)[i - shift]) * (F.col(a)[i] - F.col(b)[i - shift])
    return total * F.lit(d / len(frames))


def motif_agreement(a: DataFrame, b: DataFrame, r: float, d: int, max_shift: int = 0) -> DataFrame:
    """sensor, motifs, agreed: motifs of a whose centroid is nearer than r to one of b, at any shift up to max_shift frames either way."""
    left, right = (m.select("sensor", "motif_id", "level_id", F.col("centroid").alias(c)) for m, c in ((a, "c1"), (b, "c2")))
    gaps = [shifted_distance("c1", "c2", d, s) for s in range(-max_shift, max_shift + 1)]
    gap = F.least(*gaps) if len(gaps) > 1 else gaps[0]
    near = left.join(right.select("sensor", "c2"), "sensor", "left").groupBy("sensor", "motif_id", "level_id").agg(F.min(gap).alias("d2"))
    return near.groupBy("sensor").agg(F.count("*").alias("motifs"), F.count_if(F.col("d2") < r * r).alias("agreed"))


def dropped_shares(funnel: DataFrame) -> DataFrame:
    """sensor, shifted, trivial: shares of clusters of high support that shift removal drops, and of members that the trivial test drops."""
    at = lambda step, c: F.max(F.when(F.col("step") == step, F.col(c)))
    per = funnel.groupBy("sensor").agg(at("high_support", "clusters").alias("high"), at("not_shifted", "clusters").alias("kept"), at("not_shifted", "rows").alias("members"), at("not_trivial", "rows").alias("left"))
    return per.select("sensor", F.round(1 - F.col("kept") / F.col("high"), 6).alias("shifted"), F.round(1 - F.col("left") / F.col("members"), 6).alias("trivial"))


def repeatability(runs: DataFrame, d: int) -> DataFrame:
    """ratio of the mean nearest-centre distance within a method's runs to that between methods; runs(method, run, centroid)."""
    a = runs.select("method", "run", F.monotonically_increasing_id().alias("k"), F.col("centroid").alias("c1"))
    b = runs.select(F.col("method").alias("m2"), F.col("run").alias("r2"), F.col("centroid").alias("c2"))
    pairs = a.crossJoin(b).where("not (method = m2 and run = r2)")  # centre sets, not data
    near = pairs.groupBy("k", "method", "m2", "r2").agg(F.sqrt(F.min(sq_dist("c1", "c2", d))).alias("g"))
    return near.agg((F.avg(F.when(F.col("method") == F.col("m2"), F.col("g"))) / F.avg(F.when(F.col("method") != F.col("m2"), F.col("g")))).alias("ratio"))
