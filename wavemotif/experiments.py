"""The experiment workloads on the given tables: growth and time, hash settings, short sets, extents of clusters, waveforms."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavemotif import oracles as O
from wavemotif.catalog import D, W, _support, query
from wavemotif.functions import vectors as VEC
from wavemotif.operators import baselines as B
from wavemotif.operators import cluster as C
from wavemotif.operators import extract as X
from wavemotif.operators import matching as M
from wavemotif.operators import measures as S
from wavemotif.operators import prep as P
from wavemotif.operators import relational as R
from wavemotif.plans import pipeline as PL
from wavemotif.sources import views as V

#: Hash settings that are compared: planes a set, sets.
GRID = ((2, 3), (2, 5), (3, 5), (3, 10), (5, 10), (8, 10))
#: Families with the width of their cells; cells of 4 are wider than these vectors are long, and then equal the sides.
FAMILIES = (("sign", 4.0), ("quantised", 4.0), ("quantised", 2.0), ("quantised", 1.0))


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def runtime_curve(spark: SparkSession, sf_dir: str, runs: tuple[int, ...] = (1, 4, 8, 16, 32), methods: tuple[str, ...] = ("grouping", "all", "cftree", "hash")) -> DataFrame:
    """method, windows, found, seconds: time against length, for closest-pair grouping and for sphere clustering of the same windows.

    The length is a growing number of runs, which is what is measured. found: groups, or clusters. seconds change from run to run.
    """
    rows, first = [], V.planted_view(spark, sf_dir).select("series_id").distinct().orderBy("series_id").limit(max(runs))
    ids = [r.series_id for r in first.collect()]  # as many as the longest length has runs
    series = C.cut(V.planted_view(spark, sf_dir).where(F.col("series_id").isin(ids)))
    for k in (k for k in runs if k <= len(ids)):
        win = C.cut(P.reduced_windows(P.znormalize(series.where(F.col("series_id").isin(ids[:k]))), W, D, None))
        for method in methods:
            began = time.time()
            if method == "grouping":
                got = B.closest_pair_grouping(win, D, W, "radius", r=1.0).agg(F.count_distinct("group_id")).first()[0]
            else:
                cand = P.drop_repeated_words(win.where("dev >= 1"), D)
                got = C.cluster(cand, 1.0, method).agg(F.count_distinct("cluster_id")).first()[0]
            rows.append((method, win.count(), got, round(time.time() - began, 3)))
    return spark.createDataFrame(rows, "method string, windows long, found long, seconds double")


query("workload_runtime")(runtime_curve)

# ---------------------------------------------------------------- hash settings
_X = f"SELECT series_id, t, [{', '.join(f'p{j}' for j in range(D))}] AS x FROM ({O.candidates(O.RUN)})"


def _sweep_sql() -> str:
    parts = []
    for family, width in FAMILIES:
        for per_set, sets in GRID:
            b = O.bucket_rows(O.RUN, family, sets, per_set, width)
            parts.append(f"SELECT '{family}' AS family, {width}::DOUBLE AS width, {per_set} AS per_set, {sets} AS sets, count(*) AS pairs, count(h.t) AS candidates, count(*) FILTER (near)::BIGINT AS near, count(h.t) FILTER (near)::BIGINT AS found FROM p LEFT JOIN (SELECT DISTINCT a.series_id, a.t, b.t AS u FROM ({b}) a JOIN ({b}) b ON a.series_id = b.series_id AND a.set = b.set AND a.bucket = b.bucket AND a.t < b.t) h ON h.series_id = p.series_id AND h.t = p.t AND h.u = p.u")
    return f"WITH c AS MATERIALIZED ({_X}), p AS MATERIALIZED (SELECT a.series_id, a.t, b.t AS u, {O.sq('a.x', 'b.x')} < 4 AS near FROM c a JOIN c b ON a.series_id = b.series_id AND a.t < b.t) " + " UNION ALL ".join(parts)


@query("hash_sweep", _sweep_sql())
def _hash_sweep(s: SparkSession, d: str) -> DataFrame:
    """family, width, per_set, sets, pairs, candidates, near, found: pairs of a run that share a bucket, and those of them within 2, by setting."""
    cand = P.candidates(V.run_view(s, d), W, D).select("series_id", "t", "x")
    settings = [(f, width, per_set, sets) for f, width in FAMILIES for per_set, sets in GRID]
    keys = [F.array(*[VEC.bucket_key(F.col("x"), p, f, width) for p in VEC.fixed_planes(sets, per_set, D)]).alias(f"k{i}") for i, (f, width, per_set, sets) in enumerate(settings)]
    a = C.cut(cand.select("*", *keys))
    names = [f"k{i}" for i in range(len(settings))]
    b = a.select("series_id", F.col("t").alias("u"), F.col("x").alias("y"), *[F.col(n).alias(f"{n}_b") for n in names])
    pairs = a.join(b, "series_id").where("t < u").withColumn("near", VEC.sq_dist("x", "y", D) < 4)
    hit = lambda n: F.exists(F.zip_with(n, f"{n}_b", lambda p, q: p == q), lambda h: h)
    both = pairs.agg(F.count("*").alias("pairs"), F.count_if("near").alias("near"), *[F.struct(F.count_if(hit(n)).alias("candidates"), F.count_if(hit(n) & F.col("near")).alias("found")).alias(n) for n in names])
    rows = F.array(*[F.struct(F.lit(f).alias("family"), F.lit(width).alias("width"), F.lit(per_set).alias("per_set"), F.lit(sets).alias("sets"), F.col(f"k{i}.candidates"), F.col(f"k{i}.found")) for i, (f, width, per_set, sets) in enumerate(settings)])
    return both.select("pairs", "near", F.explode(rows).alias("r")).select("r.family", "r.width", "r.per_set", "r.sets", "pairs", "r.candidates", "near", "r.found")


# ---------------------------------------------------------------- short sets, with a support of two
def _short(s: SparkSession, d: str) -> dict[str, tuple[DataFrame, int]]:
    return {"beats": (V.flag_view(s, d), 20), "calls": (V.region_view(s, d), 20), "hours_long": (V.clock_view(s, d), 80), "hours_short": (V.clock_view(s, d), 14)}


@query("workload_short_sets")
def _short_sets(s: SparkSession, d: str) -> DataFrame:
    """experiment, method, motifs, members, agreed: motifs in more than two places of short series (w = 20, 80 with the wider radius, 14), and how
    many of them the CF-tree form has too, moved by two frames at most."""
    parts = []
    for name, (series, w) in _short(s, d).items():
        dims = w // 2
        got = {m: C.cut(PL.discover(series, w, 2, method=m).motifs) for m in ("cftree", "hash")}
        for m, motifs in got.items():
            agreed = S.motif_agreement(motifs, got["cftree"], VEC.adjusted_radius(w), dims, 2).agg(F.sum("agreed").alias("agreed"))
            parts.append(motifs.agg(F.lit(name).alias("experiment"), F.lit(m).alias("method"), F.count("*").alias("motifs"), F.sum("support").alias("members")).crossJoin(F.broadcast(agreed)))  # one row each
    return _union(parts)


@query("workload_cluster_shapes")
def _shapes(s: SparkSession, d: str) -> DataFrame:
    """method, clusters, widest: the farthest member from its centre in clusters of the smoothed view, by spheres, k-means and density."""
    cand = C.cut(P.candidates(V.smoothed(V.flag_view(s, d)), W, D))
    spheres = C.cut(C.cluster(cand, 1.0, "cftree"))
    k = max(2, spheres.select("sensor", "cluster_id").distinct().count())
    dense = B.dbscan(cand.select("sensor", F.struct("series_id", "t").alias("id"), "x"), 1.0, 3, D).where("cluster_id is not null")
    dense = dense.select("id.series_id", "id.t", F.xxhash64("cluster_id").alias("cluster_id"))
    groups = {"spheres": spheres, "kmeans": C.cut(B.kmeans_ml(cand, k)), "density": C.cut(cand.join(dense, ["series_id", "t"]))}
    return _union([S.tightness(a, D).agg(F.lit(name).alias("method"), F.count("*").alias("clusters"), F.round(F.max("max_dist"), 4).alias("widest")) for name, a in groups.items()])


@query("top_motifs_fleet")
def _fleet_waveforms(s: SparkSession, d: str) -> DataFrame:
    """sensor, motif_id, step, v: the mean original waveform of the three best supported motifs of each fleet sensor."""
    series = C.cut(V.fleet_view(s, d))
    r = PL.discover(series, W, _support(s, d))
    best = R.top_per_group(r.motifs, ["sensor"], [F.desc("support"), F.col("motif_id"), F.col("level_id")], 3).select("sensor", F.col("motif_id").alias("cluster_id"), "level_id")
    occ = r.stages["motifs"].join(F.broadcast(best), ["sensor", "cluster_id", "level_id"]).select("sensor", "series_id", "t", F.col("cluster_id").alias("motif_id"))
    return M.expand(occ, series, W).groupBy("sensor", "motif_id", "step").agg(F.round(F.avg("v"), 2).alias("v"))


@query("workload_dropped_shares")
def _shares(s: SparkSession, d: str) -> DataFrame:
    """sensor, shifted, trivial: shares that the two later steps drop, in the six fleet sensors."""
    return S.dropped_shares(PL.discover(V.fleet_view(s, d), W, _support(s, d)).funnel())


@query("workload_separators")
def _separators(s: SparkSession, d: str) -> DataFrame:
    """members, segments, longest: into how many parts the trivial test falls, and the members of the largest."""
    series = C.stored(V.planted_view(s, d))
    high = X.high_support(C.cluster(P.candidates(series, W, D), 1.0, "cftree"), _support(s, d))
    windows = P.reduced_windows(P.znormalize(series), W, D, None)
    mean = C.centers(high, D).select("sensor", "cluster_id", F.col("centroid").alias("c"))
    members, keys = X.member_segments(high.join(mean, ["sensor", "cluster_id"]), windows, 2.0, D)
    return members.groupBy(*keys).agg(F.count("*").alias("n")).agg(F.sum("n").alias("members"), F.count("*").alias("segments"), F.max("n").alias("longest"))
