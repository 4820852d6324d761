"""The whole procedure: from series to motifs, with a record of how many rows each step leaves."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavemotif.functions.vectors import adjusted_radius
from wavemotif.operators import cluster as C
from wavemotif.operators import extract as X
from wavemotif.operators import prep as P


@dataclass
class MotifResult:
    motifs: DataFrame
    occurrences: DataFrame
    stages: dict[str, DataFrame]

    def funnel(self) -> DataFrame:
        """FUNNEL: sensor, step, rows and clusters after each step."""
        parts = []
        for i, (name, df) in enumerate(self.stages.items()):
            n = F.count_distinct("cluster_id") if "cluster_id" in df.columns else F.lit(None)
            parts.append(df.groupBy("sensor").agg(F.count("*").alias("rows"), n.cast("long").alias("clusters")).select("sensor", F.lit(i).alias("at"), F.lit(name).alias("step"), "rows", "clusters"))
        return reduce(DataFrame.unionByName, parts)


def discover(series: DataFrame, w: int = 20, s: int = 8, r: float | None = None, f: float = 1.0, method: str = "cftree", d: int | None = None, p: int = 50, sigma_t: int = 2, eps: float = 0.5, min_pts: int = 2, cascade: str = "greedy", skip: tuple[str, ...] = (), group: tuple[str, ...] = ("sensor",), space: str = "z", **options) -> MotifResult:
    """Motifs of every sensor. Only w and s need be given. skip: flat, words, shifted, trivial, levels. space: units of levels and
    eps, z-scores or raw."""
    d, r = d or max(1, w // 2), adjusted_radius(w) if r is None else r
    series = C.stored(series)  # thin, and read for each pass over windows, which are never kept
    every = P.reduced_windows(P.znormalize(series), w, d, None)
    unflat = every if "flat" in skip else every.where(F.col("dev") >= f)
    cand = unflat.withColumn("word", F.lit("")) if "words" in skip else P.drop_repeated_words(unflat, d)
    if method == "parallel":
        assigned = C.cluster_parallel(cand, r, d, **options)
    elif method == "cf_shards":
        assigned = C.cluster_cf_shards(cand, r, d, **options)
    elif method == "words":
        assigned = C.word_clusters(cand, d)
    else:
        assigned = C.cluster(cand, r, method, group, **options)
    assigned = assigned if method == "words" or C.streams(method, group, **options) else C.stored(assigned)
    high = X.high_support(assigned, s)
    shifted = high if "shifted" in skip else X.drop_shifted(high, d, p, sigma_t, cascade=cascade)
    # from here on rows are places with their level; vectors stay with the clusters
    place = ["sensor", "series_id", "t", "cluster_id"]
    members = (shifted if "trivial" in skip else X.drop_trivial(shifted, every, r)).select(*place, "level").transform(C.stored)
    groups = members if "shifted" in skip or "trivial" in skip else X.drop_shifted(members, d, p, sigma_t, cascade=cascade)
    if space == "raw":
        groups = X.raw_levels(groups, P.moments(series))
    final = groups.withColumn("level_id", F.lit(0).cast("long")) if "levels" in skip else X.split_levels(groups, eps, min_pts, s)
    final = C.stored(final)
    occurrences = final.join(assigned.select(*place, "x", "dist", "evals"), place).select("sensor", "series_id", "t", "x", "level", "cluster_id", "dist", "evals", "level_id")
    stages = {"windows": every, "not_flat": unflat, "candidates": cand, "clusters": assigned, "high_support": high, "not_shifted": shifted, "not_trivial": members, "groups": groups, "motifs": final}
    return MotifResult(X.motifs(occurrences, d, final), occurrences, stages)


def discover_many(series: DataFrame, widths: tuple[int, ...], s: int, **options) -> DataFrame:
    """MOTIFS of several widths, with a column w."""
    parts = [discover(series, w, s, **options).motifs.withColumn("w", F.lit(w)) for w in widths]
    return reduce(DataFrame.unionByName, parts)
