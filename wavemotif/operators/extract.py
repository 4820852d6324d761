"""From clusters to motifs: support, shifted clusters, trivial members, levels."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.functions.vectors import sq_dist
from wavemotif.operators.cluster import stored

CLUSTER = ["sensor", "cluster_id"]
#: Rows that the shift test gathers before it works on whole runs or clusters.
CHUNK_ROWS = 50_000


def high_support(assigned: DataFrame, s: int, support: str = "members") -> DataFrame:
    """Members of clusters with more than s members, or members in more than s runs."""
    n = F.count("*") if support == "members" else F.count_distinct("series_id")
    kept = assigned.groupBy(*CLUSTER).agg(n.alias("c")).where(F.col("c") > s).select(*CLUSTER).transform(stored)
    return assigned.join(kept, CLUSTER, "left_semi")


def shift_diffs(assigned: DataFrame, t_s: int, nearest: str = "time") -> DataFrame:
    """(sensor, small, large, pairs, sum_diff, sum_sq, small_n): for every member of a cluster the signed distance in time to the
    nearest member, less than t_s away in the same run, of each cluster that is larger (or as large, with a smaller id)."""
    if nearest == "time":
        rows = near_larger(assigned, t_s).select("sensor", "small", "small_n", F.explode("near").alias("e"))
        one = rows.select("sensor", "small", "small_n", F.expr(f"(e - pmod(e, {2 * t_s})) div {2 * t_s}").alias("large"), (F.pmod("e", F.lit(2 * t_s)) - t_s).alias("diff"))
        return one.groupBy("sensor", "small", "large", "small_n").agg(F.count("*").alias("pairs"), F.sum("diff").alias("sum_diff"), F.sum(F.col("diff") * F.col("diff")).alias("sum_sq"))
    size = assigned.groupBy(*CLUSTER).agg(F.count("*").alias("n"))
    rows = assigned.join(size, CLUSTER).select(*CLUSTER, "series_id", "t", "n", "x")
    a = rows.withColumn("bin", F.floor(F.col("t") / t_s))
    b = rows.select("sensor", "series_id", F.col("cluster_id").alias("large"), F.col("t").alias("t2"), F.col("n").alias("n2"), F.col("x").alias("y"), F.explode(F.array(*[F.floor(F.col("t") / t_s) + i for i in (-1, 0, 1)])).alias("bin"))
    bigger = (F.col("n2") > F.col("n")) | ((F.col("n2") == F.col("n")) & (F.col("large") < F.col("cluster_id")))
    near = a.join(b, ["sensor", "series_id", "bin"]).where(bigger & (F.abs(F.col("t2") - F.col("t")) < t_s)).withColumn("diff", F.col("t2") - F.col("t"))
    by_shape = F.struct(F.aggregate(F.zip_with("x", "y", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda m, v: m + v).alias("a"), F.col("diff").alias("diff"))
    one = near.groupBy("sensor", "cluster_id", "large", "series_id", "t", "n").agg(F.min(by_shape).alias("m"))
    return one.groupBy("sensor", F.col("cluster_id").alias("small"), "large", F.col("n").alias("small_n")).agg(F.count("*").alias("pairs"), F.sum("m.diff").alias("sum_diff"), F.sum(F.col("m.diff") * F.col("m.diff")).alias("sum_sq"))


def _whole(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Rows sorted by the keys in tables of some CHUNK_ROWS rows, none of which parts rows of equal keys."""
    held: list[pa.Table] = []
    for batch in batches:
        held.append(pa.Table.from_batches([batch]))
        if sum(len(p) for p in held) < CHUNK_ROWS:
            continue
        rows = pa.concat_tables(held).combine_chunks()
        same = np.ones(len(rows), bool)
        for k in keys:
            v = rows.column(k).to_numpy(zero_copy_only=False)
            same &= v == v[-1]
        end = int(np.flatnonzero(~same).max(initial=-1)) + 1
        if end:
            yield rows.slice(0, end)
        held = [rows.slice(end)]
    if held and sum(len(p) for p in held):
        yield pa.concat_tables(held).combine_chunks()


def _near_of(run: np.ndarray, t: np.ndarray, c: np.ndarray, n: np.ndarray, t_s: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(member, cluster, diff) of rows sorted by run and t: the nearest member of each larger cluster less than t_s away, earlier before later."""
    rows, size = np.arange(len(t)), len(t)
    line = t + run * (int(t.max()) - int(t.min()) + 2 * t_s)  # runs lie t_s apart or more
    reach = int(np.maximum(rows - np.searchsorted(line, line - t_s, "right"), np.searchsorted(line, line + t_s) - 1 - rows).max(initial=0))
    sides = []
    for sign in (-1, 1):
        at = rows[None, :] + sign * np.arange(1, reach + 1)[:, None]
        inside = (at >= 0) & (at < size)
        at = np.clip(at, 0, size - 1)
        diff = t[at] - t
        ok = inside & (run[at] == run) & (np.abs(diff) < t_s) & ((n[at] > n) | ((n[at] == n) & (c[at] < c)))
        sides.append((np.where(ok, c[at], -1), np.abs(diff), diff, ok))
    out = []
    for side in (0, 1):
        (own, gap, diff, ok), (other, far, _, there) = sides[side], sides[1 - side]
        for k in range(reach):
            good = ok[k].copy()
            for j in range(k):
                good &= ~(ok[j] & (own[j] == own[k]))
            for j in range(reach):
                good &= ~(there[j] & (other[j] == own[k]) & ((far[j] <= gap[k]) if side else (far[j] < gap[k])))
            i = np.flatnonzero(good)
            out.append((i, own[k, i], diff[k, i]))
    if not out:
        return (np.empty(0, np.int64),) * 3
    return tuple(np.concatenate(p) for p in zip(*out, strict=True))


def near_larger(assigned: DataFrame, t_s: int) -> DataFrame:
    """(sensor, small, small_n, near): a row a member, with large * 2 t_s + t_s + diff for the nearest member of each larger cluster less than
    t_s steps away in its run. Thin rows are sorted by run once; members without such a neighbour are left out."""
    size = assigned.groupBy(*CLUSTER).agg(F.count("*").alias("n")).transform(stored)
    rows = assigned.select(*CLUSTER, "series_id", "t").join(size, CLUSTER).repartition("sensor", "series_id").sortWithinPartitions("sensor", "series_id", "t")

    def fn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _whole(batches, ["sensor", "series_id"]):
            sensor, series, t, c, n = (rows.column(k).to_numpy(zero_copy_only=False) for k in ("sensor", "series_id", "t", "cluster_id", "n"))
            new = np.concatenate([[False], (sensor[1:] != sensor[:-1]) | (series[1:] != series[:-1])])
            i, large, diff = _near_of(np.cumsum(new), t, c, n, t_s)
            if not len(i):
                continue
            order = np.argsort(i, kind="stable")
            member, first = np.unique(i[order], return_index=True)
            near = pa.ListArray.from_arrays(pa.array(np.append(first, len(order)), pa.int32()), pa.array((large * (2 * t_s) + t_s + diff)[order]))
            yield pa.RecordBatch.from_arrays([pa.array(sensor[member], pa.string()), pa.array(c[member]), pa.array(n[member]), near], ["sensor", "small", "small_n", "near"])

    return rows.mapInArrow(fn, "sensor string, small long, small_n long, near array<long>")


def shifted_forms(assigned: DataFrame, t_s: int, p: int = 50, sigma_t: int = 2, rule: str = "deviation") -> DataFrame:
    """The rows of shift_matches(shift_diffs(..)), a cluster at a time: sums of pairs are never shuffled, only a row a member."""
    rows = near_larger(assigned, t_s).repartition("sensor", "small").sortWithinPartitions("sensor", "small")

    def fn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _whole(batches, ["sensor", "small"]):
            near = rows.column("near").combine_chunks()
            near = near.chunk(0) if isinstance(near, pa.ChunkedArray) else near
            sensor, small, n = (rows.column(k).to_numpy(zero_copy_only=False) for k in ("sensor", "small", "small_n"))
            row = np.repeat(np.arange(len(rows)), near.value_lengths().to_numpy())
            e = near.flatten().to_numpy()
            new = np.concatenate([[False], (sensor[1:] != sensor[:-1]) | (small[1:] != small[:-1])])
            of, large, diff = np.cumsum(new)[row], e // (2 * t_s), e % (2 * t_s) - t_s
            order = np.lexsort((large, of))
            of, large, diff, row = of[order], large[order], diff[order], row[order]
            starts = np.flatnonzero(np.concatenate([[True], (of[1:] != of[:-1]) | (large[1:] != large[:-1])]))
            pairs = np.diff(np.append(starts, len(of)))
            total, square = np.add.reduceat(diff, starts), np.add.reduceat(diff * diff, starts)
            size = n[row[starts]]
            hit = 100 * pairs >= p * size if rule == "share" else (100 * pairs > p * size) & (pairs * square - total * total < sigma_t**2 * pairs * pairs)
            at = row[starts[hit]]
            yield pa.RecordBatch.from_arrays([pa.array(sensor[at], pa.string()), pa.array(small[at]), pa.array(n[at]), pa.array(large[starts[hit]])], ["sensor", "small", "small_n", "large"])

    return rows.mapInArrow(fn, "sensor string, small long, small_n long, large long")


def shift_diffs_sweep(assigned: DataFrame, t_s: int) -> DataFrame:
    """The rows of shift_diffs by a sweep: in each run the starts of two clusters are merged in order, and a start meets the nearer of its two
    neighbours (the earlier one of equals). A task a run; sums of runs are added up."""
    size = assigned.groupBy(*CLUSTER).agg(F.count("*").alias("n"))
    rows = assigned.join(size, CLUSTER).select(*CLUSTER, "series_id", "t", "n")

    def fn(g: pd.DataFrame) -> pd.DataFrame:
        starts = [(int(n), int(c), np.sort(of.t.to_numpy())) for (c, n), of in g.groupby(["cluster_id", "n"])]
        out = []
        for n, c, own in starts:
            for m, large, other in starts:
                if m > n or (m == n and large < c):
                    at = np.searchsorted(other, own)
                    before, after = other[np.maximum(at - 1, 0)] - own, other[np.minimum(at, len(other) - 1)] - own
                    diff = np.where((at == 0) | ((at < len(other)) & (np.abs(after) < np.abs(before))), after, before)
                    diff = diff[np.abs(diff) < t_s]
                    if len(diff):
                        out.append((g.sensor.iloc[0], c, large, n, len(diff), int(diff.sum()), int((diff * diff).sum())))
        return pd.DataFrame(out, columns=["sensor", "small", "large", "small_n", "pairs", "sum_diff", "sum_sq"])

    parts = rows.groupBy("sensor", "series_id").applyInPandas(fn, "sensor string, small long, large long, small_n long, pairs long, sum_diff long, sum_sq long")
    return parts.groupBy("sensor", "small", "large", "small_n").agg(*[F.sum(c).alias(c) for c in ("pairs", "sum_diff", "sum_sq")])


def shift_matches(diffs: DataFrame, p: int = 50, sigma_t: int = 2, rule: str = "deviation") -> DataFrame:
    """(sensor, small, large): small is a shifted form of large. In integers: pairs of more than p percent, deviation below sigma_t."""
    many = 100 * F.col("pairs") > p * F.col("small_n")
    if rule == "share":
        return diffs.where(100 * F.col("pairs") >= p * F.col("small_n")).select("sensor", "small", "large")
    tight = F.col("pairs") * F.col("sum_sq") - F.col("sum_diff") * F.col("sum_diff") < sigma_t**2 * F.col("pairs") * F.col("pairs")
    return diffs.where(many & tight).select("sensor", "small", "large")


def drop_shifted(assigned: DataFrame, t_s: int = 10, p: int = 50, sigma_t: int = 2, nearest: str = "time", cascade: str = "greedy", rule: str = "deviation") -> DataFrame:
    """Members of clusters that are not a shifted form of a larger one. greedy: only of one that is kept itself."""
    if nearest == "time":
        matches = shifted_forms(assigned, t_s, p, sigma_t, rule)
    else:
        diffs = shift_diffs(assigned, t_s, nearest)
        matches = shift_matches(diffs, p, sigma_t, rule).join(diffs.select("sensor", "small", "small_n").distinct(), ["sensor", "small"])
    if cascade == "independent":
        gone = matches.select("sensor", F.col("small").alias("cluster_id")).distinct()
    else:

        def fn(g: pd.DataFrame) -> pd.DataFrame:  # matches of one sensor; clusters without one are kept
            g = g.sort_values(["small_n", "small"], ascending=[False, True])
            out: set[int] = set()
            small, large = g.small.to_numpy(), g.large.to_numpy()
            starts = np.flatnonzero(np.concatenate([[True], small[1:] != small[:-1]]))
            for a, b in zip(starts, [*starts[1:], len(small)], strict=True):
                if any(c not in out for c in large[a:b].tolist()):
                    out.add(int(small[a]))
            return pd.DataFrame({"sensor": g.sensor.iloc[0], "cluster_id": np.array(sorted(out), np.int64)})

        gone = matches.groupBy("sensor").applyInPandas(fn, "sensor string, cluster_id long")
    return assigned.join(stored(gone), CLUSTER, "left_anti")


def _scan(m: pd.DataFrame, w: pd.DataFrame, delta2: float) -> list:
    """Index of the members of one run and cluster (with its mean c) that are kept, among the windows w of the run."""
    w = w.sort_values("t")
    at, x = w.t.to_numpy(), np.array(w.x.tolist(), float) if len(w) else np.empty((0, 1))
    keep, last = [], None
    c = np.array(m.c.iloc[0])
    m = m.sort_values("t")
    for i, t, v in zip(m.index, m.t, m.x, strict=True):
        v = np.array(v)
        if last is not None:
            a, b = np.searchsorted(at, [last[0] + 1, t])
            s = x[a:b]
            if not (len(s) and ((((s - last[1]) ** 2).sum(axis=1) > delta2) & (((s - v) ** 2).sum(axis=1) > delta2)).any() and (((s - c) ** 2).sum(axis=1) > delta2).any()):
                continue
        keep.append(i)
        last = (t, v)
    return keep


def drop_trivial(assigned: DataFrame, reduced: DataFrame, r: float, delta: float | None = None, separators: bool = False) -> DataFrame:
    """Members of a cluster in one run, in time order, kept only if between them and the last kept one lie a window farther than
    delta from both and a window farther than delta from the centroid. Runs are independent; a cogrouped task scans one run.

    separators: a window farther from the centroid than delta and the farthest member together is farther than delta from every member, so
    it parts any two of them. What lies between two such windows is scanned by a task of its own, and a long run is no longer one task.
    """
    delta = delta or 2 * r
    delta2, dims, columns = delta**2, _dims(assigned), assigned.columns
    mean = assigned.groupBy(*CLUSTER).agg(F.array(*[F.avg(F.col("x")[i]) for i in range(dims)]).alias("c"))
    keys = ["sensor", "series_id"]
    if separators:
        members, windows, keys = _segments(assigned.join(mean, CLUSTER), reduced, delta, dims)

        def fn(m: pd.DataFrame, w: pd.DataFrame) -> pd.DataFrame:
            keep = [i for _, g in m.groupby("cluster_id") for i in _scan(g, w, delta2)]
            return m.loc[keep][columns]

        members, windows = (df.select(*[F.col(c).alias(c) for c in df.columns]) for df in (members, windows))
        return members.groupBy(*keys).cogroup(windows.groupBy(*keys)).applyInPandas(fn, assigned.schema)
    # a member that is alone in its run stays; the others are scanned by their places, and only what goes comes back
    several = assigned.groupBy(*CLUSTER, "series_id").agg(F.sort_array(F.collect_list("t")).alias("ts")).where(F.size("ts") > 1).join(mean, CLUSTER)
    windows = reduced.select(*keys, "t", "x")

    def gone(several: pa.Table, windows: pa.Table) -> pa.Table:
        sensor, series, cluster, place = [], [], [], []
        if len(several):
            at = windows.column("t").to_numpy()
            order = np.argsort(at, kind="stable")
            at, x = at[order], _matrix(windows.column("x"))[order]
            for c, ts, mean in zip(several.column("cluster_id").to_pylist(), several.column("ts").to_pylist(), _matrix(several.column("c")), strict=True):
                drop = _trivial(np.array(ts), mean, at, x, delta2)
                cluster += [c] * len(drop)
                place += drop
            sensor, series = ([several.column(k)[0].as_py()] * len(place) for k in keys)
        return pa.table({"sensor": pa.array(sensor, pa.string()), "series_id": pa.array(series, pa.int64()), "t": pa.array(place, pa.int64()), "cluster_id": pa.array(cluster, pa.int64())})

    several, windows = (df.select(*[F.col(c).alias(c) for c in df.columns]) for df in (several, windows))
    out = several.groupBy(*keys).cogroup(windows.groupBy(*keys)).applyInArrow(gone, "sensor string, series_id long, t long, cluster_id long")
    return assigned.join(stored(out), [*keys, "t", "cluster_id"], "left_anti").select(*columns)


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    flat = np.concatenate([np.asarray(c.flatten()) for c in column.chunks]) if column.num_chunks else np.empty(0)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 1))


def _trivial(ts: np.ndarray, c: np.ndarray, at: np.ndarray, x: np.ndarray, delta2: float) -> list[int]:
    """Of the members ts of one run and cluster, those with no window between them and the last kept one that parts them."""
    place = np.searchsorted(at, ts)
    if (place >= len(at)).any() or (at[place] != ts).any():
        raise ValueError("a member is not among the windows of its run")
    far = ((x[place[0] : place[-1]] - c) ** 2).sum(axis=1) > delta2
    last, out = place[0], []
    for p, t in zip(place[1:].tolist(), ts[1:].tolist(), strict=True):
        parted = far[last + 1 - place[0] : p - place[0]].any()
        if parted:
            s = x[last + 1 : p]
            parted = ((((s - x[last]) ** 2).sum(axis=1) > delta2) & (((s - x[p]) ** 2).sum(axis=1) > delta2)).any()
        if parted:
            last = p
        else:
            out.append(t)
    return out


def _segments(members: DataFrame, reduced: DataFrame, delta: float, dims: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Members and windows with the number of separators before them, for each cluster and run in which it has members."""
    far = members.groupBy(*CLUSTER).agg(F.sqrt(F.max(sq_dist("x", "c", dims))).alias("reach"), F.any_value("c").alias("c"))
    runs = members.groupBy(*CLUSTER, "series_id").agg(F.min("t").alias("first"), F.max("t").alias("last")).join(far, CLUSTER)
    rows = reduced.select("sensor", "series_id", "t", "x").join(runs, ["sensor", "series_id"]).where(F.col("t").between(F.col("first"), F.col("last")))
    parts = (F.sqrt(sq_dist("x", "c", dims)) > (delta + F.col("reach")) * (1 + 1e-12) + 1e-12).cast("long")
    segment = F.sum(parts).over(Window.partitionBy(*CLUSTER, "series_id").orderBy("t")).alias("segment")
    rows = rows.select(*CLUSTER, "series_id", "t", "x", segment)
    at = rows.select(*CLUSTER, "series_id", "t", "segment")
    return members.join(at, [*CLUSTER, "series_id", "t"]), rows, [*CLUSTER, "series_id", "segment"]


def member_segments(members: DataFrame, reduced: DataFrame, delta: float, dims: int) -> tuple[DataFrame, list[str]]:
    """Places of members with the number of separators before them, as _segments gives it, and the names of the keys of a segment. A run and
    its clusters meet in one task, so no window is repeated for each cluster."""
    far = members.groupBy(*CLUSTER).agg(F.sqrt(F.max(sq_dist("x", "c", dims))).alias("reach"), F.any_value("c").alias("c"))
    keys = ["sensor", "series_id"]
    places = members.groupBy(*CLUSTER, "series_id").agg(F.sort_array(F.collect_list("t")).alias("ts")).join(far, CLUSTER)

    def fn(places: pa.Table, windows: pa.Table) -> pa.Table:
        clusters, ts, segments = [], [], []
        if len(places) and len(windows):
            at = windows.column("t").to_numpy()
            order = np.argsort(at, kind="stable")
            at, x = at[order], _matrix(windows.column("x"))[order]
            for cluster, own, c, reach in zip(places.column("cluster_id").to_pylist(), places.column("ts").to_pylist(), _matrix(places.column("c")), places.column("reach").to_numpy(), strict=True):
                a, b = np.searchsorted(at, [own[0], own[-1] + 1])
                d2 = np.zeros(b - a)
                for i in range(dims):
                    d2 += (x[a:b, i] - c[i]) * (x[a:b, i] - c[i])
                before = np.cumsum(np.sqrt(d2) > (delta + reach) * (1 + 1e-12) + 1e-12)
                clusters += [cluster] * len(own)
                ts += own
                segments += before[np.searchsorted(at[a:b], own)].tolist()
        sensor, series = ([places.column(k)[0].as_py()] * len(ts) if ts else [] for k in keys)
        return pa.table({"sensor": pa.array(sensor, pa.string()), "cluster_id": pa.array(clusters, pa.int64()), "series_id": pa.array(series, pa.int64()), "t": pa.array(ts, pa.int64()), "segment": pa.array(segments, pa.int64())})

    places, windows = (df.select(*[F.col(c).alias(c) for c in df.columns]) for df in (places, reduced.select(*keys, "t", "x")))
    out = places.groupBy(*keys).cogroup(windows.groupBy(*keys)).applyInArrow(fn, "sensor string, cluster_id long, series_id long, t long, segment long")
    return out, [*CLUSTER, "series_id", "segment"]


def _dims(df: DataFrame) -> int:
    row = df.select(F.size("x").alias("d")).first()
    return row.d if row else 1


def drop_trivial_closest(assigned: DataFrame, gap: int) -> DataFrame:
    """Of members of a cluster that follow each other by at most gap steps, the one nearest to the centroid."""
    order = Window.partitionBy(*CLUSTER, "series_id").orderBy("t")
    island = F.sum(F.when(F.col("t") - F.lag("t").over(order) > gap, 1).otherwise(0)).over(order)
    ranked = assigned.withColumn("island", island).withColumn("rank", F.row_number().over(Window.partitionBy(*CLUSTER, "series_id", "island").orderBy("dist", "t")))
    return ranked.where("rank = 1").drop("island", "rank")


def split_levels(group: DataFrame, eps: float = 0.5, min_pts: int = 2, s: int = 0) -> DataFrame:
    """Group-motifs split by the level of their windows (density clustering on a line); parts with more than s members.

    Levels are compared at nine decimals. A row with min_pts rows within eps, itself included, is a core; cores within eps of
    each other share a level; other rows go to the nearest core within eps, ties to the lower; the rest leave the motif."""
    eps = round(eps * 1e9)
    rows = group.withColumn("lv", F.round(F.col("level") * 1e9).cast("long"))
    order = Window.partitionBy(*CLUSTER).orderBy("lv")
    # rows within eps of one follow each other: there are min_pts of them if that many in a row, with it among them, are near
    around = lambda i: F.col("lv") if not i else F.lead("lv", i).over(order) if i > 0 else F.lag("lv", -i).over(order)
    spans = [(F.col("lv") - around(i - min_pts + 1) <= eps) & (around(i) - F.col("lv") <= eps) for i in range(min_pts)]
    rows = rows.withColumn("core", reduce(Column.__or__, [F.coalesce(c, F.lit(False)) for c in spans]) if min_pts > 0 else F.lit(True))
    cores = rows.where("core").select(*CLUSTER, "lv").distinct()
    jump = F.when(F.col("lv") - F.lag("lv").over(order) > eps, 1).otherwise(0)
    cores = cores.withColumn("jump", jump).withColumn("level_id", F.sum("jump").over(order).cast("long")).drop("jump")
    ladder = rows.join(cores.withColumn("own", F.col("lv")), [*CLUSTER, "lv"], "left")
    below = order.rowsBetween(Window.unboundedPreceding, 0)
    above = Window.partitionBy(*CLUSTER).orderBy(F.desc("lv")).rowsBetween(Window.unboundedPreceding, 0)  # a frame that only grows is read once
    pick = lambda w: F.last(F.when(F.col("own").isNotNull(), F.struct("own", "level_id")), ignorenulls=True).over(w)
    ladder = ladder.withColumn("lo", pick(below)).withColumn("hi", pick(above))
    dlo, dhi = F.col("lv") - F.col("lo.own"), F.col("hi.own") - F.col("lv")
    use_lo = F.col("lo").isNotNull() & (dlo <= eps) & (F.col("hi").isNull() | (dlo <= dhi))
    level = F.when(use_lo, F.col("lo.level_id")).when(F.col("hi").isNotNull() & (dhi <= eps), F.col("hi.level_id"))
    out = ladder.withColumn("level_id", level).where("level_id is not null").drop("lv", "core", "own", "lo", "hi")
    big = out.groupBy(*CLUSTER, "level_id").agg(F.count("*").alias("c")).where(F.col("c") > s).drop("c")
    return out.join(big, [*CLUSTER, "level_id"], "left_semi")


def is_frequent(members: DataFrame, s: int) -> DataFrame:
    """(sensor, cluster_id, support, frequent) of clusters without trivial members: more than s are left."""
    return members.groupBy(*CLUSTER).agg(F.count("*").alias("support")).withColumn("frequent", F.col("support") > s)


def raw_levels(group: DataFrame, moments: DataFrame) -> DataFrame:
    """Members with the level in the units of the series, from the moments (n, s, q) of the runs; runs without a row are left out."""
    square = F.col("n").cast("decimal(38,0)") * F.col("q") - F.col("s").cast("decimal(38,0)") * F.col("s")
    m = moments.select("sensor", "series_id", F.sqrt(square.cast("double")).alias("_dev"), F.col("s").cast("double").alias("_sum"), F.col("n").cast("double").alias("_n"))
    return group.join(m, ["sensor", "series_id"]).withColumn("level", (F.col("level") * F.col("_dev") + F.col("_sum")) / F.col("_n")).select(*group.columns)


def motifs(occurrences: DataFrame, d: int, places: DataFrame | None = None) -> DataFrame:
    """MOTIFS from the members of final motifs; places: the same members without vectors. Centroids come from a second pass, which is left out
    where they are not asked for."""
    keys = ["sensor", F.col("cluster_id").alias("motif_id"), "level_id"]
    thin = (places or occurrences).groupBy(*keys).agg(F.count("*").alias("support"), F.count_distinct("series_id").alias("runs"), F.min("level").alias("level_lo"), F.max("level").alias("level_hi"))
    mean = occurrences.groupBy(*keys).agg(F.array(*[F.avg(F.col("x")[i]) for i in range(d)]).alias("centroid"), F.avg("dist").alias("mean_dist"))
    return thin.join(mean, ["sensor", "motif_id", "level_id"], "left").select("sensor", "motif_id", "level_id", "support", "runs", "centroid", "level_lo", "level_hi", "mean_dist")
