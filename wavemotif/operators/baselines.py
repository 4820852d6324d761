"""Methods to compare with: closest pairs, iterative closest-pair grouping, agglomeration, k-means, density clustering.

The pair searches are quadratic by nature and meant for short inputs; runs do not mix with overlapping windows of themselves.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from wavemotif.functions.vectors import sq_dist
from wavemotif.operators.blocks import LEAST_ROWS, MOST_ROWS, OWN, Block, Near, connected, dealt, forest, met, nearest_pair
from wavemotif.operators.cluster import ASSIGNED, SLACK, cut, haar_cells, not_settled, stored, vectors
from wavemotif.operators.linkage import complete_linkage, single_linkage

#: Rows on each side of one task of the density search.
BLOCK_ROWS = 16_384


def least_pairs(a: DataFrame, b: DataFrame, keys: list[str], d: int, exclusion: int, block: int | None = None, reach: DataFrame | None = None) -> DataFrame:
    """PAIR: the nearest free pair of rows, for each pair of blocks that rows of a sensor are dealt in; a and b are one table with sensor,
    series_id, t and x. keys: sensor and, if given, a bin, whose rows meet those of it and of the next ones. reach: (sensor, reach), beyond which no
    pair can be the nearest."""
    if a is not b:
        raise ValueError("rows meet those of their own table")
    rows = a.select("sensor", "series_id", "t", "x", *keys[1:])

    def fn(u: Block, v: Block, reach: float = np.inf) -> pa.Table:
        best = nearest_pair(u, v, exclusion, reach, along if reach < np.inf else None)
        return pa.table([pa.array([c], t) for c, t in zip(best, kinds, strict=True)], ["d2", "series_a", "t_a", "series_b", "t_b"]) if best else pa.table({"d2": pa.array([], pa.float64())})

    kinds = (pa.float64(), *[pa.int64()] * 4)
    size = {} if block is None else {"least": block, "most": block}
    got = met(rows.drop(*keys[1:]) if len(keys) == 1 else rows, ["series_id", "t"], fn, "d2 double, series_a long, t_a long, series_b long, t_b long", F.col(keys[1]) if len(keys) > 1 else None, reach=reach, **size)
    return got.select("sensor", "series_a", "t_a", "series_b", "t_b", "d2")


def along(x: np.ndarray) -> np.ndarray:
    """A projection that no distance is shorter than: the difference between both halves of a vector."""
    m = x.shape[1] // 2
    return (x[:, :m].sum(axis=1) - x[:, m : 2 * m].sum(axis=1)) / (2 * m) ** 0.5 if m else x[:, 0]


def closest_pair(win: DataFrame, d: int, exclusion: int, method: str = "brute") -> DataFrame:
    """The nearest two windows of each sensor that do not overlap; ties to the smaller keys.

    reference: distances to one reference window order the windows; a pair nearer than the best one so far cannot lie farther
    apart in that order, so a band join over bins of that width is enough. The best one so far is of pairs that share a block. Either way rows
    meet in blocks, so no task holds a sensor or a bin.
    """
    win = win.select("sensor", "series_id", "t", "x")
    if method == "brute":
        pairs = least_pairs(win, win, ["sensor"], d, exclusion)
    else:
        ref = win.groupBy("sensor").agg(F.min_by("x", F.struct("series_id", "t")).alias("ref"))
        rows = win.join(F.broadcast(ref), "sensor").withColumn("g", F.sqrt(sq_dist("x", "ref", d))).drop("ref").transform(stored)  # a row a sensor
        bound = nearest_in_blocks(rows, exclusion).groupBy("sensor").agg((F.sqrt(F.min("d2")) + 1e-9).alias("bound"))
        span = rows.groupBy("sensor").agg(((F.max("g") - F.min("g")) * LEAST_ROWS / F.count("*")).alias("side"))  # bins need not be narrower than a block
        reach = span.join(bound, "sensor", "left").select("sensor", F.coalesce("bound", F.lit(float("inf"))).alias("reach"), F.greatest("side", F.coalesce("bound", F.lit(float("inf")))).alias("side")).transform(cut)
        rows = rows.join(F.broadcast(reach), "sensor").withColumn("bin", F.floor(F.col("g") / (F.col("side") * (1 + 1e-9))).cast("long")).drop("side", "reach")
        pairs = least_pairs(rows, rows, ["sensor", "bin"], d, exclusion, MOST_ROWS, reach.drop("side"))
    best = pairs.groupBy("sensor").agg(F.min(F.struct("d2", "series_a", "t_a", "series_b", "t_b")).alias("m"))
    return best.select("sensor", "m.series_a", "m.t_a", "m.series_b", "m.t_b", F.col("m.d2").alias("d2"))


def nearest_in_blocks(rows: DataFrame, exclusion: int) -> DataFrame:
    """(sensor, d2): of each block that rows are dealt in, its nearest free pair."""
    parts, _ = dealt(rows.select("sensor", "series_id", "t", "x"), ["sensor"], ["series_id", "t"], LEAST_ROWS, MOST_ROWS, 8)

    def fn(group: pa.Table) -> pa.Table:
        u = Block(group)
        best = nearest_pair(u, u, exclusion, np.inf, along)
        return pa.table({"sensor": group.column("sensor").slice(0, int(best is not None)), "d2": pa.array([best[0]] if best else [], pa.float64())})

    return parts.groupBy("sensor", "part").applyInArrow(fn, "sensor string, d2 double")


def nearest_later(x: np.ndarray, s: np.ndarray, t: np.ndarray, w: int, cells: int = 1 << 21) -> tuple[np.ndarray, np.ndarray]:
    """For each row, of the rows after it that are not less than w steps later in its run: the least squared distance and the first row
    that has it (infinity and -1 without any). Rows are sorted by run and time; a product tells distances up to rounding, the least are computed."""
    n, d = x.shape
    gap, partner = np.full(n, np.inf), np.full(n, -1)
    columns, h = np.ascontiguousarray(x.T), (x * x).sum(axis=1)
    top = float(h.max(initial=0.0))
    end = np.searchsorted(s, s, "right")
    step = max(1, cells // max(1, n))
    for a in range(0, n, step):
        b = min(n, a + step)
        rough = h[a:] - 2.0 * (x[a:b] @ columns[:, a:])
        for i in range(a, b):
            first = i + 1 + int(np.searchsorted(t[i + 1 : end[i]], t[i] + w))
            rough[i - a, : first - a] = np.inf
        least = rough.min(axis=1)
        i, k = np.nonzero(rough <= (least + SLACK * (top + h[a:b]))[:, None])
        i, k = i[np.isfinite(rough[i, k])], k[np.isfinite(rough[i, k])]
        d2 = (columns[0, a + k] - columns[0, a + i]) ** 2
        for c in columns[1:]:
            d2 += (c[a + k] - c[a + i]) ** 2
        order = np.lexsort((k, d2, i))
        if len(order):
            order = order[np.concatenate([[True], i[order][1:] != i[order][:-1]])]
            gap[a + i[order]], partner[a + i[order]] = d2[order], a + k[order]
    return gap, partner


def closest_pair_grouping(win: DataFrame, d: int, w: int, mode: str = "radius", r: float = 1.0, max_groups: int | None = None, bits: int = 6) -> DataFrame:
    """Groups grown from closest pairs, each followed by removal of what it covers, until the rule of the mode ends it; a task a sensor.

    radius: windows nearer than r to the centre of the pair join; it ends when the pair is farther than 2r. description_length: the
    nearest windows join while coding them as differences from the centre saves bits; it ends when the pair itself saves none. Joined
    windows do not overlap. max_groups ends it earlier. Nearest partners are kept; where one was removed, the distance to it is a lower bound, and
    the search is done again only when that bound is the least.
    """

    def fn(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["series_id", "t"], ignore_index=True)
        x, s, t = np.array(rows.x.tolist(), float).reshape(-1, d), rows.series_id.to_numpy(), rows.t.to_numpy()
        columns, levels = np.ascontiguousarray(x.T), 2**bits
        alive, stale = np.ones(len(x), bool), np.zeros(len(x), bool)
        gap, partner = nearest_later(x, s, t, w)

        def saved(diff: np.ndarray) -> float:
            return d * bits - float(np.log2(1 + 2 * np.abs(np.round(diff / 6 * levels))).sum()) - np.log2(alive.sum())

        def search(i: int) -> None:
            d2 = (columns[0, i + 1 :] - columns[0, i]) ** 2
            for c in columns[1:]:
                d2 += (c[i + 1 :] - c[i]) ** 2
            d2[~alive[i + 1 :] | ((s[i + 1 :] == s[i]) & (t[i + 1 :] - t[i] < w))] = np.inf
            k = int(d2.argmin()) if len(d2) else -1
            gap[i], partner[i] = (d2[k], i + 1 + k) if k >= 0 and d2[k] < np.inf else (np.inf, -1)

        out, g = [], 0
        while len(x) and (max_groups is None or g < max_groups):
            a = int(gap.argmin())
            if stale[a] and gap[a] < np.inf:  # its partner is gone: the gap is a lower bound until it is searched again
                stale[a] = False
                search(a)
                continue
            b = partner[a]
            if gap[a] == np.inf or (mode == "radius" and gap[a] > 4 * r * r):
                break
            centre = (x[a] + x[b]) / 2
            if mode == "description_length" and saved(x[a] - centre) + saved(x[b] - centre) <= 0:
                break
            rest = np.flatnonzero(alive)
            dist = np.sqrt(((x[rest] - centre) ** 2).sum(axis=1))
            free, taken = alive.copy(), []
            for k in np.argsort(dist, kind="stable"):
                i = rest[k]
                if mode == "radius" and dist[k] >= r:
                    break
                if not free[i]:
                    continue
                if mode == "description_length" and len(taken) >= 2 and saved(x[i] - centre) <= 0:
                    break
                taken.append(i)
                lo, hi = np.searchsorted(s, s[i]), np.searchsorted(s, s[i], "right")
                free[lo:hi] &= np.abs(t[lo:hi] - t[i]) >= w
            gone = alive & ~free
            if not taken:  # a pair at 2r exactly
                gone[[a, b]] = True
            alive &= ~gone
            gap[gone] = np.inf
            stale |= alive & (partner >= 0) & gone[partner]
            if taken:
                out += [(s[i], t[i], g) for i in taken]
                g += 1
        done = pd.DataFrame(out, columns=["series_id", "t", "group_id"])
        return done.assign(sensor=rows.sensor.iloc[0])[["sensor", "series_id", "t", "group_id"]]

    return win.select("sensor", "series_id", "t", "x").groupBy("sensor").applyInPandas(fn, "sensor string, series_id long, t long, group_id int")


def agglomerate(win: DataFrame, cutoff: float, linkage: str = "complete", group: tuple[str, ...] = ("sensor", "series_id")) -> DataFrame:
    """Hierarchical clustering of each group of its own up to a cutoff; a task a group, which keeps its rows and a short list a cluster, no pairs.

    Clusters are linked while their linkage is below the cutoff, the least first, ties to the least rows; of single linkage the clusters
    are what links below the cutoff connect. evals counts the distances that were met.
    """

    def fn(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("series_id", "ascending"), ("t", "ascending")])
        ids, evals = (complete_linkage if linkage == "complete" else single_linkage)(vectors(rows.column("x")), cutoff)
        ids = np.unique(ids, return_inverse=True)[1].astype(np.int64)
        rows = rows.append_column("cluster_id", pa.array(ids)).append_column("dist", pa.array(np.zeros(len(ids))))
        return rows.append_column("evals", pa.array(np.full(len(ids), evals, np.int64)))

    return win.select("sensor", "series_id", "t", "x", "level").groupBy(*group).applyInArrow(fn, ASSIGNED)


def kmeans_lloyd(cand: DataFrame, k: int, rounds: int, d: int, scale: int = 1_000_000) -> DataFrame:
    """Rounds of k-means from the first k keys; coordinates as scaled integers, so sums do not depend on order.

    k centres are broadcast; sums are combined before the shuffle."""
    rows = cand.select("sensor", "series_id", "t", *[F.round(F.col("x")[i] * scale).cast("long").alias(f"q{i}") for i in range(d)])
    first = rows.orderBy("sensor", "series_id", "t").limit(k).collect()
    centres = [[float(r[f"q{i}"]) for i in range(d)] for r in first]

    def nearest(rows: DataFrame) -> DataFrame:
        best = F.least(*[F.struct(sum(((F.col(f"q{i}") - F.lit(c[i])) * (F.col(f"q{i}") - F.lit(c[i])) for i in range(1, d)), (F.col("q0") - F.lit(c[0])) * (F.col("q0") - F.lit(c[0]))).alias("d2"), F.lit(j).cast("long").alias("c")) for j, c in enumerate(centres)])
        return rows.withColumn("cluster_id", best["c"])

    for _ in range(rounds):
        sums = {r.cluster_id: r for r in nearest(rows).groupBy("cluster_id").agg(F.count("*").alias("n"), *[F.sum(f"q{i}").alias(f"s{i}") for i in range(d)]).collect()}  # k rows
        centres = [[sums[j][f"s{i}"] / sums[j]["n"] for i in range(d)] if j in sums else c for j, c in enumerate(centres)]
    return nearest(rows).select("sensor", "series_id", "t", "cluster_id")


def kmeans_ml(cand: DataFrame, k: int, iters: int = 20, seed: int = 1) -> DataFrame:
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = cand.withColumn("features", array_to_vector("x"))
    model = KMeans(k=k, maxIter=iters, seed=seed).fit(rows)
    return model.transform(rows).select("sensor", "series_id", "t", "x", "level", F.col("prediction").cast("long").alias("cluster_id"))


def near_blocks(rows: DataFrame, eps: float, d: int, fn: Callable[[np.ndarray | Near, pa.Table, pa.Table, bool], pa.Table], schema: str, block: int = BLOCK_ROWS, *, parts: bool = False) -> DataFrame:
    """fn(near, u, v, self) for each pair of blocks of one sensor, near telling which rows of u and v lie within eps; self: u is v. parts: near
    tells it of the rows it is asked for.

    Blocks are parts of cells along one Haar difference; a cell meets itself and the next one. Pairs stay in their task: only what fn makes
    of them leaves it."""
    cell = haar_cells("x", eps * (1 + 1e-9), d, 1)[0] if d > 1 else F.floor(F.col("x")[0] / (eps * (1 + 1e-9)))

    def run(u: Block, v: Block) -> pa.Table:
        near = Near(u, v, eps)
        return fn(near if parts else near(np.arange(u.n), np.arange(v.n)), u.table, v.table, u is v)

    return met(rows, ["id"], run, schema, cell, least=block, most=block)


def counted_alone(rows: DataFrame, eps: float, rows_a_block: int) -> DataFrame:
    """rows with n: how many others of the block it is dealt to lie within eps."""
    dealt_, _ = dealt(rows, ["sensor"], ["id"], rows_a_block, rows_a_block, 1)

    def fn(group: pa.Table) -> pa.Table:
        u = Block(group)
        near, n = Near(u, u, eps), np.empty(u.n, np.int64)
        for a in range(0, u.n, OWN):
            own = np.arange(a, min(u.n, a + OWN))
            n[own] = np.count_nonzero(near(own, np.arange(u.n)), axis=1) - 1
        return group.drop_columns(["part"]).append_column("n", pa.array(n))

    return dealt_.groupBy("sensor", "part").applyInArrow(fn, StructType([*rows.schema.fields, StructField("n", LongType())]))


def dbscan(cand: DataFrame, eps: float, min_pts: int, d: int, max_rounds: int = 100) -> DataFrame:
    """Density clustering: cores have min_pts rows within eps, themselves included; cores within eps share a cluster (its smallest
    id), other rows join the smallest cluster within eps, the rest are noise (null). Pairs are counted where they meet, for rows that no
    block alone shows to be cores; only a forest of the cores' links and the few links of other rows are kept. cand has id, of any type with an
    order, unique over all sensors."""
    kind = cand.schema["id"].dataType.simpleString()
    rows = cand.select("sensor", "id", "x").transform(stored)  # read back, parts of ids may be null, as in what tasks return
    rows = counted_alone(rows, eps, BLOCK_ROWS).select("sensor", "id", "x", (F.col("n") + 1 >= min_pts).alias("core")).transform(stored)

    def flags(*tables: pa.Table) -> list[np.ndarray]:
        return [np.asarray(t.column("core").combine_chunks()).astype(bool) for t in tables]

    def count(near: Near, u: pa.Table, v: pa.Table, self: bool) -> pa.Table:
        parts = []
        for own, other, of in ((u, v, near), (v, u, None))[: 1 if self else 2]:
            i = np.flatnonzero(~flags(own)[0])
            of = of or near.turned(Block(v), Block(u))
            n = np.concatenate([np.empty(0, np.int64), *[np.count_nonzero(of(i[a : a + OWN], np.arange(len(other))), axis=1) for a in range(0, len(i), OWN)]]) - int(self)
            parts.append(pa.table({"id": own.column("id").take(pa.array(i)), "n": pa.array(n, pa.int64())}).filter(pa.array(n > 0)))
        return pa.concat_tables(parts)

    def links(near: Near, u: pa.Table, v: pa.Table, self: bool) -> pa.Table:
        a, b = (np.flatnonzero(c) for c in flags(u, v))
        back = near if self else near.turned(Block(v), Block(u))
        if self:
            _, i, j = connected(near, a)
        else:  # what a block connects is in its own links, so one link of each two components is enough
            i, j = forest(near, back, a, b)
            (own, *_), (other, *_) = connected(Near(Block(u), Block(u), eps), a), connected(Near(Block(v), Block(v), eps), b)
            first = np.unique(own[i] * (len(v) + 1) + other[j], return_index=True)[1]
            i, j = i[first], j[first]
        parts = [pa.table({"a": u.column("id").take(pa.array(i)), "b": v.column("id").take(pa.array(j)), "both": pa.array(np.ones(len(i), bool))})]
        for own, cores, other, of in ((u, b, v, near), (v, a, u, back))[: 1 if self else 2]:
            rest = np.flatnonzero(~flags(own)[0])
            for lo in range(0, len(rest), OWN):
                k, m = np.nonzero(of(rest[lo : lo + OWN], cores))
                parts.append(pa.table({"a": own.column("id").take(pa.array(rest[lo + k])), "b": other.column("id").take(pa.array(cores[m])), "both": pa.array(np.zeros(len(k), bool))}))
        return pa.concat_tables(parts)

    n = near_blocks(rows, eps, d, count, f"id {kind}, n long", parts=True).groupBy("id").agg(F.sum("n").alias("n"))
    rows = rows.join(n, "id", "left").select("sensor", "id", "x", (F.col("core") | (F.coalesce("n", F.lit(0)) + 1 >= min_pts)).alias("core")).transform(stored)
    core = rows.where("core").select("id")
    found = near_blocks(rows, eps, d, links, f"a {kind}, b {kind}, both boolean", parts=True).transform(cut)
    links_ = found.where("both").select("a", "b")
    links_ = links_.unionByName(links_.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().transform(cut)
    label = core.select("id", F.col("id").alias("root"))
    for _ in range(max_rounds):
        low = links_.join(label.select(F.col("id").alias("b"), "root"), "b").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("low"))
        after = label.join(low, "id", "left").select("id", F.least("root", F.coalesce("low", "root")).alias("root"))
        after = after.join(after.select(F.col("id").alias("root"), F.col("root").alias("far")), "root", "left").select("id", F.coalesce("far", "root").alias("root")).transform(cut)
        if after.exceptAll(label).isEmpty():
            break
        label = after
    else:
        raise not_settled("the labels of cores", max_rounds)
    border = found.where("not both").select("a", "b").join(label.select(F.col("id").alias("b"), "root"), "b").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("near"))
    return rows.select("id").join(label, "id", "left").join(border, "id", "left").select("id", F.coalesce("root", "near").alias("cluster_id"))
