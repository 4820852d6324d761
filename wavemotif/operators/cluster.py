"""Bounded-sphere clustering of candidate vectors, sequential, by CF-tree, by hash buckets, and in parallel.

A vector joins the nearest centroid of a candidate set if it is nearer than R, and the centroid moves to the mean; otherwise it
opens a cluster. The methods differ in the candidate set. Sequential insertion is imperative state, so it runs in one Arrow task a
group, through which the rows of a whole sensor only pass where the state holds no vectors; the parallel forms keep that state to a shard or a bucket and merge with DataFrame operations.
Cluster ids of one group count from 0 in the order of opening.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wavemotif.functions.vectors import cf_sum, dot, fixed_planes, sq_dist

#: Rows of a bucket that one task clusters; a larger bucket is dealt in parts, whose centres the merge brings together.
PART_ROWS = 20_000
#: Largest number of such buckets whose names are broadcast.
BROADCAST_HOT = 100_000
#: Largest number of cells of vectors (some 100 bytes each) that grid_near broadcasts.
GRID_BROADCAST = 100_000
NUMBER_BINS = 1024
#: Share of the squared lengths that bounds the rounding of a distance by a product of up to some hundred values.
SLACK = 1e-12
ASSIGNED = "sensor string, series_id long, t long, x array<double>, level double, cluster_id long, dist double, evals long"


def closest(c: np.ndarray, h: np.ndarray, x: np.ndarray, top: float) -> tuple[int, float]:
    """The first nearest row of c to x, and its squared distance. h: squared lengths of c, at most top.

    One product of c and x tells all distances up to rounding; those within that of the least are then computed as they are defined."""
    rough = h - 2.0 * (c @ x)
    near = np.flatnonzero(rough <= rough.min() + SLACK * (top + float(x @ x)))
    d2 = ((c[near] - x) ** 2).sum(axis=1)
    i = int(d2.argmin())
    return int(near[i]), float(d2[i])


def closest_of_all(x: np.ndarray, c: np.ndarray, rows: int = 256) -> np.ndarray:
    """For each row of x the first nearest row of c, as closest() gives it."""
    h, out = (c * c).sum(axis=1), np.empty(len(x), np.int64)
    top = float(h.max())
    for a in range(0, len(x), rows):
        part = x[a : a + rows]
        rough = h - 2.0 * (part @ c.T)
        near = rough <= (rough.min(axis=1) + SLACK * (top + (part * part).sum(axis=1)))[:, None]
        out[a : a + rows] = near.argmax(axis=1)
        for i in np.flatnonzero(near.sum(axis=1) > 1):
            k = np.flatnonzero(near[i])
            out[a + i] = k[((c[k] - part[i]) ** 2).sum(axis=1).argmin()]
    return out


class Spheres:
    """Centroids as running sums."""

    def __init__(self, d: int, r: float, frozen: bool = False):
        self.r2, self.frozen, self.k, self.evals = r * r, frozen, 0, 0
        self.sum, self.n, self.c = np.zeros((64, d)), np.zeros(64), np.zeros((64, d))
        self.h, self.top = np.zeros(64), 0.0  # squared lengths of the centroids and their largest so far

    def nearest(self, x: np.ndarray, among: np.ndarray | None = None) -> tuple[int, float]:
        c, h = (self.c[: self.k], self.h[: self.k]) if among is None else (self.c[among], self.h[among])
        self.evals += len(c)
        if not len(c):
            return -1, np.inf
        i, d2 = closest(c, h, x, self.top)
        return (i if among is None else int(among[i])), d2

    def place(self, i: int, c: np.ndarray) -> None:
        self.c[i], self.h[i] = c, c @ c
        self.top = max(self.top, float(self.h[i]))

    def open(self, x: np.ndarray, n: float = 1) -> int:
        if self.k == len(self.n):
            self.sum, self.n, self.c, self.h = (np.concatenate([a, np.zeros_like(a)]) for a in (self.sum, self.n, self.c, self.h))
        i, self.k = self.k, self.k + 1
        self.sum[i], self.n[i] = n * x, n
        self.place(i, x)
        return i

    def add(self, i: int, x: np.ndarray, n: float = 1) -> None:
        self.sum[i] += n * x
        self.n[i] += n
        if not self.frozen:
            self.place(i, self.sum[i] / self.n[i])

    def insert(self, x: np.ndarray, among: np.ndarray | None = None, n: float = 1) -> int:
        """The cluster of x; n: how many vectors x is the centroid of, inserted whole."""
        i, d2 = self.nearest(x, among)
        if d2 < self.r2:
            self.add(i, x, n)
            return i
        return self.open(x, n)


def insert_all(x: np.ndarray, r: float, frozen: bool = False, features: np.ndarray | None = None, **_) -> tuple[np.ndarray, int]:
    """features: as of insert_cftree."""
    s = Spheres(x.shape[1], r, frozen)
    return np.array([s.insert(v, n=1 if features is None else features[i, 0]) for i, v in enumerate(x)], np.int64), s.evals


def insert_point_link(x: np.ndarray, r: float, **_) -> tuple[np.ndarray, int]:
    """Joins the cluster of the nearest vector seen, if nearer than r."""
    ids, evals = np.zeros(len(x), np.int64), 0
    h = (x * x).sum(axis=1)
    k, top = 0, float(h.max(initial=0.0))
    for i, v in enumerate(x):
        evals += i
        j, d2 = closest(x[:i], h[:i], v, top) if i else (-1, np.inf)
        if d2 < r * r:
            ids[i] = ids[j]
        else:
            ids[i], k = k, k + 1
    return ids, evals


def insert_hashed(x: np.ndarray, r: float, sets: int = 5, per_set: int = 3, family: str = "sign", width: float = 4.0, rehash: bool = False, **_) -> tuple[np.ndarray, int]:
    """Candidates are the centroids that share a bucket; a centroid is hashed when it is opened."""
    planes = np.array(fixed_planes(sets, per_set, x.shape[1]), float)

    names: list[dict] = [{} for _ in range(sets)]

    def keys(v: np.ndarray) -> np.ndarray:
        """A number for the bucket of v in each set."""
        p = planes @ v
        p = p >= 0 if family == "sign" else np.floor(p / (width * np.linalg.norm(planes, axis=2)))
        return np.array([of.setdefault(tuple(row), len(of)) for of, row in zip(names, p.tolist(), strict=True)])

    s, ids = Spheres(x.shape[1], r), np.zeros(len(x), np.int64)
    bucket, held = np.zeros((sets, 64), np.int64), np.zeros(64, np.int64)  # entries in order: their buckets, and the centroid they are of
    n, of = 0, {}
    for i, v in enumerate(x):
        own = keys(v)
        among = held[:n][(bucket[:, :n] == own[:, None]).any(axis=0)]
        before = s.k
        ids[i] = s.insert(v, np.unique(among) if rehash else among)
        if s.k > before or rehash:
            again = own if s.k > before else keys(s.c[ids[i]])
            seen = of.setdefault(int(ids[i]), set()) if rehash else ()
            if tuple(again) in seen:
                continue
            if rehash:
                seen.add(tuple(again))
            if n == len(held):
                bucket, held = np.concatenate([bucket, np.zeros_like(bucket)], axis=1), np.concatenate([held, np.zeros_like(held)])
            bucket[:, n], held[n], n = again, ids[i], n + 1
    return ids, s.evals


class Node:
    """Children in the rows of cf (n, vector sum, squared sum) with their centroids c: nodes, or in a leaf the ids of entries."""

    __slots__ = ("cf", "c", "children", "leaf")

    def __init__(self, d: int, leaf: bool, size: int):
        self.leaf, self.children, self.cf, self.c = leaf, [], np.zeros((size, d + 2)), np.zeros((size, d))

    def put(self, child: Node | int, cf: np.ndarray) -> None:
        k = len(self.children)
        self.children.append(child)
        self.cf[k], self.c[k] = cf, cf[1:-1] / cf[0]

    def add(self, k: int, one: np.ndarray) -> None:
        cf = self.cf[k]
        cf += one
        np.divide(cf[1:-1], cf[0], out=self.c[k])

    def nearest(self, v: np.ndarray) -> tuple[int, float]:
        gap = self.c[: len(self.children)] - v
        d2 = np.add.reduce(np.multiply(gap, gap, out=gap), axis=1)
        k = int(d2.argmin())
        return k, d2[k]

    def split(self) -> tuple[tuple[Node, np.ndarray], tuple[Node, np.ndarray]]:
        """Two nodes around the children farthest apart, each with its sum."""
        c, size = self.c[: len(self.children)], len(self.cf)
        gap = ((c[:, None] - c[None]) ** 2).sum(axis=2)
        a, b = np.unravel_index(gap.argmax(), gap.shape)
        out = [(Node(c.shape[1], self.leaf, size), np.zeros(self.cf.shape[1])) for _ in range(2)]
        for k, child in enumerate(self.children):
            to, total = out[0 if gap[k, a] <= gap[k, b] else 1]
            to.put(child, self.cf[k])
            total += self.cf[k]
        return out[0], out[1]


class CFTree:
    """Descends by the nearest child centroid to one leaf entry; absorbs there, or opens an entry and splits full nodes. Holds clustering
    features only, no vector."""

    def __init__(self, d: int, r: float, branching: int = 50, absorb: str = "centroid", **_):
        self.r2, self.branching, self.absorb, self.d = r * r, branching, absorb, d
        self.root, self.evals, self.opened = Node(d, True, branching + 1), 0, 0

    def insert(self, v: np.ndarray, one: np.ndarray | None = None) -> int:
        """The entry of v; one: the row (n, vector sum, squared sum) to insert whole, with v its centroid."""
        one = np.concatenate([[1.0], v, [float(v @ v)]]) if one is None else one
        path, node = [], self.root
        while not node.leaf:
            self.evals += len(node.children)
            k, _ = node.nearest(v)
            path.append((node, k))
            node = node.children[k]
        entry = -1
        if node.children:
            self.evals += len(node.children)
            k, d2 = node.nearest(v)
            if self.absorb == "centroid":
                near = d2 < self.r2
            else:
                after = node.cf[k] + one
                m = after[1:-1] / after[0]
                near = after[-1] / after[0] - m @ m <= self.r2
            if near:
                node.add(k, one)
                entry = node.children[k]
        for parent, k in path:
            parent.add(k, one)
        if entry >= 0:
            return entry
        entry, self.opened = self.opened, self.opened + 1
        node.put(entry, one)
        while len(node.children) > self.branching:
            left, right = node.split()
            if not path:
                self.root = Node(self.d, False, self.branching + 1)
                self.root.put(*left)
                self.root.put(*right)
                break
            parent, k = path.pop()
            children, cfs = parent.children, parent.cf[: len(parent.children)].copy()
            parent.children = children[:k]
            parent.put(*left)
            parent.put(*right)
            for child, cf in zip(children[k + 1 :], cfs[k + 1 :], strict=True):
                parent.put(child, cf)
            node = parent
        return entry


def insert_cftree(x: np.ndarray, r: float, branching: int = 50, absorb: str = "centroid", features: np.ndarray | None = None, **_) -> tuple[np.ndarray, int]:
    """Inserts all rows in a CFTree. features: rows (n, vector sum, squared sum) to insert whole, with x their centroids; else each vector
    counts once."""
    tree = CFTree(x.shape[1], r, branching, absorb)
    return np.array([tree.insert(v, None if features is None else features[i]) for i, v in enumerate(x)], np.int64), tree.evals


METHODS: dict[str, Callable[..., tuple[np.ndarray, int]]] = {"all": insert_all, "point": insert_point_link, "hash": insert_hashed, "cftree": insert_cftree}


def means_of(x: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """The mean of each cluster 0, 1, ..."""
    k = int(ids.max()) + 1
    c = np.zeros((k, x.shape[1]))
    np.add.at(c, ids, x)
    return c / np.bincount(ids, minlength=k)[:, None]


class AllSpheres(Spheres):
    """Spheres that look at all centroids, with the options that insert_all takes."""

    def __init__(self, d: int, r: float, frozen: bool = False, **_):
        super().__init__(d, r, frozen)


#: Methods whose state holds clusters and no vectors, so that a group may be of any size.
STREAMED: dict[str, Callable[..., AllSpheres | CFTree]] = {"all": AllSpheres, "cftree": CFTree}


def streams(method: str, group: tuple[str, ...] = ("sensor",), order: str = "time", refine: bool = False, recluster: int = 0, **_) -> bool:
    """Whether cluster() lets rows pass by: groups of many runs, in an order that needs no count, in one pass."""
    return method in STREAMED and "series_id" not in group and order != "random" and not refine and not recluster


def cluster_stream(rows: DataFrame, method: str, group: tuple[str, ...], order: str, **options) -> DataFrame:
    """ASSIGNED as by cluster(): rows (with r) pass in order through the task of their group, which keeps the clusters and no row.

    Rows with their ids are stored; the distance to the mean and the group's evals are joined only where they are asked for."""
    mixed = F.pmod(F.col("t") * 7919 + 13, F.lit(104_729))
    by = [mixed, F.col("t"), F.col("series_id")] if order == "hash" else [F.col("series_id"), F.col("t")]
    make = STREAMED[method]

    def fn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, state = None, None
        for batch in batches:
            if not len(batch):
                continue
            x = np.asarray(batch.column("x").flatten()).reshape(len(batch), -1)
            keys = [batch.column(k).to_numpy(zero_copy_only=False) for k in group]
            new = np.zeros(len(batch), bool)
            for k in keys:
                new[1:] |= k[1:] != k[:-1]
            ids, evals = np.empty(len(batch), np.int64), np.empty(len(batch), np.int64)
            starts = [0, *np.flatnonzero(new).tolist(), len(batch)]
            for a, b in zip(starts[:-1], starts[1:], strict=True):
                own = tuple(k[a] for k in keys)
                if state is None or own != now:
                    now, state = own, make(x.shape[1], batch.column("r")[a].as_py(), **options)
                for i in range(a, b):
                    ids[i] = state.insert(x[i])
                    evals[i] = state.evals
            kept = batch.select(["sensor", "series_id", "t", "x", "level"])
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(ids), pa.array(evals)], [*kept.schema.names, "cluster_id", "evals"])

    ordered = rows.repartition(*group).sortWithinPartitions(*group, *by)
    placed = stored(ordered.mapInArrow(fn, "sensor string, series_id long, t long, x array<double>, level double, cluster_id long, evals long"))
    keys, d = [*group, "cluster_id"], _width(placed)
    sums = placed.groupBy(*keys).agg(cf_sum(F.col("x"), d).alias("cf"))
    means = sums.select(*keys, F.transform("cf.ls", lambda v: v / F.col("cf.n")).alias("c"))
    evals = placed.groupBy(*group).agg(F.max("evals").alias("evals"))
    return placed.drop("evals").join(means, keys, "left").join(evals, list(group), "left").select("sensor", "series_id", "t", "x", "level", "cluster_id", F.sqrt(sq_dist("x", "c", d)).alias("dist"), "evals")


def point_link(rows: DataFrame) -> DataFrame:
    """ASSIGNED as by cluster(): the nearest vector seen does not depend on the clusters, so rows (with r) meet in pairs of blocks; one task a
    sensor then follows the links, with a few numbers a row."""
    from wavemotif.operators.blocks import LEAST_ROWS, nearest_rows  # which builds on this module

    d, rows = _width(rows), stored(rows)
    along = haar_cells("x", 1.0, d, 1, whole=False)[0] if d > 1 else F.col("x")[0]
    side = F.greatest(F.first("r") * (1 + 1e-9), (F.max("p") - F.min("p")) * LEAST_ROWS / F.count("*"))  # bins need not be narrower than a block
    reach = rows.withColumn("p", along).groupBy("sensor").agg(F.first("r").alias("reach"), side.alias("side")).transform(cut)
    binned = rows.join(F.broadcast(reach), "sensor").withColumn("bin", F.floor(along / F.col("side")).cast("long"))
    near = nearest_rows(binned, None, 1, reach.drop("side"), F.col("bin")).groupBy("sensor", "series_a", "t_a").agg(F.min(F.struct("d2", "series_b", "t_b")).alias("m"))
    near = near.select("sensor", F.col("series_a").alias("series_id"), F.col("t_a").alias("t"), "m.series_b", "m.t_b")

    def follow(group: pa.Table) -> pa.Table:
        s, t, s2, t2 = (group.column(c).to_numpy() for c in ("series_id", "t", "series_b", "t_b"))
        order = np.lexsort((t, s))
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        linked = np.flatnonzero(group.column("series_b").is_valid().to_numpy())
        both = np.lexsort((np.concatenate([np.zeros(len(s), np.int8), np.ones(len(linked), np.int8)]), np.concatenate([t, t2[linked].astype(np.int64)]), np.concatenate([s, s2[linked].astype(np.int64)])))
        asks = both >= len(s)
        to = np.arange(len(s))
        to[rank[linked[both[asks] - len(s)]]] = (np.cumsum(~asks) - 1)[asks]
        while (to[to] != to).any():
            to = to[to]
        ids = (np.cumsum(to == np.arange(len(to))) - 1)[to]
        return pa.table({"sensor": group.column("sensor"), "series_id": s, "t": t, "cluster_id": ids[rank], "evals": np.full(len(s), len(s) * (len(s) - 1) // 2)})

    place = ["sensor", "series_id", "t"]
    ids = rows.select(*place).join(near, place, "left").groupBy("sensor").applyInArrow(follow, "sensor string, series_id long, t long, cluster_id long, evals long")
    placed = stored(rows.drop("r").join(ids, place))
    means = placed.groupBy("sensor", "cluster_id").agg(cf_sum(F.col("x"), d).alias("cf")).select("sensor", "cluster_id", F.transform("cf.ls", lambda v: v / F.col("cf.n")).alias("c"))
    return placed.join(means, ["sensor", "cluster_id"], "left").select(*place, "x", "level", "cluster_id", F.sqrt(sq_dist("x", "c", d)).alias("dist"), "evals")


def _width(df: DataFrame) -> int:
    row = df.select(F.size("x").alias("d")).first()
    return row.d if row else 1


def cluster(cand: DataFrame, r: float | DataFrame = 1.0, method: str = "all", group: tuple[str, ...] = ("sensor",), order: str = "time", seed: int = 0, refine: bool = False, recluster: int = 0, rejoin: bool = False, **options) -> DataFrame:
    """ASSIGNED: cluster_id and distance to the final centroid of every candidate; evals is the group's number of distances.

    r: one radius, or a table (sensor, r); sensors without a row are left out. recluster: passes in which members r or farther from
    the final centroid leave their cluster and are clustered among themselves. refine: each vector ends at the nearest centroid.
    rejoin: clusters of a sensor that came to lie within each other's radius are joined after the pass, see rejoined().
    """
    if rejoin:
        return rejoined(cluster(cand, r, method, group, order, seed, refine, recluster, **options), r, method, **options)
    insert = METHODS[method]
    rows = cand.select("sensor", "series_id", "t", "x", "level")
    rows = rows.join(r.select("sensor", "r"), "sensor") if isinstance(r, DataFrame) else rows.withColumn("r", F.lit(float(r)))
    if streams(method, group, order, refine, recluster):
        return cluster_stream(rows, method, group, order, **options)
    if method == "point" and group == ("sensor",) and order == "time" and not refine and not recluster:
        return point_link(rows)

    def fn(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["series_id", "t"], ignore_index=True)
        if order == "random":
            rows = rows.iloc[np.random.default_rng(seed).permutation(len(rows))].reset_index(drop=True)
        elif order == "hash":
            rows = rows.iloc[np.lexsort((rows.t, (rows.t * 7919 + 13) % 104_729))].reset_index(drop=True)
        x, radius = np.array(rows.x.tolist(), float), float(rows.r.iloc[0])
        ids, evals = insert(x, radius, **options)
        c = means_of(x, ids)
        for _ in range(recluster):
            out = ((x - c[ids]) ** 2).sum(axis=1) >= radius * radius
            if not out.any():
                break
            again, more = insert(x[out], radius, **options)
            ids[out] = again + len(c)
            ids, evals = np.unique(ids, return_inverse=True)[1], evals + more  # a cluster may have lost all members
            c = means_of(x, ids)
        if refine:
            ids = closest_of_all(x, c)
        rows["cluster_id"], rows["dist"], rows["evals"] = ids, np.sqrt(((x - c[ids]) ** 2).sum(axis=1)), evals
        return rows[["sensor", "series_id", "t", "x", "level", "cluster_id", "dist", "evals"]]

    return rows.groupBy(*group).applyInPandas(fn, ASSIGNED)


def word_clusters(cand: DataFrame, d: int) -> DataFrame:
    """Clusters of equal words: a deterministic grouping in plain DataFrame operations; ids by word within the sensor. Rows with their ids are
    stored; the distance to the mean is joined only where it is asked for."""
    ids = stored(cand.select("sensor", "word").distinct().withColumn("cluster_id", (F.row_number().over(Window.partitionBy("sensor").orderBy("word")) - 1).cast("long")))
    rows = stored(cand.join(ids, ["sensor", "word"]).select("sensor", "series_id", "t", "x", "level", "cluster_id"))
    mean = rows.groupBy("sensor", "cluster_id").agg(cf_sum(F.col("x"), d).alias("cf")).select("sensor", "cluster_id", F.transform("cf.ls", lambda v: v / F.col("cf.n")).alias("c"))
    return rows.join(mean, ["sensor", "cluster_id"], "left").select("sensor", "series_id", "t", "x", "level", "cluster_id", F.sqrt(sq_dist("x", "c", d)).alias("dist"), F.lit(0).cast("long").alias("evals"))


def centers(assigned: DataFrame, d: int) -> DataFrame:
    """CENTERS: sensor, cluster_id, n, centroid."""
    out = assigned.groupBy("sensor", "cluster_id").agg(cf_sum(F.col("x"), d).alias("cf"))
    return out.select("sensor", "cluster_id", F.col("cf.n").alias("n"), F.transform("cf.ls", lambda v: v / F.col("cf.n")).alias("centroid"))


# ---------------------------------------------------------------- parallel
def cut(df: DataFrame) -> DataFrame:
    """Cuts the lineage in the shared checkpoint folder."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors see; a temporary one only where driver and executors are one process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors see")
    return base or tempfile.mkdtemp(prefix="wavemotif-")


def stored(df: DataFrame) -> DataFrame:
    """df written to the shared folder in columns and read back: smaller than cut() for wide rows, and only the columns in use are read again."""
    path = f"{shared_folder(df.sparkSession)}/stage-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.parquet(path)


def not_settled(what: str, rounds: int) -> RuntimeError:
    return RuntimeError(f"{what} did not settle in {rounds} rounds; give max_rounds a larger value")


def bucketed(df: DataFrame, x: str, d: int, sets: int, per_set: int, family: str, width: float) -> DataFrame:
    """df with bucket, a row for each set of planes."""
    planes = np.array(fixed_planes(sets, per_set, d), float).reshape(-1, d)
    unit = np.ones(len(planes)) if family == "sign" else width * np.linalg.norm(planes, axis=1)

    @F.pandas_udf("array<string>")
    def keys(vectors: pd.Series) -> pd.Series:
        side = np.floor(np.array(vectors.tolist(), float).reshape(-1, d) @ planes.T / unit)
        side = (side >= 0).astype(int) if family == "sign" else side.astype(int)
        return pd.Series([[f"{i}:" + "_".join(map(str, row[i * per_set : (i + 1) * per_set])) for i in range(sets)] for row in side.tolist()])

    return df.withColumn("bucket", F.explode(keys(F.col(x))))


def near_matrix(x: np.ndarray, y: np.ndarray, r2: float) -> np.ndarray:
    """Which rows of x and y are nearer than the root of r2. A product tells distances up to rounding; those near the bound are computed as
    sq_dist does."""
    own, h = (x * x).sum(axis=1), (y * y).sum(axis=1)
    rough = own[:, None] + h - 2.0 * (x @ y.T)
    near = rough < r2
    i, j = np.nonzero(np.abs(rough - r2) <= SLACK * (1 + r2 + 4 * float(max(own.max(initial=0.0), h.max(initial=0.0)))))
    d2 = np.zeros(len(i))
    for c in range(x.shape[1]):
        d2 += (x[i, c] - y[j, c]) * (x[i, c] - y[j, c])
    near[i, j] = d2 < r2
    return near


def vectors(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    return np.concatenate([np.empty(0), *[np.asarray(c.flatten()) for c in chunks]]).reshape(len(column), -1)


def dominating(cores: DataFrame, r: float, block: int = 256) -> DataFrame:
    """(sensor, cluster_id, c): centres from the one with most members (of equals the least id) on, unless one before is nearer than r and
    stayed. They pass through one task a sensor, which keeps those that stayed."""
    ordered = cores.select("sensor", "n", "id", "c").repartition("sensor").sortWithinPartitions("sensor", F.desc("n"), "id")

    def fn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, kept, k = None, np.empty((0, 0)), 0
        for batch in batches:
            sensors, x = batch.column("sensor").to_numpy(zero_copy_only=False), vectors(batch.column("c"))
            stay, ids = [], []
            starts = np.flatnonzero(np.concatenate([[True], sensors[1:] != sensors[:-1]])) if len(batch) else []
            for a, b in zip(starts, [*starts[1:], len(batch)], strict=True) if len(batch) else ():
                if sensors[a] != now:
                    now, kept, k = sensors[a], np.empty((1024, x.shape[1])), 0
                for lo in range(a, b, block):
                    at = np.arange(lo, min(b, lo + block))
                    for other in range(0, k, 8192):
                        at = at[~near_matrix(x[at], kept[other : min(k, other + 8192)], r * r).any(axis=1)]
                    near, free = near_matrix(x[at], x[at], r * r), np.ones(len(at), bool)
                    for i in range(len(at)):
                        if free[i]:
                            free[i + 1 :] &= ~near[i, i + 1 :]
                    at = at[free]
                    while k + len(at) > len(kept):
                        kept = np.concatenate([kept, np.empty_like(kept)])
                    kept[k : k + len(at)] = x[at]
                    stay.append(at)
                    ids.append(np.arange(k, k + len(at)))
                    k += len(at)
            if stay:
                part = batch.select(["sensor", "c"]).take(pa.array(np.concatenate(stay)))
                yield pa.RecordBatch.from_arrays([part.column("sensor"), pa.array(np.concatenate(ids)), part.column("c")], ["sensor", "cluster_id", "c"])

    return ordered.mapInArrow(fn, "sensor string, cluster_id long, c array<double>")


def bucket_forest(dealt: DataFrame, r: float, d: int, block: int = 256) -> DataFrame:
    """(sensor, aid, bid): links of centres nearer than r that connect, without cycles, what such links connect within each bucket. Pairs
    stay in the task of the bucket, a block of rows beside those not reached yet."""

    def fn(group: pa.Table) -> pa.Table:
        x, ids = vectors(group.column("c")), group.column("id").to_numpy()
        free, a, b = np.arange(len(x)), [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        while len(free):
            todo, free = [free[:1]], free[1:]
            while todo:
                at = todo.pop()
                for lo in range(0, len(at), block):
                    own = at[lo : lo + block]
                    near = near_matrix(x[own], x[free], r * r)
                    hit = near.any(axis=0)
                    if hit.any():
                        a.append(ids[own[near[:, hit].argmax(axis=0)]])
                        b.append(ids[free[hit]])
                        todo.append(free[hit])
                        free = free[~hit]
        a, b = np.concatenate(a), np.concatenate(b)
        return pa.table({"sensor": pa.array([group.column("sensor")[0].as_py()] * len(a), pa.string()), "aid": pa.array(a), "bid": pa.array(b)})

    return dealt.select("sensor", "bucket", "id", "c").groupBy("sensor", "bucket").applyInArrow(fn, "sensor string, aid long, bid long")


def bucket_nearest(spread: DataFrame, dealt: DataFrame, hot: DataFrame, r: float, d: int) -> DataFrame:
    """(sensor, series_id, t, d2, root): of the centres that share a bucket with a row and are nearer than r, the nearest, ties to the least id."""
    from wavemotif.operators.matching import nearest_within  # which builds on this module

    centres = dealt.select("sensor", "bucket", F.col("id").alias("root"), "c").join(hot, ["sensor", "bucket"], "left")
    centres = centres.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")

    def fn(rows: pa.Table, centres: pa.Table) -> pa.Table:
        root = centres.column("root").to_numpy()
        order = np.argsort(root, kind="stable")
        i, k, d2 = nearest_within(vectors(rows.column("x")), vectors(centres.column("c"))[order], r) if len(rows) and len(root) else (np.empty(0, np.int64),) * 2 + (np.empty(0),)
        part = rows.select(["sensor", "series_id", "t"]).take(pa.array(i))
        return part.append_column("d2", pa.array(d2)).append_column("root", pa.array(root[order][k]))

    rows = spread.select("sensor", "bucket", "part", "series_id", "t", "x")
    rows, centres = (df.select(*[F.col(c).alias(c) for c in df.columns]) for df in (rows, centres))
    on = ["sensor", "bucket", "part"]
    near = rows.groupBy(*on).cogroup(centres.groupBy(*on)).applyInArrow(fn, "sensor string, series_id long, t long, d2 double, root long")
    return near.groupBy("sensor", "series_id", "t").agg(F.min(F.struct("d2", "root")).alias("m")).select("sensor", "series_id", "t", "m.d2", "m.root")


def numbered(df: DataFrame, key: str, name: str) -> DataFrame:
    """df with the numbers 1, 2, .. of its rows a sensor, by a unique key: counts of hashed bins first, so no task sorts more than a bin."""
    binned = df.withColumn("_bin", F.pmod(F.xxhash64(key), F.lit(NUMBER_BINS)))
    before = Window.partitionBy("sensor").orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)
    offsets = binned.groupBy("sensor", "_bin").agg(F.count("*").alias("_n")).select("sensor", "_bin", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    place = F.row_number().over(Window.partitionBy("sensor", "_bin").orderBy(key))
    return binned.withColumn("_place", place).join(offsets, ["sensor", "_bin"]).withColumn(name, F.col("_before") + F.col("_place")).drop("_bin", "_place", "_before")


def cluster_parallel(cand: DataFrame, r: float = 1.0, d: int = 10, sets: int = 10, per_set: int = 8, family: str = "quantised", width: float = 4.0, merge: str = "dominating", max_rounds: int = 50) -> DataFrame:
    """ASSIGNED by bucket-local clustering and a merge.

    dominating: of centres within r the one with most members wins and the others go, until no two are that near; vectors then go
    to the nearest surviving centre within r, else they stay alone (cluster_id below 0), so a member is within r of a fixed
    centre. components: centres within r are one cluster, whatever its extent.
    """
    rows = stored(cand.select("sensor", "series_id", "t", "x", "level"))  # read several times

    def local(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["series_id", "t"])
        x = np.array(group.x.tolist(), float)
        ids, _ = insert_all(x, r)
        k = int(ids.max()) + 1
        c = np.zeros((k, x.shape[1]))
        np.add.at(c, ids, x)
        n = np.bincount(ids, minlength=k)
        return pd.DataFrame({"sensor": group.sensor.iloc[0], "n": n, "c": list(c / n[:, None])})

    spread = bucketed(rows, "x", d, sets, per_set, family, width)
    hot = spread.groupBy("sensor", "bucket").agg(F.ceil(F.count("*") / PART_ROWS).alias("parts")).where("parts > 1").transform(cut)
    hot = F.broadcast(hot) if hot.count() <= BROADCAST_HOT else hot
    spread = spread.join(hot, ["sensor", "bucket"], "left").withColumn("part", F.pmod(F.xxhash64("series_id", "t"), F.coalesce("parts", F.lit(1))))
    cores = spread.groupBy("sensor", "bucket", "part").applyInPandas(local, "sensor string, n long, c array<double>")
    cores = cores.withColumn("id", F.xxhash64(F.col("c"))).dropDuplicates(["sensor", "id"]).transform(cut)
    keyed = rows.withColumn("aid", F.struct("series_id", "t"))
    if merge == "dominating":
        from wavemotif.operators.matching import match  # which builds on this module

        final = dominating(cores, r).select("sensor", F.col("cluster_id").alias("motif_id"), F.col("c").alias("centroid"))
        best = match(rows, final, r, d).select("sensor", F.struct("series_id", "t").alias("aid"), F.col("motif_id").alias("cluster_id"), "dist").transform(cut)
    else:
        dealt = bucketed(cores, "c", d, sets, per_set, family, width)
        links = bucket_forest(dealt, r, d)
        near = links.unionByName(links.select("sensor", F.col("bid").alias("aid"), F.col("aid").alias("bid"))).distinct().transform(cut)
        label = cores.select("sensor", "id", F.col("id").alias("root"))
        for _ in range(max_rounds):
            low = near.join(label.select("sensor", F.col("id").alias("bid"), "root"), ["sensor", "bid"]).groupBy("sensor", F.col("aid").alias("id")).agg(F.min("root").alias("low"))
            after = label.join(low, ["sensor", "id"], "left").select("sensor", "id", F.least("root", F.coalesce("low", "root")).alias("root"))
            jump = after.select("sensor", F.col("id").alias("root"), F.col("root").alias("far"))
            after = after.join(jump, ["sensor", "root"], "left").select("sensor", "id", F.coalesce("far", "root").alias("root")).transform(cut)
            if after.exceptAll(label).isEmpty():
                break
            label = after
        else:
            raise not_settled("the merge of centres", max_rounds)
        roots = label.select("sensor", "root").distinct().withColumn("cluster_id", (F.row_number().over(Window.partitionBy("sensor").orderBy("root")) - 1).cast("long"))
        names = label.join(roots, ["sensor", "root"]).select("sensor", F.col("id").alias("root"), "cluster_id")
        best = bucket_nearest(spread, dealt, hot, r, d).join(names, ["sensor", "root"])
        best = best.select("sensor", F.struct("series_id", "t").alias("aid"), "cluster_id", F.sqrt("d2").alias("dist")).transform(cut)
    # rows without a cluster count down from -1, so no run is too long for its ids
    alone = numbered(keyed.select("sensor", "aid").join(best, ["sensor", "aid"], "left_anti"), "aid", "own").withColumn("own", -F.col("own"))
    out = keyed.join(best, ["sensor", "aid"], "left").join(alone, ["sensor", "aid"], "left")
    return out.select("sensor", "series_id", "t", "x", "level", F.coalesce("cluster_id", "own").alias("cluster_id"), F.coalesce("dist", F.lit(0.0)).alias("dist"), F.lit(0).cast("long").alias("evals"))


def within_radius(joined: DataFrame, r: float, d: int, method: str, **options) -> DataFrame:
    """ASSIGNED of stored rows whose clusters were joined whole, so that some windows lie r or farther from the centroid: those are clustered
    among themselves."""
    place = ["sensor", "series_id", "t"]
    means = centers(joined, d).select("sensor", "cluster_id", "centroid")
    beside = joined.join(means, ["sensor", "cluster_id"]).withColumn("far", sq_dist("x", "centroid", d) >= r * r).drop("centroid").transform(stored)
    again = cluster(beside.where("far"), r, method, **options)
    above = joined.groupBy("sensor").agg((F.max("cluster_id") + 1).alias("above"))
    again = again.join(above, "sensor").select(*place, (F.col("cluster_id") + F.col("above")).alias("own"))
    joined = beside.join(again, place, "left").withColumn("cluster_id", F.coalesce("own", "cluster_id")).drop("own", "far").transform(stored)
    means = centers(joined, d).select("sensor", "cluster_id", "centroid")
    return joined.join(means, ["sensor", "cluster_id"]).select(*place, "x", "level", "cluster_id", F.sqrt(sq_dist("x", "centroid", d)).alias("dist"), "evals")


def rejoined(assigned: DataFrame, r: float, method: str, **options) -> DataFrame:
    """ASSIGNED: clusters of a sensor joined whole where their centroids lie within r.

    The more runs pass by, the more spheres open beside those of a frequent shape and take part of its windows, although in the end the
    centroids lie within each other's radius. So the clusters, a row each, are inserted whole by the same method, the largest first;
    windows that lie r or farther from the centroid then are clustered once more among themselves, so the spheres keep their bound."""
    d = _width(assigned)
    cfs = assigned.groupBy("sensor", "cluster_id").agg(cf_sum(F.col("x"), d).alias("cf")).select("sensor", F.col("cluster_id").alias("part"), "cf.n", "cf.ls", "cf.ss")

    def whole(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["n", "part"], ascending=[False, True], ignore_index=True)
        cf = np.column_stack([group.n, np.array(group.ls.tolist(), float), group.ss]).astype(float)
        group["cluster_id"], group["more"] = METHODS[method](cf[:, 1:-1] / cf[:, :1], r, features=cf, **options)
        return group[["sensor", "part", "cluster_id", "more"]]

    ids = cfs.groupBy("sensor").applyInPandas(whole, "sensor string, part long, cluster_id long, more long")
    parts = assigned.withColumnRenamed("cluster_id", "part")
    joined = parts.join(ids, ["sensor", "part"]).select("sensor", "series_id", "t", "x", "level", "cluster_id", (F.col("evals") + F.col("more")).alias("evals")).transform(stored)
    return within_radius(joined, r, d, method, **options)


def cluster_cf_shards(cand: DataFrame, r: float = 1.0, d: int = 10, shards: int = 64, branching: int = 50, absorb: str = "centroid") -> DataFrame:
    """ASSIGNED by CF-trees of shards and one tree over their clustering features.

    A shard of a sensor holds windows picked by a hash of their place and builds a tree of its own. Clustering features add up,
    so those of all shards are inserted whole in one tree a sensor, which sees a row a shard cluster and no window. A window
    follows its shard cluster, unless it lies r or farther from the centroid then: those are clustered once more among themselves. As
    elsewhere, members may end farther than r from the final centroid, but few do.
    """
    rows = cand.select("sensor", "series_id", "t", "x", "level").withColumn("shard", F.pmod(F.xxhash64("series_id", "t"), F.lit(shards)))

    def local(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["series_id", "t"], ignore_index=True)
        group["part"], group["evals"] = insert_cftree(np.array(group.x.tolist(), float), r, branching, absorb)
        return group

    def whole(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["shard", "part"], ignore_index=True)
        cf = np.column_stack([group.n, np.array(group.ls.tolist(), float), group.ss]).astype(float)
        group["cluster_id"], group["more"] = insert_cftree(cf[:, 1:-1] / cf[:, :1], r, branching, absorb, cf)
        return group[["sensor", "shard", "part", "cluster_id", "more"]]

    placed = rows.groupBy("sensor", "shard").applyInPandas(local, "sensor string, series_id long, t long, x array<double>, level double, shard long, part long, evals long").transform(cut)
    cfs = placed.groupBy("sensor", "shard", "part").agg(cf_sum(F.col("x"), d).alias("cf")).select("sensor", "shard", "part", "cf.n", "cf.ls", "cf.ss")
    ids = cfs.groupBy("sensor").applyInPandas(whole, "sensor string, shard long, part long, cluster_id long, more long")
    joined = placed.join(ids, ["sensor", "shard", "part"]).select("sensor", "series_id", "t", "x", "level", "cluster_id", (F.col("evals") + F.col("more")).alias("evals")).transform(stored)
    return within_radius(joined, r, d, "cftree", branching=branching, absorb=absorb)


def haar_cells(x: str, side: float, d: int, q: int, whole: bool = True) -> list[Column]:
    """Cells of a side over the first q projections on orthonormal Haar differences, or where in units of it they lie; no distance is shorter
    than its projections."""
    half = d // 2
    rows = [[1.0] * m + [-1.0] * m + [0.0] * (d - 2 * m) for m in (half, half // 2)[:q] if m]
    at = [dot(F.col(x), [w / sum(v * v for v in row) ** 0.5 for w in row]) / side for row in rows]
    return [F.floor(p).cast("long") for p in at] if whole else at


def grid_near(a: DataFrame, b: DataFrame, eps: float, d: int, q: int = 2, limit: int = GRID_BROADCAST, part_rows: int = PART_ROWS) -> DataFrame:
    """a(sensor, x, ..) beside b(sensor, y, ..) with d2, for all pairs of a sensor at distance eps or less.

    A row of a meets the rows of b in 3**q cells around it. Cells of b go to the executors while they are at most limit rows;
    beyond that both sides are shuffled, and rows of a in a cell with more than part_rows are dealt in parts, each beside all of b there.
    """
    side = eps * (1 + 1e-9)
    left, right, on = a, b, ["sensor"]
    for i, (mine, other) in enumerate(zip(haar_cells("x", side, d, q), haar_cells("y", side, d, q), strict=True)):
        left = left.withColumn(f"_c{i}", mine)
        right = right.withColumn("_at", other).withColumn(f"_c{i}", F.explode(F.array(F.col("_at") - 1, F.col("_at"), F.col("_at") + 1))).drop("_at")
        on.append(f"_c{i}")
    if limit and right.limit(limit + 1).count() <= limit:
        pairs = left.join(F.broadcast(right), on)
    else:
        hot = left.groupBy(*on).agg(F.ceil(F.count("*") / part_rows).alias("_parts")).where("_parts > 1").transform(cut)
        hot = F.broadcast(hot) if hot.count() <= BROADCAST_HOT else hot
        left = left.join(hot, on, "left").withColumn("_part", F.pmod(F.xxhash64(*a.columns), F.coalesce("_parts", F.lit(1)))).drop("_parts")
        right = right.join(hot, on, "left").withColumn("_part", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("_parts", F.lit(1)) - 1))).drop("_parts")
        on = [*on, "_part"]
        pairs = left.join(right, on)
    return pairs.withColumn("d2", sq_dist("x", "y", d)).where(F.col("d2") <= eps * eps).drop(*on[1:])


def eps_join(a: DataFrame, eps: float, d: int, method: str = "grid", q: int = 2) -> DataFrame:
    """(sensor, aid, bid) for pairs aid < bid of one sensor at distance <= eps, by grid_near or, as its baseline, by all pairs."""
    left, right = a.select("sensor", F.col("id").alias("aid"), "x"), a.select("sensor", F.col("id").alias("bid"), F.col("x").alias("y"))
    if method == "brute":
        return left.join(right, "sensor").where((F.col("aid") < F.col("bid")) & (sq_dist("x", "y", d) <= eps * eps)).select("sensor", "aid", "bid")
    return grid_near(left, right, eps, d, q, limit=0).where("aid < bid").select("sensor", "aid", "bid")
