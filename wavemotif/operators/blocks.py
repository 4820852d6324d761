"""Rows of a sensor met in pairs of blocks: a block is one packed row, so that a shuffle copies bytes and no rows, and what a pair of blocks
yields stays in its task.

Distances are told by products in single precision up to rounding; those that matter are then computed as they are defined.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from wavemotif.operators.cluster import cut, vectors

#: Share of the squared lengths that bounds the rounding of distances by products in single precision.
ROUGH = 1e-5
#: Rows of a block: at least and at most, and about how many blocks a bin has between the two.
LEAST_ROWS, MOST_ROWS, BLOCKS = 1024, 65_536, 16
#: Rows and columns of the distances held at once.
OWN, COLUMNS = 256, 2048


class Block:
    """Rows of a table, x as a matrix; other columns as attributes."""

    def __init__(self, table: pa.Table, x: np.ndarray | None = None):
        self.table, self.x, self.n = table, vectors(table.column("x")) if x is None else x, len(table)

    def __getattr__(self, name: str) -> np.ndarray:
        value = self.table.column(name).to_numpy()
        setattr(self, name, value)
        return value

    def take(self, rows: np.ndarray) -> Block:
        return Block(self.table.take(pa.array(rows)), self.x[rows])


def unpacked(whole: bytes) -> pa.Table:
    return pa.ipc.open_stream(pa.py_buffer(whole)).read_all()


def dealt(rows: DataFrame, keys: list[str], by: list[str], least: int, most: int, blocks: int) -> tuple[DataFrame, DataFrame]:
    """rows with part, dealt by a hash of the columns by, and (keys, part) of all parts."""
    n = F.count("*")
    full = F.ceil(n / F.greatest(F.lit(least), F.least(F.lit(most), F.ceil(n / blocks))))
    parts = rows.groupBy(*keys).agg(F.when(full > 1, full + 1).otherwise(1).cast("long").alias("_n")).transform(cut)  # one more, as a hash does not deal evenly
    every = parts.select(*keys, F.explode(F.sequence(F.lit(0).cast("long"), F.col("_n") - 1)).alias("part"))
    return rows.join(parts, keys).withColumn("part", F.pmod(F.xxhash64(*by), F.col("_n"))).drop("_n"), every


def met(rows: DataFrame, by: list[str], fn: Callable[..., pa.Table], schema: str, bin_: Column | None = None, least: int = LEAST_ROWS, most: int = MOST_ROWS, blocks: int = BLOCKS, reach: DataFrame | None = None) -> DataFrame:
    """fn(u, v) for each pair of blocks of a sensor's rows in one bin or in bins that follow each other; u is v where a block meets itself. by:
    columns unique in a sensor, by which rows are dealt and sorted. reach: (sensor, reach), a third argument. sensor is added to what fn returns."""
    binned = rows.select("sensor", *[c for c in rows.columns if c != "sensor"], (F.lit(0) if bin_ is None else bin_).cast("long").alias("_bin"))
    parts, every = dealt(binned, ["sensor", "_bin"], by, least, most, blocks)

    def pack(group: pa.Table) -> pa.Table:
        body = group.drop_columns(["sensor", "_bin", "part"]).combine_chunks()
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, body.schema) as out:
            out.write_table(body)
        head = [group.column(c).slice(0, 1) for c in ("sensor", "_bin", "part")]
        return pa.table([*head, pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["sensor", "_bin", "part", "rows"])

    packed = parts.groupBy("sensor", "_bin", "part").applyInArrow(pack, "sensor string, _bin long, part long, rows binary")
    other = every.select("sensor", "_bin", F.struct("_bin", "part").alias("_other"))
    near = [other.select("sensor", (F.col("_bin") + o).alias("_bin"), "_other") for o in (-1, 0, 1)] if bin_ is not None else [other, other.limit(0), other.limit(0)]
    pairs = packed.join(F.broadcast(near[0].unionByName(near[1]).unionByName(near[2])), ["sensor", "_bin"]).withColumn("_own", F.struct("_bin", "part"))
    pairs = pairs.withColumn("_lo", F.least("_own", "_other")).withColumn("_hi", F.greatest("_own", "_other")).withColumn("_first", F.col("_own") == F.col("_lo"))
    if reach is not None:
        pairs = pairs.join(F.broadcast(reach), "sensor")

    def run(group: pa.Table) -> pa.Table:
        first = group.column("_first").to_pylist()
        u = v = None
        for k, is_first in enumerate(first):
            block = Block(unpacked(group.column("rows")[k].as_py()).sort_by([(c, "ascending") for c in by]) if sorts else unpacked(group.column("rows")[k].as_py()))
            u, v = (block, v) if is_first else (u, block)
        self = group.column("_lo")[0].as_py() == group.column("_hi")[0].as_py()
        v = u if self else v
        if u is None or v is None:  # by chance a block may be empty
            return empty
        got = fn(u, v, *((group.column("reach")[0].as_py(),) if reached else ()))
        return got.add_column(0, "sensor", pa.array([group.column("sensor")[0].as_py()] * len(got), pa.string())) if len(got) else empty

    reached = reach is not None
    sorts = all(f.dataType.typeName() in ("long", "integer", "string") for f in rows.select(*by).schema)
    empty = to_arrow_schema(StructType.fromDDL("sensor string, " + schema)).empty_table()
    return pairs.drop("_own", "_other", "_bin", "part").groupBy("sensor", "_lo", "_hi").applyInArrow(run, "sensor string, " + schema)


class Rough:
    """Squared distances of rows of x and y in single precision: tile(a, b, lo, hi) and a bound of their error."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        hx, hy = (x * x).sum(axis=1), (y * y).sum(axis=1)
        one = np.ones
        self.left = np.column_stack([-2.0 * x, hx, one(len(x))]).astype(np.float32)
        self.right = np.ascontiguousarray(np.column_stack([y, one(len(y)), hy]).T.astype(np.float32))
        self.slack = ROUGH * (1 + float(hx.max(initial=0.0)) + float(hy.max(initial=0.0)))
        self.room = np.empty(OWN * COLUMNS, np.float32)

    def tile(self, a: int, b: int, lo: int, hi: int) -> np.ndarray:
        out = self.room[: (b - a) * (hi - lo)].reshape(b - a, hi - lo)
        return np.matmul(self.left[a:b], self.right[:, lo:hi], out=out)


class Near:
    """Which rows of u and v lie within eps: near(i, j) for rows i of u and j of v. A product tells distances up to rounding; those near the
    bound are computed as sq_dist does."""

    def __init__(self, u: Block, v: Block, eps: float, rough: Rough | None = None):
        self.x, self.y, self.e2, self.rough = u.x, v.x, eps * eps, rough or Rough(u.x, v.x)

    def __call__(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out, slack = np.empty((len(i), len(j)), bool), self.rough.slack
        left, right = self.rough.left[i], self.rough.right if len(j) == len(self.y) else np.ascontiguousarray(self.rough.right[:, j])
        for a in range(0, len(i), OWN):
            for k in range(0, len(j), COLUMNS):
                tile, part = left[a : a + OWN] @ right[:, k : k + COLUMNS], out[a : a + OWN, k : k + COLUMNS]
                np.less_equal(tile, self.e2 + slack, out=part)
                flat = np.flatnonzero(part)
                flat = flat[tile.ravel()[flat] >= self.e2 - slack]
                m, n = flat // part.shape[1], flat % part.shape[1]
                part[m, n] = exact(self.x, self.y, i[a + m], j[k + n]) <= self.e2
        return out

    def turned(self, v: Block, u: Block) -> Near:
        """The same with u and v in each other's place."""
        return Near(v, u, self.e2**0.5)


def forest(near: Near, back: Near, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (row of u, row of v) that connect, without cycles, what near connects of rows a of u and b of v: from rows reached last on to those
    not reached yet, so that few pairs are looked at where many are near."""
    free, out, starts = [a, b], [(a[:0], b[:0])], a[:0]
    while len(free[0]) and len(free[1]):
        if not len(starts):  # of a few rows together, those that are near no row are left out
            starts = free[0][:OWN]
            any_ = near(starts, free[1]).any(axis=1)
            starts, free[0] = starts[any_], np.concatenate([starts[any_], free[0][OWN:]])
            continue
        first, starts = starts[:1], starts[1:]
        if first[0] != free[0][0]:  # reached meanwhile; both are in order
            continue
        todo, free[0] = [(first, 0)], free[0][1:]
        while todo:
            at, side = todo.pop()
            for lo in range(0, len(at), OWN):
                own, other = at[lo : lo + OWN], free[1 - side]
                if not len(other):
                    break
                table = (near, back)[side](own, other)
                hit = table.any(axis=0)
                if hit.any():
                    ends = own[table[:, hit].argmax(axis=0)], other[hit]
                    out.append(ends if side == 0 else ends[::-1])
                    todo.append((other[hit], 1 - side))
                    free[1 - side] = other[~hit]
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def connected(near: Near, a: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For rows a of one block the component that near connects them to, a number each, and pairs that connect these without cycles."""
    label, free, out, k, starts = np.full(len(near.x), -1), a, [(a[:0], a[:0])], 0, a[:0]
    while len(free):
        if not len(starts):  # of a few rows together, those that are near no other row are done
            starts = free[:OWN]
            any_ = np.count_nonzero(near(starts, free), axis=1) > 1
            label[starts[~any_]] = k + np.arange(np.count_nonzero(~any_))
            k += np.count_nonzero(~any_)
            starts, free = starts[any_], np.concatenate([starts[any_], free[OWN:]])
            continue
        first, starts = starts[:1], starts[1:]
        if first[0] != free[0]:  # reached meanwhile; both are in order
            continue
        todo, free = [first], free[1:]
        label[first] = k
        while todo:
            at = todo.pop()
            for lo in range(0, len(at), OWN):
                if not len(free):
                    break
                table = near(at[lo : lo + OWN], free)
                hit = table.any(axis=0)
                if hit.any():
                    out.append((at[lo : lo + OWN][table[:, hit].argmax(axis=0)], free[hit]))
                    todo.append(free[hit])
                    label[free[hit]] = k
                    free = free[~hit]
        k += 1
    return label, *(np.concatenate(c) for c in zip(*out, strict=True))


def exact(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Squared distances of pairs of rows, column by column."""
    d2 = np.zeros(len(i))
    for c in range(x.shape[1]):
        gap = x[i, c] - y[j, c]
        d2 += gap * gap
    return d2


def nearest_pair(u: Block, v: Block, exclusion: int, reach: float = np.inf, line: Callable[[np.ndarray], np.ndarray] | None = None) -> tuple | None:
    """(d2, series_a, t_a, series_b, t_b): the nearest rows of u and v that are not less than exclusion steps apart in one run, a before b, ties
    to the least; of pairs beyond reach none need be found. line: a projection that no distance is shorter than, by which rows are met in order."""
    best, same = None, u is v
    if line is not None:
        p = line(u.x)
        order = np.argsort(p, kind="stable")
        u, p = u.take(order), p[order]
        q = p if same else line(v.x)
        order = np.argsort(q, kind="stable")
        v, q = (u, p) if same else (v.take(order), q[order])
    rough = Rough(u.x, v.x)
    far = reach * reach if reach < np.inf else np.inf
    for a in range(0, u.n, OWN):
        b, lo, hi = min(u.n, a + OWN), 0, v.n
        if same:
            lo = a
        if line is not None and far < np.inf:
            band = far**0.5 * (1 + 1e-9) + 1e-9
            lo, hi = max(lo, int(np.searchsorted(q, p[a] - band))), int(np.searchsorted(q, p[b - 1] + band, "right"))
        for k in range(lo, hi, COLUMNS):
            tile = rough.tile(a, b, k, min(hi, k + COLUMNS))
            if tile.min() > far + rough.slack:
                continue
            i, j = np.nonzero(tile <= far + rough.slack)
            i, j = i + a, j + k
            s, t, s2, t2 = u.series_id[i], u.t[i], v.series_id[j], v.t[j]
            ok = (s != s2) | (np.abs(t - t2) >= exclusion)
            if not ok.any():
                continue
            i, j, s, t, s2, t2 = i[ok], j[ok], s[ok], t[ok], s2[ok], t2[ok]
            d2 = exact(u.x, v.x, i, j)
            least = d2.min()
            if least > far:
                continue
            at = np.flatnonzero(d2 == least)
            swap = (s2[at] < s[at]) | ((s2[at] == s[at]) & (t2[at] < t[at]))
            s, t, s2, t2 = np.where(swap, s2[at], s[at]), np.where(swap, t2[at], t[at]), np.where(swap, s[at], s2[at]), np.where(swap, t[at], t2[at])
            m = np.lexsort((t2, s2, t, s))[0]
            got = (float(least), int(s[m]), int(t[m]), int(s2[m]), int(t2[m]))
            best = got if best is None else min(best, got)
            far = best[0]
    return best


def nearest_of(u: Block, v: Block, start: np.ndarray, end: np.ndarray, keep: int = 1, limit: float = np.inf) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of u, row of v, d2): for each row of u, of the rows start <= j < end of v (both do not fall from row to row) the keep nearest below
    limit, a squared distance, in order, ties to the first."""
    rough, out = Rough(u.x, v.x), []
    for a in range(0, u.n, OWN):
        b = min(u.n, a + OWN)
        held = (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        bound = np.full(b - a, limit)
        for k in range(int(start[a]), int(end[b - 1]), COLUMNS):
            hi = min(int(end[b - 1]), k + COLUMNS)
            tile = rough.tile(a, b, k, hi)
            if start[b - 1] > k or end[a] < hi:
                at = np.arange(k, hi)
                tile[(at < start[a:b, None]) | (at >= end[a:b, None])] = np.inf
            least = tile.min(axis=1)
            rows = np.flatnonzero((least <= bound + rough.slack) & (least < np.inf))
            if not len(rows):
                continue
            # what lies beyond the keep nearest by the product, and twice its error, is none of them
            own = tile[rows] if len(rows) < b - a else tile
            few = least[rows] if keep == 1 else np.partition(own, min(keep, hi - k) - 1, axis=1)[:, min(keep, hi - k) - 1]
            far = np.minimum(np.minimum(bound[rows] + rough.slack, few + 2 * rough.slack), np.finfo(np.float32).max).astype(np.float32)
            at = np.flatnonzero(np.less_equal(own, far[:, None]))
            i, j = rows[at // (hi - k)], k + at % (hi - k)
            d2 = exact(u.x, v.x, i + a, j)
            below = d2 < limit
            i, j, d2 = (np.concatenate([h, n[below]]) for h, n in zip(held, (i, j, d2), strict=True))
            order = np.lexsort((j, d2, i))
            i, j, d2 = i[order], j[order], d2[order]
            place = np.arange(len(i)) - np.searchsorted(i, i)
            ok = place < keep
            held = (i[ok], j[ok], d2[ok])
            last = place == keep - 1
            bound[i[last]] = d2[last]
        out.append((held[0] + a, held[1], held[2]))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))


def place_in(v: Block, s: np.ndarray, t: np.ndarray) -> np.ndarray:
    """For each place (s, t) how many rows of v, sorted by series_id and t, lie before it."""
    order = np.lexsort((np.concatenate([np.ones(v.n, np.int8), np.zeros(len(s), np.int8)]), np.concatenate([v.t, t]), np.concatenate([v.series_id, s])))
    own = order >= v.n
    before = np.cumsum(~own)[own]
    out = np.empty(len(s), np.int64)
    out[order[own] - v.n] = before
    return out


def nearest_rows(rows: DataFrame, w: int | None, keep: int = 1, reach: DataFrame | None = None, bin_: Column | None = None) -> DataFrame:
    """(sensor, series_a, t_a, series_b, t_b, d2): for each row a, its keep nearest rows b of each block, ties to the first. b lies before a in the
    order of series_id and t; or, with w, after it and not less than w steps later in its run. reach: (sensor, reach), below which b must lie."""

    def fn(u: Block, v: Block, reach: float = np.inf) -> pa.Table:
        parts = []
        for a, b in ((u, v), (v, u))[: 1 if u is v else 2]:
            at = place_in(b, a.series_id, a.t if w is None else a.t + w)
            i, j, d2 = nearest_of(a, b, np.zeros_like(at) if w is None else at, at if w is None else np.full_like(at, b.n), keep, reach * reach)
            parts.append(pa.table({"series_a": a.series_id[i], "t_a": a.t[i], "series_b": b.series_id[j], "t_b": b.t[j], "d2": d2}))
        return pa.concat_tables(parts)

    return met(rows.select("sensor", "series_id", "t", "x", *([] if bin_ is None else ["bin"])), ["series_id", "t"], fn, "series_a long, t_a long, series_b long, t_b long, d2 double", bin_, reach=reach)
