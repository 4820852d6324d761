"""Complete and single linkage up to a cutoff with memory in proportion to the rows: no table of pairs.

In complete linkage each cluster keeps a short list of its nearest clusters and a bound: all clusters nearer than it are in the list. Linkages only grow as
clusters join, so a list stays true; it is made again when it is empty. Clusters that are each other's nearest join in rounds, which gives
the clusters of joining the least pair of all, one after the other, ties to the least rows included.
"""

from __future__ import annotations

import numpy as np

#: Share of the squared lengths that bounds the rounding of distances by products, in single and in double precision.
ROUGH, SLACK = 1e-5, 1e-12
#: Clusters searched together, and columns they are met with at once.
OWN, COLUMNS = 256, 2048
#: Distances held at once where members meet.
CELLS = 1 << 21


def distances(x: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return np.sqrt(((x[i] - x[j]) ** 2).sum(axis=1))


class Complete:
    """Clusters of the distinct rows of x by complete linkage below a cutoff; a cluster is named by its first row."""

    def __init__(self, x: np.ndarray, cutoff: float, keep: int = 16):
        n = len(x)
        self.x, self.cutoff, self.keep = x, cutoff, keep
        self.root, self.size, self.alive = np.arange(n), np.ones(n, np.int64), np.ones(n, bool)
        self.ls, self.ss = x.copy(), (x * x).sum(axis=1)
        self.near, self.gap, self.held = np.full((n, keep), -1, np.int32), np.zeros((n, keep)), np.zeros((n, keep), np.int32)
        self.bound, self.partner, self.evals = np.zeros(n), np.full(n, -1), 0

    def put(self, rows: np.ndarray, r: np.ndarray, ids: np.ndarray, gaps: np.ndarray, bound: np.ndarray) -> None:
        """Lists of rows from entries (r, ids, gaps), all below the bound. The nearest is kept even where those behind it tie with it."""
        order = np.lexsort((ids, gaps, r))
        r, ids, gaps, bound = r[order], ids[order], gaps[order], bound.copy()
        k = np.arange(len(r)) - np.searchsorted(r, np.arange(len(rows)))[r]
        bound[r[k == self.keep]] = gaps[k == self.keep]
        ok = (k < self.keep) & (gaps < bound[r]) | (k == 0)
        at = rows[r[ok]], k[ok]
        self.near[rows] = -1
        self.near[at], self.gap[at], self.held[at] = ids[ok], gaps[ok], self.size[ids[ok]]
        self.bound[rows], self.partner[rows] = bound, self.near[rows, 0]

    def now(self, rows: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Entries of the lists of rows, each now part of own, by the clusters of now; one of which a part was not listed lies at the bound or beyond."""
        r, k = np.nonzero(self.near[rows] >= 0)
        ids, gaps, sizes = self.root[self.near[rows[r], k]], self.gap[rows[r], k], self.held[rows[r], k]
        ok = np.flatnonzero(ids != own[r])
        ok = ok[np.lexsort((ids[ok], r[ok]))]
        r, ids, gaps, sizes = r[ok], ids[ok], gaps[ok], sizes[ok]
        if not len(r):
            return r, ids, gaps
        at = np.flatnonzero(np.concatenate([[True], (r[1:] != r[:-1]) | (ids[1:] != ids[:-1])]))
        r, ids, gaps, sizes = r[at], ids[at], np.maximum.reduceat(gaps, at), np.add.reduceat(sizes, at)
        ok = (sizes == self.size[ids]) & (gaps < self.bound[rows[r]])
        return r[ok], ids[ok], gaps[ok]

    def meet(self, a: int, others: np.ndarray, reach: float) -> tuple[np.ndarray, np.ndarray]:
        """Those of others whose linkage to a is below reach, and it. A product tells distances up to rounding; the farthest are computed."""
        u, found = self.members(np.array([a])), [(others[:0], np.empty(0))]
        h = self.h[u]
        slack, limit = SLACK * (1 + 4 * self.h_top), reach * reach
        ends, lo = np.cumsum(self.size[others]), 0
        self.evals += len(u) * int(ends[-1])
        while lo < len(others):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + CELLS // len(u), "right")))
            b = others[lo:hi]
            v = self.members(b)
            m = self.size[b]
            at = np.cumsum(m) - m
            rough = h[:, None] + self.h[v] - 2.0 * (self.x[u] @ self.x[v].T)
            far = rough.max(axis=0)
            link = np.maximum.reduceat(far, at)
            link[link > limit + slack] = np.inf
            cols = np.flatnonzero(far >= np.repeat(link, m) - slack)
            i, j = np.nonzero(rough[:, cols] >= np.repeat(link, m)[cols] - slack)
            to = np.repeat(np.arange(len(b)), m)[cols[j]]
            gaps = np.zeros(len(b))
            np.maximum.at(gaps, to, distances(self.x, u[i], v[cols[j]]))
            ok = np.isfinite(link) & (gaps < reach)
            found.append((b[ok], gaps[ok]))
            lo = hi
        return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])

    def members(self, clusters: np.ndarray) -> np.ndarray:
        m = self.size[clusters]
        return self.order[np.arange(int(m.sum())) + np.repeat(self.start[clusters] - np.cumsum(m) + m, m)]

    def search(self, rows: np.ndarray, want: int) -> np.ndarray:
        """Makes the lists of rows from about want nearest by the mean of their squared distances, which no linkage is below. Returns those
        whose lists are empty although there may be clusters below the cutoff; others with empty lists are done."""
        active = np.flatnonzero(self.alive)
        self.order = np.argsort(self.root, kind="stable")
        count = np.bincount(self.root, minlength=len(self.root))
        self.start = np.cumsum(count) - count
        mean, h = self.ls[active] / self.size[active, None], self.ss[active] / self.size[active]
        columns, top = np.column_stack([-2.0 * mean, h]).astype(np.float32), float(h.max())
        few = slice(None, None, 8 if len(active) > 4096 else 1)
        k, some = max(2, (want + 1) // (few.step or 1)), np.ascontiguousarray(columns[few].T)
        blocks = [np.ascontiguousarray(columns[a : a + COLUMNS].T) for a in range(0, len(active), COLUMNS)]
        room, hit = np.empty((OWN, COLUMNS), np.float32), np.empty((OWN, COLUMNS), bool)
        left = [rows[:0]]
        self.evals += len(rows) * len(active)
        for lo in range(0, len(rows), OWN):
            own = rows[lo : lo + OWN]
            q, hq = np.column_stack([self.ls[own] / self.size[own, None], np.ones(len(own))]).astype(np.float32), self.ss[own] / self.size[own]
            part = q @ some
            g = part.shape[1] // (16 * k) * 16 * k
            if g > 64 * k:  # least values of groups are enough to tell how far to look
                part = np.concatenate([part[:, :g].reshape(len(own), 16 * k, -1).min(axis=2), part[:, g:]], axis=1)
            reach2 = np.partition(part, k, axis=1)[:, k] + hq if part.shape[1] > k else np.full(len(own), np.inf)
            reach = np.where(reach2 < self.cutoff**2, np.sqrt(np.maximum(reach2, 0)), self.cutoff)
            limit = (reach * reach - hq + ROUGH * (1 + top + hq)).astype(np.float32)[:, None]
            pairs = []
            for i, block in enumerate(blocks):
                w = block.shape[1]
                out, near = room.ravel()[: len(own) * w].reshape(len(own), w), hit.ravel()[: len(own) * w].reshape(len(own), w)
                at = np.flatnonzero(np.less(np.matmul(q, block, out=out), limit, out=near))
                pairs.append((at // w, i * COLUMNS + at % w))
            r, j = (np.concatenate(p) for p in zip(*pairs, strict=True))
            j = active[j]
            r, j = r[j != own[r]], j[j != own[r]]
            one = (self.size[own[r]] == 1) & (self.size[j] == 1)
            gaps = distances(self.x, own[r[one]], j[one])
            found = [(r[one], j[one], gaps)]
            r, j = r[~one], j[~one]
            order = np.argsort(r, kind="stable")
            r, j = r[order], j[order]
            for i in np.unique(r):
                ids, gaps = self.meet(own[i], j[np.searchsorted(r, i) : np.searchsorted(r, i, "right")], reach[i])
                found.append((np.full(len(ids), i), ids, gaps))
            r, j, gaps = (np.concatenate(f) for f in zip(*found, strict=True))
            ok = gaps < reach[r]
            self.put(own, r[ok], j[ok], gaps[ok], reach)
            empty = self.partner[own] < 0
            self.alive[own[empty & (reach >= self.cutoff)]] = False
            left.append(own[empty & (reach < self.cutoff)])
        return np.concatenate(left)

    def join(self) -> np.ndarray | None:
        """Joins clusters that are each other's nearest. Returns those whose lists are empty now, none if there were no such clusters."""
        a = np.flatnonzero(self.alive & (self.partner >= 0))
        a = a[(self.partner[self.partner[a]] == a) & (a < self.partner[a])]
        if not len(a):
            return None
        b, to = self.partner[a], np.arange(len(self.root))
        to[b] = a
        self.root = to[self.root]
        for of in (self.size, self.ls, self.ss):
            of[a] += of[b]
        self.alive[b] = False
        gone = np.zeros(len(to), bool)
        gone[a] = gone[b] = True
        rest = np.flatnonzero(self.alive & ~gone)
        rest = rest[gone[self.partner[rest]]]
        # of a joined cluster both lists are true up to the lesser bound
        own, (r, ids, gaps) = self.now(rest, rest), (np.concatenate(p) for p in zip(self.now(a, a), self.now(b, a), strict=True))
        order = np.lexsort((ids, r))
        r, ids, gaps = r[order], ids[order], gaps[order]
        both, bound = np.flatnonzero((r[1:] == r[:-1]) & (ids[1:] == ids[:-1])), np.minimum(self.bound[a], self.bound[b])
        r, ids, gaps = r[both], ids[both], np.maximum(gaps[both], gaps[both + 1])
        ok = gaps < bound[r]
        self.put(rest, *own, self.bound[rest])
        self.put(a, r[ok], ids[ok], gaps[ok], bound)
        todo = np.concatenate([rest, a])
        todo = todo[self.partner[todo] < 0]
        done = self.bound[todo] >= self.cutoff
        self.alive[todo[done]] = False
        return todo[~done]

    def run(self) -> np.ndarray:
        """For each row the first row of its cluster."""
        self.h = (self.x * self.x).sum(axis=1)
        self.h_top = float(self.h.max(initial=0.0))
        todo = np.arange(len(self.x))
        while todo is not None:
            want = self.keep
            while len(todo):
                todo = self.search(todo, want)
                want *= 4
            todo = self.join()
        return self.root


def complete_linkage(x: np.ndarray, cutoff: float, keep: int = 16) -> tuple[np.ndarray, int]:
    """For each row of x the first row of its cluster, and the number of distances met. Clusters join while their complete linkage is below
    the cutoff, the least first, ties to the least rows; equal rows are one from the start."""
    if cutoff <= 0:
        return np.arange(len(x)), 0
    _, first, of = np.unique(x + 0.0, axis=0, return_index=True, return_inverse=True)
    rows = np.sort(first)
    clusters = Complete(x[rows], cutoff, keep)
    return rows[clusters.run()[np.searchsorted(rows, first[of.ravel()])]], clusters.evals


def single_linkage(x: np.ndarray, cutoff: float) -> tuple[np.ndarray, int]:
    """For each row of x the first row that links below the cutoff connect with it, and the number of distances met."""
    root, free, evals = np.arange(len(x)), np.arange(len(x)), 0
    h = (x * x).sum(axis=1)
    slack = SLACK * (1 + cutoff * cutoff + 4 * float(h.max(initial=0.0)))
    while len(free):
        start, todo, free = free[0], [free[:1]], free[1:]
        while todo:
            at = todo.pop()
            step = max(1, CELLS // max(1, len(free)))
            for lo in range(0, len(at), step):
                own = at[lo : lo + step]
                evals += len(own) * len(free)
                off = h[own, None] + h[free] - 2.0 * (x[own] @ x[free].T) - cutoff * cutoff
                near = off < 0
                i, j = np.nonzero(np.abs(off) <= slack)
                near[i, j] = distances(x, own[i], free[j]) < cutoff
                hit = near.any(axis=0)
                if hit.any():
                    root[free[hit]] = start
                    todo.append(free[hit])
                    free = free[~hit]
    return root, evals
