"""Rows of a sensor met in pairs of blocks."""

import numpy as np
import pytest

from wavemotif.operators import baselines as B
from wavemotif.operators import blocks as K
from wavemotif.operators import cluster as C

WIN = "sensor string, series_id long, t long, x array<double>, level double"


def test_blocks_meet_once(spark):
    """A pair of blocks meets in one task, not in two that are each other's mirror."""
    rng = np.random.default_rng(6)
    win = spark.createDataFrame([("s", i // 40, i % 40, v, 0.0) for i, v in enumerate(rng.normal(size=(400, 3)).tolist())], WIN)
    met = K.met(win, ["series_id", "t"], lambda u, v: u.table.select(["t"]).slice(0, 1), "t long", least=100, most=100)
    assert met.count() == 15  # of five blocks
    assert len(B.least_pairs(win, win, ["sensor"], 3, 5, block=64).collect()) <= 36


def test_reference_search_needs_no_pair_in_a_run(spark):
    """Runs of one window each: no two windows of a run bound the search, and the pair is found as by brute force."""
    x = np.random.default_rng(3).normal(size=(50, 4)).tolist()
    win = spark.createDataFrame([("s", i, 0, v, 0.0) for i, v in enumerate(x)], WIN)
    got = [B.closest_pair(win, 4, 5, m).collect() for m in ("brute", "reference")]
    assert len(got[0]) == 1 and got[0] == got[1]


@pytest.mark.parametrize("digits", [1, 6])
def test_point_link_in_blocks(spark, monkeypatch, digits):
    """Clusters as by insertion in order, ties included; rows of a sensor meet in blocks and not in one task."""
    monkeypatch.setattr(K.met, "__defaults__", (None, 32, 32, 16, None))
    monkeypatch.setitem(C.METHODS, "point", None)
    rng = np.random.default_rng(5)
    x = np.round(rng.normal(size=(400, 4)), digits)
    rows = [("ab"[i % 2], i // 20, i % 20, v, 0.0) for i, v in enumerate(x.tolist())]
    got = C.cluster(spark.createDataFrame(rows, WIN), 0.8, "point").orderBy("sensor", "series_id", "t").collect()
    for k, sensor in enumerate("ab"):
        ids, evals = C.insert_point_link(x[k::2], 0.8)
        own = [r for r in got if r.sensor == sensor]
        assert [r.cluster_id for r in own] == ids.tolist() and own[0].evals == evals
        c = C.means_of(x[k::2], ids)
        assert np.allclose([r.dist for r in own], np.sqrt(((x[k::2] - c[ids]) ** 2).sum(axis=1)))


@pytest.mark.parametrize("keep", [1, 3])
def test_nearest_rows_of_a_block(monkeypatch, keep):
    monkeypatch.setattr(K, "OWN", 32)
    monkeypatch.setattr(K, "COLUMNS", 64)
    import pyarrow as pa

    rng = np.random.default_rng(1)
    x = np.round(rng.normal(size=(600, 3)), 1)
    u, v = (K.Block(pa.table({"x": pa.array(list(p), pa.list_(pa.float64()))})) for p in (x[:250], x[250:]))
    start = np.sort(rng.integers(0, 200, u.n))
    end = np.sort(rng.integers(200, v.n + 1, u.n))
    i, j, d2 = K.nearest_of(u, v, start, end, keep, 0.5)
    for a in range(u.n):
        near = sorted((sum((p - q) * (p - q) for p, q in zip(v.x[b], u.x[a], strict=True)), b) for b in range(start[a], end[a]))
        assert list(zip(d2[i == a].tolist(), j[i == a].tolist(), strict=True)) == [n for n in near if n[0] < 0.5][:keep]


def test_links_of_blocks_connect_what_is_near(monkeypatch):
    """Components as by a dense matrix, of one block and of two, without cycles; rows that are near none are met a few together."""
    import pyarrow as pa

    monkeypatch.setattr(K, "OWN", 16)
    asked, call = [], K.Near.__call__
    monkeypatch.setattr(K.Near, "__call__", lambda self, i, j: asked.append(len(i)) or call(self, i, j))
    rng = np.random.default_rng(2)
    x = np.round(np.concatenate([rng.normal(0, 0.4, (150, 3)), rng.uniform(-9, 9, (150, 3))])[rng.permutation(300)], 2)

    def roots(n, pairs):
        to = list(range(n))
        for a, b in pairs:
            while to[a] != a:
                a = to[a]
            while to[b] != b:
                b = to[b]
            to[max(a, b)] = min(a, b)
        for a in range(n):
            to[a] = to[to[a]]
        return to

    u, v = (K.Block(pa.table({"x": pa.array(list(p), pa.list_(pa.float64()))})) for p in (x[:160], x[160:]))
    near = ((x[:, None] - x[None]) ** 2).sum(axis=2) <= 0.25
    label, i, j = K.connected(K.Near(u, u, 0.5), np.arange(u.n))
    want = roots(u.n, zip(*np.nonzero(near[:160, :160]), strict=True))
    assert roots(u.n, zip(i, j, strict=True)) == want and len(i) == u.n - len(set(want))
    assert all((label == label[a]).tolist() == [w == want[a] for w in want] for a in range(u.n))
    assert len(asked) < u.n
    forward = K.Near(u, v, 0.5)
    i, j = K.forest(forward, forward.turned(v, u), np.arange(u.n), np.arange(v.n))
    a, b = np.nonzero(near[:160, 160:])
    want = roots(300, zip(a, b + 160, strict=True))
    assert roots(300, zip(i, j + 160, strict=True)) == want and len(i) == 300 - len(set(want))
