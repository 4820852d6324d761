"""Worked examples and properties."""

import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from wavemotif import catalog
from wavemotif.functions import vectors as VEC
from wavemotif.operators import baselines as B
from wavemotif.operators import cluster as C
from wavemotif.operators import extract as X
from wavemotif.operators import linkage as L
from wavemotif.operators import matching as M
from wavemotif.operators import measures as S
from wavemotif.operators import prep as P
from wavemotif.operators import relational as R
from wavemotif.plans import pipeline as PL
from wavemotif.sources import files as FS
from wavemotif.sources import views as V

SF = "/root/testdata/sf0.001"
ROW = "sensor string, series_id long, t long, x array<double>, level double, cluster_id long, dist double, evals long"


def series(spark, values, sid=0):
    return spark.createDataFrame([("s", sid, t, int(v * 100)) for t, v in enumerate(values)], "sensor string, series_id long, t long, v long")


def members(spark, rows):
    return spark.createDataFrame([("s", 0, t, [0.0], float(lv), c, 0.0, 0) for c, t, lv in rows], ROW)


def test_z_scores(spark):
    z = [r.z for r in P.znormalize(series(spark, [1, 2, 3])).orderBy("t").collect()]
    assert z == pytest.approx([-1.5**0.5, 0, 1.5**0.5])


def test_constant_and_short_runs_vanish(spark):
    assert P.znormalize(series(spark, [4] * 9)).isEmpty()
    assert P.reduced_windows(P.znormalize(series(spark, range(5))), 20, 10).isEmpty()


def test_ramp_keeps_one_window(spark):
    assert P.candidates(series(spark, range(40)), 20, 10).count() == 1


def test_zero_mean_and_fractional_frames(spark):
    for w, d in ((20, 10), (14, 5), (10, 4)):
        rows = P.reduced_windows(P.znormalize(V.run_view(spark, SF)), w, d, None).collect()
        assert rows and max(abs(sum(r.x)) for r in rows) < 1e-9
        assert all(sum(c for _, c in f) == pytest.approx(w / d) for f in P.frame_weights(w, d))


def test_partitioning_does_not_matter(spark):
    words = []
    for n in ("1", "5"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        words.append(sorted(map(tuple, P.candidates(V.run_view(spark, SF), 20, 10).select("series_id", "t", "word").collect())))
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    assert words[0] == words[1]


def test_plan_of_preprocessing(spark):
    plan = P.candidates(V.run_view(spark, SF), 20, 10)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 4 and "CartesianProduct" not in plan and "Python" not in plan


def test_drift_leaves_outlier_and_frozen_centre_does_not():
    x = np.array([[0.0, 0], [0.9, 0], [1.2, 0], [1.5, 0], [1.8, 0]])
    ids, _ = C.insert_all(x, 1.0)
    mean = np.array([x[ids == i].mean(axis=0) for i in range(ids.max() + 1)])
    frozen, _ = C.insert_all(x, 1.0, frozen=True)
    first = np.array([x[frozen == i][0] for i in range(frozen.max() + 1)])
    assert (np.linalg.norm(x - first[frozen], axis=1) < 1).all()
    assert np.linalg.norm(x - mean[ids], axis=1).max() > 0


@pytest.mark.parametrize("method", ["all", "hash", "cftree", "point"])
def test_every_candidate_once_and_fewer_distances(spark, method):
    cand = P.candidates(V.planted_view(spark, SF).where("series_id <= 3"), 20, 10)
    got = C.cluster(cand, 1.0, method)
    assert got.count() == cand.count() == got.select("series_id", "t").distinct().count()
    if method in ("hash", "cftree"):
        assert got.first().evals < C.cluster(cand, 1.0, "all").first().evals


def test_outliers_below_twice_the_clusters(spark):
    got = C.cluster(P.candidates(V.planted_view(spark, SF), 20, 10), 1.0, "all")
    assert S.radius_outliers(got, 1.0, 10).first().below_twice


def test_parallel_members_within_radius(spark):
    cand = P.candidates(V.planted_view(spark, SF).where("series_id <= 3"), 20, 10)
    got = C.cluster_parallel(cand, 1.0, 10, sets=5, per_set=6)
    assert got.count() == cand.count() and got.agg(F.max("dist")).first()[0] < 1


def test_shifted_twins(spark):
    big = [(1, t, 0) for t in range(0, 600, 50)] + [(1, 900, 0)]
    assert {r.cluster_id for r in X.drop_shifted(members(spark, big + [(2, t + 3, 0) for t in range(0, 600, 50)])).collect()} == {1}
    swing = [(2, t + (6 if i % 2 else -6), 0) for i, t in enumerate(range(50, 600, 50))]
    assert {r.cluster_id for r in X.drop_shifted(members(spark, big + swing)).collect()} == {1, 2}


def test_chain_of_shifts(spark):
    rows = [(1, t, 0) for t in range(100, 1300, 100)] + [(2, t + 6, 0) for t in range(100, 1200, 100)] + [(3, t + 12, 0) for t in range(100, 1100, 100)]
    kept = lambda how: {r.cluster_id for r in X.drop_shifted(members(spark, rows), cascade=how).collect()}
    assert kept("greedy") == {1, 3} and kept("independent") == {1}


def test_trivial_members(spark):
    ramp = [(t, [0.0]) for t in range(10)]
    dip = [(t, [9.0 if 3 <= t <= 6 else 0.0]) for t in range(10)]
    for values, kept in ((ramp, {0}), (dip, {0, 9})):
        win = spark.createDataFrame([("s", 0, t, x) for t, x in values], "sensor string, series_id long, t long, x array<double>")
        assert {r.t for r in X.drop_trivial(members(spark, [(1, 0, 0), (1, 9, 0)]), win, 1.0).collect()} == kept


def test_levels(spark):
    rows = [(1, i, lv) for i, lv in enumerate((0, 0.1, 0.2, 5, 5.1, 9))]
    got = {r.t: r.level_id for r in X.split_levels(members(spark, rows), 0.5, 2).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 3: 1, 4: 1}


def test_grid_join_equals_brute(spark):
    rows = P.candidates(V.run_view(spark, SF), 20, 10).select("sensor", (F.col("series_id") * 1000 + F.col("t")).alias("id"), "x")
    pairs = [sorted(map(tuple, C.eps_join(rows, 2.0, 10, m).collect())) for m in ("brute", "grid")]
    assert pairs[0] and pairs[0] == pairs[1]


def test_radius_rule():
    assert [VEC.adjusted_radius(w) for w in (14, 20, 80)] == [1.0, 1.0, 2.0]


def test_radius_and_planted_runs_read_a_given_table(spark):
    """Both made their rows up before."""
    for name in ("adjusted_radius_table", "source_planted_runs"):
        assert any("events" in f for f in catalog.queries()[name](spark, SF).inputFiles())


def test_shapes_are_planted_onto_long_runs(spark):
    flat = spark.range(0, 26 * 1500).select(F.lit("x").alias("sensor"), F.floor(F.col("id") / 1500).alias("series_id"), (F.col("id") % 1500).alias("t"), F.lit(7).cast("long").alias("v"))
    got = {(r.series_id, r.t): r.v for r in FS.planted_onto(flat).collect()}
    assert len(got) == 26 * 1500
    for (k, t), v in got.items():
        b, u = divmod(t, 60)
        a, p = u - 2 - (7 * k + 13 * b) % 11, u - 29 - (5 * k + 17 * b) % 11
        assert v == 7 + (3000 if 10 <= a <= 17 else 0) + (3000 if p in (2, 3, 14, 15) else 0)


def test_nearest_by_products_is_the_first_exact_one():
    """Nearest centres, near members and buckets are those of plain loops, ties and large values included, at a fraction of the time."""
    import time

    rng = np.random.default_rng(4)
    for scale in (1.0, 4e4):
        x = rng.integers(-2, 3, (600, 4)) * scale + 10 * scale
        c = np.concatenate([x[:90], x[:90], x.mean(axis=0)[None]])
        want = ((x[:, None] - c[None]) ** 2).sum(axis=2).argmin(axis=1)
        assert (C.closest_of_all(x, c) == want).all()
        ids, k = [], 0
        for i, v in enumerate(x):
            d2 = ((x[:i] - v) ** 2).sum(axis=1)
            ids.append(ids[d2.argmin()] if i and d2.min() < (1.5 * scale) ** 2 else k)
            k = max(k, ids[-1] + 1)
        got, evals = C.insert_point_link(x, 1.5 * scale)
        assert got.tolist() == ids and evals == 600 * 599 // 2
    x = rng.normal(size=(8000, 10))
    start = time.perf_counter()
    plain = [((x[a : a + 250, None] - x[None, :5000]) ** 2).sum(axis=2).argmin(axis=1) for a in range(0, 1000, 250)]
    middle = time.perf_counter()
    got = C.closest_of_all(x, x[:5000])
    assert time.perf_counter() - middle < 4 * (middle - start)  # eight times as many rows; 8 before
    assert (got[:1000] == np.concatenate(plain)).all()


def test_closest_pair_meets_in_blocks(spark):
    """No task holds all windows of a sensor, and blocks of any size give the pair of all pairs, ties to the smaller keys."""
    rng = np.random.default_rng(6)
    x = rng.integers(0, 4, (400, 3)).astype(float)
    rows = [("s", i // 40, i % 40, v) for i, v in enumerate(x.tolist())]
    win = spark.createDataFrame([(*r, 0.0, 0.0) for r in rows], "sensor string, series_id long, t long, x array<double>, g double, bound double")
    want = min((sum((p - q) ** 2 for p, q in zip(a[3], b[3], strict=True)), *a[1:3], *b[1:3]) for a in rows for b in rows if a[1] < b[1] or (a[1] == b[1] and b[2] - a[2] >= 5))
    got = B.least_pairs(win, win, ["sensor"], 3, 5, block=64).collect()
    assert len(got) > 30 and min((r.d2, r.series_a, r.t_a, r.series_b, r.t_b) for r in got) == want
    for method in ("brute", "reference"):
        assert [tuple(r)[1:] for r in B.closest_pair(win, 3, 5, method).collect()] == [(*want[1:], want[0])]


def test_asof_ties_and_tolerance(spark):
    left = spark.createDataFrame([(1, 5), (1, 50)], "k long, t long")
    right = spark.createDataFrame([(1, 3, "a"), (1, 7, "b")], "k long, t long, name string")
    got = lambda **o: [r.name for r in R.asof_join(left, right, "t", ["k"], ["name"], **o).orderBy("t").collect()]
    assert got() == ["a", "b"] and got(direction="forward") == ["b", None]
    assert got(direction="nearest") == ["a", "b"] and got(tolerance=5) == ["a", None]


def test_shards_of_cf_trees(spark):
    """One shard is the plain tree after its features met again; several keep every window once, near its centre."""
    cand = P.candidates(V.planted_view(spark, SF), 20, 10)
    assert C.cluster_cf_shards(cand.where("false"), 1.0, 10).isEmpty()
    rows = C.cluster_cf_shards(cand, 1.0, 10, shards=8)
    assert rows.select("sensor", "series_id", "t").exceptAll(cand.select("sensor", "series_id", "t")).isEmpty() and rows.count() == cand.count()
    k = rows.select("cluster_id").distinct().count()
    plain = C.cluster(cand, 1.0, "cftree").select("cluster_id").distinct().count()
    assert 0.5 * plain < k < 2 * plain
    assert rows.where("dist >= 1").count() < 2 * k


def test_features_inserted_whole_add_up():
    rng = np.random.default_rng(3)
    x = rng.normal(0, 1, (300, 4))
    cf = np.column_stack([np.ones(300), x, (x * x).sum(axis=1)])
    assert (C.insert_cftree(x, 0.8)[0] == C.insert_cftree(x, 0.8, features=cf)[0]).all()


def test_reclustering_leaves_fewer_outliers(spark):
    cand = P.candidates(V.planted_view(spark, SF), 20, 10)
    before, after = (C.cluster(cand, 1.0, "cftree", recluster=n).where("dist >= 1").count() for n in (0, 3))
    assert after <= before and C.cluster(cand, 1.0, "cftree", recluster=3).count() == cand.count()


def test_raw_radius_gives_the_clusters_of_z_scores(spark):
    from wavemotif import catalog

    rows = catalog.queries()["cluster_raw_radius"](spark, SF).collect()
    assert rows and all(r.windows == r.same for r in rows)


def test_measures_of_distance(spark):
    rows = spark.createDataFrame([([1.0, -1.0], 5.0), ([0.0, 0.0], 2.0)], "x array<double>, level double")
    got = {m: [r.x for r in P.for_measure(rows, 2, m).collect()] for m in ("euclidean_centred", "euclidean", "euclidean_znorm")}
    assert got == {"euclidean_centred": [[1, -1], [0, 0]], "euclidean": [[6, 4], [2, 2]], "euclidean_znorm": [[1, -1], [0, 0]]}
    with pytest.raises(ValueError):
        P.for_measure(rows, 2, "other")


@pytest.mark.parametrize("mode", ["radius", "description_length"])
def test_closest_pair_grouping_goes_on_until_its_rule_ends_it(spark, mode):
    """Groups by steps of the distributed pair search, and no pair left that the rule would take; more than three groups."""
    win = C.cut(catalog._reduced(spark, SF))
    rows = {(r.series_id, r.t): r.x for r in win.collect()}
    got = {}
    for r in B.closest_pair_grouping(win, 10, 20, mode, r=1.5).collect():
        got.setdefault(r.group_id, []).append((r.series_id, r.t))
    assert sorted(got) == list(range(len(got))) and (len(got) > 3 or mode != "radius")
    left = set(rows)
    for g in range(min(2, len(got))):
        p = B.closest_pair(win.join(spark.createDataFrame(list(left), "series_id long, t long"), ["series_id", "t"]), 10, 20).first()
        c = [(a + b) / 2 for a, b in zip(rows[p.series_a, p.t_a], rows[p.series_b, p.t_b], strict=True)]
        near = sorted(left, key=lambda k: (sum((a - b) ** 2 for a, b in zip(rows[k], c, strict=True)), k))
        assert near[0] in got[g]
        left -= {(s, t + i) for s, t in got[g] for i in range(-19, 20)}
    for g in range(min(2, len(got)), len(got)):
        left -= {(s, t + i) for s, t in got[g] for i in range(-19, 20)}
    if left:
        p = B.closest_pair(win.join(spark.createDataFrame(list(left), "series_id long, t long"), ["series_id", "t"]), 10, 20).first()
        half = [abs(a - b) / 2 for a, b in zip(rows[p.series_a, p.t_a], rows[p.series_b, p.t_b], strict=True)] if p else []
        assert p is None or (p.d2 > 9 if mode == "radius" else 60 - sum(np.log2(1 + 2 * round(h / 6 * 64)) for h in half) <= np.log2(len(left)))
    flat = [(a, b) for m in got.values() for a in m for b in m if a < b]
    assert all(a[0] != b[0] or b[1] - a[1] >= 20 for a, b in flat)


@pytest.mark.parametrize("linkage", ["complete", "single"])
def test_agglomeration_joins_runs_of_a_sensor(spark, linkage):
    """Equal shapes of different runs join; clusters as by a dense matrix."""
    rng = np.random.default_rng(4)
    rows = [("s", i % 6, i // 6, (rng.normal(0, 0.4, 3) + rng.integers(0, 4, 3)).tolist(), 0.0) for i in range(150)]
    rows += [("s", 7, 0, [9.0] * 3, 0.0), ("s", 8, 0, [9.0] * 3, 0.0)]
    rows.sort(key=lambda r: r[1:3])
    win = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double")
    got = [r.cluster_id for r in B.agglomerate(win, 1.2, linkage, group=("sensor",)).orderBy("series_id", "t").collect()]
    x = np.array([r[3] for r in rows])
    gap = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    np.fill_diagonal(gap, np.inf)
    ids = np.arange(len(x))
    while gap.min() < 1.2:
        a, b = sorted(np.unravel_index(gap.argmin(), gap.shape))
        gap[a] = gap[:, a] = (np.maximum if linkage == "complete" else np.minimum)(gap[a], gap[b])
        gap[a, a] = gap[b] = gap[:, b] = np.inf
        ids[ids == b] = a
    assert got == np.unique(ids, return_inverse=True)[1].tolist() and got[-1] == got[-2]


def plain_agglomeration(x, cutoff, linkage):
    """Clusters by a dense matrix, the least pair first, ties to the least rows."""
    gap = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    np.fill_diagonal(gap, np.inf)
    ids = np.arange(len(x))
    while gap.min() < cutoff:
        a, b = sorted(np.unravel_index(gap.argmin(), gap.shape))
        gap[a] = gap[:, a] = (np.maximum if linkage == "complete" else np.minimum)(gap[a], gap[b])
        gap[a, a] = gap[b] = gap[:, b] = np.inf
        ids[ids == b] = a
    return ids


@pytest.mark.parametrize("keep", [1, 3, 16])
def test_linkage_with_ties_and_short_lists(monkeypatch, keep):
    """Rows with many ties and copies, lists shorter than what is near, blocks smaller than the rows: clusters as by a dense matrix."""
    monkeypatch.setattr(L, "OWN", 16)
    monkeypatch.setattr(L, "COLUMNS", 32)
    monkeypatch.setattr(L, "CELLS", 64)
    rng = np.random.default_rng(keep)
    for trial in range(8):
        x = rng.integers(0, 4, (120 + trial, 3)) + (trial % 2) * rng.normal(0, 0.3, (120 + trial, 3))
        for cutoff in (0.0, 1.2, 2.0, 2.9):
            assert L.complete_linkage(x, cutoff, keep)[0].tolist() == plain_agglomeration(x, cutoff, "complete").tolist()
            assert L.single_linkage(x, cutoff)[0].tolist() == plain_agglomeration(x, cutoff, "single").tolist()


@pytest.mark.parametrize("linkage", [L.complete_linkage, L.single_linkage])
def test_linkage_keeps_no_pairs(linkage):
    """4,000 rows that are all near each other: 8 million links below the cutoff, but some numbers a row are kept."""
    x = np.random.default_rng(5).normal(0, 0.3, (4000, 4))
    tracemalloc.start()
    ids, _ = linkage(x, 6.0)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert not ids.any() and peak < 120e6



@pytest.mark.parametrize("method", ["all", "cftree"])
def test_spheres_of_one_shape_are_joined(spark, method):
    """Windows of one shape that sequential insertion splits: joined, one cluster has nearly all of them, no window is lost, few lie outside."""
    x = np.random.default_rng(6).normal(0, 0.26, (3000, 10))
    rows = [("s", i // 100, i % 100, v.tolist(), 0.0) for i, v in enumerate(x)] + [("z", 0, 0, [9.0] * 10, 0.0)]
    cand = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double")
    share = lambda df: df.groupBy("cluster_id").count().agg(F.max("count")).first()[0] / 3000
    assert share(C.cluster(cand, 1.0, method)) < 0.7
    got = C.cut(C.cluster(cand, 1.0, method, rejoin=True))
    assert got.columns == C.cluster(cand, 1.0, method).columns and got.select("sensor", "series_id", "t", "x").exceptAll(cand.select("sensor", "series_id", "t", "x")).isEmpty()
    inside = float((np.linalg.norm(x - x.mean(axis=0), axis=1) < 1).mean())
    assert got.count() == 3001 and share(got) > 0.98 * inside > 0.7 and S.radius_outliers(got, 1.0, 10).where("not below_twice").isEmpty()


@pytest.mark.parametrize("method", ["all", "cftree"])
def test_pipelines_find_shapes_of_many_runs(spark, method):
    """As registered, over the 100 runs of sf0.01: without joining the shares found were 0.6 to 0.81."""
    r = catalog._planted(spark, "/root/testdata/sf0.01", method=method, **catalog._PIPELINE[method])
    found = S.match_quality(r.stages["motifs"], V.planted_truth(spark, "/root/testdata/sf0.01")).collect()
    assert len(found) == 2 and min(f.recall for f in found) > 0.9


def test_variants_over_a_sensor(spark):
    q, cand = catalog.queries(), C.cut(catalog._cand(spark, SF))
    rows = [((r.series_id, r.t), np.array(r.x)) for r in cand.orderBy("series_id", "t").collect()]
    near = {(a, b): ((x - y) ** 2).sum() for i, (a, x) in enumerate(rows) for b, y in rows[i + 1 :]}
    assert {((r.series_a, r.t_a), (r.series_b, r.t_b)) for r in q["grid_eps_join_sensor"](spark, SF).collect()} == {k for k, v in near.items() if v <= 2.25}
    one = {(f.family): (f.near, f.found) for f in q["hash_tradeoff"](spark, SF).collect()}
    for r in q["hash_tradeoff_sensor"](spark, SF).collect():
        assert r.near == sum(v < 4 for v in near.values()) > one[r.family][0] and one[r.family][1] <= r.found <= r.near
    for name, per_run in (("agglomerate_sensor", "agglomerate_small"), ("cluster_point_link_sensor", "cluster_point_link_per_run"), ("cluster_frozen_centre_sensor", "cluster_frozen_centre"), ("cluster_random_order_sensor", "cluster_random_order_per_run")):
        got = q[name](spark, SF).collect()
        runs = {}
        for r in got:
            runs.setdefault(r.cluster_id, set()).add(r.series_id)
        assert len(got) == len(rows) and max(map(len, runs.values())) > 1


def test_places_of_long_runs_are_not_mixed(spark):
    """Windows 1,000 and 1,000,000 steps on in a run are not those of the next run."""
    rows = [("s", 1, 1000 + i, [0.1 * i] + [0.0] * 9, 0.0) for i in range(4)] + [("s", 2, i, [50.0 + 20 * i] + [0.0] * 9, 0.0) for i in range(4)]
    cand = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double")
    got = sorted(map(tuple, catalog.dbscan_places(cand, 1.0, 3, 10).collect()), key=lambda r: r[:3])
    assert got == [("s", 1, 1000 + i, 1, 1000) for i in range(4)] + [("s", 2, i, None, None) for i in range(4)]
    far = [("s", 1, 1_000_000, [float(i * 40) for i in range(1, 11)], 0.0), ("s", 2, 0, [float(-i * 70) for i in range(1, 11)], 0.0)]
    ids = [r.cluster_id for r in C.cluster_parallel(spark.createDataFrame(far, "sensor string, series_id long, t long, x array<double>, level double"), 1.0, 10).collect()]
    assert len(set(ids)) == 2


def test_planes_are_independent():
    """Normals without mean; no two of 80 are nearly parallel, and sets differ."""
    p = np.array(VEC.fixed_planes(10, 8, 10), float).reshape(-1, 10)
    assert (np.abs(p.sum(axis=1)) <= 10).all()
    p /= np.linalg.norm(p, axis=1)[:, None]
    near = np.abs(p @ p.T)[np.triu_indices(80, 1)]
    assert near.max() < 0.99 and (near > 0.9).mean() < 0.01 and abs(np.corrcoef(p[:40].ravel(), p[40:].ravel())[0, 1]) < 0.2


def test_merges_that_do_not_settle_raise(spark):
    rows = [("s", 0, i, [0.9 * i, 0.0, 0.0, 0.0], 0.0) for i in range(60)]
    cand = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double")
    with pytest.raises(RuntimeError):
        C.cluster_parallel(cand, 1.0, 4, sets=4, per_set=1, merge="components", max_rounds=1).count()
    with pytest.raises(RuntimeError):
        B.dbscan(cand.select("sensor", F.col("t").alias("id"), "x"), 1.0, 2, 4, max_rounds=1).count()


def test_hot_buckets_are_dealt_in_parts(spark, monkeypatch):
    """A bucket with all rows, in parts: every row once, within the radius of a centre; no more clusters than twice those of one part."""
    rng = np.random.default_rng(2)
    rows = [("s", 0, i, (rng.normal(0, 0.05, 4) + 40 * (i % 3)).tolist(), 0.0) for i in range(300)]
    cand = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double")
    got = []
    for size in (20_000, 25):
        monkeypatch.setattr(C, "PART_ROWS", size)
        a = C.cluster_parallel(cand, 1.0, 4, sets=3, per_set=1, family="sign").collect()
        assert len(a) == 300 and max(r.dist for r in a) < 1
        got.append({frozenset(r.t % 3 for r in a if r.cluster_id == c) for c in {r.cluster_id for r in a}})
    assert got[0] == got[1] == {frozenset([i]) for i in range(3)}


def test_rows_outside_of_the_grid_raise(spark):
    with pytest.raises(Exception, match="outside of the grid"):
        spark.range(5).select(V.on_grid(F.col("id"), 3)).collect()
    assert [r[0] for r in spark.range(3).select(V.on_grid(F.col("id"), 3)).collect()] == [0, 1, 2]


def test_separators_give_the_same_members(spark):
    high, win = catalog._high(spark, SF), catalog._planted_windows(spark, SF)
    got = [sorted((r.cluster_id, r.series_id, r.t) for r in X.drop_trivial(high, win, r, separators=s).collect()) for r in (0.3, 2.0) for s in (False, True)]
    assert got[0] == got[1] and got[2] == got[3] and len(got[0]) > len(got[2])


def test_agreement_when_moved(spark):
    a = spark.createDataFrame([("s", 1, 0, [0.0, 0.0, 3.0, 3.0, 0.0, 0.0]), ("s", 2, 0, [5.0, 0.0, 0.0, 0.0, 0.0, -5.0])], "sensor string, motif_id long, level_id long, centroid array<double>")
    b = spark.createDataFrame([("s", 9, 0, [0.0, 0.0, 0.0, 3.0, 3.0, 0.0])], a.schema)
    assert [S.motif_agreement(a, b, 1.0, 6, k).first().agreed for k in (0, 1)] == [0, 1]


def test_sql_functions(spark):
    from wavemotif.functions import sql as SQL

    SQL.register_sql(spark)
    one = lambda e: spark.sql(f"SELECT {e}").first()[0]
    assert one("sq_dist(array(1D, 2D), array(4D, 6D))") == 25 and one("sax_word(array(-1D, -0.1D, 0D, 0.7D))") == "abcd"
    assert one("sax_mindist('abc', 'bcd', 6)") == 0 and one("sax_mindist('ad', 'da', 4)") == pytest.approx((2 * 2 * 1.34**2) ** 0.5)
    assert spark.sql("SELECT count(*) FROM explode_windows(array(1D, 2D, 3D), 2)").first()[0] == 2 and spark.sql("SELECT count(*) FROM explode_windows(null, 2)").first()[0] == 0


def test_purity_and_adjusted_rand(spark):
    rows = [("s", lab, i, [0.0], 0.0, c, 0.0, 0) for i, (lab, c) in enumerate([(0, 0), (0, 0), (1, 1), (1, 1), (1, 0)])]
    r = S.purity(spark.createDataFrame(rows, ROW)).first()
    assert (r.clusters, r.rows, r.pure) == (2, 5, 4) and r.adjusted_rand == pytest.approx((2 - 1.6) / (4 - 1.6), abs=1e-6)
    same = [("s", c, i, [0.0], 0.0, c, 0.0, 0) for i, c in enumerate([0, 0, 1, 1])]
    assert S.purity(spark.createDataFrame(same, ROW)).first().adjusted_rand == 1


def test_time_curve(spark):
    from wavemotif.experiments import runtime_curve

    rows = runtime_curve(spark, SF, (1, 2)).collect()
    assert len(rows) == 8 and all(r.found > 0 and r.seconds > 0 for r in rows) and {r.windows for r in rows} == {338, 676}


def vectors_of(spark, n, seed):
    """n vectors of ten frames with mean zero, in two sensors; the first third is one vector repeated, a hot cell."""
    x = np.random.default_rng(seed).normal(size=(n, 10))
    x[: n // 3] = x[0]
    x -= x.mean(axis=1, keepdims=True)
    return [("ab"[i % 2], i // 7, i % 7, v.tolist()) for i, v in enumerate(x)]


@pytest.mark.parametrize("limit", [100_000, 0])
def test_grid_near_is_exact_in_both_forms(spark, limit):
    a, b = vectors_of(spark, 300, 1), vectors_of(spark, 60, 2) + vectors_of(spark, 300, 1)[:2]
    left = spark.createDataFrame(a, "sensor string, series_id long, t long, x array<double>")
    right = spark.createDataFrame([(s, i, v) for i, (s, _, _, v) in enumerate(b)], "sensor string, k long, y array<double>")
    for eps in (0.5, 2.5):
        got = sorted((r.sensor, r.series_id, r.t, r.k) for r in C.grid_near(left, right, eps, 10, limit=limit, part_rows=20).collect())
        want = sorted((s, i, t, k) for s, i, t, x in a for k, (s2, _, _, y) in enumerate(b) if s == s2 and sum((p - q) ** 2 for p, q in zip(x, y, strict=True)) <= eps * eps)
        assert got == want and got


def test_measures_by_grid_equal_all_centres(spark):
    rows = [(s, i, t, x, 0.0, (i * 7 + t) % 12, 0.0, 0) for s, i, t, x in vectors_of(spark, 240, 3)]
    rows += [("alone", 0, 0, [1.0, -1.0] + [0.0] * 8, 0.0, 0, 0.0, 0)]
    assigned = C.cut(spark.createDataFrame(rows, ROW))
    mean = {(r.sensor, r.cluster_id): np.array(r.centroid) for r in C.centers(assigned, 10).collect()}
    gaps = {(s, i, t): {c: float(((np.array(x) - m) ** 2).sum()) for (s2, c), m in mean.items() if s2 == s} for s, i, t, x, *_ in rows}
    wrong = {s: sum(min(gaps[s, i, t], key=lambda c, g=gaps[s, i, t]: (round(g[c], 9), c)) != k for s2, i, t, _, _, k, _, _ in rows if s2 == s) for s in ("a", "b", "alone")}
    for r in (0.5, 3.0):  # most members beyond r, and none
        assert {x.sensor: x.misplaced for x in S.misplacement(assigned, 10, r).collect()} == wrong
    for r in (1.0, 3.0):
        shared = {s: sum(sum(v < r * r for v in g.values()) > 1 for (s2, _, _), g in gaps.items() if s2 == s) for s in ("a", "b", "alone")}
        assert {x.sensor: x.shared for x in S.overlap_share(assigned, r, 10).collect()} == shared
        rare = {k for k, g in gaps.items() if min(v for c, v in g.items()) > r * r}
        motifs = C.centers(assigned, 10).withColumnRenamed("cluster_id", "motif_id")
        assert {(x.sensor, x.series_id, x.t) for x in M.rare_windows(assigned, motifs, 10**6, r, 10).collect()} == rare
        best = {k: min((round(v, 9), c) for c, v in g.items())[1] for k, g in gaps.items() if min(g.values()) < r * r}
        assert {(x.sensor, x.series_id, x.t): x.motif_id for x in M.match(assigned, motifs, r, 10).collect()} == best


def test_numbers_are_gapless_a_sensor(spark):
    rows = spark.range(5000).select(F.when(F.col("id") % 3 == 0, "a").otherwise("b").alias("sensor"), F.struct(F.col("id").alias("series_id"), (F.col("id") % 5).alias("t")).alias("aid"))
    got = C.numbered(rows, "aid", "own").collect()
    for s in ("a", "b"):
        own = sorted(r.own for r in got if r.sensor == s)
        assert own == list(range(1, len(own) + 1))
    assert sorted(map(str, got)) == sorted(map(str, C.numbered(rows.repartition(3), "aid", "own").collect()))


def test_shifted_forms_a_cluster_at_a_time(spark, monkeypatch):
    """The sums of a row a member equal the sweep, over chunks smaller than a run, and give the same shifted clusters."""
    monkeypatch.setattr(X, "CHUNK_ROWS", 7)
    rng = np.random.default_rng(3)
    rows = [("s", r, int(t), int(c), [0.0]) for r in range(4) for t, c in zip(np.sort(rng.choice(80, 50, replace=False)), rng.integers(-2, 6, 50), strict=True)]
    rows += [("s", 9, t, c, [0.0]) for t in range(0, 200, 20) for c, t in ((7, t), (8, t + 3))]
    a = spark.createDataFrame(rows, "sensor string, series_id long, t long, cluster_id long, x array<double>")
    cols = ["sensor", "small", "large", "small_n", "pairs", "sum_diff", "sum_sq"]
    sweep = X.shift_diffs_sweep(a, 10).select(*cols)
    assert sorted(X.shift_diffs(a, 10).select(*cols).collect()) == sorted(sweep.collect())
    for rule, p in (("deviation", 50), ("deviation", 10), ("share", 30)):
        want = X.shift_matches(sweep, p, 2, rule).collect()
        assert sorted(X.shifted_forms(a, 10, p, 2, rule).select("sensor", "small", "large").collect()) == sorted(want) and want


def test_matching_on_executors_equals_the_grid(spark):
    rng = np.random.default_rng(4)
    x, c = rng.normal(size=(300, 4)), rng.normal(size=(9, 4))
    c[5] = c[2]  # equal motifs: the smaller id wins
    win = spark.createDataFrame([(f"s{i % 2}", 0, i, x[i].tolist()) for i in range(300)], "sensor string, series_id long, t long, x array<double>")
    motifs = spark.createDataFrame([(f"s{j % 2}", 100 - j, c[j].tolist()) for j in range(9)] + [("s0", 7, c[2].tolist())], "sensor string, motif_id long, centroid array<double>")
    got = sorted(M.match(win, motifs, 1.5, 4).collect())
    assert got == sorted(M.match(win, motifs, 1.5, 4, limit=0).collect()) and len(got) > 50
    assert "hashpartitioning(series_id" not in M.match(win, motifs, 1.5, 4)._jdf.queryExecution().executedPlan().toString()


def test_places_are_kept_without_vectors(spark):
    """Stages after clustering hold places only; the vectors of occurrences come back from the clusters."""
    r = PL.discover(V.planted_view(spark, "/root/testdata/sf0.001"), 20, 8, method="words")
    assert all("x" not in r.stages[k].columns for k in ("not_trivial", "groups", "motifs")) and "x" in r.occurrences.columns
    assert r.occurrences.count() == r.stages["motifs"].count() == r.motifs.agg({"support": "sum"}).first()[0] > 0


def test_nearest_later_rows_are_the_first_exact_ones():
    rng = np.random.default_rng(5)
    x = np.round(rng.normal(size=(120, 3)), 1)  # equal distances occur
    s, t = np.repeat(np.arange(6), 20), np.tile(np.arange(20), 6)
    for cells in (1, 1 << 21):
        gap, partner = B.nearest_later(x, s, t, 5, cells)
        for i in range(120):
            free = [j for j in range(i + 1, 120) if s[j] != s[i] or t[j] - t[i] >= 5]
            d2 = [((x[j, 0] - x[i, 0]) ** 2 + (x[j, 1] - x[i, 1]) ** 2) + (x[j, 2] - x[i, 2]) ** 2 for j in free]
            assert (gap[i], partner[i]) == ((min(d2), free[d2.index(min(d2))]) if free else (np.inf, -1))


def test_density_clusters_in_blocks_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(B.near_blocks, "__defaults__", (16,))
    rng = np.random.default_rng(6)
    x = np.round(np.concatenate([rng.normal(c, 0.5, (50, 4)) for c in (0, 3, 9)]), 2)
    x[:4] = x[4]  # equal rows
    cand = spark.createDataFrame([("s", i, v.tolist()) for i, v in enumerate(x)], "sensor string, id long, x array<double>")
    for min_pts in (1, 2, 5):
        near = ((x[:, None] - x[None]) ** 2).sum(axis=2) <= 0.64
        core = near.sum(axis=1) >= min_pts
        root = np.where(core, np.arange(len(x)), len(x))
        for _ in x:
            root = np.where(core, np.where(near & core, root, len(x)).min(axis=1), len(x))
        want = np.where(core, root, np.where(near & core, root, len(x)).min(axis=1))
        got = {r.id: r.cluster_id for r in B.dbscan(cand, 0.8, min_pts, 4).collect()}
        assert [len(x) if got[i] is None else got[i] for i in range(len(x))] == want.tolist()
    pairs = B.near_blocks(cand.transform(C.cut), 0.8, 4, lambda near, u, v, self: u.select([]).append_column("n", [[int(near.sum())] * len(u)]).slice(0, 1), "n long")
    assert pairs.count() > 10  # many blocks


@pytest.mark.parametrize("method", ["all", "cftree"])
def test_rows_of_a_sensor_pass_through_its_task(spark, method):
    """Ids as by insertion in order, over batches smaller than a sensor; no task is handed all rows of a sensor at once."""
    rng = np.random.default_rng(7)
    rows = [("ab"[i % 2], int(i % 7), i, (rng.normal(0, 0.3, 4) + rng.integers(0, 3, 4)).tolist(), 0.0) for i in range(400)]
    cand = spark.createDataFrame(rows, "sensor string, series_id long, t long, x array<double>, level double").repartition(5)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 30)
    try:
        out = C.cluster(cand, 1.0, method)
        got = {(r.sensor, r.series_id, r.t): r for r in out.collect()}
        hashed = {(r.sensor, r.series_id, r.t): r.cluster_id for r in C.cluster(cand, 1.0, method, order="hash").collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert "FlatMapGroups" not in out._jdf.queryExecution().toString() and C.streams(method)
    for s in "ab":
        own = sorted((r for r in rows if r[0] == s), key=lambda r: r[1:3])
        x = np.array([r[3] for r in own])
        ids, evals = C.METHODS[method](x, 1.0)
        c = C.means_of(x, ids)
        assert [got[r[:3]].cluster_id for r in own] == ids.tolist() and {got[r[:3]].evals for r in own} == {evals}
        assert np.allclose([got[r[:3]].dist for r in own], np.sqrt(((x - c[ids]) ** 2).sum(axis=1)))
        own.sort(key=lambda r: ((r[2] * 7919 + 13) % 104_729, r[2], r[1]))
        assert [hashed[r[:3]] for r in own] == C.METHODS[method](np.array([r[3] for r in own]), 1.0)[0].tolist()


@pytest.mark.parametrize("min_pts", [1, 2, 4])
def test_levels_of_large_clusters_take_one_pass(spark, min_pts):
    """Levels as by comparing all rows; no window frame is read again for each row."""
    rng = np.random.default_rng(8)
    level = np.round(rng.uniform(0, 8, 120), 1)
    out = X.split_levels(members(spark, [(1, i, lv) for i, lv in enumerate(level)]), 0.2, min_pts)
    plan = out._jdf.queryExecution().toString()
    assert "RangeFrame, -" not in plan and "unboundedfollowing$" not in plan.split("Physical Plan")[-1]
    lv = np.round(level * 1e9).astype(int)
    near = np.abs(lv[:, None] - lv) <= 200_000_000
    core = near.sum(axis=1) >= min_pts
    steps = np.unique(lv[core])
    ids = dict(zip(steps.tolist(), np.cumsum(np.diff(steps, prepend=steps[:1]) > 200_000_000).tolist(), strict=True))
    want = {i: ids[min(steps.tolist(), key=lambda c: (abs(c - v), c))] for i, v in enumerate(lv.tolist()) if near[i][core].any()}
    assert {r.t: r.level_id for r in out.collect()} == want


def test_segments_of_members_repeat_no_window(spark):
    rng = np.random.default_rng(9)
    win = spark.createDataFrame([("s", i // 60, i % 60, rng.normal(0, 2, 3).tolist()) for i in range(180)], "sensor string, series_id long, t long, x array<double>")
    m = win.where("t % 5 = 0").withColumn("cluster_id", F.pmod("t", F.lit(3))).withColumn("c", F.array(*[F.lit(0.1)] * 3))
    got, keys = X.member_segments(m, win, 0.3, 3)
    want, _, same = X._segments(m, win, 0.3, 3)
    cols = [*keys, "t"]
    assert keys == same and sorted(got.select(*cols).collect()) == sorted(want.select(*cols).collect())
    assert got.select("segment").distinct().count() > 1 and "Window" not in got._jdf.queryExecution().toString()


def test_centres_meet_without_pairs(spark, monkeypatch):
    """Centres that stay, links and nearest centres as by brute force; near centres that share no bucket are merged too."""
    monkeypatch.setattr(C.dominating, "__defaults__", (8,))
    rng = np.random.default_rng(10)
    x, n = np.round(rng.normal(0, 1, (150, 3)), 1), rng.integers(1, 9, 150)
    x = np.unique(x, axis=0)
    n, r2 = n[: len(x)], 0.81
    d2 = sum((x[:, None, c] - x[None, :, c]) ** 2 for c in range(3))
    cores = spark.createDataFrame([("s", i, int(n[i]), v.tolist(), "b") for i, v in enumerate(x)], "sensor string, id long, n long, c array<double>, bucket string")
    kept: list[int] = []
    for i in sorted(range(len(x)), key=lambda i: (-n[i], i)):
        if not (d2[i, kept] < r2).any():
            kept.append(i)
    got = sorted(C.dominating(cores, 0.9).collect(), key=lambda r: r.cluster_id)
    assert [r.cluster_id for r in got] == list(range(len(kept))) and [r.c for r in got] == x[kept].tolist()
    links, root = C.bucket_forest(cores, 0.9, 3, 8).collect(), np.arange(len(x))
    assert all(d2[r.aid, r.bid] < r2 for r in links)
    for r in links:
        root[root == root[r.aid]] = root[r.bid]
    want = np.arange(len(x))
    for _ in x:
        want = np.where(d2 < r2, want, len(x)).min(axis=1)
    assert len(set(root)) == len(set(want)) == len(x) - len(links) and len(set(zip(root, want, strict=True))) == len(set(want))
    hot = spark.createDataFrame([("s", "b", 2)], "sensor string, bucket string, parts long")
    rows = spark.createDataFrame([("s", "b", i % 2, 0, i, v.tolist()) for i, v in enumerate(x + 0.05)], "sensor string, bucket string, part long, series_id long, t long, x array<double>")
    gap = ((x + 0.05)[:, None, 0] - x[None, :, 0]) ** 2 + ((x + 0.05)[:, None, 1] - x[None, :, 1]) ** 2 + ((x + 0.05)[:, None, 2] - x[None, :, 2]) ** 2
    assert {r.t: r.root for r in C.bucket_nearest(rows, cores, hot, 0.9, 3).collect()} == {i: int(g.argmin()) for i, g in enumerate(gap) if g.min() < r2}
    side = np.array(VEC.fixed_planes(1, 1, 4)[0][0], float)
    side /= np.linalg.norm(side)
    apart = [("s", 0, i, (side * (0.05 if i % 2 else -0.05)).tolist(), 0.0) for i in range(6)]
    out = C.cluster_parallel(spark.createDataFrame(apart, "sensor string, series_id long, t long, x array<double>, level double"), 1.0, 4, sets=1, per_set=1)
    assert {r.cluster_id for r in out.collect()} == {0}


def test_windows_outside_of_joined_shard_clusters_are_clustered_again(spark):
    x = np.random.default_rng(11).uniform(0, 4, (1500, 2))
    cand = spark.createDataFrame([("ab"[i % 2], 0, i, v.tolist(), 0.0) for i, v in enumerate(x)], "sensor string, series_id long, t long, x array<double>, level double")
    rows = C.cluster_cf_shards(cand, 1.0, 2, shards=4)
    assert rows.count() == rows.select("sensor", "series_id", "t").distinct().count() == 1500
    assert all(r.outliers < 2 * r.clusters for r in S.radius_outliers(rows, 1.0, 2).collect())
