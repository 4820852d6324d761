"""The registered queries of the engine and their DuckDB counterparts, side by side."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wavemotif import oracles as O
from wavemotif.functions import sql as SQL
from wavemotif.functions import vectors as VEC
from wavemotif.operators import baselines as B
from wavemotif.operators import cluster as C
from wavemotif.operators import extract as X
from wavemotif.operators import matching as M
from wavemotif.operators import measures as S
from wavemotif.operators import prep as P
from wavemotif.operators import relational as R
from wavemotif.plans import pipeline as PL
from wavemotif.sources import files as FS
from wavemotif.sources import views as V
from wavemotif.streaming import stream as ST

W, D = O.W, O.D
Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        _QUERIES[name] = f
        if sql:
            _SQL[name] = sql
        return f

    return put


def both(name: str, sql: str) -> None:
    """A query whose statement is the same in both engines; tables stand in braces."""
    tables = [t for t in ("lineitem", "orders", "customer", "supplier", "nation", "region", "events", "part", "embeddings", "labels", "conversations", "pages") if f"{{{t}}}" in sql]
    _QUERIES[name] = lambda spark, sf_dir: spark.sql(sql, **{t: V.load(spark, sf_dir, t) for t in tables})
    _SQL[name] = sql.format(**{t: t for t in tables})


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PL.discover(V.planted_view(spark, sf_dir), W, 8).motifs


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


# ---------------------------------------------------------------- views
for _name, _f in V.VIEWS.items():
    query(f"series_{_name}_view", {"run": O.RUN, "clock": O.CLOCK, "flag": O.FLAG, "region": O.REGION, "fleet": O.FLEET, "text": O.TEXT, "planted": O.PLANTED}[_name] if _name != "fleet" else f"SELECT sensor, series_id, t, v::BIGINT AS v FROM ({O.FLEET.replace('UNPIVOT f ON', 'FROM (UNPIVOT f ON').replace('VALUE v', 'VALUE v)')})")(_f)
query("series_cumulative_view", O.CUMULATIVE)(lambda s, d: V.cumulative(V.run_view(s, d)))
query("series_smoothed_view", O.SMOOTHED)(lambda s, d: V.smoothed(V.flag_view(s, d)))
query("resample_fill_previous", f"SELECT sensor, count(*) AS steps, min(t) AS first, sum(v)::BIGINT AS total FROM ({O.CLOCK}) GROUP BY 1")(lambda s, d: V.clock_view(s, d).groupBy("sensor").agg(F.count("*").alias("steps"), F.min("t").alias("first"), F.sum("v").alias("total")))


# ---------------------------------------------------------------- pre-processing
def _run(s: SparkSession, d: str) -> DataFrame:
    return V.run_view(s, d)


def _reduced(s: SparkSession, d: str, w: int = W, dims: int = D, f: float | None = None, **k) -> DataFrame:
    return P.reduced_windows(P.znormalize(_run(s, d)), w, dims, f, **k)


def _cand(s: SparkSession, d: str) -> DataFrame:
    return P.candidates(_run(s, d), W, D)


def _rounded(df: DataFrame, dims: int) -> DataFrame:
    return df.select("sensor", "series_id", "t", F.round("level", 6).alias("level"), *[F.round(F.col("x")[j], 6).alias(f"p{j}") for j in range(dims)])


def _rounded_sql(rows: str, dims: int = D) -> str:
    return f"SELECT sensor, series_id, t, round(level, 6) AS level, {', '.join(f'round(p{j}, 6) AS p{j}' for j in range(dims))} FROM ({rows})"


query("znorm_run", f"SELECT sensor, series_id, t, round(z, 6) AS z FROM ({O.z(O.RUN)})")(lambda s, d: P.znormalize(_run(s, d)).select("sensor", "series_id", "t", F.round("z", 6).alias("z")))
query("znorm_sensor", f"SELECT sensor, series_id, t, round(z, 6) AS z FROM ({O.z(O.RUN, 'sensor')})")(lambda s, d: P.znormalize(_run(s, d), "sensor").select("sensor", "series_id", "t", F.round("z", 6).alias("z")))
query("window_count_identity", f"SELECT sensor, sum(greatest(n - {W - 1}, 0))::BIGINT AS windows FROM (SELECT sensor, series_id, count(*) AS n FROM ({O.RUN}) GROUP BY 1, 2) GROUP BY 1")(lambda s, d: P.expected_windows(_run(s, d), W))
query("windows_materialized", f"SELECT series_id, t, round(a, 6) AS first, round(b, 6) AS last FROM (SELECT series_id, t, z AS a, lead(z, {W - 1}) OVER (PARTITION BY series_id ORDER BY t) AS b FROM ({O.z(O.RUN)})) WHERE b IS NOT NULL")(lambda s, d: P.materialized_windows(P.znormalize(_run(s, d)), W).select("series_id", "t", F.round(F.col("win")[0], 6).alias("first"), F.round(F.col("win")[W - 1], 6).alias("last")))
query("flat_filter_range", f"SELECT series_id, t FROM ({O.reduced(O.RUN)}) WHERE dev >= 3.5")(lambda s, d: _reduced(s, d, f=3.5).select("series_id", "t"))
query("flat_filter_from_mean", f"SELECT series_id, t FROM ({O.reduced(O.RUN)}) WHERE dev2 >= 2.5")(lambda s, d: _reduced(s, d, f=2.5, deviation="from_mean").select("series_id", "t"))
query("merge_levels", _rounded_sql(O.reduced(O.RUN)))(lambda s, d: _rounded(_reduced(s, d), D))
query("merge_levels_fractional", _rounded_sql(O.reduced(O.RUN, 14, 5), 5))(lambda s, d: _rounded(_reduced(s, d, 14, 5), 5))
query("sax_words", f"SELECT series_id, t, word FROM ({O.words(O.reduced(O.RUN))})")(lambda s, d: _reduced(s, d).select("series_id", "t", VEC.sax_word(F.col("x"), D).alias("word")))
query("drop_repeated_words", f"SELECT series_id, t, word FROM ({O.candidates(O.CLOCK)})")(lambda s, d: P.candidates(V.clock_view(s, d), W, D).select("series_id", "t", "word"))
query("drop_repeated_words_adjacent", f"SELECT series_id, t, word FROM ({O.candidates(O.RUN, adjacency='step')})")(lambda s, d: P.drop_repeated_words(_reduced(s, d, f=1.0), D, adjacency="step").select("series_id", "t", "word"))
query("candidate_matrix", f"SELECT sensor, series_id, count(*) AS candidates, count(DISTINCT word) AS words FROM ({O.candidates(O.PLANTED)}) GROUP BY 1, 2")(lambda s, d: P.candidates(V.planted_view(s, d), W, D).groupBy("sensor", "series_id").agg(F.count("*").alias("candidates"), F.count_distinct("word").alias("words")))

# ---------------------------------------------------------------- clustering
_ids = ("series_id", "t", "cluster_id")
_per_run = {"group": ("sensor", "series_id")}
query("cluster_all_per_run", O.sequential(O.RUN, 2.0))(lambda s, d: C.cluster(_cand(s, d), 2.0, "all", **_per_run).select(*_ids))
query("cluster_point_link_per_run", O.sequential(O.RUN, 1.5, link="point"))(lambda s, d: C.cluster(_cand(s, d), 1.5, "point", **_per_run).select(*_ids))
query("cluster_frozen_centre", O.sequential(O.RUN, 2.0, frozen=True))(lambda s, d: C.cluster(_cand(s, d), 2.0, "all", frozen=True, **_per_run).select(*_ids))
query("cluster_random_order_per_run", O.sequential(O.RUN, 2.0, order="(t * 7919 + 13) % 104729"))(lambda s, d: C.cluster(_cand(s, d), 2.0, "all", order="hash", **_per_run).select(*_ids))
# the same forms over all runs of a sensor
query("cluster_point_link_sensor")(lambda s, d: C.cluster(_cand(s, d), 1.5, "point").select(*_ids))
query("cluster_frozen_centre_sensor")(lambda s, d: C.cluster(_cand(s, d), 2.0, "all", frozen=True).select(*_ids))
query("cluster_random_order_sensor")(lambda s, d: C.cluster(_cand(s, d), 2.0, "all", order="hash").select(*_ids))

_ONE_EACH = f"SELECT series_id, count(*) AS members, count(*) AS assigned FROM ({O.candidates(O.RUN)}) GROUP BY 1"


def _one_each(cand: DataFrame, assigned: DataFrame) -> DataFrame:
    got = assigned.groupBy("series_id").agg(F.count_distinct("t").alias("assigned"))
    return cand.groupBy("series_id").agg(F.count("*").alias("members")).join(got, "series_id")


for _m in ("cftree", "hash"):
    query("cluster_cftree" if _m == "cftree" else "cluster_hashed", _ONE_EACH)(lambda s, d, m=_m: _one_each(_cand(s, d), C.cluster(_cand(s, d), 1.0, m, **({} if m == "hash" else {"refine": True}))))
query("cluster_parallel_dominating", _ONE_EACH)(lambda s, d: _one_each(_cand(s, d), C.cluster_parallel(_cand(s, d), 1.0, D, sets=5, per_set=6)))
query("cluster_parallel_components", _ONE_EACH)(lambda s, d: _one_each(_cand(s, d), C.cluster_parallel(_cand(s, d), 1.0, D, sets=5, per_set=6, merge="components")))

query("cluster_cf_shards", _ONE_EACH)(lambda s, d: _one_each(_cand(s, d), C.cluster_cf_shards(_cand(s, d), 1.0, D, shards=8)))
query("cluster_recluster_outliers", _ONE_EACH)(lambda s, d: _one_each(_cand(s, d), C.cluster(_cand(s, d), 1.0, "cftree", recluster=3)))


@query("cluster_raw_radius", f"SELECT series_id, count(*) AS windows, count(*) AS same FROM ({O.reduced(O.RUN)}) GROUP BY 1")
def _raw_radius(s: SparkSession, d: str) -> DataFrame:
    """Clusters of raw windows with the radius of the sensor's deviation beside those of z-scores with radius 2: the same ones."""
    raw = C.cluster(P.reduced_windows(P.raw_values(_run(s, d)), W, D, None), P.sensor_radius(_run(s, d), 2.0), **_per_run).select(*_ids)
    z = C.cluster(P.reduced_windows(P.znormalize(_run(s, d), "sensor"), W, D, None), 2.0, **_per_run).select("series_id", "t", F.col("cluster_id").alias("z_id"))
    return raw.join(z, ["series_id", "t"]).groupBy("series_id").agg(F.count("*").alias("windows"), F.count_if(F.col("cluster_id") == F.col("z_id")).alias("same"))


_MEASURED = {"euclidean_centred": "p{j}", "euclidean": "p{j} + level", "euclidean_znorm": "p{j} / nullif(sqrt((" + " + ".join(f"p{j} * p{j}" for j in range(D)) + f") / {float(D)}::DOUBLE), 0)"}
for _m, _e in _MEASURED.items():
    _xs = ", ".join(_e.format(j=j) for j in range(D))
    query(f"distance_{_m}", f"SELECT series_id, count(*) FILTER ({O.sq('x', 'y')} < 4)::BIGINT AS near, count(*) AS pairs FROM (SELECT series_id, x, lead(x) OVER (PARTITION BY series_id ORDER BY t) AS y FROM (SELECT series_id, t, [{_xs}] AS x FROM ({O.reduced(O.RUN)}))) WHERE y IS NOT NULL GROUP BY 1")(lambda s, d, m=_m: neighbours_near(P.for_measure(_reduced(s, d), D, m), 2.0, D))


def neighbours_near(win: DataFrame, r: float, d: int) -> DataFrame:
    """How many windows of a run lie within r of the next one."""
    rows = win.select("series_id", "x", F.lead("x").over(Window.partitionBy("sensor", "series_id").orderBy("t")).alias("y")).where("y is not null")
    return rows.groupBy("series_id").agg(F.count_if(VEC.sq_dist("x", "y", d) < r * r).alias("near"), F.count("*").alias("pairs"))


def _bucket_rows(s: SparkSession, d: str, family: str) -> DataFrame:
    planes = VEC.fixed_planes(5, 3, D)
    keys = F.array(*[VEC.bucket_key(F.col("x"), p, family) for p in planes])
    return _cand(s, d).select("sensor", "series_id", "t", F.posexplode(keys).alias("set", "bucket"))


for _fam in ("sign", "quantised"):
    query(f"hash_bucket_ids_{_fam}", O.bucket_rows(O.RUN, _fam))(lambda s, d, f=_fam: _bucket_rows(s, d, f))
query("hash_candidate_pairs", f"WITH b AS ({O.bucket_rows(O.RUN, 'quantised')}) SELECT a.series_id, count(DISTINCT (a.t, b.t)) AS pairs FROM b a JOIN b ON a.series_id = b.series_id AND a.set = b.set AND a.bucket = b.bucket AND a.t < b.t GROUP BY 1")(lambda s, d: (lambda a: a.join(a.select("series_id", "set", "bucket", F.col("t").alias("t2")), ["series_id", "set", "bucket"]).where("t < t2").groupBy("series_id").agg(F.count_distinct("t", "t2").alias("pairs")))(_bucket_rows(s, d, "quantised")))

_NEAR = f"SELECT series_id, t, [{', '.join(f'p{j}' for j in range(D))}] AS x FROM ({O.candidates(O.RUN)})"
query("hash_tradeoff", " UNION ALL ".join(f"SELECT '{f}' AS family, count(*) AS near, count(h.t) AS found FROM (SELECT a.series_id, a.t, b.t AS u FROM ({_NEAR}) a JOIN ({_NEAR}) b ON a.series_id = b.series_id AND a.t < b.t WHERE {O.sq('a.x', 'b.x')} < 4) p LEFT JOIN (SELECT DISTINCT a.series_id, a.t, b.t AS u FROM ({O.bucket_rows(O.RUN, f)}) a JOIN ({O.bucket_rows(O.RUN, f)}) b ON a.series_id = b.series_id AND a.set = b.set AND a.bucket = b.bucket AND a.t < b.t) h ON h.series_id = p.series_id AND h.t = p.t AND h.u = p.u" for f in ("sign", "quantised")))(lambda s, d: _hash_tradeoff(s, d))


def _hash_tradeoff(s: SparkSession, d: str) -> DataFrame:
    c = _cand(s, d).select("series_id", "t", "x")
    near = c.join(c.select("series_id", F.col("t").alias("u"), F.col("x").alias("y")), "series_id").where("t < u").where(VEC.sq_dist("x", "y", D) < 4).select("series_id", "t", "u")
    out = None
    for f in ("sign", "quantised"):
        b = _bucket_rows(s, d, f)
        hit = b.join(b.select("series_id", "set", "bucket", F.col("t").alias("u")), ["series_id", "set", "bucket"]).where("t < u").select("series_id", "t", "u").distinct().withColumn("hit", F.lit(1))
        row = near.join(hit, ["series_id", "t", "u"], "left").agg(F.lit(f).alias("family"), F.count("*").alias("near"), F.count("hit").alias("found"))
        out = row if out is None else out.unionByName(row)
    return out


query("grid_eps_join", f"SELECT a.series_id, a.t, b.t AS u FROM ({_NEAR}) a JOIN ({_NEAR}) b ON a.series_id = b.series_id AND a.t < b.t WHERE {O.sq('a.x', 'b.x')} <= 2.25")(lambda s, d: C.eps_join(_cand(s, d).select(F.col("series_id").alias("sensor"), F.col("t").alias("id"), "x"), 1.5, D).select(F.col("sensor").alias("series_id"), F.col("aid").alias("t"), F.col("bid").alias("u")))


@query("grid_eps_join_sensor", f"SELECT 'value' AS sensor, a.series_id AS series_a, a.t AS t_a, b.series_id AS series_b, b.t AS t_b FROM ({_NEAR}) a JOIN ({_NEAR}) b ON (a.series_id < b.series_id OR (a.series_id = b.series_id AND a.t < b.t)) AND {O.sq('a.x', 'b.x')} <= 2.25")
def _eps_sensor(s: SparkSession, d: str) -> DataFrame:
    """Near pairs over all runs of a sensor, by place."""
    pairs = C.eps_join(_cand(s, d).select("sensor", F.struct("series_id", "t").alias("id"), "x"), 1.5, D)
    return pairs.select("sensor", F.col("aid.series_id").alias("series_a"), F.col("aid.t").alias("t_a"), F.col("bid.series_id").alias("series_b"), F.col("bid.t").alias("t_b"))


@query("hash_tradeoff_sensor")
def _hash_tradeoff_sensor(s: SparkSession, d: str) -> DataFrame:
    """Near pairs over all runs of a sensor, and those that share a bucket, by family."""
    planes, families = VEC.fixed_planes(5, 3, D), ("sign", "quantised")
    keys = [F.array(*[VEC.bucket_key(F.col("x"), p, f) for p in planes]).alias(f) for f in families]
    a = C.cut(_cand(s, d).select("sensor", F.struct("series_id", "t").alias("id"), "x", *keys))
    b = a.select("sensor", F.col("id").alias("other"), F.col("x").alias("y"), *[F.col(f).alias(f"{f}_b") for f in families])
    near = a.join(b, "sensor").where("id < other").where(VEC.sq_dist("x", "y", D) < 4)
    hit = lambda f: F.count_if(F.exists(F.zip_with(f, f"{f}_b", lambda p, q: p == q), lambda h: h))
    both = near.agg(F.count("*").alias("near"), *[hit(f).alias(f) for f in families])
    return both.select("near", F.explode(F.array(*[F.struct(F.lit(f).alias("family"), F.col(f).alias("found")) for f in families])).alias("r")).select("r.family", "near", "r.found")


_CF = f"SELECT series_id, count(*) AS n, {', '.join(f'round(sum(p{j}), 6) AS ls{j}' for j in range(3))}, round(sum({' + '.join(f'p{j} * p{j}' for j in range(D))}), 6) AS ss FROM ({O.candidates(O.RUN)}) GROUP BY 1"
_cf_cols = lambda: ["series_id", F.col("cf.n").alias("n"), *[F.round(F.col("cf.ls")[j], 6).alias(f"ls{j}") for j in range(3)], F.round("cf.ss", 6).alias("ss")]
query("cf_triples", _CF)(lambda s, d: _cand(s, d).groupBy("series_id").agg(VEC.cf_sum(F.col("x"), D).alias("cf")).select(*_cf_cols()))


@query("cf_merge", _CF)
def _cf_merge(s: SparkSession, d: str) -> DataFrame:
    parts = _cand(s, d).groupBy("series_id", (F.col("t") % 2).alias("half")).agg(VEC.cf_sum(F.col("x"), D).alias("cf"))
    a, b = (parts.where(f"half = {i}").select("series_id", F.col("cf").alias(f"c{i}")) for i in (0, 1))
    return a.join(b, "series_id").withColumn("cf", VEC.cf_merge(F.col("c0"), F.col("c1"))).select(*_cf_cols())


query("adjusted_radius_table", O.RADII)(lambda s, d: _run(s, d).groupBy("series_id").agg(F.count("*").alias("w")).select("series_id", "w", F.round(VEC.adjusted_radius_of("w"), 6).alias("r")))
_ALL_X = f"SELECT series_id, t, [{', '.join(f'p{j}' for j in range(D))}] AS x FROM ({O.reduced(O.RUN)})"
query("nontrivial_pairs", f"WITH w AS MATERIALIZED ({_ALL_X}), p AS (SELECT a.series_id, a.t, b.t AS u, a.x, b.x AS y FROM w a JOIN w b ON a.series_id = b.series_id AND a.t < b.t WHERE {O.sq('a.x', 'b.x')} <= 4) SELECT series_id, t, u, EXISTS (SELECT 1 FROM w m WHERE m.series_id = p.series_id AND m.t > p.t AND m.t < p.u AND {O.sq('m.x', 'p.x')} > 4 AND {O.sq('m.x', 'p.y')} > 4) AS nontrivial FROM p")(lambda s, d: nontrivial_pairs(_reduced(s, d), 2.0, D).select("series_id", "t", "u", "nontrivial"))


def nontrivial_pairs(win: DataFrame, delta: float, d: int) -> DataFrame:
    """Pairs of windows of one run within delta, and whether a window between them is farther than delta from both."""
    w = win.select("series_id", "t", "x")
    p = w.join(w.select("series_id", F.col("t").alias("u"), F.col("x").alias("y")), "series_id").where("t < u").where(VEC.sq_dist("x", "y", d) <= delta**2)
    m = win.select(F.col("series_id").alias("s"), F.col("t").alias("tm"), F.col("x").alias("z"))
    apart = (VEC.sq_dist("z", "x", d) > delta**2) & (VEC.sq_dist("z", "y", d) > delta**2)
    return p.join(m, (F.col("series_id") == F.col("s")) & (F.col("tm") > F.col("t")) & (F.col("tm") < F.col("u")) & apart, "left").groupBy("series_id", "t", "u").agg((F.count("s") > 0).alias("nontrivial"))


# ---------------------------------------------------------------- extraction, over a coarse deterministic grouping
def _coarse(s: SparkSession, d: str) -> DataFrame:
    c = P.candidates(V.planted_view(s, d), W, D)
    return C.word_clusters(c.withColumn("word", F.concat(*[F.when(F.col("x")[j] < 0, "0").otherwise("1") for j in range(0, D, 2)])), D)


_COARSE = O.first_letters(O.PLANTED)
_HIGH = O.supported(_COARSE, 200)


def _high(s: SparkSession, d: str) -> DataFrame:
    return X.high_support(_coarse(s, d), 200)


query("high_support", f"SELECT cluster_id, count(*) AS n FROM ({_HIGH}) GROUP BY 1")(lambda s, d: _high(s, d).groupBy("cluster_id").agg(F.count("*").alias("n")))
query("high_support_runs", f"SELECT cluster_id, count(DISTINCT series_id) AS runs FROM ({O.supported(_COARSE, 28, 'count(DISTINCT series_id)')}) GROUP BY 1")(lambda s, d: X.high_support(_coarse(s, d), 28, "runs").groupBy("cluster_id").agg(F.count_distinct("series_id").alias("runs")))
query("shift_diff_list", O.shift_diffs(_HIGH))(lambda s, d: X.shift_diffs(_high(s, d), 10))
query("shift_diff_sweep", O.shift_diffs(_HIGH))(lambda s, d: X.shift_diffs_sweep(_high(s, d), 10))
query("drop_shifted", f"WITH h AS MATERIALIZED ({_HIGH}) SELECT DISTINCT cluster_id FROM h WHERE cluster_id NOT IN (SELECT small FROM ({O.matches('SELECT * FROM h')}))")(lambda s, d: X.drop_shifted(_high(s, d), cascade="independent").select("cluster_id").distinct())
query("drop_shifted_share", f"WITH h AS MATERIALIZED ({_HIGH}) SELECT DISTINCT cluster_id FROM h WHERE cluster_id NOT IN (SELECT small FROM ({O.matches('SELECT * FROM h', 'share')}))")(lambda s, d: X.drop_shifted(_high(s, d), cascade="independent", rule="share").select("cluster_id").distinct())
query("drop_shifted_greedy", O.greedy(_HIGH))(lambda s, d: X.drop_shifted(_high(s, d)).select("cluster_id").distinct())
_LEVELS = f"""WITH g AS (SELECT series_id, t, cluster_id, round(level * 1e9)::BIGINT AS lv FROM ({_HIGH})),
 c AS (SELECT *, count(*) OVER (PARTITION BY cluster_id ORDER BY lv RANGE BETWEEN 20000000 PRECEDING AND 20000000 FOLLOWING) >= 3 AS core FROM g),
 k AS (SELECT cluster_id, lv, sum(j) OVER (PARTITION BY cluster_id ORDER BY lv) AS level_id FROM (SELECT *, CASE WHEN lv - lag(lv) OVER (PARTITION BY cluster_id ORDER BY lv) > 20000000 THEN 1 ELSE 0 END AS j FROM (SELECT DISTINCT cluster_id, lv FROM c WHERE core)))
 SELECT c.cluster_id, k.level_id::BIGINT AS level_id, count(*) AS n FROM c, LATERAL (SELECT level_id FROM k WHERE k.cluster_id = c.cluster_id AND abs(k.lv - c.lv) <= 20000000 ORDER BY abs(k.lv - c.lv), k.lv LIMIT 1) k GROUP BY 1, 2 HAVING count(*) > 5"""
_M = f"SELECT series_id AS sid, count(*)::DOUBLE AS n, sum(v)::BIGINT AS s, sqrt((count(*)::DECIMAL(38,0) * sum(v::DECIMAL(18,0) * v::DECIMAL(18,0))::DECIMAL(38,0) - sum(v)::DECIMAL(38,0) * sum(v))::DOUBLE) AS dev FROM ({O.PLANTED}) GROUP BY 1"
_RAW_HIGH = f"(SELECT h.* REPLACE ((level * dev + s::DOUBLE) / n AS level) FROM ({_HIGH}) h JOIN ({_M}) m ON h.series_id = m.sid)"
query("level_dbscan_raw", _LEVELS.replace(f"({_HIGH})", _RAW_HIGH).replace("20000000", "5000000000"))(lambda s, d: X.split_levels(X.raw_levels(_high(s, d), P.moments(V.planted_view(s, d))), 5.0, 3, 5).groupBy("cluster_id", "level_id").agg(F.count("*").alias("n")))
query("level_dbscan", _LEVELS)(lambda s, d: X.split_levels(_high(s, d), 0.02, 3, 5).groupBy("cluster_id", "level_id").agg(F.count("*").alias("n")))


# ---------------------------------------------------------------- whole procedure: accuracy on planted shapes
def _support(spark: SparkSession, d: str) -> int:
    return max(2, int(0.85 * V.load(spark, d, "supplier").count()))


def _planted(s: SparkSession, d: str, w: int = W, **options) -> PL.MotifResult:
    """Motifs of the planted view in at least 85 percent as many places as there are runs."""
    return PL.discover(V.planted_view(s, d), w, _support(s, d), **options)


def planted_quality(series: DataFrame, truth: DataFrame, support: int, w: int = W, **options) -> DataFrame:
    """shape, instances, found, members, recall, precision of the best motif of each shape."""
    q = S.match_quality(PL.discover(series, w, support, **options).stages["motifs"], truth)
    return q.withColumns({c: F.round(c, 4) for c in ("recall", "precision")})


def _accuracy(w: int = W, **options) -> Query:
    return lambda s, d: planted_quality(V.planted_view(s, d), V.planted_truth(s, d), _support(s, d), w, **options)


#: Least share of planted instances (held step, two pulses) that the best motif of a shape finds over all runs of a table, by method.
LEAST_FOUND = {"all": (0.75, 0.6), "cftree": (0.75, 0.55), "hash": (0.7, 0.6), "parallel": (0.85, 0.8), "cf_shards": (0.9, 0.85)}
_PLACES = "SELECT k.series_id, b.range AS b FROM (SELECT DISTINCT l_suppkey AS series_id FROM lineitem) k, range(5) b"


def guarded(s: SparkSession, d: str, method: str, **options) -> DataFrame:
    """shape, instances, enough (the share found is as large as is known for the method), below_twice (members farther than the radius
    from their final centroid are fewer than twice the clusters, in every sensor)."""
    r, least = _planted(s, d, method=method, **options), LEAST_FOUND[method]
    found = S.match_quality(r.stages["motifs"], V.planted_truth(s, d))
    bound = S.radius_outliers(r.stages["clusters"], 1.0, D).agg(F.min("below_twice").alias("below_twice"))
    enough = F.col("recall") >= F.when(F.col("shape") == "held_step", least[0]).otherwise(least[1])
    return found.crossJoin(F.broadcast(bound)).select("shape", "instances", enough.alias("enough"), "below_twice")  # one row


#: The sequential methods open more spheres beside a frequent shape the more runs there are, so theirs are joined after the pass.
_PIPELINE = {"cf_shards": {"shards": 8}, "all": {"rejoin": True}, "cftree": {"rejoin": True}}
for _m in LEAST_FOUND:
    query(f"motifs_pipeline_{_m}", f"SELECT shape, count(*) AS instances, true AS enough, true AS below_twice FROM ({_PLACES}), (VALUES ('held_step'), ('two_pulses')) v(shape) GROUP BY 1")(lambda s, d, m=_m: guarded(s, d, m, **_PIPELINE.get(m, {})))
query("motifs_multi_width")(lambda s, d: PL.discover_many(V.planted_view(s, d), (14, 20, 40), _support(s, d)).select("w", "sensor", "motif_id", "level_id", "support", "runs"))
query("ablation_no_shift_no_trivial")(lambda s, d: _planted(s, d, skip=("flat", "words", "shifted", "trivial")).funnel())

# ---------------------------------------------------------------- measures, over sequential clusters of runs
_SEQ = O.sequential(O.RUN, 2.0)


def _seq(s: SparkSession, d: str) -> DataFrame:
    """Clusters of runs side by side: the run is the sensor, so that measures are taken for each."""
    return C.cut(C.cluster(_cand(s, d), 2.0, "all", group=("sensor", "series_id")).withColumn("sensor", F.col("series_id").cast("string")))


_SEQ_X = f"SELECT s.series_id::VARCHAR AS sensor, s.series_id, s.t, s.cluster_id, w.x FROM seq s JOIN ({_ALL_X}) w ON w.series_id = s.series_id AND w.t = s.t"
_CENT = f"SELECT sensor, cluster_id, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c, count(*) AS n FROM m GROUP BY 1, 2"


def _measure(body: str) -> str:
    head, tail = _SEQ.rsplit(" SELECT series_id, t, cluster_id FROM s", 1)
    return f"{head}, seq AS MATERIALIZED (SELECT series_id, t, cluster_id FROM s), m AS MATERIALIZED ({_SEQ_X}), k AS MATERIALIZED ({_CENT}) {body}"


query("radius_outliers", _measure(f"SELECT sensor, count(*) FILTER ({O.sq('x', 'c')} > 4) AS outliers, count(DISTINCT cluster_id) AS clusters, count(*) FILTER ({O.sq('x', 'c')} > 4) < 2 * count(DISTINCT cluster_id) AS below_twice FROM m JOIN k USING (sensor, cluster_id) GROUP BY 1"))(lambda s, d: S.radius_outliers(_seq(s, d), 2.0, D))
query("cluster_diameter", _measure(f"SELECT a.sensor, a.cluster_id, count(*) FILTER (a.t = b.t) AS n, round(sqrt(max({O.sq('a.x', 'b.x')})), 6) AS diameter, max({O.sq('a.x', 'b.x')}) <= 16 AS within FROM m a JOIN m b ON a.sensor = b.sensor AND a.cluster_id = b.cluster_id AND a.t <= b.t GROUP BY 1, 2"))(lambda s, d: S.cluster_diameter(_seq(s, d), 2.0, D))
query("misplacement", _measure(f"SELECT sensor, count(*) AS members, count(*) FILTER (best <> cluster_id) AS misplaced FROM (SELECT m.sensor, m.t, m.cluster_id, min_by(k.cluster_id, {O.sq('m.x', 'k.c')}) AS best FROM m JOIN k USING (sensor) GROUP BY 1, 2, 3) GROUP BY 1".replace("JOIN k USING (sensor)", "JOIN k ON k.sensor = m.sensor")))(lambda s, d: S.misplacement(_seq(s, d), D))
query("tightness", _measure(f"SELECT m.sensor, m.cluster_id, count(*) AS n, round(avg(sqrt({O.sq('x', 'c')})), 6) AS mean_dist, round(max(sqrt({O.sq('x', 'c')})), 6) AS max_dist FROM m JOIN k ON k.sensor = m.sensor AND k.cluster_id = m.cluster_id GROUP BY 1, 2"))(lambda s, d: S.tightness(_seq(s, d), D))
query("overlap_share", _measure(f"SELECT sensor, count(*) AS members, count(*) FILTER (c > 1) AS shared FROM (SELECT m.sensor, m.t, count(*) FILTER ({O.sq('m.x', 'k.c')} < 4) AS c FROM m JOIN k ON k.sensor = m.sensor GROUP BY 1, 2) GROUP BY 1"))(lambda s, d: S.overlap_share(_seq(s, d), 2.0, D))
query("candidate_set_size")(lambda s, d: (lambda c: C.cluster(c, 1.0, "all").select(F.lit("all").alias("method"), "evals").distinct().unionByName(C.cluster(c, 1.0, "cftree").select(F.lit("cftree").alias("method"), "evals").distinct()).unionByName(C.cluster(c, 1.0, "hash").select(F.lit("hash").alias("method"), "evals").distinct()))(C.cut(P.candidates(V.planted_view(s, d), W, D))))


@query("purity_embeddings")
def _purity(s: SparkSession, d: str) -> DataFrame:
    """Purity of clusters of the given vectors, whose labels do not follow their distances: adjusted_rand is near 0 for any method."""
    rows = V.load(s, d, "embeddings").select(F.lit("embedding").alias("sensor"), F.col("label").cast("long").alias("series_id"), F.col("vec_id").alias("t"), F.transform("embedding", lambda e: e.cast("double")).alias("x"), F.lit(0.0).alias("level"))
    return S.purity(C.cluster(rows, 1.2, "all"))


@query("motif_agreement")
def _agreement(s: SparkSession, d: str) -> DataFrame:
    a, b = (_planted(s, d, method=m).motifs for m in ("cftree", "all"))
    return S.motif_agreement(a, b, 1.0, D)


# ---------------------------------------------------------------- baselines
_PAIRS = f"SELECT a.series_id AS series_a, a.t AS t_a, b.series_id AS series_b, b.t AS t_b, {O.sq('a.x', 'b.x')} AS d2 FROM w a JOIN w b ON a.series_id < b.series_id OR (a.series_id = b.series_id AND b.t - a.t >= 20)"
_PAIR_SQL = f"WITH w AS MATERIALIZED (SELECT * FROM ({_ALL_X})) SELECT series_a, t_a, series_b, t_b, round(d2, 6) AS d2 FROM ({_PAIRS}) ORDER BY d2, series_a, t_a, series_b, t_b LIMIT 1"
for _m in ("brute", "reference"):
    query(f"closest_pair_{_m}", _PAIR_SQL)(lambda s, d, m=_m: B.closest_pair(C.cut(_reduced(s, d)), D, W, m).select("series_a", "t_a", "series_b", "t_b", F.round("d2", 6).alias("d2")))
for _m in ("radius", "description_length"):
    query(f"closest_pair_grouping_{'dl' if _m != 'radius' else _m}")(lambda s, d, m=_m: B.closest_pair_grouping(_reduced(s, d), D, W, m, r=1.5))
query("agglomerate_small")(lambda s, d: B.agglomerate(_cand(s, d), 2.0).select(*_ids))
query("agglomerate_sensor")(lambda s, d: B.agglomerate(_cand(s, d), 2.0, group=("sensor",)).select(*_ids))
query("kmeans_lloyd3", O.lloyd(O.RUN, 8, 3))(lambda s, d: B.kmeans_lloyd(_cand(s, d), 8, 3, D))
query("kmeans_ml")(lambda s, d: B.kmeans_ml(_cand(s, d), 8).select("series_id", "t", "cluster_id"))
_DB = f"""WITH RECURSIVE w AS MATERIALIZED (SELECT series_id * 1000 + t AS id, x FROM ({_NEAR})),
 e AS MATERIALIZED (SELECT a.id AS a, b.id AS b FROM w a JOIN w b ON a.id <> b.id AND {O.sq('a.x', 'b.x')} <= 2.25),
 c AS MATERIALIZED (SELECT a AS id FROM e GROUP BY 1 HAVING count(*) + 1 >= 4), l AS MATERIALIZED (SELECT e.a, e.b FROM e JOIN c x ON x.id = e.a JOIN c y ON y.id = e.b),
 r AS (SELECT id, id AS root FROM c UNION SELECT l.a, r.root FROM r JOIN l ON l.b = r.id WHERE r.root < l.a), k AS MATERIALIZED (SELECT id, min(root) AS root FROM r GROUP BY 1)
 SELECT w.id, coalesce(k.root, (SELECT min(k2.root) FROM e JOIN k k2 ON k2.id = e.b WHERE e.a = w.id)) AS cluster_id FROM w LEFT JOIN k ON k.id = w.id"""


def dbscan_places(cand: DataFrame, eps: float, min_pts: int, d: int) -> DataFrame:
    """sensor, series_id, t and the place that names its cluster: cluster_series, cluster_t (null for noise). Places are keys as they are."""
    got = B.dbscan(cand.select("sensor", F.struct("sensor", "series_id", "t").alias("id"), "x"), eps, min_pts, d)
    return got.select("id.sensor", "id.series_id", "id.t", F.col("cluster_id.series_id").alias("cluster_series"), F.col("cluster_id.t").alias("cluster_t"))


query("dbscan_windows", _DB)(lambda s, d: dbscan_places(_cand(s, d), 1.5, 4, D).select((F.col("series_id") * 1000 + F.col("t")).alias("id"), (F.col("cluster_series") * 1000 + F.col("cluster_t")).alias("cluster_id")))
query("dbscan_windows_by_place", f"SELECT 'value' AS sensor, id // 1000 AS series_id, id % 1000 AS t, cluster_id // 1000 AS cluster_series, cluster_id % 1000 AS cluster_t FROM ({_DB})")(lambda s, d: dbscan_places(_cand(s, d), 1.5, 4, D))

# ---------------------------------------------------------------- use of motifs
_MEANS = f"SELECT cluster_id AS motif_id, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c FROM (SELECT * FROM h) GROUP BY 1"
_ALL_P = f"SELECT series_id, t, [{', '.join(f'p{j}' for j in range(D))}] AS x FROM ({O.reduced(O.PLANTED)})"


def _means(s: SparkSession, d: str) -> DataFrame:
    return C.centers(_high(s, d), D).select("sensor", F.col("cluster_id").alias("motif_id"), "centroid")


def _planted_windows(s: SparkSession, d: str) -> DataFrame:
    return P.reduced_windows(P.znormalize(V.planted_view(s, d)), W, D, None)


query("match_motifs", f"WITH h AS MATERIALIZED ({_HIGH}), k AS MATERIALIZED ({_MEANS}) SELECT series_id, t, min_by(motif_id, d2) AS motif_id FROM (SELECT w.series_id, w.t, k.motif_id, {O.sq('w.x', 'k.c')} AS d2 FROM ({_ALL_P}) w, k) WHERE d2 < 4 GROUP BY 1, 2")(lambda s, d: M.match(_planted_windows(s, d), _means(s, d), 2.0, D).select("series_id", "t", "motif_id"))
_OCC = f"SELECT sensor, series_id, t, cluster_id AS motif_id FROM ({_HIGH})"
_occ = lambda s, d: _high(s, d).select("sensor", "series_id", "t", F.col("cluster_id").alias("motif_id"))
query("expand_occurrences", f"SELECT o.motif_id, o.series_id, o.t, v.t - o.t AS step, v.v FROM ({_OCC}) o JOIN ({O.PLANTED}) v ON v.series_id = o.series_id AND v.t BETWEEN o.t AND o.t + 19")(lambda s, d: M.expand(_occ(s, d), V.planted_view(s, d), W).select("motif_id", "series_id", "t", "step", "v"))
_EV = "SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS t FROM events"
_HIST = f"""SELECT DISTINCT user_id AS series_id, t - 12 AS start, 1 AS positive FROM ({_EV}) WHERE event_type = 'error' AND t - 12 >= 0 UNION ALL
 SELECT series_id, start, 0 FROM (SELECT user_id AS series_id, unnest(range(0, max(t) - 8, 10)) AS start FROM ({_EV}) GROUP BY 1 HAVING max(t) >= 10) p
 WHERE NOT EXISTS (SELECT 1 FROM ({_EV}) f WHERE f.event_type = 'error' AND f.user_id = p.series_id AND f.t BETWEEN p.start - 2 AND p.start + 11)"""


def _faults(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return V.load(s, d, "events").withColumn("t", (F.row_number().over(order) - 1).cast("long")).where("event_type = 'error'").select(F.col("user_id").alias("series_id"), "t")


_hist = lambda s, d: M.fault_histories(_run(s, d), _faults(s, d), 10, 2, 2)
query("fault_histories", _HIST)(_hist)
_RUN_OCC = f"SELECT series_id, t, cluster_id % 4 AS motif_id FROM ({O.first_letters(O.RUN)})"


def _run_occ(s: SparkSession, d: str) -> DataFrame:
    c = _cand(s, d).withColumn("word", F.concat(*[F.when(F.col("x")[j] < 0, "0").otherwise("1") for j in range(0, D, 2)]))
    return C.word_clusters(c, D).select("series_id", "t", (F.col("cluster_id") % 4).alias("motif_id"))


_FEAT = f"SELECT h.series_id, h.start, h.positive, {', '.join(f'count(*) FILTER (o.motif_id = {i}) AS m{i}' for i in range(4))} FROM ({_HIST}) h LEFT JOIN ({_RUN_OCC}) o ON o.series_id = h.series_id AND o.t BETWEEN h.start AND h.start + 9 GROUP BY 1, 2, 3"
_feat = lambda s, d: M.motif_features(_hist(s, d), _run_occ(s, d), [0, 1, 2, 3], 10).withColumnsRenamed({str(i): f"m{i}" for i in range(4)})
query("motif_features", _FEAT)(_feat)
query("positive_motifs", f"SELECT positive, count(*) AS histories, {', '.join(f'count(*) FILTER (m{i} > 0) AS with{i}' for i in range(4))} FROM ({_FEAT}) GROUP BY 1")(lambda s, d: _feat(s, d).groupBy("positive").agg(F.count("*").alias("histories"), *[F.count_if(F.col(f"m{i}") > 0).alias(f"with{i}") for i in range(4)]))
query("temporal_rules", f"WITH o AS ({_RUN_OCC}), h AS (SELECT DISTINCT a.motif_id AS motif_a, 'error' AS event_b, a.series_id, a.t FROM o a JOIN ({_EV}) b ON b.user_id = a.series_id AND b.event_type = 'error' AND b.t > a.t AND b.t <= a.t + 5) SELECT motif_a, event_b, (SELECT count(*) FROM o WHERE o.motif_id = h.motif_a) AS support, count(*) AS followed, round(count(*) / (SELECT count(*) FROM o WHERE o.motif_id = h.motif_a), 6) AS confidence FROM h GROUP BY 1, 2")(lambda s, d: M.temporal_rules(_run_occ(s, d), _faults(s, d).withColumn("motif_id", F.lit("error")), 5).withColumn("confidence", F.round("confidence", 6)))
query("known_events", f"WITH c AS (SELECT series_id, t, abs(v - lag(v) OVER (PARTITION BY series_id ORDER BY t)) AS ch FROM ({O.RUN})), h AS (SELECT *, t - row_number() OVER (PARTITION BY series_id ORDER BY t) AS g FROM c WHERE ch >= 8000) SELECT series_id, min(t) AS start, max(t) AS stop, count(*) AS hits FROM h GROUP BY series_id, g")(lambda s, d: M.known_events(_run(s, d), 8000).select("series_id", "start", "stop", "hits"))
query("rare_windows", f"WITH h AS MATERIALIZED ({_HIGH}), k AS MATERIALIZED ({_MEANS}), r AS (SELECT * FROM ({_COARSE}) WHERE cluster_id IN (SELECT cluster_id FROM ({_COARSE}) GROUP BY 1 HAVING count(*) <= 100)) SELECT r.series_id, r.t FROM r, k GROUP BY 1, 2 HAVING min({O.sq('r.x', 'k.c')}) > 4")(lambda s, d: M.rare_windows(_coarse(s, d), _means(s, d), 100, 2.0, D).select("series_id", "t"))


@query("fault_classifier")
def _classifier(s: SparkSession, d: str) -> DataFrame:
    """positive, predicted, n over the histories of odd runs, by a tree that was fitted on those of even runs."""
    f = C.cut(_feat(s, d).join(_level_feat(s, d), ["series_id", "start", "positive"]).where("rising is not null").fillna(0))
    names = [*[f"m{i}" for i in range(4)], "level", "rising", "change"]
    fitted = M.train_fault_classifier(f.where("series_id % 2 = 0"), names)
    return fitted.transform(f.where("series_id % 2 = 1")).groupBy("positive", F.col("prediction").cast("int").alias("predicted")).agg(F.count("*").alias("n"))


_LEVEL_SQL = f"""WITH r AS MATERIALIZED (SELECT series_id, t, v, v - lag(v) OVER (PARTITION BY series_id ORDER BY t) AS rise FROM ({O.RUN})), b AS (SELECT min(v) AS lo, max(v) AS hi FROM r),
 p AS (SELECT h.series_id, h.start, h.positive, sum(r.v)::BIGINT AS s, count(r.v) AS n, count(*) FILTER (r.rise > 0) AS up, arg_min(r.v, r.t) AS a, arg_max(r.v, r.t) AS z FROM ({_HIST}) h LEFT JOIN r ON r.series_id = h.series_id AND r.t BETWEEN h.start AND h.start + 9 GROUP BY 1, 2, 3)
 SELECT series_id, start, positive, CASE WHEN n > 0 THEN least(3, floor((s - n * lo) * 4 / (n * (hi - lo))))::INTEGER END AS level, CASE WHEN n > 0 THEN floor(100 * up / n)::INTEGER END AS rising, z - a AS change FROM p, b"""
_level_feat = lambda s, d: M.level_features(_hist(s, d), _run(s, d), 10)
query("level_features", _LEVEL_SQL)(_level_feat)
_LIFT = f"WITH o AS MATERIALIZED ({_RUN_OCC}), e AS MATERIALIZED ({_EV}), h AS (SELECT o.motif_id, o.series_id, o.t, bool_or(e.t IS NOT NULL) AS hit FROM o LEFT JOIN e ON e.user_id = o.series_id AND e.event_type = 'error' AND e.t > o.t AND e.t <= o.t + 5 GROUP BY 1, 2, 3) SELECT motif_id, count(*) AS support, count(*) FILTER (hit) AS followed, round((count(*) FILTER (hit) / count(*)) / (SELECT count(*) FILTER (hit) / count(*) FROM h), 6) AS lift FROM h GROUP BY 1"


@query("temporal_rules_lift", _LIFT)
def _lift(s: SparkSession, d: str) -> DataFrame:
    b = _faults(s, d).withColumn("motif_id", F.lit("error"))
    return M.rule_lift(_run_occ(s, d), b, 5).withColumn("lift", F.round("lift", 6))


# ---------------------------------------------------------------- operators
both("op_semi", "SELECT o_orderkey FROM {orders} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey AND l_quantity > 49)")
both("op_anti", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)")
both("op_full_outer", "SELECT coalesce(s_nationkey, c_nationkey) AS nation, s, c FROM (SELECT s_nationkey, count(*) AS s FROM {supplier} GROUP BY 1) a FULL OUTER JOIN (SELECT c_nationkey, count(*) AS c FROM {customer} WHERE c_mktsegment = 'BUILDING' GROUP BY 1) b ON s_nationkey = c_nationkey")
for _n, _g in (("rollup", "ROLLUP (o_orderpriority, o_orderstatus)"), ("cube", "CUBE (o_orderpriority, o_orderstatus)"), ("grouping_sets", "GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")):
    both(f"op_{_n}", f"SELECT o_orderpriority, o_orderstatus, count(*) AS n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM {{orders}} GROUP BY {_g}")
both("op_rank_family", "SELECT o_custkey, o_orderkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS q FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
both("op_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS last4, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto, lead(value, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS ahead FROM {events}")
both("op_intersect_all", "SELECT s_nationkey AS k FROM {supplier} INTERSECT ALL SELECT c_nationkey FROM {customer}")
both("op_except_all", "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}")
both("op_star_join", "SELECT r_name, o_orderpriority, count(*) AS n FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY 1, 2")
both("op_recursive_grid", "WITH RECURSIVE g AS (SELECT 0 AS i UNION ALL SELECT i + 1 FROM g WHERE i < 20) SELECT i, (SELECT count(*) FROM {region}) AS regions FROM g")
both("op_scalar_subquery", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM {orders})")
both("op_union_distinct", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")
query("op_union_by_name", "SELECT s_suppkey AS key, s_nationkey AS nation, NULL AS segment FROM supplier UNION ALL SELECT c_custkey, c_nationkey, c_mktsegment FROM customer")(lambda s, d: V.load(s, d, "supplier").select(F.col("s_suppkey").alias("key"), F.col("s_nationkey").alias("nation")).unionByName(V.load(s, d, "customer").select(F.col("c_custkey").alias("key"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment")), allowMissingColumns=True))
query("op_topk_per_group", "SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS INTEGER) AS rank FROM orders QUALIFY rank <= 3")(lambda s, d: R.top_per_group(V.load(s, d, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "rank"))
_T = "SELECT user_id, event_id, epoch_us(ts) // 60000000 AS m, event_type FROM events"


def _minutes(s: SparkSession, d: str) -> DataFrame:
    return V.load(s, d, "events").select("user_id", "event_id", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 60_000_000).alias("m"), "event_type")


_ASOF = f"SELECT l.user_id, l.event_id, (SELECT max(m) FROM ({_T}) r WHERE r.event_type = 'error' AND r.user_id = l.user_id AND r.m <= l.m) AS m_matched FROM ({_T}) l WHERE l.event_type <> 'error'"
query("op_asof_backward", _ASOF)(lambda s, d: (lambda e: R.asof_join(e.where("event_type <> 'error'").select("user_id", "event_id", "m"), e.where("event_type = 'error'"), "m", ["user_id"], ["event_type"]).select("user_id", "event_id", "m_matched"))(_minutes(s, d)))
query("op_asof_nearest", f"SELECT l.user_id, l.event_id, (SELECT arg_min(m, abs(m - l.m) * 2 + CASE WHEN m > l.m THEN 1 ELSE 0 END) FROM ({_T}) r WHERE r.event_type = 'error' AND r.user_id = l.user_id) AS m_matched FROM ({_T}) l WHERE l.event_type <> 'error'")(lambda s, d: (lambda e: R.asof_join(e.where("event_type <> 'error'").select("user_id", "event_id", "m"), e.where("event_type = 'error'"), "m", ["user_id"], ["event_type"], "nearest").select("user_id", "event_id", "m_matched"))(_minutes(s, d)))
query("op_range_join", f"SELECT a.event_id, b.event_id AS other FROM ({_T}) a JOIN ({_T}) b ON a.user_id = b.user_id AND b.event_type = 'error' AND a.m BETWEEN b.m - 120 AND b.m")(lambda s, d: (lambda e: R.range_join(e.select("user_id", "event_id", "m"), e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("other"), (F.col("m") - 120).alias("lo"), F.col("m").alias("hi")), "m", "lo", "hi", ["user_id"], 240).select("event_id", "other"))(_minutes(s, d)))
query("op_islands", f"SELECT user_id, event_id, CAST(sum(n) OVER (PARTITION BY user_id ORDER BY m, event_id) AS BIGINT) AS island FROM (SELECT *, CASE WHEN m - lag(m) OVER (PARTITION BY user_id ORDER BY m, event_id) > 600 THEN 1 ELSE 0 END AS n FROM ({_T}))")(lambda s, d: _islands(s, d))


def _islands(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("m", "event_id")
    new = F.when(F.col("m") - F.lag("m").over(order) > 600, 1).otherwise(0)
    return _minutes(s, d).withColumn("n", new).select("user_id", "event_id", F.sum("n").over(order).alias("island"))


query("op_pivot", "SELECT user_id, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'click') AS click FROM events GROUP BY 1")(lambda s, d: V.load(s, d, "events").groupBy("user_id").pivot("event_type", ["error", "click"]).count().fillna(0))
query("op_unpivot", "SELECT l_orderkey, l_linenumber, kind, amount FROM (UNPIVOT (SELECT l_orderkey, l_linenumber, l_discount, l_tax FROM lineitem) ON l_discount, l_tax INTO NAME kind VALUE amount)")(lambda s, d: V.load(s, d, "lineitem").unpivot(["l_orderkey", "l_linenumber"], ["l_discount", "l_tax"], "kind", "amount"))
query("op_json_props", "SELECT event_id, CAST(props->>'$.k' AS INTEGER) AS k FROM events")(lambda s, d: V.load(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
query("op_percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")(lambda s, d: V.load(s, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.9), 6).alias("p90")))
query("op_sample_hash", "SELECT event_id FROM events WHERE (event_id * 7919 + 13) % 104729 % 100 < 10")(lambda s, d: R.sample_rows(V.load(s, d, "events"), "event_id", 10).select("event_id"))
query("op_approx_distinct", "SELECT count(DISTINCT user_id) AS users, true AS near FROM events")(lambda s, d: V.load(s, d, "events").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("a")).select("users", (F.abs(F.col("a") - F.col("users")) <= 0.1 * F.col("users")).alias("near")))
query("op_map_features", "SELECT user_id, count(*) FILTER (event_type = 'error') AS errors FROM events GROUP BY 1")(lambda s, d: V.load(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.coalesce(F.try_element_at("m", F.lit("error")), F.lit(0)).cast("long").alias("errors")))
query("op_string_words", r"SELECT conv_id, turn, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS words FROM conversations")(lambda s, d: V.load(s, d, "conversations").select("conv_id", "turn", F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).cast("long").alias("words")))
query("op_date_gaps", "SELECT o_custkey, max(g) AS longest FROM (SELECT o_custkey, date_diff('day', lag(o_orderdate::DATE) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), o_orderdate::DATE) AS g FROM orders) GROUP BY 1")(lambda s, d: V.load(s, d, "orders").withColumn("g", F.datediff(F.to_date("o_orderdate"), F.lag(F.to_date("o_orderdate")).over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))).cast("long")).groupBy("o_custkey").agg(F.max("g").alias("longest")))

# ---------------------------------------------------------------- streaming
_HOUR = "SELECT event_type, date_trunc('hour', ts) AS start, count(*) AS n FROM events GROUP BY 1, 2"
query("stream_tumbling", _HOUR)(ST.tumbling)
query("stream_sliding", "SELECT event_type, date_trunc('hour', ts) - INTERVAL 1 HOUR * k AS start, count(*) AS n FROM events, (VALUES (0), (1)) s(k) GROUP BY 1, 2")(lambda s, d: ST.tumbling(s, d, "2 hours", "1 hour"))
query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")(ST.dedup)
query("stream_windows_batch_equal", f"SELECT series_id, t, word FROM ({O.words(O.reduced(O.RUN))})")(ST.windows_equal)

# ---------------------------------------------------------------- later steps and robustness, without a DuckDB form
query("drop_trivial", O.drop_trivial(_HIGH, _ALL_P))(lambda s, d: X.drop_trivial(_high(s, d), _planted_windows(s, d), 1.0).select(*_ids))
query("frequent_motif_test", f"SELECT sensor, cluster_id, count(*) AS support, count(*) > 90 AS frequent FROM ({O.drop_trivial(_HIGH, _ALL_P)}) JOIN (SELECT DISTINCT sensor FROM ({O.PLANTED})) ON true GROUP BY 1, 2")(lambda s, d: X.is_frequent(X.drop_trivial(_high(s, d), _planted_windows(s, d), 1.0), 90))
query("drop_trivial_separators", O.drop_trivial(_HIGH, _ALL_P))(lambda s, d: X.drop_trivial(_high(s, d), _planted_windows(s, d), 1.0, separators=True).select(*_ids))
query("drop_trivial_closest", O.closest_of_islands(_HIGH, W))(lambda s, d: X.drop_trivial_closest(_high(s, d), W).select(*_ids))


@query("order_sensitivity")
def _order(s: SparkSession, d: str) -> DataFrame:
    """Motifs of a random insertion order that agree with those of time order."""
    a, b = (_planted(s, d, method="all", **o).motifs for o in ({"order": "random", "seed": 1}, {}))
    return S.motif_agreement(a, b, 1.0, D)


@query("growth_slope")
def _growth(s: SparkSession, d: str) -> DataFrame:
    """Slope of log distances on log candidates over a growing part of the runs, up to all of them, by method."""
    cand = C.cut(P.candidates(V.planted_view(s, d), W, D))
    parts = []
    for method in ("all", "cftree", "hash"):
        for share in (8, 4, 2, 1):  # the growth is what is measured
            part = C.cluster(cand.where(F.col("series_id") % share == 0), 1.0, method)
            parts.append(part.agg(F.lit(method).alias("method"), F.count("*").alias("n"), F.max("evals").alias("evals")))
    rows = reduce(DataFrame.unionByName, parts)
    return rows.groupBy("method").agg(F.round(F.regr_slope(F.log("evals"), F.log("n")), 3).alias("slope"))

# ---------------------------------------------------------------- accuracy against planted shapes, model files, generated runs
_TRUTH = "SELECT series_id, 60 * b + 2 + (7 * series_id + 13 * b) % 11 AS t0, 'held_step' AS shape FROM k UNION ALL SELECT series_id, 60 * b + 29 + (5 * series_id + 17 * b) % 11, 'two_pulses' FROM k"
_QUALITY = f"""WITH h AS MATERIALIZED ({_HIGH}), k AS (SELECT series_id, r.range AS b FROM (SELECT DISTINCT l_suppkey AS series_id FROM lineitem), range(5) r), tr AS MATERIALIZED ({_TRUTH}),
 c AS (SELECT h.cluster_id, tr.shape, unnest([h.t - t0 - 1, h.t - t0, h.t - t0 + 1]) AS off, h.series_id, h.t, t0 FROM h JOIN tr ON tr.series_id = h.series_id AND abs(h.t - t0) <= 10),
 g AS (SELECT cluster_id, shape, off, count(DISTINCT (series_id, t0)) AS found, count(DISTINCT (series_id, t)) AS inside FROM c GROUP BY 1, 2, 3),
 b AS (SELECT shape, max({{'found': found, 'inside': inside, 'members': members}}) AS m FROM g JOIN (SELECT cluster_id, count(*) AS members FROM h GROUP BY 1) USING (cluster_id) GROUP BY 1)
 SELECT shape, instances, m.found AS found, m.members AS members, round(m.found / instances, 6) AS recall, round(m.inside / m.members, 6) AS precision FROM (SELECT shape, count(*) AS instances FROM tr GROUP BY 1) JOIN b USING (shape)"""
query("match_quality", _QUALITY)(lambda s, d: S.match_quality(_high(s, d).withColumn("level_id", F.lit(0)), V.planted_truth(s, d)).withColumns({c: F.round(c, 6) for c in ("recall", "precision")}))
_PARITY = lambda series, name: f"SELECT '{name}' AS method, series_id % 2 AS run, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c FROM ({O.first_letters(series)}) GROUP BY cluster_id, series_id % 2"
_REPEAT = f"""WITH c AS MATERIALIZED (SELECT *, row_number() OVER () AS k FROM ({_PARITY(O.RUN, 'run')} UNION ALL {_PARITY(O.PLANTED, 'planted')})),
 g AS (SELECT a.k, a.method, b.method AS m2, sqrt(min({O.sq('a.c', 'b.c')})) AS g FROM c a JOIN c b ON NOT (a.method = b.method AND a.run = b.run) GROUP BY a.k, a.method, b.method, b.run)
 SELECT round(avg(g) FILTER (method = m2) / avg(g) FILTER (method <> m2), 6) AS ratio FROM g"""


@query("repeatability", _REPEAT)
def _repeatability(s: SparkSession, d: str) -> DataFrame:
    """Centres of one half of the runs against those of the other half, and against those of other data."""
    sets = []
    for name, series in (("run", V.run_view(s, d)), ("planted", V.planted_view(s, d))):
        c = P.candidates(series, W, D)
        c = C.word_clusters(c.withColumn("word", F.concat(*[F.when(F.col("x")[j] < 0, "0").otherwise("1") for j in range(0, D, 2)])), D)
        sets.append(c.withColumn("run", F.col("series_id") % 2).groupBy("cluster_id", "run").agg(F.array(*[F.avg(F.col("x")[j]) for j in range(D)]).alias("centroid")).select(F.lit(name).alias("method"), "run", "centroid"))
    return S.repeatability(C.cut(sets[0].unionByName(sets[1])), D).withColumn("ratio", F.round("ratio", 6))


@query("model_roundtrip_match", _SQL["match_motifs"])
def _model(s: SparkSession, d: str) -> DataFrame:
    """Matching with motifs that were saved and loaded."""
    path = f"{ST.folder(s)}/model"
    FS.save_model(_means(s, d), path, w=W, d=D, r=2.0)
    motifs, p = FS.load_model(s, path)
    return M.match(_planted_windows(s, d), motifs, p["r"], p["d"]).select("series_id", "t", "motif_id")


@query("source_csv_roundtrip", O.RUN)
def _csv(s: SparkSession, d: str) -> DataFrame:
    path = f"{ST.folder(s)}/csv"
    FS.export(_run(s, d), path)
    return FS.read_series(s, path)


@query("source_json_roundtrip", O.RUN)
def _json(s: SparkSession, d: str) -> DataFrame:
    path = f"{ST.folder(s)}/json"
    FS.export(_run(s, d), path, "json")
    return FS.read_series(s, path, "json")


@query("sink_stage_roundtrip", f"SELECT sensor, series_id, t, word FROM ({O.candidates(O.FLAG)})")
def _stage(s: SparkSession, d: str) -> DataFrame:
    path = f"{ST.folder(s)}/stage"
    FS.write_stage(P.candidates(V.flag_view(s, d), W, D), path)
    return FS.read_stage(s, path).select("sensor", "series_id", "t", "word")


query("source_planted_runs", f"SELECT 'planted' AS sensor, series_id, t, (v + (CASE WHEN t % 60 - 2 - (7 * series_id + 13 * (t // 60)) % 11 BETWEEN 10 AND 17 THEN 3000 ELSE 0 END) + (CASE WHEN t % 60 - 29 - (5 * series_id + 17 * (t // 60)) % 11 IN (2, 3, 14, 15) THEN 3000 ELSE 0 END))::BIGINT AS v FROM ({O.RUN})")(lambda s, d: FS.planted_onto(_run(s, d)))

# ---------------------------------------------------------------- whole procedure with clusters of equal words, exact in both engines
_WORD_STEPS = O.procedure(O.PLANTED, 8, _ALL_P)


def _words(s: SparkSession, d: str) -> PL.MotifResult:
    return PL.discover(V.planted_view(s, d), W, 8, method="words")


query("motifs_words_pipeline", f"{_WORD_STEPS} SELECT cluster_id AS motif_id, level_id, count(*) AS support, count(DISTINCT series_id) AS runs FROM f GROUP BY 1, 2")(lambda s, d: _words(s, d).motifs.select("motif_id", "level_id", "support", "runs"))
query("group_motifs", f"{_WORD_STEPS} SELECT 'quantity' AS sensor, cluster_id, count(*) AS n FROM g GROUP BY 2")(lambda s, d: _words(s, d).stages["groups"].groupBy("sensor", "cluster_id").agg(F.count("*").alias("n")))
query("final_motifs", f"{_WORD_STEPS} SELECT cluster_id AS motif_id, level_id, series_id, t FROM f")(lambda s, d: _words(s, d).stages["motifs"].select(F.col("cluster_id").alias("motif_id"), "level_id", "series_id", "t"))
_FUNNEL = f"""{_WORD_STEPS}, a AS (SELECT * FROM ({O.reduced(O.PLANTED)}))
 SELECT 'quantity' AS sensor, pos::INTEGER AS "at", step, n AS rows, k AS clusters FROM (
 SELECT 0 AS pos, 'windows' AS step, count(*) AS n, NULL::BIGINT AS k FROM a UNION ALL SELECT 1, 'not_flat', count(*), NULL FROM a WHERE dev >= 1
 UNION ALL SELECT 2, 'candidates', count(*), NULL FROM w0 UNION ALL SELECT 3, 'clusters', count(*), count(DISTINCT cluster_id) FROM w0
 UNION ALL SELECT 4, 'high_support', count(*), count(DISTINCT cluster_id) FROM h UNION ALL SELECT 5, 'not_shifted', count(*), count(DISTINCT cluster_id) FROM k1
 UNION ALL SELECT 6, 'not_trivial', count(*), count(DISTINCT cluster_id) FROM m1 UNION ALL SELECT 7, 'groups', count(*), count(DISTINCT cluster_id) FROM g
 UNION ALL SELECT 8, 'motifs', count(*), count(DISTINCT cluster_id) FROM f) WHERE n > 0"""
query("funnel", _FUNNEL)(lambda s, d: _words(s, d).funnel())
query("dropped_shares", f"SELECT sensor, round(1 - max(clusters) FILTER (step = 'not_shifted') / max(clusters) FILTER (step = 'high_support'), 6) AS shifted, round(1 - max(rows) FILTER (step = 'not_trivial') / max(rows) FILTER (step = 'not_shifted'), 6) AS trivial FROM ({_FUNNEL}) GROUP BY 1")(lambda s, d: S.dropped_shares(_words(s, d).funnel()))
_HALVES = f"SELECT series_id % 2 AS run, cluster_id, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c FROM ({_COARSE}) GROUP BY 1, 2"
_GAPS = ", ".join("(" + " + ".join(f"(a.c[{i + 1}] - b.c[{i + 1 - k}]) * (a.c[{i + 1}] - b.c[{i + 1 - k}])" for i in range(D) if 0 <= i - k < D) + f") * {D / (D - abs(k))!r}::DOUBLE" for k in range(-2, 3))


@query("motif_agreement_shifted", f"WITH c AS MATERIALIZED ({_HALVES}), n AS (SELECT a.cluster_id, min(least({_GAPS})) AS d2 FROM c a JOIN c b ON a.run = 0 AND b.run = 1 GROUP BY 1) SELECT 'quantity' AS sensor, count(*) AS motifs, count(*) FILTER (d2 < 1) AS agreed FROM n")
def _agreement_shifted(s: SparkSession, d: str) -> DataFrame:
    """Motifs of one half of the runs that agree with one of the other half when moved by two frames at most."""
    rows = _coarse(s, d).withColumn("run", F.col("series_id") % 2)
    mean = C.cut(rows.groupBy("sensor", "run", F.col("cluster_id").alias("motif_id")).agg(F.array(*[F.avg(F.col("x")[j]) for j in range(D)]).alias("centroid")).withColumn("level_id", F.lit(0)))
    return S.motif_agreement(mean.where("run = 0"), mean.where("run = 1"), 1.0, D, 2)


# ---------------------------------------------------------------- more joins and streams
query("op_interval_join", "SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'error' AND a.ts BETWEEN b.ts - INTERVAL 3 HOUR AND b.ts")(lambda s, d: (lambda e: R.interval_join(e.select("user_id", "event_id", "ts"), e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("other"), F.expr("ts - interval 3 hours").alias("lo"), F.col("ts").alias("hi")), "ts", "lo", "hi", ["user_id"], 10_800).select("event_id", "other"))(V.load(s, d, "events")))
query("stream_session", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(j) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS j FROM events)) GROUP BY user_id, g")(ST.sessions)
query("stream_rules", "SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type <> 'error' AND b.event_type = 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")(ST.rules)
_SHORT = O.words(O.reduced(O.RUN, 20, 4), 4)
query("stream_match", f"WITH w AS MATERIALIZED ({_SHORT}) SELECT series_id, t, word, support FROM w JOIN (SELECT word, count(*) AS support FROM w GROUP BY 1 HAVING count(*) > 100) USING (word)")(ST.match)
query("stream_cluster", f"SELECT word, count(*) AS n, sum(t)::BIGINT AS v FROM ({_SHORT}) GROUP BY 1")(ST.centres)

# ---------------------------------------------------------------- experiment workloads on the planted and fleet views


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


@query("workload_methods")
def _methods(s: SparkSession, d: str) -> DataFrame:
    """method, clusters, outliers, misplaced, evals over the same candidates: quality and cost side by side."""
    cand = C.cut(P.candidates(V.planted_view(s, d), W, D))
    parts = []
    for method in ("all", "cftree", "hash", "parallel"):
        a = C.cut(C.cluster_parallel(cand, 1.0, D) if method == "parallel" else C.cluster(cand, 1.0, method))
        evals = a.groupBy("sensor").agg(F.max("evals").alias("evals"))
        parts.append(S.radius_outliers(a, 1.0, D).join(S.misplacement(a, D), "sensor").join(evals, "sensor").withColumn("method", F.lit(method)))
    return _union(parts).select("method", "sensor", "members", "clusters", "outliers", "below_twice", "misplaced", "evals")


@query("workload_widths")
def _widths(s: SparkSession, d: str) -> DataFrame:
    """w, motifs, members over window lengths, with the radius of each length."""
    parts = [_planted(s, d, w).motifs.groupBy("sensor").agg(F.count("*").alias("motifs"), F.sum("support").alias("members")).withColumn("w", F.lit(w)) for w in (10, 14, 20, 40, 80, 200)]
    return _union(parts).select("w", "sensor", "motifs", "members")


@query("workload_orders")
def _orders(s: SparkSession, d: str) -> DataFrame:
    """seed, shape and quality over random insertion orders."""
    return _union([_accuracy(method="cftree", order="random", seed=i)(s, d).withColumn("seed", F.lit(i)) for i in range(1, 6)])


@query("workload_ablation")
def _ablation(s: SparkSession, d: str) -> DataFrame:
    """left_out, motifs, members: the whole procedure, and without each step."""
    parts = []
    for left_out in ("none", "flat", "words", "shifted", "trivial", "levels"):
        m = _planted(s, d, skip=(left_out,)).motifs
        parts.append(m.groupBy("sensor").agg(F.count("*").alias("motifs"), F.sum("support").alias("members")).withColumn("left_out", F.lit(left_out)))
    return _union(parts).select("left_out", "sensor", "motifs", "members")


@query("workload_kmeans_spheres")
def _kmeans_spheres(s: SparkSession, d: str) -> DataFrame:
    """method, clusters, widest, mean_widest: extent of clusters of high support, k-means with as many centres against spheres."""
    cand = C.cut(P.candidates(V.planted_view(s, d), W, D))
    spheres = C.cut(X.high_support(C.cluster(cand, 1.0, "cftree"), _support(s, d)))
    k = max(2, spheres.select("sensor", "cluster_id").distinct().count())
    means = C.cut(B.kmeans_ml(cand, k))
    parts = [S.tightness(a, D).agg(F.lit(name).alias("method"), F.count("*").alias("clusters"), F.round(F.max("max_dist"), 4).alias("widest"), F.round(F.avg("max_dist"), 4).alias("mean_widest"), F.round(F.avg("mean_dist"), 4).alias("mean_dist")) for name, a in (("spheres", spheres), ("kmeans", means))]
    return _union(parts)


@query("workload_missed_instances")
def _missed(s: SparkSession, d: str) -> DataFrame:
    """step, shape and quality before and after every window is matched with the motifs found."""
    r = _planted(s, d)
    found = r.stages["motifs"]
    keyed = r.motifs.withColumn("motif_id", F.struct("motif_id", "level_id"))
    scanned = M.match(r.stages["windows"], keyed, 1.0, D).select("series_id", "t", F.col("motif_id.motif_id").alias("cluster_id"), F.lit("quantity").alias("sensor"), F.col("motif_id.level_id").alias("level_id"))
    truth = V.planted_truth(s, d)
    return _union([S.match_quality(o, truth).withColumn("step", F.lit(name)) for name, o in (("found", found), ("scanned", C.cut(scanned)))])


@query("workload_levels")
def _levels(s: SparkSession, d: str) -> DataFrame:
    """Motifs by level where odd blocks are raised by a step: equal shapes at two heights are told apart."""
    m = PL.discover(V.planted_view(s, d, level_step=20), W, _support(s, d) // 2, eps=0.1).motifs
    return m.groupBy("sensor", "motif_id").agg(F.count("*").alias("levels"), F.sum("support").alias("support"))


@query("workload_fleet")
def _fleet(s: SparkSession, d: str) -> DataFrame:
    """The funnel of all six fleet sensors."""
    return PL.discover(V.fleet_view(s, d), W, _support(s, d)).funnel()


@query("top_motifs_expanded")
def _top(s: SparkSession, d: str) -> DataFrame:
    """Mean original waveform of the five best supported motifs: sensor, motif_id, step, v."""
    r = _planted(s, d)
    best = R.top_per_group(r.motifs, ["sensor"], [F.desc("support"), F.col("motif_id"), F.col("level_id")], 5).select("sensor", F.col("motif_id").alias("cluster_id"), "level_id")
    occ = r.stages["motifs"].join(F.broadcast(best), ["sensor", "cluster_id", "level_id"]).select("sensor", "series_id", "t", F.col("cluster_id").alias("motif_id"))
    return M.expand(occ, V.planted_view(s, d), W).groupBy("sensor", "motif_id", "step").agg(F.round(F.avg("v"), 2).alias("v"))

query("stream_resumed", f"SELECT series_id, count(*) AS steps, sum(v)::BIGINT AS total FROM ({O.RUN}) GROUP BY 1")(ST.resumed)

# ---------------------------------------------------------------- SQL surface
query("profile_series", f"SELECT sensor, series_id, count(*) AS n, min(v) AS lowest, max(v) AS highest, round(avg(v::DOUBLE), 4) AS mean, round(stddev_pop(v::DOUBLE), 4) AS dev_pop, round(stddev_samp(v::DOUBLE), 4) AS dev, round(corr(v::DOUBLE, t::DOUBLE), 6) AS corr_t, round(regr_slope(v::DOUBLE, t::DOUBLE), 4) AS slope_t FROM ({O.RUN}) GROUP BY 1, 2")(lambda s, d: SQL.profile_series(_run(s, d)).drop("skew", "kurt").withColumns({c: F.round(c, 6 if c == "corr_t" else 4) for c in ("mean", "dev_pop", "dev", "corr_t", "slope_t")}))


def _sql(body: str, view: Query = _run) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        SQL.register_sql(s, view(s, d))
        return s.sql(body)

    return run


query("sql_words", f"SELECT series_id, t, word FROM ({O.words(O.reduced(O.RUN))})")(_sql("SELECT series_id, t, sax_word(x) AS word FROM reduced"))
query("sql_neighbours", f"SELECT series_id, t, round({O.sq('x', 'y')}, 6) AS d2 FROM (SELECT series_id, t, x, lead(x) OVER (PARTITION BY series_id ORDER BY t) AS y FROM ({_ALL_X})) WHERE y IS NOT NULL")(_sql("SELECT series_id, t, round(sq_dist(x, y), 6) AS d2 FROM (SELECT series_id, t, x, lead(x) OVER (PARTITION BY series_id ORDER BY t) AS y FROM reduced) WHERE y IS NOT NULL"))
query("udtf_windows", f"SELECT series_id, t AS start, a AS first, b AS last FROM (SELECT series_id, t, v::DOUBLE AS a, lead(v::DOUBLE, 19) OVER (PARTITION BY series_id ORDER BY t) AS b FROM ({O.RUN})) WHERE b IS NOT NULL")(_sql("SELECT r.series_id, e.start, e.win[0] AS first, e.win[19] AS last FROM (SELECT series_id, transform(array_sort(collect_list(struct(t, v))), p -> CAST(p.v AS DOUBLE)) AS vs FROM series GROUP BY series_id) r, LATERAL explode_windows(r.vs, 20) e"))
query("udaf_medoid", f"WITH w AS MATERIALIZED ({_NEAR}), g AS (SELECT a.series_id, a.x, round(sum(sqrt({O.sq('a.x', 'b.x')})), 6) AS total FROM w a JOIN w b ON a.series_id = b.series_id GROUP BY a.series_id, a.t, a.x) SELECT series_id, min(total) AS total FROM g GROUP BY 1")(lambda s, d: _medoids(s, d))


def _medoids(s: SparkSession, d: str) -> DataFrame:
    """series_id, total: the sum of distances from the medoid of a run's candidates."""
    rows = C.cut(_cand(s, d).select("series_id", "x"))
    mid = rows.groupBy("series_id").agg(SQL.medoid("x").alias("m"))
    return rows.join(mid, "series_id").groupBy("series_id").agg(F.round(F.sum(F.sqrt(VEC.sq_dist("x", "m", D))), 6).alias("total"))


from wavemotif import experiments as _experiments  # noqa: E402, F401  registers its queries
