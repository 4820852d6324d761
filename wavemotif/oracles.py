"""DuckDB statements that give the same rows as the registered queries."""

from __future__ import annotations

from wavemotif.functions.vectors import BREAKPOINTS, fixed_planes

W, D = 20, 10
RUN = "SELECT 'value' AS sensor, user_id AS series_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS v FROM events"
CLOCK = """SELECT sensor, 0::BIGINT AS series_id, t, v FROM (
 SELECT g.sensor, g.t, last_value(k.v IGNORE NULLS) OVER (PARTITION BY g.sensor ORDER BY g.t) AS v
 FROM (SELECT DISTINCT event_type AS sensor, r.range AS t FROM events, range(720) r) g
 LEFT JOIN (SELECT event_type AS sensor, date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS t, sum(CAST(round(value * 100) AS BIGINT))::BIGINT AS v FROM events GROUP BY 1, 2) k
 ON k.sensor = g.sensor AND k.t = g.t) WHERE v IS NOT NULL"""
FLAG = """SELECT 'quantity' AS sensor, dense_rank() OVER (ORDER BY flag) - 1 AS series_id, row_number() OVER (PARTITION BY flag ORDER BY day) - 1 AS t, v FROM (
 SELECT l_returnflag || l_linestatus AS flag, l_shipdate::DATE AS day, sum(CAST(round(l_quantity * 100) AS BIGINT))::BIGINT AS v FROM lineitem GROUP BY 1, 2)"""
REGION = """SELECT sensor, series_id, row_number() OVER (PARTITION BY sensor, series_id ORDER BY day) - 1 AS t, v FROM (
 SELECT o_orderpriority AS sensor, n_regionkey::BIGINT AS series_id, o_orderdate::DATE AS day, sum(CAST(round(o_totalprice * 100) AS BIGINT))::BIGINT AS v
 FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2, 3)"""
_WEEKLY = """SELECT l_suppkey AS series_id, floor(date_diff('day', DATE '1995-01-02', l_shipdate::DATE) / 7.0)::BIGINT AS t,
 sum(CAST(round(l_quantity * 100) AS BIGINT))::BIGINT AS quantity, sum(CAST(round(l_extendedprice * 100) AS BIGINT))::BIGINT AS price, sum(CAST(round(l_discount * 100) AS BIGINT))::BIGINT AS discount,
 sum(CAST(round(l_tax * 100) AS BIGINT))::BIGINT AS tax, 100 * count(*) AS lines, 100 * count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1, 2"""
FLEET = f"""WITH wk AS ({_WEEKLY}), g AS (SELECT DISTINCT series_id, r.range AS t FROM wk, range(357) r),
 f AS (SELECT g.series_id, g.t, coalesce(quantity, 0) AS quantity, coalesce(price, 0) AS price, coalesce(discount, 0) AS discount, coalesce(tax, 0) AS tax, coalesce(lines, 0) AS lines, coalesce(orders, 0) AS orders FROM g LEFT JOIN wk ON wk.series_id = g.series_id AND wk.t = g.t)
 UNPIVOT f ON quantity, price, discount, tax, lines, orders INTO NAME sensor VALUE v"""
PLANTED = f"""SELECT 'quantity' AS sensor, series_id, t, (round(q / 10.0)::BIGINT + CASE WHEN t // 60 < 5 THEN
 CASE WHEN t % 60 - 2 - (7 * series_id + 13 * (t // 60)) % 11 BETWEEN 10 AND 17 THEN 3000 ELSE 0 END
 + CASE WHEN t % 60 - 29 - (5 * series_id + 17 * (t // 60)) % 11 IN (2, 3, 14, 15) THEN 3000 ELSE 0 END ELSE 0 END)::BIGINT AS v
 FROM (SELECT g.series_id, g.t, coalesce(quantity, 0) AS q FROM (SELECT DISTINCT l_suppkey AS series_id, r.range AS t FROM lineitem, range(357) r) g LEFT JOIN ({_WEEKLY}) wk ON wk.series_id = g.series_id AND wk.t = g.t)"""
TEXT = r"""SELECT 'word_length' AS sensor, doc_id AS series_id, generate_subscripts(w, 1) - 1 AS t, (least(length(unnest(w)), 15) * 100)::BIGINT AS v FROM (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents)"""
CUMULATIVE = f"SELECT sensor, series_id, t, (sum(dev) OVER (PARTITION BY sensor, series_id ORDER BY t))::BIGINT AS v FROM (SELECT *, count(*) OVER k * v - sum(v) OVER k AS dev FROM ({RUN}) WINDOW k AS (PARTITION BY sensor, series_id))"
SMOOTHED = f"SELECT sensor, series_id, t, v::BIGINT AS v FROM (SELECT sensor, series_id, t, sum(v) OVER w AS v, count(*) OVER w AS c FROM ({FLAG}) WINDOW w AS (PARTITION BY sensor, series_id ORDER BY t ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)) WHERE c = 7"


def z(series: str, keys: str = "sensor, series_id") -> str:
    return f"""SELECT sensor, series_id, t, v, (n * v - s)::DOUBLE / sqrt((n::DECIMAL(38,0) * q - s::DECIMAL(38,0) * s)::DOUBLE) AS z FROM (
 SELECT *, count(*) OVER k AS n, (sum(v) OVER k)::BIGINT AS s, (sum(v::DECIMAL(18,0) * v::DECIMAL(18,0)) OVER k)::DECIMAL(38,0) AS q FROM ({series}) WINDOW k AS (PARTITION BY {keys})) WHERE n::DECIMAL(38,0) * q - s::DECIMAL(38,0) * s > 0"""


def reduced(series: str, w: int = W, d: int = D) -> str:
    """t, p0 .. (centred), level, dev; every window."""
    from wavemotif.operators.prep import frame_weights

    lead = lambda i: f"lead(z, {i}) OVER o" if i else "z"
    if w % d == 0:
        g = w // d
        parts = [f"({' + '.join(lead(j * g + i) for i in range(g))}) / {float(g)}::DOUBLE" for j in range(d)]
    else:
        parts = [f"({' + '.join(f'{lead(i)} * {c!r}::DOUBLE' for i, c in ps)}) / {w / d!r}::DOUBLE" for ps in frame_weights(w, d)]
    return f"""SELECT sensor, series_id, t, level, hi - lo AS dev, greatest(hi - level, level - lo) AS dev2, {', '.join(f'p{j} - level AS p{j}' for j in range(d))} FROM (
 SELECT *, ({' + '.join(f'p{j}' for j in range(d))}) / {float(d)}::DOUBLE AS level FROM (
  SELECT sensor, series_id, t, {', '.join(f'{p} AS p{j}' for j, p in enumerate(parts))}, max(z) OVER f AS hi, min(z) OVER f AS lo, count(*) OVER f AS have
  FROM ({z(series)}) WINDOW o AS (PARTITION BY sensor, series_id ORDER BY t), f AS (PARTITION BY sensor, series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND {w - 1} FOLLOWING)) WHERE have = {w})"""


def words(rows: str, d: int = D, alphabet: int = 4) -> str:
    cuts = BREAKPOINTS[alphabet]
    letter = lambda j: "CASE " + " ".join(f"WHEN p{j} < {c}::DOUBLE THEN '{'abcdef'[i]}'" for i, c in enumerate(cuts)) + f" ELSE '{'abcdef'[len(cuts)]}' END"
    return f"SELECT *, {' || '.join(letter(j) for j in range(d))} AS word FROM ({rows})"


def candidates(series: str, w: int = W, d: int = D, adjacency: str = "surviving") -> str:
    gap = "" if adjacency == "surviving" else " AND t - lag(t) OVER o = 1"
    return f"SELECT * FROM ({words(f'SELECT * FROM ({reduced(series, w, d)}) WHERE dev >= 1', d)}) WINDOW o AS (PARTITION BY sensor, series_id ORDER BY t) QUALIFY NOT coalesce(word IS NOT DISTINCT FROM lag(word) OVER o{gap}, false)"


def word_clusters(series: str) -> str:
    return f"SELECT sensor, series_id, t, level, [{', '.join(f'p{j}' for j in range(D))}] AS x, dense_rank() OVER (PARTITION BY sensor ORDER BY word) - 1 AS cluster_id FROM ({candidates(series)})"


def first_letters(series: str) -> str:
    """A coarse deterministic grouping: by the signs of every other value."""
    key = " || ".join(f"CASE WHEN p{j} < 0 THEN '0' ELSE '1' END" for j in range(0, D, 2))
    return f"SELECT sensor, series_id, t, level, [{', '.join(f'p{j}' for j in range(D))}] AS x, dense_rank() OVER (PARTITION BY sensor ORDER BY {key}) - 1 AS cluster_id FROM ({candidates(series)})"


def sq(a: str, b: str, d: int = D) -> str:
    return " + ".join(f"({a}[{i}] - {b}[{i}]) * ({a}[{i}] - {b}[{i}])" for i in range(1, d + 1))


def sequential(series: str, r: float, link: str = "centroid", frozen: bool = False, order: str = "t") -> str:
    """Clusters of each run by insertion in order, as a recursion with the state of all runs side by side."""
    cand = f"SELECT sensor, series_id, t, [{', '.join(f'p{j}' for j in range(D))}] AS x, row_number() OVER (PARTITION BY series_id ORDER BY {order}, t) AS rn FROM ({candidates(series)})"
    centre = "list_transform(range(1, 11), lambda i: c.ls[i] / c.n)"
    dist = f"list_sum(list_transform(range(1, 11), lambda i: ({centre}[i] - x[i]) * ({centre}[i] - x[i])))" if not frozen and link == "centroid" else "list_sum(list_transform(range(1, 11), lambda i: (c.ls[i] - x[i]) * (c.ls[i] - x[i])))"
    grow = "k" if frozen else f"list_transform(range(1, len(k) + 1), lambda j: CASE WHEN j = b THEN {{'n': k[j].n + 1, 'ls': list_transform(range(1, 11), lambda i: k[j].ls[i] + x[i]), 'id': k[j].id}} ELSE k[j] END)"
    if link == "point":
        grow = "list_append(k, {'n': 1::BIGINT, 'ls': x, 'id': k[b].id})"
    opened = "(list_max(list_transform(k, lambda c: c.id)) + 1)" if link == "point" else "len(k)"
    return f"""WITH RECURSIVE cand AS MATERIALIZED ({cand}),
 s AS (SELECT series_id, t, rn, [{{'n': 1::BIGINT, 'ls': x, 'id': 0::BIGINT}}] AS k, 0::BIGINT AS cluster_id FROM cand WHERE rn = 1
 UNION ALL
 SELECT series_id, t, rn, CASE WHEN m < {r * r}::DOUBLE THEN {grow} ELSE list_append(k, {{'n': 1::BIGINT, 'ls': x, 'id': {opened}::BIGINT}}) END, (CASE WHEN m < {r * r}::DOUBLE THEN k[b].id ELSE {opened} END)::BIGINT
 FROM (SELECT *, list_position(ds, m) AS b FROM (SELECT *, list_min(ds) AS m FROM (
   SELECT c.series_id, c.t, c.rn, c.x, s.k, list_transform(s.k, lambda c: {dist.replace('x[i]', 'x[i]')}) AS ds FROM s JOIN cand c ON c.series_id = s.series_id AND c.rn = s.rn + 1))))
 SELECT series_id, t, cluster_id FROM s"""


def shift_diffs(clusters: str, t_s: int = 10) -> str:
    return f"""SELECT sensor, small, large, small_n, count(*) AS pairs, sum(diff)::BIGINT AS sum_diff, sum(diff * diff)::BIGINT AS sum_sq FROM (
 SELECT a.sensor, a.cluster_id AS small, b.cluster_id AS large, a.n AS small_n, a.series_id, a.t, min({{'a': abs(b.t - a.t), 'd': b.t - a.t}}).d AS diff
 FROM (SELECT *, count(*) OVER (PARTITION BY sensor, cluster_id) AS n FROM ({clusters})) a JOIN (SELECT *, count(*) OVER (PARTITION BY sensor, cluster_id) AS n FROM ({clusters})) b
 ON a.sensor = b.sensor AND a.series_id = b.series_id AND abs(b.t - a.t) < {t_s} AND (b.n > a.n OR (b.n = a.n AND b.cluster_id < a.cluster_id)) GROUP BY ALL) GROUP BY ALL"""


def supported(clusters: str, s: int, count: str = "count(*)") -> str:
    return f"SELECT * FROM ({clusters}) WHERE (sensor, cluster_id) IN (SELECT (sensor, cluster_id) FROM ({clusters}) GROUP BY sensor, cluster_id HAVING {count} > {s})"


def matches(clusters: str, rule: str = "deviation") -> str:
    test = "100 * pairs > 50 * small_n AND pairs * sum_sq - sum_diff * sum_diff < 4 * pairs * pairs" if rule == "deviation" else "100 * pairs >= 50 * small_n"
    return f"SELECT sensor, small, large FROM ({shift_diffs(clusters)}) WHERE {test}"


def greedy(clusters: str) -> str:
    """Kept clusters by greedy shift removal, of one sensor."""
    return f"""WITH RECURSIVE mt AS MATERIALIZED (SELECT DISTINCT small, large FROM ({matches(clusters)})),
 rk AS MATERIALIZED (SELECT cluster_id, row_number() OVER (ORDER BY n DESC, cluster_id) AS rn FROM (SELECT cluster_id, count(*) AS n FROM ({clusters}) GROUP BY 1)),
 lg AS MATERIALIZED (SELECT rk.rn, rk.cluster_id, coalesce((SELECT list(large) FROM mt WHERE small = rk.cluster_id), []) AS larger FROM rk),
 g AS (SELECT rn, [cluster_id] AS kept FROM lg WHERE rn = 1 UNION ALL
  SELECT lg.rn, CASE WHEN list_has_any(g.kept, lg.larger) THEN g.kept ELSE list_append(g.kept, lg.cluster_id) END FROM g JOIN lg ON lg.rn = g.rn + 1)
 SELECT unnest(kept) AS cluster_id FROM (SELECT kept FROM g ORDER BY rn DESC LIMIT 1)"""


def bucket_rows(series: str, family: str, sets: int = 5, per_set: int = 3, width: float = 4.0) -> str:
    planes, out = fixed_planes(sets, per_set, D), []
    for i, p in enumerate(planes):
        dots = [" + ".join(["0.0::DOUBLE", *[f"p{j} * {float(c)}::DOUBLE" for j, c in enumerate(n)]]) for n in p]
        key = " || ".join(f"CASE WHEN {e} >= 0 THEN '1' ELSE '0' END" for e in dots) if family == "sign" else " || '_' || ".join(f"floor(({e}) / {width * float(sum(c * c for c in n)) ** 0.5!r}::DOUBLE)::BIGINT::VARCHAR" for e, n in zip(dots, p, strict=True))
        out.append(f"SELECT sensor, series_id, t, {i} AS set, {key} AS bucket FROM c")
    return f"WITH c AS ({candidates(series)}) " + " UNION ALL ".join(out)


RADII = f"SELECT series_id, count(*) AS w, round(CASE WHEN count(*) > 20 THEN sqrt(count(*) / 20.0::DOUBLE) ELSE 1.0::DOUBLE END, 6) AS r FROM ({RUN}) GROUP BY 1"


def drop_trivial(clusters: str, windows: str, delta2: float = 4.0) -> str:
    """Members kept by the scan in time order, as a recursion over (cluster, run) with the time of the last kept member."""
    return f"""WITH RECURSIVE h AS MATERIALIZED ({clusters}), w AS MATERIALIZED ({windows}), k AS MATERIALIZED (SELECT cluster_id, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c FROM h GROUP BY 1),
 m AS MATERIALIZED (SELECT h.series_id, h.t, h.cluster_id, h.x, k.c, row_number() OVER (PARTITION BY h.cluster_id, h.series_id ORDER BY h.t) AS rn FROM h JOIN k ON k.cluster_id = h.cluster_id),
 p AS MATERIALIZED (SELECT a.cluster_id, a.series_id, a.t AS t1, b.t AS t2 FROM m a JOIN m b ON a.cluster_id = b.cluster_id AND a.series_id = b.series_id AND a.rn < b.rn JOIN w ON w.series_id = a.series_id AND w.t > a.t AND w.t < b.t
  GROUP BY 1, 2, 3, 4 HAVING bool_or({sq('w.x', 'a.x')} > {delta2} AND {sq('w.x', 'b.x')} > {delta2}) AND bool_or({sq('w.x', 'a.c')} > {delta2})),
 g AS (SELECT cluster_id, series_id, rn, t, t AS last, true AS kept FROM m WHERE rn = 1 UNION ALL
  SELECT m.cluster_id, m.series_id, m.rn, m.t, CASE WHEN p.t1 IS NULL THEN g.last ELSE m.t END, p.t1 IS NOT NULL
  FROM g JOIN m ON m.cluster_id = g.cluster_id AND m.series_id = g.series_id AND m.rn = g.rn + 1 LEFT JOIN p ON p.cluster_id = m.cluster_id AND p.series_id = m.series_id AND p.t1 = g.last AND p.t2 = m.t)
 SELECT series_id, t, cluster_id FROM g WHERE kept"""


def closest_of_islands(clusters: str, gap: int) -> str:
    """Of members of a cluster and run that follow each other by at most gap steps, the one nearest to the centroid."""
    return f"""WITH h AS MATERIALIZED ({clusters}), k AS (SELECT cluster_id, [{', '.join(f'avg(x[{i}])' for i in range(1, D + 1))}] AS c FROM h GROUP BY 1),
 m AS (SELECT h.*, {sq('x', 'c')} AS d2, CASE WHEN h.t - lag(h.t) OVER (PARTITION BY h.cluster_id, h.series_id ORDER BY h.t) > {gap} THEN 1 ELSE 0 END AS j FROM h JOIN k ON k.cluster_id = h.cluster_id),
 i AS (SELECT *, sum(j) OVER (PARTITION BY cluster_id, series_id ORDER BY t) AS island FROM m)
 SELECT series_id, t, cluster_id FROM i QUALIFY row_number() OVER (PARTITION BY cluster_id, series_id, island ORDER BY d2, t) = 1"""


def procedure(series: str, s: int, windows: str) -> str:
    """The steps after candidates with clusters of equal words, as tables: w0 clusters, h of high support, k1 not shifted, m1 not trivial, g not
    shifted again, f split by levels."""
    return f"""WITH w0 AS MATERIALIZED ({word_clusters(series)}), h AS MATERIALIZED ({supported('SELECT * FROM w0', s)}),
 k1 AS MATERIALIZED (SELECT * FROM h WHERE cluster_id IN ({greedy('SELECT * FROM h')})),
 tr AS MATERIALIZED ({drop_trivial('SELECT * FROM k1', windows)}),
 m1 AS MATERIALIZED (SELECT k1.* FROM k1 JOIN tr ON tr.series_id = k1.series_id AND tr.t = k1.t AND tr.cluster_id = k1.cluster_id),
 g AS MATERIALIZED (SELECT * FROM m1 WHERE cluster_id IN ({greedy('SELECT * FROM m1')})),
 lv AS MATERIALIZED (SELECT series_id, t, cluster_id, round(level * 1e9)::BIGINT AS lv FROM g),
 co AS MATERIALIZED (SELECT *, count(*) OVER (PARTITION BY cluster_id ORDER BY lv RANGE BETWEEN 500000000 PRECEDING AND 500000000 FOLLOWING) >= 2 AS core FROM lv),
 ld AS MATERIALIZED (SELECT cluster_id, lv, sum(j) OVER (PARTITION BY cluster_id ORDER BY lv) AS level_id FROM (SELECT *, CASE WHEN lv - lag(lv) OVER (PARTITION BY cluster_id ORDER BY lv) > 500000000 THEN 1 ELSE 0 END AS j FROM (SELECT DISTINCT cluster_id, lv FROM co WHERE core))),
 pl AS MATERIALIZED (SELECT co.series_id, co.t, co.cluster_id, p.level_id::BIGINT AS level_id FROM co, LATERAL (SELECT level_id FROM ld WHERE ld.cluster_id = co.cluster_id AND abs(ld.lv - co.lv) <= 500000000 ORDER BY abs(ld.lv - co.lv), ld.lv LIMIT 1) p),
 f AS MATERIALIZED (SELECT * FROM pl QUALIFY count(*) OVER (PARTITION BY cluster_id, level_id) > {s})"""


def lloyd(series: str, k: int, rounds: int) -> str:
    """Rounds of k-means from the first k keys, one pair of common tables a round."""
    q = [f"q{j}" for j in range(D)]
    gap = " + ".join(f"(r.{c} - m.{c}) * (r.{c} - m.{c})" for c in q)
    near = lambda i: f"SELECT r.sensor, r.series_id, r.t, {', '.join(f'any_value(r.{c}) AS {c}' for c in q)}, min({{'d2': {gap}, 'c': m.c}}).c AS cluster_id FROM r, m{i} m GROUP BY 1, 2, 3"
    steps = [f"r AS MATERIALIZED (SELECT sensor, series_id, t, {', '.join(f'round(p{j} * 1000000)::BIGINT AS q{j}' for j in range(D))} FROM ({candidates(series)}))", f"m0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY sensor, series_id, t) - 1 AS c, {', '.join(f'{c}::DOUBLE AS {c}' for c in q)} FROM r ORDER BY sensor, series_id, t LIMIT {k})"]
    for i in range(rounds):
        steps.append(f"m{i + 1} AS MATERIALIZED (SELECT m.c, {', '.join(f'coalesce(s.{c}, m.{c}) AS {c}' for c in q)} FROM m{i} m LEFT JOIN (SELECT cluster_id, {', '.join(f'sum({c})::DOUBLE / count(*) AS {c}' for c in q)} FROM ({near(i)}) GROUP BY 1) s ON s.cluster_id = m.c)")
    return f"WITH {', '.join(steps)} SELECT sensor, series_id, t, cluster_id FROM ({near(rounds)})"
