"""DuckDB SQL that computes the queries' rows independently from the base tables."""

from __future__ import annotations

CUST = """cust AS (SELECT c_custkey AS id, c_acctbal / 1000 AS x, CAST(0.4 AS DOUBLE) * c_nationkey AS y,
    CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS grp FROM customer)"""


def greedy(src: str, name: str, dims: list[str], k: int, part: str = "0") -> str:
    """Recursive farthest-first over ``src`` (id, dims..., part): rows (part, step, id, pid, pd, md)."""
    d = lambda p: " + ".join(f"abs({c} - {p}{c})" for c in dims)
    cols = ", ".join(dims)
    firsts = ", ".join(f"first_value({c}) OVER w AS p_{c}" for c in dims)
    return f"""{name} AS (
    SELECT part, 1 AS step, id, {cols}, pid, CAST('Infinity' AS DOUBLE) AS pd, {d("p_")} AS md FROM (
        SELECT {part} AS part, id, {cols}, first_value(id) OVER w AS pid, {firsts} FROM {src} WINDOW w AS (PARTITION BY {part} ORDER BY id))
    UNION ALL
    SELECT part, step + 1, id, {cols}, np, nd, least(md, {d("p_")}) FROM (
        SELECT part, step, id, {cols}, md, first_value(id) OVER w AS np, first_value(md) OVER w AS nd, {firsts}
        FROM {name} WHERE step < {k} WINDOW w AS (PARTITION BY part ORDER BY md DESC, id)))"""


def sequential(src: str, name: str) -> str:
    """Sequential net in SQL over ``src`` (part, rn, id, x, y, thr): state per part is the list of net points kept so far."""
    return f"""{name} AS (
    SELECT part, CAST(0 AS BIGINT) AS rn, CAST([] AS STRUCT(id BIGINT, x DOUBLE, y DOUBLE)[]) AS net FROM (SELECT DISTINCT part FROM {src})
    UNION ALL
    SELECT s.part, s.rn, CASE WHEN len(list_filter(n.net, lambda p: abs(p.x - s.x) + abs(p.y - s.y) <= s.thr)) > 0 THEN n.net
        ELSE list_append(n.net, {{'id': s.id, 'x': s.x, 'y': s.y}}) END
    FROM {name} n JOIN {src} s ON s.part = n.part AND s.rn = n.rn + 1)"""


def net_points(state: str, name: str) -> str:
    return f"""{name} AS (SELECT part, i AS pos, net[i].id AS nid, net[i].x AS nx, net[i].y AS ny
    FROM (SELECT part, net, unnest(range(1, len(net) + 1)) AS i FROM (SELECT part, arg_max(net, rn) AS net FROM {state} GROUP BY part)))"""


def owners(src: str, net: str, name: str) -> str:
    """Each row of ``src`` with the earliest net point within its threshold."""
    return f"""{name} AS (SELECT s.part, s.id, s.grp, min(n.pos) AS pos FROM {src} s JOIN {net} n ON s.part = n.part AND abs(n.nx - s.x) + abs(n.ny - s.y) <= s.thr GROUP BY s.part, s.id, s.grp)"""


NET1 = f"""WITH RECURSIVE {CUST},
src AS (SELECT 0 AS part, row_number() OVER (ORDER BY id) AS rn, id, x, y, grp, CAST(1.0 AS DOUBLE) AS thr FROM cust),
{sequential("src", "state")}, {net_points("state", "net")}, {owners("src", "net", "own")}"""

NET4 = NET1.replace("SELECT 0 AS part, row_number() OVER (ORDER BY id)", "SELECT id % 4 AS part, row_number() OVER (PARTITION BY id % 4 ORDER BY id)")

RATES = ", ".join(f"CAST(sum(CASE WHEN brand = {b} THEN l_quantity ELSE 0 END) AS DOUBLE) AS q{b}" for b in range(1, 11))
BRANDS = """lines AS (SELECT o_custkey AS id, l_quantity, l_linestatus, CAST(regexp_extract(p_brand, '(\\d+)', 1) AS INTEGER) AS brand
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey)"""


def _ahead(b: int) -> str:
    return " + ".join(f"CAST(q{o} > q{b} OR (q{o} = q{b} AND {o} < {b}) AS INTEGER)" for o in range(1, 11) if o != b)


LINE = """line AS (SELECT row_number() OVER (ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_discount, l_tax, l_shipdate) - 1 AS id,
    CAST(dense_rank() OVER (ORDER BY l_linestatus) - 1 AS INTEGER) AS grp, l_quantity AS a, l_extendedprice AS b, l_discount AS c, l_tax AS d,
    CAST(date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE) AS e, o_totalprice AS f
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
z AS (SELECT id, grp, """ + ", ".join(f"({c} - round(avg({c}) OVER (), 6)) / round(stddev_pop({c}) OVER (), 6) AS {c}" for c in "abcdef") + " FROM line)"

NATIONS = """nat AS (SELECT n_nationkey AS id, n_regionkey AS grp, round(coalesce(a, 0) / 1000, 6) AS x, round(coalesce(b, 0) / 1000, 6) AS y, coalesce(n, 0) / CAST(10 AS DOUBLE) AS w
    FROM nation LEFT JOIN (SELECT c_nationkey, avg(c_acctbal) AS a, count(*) AS n FROM customer GROUP BY 1) ON c_nationkey = n_nationkey
    LEFT JOIN (SELECT s_nationkey, avg(s_acctbal) AS b FROM supplier GROUP BY 1) ON s_nationkey = n_nationkey)"""

ANCHORS = """anchors AS (SELECT grp AS anchor, arg_min(x, id) AS ax, arg_min(y, id) AS ay FROM cust GROUP BY grp)"""

_MASKS = """piv AS (SELECT DISTINCT step, pid, pd FROM ff),
member AS (SELECT v.step AS pivot, p.grp, min(abs(p.x - q.x) + abs(p.y - q.y)) AS dist FROM piv v JOIN cust q ON q.id = v.pid CROSS JOIN cust p GROUP BY 1, 2),
caps AS (SELECT unnest(range(32)) AS t),
sets AS (SELECT t, 2 * bit_count(CAST(t AS INTEGER)) AS cap FROM caps)"""

HALL = f"""WITH RECURSIVE {CUST}, {greedy("cust", "ff", ["x", "y"], 10)}, {_MASKS},
masks AS (SELECT h.step AS h, m.pivot, CAST(sum(CASE WHEN m.dist < h.pd / 2 THEN 1 << m.grp ELSE 0 END) AS BIGINT) AS mask
    FROM piv h JOIN member m ON m.pivot <= h.step GROUP BY 1, 2),
hall AS (SELECT h, t, count(*) FILTER ((mask & (31 - t)) = 0) AS confined FROM masks CROSS JOIN caps GROUP BY 1, 2),
ok AS (SELECT h, bool_and(confined <= cap) AS feasible FROM hall JOIN sets USING (t) GROUP BY 1)"""

SQL: dict[str, str] = {
    "group_caps": "SELECT CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS grp, c_mktsegment AS name, 10 AS cap FROM (SELECT DISTINCT c_mktsegment FROM customer)",
    "crossed_groups_rollup": "SELECT l_linestatus, o_orderpriority, count(*) AS points FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ROLLUP (l_linestatus, o_orderpriority)",
    "crossed_groups_cube": "SELECT l_linestatus, o_orderpriority, count(*) AS points FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY CUBE (l_linestatus, o_orderpriority)",
    "events_in_summaries": "WITH v AS (SELECT DISTINCT date_trunc('day', ts) AS a FROM events) SELECT CAST(date_diff('day', DATE '1970-01-01', CAST(a AS DATE)) AS INTEGER) AS start_day, count(*) AS events FROM v JOIN events ON ts >= a AND ts < a + INTERVAL 36 HOUR GROUP BY a",
    "points_w1_rankings": f"WITH {BRANDS}, q AS (SELECT id, {RATES} FROM lines GROUP BY id) SELECT id AS c_custkey, {', '.join(f'CAST({_ahead(b)} AS INTEGER) AS p{b}' for b in range(1, 11))} FROM q",
    "points_w2_scores": f"""WITH {BRANDS}, s AS (SELECT id, brand, l_linestatus, CAST(least(4, floor(avg(l_quantity) / 10)) AS BIGINT) AS v FROM lines GROUP BY ALL)
        SELECT id AS point_id, CAST(sum(v) AS BIGINT) AS total, CAST(sum(v * (2 * (brand - 1) + CASE WHEN l_linestatus = 'F' THEN 0 ELSE 1 END + 1)) AS BIGINT) AS weighted FROM s GROUP BY id""",
    "points_w3_normalised": f"WITH {LINE} SELECT id AS point_id, grp, {', '.join(f'round({c}, 4) + 0.0 AS z{i}' for i, c in enumerate('abcdef'))} FROM z",
    "metric_profile": f"""WITH {CUST}, {ANCHORS}, d AS (
        SELECT anchor, abs(x - ax) + abs(y - ay) AS l1, sqrt((x - ax) * (x - ax) + (y - ay) * (y - ay)) AS l2, greatest(abs(x - ax), abs(y - ay)) AS linf,
            CAST((x <> ax)::INT + (y <> ay)::INT AS DOUBLE) AS hamming FROM cust CROSS JOIN anchors),
        l AS (UNPIVOT d ON l1, l2, linf, hamming INTO NAME metric VALUE v)
        SELECT metric, CAST(anchor AS INTEGER) AS anchor, round(max(v), 6) AS most, round(avg(v), 6) AS mean FROM l GROUP BY ALL""",
    "inversion_profile": f"""WITH {BRANDS}, q AS (SELECT id, {RATES} FROM lines GROUP BY id), p AS (SELECT id, [{', '.join(_ahead(b) for b in range(1, 11))}] AS r FROM q),
        a AS (SELECT r AS ar FROM p WHERE id = (SELECT min(id) FROM p)),
        pairs AS (SELECT i, j FROM range(1, 11) t(i), range(1, 11) u(j) WHERE i < j)
        SELECT id AS point_id, CAST(sum(CASE WHEN (r[i] > r[j]) <> (ar[i] > ar[j]) THEN 1 ELSE 0 END) AS BIGINT) AS inversions FROM p CROSS JOIN a CROSS JOIN pairs GROUP BY id""",
    "aspect_ratio_embeddings": """WITH e AS (SELECT vec_id AS id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS v FROM embeddings),
        d AS (SELECT list_sum(list_transform(range(1, len(a.v) + 1), lambda i: abs(a.v[i] - b.v[i]))) AS d FROM e a JOIN e b ON a.id < b.id)
        SELECT round(max(d), 6) AS max_dist, round(min(d) FILTER (d > 0), 6) AS min_dist, round(max(d) / min(d) FILTER (d > 0), 6) AS aspect_ratio FROM d""",
    "aspect_ratio_customer": f"""WITH {CUST}, d AS (SELECT abs(a.x - b.x) + abs(a.y - b.y) AS d FROM cust a JOIN cust b ON a.id < b.id)
        SELECT round(max(d), 6) AS max_dist, round(min(d) FILTER (d > 0), 6) AS min_dist, round(max(d) / min(d) FILTER (d > 0), 3) AS aspect_ratio FROM d""",
    "farthest_first_customer": f"WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 12)} SELECT CAST(step - 1 AS INTEGER) AS rank, pid AS point_id, CASE WHEN step = 1 THEN 0 ELSE round(pd, 6) END AS delta, round((SELECT max(md) FROM ff WHERE step = 12), 6) AS radius FROM (SELECT DISTINCT step, pid, pd FROM ff)",
    "farthest_first_lineitem": f"WITH RECURSIVE {LINE}, {greedy('z', 'ff', list('abcdef'), 8)} SELECT CAST(step - 1 AS INTEGER) AS rank, pid AS point_id, CASE WHEN step = 1 THEN 0 ELSE round(pd, 4) END AS delta, round((SELECT max(md) FROM ff WHERE step = 8), 4) AS radius FROM (SELECT DISTINCT step, pid, pd FROM ff)",
    "farthest_first_per_shard": f"WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 5, 'id % 4')} SELECT part AS shard, CAST(step - 1 AS INTEGER) AS rank, pid AS point_id, CASE WHEN step = 1 THEN 0 ELSE round(pd, 6) END AS delta, round(r, 6) AS radius FROM (SELECT DISTINCT part, step, pid, pd FROM ff) JOIN (SELECT part, max(md) AS r FROM ff WHERE step = 5 GROUP BY part) USING (part)",
    "lower_bound_radius": f"WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 10, 'id % 4')} SELECT round(max(md) / 2, 6) AS lower_bound FROM ff WHERE step = 10",
    "net_aggregate_customer": f"""{NET4}, d AS (SELECT part, nid, o.grp, o.id, abs(s.x - nx) + abs(s.y - ny) AS dist FROM own o JOIN net USING (part, pos) JOIN src s USING (part, id))
        SELECT part AS shard, nid AS net_id, grp, min(id) AS rep_id, round(arg_min(dist, id), 6) AS dist FROM d GROUP BY ALL""",
    "sql_distances": f"""WITH {CUST} SELECT id AS point_id, round(abs(x - 1) + abs(y - 1), 6) AS l1, round(sqrt((x - 1) * (x - 1) + (y - 1) * (y - 1)), 6) AS l2,
        round(greatest(abs(x - 1), abs(y - 1)), 6) AS linf, CAST((x <> 1)::INT + (y <> 1)::INT AS DOUBLE) AS hamming FROM cust""",
    "threshold_net_customer": f"{NET1} SELECT nid AS net_id, CAST(bit_or(1 << grp) AS BIGINT) AS groups, count(*) AS members FROM own JOIN net USING (part, pos) GROUP BY nid",
    "net_representatives_first": f"{NET1} SELECT nid AS net_id, grp, min(id) AS rep_id FROM own JOIN net USING (part, pos) GROUP BY nid, grp",
    "net_representatives_nearest": f"""{NET1}, d AS (SELECT nid, o.grp, o.id, abs(s.x - nx) + abs(s.y - ny) AS dist FROM own o JOIN net USING (part, pos) JOIN src s USING (id))
        SELECT nid AS net_id, grp, id AS rep_id FROM (SELECT *, row_number() OVER (PARTITION BY nid, grp ORDER BY dist, id) AS r FROM d) WHERE r = 1""",
    "net_packing_covering": f"""{NET1}, gap AS (SELECT min(abs(a.nx - b.nx) + abs(a.ny - b.ny)) AS g FROM net a JOIN net b ON a.pos < b.pos),
        cov AS (SELECT max(d) AS c FROM (SELECT min(abs(x - nx) + abs(y - ny)) AS d FROM src JOIN net USING (part) GROUP BY id))
        SELECT (SELECT count(*) FROM net) AS net_points, round(g, 6) AS least_gap, round(c, 6) AS covering, g >= 1.0 AS packed, c <= 1.0 AS covered FROM gap, cov""",
    "merge_nets_two_shards": f"""WITH RECURSIVE {CUST},
        src AS (SELECT id % 2 AS part, row_number() OVER (PARTITION BY id % 2 ORDER BY id) AS rn, id, x, y, grp, CASE WHEN id % 2 = 0 THEN 0.5 ELSE 1.0 END::DOUBLE AS thr FROM cust),
        {sequential("src", "state")}, {net_points("state", "net")}, {owners("src", "net", "own")},
        bits AS (SELECT part, pos, nid, nx, ny, bit_or(1 << grp) AS b FROM own JOIN net USING (part, pos) GROUP BY ALL),
        line AS (SELECT 0 AS part, row_number() OVER (ORDER BY part DESC, pos) AS rn, nid AS id, nx AS x, ny AS y, b, CASE WHEN part = 1 THEN -1 ELSE 1.0 END::DOUBLE AS thr FROM bits),
        {sequential("line", "mstate")}, {net_points("mstate", "mnet")},
        mown AS (SELECT l.id, l.b, CASE WHEN l.thr < 0 THEN min(n.pos) FILTER (n.nid = l.id) ELSE min(n.pos) FILTER (abs(n.nx - l.x) + abs(n.ny - l.y) <= 1.0) END AS pos FROM line l JOIN mnet n USING (part) GROUP BY l.id, l.b, l.thr)
        SELECT nid AS net_id, CAST(bit_or(b) AS BIGINT) AS groups FROM mown JOIN mnet USING (pos) GROUP BY nid""",
    "worker_nets": f"""WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 10, 'id % 4')}, rt AS (SELECT part, max(md) / 8 AS r FROM ff WHERE step = 10 GROUP BY part),
        src AS (SELECT id % 4 AS part, row_number() OVER (PARTITION BY id % 4 ORDER BY id) AS rn, id, x, y, grp, 2 * (CAST(1 AS DOUBLE) / 3) * r AS thr FROM cust JOIN rt ON rt.part = id % 4),
        {sequential("src", "state")}, {net_points("state", "net")}
        SELECT part AS shard, round(r, 6) AS r_t, count(*) AS net_points, CAST(sum(nid) AS BIGINT) AS id_sum FROM net JOIN rt USING (part) GROUP BY part, r""",
    "coordinator_net": f"""WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 10, 'id % 4')}, rt AS (SELECT part, max(md) / 8 AS r FROM ff WHERE step = 10 GROUP BY part),
        src AS (SELECT id % 4 AS part, row_number() OVER (PARTITION BY id % 4 ORDER BY id) AS rn, id, x, y, grp, 2 * (CAST(1 AS DOUBLE) / 3) * r AS thr FROM cust JOIN rt ON rt.part = id % 4),
        {sequential("src", "state")}, {net_points("state", "net")}, {owners("src", "net", "own")},
        bits AS (SELECT part, pos, nid, nx, ny, bit_or(1 << grp) AS b FROM own JOIN net USING (part, pos) GROUP BY ALL),
        line AS (SELECT 0 AS part, row_number() OVER (ORDER BY part, pos) AS rn, nid AS id, nx AS x, ny AS y, b, 2 * (CAST(1 AS DOUBLE) / 3) * (SELECT max(r) FROM rt) AS thr FROM bits),
        {sequential("line", "mstate")}, {net_points("mstate", "mnet")},
        mown AS (SELECT l.id, l.b, min(n.pos) AS pos FROM line l JOIN mnet n ON abs(n.nx - l.x) + abs(n.ny - l.y) <= l.thr GROUP BY l.id, l.b)
        SELECT nid AS net_id, CAST(bit_or(b) AS BIGINT) AS groups FROM mown JOIN mnet USING (pos) GROUP BY nid""",
    "hall_feasible_prefixes": f"{HALL} SELECT CAST(h AS INTEGER) AS prefix, CAST(sum(mask) AS BIGINT) AS mask_sum, feasible FROM masks JOIN ok USING (h) GROUP BY h, feasible",
    "static_prefix_and_radius": f"""{HALL}, best AS (SELECT max(h) AS h FROM ok WHERE feasible),
        radii AS (SELECT DISTINCT m.dist AS rho FROM member m, best b JOIN piv v ON v.step = b.h WHERE m.pivot <= b.h AND m.dist < v.pd / 2),
        rm AS (SELECT rho, m.pivot, sum(CASE WHEN m.dist <= rho THEN 1 << m.grp ELSE 0 END) AS mask FROM radii, best b JOIN member m ON m.pivot <= b.h GROUP BY 1, 2),
        rh AS (SELECT rho, t, count(*) FILTER ((CAST(mask AS BIGINT) & (31 - t)) = 0) AS confined FROM rm CROSS JOIN caps GROUP BY 1, 2),
        rok AS (SELECT rho FROM rh JOIN sets USING (t) GROUP BY rho HAVING bool_and(confined <= cap))
        SELECT CAST((SELECT h FROM best) AS INTEGER) AS prefix, round(min(rho), 6) AS radius FROM rok""",
    "exact_fair_nations": f"""WITH {NATIONS}, d AS (SELECT a.id AS p, b.id AS c, abs(a.x - b.x) + abs(a.y - b.y) + abs(a.w - b.w) AS d FROM nat a CROSS JOIN nat b),
        combo AS (SELECT r0.id AS a, r1.id AS b, r2.id AS c, r3.id AS e, r4.id AS f FROM nat r0, nat r1, nat r2, nat r3, nat r4 WHERE r0.grp = 0 AND r1.grp = 1 AND r2.grp = 2 AND r3.grp = 3 AND r4.grp = 4),
        far AS (SELECT k.a, k.b, k.c, k.e, k.f, d.p, min(d.d) AS md FROM combo k, d WHERE d.c IN (k.a, k.b, k.c, k.e, k.f) GROUP BY ALL)
        SELECT round(min(cost), 6) AS optimum FROM (SELECT max(md) AS cost FROM far GROUP BY a, b, c, e, f)""",
    "cost_fixed_centers": f"WITH {CUST}, {ANCHORS} SELECT round(max(d), 6) AS cost FROM (SELECT id, min(abs(x - ax) + abs(y - ay)) AS d FROM cust CROSS JOIN anchors GROUP BY id)",
    "cost_by_group": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, grp, min(abs(x - ax) + abs(y - ay)) AS d FROM cust CROSS JOIN anchors GROUP BY id, grp) SELECT grp, round(max(d), 6) AS cost, round(avg(d), 6) AS mean_dist, count(*) AS points FROM d GROUP BY grp",
    "assign_nearest": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, anchor, abs(x - ax) + abs(y - ay) AS d FROM cust CROSS JOIN anchors), r AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d, anchor) AS r FROM d) SELECT id AS point_id, CAST(anchor AS INTEGER) AS center, round(d, 6) AS dist FROM r WHERE r = 1",
    "uncovered_points": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, min(abs(x - ax) + abs(y - ay)) AS d FROM cust CROSS JOIN anchors GROUP BY id) SELECT id AS point_id, round(d, 6) AS dist FROM d WHERE d > 3",
    "ball_join_suppliers": f"""WITH {CUST}, s AS (SELECT s_suppkey AS sid, s_acctbal / 1000 AS sx, CAST(0.4 AS DOUBLE) * s_nationkey AS sy FROM supplier)
        SELECT id AS point_id, sid AS center_id, round(abs(x - sx) + abs(y - sy), 6) AS dist FROM cust JOIN s ON abs(x - sx) + abs(y - sy) <= 0.5""",
    "nearest_two_centers": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, anchor, abs(x - ax) + abs(y - ay) AS d FROM cust CROSS JOIN anchors), r AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d, anchor) AS r FROM d) SELECT id AS point_id, CAST(r - 1 AS INTEGER) AS place, CAST(anchor AS INTEGER) AS center, round(d, 6) AS dist FROM r WHERE r <= 2",
    "farthest_customers": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, anchor, abs(x - ax) + abs(y - ay) AS d FROM cust CROSS JOIN anchors), r AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d, anchor) AS r FROM d) SELECT id AS point_id, CAST(anchor AS INTEGER) AS center, round(d, 6) AS dist FROM r WHERE r = 1 ORDER BY d DESC, id LIMIT 20",
    "distance_profile": f"WITH {CUST}, {ANCHORS}, d AS (SELECT id, min(abs(x - ax) + abs(y - ay)) AS d FROM cust CROSS JOIN anchors GROUP BY id) SELECT round(quantile_cont(d, 0.5), 6) AS p50, round(quantile_cont(d, 0.9), 6) AS p90, round(quantile_cont(d, 0.99), 6) AS p99, round(max(d), 6) AS cost FROM d",
    "partition_check": "SELECT count(*) AS points, count(DISTINCT c_custkey) AS dealt, CAST(0 AS BIGINT) AS twice, CAST(0 AS BIGINT) AS lost, CAST(0 AS BIGINT) AS extra FROM customer",
    "representation_greedy": f"""WITH RECURSIVE {CUST}, {greedy('cust', 'ff', ['x', 'y'], 10)}, c AS (SELECT grp, count(*) AS used FROM (SELECT DISTINCT pid FROM ff) JOIN cust ON id = pid GROUP BY grp)
        SELECT grp, p.n AS points, coalesce(used, 0) AS used, round(p.n / (SELECT count(*) FROM cust), 6) AS point_share, round(coalesce(used, 0) / 10, 6) AS center_share
        FROM (SELECT grp, count(*) AS n FROM cust GROUP BY grp) p LEFT JOIN c USING (grp)""",
    "hourly_event_groups": "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS events, round(sum(value), 4) AS value FROM events GROUP BY ALL",
    "session_events": """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g)
        SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, n""",
}
