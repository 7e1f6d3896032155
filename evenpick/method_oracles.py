"""DuckDB SQL of the end-to-end queries: each method replayed on the base tables, down to the ids of its centers and their cost."""

from __future__ import annotations

from collections.abc import Mapping

from evenpick.oracles import BRANDS, LINE, NATIONS
from evenpick.replay import Replay

FIVE_TWO, FIVE_TEN, FIVE_FOUR, TWO_TEN = dict.fromkeys(range(5), 2), dict.fromkeys(range(5), 10), dict.fromkeys(range(5), 4), dict.fromkeys(range(2), 10)
SKEWED = {0: 1, 1: 9, 2: 9, 3: 1}
XY = "c_acctbal / 1000 AS x0, CAST(0.4 AS DOUBLE) * c_nationkey AS x1"
CUST = f"pts AS (SELECT c_custkey AS id, {XY}, CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS grp FROM customer)"
ALIKE = f"pts AS (SELECT c_custkey AS id, {XY}, 0 AS grp FROM customer)"
CORR = f"""cuts AS (SELECT quantile_cont(c_acctbal, [0.25, 0.5, 0.75]) AS q FROM customer),
pts AS (SELECT c_custkey AS id, {XY}, CAST(c_acctbal >= q[1] AS INTEGER) + CAST(c_acctbal >= q[2] AS INTEGER) + CAST(c_acctbal >= q[3] AS INTEGER) AS grp FROM customer CROSS JOIN cuts)"""
NAT = f"{NATIONS}, pts AS (SELECT id, grp, x AS x0, y AS x1, w AS x2 FROM nat)"
ORD = """ord AS (SELECT o_orderkey AS id, o_totalprice AS p, CAST(date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS d, CAST(dense_rank() OVER (ORDER BY o_orderstatus) - 1 AS INTEGER) AS grp FROM orders),
pts AS (SELECT id, grp, (p - round(avg(p) OVER (), 6)) / round(stddev_pop(p) OVER (), 6) AS x0, (d - round(avg(d) OVER (), 6)) / round(stddev_pop(d) OVER (), 6) AS x1 FROM ord)"""
EVT = """pts AS (SELECT event_id AS id, CAST(dense_rank() OVER (ORDER BY event_type) - 1 AS INTEGER) AS grp, value / 100 AS x0, hour(ts) / CAST(24 AS DOUBLE) AS x1,
    (dayofweek(ts) + 1) / CAST(7 AS DOUBLE) AS x2, round(ln(1 + value), 6) AS x3, date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS day FROM events)"""


def line_points(groups: int) -> str:
    if groups == 2:
        return LINE + ", pts AS (SELECT id, grp, a AS x0, b AS x1, c AS x2, d AS x3, e AS x4, f AS x5 FROM z)"
    by_priority = LINE.replace("l_linestatus) - 1 AS INTEGER) AS grp", "o_orderpriority) - 1 AS INTEGER) AS grp")
    return by_priority + ", pts AS (SELECT id, grp, a AS x0, b AS x1, c AS x2, d AS x3, e AS x4, f AS x5 FROM z)"


def customers() -> Replay:
    return Replay(CUST, 2, 5)


def lines(groups: int = 2) -> Replay:
    return Replay(line_points(groups), 6, groups)


# Centers of every method on a relation of points; ``caps`` as the query has them.


def budgeted(r: Replay, caps, budget: int, shards: int) -> str:
    return r.static(r.chosen(r.budget(r.dealt(shards), budget)), caps)


def budgeted_at_centers(r: Replay, caps, budget: int, shards: int) -> str:
    return r.lifted(r.copies(r.budget(r.dealt(shards), budget)), caps)


def guaranteed_net(r: Replay, k: int, eps: float, shards: int) -> str:
    nets, rt = r.worker_nets(r.dealt(shards), k, eps)
    return r.folded(nets, f"(SELECT 2 * (CAST({eps} AS DOUBLE) / 3) * max(r) FROM {rt})")


def guaranteed(r: Replay, caps, eps: float, shards: int) -> str:
    return r.lifted(r.copies(guaranteed_net(r, sum(caps.values()), eps, shards)), caps)


def one_pass(r: Replay, caps, eps: float) -> str:
    return r.lifted(r.copies(r.net_rows(r.incremental_nets(r.whole(), sum(caps.values()), f"(CAST({eps} AS DOUBLE) / 3)"))), caps)


def one_pass_budget(r: Replay, caps, budget: int) -> str:
    return r.static(r.chosen(r.net_rows(r.budget_nets(r.whole(), budget))), caps)


def sharded(r: Replay, caps, eps: float, shards: int) -> str:
    s = r.incremental_nets(r.dealt(shards), sum(caps.values()), f"(CAST({eps} AS DOUBLE) / 3 / 2)")
    return r.lifted(r.copies(r.folded(r.net_rows(s), f"(SELECT 2 * (CAST({eps} AS DOUBLE) / 3 / 4) * max(r) FROM {s})")), caps)


def streamed_guaranteed(r: Replay, caps, eps: float, shards: int) -> str:
    s = r.incremental_nets(r.dealt(shards), sum(caps.values()), f"(CAST({eps} AS DOUBLE) / 6)")
    return r.lifted(r.copies(r.folded(r.net_rows(s), f"(SELECT 2 * (CAST({eps} AS DOUBLE) / 12) * max(r) FROM {s})")), caps)


def scanned(r: Replay, caps, budget: int, shards: int) -> str:
    return r.static(r.chosen(r.net_rows(r.budget_nets(r.dealt(shards), budget))), caps)


def reported(base: Replay, method, caps: Mapping[int, int], *args) -> str:
    return base.report(method(base, caps, *args), sum(caps.values()))


def _all_on_nations() -> str:
    """Every method on the nations: centers, cost, and the ratio to the exact optimum."""
    caps, r = dict.fromkeys(range(5), 1), Replay(NAT, 3, 5)
    runs = {
        "static": lambda: r.static(r.whole(), caps),
        "two_pass": lambda: r.two_pass(r.whole(), caps, 0.1),
        "prior_distributed": lambda: r.prior(r.dealt(3), caps, 0.1),
        "distributed": lambda: guaranteed(r, caps, 1.0, 3),
        "distributed_budget": lambda: budgeted(r, caps, 25, 3),
        "one_pass": lambda: one_pass(r, caps, 1.0),
        "one_pass_budget": lambda: one_pass_budget(r, caps, 25),
        "sharded": lambda: sharded(r, caps, 1.0, 3),
    }
    factor = {"static": 3, "two_pass": 3.1, "prior_distributed": 17.1, "distributed": 6, "distributed_budget": 3, "one_pass": 6, "one_pass_budget": 3, "sharded": 6}
    best, rows = r.exact("pts", caps), []
    for name, run in runs.items():
        c = run()
        cost = r.cost(c)
        rows.append(f"SELECT '{name}' AS method, (SELECT string_agg(id, ',' ORDER BY rank) FROM {c}) AS centers, round(v.cost, 6) AS cost, round(v.cost / b.cost, 6) AS ratio_to_optimum, v.cost <= {factor[name]} * b.cost AS within_factor FROM {cost} v CROSS JOIN {best} b")
    return r.sql(" UNION ALL ".join(rows))


def _plain() -> str:
    """Plain k-center, one group, by every path."""
    caps, r = {0: 10}, Replay(ALIKE, 2, 1)
    runs = {
        "static": lambda: r.static(r.whole(), caps),
        "two_pass": lambda: r.two_pass(r.whole(), caps, 0.1),
        "prior_distributed": lambda: r.prior(r.dealt(4), caps, 0.1),
        "distributed": lambda: guaranteed(r, caps, 1.0, 4),
        "distributed_budget": lambda: budgeted(r, caps, 24, 4),
        "one_pass": lambda: one_pass(r, caps, 3.0),
        "one_pass_budget": lambda: one_pass_budget(r, caps, 24),
        "sharded": lambda: sharded(r, caps, 3.0, 4),
    }
    return r.sql(" UNION ALL ".join(f"SELECT '{n}' AS method, CAST(rank AS INTEGER) AS rank, id AS point_id FROM {run()}" for n, run in runs.items()))


def _budget_sweep() -> str:
    r = customers()
    deal = r.dealt(4)
    rows = []
    for b in (5, 10, 20, 40, 80):
        cover, cost = r.radius(r.greedy(deal, b)), r.cost(r.static(r.chosen(r.budget(deal, b)), FIVE_TWO))
        rows.append(f"SELECT {b} AS budget, (SELECT round(max(r), 6) FROM {cover}) AS coverage, (SELECT round(cost, 6) FROM {cost}) AS cost")
    return r.sql(" UNION ALL ".join(rows))


def _eps_sweep() -> str:
    r, rows = customers(), []
    for e in (3.0, 1.0, 0.5):
        net = guaranteed_net(r, 10, e, 4)
        cost = r.cost(r.lifted(r.copies(net), FIVE_TWO))
        rows.append(f"SELECT CAST({e} AS DOUBLE) AS eps, (SELECT count(DISTINCT nid) FROM {net}) AS net_points, (SELECT round(cost, 6) FROM {cost}) AS cost")
    return r.sql(" UNION ALL ".join(rows))


def _sufficient() -> str:
    r = customers()
    deal = r.dealt(4)
    low = r.radius(r.greedy(deal, 10))
    rows = [f"SELECT CAST({b} AS BIGINT) AS budget WHERE (SELECT max(r) FROM {r.radius(r.greedy(deal, b))}) <= CAST(3.0 AS DOUBLE) / 3 * ((SELECT max(r) FROM {low}) / 2)" for b in (20, 40, 80, 160, 320)]
    return r.sql(f"SELECT min(budget) AS budget FROM ({' UNION ALL '.join(rows)})")


def _windows(days: int) -> str:
    """Fair centers of every window of ``days`` days that starts each day."""
    r = Replay(EVT, 4, 5)
    deal = r.add(f"SELECT day - back AS part, id, grp, x0, x1, x2, x3 FROM pts CROSS JOIN (SELECT unnest(range({days})) AS back)")
    s = r.static(r.chosen(r.net_rows(r.budget_nets(deal, 60)), deal, True), FIVE_TWO)
    return r.sql(f"SELECT CAST(part AS INTEGER) AS start_day, CAST(rank AS INTEGER) AS rank, id AS point_id, CAST(grp AS INTEGER) AS grp FROM {s}")


def _trace(r: Replay, budget: int, every: int, doublings: bool) -> str:
    state = r.budget_nets(r.whole(), budget, True)
    rows = r.add(f"SELECT rn, r, doublings, net FROM {state} WHERE rn > 0 AND (rn % {every} = 0 OR rn = (SELECT count(*) FROM pts))")
    held = r.add(f"SELECT rn, count(DISTINCT id) AS held FROM (SELECT rn, unnest(list_concat(list_transform(net, lambda p: p.id), list_transform(flatten(list_transform(net, lambda p: p.reps)), lambda q: q.id))) AS id FROM {rows}) WHERE id IS NOT NULL GROUP BY rn")
    out = f"SELECT rn AS n_seen, round(r, 6) AS r, CAST(len(net) AS BIGINT) AS net_points, held AS points_held, CAST(doublings AS BIGINT) AS doublings FROM {rows} JOIN {held} USING (rn)"
    if not doublings:
        return r.sql(out)
    return r.sql(f"SELECT *, round(r / nullif(before, 0), 6) AS factor FROM (SELECT *, lag(r) OVER (ORDER BY n_seen) AS before FROM ({out})) WHERE r > before")


def _bound() -> str:
    r = customers()
    net = r.net(r.add(f"SELECT *, CAST(1.0 AS DOUBLE) AS thr FROM {r.whole()}"))
    c = r.lifted(r.copies(net), FIVE_TWO)
    at = r.add(f"SELECT DISTINCT p.* FROM {net} n JOIN pts p ON p.id = n.nid")
    cover = r.cost(at)
    cost = r.cost(c)
    core = r.add(f"SELECT max(d) AS cost FROM (SELECT p.id, min({r.far('p', 'v')}) AS d FROM {at} p CROSS JOIN (SELECT q.* FROM {c} JOIN pts q USING (id)) v GROUP BY p.id)")
    return r.sql(f"SELECT (SELECT count(*) FROM pts) AS points, round(a.cost, 6) AS cost, round(b.cost, 6) AS net_cost, round(c.cost, 6) AS covering, round(b.cost + 2 * c.cost, 6) AS bound, a.cost <= b.cost + 2 * c.cost AS bound_holds FROM {cost} a, {core} b, {cover} c")


def _distortion() -> str:
    r = customers()
    net = r.net(r.add(f"SELECT *, CAST(1.0 AS DOUBLE) AS thr FROM {r.whole()}"))
    at = r.add(f"SELECT DISTINCT p.* FROM {net} n JOIN pts p ON p.id = n.nid")
    anchors = r.add("SELECT min(id) AS id FROM pts GROUP BY grp")
    full = r.cost(anchors)
    core = r.add(f"SELECT max(d) AS cost FROM (SELECT p.id, min({r.far('p', 'v')}) AS d FROM {at} p CROSS JOIN (SELECT q.* FROM {anchors} JOIN pts q USING (id)) v GROUP BY p.id)")
    return r.sql(f"SELECT (SELECT count(*) FROM pts) AS points, (SELECT count(*) FROM {at}) AS net_points, round(c.cost, 6) AS core_cost, round(f.cost, 6) AS full_cost, round(abs(1 - c.cost / f.cost), 6) AS distortion FROM {full} f, {core} c")


def _hierarchy() -> str:
    r = customers()
    nets, rt = r.worker_nets(r.dealt(16), 10, 1.0)
    third = "(CAST(1.0 AS DOUBLE) / 3)"
    one = r.folded(nets, f"(SELECT {third} * max(r) / 2 FROM {rt})", "part // 4")
    two = r.folded(one, f"(SELECT {third} * max(r) / 1 FROM {rt})")
    return r.sql(f"SELECT nid AS net_id, CAST(sum(1 << grp) AS BIGINT) AS groups FROM {two} GROUP BY nid")


def _dimension() -> str:
    r = customers()
    sizes = [r.net(r.add(f"SELECT *, CAST({t} AS DOUBLE) AS thr FROM {r.whole()}")) for t in (0.5, 1.0)]
    return r.sql(f"SELECT round(log2((SELECT count(DISTINCT nid) FROM {sizes[0]}) / (SELECT count(DISTINCT nid) FROM {sizes[1]})), 6) AS dimension")


def _sent() -> str:
    r = customers()
    reps = r.budget(r.dealt(10), 24)
    per = r.add(f"SELECT part, count(DISTINCT nid) AS n, count(*) AS r FROM {reps} GROUP BY part")
    return r.sql(f"SELECT count(*) AS shards, CAST(sum(n) AS BIGINT) AS net_points, CAST(sum(r) AS BIGINT) AS representatives, max(r) AS most_of_a_shard FROM {per}")


def _feasible() -> str:
    r = customers()
    c = budgeted(r, FIVE_TWO, 24, 4)
    return r.sql(f"SELECT CAST(g AS INTEGER) AS grp, (SELECT count(*) FROM {c} WHERE grp = g) AS used, 2 AS cap, (SELECT count(*) FROM {c} WHERE grp = g) <= 2 AS fits FROM range(5) t(g)")


def _binding() -> str:
    r = Replay(CORR, 2, 4)
    fair = r.cost(r.static(r.whole(), SKEWED))
    plain = r.radius(r.greedy(r.whole(), 20))
    return r.sql(f"SELECT (SELECT count(*) FROM pts) AS points, round(cost, 6) AS fair_cost, round(r, 6) AS plain_cost, round(cost / r, 6) AS price FROM {fair}, {plain}")


def _ratio() -> str:
    r = customers()
    cost = r.cost(budgeted(r, FIVE_TWO, 24, 4))
    g = r.radius(r.greedy(r.whole(), 10))
    return r.sql(f"SELECT round(cost, 6) AS cost, round(r, 6) AS greedy_radius, round(cost / r, 6) AS ratio_greedy, round(2 * cost / r, 6) AS ratio_true FROM {cost}, {g}")


def _plugged() -> str:
    """The exact solver on the labelled copies of the nations' net: its cost over the copies."""
    r, caps = Replay(NAT, 3, 5), dict.fromkeys(range(5), 1)
    copies = r.copies(guaranteed_net(r, 5, 1.0, 3))
    return r.sql(f"SELECT (SELECT count(*) FROM {copies}) AS copies, round(cost, 6) AS net_optimum FROM {r.exact(copies, caps)}")


def _filled() -> str:
    r = Replay(CORR, 2, 4)
    rel = r.whole()
    return r.report(r.fill(rel, r.static(rel, SKEWED), SKEWED), 20)


def _random() -> str:
    r = lines()
    c = r.add("SELECT id, grp, row_number() OVER (PARTITION BY grp ORDER BY md5('3:' || id), id) AS rn FROM pts")
    got = r.add(f"SELECT row_number() OVER (ORDER BY grp, rn) - 1 AS rank, id, grp FROM {c} WHERE rn <= 10")
    return r.report(got, 20)


def _counters() -> str:
    r = customers()
    return r.sql(f"SELECT part AS shard, plain, pruned FROM {r.evaluations(r.dealt(4), 24)}")


def _one_pass_state(kind: str) -> str:
    r = customers()
    s = r.budget_nets(r.whole(), 60) if kind == "budget" else r.incremental_nets(r.whole(), 10, "(CAST(1.0 AS DOUBLE) / 3)")
    return r.sql(r.checked(s))


USERS = """types AS (SELECT event_type, row_number() OVER (ORDER BY event_type) AS t FROM (SELECT DISTINCT event_type FROM events)),
counts AS (SELECT user_id, list(coalesce(n, 0) ORDER BY t) AS c FROM (SELECT DISTINCT user_id FROM events) CROSS JOIN types LEFT JOIN (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) USING (user_id, event_type) GROUP BY user_id),
seg AS (SELECT c_custkey, CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS grp FROM customer),
pts AS (SELECT user_id AS id, grp, {pairs} FROM counts JOIN seg ON c_custkey = user_id)"""
#: The later of two types stands first where it has more events; ties go to the earlier type.
USERS = USERS.format(pairs=", ".join(f"CAST(c[{j}] > c[{i}] AS DOUBLE) AS x{n}" for n, (i, j) in enumerate((i, j) for i in range(1, 6) for j in range(i + 1, 6))))


def _users() -> str:
    return reported(Replay(USERS, 10, 5), one_pass_budget, FIVE_TWO, 30)


def token_hash(token: str) -> str:
    return f"CAST('0x' || substr(md5({token}), 1, 15) AS BIGINT)"


def hashed(table: str, point_id: str, group: str, text: str, dim: int) -> str:
    """Signed token counts of a text column as points."""
    cells = ", ".join(f"CAST(coalesce(sum(s) FILTER (j = {i}), 0) AS DOUBLE) AS x{i}" for i in range(dim))
    return f"""said AS (SELECT {point_id} AS id, {group} AS grp, regexp_extract_all(lower(coalesce({text}, '')), '[\\p{{L}}\\p{{N}}]+') AS w FROM {table}),
flat AS (SELECT id, h % {dim} AS j, CASE WHEN (h >> 40) & 1 = 1 THEN -1 ELSE 1 END AS s FROM (SELECT id, {token_hash('t')} AS h FROM (SELECT id, unnest(w) AS t FROM said))),
pts AS (SELECT s.id, CAST(any_value(s.grp) AS INTEGER) AS grp, {cells} FROM (SELECT DISTINCT id, grp FROM said) s LEFT JOIN flat f ON f.id = s.id GROUP BY s.id)"""


HOSTS = """hosts AS (SELECT page_id, html, coalesce(regexp_extract(url, '^[a-z]+://([^/?#:]*)', 1), '') AS host FROM pages),
top AS (SELECT host, row_number() OVER (ORDER BY count(*) DESC, host) - 1 AS g FROM hosts GROUP BY host QUALIFY row_number() OVER (ORDER BY count(*) DESC, host) <= 5),
owned AS (SELECT page_id, html, coalesce(g, 5) AS g FROM hosts LEFT JOIN top USING (host)), """
ROLES = "turns AS (SELECT conv_id * 100000 + turn AS id, text, dense_rank() OVER (ORDER BY role) - 1 AS g FROM conversations), "
LANGS = "langs AS (SELECT doc_id, text, dense_rank() OVER (ORDER BY lang) - 1 AS g FROM documents), "


def _texts(base: str, dim: int, groups: int, caps, budget: int, shards: int) -> str:
    return reported(Replay(base, dim, groups), budgeted, caps, budget, shards)


def _benchmark() -> str:
    """Cost of the benchmark items against fair centers of the documents."""
    r = Replay(LANGS + hashed("langs", "doc_id", "g", "text", 64), 64, 4)
    c = budgeted(r, dict.fromkeys(range(4), 5), 24, 10)
    other = hashed("benchmark", "item_id", "0", "text", 64).replace("said AS", "said2 AS").replace("FROM said", "FROM said2").replace("flat AS", "flat2 AS").replace("JOIN flat", "JOIN flat2").replace("pts AS", "items AS")
    r.parts.append(other)
    cost = r.add(f"SELECT max(d) AS cost FROM (SELECT p.id, min({r.far('p', 'v')}) AS d FROM items p CROSS JOIN (SELECT q.* FROM {c} JOIN pts q USING (id)) v GROUP BY p.id)")
    return r.sql(f"SELECT round(cost, 6) AS cost FROM {cost}")


def _features() -> str:
    base = hashed("documents", "doc_id", "0", "text", 64)
    total = " + ".join(f"abs(x{i})" for i in range(64))
    weighted = " + ".join(f"{i + 1} * x{i}" for i in range(64))
    return f"WITH {base} SELECT id AS point_id, CAST({total} AS BIGINT) AS norm, CAST({weighted} AS BIGINT) AS weighted FROM pts"


def _set_metrics() -> str:
    return f"""WITH {BRANDS}, s AS (SELECT id, brand, l_linestatus, CAST(least(4, floor(avg(l_quantity) / 10)) AS DOUBLE) AS v FROM lines GROUP BY ALL),
        c AS (SELECT * FROM s WHERE v <> 0), ids AS (SELECT DISTINCT id FROM s), f AS (SELECT brand, l_linestatus, v FROM c WHERE id = (SELECT min(id) FROM ids)),
        j AS (SELECT i.id, count(f.v) AS shared, count(c.v) AS mine, coalesce(sum(c.v * f.v), 0) AS dot, coalesce(sum(c.v * c.v), 0) AS aa FROM ids i LEFT JOIN c USING (id) LEFT JOIN f USING (brand, l_linestatus) GROUP BY i.id),
        n AS (SELECT count(*) AS theirs, sum(v * v) AS bb FROM f),
        d AS (SELECT CASE WHEN mine + theirs - shared = 0 THEN 0 ELSE 1 - shared / (mine + theirs - shared) END AS jac,
            acos(greatest(-1, least(1, CASE WHEN aa * bb > 0 THEN dot / sqrt(aa * bb) ELSE 0 END))) / pi() AS ang FROM j, n)
        SELECT round(max(jac), 6) AS jaccard_max, round(avg(jac), 6) AS jaccard_avg, round(max(ang), 6) AS angular_max, round(avg(ang), 6) AS angular_avg FROM d"""


def _distinct() -> str:
    xs = ", ".join(f"x{i}" for i in range(10))
    return f"WITH {USERS} SELECT min(id) AS point_id, grp FROM pts WHERE grp IN (0, 2, 4) GROUP BY grp, {xs}"


def _overlap() -> str:
    r = Replay(CORR, 2, 4)
    a, b = r.static(r.whole(), SKEWED), r.two_pass(r.whole(), SKEWED, 0.1)
    return r.sql(f"SELECT id AS point_id, CAST(grp AS INTEGER) AS grp, id IN (SELECT id FROM {b}) AS shared FROM {a}")


def _groups() -> str:
    r = customers()
    a = r.add("SELECT * FROM pts QUALIFY row_number() OVER (PARTITION BY grp ORDER BY id) = 1")
    own = r.add(f"SELECT p.id, p.grp, min({{'d': {r.far('p', 'a')}, 'at': a.grp}}) AS b FROM pts p CROSS JOIN {a} a GROUP BY p.id, p.grp")
    rep = r.add(f"SELECT b.at AS at, grp, min({{'d': b.d, 'id': id}}).id AS id FROM {own} GROUP BY b.at, grp")
    return r.sql(f"SELECT a.id AS net_id, CAST(sum(1 << r.grp) AS BIGINT) AS groups, CAST(count(*) AS INTEGER) AS n_reps, string_agg(r.id, ',' ORDER BY r.grp) AS rep_ids FROM {rep} r JOIN {a} a ON a.grp = r.at GROUP BY a.id")


SQL: dict[str, str] = {
    "static_centers": reported(lines(), lambda r, caps: (lambda rel: r.fill(rel, r.static(rel, caps), caps))(r.whole()), TWO_TEN),
    "static_rounds_centers": reported(customers(), lambda r, caps: r.static(r.whole(), caps), FIVE_TWO),
    "static_filled_centers": _filled(),
    "distributed_centers": reported(customers(), guaranteed, FIVE_TWO, 1.0, 4),
    "distributed_budget_centers": reported(lines(), budgeted, TWO_TEN, 24, 10),
    "distributed_budget_located_center": reported(lines(5), budgeted_at_centers, FIVE_TEN, 24, 10),
    "single_scan_workers": reported(customers(), scanned, FIVE_TWO, 24, 4),
    "one_pass_centers": reported(customers(), one_pass, FIVE_TWO, 1.0),
    "one_pass_budget_centers": reported(customers(), one_pass_budget, FIVE_TWO, 60),
    "sharded_one_pass_centers": reported(customers(), sharded, FIVE_TWO, 1.0, 4),
    "two_pass_centers": reported(customers(), lambda r, caps: r.two_pass(r.whole(), caps, 0.1), FIVE_TWO),
    "two_pass_correlated": reported(Replay(CORR, 2, 4), lambda r, caps: r.two_pass(r.whole(), caps, 0.1), SKEWED),
    "prior_distributed_centers": reported(lines(), lambda r, caps: r.prior(r.dealt(10), caps, 0.1), TWO_TEN),
    "random_centers": _random(),
    "guaranteed_orders": reported(Replay(ORD, 2, 3), guaranteed, dict.fromkeys(range(3), 10), 3.0, 8),
    "streaming_sharded_centers": reported(Replay(EVT, 4, 5), scanned, FIVE_FOUR, 60, 2),
    "streaming_guaranteed_centers": reported(Replay(EVT, 4, 5), streamed_guaranteed, FIVE_FOUR, 6.0, 2),
    "streaming_versioned_nets": f"""WITH {EVT}, v AS (SELECT id, grp, ceil(id * 3 / CAST((SELECT max(id) FROM pts) AS DOUBLE)) AS third FROM pts)
        SELECT CAST(i AS INTEGER) AS version, count(*) AS seen, CAST(bit_or(1 << grp) AS BIGINT) AS groups, TRUE AS packed, TRUE AS covered FROM v JOIN range(1, 4) t(i) ON third <= i GROUP BY i""",
    "sql_surface": reported(customers(), scanned, FIVE_TWO, 24, 4),
    "bounds_on_nations": _all_on_nations(),
    "plain_k_center": _plain(),
    "solver_plugged_in": _plugged(),
    "binding_capacities": _binding(),
    "budget_sweep": _budget_sweep(),
    "eps_sweep": _eps_sweep(),
    "smallest_sufficient_budget": _sufficient(),
    "cost_ratio_customer": _ratio(),
    "doubling_dimension_customer": _dimension(),
    "points_sent": _sent(),
    "feasibility_check": _feasible(),
    "cost_bound_check": _bound(),
    "coreset_distortion_check": _distortion(),
    "hierarchical_merge_check": _hierarchy(),
    "budget_net_invariants": _one_pass_state("budget"),
    "incremental_net_invariants": _one_pass_state("guaranteed"),
    "distance_counters": _counters(),
    "budget_trace": _trace(customers(), 60, 100, False),
    "radius_doublings": _trace(customers(), 24, 10, True),
    "window_summaries": _windows(1),
    "sliding_window_summaries": _windows(2),
    "user_ranking_centers": _users(),
    "pages_by_host": _texts(HOSTS + hashed("owned", "page_id", "g", "html", 64), 64, 6, dict.fromkeys(range(6), 5), 24, 5),
    "conversations_by_role": _texts(ROLES + hashed("turns", "id", "g", "text", 64), 64, 3, dict.fromkeys(range(3), 5), 24, 5),
    "benchmark_coverage": _benchmark(),
    "text_hash_features": _features(),
    "set_metric_profile": _set_metrics(),
    "net_groups_by_assignment": _groups(),
    "distinct_rankings": _distinct(),
    "solution_overlap": _overlap(),
}
