"""DuckDB texts that compute the same results from the same tables, written apart from the plans."""

from __future__ import annotations

import math

from nodeflux.functions.rng import duck_u01
from nodeflux.sources.graphs import DUCK

A = 0.2


def graph(name: str) -> str:
    """CTEs nd(node, key, deg), e(src, dst, pos, src_deg, dst_deg), st(n, m, max_deg)."""
    unit = (
        "u AS MATERIALIZED (SELECT vec_id, list_transform(v, lambda x: x / sqrt(list_sum(list_transform(v, lambda y: y * y)))) AS v "
        "FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings)), "
        if name == "knn" else ""
    )
    return f"""{unit}raw AS MATERIALIZED ({DUCK[name]}),
bo AS MATERIALIZED (SELECT DISTINCT a, b FROM (SELECT a, b FROM raw UNION ALL SELECT b, a FROM raw) WHERE a <> b),
nd AS MATERIALIZED (SELECT row_number() OVER (ORDER BY a) - 1 AS node, a AS key, count(*) AS deg FROM bo GROUP BY a),
e AS MATERIALIZED (SELECT x.node AS src, y.node AS dst, row_number() OVER (PARTITION BY x.node ORDER BY y.node) AS pos, x.deg AS src_deg, y.deg AS dst_deg
  FROM bo JOIN nd x ON a = x.key JOIN nd y ON b = y.key),
st AS MATERIALIZED (SELECT count(*) AS n, sum(deg) // 2 AS m, max(deg) AS max_deg FROM nd)"""


def uniform(k: int, seed: int = 0) -> str:
    return f"""tg AS MATERIALIZED (SELECT row_number() OVER (ORDER BY u, t) - 1 AS qid, t FROM
 (SELECT node AS t, {duck_u01(str(seed), "'node'", "node")} AS u FROM nd ORDER BY u, t LIMIT {k}))"""


def by_degree(k: int, seed: int = 0) -> str:
    return f"""tg AS MATERIALIZED (SELECT row_number() OVER (ORDER BY u, t) - 1 AS qid, t FROM
 (SELECT src AS t, min({duck_u01(str(seed), "'edge'", "src", "dst")}) AS u FROM e GROUP BY src ORDER BY u, t LIMIT {k}))"""


STRATUM = "CASE WHEN deg >= 100 * a THEN 'huge' WHEN deg >= 10 * a THEN 'large' WHEN deg >= a THEN 'above' WHEN deg >= 0.1 * a THEN 'below' WHEN deg >= 0.01 * a THEN 'small' END"


def strata(k: int, seed: int = 0) -> str:
    return f"""SELECT row_number() OVER (ORDER BY u, t) - 1 AS qid, t, stratum FROM (
 SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY u, t) AS r FROM (
  SELECT node AS t, {duck_u01(str(seed), "'stratum'", "node")} AS u, {STRATUM} AS stratum
  FROM nd, (SELECT 2.0 * m / n AS a FROM st)) WHERE stratum IS NOT NULL) WHERE r <= {k}"""


def series(start: str, keys: str, decay: float, weights: list[float]) -> str:
    """sv(keys, node, value); start selects keys, node, r."""
    k = f"{keys}, " if keys else ""
    w = "CASE hop " + " ".join(f"WHEN {i} THEN {x!r}" for i, x in enumerate(weights)) + " END"
    return f"""rr AS (SELECT 0 AS hop, {k}node, r FROM ({start})
 UNION ALL SELECT hop + 1 AS hop, {k}dst AS node, sum({decay!r} * r / src_deg) AS r FROM rr JOIN e ON node = src WHERE hop < {len(weights) - 1} GROUP BY ALL),
sv AS (SELECT {k}node, sum(r * {w}) AS value FROM rr GROUP BY ALL)"""


ONE_HOT = "SELECT qid, t AS node, 1.0::DOUBLE AS r FROM tg"
UNIFORM_START = "SELECT node, 1.0::DOUBLE / n AS r FROM nd, st"


def query(graph_name: str, *ctes: str, final: str, targets: str | None = None) -> str:
    parts = [graph(graph_name)] + ([targets] if targets else []) + list(ctes)
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + final


def power(iterations: int, a: float = A) -> str:
    """pw(i, node, pi)."""
    return f"""pw AS (SELECT 0 AS i, node, 1.0::DOUBLE / n AS pi FROM nd, st
 UNION ALL SELECT i + 1 AS i, dst AS node, {1 - a!r} * sum(pi / src_deg) + {a!r} / any_value(n) AS pi FROM pw JOIN e ON node = src, st WHERE i < {iterations} GROUP BY ALL)"""


def push(theta: str, hops: int, seed: int = 0, reps: int = 1) -> str:
    """ph(hop, qid, rep, node, r, n_in, n_exact) and pe(qid, rep, t, pagerank, increments, exact_increments); theta is SQL over tg."""
    share = f"({1 - A!r} * r / src_deg)"
    coin = duck_u01(str(seed), "qid", "rep", "hop", "src", "dst")
    return f"""ph AS (SELECT 0 AS hop, qid, rep, t AS node, 1.0::DOUBLE AS r, 0::BIGINT AS n_in, 0::BIGINT AS n_exact, ({theta})::DOUBLE AS theta FROM tg, (SELECT unnest(range({reps})) AS rep)
 UNION ALL SELECT hop + 1 AS hop, qid, rep, dst AS node, sum(greatest({share}, theta)) AS r, count(*) AS n_in, sum(({share} >= theta)::BIGINT)::BIGINT AS n_exact, theta
 FROM ph JOIN e ON node = src WHERE hop < {hops} AND ({share} >= theta OR {coin} < {share} / theta) GROUP BY ALL),
pe AS (SELECT qid, rep, tg.t, sum({A!r} * d.deg * r / (n * f.deg)) AS pagerank, sum(n_in) AS increments, sum(n_exact) AS exact_increments, any_value(theta) AS theta
 FROM ph JOIN tg USING (qid) JOIN nd d ON d.node = tg.t JOIN nd f ON f.node = ph.node, st GROUP BY qid, rep, tg.t)"""


#: Hops up to the method's own cap at c = 0.1 and c = 0.5.
WHOLE, WHOLE_LOOSE = "(SELECT ceil(ln(0.1 * 0.2 / (2 * n)) / ln(0.8)) FROM st)", "(SELECT ceil(ln(0.5 * 0.2 / (2 * n)) / ln(0.8)) FROM st)"


def places(theta: str, hops: str, binomial: bool = False, seed: int = 0, reps: int = 1, a: float = A) -> str:
    """pe as of push, with draws, where light nodes choose list places by gaps or by number and places; theta is SQL over tg and nd."""
    share, front = f"{1 - a!r} * r / deg", "qid, rep, hop, node, deg, theta, r"
    u = duck_u01(str(seed), "hop", "qid", "rep", "node", "j")
    if binomial:
        law = f"exp(lgamma(deg + 1) - lgamma(j + 1) - lgamma(deg - j + 1) + j * ln({share} / theta) + (deg - j) * ln(1 - {share} / theta))"
        chosen = f"""SELECT {front}, j AS place FROM (SELECT *, sum((cdf < first)::INT) OVER (PARTITION BY qid, rep, node) AS k,
   row_number() OVER (PARTITION BY qid, rep, node ORDER BY j = 0, u, j) AS nth FROM (SELECT *, sum({law}) OVER (PARTITION BY qid, rep, node ORDER BY j) AS cdf,
   max(CASE WHEN j = 0 THEN u END) OVER (PARTITION BY qid, rep, node) AS first FROM (SELECT *, {u} AS u FROM (SELECT {front}, unnest(range(deg + 1)) AS j FROM ph WHERE {share} < theta AND hop < {hops})))) WHERE nth <= k"""
    else:
        gap = f"least(1 + floor(ln({u}) / ln(1 - {share} / theta)), deg + 1)"
        chosen = f"""SELECT {front}, place FROM (SELECT *, sum({gap}) OVER (PARTITION BY qid, rep, node ORDER BY j) AS place
   FROM (SELECT {front}, unnest(range(deg)) AS j FROM ph WHERE {share} < theta AND hop < {hops})) WHERE place <= deg"""
    return f"""ph AS (SELECT 0 AS hop, qid, rep, t AS node, deg, 1.0::DOUBLE AS r, 0::BIGINT AS n_in, 0::BIGINT AS n_exact, ({theta})::DOUBLE AS theta FROM tg JOIN nd ON node = t, st, (SELECT unnest(range({reps})) AS rep)
 UNION ALL SELECT hop + 1 AS hop, qid, rep, dst AS node, dst_deg AS deg, sum(greatest({share.replace("deg", "src_deg")}, theta)) AS r, count(*) AS n_in, sum(({share.replace("deg", "src_deg")} >= theta)::BIGINT)::BIGINT AS n_exact, theta FROM (
  SELECT {front}, pos AS place FROM ph JOIN e ON node = src WHERE {share} >= theta AND hop < {hops} UNION ALL {chosen}) x(qid, rep, hop, node, own_deg, theta, r, place)
 JOIN e ON src = node AND pos = place GROUP BY ALL),
pe AS (SELECT qid, rep, tg.t, sum({a!r} * d.deg * r / (n * ph.deg)) AS pagerank, sum(n_in) AS increments, sum(n_exact) AS exact_increments,
 sum(n_in - n_exact) + sum(({share.replace("deg", "ph.deg")} < theta AND hop < {hops})::INT) AS draws FROM ph JOIN tg USING (qid) JOIN nd d ON d.node = tg.t, st GROUP BY qid, rep, tg.t)"""


def reverse(eps: str, rounds: int) -> str:
    """rv(round, qid, node, p, r, touched, eps); eps is SQL over tg and st."""
    return f"""rv AS (SELECT 0 AS round, qid, t AS node, 0.0::DOUBLE AS p, 1.0::DOUBLE AS r, 0::BIGINT AS touched, ({eps})::DOUBLE AS eps FROM tg JOIN nd ON node = t, st
 UNION ALL SELECT round + 1 AS round, qid, to_node AS node, sum(dp) AS p, sum(dr) AS r, sum(dt)::BIGINT AS touched, eps FROM (
  SELECT round, qid, eps, unnest(list_concat(
    [{{'to_node': node, 'dp': p + CASE WHEN r >= eps THEN {A!r} * r ELSE 0 END, 'dr': CASE WHEN r >= eps THEN 0.0 ELSE r END, 'dt': touched}}],
    CASE WHEN r >= eps THEN list_transform(nb, lambda x: {{'to_node': x.dst, 'dp': 0.0::DOUBLE, 'dr': {1 - A!r} * r / x.dst_deg, 'dt': 1::BIGINT}}) ELSE [] END), recursive := true)
  FROM rv JOIN ad ON node = src WHERE round < {rounds}) GROUP BY ALL)"""


def explore(k: int, rounds: int, bound: int, seed: int = 0) -> str:
    """sx(round, qid, rep, node, p, r): k partial reverse explorations that expand nodes up to a degree by keyed coins."""
    coin = duck_u01(str(seed), "1000003 + round", "qid", "rep", "node")
    return f"""sx AS (SELECT 0 AS round, qid, rep, t AS node, 0.0::DOUBLE AS p, 1.0::DOUBLE AS r FROM tg, (SELECT unnest(range({k})) AS rep)
 UNION ALL SELECT round + 1 AS round, qid, rep, to_node AS node, sum(dp) AS p, sum(dr) AS r FROM (
  SELECT round, qid, rep, unnest(list_concat([{{'to_node': node, 'dp': p + CASE WHEN go THEN {A!r} * r ELSE 0 END, 'dr': CASE WHEN go THEN 0.0 ELSE r END}}],
    CASE WHEN go THEN list_transform(nb, lambda x: {{'to_node': x.dst, 'dp': 0.0::DOUBLE, 'dr': {1 - A!r} * r / x.dst_deg}}) ELSE [] END), recursive := true)
  FROM (SELECT *, r > 0 AND len(nb) <= {bound} AND (round = 0 OR {coin} < 0.5) AS go FROM sx JOIN ad ON node = src WHERE round < {rounds})) GROUP BY ALL)"""


ADJ = "ad AS MATERIALIZED (SELECT src, list({'dst': dst, 'dst_deg': dst_deg}) AS nb FROM e GROUP BY src)"


def randomized(theta: float, hops: int, edge: bool, seed: int = 0, reps: int = 1) -> str:
    """rz(hop, qid, rep, node, r)."""
    inc = f"({1 - A!r} * r / dst_deg)"
    coin = duck_u01(str(seed), "qid", "rep", "hop", "src", *(["dst"] if edge else []))
    return f"""rz AS (SELECT 0 AS hop, qid, rep, t AS node, 1.0::DOUBLE AS r, 0::BIGINT AS n_in FROM tg, (SELECT unnest(range({reps})) AS rep)
 UNION ALL SELECT hop + 1 AS hop, qid, rep, dst AS node, sum(greatest({inc}, {theta!r})) AS r, count(*) AS n_in
 FROM rz JOIN e ON node = src WHERE hop < {hops} AND ({inc} >= {theta!r} OR {inc} >= {coin} * {theta!r}) GROUP BY ALL)"""


def walks(n_walks: int, cap: int, seed: int = 0) -> str:
    """wk(step, wid, node, stop)."""
    start = duck_u01(str(seed), "-1", "wid")
    stop = f"{duck_u01(str(seed), 'step', 'wid', '0')} < {A!r}"
    place = f"least(floor({duck_u01(str(seed), 'w.step', 'w.wid', '1')} * nd.deg) + 1, nd.deg)"
    return f"""wk AS (SELECT *, {stop} AS stop FROM (SELECT 0 AS step, wid, least(floor({start} * n), n - 1)::BIGINT AS node FROM (SELECT unnest(range({n_walks})) AS wid), st)
 UNION ALL SELECT *, {stop} AS stop FROM (SELECT w.step + 1 AS step, w.wid, e.dst AS node FROM wk w JOIN nd ON nd.node = w.node JOIN e ON e.src = w.node AND e.pos = {place} WHERE NOT w.stop AND w.step < {cap}))"""


def hop_cap(n: str, c: float = 0.1, a: float = A) -> str:
    return f"ceil(ln({c!r} * {a!r} / (2 * {n})) / ln({1 - a!r}))"


def theta_auto(n: str, m: str, deg: str, c: float = 0.1, pf: float = 0.1, a: float = A) -> str:
    return f"({a!r} * {c * c!r} * {pf!r} / (4 * {hop_cap(n, c, a)}) * greatest(1.0 / {deg}, sqrt({2 * (1 - a)!r} / {m})))"


def poisson(h: float, hops: int) -> list[float]:
    return [math.exp(-h) * h**k / math.factorial(k) for k in range(hops + 1)]
