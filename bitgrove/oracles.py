"""SQL twins of the queries, for DuckDB over the same tables. They follow other plans: ids are tried one by one, node filters
are made per level from their own ranges, and descents are chains of plain selects."""

from __future__ import annotations

import math

from .functions import theory as T
from .functions.hashing import Spec, make_spec, sql_murmur3, sql_positions
from .sources.collections import kept_ranges
from .workloads import ACCURACY_TARGETS, DENSE, DEPTH, FAMILY_SPECS, FRACTIONS, GRID_ACCURACY, GRID_M, LAYOUTS, PART_DEPTH, PART_DRAWS, ROUNDS, SPARSE, SPEC, TAGS
from .workloads import NATIONS as NATION_SPEC

ORDERS = "SELECT max(o_orderkey) + 1 AS M FROM orders"
CUSTOMERS = "SELECT max(c_custkey) + 1 AS M FROM customer"


def suppliers() -> str:
    return "SELECT DISTINCT l_suppkey::VARCHAR AS set_id, l_orderkey AS x FROM lineitem"


def parts() -> str:
    return "SELECT DISTINCT l_partkey::VARCHAR AS set_id, l_orderkey AS x FROM lineitem"


SIZES = f"(SELECT DISTINCT n FROM (SELECT count(*) AS n FROM ({suppliers()}) GROUP BY set_id))"
FLAGS = "SELECT DISTINCT l_returnflag AS set_id, l_orderkey AS x FROM lineitem"
NATIONS = "SELECT DISTINCT c_nationkey::VARCHAR AS set_id, c_custkey AS x FROM customer"
RUNS = "SELECT DISTINCT j::VARCHAR AS set_id, s + d AS x FROM (SELECT j, r, ('0x' || substr(md5(j || ':' || r), 1, 8))::BIGINT % (M - 100) AS s FROM range(5) a(j), range(6) b(r), dom), range(100) c(d)"


def base(sets: str, spec: Spec = SPEC, domain: str = ORDERS, ids: str | None = None) -> str:
    """CTEs dom, sets, ids, idpos (x, i, pos), bits (set_id, pos), found (set_id, x)."""
    pos = ", ".join(sql_positions(spec))
    turns = ", ".join(map(str, range(spec.k)))
    return f"""WITH dom AS ({domain}), sets AS ({sets}), ids AS ({ids or "SELECT unnest(range(0, (SELECT M FROM dom)::BIGINT)) AS x"}),
    idpos AS MATERIALIZED (SELECT x, unnest([{turns}]) AS i, unnest([{pos}]) AS pos FROM ids),
    bits AS MATERIALIZED (SELECT DISTINCT set_id, unnest([{pos}]) AS pos FROM sets),
    found AS MATERIALIZED (SELECT set_id, x FROM idpos JOIN bits USING (pos) GROUP BY set_id, x HAVING count(DISTINCT i) = {spec.k})"""


def tree(spec: Spec, depth: int, cut: str = "(x << level) // M") -> str:
    """CTEs nodebits (level, idx, pos), node (level, idx, t1, occ)."""
    return f""", levels AS (SELECT unnest(range(0, {depth + 1})) AS level),
    nodebits AS MATERIALIZED (SELECT DISTINCT level, {cut} AS idx, pos FROM idpos, levels, dom),
    node AS MATERIALIZED (SELECT level, idx, t1, occ FROM (SELECT level, idx, count(*) AS t1 FROM nodebits GROUP BY level, idx) JOIN (SELECT level, {cut} AS idx, count(*) AS occ FROM ids, levels, dom GROUP BY ALL) USING (level, idx))"""


def live(spec: Spec, depth: int, weights: str = "floored", tau: float | None = None, start: int = 0) -> str:
    """CTEs cand and live (set_id, level, idx, weight, occ)."""
    m, c = spec.m, spec.k * math.log(1 - 1 / spec.m)
    below = f"({m}::DOUBLE * ({m} - t1 - t2 + common))"
    arg = f"(1 - ({m}::DOUBLE * common - t1 * t2::DOUBLE) / nullif({below}, 0))"
    bad = f"(t1 >= {m} OR t2 >= {m} OR {arg} IS NULL OR {arg} <= 0)"
    value = f"CASE WHEN {bad} THEN coalesce(n_hat, 1.0) * occ / M::DOUBLE ELSE ln({arg}) / ({c!r}) END"
    if weights == "prior":
        weight, keep = "coalesce(n_hat, 1.0) * occ / M::DOUBLE", "common >= 1"
    elif weights == "floored":
        weight, keep = f"greatest({value}, 0.5)", "common >= 1"
    else:
        weight, keep = f"greatest({value}, 0.0)", "common >= 1" + (f" AND ({bad} OR ({value}) >= {tau})" if tau is not None else "")
    chain = f", live{start} AS (SELECT * FROM cand WHERE level = {start} AND keep)"
    for at in range(start + 1, depth + 1):
        chain += f", seen{at} AS (SELECT c.* FROM cand c JOIN live{at - 1} p ON c.set_id = p.set_id AND c.level = {at} AND c.idx // 2 = p.idx), live{at} AS (SELECT * FROM seen{at} WHERE keep)"
    return f""", filt AS (SELECT set_id, count(*) AS t2, CASE WHEN count(*) < {m} THEN ln(({m} - count(*)) / {m}::DOUBLE) / ({c!r}) END AS n_hat FROM bits GROUP BY set_id),
    shared AS (SELECT set_id, level, idx, count(*) AS common FROM bits JOIN nodebits USING (pos) GROUP BY ALL),
    pre AS (SELECT f.set_id, n.level, n.idx, n.occ, t1, t2, n_hat, coalesce(common, 0) AS common, M FROM filt f CROSS JOIN node n LEFT JOIN shared s ON s.set_id = f.set_id AND s.level = n.level AND s.idx = n.idx, dom),
    cand AS MATERIALIZED (SELECT set_id, level, idx, occ, {weight} AS weight, {keep} AS keep FROM pre){chain},
    live AS MATERIALIZED ({" UNION ALL ".join(f"SELECT * FROM live{at}" for at in range(start, depth + 1))})"""


def sweep_ops(sets: str, spec: Spec, depth: int, start: int, method: str = "") -> str:
    seen = " UNION ALL ".join([f"SELECT set_id, level, occ, keep FROM cand WHERE level = {start}", *(f"SELECT set_id, level, occ, keep FROM seen{at}" for at in range(start + 1, depth + 1))])
    return f"SELECT set_id, {method}count(*) FILTER (level > {start}) AS intersections, coalesce(sum(occ) FILTER (level = {depth} AND keep), 0)::BIGINT AS memberships, count(*) FILTER (keep) AS nodes_visited, count(*) FILTER (level = {depth} AND keep) AS leaves_probed FROM ({seen}) GROUP BY set_id"


def drawn(spec: Spec, depth: int, draws: int | str, weights: str, seed: int = 1) -> str:
    """draws: a number, or an expression over n, the size of a set. CTEs reach (positives, ands, probes of live nodes) and path{depth}, then samples (set_id, draw, x, intersections, memberships)."""
    w = "positives" if weights == "exact" else "weight"
    out = f""", atleaf AS MATERIALIZED (SELECT l.set_id, l.idx, f.x FROM live{depth} l JOIN (SELECT set_id, x, (x << {depth}) // M AS idx FROM found, dom) f ON f.set_id = l.set_id AND f.idx = l.idx),
    hits AS (SELECT l.set_id, l.level, l.idx, count(*) AS positives FROM live l JOIN atleaf f ON f.set_id = l.set_id AND (f.idx >> ({depth} - l.level)) = l.idx GROUP BY ALL),
    cost AS (SELECT a.set_id, a.level, a.idx, 2 * count(*) FILTER (b.level < {depth}) AS ands, coalesce(sum(b.occ) FILTER (b.level = {depth}), 0)::BIGINT AS probes FROM live a JOIN live b ON a.set_id = b.set_id AND b.level >= a.level AND (b.idx >> (b.level - a.level)) = a.idx GROUP BY ALL),
    reach AS MATERIALIZED (SELECT l.set_id, l.level, l.idx, l.weight, coalesce(h.positives, 0) AS positives, c.ands, c.probes FROM live l JOIN cost c USING (set_id, level, idx) LEFT JOIN hits h USING (set_id, level, idx)),
    path0 AS (SELECT f.set_id, draw, CASE WHEN positives > 0 THEN 0::BIGINT END AS idx, CASE WHEN coalesce(positives, 0) > 0 THEN 0 ELSE coalesce(ands, 0) END AS ands, CASE WHEN coalesce(positives, 0) > 0 THEN 0 ELSE coalesce(probes, 0) END AS probes FROM (SELECT set_id, unnest(range(0, ({draws})::BIGINT)) AS draw FROM filt JOIN (SELECT set_id, count(*) AS n FROM sets GROUP BY set_id) USING (set_id)) f LEFT JOIN reach r ON r.set_id = f.set_id AND r.level = 0)"""
    for at in range(depth):
        coin = f"('0x' || substr(md5(concat_ws(':', '{seed}', p.set_id, draw, '{at}', p.idx)), 1, 8))::BIGINT / 4294967296::DOUBLE"
        share = f"CASE WHEN l.weight IS NOT NULL AND r.weight IS NULL THEN 1.0 WHEN l.weight IS NULL THEN 0.0 WHEN coalesce(l.{w}, 0) + coalesce(r.{w}, 0) > 0 THEN coalesce(l.{w}, 0)::DOUBLE / (coalesce(l.{w}, 0) + coalesce(r.{w}, 0)) ELSE 0.5 END"
        out += f""", step{at} AS (SELECT p.set_id, draw, p.idx, p.ands, p.probes, {coin} < {share} AS raw, coalesce(l.positives, 0) > 0 AS lp, coalesce(r.positives, 0) > 0 AS rp, coalesce(l.ands, 0) AS la, coalesce(r.ands, 0) AS ra, coalesce(l.probes, 0) AS lm, coalesce(r.probes, 0) AS rm
      FROM path{at} p LEFT JOIN reach l ON l.set_id = p.set_id AND l.level = {at + 1} AND l.idx = 2 * p.idx LEFT JOIN reach r ON r.set_id = p.set_id AND r.level = {at + 1} AND r.idx = 2 * p.idx + 1),
    path{at + 1} AS (SELECT set_id, draw, CASE WHEN idx IS NOT NULL THEN 2 * idx + CASE WHEN (raw AND lp) OR (NOT raw AND NOT rp) THEN 0 ELSE 1 END END AS idx,
      ands + CASE WHEN idx IS NULL THEN 0 ELSE 2 + CASE WHEN raw AND NOT lp THEN la WHEN NOT raw AND NOT rp THEN ra ELSE 0 END END AS ands,
      probes + CASE WHEN idx IS NULL THEN 0 WHEN raw AND NOT lp THEN lm WHEN NOT raw AND NOT rp THEN rm ELSE 0 END AS probes FROM step{at})"""
    pick = f"('0x' || substr(md5(concat_ws(':', '{seed}', 'pick', p.set_id, draw)), 1, 8))::BIGINT / 4294967296::DOUBLE"
    return out + f""", ranked AS (SELECT *, row_number() OVER (PARTITION BY set_id, idx ORDER BY md5(concat_ws(':', '{seed}', 'leaf', set_id, x)), x) AS rank FROM atleaf),
    samples AS (SELECT p.set_id, draw, f.x, p.ands::BIGINT AS intersections, (p.probes + coalesce(o.probes, 0))::BIGINT AS memberships
      FROM path{depth} p LEFT JOIN reach o ON o.set_id = p.set_id AND o.level = {depth} AND o.idx = p.idx LEFT JOIN ranked f ON f.set_id = p.set_id AND f.idx = p.idx AND f.rank = floor({pick} * o.positives)::BIGINT + 1)"""


def _coin(seed: int, parts: str) -> str:
    return f"('0x' || substr(md5(concat_ws(':', '{seed}', {parts})), 1, 8))::BIGINT / 4294967296::DOUBLE"


def _placed(rows: str, value: str, what: str, draws: int = 5, seed: int = 2) -> str:
    """CTE chosen (set_id, draw, value): draws by the rank that a coin names."""
    return f""", placed AS (SELECT set_id, {value}, row_number() OVER (PARTITION BY set_id ORDER BY md5(concat_ws(':', '{seed}', '{what}', set_id, {value})), {value}) AS rank FROM {rows}),
    chosen AS (SELECT t.set_id, t.draw, p.{value} FROM (SELECT set_id, draw, floor({_coin(seed, f"'{what}', set_id, draw")} * n)::BIGINT + 1 AS rank FROM (SELECT set_id, count(*) AS n FROM placed GROUP BY set_id), range({draws}) d(draw)) t JOIN placed p ON p.set_id = t.set_id AND p.rank = t.rank)"""


def sampling(sets: str, draws: int | str, weights: str = "floored", tau: float | None = None, spec: Spec = SPEC, depth: int = DEPTH, domain: str = ORDERS, ids: str | None = None) -> str:
    return base(sets, spec, domain, ids) + tree(spec, depth) + live(spec, depth, weights if weights in ("paper", "prior") else "floored", tau) + drawn(spec, depth, draws, weights)


def _nation_draws(weights: str) -> str:
    """ROUNDS draws per customer of a nation; only the printed weights leave out nodes by estimate, with the threshold unset."""
    return sampling(NATIONS, f"{ROUNDS} * n", weights, None, NATION_SPEC, DEPTH, CUSTOMERS)


def values(names: str, rows) -> str:
    return f"(VALUES {', '.join('(' + ', '.join(f'{v!r}::DOUBLE' if isinstance(v, float) else repr(v) for v in r) + ')' for r in rows)}) v({names})"


def chi(samples: str, members: str) -> str:
    return f"""SELECT set_id, n, draws, round(q, 6) AS q, df, round(CASE WHEN df > 0 THEN 1 / (1 + exp(1.5976::DOUBLE * z + 0.07056::DOUBLE * z * z * z)) END, 6) AS p_value FROM (
      SELECT *, n - 1 AS df, (pow(q / nullif(n - 1, 0), 1.0::DOUBLE / 3) - (1 - 2.0::DOUBLE / (9 * (n - 1)))) / sqrt(2.0::DOUBLE / (9 * (n - 1))) AS z FROM (
      SELECT set_id, count(*) AS n, sum(o)::BIGINT AS draws, CASE WHEN sum(o) > 0 THEN sum(o * o)::BIGINT / (sum(o)::BIGINT::DOUBLE / count(*)) - sum(o)::BIGINT END AS q FROM (
      SELECT m.set_id, m.x, count(s.x) AS o FROM {members} m LEFT JOIN {samples} s ON s.set_id = m.set_id AND s.x = m.x GROUP BY ALL) GROUP BY set_id))"""


DIGEST = "SELECT set_id, count(*) AS n, sum(x)::BIGINT AS sum_x FROM found GROUP BY set_id"
RECOVERY = "SELECT set_id, count(t) AS n_true, count(f) AS n_found, count(*) FILTER (t AND f) AS n_both FROM (SELECT *, true AS t FROM sets) FULL JOIN (SELECT *, true AS f FROM found) USING (set_id, x) GROUP BY set_id"
NODES = "SELECT level, idx, occ AS occupied, t1 AS ones FROM node"
PAIRED = "SELECT DISTINCT (set_id::INT // 2)::VARCHAR AS set_id, pos FROM bits"
PREIMAGE = "SELECT set_id, count(*) AS listed, count(DISTINCT x) AS memberships FROM idpos JOIN bits USING (pos) GROUP BY set_id"
CUST_ROWS = "SELECT c_custkey AS x FROM customer"


def _positions(family: str) -> str:
    spec = FAMILY_SPECS[family]
    source = sql_murmur3(CUST_ROWS) if family == "murmur3" else CUST_ROWS
    return f"SELECT x, unnest([0, 1, 2])::INT AS i, unnest([{', '.join(sql_positions(spec))}])::BIGINT AS pos FROM ({source})"


def _size(n: str, d: str, a: str, k: str = "3") -> str:
    fp = f"({n} * (1 - {a}) / ({a} * ({d} - {n})))"
    return f"{k} * {n} / -ln(1 - pow({fp}, 1.0::DOUBLE / {k}))"


def _hash_family() -> str:
    out = []
    for family, spec in FAMILY_SPECS.items():
        murmur = family == "murmur3"
        src = lambda q: f"({sql_murmur3(q)})" if murmur else f"({q})"  # noqa: B023, E731
        pos = ", ".join(sql_positions(spec))
        ids = src("SELECT unnest(range(0, (SELECT max(o_orderkey) + 1 FROM orders)::BIGINT)) AS x")
        out.append(f"SELECT '{family}' AS family, set_id, count(*) AS n FROM (SELECT set_id, x FROM (SELECT x, unnest([0, 1, 2]) AS i, unnest([{pos}]) AS pos FROM {ids}) JOIN (SELECT DISTINCT set_id, unnest([{pos}]) AS pos FROM {src(suppliers())}) USING (pos) GROUP BY ALL HAVING count(DISTINCT i) = 3) GROUP BY set_id")
    return " UNION ALL ".join(out)


def _path_probability() -> str:
    head = base(suppliers()) + tree(SPEC, DEPTH)
    out = []
    for weights, tau in (("paper", 0.0), ("floored", None), ("exact", None)):
        w = "positives::DOUBLE" if weights == "exact" else "weight"
        chain = "c0 AS (SELECT set_id, idx, 1.0::DOUBLE AS p FROM ok WHERE level = 0)"
        for at in range(1, DEPTH + 1):
            chain += f", c{at} AS (SELECT a.set_id, a.idx, u.p * CASE WHEN sum({w}) OVER s > 0 THEN {w} / sum({w}) OVER s ELSE 1.0::DOUBLE / count(*) OVER s END AS p FROM ok a JOIN c{at - 1} u ON u.set_id = a.set_id AND a.idx // 2 = u.idx WHERE a.level = {at} WINDOW s AS (PARTITION BY a.set_id, a.idx // 2))"
        one = head + live(SPEC, DEPTH, "paper" if weights == "paper" else "floored", tau) + drawn(SPEC, 0, 1, weights).split(", path0")[0].replace("live0 l JOIN (SELECT set_id, x, (x << 0)", f"live{DEPTH} l JOIN (SELECT set_id, x, (x << {DEPTH})").replace("f.idx >> (0 - l.level)", f"f.idx >> ({DEPTH} - l.level)").replace("b.level < 0", f"b.level < {DEPTH}").replace("b.level = 0", f"b.level = {DEPTH}")
        one += f", ok AS (SELECT * FROM reach WHERE positives > 0), {chain}, pr AS (SELECT f.set_id, f.x, c.p / count(*) OVER (PARTITION BY f.set_id, f.idx) AS p FROM atleaf f JOIN c{DEPTH} c USING (set_id, idx))"
        out.append(f"(SELECT '{weights}' AS weights, set_id, any_value(n) AS n, count(*) FILTER (p > 0) AS reachable, round(sum(abs(p - u)) / 2, 6) AS total_variation, round(max(p / u), 6) AS max_ratio FROM ({one} SELECT set_id, coalesce(p, 0.0::DOUBLE) AS p, count(*) OVER (PARTITION BY set_id) AS n, 1.0::DOUBLE / count(*) OVER (PARTITION BY set_id) AS u FROM found LEFT JOIN pr USING (set_id, x)) GROUP BY set_id)")
    return " UNION ALL ".join(out)


def _sparse(x: str) -> str:
    return f"(({x} * 48271 + 11) % 2147483647)"


def _kept(fraction: float, layout: str) -> str:
    return f"((x << 8) // 2147483647) IN ({', '.join(map(str, kept_ranges(fraction, layout)))})"


SPARSE_SETS = f"SELECT set_id, {_sparse('x')} AS x FROM ({suppliers()})"
SPARSE_IDS = f"SELECT {_sparse('o_orderkey')} AS x FROM orders"
SPARSE_DOM = "SELECT 2147483647::BIGINT AS M"


def _fraction(inner, layouts=LAYOUTS, fractions=FRACTIONS) -> str:
    return " UNION ALL ".join(f"(SELECT '{lay}' AS layout, {f}::DOUBLE AS fraction, q.* FROM ({base(f'SELECT * FROM ({SPARSE_SETS}) WHERE {_kept(f, lay)}', SPARSE, SPARSE_DOM, f'SELECT * FROM ({SPARSE_IDS}) WHERE {_kept(f, lay)}')}{inner}) q)" for lay in layouts for f in fractions)


TOKENS = "SELECT DISTINCT t AS set_id, doc_id AS x FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS t FROM documents) WHERE t <> ''"
TAG_SETS = f"SELECT set_id, x FROM ({TOKENS}) QUALIFY count(*) OVER (PARTITION BY set_id) >= 0.05 * (SELECT count(*) FROM documents)"
USERS = "SELECT DISTINCT event_type || '/' || strftime(ts, '%Y-%m-%d') AS set_id, user_id AS x FROM events WHERE user_id IS NOT NULL"
LEFT = "SELECT c_custkey AS x FROM customer, (SELECT max(c_custkey) + 1 AS d FROM customer) WHERE c_custkey < d // 4 OR c_custkey >= d // 2 OR c_custkey % 2 = 0"


def _pow2() -> str:
    return base("SELECT 'a' AS set_id, 0::BIGINT AS x") + tree(SPEC, DEPTH, "(x >> greatest(0, (length(bin((M - 1)::BIGINT)) - level))::INT)")


def _measured() -> str:
    out = []
    for target in ACCURACY_TARGETS:
        spec = make_spec(round(T.size_for(600, 15_000, target)), domain=150_000)
        out.append(f"(SELECT {target}::DOUBLE AS target, {spec.m}::BIGINT AS m, round(avg(n / p::DOUBLE), 6) AS accuracy FROM ({base(suppliers(), spec)} SELECT s.set_id, s.n, f.p FROM (SELECT set_id, count(*) AS n FROM sets GROUP BY ALL) s JOIN (SELECT set_id, count(*) AS p FROM found GROUP BY ALL) f USING (set_id)))")
    return " UNION ALL ".join(out)


def _theory() -> str:
    m = _size("n", "domain", "0.9::DOUBLE")
    eps = "sqrt(2.0::DOUBLE * n * 3 * (ln(m) + ln(ln(m)) + ln(n))) / m"
    return f"""SELECT domain, n, round(m, 4) AS m, round({eps}, 4) AS epsilon, round(2 * {eps} * 9, 4) AS f, round(2.0::DOUBLE / n * pow(0.98::DOUBLE, 9), 4) AS low, round(2.0::DOUBLE / n * pow(1.04::DOUBLE, 9), 4) AS high,
    round(log2(domain / 1000::DOUBLE) + domain::DOUBLE * 9 * n / m, 4) AS nodes, round(n * (log2(domain / 1000::DOUBLE) + 9000::DOUBLE / m), 4) AS nodes_recover, round(m * ln(2) / (9 * n), 4) AS critical_leaf, round(log2(domain::DOUBLE * 9 * n / (m * ln(2))), 4) AS critical_depth,
    round(2 * exp(-(0.0001::DOUBLE * m * m) / (6 * n)), 4) AS zero_tail, round(m + 3::DOUBLE * domain / m, 4) AS preimage_cost, round(0.3::DOUBLE / 0.4, 4) AS branch, round(0.6 + 0.6 * 1.2 + 0.6 * 1.44 + 0.6 * 1.728 + 0.6 * 2.0736::DOUBLE, 4) AS finite_branch, round(pow(1 - exp(-3.0::DOUBLE * n / m), 3), 4) AS fp, round(exp(9 * 10 * 20 * ln(1 - 1 / m)), 4) AS and_exact
    FROM (SELECT *, {m} AS m FROM (SELECT d::BIGINT AS domain, n::BIGINT AS n FROM {values('d', [(d,) for d in GRID_M])}, {SIZES} z))"""


def _params() -> str:
    fp = "(n * (1 - accuracy) / (accuracy * (domain - n)))"
    m = f"CASE WHEN n < domain THEN CASE WHEN pow({fp}, 1.0::DOUBLE / 3) < 1 THEN {_size('n', 'domain', 'accuracy')} END END"
    deep = "(SELECT min(i) FROM range(0, 64) r(i) WHERE domain / pow(2.0::DOUBLE, i) <= 2 OR (domain / pow(2.0::DOUBLE, i)) / log2(domain / pow(2.0::DOUBLE, i)) <= ratio)"
    domains = f"(SELECT d::BIGINT AS domain FROM {values('d', [(d,) for d in GRID_M])} UNION SELECT coalesce(max(o_orderkey), 0) + 1 FROM orders) v"
    return f"""SELECT domain, n, accuracy, ratio, round(m)::BIGINT AS m, depth, round(domain / pow(2.0::DOUBLE, depth), 3) AS leaf, round((pow(2.0::DOUBLE, depth + 1) - 1) * m / 8 / 1048576, 3) AS mb, round(greatest(0, pow(2.0::DOUBLE, depth) - 2) * m / 8 / 1048576, 3) AS mb_tabulated, round(m * ln(2) / (9 * n), 3) AS critical_leaf
    FROM (SELECT *, {m} AS m, {deep} AS depth FROM (SELECT domain, n, a AS accuracy, q AS ratio FROM {SIZES} z, {domains}, {values('a', [(a,) for a in GRID_ACCURACY]).replace(' v(', ' w(')}, {values('q', [(120.0,), (1500.0,)]).replace(' v(', ' y(')}))"""


def _start_level() -> str:
    """The sweep from each of the upper levels; the one that counts is the first that is not nearly full."""
    full = " + ".join(f"(1 - pow(1 - 1.0::DOUBLE / {SPEC.m}, {SPEC.k} * M / {2**at}::DOUBLE) > 0.95)::INT" for at in range(DEPTH))
    each = (f"(SELECT q.* FROM ({base(suppliers())}{tree(SPEC, DEPTH)}{live(SPEC, DEPTH, start=at)} {sweep_ops('', SPEC, DEPTH, at)}) q, ({ORDERS}) o WHERE {full} = {at})" for at in range(4))
    return " UNION ALL ".join(each)


def _printed(sets: str, draws: int) -> str:
    """As sampling, with what the printed control flow pays for dead siblings of live nodes."""
    seen = " UNION ALL ".join(f"SELECT set_id, level, idx, occ, keep FROM seen{at}" for at in range(1, DEPTH + 1))
    extra = f"""dead AS (SELECT set_id, level - 1 AS level, idx // 2 AS idx, CASE WHEN level = {DEPTH} THEN 0 ELSE 2 END AS more_ands, CASE WHEN level = {DEPTH} THEN sum(occ) FILTER (NOT keep) ELSE 0 END AS more_probes FROM ({seen}) GROUP BY set_id, level, idx // 2 HAVING count(*) FILTER (keep) = 1 AND count(*) FILTER (NOT keep) = 1),
    cost AS (SELECT a.set_id, a.level, a.idx, 2 * count(*) FILTER (b.level < {DEPTH}) + coalesce(sum(more_ands), 0)::BIGINT AS ands, (coalesce(sum(b.occ) FILTER (b.level = {DEPTH}), 0) + coalesce(sum(more_probes), 0))::BIGINT AS probes FROM live a JOIN live b ON a.set_id = b.set_id AND b.level >= a.level AND (b.idx >> (b.level - a.level)) = a.idx LEFT JOIN dead d ON d.set_id = b.set_id AND d.level = b.level AND d.idx = b.idx GROUP BY a.set_id, a.level, a.idx),"""
    whole = sampling(sets, draws, "paper", 0.0)
    at, to = whole.index("cost AS ("), whole.index("reach AS MATERIALIZED")
    return whole[:at] + extra + whole[to:] + " SELECT * FROM samples"


def _noreplace(sets: str, draws: int, seed: int = 1) -> str:
    """Draws take the ids of their leaf in the order of a digest; those that find none left take unused ids of the set."""
    head = sampling(sets, draws).rsplit(", samples AS", 1)[0]
    return head + f""", turn AS (SELECT *, row_number() OVER (PARTITION BY set_id, idx ORDER BY draw) AS rank FROM path{DEPTH}),
    first AS (SELECT p.set_id, p.draw, f.x, p.ands::BIGINT AS intersections, (p.probes + coalesce(o.probes, 0))::BIGINT AS memberships FROM turn p LEFT JOIN reach o ON o.set_id = p.set_id AND o.level = {DEPTH} AND o.idx = p.idx LEFT JOIN ranked f ON f.set_id = p.set_id AND f.idx = p.idx AND f.rank = p.rank),
    spare AS (SELECT a.set_id, a.x, row_number() OVER (PARTITION BY a.set_id ORDER BY md5(concat_ws(':', '{seed}', 'spare', a.set_id, a.x)), a.x) AS rank FROM atleaf a WHERE NOT EXISTS (SELECT 1 FROM first f WHERE f.set_id = a.set_id AND f.x = a.x)),
    short AS (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY draw) AS rank FROM first WHERE x IS NULL)
    SELECT * FROM first WHERE x IS NOT NULL UNION ALL SELECT s.set_id, s.draw, p.x, s.intersections, s.memberships FROM short s LEFT JOIN spare p ON p.set_id = s.set_id AND p.rank = s.rank"""


def _rejection(sets: str, draws: int, seed: int) -> str:
    """Draws with the floored weights, thinned by the exact chance of what they hit."""
    chain = "c0 AS (SELECT set_id, idx, 1.0::DOUBLE AS p FROM reach WHERE level = 0 AND positives > 0)"
    for at in range(1, DEPTH + 1):
        chain += f", c{at} AS (SELECT a.set_id, a.idx, u.p * CASE WHEN sum(weight) OVER s > 0 THEN weight / sum(weight) OVER s ELSE 1.0::DOUBLE / count(*) OVER s END AS p FROM reach a JOIN c{at - 1} u ON u.set_id = a.set_id AND a.idx // 2 = u.idx WHERE a.level = {at} AND a.positives > 0 WINDOW s AS (PARTITION BY a.set_id, a.idx // 2))"
    head = base(sets) + tree(SPEC, DEPTH) + live(SPEC, DEPTH) + drawn(SPEC, DEPTH, draws, "floored", seed)
    return head + f""", {chain}, pr AS (SELECT f.set_id, f.x, c.p / count(*) OVER (PARTITION BY f.set_id, f.idx) AS p FROM atleaf f JOIN c{DEPTH} c USING (set_id, idx)),
    low AS (SELECT set_id, min(p) AS least FROM pr GROUP BY set_id)
    SELECT s.set_id, s.draw::INT AS draw, s.x FROM samples s JOIN pr ON pr.set_id = s.set_id AND pr.x = s.x JOIN low ON low.set_id = s.set_id WHERE {_coin(seed, "s.set_id, s.draw, 'keep'")} < least / p"""


ORACLES = {
    "q_positions_affine": _positions("affine_mod_p"),
    "q_positions_affine_mod_m": _positions("affine_mod_m"),
    "q_positions_murmur3": _positions("murmur3"),
    "q_positions_md5": _positions("md5"),
    "q_filter_ones": base(suppliers()) + " SELECT set_id, count(*) AS ones FROM bits GROUP BY set_id",
    "q_filter_words": base(suppliers()) + " SELECT set_id, pos FROM bits",
    "q_membership": base(suppliers()) + " " + DIGEST,
    "q_union": base(suppliers()) + f" SELECT set_id, count(*) AS ones FROM ({PAIRED}) GROUP BY set_id",
    "q_intersection_ones": base(suppliers()) + " SELECT (a.set_id::INT // 2)::VARCHAR AS set_id, count(*) AS ones FROM bits a JOIN bits b ON a.pos = b.pos AND a.set_id::INT % 2 = 0 AND b.set_id::INT = a.set_id::INT + 1 GROUP BY ALL",
    "q_size_estimate": base(suppliers()) + f" SELECT set_id, n, ones, round(CASE WHEN ones < {SPEC.m} THEN ln(({SPEC.m}::DOUBLE - ones) / {SPEC.m}) / ({SPEC.k * math.log(1 - 1 / SPEC.m)!r}) END, 6) AS n_hat FROM (SELECT set_id, count(*) AS n FROM sets GROUP BY ALL) JOIN (SELECT set_id, count(*) AS ones FROM bits GROUP BY ALL) USING (set_id)",
    "q_overlap_estimate": base(FLAGS, DENSE) + f", t AS (SELECT set_id, count(*) AS n FROM bits GROUP BY ALL), j AS (SELECT a.set_id AS left_id, b.set_id AS right_id, count(*) AS c FROM bits a JOIN bits b ON a.pos = b.pos AND a.set_id < b.set_id GROUP BY ALL), e AS (SELECT left_id, right_id, x.n AS t1, y.n AS t2, c AS common, 1 - ({DENSE.m}::DOUBLE * c - x.n * y.n::DOUBLE) / nullif({DENSE.m}::DOUBLE * ({DENSE.m} - x.n - y.n + c), 0) AS arg FROM j JOIN t x ON x.set_id = left_id JOIN t y ON y.set_id = right_id) SELECT left_id, right_id, t1, t2, common, CASE WHEN t1 >= {DENSE.m} OR t2 >= {DENSE.m} THEN 'saturated' WHEN arg IS NULL OR arg <= 0 THEN 'undefined' WHEN arg > 1 THEN 'negative' ELSE 'ok' END AS status, round(CASE WHEN t1 < {DENSE.m} AND t2 < {DENSE.m} AND arg > 0 THEN ln(arg) / ({DENSE.k * math.log(1 - 1 / DENSE.m)!r}) END, 6) AS estimate FROM e",
    "q_fp_observed_vs_formula": base(suppliers()) + f" SELECT set_id, n, positives, round((positives - n) / (M - n)::DOUBLE, 6) AS observed, round(pow(1 - exp(-3.0::DOUBLE * n / {SPEC.m}), 3), 6) AS formula FROM (SELECT set_id, count(*) AS n FROM sets GROUP BY ALL) JOIN (SELECT set_id, count(*) AS positives FROM found GROUP BY ALL) USING (set_id), dom",
    "q_false_overlap": f"SELECT n AS n1, n2::BIGINT AS n2, m::BIGINT AS m, round(1 - exp(9 * n * n2 * ln(1 - 1.0::DOUBLE / m)), 6) AS p FROM {SIZES} z, {values('n2, m', [(b, m) for b in (1, 10, 100) for m in (1000, 60869)])}",
    "q_sizing": f"SELECT domain::BIGINT AS domain, n, accuracy, round({_size('n', 'domain', 'accuracy')}, 3) AS m, round(n * (1 - accuracy) / (accuracy * (domain - n)), 9) AS fp, round(n / (n + (domain - n) * (n * (1 - accuracy) / (accuracy * (domain - n)))), 6) AS back FROM {SIZES} z, {values('domain, accuracy', [(d, a) for d in GRID_M for a in GRID_ACCURACY])}",
    "q_leaf_choice": f"SELECT domain, ratio, depth, round(domain / pow(2.0::DOUBLE, depth), 6) AS leaf FROM (SELECT *, (SELECT min(i) FROM range(0, 40) r(i) WHERE domain / pow(2.0::DOUBLE, i) <= 2 OR (domain / pow(2.0::DOUBLE, i)) / log2(domain / pow(2.0::DOUBLE, i)) <= ratio) AS depth FROM (SELECT DISTINCT max(x) - min(x) + 1 AS domain FROM ({suppliers()}) GROUP BY set_id) z, {values('ratio', [(float(r),) for r in (60, 120, 250, 1500)])})",
    "q_tree_complete_ones": base("SELECT 'a' AS set_id, 0::BIGINT AS x") + tree(SPEC, DEPTH) + " " + NODES,
    "q_tree_pow2": _pow2() + " " + NODES,
    "q_tree_one_pass": base("SELECT 'a' AS set_id, 0::BIGINT AS x") + tree(SPEC, 4) + " SELECT level, idx, t1 AS ones FROM node",
    "q_tree_occupied_nodes": base("SELECT 'a' AS set_id, 0::BIGINT AS x", SPARSE, SPARSE_DOM, f"SELECT {_sparse('c_custkey')} AS x FROM customer") + tree(SPARSE, 12) + " SELECT level, count(*) AS n_nodes, sum(occ)::BIGINT AS occupied, sum(t1)::BIGINT AS ones FROM node GROUP BY level",
    "q_tree_growth": base("SELECT 'a' AS set_id, 0::BIGINT AS x", SPEC, CUSTOMERS, CUST_ROWS) + tree(SPEC, DEPTH) + " " + NODES,
    "q_tree_rebuild": base("SELECT 'a' AS set_id, 0::BIGINT AS x", SPEC, CUSTOMERS, LEFT) + tree(SPEC, DEPTH) + " " + NODES,
    "q_tree_truncated": base(suppliers()) + tree(SPEC, 2) + live(SPEC, 2, start=1) + " " + sweep_ops("", SPEC, 2, 1),
    "q_tree_memory": base("SELECT 'a' AS set_id, 0::BIGINT AS x") + tree(SPEC, DEPTH) + f" SELECT level, n_nodes, n_nodes * {SPEC.words * 8} AS dense_bytes, word_rows FROM (SELECT level, count(*) AS n_nodes FROM node GROUP BY level) JOIN (SELECT level, count(*) AS word_rows FROM (SELECT DISTINCT level, idx, pos // 64 FROM nodebits) GROUP BY level) USING (level)",
    "q_sample_one": sampling(suppliers(), 1) + " SELECT * FROM samples",
    "q_sample_many_replace": sampling(suppliers(), 20) + " SELECT * FROM samples",
    "q_sample_paper": sampling(suppliers(), 10, "paper", 0.0) + " SELECT * FROM samples",
    "q_sample_exact": sampling(suppliers(), 20, "exact") + " SELECT * FROM samples",
    "q_sample_prior": sampling(suppliers(), 10, "prior") + " SELECT * FROM samples",
    "q_sample_printed": _printed(suppliers(), 10),
    "q_sample_ops": sampling(suppliers(), 20) + " SELECT set_id, count(*) AS draws, sum(intersections)::BIGINT AS intersections, sum(memberships)::BIGINT AS memberships FROM samples GROUP BY set_id",
    "q_path_probability": _path_probability(),
    "q_recover_safe": base(suppliers()) + " " + DIGEST,
    "q_recover_threshold": base(suppliers()) + tree(SPEC, DEPTH) + live(SPEC, DEPTH, "paper", 15.0) + f", kept AS (SELECT f.set_id, f.x FROM found f, dom, live{DEPTH} l WHERE l.set_id = f.set_id AND l.idx = (f.x << {DEPTH}) // M) " + RECOVERY.replace("FROM found", "FROM kept"),
    "q_recover_ops": base(parts()) + tree(SPEC, DEPTH) + live(SPEC, DEPTH, start=2) + " " + sweep_ops("", SPEC, DEPTH, 2),
    "q_probe_sample": base(suppliers()) + _placed("found", "x", "probe") + " SELECT set_id, draw, x FROM chosen",
    "q_probe_reservoir": base(suppliers()) + f", walked AS (SELECT set_id, x, row_number() OVER (PARTITION BY set_id ORDER BY x) AS j FROM found) SELECT set_id, arg_max(x, j) AS x FROM walked WHERE {_coin(2, "'reservoir', set_id, x")} * j < 1 GROUP BY set_id",
    "q_probe_recover": base(suppliers()) + " " + DIGEST,
    "q_preimage_sample": base(suppliers()) + _placed("bits", "pos", "bit") + ", fits AS (SELECT DISTINCT c.set_id, c.draw, f.x FROM chosen c JOIN idpos p USING (pos) JOIN found f ON f.set_id = c.set_id AND f.x = p.x) SELECT c.set_id, c.draw, c.pos, arg_min(f.x, md5(concat_ws(':', '2', 'pre', c.set_id, c.draw, f.x))) AS x FROM chosen c LEFT JOIN fits f ON f.set_id = c.set_id AND f.draw = c.draw GROUP BY ALL",
    **{f"q_preimage_{n}": base(suppliers()) + " " + DIGEST for n in ("set_bits", "first_function", "unset_bits", "auto")},
    "q_truth": f"SELECT set_id, count(*) AS n, sum(x)::BIGINT AS sum_x FROM ({suppliers()}) GROUP BY set_id",
    "q_precision_recall": base(suppliers()) + f" SELECT *, round(n_both / n_found::DOUBLE, 6) AS precision, round(n_both / n_true::DOUBLE, 6) AS recall FROM ({RECOVERY})",
    "q_chi_square": _nation_draws("exact") + " " + chi("samples", "sets"),
    "q_chi_square_floored": _nation_draws("floored") + " " + chi("samples", "sets"),
    "w_chi_square": " UNION ALL ".join(f"(SELECT '{w}' AS weights, q.* FROM ({_nation_draws(w)} {chi('samples', 'found')}) q)" for w in ("paper", "floored", "exact")),
    "q_accuracy": _nation_draws("exact") + " SELECT s.set_id, count(*) AS draws, round(avg(CASE WHEN t.x IS NULL THEN 0 ELSE 1 END), 6) AS accuracy FROM samples s LEFT JOIN sets t ON t.set_id = s.set_id AND t.x = s.x WHERE s.x IS NOT NULL GROUP BY s.set_id",
    "q_draw_histogram": _nation_draws("exact") + " SELECT set_id, (x * 10 // M + 1)::BIGINT AS bucket, count(*) AS draws FROM samples, dom WHERE x IS NOT NULL GROUP BY ALL",
    "q_theory": _theory(),
    "w_sample_uniform_ops": sampling(suppliers(), 20) + " SELECT set_id, round(avg(intersections), 6) AS tree_intersections, round(avg(memberships), 6) AS tree_memberships, 0::BIGINT AS probe_intersections, any_value(M)::BIGINT AS probe_memberships FROM samples, dom GROUP BY set_id",
    "w_sample_clustered_ops": sampling(RUNS, 20) + " SELECT set_id, round(avg(intersections), 6) AS intersections, round(avg(memberships), 6) AS memberships FROM samples GROUP BY set_id",
    "w_hash_family": _hash_family(),
    "w_params_table": _params(),
    "w_measured_accuracy": _measured(),
    "w_recover_ops": base(parts()) + tree(SPEC, DEPTH) + live(SPEC, DEPTH) + f" SELECT set_id, method, intersections, memberships FROM ({sweep_ops('', SPEC, DEPTH, 0, "'tree' AS method, ")}) UNION ALL SELECT set_id, 'probe', 0, M FROM filt, dom UNION ALL SELECT set_id, 'preimage', 0, memberships FROM ({PREIMAGE})",
    "w_preimage_density": base(f"{FLAGS} UNION ALL SELECT * FROM ({suppliers()}) UNION ALL SELECT 'p' || set_id, x FROM ({parts()})") + f" SELECT set_id, ones, CASE WHEN ones * 2 <= {SPEC.m} THEN 'set' ELSE 'unset' END AS side, listed, memberships FROM (SELECT set_id, count(*) AS ones FROM bits GROUP BY ALL) JOIN ({PREIMAGE}) USING (set_id)",
    "w_fraction_memory": _fraction(tree(SPARSE, PART_DEPTH) + " SELECT count(*) AS n_nodes, coalesce(sum(t1), 0)::BIGINT AS ones FROM node"),
    "w_fraction_accuracy": _fraction(f" SELECT set_id, n_true, n_found, round(n_both / nullif(n_found, 0)::DOUBLE, 6) AS precision FROM ({RECOVERY})"),
    "w_fraction_sample": _fraction(tree(SPARSE, PART_DEPTH) + live(SPARSE, PART_DEPTH) + drawn(SPARSE, PART_DEPTH, PART_DRAWS, "floored") + " SELECT count(*) AS draws, sum(intersections)::BIGINT AS intersections, sum(memberships)::BIGINT AS memberships FROM samples", fractions=(0.1, 0.5, 1.0)),
    "w_start_level": _start_level(),
    "q_sample_many_noreplace": _noreplace(suppliers(), 50),
    "q_sample_rejection": _rejection(suppliers(), 50, 3),
    "w_tag_filters": base(TAG_SETS, TAGS, "SELECT max(doc_id) + 1 AS M FROM documents") + f" SELECT set_id, n_true, n_found FROM ({RECOVERY})",
    "w_user_tags": base(USERS, TAGS, "SELECT max(user_id) + 1 AS M FROM events") + f" SELECT set_id, n_true, n_found FROM ({RECOVERY})",
    "w_adjacency": base(NATIONS, SPEC, CUSTOMERS) + " " + RECOVERY,
    "w_growth": base("SELECT 'a' AS set_id, 0::BIGINT AS x", TAGS, "SELECT max(user_id) + 1 AS M FROM events", "SELECT DISTINCT user_id AS x FROM events WHERE user_id IS NOT NULL") + tree(TAGS, 4) + " " + NODES,
    "w_sweep": f"SELECT d::BIGINT AS domain, n, k::BIGINT AS k, a AS accuracy, round({_size('n', 'd', 'a', 'k')}, 1) AS m, round(n * (1 - a) / (a * (d - n)), 9) AS fp FROM {SIZES} z, {values('d, k, a', [(d, k, a) for d in GRID_M for k in (1, 3, 5) for a in (0.5, 0.9)])}",
}
