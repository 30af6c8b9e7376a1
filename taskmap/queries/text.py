"""SQL of the same definitions, for checking against another engine: parts that the oracles share."""

from __future__ import annotations

from taskmap.operators.noise import NOISE_FACTORS, NOISE_MODULUS
from taskmap.topology import Topology

SYMMETRIC = "e AS (SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT a AS src, b AS dst, w FROM p WHERE a <> b UNION ALL SELECT b, a, w FROM p WHERE a <> b) GROUP BY src, dst)"


def parts(weights: str = "unit") -> str:
    return f"v AS (SELECT p_partkey AS id, CAST({'1' if weights == 'unit' else 'p_size'} AS BIGINT) AS c FROM part)"


def units(select: str) -> str:
    return f"v AS (SELECT id, CAST(1 AS BIGINT) AS c FROM ({select}))"


def together(members: str) -> str:
    """p from pairs of members(g, k) of one group."""
    return f"mem AS ({members}), p AS (SELECT x.k AS a, y.k AS b, CAST(1 AS BIGINT) AS w FROM mem x JOIN mem y ON x.g = y.g AND x.k < y.k)"


def graph(name: str, weights: str = "unit") -> str:
    """CTEs v(id, c) and e(src, dst, w)."""
    one = "CAST(1 AS BIGINT) AS w"
    if name == "copurchase":
        return f"{parts(weights)}, {together('SELECT DISTINCT l_orderkey AS g, l_partkey AS k FROM lineitem')}, {SYMMETRIC}"
    if name == "mesh":
        arms = [("id + 1", "id % wd < wd - 1"), ("id + wd", "TRUE"), ("id + wd + 1", "id % wd < wd - 1")]
        union = " UNION ALL ".join(f"SELECT id AS a, {b} AS b, {one} FROM v, wide WHERE {where}" for b, where in arms)
        return f"{parts(weights)}, wide AS (SELECT CAST(floor(sqrt(count(*))) AS BIGINT) AS wd FROM part), p AS (SELECT a, b, w FROM ({union}) WHERE b IN (SELECT id FROM v)), {SYMMETRIC}"
    if name == "line_adjacent":
        lead = "lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice)"
        return f"{parts()}, p AS (SELECT a, b, {one} FROM (SELECT l_partkey AS a, {lead} AS b FROM lineitem) WHERE b IS NOT NULL), {SYMMETRIC}"
    if name == "chain":
        turns = "SELECT DISTINCT conv_id * 16 + turn AS id, conv_id, turn FROM conversations"
        return f"t AS ({turns}), {units('SELECT id FROM t')}, p AS (SELECT x.id AS a, y.id AS b, {one} FROM t x JOIN t y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1), {SYMMETRIC}"
    if name == "colink":
        links = "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS link FROM pages"
        members = "SELECT link AS g, page_id AS k FROM lk WHERE link IN (SELECT link FROM lk GROUP BY link HAVING count(*) BETWEEN 2 AND 50)"
        return f"lk AS ({links}), {units('SELECT page_id AS id FROM pages')}, {together(members)}, {SYMMETRIC}"
    if name == "geometric":
        raw = "SELECT vec_id AS id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings"
        scaled = "SELECT id, (x - min(x) OVER ()) / (max(x) OVER () - min(x) OVER ()) AS x, (y - min(y) OVER ()) / (max(y) OVER () - min(y) OVER ()) AS y, 0.55 * sqrt(ln(count(*) OVER ()) / count(*) OVER ()) AS r FROM raw"
        near = "(m.x - n.x) * (m.x - n.x) + (m.y - n.y) * (m.y - n.y) < m.r * m.r"
        return f"raw AS ({raw}), pts AS ({scaled}), {units('SELECT id FROM raw')}, p AS (SELECT m.id AS a, n.id AS b, {one} FROM pts m JOIN pts n ON m.id < n.id AND {near}), {SYMMETRIC}"
    if name == "coship":
        return f"{units('SELECT s_suppkey AS id FROM supplier')}, {together('SELECT DISTINCT l_orderkey AS g, l_suppkey AS k FROM lineitem')}, {SYMMETRIC}"
    if name == "trade":
        pairs = f"SELECT o_custkey * 2 AS a, l_suppkey * 2 + 1 AS b, {one} FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
        return f"p AS ({pairs}), {SYMMETRIC}, {units('SELECT DISTINCT src AS id FROM e')}"
    if name == "handoff":
        pairs = f"SELECT a, b, {one} FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events) WHERE b IS NOT NULL"
        return f"{units('SELECT DISTINCT user_id AS id FROM events')}, p AS ({pairs}), {SYMMETRIC}"
    if name == "overlap":
        words = "SELECT DISTINCT doc_id, word FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '\\s+')) AS word FROM documents) WHERE word <> ''"
        members = "SELECT word AS g, doc_id AS k FROM wd WHERE word IN (SELECT word FROM wd GROUP BY word HAVING count(*) BETWEEN 2 AND 20)"
        return f"wd AS ({words}), {units('SELECT doc_id AS id FROM documents')}, {together(members)}, {SYMMETRIC}"
    raise ValueError(name)


def mapping(kind: str = "mod", k: int = 32) -> str:
    if kind == "mod":
        return f"m AS (SELECT id, CAST(id % {k} AS INTEGER) AS pe FROM v)"
    return f"m AS (SELECT id, CAST(id * {k} // (SELECT count(*) FROM v) AS INTEGER) AS pe FROM v)"


def distance(t: Topology, x: str, y: str) -> str:
    arms = [f"WHEN {x} = {y} THEN 0"] + [f"WHEN {x} // {n} = {y} // {n} THEN {d}" for n, d in zip(t.sizes[:-1], t.distances)]
    return f"CASE {' '.join(arms)} ELSE {t.distances[-1]} END"


def level(t: Topology, x: str, y: str) -> str:
    arms = [f"WHEN {x} = {y} THEN 0"] + [f"WHEN {x} // {n} = {y} // {n} THEN {i + 1}" for i, n in enumerate(t.sizes[:-1])]
    return f"CASE {' '.join(arms)} ELSE {len(t.sizes)} END"


def bound(total: str, k: int | str, num: int = 3, den: int = 100) -> str:
    return f"(({den + num} * {total} + {den} * {k} - 1) // ({den} * {k}))"


def noise(a: str, b: str, seed: int = 0) -> str:
    p, (x, y, z) = NOISE_MODULUS, NOISE_FACTORS
    return f"(((least({a}, {b}) % {p}) * {x} + (greatest({a}, {b}) % {p}) * {y} + {(seed % p) * z}) % {p})"


PLACED = "pl AS (SELECT e.src, e.dst, e.w, s.pe AS pe_s, t.pe AS pe_d FROM e JOIN m s ON s.id = e.src JOIN m t ON t.id = e.dst)"


def conn(m: str = "m", name: str = "conn") -> str:
    return f"{name} AS (SELECT e.src AS id, {m}.pe, CAST(sum(e.w) AS BIGINT) AS w FROM e JOIN {m} ON {m}.id = e.dst GROUP BY e.src, {m}.pe)"


def gain(t: Topology, m: str = "m", c: str = "conn", name: str = "gain") -> str:
    d = f"{distance(t, f'{m}.pe', 'x.pe')} - {distance(t, 'c.pe', 'x.pe')}".replace("CASE", "(CASE").replace("END", "END)")
    return f"{name} AS (SELECT c.id, {m}.pe AS pe_old, c.pe AS pe_new, CAST(sum(x.w * ({d})) AS BIGINT) AS gain FROM {c} c JOIN {m} ON {m}.id = c.id JOIN {c} x ON x.id = c.id WHERE c.pe <> {m}.pe GROUP BY c.id, {m}.pe, c.pe)"


def best(gain_name: str = "gain", name: str = "best") -> str:
    return f"{name} AS (SELECT id, pe_old, pe_new, gain FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY gain DESC, pe_new) AS r FROM {gain_name}) WHERE r = 1)"


def regain(t: Topology, m: str = "m", x: str = "prop", name: str = "re") -> str:
    at = f"(CASE WHEN y.id IS NOT NULL AND (y.gain > x.gain OR (y.gain = x.gain AND y.id < x.id)) THEN y.pe_new ELSE {m}.pe END)"
    near = f"SELECT x.id, x.pe_old, x.pe_new, x.gain, e.w, {at} AS place FROM {x} x JOIN e ON e.src = x.id JOIN {m} ON {m}.id = e.dst LEFT JOIN {x} y ON y.id = e.dst"
    change = f"w * (({distance(t, 'pe_old', 'place')}) - ({distance(t, 'pe_new', 'place')}))"
    return f"{name} AS (SELECT id, pe_old, pe_new, gain, CAST(sum({change}) AS BIGINT) AS regain FROM ({near}) GROUP BY id, pe_old, pe_new, gain)"


def moved(m: str, moves: str, name: str) -> str:
    return f"{name} AS (SELECT {m}.id, coalesce(x.pe_new, {m}.pe) AS pe FROM {m} LEFT JOIN {moves} x ON x.id = {m}.id)"


RATED = f"rt AS (SELECT e.src, e.dst, e.w, u.c AS cu, z.c AS cv, CAST(e.w AS DOUBLE) * e.w / CAST(u.c * z.c AS DOUBLE) AS rating, {noise('e.src', 'e.dst')} AS noise FROM e JOIN v u ON u.id = e.src JOIN v z ON z.id = e.dst)"


def prefs(name: str = "pf", where: str = "TRUE") -> str:
    return f"{name} AS (SELECT src AS id, dst AS pref FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY rating DESC, noise DESC, dst DESC) AS r FROM rt WHERE {where}) WHERE r = 1)"


def mutual(pref: str = "pf", name: str = "mt") -> str:
    return f"{name} AS (SELECT x.id, least(x.id, x.pref) AS coarse_id FROM {pref} x JOIN {pref} y ON y.id = x.pref AND y.pref = x.id)"


def paired(members: str, key: str, name: str = "pr") -> str:
    ranked = f"SELECT id, {key} AS k, (row_number() OVER (PARTITION BY {key} ORDER BY id) - 1) // 2 AS slot FROM ({members})"
    return f"{name}_r AS ({ranked}), {name} AS (SELECT id, first AS coarse_id FROM (SELECT id, min(id) OVER (PARTITION BY k, slot) AS first, count(*) OVER (PARTITION BY k, slot) AS n FROM {name}_r) WHERE n = 2)"


COARSE = "pj AS (SELECT v.id, coalesce(mt.coarse_id, v.id) AS coarse_id FROM v LEFT JOIN mt ON mt.id = v.id)"


def blocks(k: int) -> str:
    total = "(SELECT sum(c) FROM v)"
    return f"b AS (SELECT pe, weight, CAST({bound(total, k)} AS BIGINT) AS bound, CAST({total} // {k} AS BIGINT) AS average FROM (SELECT CAST(r.range AS INTEGER) AS pe, CAST(coalesce(sum(v.c), 0) AS BIGINT) AS weight FROM range({k}) r LEFT JOIN m ON m.pe = r.range LEFT JOIN v ON v.id = m.id GROUP BY r.range))"


CANDIDATES = "cand AS (SELECT v.id, v.c, m.pe AS pe_old, b.weight, b.bound FROM v JOIN m ON m.id = v.id JOIN b ON b.pe = m.pe WHERE b.weight > b.bound AND 2 * v.c <= 3 * (b.weight - b.average))"


def targets(t: Topology, objective: str = "cut", limit: str = "bound - least(100, (bound - average) // 2)") -> str:
    """tg(id, c, pe_old, weight, bound, pe_new, gain)."""
    accept = f"acc AS (SELECT pe, row_number() OVER (ORDER BY pe) - 1 AS i FROM b WHERE weight <= {limit})"
    near = "nr AS (SELECT cand.id, cand.pe_old, conn.pe AS pe_new FROM cand JOIN conn ON conn.id = cand.id JOIN acc ON acc.pe = conn.pe WHERE conn.pe <> cand.pe_old)"
    rest = f"rs AS (SELECT cand.id, cand.pe_old, acc.pe AS pe_new FROM cand JOIN acc ON acc.i = {noise('cand.id', 'cand.id')} % (SELECT count(*) FROM acc) WHERE cand.id NOT IN (SELECT id FROM nr))"
    if objective == "cut":
        gain_of = "coalesce((SELECT w FROM conn WHERE conn.id = o.id AND conn.pe = o.pe_new), 0) - coalesce((SELECT w FROM conn WHERE conn.id = o.id AND conn.pe = o.pe_old), 0)"
    else:
        gain_of = f"coalesce((SELECT sum(w * (({distance(t, 'o.pe_old', 'conn.pe')}) - ({distance(t, 'o.pe_new', 'conn.pe')}))) FROM conn WHERE conn.id = o.id), 0)"
    every = f"ev AS (SELECT o.id, o.pe_new, CAST({gain_of} AS BIGINT) AS gain FROM (SELECT * FROM nr UNION ALL SELECT * FROM rs) o)"
    pick = "bs AS (SELECT id, pe_new, gain FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY gain DESC, pe_new) AS r FROM ev) WHERE r = 1)"
    return f"{accept}, {near}, {rest}, {every}, {pick}, tg AS (SELECT cand.*, bs.pe_new, bs.gain FROM cand JOIN bs ON bs.id = cand.id)"


BUCKET = "CAST(CASE WHEN gain > 0 THEN 0 WHEN gain = 0 THEN 1 ELSE length(bin(-gain)) + 1 END AS INTEGER)"
PREFIX = f"px AS (SELECT * FROM (SELECT *, CAST(coalesce(sum(c) OVER (PARTITION BY pe_old ORDER BY bucket, id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before FROM (SELECT *, {BUCKET} AS bucket FROM tg)) WHERE before < weight - bound)"
