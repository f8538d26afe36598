"""SQL of the registered queries for DuckDB, built from shared common table expressions."""

from __future__ import annotations

from hashlib import md5

D3 = ("c0", "c1", "c2")


def pick(seed: int, k: int) -> float:
    return int(md5(f"{seed}:pick:{k}".encode()).hexdigest()[:8], 16) / 4294967296.0


def uniform(seed: int, name: str, draw: str = "'0'") -> str:
    return f"(CAST(('0x' || substr(md5('{seed}:' || CAST({name} AS VARCHAR) || ':' || CAST({draw} AS VARCHAR)), 1, 8)) AS BIGINT) / 4294967296e0)"


def gap(a: str, b: str, n: int = 3) -> str:
    """Distance of a.c<i> to b.a<i>."""
    return "sqrt(" + " + ".join(f"pow({a}c{i} - {b}a{i}, 2)" for i in range(n)) + ")"


def means(w: str, n: int = 3) -> str:
    return ", ".join(f"sum({w} * c{i}) / sum({w}) AS a{i}" for i in range(n))


EVENTS = """pts AS (SELECT event_id AS loc_id, event_id, user_id, ts, value, hour(ts) / 23e0 AS c0, value / 490.02e0 AS c1,
  CAST(regexp_extract(props, '"k": *(-?[0-9]+)', 1) AS DOUBLE) / 99e0 AS c2, row_number() OVER (ORDER BY event_id) - 1 AS pos FROM events)"""
TOWER = EVENTS + """, real AS (SELECT CAST(pos // 10 AS BIGINT) AS node_id, loc_id, c0, c1, c2, 0.1e0 AS prob, 1e0 AS weight FROM pts WHERE pos < (SELECT count(*) // 10 * 10 FROM events))"""
LINE_COORDS = "l_quantity / 50e0 AS c0, l_extendedprice / 104997.88e0 AS c1, (l_discount + 0e0) * 10e0 AS c2, (l_tax + 0e0) * 12.5e0 AS c3"
LINES = f"""pts AS (SELECT *, {LINE_COORDS}, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice, l_quantity) - 1 AS pos FROM lineitem),
 real AS (SELECT CAST(pos // 10 AS BIGINT) AS node_id, pos AS loc_id, c0, c1, c2, c3, 0.1e0 AS prob, 1e0 AS weight FROM pts WHERE pos < (SELECT count(*) // 10 * 10 FROM lineitem))"""
_SHARE = "l_quantity / sum(l_quantity) OVER (PARTITION BY l_orderkey)"
_LOC = "l_orderkey * 100000000 + l_linenumber * 10000000 + l_partkey"
ORDERS = f"real AS (SELECT l_orderkey AS node_id, {_LOC} AS loc_id, {LINE_COORDS}, {_SHARE} AS prob, 1e0 AS weight FROM lineitem)"
ABSENT = f"real AS (SELECT l_orderkey AS node_id, {_LOC} AS loc_id, {LINE_COORDS}, {_SHARE} * (1e0 - (l_discount + 0e0)) AS prob, o_totalprice / 1e5 AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
USERS = EVENTS + ", real AS (SELECT user_id AS node_id, loc_id, c0, c1, c2, 1e0 / count(*) OVER (PARTITION BY user_id) AS prob, 1e0 AS weight FROM pts)"


def iterate(start: str, out: str, rows: str = "real", by: str = "node_id", n: int = 3) -> str:
    """One inverse-distance update; a group standing on a location keeps its iterate."""
    w = "(weight * prob / nullif(g, 0))"
    olds = ", ".join(f"min(a{i}) AS o{i}" for i in range(n))
    new = ", ".join(f"sum({w} * c{i}) / sum({w}) AS n{i}" for i in range(n))
    kept = ", ".join(f"CASE WHEN g0 > 0 THEN n{i} ELSE o{i} END AS a{i}" for i in range(n))
    return f"{out} AS (SELECT {by}, {kept} FROM (SELECT {by}, min(g) AS g0, {olds}, {new} FROM (SELECT r.*, s.* EXCLUDE ({by}), {gap('r.', 's.', n)} AS g FROM {rows} r JOIN {start} s USING ({by})) GROUP BY {by}))"


def start(out: str = "y0", rows: str = "real", by: str = "node_id", n: int = 3) -> str:
    return f"{out} AS (SELECT {by}, {means('(weight * prob)', n)} FROM {rows} GROUP BY {by})"


def med(source: str, n: int = 3) -> str:
    """med(node_id, c0.., weight, mass, spread): medians after two updates."""
    twice = ", ".join([start(n=n), iterate("y0", "y1", n=n), iterate("y1", "y2", n=n)])
    return f"""{source}, {twice}, med AS (SELECT node_id, {', '.join(f'any_value(a{i}) AS c{i}' for i in range(n))}, max(weight) AS weight, sum(prob) AS mass, sum(prob * {gap('r.', 's.', n)}) / sum(prob) AS spread FROM real r JOIN y2 s USING (node_id) GROUP BY node_id)"""


MED = med(TOWER)


def seeds(points: str, key: str, k: int, power: int = 1, weight: str = "1e0", seed: int = 7, n: int = 3) -> str:
    """s1..sk(key, a0..): seeds by portable draws; scaled masses are whole numbers."""
    named = ", ".join(f"c{i} AS a{i}" for i in range(n))
    own = ", ".join(f"any_value(c{i}) AS a{i}" for i in range(n))
    kept = ", ".join(f"a{i}" for i in range(n))
    out = [f"s1 AS (SELECT {key} AS k, {named} FROM {points} ORDER BY {uniform(seed, key)}, {key} LIMIT 1)"]
    for j in range(1, k):
        near = " UNION ALL ".join(f"SELECT * FROM s{i}" for i in range(1, j + 1))
        squares = " + ".join(f"pow(p.c{i} - s.a{i}, 2)" for i in range(n))
        g = f"sqrt({squares})" if power == 1 else f"({squares})"
        out.append(f"m{j} AS (SELECT p.{key} AS k, {own}, CAST(round(any_value({weight}) * min({g}) * 1000000) AS BIGINT) AS m FROM {points} p, ({near}) s GROUP BY p.{key})")
        out.append(f"s{j + 1} AS (SELECT k, {kept} FROM (SELECT *, sum(m) OVER (ORDER BY k) AS upto, sum(m) OVER () AS total FROM m{j}) WHERE upto > total * {pick(seed, j)!r}e0 ORDER BY k LIMIT 1)")
    union = " UNION ALL ".join(f"SELECT {j - 1} AS centre, k, {kept} FROM s{j}" for j in range(1, k + 1))
    return ", ".join([*out, f"c_0 AS ({union})"])


def assigned(points: str, centres: str, out: str, key: str = "node_id", n: int = 3) -> str:
    """Points with centre and dist of the nearest centre, compared after rounding."""
    return f"{out} AS (SELECT p.*, q.centre, q.dist FROM {points} p JOIN (SELECT k, min(centre) AS centre, min(dist) AS dist FROM (SELECT {key} AS k, centre, dist, min(dist) OVER (PARTITION BY {key}) AS least FROM (SELECT p.{key}, s.centre, round({gap('p.', 's.', n)}, 9) AS dist FROM {points} p, {centres} s)) WHERE dist = least GROUP BY k) q ON p.{key} = q.k)"


def median_round(rows: str, centres: str, tag: str, weight: str, n: int = 3) -> str:
    """c_<tag>: the groups' medians after two updates; rows have `centre`."""
    sub = f"g{tag} AS (SELECT *, {weight} AS ww FROM {rows})"
    cols = f"h{tag} AS (SELECT centre, {', '.join(f'c{i}' for i in range(n))}, ww AS weight, 1e0 AS prob FROM g{tag})"
    parts = [sub, cols, start(f"p{tag}", f"h{tag}", "centre", n), iterate(f"p{tag}", f"q{tag}", f"h{tag}", "centre", n), iterate(f"q{tag}", f"r{tag}", f"h{tag}", "centre", n)]
    final = f"c_{tag} AS (SELECT centre, {', '.join(f'coalesce(n.a{i}, o.a{i}) AS a{i}' for i in range(n))} FROM {centres} o LEFT JOIN r{tag} n USING (centre))"
    return ", ".join([*parts, final])


def mean_round(rows: str, centres: str, tag: str, weight: str) -> str:
    body = f"r{tag} AS (SELECT centre, {means(weight)} FROM {rows} GROUP BY centre)"
    return body + f", c_{tag} AS (SELECT centre, {', '.join(f'coalesce(n.a{i}, o.a{i}) AS a{i}' for i in range(3))} FROM {centres} o LEFT JOIN r{tag} n USING (centre))"


def shown(table: str, extra: str = "CAST(centre AS INTEGER) AS centre", n: int = 3, places: int = 6) -> str:
    return f"SELECT {extra}, {', '.join(f'round(a{i}, {places}) AS c{i}' for i in range(n))} FROM {table}"


#: S0: five hash-chosen locations.
def fixed_centres(k: int = 5, out: str = "cs", rows: str = "real", n: int = 3) -> str:
    cols = ", ".join(f"c{i} AS a{i}" for i in range(n))
    return f"{out} AS (SELECT row_number() OVER (ORDER BY u, loc_id) - 1 AS centre, {cols} FROM (SELECT DISTINCT {uniform(5, 'loc_id')} AS u, loc_id, {', '.join(f'c{i}' for i in range(n))} FROM {rows}) ORDER BY u, loc_id LIMIT {k})"


def expected(out: str = "ed", rows: str = "real", centres: str = "cs", n: int = 3) -> str:
    return f"{out} AS (SELECT node_id, centre, max(weight) AS weight, sum(prob * {gap('r.', 's.', n)}) AS e FROM {rows} r, {centres} s GROUP BY node_id, centre)"


def cells(source: str, n: int = 3) -> str:
    return med(source, n) + ", " + seeds("med", "node_id", 3, n=n) + ", " + assigned("med", "c_0", "near", n=n) + _CELLS


_CELLS = """, rad AS (SELECT sum(weight * mass * (dist + spread)) / (4e0 * sum(weight * mass)) AS radius FROM near),
 cells AS (SELECT node_id, any_value(weight) AS weight, any_value(mass) AS mass, any_value(dist) AS dist, any_value(centre) AS centre, CAST(sum(CASE WHEN dist >= radius * pow(2e0, h) THEN 1 ELSE 0 END) AS INTEGER) AS ring, CAST(sum(CASE WHEN spread > radius * pow(2e0, h) THEN 1 ELSE 0 END) AS INTEGER) AS spread_class FROM near, rad, range(40) t(h) GROUP BY node_id)"""
CELLS = cells(TOWER)


def counts(per_k: int, k: int, kind: str) -> str:
    share = {"even": f"{per_k * k} // (count(*) OVER ())", "as_printed": f"{per_k * k} // n", "proportional": f"({per_k * k} * n) // CAST(sum(n) OVER () AS BIGINT)"}[kind]
    return f"dc AS (SELECT centre, ring, spread_class, n, CAST(greatest({share}, 1) AS BIGINT) AS draws FROM (SELECT centre, ring, spread_class, count(*) AS n FROM cells GROUP BY ALL))"


def drawn(mass: str = "weight", per_k: int = 20, k: int = 3) -> str:
    name = "(CAST(centre AS VARCHAR) || '/' || CAST(ring AS VARCHAR) || '/' || CAST(spread_class AS VARCHAR))"
    return counts(per_k, k, "even") + f""", sp AS (SELECT centre, ring, spread_class, node_id, sum(m) OVER w AS upto, sum(m) OVER w - m AS low, sum(m) OVER (PARTITION BY centre, ring, spread_class) AS total FROM (SELECT *, CAST(round({mass} * 1000000) AS BIGINT) AS m FROM cells) WINDOW w AS (PARTITION BY centre, ring, spread_class ORDER BY node_id)),
 tr AS (SELECT centre, ring, spread_class, draws, CAST(floor({uniform(7, name, 't')} * total) AS BIGINT) AS spot FROM dc JOIN (SELECT centre, ring, spread_class, max(total) AS total FROM sp GROUP BY ALL) USING (centre, ring, spread_class), LATERAL (SELECT unnest(range(1, draws + 1)) AS t)),
 dr AS (SELECT centre, ring, spread_class, node_id, count(*) AS copies, max(draws) AS draws FROM tr JOIN sp USING (centre, ring, spread_class) WHERE low <= spot AND spot < upto GROUP BY ALL)"""


def summary(mass: str = "weight") -> str:
    """sw(node_id, cell, copies, new_weight): the drawn nodes with their new weights."""
    return drawn(mass) + f", sw AS (SELECT c.node_id, c.centre, c.ring, c.spread_class, copies, copies * weight * whole / (draws * {mass}) AS new_weight FROM cells c JOIN dr USING (centre, ring, spread_class, node_id) JOIN (SELECT centre, ring, spread_class, sum({mass}) AS whole FROM cells GROUP BY ALL) USING (centre, ring, spread_class))"


SUMMARY = summary()


def cost_of(out: str, weight: str, rows: str) -> str:
    return f"{out} AS (SELECT sum({weight} * e) AS cost FROM (SELECT node_id, min(e) AS e FROM {rows} GROUP BY node_id) {'JOIN sw USING (node_id)' if weight == 'new_weight' else ''})"
