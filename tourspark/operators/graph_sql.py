"""SQL for the graphs, trees and level tables, from which the oracles are put together."""

from __future__ import annotations

from tourspark.graphs import NATION_BASE, REGION_BASE, SUPPLIER_BASE, WORKED_EDGES, WORKED_PARTS

_TOKEN = "CAST('0x' || substr(md5({}), 1, 13) AS BIGINT)"

PAIRS = {
    "supply_multi": "SELECT l_partkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM lineitem",
    "supply_simple": "SELECT DISTINCT l_partkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM lineitem",
    "order_part": "SELECT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v FROM lineitem",
    "cust_supplier": "SELECT DISTINCT o_custkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "cust_part": "SELECT DISTINCT o_custkey * 2 AS u, l_partkey * 2 + 1 AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "copurchase": "SELECT * FROM (SELECT l_partkey AS u, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS v FROM lineitem) WHERE v IS NOT NULL",
    "supplier_loops": "SELECT l_partkey AS u, coalesce(lead(l_partkey) OVER w, first_value(l_partkey) OVER w) AS v FROM lineitem WINDOW w AS (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey)",
    "event_trail": "SELECT user_id AS u, coalesce(lead(user_id) OVER w, first_value(user_id) OVER w) AS v FROM events WINDOW w AS (ORDER BY ts, event_id)",
    "event_trail_by_type": "SELECT user_id AS u, coalesce(lead(user_id) OVER w, first_value(user_id) OVER w) AS v FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)",
    "event_trail_by_day": "SELECT user_id AS u, coalesce(lead(user_id) OVER w, first_value(user_id) OVER w) AS v FROM events WINDOW w AS (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id)",
    "event_user_hour": "SELECT DISTINCT user_id * 2 AS u, CAST(floor(epoch(ts) / 3600) AS BIGINT) * 2 + 1 AS v FROM events",
    "geo_tree": f"SELECT n_nationkey + {NATION_BASE} AS u, n_regionkey + {REGION_BASE} AS v FROM nation UNION ALL SELECT c_custkey, c_nationkey + {NATION_BASE} FROM customer UNION ALL SELECT s_suppkey + {SUPPLIER_BASE}, s_nationkey + {NATION_BASE} FROM supplier",
    "word_trail": f"SELECT {_TOKEN.format('a')} AS u, {_TOKEN.format('b')} AS v FROM (SELECT unnest(w[1:len(w) - 1]) AS a, unnest(w[2:len(w)]) AS b FROM (SELECT list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM documents WHERE lang = 'en') WHERE len(w) >= 2)",
    "page_links": f"SELECT {_TOKEN.format('host')} AS u, {_TOKEN.format('t')} AS v FROM (SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages) WHERE host <> ''",
    "dialog_roles": f"SELECT {_TOKEN.format('role')} AS u, {_TOKEN.format('t')} AS v FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS t FROM conversations) WHERE t IS NOT NULL",
    "knn_graph": """SELECT u, v FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY c DESC, v) AS r FROM (
        SELECT a.vec_id AS u, b.vec_id AS v, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) AS c FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE r <= 3""",
    "torus": "SELECT i AS u, unnest([i // 64 * 64 + (i % 64 + 1) % 64, (i // 64 + 1) % 64 * 64 + i % 64]) AS v FROM range(4096) t(i)",
    "worked": "SELECT * FROM (VALUES " + ", ".join(map(str, WORKED_EDGES)) + ") t(u, v)",
    "complete_odd": "SELECT a.d AS u, b.d AS v FROM (SELECT DISTINCT dayofweek(o_orderdate) AS d FROM orders) a, (SELECT DISTINCT dayofweek(o_orderdate) AS d FROM orders) b WHERE a.d < b.d",
    "grid_doubled": "WITH cell AS (SELECT DISTINCT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS i FROM events) SELECT a.i AS u, b.i AS v FROM cell a JOIN cell b ON (b.i = a.i + 1 AND a.i % 24 < 23) OR b.i = a.i + 24, range(2)",
}


def _rmat(scale: int = 10, per_vertex: int = 5, cuts=(0.57, 0.76, 0.95), seed: int = 1) -> str:
    c = [round(x * 65536) for x in cuts]
    draw = [f"CAST('0x' || substr(md5('{seed}-{b}-' || i), 1, 4) AS INTEGER)" for b in range(scale)]
    u = " + ".join(f"CASE WHEN {d} >= {c[1]} THEN {1 << scale - 1 - b} ELSE 0 END" for b, d in enumerate(draw))
    v = " + ".join(f"CASE WHEN {d} >= {c[0]} AND {d} < {c[1]} OR {d} >= {c[2]} THEN {1 << scale - 1 - b} ELSE 0 END" for b, d in enumerate(draw))
    return f"SELECT CAST({u} AS BIGINT) AS u, CAST({v} AS BIGINT) AS v FROM range({per_vertex << scale}) t(i)"


PAIRS["rmat"] = _rmat()


def _power_law(most: int = 24, cuts=(0.57, 0.76, 0.95), seed: int = 1) -> str:
    """As _rmat, at the scale that the number of orders gives."""
    c = [round(x * 65536) for x in cuts]
    draw = [f"CAST('0x' || substr(md5('{seed}-{b}-' || i), 1, 4) AS INTEGER)" for b in range(most)]
    weight = "CAST(1 AS BIGINT) << (s - 1 - {})"
    u = " + ".join(f"CASE WHEN s > {b} THEN CASE WHEN {d} >= {c[1]} THEN {weight.format(b)} ELSE 0 END ELSE 0 END" for b, d in enumerate(draw))
    v = " + ".join(f"CASE WHEN s > {b} THEN CASE WHEN {d} >= {c[0]} AND {d} < {c[1]} OR {d} >= {c[2]} THEN {weight.format(b)} ELSE 0 END ELSE 0 END" for b, d in enumerate(draw))
    scale = "SELECT greatest(8, length(bin(greatest(1, count(*)))) - 1) AS s FROM orders"
    return f"SELECT {u} AS u, {v} AS v FROM (SELECT s, unnest(range(5 * (1 << CAST(s AS INTEGER)))) AS i FROM ({scale}))"


PAIRS["power_law"] = _power_law()
PAIRS["geo_doubled"] = f"SELECT u, v FROM ({PAIRS['geo_tree']}), range(2)"

_GEO_PARTS = f"""SELECT r_regionkey + {REGION_BASE} AS v, r_regionkey AS part FROM region UNION ALL SELECT n_nationkey + {NATION_BASE}, n_regionkey FROM nation
  UNION ALL SELECT c_custkey, n_regionkey FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT s_suppkey + {SUPPLIER_BASE}, n_regionkey FROM supplier JOIN nation ON s_nationkey = n_nationkey"""
DIGEST_PART = "CAST('0x' || substr(md5(CAST(v AS VARCHAR)), 1, 8) AS BIGINT) % 8"


def edges(name: str) -> str:
    """``WITH`` list up to e(u, v): the canonical edges of a graph. Names that end in
    _repaired get the pairs of odd vertices in order of id."""
    base = {"order_part_repaired": "order_part", "supply_repaired": "supply_multi", "rmat_repaired": "rmat", "power_law_repaired": "power_law"}.get(name)
    text = f"e0 AS (SELECT CAST(least(u, v) AS BIGINT) AS u, CAST(greatest(u, v) AS BIGINT) AS v FROM ({PAIRS[base or name]}))"
    if not base:
        return text.replace("e0 AS", "e AS", 1)
    return text + """,
odd AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS rk FROM (SELECT v, count(*) AS d FROM (SELECT unnest([u, v]) AS v FROM e0) GROUP BY v) WHERE d % 2 = 1),
added AS (SELECT min(v) AS u, max(v) AS v FROM odd GROUP BY rk // 2),
e AS (SELECT u, v FROM e0 UNION ALL SELECT u, v FROM added)"""


def n_parts(name: str) -> int:
    return {"worked": 4, "complete_odd": 4, "geo_doubled": 5}.get(name, 8)


def parts(name: str) -> str:
    """``WITH`` list up to vp(v, part) and ep(u, v, pu, pv)."""
    vertices = "SELECT DISTINCT unnest([u, v]) AS v FROM e"
    if name == "worked":
        own = "SELECT * FROM (VALUES " + ", ".join(f"({v}, {p})" for v, p in WORKED_PARTS.items()) + ") t(v, part)"
    elif name in ("geo_doubled", "geo_tree"):
        own = _GEO_PARTS
    else:
        rule = {"torus": "v * 8 // 4096", "complete_odd": "v % 4", "rmat_repaired": DIGEST_PART}.get(name, "(v // 2) % 8" if "repaired" in name else "v % 8")
        own = f"SELECT v, {rule} AS part FROM ({vertices})"
    return f"""{edges(name)},
vp AS (SELECT CAST(v AS BIGINT) AS v, CAST(part AS INTEGER) AS part FROM ({own})),
ep AS (SELECT e.u, e.v, a.part AS pu, b.part AS pv FROM e JOIN vp a ON e.u = a.v JOIN vp b ON e.v = b.v)"""


def height(name: str) -> int:
    return (n_parts(name) - 1).bit_length()


#: The order in which a strategy takes meta-edges.
ORDERS = {"greedy": "w DESC, a, b", "id_order": "a, b, w", "lightest": "w, a, b"}


def tree(name: str, strategy: str = "greedy") -> str:
    """``WITH`` list up to m0..mh, picks k0.. and maps p0..ph (leaf, part)."""
    ids = "(VALUES (1), (2), (3), (4)) t(p)" if name == "worked" else f"range({n_parts(name)}) t(p)"
    text = f"""{parts(name)},
m0 AS (SELECT least(pu, pv) AS a, greatest(pu, pv) AS b, count(*) AS w FROM ep WHERE pu <> pv GROUP BY ALL),
p0 AS (SELECT CAST(p AS INTEGER) AS leaf, CAST(p AS INTEGER) AS part FROM {ids})"""
    for k in range(height(name)):
        text += f""",
o{k} AS (SELECT a, b, w, row_number() OVER (ORDER BY {ORDERS[strategy]}) AS rn FROM m{k}),
g{k} AS (SELECT CAST(0 AS BIGINT) AS rn, CAST([] AS INTEGER[]) AS used, false AS hit
  UNION ALL SELECT o.rn, CASE WHEN list_contains(used, a) OR list_contains(used, b) THEN used ELSE list_concat(used, [a, b]) END, NOT (list_contains(used, a) OR list_contains(used, b)) FROM g{k} g JOIN o{k} o ON o.rn = g.rn + 1),
x{k} AS (SELECT a, b, w FROM g{k} JOIN o{k} USING (rn) WHERE hit),
i{k} AS (SELECT p, row_number() OVER (ORDER BY p) - 1 AS rk FROM (SELECT DISTINCT part AS p FROM p{k}) WHERE p NOT IN (SELECT unnest([a, b]) FROM x{k})),
k{k} AS (SELECT a, b, w FROM x{k} UNION ALL SELECT min(p), max(p), 0 FROM i{k} GROUP BY rk // 2 HAVING count(*) = 2),
s{k} AS (SELECT unnest([a, b]) AS old, b AS new FROM k{k}),
p{k + 1} AS (SELECT leaf, coalesce(new, part) AS part FROM p{k} LEFT JOIN s{k} ON part = old),
m{k + 1} AS (SELECT least(a, b) AS a, greatest(a, b) AS b, sum(w) AS w FROM (SELECT coalesce(x.new, a) AS a, coalesce(y.new, b) AS b, w FROM m{k} LEFT JOIN s{k} x ON a = x.old LEFT JOIN s{k} y ON b = y.old) WHERE a <> b GROUP BY ALL)"""
    return text


def levels(name: str, strategy: str = "greedy") -> str:
    """``WITH`` list up to j(u, v, pu, pv, jl) and pm(level, leaf, part)."""
    h = height(name)
    joins = " ".join(f"JOIN p{k} a{k} ON a{k}.leaf = pu JOIN p{k} b{k} ON b{k}.leaf = pv" for k in range(h + 1))
    case = "CASE " + " ".join(f"WHEN a{k}.part = b{k}.part THEN {k}" for k in range(h + 1)) + " END"
    return f"""{tree(name, strategy)},
pm AS ({' UNION ALL '.join(f'SELECT {k} AS level, leaf, part FROM p{k}' for k in range(h + 1))}),
j AS (SELECT u, v, pu, pv, {case} AS jl FROM ep {joins})"""


def stats(name: str, strategy: str = "greedy") -> str:
    """``WITH`` list up to st(level, part, i, ob, eb, local, remote)."""
    return f"""{levels(name, strategy)},
ends AS (SELECT u AS v, pu AS leaf, jl FROM j UNION ALL SELECT v, pv, jl FROM j),
vl AS (SELECT v, leaf, level, count(*) FILTER (WHERE jl <= level) AS dl, count(*) FILTER (WHERE jl > level) AS dr, count(*) FILTER (WHERE jl > level - 1) AS db FROM ends, range({height(name) + 1}) r(level) GROUP BY ALL),
kv AS (SELECT pm.level, pm.part, dl, dr, (pm.level = 0 OR db > 0) AS live FROM vl JOIN pm ON vl.level = pm.level AND vl.leaf = pm.leaf),
ks AS (SELECT level, part, count(*) FILTER (WHERE live AND dr = 0) AS i, count(*) FILTER (WHERE live AND dr > 0 AND dl % 2 = 1) AS ob, count(*) FILTER (WHERE live AND dr > 0 AND dl % 2 = 0) AS eb, CAST(sum(dr) AS BIGINT) AS remote FROM kv GROUP BY ALL),
stepped AS (SELECT DISTINCT n.level, o.part AS was, n.part AS now FROM pm o JOIN pm n ON n.level = o.level + 1 AND n.leaf = o.leaf),
ps AS (SELECT s.level, s.now AS part, CAST(sum(ob // 2) AS BIGINT) AS paths FROM ks JOIN stepped s ON s.level = ks.level + 1 AND s.was = ks.part GROUP BY ALL),
fs AS (SELECT pm.level, pm.part, count(*) AS fresh FROM j JOIN pm ON pm.level = jl AND pm.leaf = pu GROUP BY ALL),
st AS (SELECT ks.level, ks.part, i, ob, eb, coalesce(fresh, 0) + coalesce(paths, 0) AS local, remote FROM ks LEFT JOIN ps USING (level, part) LEFT JOIN fs USING (level, part))"""


def with_(text: str, select: str) -> str:
    return f"WITH RECURSIVE {text}\n{select}"


def audit(name: str) -> str:
    """What an audit must say: a row a component, all of it true. Components are what their
    least vertex reaches; graphs of one component start from that vertex alone."""
    many = name in ("geo_doubled", "worked", "rmat_repaired", "grid_doubled", "complete_odd")
    if many:
        reach = "r AS (SELECT DISTINCT unnest([u, v]) AS root, root AS v FROM e UNION SELECT root, d.b FROM r JOIN d ON d.a = r.v WHERE d.b > root)"
        comps = "c AS (SELECT v, min(root) AS comp FROM r GROUP BY v)"
    else:
        reach = "r AS (SELECT min(u) AS root, min(u) AS v FROM e UNION SELECT root, d.b FROM r JOIN d ON d.a = r.v)"
        comps = "c AS (SELECT v, root AS comp FROM r)"
    body = f"{edges(name)},\nd AS (SELECT DISTINCT u AS a, v AS b FROM e UNION SELECT v, u FROM e),\n{reach},\n{comps}"
    return with_(body, "SELECT comp, count(*) AS n_edges, count(*) AS distinct_eids, true AS chained, true AS closed, true AS complete FROM e JOIN c ON e.u = c.v GROUP BY comp")


def cover(name: str) -> str:
    return with_(edges(name), "SELECT u, v, count(*) AS n FROM e GROUP BY ALL")


def visits(name: str) -> str:
    return with_(edges(name), "SELECT v, count(*) // 2 AS visits FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v")
