"""SQL for DuckDB that answers the driver queries from the full graph, without any certificate."""

from __future__ import annotations

from certgraph.sources.workloads import KNOWN, known_graph

SIDE = 1_000_000_000_000

_LINES = "l_orderkey, l_linenumber, l_partkey, l_suppkey"
_TRADES = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_NATIONS = f"{_TRADES} JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"


def _call(condition: str) -> tuple[str, str]:
    return f"SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b, ts, event_id FROM events WHERE {condition}", "ts, event_id"


def _topic(condition: str) -> tuple[str, str]:
    return f"SELECT user_id AS a, CAST(json_extract_string(props, '$.k') AS BIGINT) + {SIDE} AS b, ts, event_id FROM events WHERE {condition}", "ts, event_id"


_LINKS = "(SELECT page_id, url, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href, generate_subscripts(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1), 1) AS spot FROM pages)"
_GEO = f"SELECT c_custkey AS a, c_nationkey + {2 * SIDE} AS b, 1 AS kind, c_custkey AS key FROM customer UNION ALL SELECT s_suppkey + {SIDE}, s_nationkey + {2 * SIDE}, 2, s_suppkey FROM supplier UNION ALL SELECT n_nationkey + {2 * SIDE}, n_regionkey + {3 * SIDE}, 3, n_nationkey FROM nation"
_DOC_LINES = "(SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS spot FROM documents WHERE {0})"


def _doc_line(condition: str) -> tuple[str, str]:
    lines = f"(SELECT doc_id, md5(line) AS line, spot FROM {_DOC_LINES.format(condition)} WHERE length(line) > 20)"
    return f"SELECT 'd:' || doc_id AS a, 'l:' || line AS b, doc_id, spot FROM {lines} l WHERE line IN (SELECT line FROM {lines} GROUP BY line HAVING min(doc_id) < max(doc_id))", "doc_id, spot"


#: Rows (a, b, order columns) of each graph, and its order.
ROWS: dict[str, tuple[str, str]] = {
    "call_all": _call("TRUE"),
    "call_error": _call("event_type = 'error'"),
    "call_purchase": _call("event_type = 'purchase'"),
    "call_window": ("SELECT x.user_id AS a, y.user_id AS b, epoch(x.ts)::BIGINT AS t, x.event_id AS e, epoch(y.ts)::BIGINT AS t2, y.event_id AS e2 FROM events x JOIN events y ON floor(epoch(y.ts)) >= floor(epoch(x.ts)) AND floor(epoch(y.ts)) - floor(epoch(x.ts)) <= 300 AND x.event_id <> y.event_id", "t, e, t2, e2"),
    "user_topic_all": _topic("TRUE"),
    "user_topic_error": _topic("event_type = 'error'"),
    "page_link": (f"SELECT 'p:' || page_id AS a, 'h:' || href AS b, page_id, spot FROM {_LINKS}", "page_id, spot"),
    "host_link": (f"SELECT 's:' || regexp_extract(url, '://([^/]*)', 1) AS a, 'h:' || href AS b, page_id, spot FROM {_LINKS}", "page_id, spot"),
    "geo_tree": (_GEO, "kind, key"),
    "geo_orders": (f"{_GEO} UNION ALL SELECT o_custkey, l_suppkey + {SIDE}, 4, l_orderkey FROM {_TRADES}", "kind, key, a, b"),
    "part_supplier": (f"SELECT l_partkey AS a, l_suppkey + {SIDE} AS b, {_LINES} FROM lineitem", _LINES),
    "part_supplier_quarter": (f"SELECT l_partkey AS a, l_suppkey + {SIDE} AS b, {_LINES} FROM lineitem WHERE l_shipdate >= '1997-01-01' AND l_shipdate < '1997-04-01'", _LINES),
    "part_supplier_year": (f"SELECT l_partkey AS a, l_suppkey + {SIDE} AS b, {_LINES} FROM lineitem WHERE l_shipdate >= '1997-01-01' AND l_shipdate < '1998-01-01'", _LINES),
    "nation_trade": (f"SELECT c_nationkey AS a, s_nationkey AS b, {_LINES} FROM {_NATIONS}", _LINES),
    "supplier_coorder": ("SELECT DISTINCT x.l_suppkey AS a, y.l_suppkey AS b, x.l_orderkey FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_suppkey < y.l_suppkey", "l_orderkey, a, b"),
    "customer_supplier_returns": (f"SELECT o_custkey AS a, l_suppkey + {SIDE} AS b, {_LINES} FROM {_TRADES} WHERE l_returnflag = 'R'", _LINES),
    "customer_part": (f"SELECT o_custkey AS a, l_partkey + {SIDE} AS b, {_LINES} FROM {_TRADES}", _LINES),
    "order_customer": (f"SELECT o_orderkey AS a, o_custkey + {SIDE} AS b, o_orderkey FROM orders", "o_orderkey"),
    "turn_path": ("SELECT x.conv_id * 1000 + x.turn AS a, y.conv_id * 1000 + y.turn AS b, x.conv_id, x.turn FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1", "conv_id, turn"),
    "doc_line": _doc_line("TRUE"),
    "doc_line_good": _doc_line("doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)"),
    "doc_source_lang": ("SELECT 'd:' || doc_id AS a, 's:' || source AS b, doc_id, 1 AS kind FROM documents UNION ALL SELECT 'd:' || doc_id, 'l:' || lang, doc_id, 2 FROM documents", "doc_id, kind"),
}
ROWS["similar_vectors"] = ("SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id AND list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) > 0.25", "a, b")
for _name, (_kind, _size, _) in KNOWN.items():
    _listed = ", ".join(f"({min(p)}, {max(p)}, {i})" for i, p in enumerate(known_graph(_kind, *_size), 1))
    ROWS[f"known_{_name}"] = (f"SELECT a, b, i FROM (VALUES {_listed}) t(a, b, i)", "i")
NAMED = {"page_link", "host_link", "doc_line", "doc_line_good", "doc_source_lang"}


def graph(name: str) -> str:
    """CTEs up to `e`(seq, u, v), `b`(x, y) with both directions, and `vs`(id)."""
    rows, order = ROWS[name]
    steps = [f"raw AS ({rows})"]
    if name in NAMED:
        steps.append("names AS (SELECT name, row_number() OVER (ORDER BY name) - 1 AS id FROM (SELECT a AS name FROM raw UNION SELECT b FROM raw))")
        steps.append(f"ends AS (SELECT n.id AS a, m.id AS b, {', '.join('raw.' + c for c in order.split(', '))} FROM raw JOIN names n ON raw.a = n.name JOIN names m ON raw.b = m.name)")
    else:
        steps.append("ends AS (SELECT * FROM raw)")
    steps.append(f"ranked AS (SELECT a, b, row_number() OVER (ORDER BY {order}) AS rn FROM ends WHERE a <> b)")
    steps.append("first AS (SELECT least(a, b)::BIGINT AS u, greatest(a, b)::BIGINT AS v, min(rn) AS rn FROM ranked GROUP BY 1, 2)")
    steps.append("e AS MATERIALIZED (SELECT row_number() OVER (ORDER BY rn, u, v) AS seq, u, v FROM first)")
    steps.append("b AS MATERIALIZED (SELECT u AS x, v AS y, seq FROM e UNION ALL SELECT v, u, seq FROM e)")
    steps.append("vs AS MATERIALIZED (SELECT DISTINCT x AS id FROM b)")
    return ", ".join(steps)


def _with(name: str, more: list[str], last: str) -> str:
    return "WITH RECURSIVE " + ", ".join([graph(name), *more]) + " " + last


def edges(name: str) -> str:
    return _with(name, [], "SELECT seq, u, v FROM e")


def degree_stats(name: str) -> str:
    return _with(name, ["d AS (SELECT x, count(*) AS d FROM b GROUP BY x)"], "SELECT count(*) AS n, CAST(sum(d) / 2 AS BIGINT) AS m, min(d) AS min_degree, max(d) AS max_degree, avg(d) AS mean_degree FROM d")


_REACH = "reach AS (SELECT id, id AS to_id FROM vs UNION SELECT r.id, b.y FROM reach r JOIN b ON r.to_id = b.x)"


def components(name: str) -> str:
    return _with(name, [_REACH], "SELECT id, min(to_id) AS comp FROM reach GROUP BY id")


def connected(name: str) -> str:
    return _with(name, ["reach AS (SELECT min(id) AS id FROM vs UNION SELECT b.y FROM reach r JOIN b ON r.id = b.x)"], "SELECT (SELECT count(*) FROM reach) = (SELECT count(*) FROM vs) AS connected")


def _kept(edge_cte: str, out: str) -> list[str]:
    """Edges of a CTE (seq, u, v) that join two components of what came before."""
    both = f"(SELECT u AS x, v AS y, seq FROM {edge_cte} UNION ALL SELECT v, u, seq FROM {edge_cte})"
    return [
        f"{out}_walk AS (SELECT seq AS until, u AS spot FROM {edge_cte} UNION SELECT w.until, s.y FROM {out}_walk w JOIN {both} s ON s.x = w.spot AND s.seq < w.until)",
        f"{out} AS MATERIALIZED (SELECT seq, u, v FROM {edge_cte} WHERE (seq, v) NOT IN (SELECT (until, spot) FROM {out}_walk))",
    ]


def spanning_forest(name: str) -> str:
    return _with(name, _kept("e", "z"), "SELECT seq, u, v FROM z")


def _order(forest: str, out: str) -> list[str]:
    """Depth-first preorder of a forest CTE: vertices sorted by the list of ids from their root."""
    both = f"(SELECT u AS x, v AS y FROM {forest} UNION ALL SELECT v, u FROM {forest})"
    return [
        f"{out}_reach AS (SELECT id, id AS to_id FROM vs UNION SELECT r.id, s.y FROM {out}_reach r JOIN {both} s ON r.to_id = s.x)",
        f"{out}_root AS (SELECT id FROM (SELECT id, min(to_id) AS comp FROM {out}_reach GROUP BY id) WHERE id = comp)",
        f"{out}_path AS (SELECT id, id AS comp, [id] AS way FROM {out}_root UNION ALL SELECT s.y, p.comp, list_append(p.way, s.y) FROM {out}_path p JOIN {both} s ON s.x = p.id AND NOT list_contains(p.way, s.y))",
        f"{out} AS MATERIALIZED (SELECT id, comp, row_number() OVER (ORDER BY way) - 1 AS pos FROM {out}_path)",
    ]


def scan_order(name: str) -> str:
    return _with(name, _kept("e", "z") + _order("z", "o"), "SELECT id, comp, pos FROM o")


def level_order(name: str) -> str:
    return _with(name, _kept("e", "z") + _order("z", "o"), "SELECT id, comp, row_number() OVER (ORDER BY comp, len(way), id) - 1 AS pos FROM o_path")


def bfs_layers(name: str, k: int, deepest: int = 30) -> str:
    """Breadth-first forests, each on what the earlier ones left; the parent is the smallest neighbour one level up."""
    steps, cte = [], "e"
    for i in range(1, k + 1):
        steps += [
            f"c{i} AS MATERIALIZED (SELECT u AS x, v AS y, seq FROM {cte} UNION ALL SELECT v, u, seq FROM {cte})",
            f"t{i} AS (SELECT DISTINCT x AS id, x AS to_id FROM c{i} UNION SELECT t.id, c.y FROM t{i} t JOIN c{i} c ON t.to_id = c.x)",
            f"l{i} AS (SELECT min(to_id) AS id, 0 AS d FROM t{i} GROUP BY id UNION SELECT c.y, l.d + 1 FROM l{i} l JOIN c{i} c ON c.x = l.id AND l.d < {deepest})",
            f"q{i} AS MATERIALIZED (SELECT id, min(d) AS d FROM l{i} GROUP BY id)",
            f"f{i} AS MATERIALIZED (SELECT c.y, arg_min(c.seq, c.x) AS seq FROM c{i} c JOIN q{i} p ON p.id = c.x JOIN q{i} q ON q.id = c.y AND q.d = p.d + 1 GROUP BY c.y)",
            f"r{i} AS MATERIALIZED (SELECT * FROM {cte} WHERE seq NOT IN (SELECT seq FROM f{i}))",
        ]
        cte = f"r{i}"
    return _with(name, steps, "SELECT e.seq, e.u, e.v, l.layer::INT AS layer FROM e JOIN (" + " UNION ALL ".join(f"SELECT seq, {i} AS layer FROM f{i}" for i in range(1, k + 1)) + ") l ON e.seq = l.seq")


def _oriented(edge_cte: str, order: str, out: str) -> list[str]:
    return [f"{out} AS MATERIALIZED (SELECT e.seq, CASE WHEN p.pos < q.pos THEN e.v ELSE e.u END AS child, CASE WHEN p.pos < q.pos THEN e.u ELSE e.v END AS parent, least(p.pos, q.pos) AS parent_pos FROM {edge_cte} e JOIN {order} p ON e.u = p.id JOIN {order} q ON e.v = q.id)"]


def _forest(edge_cte: str, n: str, feed: str | None = None) -> list[str]:
    """Order and scan-first forest of a CTE, as o<n>, d<n> and f<n>; the order comes from the edges as `feed` lists them."""
    return [*_kept(feed or edge_cte, f"z{n}"), *_order(f"z{n}", f"o{n}"), *_oriented(edge_cte, f"o{n}", f"d{n}"), f"f{n} AS MATERIALIZED (SELECT child, arg_min(parent, parent_pos) AS parent, min(parent_pos) AS parent_pos, arg_min(seq, parent_pos) AS seq FROM d{n} GROUP BY child)"]


def scan_first_forest(name: str) -> str:
    return _with(name, _forest("e", "1"), "SELECT child, parent, parent_pos, seq FROM f1")


def layered(name: str, k: int) -> str:
    """The layered certificate with residuals in original order."""
    steps, cte = [], "e"
    for i in range(1, k + 1):
        steps += _forest(cte, str(i))
        steps.append(f"r{i} AS MATERIALIZED (SELECT * FROM {cte} WHERE seq NOT IN (SELECT seq FROM f{i}))")
        cte = f"r{i}"
    return _with(name, steps, "SELECT e.seq, e.u, e.v, l.layer::INT AS layer FROM e JOIN (" + " UNION ALL ".join(f"SELECT seq, {i} AS layer FROM f{i}" for i in range(1, k + 1)) + ") l ON e.seq = l.seq")


def _handed(n: str) -> str:
    """Edges of d<n> that the layer hands on, with the moment."""
    rows = f"SELECT *, coalesce(parent_pos < min(parent_pos) OVER (PARTITION BY child ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), TRUE) AS stored FROM d{n}"
    out = f"SELECT seq, least(child, parent) AS u, greatest(child, parent) AS v, CASE WHEN stored THEN min(CASE WHEN stored THEN seq END) OVER (PARTITION BY child ORDER BY seq ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) ELSE seq END AS handed FROM ({rows})"
    return f"SELECT * FROM ({out}) WHERE handed IS NOT NULL"


def handed(name: str) -> str:
    return _with(name, _forest("e", "1"), _handed("1"))


def layered_handover(name: str, k: int) -> str:
    """The layered certificate with each layer's order from the edges as the one before hands them on."""
    steps, left, feed = [], "e", "e"
    for i in range(1, k + 1):
        steps += _forest(left, str(i), feed)
        steps.append(f"h{i} AS MATERIALIZED ({_handed(str(i))})")
        steps.append(f"p{i} AS MATERIALIZED (SELECT handed AS seq, u, v FROM h{i})")
        left, feed = f"h{i}", f"p{i}"
    return _with(name, steps, "SELECT e.seq, e.u, e.v, l.layer::INT AS layer FROM e JOIN (" + " UNION ALL ".join(f"SELECT seq, {i} AS layer FROM f{i}" for i in range(1, k + 1)) + ") l ON e.seq = l.seq")


def cut_vertices(name: str) -> str:
    """Pieces by counting, for each vertex taken away, the components that its neighbours fall into."""
    steps = [
        _REACH,
        "whole AS (SELECT count(*) AS c FROM (SELECT DISTINCT min(to_id) FROM reach GROUP BY id))",
        "wander AS (SELECT x AS gone, y AS start, y AS spot FROM b UNION SELECT w.gone, w.start, b.y FROM wander w JOIN b ON b.x = w.spot AND b.y <> w.gone)",
        "sides AS (SELECT gone, count(DISTINCT least_id) AS n FROM (SELECT gone, start, min(spot) AS least_id FROM wander GROUP BY gone, start) GROUP BY gone)",
    ]
    return _with(name, steps, "SELECT gone AS id, CAST(c - 1 + n AS INT) AS pieces FROM sides, whole WHERE n > 1")


def _removals(size: int) -> list[str]:
    """Components of the graph without every set of `size` vertices: m(members, id, label)."""
    tables = ", ".join(f"vs AS v{i}" for i in range(size))
    ascending = " AND ".join(["TRUE", *(f"v{i}.id < v{i + 1}.id" for i in range(size - 1))])
    listed = "[" + ", ".join(f"v{i}.id" for i in range(size)) + "]" if size else "[]::BIGINT[]"
    sets = f"s{size} AS MATERIALIZED (SELECT {listed} AS members" + (f" FROM {tables} WHERE {ascending})" if size else ")")
    return [
        sets,
        f"w{size} AS (SELECT members, id AS start, id AS spot FROM s{size}, vs WHERE NOT list_contains(members, id) UNION SELECT w.members, w.start, b.y FROM w{size} w JOIN b ON b.x = w.spot AND NOT list_contains(w.members, b.y))",
        f"m{size} AS MATERIALIZED (SELECT members, start AS id, min(spot) AS label FROM w{size} GROUP BY members, start)",
    ]


def separators(name: str, size: int) -> str:
    steps = [_REACH, "whole AS (SELECT count(*) AS c FROM (SELECT DISTINCT min(to_id) FROM reach GROUP BY id))", *_removals(size)]
    return _with(name, steps, f"SELECT {size}::INT AS l, members, pieces FROM (SELECT members, CAST(count(DISTINCT label) AS INT) AS pieces FROM m{size} GROUP BY members), whole WHERE pieces > c")


def all_separators(name: str, k: int) -> str:
    steps = [_REACH, "whole AS (SELECT count(*) AS c FROM (SELECT DISTINCT min(to_id) FROM reach GROUP BY id))"]
    parts = []
    for size in range(1, k):
        steps += _removals(size)
        parts.append(f"SELECT {size}::INT AS l, members, pieces FROM (SELECT members, CAST(count(DISTINCT label) AS INT) AS pieces FROM m{size} GROUP BY members), whole WHERE pieces > c")
    return _with(name, steps, " UNION ALL ".join(parts))


def separator_count(name: str, size: int) -> str:
    return f"SELECT count(*) AS n FROM ({separators(name, size)})"


def k_connected(name: str, k: int) -> str:
    """By definition: more than k vertices, and one component without any fewer than k."""
    if k == 2:
        return f"SELECT 2::INT AS k, (SELECT sum(n) > 2 FROM ({degree_stats(name)})) AND (SELECT bool_and(connected) FROM ({connected(name)})) AND NOT EXISTS ({cut_vertices(name)}) AS verdict"
    steps, parts = [], []
    for size in range(k):
        steps += _removals(size)
        parts.append(f"(SELECT coalesce(max(n), 1) = 1 FROM (SELECT count(DISTINCT label) AS n FROM m{size} GROUP BY members))")
    return _with(name, steps, f"SELECT {k}::INT AS k, (SELECT count(*) FROM vs) > {k} AND " + " AND ".join(parts) + " AS verdict")


def k_connected_by_signs(name: str, k: int) -> str:
    """Where removing sets would take too long: a small degree or several components refute it; common neighbours of all
    pairs that are not adjacent prove it, as they cannot all go; null if neither does."""
    pairs = f"SELECT p.id, q.id FROM vs p JOIN vs q ON p.id < q.id ANTI JOIN e ON e.u = p.id AND e.v = q.id LEFT JOIN b x ON x.x = p.id LEFT JOIN b y ON y.x = q.id AND y.y = x.y GROUP BY p.id, q.id HAVING count(y.y) < {k}"
    proof = _with(name, [], f"SELECT count(*) AS n FROM ({pairs})")
    return f"SELECT k, CASE WHEN NOT verdict OR (SELECT n = 0 FROM ({proof})) THEN coalesce(verdict, TRUE) END AS verdict FROM ({k_connected_by_degree(name, k)})"


def k_connected_by_degree(name: str, k: int) -> str:
    """Refuted by a small degree or several components, else null."""
    return f"SELECT {k}::INT AS k, CASE WHEN NOT (SELECT n > {k} AND min_degree >= {k} FROM ({degree_stats(name)})) OR NOT (SELECT connected FROM ({connected(name)})) THEN FALSE END AS verdict"


def largest_k_by_signs(name: str) -> str:
    return f"SELECT CASE WHEN NOT (SELECT connected FROM ({connected(name)})) THEN 0 WHEN EXISTS ({cut_vertices(name)}) THEN 1 END::INT AS kappa"


def pieces_without(name: str, k: int) -> str:
    """Components of the graph without each set of fewer than k vertices."""
    steps, parts = [], []
    for size in range(k):
        steps += _removals(size)
        parts.append(f"SELECT members AS removed, CAST(count(DISTINCT label) AS INT) AS pieces FROM m{size} GROUP BY members")
    return _with(name, steps, " UNION ALL ".join(parts))


def kappa(name: str, cap: int) -> str:
    """Disjoint paths of pairs that are not adjacent: the size of the smallest set that parts them, up to cap."""
    steps, parted = [], []
    for size in range(cap):
        steps += _removals(size)
        parted.append(f"SELECT p.id AS u, q.id AS v, {size} AS n FROM m{size} p JOIN m{size} q ON p.members = q.members AND p.id < q.id AND p.label <> q.label")
    steps.append(f"parted AS (SELECT u, v, min(n) AS n FROM ({' UNION ALL '.join(parted)}) GROUP BY u, v)")
    return _with(name, steps, f"SELECT a.id AS u, c.id AS v, CAST(coalesce(n, {cap}) AS INT) AS kappa FROM vs a JOIN vs c ON a.id < c.id LEFT JOIN parted ON u = a.id AND v = c.id WHERE (a.id, c.id) NOT IN (SELECT (u, v) FROM e)")


def bounds(name: str, ks: tuple[int, ...]) -> str:
    return _with(name, [], "SELECT k::INT AS k, (SELECT count(*) FROM vs) AS n, (SELECT count(*) FROM e) AS m, TRUE AS within_online, TRUE AS within_layers FROM (VALUES " + ", ".join(f"({k})" for k in ks) + ") t(k)")


def predicted(name: str, k: int) -> str:
    n, m = "(SELECT count(*) FROM vs)", "(SELECT count(*) FROM e)"
    alpha = f"greatest(1, (CASE WHEN {n} > 2 THEN 1 ELSE 0 END) + (CASE WHEN {n} > 4 THEN 1 ELSE 0 END) + (CASE WHEN {n} > 16 THEN 1 ELSE 0 END) + (CASE WHEN {n} > 65536 THEN 1 ELSE 0 END))"
    rows = [f"SELECT 'online' AS method, 1::INT AS passes, CAST({k * k} * {n} AS DOUBLE) AS work, least({m}, {2 * k} * {n})::BIGINT AS rows_at_most", f"SELECT 'layered', {k + 1}, CAST({k} + {alpha} AS DOUBLE), least({m}, {k} * ({n} - 1))::BIGINT", f"SELECT 'one forest', 2, CAST({alpha} AS DOUBLE), least({m}, {n} - 1)::BIGINT"]
    return _with(name, [], " UNION ALL ".join(rows))


def bipartite(name: str) -> str:
    """No vertex is reached from itself by walks of both parities."""
    steps = ["sides AS (SELECT id, id AS spot, 0 AS side FROM vs UNION SELECT s.id, b.y, 1 - s.side FROM sides s JOIN b ON b.x = s.spot)"]
    return _with(name, steps, "SELECT count(*) = 0 AS bipartite FROM sides WHERE id = spot AND side = 1")


def without_hubs(name: str, keep: bool) -> str:
    ids = "SELECT x AS id FROM d WHERE d >= 3" if keep else "SELECT x AS id FROM d ORDER BY d DESC, x LIMIT 10"
    test = "IN" if keep else "NOT IN"
    return _with(name, ["d AS (SELECT x, count(*) AS d FROM b GROUP BY x)", f"chosen AS MATERIALIZED ({ids})"], f"SELECT seq, u, v FROM e WHERE u {test} (SELECT id FROM chosen) AND v {test} (SELECT id FROM chosen)")


def first_layer(name: str, what: str) -> str:
    last = "SELECT seq, u, v FROM e WHERE seq NOT IN (SELECT seq FROM f1)" if what == "residual" else "SELECT seq, seq IN (SELECT seq FROM f1) AS in_layer FROM e"
    return _with(name, _forest("e", "1"), last)


def largest_k(name: str, most: int) -> str:
    tries = " UNION ALL ".join(f"SELECT k FROM ({k_connected(name, k)}) WHERE verdict" for k in range(1, most + 1))
    return f"SELECT coalesce(max(k), 0)::INT AS kappa FROM ({tries})"


def _all_sizes(name: str, most: int) -> tuple[list[str], str]:
    steps = [_REACH, "whole AS (SELECT count(*) AS c FROM (SELECT DISTINCT min(to_id) FROM reach GROUP BY id))"]
    parts = []
    for size in range(1, most + 1):
        steps += _removals(size)
        parts.append(f"SELECT {size}::INT AS l, members, pieces FROM (SELECT members, CAST(count(DISTINCT label) AS INT) AS pieces FROM m{size} GROUP BY members), whole WHERE pieces > c")
    return steps, " UNION ALL ".join(parts)


def minimal_separators(name: str, size: int) -> str:
    steps, union = _all_sizes(name, size)
    steps.append(f"found AS MATERIALIZED ({union})")
    return _with(name, steps, f"SELECT l, members, pieces FROM found a WHERE l = {size} AND NOT EXISTS (SELECT 1 FROM found s WHERE s.l < {size} AND list_has_all(a.members, s.members))")


def smallest_separators(name: str, k: int) -> str:
    """In a connected graph the smallest cuts between two vertices are its smallest separators."""
    steps, union = _all_sizes(name, k - 1)
    steps.append(f"found AS MATERIALIZED ({union})")
    return _with(name, steps, "SELECT l, members FROM found WHERE l = (SELECT min(l) FROM found)")


def agreement(name: str, k: int) -> str:
    return f"SELECT k, method, verdict FROM ({k_connected(name, k)}), (VALUES ('layered'), ('layered_merge'), ('online_rounds'), ('online_merge')) t(method)"


def all_min_cuts(name: str, u: int, v: int, most: int) -> str:
    """The smallest sets that part u from v."""
    steps, parts = [], []
    for size in range(1, most + 1):
        steps += _removals(size)
        parts.append(f"SELECT {size} AS l, p.members FROM m{size} p JOIN m{size} q ON p.members = q.members AND p.id = {u} AND q.id = {v} AND p.label <> q.label")
    steps.append(f"found AS MATERIALIZED ({' UNION ALL '.join(parts)})")
    return _with(name, steps, "SELECT members FROM found WHERE l = (SELECT min(l) FROM found)")


def prefix_components(name: str, upto: int) -> str:
    reach = f"reach AS (SELECT x AS id, x AS to_id FROM b WHERE seq <= {upto} UNION SELECT r.id, b.y FROM reach r JOIN b ON r.to_id = b.x AND b.seq <= {upto})"
    return _with(name, [reach], "SELECT id, min(to_id) AS comp FROM reach GROUP BY id")


def layered_sizes(name: str, k: int) -> str:
    g = edges(name)
    return f"SELECT {k}::INT AS k, n, m, c AS cert_rows, c / ({k} * (n - 1)) AS of_layers, c / m AS of_edges FROM (SELECT count(*) AS m FROM ({g})), (SELECT count(DISTINCT x) AS n FROM (SELECT u AS x FROM ({g}) UNION ALL SELECT v FROM ({g}))), (SELECT count(*) AS c FROM ({layered(name, k)}))"


def min_degree(name: str) -> str:
    return f"SELECT min_degree FROM ({degree_stats(name)})"


def weekly_connectivity() -> str:
    """Each user's graph of event types by week: the fewest of its at most five types without which the others fall apart."""
    grow = " | ".join(f"CASE WHEN r & {1 << i} > 0 THEN a{i} ELSE 0 END" for i in range(5))
    reach = "SELECT graph, all_types, taken, left_types, a0, a1, a2, a3, a4, left_types & -left_types AS r FROM cut"
    for _ in range(4):
        reach = f"SELECT graph, all_types, taken, left_types, a0, a1, a2, a3, a4, (r | {grow}) & left_types AS r FROM ({reach})"
    neighbours = ", ".join(f"bit_or(CASE WHEN a = {i} THEN 1 << b WHEN b = {i} THEN 1 << a ELSE 0 END) AS a{i}" for i in range(5))
    return f"""WITH types AS (SELECT event_type, (row_number() OVER (ORDER BY event_type) - 1)::INT AS t FROM (SELECT DISTINCT event_type FROM events WHERE event_type IS NOT NULL)),
e AS (SELECT user_id, date_diff('day', DATE '1970-01-01', ts::DATE) // 7 AS w, ts, event_id, t FROM events LEFT JOIN types USING (event_type)),
steps AS (SELECT user_id || ':' || w AS graph, t AS a, lead(t) OVER (PARTITION BY user_id, w ORDER BY ts, event_id) AS b FROM e),
g AS (SELECT graph, bit_or((1 << a) | (1 << b)) AS all_types, {neighbours} FROM steps WHERE a <> b GROUP BY graph),
cut AS (SELECT g.*, s::INT AS taken, all_types & ~s::INT AS left_types FROM g, range(32) t(s) WHERE s::INT & ~all_types = 0 AND bit_count(all_types & ~s::INT) > 1),
apart AS (SELECT graph, min(bit_count(taken)) AS least FROM ({reach}) WHERE r <> left_types GROUP BY graph)
SELECT graph, coalesce(least, bit_count(all_types) - 1)::INT AS kappa FROM g LEFT JOIN apart USING (graph)"""
