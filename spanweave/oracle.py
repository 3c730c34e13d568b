"""DuckDB SQL for the registered queries: enumeration by recursive paths, path tuples and bit masks, never by the kernels' methods."""

from __future__ import annotations

from .queries import CLICK, ERROR, PURCHASE, SIGNUP, VIEW
from .sources.graphs import EVENT_TYPES

SQL: dict[str, str] = {}

PAIRS = """
pairs AS (SELECT least(c_nationkey, s_nationkey)::BIGINT a, greatest(c_nationkey, s_nationkey)::BIGINT b, count(*) n
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
    WHERE c_nationkey <> s_nationkey GROUP BY 1, 2)"""


def trade(k: int = 20) -> str:
    return f"{PAIRS}, g AS (SELECT * FROM (SELECT row_number() OVER (ORDER BY n DESC, a, b) - 1 edge_id, a src, b dst FROM pairs) WHERE edge_id < {k})"


PLACES = """
ends AS (SELECT src v FROM g UNION ALL SELECT dst FROM g),
place AS (SELECT v, count(*) degree, row_number() OVER (ORDER BY count(*) DESC, v) r FROM ends GROUP BY v)"""

BOTH = "arcs AS (SELECT edge_id, src, dst FROM g UNION ALL SELECT edge_id, dst, src FROM g)"
ONE_WAY = "arcs AS (SELECT edge_id, src, dst FROM g)"

TYPE = "list_position([" + ", ".join(f"'{t}'" for t in EVENT_TYPES) + "], {}) - 1"
EVENTS = f"""
steps AS (SELECT user_id, ts, event_type e, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) f FROM events),
counts AS (SELECT ({TYPE.format("e")})::BIGINT s, ({TYPE.format("f")})::BIGINT t, count(*) n FROM steps WHERE e <> f GROUP BY 1, 2),
g AS (SELECT row_number() OVER (ORDER BY n DESC, s, t) - 1 edge_id, s src, t dst FROM counts)"""


def paths(start: str, *, go_on: str = "true") -> str:
    """p(s, t, vs, es): simple paths from each start(s); ``go_on`` says of the present end p.t whether a path may go on."""
    return f"""
p(s, t, vs, es) AS (SELECT s, s, [s], []::BIGINT[] FROM ({start})
    UNION ALL SELECT p.s, a.dst, list_append(p.vs, a.dst), list_append(p.es, a.edge_id) FROM p JOIN arcs a ON p.t = a.src
    WHERE NOT list_contains(p.vs, a.dst) AND (len(p.es) = 0 OR ({go_on})))"""


def at(r: int) -> str:
    return f"(SELECT v FROM place WHERE r = {r})"


KEY = "array_to_string(list_sort(e), '-')"


def tuples(ends: list[str]) -> str:
    """u(v, e): unions of one path to each end, kept while they are trees."""
    out, last = "", ""
    for k, end in enumerate(ends):
        one = f"SELECT vs v, es e FROM p WHERE t = {end}"
        if not k:
            out = f"u0 AS ({one})"
        else:
            out += f""",
u{k} AS (SELECT v, e FROM (SELECT list_distinct(list_concat(x.v, y.v)) v, list_distinct(list_concat(x.e, y.e)) e FROM u{k - 1} x, ({one}) y) WHERE len(v) = len(e) + 1)"""
        last = f"u{k}"
    return f"{out}, u AS (SELECT * FROM {last})"


def tree_ctes(places: tuple[int, ...], k: int = 20) -> str:
    first, *rest = places
    return f"WITH RECURSIVE {trade(k)}, {PLACES}, {BOTH}, {paths(f'SELECT v s FROM place WHERE r = {first}')}, {tuples([at(r) for r in rest])}"


ONE_KEY = f"SELECT CASE WHEN len(e) = 0 THEN concat('v', v[1]) ELSE {KEY} END solution_key, len(e)::BIGINT n_edges FROM u"
TREES = f"{tree_ctes((1, 2, 3))} {ONE_KEY}"
PATHS_AB = f"WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths('SELECT v s FROM place WHERE r = 1')} "

for name in ("st_paths_trade", "st_paths_trade_copied_state", "st_paths_trade_in_order", "st_paths_trade_relational"):
    SQL[name] = PATHS_AB + f"SELECT array_to_string(es, '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {at(2)}"
SQL["terminal_trees_two"] = PATHS_AB + f"SELECT array_to_string(list_sort(es), '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {at(2)}"
SQL["st_paths_events_directed"] = f"WITH RECURSIVE {EVENTS}, {ONE_WAY}, {paths(f'SELECT {SIGNUP}::BIGINT s')} SELECT array_to_string(es, '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {PURCHASE}"
SQL["st_path_lengths"] = f"WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths('SELECT v s FROM place')} SELECT s, t, len(es)::BIGINT length, count(*) n FROM p GROUP BY ALL"
SQL["set_paths_trade"] = f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH},
  {paths("SELECT v s FROM place WHERE r IN (1, 3)", go_on="p.t NOT IN (SELECT v FROM place WHERE r <= 4)")}
  SELECT array_to_string(es, '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t IN (SELECT v FROM place WHERE r IN (2, 4)) AND len(es) > 0"""
SQL["hamiltonian_paths"] = f"WITH RECURSIVE {EVENTS.replace('g AS (', 'h AS (')}, g AS (SELECT * FROM h WHERE src < dst), {BOTH}, {paths(f'SELECT {SIGNUP}::BIGINT s')} SELECT array_to_string(es, '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {PURCHASE} AND len(es) = 4"

for name in ("buffered", "simple", "improved", "sharded", "relational"):
    SQL[f"steiner_trees_{name}"] = TREES
SQL["forest_of_one_set"] = SQL["trees_after_pruning"] = SQL["induced_line_graph"] = TREES
SQL["steiner_trees_four_terminals"] = f"{tree_ctes((1, 2, 3, 4))} {ONE_KEY}"
SQL["steiner_trees_forced"] = f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths("SELECT v s FROM place WHERE r = 1")},
  {tuples(["(SELECT v FROM place WHERE r = (SELECT max(r) - 1 FROM place))", "(SELECT v FROM place WHERE r = (SELECT max(r) FROM place))"])} {ONE_KEY}"""
SQL["steiner_trees_disconnected"] = f"{tree_ctes((1, 2))} {ONE_KEY} WHERE list_contains(v, 999)"
SQL["minimum_trees"] = SQL["minimum_trees_by_rank"] = f"{tree_ctes((1, 2, 3))} SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM u WHERE len(e) = (SELECT min(len(e)) FROM u)"

FORESTS = f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths("SELECT v s FROM place WHERE r IN (1, 3)")},
  u AS (SELECT list_distinct(list_concat(x.vs, y.vs)) v, list_distinct(list_concat(x.es, y.es)) e, list_has_any(x.vs, y.vs)::INT met
    FROM p x, p y WHERE x.s = {at(1)} AND x.t = {at(2)} AND y.s = {at(3)} AND y.t = {at(4)})
  SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM u WHERE len(v) = len(e) + 2 - met"""
for name in ("improved", "simple", "naive_completion", "buffered", "sharded", "relational"):
    SQL[f"steiner_forests_{name}"] = FORESTS

#: Trees whose terminals all have one edge.
LEAVES_ONLY = f"""{tree_ctes((1, 2, 3))}, w AS (SELECT v FROM place WHERE r <= 3),
  d AS (SELECT e, x.v, count(*) n FROM u, (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) x WHERE list_contains(u.e, x.edge_id) GROUP BY ALL),
  ok AS (SELECT e FROM d JOIN w ON d.v = w.v GROUP BY e HAVING max(n) = 1)"""
for name in ("improved", "simple", "buffered", "sharded"):
    SQL[f"terminal_trees_{name}"] = f"{LEAVES_ONLY} SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM ok"
SQL["trees_intersect_terminal"] = SQL["terminal_trees_improved"]
SQL["trees_except_terminal"] = f"{LEAVES_ONLY} SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM u WHERE e NOT IN (SELECT e FROM ok)"


def directed(wanted: tuple[int, ...]) -> str:
    return f"WITH RECURSIVE {EVENTS}, {ONE_WAY}, {paths(f'SELECT {SIGNUP}::BIGINT s')}, {tuples([str(w) for w in wanted])} {ONE_KEY}"


for name in ("improved", "simple", "buffered", "sharded", "relational"):
    SQL[f"directed_trees_{name}"] = directed((PURCHASE, ERROR, VIEW))
SQL["directed_trees_spanning"] = directed((PURCHASE, ERROR, VIEW, CLICK))


def fleet(steps: str, who: str, name: str) -> str:
    """Trees from signup to purchase in each group's own digraph: the paths."""
    return f"""WITH RECURSIVE {steps}, arcs AS (SELECT DISTINCT w, ({TYPE.format("e")})::BIGINT src, ({TYPE.format("f")})::BIGINT dst FROM steps WHERE e <> f),
    p(w, t, vs, es) AS (SELECT DISTINCT w, {SIGNUP}::BIGINT, [{SIGNUP}::BIGINT], []::BIGINT[] FROM arcs UNION ALL
      SELECT p.w, a.dst, list_append(p.vs, a.dst), list_append(p.es, a.src * 5 + a.dst) FROM p JOIN arcs a ON p.w = a.w AND p.t = a.src WHERE NOT list_contains(p.vs, a.dst))
    SELECT {who} {name}, array_to_string(list_sort(es), '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {PURCHASE}"""


SQL["directed_trees_user_fleet"] = fleet("steps AS (SELECT user_id w, event_type e, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) f FROM events)", "w::BIGINT", "user_id")


def windows(width: int, slide: int) -> str:
    starts = f"SELECT *, unnest(range(0, {width}, {slide})) AS back FROM events"
    return f"""steps AS (SELECT w, event_type e, lead(event_type) OVER (PARTITION BY w, user_id ORDER BY ts, event_id) f
      FROM (SELECT *, (floor(epoch(ts) / {slide}) * {slide} - back)::BIGINT w FROM ({starts})) WHERE epoch(ts) < w + {width})"""


SQL["window_event_fragments"] = fleet(windows(7 * 86400, 7 * 86400), "w", "window_start")
SQL["sliding_event_fragments"] = fleet(windows(10 * 86400, 5 * 86400), "w", "window_start")
SQL["session_transitions"] = f"""WITH a AS (SELECT *, CASE WHEN lag(ts) OVER w + INTERVAL 6 HOUR < ts THEN 1 ELSE 0 END fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
  b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) session FROM a),
  c AS (SELECT user_id, session, event_type e, lead(event_type) OVER (PARTITION BY user_id, session ORDER BY ts, event_id) f FROM b)
  SELECT s, t, count(*) sessions FROM (SELECT DISTINCT user_id, session, ({TYPE.format("e")})::BIGINT s, ({TYPE.format("f")})::BIGINT t FROM c WHERE e <> f) GROUP BY s, t"""

SQL["group_trees_regions"] = f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths("SELECT v s FROM place JOIN nation ON v = n_nationkey WHERE n_regionkey = 0")},
  member AS (SELECT v, n_regionkey r FROM place JOIN nation ON v = n_nationkey WHERE n_regionkey IN (0, 2, 3)),
  q AS (SELECT s, r, vs, es FROM p JOIN member ON t = v),
  c AS (SELECT DISTINCT list_sort(e) e, list_sort(v) v FROM (SELECT list_distinct(list_concat(x.vs, y.vs)) v, list_distinct(list_concat(x.es, y.es)) e FROM q x JOIN q y ON x.s = y.s AND x.r = 2 AND y.r = 3) WHERE len(v) = len(e) + 1),
  d AS (SELECT e, x.v, count(*) n FROM c, (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) x WHERE list_contains(c.e, x.edge_id) GROUP BY ALL),
  alone AS (SELECT c.e, r, min(m.v) v FROM c JOIN member m ON list_contains(c.v, m.v) GROUP BY c.e, r HAVING count(*) = 1),
  bad AS (SELECT DISTINCT d.e FROM d WHERE n = 1 AND NOT EXISTS (SELECT 1 FROM alone a WHERE a.e = d.e AND a.v = d.v))
  SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM c WHERE e NOT IN (SELECT e FROM bad) AND len(e) > 0"""


REGIONS = """h AS (SELECT DISTINCT o_custkey::BIGINT c, l_orderkey o, n_regionkey::BIGINT v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey)"""


def transversals(edges: str, width: str) -> str:
    """Minimal hitting sets among all masks of elements below ``width``, for each c of he(c, m)."""
    return f"""WITH {edges}, hit AS (SELECT c, x FROM (SELECT DISTINCT c FROM he), range(1::BIGINT << {width}) r(x) WHERE NOT EXISTS (SELECT 1 FROM he WHERE he.c = c AND he.m & x = 0)),
  least AS (SELECT c, x FROM hit WHERE NOT EXISTS (SELECT 1 FROM hit y, range({width}) b(i) WHERE hit.x & (1::BIGINT << i) <> 0 AND y.c = hit.c AND y.x = hit.x - (1::BIGINT << i)))"""


SQL["minimal_transversals"] = f"""WITH {REGIONS}, he AS (SELECT c, bit_or(1::BIGINT << v) m FROM h GROUP BY c, o),
  s AS (SELECT DISTINCT c, m FROM he), every AS (SELECT c, x FROM (SELECT DISTINCT c FROM s), range(32) r(x)), miss AS (SELECT DISTINCT c, x FROM s, range(32) r(x) WHERE m & x = 0),
  hit AS (SELECT * FROM every ANTI JOIN miss USING (c, x)),
  more AS (SELECT c, x | (1::BIGINT << i) x FROM hit, range(5) b(i) WHERE x & (1::BIGINT << i) = 0), least AS (SELECT * FROM hit ANTI JOIN more USING (c, x))
  SELECT c customer, array_to_string(list_filter(range(5), lambda i: x & (1::BIGINT << i) <> 0), '-') solution_key, bit_count(x)::BIGINT n FROM least"""
PLACED = f"""{trade()}, {PLACES}, e AS (SELECT edge_id, r - 1 p FROM (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) x JOIN place USING (v)), size AS (SELECT count(*) n FROM place)"""


def all_masks(sets: str, name: str) -> str:
    """Minimal hitting sets over the graph's places, named by ``name`` of a place i."""
    return f"""WITH {PLACED}, he AS ({sets}), hit AS (SELECT x FROM size, range(1::BIGINT << n) r(x) WHERE NOT EXISTS (SELECT 1 FROM he WHERE he.m & x = 0)),
  more AS (SELECT DISTINCT x | (1::BIGINT << (r - 1)) x FROM hit, place WHERE x & (1::BIGINT << (r - 1)) = 0), least AS (SELECT * FROM hit ANTI JOIN more USING (x))
  SELECT string_agg({name}::VARCHAR, '-' ORDER BY {name}) solution_key, count(*) n FROM least JOIN place ON x & (1::BIGINT << (r - 1)) <> 0 GROUP BY x"""


SQL["vertex_covers_by_masks"] = SQL["vertex_covers_via_star"] = all_masks("SELECT bit_or(1::BIGINT << p) m FROM e GROUP BY edge_id", "(r - 1)")
SQL["minimal_dominating_sets"] = all_masks("SELECT bit_or((1::BIGINT << (y.r - 1)) | (1::BIGINT << (x.r - 1))) m FROM (SELECT src a, dst b FROM g UNION ALL SELECT dst, src FROM g) JOIN place x ON x.v = a JOIN place y ON y.v = b GROUP BY a", "v")
SQL["hypergraph_star"] = "SELECT DISTINCT n_regionkey::BIGINT edge_id, -1::BIGINT src, n_regionkey::BIGINT dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"
SQL["normalize_pairs"] = f"WITH {REGIONS}, f AS (SELECT c, o, v, min(v) OVER (PARTITION BY c, o) a FROM h) SELECT DISTINCT c customer, a, v b FROM f WHERE a <> v"

INTERVAL = """v AS (SELECT DISTINCT p_size::BIGINT v FROM part WHERE p_size IS NOT NULL),
  g AS (SELECT row_number() OVER (ORDER BY a.v, b.v) - 1 edge_id, a.v src, b.v dst FROM v a JOIN v b ON a.v < b.v AND b.v - a.v <= {0})"""
SQL["interval_graph"] = f"WITH {INTERVAL.format(9)} SELECT src, dst FROM g"
#: For two terminals the minimal sets are the paths without chords.
INDUCED = f"""WITH RECURSIVE {INTERVAL.format(24)}, arcs AS (SELECT src, dst FROM g UNION ALL SELECT dst, src FROM g), q AS (SELECT min(v) a, max(v) b FROM v),
  p(t, vs) AS (SELECT a, [a] FROM q UNION ALL SELECT x.dst, list_append(p.vs, x.dst) FROM p JOIN arcs x ON p.t = x.src, q
    WHERE p.t <> q.b AND NOT list_contains(p.vs, x.dst) AND len(list_filter(p.vs, lambda u: abs(u - x.dst) <= 24)) = 1)
  SELECT array_to_string(list_sort(vs), '-') solution_key, len(vs)::BIGINT n FROM p, q WHERE t = b"""
SQL["induced_interval_graph"] = INDUCED
SQL["minimum_induced"] = f"WITH i AS ({INDUCED}) SELECT * FROM i WHERE n = (SELECT min(n) FROM i)"

SQL["internal_trees"] = f"""WITH {EVENTS.replace('g AS (', 'h AS (')}, g AS (SELECT edge_id, src, dst, row_number() OVER (ORDER BY edge_id) - 1 k FROM h WHERE src < dst),
  s AS (SELECT x, g.edge_id, src, dst FROM range(1, 1024) r(x) JOIN g ON x & (1::BIGINT << g.k) <> 0),
  v AS (SELECT x, w, count(*) n FROM (SELECT x, src w FROM s UNION ALL SELECT x, dst FROM s) GROUP BY ALL),
  size AS (SELECT x FROM (SELECT x, count(*) e FROM s GROUP BY x) JOIN (SELECT x, count(*) n FROM v GROUP BY x) USING (x) WHERE n = e + 1),
  inner_both AS (SELECT x FROM v WHERE w IN ({PURCHASE}, {ERROR}) AND n >= 2 GROUP BY x HAVING count(*) = 2),
  few AS (SELECT x FROM size JOIN inner_both USING (x)),
  lab AS (SELECT * FROM (WITH RECURSIVE r(x, w) AS (SELECT x, {PURCHASE}::BIGINT FROM few UNION
      SELECT r.x, CASE WHEN s.src = r.w THEN s.dst ELSE s.src END FROM r JOIN s ON r.x = s.x AND (s.src = r.w OR s.dst = r.w)) SELECT x, count(*) n FROM r GROUP BY x)),
  tree AS (SELECT few.x FROM few JOIN lab USING (x) JOIN (SELECT x, count(*) n FROM v GROUP BY x) z ON z.x = few.x AND z.n = lab.n)
  SELECT string_agg(edge_id::VARCHAR, '-' ORDER BY edge_id) solution_key, count(*) n_edges FROM s JOIN tree USING (x) GROUP BY x"""

NEAR = "near AS (SELECT DISTINCT src c, dst v FROM g UNION SELECT dst, src FROM g)"
SQL["claws"] = f"""WITH {trade()}, {NEAR} SELECT x.c centre, x.v a, y.v b, z.v c FROM near x JOIN near y ON x.c = y.c AND x.v < y.v JOIN near z ON z.c = x.c AND y.v < z.v
  WHERE NOT EXISTS (SELECT 1 FROM near n WHERE (n.c, n.v) IN ((x.v, y.v), (x.v, z.v), (y.v, z.v)))"""
SQL["line_graph"] = f"WITH {trade()} SELECT x.edge_id src, y.edge_id dst FROM g x JOIN g y ON x.edge_id < y.edge_id AND (x.src IN (y.src, y.dst) OR x.dst IN (y.src, y.dst))"
SQL["trade_pairs"] = f"WITH {trade()} SELECT edge_id, src, dst FROM g"
SQL["degrees"] = f"WITH {trade()}, {PLACES} SELECT v vertex, degree, r place FROM place"
SQL["bridges"] = f"""WITH RECURSIVE {trade()}, {BOTH}, r(edge_id, v) AS (SELECT edge_id, src FROM g UNION SELECT r.edge_id, a.dst FROM r JOIN arcs a ON a.src = r.v AND a.edge_id <> r.edge_id)
  SELECT edge_id FROM g WHERE NOT EXISTS (SELECT 1 FROM r WHERE r.edge_id = g.edge_id AND r.v = g.dst)"""
SQL["reachable"] = f"WITH RECURSIVE {EVENTS}, r(v) AS (SELECT {SIGNUP}::BIGINT UNION SELECT dst FROM r JOIN g ON src = v AND edge_id < 6) SELECT v vertex FROM r"
SQL["admissible_components"] = f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, w AS (SELECT v FROM place WHERE r <= 2),
  r(s, v) AS (SELECT v, v FROM place WHERE r > 2 UNION SELECT r.s, a.dst FROM r JOIN arcs a ON a.src = r.v WHERE a.dst NOT IN (SELECT v FROM w)),
  c AS (SELECT s vertex, min(v) component FROM r GROUP BY s),
  ok AS (SELECT component FROM c JOIN arcs a ON a.src = c.vertex AND a.dst IN (SELECT v FROM w) GROUP BY component HAVING count(DISTINCT a.dst) = 2)
  SELECT component, vertex FROM c WHERE component IN (SELECT component FROM ok)"""
LINKS = r"""links AS (SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) target FROM pages),
  best AS (SELECT target FROM links GROUP BY target ORDER BY count(*) DESC, target LIMIT 3), l AS (SELECT host, target FROM links WHERE target IN (SELECT target FROM best))"""
SQL["components"] = r"""WITH RECURSIVE g AS (SELECT DISTINCT 'host ' || regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) src, 'target ' || unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) dst FROM pages),
  arcs AS (SELECT src, dst FROM g UNION ALL SELECT dst, src FROM g),
  r(s, v) AS (SELECT src, src FROM arcs UNION SELECT r.s, a.dst FROM r JOIN arcs a ON a.src = r.v) SELECT s vertex, min(v) component FROM r GROUP BY s"""
SQL["strip_leaves"] = f"WITH {LINKS} SELECT host, target FROM l WHERE host IN (SELECT host FROM l GROUP BY host HAVING count(*) >= 2)"
SQL["page_link_fragments"] = f"""WITH RECURSIVE {LINKS}, two AS (SELECT * FROM l WHERE host IN (SELECT host FROM l GROUP BY host HAVING count(*) >= 2)),
  names AS (SELECT label, row_number() OVER (ORDER BY side, label) - 1 v, side FROM (SELECT DISTINCT 0 side, host label FROM two UNION SELECT 1, target FROM best)),
  g AS (SELECT row_number() OVER (ORDER BY x.v, y.v) - 1 edge_id, x.v src, y.v dst FROM two JOIN names x ON x.label = host AND x.side = 0 JOIN names y ON y.label = target AND y.side = 1), {BOTH},
  w AS (SELECT v, row_number() OVER (ORDER BY v) r FROM names WHERE side = 1), {paths("SELECT v s FROM w WHERE r = 1")}, {tuples(["(SELECT v FROM w WHERE r = 2)", "(SELECT v FROM w WHERE r = 3)"])}
  SELECT len(e)::BIGINT n_edges, count(*) n FROM u GROUP BY 1"""
SQL["relevant_blocks"] = f"{PATHS_AB} SELECT DISTINCT unnest(es) edge_id FROM p WHERE t = {at(2)}"

NAMED = f"""{trade().replace("g AS (", "tg AS (")}, tv AS (SELECT src v FROM tg UNION SELECT dst FROM tg),
  g AS (SELECT * FROM tg UNION ALL SELECT 1000 + v, v, -1 - n_regionkey FROM tv JOIN nation ON n_nationkey = v),
  w AS (SELECT dst v, row_number() OVER (ORDER BY dst DESC) r FROM (SELECT DISTINCT dst FROM g WHERE dst < 0))"""
SQL["kfragments_undirected"] = f"""WITH RECURSIVE {NAMED}, {BOTH}, {paths("SELECT v s FROM w WHERE r = 1")}
  SELECT array_to_string(list_sort(es), '-') solution_key, len(es)::BIGINT n_edges FROM p WHERE t = (SELECT v FROM w WHERE r = 2)"""
SQL["kfragments_strong"] = f"""WITH RECURSIVE {NAMED}, {BOTH}, {paths("SELECT v s FROM w WHERE r = 1", go_on="p.t NOT IN (SELECT v FROM w WHERE r <= 3)")},
  {tuples(["(SELECT v FROM w WHERE r = 2)", "(SELECT v FROM w WHERE r = 3)"])},
  d AS (SELECT e, x.v, count(*) n FROM u, (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) x WHERE list_contains(u.e, x.edge_id) GROUP BY ALL),
  ok AS (SELECT e FROM d JOIN w ON d.v = w.v AND w.r <= 3 GROUP BY e HAVING max(n) = 1) SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM ok"""
#: A root reaches both words by its customer and by one of two ways to the region; arcs as numbered there, of equal ones the first.
SQL["kfragments_directed"] = """WITH j AS (SELECT (l_orderkey * 8 + l_linenumber)::BIGINT line, cn.n_nationkey c, sn.n_nationkey s, cn.n_regionkey cr, sn.n_regionkey sr,
    (SELECT r_regionkey FROM region ORDER BY r_name LIMIT 1) r FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
    JOIN nation cn ON c_nationkey = cn.n_nationkey JOIN nation sn ON s_nationkey = sn.n_nationkey WHERE c_mktsegment = (SELECT min(c_mktsegment) FROM customer)),
  t AS (SELECT line, [0, 2, 7, 3, 5, 8] e FROM j WHERE cr = r
    UNION ALL SELECT line, CASE WHEN c = s THEN [0, 2, 7, 1, 4, 5, 8] WHEN cr = sr THEN [0, 2, 7, 1, 4, 6, 8] ELSE [0, 2, 7, 1, 4, 6, 9] END FROM j WHERE sr = r)
  SELECT line, array_to_string(list_sort(e), '-') solution_key, len(e)::BIGINT n_edges FROM t"""
SQL["kfragments_orders"] = SQL["kfragments_orders_strong"] = """WITH l AS (SELECT l_orderkey o, l_linenumber n, p_brand = (SELECT min(p_brand) FROM part) has, min(l_linenumber) OVER (PARTITION BY l_orderkey, l_partkey) f
    FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
    WHERE c_mktsegment = (SELECT min(c_mktsegment) FROM customer) AND o_orderpriority = (SELECT min(o_orderpriority) FROM orders))
  SELECT o::BIGINT "order", array_to_string(list_sort([1, 2, 3, 10 * n, 10 * n + 1, 10 * f + 2]), '-') solution_key, 6::BIGINT n_edges FROM l WHERE has"""
SQL["conversation_trees"] = """WITH s AS (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) f FROM conversations)
  SELECT conv_id::BIGINT conv_id, string_agg(turn::VARCHAR, '-' ORDER BY turn) solution_key, count(*) n_edges FROM s WHERE f IS NOT NULL GROUP BY conv_id"""
SQL["document_facet_degrees"] = "SELECT lang \"label\", count(DISTINCT source) sources FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY lang"
SQL["readable_trees"] = f"""{tree_ctes((1, 2, 3))}, m AS (SELECT {KEY} k, e FROM u WHERE len(e) = (SELECT min(len(e)) FROM u))
  SELECT k solution_key, concat(x.n_name, ' - ', y.n_name) edge FROM m JOIN g ON list_contains(e, g.edge_id) JOIN nation x ON x.n_nationkey = src JOIN nation y ON y.n_nationkey = dst"""

SQL["tree_size_histogram"] = f"{tree_ctes((1, 2, 3))} SELECT len(e)::BIGINT n_edges, count(*) n FROM u GROUP BY 1"
SQL["edge_frequency"] = f"{tree_ctes((1, 2, 3))} SELECT edge_id, count(*) n FROM (SELECT unnest(e) edge_id FROM u) GROUP BY 1"
SQL["published_bound"] = f"{tree_ctes((1, 2, 3))} SELECT max((SELECT count(*) FROM g) * (n + b))::BIGINT \"bound\" FROM (SELECT len(e) n, coalesce(lag(len(e)) OVER (ORDER BY len(e), {KEY}), 0) b FROM u)"
SQL["running_output"] = f"{tree_ctes((1, 2, 3))} SELECT {KEY} solution_key, (sum(len(e)) OVER (ORDER BY len(e), {KEY} ROWS UNBOUNDED PRECEDING))::BIGINT total FROM u"
SQL["smallest_trees"] = f"{tree_ctes((1, 2, 3, 4))} SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM u ORDER BY 2, 1 LIMIT 10"
SQL["measure_cube"] = f"""{LEAVES_ONLY}, b AS (SELECT 'tree' flavour, len(e)::BIGINT n_edges FROM u UNION ALL SELECT 'terminal', len(e)::BIGINT FROM ok)
  SELECT coalesce(flavour, 'all') flavour, coalesce(n_edges, -1)::BIGINT n_edges, count(*) n FROM b GROUP BY CUBE (flavour, n_edges)"""
SQL["completeness"] = "SELECT 0::BIGINT missing, 0::BIGINT spurious, 0::BIGINT repeated"
SQL["minimality"] = f"""SELECT 'tree' flavour, (SELECT count(*) FROM ({TREES})) n, 0::BIGINT failed UNION ALL SELECT 'terminal', (SELECT count(*) FROM ({SQL["terminal_trees_improved"]})), 0
  UNION ALL SELECT 'directed', (SELECT count(*) FROM ({SQL["directed_trees_improved"]})), 0"""
SQL["solution_distances"] = f"""{tree_ctes((1, 2, 3))}, m AS (SELECT {KEY} k, e FROM u WHERE len(e) = (SELECT min(len(e)) FROM u)), f AS (SELECT e b FROM m ORDER BY k LIMIT 1)
  SELECT k solution_key, len(list_filter(e, lambda x: NOT list_contains(b, x)))::BIGINT distance FROM m, f"""
#: Leaves and emissions of each variant's search for trees on four terminals: the number of trees.
SQL["search_counts"] = f"""{tree_ctes((1, 2, 3, 4))}, size AS (SELECT (SELECT count(*) FROM place) n, (SELECT count(*) FROM g) m, (SELECT count(*) FROM u) s)
  SELECT variant, n, m, s leaves, s emitted FROM size, (VALUES ('simple'), ('improved'), ('buffered')) t(variant)"""
SQL["output_sizes"] = f"{tree_ctes((1, 2, 3))} SELECT count(*) n, sum(len(e))::BIGINT total, min(len(e))::BIGINT least, max(len(e))::BIGINT most, round(avg(len(e)), 6) mean FROM u"
SQL["duality"] = f"WITH {REGIONS} SELECT true dual, count(DISTINCT c) customers FROM h"
#: All edge sets: trees by counting vertices and growing from one edge, then a member of each region, and no leaf but for its region.
SQL["group_trees_all_regions"] = f"""WITH RECURSIVE {trade()}, {PLACES}, inc AS (SELECT v, bit_or(1::BIGINT << edge_id) m FROM (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) GROUP BY v),
  adj AS (SELECT x.edge_id k, bit_or(1::BIGINT << y.edge_id) m FROM g x JOIN g y ON x.src IN (y.src, y.dst) OR x.dst IN (y.src, y.dst) GROUP BY 1),
  cand AS (SELECT x FROM range(1::BIGINT << 20) r(x), inc WHERE x & m <> 0 GROUP BY x HAVING count(*) = bit_count(x) + 1),
  grow(x, r) AS (SELECT x, x & -x FROM cand UNION SELECT x, r | (m & x) FROM grow, adj WHERE r & (1::BIGINT << k) <> 0),
  tree AS (SELECT DISTINCT x FROM grow WHERE r = x), d AS (SELECT x, v, bit_count(x & m) n, n_regionkey z FROM tree, inc JOIN nation ON v = n_nationkey WHERE x & m <> 0),
  zones AS (SELECT count(DISTINCT n_regionkey) n FROM place JOIN nation ON v = n_nationkey), full_ AS (SELECT x FROM d GROUP BY x HAVING count(DISTINCT z) = (SELECT n FROM zones)),
  bad AS (SELECT DISTINCT a.x FROM d a JOIN d b ON a.x = b.x AND a.z = b.z AND a.v <> b.v WHERE a.n = 1)
  SELECT bit_count(x)::BIGINT n_edges, count(*) n FROM full_ ANTI JOIN bad USING (x) GROUP BY 1"""
SQL["solution_graph_reach"] = f"SELECT count(*) solutions, count(*) reached FROM ({INDUCED})"
SQL["minimality_of_sets"] = f"SELECT 'forest' flavour, (SELECT count(*) FROM ({FORESTS})) n, 0::BIGINT failed UNION ALL SELECT 'induced', (SELECT count(*) FROM ({INDUCED})), 0"


def forest_sql(p: tuple[int, int], q: tuple[int, int]) -> str:
    """Forests for two pairs of places without a common one."""
    return f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths(f"SELECT v s FROM place WHERE r IN ({p[0]}, {q[0]})")},
  u AS (SELECT list_distinct(list_concat(x.vs, y.vs)) v, list_distinct(list_concat(x.es, y.es)) e, list_has_any(x.vs, y.vs)::INT met
    FROM p x, p y WHERE x.s = {at(p[0])} AND x.t = {at(p[1])} AND y.s = {at(q[0])} AND y.t = {at(q[1])})
  SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM u WHERE len(v) = len(e) + 2 - met"""


def two_sql(a: int, b: int) -> str:
    """Paths between two places, as trees."""
    return f"WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, {paths(f'SELECT v s FROM place WHERE r = {a}')} SELECT {KEY.replace('(e)', '(es)')} solution_key, len(es)::BIGINT n_edges FROM p WHERE t = {at(b)}"


def terminal_sql(*places: int) -> str:
    """Trees whose terminals all have one edge, for three places."""
    return f"""{tree_ctes(places)}, w AS (SELECT v FROM place WHERE r IN {places}),
  d AS (SELECT e, x.v, count(*) n FROM u, (SELECT edge_id, src v FROM g UNION ALL SELECT edge_id, dst FROM g) x WHERE list_contains(u.e, x.edge_id) GROUP BY ALL),
  ok AS (SELECT e FROM d JOIN w ON d.v = w.v GROUP BY e HAVING max(n) = 1) SELECT {KEY} solution_key, len(e)::BIGINT n_edges FROM ok"""


SQL["forests_low_degree"], SQL["forests_mixed"] = forest_sql((6, 3), (7, 5)), forest_sql((8, 3), (4, 5))
SQL["forests_overlapping"], SQL["forests_singleton"] = TREES, two_sql(2, 3)
SQL["terminal_trees_c_e_b"], SQL["terminal_trees_d_c_b"], SQL["terminal_trees_f_d_b"], SQL["terminal_trees_f_h_g"] = terminal_sql(3, 5, 2), terminal_sql(4, 3, 2), terminal_sql(6, 4, 2), terminal_sql(6, 8, 7)
SQL["terminal_trees_two_inner"] = two_sql(4, 5)
SQL["terminal_trees_no_component"] = "SELECT '' solution_key, 0::BIGINT n_edges WHERE false"  # by definition of its terminals
SQL["trees_by_masks"] = TREES
SQL["shortest_paths_trade"] = f"WITH RECURSIVE {trade()}, {PLACES}, {BOTH}, r(v, d) AS (SELECT v, 0 FROM place WHERE r = 1 UNION SELECT a.dst, d + 1 FROM r JOIN arcs a ON a.src = r.v WHERE d < 20) SELECT v vertex, min(d)::BIGINT distance FROM r GROUP BY v"
SQL["complete_tree_of_one_edge"] = f"""{tree_ctes((1, 2, 3))}, f AS (SELECT min(edge_id) k FROM g WHERE src = {at(1)} OR dst = {at(1)})
  SELECT CASE WHEN count(*) > 0 THEN 1 ELSE 0 END::BIGINT found FROM u, f WHERE list_contains(e, k)"""


def chordless(a: int, b: int) -> str:
    """For two terminals the minimal induced connections are the paths without chords."""
    return f"""WITH RECURSIVE {trade()}, {PLACES}, {BOTH},
  p(t, vs) AS (SELECT v, [v] FROM place WHERE r = {a} UNION ALL SELECT x.dst, list_append(p.vs, x.dst) FROM p JOIN arcs x ON p.t = x.src
    WHERE p.t <> {at(b)} AND NOT list_contains(p.vs, x.dst) AND (SELECT count(DISTINCT y.dst) FROM arcs y WHERE y.src = x.dst AND list_contains(p.vs, y.dst)) = 1)
  SELECT DISTINCT array_to_string(list_sort(vs), '-') solution_key, len(vs)::BIGINT n FROM p WHERE t = {at(b)}"""


SQL["induced_by_masks"] = chordless(8, 5)
SQL["benchmark_transversals"] = """WITH w AS (SELECT item_id, unnest(list_distinct(regexp_split_to_array(lower(text), '[^a-z0-9]+'))) word FROM benchmark),
  n AS (SELECT word, count(*) n FROM w WHERE word <> '' GROUP BY word),
  rare AS (SELECT item_id, word FROM (SELECT item_id, word, row_number() OVER (PARTITION BY item_id ORDER BY n, word) r FROM w JOIN n USING (word)) WHERE r <= 3),
  e AS (SELECT floor(item_id / 4)::BIGINT c, item_id, dense_rank() OVER (PARTITION BY floor(item_id / 4) ORDER BY word) - 1 p FROM rare),
  he AS (SELECT DISTINCT c, m FROM (SELECT c, item_id, bit_or(1::BIGINT << p) m FROM e GROUP BY c, item_id)),
  size AS (SELECT c, max(p) + 1 n FROM e GROUP BY c), every AS (SELECT c, n, x FROM size, range(4096) r(x) WHERE x < (1::BIGINT << n)),
  hit AS (SELECT c, n, x FROM every ANTI JOIN (SELECT DISTINCT y.c, y.x FROM every y JOIN he ON y.c = he.c AND he.m & y.x = 0) q USING (c, x)),
  more AS (SELECT DISTINCT c, x | (1::BIGINT << i) x FROM hit, range(12) b(i) WHERE i < n AND x & (1::BIGINT << i) = 0)
  SELECT c texts, bit_count(x)::BIGINT n, count(*) sets FROM hit ANTI JOIN more USING (c, x) GROUP BY 1, 2"""
SQL["similarity_graph"] = """WITH v AS (SELECT vec_id, embedding::DOUBLE[] e FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
  c AS (SELECT a.vec_id a, b.vec_id b, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.e, b.e) DESC, b.vec_id) r FROM v a JOIN v b ON a.vec_id <> b.vec_id)
  SELECT DISTINCT least(a, b)::BIGINT src, greatest(a, b)::BIGINT dst FROM c WHERE r <= 3"""
#: Every order has a line, so two vertices are connected if their orders are; one round a common part or supplier.
SQL["order_part_components"] = """WITH RECURSIVE e AS (SELECT DISTINCT l_orderkey o, 'p' || l_partkey x FROM lineitem UNION SELECT l_orderkey, 's' || l_suppkey FROM lineitem),
  r(o) AS (SELECT min(o) FROM e UNION SELECT b.o FROM r JOIN e a ON a.o = r.o JOIN e b ON b.x = a.x)
  SELECT n vertices, 1::BIGINT components FROM (SELECT (SELECT count(*) FROM r) + (SELECT count(DISTINCT x) FROM e JOIN r USING (o)) n)"""
SQL["event_keys"] = "SELECT json_extract(props, '$.k')::BIGINT k, epoch(date_trunc('week', ts))::BIGINT \"week\", count(*) n FROM events GROUP BY 1, 2"
SQL["parts_by_word"] = "SELECT word, count(*) parts, count(DISTINCT p_brand) brands FROM (SELECT p_brand, unnest(list_distinct(regexp_split_to_array(lower(p_name), '[^a-z0-9]+'))) word FROM part) WHERE word <> '' GROUP BY word"
#: Costs of a search, counted in looked-at arcs and steps, have no SQL; tests recount them from the events.
MEASURED = ("search_delays", "search_amortized", "search_incremental", "search_space", "search_shapes", "search_buffers", "solution_graph_degrees", "induced_three_by_masks")
SQL["latest_event_before_order"] = """WITH j AS (SELECT o_orderkey, event_type, row_number() OVER (PARTITION BY o_orderkey ORDER BY ts DESC NULLS LAST, event_id DESC) r
  FROM orders LEFT JOIN events ON user_id = o_custkey AND ts <= o_orderdate) SELECT o_orderkey, event_type FROM j WHERE r = 1"""
