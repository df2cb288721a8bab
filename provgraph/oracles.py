"""SQL building blocks for the carriers and methods, for an engine with list functions and recursive queries."""

from __future__ import annotations

STAR = """WITH RECURSIVE ship AS (SELECT 'x:' || l_orderkey || '_' || l_linenumber AS x, l_orderkey AS ok, l_suppkey AS sk, l_partkey AS pk, l_shipdate AS t FROM lineitem),
star_n AS (
  SELECT 'r:' || r_regionkey AS node_id, 'activity' AS node_type, 'region' AS kind, NULL AS class, 0 AS level FROM region
  UNION ALL SELECT 'n:' || n_nationkey, 'activity', 'nation', NULL, 0 FROM nation
  UNION ALL SELECT 'c:' || c_custkey, 'activity', 'customer', NULL, 1 FROM customer
  UNION ALL SELECT 's:' || s_suppkey, 'activity', 'supplier', NULL, 1 FROM supplier
  UNION ALL SELECT 'o:' || o_orderkey, 'activity', 'order', NULL, 2 FROM orders
  UNION ALL SELECT 'p:' || p_partkey, 'entity', 'part', CASE WHEN starts_with(p_type, 'PROMO') THEN 'program' ELSE 'dependency' END, 2 FROM part
  UNION ALL SELECT DISTINCT x, 'entity', 'shipment', 'data', 3 FROM ship),
star_e AS (
  SELECT src, dst, label, min(b) AS b, max(b) AS e, count(*) AS n, max(level) AS level FROM (
    SELECT 'n:' || n_nationkey AS src, 'r:' || n_regionkey AS dst, 'wasInformedBy' AS label, NULL::TIMESTAMP AS b, 0 AS level FROM nation
    UNION ALL SELECT 'c:' || c_custkey, 'n:' || c_nationkey, 'wasInformedBy', NULL, 1 FROM customer
    UNION ALL SELECT 's:' || s_suppkey, 'n:' || s_nationkey, 'wasInformedBy', NULL, 1 FROM supplier
    UNION ALL SELECT 'o:' || o_orderkey, 'c:' || o_custkey, 'wasInformedBy', NULL, 2 FROM orders
    UNION ALL SELECT 'o:' || ok, 'p:' || pk, 'used', o_orderdate, 2 FROM ship JOIN orders ON ok = o_orderkey
    UNION ALL SELECT 's:' || sk, x, 'used', t, 3 FROM ship
    UNION ALL SELECT x, 'o:' || ok, 'wasGeneratedBy', t, 3 FROM ship) GROUP BY src, dst, label)
"""

AUDIT = """WITH acc AS (
  SELECT event_id AS seq, ts, 'd:' || user_id || ':' || strftime(ts, '%Y-%m-%d') AS actor,
    CASE WHEN event_type IN ('view', 'click') THEN 'read' WHEN event_type = 'purchase' THEN 'written' WHEN event_type = 'signup' THEN 'spawned' ELSE 'failed' END AS op,
    CASE WHEN event_type = 'signup' THEN 't:' || event_id ELSE 'f:' || (props->>'$.k') END AS object, round(value * 1000000)::BIGINT AS dur_us FROM events),
aud_e AS (
  SELECT CASE WHEN op = 'read' THEN actor ELSE object END AS src, CASE WHEN op = 'read' THEN object ELSE actor END AS dst,
    CASE op WHEN 'read' THEN 'used' WHEN 'written' THEN 'wasGeneratedBy' ELSE 'wasInformedBy' END AS label, min(epoch_us(ts)) AS b, max(epoch_us(ts) + dur_us) AS e, max(epoch_us(ts)) AS lastb, count(*) AS n
  FROM acc WHERE op <> 'failed' GROUP BY ALL
  UNION ALL SELECT DISTINCT actor, 'u:' || split_part(actor, ':', 2), 'wasInformedBy', NULL, NULL, NULL, 1 FROM acc)
"""

HAZARDS = """, hr AS (SELECT dst AS file, src AS reader, b FROM aud_e WHERE label = 'used'), hw AS (SELECT src AS file, dst AS writer, b FROM aud_e WHERE label = 'wasGeneratedBy'),
hazards AS (SELECT reader, hr.file, writer FROM hr JOIN hw ON hr.file = hw.file WHERE reader <> writer AND hw.b > hr.b)
"""

ONE_HOP = """, one_hop AS (SELECT r.src AS process, r.dst AS in_file, w.src AS out_file, r.b <= w.e AS feasible FROM aud_e r JOIN aud_e w ON r.src = w.dst WHERE r.label = 'used' AND w.label = 'wasGeneratedBy' AND r.dst <> w.src)
"""

CONV = """WITH ct AS (SELECT conv_id AS run_id, turn, role, 'm:' || conv_id || '_' || turn AS id, lag(role) OVER w AS was, lag(turn) OVER w AS before FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
conv_n AS (SELECT run_id, id AS node_id, CASE WHEN role = 'assistant' THEN 'activity' ELSE 'entity' END AS node_type FROM ct),
conv_e AS (SELECT a.run_id, a.id AS src, b.id AS dst, 'used' AS label FROM ct a JOIN ct b ON a.run_id = b.run_id AND b.turn < a.turn WHERE a.role = 'assistant' AND b.role <> 'assistant'
  UNION ALL SELECT run_id, id, 'm:' || run_id || '_' || before, 'wasGeneratedBy' FROM ct WHERE role <> 'assistant' AND was = 'assistant')
"""

ORDERS = """WITH li AS (SELECT DISTINCT l_orderkey AS k, l_suppkey AS s, l_partkey AS p FROM lineitem),
ord_n AS (SELECT DISTINCT k AS run_id, 'o:' || k AS node_id, 'activity' AS node_type FROM li UNION ALL SELECT DISTINCT k, 's:' || k || '|' || s, 'activity' FROM li UNION ALL SELECT k, 'p:' || k || '|' || s || '|' || p, 'entity' FROM li),
ord_e AS (SELECT DISTINCT k AS run_id, 's:' || k || '|' || s AS src, 'o:' || k AS dst, 'wasInformedBy' AS label FROM li UNION ALL SELECT k, 's:' || k || '|' || s, 'p:' || k || '|' || s || '|' || p, 'used' FROM li)
"""

NODE_HASH = """, v AS (SELECT src AS node_id, label, dst AS far FROM conv_e UNION ALL SELECT dst, label, src FROM conv_e),
items AS (SELECT v.node_id, list_sort(list(v.label || ' ' || f.node_type))::VARCHAR AS items FROM v JOIN conv_n f ON f.node_id = v.far GROUP BY 1),
sig AS (SELECT n.node_type, coalesce(items, '') AS items FROM conv_n n LEFT JOIN items ON items.node_id = n.node_id)
"""

SIMILAR = """, v AS (SELECT run_id, src AS node_id, 'out ' || label || ' ' || dst AS item FROM conv_e UNION SELECT run_id, dst, 'in ' || label || ' ' || src FROM conv_e),
s AS (SELECT v.run_id, v.node_id, n.node_type, list_sort(list(item))::VARCHAR AS items FROM v JOIN conv_n n ON n.node_id = v.node_id GROUP BY ALL),
alike AS (SELECT run_id, node_id, min(node_id) OVER (PARTITION BY run_id, node_type, items) AS least FROM s)
"""

PACKABLE = """, v AS (SELECT run_id, src AS node_id, 'out' AS side, label, dst AS far FROM ord_e UNION SELECT run_id, dst, 'in', label, src FROM ord_e),
d AS (SELECT v.node_id, n.node_type, count(*) AS deg, count(*) FILTER (side = 'out') AS outs, count(*) FILTER (side = 'out' AND label = 'wasInformedBy') AS parents FROM v JOIN ord_n n ON n.node_id = v.node_id GROUP BY ALL),
packable AS (SELECT node_id, CASE WHEN node_type = 'entity' AND deg = 1 THEN 1 WHEN node_type = 'activity' AND parents = 1 AND outs = 1 THEN 2 END AS rule FROM d WHERE node_type = 'entity' AND deg = 1 OR node_type = 'activity' AND parents = 1 AND outs = 1)
"""

ARRIVAL = """, f AS (SELECT dst AS src, src AS dst, coalesce(b, TIMESTAMP '0001-01-01') AS b, coalesce(e, TIMESTAMP '9999-12-31 23:59:59.999999') AS e FROM star_e),
arr AS (SELECT 'p:0' AS node_id, TIMESTAMP '0001-01-01' AS t UNION SELECT f.dst, greatest(arr.t, f.b) FROM arr JOIN f ON f.src = arr.node_id WHERE arr.t <= f.e)
"""


def reach_sql(seed: str) -> str:
    """Everything downstream of ``seed`` in the star graph, as hit(node_id)."""
    return f", hit AS (SELECT '{seed}' AS node_id UNION SELECT src FROM star_e JOIN hit ON dst = hit.node_id)\n"


def spawn_sql(seed: str) -> str:
    return f", hit AS (SELECT '{seed}' AS node_id UNION SELECT src FROM star_e JOIN hit ON dst = hit.node_id WHERE label = 'wasInformedBy')\n"


LO, HI = "(-62135596800000000)", "253402300799999999"  # the first and last instants, in microseconds


def spread_sql(seed: str, rounds: int, as_of: str | None = None) -> str:
    """best(node_id, t) in the audit graph after ``rounds``: earliest arrivals from ``seed``, or latest departures towards it up to
    ``as_of``. A daily process is spawned at its first access."""
    timed = """born AS (SELECT actor, min(epoch_us(ts)) AS t FROM acc GROUP BY 1),
    aud_t AS (SELECT src, dst, coalesce(b, born.t) AS b, coalesce(e, born.t) AS e FROM aud_e LEFT JOIN born ON actor = src AND starts_with(dst, 'u:'))"""
    if as_of is None:
        way = f"SELECT dst AS src, src AS dst, coalesce(b, {LO}) AS b, coalesce(e, {HI}) AS e FROM aud_t"
        start, step = LO, "min(t) AS t FROM (SELECT node_id, t FROM b{k} UNION ALL SELECT dst, greatest(t, b) FROM b{k} JOIN way ON src = node_id WHERE greatest(t, b) <= e)"
    else:
        start = f"epoch_us(TIMESTAMP '{as_of}')"
        way = f"SELECT src, dst, coalesce(b, {LO}) AS b, least(coalesce(e, {HI}), {start}) AS e FROM aud_t WHERE coalesce(b, {LO}) <= {start}"
        step = "max(t) AS t FROM (SELECT node_id, t FROM b{k} UNION ALL SELECT dst, least(t, e) FROM b{k} JOIN way ON src = node_id WHERE least(t, e) >= b)"
    parts = [timed, f"way AS MATERIALIZED ({way})", f"b0 AS (SELECT '{seed}' AS node_id, {start} AS t)"]
    parts += [f"b{k + 1} AS MATERIALIZED (SELECT node_id, {step.format(k=k)} GROUP BY 1)" for k in range(rounds)]
    return ", " + ", ".join(parts) + f", best AS (SELECT * FROM b{rounds} WHERE node_id <> '{seed}')\n"


def _quotient(nodes: str, edges: str, merges: str) -> str:
    return f"""SELECT DISTINCT s.node_id AS src, d.node_id AS dst, CASE WHEN s.node_type = 'activity' AND d.node_type = 'activity' THEN 'wasInformedBy' ELSE e.label END AS label
      FROM {edges} e LEFT JOIN {merges} a ON a.child = e.src LEFT JOIN {merges} b ON b.child = e.dst
      JOIN {nodes} s ON s.node_id = coalesce(a.parent, e.src) JOIN {nodes} d ON d.node_id = coalesce(b.parent, e.dst) WHERE s.node_id <> d.node_id"""


def collapse(nodes: str, edges: str, p: str = "k") -> str:
    """One round of collapsing: {p}m (step, rule, child, parent), {p}n (node_id, node_type) and {p}e (src, dst, label) of the outcome."""
    view = "SELECT src AS node_id, 'out' AS side, label, dst AS far FROM {0} UNION SELECT dst, 'in', label, src FROM {0}"
    return f""", {p}v0 AS ({view.format(edges)}),
    {p}s0 AS (SELECT v.node_id, n.node_type, array_to_string(list_sort(list(side || ' ' || v.label || ' ' || far)), chr(10)) AS items FROM {p}v0 v JOIN {nodes} n ON n.node_id = v.node_id GROUP BY ALL),
    {p}m0 AS MATERIALIZED (SELECT node_id AS child, least AS parent FROM (SELECT node_id, min(node_id) OVER (PARTITION BY node_type, items) AS least FROM {p}s0) WHERE node_id <> least),
    {p}n1 AS MATERIALIZED (SELECT node_id, node_type FROM {nodes} WHERE node_id NOT IN (SELECT child FROM {p}m0)),
    {p}e1 AS MATERIALIZED ({_quotient(f"{p}n1", edges, f"{p}m0")}),
    {p}v1 AS ({view.format(f"{p}e1")}),
    {p}d1 AS (SELECT v.node_id, n.node_type, count(*) AS deg, max(far) AS only_far, count(*) FILTER (side = 'out') AS outs,
      count(*) FILTER (side = 'out' AND label = 'wasInformedBy') AS parents, max(far) FILTER (side = 'out' AND label = 'wasInformedBy') AS parent_proc,
      count(*) FILTER (side = 'out' AND label = 'wasGeneratedBy') AS makers, max(far) FILTER (side = 'out' AND label = 'wasGeneratedBy') AS maker,
      count(*) FILTER (side = 'in' AND label = 'used') AS users, max(far) FILTER (side = 'in' AND label = 'used') AS user_proc FROM {p}v1 v JOIN {p}n1 n ON n.node_id = v.node_id GROUP BY ALL),
    {p}p1 AS MATERIALIZED (SELECT node_id AS child, CASE WHEN node_type = 'entity' AND deg = 1 THEN 1 WHEN node_type = 'activity' AND parents = 1 AND outs = 1 THEN 2
      WHEN node_type = 'entity' AND makers = 1 AND users = 1 AND maker <> user_proc THEN 3 END AS rule, CASE rule WHEN 1 THEN only_far WHEN 2 THEN parent_proc WHEN 3 THEN maker END AS parent FROM {p}d1 WHERE rule IS NOT NULL),
    {p}up AS (SELECT child, rule, parent FROM {p}p1 UNION SELECT u.child, u.rule, q.parent FROM {p}up u JOIN {p}p1 q ON q.child = u.parent),
    {p}m1 AS MATERIALIZED (SELECT child, rule, parent FROM {p}up WHERE parent NOT IN (SELECT child FROM {p}p1)),
    {p}n AS MATERIALIZED (SELECT node_id, node_type FROM {p}n1 WHERE node_id NOT IN (SELECT child FROM {p}m1)),
    {p}e AS MATERIALIZED ({_quotient(f"{p}n", f"{p}e1", f"{p}m1")}),
    {p}m AS (SELECT 0 AS step, 'similarity' AS rule, child, parent FROM {p}m0 UNION ALL SELECT 1, 'pack' || rule, child, parent FROM {p}m1)
"""


def sizes(p: str = "k") -> str:
    return f"(SELECT count(*) FROM {p}n WHERE node_type = 'activity') AS activities, (SELECT count(*) FROM {p}n WHERE node_type = 'entity') AS entities, (SELECT count(*) FROM {p}e) AS edges"


def by_method() -> str:
    """Sizes of the conversations' summaries by method: groups of activities, of entities, and edges between groups."""
    body, rows = recursive(CONV) + collapse("conv_n", "conv_e"), ["SELECT 'collapse' AS method, " + sizes()]
    for k, (name, sides, counted) in enumerate((("ancestry", ("out",), False), ("ancestry_degree", ("out", "in"), True), ("relationship", ("out", "in"), False))):
        body += f", g{k} AS MATERIALIZED ({refine('conv_n', 'conv_e', sides, counted, 14, top=False)})"
        count = lambda t: f"(SELECT count(DISTINCT group_id) FROM g{k} JOIN conv_n x ON x.node_id = g{k}.node_id WHERE node_type = '{t}')"  # noqa: B023, E731
        rows.append(f"SELECT '{name}', {count('activity')}, {count('entity')}, (SELECT count(*) FROM (SELECT DISTINCT a.group_id AS s, b.group_id AS d, label FROM conv_e JOIN g{k} a ON a.node_id = src JOIN g{k} b ON b.node_id = dst))")
    return body + " UNION ALL ".join(rows)


def peel_sql(edges: str, rounds: int) -> str:
    """rest(src, dst): the edges left of ``edges`` when nodes without outgoing edges have been taken away ``rounds`` times."""
    parts = [f"q0 AS (SELECT src, dst FROM {edges})", *(f"q{k + 1} AS MATERIALIZED (SELECT * FROM q{k} WHERE dst IN (SELECT src FROM q{k}))" for k in range(rounds))]
    return ", " + ", ".join(parts) + f", rest AS (SELECT * FROM q{rounds})\n"


def recursive(sql: str) -> str:
    return sql.replace("WITH ", "WITH RECURSIVE ", 1)


PAGES = r"""WITH h AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages),
page_n AS (SELECT 'g:' || page_id AS node_id, 'activity' AS node_type, url AS label FROM pages UNION ALL SELECT DISTINCT 'h:' || href, 'entity', href FROM h),
page_e AS (SELECT 'g:' || page_id AS src, 'h:' || href AS dst, 'used' AS label FROM h)
"""


def reductions() -> str:
    """Reductions by graph and method with their means, over all the graphs."""
    graphs = {"orders": ("ord_n", "ord_e", 6), "conversations": ("conv_n", "conv_e", 14), "pages": ("page_n", "page_e", 10), "star": ("star_n", "star_e", 16)}
    methods = {"ancestry": (("out",), False), "ancestry_degree": (("out", "in"), True), "relationship": (("out", "in"), False)}
    body = STAR + "".join(", " + x.split("WITH ", 1)[1] for x in (CONV, ORDERS, PAGES))
    rows = []
    share = "round(1 - {0}::DOUBLE / {1}, 6)"

    def row(graph: str, method: str, n: str, e: str, files: str, processes: str, edges: str) -> str:
        all_ = (f"(SELECT count(*) FROM {n} WHERE node_type = 'entity')", f"(SELECT count(*) FROM {n} WHERE node_type = 'activity')", f"(SELECT count(*) FROM (SELECT DISTINCT src, dst, label FROM {e}))")
        return f"SELECT '{graph}' AS graph, '{method}' AS method, " + ", ".join(share.format(a, b) + f" AS {c}" for a, b, c in zip((files, processes, edges), all_, ("files", "processes", "edges"), strict=True))

    for k, (graph, (n, e, rounds)) in enumerate(graphs.items()):
        body += collapse(n, e, f"g{k}_")
        rows.append(row(graph, "collapse", n, e, *(f"(SELECT count(*) FROM g{k}_n WHERE node_type = '{t}')" for t in ("entity", "activity")), f"(SELECT count(*) FROM g{k}_e)"))
        for m, (method, (sides, counted)) in enumerate(methods.items()):
            g = f"g{k}_{m}"
            body += f", {g} AS MATERIALIZED ({refine(n, e, sides, counted, rounds, top=False)})"
            count = lambda t: f"(SELECT count(DISTINCT group_id) FROM {g} JOIN {n} x ON x.node_id = {g}.node_id WHERE node_type = '{t}')"  # noqa: B023, E731
            between = f"(SELECT count(*) FROM (SELECT DISTINCT a.group_id AS s, b.group_id AS d, label FROM {e} JOIN {g} a ON a.node_id = src JOIN {g} b ON b.node_id = dst))"
            rows.append(row(graph, method, n, e, count("entity"), count("activity"), between))
    body += ", red AS MATERIALIZED (" + " UNION ALL ".join(rows) + ")"
    return body + " SELECT * FROM red UNION ALL SELECT 'mean', method, " + ", ".join(f"round(avg({c}), 6)" for c in ("files", "processes", "edges")) + " FROM red GROUP BY method"


def refine(nodes: str, edges: str, sides: tuple[str, ...], counted: bool, rounds: int, top: bool = True, degrees: bool = False) -> str:
    """Colour refinement unrolled: a colour is the least node of a group; (node_id, group_id) after ``rounds``.

    ``degrees``: nodes start apart if their numbers of edges by label and direction differ.
    """
    views = []
    if "out" in sides:
        views.append(f"SELECT src AS node_id, 'out ' || label AS way, dst AS far FROM {edges}")
    if "in" in sides:
        views.append(f"SELECT dst AS node_id, 'in ' || label AS way, src AS far FROM {edges}")
    parts = [f"seen AS MATERIALIZED ({' UNION ALL '.join(views)})", f"c0 AS MATERIALIZED (SELECT node_id, min(node_id) OVER (PARTITION BY node_type) AS g FROM {nodes})"]
    if degrees:
        parts[1:] = [
            f"deg AS (SELECT node_id, way, count(*) AS n FROM (SELECT src AS node_id, 'out ' || label AS way FROM {edges} UNION ALL SELECT dst, 'in ' || label FROM {edges}) GROUP BY ALL)",
            "degs AS (SELECT node_id, array_to_string(list_sort(list(way || ' ' || n)), ',') AS s FROM deg GROUP BY 1)",
            f"c0 AS MATERIALIZED (SELECT x.node_id, min(x.node_id) OVER (PARTITION BY node_type, coalesce(s, '')) AS g FROM {nodes} x LEFT JOIN degs ON degs.node_id = x.node_id)",
        ]
    for k in range(rounds):
        item = "list(way || ' ' || g)" if counted else "list(DISTINCT way || ' ' || g)"
        parts.append(f"i{k} AS (SELECT seen.node_id, array_to_string(list_sort({item}), ',') AS items FROM seen JOIN c{k} ON c{k}.node_id = far GROUP BY 1)")
        parts.append(f"c{k + 1} AS MATERIALIZED (SELECT c{k}.node_id, min(c{k}.node_id) OVER (PARTITION BY g, coalesce(items, '')) AS g FROM c{k} LEFT JOIN i{k} ON i{k}.node_id = c{k}.node_id)")
    last = f"SELECT node_id, g AS group_id FROM c{rounds}"
    return (", " + ", ".join(parts) + " " + last) if top else "WITH " + ", ".join(parts) + " " + last
