"""DuckDB SQL for the queries, put together from the same definitions as the plans."""

from __future__ import annotations

_NEXT_ORDER = "o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY {by} ORDER BY o_orderdate, o_orderkey) AS b FROM orders"
_GRAMS = "(SELECT DISTINCT {key}, array_to_string(w[i : i + 7], ' ') AS gram FROM (SELECT {key}, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT {key}, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda x: x <> '') AS w FROM {table})))"

#: Pairs (a, b) of each workload.
PAIRS = {
    "part_supplier_matrix": "SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b FROM lineitem",
    "customer_part_matrix": "SELECT o_custkey * 2 AS a, l_partkey * 2 + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "event_grid": "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON y.event_id = x.event_id + 25 OR (y.event_id = x.event_id + 1 AND x.event_id % 25 < 24)",
    "order_mesh": f"SELECT {_NEXT_ORDER.format(by='o_custkey')} UNION ALL SELECT {_NEXT_ORDER.format(by='o_orderpriority, year(o_orderdate)')}",
    "part_co_order": "SELECT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y USING (l_orderkey)",
    "supplier_co_order": "SELECT x.l_suppkey AS a, y.l_suppkey AS b FROM lineitem x JOIN lineitem y USING (l_orderkey)",
    "bulk_order_part": "SELECT l_orderkey * 2 AS a, l_partkey * 2 + 1 AS b FROM lineitem WHERE l_quantity >= 45",
    "bulk_supplier_part": "SELECT l_suppkey * 2 AS a, l_partkey * 2 + 1 AS b FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'",
    "bulk_order_chain": "SELECT l_orderkey AS a, lead(l_orderkey) OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber) AS b FROM lineitem WHERE l_quantity >= 45",
    "embedding_neighbors": "SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id WHERE list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) >= 0.35",
    "document_lines": "SELECT x.doc_id AS a, y.doc_id AS b FROM lines x JOIN lines y USING (line) JOIN (SELECT line FROM lines GROUP BY line HAVING count(*) BETWEEN 2 AND 20) USING (line) UNION ALL SELECT doc_id, low FROM lines JOIN (SELECT line, min(doc_id) AS low FROM lines GROUP BY line HAVING count(*) > 20) USING (line)",
    "page_links": "SELECT page_id * 2 AS a, (dense_rank() OVER (ORDER BY encode(href)) - 1) * 2 + 1 AS b FROM hrefs JOIN (SELECT href FROM hrefs GROUP BY href HAVING count(*) >= 2) USING (href)",
    "page_domains": "SELECT page_id * 2 AS a, (dense_rank() OVER (ORDER BY encode(domain)) - 1) * 2 + 1 AS b FROM (SELECT page_id, regexp_extract(url, '^[a-z]+://(?:(?:www|m|blog)\\.)?([^/:?#]+)', 1) AS domain FROM pages) WHERE domain <> ''",
    "user_activity": "SELECT user_id * 2 AS a, (epoch_us(ts) // 3600000000) * 2 + 1 AS b FROM events",
    "event_user_chain": "SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events",
    "customer_order_chain": f"SELECT {_NEXT_ORDER.format(by='o_custkey')}",
    "conversation_turns": "SELECT k AS a, lead(k) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM (SELECT DISTINCT conv_id, turn, conv_id * 4096 + turn AS k FROM conversations)",
    "geo_tree": "SELECT o_orderkey * 4 AS a, o_custkey * 4 + 1 AS b FROM orders UNION ALL SELECT c_custkey * 4 + 1, c_nationkey::BIGINT * 4 + 2 FROM customer UNION ALL SELECT n_nationkey::BIGINT * 4 + 2, n_regionkey::BIGINT * 4 + 3 FROM nation",
    "supplier_geo_tree": "SELECT s_suppkey * 4 AS a, s_nationkey::BIGINT * 4 + 2 AS b FROM supplier UNION ALL SELECT n_nationkey::BIGINT * 4 + 2, n_regionkey::BIGINT * 4 + 3 FROM nation WHERE n_nationkey IN (SELECT s_nationkey FROM supplier)",
    "benchmark_overlap": f"SELECT doc_id * 2 AS a, item_id * 2 + 1 AS b FROM {_GRAMS.format(key='doc_id', table='documents')} JOIN {_GRAMS.format(key='item_id', table='benchmark')} USING (gram)",
}
PAIRS["with_isolated"] = PAIRS["bulk_order_part"]
PAIRS["directed_order_chain"] = PAIRS["customer_order_chain"]
_EXTRA = {
    "document_lines": "lines AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 60), ",
    "page_links": "hrefs AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages), ",
}


def edges(name: str) -> str:
    """CTEs ``e(src, dst)`` and ``v(id)``."""
    directed = name == "directed_order_chain"
    both = "SELECT a AS src, b AS dst FROM raw" + ("" if directed else " UNION ALL SELECT b, a FROM raw")
    ends = "SELECT src AS id FROM e" + (" UNION SELECT dst FROM e" if directed else "") + (" UNION SELECT p_partkey * 2 + 1 FROM part" if name == "with_isolated" else "")
    return f"{_EXTRA.get(name, '')}raw AS ({PAIRS[name]}), e AS MATERIALIZED (SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM ({both}) WHERE src <> dst), v AS (SELECT DISTINCT id::BIGINT AS id FROM ({ends}))"


def labels(name: str) -> str:
    """``edges`` and ``lab(it, id, component, old, changed)``: labels before (0) and after each synchronous sweep."""
    return f"""{edges(name)}, lab(it, id, component, old, changed) AS (
  SELECT 0, id, id, id, 1::BIGINT FROM v
  UNION ALL
  SELECT it + 1, id, low, component, sum(ch) OVER () FROM (
    SELECT l.it, l.id, l.component, least(l.component, coalesce(m.c, l.component)) AS low, coalesce((m.c < l.component)::BIGINT, 0) AS ch
    FROM lab l LEFT JOIN (SELECT e.src, min(x.component) AS c FROM e JOIN lab x ON x.id = e.dst GROUP BY e.src) m ON m.src = l.id
    WHERE l.changed > 0)), s AS (SELECT max(it) AS sweeps FROM lab), final AS (SELECT id, component FROM lab, s WHERE it = sweeps)"""


def history(name: str, order: str = "sync") -> str:
    """``edges``, ``hist(it, id, before, after)`` of every sweep, and ``s(sweeps)``."""
    if order == "sync":
        return f"{labels(name)}, hist AS MATERIALIZED (SELECT it, id, old AS before, component AS after FROM lab WHERE it > 0)"
    # a step either lets labels climb to larger neighbours or, if none did, begins the next sweep with what larger ones say
    return f"""{edges(name)}, run(step, it, id, prev, cur, climbing, moved) AS (
  SELECT 0, 1, id, id, id, 1::BIGINT, 1::BIGINT FROM v
  UNION ALL
  SELECT step + 1, nit, id, nprev, ncur, sum((ncur <> cur)::BIGINT) OVER () + (climbing = 0)::BIGINT, sum((ncur <> nprev)::BIGINT) OVER () + (climbing = 0)::BIGINT FROM (
    SELECT l.step, l.id, l.cur, l.climbing, l.it + (l.climbing = 0)::INTEGER AS nit, CASE WHEN l.climbing = 0 THEN l.cur ELSE l.prev END AS nprev,
           least(l.cur, coalesce(CASE WHEN l.climbing = 0 THEN m.above ELSE m.below END, l.cur)) AS ncur
    FROM run l LEFT JOIN (SELECT e.src, min(x.cur) FILTER (x.id > e.src) AS above, min(x.cur) FILTER (x.id < e.src) AS below FROM e JOIN run x ON x.id = e.dst GROUP BY e.src) m ON m.src = l.id
    WHERE l.climbing > 0 OR l.moved > 0)),
hist AS (SELECT it, id, any_value(prev) AS before, arg_max(cur, step) AS after FROM run GROUP BY it, id), s AS (SELECT max(it) AS sweeps FROM hist)"""


def queue(name: str) -> str:
    """``edges`` and ``q(id, parent, dist, rank)`` from the smallest id."""
    return f"""{edges(name)}, q(id, parent, dist, rank) USING KEY (id) AS (
  SELECT min(id), NULL::BIGINT, 0, 0::BIGINT FROM v
  UNION
  SELECT dst, parent, dist + 1, n + row_number() OVER (ORDER BY pr, dst) - 1 FROM (
    SELECT e.dst, arg_min(q.id, q.rank) AS parent, min(q.rank) AS pr, max(q.dist) AS dist FROM q JOIN e ON e.src = q.id
    WHERE NOT EXISTS (SELECT 1 FROM recurring.q x WHERE x.id = e.dst) GROUP BY e.dst), (SELECT count(*) AS n FROM recurring.q))"""


STATIC = {"static-taken": 1, "static-not-taken": 0}


def fold(outcomes: str, bits: int, start: str = "0::BIGINT") -> str:
    """``misses * states + end`` of a list of 0 and 1, from a start state."""
    n = 1 << bits
    half, top = n // 2, n - 1
    return (
        f"list_reduce(list_prepend({start}, {outcomes}), lambda a, x: CASE WHEN x = 1 THEN (a // {n} + (a % {n} < {half})::BIGINT) * {n} + least({top}, a % {n} + 1)"
        f" ELSE (a // {n} + (a % {n} >= {half})::BIGINT) * {n} + greatest(0, a % {n} - 1) END)"
    )


def _sites(tables: dict[str, str], first: int, bits: int | str) -> str:
    """``one(it, site, evaluations, taken, mispredictions)`` from tables ``(it, k, n, taken, o)`` by site.

    A row is a piece of an iteration's trace, the ``k``-th, whose outcomes ``o`` lists in
    order. Pieces are folded from every state, and their functions (one wide number each)
    walked through piece by piece; then iterations follow each other.
    """
    if bits in STATIC:
        missed = "sum(n) - sum(taken)" if STATIC[bits] else "sum(taken)"
        return "one AS (" + " UNION ALL ".join(f"SELECT it, '{site}' AS site, sum(n)::BIGINT AS evaluations, sum(taken)::BIGINT AS taken, ({missed})::BIGINT AS mispredictions FROM {t} GROUP BY it" for site, t in tables.items()) + ")"
    n = 1 << bits
    wide = 1 << (120 // n)
    powers = "[" + ", ".join(f"{wide**i}::HUGEINT" for i in range(n)) + "]"
    told = " UNION ALL ".join(f"SELECT it, '{site}' AS site, k, n, taken, o FROM {t}" for site, t in tables.items())
    code = f"((f // list_extract({powers}, (a % {n})::INTEGER + 1)) % {wide})"
    return f"""told AS MATERIALIZED ({told}),
piece AS (SELECT it, site, k, sum({fold('o', bits, 'st')}::HUGEINT * list_extract({powers}, st::INTEGER + 1)) AS f FROM told, range({n}) r(st) GROUP BY it, site, k),
pieces AS (SELECT it, site, list(f::HUGEINT ORDER BY k) AS fs FROM piece GROUP BY it, site),
fn AS MATERIALIZED (SELECT it, site, st, list_reduce(list_prepend(st::HUGEINT, fs), lambda a, f: (a // {n} + {code} // {n}) * {n} + {code} % {n})::BIGINT AS code FROM pieces, range({n}) r(st)),
walk(site, it, state, missed) AS (
  SELECT DISTINCT site, {first - 1}::BIGINT, 0::BIGINT, 0::BIGINT FROM told
  UNION ALL SELECT f.site, f.it::BIGINT, f.code % {n}, f.code // {n} FROM walk w JOIN fn f ON f.site = w.site AND f.it = w.it + 1 AND f.st = w.state),
one AS (SELECT t.it, t.site, t.n AS evaluations, t.taken, missed AS mispredictions FROM (SELECT it, site, sum(n)::BIGINT AS n, sum(taken)::BIGINT AS taken FROM told GROUP BY it, site) t JOIN walk w ON w.site = t.site AND w.it = t.it)"""


def _loops(d: str, bits: int | str) -> str:
    """Outcomes of a loop of ``d`` trips; from as many trips as a counter has states on, a trip more changes neither state nor misses."""
    most = 1 if bits in STATIC else 1 << bits
    return f"list_append(list_transform(range(least({d}, {most})), lambda x: 1::BIGINT), 0)"


def cc_sites(name: str, bits: int | str = 2, order: str = "sync") -> str:
    """``history`` and ``sites(variant, it, site, evaluations, taken, mispredictions)``."""
    heard = "b.before" if order == "sync" else "CASE WHEN e.dst < e.src THEN b.after ELSE b.before END"
    return f"""{history(name, order)}, its AS (SELECT unnest(range(1, sweeps + 1)) AS it, sweeps FROM s),
deg AS MATERIALIZED (SELECT v.id, count(e.src) AS d FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id),
t_sweep AS (SELECT it, 0::BIGINT AS k, (1 + (it = sweeps)::BIGINT) AS n, 1::BIGINT AS taken, CASE WHEN it = sweeps THEN [1, 0] ELSE [1] END::BIGINT[] AS o FROM its),
t_vertex AS (SELECT it, 0::BIGINT AS k, (SELECT count(*) FROM v) + 1 AS n, (SELECT count(*) FROM v) AS taken, {_loops('(SELECT count(*) FROM v)', bits)} AS o FROM its),
t_near AS (SELECT it, k, n, taken, o FROM its, (SELECT k, count(*) + sum(d)::BIGINT AS n, sum(d)::BIGINT AS taken, flatten(list({_loops('d', bits)} ORDER BY id)) AS o FROM (SELECT *, row_number() OVER (ORDER BY id) // 64 AS k FROM deg) GROUP BY k)),
outcome AS (
  SELECT it, src, dst, (heard < least(own, coalesce(min(heard) OVER (PARTITION BY it, src ORDER BY dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), own)))::BIGINT AS t
  FROM (SELECT a.it, e.src, e.dst, {heard} AS heard, a.before AS own FROM e JOIN hist a ON a.id = e.src JOIN hist b ON b.id = e.dst AND b.it = a.it)),
t_test AS (SELECT it, k, count(*) AS n, sum(t)::BIGINT AS taken, list(t ORDER BY src, dst) AS o FROM (SELECT *, row_number() OVER (PARTITION BY it ORDER BY src, dst) // 256 AS k FROM outcome) GROUP BY it, k),
{_sites({'cc.sweep': 't_sweep', 'cc.vertex': 't_vertex', 'cc.neighbor': 't_near', 'cc.test': 't_test'}, 1, bits)},
sites AS (SELECT 'conditional' AS variant, * FROM one UNION ALL SELECT 'unconditional', * FROM one WHERE site <> 'cc.test')"""


def bfs_sites(name: str, bits: int | str = 2) -> str:
    """``queue`` and ``sites`` of the search; an iteration is a level."""
    return f"""{queue(name)}, top AS (SELECT max(dist) AS d FROM q),
deg AS (SELECT q.id, q.dist, q.rank, count(e.src) AS d FROM q LEFT JOIN e ON e.src = q.id GROUP BY q.id, q.dist, q.rank),
t_queue AS (SELECT dist AS it, 0::BIGINT AS k, count(*) + (dist = any_value(top.d))::BIGINT AS n, count(*) AS taken, CASE WHEN dist = any_value(top.d) THEN list_append(list(1::BIGINT), 0) ELSE list(1::BIGINT) END AS o FROM q, top GROUP BY dist),
t_near AS (SELECT it, k, count(*) + sum(d)::BIGINT AS n, sum(d)::BIGINT AS taken, flatten(list({_loops('d', bits)} ORDER BY rank)) AS o FROM (SELECT *, dist AS it, row_number() OVER (PARTITION BY dist ORDER BY rank) // 64 AS k FROM deg) GROUP BY it, k),
t_test AS (SELECT it, k, count(*) AS n, sum(t)::BIGINT AS taken, list(t ORDER BY rank, dst) AS o FROM (
  SELECT a.dist AS it, a.rank, e.dst, coalesce((b.parent = a.id)::BIGINT, 0) AS t, row_number() OVER (PARTITION BY a.dist ORDER BY a.rank, e.dst) // 256 AS k FROM e JOIN q a ON a.id = e.src JOIN q b ON b.id = e.dst) GROUP BY it, k),
{_sites({'bfs.queue': 't_queue', 'bfs.neighbor': 't_near', 'bfs.test': 't_test'}, 0, bits)},
sites AS (SELECT 'conditional' AS variant, * FROM one UNION ALL SELECT 'unconditional', * FROM one WHERE site <> 'bfs.test')"""


def samples(name: str, method: str, bits: int = 2, order: str = "sync") -> str:
    """``sites`` and ``samples(graph, method, variant, iteration, ..)`` of one graph."""
    stores = "CASE WHEN variant = 'conditional' THEN changed ELSE v END" if method == "cc" else "CASE WHEN variant = 'conditional' THEN 2 * changed ELSE 2 * edges END"
    return f"""{cc_sites(name, bits, order) if method == 'cc' else bfs_sites(name, bits)},
flat AS (SELECT variant, it, sum(evaluations)::BIGINT AS branches, coalesce(sum(mispredictions), 0)::BIGINT AS mispredictions,
  coalesce(sum(taken) FILTER (site LIKE '%.neighbor'), 0)::BIGINT AS edges, coalesce(sum(taken) FILTER (site IN ('cc.vertex', 'bfs.queue')), 0)::BIGINT AS v, coalesce(sum(taken) FILTER (site LIKE '%.test'), 0)::BIGINT AS changed FROM sites GROUP BY variant, it),
samples AS (SELECT '{name}' AS graph, '{method}' AS method, variant, it::INTEGER AS iteration, v AS vertices_active, edges AS edges_traversed, changed, branches, mispredictions, v + edges AS loads, {stores} AS stores,
  2 * branches + v + edges + ({stores}) + CASE WHEN variant = 'conditional' THEN 0 ELSE edges END AS instructions FROM flat)"""


def all_samples(names: tuple[str, ...], methods: tuple[str, ...], bits: int = 2, order: str = "sync") -> str:
    """One relation of samples over graphs and methods, each from its own nested WITH."""
    parts = [f"(WITH RECURSIVE {samples(n, m, bits, order)} SELECT * FROM samples)" for n in names for m in methods]
    return "samples AS (" + " UNION ALL ".join(f"SELECT * FROM {p}" for p in parts) + ")"


def r(a: str, b: str) -> str:
    return f"round({a}::DOUBLE / nullif({b}::DOUBLE, 0), 6)"
