"""All queries of the graph engine, with DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline import graph as gr
from forkline import sqlapi
from forkline.functions.selection import ratio
from forkline.operators import bfs, components, measures
from forkline.operators.counters import bfs_site_stats, cc_site_stats, modelled_time
from forkline.operators.predictor import check_loop_lemmas, loop_table, nested_loop_misses, one_bit, site_predictability, two_bit
from forkline.operators.trace import cc_test_trace
from forkline.plans import experiments as x
from forkline.plans import oracles as o
from forkline.plans.workloads import WORKLOADS, build
from forkline.sources.tables import load, stored
from forkline.streaming.edges import event_pairs, previous_event, windowed_components

Query = Callable[[SparkSession, str], DataFrame]

FLAGSHIP, SMALL, CHAIN = "bulk_order_part", "bulk_supplier_part", "customer_order_chain"
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def _labels(run: Callable, name: str) -> Query:
    return lambda spark, sf_dir: run(build(name, spark, sf_dir)).labels


_final = lambda name: f"WITH RECURSIVE {o.labels(name)} SELECT id, component FROM final"

# --- components
_add("cc_unconditional", _labels(components.components_unconditional, FLAGSHIP), _final(FLAGSHIP))
_add("cc_conditional", _labels(components.components_conditional, SMALL), _final(SMALL))
_add("cc_delta", _labels(partial(components.components_conditional, scan="delta"), FLAGSHIP), _final(FLAGSHIP))
_add("cc_shortcut", _labels(partial(components.components_unconditional, shortcut=True), "bulk_order_chain"), _final("bulk_order_chain"))
_add("cc_shortcut_delta", _labels(partial(components.components_conditional, scan="delta", shortcut=True), CHAIN), _final(CHAIN))
_add("cc_hybrid", _labels(components.components_hybrid, FLAGSHIP), _final(FLAGSHIP))
_add("cc_mask_select", _labels(partial(components.components_unconditional, select_style="mask"), SMALL), _final(SMALL))
_add("cc_case_select", _labels(partial(components.components_unconditional, select_style="case"), SMALL), _final(SMALL))
_add("cc_blocked", _labels(components.components_blocked, SMALL), _final(SMALL))
_add("cc_in_place", _labels(components.components_in_place, SMALL), _final(SMALL))
_add(
    "cc_in_place_sweeps",
    lambda spark, sf_dir: x.run_of(spark, sf_dir, SMALL, "inplace").sweep_frame(spark).select("iteration", "changed"),
    f"WITH RECURSIVE {o.history(SMALL, 'inplace')} SELECT it AS iteration, sum((before <> after)::BIGINT)::BIGINT AS changed FROM hist GROUP BY it",
)
for _order in ("sync", "inplace"):
    _add(
        f"cc_distinct_labels_{_order}",
        lambda spark, sf_dir, order=_order: components.distinct_labels(x.run_of(spark, sf_dir, SMALL, order), spark),
        f"WITH RECURSIVE {o.history(SMALL, _order)} SELECT it AS iteration, count(DISTINCT after) AS labels FROM hist GROUP BY it",
    )
_add(
    "cc_in_place_totals",
    x.totals_in_place,
    f"WITH {o.all_samples(('bulk_order_part', 'part_supplier_matrix', 'supplier_co_order'), ('cc',), order='inplace')} SELECT graph, variant, max(iteration) AS sweeps, sum(branches)::BIGINT AS branches, sum(mispredictions)::BIGINT AS mispredictions, sum(stores)::BIGINT AS stores, sum(vertices_active)::BIGINT AS lower, {o.r('sum(mispredictions)', 'sum(vertices_active)')} AS ratio_lower FROM samples GROUP BY graph, variant",
)
_add("cc_approx_count", lambda spark, sf_dir: _approx(spark, sf_dir), f"WITH RECURSIVE {o.labels(SMALL)} SELECT count(DISTINCT component) AS components, true AS near FROM final")


def _approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The exact number of components, and whether the approximate one lies within three of its standard errors."""
    labels = components.components_unconditional(build(SMALL, spark, sf_dir)).labels
    exact, near = components.count_components(labels), components.approx_components(labels, 0.02).withColumnRenamed("components", "about")
    return exact.crossJoin(near).select("components", (F.abs(F.col("about") - F.col("components")) <= 0.06 * F.col("components") + 1).alias("near"))  # one row each


_add("cc_recursive_sql", lambda spark, sf_dir: sqlapi.components_recursive(build("supplier_geo_tree", spark, sf_dir), 4), _final("supplier_geo_tree"))
_add("cc_sizes", lambda spark, sf_dir: components.component_sizes(components.components_unconditional(build(SMALL, spark, sf_dir)).labels), f"WITH RECURSIVE {o.labels(SMALL)} SELECT component, count(*) AS size FROM final GROUP BY component")
_add(
    "cc_summary",
    lambda spark, sf_dir: components.component_summary(components.components_unconditional(build("embedding_neighbors", spark, sf_dir)).labels),
    f"WITH RECURSIVE {o.labels('embedding_neighbors')} SELECT sum(n)::BIGINT AS vertices, count(*) AS components, max(n) AS largest, count(*) = 1 AS connected FROM (SELECT count(*) AS n FROM final GROUP BY component)",
)
_add(
    "cc_sweep_history",
    lambda spark, sf_dir: components.components_unconditional(build(FLAGSHIP, spark, sf_dir)).sweep_frame(spark).select("iteration", "changed", "written"),
    f"WITH RECURSIVE {o.labels(FLAGSHIP)} SELECT it AS iteration, sum((component <> old)::BIGINT)::BIGINT AS changed, count(*) AS written FROM lab WHERE it > 0 GROUP BY it",
)
_add("cc_labels_after_2", lambda spark, sf_dir: components.labels_after(build(FLAGSHIP, spark, sf_dir), 2), f"WITH RECURSIVE {o.labels(FLAGSHIP)} SELECT id, component FROM lab WHERE it = 2")
_add("x15_propagation", x.x15_propagation, f"WITH RECURSIVE {o.labels(SMALL)} SELECT it AS sweep, id, component FROM lab")
_add("top_components", lambda spark, sf_dir: components.top_components(components.components_unconditional(build(SMALL, spark, sf_dir)).labels, 10), f"WITH RECURSIVE {o.labels(SMALL)} SELECT component, count(*) AS size FROM final GROUP BY component ORDER BY size DESC, component LIMIT 10")
_add("geo_tree_regions", _labels(partial(components.components_unconditional, shortcut=True), "geo_tree"), _final("geo_tree"))
for _name in ("page_links", "page_domains", "conversation_turns", "embedding_neighbors", "document_lines", "benchmark_overlap", "with_isolated"):
    _add(f"components_{_name}", _labels(components.components_unconditional, _name), _final(_name))

# --- searches
_dist = lambda name: f"WITH RECURSIVE {o.queue(name)} SELECT id, dist FROM q"
_add("bfs_conditional", lambda spark, sf_dir: bfs.bfs_conditional(build(FLAGSHIP, spark, sf_dir)).distances, _dist(FLAGSHIP))
_add("bfs_unconditional", lambda spark, sf_dir: bfs.bfs_unconditional(build(FLAGSHIP, spark, sf_dir)).distances, _dist(FLAGSHIP))
_add("bfs_mask_select", lambda spark, sf_dir: bfs.bfs_unconditional(build(SMALL, spark, sf_dir), select_style="mask").distances, _dist(SMALL))
_add("bfs_hybrid", lambda spark, sf_dir: bfs.bfs_hybrid(build(SMALL, spark, sf_dir), unconditional_levels=2).distances, _dist(SMALL))
_add("bfs_levels", x.search_levels, f"WITH RECURSIVE {o.queue(SMALL)} SELECT dist, count(*) AS vertices FROM q GROUP BY dist")
_add("bfs_queue_order", lambda spark, sf_dir: bfs.queue_order(build(SMALL, spark, sf_dir)), f"WITH RECURSIVE {o.queue(SMALL)} SELECT id, parent, dist, rank FROM q")
_add(
    "bfs_multi",
    lambda spark, sf_dir: bfs.bfs_multi(build("supplier_geo_tree", spark, sf_dir), [0, 4, 8]),
    f"WITH RECURSIVE {o.edges('supplier_geo_tree')}, m(root, id, dist) USING KEY (root, id) AS (SELECT k, k, 0 FROM (VALUES (0::BIGINT), (4::BIGINT), (8::BIGINT)) t(k) UNION SELECT m.root, e.dst, min(m.dist) + 1 FROM m JOIN e ON e.src = m.id WHERE NOT EXISTS (SELECT 1 FROM recurring.m x WHERE x.id = e.dst AND x.root = m.root) GROUP BY m.root, e.dst) SELECT root, id, dist FROM m",
)
_add("bfs_directed", lambda spark, sf_dir: bfs.bfs_conditional(build("directed_order_chain", spark, sf_dir)).distances, _dist("directed_order_chain"))
_add(
    "betweenness_sampled",
    lambda spark, sf_dir: bfs.betweenness_sampled(build("supplier_geo_tree", spark, sf_dir), [0, 4, 8]).select("id", F.round("betweenness", 6).alias("betweenness")),
    f"""WITH RECURSIVE {o.edges('supplier_geo_tree')}, p(r, id, dist, n) USING KEY (r, id) AS (
  SELECT id, id, 0, 1.0::DOUBLE FROM v
  UNION SELECT p.r, e.dst, max(p.dist) + 1, sum(p.n) FROM p JOIN e ON e.src = p.id WHERE NOT EXISTS (SELECT 1 FROM recurring.p x WHERE x.r = p.r AND x.id = e.dst) GROUP BY p.r, e.dst)
SELECT a.id, round(coalesce(sum(a.n * b.n / c.n), 0), 6) AS betweenness FROM p a LEFT JOIN (p b JOIN p c ON c.id = b.id) ON b.r = a.id AND c.r = a.r AND b.id <> a.id AND a.dist + b.dist = c.dist
WHERE a.r IN (0, 4, 8) AND a.id <> a.r GROUP BY a.id""",
)
_add(
    "depth_bounds",
    x.depth_bounds,
    " UNION ALL ".join(
        f"SELECT * FROM (WITH RECURSIVE {o.queue(n)}, far AS (SELECT id FROM q ORDER BY dist DESC, id LIMIT 1), w(id, dist) USING KEY (id) AS (SELECT id, 0 FROM far UNION SELECT e.dst, max(w.dist) + 1 FROM w JOIN e ON e.src = w.id WHERE NOT EXISTS (SELECT 1 FROM recurring.w y WHERE y.id = e.dst) GROUP BY e.dst) SELECT '{n}' AS graph, (SELECT id FROM q WHERE dist = 0) AS root, (SELECT max(dist) FROM q) AS eccentricity, (SELECT max(dist) FROM w) AS diameter_least)"
        for n in ("bulk_supplier_part", "order_mesh")
    ),
)
_add(
    "root_choice",
    x.root_choice,
    " UNION ALL ".join(f"SELECT * FROM (WITH {o.edges(n)} SELECT '{n}' AS graph, 'min_id' AS how, min(id) AS root FROM v UNION ALL SELECT '{n}', 'max_degree', (SELECT src FROM e GROUP BY src ORDER BY count(*) DESC, src LIMIT 1))" for n in x.TRACED),
)
_add("bfs_case_select", lambda spark, sf_dir: bfs.bfs_unconditional(build(SMALL, spark, sf_dir), select_style="case").distances, _dist(SMALL))


def _reach(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = build(SMALL, spark, sf_dir)
    return bfs.reach_stats(g, bfs.bfs_conditional(g).distances)


_add("reach_stats", _reach, f"WITH RECURSIVE {o.queue(SMALL)} SELECT count(*) AS reached, (SELECT count(*) FROM e WHERE src IN (SELECT id FROM q)) AS adjacencies, (max(dist) + 1)::BIGINT AS levels FROM q")
_add("reach_curve", lambda spark, sf_dir: bfs.reach_curve(bfs.bfs_conditional(build(SMALL, spark, sf_dir)).distances), f"WITH RECURSIVE {o.queue(SMALL)} SELECT dist, n AS vertices, (sum(n) OVER (ORDER BY dist))::BIGINT AS reached FROM (SELECT dist, count(*) AS n FROM q GROUP BY dist)")

# --- predictor
_KEYS = "graph, method, variant, \"order\", predictor"


def _sites_sql(body: str, method: str, bits: int) -> str:
    order = "sync" if method == "cc" else "queue"
    return f"WITH RECURSIVE {body} SELECT '{SMALL}' AS graph, '{method}' AS method, variant, '{order}' AS \"order\", '{bits}-bit' AS predictor, it::INTEGER AS iteration, site, evaluations::BIGINT AS evaluations, taken::BIGINT AS taken, coalesce(mispredictions, 0)::BIGINT AS mispredictions FROM sites WHERE variant = 'conditional'"


_add("cc_site_stats_two_bit", lambda spark, sf_dir: cc_site_stats(build(SMALL, spark, sf_dir), "conditional", two_bit()), _sites_sql(o.cc_sites(SMALL, 2), "cc", 2))
_add("cc_site_stats_one_bit", lambda spark, sf_dir: cc_site_stats(build(SMALL, spark, sf_dir), "conditional", one_bit()), _sites_sql(o.cc_sites(SMALL, 1), "cc", 1))
_add("bfs_site_stats_two_bit", lambda spark, sf_dir: bfs_site_stats(build(SMALL, spark, sf_dir), "conditional", two_bit()), _sites_sql(o.bfs_sites(SMALL, 2), "bfs", 2))
_add("bfs_site_stats_one_bit", lambda spark, sf_dir: bfs_site_stats(build(SMALL, spark, sf_dir), "conditional", one_bit()), _sites_sql(o.bfs_sites(SMALL, 1), "bfs", 1))
_PREDICTORS = {"1-bit": 1, "2-bit": 2, "3-bit": 3} | {k: k for k in o.STATIC}
_add(
    "x14_predictors",
    x.x14_predictors,
    " UNION ALL ".join(
        f"SELECT * FROM (WITH RECURSIVE {body(n, bits)} SELECT '{n}' AS graph, '{method}' AS method, '{predictor}' AS predictor, site, sum(evaluations)::BIGINT AS evaluations, sum(mispredictions)::BIGINT AS mispredictions FROM sites WHERE variant = 'conditional' GROUP BY site)"
        for n in ("bulk_supplier_part", "supplier_co_order")
        for method, body in (("cc", o.cc_sites), ("bfs", o.bfs_sites))
        for predictor, bits in _PREDICTORS.items()
    ),
)
_add("cc_site_stats_in_place", lambda spark, sf_dir: x.sites(spark, sf_dir, SMALL, "cc", order="inplace"), _sites_sql(o.cc_sites(SMALL, 2, "inplace"), "cc", 2).replace("'sync'", "'inplace'"))
_add(
    "site_predictability",
    lambda spark, sf_dir: (lambda g: site_predictability(cc_test_trace(g.edges, components.init_labels(g)).withColumn("site", F.lit("cc.test")), ["site"], ["seq_hi", "seq_lo"]))(build(SMALL, spark, sf_dir)),
    f"WITH RECURSIVE {o.cc_sites(SMALL)}, marked AS (SELECT t, coalesce(lag(t) OVER (ORDER BY src, dst) <> t, true) AS fresh FROM outcome WHERE it = 1), total AS (SELECT count(*) AS n, avg(t) AS p, sum(fresh::BIGINT)::BIGINT AS runs FROM marked) SELECT 'cc.test' AS site, n AS evaluations, round(p, 6) AS taken_rate, round(-(p * log2(p) + (1 - p) * log2(1 - p)), 6) AS entropy, runs, round(n / runs, 6) AS mean_run FROM total",
)
_add("cc_test_trace_first", lambda spark, sf_dir: (lambda g: cc_test_trace(g.edges, components.init_labels(g)))(build(SMALL, spark, sf_dir)), f"WITH RECURSIVE {o.cc_sites(SMALL)} SELECT src AS seq_hi, dst AS seq_lo, t = 1 AS taken FROM outcome WHERE it = 1")
_LOOP_LIST = "flatten(list_transform(range(k), lambda y: list_append(list_transform(range(n), lambda z: 1::BIGINT), 0)))"
_add(
    "loop_table",
    lambda spark, sf_dir: loop_table(spark, trips=x.loop_trips(spark, sf_dir)),
    f"WITH {o.edges('with_isolated')} SELECT n AS trips, b AS start, k AS repeats, (c % 4)::BIGINT AS end_state, (c // 4)::BIGINT AS mispredictions FROM (SELECT n, b, k, {o.fold(_LOOP_LIST, 2).replace('list_prepend(0::BIGINT,', 'list_prepend(b,')} AS c FROM (SELECT DISTINCT d AS n FROM (SELECT v.id, count(e.src) AS d FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id)) t1, range(4) t2(b), range(1, 7) t3(k))",
)
_LOOPS = ORACLES["loop_table"]
_CLAIMS = [
    ("three or more trips end weakly taken", "k = 1 AND n >= 3", "f = 2"),
    ("three or more trips miss 1 to 3", "k = 1 AND n >= 3", "m BETWEEN 1 AND 3"),
    ("k repeats of three or more trips miss at most k + 2", "k >= 2 AND n >= 3", "m <= k + 2"),
    ("k repeats of three or more trips miss at least k", "k >= 2 AND n >= 3", "m >= k"),
    ("no trip misses at most once", "k = 1 AND n = 0", "m <= 1"),
    ("no trip moves one state down", "k = 1 AND n = 0", "f = greatest(0, b - 1)"),
    ("one trip misses once or twice", "k = 1 AND n = 1", "m BETWEEN 1 AND 2"),
    ("one trip returns to a state that a loop can leave", "k = 1 AND n = 1 AND b < 3", "f = b"),
    ("one trip from strongly taken ends weakly taken", "k = 1 AND n = 1 AND b = 3", "f = 2"),
    ("two trips end weakly taken or weakly not taken", "k = 1 AND n = 2", "f IN (1, 2)"),
    ("two trips miss 1 to 3", "k = 1 AND n = 2", "m BETWEEN 1 AND 3"),
]
_add(
    "loop_lemmas",
    lambda spark, sf_dir: check_loop_lemmas(spark, trips=stored(x.loop_trips(spark, sf_dir), "trips")),
    f"WITH t AS (SELECT trips AS n, start AS b, repeats AS k, end_state AS f, mispredictions AS m FROM ({_LOOPS})) " + " UNION ALL ".join(f"SELECT '{claim}' AS lemma, count(*) AS cases, sum((NOT ({holds}))::BIGINT)::BIGINT AS violations FROM t WHERE {which}" for claim, which, holds in _CLAIMS),
)
_add(
    "nested_loop_misses",
    lambda spark, sf_dir: spark.createDataFrame([(nested_loop_misses(gr.degrees(build(FLAGSHIP, spark, sf_dir)), "id"),)], "mispredictions bigint"),
    f"WITH {o.edges(FLAGSHIP)}, deg AS (SELECT src, count(*) AS d FROM e GROUP BY src) SELECT ({o.fold('flatten(list(list_append(list_transform(range(d), lambda x: 1::BIGINT), 0) ORDER BY src))', 2)} // 4)::BIGINT AS mispredictions FROM deg",
)
_add(
    "steady_state_rates",
    x.supplier_rates,
    "SELECT supplier, p, 2 * p * (1 - p) AS one_bit, p * (1 - p) / (p * p + (1 - p) * (1 - p)) AS two_bit FROM (SELECT l_suppkey AS supplier, sum((l_quantity >= 45)::BIGINT)::DOUBLE / count(*)::DOUBLE AS p FROM lineitem GROUP BY l_suppkey)",
)

# --- measures
_ALL = o.all_samples(x.TRACED, ("cc", "bfs"))
_ONLY = {m: o.all_samples(x.TRACED, (m,)) for m in ("cc", "bfs")}


def _ratio_sql(samples: str, metric: str, keys: str, name: str = "ratio", flip: bool = False) -> str:
    c, u = f"sum({metric}) FILTER (variant = 'conditional')", f"sum({metric}) FILTER (variant = 'unconditional')"
    return f"WITH {samples} SELECT {keys}, {c}::BIGINT AS conditional, {u}::BIGINT AS unconditional, {o.r(u, c) if flip else o.r(c, u)} AS {name} FROM samples GROUP BY {keys}"


for _m, _b, _s in (("cc", x.x2_cc_branches, x.x3_cc_mispredictions), ("bfs", x.x5_bfs_branches, x.x6_bfs_mispredictions)):
    _add(f"branch_ratio_{_m}", _b, _ratio_sql(_ONLY[_m], "branches", "graph, method, iteration"))
    _add(f"miss_ratio_{_m}", _s, _ratio_sql(_ONLY[_m], "mispredictions", "graph, method, iteration"))
_LOWER = "sum(mispredictions)::BIGINT AS mispredictions, sum(vertices_active)::BIGINT AS lower"
_add("cc_bounds", x.x7_cc_bounds, f"WITH {_ONLY['cc']} SELECT graph, method, variant, {_LOWER}, {o.r('sum(mispredictions)', 'sum(vertices_active)')} AS ratio_lower FROM samples GROUP BY graph, method, variant")
_add(
    "bfs_bounds",
    x.x8_bfs_bounds,
    f"WITH {_ONLY['bfs']} SELECT graph, method, variant, {_LOWER}, 3 * sum(vertices_active)::BIGINT AS upper, {o.r('sum(mispredictions)', 'sum(vertices_active)')} AS ratio_lower, {o.r('sum(mispredictions)', '3 * sum(vertices_active)')} AS ratio_upper FROM samples GROUP BY graph, method, variant",
)
_add("store_growth", x.x11_stores, _ratio_sql(_ALL, "stores", "graph, method", "growth", True))
_SAMPLE_COLUMNS = "graph, method, variant, iteration, vertices_active, edges_traversed, changed, branches, mispredictions, loads, stores, instructions"
_add("samples", lambda spark, sf_dir: x.samples(spark, sf_dir).select(*_SAMPLE_COLUMNS.split(", ")), f"WITH {_ALL} SELECT {_SAMPLE_COLUMNS} FROM samples")
_TIME = "round(1.0 * instructions + 14.0 * mispredictions + 2.0 * loads + 2.0 * stores, 6)::DOUBLE"
_add(
    "modelled_cost",
    lambda spark, sf_dir: modelled_time(x.samples(spark, sf_dir), x.PROFILES[:1]).select("graph", "method", "variant", "iteration", "profile", "modelled_time", "dispatched"),
    f"WITH {_ALL} SELECT graph, method, variant, iteration, 'balanced' AS profile, {_TIME} AS modelled_time, round(branches::DOUBLE, 6) AS dispatched FROM samples",
)
_add(
    "modelled_crossover",
    lambda spark, sf_dir: measures.crossover(modelled_time(x.samples(spark, sf_dir), x.PROFILES[:1]), "modelled_time", ["profile"]),
    f"""WITH {_ALL}, sides AS (SELECT graph, method, 'balanced' AS profile, iteration, sum({_TIME}) FILTER (variant = 'unconditional') - sum({_TIME}) FILTER (variant = 'conditional') AS gain FROM samples GROUP BY graph, method, iteration),
rest AS (SELECT *, min(gain) OVER (PARTITION BY graph, method ORDER BY iteration ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS low, lag(sign(gain)) OVER (PARTITION BY graph, method ORDER BY iteration) AS before FROM sides)
SELECT graph, method, profile, min(iteration) FILTER (low >= 0) AS crossover, sum((coalesce(before, sign(gain)) <> sign(gain))::BIGINT)::BIGINT AS turns, count(*) AS iterations FROM rest GROUP BY graph, method, profile""",
)
_BY_PROFILE = ", ".join(f"('{p.name}', {p.per_instruction}, {p.per_miss}, {p.per_load}, {p.per_store})" for p in x.PROFILES)
_COSTS = f"costs AS (SELECT s.*, profile, round(a::DOUBLE * instructions + b::DOUBLE * mispredictions + c::DOUBLE * loads + d::DOUBLE * stores, 6) AS cost FROM samples s, (VALUES {_BY_PROFILE}) t(profile, a, b, c, d))"
_C, _U = "sum(cost) FILTER (variant = 'conditional')", "sum(cost) FILTER (variant = 'unconditional')"
_add("modelled_speedup", x.modelled_speedup, f"WITH {_ALL}, {_COSTS} SELECT graph, method, profile, {_C} AS conditional, {_U} AS unconditional, {o.r(_C, _U)} AS speedup FROM costs GROUP BY graph, method, profile")
_SC, _SU = "sum(stores) FILTER (variant = 'conditional')", "sum(stores) FILTER (variant = 'unconditional')"
_add(
    "search_slowdown",
    x.slowdown_and_growth,
    f"WITH {_ONLY['bfs']}, {_COSTS} SELECT graph, profile, {o.r(_U, _C)} AS slowdown, {o.r(_SU, _SC)} AS growth, {o.r(_U, _C)} <= 2 AS within_cap FROM costs GROUP BY graph, profile",
)
_add("work_constancy", x.work_constancy, f"WITH {_ONLY['cc']} SELECT graph, variant, count(*) AS sweeps, min(edges_traversed)::BIGINT AS least, max(edges_traversed)::BIGINT AS most, min(edges_traversed) = max(edges_traversed) AS constant FROM samples GROUP BY graph, variant")


def _correlation_sql(method: str) -> str:
    metrics = measures.METRICS
    pairs = [(a, b) for i, a in enumerate(metrics) for b in metrics[i + 1 :]]
    per = ", ".join(f"({_TIME if c == 'time' else c})::DOUBLE / edges_traversed AS {c}" for c in metrics)
    rows = " UNION ALL ".join(
        f"SELECT '{method}' AS method, '{a}' AS row_metric, '{b}' AS col_metric, count(*) AS n, round(CASE WHEN sum((a.{a} - m.{a}) ^ 2) > 1e-18 AND sum((a.{b} - m.{b}) ^ 2) > 1e-18 THEN sum((a.{a} - m.{a}) * (a.{b} - m.{b})) / sqrt(sum((a.{a} - m.{a}) ^ 2) * sum((a.{b} - m.{b}) ^ 2)) END, 6) AS r FROM per a, mean m"
        for a, b in pairs
    )
    return f"{_ONLY[method]}, per AS (SELECT {per} FROM samples WHERE variant = 'conditional' AND edges_traversed > 0), mean AS (SELECT {', '.join(f'avg({c}) AS {c}' for c in metrics)} FROM per), corr AS ({rows})"


_add("correlation_cc", x.x9_cc_correlation, f"WITH {_correlation_sql('cc')} SELECT * FROM corr")
_add("correlation_bfs", x.x10_bfs_correlation, f"WITH {_correlation_sql('bfs')} SELECT * FROM corr")
for _m, _name, _correlation in (("cc", "time_predictor_rank", x.x9_cc_correlation), ("bfs", "time_predictor_rank_bfs", x.x10_bfs_correlation)):
    _add(_name, lambda spark, sf_dir, c=_correlation: measures.rank_time_predictors(c(spark, sf_dir)), f"WITH {_correlation_sql(_m)} SELECT method, col_metric AS metric, r, (rank() OVER (ORDER BY abs(r) DESC NULLS LAST))::INTEGER AS rank FROM corr WHERE row_metric = 'time'")
_add(
    "per_edge_rates",
    lambda spark, sf_dir: measures.per_edge(x.samples(spark, sf_dir), ["branches", "mispredictions", "stores"]),
    f"WITH {_ALL} SELECT graph, method, variant, iteration, edges_traversed, {', '.join(f'{o.r(c, 'edges_traversed')} AS {c}_per_edge' for c in ('branches', 'mispredictions', 'stores'))} FROM samples",
)
_add("scatter_points", lambda spark, sf_dir: measures.scatter_points(x.samples(spark, sf_dir), "mispredictions", "stores"), f"WITH {_ALL} SELECT graph, method, variant, iteration, {o.r('mispredictions', 'edges_traversed')} AS x, {o.r('stores', 'edges_traversed')} AS y FROM samples WHERE edges_traversed > 0")
_add("iteration_variation", lambda spark, sf_dir: measures.iteration_variation(x.samples(spark, sf_dir), "instructions"), f"WITH {_ALL} SELECT graph, method, variant, count(*) AS iterations, round(stddev_samp(instructions) / nullif(avg(instructions), 0), 6) AS variation FROM samples GROUP BY graph, method, variant")
_add("counter_cube", lambda spark, sf_dir: measures.counter_cube(x.samples(spark, sf_dir)), f"WITH {_ALL} SELECT graph, method, variant, grouping(graph, method, variant)::BIGINT AS level, sum(branches)::BIGINT AS branches, sum(mispredictions)::BIGINT AS mispredictions, sum(stores)::BIGINT AS stores FROM samples GROUP BY CUBE (graph, method, variant)")
_add("counter_rollup", lambda spark, sf_dir: measures.counter_rollup(x.samples(spark, sf_dir)), f"WITH {_ALL} SELECT graph, method, variant, grouping(graph, method, variant)::BIGINT AS level, sum(branches)::BIGINT AS branches, sum(mispredictions)::BIGINT AS mispredictions FROM samples GROUP BY ROLLUP (graph, method, variant)")
_add("counter_grouping_sets", lambda spark, sf_dir: measures.counter_grouping_sets(x.samples(spark, sf_dir)), f"WITH {_ALL} SELECT graph, method, variant, sum(branches)::BIGINT AS branches, sum(mispredictions)::BIGINT AS mispredictions FROM samples GROUP BY GROUPING SETS ((graph), (method, variant))")
_BANDS = " UNION ALL ".join(f"SELECT * FROM (WITH {o.all_samples(x.TRACED, ('cc',), b)} SELECT graph, method, sum(mispredictions) FILTER (variant = 'conditional')::DOUBLE / sum(mispredictions) FILTER (variant = 'unconditional') AS r FROM samples GROUP BY graph, method)" for b in (1, 2, 3))
_add("miss_ratio_spread", x.predictor_band, f"SELECT graph, method, round(min(r), 6) AS least, round(max(r), 6) AS most, round(max(r) - min(r), 6) AS spread, round(stddev_samp(r), 6) AS deviation FROM ({_BANDS}) GROUP BY graph, method")
_add(
    "select_styles",
    x.select_styles,
    f"WITH {_ALL} SELECT graph, method, style, sum(instructions + edges_traversed * (w - 1))::BIGINT AS instructions FROM samples, (VALUES ('least', 1), ('mask', 9), ('case', 1)) t(style, w) WHERE variant = 'unconditional' GROUP BY graph, method, style",
)
# fmt: off
_RATE = "(p * (1 - p) / (p * p + (1 - p) * (1 - p)))"
_SWITCHES = {"at_iteration(2)": "it >= 2", "changed_fraction(0.1)": "changed <= 0.1 * n", "test_miss_rate(0.1)": f"{_RATE} <= 0.1", "modelled_cost(2.0,14.0)": f"14.0 * n * {_RATE} <= 2.0 * (n - changed)"}
_add(
    "x12_hybrid",
    x.x12_hybrid,
    f"WITH RECURSIVE {o.labels(SMALL)}, sweep AS (SELECT it, n, changed, changed / n AS p FROM (SELECT it, count(*)::DOUBLE AS n, sum((component <> old)::BIGINT)::BIGINT AS changed FROM lab WHERE it > 0 GROUP BY it)), "
    + "switch AS (" + " UNION ALL ".join(f"SELECT '{name}' AS policy, coalesce(min(it) FILTER ({rule}), 1 << 30) AS upto FROM sweep" for name, rule in _SWITCHES.items()) + ") "
    + "SELECT it AS iteration, CASE WHEN it <= upto THEN 'unconditional' ELSE 'conditional' END AS discipline, changed, CASE WHEN it <= upto THEN n::BIGINT ELSE changed END AS written, policy FROM sweep, switch",
)
# fmt: on
_add("x12_hybrid_by_time", x.x12_hybrid_by_time)
_add("cc_time_ratio", x.x1_cc_time)
_add("bfs_time_ratio", x.x4_bfs_time)
_add("speedup", lambda spark, sf_dir: measures.total_speedup(x.timed(spark, sf_dir, "cc", (SMALL,)).unionByName(x.timed(spark, sf_dir, "bfs", (SMALL,)))))

# --- graphs
_add(
    "graph_inventory",
    x.x13_inventory,
    " UNION ALL ".join(f"SELECT '{n}' AS graph, {str(n == 'directed_order_chain').lower()} AS directed, (SELECT count(*) FROM (WITH {o.edges(n)} SELECT id FROM v)) AS vertices, ((SELECT count(*) FROM (WITH {o.edges(n)} SELECT src FROM e)) // {1 if n == 'directed_order_chain' else 2})::BIGINT AS edges" for n in WORKLOADS),
)
_WALK = f"WITH {o.edges(FLAGSHIP)}, deg AS (SELECT src, count(*) AS d FROM e GROUP BY src), walk AS (SELECT (count(*) + sum(d))::BIGINT AS branches, sum(d)::BIGINT AS loads, ({o.fold('flatten(list(list_append(list_transform(range(d), lambda x: 1::BIGINT), 0) ORDER BY src))', 2)} // 4)::BIGINT AS mispredictions FROM deg)"
_add("profile_inventory", x.x13_profiles, f"{_WALK} " + " UNION ALL ".join(f"SELECT '{p.name}' AS profile, '{p.predictor.name}' AS predictor, {p.per_instruction}::DOUBLE AS per_instruction, {p.per_miss}::DOUBLE AS per_miss, {p.per_load}::DOUBLE AS per_load, {p.per_store}::DOUBLE AS per_store, {p.wrong_path}::DOUBLE AS wrong_path, branches, mispredictions, {p.per_instruction}::DOUBLE * (2 * branches + loads) + {p.per_miss}::DOUBLE * mispredictions + {p.per_load}::DOUBLE * loads AS modelled_time FROM walk" for p in x.PROFILES))
_add("degree_quantiles", lambda spark, sf_dir: gr.degree_quantiles(build(SMALL, spark, sf_dir)), f"WITH {o.edges(SMALL)}, deg AS (SELECT v.id, count(e.src) AS d FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id) " + " UNION ALL ".join(f"SELECT {q}::DOUBLE AS quantile, quantile_disc(d, {q})::BIGINT AS degree FROM deg" for q in (0.5, 0.9, 0.99)))
_add(
    "strongest_parts",
    lambda spark, sf_dir: sqlapi.knn_edges(load(spark, sf_dir, "lineitem", ["l_suppkey", "l_partkey", "l_quantity"]).groupBy(F.col("l_suppkey").alias("a"), F.col("l_partkey").alias("b")).agg(F.sum("l_quantity").alias("weight")), 3),
    "SELECT a, b, weight FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY weight DESC, b) AS place FROM (SELECT l_suppkey AS a, l_partkey AS b, sum(l_quantity) AS weight FROM lineitem GROUP BY ALL)) WHERE place <= 3",
)
_add("previous_event", lambda spark, sf_dir: previous_event(load(spark, sf_dir, "events", ["event_id", "user_id", "ts"])).select("event_id", "user_id", "previous_id"), "SELECT event_id, user_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous_id FROM events")
_add("degree_histogram", lambda spark, sf_dir: gr.degree_histogram(build("with_isolated", spark, sf_dir)), f"WITH {o.edges('with_isolated')} SELECT d AS degree, count(*) AS vertices FROM (SELECT v.id, count(e.src) AS d FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id) GROUP BY d")
_add("top_degree", lambda spark, sf_dir: gr.top_degree(build(FLAGSHIP, spark, sf_dir), 10), f"WITH {o.edges(FLAGSHIP)} SELECT src AS id, count(*) AS degree FROM e GROUP BY src ORDER BY degree DESC, id LIMIT 10")
_add("adjacency", lambda spark, sf_dir: gr.adjacency(build(SMALL, spark, sf_dir)).select("src", "chunk", "degree", F.array_join(F.col("nbrs").cast("array<string>"), ",").alias("nbrs")), f"WITH {o.edges(SMALL)} SELECT src, 0 AS chunk, count(*) AS degree, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nbrs FROM e GROUP BY src")
_add("subgraph_semi", lambda spark, sf_dir: gr.subgraph(build(FLAGSHIP, spark, sf_dir), F.col("id") % 3 != 0).edges, f"WITH {o.edges(FLAGSHIP)} SELECT src, dst FROM e WHERE src % 3 <> 0 AND dst % 3 <> 0")


def _set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = build(FLAGSHIP, spark, sf_dir), WORKLOADS[FLAGSHIP](spark, sf_dir, min_quantity=48)
    out = None
    for name, g in (("union", gr.graph_union(a, b)), ("intersect", gr.graph_intersect(a, b)), ("difference", gr.graph_difference(a, b))):
        one = g.edges.select(F.lit(name).alias("op"), "src", "dst")
        out = one if out is None else out.unionByName(one)
    return out.groupBy("op").agg(F.count("*").alias("edges"), F.sum("src").alias("sources"))


_add(
    "edge_set_ops",
    _set_ops,
    f"WITH {o.edges(FLAGSHIP)}, f AS (SELECT * FROM (WITH {o.edges(FLAGSHIP).replace('l_quantity >= 45', 'l_quantity >= 48')} SELECT src, dst FROM e)), u AS (SELECT 'union' AS op, * FROM (SELECT src, dst FROM e UNION SELECT src, dst FROM f) UNION ALL SELECT 'intersect', * FROM (SELECT src, dst FROM e INTERSECT SELECT src, dst FROM f) UNION ALL SELECT 'difference', * FROM (SELECT src, dst FROM e EXCEPT SELECT src, dst FROM f)) SELECT op, count(*) AS edges, sum(src)::BIGINT AS sources FROM u GROUP BY op",
)
for _name in WORKLOADS:
    _add(f"edges_{_name}", lambda spark, sf_dir, name=_name: WORKLOADS[name](spark, sf_dir).edges, f"WITH {o.edges(_name)} SELECT src, dst FROM e")
_add(
    "event_window_pairs",
    lambda spark, sf_dir: event_pairs(load(spark, sf_dir, "events", ["user_id", "ts"]), minutes=2),
    "SELECT DISTINCT least(x.user_id, y.user_id) AS a, greatest(x.user_id, y.user_id) AS b FROM events x JOIN events y ON y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 2 MINUTE AND x.user_id <> y.user_id",
)
_add("event_window_components", lambda spark, sf_dir: windowed_components(load(spark, sf_dir, "events", ["event_id", "user_id", "ts"]), "1 day"), """
WITH RECURSIVE ev AS (SELECT date_trunc('day', ts) AS w, user_id * 2 AS u, (epoch_us(ts) // 3600000000) * 2 + 1 AS h FROM events),
e AS (SELECT DISTINCT w, src, dst FROM (SELECT w, u AS src, h AS dst FROM ev UNION ALL SELECT w, h, u FROM ev)),
lab(it, w, id, component, changed) AS (
  SELECT 0, w, src, src, 1::BIGINT FROM (SELECT DISTINCT w, src FROM e)
  UNION ALL
  SELECT it + 1, w, id, low, sum(ch) OVER () FROM (
    SELECT l.it, l.w, l.id, least(l.component, coalesce(m.c, l.component)) AS low, coalesce((m.c < l.component)::BIGINT, 0) AS ch
    FROM lab l LEFT JOIN (SELECT e.w, e.src, min(x.component) AS c FROM e JOIN lab x ON x.id = e.dst AND x.w = e.w GROUP BY e.w, e.src) m ON m.src = l.id AND m.w = l.w WHERE l.changed > 0))
SELECT strftime(w, '%Y-%m-%d') AS day, count(*) AS vertices, count(DISTINCT component) AS components FROM lab WHERE it = (SELECT max(it) FROM lab) GROUP BY w""")
_add("degree_ratio", lambda spark, sf_dir: gr.degrees(build(SMALL, spark, sf_dir)).agg(F.count("*").alias("vertices"), ratio(F.sum("degree"), F.count("*")).alias("mean_degree")), f"WITH {o.edges(SMALL)} SELECT (SELECT count(*) FROM v) AS vertices, round((SELECT count(*) FROM e)::DOUBLE / (SELECT count(*) FROM v), 6) AS mean_degree")
