"""Registered queries of the connectivity engine and their SQL."""

from __future__ import annotations

import itertools

from pyspark.sql import functions as F

from starfold.functions import keyed, measures
from starfold.operators import alternating, baselines, incremental, paired
from starfold.sources import graphs, tables
from starfold.streaming.components import session_components

B = tables.BUILDERS


def unrolled(edges: str, levels: int) -> str:
    """SQL for components by ``levels`` rounds of one-hop minima, at least the eccentricity of the graph."""
    parts = [
        f"e AS ({edges})",
        "t AS (SELECT a AS s, b AS d FROM e UNION ALL SELECT b AS s, a AS d FROM e)",
        "c AS (SELECT s, d FROM t UNION SELECT s, s AS d FROM t)",
        "l0 AS (SELECT DISTINCT s AS v, s AS m FROM t)",
    ]
    for k in range(levels):
        parts.append(f"l{k + 1} AS (SELECT c.s AS v, MIN(p.m) AS m FROM c JOIN l{k} p ON c.d = p.v GROUP BY c.s)")
    return f"WITH {', '.join(parts)} SELECT v AS vertex, m AS component FROM l{levels}"


def closed(table: str, vertex: str, key: str) -> str:
    """SQL for chains and cliques: the least vertex of each key that has two or more."""
    return (
        f"WITH r AS (SELECT DISTINCT {key} AS k, {vertex} AS v FROM {table}), g AS (SELECT k, MIN(v) AS m, COUNT(*) AS n FROM r GROUP BY k) "
        "SELECT r.v AS vertex, g.m AS component FROM r JOIN g ON r.k = g.k WHERE g.n > 1"
    )


def _star(table: str, hub: str, leaf: str) -> str:
    return (
        f"WITH p AS (SELECT DISTINCT CAST({hub} AS BIGINT) AS h, CAST({leaf} AS BIGINT) AS f FROM {table}), g AS (SELECT h, LEAST(h, MIN(f)) AS m FROM p GROUP BY h) "
        "SELECT h AS vertex, m AS component FROM g UNION ALL SELECT p.f AS vertex, g.m AS component FROM p JOIN g ON p.h = g.h"
    )


_CS = "SELECT DISTINCT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
_SIX = lambda c, k: f"CAST(6 * {c} + {k} AS BIGINT)"
SQL = {
    "order_part": unrolled("SELECT DISTINCT 2 * l_orderkey AS a, 2 * l_partkey + 1 AS b FROM lineitem", 12),
    "customer_supplier": unrolled(_CS, 8),
    "customer_order": _star("orders", "2 * o_custkey", "2 * o_orderkey + 1"),
    "nation_region": _star("nation", "2 * n_regionkey", "2 * n_nationkey + 1"),
    "event_chain": "SELECT event_id AS vertex, (SELECT MIN(event_id) FROM events) AS component FROM events",
    "user_event_chain": closed("events", "event_id", "user_id"),
    "turn_chain": closed("conversations", "conv_id * 1000 + turn", "conv_id"),
    "line_item_chain": closed("lineitem", "l_orderkey * 10 + l_linenumber", "l_orderkey"),
    "doc_exact": closed("documents", "doc_id", "text"),
    "session_chain": (
        "WITH o AS (SELECT user_id, event_id, ts, LAG(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events), "
        "f AS (SELECT user_id, event_id, ts, CASE WHEN before IS NULL OR epoch_us(ts) - epoch_us(before) >= 1800000000 THEN 1 ELSE 0 END AS cut FROM o), "
        "i AS (SELECT user_id, event_id, SUM(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM f), "
        "g AS (SELECT user_id, k, MIN(event_id) AS m, COUNT(*) AS n FROM i GROUP BY user_id, k) "
        "SELECT i.event_id AS vertex, g.m AS component FROM i JOIN g ON i.user_id = g.user_id AND i.k = g.k WHERE g.n > 1"
    ),
    "rare_return_orders": unrolled("SELECT DISTINCT 2 * l_orderkey AS a, 2 * l_partkey + 1 AS b FROM lineitem WHERE l_returnflag = 'R' AND l_quantity >= 49", 16),
    "rare_return_parts": unrolled("SELECT DISTINCT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem WHERE l_returnflag = 'R' AND l_quantity >= 50", 20),
    "event_prop_graph": unrolled("SELECT DISTINCT 2 * user_id AS a, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS b FROM events", 8),
    "schema_graph": unrolled(
        f"SELECT {_SIX('n_regionkey', 0)} AS a, {_SIX('n_nationkey', 1)} AS b FROM nation UNION SELECT {_SIX('c_nationkey', 1)}, {_SIX('c_custkey', 2)} FROM customer "
        f"UNION SELECT {_SIX('s_nationkey', 1)}, {_SIX('s_suppkey', 3)} FROM supplier UNION SELECT {_SIX('o_custkey', 2)}, {_SIX('o_orderkey', 4)} FROM orders "
        f"UNION SELECT {_SIX('l_orderkey', 4)}, {_SIX('l_partkey', 5)} FROM lineitem UNION SELECT {_SIX('l_suppkey', 3)}, {_SIX('l_partkey', 5)} FROM lineitem", 12),
    "page_link": unrolled(
        "SELECT DISTINCT 2 * p.page_id AS a, 2 * r.k + 1 AS b FROM (SELECT page_id, UNNEST(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages) p "
        "JOIN (SELECT h, ROW_NUMBER() OVER (ORDER BY h) AS k FROM (SELECT DISTINCT UNNEST(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages) q) r ON p.h = r.h", 16),
    "doc_shared_line": unrolled(
        "WITH x AS (SELECT DISTINCT doc_id, TRIM(l) AS h FROM (SELECT doc_id, UNNEST(string_split(text, chr(10))) AS l FROM documents) q WHERE LENGTH(TRIM(l)) >= 40), "
        "f AS (SELECT h, MIN(doc_id) AS m FROM x GROUP BY h) SELECT DISTINCT f.m AS a, x.doc_id AS b FROM x JOIN f ON x.h = f.h WHERE f.m <> x.doc_id", 16),
    "page_host": unrolled(
        "SELECT DISTINCT 2 * p.page_id AS a, 2 * r.k + 1 AS b FROM (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS h FROM pages) p "
        "JOIN (SELECT h, ROW_NUMBER() OVER (ORDER BY h) AS k FROM (SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS h FROM pages WHERE url IS NOT NULL) q) r ON p.h = r.h", 3),
    "doc_line_bipartite": unrolled(
        "WITH x AS (SELECT DISTINCT doc_id, TRIM(l) AS h FROM (SELECT doc_id, UNNEST(string_split(text, chr(10))) AS l FROM documents) q WHERE LENGTH(TRIM(l)) >= 40), "
        "r AS (SELECT h, ROW_NUMBER() OVER (ORDER BY h) AS k FROM (SELECT DISTINCT h FROM x) y) SELECT 2 * x.doc_id AS a, 2 * r.k + 1 AS b FROM x JOIN r ON x.h = r.h", 24),
    "vector_neighbours": unrolled(
        "SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id "
        "WHERE list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) >= 0.3", 16),
    "doc_benchmark": unrolled(
        "SELECT DISTINCT 2 * d.i AS a, 2 * b.j + 1 AS b FROM (SELECT doc_id AS i, TRIM(l) AS h FROM (SELECT doc_id, UNNEST(string_split(text, chr(10))) AS l FROM documents) q) d "
        "JOIN (SELECT item_id AS j, TRIM(l) AS h FROM (SELECT item_id, UNNEST(string_split(text, chr(10))) AS l FROM benchmark) q) b ON d.h = b.h WHERE LENGTH(d.h) >= 20", 8),
}


def _labels(name, method):
    return lambda spark, d: method(B[name](spark, d)).whole()


QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _add(name, fn, sql=None):
    QUERIES[name] = fn
    if sql:
        ORACLES[name] = sql


for _n in B:
    _add(f"cc_alternating_{_n}", _labels(_n, alternating.connected_components), SQL.get(_n))
for _n in ("customer_supplier", "rare_return_parts", "turn_chain", "doc_shared_line"):
    _add(f"cc_paired_{_n}", _labels(_n, paired.connected_components), SQL[_n])
    _add(f"cc_sorted_{_n}", _labels(_n, paired.sorted_components), SQL[_n])
VARIANTS = {
    "cc_tree_combine": measures.METHODS["alternating_tree"], "cc_retire": measures.METHODS["alternating_retire"],
    "cc_spread": lambda e: alternating.connected_components(e, layout="spread"),
    "cc_quiet_counter": lambda e: alternating.connected_components(e, stop="quiet_counter"),
    "cc_local_forest": lambda e: alternating.connected_components(baselines.local_forest(e)),
    "cc_no_dedupe": measures.METHODS["paired_none"], "cc_within_step": measures.METHODS["paired_within_step"],
    "cc_sorted_no_dedupe": measures.METHODS["sorted_none"],
    "baseline_min_flood": baselines.min_flood, "baseline_duplicating_flood": baselines.duplicating_flood,
    "baseline_hook_compress": baselines.hook_and_compress, "baseline_hook_compress_tree": measures.METHODS["hook_compress_tree"],
    "baseline_coin_flip": baselines.coin_flip_contraction, "baseline_two_star": baselines.two_star_rounds,
    "baseline_sort_random": baselines.sort_random_contraction,
}
for _m, _f in VARIANTS.items():
    _add(_m, _labels("rare_return_orders", _f), SQL["rare_return_orders"])
    for _n in ("order_part", "customer_supplier"):
        _add(f"{_m}_{_n}", _labels(_n, _f), SQL[_n])
_add("baseline_recursive_sql", lambda s, d: baselines.recursive_sql(tables.region_tree(s, d), 2), unrolled(
    "SELECT n_regionkey - 2000000 AS a, n_nationkey - 1000000 AS b FROM nation WHERE n_nationkey + n_regionkey IS NOT NULL "
    "UNION SELECT c_nationkey - 1000000, c_custkey FROM customer WHERE c_custkey + c_nationkey IS NOT NULL", 4))

_add("seq_path_labels", lambda s, d: alternating.connected_components(graphs.seq_path(s, 10)).whole(), "SELECT CAST(range AS BIGINT) AS vertex, CAST(0 AS BIGINT) AS component FROM range(1024)")
_add("bridged_grid_labels", lambda s, d: alternating.connected_components(graphs.bridged_grid(s, 64, 6)).whole(), "SELECT CAST(range AS BIGINT) AS vertex, CAST(0 AS BIGINT) AS component FROM range(385)")


def _step_counts(spark, graphs_by_size):
    rows = [(k, alternating.connected_components(g, stop="quiet_counter").n_steps) for k, g in graphs_by_size]
    return spark.createDataFrame([(int(k), int(v)) for k, v in rows], "size long, steps long")


_add("path_step_counts", lambda s, d: _step_counts(s, [(e, graphs.seq_path(s, e)) for e in (4, 6, 8)]), "SELECT CAST(size AS BIGINT) AS size, CAST(steps AS BIGINT) AS steps FROM (VALUES (4, 8), (6, 11), (8, 14)) t(size, steps)")
_add("grid_step_counts", lambda s, d: _step_counts(s, [(c, graphs.bridged_grid(s, 1 << c, c)) for c in (4, 6)]), "SELECT CAST(size AS BIGINT) AS size, CAST(steps AS BIGINT) AS steps FROM (VALUES (4, 6), (6, 8)) t(size, steps)")
_add(
    "figure_trace",
    lambda s, d: alternating.trace(graphs.figure_path(s), 3).where("dst is not null").select(F.col("step").cast("long"), "src", "dst", "mult"),
    "SELECT CAST(step AS BIGINT) AS step, CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(mult AS BIGINT) AS mult FROM (VALUES "
    "(0,1,3,1),(0,3,1,1),(0,3,4,1),(0,4,3,1),(0,4,2,1),(0,2,4,1),(1,3,1,1),(1,1,3,1),(1,4,1,1),(1,3,2,1),(1,2,4,1),(1,4,2,1),"
    "(2,1,3,1),(2,3,1,1),(2,1,4,1),(2,2,1,2),(2,4,2,1),(3,3,1,1),(3,1,3,1),(3,4,1,1),(3,1,2,2),(3,2,1,1)) t(step, src, dst, mult)",
)
_FIB = {0: 1, 1: 2, 2: 3, 3: 5, 4: 8, 5: 13}
_add(
    "fibonacci_gap",
    lambda s, d: measures.label_gap(alternating.trace(graphs.seq_path(s, 7), 5)).select(F.col("step").cast("long"), "vertex", "label"),
    "SELECT CAST(f.step AS BIGINT) AS step, CAST(v.range AS BIGINT) AS vertex, CAST(GREATEST(0, v.range - f.gap) AS BIGINT) AS label FROM range(128) v CROSS JOIN (VALUES "
    + ", ".join(f"({k}, {g})" for k, g in _FIB.items()) + ") f(step, gap)",
)
_add(
    "edge_count_invariant",
    lambda s, d: measures.check_invariants(alternating.trace(graphs.seq_path(s, 6), 5), 63).select(F.col("step").cast("long"), "edges", "loops", "rose"),
    "SELECT CAST(range AS BIGINT) AS step, CAST(126 AS BIGINT) AS edges, CAST(0 AS BIGINT) AS loops, CAST(0 AS BIGINT) AS rose FROM range(6)",
)
_add("label_retention", lambda s, d: measures.label_retention(graphs.seq_path(s, 6)))
def _values(columns: str, types: str, rows: str) -> str:
    names = columns.split(", ")
    return "SELECT " + ", ".join(f"CAST({n} AS {t}) AS {n}" for n, t in zip(names, types.split(), strict=True)) + f" FROM (VALUES {rows}) t({columns})"


_COSTS, _COST_TYPES = "method, steps, passes, work, dup_factor, components", "VARCHAR BIGINT BIGINT BIGINT DOUBLE BIGINT"
_add("duplication_factors", lambda s, d: measures.model_costs(s, graphs.seq_path(s, 8), ["alternating", "paired", "paired_within_step", "paired_none"]), _values(
    _COSTS, _COST_TYPES, "('alternating', 13, 13, 6630, 1.0, 1), ('paired', 17, 34, 8670, 1.0, 1), ('paired_within_step', 14, 28, 19020, 4.266667, 1), ('paired_none', 14, 14, 21726, 4.7, 1)"))
_add("model_costs", lambda s, d: measures.model_costs(s, graphs.bridged_grid(s, 16, 4), ["alternating", "paired", "sorted", "min_flood", "hook_compress", "two_star"]), _values(
    _COSTS, _COST_TYPES, "('alternating', 5, 5, 1240, 1.0, 1), ('paired', 11, 22, 1631, 0.870968, 1), ('sorted', 11, 22, 1631, 0.870968, 1), ('min_flood', 5, 5, 1240, 1.0, 1), "
    "('hook_compress', 5, 5, 1240, 1.0, 1), ('two_star', 5, 10, 862, 0.741935, 1)"))
_ORDERS = ", ".join(f"'{''.join(map(str, p))}'" for p in itertools.permutations(range(4)))
_add("four_path_labels", lambda s, d: alternating.connected_components(tables.four_paths(s, d)).whole(), (
    "WITH k AS (SELECT DISTINCT c_custkey AS k, c_custkey >> 2 AS g FROM customer WHERE c_custkey IS NOT NULL), p AS (SELECT g, ROW_NUMBER() OVER (PARTITION BY g ORDER BY k) AS j FROM k), "
    f"v AS (SELECT g, 4 * g + CAST(SUBSTR(LIST_EXTRACT([{_ORDERS}], CAST((g % 24 + 24) % 24 + 1 AS BIGINT)), j, 1) AS BIGINT) AS vertex FROM p) "
    "SELECT vertex, component FROM (SELECT vertex, MIN(vertex) OVER (PARTITION BY g) AS component, COUNT(*) OVER (PARTITION BY g) AS n FROM v) q WHERE n > 1"))


def _bounds(spark, rows):
    """(name, within): whether the steps that change something, one less than those counted, are within the proved bound."""
    return spark.createDataFrame([(n, bool(steps - 1 <= bound)) for n, steps, bound in rows], "name string, within boolean")


def _step_bounds(s, d):
    quiet = {"stop": "quiet_counter"}
    rows = [("four_paths", alternating.connected_components(graphs.all_four_paths(s), **quiet).n_steps, 3)]
    rows += [(f"stars_{a}_{b}_{up}", alternating.run_twins(graphs.star_pair_twins(s, a, b, up), **quiet).n_steps, 3) for a, b in ((3, 4), (6, 2)) for up in (True, False)]
    rows += [(f"path_{e}", alternating.connected_components(graphs.shuffled_path(s, e), **quiet).n_steps, 3 + 3 * (e - 2)) for e in (4, 6, 8)]
    return _bounds(s, rows)


_add("step_bounds", _step_bounds, _values("name, within", "VARCHAR BOOLEAN", ", ".join(
    f"('{n}', true)" for n in ("four_paths", "stars_3_4_True", "stars_3_4_False", "stars_6_2_True", "stars_6_2_False", "path_4", "path_6", "path_8"))))
_add("steps_by_partitions", lambda s, d: _step_counts(s, [(n, graphs.seq_path(s, 6).repartition(n)) for n in (1, 4, 16)]), _values("size, steps", "BIGINT BIGINT", "(1, 11), (4, 11), (16, 11)"))
_add(
    "largest_key", lambda s, d: s.createDataFrame([measures.largest_key(B["customer_supplier"](s, d))], "max_key_rows long, max_acting_key_rows long"),
    f"WITH e AS ({_CS}), t AS (SELECT a AS s, b AS d FROM e UNION ALL SELECT b, a FROM e), k AS (SELECT s, COUNT(*) AS n, MIN(d) AS m FROM t GROUP BY s) "
    "SELECT MAX(n) AS max_key_rows, MAX(CASE WHEN m < s THEN n END) AS max_acting_key_rows FROM k",
)
_add("figure_edge_delta", lambda s, d: measures.edge_delta(alternating.trace(graphs.figure_path(s), 2), 2).select("src", "dst", F.col("change").cast("long")), _values(
    "src, dst, change", "BIGINT BIGINT BIGINT", "(1, 4, 1), (2, 1, 1), (2, 1, 1), (4, 1, -1), (3, 2, -1), (2, 4, -1)"))


def _over(name, fn):
    return lambda s, d: fn(alternating.connected_components(B[name](s, d)).whole())


_CO = SQL["rare_return_orders"]
_add("component_sizes", _over("rare_return_orders", measures.component_sizes), f"SELECT component, COUNT(*) AS n FROM ({_CO}) q GROUP BY component")
_add("size_histogram", _over("rare_return_orders", measures.size_histogram), f"SELECT n, COUNT(*) AS components FROM (SELECT component, COUNT(*) AS n FROM ({_CO}) q GROUP BY component) r GROUP BY n")
_add("largest_components", _over("rare_return_orders", lambda x: measures.largest_components(x, 10)), f"SELECT component, COUNT(*) AS n FROM ({_CO}) q GROUP BY component ORDER BY n DESC, component LIMIT 10")


_add("component_filter", _over("rare_return_orders", lambda x: measures.component_filter(x, 3, 6)), f"WITH q AS ({_CO}) SELECT vertex, component FROM q WHERE component IN (SELECT component FROM q GROUP BY component HAVING COUNT(*) BETWEEN 3 AND 6)")
_add("coverage", _over("rare_return_orders", measures.coverage), f"WITH h AS (SELECT n, COUNT(*) AS components FROM (SELECT component, COUNT(*) AS n FROM ({_CO}) q GROUP BY component) r GROUP BY n) "
     "SELECT n, components, DENSE_RANK() OVER (ORDER BY n DESC) AS size_rank, CAST(SUM(n * components) OVER (ORDER BY n DESC ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS vertices_reached FROM h")


def _rollup(s, d):
    labels = alternating.connected_components(tables.doc_exact(s, d)).whole()
    docs = measures.attach_components(tables.table(s, d, "documents", ["doc_id", "lang", "source"]), "doc_id", labels)
    return docs.rollup("lang", "source").agg(F.count("*").alias("n"), F.count_distinct("component").alias("components"))


_add("component_rollup", _rollup, "WITH x AS (SELECT lang, source, MIN(doc_id) OVER (PARTITION BY text) AS c FROM documents) SELECT lang, source, COUNT(*) AS n, COUNT(DISTINCT c) AS components FROM x GROUP BY ROLLUP (lang, source)")
_add("attach_components", lambda s, d: measures.attach_components(tables.table(s, d, "documents", ["doc_id"]), "doc_id", alternating.connected_components(tables.doc_exact(s, d)).whole()), "SELECT doc_id, MIN(doc_id) OVER (PARTITION BY text) AS component FROM documents")
_add("isolated_vertices", lambda s, d: alternating.connected_components(tables.doc_exact(s, d), vertices=tables.table(s, d, "documents", ["doc_id"]).select(F.col("doc_id").alias("vertex"))).whole(), "SELECT doc_id AS vertex, MIN(doc_id) OVER (PARTITION BY text) AS component FROM documents")


def _incremental(s, d):
    e = B["rare_return_orders"](s, d)
    old = alternating.connected_components(e.where("a % 4 = 0")).whole()
    return incremental.merge_edges(old, e.where("a % 4 <> 0"))


_add("star_merge_sessions", lambda s, d: keyed.components_by_key(tables.session_links(s, d)).select("vertex", "component"), SQL["session_chain"])
_add("incremental_merge", _incremental, SQL["rare_return_orders"])
_add(
    "session_window_components", lambda s, d: session_components(tables.table(s, d, "events", ["event_id", "user_id", "ts"])),
    "WITH o AS (SELECT user_id, event_id, ts, LAG(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events), "
    "f AS (SELECT user_id, event_id, ts, CASE WHEN before IS NULL OR epoch_us(ts) - epoch_us(before) >= 1800000000 THEN 1 ELSE 0 END AS cut FROM o), "
    "i AS (SELECT user_id, event_id, SUM(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM f) "
    "SELECT user_id, MIN(event_id) AS component, COUNT(*) AS n FROM i GROUP BY user_id, k",
)
