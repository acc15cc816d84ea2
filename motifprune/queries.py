"""The engine's registered queries and the SQL that each is held against.

An oracle derives its graph by the same rule and matches by plain staged joins, so it shares no code path
with prefix sets or pruned lists.
"""

from __future__ import annotations

import json
from collections import Counter, OrderedDict
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.operators import counting, kernel, metrics, relational, surface
from motifprune.operators.frontier import Policy, Run, make_plan, match, match_without_prefix_sets, runner
from motifprune.operators.joins import match_joins, match_sql
from motifprune.plans.execution import ExecutionPlan, Options
from motifprune.plans.pattern import CATALOGUE, WORKLOAD, Pattern, automorphisms, connected_shapes
from motifprune.plans.schedule import choose_schedule
from motifprune.sources.graphs import GRAPHS, Graph, checkpoint_folder, edges_sql
from motifprune.streaming.deltas import running_degree_table, running_matches, session_activity, windowed_activity

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


_GRAPHS: OrderedDict[tuple, Graph] = OrderedDict()
KEPT_GRAPHS = 4


def graph_of(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A derived graph; the few last used ones stay persisted, others are freed."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _GRAPHS:
        _GRAPHS[key] = Graph.from_testdata(spark, sf_dir, name)
    _GRAPHS.move_to_end(key)
    while len(_GRAPHS) > KEPT_GRAPHS:
        (app, *_), old = _GRAPHS.popitem(last=False)
        if app == key[0]:
            old.release()
    return _GRAPHS[key]


def add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def on(graph: str, action: Callable[[Graph], DataFrame]) -> Query:
    return lambda spark, sf_dir: action(graph_of(spark, sf_dir, graph))


def _sql(p: Pattern, graph: str, variant: str = "edge", output: str = "count", labels: str | None = None) -> str:
    return match_sql(p, variant, "duckdb", edges_sql(graph), output, labels=labels)


def _with(graph: str, rest: str) -> str:
    return f"WITH e AS MATERIALIZED ({edges_sql(graph)}), arc AS MATERIALIZED (SELECT src AS u, dst AS w FROM e UNION ALL SELECT dst, src FROM e), deg AS MATERIALIZED (SELECT u, count(*) AS d FROM arc GROUP BY u) {rest}"


# ------------------------------------------------------------------ graphs
for g in GRAPHS:
    add(f"graph_summary_{g}", on(g, Graph.summary), _with(g, "SELECT count(*) AS n_vertices, CAST(sum(d) / 2 AS BIGINT) AS n_edges, max(d) AS d_max, round(avg(d), 9) AS d_avg FROM deg"))

_TRIANGLES = "tri AS (SELECT count(*) AS t FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst), sizes AS (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(sum(d) / 2 AS DOUBLE) AS m FROM deg)"


def _stats(g: Graph) -> DataFrame:
    edges = F.nullif("n_edges", F.lit(0))  # a sum over no rows is null in SQL
    n, m, t = (c.cast("double") for c in (F.col("n_vertices"), edges, F.col("n_triangles")))
    return g.stats_frame().select("n_vertices", edges.alias("n_edges"), "n_triangles", F.round(F.try_divide(2 * m, n * n), 9).alias("p1"), F.round(F.least(F.lit(1.0), F.try_divide(6 * t * n, 4 * m * m)), 9).alias("p2"))


for g in ("basket_r", "coact", "colink", "colink_all"):
    add(f"graph_stats_{g}", on(g, _stats), _with(g, f", {_TRIANGLES} SELECT CAST(n AS BIGINT) AS n_vertices, CAST(m AS BIGINT) AS n_edges, t AS n_triangles, round(2 * m / (n * n), 9) AS p1, round(least(1.0, 6 * t * n / (4 * m * m)), 9) AS p2 FROM tri, sizes"))


def _edges(g: Graph) -> DataFrame:
    return g.edges


add("interval_join_edges", on("coact", _edges), edges_sql("coact"))
add("json_filter_edges", on("coact_json", _edges), edges_sql("coact_json"))
add("line_sharing_edges", on("lines", _edges), edges_sql("lines"))
add("line_sharing_edges_all", on("lines_all", _edges), edges_sql("lines_all"))
add("colink_edges_all", on("colink_all", _edges), edges_sql("colink_all"))
add("similar_vector_edges", on("embed", _edges), edges_sql("embed"))
add("relabel_by_degree", on("basket_r25", lambda g: g.relabel("degree")[1]), _with("basket_r25", "SELECT u AS v, row_number() OVER (ORDER BY d, u) - 1 AS new_id FROM deg"))
add("clique4_relabelled", on("basket_r", lambda g: match(g.relabel("degree")[0], CATALOGUE["clique4"], output="count")), _sql(CATALOGUE["clique4"], "basket_r"))
add("sample_half_of_edges", on("basket_r", lambda g: g.sample_edges(0.5).edges), _with("basket_r", "SELECT src, dst FROM e WHERE CAST('0x' || substr(md5('0-' || src || '-' || dst), 1, 8) AS BIGINT) < 2147483648"))
_CORE_ROUNDS = 24  # more than the given tables need; each leaves out what has fallen below the degree
_ROUND = "r{} AS MATERIALIZED (SELECT src, dst FROM r{p} WHERE src IN (SELECT u FROM (SELECT src AS u FROM r{p} UNION ALL SELECT dst FROM r{p}) GROUP BY u HAVING count(*) >= 3) AND dst IN (SELECT u FROM (SELECT src AS u FROM r{p} UNION ALL SELECT dst FROM r{p}) GROUP BY u HAVING count(*) >= 3))"
add("core_of_degree_3", on("basket_r25", lambda g: g.k_core(3).edges), _with("basket_r25", ", r0 AS MATERIALIZED (SELECT src, dst FROM e), " + ", ".join(_ROUND.format(k, p=k - 1) for k in range(1, _CORE_ROUNDS + 1)) + f" SELECT * FROM r{_CORE_ROUNDS}"))
add("high_degree_subgraph", on("basket_r", lambda g: g.subgraph(g.degrees.where("deg >= 15").select(F.col("u").alias("v"))).edges), _with("basket_r", "SELECT src, dst FROM e WHERE src IN (SELECT u FROM deg WHERE d >= 15) AND dst IN (SELECT u FROM deg WHERE d >= 15)"))

# ------------------------------------------------------------------ matching, both variants
for g in ("basket_r", "coact", "lines"):
    for k in (3, 4, 5):
        add(f"clique{k}_count_{g}", on(g, lambda x, k=k: counting.count_cliques(x, k)), _sql(Pattern.of([(a, b) for a in range(k) for b in range(a)]), g))
for k in (3, 4):  # the cliques of 5 of one line that a tenth of the documents share are beyond listing
    add(f"clique{k}_count_lines_all", on("lines_all", lambda x, k=k: counting.count_cliques(x, k)), _sql(Pattern.of([(a, b) for a in range(k) for b in range(a)]), "lines_all"))
for w in WORKLOAD:
    for variant in ("edge", "vertex"):
        for g in ("basket_r", "coact") if w in WORKLOAD[:5] else ("basket_r",):
            add(f"{w}_{variant}_{g}", on(g, lambda x, w=w, v=variant: match(x, CATALOGUE[w], v, output="count")), _sql(CATALOGUE[w], g, variant))
for w in ("clique4", "near_clique5", "clique5"):
    add(f"{w}_vertex_colink", on("colink", lambda x, w=w: match(x, CATALOGUE[w], "vertex", output="count")), _sql(CATALOGUE[w], "colink", "vertex"))
for w in ("clique4", "near_clique5", "clique5"):
    add(f"{w}_vertex_colink_all", on("colink_all", lambda x, w=w: match(x, CATALOGUE[w], "vertex", output="count")), _sql(CATALOGUE[w], "colink_all", "vertex"))
for w in ("path4", "star4", "cycle4", "tailed_triangle", "diamond", "cycle5", "bowtie"):
    add(f"{w}_edge_basket_r25", on("basket_r25", lambda x, w=w: match(x, CATALOGUE[w], output="count")), _sql(CATALOGUE[w], "basket_r25"))
add("house5_rows_edge", on("basket_r25", lambda g: match(g, CATALOGUE["house5"])), _sql(CATALOGUE["house5"], "basket_r25", "edge", "rows"))
add("clique4_rows_vertex", on("basket_r25", lambda g: match(g, CATALOGUE["clique4"], "vertex")), _sql(CATALOGUE["clique4"], "basket_r25", "vertex", "rows"))
add("house5_cost_schedule", on("basket_r", lambda g: match(g, CATALOGUE["house5"], schedule=choose_schedule(CATALOGUE["house5"], g.stats, "cost"), output="count")), _sql(CATALOGUE["house5"], "basket_r"))

# ------------------------------------------------------------------ policies and options
for w, g in (("clique4", "coact"), ("near_clique5", "coact"), ("house5", "basket_r")):
    for policy in ("none", "eager", "degree", "random", "oracle"):
        add(f"{w}_{policy}", on(g, lambda x, w=w, p=policy: match(x, CATALOGUE[w], policy=p, output="count")), _sql(CATALOGUE[w], g))
add("near_clique5_lazy_hubs", on("coact", lambda g: match(g, CATALOGUE["near_clique5"], policy=Policy("eager", lazy_degree=16), output="count")), _sql(CATALOGUE["near_clique5"], "coact"))
add("near_clique5_literal_model", on("coact", lambda g: match(g, CATALOGUE["near_clique5"], policy=Policy("online", order_discount=False), bound_prefix=False, output="count")), _sql(CATALOGUE["near_clique5"], "coact"))
for w in ("clique5", "wheel6"):
    add(f"{w}_without_reuse", on("basket_r", lambda x, w=w: match(x, CATALOGUE[w], "vertex", "eager", "count", reuse_aux=False)), _sql(CATALOGUE[w], "basket_r", "vertex"))
    add(f"{w}_without_sharing", on("basket_r", lambda x, w=w: match(x, CATALOGUE[w], "vertex", "none", "count", share=False, merge=False)), _sql(CATALOGUE[w], "basket_r", "vertex"))

# ------------------------------------------------------------------ engines and baselines


def _kernel(w: str, variant: str, **options) -> Callable[[Graph], DataFrame]:
    return lambda g: kernel.match_kernel(g, make_plan(CATALOGUE[w], variant), **options).agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))


for w, variant in (("clique4", "edge"), ("house5", "vertex"), ("wheel6", "vertex")):
    oracle = _sql(CATALOGUE[w], "basket_r", variant)
    add(f"{w}_kernel", on("basket_r", _kernel(w, variant, policy="online")), oracle)
    add(f"{w}_kernel_nested", on("basket_r", _kernel(w, variant, policy="online", nested=True, split_threshold=8)), oracle)
    add(f"{w}_compiled_baseline", on("basket_r", _kernel(w, variant, policy="none")), oracle)
for w in ("clique4", "house5"):
    add(f"{w}_interpreted", on("basket_r", _kernel(w, "edge", policy="none", engine="interpreted")), _sql(CATALOGUE[w], "basket_r"))
    add(f"{w}_scratch_sets", on("basket_r", lambda x, w=w: match_without_prefix_sets(x, CATALOGUE[w])), _sql(CATALOGUE[w], "basket_r"))
    add(f"{w}_scratch_sets_vertex", on("basket_r", lambda x, w=w: match_without_prefix_sets(x, CATALOGUE[w], "vertex")), _sql(CATALOGUE[w], "basket_r", "vertex"))
    add(f"{w}_binary_join", on("basket_r", lambda x, w=w: match_joins(x, CATALOGUE[w])), _sql(CATALOGUE[w], "basket_r"))
add("house5_kernel_rows", on("basket_r25", lambda g: kernel.match_kernel(g, make_plan(CATALOGUE["house5"]), "online", output="rows")), _sql(CATALOGUE["house5"], "basket_r25", "edge", "rows"))
for w in ("star4", "cycle4", "near_clique5", "house5"):
    add(f"count_tail_factor_{w}", on("basket_r", lambda x, w=w: counting.count_tail_factor(x, CATALOGUE[w])), _sql(CATALOGUE[w], "basket_r"))

# ------------------------------------------------------------------ pruned lists and the cost model (clique of 4, sets unbounded)
_OPEN = {"bound_prefix": False}
_COMMON = ", meet AS (SELECT a.u, a.w, count(c.w) AS n, CAST(coalesce(sum(c.w), 0) AS BIGINT) AS s FROM arc a LEFT JOIN (SELECT x.u AS p, y.u AS q, x.w FROM arc x JOIN arc y ON x.w = y.w) c ON c.p = a.u AND c.q = a.w GROUP BY a.u, a.w)"
_READS = ", reads AS (SELECT a.u AS u1, b.w AS x, count(*) AS reads FROM arc a JOIN arc b ON a.u = b.u JOIN arc c ON c.u = a.w AND c.w = b.w WHERE a.u < a.w AND a.u < b.w AND a.w < b.w GROUP BY a.u, b.w)"


def _aux_table(g: Graph) -> DataFrame:
    run = runner(g, CATALOGUE["clique4"], "edge", "eager", **_OPEN)
    run._build(run.start(), 1)
    return run.tables[0].select("u1", "x", F.size("keep").cast("long").alias("n"), F.aggregate("keep", F.lit(0).cast("long"), lambda a, b: a + b).alias("ids_sum"))


def _truth(g: Graph) -> DataFrame:
    return metrics.list_truth(runner(g, CATALOGUE["clique4"], "edge", "eager", **_OPEN), 0)


def _guess(g: Graph) -> DataFrame:
    run = runner(g, CATALOGUE["clique4"], "edge", Policy("online", order_discount=False), **_OPEN)
    guess = F.round("reuse", 5).alias("reuse"), F.round("overlap", 5).alias("overlap"), (F.col("gain") > 0).alias("build")
    by_class = metrics.guessed_by_class(run, 0)
    if by_class is not None:  # estimated once for two classes
        return by_class.select("us", "xs", *guess).select(F.explode("us").alias("u1"), "xs", "reuse", "overlap", "build").select("u1", F.explode("xs").alias("x"), "reuse", "overlap", "build").where("u1 <> x")
    return run.considered(run.start(), run.plan.aux[0]).select("u1", "x", *guess)


add("aux_graph_1_3_4", on("basket_r", _aux_table), _with("basket_r", _COMMON + " SELECT u AS u1, w AS x, n, s AS ids_sum FROM meet"))
add("aux_reuse_true", on("basket_r", lambda g: runner(g, CATALOGUE["clique4"], **_OPEN).true_reuse(make_plan(CATALOGUE["clique4"], **_OPEN).aux[0])), _with("basket_r", _READS + " SELECT * FROM reads"))
_EXACT = _with("basket_r", _COMMON + _READS + " SELECT b.u AS u1, b.w AS x, dx.d AS deg, du.d AS keep_size, b.n AS overlap, coalesce(r.reads, 0) AS reads, coalesce(r.reads, 0) * (dx.d - b.n) - (du.d + dx.d) AS gain FROM meet b JOIN deg dx ON dx.u = b.w JOIN deg du ON du.u = b.u LEFT JOIN reads r ON r.u1 = b.u AND r.x = b.w")
add("gain_exact", on("basket_r", _truth), _EXACT)
_WORK = "CAST(coalesce(sum({}), 0) AS BIGINT) AS "
add(
    "work_plain_vs_pruned",
    on("basket_r", lambda g: _truth(g).agg(F.sum(F.col("reads") * F.col("deg")).alias("list_reads_plain"), F.sum(F.col("keep_size") + F.col("deg") + F.col("reads") * F.col("overlap")).cast("long").alias("list_reads_pruned"), F.sum("gain").alias("gain"))),
    f"SELECT {_WORK.format('reads * deg')}list_reads_plain, {_WORK.format('keep_size + deg + reads * overlap')}list_reads_pruned, {_WORK.format('gain')}gain FROM ({_EXACT})",
)
add(
    "gain_online",
    on("coact", _guess),
    _with("coact", f", {_TRIANGLES}, p AS (SELECT n, least(1.0, 6 * t * n / (4 * m * m)) AS p2 FROM tri, sizes), g AS (SELECT a.u AS u1, a.w AS x, du.d * p2 AS reuse, du.d * dx.d / n AS overlap, CAST(dx.d AS DOUBLE) AS dx, CAST(du.d AS DOUBLE) AS du FROM arc a JOIN deg du ON du.u = a.u JOIN deg dx ON dx.u = a.w, p) SELECT u1, x, round(reuse, 5) AS reuse, round(overlap, 5) AS overlap, reuse * (dx - overlap) - (du + dx) > 0 AS build FROM g"),
)
_W1_WORK = ", ops AS (SELECT floor(log2(d2.d)) AS degree_bucket, d1.d AS prefix, d2.d AS adjacency FROM arc a JOIN deg d1 ON d1.u = a.u JOIN deg d2 ON d2.u = a.w WHERE a.u < a.w UNION ALL SELECT floor(log2(d3.d)), b.n, d3.d FROM meet b JOIN arc x ON x.u = b.u JOIN arc y ON y.u = b.w AND y.w = x.w JOIN deg d3 ON d3.u = x.w WHERE b.u < b.w AND b.w < x.w)"
add("comparisons_by_degree_none", on("basket_r", lambda g: _by_degree(g)), _with("basket_r", _COMMON + _W1_WORK + " SELECT CAST(degree_bucket AS INTEGER) AS degree_bucket, CAST(sum(prefix) AS BIGINT) AS prefix, CAST(sum(adjacency) AS BIGINT) AS adjacency FROM ops GROUP BY degree_bucket"))
add("adjacency_scan_share_clique4", on("basket_r", lambda g: metrics.adjacency_scan_share(g, CATALOGUE["clique4"], **_OPEN)), _with("basket_r", _COMMON + _W1_WORK + " SELECT round(100 * CAST(sum(adjacency) AS DOUBLE) / (sum(prefix) + sum(adjacency)), 6) AS share FROM ops"))


def _by_degree(g: Graph) -> DataFrame:
    got = metrics.work_counters(g, CATALOGUE["clique4"], "edge", "none", **_OPEN)
    return got.groupBy("degree_bucket").pivot("metric", ["prefix", "adjacency"]).agg(F.sum("value"))


def _prefix_sizes(g: Graph) -> DataFrame:
    run = Run(g, make_plan(CATALOGUE["clique4"], **_OPEN))
    key = run.plan.key(2, 3)
    return run.frame(2).select("u1", "u2", F.size(run.column(key)).cast("long").alias("n"))


def _list_maps(g: Graph) -> DataFrame:
    run = runner(g, CATALOGUE["clique4"], "edge", "eager", **_OPEN)
    run._build(run.start(), 1)
    maps = surface.list_maps(run, 0)
    return maps.select("u1", F.size("lists").cast("long").alias("lists"), F.aggregate(F.map_values("lists"), F.lit(0).cast("long"), lambda n, x: n + F.size(x)).alias("kept"))


add("aux_map_1_3_4", on("basket_r", _list_maps), _with("basket_r", _COMMON + " SELECT u AS u1, count(*) AS lists, CAST(sum(n) AS BIGINT) AS kept FROM meet GROUP BY u"))
add("prefix_set_sizes", on("basket_r", _prefix_sizes), _with("basket_r", _COMMON + " SELECT u AS u1, w AS u2, n FROM meet WHERE u < w"))

# ------------------------------------------------------------------ applications
for k, g in ((3, "basket_r25"), (4, "basket_r25"), (5, "basket_r25"), (3, "colink"), (3, "colink_all")):
    names = {p.canonical_form(): n for n, p in CATALOGUE.items() if p.n == k}
    parts = [f"SELECT '{names.get(p.canonical_form(), f'shape{k}_{at}')}' AS shape, {len(p.edges)} AS n_edges, cnt FROM ({_sql(p, g, 'vertex')})" for at, p in enumerate(connected_shapes(k))]
    add(f"motif{k}_census_{g}", on(g, lambda x, k=k: counting.motif_census(x, k)), " UNION ALL ".join(parts))
_KIND = "SELECT DISTINCT v, CAST(floor(v / 1000000) AS INTEGER) AS label FROM (SELECT src AS v FROM e UNION SELECT dst FROM e)"
_LABEL = "SELECT vec_id AS v, CAST(label AS INTEGER) AS label FROM embeddings"
_SALE = Pattern.of([(0, 1), (1, 2), (0, 2)], (1, 2, 3), "sale")
_CHAIN = Pattern.of([(0, 1), (1, 2)], (1, 2, 3), "chain")
_MIXED = Pattern.of([(0, 1), (1, 2)], (0, 1, 0), "mixed")
add("labelled_triangle", on("commerce", lambda g: match(g, _SALE, output="count")), _sql(_SALE, "commerce", labels=_KIND))
add("labelled_diamond", on("commerce", lambda g: match(g, _DIAMOND, "vertex", "none", "count")), None)
_DIAMOND = Pattern.of([(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)], (1, 2, 3, 1), "two_buyers")
ORACLES["labelled_diamond"] = _sql(_DIAMOND, "commerce", "vertex", labels=_KIND)
add("labelled_wedge_embed", on("embed", lambda g: match(g, _MIXED, output="count")), _sql(_MIXED, "embed", labels=_LABEL))
add("support_chain", on("commerce", lambda g: counting.pattern_support(g, _CHAIN)), f"SELECT least(count(DISTINCT v1), count(DISTINCT v2), count(DISTINCT v3)) AS support FROM ({_sql(_CHAIN, 'commerce', 'edge', 'rows', _KIND)})")
_PATHS = f"""
WITH e AS MATERIALIZED ({edges_sql('commerce')}), lab AS ({_KIND}),
arc AS MATERIALIZED (SELECT a.u, a.w, x.label AS lu, y.label AS lw FROM (SELECT src AS u, dst AS w FROM e UNION ALL SELECT dst, src FROM e) a JOIN lab x ON x.v = a.u JOIN lab y ON y.v = a.w),
two AS (SELECT lu || '-' || lw AS labels, least(count(DISTINCT u), count(DISTINCT w)) AS support FROM arc WHERE lu <= lw GROUP BY lu, lw),
three AS (SELECT a.lu || '-' || a.lw || '-' || b.lw AS labels, least(count(DISTINCT a.u), count(DISTINCT a.w), count(DISTINCT b.w)) AS support FROM arc a JOIN arc b ON b.u = a.w AND b.w <> a.u WHERE a.lu <= b.lw GROUP BY a.lu, a.lw, b.lw)
SELECT 'path2' AS pattern, labels, support FROM two WHERE support >= 20 UNION ALL SELECT 'path3', labels, support FROM three WHERE support >= 20"""
add("frequent_labelled_paths", on("commerce", lambda g: counting.frequent_patterns(g, 20)), _PATHS)
for kind, query in {
    "kernel": lambda g: kernel.match_kernel(g, make_plan(_SALE), "online").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt")),
    "interpreted": lambda g: kernel.match_kernel(g, make_plan(_SALE), "none", engine="interpreted").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt")),
    "ego": lambda g: kernel.match_kernel(g, make_plan(_SALE), "online", most_arcs=0).agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt")),
    "scratch": lambda g: match_without_prefix_sets(g, _SALE),
    "eager": lambda g: match(g, _SALE, policy="eager", output="count"),
}.items():
    add(f"labelled_triangle_{kind}", on("commerce", query), _sql(_SALE, "commerce", labels=_KIND))

# ------------------------------------------------------------------ relational operators around matches
_K4 = CATALOGUE["clique4"]
_ROOTS = f"SELECT v{choose_schedule(_K4).order[0] + 1} AS root, count(*) AS cnt FROM ({_sql(_K4, 'basket_r', 'edge', 'rows')}) GROUP BY 1"
add("seeded_match", on("basket_r", lambda g: relational.seeded_match(g, _K4, g.degrees.where("deg >= 20").select("u"))), f"SELECT m.* FROM ({_sql(_K4, 'basket_r', 'edge', 'rows')}) m WHERE v{choose_schedule(_K4).order[0] + 1} IN ({_with('basket_r', 'SELECT u FROM deg WHERE d >= 20')})")
add("topk_roots", on("basket_r", lambda g: relational.topk_roots(g, _K4)), f"SELECT * FROM ({_ROOTS}) ORDER BY cnt DESC, root LIMIT 10")
add("match_rank_window", on("basket_r", lambda g: relational.rank_in_degree_class(g, _K4)), f"SELECT CAST(degree_bucket AS INTEGER) AS degree_bucket, root, cnt, CAST(place AS INTEGER) AS place FROM (SELECT *, row_number() OVER (PARTITION BY degree_bucket ORDER BY cnt DESC, root) AS place FROM (SELECT floor(log2(d)) AS degree_bucket, root, cnt FROM ({_ROOTS}) r JOIN ({_with('basket_r', 'SELECT * FROM deg')}) x ON x.u = r.root)) WHERE place <= 3")
for kind in ("rollup", "cube"):
    add(f"{kind}_report", on("basket_r", lambda g, k=kind: relational.edge_report(g, k)), _with("basket_r", f"SELECT CAST(coalesce(low, -1) AS INTEGER) AS low, CAST(coalesce(high, -1) AS INTEGER) AS high, count(*) AS edges FROM (SELECT least(floor(log2(a.d)), floor(log2(b.d))) AS low, greatest(floor(log2(a.d)), floor(log2(b.d))) AS high FROM e JOIN deg a ON a.u = src JOIN deg b ON b.u = dst) GROUP BY {kind}(low, high)"))
add("degree_deciles", on("basket_r", relational.degree_deciles), _with("basket_r", "SELECT CAST(decile AS INTEGER) AS decile, count(*) AS vertices, min(d) AS least, max(d) AS most FROM (SELECT *, ntile(10) OVER (ORDER BY d, u) AS decile FROM deg) GROUP BY decile"))
_EVENTS: Callable[[SparkSession, str], DataFrame] = lambda spark, d: spark.read.parquet(f"{d}/events.parquet")
add("session_counts", lambda s, d: relational.sessions(_EVENTS(s, d)), "SELECT user_id, CAST(session_no AS BIGINT) AS session_no, count(*) AS n_events FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session_no FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 1800 SECOND THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY ALL")
add("last_click_before_purchase", lambda s, d: relational.last_before(_EVENTS(s, d), "click", "purchase"), "SELECT event_id, coalesce(earlier_id, -1) AS earlier_id FROM (SELECT *, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS earlier_id FROM events WHERE event_type IN ('click', 'purchase')) WHERE event_type = 'purchase'")
add("hourly_activity", lambda s, d: windowed_activity(_EVENTS(s, d)).drop("n_users", "window_start").groupBy("event_type").agg(F.count("*").alias("hours"), F.sum("n_events").alias("n_events")), "SELECT event_type, count(*) AS hours, CAST(sum(n) AS BIGINT) AS n_events FROM (SELECT event_type, date_trunc('hour', ts) AS h, count(*) AS n FROM events GROUP BY ALL) GROUP BY event_type")


def _edge_files(spark: SparkSession, sf_dir: str, use: str) -> str:
    g = graph_of(spark, sf_dir, "basket_r25")
    path = f"{checkpoint_folder(spark)}/edge-stream-{use}-{abs(hash(sf_dir))}"
    timed = g.edges.withColumn("ts", F.timestamp_seconds(F.lit(1_700_000_000) + F.pmod(F.xxhash64("src", "dst"), F.lit(4)) * 60))
    timed.repartition(4, "ts").write.mode("overwrite").parquet(path)
    return path


def _stream_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triangles found batch by batch as edges arrive in four files."""
    found = running_matches(spark, _edge_files(spark, sf_dir, "matches"), CATALOGUE["triangle"])
    return spark.createDataFrame([(sum(n for _, n in found),)], "cnt long")


add("stream_delta_total", _stream_total, _sql(CATALOGUE["triangle"], "basket_r25"))

def _stream_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degrees kept as state while edges arrive in four files."""
    return running_degree_table(spark, _edge_files(spark, sf_dir, "degrees"))


add("stream_running_degrees", _stream_degrees, _with("basket_r25", "SELECT u, d AS degree FROM deg"))
add("session_window_counts", lambda s, d: session_activity(_EVENTS(s, d)).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n_events").alias("n_events")), "SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS n_events FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 1800 SECOND THEN 0 ELSE 1 END AS fresh FROM events) GROUP BY user_id")

# ------------------------------------------------------------------ planning tables (of the patterns, with the baskets of lineitem that can hold each)
_SIZES = ", ".join(f"('{w}', {CATALOGUE[w].n})" for w in WORKLOAD)


def _with_baskets(plans: DataFrame, sf_dir: str) -> DataFrame:
    """plans with baskets: the orders that have at least as many different parts as the pattern has vertices."""
    spark = plans.sparkSession
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    sizes = lines.groupBy("l_orderkey").agg(F.countDistinct("l_partkey").alias("k")).groupBy("k").agg(F.count("*").alias("orders"))
    needs = spark.createDataFrame([(w, CATALOGUE[w].n) for w in WORKLOAD], "pattern string, n int")
    held = needs.join(F.broadcast(sizes), F.col("k") >= F.col("n"), "left").groupBy("pattern").agg(F.coalesce(F.sum("orders"), F.lit(0)).alias("baskets"))
    return plans.join(held, "pattern")


def _with_baskets_sql(plans: str) -> str:
    sizes = "SELECT k, count(*) AS orders FROM (SELECT count(DISTINCT l_partkey) AS k FROM lineitem GROUP BY l_orderkey) GROUP BY k"
    return f"WITH sizes AS ({sizes}), held AS (SELECT pattern, CAST(coalesce(sum(orders), 0) AS BIGINT) AS baskets FROM (VALUES {_SIZES}) p(pattern, n) LEFT JOIN sizes ON k >= n GROUP BY pattern) SELECT * FROM ({plans}) JOIN held USING (pattern)"


_SPECS = {"clique4": (24, 1, 1), "house5": (2, 1, 2), "near_clique5": (12, 2, 4), "clique5": (120, 4, 4), "wheel6": (10, 6, 10), "prism6": (12, 2, 3), "octahedron6": (48, 6, 7), "near_clique7": (240, 16, 20)}


def _spec_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(w, len(automorphisms(CATALOGUE[w])), *(ExecutionPlan(choose_schedule(CATALOGUE[w]), Options(v, bound_prefix=False)).unbounded_specs() for v in ("edge", "vertex"))) for w in WORKLOAD]
    return _with_baskets(spark.createDataFrame(rows, "pattern string, automorphisms int, specs_edge int, specs_vertex int"), sf_dir)


add("aux_spec_table", _spec_table, _with_baskets_sql("SELECT * FROM (VALUES " + ", ".join(f"('{w}', {a}, {b}, {c})" for w, (a, b, c) in _SPECS.items()) + ") t(pattern, automorphisms, specs_edge, specs_vertex)"))
_SCHEDULES = {  # fixed values: matching order, and pairs of places whose ids ascend
    "clique4": ("(0, 1, 2, 3)", "((1, 2), (1, 3), (1, 4), (2, 3), (2, 4), (3, 4))"),
    "house5": ("(0, 1, 4, 2, 3)", "((1, 2),)"),
    "near_clique5": ("(0, 1, 2, 3, 4)", "((1, 2), (1, 3), (2, 3), (4, 5))"),
    "clique5": ("(0, 1, 2, 3, 4)", "((1, 2), (1, 3), (1, 4), (1, 5), (2, 3), (2, 4), (2, 5), (3, 4), (3, 5), (4, 5))"),
    "wheel6": ("(0, 1, 2, 3, 4, 5)", "((2, 3), (2, 4), (2, 5), (2, 6), (3, 6))"),
    "prism6": ("(0, 1, 2, 3, 4, 5)", "((1, 2), (1, 3), (1, 4), (1, 5), (1, 6), (2, 3))"),
    "octahedron6": ("(0, 2, 4, 1, 3, 5)", "((1, 2), (1, 3), (1, 4), (1, 5), (1, 6), (2, 3), (2, 5), (2, 6), (3, 6))"),
    "near_clique7": ("(0, 1, 2, 3, 4, 5, 6)", "((1, 2), (1, 3), (1, 4), (1, 5), (2, 3), (2, 4), (2, 5), (3, 4), (3, 5), (4, 5), (6, 7))"),
}
add("schedule_table", lambda s, d: _with_baskets(s.createDataFrame([(w, str(choose_schedule(CATALOGUE[w]).order), str(choose_schedule(CATALOGUE[w]).checks)) for w in WORKLOAD], "pattern string, matching_order string, checks string"), d), _with_baskets_sql("SELECT * FROM (VALUES " + ", ".join(f"('{w}', '{o}', '{c}')" for w, (o, c) in _SCHEDULES.items()) + ") t(pattern, matching_order, checks)"))
_PLANS = {  # fixed values: steps by kind, pruned lists, those built from others
    ("clique4", "edge"): (3, 3, 0, 0, 1, 0),
    ("clique4", "vertex"): (3, 3, 0, 0, 1, 0),
    ("house5", "edge"): (4, 2, 0, 3, 1, 0),
    ("house5", "vertex"): (4, 2, 3, 0, 2, 0),
    ("near_clique5", "edge"): (4, 5, 0, 1, 1, 0),
    ("near_clique5", "vertex"): (4, 5, 1, 0, 3, 1),
    ("clique5", "edge"): (4, 6, 0, 0, 2, 1),
    ("clique5", "vertex"): (4, 6, 0, 0, 2, 1),
    ("wheel6", "edge"): (5, 5, 0, 5, 4, 3),
    ("wheel6", "vertex"): (5, 5, 5, 0, 4, 3),
    ("prism6", "edge"): (5, 4, 0, 3, 2, 0),
    ("prism6", "vertex"): (5, 4, 3, 0, 3, 0),
    ("octahedron6", "edge"): (5, 7, 0, 2, 5, 2),
    ("octahedron6", "vertex"): (5, 7, 2, 0, 5, 2),
    ("near_clique7", "edge"): (6, 14, 0, 1, 5, 3),
    ("near_clique7", "vertex"): (6, 14, 1, 0, 9, 6),
}


def _plan_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps and pruned lists of each workload's plan, read from its exported form."""
    rows = []
    for w in WORKLOAD:
        for v in ("edge", "vertex"):
            plan = json.loads(surface.plan_json(make_plan(CATALOGUE[w], v)))
            kinds = Counter(x["kind"] for x in plan["steps"])
            rows.append((w, v, *(kinds[k] for k in ("init", "intersect", "subtract", "carry")), len(plan["aux"]), sum(x["parent"] is not None for x in plan["aux"])))
    return _with_baskets(spark.createDataFrame(rows, "pattern string, variant string, inits int, intersections int, subtractions int, carried int, lists int, built_from_lists int"), sf_dir)


add("plan_table", _plan_table, _with_baskets_sql("SELECT * FROM (VALUES " + ", ".join(f"('{w}', '{v}', {', '.join(map(str, n))})" for (w, v), n in _PLANS.items()) + ") t(pattern, variant, inits, intersections, subtractions, carried, lists, built_from_lists)"))

# ------------------------------------------------------------------ experiment workloads
# Seconds, ratios and work differ from run to run or have no SQL: they come from metrics' functions and bench.py. The
# queries run the same experiments and give their counts, which SQL holds; those on work alone are held by tests.
_FULL = [CATALOGUE[w] for w in WORKLOAD]
_FIRST5 = _FULL[:5]
SIX_GRAPHS = ("basket_r", "coact", "coact600", "commerce", "colink", "embed")


def _counts_sql(patterns: list[Pattern], graph: str, variant: str, name: str, values: tuple, more: str = "") -> str:
    """The count of each pattern, repeated for each value of a column."""
    own = " UNION ALL ".join(f"SELECT '{p.name}' AS pattern, cnt FROM ({_sql(p, graph, variant)})" for p in patterns)
    each = ", ".join(f"({v!r})" if isinstance(v, str) else f"({str(v).lower()})" for v in values)
    return f"SELECT {more}pattern, {name}, cnt FROM ({own}) CROSS JOIN (VALUES {each}) t({name})"


_modes = tuple(m for m, _, _ in metrics.MODES)
add("ablation_grid", on("coact", lambda g: metrics.ablation(g, _FIRST5).select("pattern", "mode", "cnt")), _counts_sql(_FIRST5, "coact", "vertex", "mode", _modes))
for variant in ("edge", "vertex"):
    add(f"base_against_online_{variant}", on("basket_r", lambda g, v=variant: metrics.ablation(g, _FULL, v).select("pattern", "mode", "cnt")), _counts_sql(_FULL, "basket_r", variant, "mode", _modes))
    add(f"against_compiled_{variant}", on("basket_r", lambda g, v=variant: metrics.compare_engines(g, _FULL, v, ("online+nested", "compiled")).select("pattern", "engine", "cnt")), _counts_sql(_FULL, "basket_r", variant, "engine", ("online+nested", "compiled")))
add("against_interpreted_edge", on("basket_r", lambda g: metrics.compare_engines(g, _FULL, "edge", ("online+nested", "interpreted")).select("pattern", "engine", "cnt")), _counts_sql(_FULL, "basket_r", "edge", "engine", ("online+nested", "interpreted")))
add("against_counting_edge", on("basket_r", lambda g: metrics.compare_engines(g, _FULL, "edge", ("online+nested", "tail_factor")).select("pattern", "engine", "cnt")), _counts_sql(_FULL, "basket_r", "edge", "engine", ("online+nested", "tail_factor")))


def _reuse_on_off(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [metrics.reuse_ablation(graph_of(spark, sf_dir, g), [CATALOGUE["clique5"], CATALOGUE["wheel6"]]).select("graph", "pattern", "reuse", "cnt") for g in SIX_GRAPHS]
    return reduce(DataFrame.unionByName, parts)


add("reuse_on_off", _reuse_on_off, " UNION ALL ".join(_counts_sql([CATALOGUE["clique5"], CATALOGUE["wheel6"]], g, "vertex", "reuse", (False, True), f"'{g}' AS graph, ") for g in SIX_GRAPHS))
add("policy_comparison", on("coact", lambda g: metrics.policy_comparison(g, _FIRST5, work=False).select("pattern", "policy", "cnt")), _counts_sql(_FIRST5, "coact", "edge", "policy", ("none", "eager", "online", "degree", "random", "oracle")))
add("compile_time", on("basket_r", lambda g: metrics.compile_time(g, _FULL).select("pattern", "engine", (F.col("seconds") > 0).alias("timed"))), "SELECT pattern, engine, true AS timed FROM (VALUES " + ", ".join(f"('{w}')" for w in WORKLOAD) + ") p(pattern) CROSS JOIN (VALUES ('generated'), ('interpreted'), ('frontier')) e(engine)")


def _balance(g: Graph) -> DataFrame:
    parts = [metrics.task_balance(g, make_plan(CATALOGUE["house5"], "vertex"), policy, nested).select(F.lit(mode).alias("mode"), "cnt", (F.col("imbalance") >= 1).alias("measured")) for mode, policy, nested in metrics.MODES]
    return reduce(DataFrame.unionByName, parts)


add("task_balance", on("basket_r", _balance), f"SELECT mode, cnt, true AS measured FROM ({_counts_sql([CATALOGUE['house5']], 'basket_r', 'vertex', 'mode', _modes)})")
add("aux_bytes", on("basket_r", lambda g: metrics.aux_memory(g, _FULL).select("pattern", "variant", "graph_bytes")), _with("basket_r", ", x AS (SELECT CAST(sum(d) * 8 AS BIGINT) AS graph_bytes FROM deg) SELECT pattern, variant, graph_bytes FROM x CROSS JOIN (VALUES " + ", ".join(f"('{w}')" for w in WORKLOAD) + ") p(pattern) CROSS JOIN (VALUES ('edge'), ('vertex')) v(variant)"))
add("list_usage", on("basket_r", lambda g: metrics.list_usage(g, _FULL, policy="eager").select("pattern", (F.col("used") + F.col("unused") == F.col("built")).alias("adds_up"), (F.col("built") == F.col("considered")).alias("all_built"))), "SELECT pattern, true AS adds_up, true AS all_built FROM (VALUES " + ", ".join(f"('{w}')" for w in WORKLOAD) + ") p(pattern)")
add("comparisons_by_degree_near_clique5", on("coact", lambda g: metrics.comparisons_by_degree(g, CATALOGUE["near_clique5"])))
add("audit_cost_model", on("coact", lambda g: metrics.audit_cost_model(g, CATALOGUE["clique4"])))


def _shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scan shares of cliques with sets unbounded, on six graphs."""
    rows = [(g, *(metrics.adjacency_scan_share(graph_of(spark, sf_dir, g), CATALOGUE[w]).first()[0] for w in ("clique4", "clique5"))) for g in SIX_GRAPHS]
    return spark.createDataFrame(rows, "graph string, clique4 double, clique5 double")


add("adjacency_scan_shares", _shares)


def _clique4_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [metrics.adjacency_scan_share(graph_of(spark, sf_dir, g), CATALOGUE["clique4"], **_OPEN).select(F.lit(g).alias("graph"), "share") for g in SIX_GRAPHS]
    return reduce(DataFrame.unionByName, parts)


add("adjacency_scan_shares_clique4", _clique4_shares, " UNION ALL ".join(f"SELECT '{g}' AS graph, share FROM ({_with(g, _COMMON + _W1_WORK + ' SELECT round(100 * CAST(sum(adjacency) AS DOUBLE) / (sum(prefix) + sum(adjacency)), 6) AS share FROM ops')})" for g in SIX_GRAPHS))
