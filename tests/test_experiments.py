import time

import pytest
from motifprune.operators import counting, kernel, metrics, surface
from motifprune.operators.frontier import Run, make_plan, match, runner
from motifprune.operators.joins import brute_force
from motifprune.plans.pattern import CATALOGUE, Pattern
from motifprune.sources.graphs import Graph
from motifprune.streaming.deltas import delta_matches, running_degree_table, session_activity
from pyspark.sql import functions as F
from test_matching import some_graph


@pytest.fixture(scope="module")
def graph(spark):
    pairs = some_graph(12, 0.5, 3)
    return Graph.of(spark, pairs, {v: v % 2 for v in range(12)}).cached(), set(pairs)


def test_ablation_and_engines_agree(graph):
    g, edges = graph
    p = CATALOGUE["near_clique5"]
    want = len(brute_force(edges, p, "vertex"))
    rows = metrics.ablation(g, [p]).collect()
    assert [r["mode"] for r in rows] == ["base", "base+nested", "online", "online+nested"]
    assert {r["cnt"] for r in rows} == {want} and all(r["imbalance"] >= 1 and r["speedup"] > 0 and not r["over_limit"] for r in rows)
    assert rows[0]["comparisons"] == rows[1]["comparisons"]  # cutting roots changes no work
    got = metrics.compare_engines(g, [p], "edge", metrics.ENGINES).collect()
    assert {r["cnt"] for r in got} == {len(brute_force(edges, p))} and len(got) == 5


def test_time_limit_leaves_a_marker(spark, graph):
    slow = spark.range(4).repartition(4).mapInPandas(lambda batches: ((time.sleep(20), b)[1] for b in batches), "id long")
    out, seconds, over = metrics.timed_within(spark, slow.count, 1.5)
    assert out is None and over and seconds < 15
    with pytest.raises(ZeroDivisionError):
        metrics.timed_within(spark, lambda: 1 / 0, 60)
    row = metrics.timed_match(graph[0], CATALOGUE["triangle"], limit=600)
    assert row["cnt"] == len(brute_force(graph[1], CATALOGUE["triangle"])) and not row["over_limit"]


def test_lists_alive_at_once(spark):
    """Two roots' lists are never alive together: the most bytes of a worker are those of its richest root."""
    six = Graph.of(spark, [(1, 2), (1, 3), (1, 4), (2, 3), (2, 4), (3, 4), (2, 5), (3, 6), (4, 5)])
    plan = make_plan(CATALOGUE["clique4"], "edge", bound_prefix=False)
    per_root = {r["root"]: r["aux_bytes"] for r in kernel.match_kernel(six, plan, "eager").collect()}
    assert per_root[1] == 8 * 6  # of vertices 2, 3 and 4: two neighbours each
    assert metrics.aux_memory(six, [CATALOGUE["clique4"]], ("edge",)).first()["most_bytes"] <= max(per_root.values())


def test_frequent_paths_against_enumeration(spark, graph):
    g, edges = graph
    labels = {v: v % 2 for v in range(12)}
    got = {(r["pattern"], r["labels"]): r["support"] for r in counting.frequent_patterns(g, 1, 4).collect()}
    for size in (2, 3, 4):
        for bits in range(1 << size):
            own = tuple(bits >> k & 1 for k in range(size))
            if own > own[::-1]:
                continue
            p = Pattern.of([(k, k + 1) for k in range(size - 1)], own)
            want = counting.pattern_support(g, p).first()[0]
            assert got.get((f"path{size}", "-".join(map(str, own))), 0) == want
    assert len(brute_force(edges, Pattern.of([(0, 1)], (0, 1)), "edge", labels)) > 0


def test_census_of_five(spark, graph):
    g, edges = graph
    got = counting.motif_census(g, 5)
    assert got.count() == 21
    some = {r["shape"]: r["cnt"] for r in got.collect()}
    for name in ("clique5", "house5", "cycle5"):
        assert some[name] == len(brute_force(edges, CATALOGUE[name], "vertex"))


def test_maps_and_partitioned_matches(spark, graph, tmp_path):
    g, edges = graph
    run = runner(g, CATALOGUE["clique4"], "edge", "eager", bound_prefix=False)
    run._build(run.start(), 1)
    lists = {(r["u1"], r["x"]): r["keep"] for r in run.tables[0].collect()}
    maps = {(r["u1"], x): kept for r in surface.list_maps(run, 0).collect() for x, kept in r["lists"].items()}
    assert maps == lists
    rows = match(g, CATALOGUE["triangle"])
    surface.write_matches(rows, str(tmp_path / "m"), 4)
    assert {tuple(r) for r in surface.read_matches(spark, str(tmp_path / "m")).collect()} == {tuple(r) for r in rows.collect()}
    some = surface.read_matches(spark, str(tmp_path / "m"), [1, 2], 4)
    assert {tuple(r) for r in some.collect()} == {tuple(r) for r in rows.where("v1 IN (1, 2)").collect()}
    assert "PartitionFilters: [part" in some._jdf.queryExecution().toString()


def test_state_over_streams(spark, graph, tmp_path):
    g, _ = graph
    for k in range(3):
        g.edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(3)) == k).selectExpr("src", "dst", f"timestamp_seconds(1700000000 + {k}) AS ts").coalesce(1).write.mode("append").parquet(str(tmp_path / "s"))
    got = {r["u"]: r["degree"] for r in running_degree_table(spark, str(tmp_path / "s")).collect()}
    assert got == {r["u"]: r["deg"] for r in g.degrees.collect()}
    events = spark.createDataFrame([(1, 0), (1, 1000), (1, 5000), (2, 0)], "user_id long, at long").select("user_id", F.timestamp_seconds("at").alias("ts"))
    assert sorted((r["user_id"], r["n_events"]) for r in session_activity(events).collect()) == [(1, 1), (1, 2), (2, 1)]
    with pytest.raises(ValueError, match="labelled"):
        delta_matches(g.edges, g.edges, Pattern.of([(0, 1)], (0, 1)))


def test_cost_model_is_audited(graph):
    g, _ = graph
    rows = metrics.audit_cost_model(g, CATALOGUE["clique4"]).collect()
    assert rows and all(r["lists"] > 0 and r["false_builds"] + r["missed_builds"] <= r["lists"] for r in rows)
    whole = metrics.comparisons_by_degree(g, CATALOGUE["clique4"]).groupBy("mode").agg(F.sum("comparisons").alias("n"), F.max("running").alias("last")).collect()
    for r in whole:
        assert r["n"] == r["last"] == metrics.comparisons(Run(g, make_plan(CATALOGUE["clique4"]), __import__("motifprune.operators.frontier", fromlist=["Policy"]).Policy(r["mode"])).counts()).first()[0]
    usage = metrics.list_usage(g, [CATALOGUE["near_clique5"]], policy="eager").first()
    assert usage["used"] + usage["unused"] == usage["built"] == usage["considered"] > 0


def test_cost_model_of_crowded_graphs_is_audited_without_a_frontier(spark, graph, monkeypatch):
    from motifprune.sources import graphs

    read = lambda g, name: sorted((r["aux"], r["degree_bucket"], r["lists"], r["false_builds"], r["missed_builds"], *(None if r[c] is None else round(r[c], 9) for c in ("reuse_ratio", "overlap_ratio"))) for r in metrics.audit_cost_model(g, CATALOGUE[name]).collect())
    want = {name: read(graph[0], name) for name in ("clique4", "near_clique5")}
    monkeypatch.setattr(graphs, "CROWDED_IDS", 0)
    monkeypatch.setattr(graphs, "CROWDED_MEAN", 0)
    g = Graph(graph[0].edges)
    assert g.crowded_whole and {name: read(g, name) for name in want} == want
    assert "SortMergeJoin" not in metrics.audit_cost_model(g, CATALOGUE["clique4"])._jdf.queryExecution().executedPlan().toString()
