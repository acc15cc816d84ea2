import random
from datetime import datetime, timedelta

import duckdb
import numpy as np
import pytest

from motifprune import queries
from motifprune.operators import counting, metrics, surface
from motifprune.operators.frontier import make_plan, match
from motifprune.plans.pattern import CATALOGUE
from motifprune.sources import compressed, graphs
from motifprune.sources.graphs import Graph, edges_sql, read_edge_list
from motifprune.streaming.deltas import delta_matches, running_matches, windowed_activity

SF = "/root/testdata/sf0.001"
TABLES = ("lineitem", "orders", "customer", "supplier", "events", "documents", "pages", "embeddings")


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", ["basket", "basket_r", "basket_r25", "coact", "commerce", "lines", "colink", "embed"])
def test_derived_graphs_match_their_sql(spark, duck, name):
    assert {tuple(r) for r in Graph.from_testdata(spark, SF, name).edges.collect()} == set(duck.execute(edges_sql(name)).fetchall())


def test_items_with_many_holders_keep_all_pairs(spark, tmp_path):
    line, other = "a line that very many documents share", "a line of just two documents"
    rows = [(k, f"{line}\nonly here {k:030d}" + (f"\n{other}" if k == 3 else "")) for k in range(150)] + [(500, other), (501, None), (502, "")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    pages = [(k, f'<a href="/home"></a><a href="/p{k}">') for k in range(70)]
    spark.createDataFrame(pages, "page_id long, html string").write.parquet(str(tmp_path / "pages.parquet"))
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    want = {(a, b) for b in range(150) for a in range(b)} | {(3, 500)}
    for name, pairs in (("lines_all", want), ("colink_all", {(a, b) for b in range(70) for a in range(b)})):
        got = [tuple(r) for r in Graph.from_testdata(spark, str(tmp_path), name).edges.collect()]
        assert len(got) == len(pairs) and set(got) == pairs
        assert set(con.execute(edges_sql(name)).fetchall()) == pairs
    assert queries.QUERIES["line_sharing_edges_all"](spark, str(tmp_path)).count() == len(want)


@pytest.mark.parametrize("seed", range(3))
def test_cliques_of_items_are_counted_by_classes(spark, tmp_path, monkeypatch, seed):
    rng, lines = random.Random(seed), [f"a line that some documents share {k}" for k in range(9)]
    held = [(7 * k - 40, [x for j, x in enumerate(lines) if rng.random() < 0.5 / (j + 1)] + ["a line of one document"] * (k == 5)) for k in range(60)]
    spark.createDataFrame([(k, "\n".join([*own, *own[:1], "short"])) for k, own in held] + [(1000, None), (1001, "")], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    plain = Graph.from_testdata(spark, str(tmp_path), "lines_all")
    assert plain.classes is None
    want = {w: match(plain, CATALOGUE[w], "vertex", "none", "count").first()[0] for w in ("triangle", "clique4", "wedge")}
    monkeypatch.setattr(graphs, "CROWDED_GROUPS", 0)
    g = Graph.from_testdata(spark, str(tmp_path), "lines_all")
    assert len(g.classes.weights) < g.classes.shape()[0] == len({v for r in plain.edges.collect() for v in r})
    for w in ("triangle", "clique4"):
        assert match(g, CATALOGUE[w], output="count").first()[0] == want[w]
    assert {r["shape"]: r["cnt"] for r in counting.motif_census(g, 3).collect()} == {"wedge": want["wedge"], "triangle": want["triangle"]}
    assert g.stats == plain.stats
    assert "adj" not in g.__dict__
    monkeypatch.setattr(graphs, "LATER_EDGES", 0)
    assert Graph.from_testdata(spark, str(tmp_path), "lines_all").classes is None


@pytest.mark.parametrize("name", ["graph_stats_basket_r", "clique4_count_lines", "house5_vertex_basket_r", "aux_graph_1_3_4", "gain_exact", "comparisons_by_degree_none", "motif4_census_basket_r25", "labelled_triangle", "support_chain", "topk_roots", "cube_report", "session_counts", "last_click_before_purchase"])
def test_queries_match_their_oracles(spark, duck, name):
    got = queries.QUERIES[name](spark, SF)
    rel = duck.execute(queries.ORACLES[name])
    columns = [c[0] for c in rel.description]
    assert sorted(got.columns) == sorted(columns)
    assert sorted(map(str, (tuple(r) for r in got.select(*columns).collect()))) == sorted(map(str, rel.fetchall()))


@pytest.mark.parametrize("name", ["graph_summary_colink", "graph_stats_colink"])
def test_a_graph_without_edges_matches_its_sql(spark, tmp_path, name):
    spark.createDataFrame([(k, f'<a href="/p{k}">') for k in range(3)], "page_id long, html string").write.parquet(str(tmp_path / "pages.parquet"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet/*.parquet'")
    rel = con.execute(queries.ORACLES[name])
    columns = [c[0] for c in rel.description]
    assert [tuple(r) for r in queries.QUERIES[name](spark, str(tmp_path)).select(*columns).collect()] == rel.fetchall()


@pytest.mark.parametrize("name", ["aux_spec_table", "schedule_table", "plan_table"])
def test_planning_tables_read_lineitem(spark, duck, name):
    got = queries.QUERIES[name](spark, SF)
    assert [f for f in got.inputFiles() if "lineitem" in f] and got.agg({"baskets": "min"}).first()[0] > 0
    rel = duck.execute(queries.ORACLES[name])
    columns = [c[0] for c in rel.description]
    assert got.columns == columns and sorted(tuple(r) for r in got.collect()) == sorted(rel.fetchall())


def test_text_edge_list_and_stored_graph(spark, tmp_path):
    (tmp_path / "g.txt").write_text("# a comment\n1 2\n2\t1\n2 3\n3 3\n\n1 3\n")
    g = Graph(read_edge_list(spark, str(tmp_path / "g.txt")))
    assert {tuple(r) for r in g.edges.collect()} == {(1, 2), (2, 3), (1, 3)}
    g.save(str(tmp_path / "adj"), 2)
    back = Graph.load(spark, str(tmp_path / "adj"))
    assert match(back, CATALOGUE["triangle"]).count() == 1 and back.edges.count() == 3


def test_relabel_core_sample(spark):
    g = Graph.from_testdata(spark, SF, "basket_r25")
    dense, ids = g.relabel("degree")
    assert sorted(r["new_id"] for r in ids.collect()) == list(range(g.degrees.count()))
    assert match(dense, CATALOGUE["triangle"], output="count").first() == match(g, CATALOGUE["triangle"], output="count").first()
    assert g.k_core(2).degrees.agg({"deg": "min"}).first()[0] >= 2
    assert 0 < g.sample_edges(0.5).edges.count() < g.edges.count()


def test_stream_deltas_add_up(spark, tmp_path):
    g = Graph.from_testdata(spark, SF, "basket_r")
    halves = [g.edges.where(f"(src + dst) % 2 = {k}") for k in (0, 1)]
    p = CATALOGUE["triangle"]
    total = match(g, p, output="count").first()[0]
    assert match(Graph(halves[0]), p, output="count").first()[0] + delta_matches(halves[0], halves[1], p).count() == total
    for k, half in enumerate(halves):
        half.selectExpr("src", "dst", f"timestamp_seconds(1700000000 + {k}) AS ts").coalesce(1).write.mode("append").parquet(str(tmp_path / "s"))
    found = running_matches(spark, str(tmp_path / "s"), p)
    assert sum(n for _, n in found) == total
    assert windowed_activity(spark.read.parquet(f"{SF}/events.parquet"), "1 day").count() > 0


def test_sql_surface(spark):
    g = Graph.of(spark, [(1, 2), (2, 3), (1, 3), (3, 4)])
    surface.register(spark, g)
    assert spark.sql("SELECT * FROM match_pattern(TABLE(graph_edges), 'triangle', 'edge')").count() == 1
    assert spark.sql("SELECT pattern_canonical_form('1-2,2-3') = pattern_canonical_form('5-7,5-6') AS same").first()["same"]
    assert '"steps"' in surface.plan_json(make_plan(CATALOGUE["house5"])) and surface.schedule_frame(spark, make_plan(CATALOGUE["house5"])).count() == 1


def test_entry_imports_without_the_other_operators():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def some_copies(spark, path, seed):
    """coact of users of whom many have the same events, and the same graph from its edges; some have events alone, or rows without user, type or time."""
    rng, start = random.Random(seed), datetime(2024, 1, 1)
    held = {u: [(rng.choice("ab"), rng.randrange(1500)) for _ in range(2)] for u in range(6)} | {7: [("alone", 5)]}
    held |= {51 + v: [(str(pair), 0) for pair in CATALOGUE["house5"].edges if v in pair] for v in range(5)}
    rows = [(u + 10 * c, kind, start + timedelta(seconds=at)) for u, own in held.items() for c in range(1 + (u + seed) % 3 if u < 7 else 3) for kind, at in own * (1 + (u == 1))]
    spark.createDataFrame([*rows, (None, "a", start), (99, None, start), (98, "a", None)], "user_id long, event_type string, ts timestamp").write.parquet(str(path / "events.parquet"))
    g = Graph.from_testdata(spark, str(path), "coact")
    return g, Graph(Graph.from_testdata(spark, str(path), "coact").edges)


@pytest.mark.parametrize("seed", range(2))
def test_users_with_the_same_events_are_one_class(spark, tmp_path, seed):
    g, plain = some_copies(spark, tmp_path, seed)
    assert g.crowded_whole and g.stats == plain.stats and sorted(g.degree_classes) == sorted(plain.degree_classes)
    assert len(g.alike.weights) < g.stats.n_vertices and "adj" not in g.__dict__
    assert sorted(g.alike.members.tolist()) == sorted(r["u"] for r in plain.adj.collect())


def test_users_with_events_of_their_own_are_no_classes(spark):
    assert Graph.from_testdata(spark, SF, "coact").alike is None


@pytest.mark.parametrize("w,variant,policy", [("clique4", "edge", "online"), ("clique4", "vertex", "online"), ("wheel6", "edge", "online"), ("house5", "edge", "online"), ("near_clique5", "edge", "online"), ("near_clique5", "edge", "random"), ("house5", "vertex", "online")])
def test_counts_by_class_make_no_pair_of_copies(spark, tmp_path, w, variant, policy):
    g, plain = some_copies(spark, tmp_path, 1)
    assert match(g, CATALOGUE[w], variant, policy, "count").first()[0] == match(plain, CATALOGUE[w], variant, "none", "count").first()[0] > 0
    assert "adj" not in g.__dict__


def test_cost_model_is_audited_by_class(spark, tmp_path):
    g, plain = some_copies(spark, tmp_path, 1)
    got, want = ({(r["aux"], r["degree_bucket"]): (r["lists"], r["false_builds"], r["missed_builds"], r["reuse_ratio"], r["overlap_ratio"]) for r in metrics.audit_cost_model(x, CATALOGUE["clique4"]).collect()} for x in (g, plain))
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)
    assert "adj" not in g.__dict__


def test_gain_is_guessed_by_class(spark, tmp_path):
    g, plain = some_copies(spark, tmp_path, 1)
    assert sorted(map(tuple, queries._guess(g).collect())) == sorted(map(tuple, queries._guess(plain).collect()))
    assert "adj" not in g.__dict__


def test_classes_are_counted_in_blocks(spark, tmp_path, monkeypatch):
    known = some_copies(spark, tmp_path, 1)[0].alike

    def totals():
        c = compressed.TwinCounter(known)
        lists = [sorted(zip(*(np.concatenate(x).tolist() for x in zip(*c.later_lists(v))))) for v in range(len(known.weights)) if known.degrees[v]]
        return [sum(count(v) for v in range(len(known.weights))) for count in (c.induced_houses5, c.near_cliques5, c.houses5, c.wheels6)], lists

    want = totals()
    for name, value in (("BLOCK_IDS", 7), ("SQUARE", 0), ("ROWS_AT_ONCE", 2), ("CELLS_AT_ONCE", 3), ("FOURTH_POWER", 0)):
        monkeypatch.setattr(compressed, name, value)
    assert totals() == want and want[0][0] > 0
