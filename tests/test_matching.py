import random

import pytest
from pyspark.sql import functions as F

from motifprune.operators import counting, kernel, metrics
from motifprune.operators.frontier import Policy, Run, make_plan, match, match_batches, match_without_prefix_sets, runner
from motifprune.operators.joins import brute_force, match_joins
from motifprune.plans.pattern import CATALOGUE, Pattern
from motifprune.plans.schedule import choose_schedule, connected_orders
from motifprune.sources.graphs import Graph

SIX = [(1, 2), (1, 3), (1, 4), (2, 3), (2, 4), (3, 4), (2, 5), (3, 6), (4, 5)]


def some_graph(n=9, share=0.6, seed=1):
    random.seed(seed)
    return [(a, b) for b in range(n) for a in range(b) if random.random() < share]


@pytest.fixture(scope="module")
def small(spark):
    pairs = some_graph()
    return Graph.of(spark, pairs).cached(), set(pairs)


@pytest.mark.parametrize("name", ["triangle", "path4", "cycle4", "diamond", "clique4", "house5", "bowtie", "near_clique5", "wheel6", "prism6"])
@pytest.mark.parametrize("variant", ["edge", "vertex"])
def test_engines_and_policies_agree_with_brute_force(small, name, variant):
    g, edges = small
    p = CATALOGUE[name]
    want = len(brute_force(edges, p, variant))
    assert match(g, p, variant, "online", "count").first()[0] == want
    assert match(g, p, variant, "eager", "count").first()[0] == want
    for policy in ("none", "eager", "online"):
        assert kernel.match_kernel(g, make_plan(p, variant), policy, nested=policy == "eager", split_threshold=2).agg(F.sum("cnt")).first()[0] == want


@pytest.mark.parametrize("variant", ["edge", "vertex"])
def test_baselines_options_and_rows(small, spark, tmp_path, variant):
    g, edges = small
    p = CATALOGUE["house5"]
    want = brute_force(edges, p, variant)
    assert {tuple(r) for r in match_joins(g, p, variant, "rows").collect()} == {tuple(r) for r in match(g, p, variant).collect()}
    assert match(g, p, variant).distinct().count() == len(want)
    assert match_without_prefix_sets(g, p, variant).first()[0] == len(want)
    assert kernel.match_kernel(g, make_plan(p, variant), "none", engine="interpreted").agg(F.sum("cnt")).first()[0] == len(want)
    for options in ({"bound_prefix": False}, {"share": False, "merge": False}, {"reuse_aux": False}):
        assert match(g, p, variant, "eager", "count", **options).first()[0] == len(want)
    for policy in (Policy("degree", degree_at=4), Policy("random"), Policy("oracle"), Policy("eager", lazy_degree=4), Policy("online", order_discount=False)):
        assert match(g, p, variant, policy, "count").first()[0] == len(want)
    assert match_batches(g, p, str(tmp_path / "rows"), 3, variant).count() == len(want)
    for order in list(connected_orders(p))[::17][:3]:
        assert match(g, p, variant, "none", "count", schedule=choose_schedule(p, strategy="given", order=order)).first()[0] == len(want)
    assert match(g, p, variant, limit=2).count() == min(2, len(want))


def test_closed_forms(spark):
    k6 = Graph.of(spark, [(a, b) for b in range(6) for a in range(b)])
    assert match(k6, CATALOGUE["cycle4"], "edge", output="count").first()[0] == 45
    assert match(k6, CATALOGUE["cycle4"], "vertex", output="count").first()[0] == 0
    assert counting.count_cliques(k6, 5).first()[0] == 6
    ring = Graph.of(spark, [(k, (k + 1) % 5) for k in range(5)])
    assert match(ring, CATALOGUE["cycle5"], "vertex", output="count").first()[0] == 1
    outer, inner, spokes = [(k, (k + 1) % 5) for k in range(5)], [(5 + k, 5 + (k + 2) % 5) for k in range(5)], [(k, 5 + k) for k in range(5)]
    petersen = Graph.of(spark, outer + inner + spokes)
    assert [match(petersen, CATALOGUE[x], output="count").first()[0] for x in ("triangle", "cycle4", "cycle5")] == [0, 0, 12]
    hub = Graph.of(spark, [(0, k) for k in range(1, 201)] + [(2 * k + 1, 2 * k + 2) for k in range(10)])
    assert match(hub, CATALOGUE["triangle"], policy=Policy("eager", lazy_degree=8), output="count").first()[0] == 10
    empty = Graph(k6.edges.limit(0))
    assert match(empty, CATALOGUE["house5"], output="count").first()[0] == 0 and match(empty, CATALOGUE["triangle"]).count() == 0
    loops = Graph.of(spark, [(1, 1), (1, 2), (2, 1), (2, 3)])
    assert loops.edges.count() == 2 and match(loops, CATALOGUE["edge"], output="count").first()[0] == 2


def test_worked_case_of_pruned_lists(spark):
    g = Graph.of(spark, SIX)
    run = runner(g, CATALOGUE["clique4"], "edge", "eager", bound_prefix=False)
    run._build(run.start().where("u1 = 1"), 1)
    assert {r["x"]: r["keep"] for r in run.tables[0].collect()} == {2: [3, 4], 3: [2, 4], 4: [2, 3]}
    assert match(g, CATALOGUE["clique4"]).count() == 1


@pytest.mark.parametrize("name,variant", [("clique4", "edge"), ("near_clique5", "vertex"), ("wheel6", "edge")])
def test_both_engines_count_the_same_work(small, name, variant):
    g, _ = small
    plan = make_plan(CATALOGUE[name], variant)
    for policy in ("none", "eager", "online"):
        a = metrics.comparisons(Run(g, plan, Policy(policy)).counts()).first()[0]
        assert metrics.task_balance(g, plan, policy).first()["comparisons"] == a


@pytest.mark.parametrize("name", ["star4", "cycle4", "diamond", "house5", "near_clique5"])
def test_tail_factors(small, name):
    g, edges = small
    assert counting.count_matches(g, CATALOGUE[name], tail="factor").first()[0] == len(brute_force(edges, CATALOGUE[name]))


def test_labels_support_and_census(spark):
    pairs, labels = some_graph(8, 0.5, 4), {v: v % 3 for v in range(8)}
    g = Graph.of(spark, pairs, labels)
    p = Pattern.of([(0, 1), (1, 2)], (0, 1, 2))
    found = brute_force(set(pairs), p, "edge", labels)
    assert match(g, p, output="count").first()[0] == len(found)
    assert counting.pattern_support(g, p).first()[0] == (min(len({m[k] for m in found}) for k in range(3)) if found else 0)
    census = {r["shape"]: r["cnt"] for r in counting.motif_census(g, 3).collect()}
    assert census == {"wedge": len(brute_force(set(pairs), CATALOGUE["wedge"], "vertex")), "triangle": len(brute_force(set(pairs), CATALOGUE["triangle"], "vertex"))}
    assert counting.frequent_patterns(g, 1, 2).count() > 0


def test_broadcast_bound(small):
    with pytest.raises(ValueError, match="bound"):
        kernel.compressed_rows(small[0], 3)


@pytest.mark.parametrize("n,share,ids", [(150, 0.5, 1), (70, 1.0, -(1 << 40)), (12, 0.2, 5)])
def test_cliques_of_crowded_graphs_ship_no_frontier(spark, monkeypatch, n, share, ids):
    from motifprune.sources import compressed, graphs

    pairs = [(ids * a, ids * b) for a, b in some_graph(n, share, n)] + [(ids * a, ids * (n + a)) for a in range(n)]
    want = {k: match(Graph.of(spark, pairs), CATALOGUE[w], "vertex", "none", "count").first()[0] for k, w in ((3, "triangle"), (4, "clique4"), (2, "wedge"))}
    stats = Graph.of(spark, pairs).stats
    monkeypatch.setattr(graphs, "CROWDED_IDS", 0)
    monkeypatch.setattr(graphs, "CROWDED_MEAN", 0)
    monkeypatch.setattr(compressed, "BLOCK_WORDS", 64)
    monkeypatch.setattr(compressed, "BLOCK_IDS", 300)
    g = Graph.of(spark, pairs)
    assert g.crowded and g.stats == stats
    lists = g.later.value
    assert sorted((int(lists.ids[k]), int(lists.ids[w])) if lists.ids[k] < lists.ids[w] else (int(lists.ids[w]), int(lists.ids[k])) for k in range(len(lists.ids)) for w in lists.flat[lists.begin[k] : lists.end[k]]) == sorted(tuple(r) for r in g.edges.collect())
    for k, w in ((3, "triangle"), (4, "clique4")):
        for variant in ("edge", "vertex"):
            out = match(g, CATALOGUE[w], variant, output="count")
            assert out.first()[0] == want[k]
            assert "SortMergeJoin" not in out._jdf.queryExecution().executedPlan().toString() and "explode" not in out._jdf.queryExecution().toString()
    got = {r["shape"]: r["cnt"] for r in counting.motif_census(g, 3).collect()}
    assert got == {"wedge": want[2], "triangle": want[3]}


@pytest.mark.parametrize("n,share,ids", [(10, 0.6, -(1 << 40)), (8, 1.0, 3), (9, 0.5, 1)])
def test_houses_wheels_and_near_cliques_of_crowded_graphs_ship_no_frontier(spark, monkeypatch, n, share, ids):
    from motifprune.sources import compressed, graphs

    pairs = [(ids * a, ids * b) for a, b in some_graph(n, share, n)]
    monkeypatch.setattr(graphs, "CROWDED_IDS", 0)
    monkeypatch.setattr(graphs, "CROWDED_MEAN", 0)
    monkeypatch.setattr(compressed, "BLOCK_WORDS", 4)
    monkeypatch.setattr(compressed, "BLOCK_IDS", 7)
    g = Graph.of(spark, pairs)
    for w in ("near_clique5", "house5", "wheel6"):
        out = match(g, CATALOGUE[w], output="count")
        assert out.first()[0] == len(brute_force({tuple(sorted(p)) for p in pairs}, CATALOGUE[w], "edge"))
        assert "explode" not in out._jdf.queryExecution().toString()


def with_twins(pairs, copies):
    """Each vertex copies times, linked with its copies and with those of its neighbours."""
    at = {v for p in pairs for v in p}
    many = {v: [100 * v + k for k in range(1 + v % copies)] for v in at}
    return {(a, b) for p in pairs for a in many[p[0]] for b in many[p[1]]} | {(a, b) for v in at for a in many[v] for b in many[v] if a < b}


@pytest.mark.parametrize("pairs,copies,ids", [(some_graph(11, 0.5, 3), 1, -(1 << 40)), ([(0, 1), (1, 2), (2, 3), (3, 0), (0, 4), (1, 4)], 3, 3), (some_graph(6, 1.0), 2, 1)])
def test_induced_houses_and_near_cliques_by_chance_ship_no_frontier(spark, monkeypatch, pairs, copies, ids):
    from motifprune.sources import compressed, graphs

    n = len({v for p in pairs for v in p})
    pairs = {tuple(sorted((ids * a, ids * b))) for a, b in with_twins(pairs, copies)}
    g = Graph.of(spark, sorted(pairs))
    cases = (("house5", "vertex", "online"), ("near_clique5", "edge", "random"))
    monkeypatch.setattr(graphs, "CROWDED_IDS", 0)
    monkeypatch.setattr(graphs, "CROWDED_MEAN", 0)
    for name, value in (("BLOCK_IDS", 7), ("SUMMED_IDS", 5), ("ROWS_AT_ONCE", 2), ("CELLS_AT_ONCE", 3)):
        monkeypatch.setattr(compressed, name, value)
    for w, variant, policy in cases:
        out = match(g, CATALOGUE[w], variant, policy, "count")
        assert out.first()[0] == len(brute_force(pairs, CATALOGUE[w], variant))
        assert "explode" not in out._jdf.queryExecution().toString()
    assert len(g.twins.value.weights) <= n and int(g.twins.value.weights.sum()) == len({v for p in pairs for v in p})


def test_counts_of_large_graphs_under_a_policy_come_from_the_kernel(small, monkeypatch):
    from motifprune.operators import frontier

    g, edges = small
    monkeypatch.setattr(frontier, "SHIPPED_IDS", 0)
    for variant in ("edge", "vertex"):
        want = len(brute_force(edges, CATALOGUE["house5"], variant))
        for policy in ("none", "eager", "degree", "random", "oracle"):
            out = match(g, CATALOGUE["house5"], variant, policy, "count")
            assert out.first()[0] == want
            assert ("MapInArrow" in out._jdf.queryExecution().executedPlan().toString()) == (policy in ("none", "eager", "degree"))


@pytest.mark.parametrize("name", ["triangle", "cycle4", "clique4", "house5", "near_clique5", "wheel6"])
@pytest.mark.parametrize("variant", ["edge", "vertex"])
def test_kernel_decides_by_true_reads_and_by_chance(small, monkeypatch, name, variant):
    from motifprune.operators import frontier

    g, edges = small
    p, plan = CATALOGUE[name], make_plan(CATALOGUE[name], variant)
    want = len(brute_force(edges, p, variant))
    for policy in ("random", "oracle"):
        got = kernel.match_kernel(g, plan, policy, nested=policy == "random", split_threshold=3).agg(F.sum("cnt"), F.sum("lists_built"), F.sum("lists_considered")).first()
        assert got[0] == want and got[1] <= got[2]
        if policy == "oracle" and len(plan.aux) == 1:  # made are those that pay, by the frontier's rule
            run = runner(g, p, variant, "oracle")
            run.frame(plan.n - 1)
            assert got[1] == run.tables[0].count()
            run.release()
    for out in (match(g, p, variant, "oracle", "count"), match_without_prefix_sets(g, p, variant)):
        assert "MapInArrow" not in out._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(frontier, "DECIDED_IDS", 0)
    monkeypatch.setattr(frontier, "SHIPPED_IDS", 0)
    monkeypatch.setattr(kernel, "JOINED_LISTS", 2)
    monkeypatch.setattr(kernel, "READS_HELD", 3)
    for out in (match(g, p, variant, "oracle", "count"), match(g, p, variant, "random", "count"), match_without_prefix_sets(g, p, variant)):
        assert out.first()[0] == want
        assert "MapInArrow" in out._jdf.queryExecution().executedPlan().toString()


def test_kernel_chooses_the_lists_that_frames_choose(spark):
    import numpy as np

    x = np.array([0, 1, -5, 1 << 40, 12345], dtype=np.int64)
    want = [r[0] for r in spark.createDataFrame([(int(v),) for v in x], "x long").select(F.xxhash64("x", F.lit(7).cast("long"), F.lit(-(1 << 35)).cast("long"))).collect()]
    assert kernel.spark_hash(x, 7, -(1 << 35)).view(np.int64).tolist() == want


def test_wheels_around_long_lists():
    """A hub whose neighbours are linked all the way round: counts beyond one block of rows against those of cycles."""
    import numpy as np

    from motifprune.sources.compressed import Lists, WholeCounter

    n = 600  # 0 is the hub; the rim joins vertices whose numbers differ by 1 or 2
    rim = [[1 + (k + d) % n for d in (-2, -1, 1, 2)] for k in range(n)]
    lists = [list(range(1, n + 1))] + [sorted([0, *x]) for x in rim]
    size = np.array([len(x) for x in lists])
    counter = WholeCounter(Lists(np.arange(n + 1), np.cumsum(size) - size, np.cumsum(size), np.array(sum(lists, []), dtype=np.int32)))
    small = {(min(a, b), max(a, b)) for a in range(12) for b in ((a + 1) % 12, (a + 2) % 12)}
    assert counter.wheels6(0) * 12 == len(brute_force(small, CATALOGUE["cycle5"], "edge")) * n


def test_compressed_lists_come_from_tasks_and_keep_ids(spark, monkeypatch):
    far = 1 << 40
    pairs = [(far + a, b - far) if (a + b) % 2 else (b - far, far + a) for a in range(6) for b in range(7) if (a * b) % 4 != 1]
    g = Graph.of(spark, pairs + [(1, 2), (2, 3), (1, 3), (3, far)])
    monkeypatch.setattr("pyspark.sql.DataFrame.toPandas", None)  # the driver gets packed lists, not a row for each arc
    lists = kernel.compressed_rows(g)
    got = {(int(u), int(lists.ids[w])) for u, a, b in zip(lists.ids, lists.begin, lists.end) for w in lists.flat[a:b]}
    assert lists.flat.dtype == __import__("numpy").int32 and got == {tuple(r) for r in g.arcs.collect()}
    for name in ("wedge", "triangle", "cycle4"):
        rows = kernel.match_kernel(g, make_plan(CATALOGUE[name]), "none", output="rows")
        assert {tuple(r) for r in rows.collect()} == {tuple(r) for r in match(g, CATALOGUE[name]).collect()}
    assert {r["root"] for r in kernel.match_kernel(g, make_plan(CATALOGUE["wedge"]), "online").collect()} == {r["u"] for r in g.degrees.collect()}


def test_plans_have_no_cartesian_product(small):
    plan = match(small[0], CATALOGUE["house5"], "edge", "eager", "count")._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_gain_is_filtered_before_lists_are_joined(small):
    g, _ = small
    run = runner(g, CATALOGUE["clique4"], "edge", "online", bound_prefix=False)
    spec = run.plan.aux[0]
    lists = run._lists(run.considered(run.start(), spec).where("gain > 0"), spec)
    text = lists._jdf.queryExecution().optimizedPlan().toString().splitlines()
    depth = lambda line: len(line) - len(line.lstrip(" :+-"))
    gain = next(k for k, line in enumerate(text) if ("Join Inner" in line or "Filter" in line) and "reuse#" in line and "> " in line)
    joined = next(k for k, line in enumerate(text) if "Join LeftOuter" in line)
    assert joined < gain and depth(text[joined]) < depth(text[gain])  # lists join what the filter lets through
    assert run.build_aux(run.start(), 0, spec).count() == run.considered(run.start(), spec).where("gain > 0").count()


def test_gains_ship_no_sets(small):
    from motifprune import queries

    plan = queries._guess(small[0])._jdf.queryExecution().optimizedPlan().toString().splitlines()
    at = next(k for k, line in enumerate(plan) if "Generate explode" in line)
    assert any("Join" in line for line in plan[:at]) and not any("keep_set#" in line for line in plan[:at])


@pytest.mark.parametrize("variant", ["edge", "vertex"])
def test_every_engine_heeds_labels(spark, variant):
    pairs = some_graph(9, 0.6, 6)
    labels = {v: v % 3 for v in range(8)}  # one vertex has none
    g = Graph.of(spark, pairs, labels)
    for p in (Pattern.of([(0, 1), (1, 2)], (0, 1, 2)), Pattern.of([(0, 1), (1, 2), (0, 2), (2, 3)], (0, 1, 2, 1))):
        want = len(brute_force(set(pairs), p, variant, labels))
        assert want or variant == "vertex" and p.n == 4
        assert match(g, p, variant, output="count").first()[0] == want
        assert match_without_prefix_sets(g, p, variant).first()[0] == want
        for options in ({"policy": "none"}, {"policy": "online"}, {"policy": "none", "engine": "interpreted"}, {"policy": "eager", "most_arcs": 1}):
            assert kernel.match_kernel(g, make_plan(p, variant), **options).agg(F.sum("cnt")).first()[0] == want
    with pytest.raises(ValueError, match="labelled"):
        kernel.match_kernel(Graph(g.edges), make_plan(p), "none")


def test_roots_are_shipped_labelled_lists_only(spark):
    """A hub whose label the pattern lacks is linked with all roots: neither its list nor its place in lists is shipped."""
    pairs = [(k, 100 + k % 3) for k in range(9)] + [(k, 200 + k % 2) for k in range(9)] + [(100 + a, 200 + b) for a in range(3) for b in range(2)] + [(k, 999) for k in (*range(9), 100, 200)]
    labels = {v: 4 if v == 999 else 1 + v // 100 for pair in pairs for v in pair}
    g, sale = Graph.of(spark, pairs, labels), Pattern.of([(0, 1), (1, 2), (0, 2)], (1, 2, 3))
    plan = make_plan(sale)
    shipped = kernel.ego_lists(g, plan).collect()
    assert {r["root"] for r in shipped} == set(range(9)) and {r["u"] for r in shipped} == {*range(9), 100, 101, 102}
    assert all(r["nbrs"] == [200, 201] and r["labels"] == [3, 3] for r in shipped if r["u"] >= 100) and not any(999 in r["nbrs"] for r in shipped)
    for p in (sale, Pattern.of([(0, 1), (1, 2), (0, 2), (2, 3)], (1, 2, 3, 1)), Pattern.of([(0, 3), (3, 1), (1, 2)], (1, 3, 4, 2))):
        for variant in ("edge", "vertex"):
            for policy in ("online", "eager", "none"):
                assert kernel.match_kernel(g, make_plan(p, variant), policy, most_arcs=0).agg(F.sum("cnt")).first()[0] == len(brute_force(set(pairs), p, variant, labels))


@pytest.mark.parametrize("name,variant", [("clique4", "edge"), ("house5", "vertex"), ("cycle5", "edge"), ("prism6", "vertex")])
def test_graphs_beyond_the_broadcast_bound(small, name, variant):
    g, edges = small
    plan = make_plan(CATALOGUE[name], variant)
    want = brute_force(edges, CATALOGUE[name], variant)
    near, whole = (kernel.match_kernel(g, plan, "online", nested=True, split_threshold=3, most_arcs=most) for most in (1, 1 << 30))
    measures = [F.sum(m).alias(m) for m in kernel.MEASURES]
    assert near.agg(*measures).first() == whole.agg(*measures).first() and near.agg(F.sum("cnt")).first()[0] == len(want)
    assert "Broadcast" not in near._jdf.queryExecution().optimizedPlan().toString()
    rows = kernel.match_kernel(g, plan, "none", output="rows", most_arcs=1)
    assert {tuple(r) for r in rows.collect()} == {tuple(r) for r in match(g, CATALOGUE[name], variant).collect()}


def test_rows_of_one_root_come_in_bounded_batches(spark, monkeypatch):
    monkeypatch.setattr(kernel, "ROWS_A_BATCH", 50)
    kernel.compile_plan.cache_clear()
    star = Graph.of(spark, [(0, k) for k in range(1, 41)])
    worker = kernel._Worker(make_plan(CATALOGUE["wedge"]), Policy("none"), None, True, "generated")
    out, lists = [], {0: __import__("numpy").arange(1, 41), **{k: __import__("numpy").array([0]) for k in range(1, 41)}}
    sizes = [len(b) for v in range(41) for b in worker.one(lists.__getitem__, None, v, 0, 1, out)]
    assert sum(sizes) == 780 and max(sizes) < 50 + 41
    assert kernel.match_kernel(star, make_plan(CATALOGUE["wedge"]), "none", output="rows").count() == 780
    kernel.compile_plan.cache_clear()


def test_list_measures(small):
    g, _ = small
    plan = make_plan(CATALOGUE["near_clique5"], "vertex")
    r = kernel.match_kernel(g, plan, "eager").agg(*(F.sum(m).alias(m) for m in kernel.MEASURES), F.max("aux_bytes").alias("most")).first()
    assert 0 < r["lists_used"] <= r["lists_built"] <= r["lists_considered"] and r["most"] > 0
    assert kernel.match_kernel(g, plan, "none").agg(F.sum("aux_bytes"), F.sum("lists_used")).first() == (0, 0)


def test_persisted_frames_are_freed(spark, tmp_path):
    g = Graph.of(spark, some_graph(8, 0.7, 77)).cached()  # of its own: equal plans share what is persisted
    store = g.spark.sparkContext._jsc.sc().getPersistentRDDs
    g.adj.count(), g.stats, g.degree_classes
    __import__("gc").collect()  # results of tests before
    before = store().size()
    match_batches(g, CATALOGUE["near_clique5"], str(tmp_path / "m"), 3, "vertex", "eager")
    assert store().size() <= before
    out = match(g, CATALOGUE["near_clique5"], "vertex", "eager", "count")
    out.collect()
    assert store().size() > before
    del out
    __import__("gc").collect()
    assert store().size() <= before


def test_hubs_lists_are_made_when_read(small):
    g, edges = small
    p = CATALOGUE["near_clique5"]
    run = runner(g, p, "vertex", Policy("eager", lazy_degree=1))
    got = run.count()
    assert got.first()[0] == len(brute_force(edges, p, "vertex"))
    for j, spec in enumerate(run.plan.aux):
        keys = run._keys(spec)
        reads = {tuple(r) for r in run.true_reuse(spec).select(*keys, "x").collect()}
        made = [tuple(r) for r in run.tables[j].select(*keys, "x").collect()]
        assert set(made) <= reads and len(made) == len(set(made))  # none that no loop reads, none twice


def test_lists_that_cannot_pay_are_left_out(spark):
    ring = Graph.of(spark, [(k, (k + 1) % 50) for k in range(50)] + [(k, (k + 2) % 50) for k in range(50)])
    run = runner(ring, CATALOGUE["clique4"])
    run.last()
    assert not run.worthwhile and not run.held and not run.tables  # nothing is persisted, joined or built
    dense = Graph.of(spark, [(a, b) for b in range(60) for a in range(b) if (a * 7 + b * 3) % 5])
    free = runner(dense, CATALOGUE["near_clique5"], "edge", Policy("online", join_cost=0.0))
    assert free.worthwhile


def test_supersets_prune_alike(spark):
    """With C within D: C & (D & N) = C & N, and C - (D & N) = C - N."""
    from motifprune.functions import sets

    random.seed(8)
    rows = []
    for _ in range(200):
        d = sorted(random.sample(range(40), random.randrange(25)))
        rows.append((sorted(random.sample(d, random.randrange(len(d) + 1))), d, sorted(random.sample(range(40), random.randrange(25)))))
    df = spark.createDataFrame(rows, "c array<long>, d array<long>, n array<long>")
    c, d, n = (F.col(x) for x in "cdn")
    kept = sets.set_intersect(d, n)
    bad = df.where((sets.set_intersect(c, kept) != sets.set_intersect(c, n)) | (sets.set_subtract(c, kept) != sets.set_subtract(c, n)))
    assert bad.count() == 0
    plan = make_plan(CATALOGUE["wheel6"], "vertex")
    for spec in plan.aux:  # the set that a list is cut to holds each set that it is read for
        for k, i in spec.consumers:
            later = plan.key(k - 1, i)
            assert set(spec.keep[0]) <= set(later[0]) and set(spec.keep[1]) <= set(later[1]) and set(spec.keep[2]) <= set(later[2])
