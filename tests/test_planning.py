import itertools
import random

import pytest

from motifprune.plans.costmodel import CostModel, GraphStats, gain_value
from motifprune.plans.execution import SUBTRACT, ExecutionPlan, Options, explain
from motifprune.plans.pattern import CATALOGUE, WORKLOAD, Pattern, automorphisms, connected_shapes
from motifprune.plans.schedule import canonical_checks, choose_schedule, connected_orders, greedy_order

KNOWN = {"clique4": (24, 1, 1), "house5": (2, 1, 2), "near_clique5": (12, 2, 4), "clique5": (120, 4, 4), "wheel6": (10, 6, 10), "prism6": (12, 2, 3), "octahedron6": (48, 6, 7), "near_clique7": (240, 16, 20)}


@pytest.mark.parametrize("name", WORKLOAD)
def test_symmetries_and_numbers_of_pruned_lists(name):
    p = CATALOGUE[name]
    specs = [ExecutionPlan(choose_schedule(p), Options(v, bound_prefix=False)).unbounded_specs() for v in ("edge", "vertex")]
    assert (len(automorphisms(p)), *specs) == KNOWN[name]


@pytest.mark.parametrize("text", ["1-1", "1-2,3-4", "", ",".join(f"{k}-{k + 1}" for k in range(9))])
def test_invalid_patterns(text):
    with pytest.raises(ValueError):
        Pattern.parse(text)


@pytest.mark.parametrize("name", ["triangle", "house5", "diamond", "cycle5", "bowtie", "star4", "wheel6"])
def test_checks_keep_one_arrangement_of_each(name):
    p = CATALOGUE[name]
    for order in list(connected_orders(p))[:20]:
        checks = canonical_checks(p, order)
        for ids in itertools.islice(itertools.permutations(range(p.n)), 24):
            kept = sum(all(ids[s[order[a - 1]]] < ids[s[order[b - 1]]] for a, b in checks) for s in automorphisms(p))
            assert kept == 1


def test_orders_and_strategies():
    p, stats = CATALOGUE["house5"], GraphStats(1000, 5000, 900, 40)
    assert greedy_order(p) in set(connected_orders(p))
    assert choose_schedule(p, stats, "cost").order in set(connected_orders(p))
    with pytest.raises(ValueError):
        choose_schedule(p, strategy="given", order=(2, 4, 0, 1, 3))


def test_deferred_subtraction_and_merging():
    plan = ExecutionPlan(choose_schedule(CATALOGUE["path4"]), Options("vertex"))
    assert any(x.deferred for x in plan.steps)
    assert any(x.kind == SUBTRACT for x in plan.steps)
    merged = ExecutionPlan(choose_schedule(CATALOGUE["clique5"]), Options("edge"))
    assert [len(x.consumers) for x in merged.aux] == [3, 1] and merged.aux[1].parent == 0
    assert "loop 1" in explain(merged)


def test_census_shapes():
    assert [len(connected_shapes(k)) for k in (3, 4, 5)] == [2, 6, 21]
    a, b = Pattern.parse("1-2,2-3,3-1,3-4"), Pattern.parse("9-8,8-7,9-7,9-5")
    assert a.canonical_form() == b.canonical_form() == CATALOGUE["tailed_triangle"].canonical_form()


def test_cost_model_bounds_and_identity():
    s = GraphStats(100, 400, 2000, 30)
    assert s.p2 == 1.0 and GraphStats(100, 400, 2000, 30, "distinct").p2 == pytest.approx(2000 * 100 / 800**2)
    plan = ExecutionPlan(choose_schedule(CATALOGUE["clique4"]), Options("edge", bound_prefix=False))
    assert CostModel.literal(s).shrink(plan, 1, 3, 2) == s.p2
    random.seed(3)
    for _ in range(50):  # the gain is what plain reading costs less what pruned reading costs
        n, deg, keep, filt, prefix = (random.randrange(1, 40) for _ in range(5))
        plain, pruned = n * (prefix + deg), filt + deg + n * (prefix + keep)
        assert gain_value(n, deg, keep, filt) == plain - pruned
