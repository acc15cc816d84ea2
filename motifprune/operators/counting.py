"""Counting without the last loops, clique and motif counts, labelled matching and pattern support."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import factorial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifprune.functions import sets
from motifprune.operators.frontier import Run, match
from motifprune.plans.execution import ExecutionPlan, Options
from motifprune.plans.pattern import CATALOGUE, Pattern, automorphisms, connected_shapes
from motifprune.plans.schedule import Schedule, connected_orders
from motifprune.sources.graphs import Graph


def partitions_of(items: list[int]) -> Iterator[list[list[int]]]:
    """All ways to cut a list into blocks."""
    if not items:
        yield []
        return
    first, rest = items[0], items[1:]
    for smaller in partitions_of(rest):
        yield [[first], *smaller]
        for k in range(len(smaller)):
            yield [*smaller[:k], [first, *smaller[k]], *smaller[k + 1 :]]


def tail_order(p: Pattern) -> tuple[tuple[int, ...], int]:
    """A connected order whose last vertices are pairwise non-adjacent, and the most of them (at least one)."""

    def tail(order: tuple[int, ...]) -> int:
        r = 1
        while r < p.n - 1 and not any(p.adjacent(order[-r - 1], v) for v in order[-r:]):
            r += 1
        return r

    best = max(connected_orders(p), key=lambda o: (tail(o), sum((p.n - k) * len(p.neighbours(v)) for k, v in enumerate(o))))
    return best, tail(best)


def count_tail_factor(graph: Graph, p: Pattern) -> DataFrame:
    """One row cnt (edge-induced): the last r vertices, pairwise non-adjacent, are counted and not enumerated.

    Heads are matched without id checks. The number of ways to choose different vertices from the r candidate sets is
    a signed sum over the ways to merge them, and the total is divided by the number of automorphisms.
    """
    if p.labels is not None:
        raise ValueError("labelled patterns are counted by match")
    order, r = tail_order(p)
    n, head = p.n, p.n - r
    plan = ExecutionPlan(Schedule(p, order, ()), Options("edge", bound_prefix=False))
    run = Run(graph, plan)
    df = run.frame(head)
    left = {i: sets.set_exclude(F.col(run.column(plan.key(head, i))), *(F.col(f"u{j}") for j in range(1, head + 1) if not plan.schedule.linked(j, i))) for i in range(head + 1, n + 1)}

    def size(block: list[int]) -> Column:
        return F.size(reduce(sets.set_intersect, [left[i] for i in block])).cast("long")

    total: Column = F.lit(0).cast("long")
    for blocks in partitions_of(list(left)):
        sign = reduce(lambda a, b: a * b, [(-1) ** (len(b) - 1) * factorial(len(b) - 1) for b in blocks])
        total = total + reduce(lambda a, b: a * b, [size(b) for b in blocks]) * sign
    return df.agg(F.coalesce(F.sum(total), F.lit(0)).alias("all")).select(F.expr(f"`all` div {len(automorphisms(p))}").cast("long").alias("cnt"))


def count_matches(graph: Graph, p: Pattern, variant: str = "edge", tail: str = "none", **options) -> DataFrame:
    """tail="factor" counts the last non-adjacent vertices from set sizes (edge-induced only)."""
    if tail == "factor":
        if variant != "edge":
            raise ValueError("counting by factors is edge-induced")
        return count_tail_factor(graph, p)
    return match(graph, p, variant, output="count", **options)


def count_cliques(graph: Graph, k: int, policy: str = "online") -> DataFrame:
    return match(graph, Pattern.of([(a, b) for b in range(k) for a in range(b)]), "edge", policy, "count")


def motif_census(graph: Graph, k: int, policy: str = "none") -> DataFrame:
    """(shape, n_edges, cnt) of every connected shape of k vertices, vertex-induced.

    For shapes of 3 in a crowded graph, wedges are the pairs of neighbours less three for each triangle.
    """
    known = {p.canonical_form(): name for name, p in CATALOGUE.items() if p.n == k}
    parts = []
    by_degree = k == 3 and graph.counts_cliques
    for at, p in enumerate(connected_shapes(k)):
        name = known.get(p.canonical_form(), f"shape{k}_{at}")
        if by_degree:
            found = graph.clique_count(3)
            if len(p.edges) == 2:
                found = graph.wedges().join(F.broadcast(found)).select((F.col("pairs") - 3 * F.col("cnt")).alias("cnt"))  # one row each
            parts.append(found.select(F.lit(name).alias("shape"), F.lit(len(p.edges)).alias("n_edges"), "cnt"))
            continue
        parts.append(match(graph, p, "vertex", policy, "count").select(F.lit(name).alias("shape"), F.lit(len(p.edges)).alias("n_edges"), "cnt"))
    return reduce(DataFrame.unionByName, parts)


def pattern_support(graph: Graph, p: Pattern, policy: str = "none") -> DataFrame:
    """One row support: the least number of different data vertices that some pattern vertex takes, over all arrangements."""
    rows = match(graph, p, "edge", policy)
    orbits = sorted({tuple(sorted({s[v] for s in automorphisms(p)})) for v in range(p.n)})
    taken = rows.select(F.explode(F.array(*(F.struct(F.lit(k).alias("orbit"), F.col(f"v{v + 1}").alias("x")) for k, o in enumerate(orbits) for v in o))).alias("t")).select("t.*")
    sizes = taken.distinct().groupBy("orbit").agg(F.count("*").alias("n"))
    return sizes.agg(F.when(F.count("*") == len(orbits), F.min("n")).otherwise(0).cast("long").alias("support"))


def frequent_patterns(graph: Graph, least: int, k: int = 3) -> DataFrame:
    """(pattern, labels, support) of labelled paths of 2 to k vertices with support of at least `least`.

    One job a length: all paths whose beginnings and ends are frequent are grown by an edge and grouped by their labels.
    A path stands in both directions; only the one whose labels come first is reported. If labels read the same both
    ways, both directions count, so each place's vertices are those of its orbit.
    """
    named = lambda c, own: graph.labels.select(F.col("v").alias(c), F.col("label").alias(own))
    step = graph.arcs.join(named("u", "from"), "u").join(named("w", "to"), "w")
    paths = step.select(F.col("u").alias("x1"), F.col("w").alias("x2"), F.array("from", "to").alias("labels"))
    found = []
    for size in range(2, k + 1):
        places = [f"x{j}" for j in range(1, size + 1)]
        forward = paths.where(F.col("labels") <= F.reverse("labels"))
        support = forward.groupBy("labels").agg(F.least(*(F.countDistinct(c) for c in places)).alias("support")).where(F.col("support") >= least)
        kept = [(tuple(r["labels"]), r["support"]) for r in support.collect()]  # as many as there are frequent paths of labels
        found += [(f"path{size}", "-".join(map(str, labels)), n) for labels, n in sorted(kept)]
        if size == k or not kept:
            break
        both = sorted({x for labels, _ in kept for x in (labels, labels[::-1])})
        frequent = graph.spark.createDataFrame([(list(x),) for x in both], graph.labels.select(F.array("label").alias("labels")).schema)
        paths = paths.join(F.broadcast(frequent), "labels", "left_semi")
        grown = paths.join(step.select(F.col("u").alias(places[-1]), F.col("w").alias(f"x{size + 1}"), "to"), places[-1])
        grown = grown.where(reduce(lambda a, b: a & b, [F.col(f"x{size + 1}") != F.col(c) for c in places]))
        grown = grown.withColumn("labels", F.concat("labels", F.array("to"))).withColumn("end", F.slice("labels", 2, size))
        paths = grown.join(F.broadcast(frequent.withColumnRenamed("labels", "end")), "end", "left_semi").select(*places, f"x{size + 1}", "labels")
    return graph.spark.createDataFrame(found, "pattern string, labels string, support long")
