"""Matching by plain joins: SQL text for Spark and DuckDB, and brute force for tiny graphs."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame

from motifprune.plans.pattern import Pattern, automorphisms
from motifprune.plans.schedule import Schedule, choose_schedule
from motifprune.sources.graphs import Graph


def match_sql(pattern: Pattern, variant: str = "edge", dialect: str = "spark", edges: str = "SELECT src, dst FROM graph_edges", output: str = "count", schedule: Schedule | None = None, labels: str | None = None) -> str:
    """One step a vertex: the first back edge joins, further ones are semi joins, non-edges anti joins.

    edges and labels are SQL of (src, dst) and (v, label).
    """
    s = schedule or choose_schedule(pattern)
    kept = " MATERIALIZED" if dialect == "duckdb" else ""
    steps = [f"e AS{kept} ({edges})", f"arc AS{kept} (SELECT src AS u, dst AS w FROM e UNION ALL SELECT dst, src FROM e)"]
    if pattern.labels:
        steps.append(f"lab AS{kept} ({labels})")
    label = lambda p, of: f" AND EXISTS (SELECT 1 FROM lab WHERE lab.v = {of} AND lab.label = {pattern.labels[s.order[p - 1]]})" if pattern.labels else ""
    steps.append(f"l1 AS{kept} (SELECT DISTINCT u AS u1 FROM arc WHERE true{label(1, 'u')})")
    for i in range(2, s.n + 1):
        near = sorted(s.before(i - 1, i))
        where = []
        for j in range(1, i):
            if j in near[1:]:
                where.append(f"EXISTS (SELECT 1 FROM arc x WHERE x.u = l.u{j} AND x.w = a.w)")
            elif j not in near and variant == "vertex":
                where.append(f"NOT EXISTS (SELECT 1 FROM arc x WHERE x.u = l.u{j} AND x.w = a.w)")
            if (j, i) in s.checks:
                where.append(f"a.w > l.u{j}")
            elif (i, j) in s.checks:
                where.append(f"a.w < l.u{j}")
            elif j not in near:
                where.append(f"a.w <> l.u{j}")
        steps.append(f"l{i} AS{kept} (SELECT l.*, a.w AS u{i} FROM l{i - 1} l JOIN arc a ON a.u = l.u{near[0]} WHERE {' AND '.join(where) or 'true'}{label(i, 'a.w')})")
    shown = "CAST(count(*) AS BIGINT) AS cnt" if output == "count" else ", ".join(f"u{s.order.index(v) + 1} AS v{v + 1}" for v in range(s.n))
    return f"WITH {', '.join(steps)} SELECT {shown} FROM l{s.n}"


def match_joins(graph: Graph, pattern: Pattern, variant: str = "edge", output: str = "count") -> DataFrame:
    labels = {"own_labels": graph.labels} if pattern.labels else {}
    text = match_sql(pattern, variant, "spark", "SELECT src, dst FROM {own_edges}", output, labels="SELECT v, label FROM {own_labels}")
    return graph.spark.sql(text, own_edges=graph.edges, **labels)


def brute_force(edges: set[tuple[int, int]], pattern: Pattern, variant: str = "edge", labels: dict[int, int] | None = None) -> set[tuple[int, ...]]:
    """Matches by trying every arrangement; one tuple, the least, for each subgraph."""
    linked = {frozenset(e) for e in edges}
    out = set()
    for t in permutations(sorted({v for e in edges for v in e}), pattern.n):
        good = all((frozenset((t[a], t[b])) in linked) if pattern.adjacent(a, b) else variant == "edge" or frozenset((t[a], t[b])) not in linked for b in range(pattern.n) for a in range(b))
        if good and (pattern.labels is None or all(labels.get(t[v]) == pattern.labels[v] for v in range(pattern.n))):
            out.add(min(tuple(t[s[v]] for v in range(pattern.n)) for s in automorphisms(pattern)))
    return out
