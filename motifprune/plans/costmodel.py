"""When shortening an adjacency list pays: expected reuse times expected shrinkage against the scan up front."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from motifprune.plans.execution import AuxSpec, ExecutionPlan


@dataclass(frozen=True)
class GraphStats:
    n_vertices: int
    n_edges: int
    n_triangles: int
    d_max: int
    triangle_unit: str = "ordered"

    @property
    def d_avg(self) -> float:
        return 2 * self.n_edges / max(1, self.n_vertices)

    @property
    def p1(self) -> float:
        """Probability that two vertices are adjacent."""
        return 2 * self.n_edges / max(1, self.n_vertices) ** 2

    @property
    def p2(self) -> float:
        """Probability that two vertices with a common neighbour are adjacent, at most 1."""
        unit = 6 if self.triangle_unit == "ordered" else 1
        return min(1.0, unit * self.n_triangles * self.n_vertices / max(1, 2 * self.n_edges) ** 2)


@dataclass(frozen=True)
class CostModel:
    """order_discount halves expected sizes for each id check not yet applied; literal switches it off."""

    stats: GraphStats
    order_discount: bool = True

    @classmethod
    def literal(cls, stats: GraphStats) -> CostModel:
        return cls(stats, order_discount=False)

    def shrink(self, plan: ExecutionPlan, h: int, i: int, upto: int) -> float:
        """By how much the candidates of i are expected to shrink from depth h to depth upto."""
        s, out = plan.schedule, 1.0
        for j in range(h + 1, upto + 1):
            if s.linked(j, i):
                joint = any(s.linked(t, j) and s.linked(t, i) for t in range(1, j))
                out *= self.stats.p2 if joint else self.stats.p1
            if self.order_discount and ((j, i) in s.checks or (i, j) in s.checks):
                out *= 0.5
        if self.order_discount and not plan.options.bound_prefix:
            out *= 0.5 ** sum((j, i) in s.checks or (i, j) in s.checks for j in range(1, h + 1))
        return out

    def reuse(self, plan: ExecutionPlan, spec: AuxSpec, size) -> Column:
        """Expected number of reads of one list: matches of h+1..k for each vertex of the selecting set.

        size(key) gives the column of a prefix set's size.
        """
        terms = []
        for k in sorted({k for k, _ in spec.consumers}):
            reads = sum(1 for kk, _ in spec.consumers if kk == k)
            product: Column = F.lit(float(reads))
            for d in range(spec.h + 1, k + 1):
                key = plan.key(spec.h, d)
                product = product * (size(key) if key else F.lit(float(self.stats.n_vertices))) * F.lit(self.shrink(plan, spec.h, d, d - 1))
            terms.append(product / F.greatest(size(spec.select), F.lit(1)))
        return reduce(lambda a, b: a + b, terms)

    def overlap(self, keep_size: Column, degree: Column) -> Column:
        """Expected length of the shortened list, its members being any vertices alike."""
        return keep_size * degree / F.lit(float(max(1, self.stats.n_vertices)))


def gain(reuse: Column, degree: Column, overlap: Column, keep_size: Column) -> Column:
    """Comparisons saved by reading the shortened list, less those of making it."""
    return reuse * (degree - overlap) - (keep_size + degree)


def gain_value(reuse: float, degree: float, overlap: float, keep_size: float) -> float:
    return reuse * (degree - overlap) - (keep_size + degree)


def worth(plan: ExecutionPlan, spec: AuxSpec, model: CostModel, classes: list[tuple[float, float]], join_cost: float) -> bool:
    """Whether a pruned list's positive gains, summed over a graph's degree classes (degree, vertices), exceed its look-ups.

    The first vertex's degree stands for the sizes of the first sets, which shrink as the model expects; list owners are met
    in proportion to their degree. Every read is one look-up, also of lists that are not made.
    """
    ends = sum(d * n for d, n in classes)
    gained = looked_up = 0.0
    for s, n in classes:
        rows, size = n, {}
        for d in range(2, spec.h + 1):  # partial matches of the depth at which the list is made
            rows *= s * model.shrink(plan, 1, d, d - 1)
        for d in range(spec.h + 1, plan.n + 1):
            size[d] = s * model.shrink(plan, 1, d, spec.h) if plan.key(spec.h, d) else float(model.stats.n_vertices)
        k0, i0 = spec.consumers[0]
        reuse = 0.0
        for k in sorted({k for k, _ in spec.consumers}):
            product = float(sum(1 for kk, _ in spec.consumers if kk == k))
            for d in range(spec.h + 1, k + 1):
                product *= size[d] * model.shrink(plan, spec.h, d, d - 1)
            reuse += product / max(1.0, size[k0])
        lists = rows * size[k0]
        looked_up += lists * reuse
        for d, m in classes:
            one = gain_value(reuse, d, size[i0] * d / max(1, model.stats.n_vertices), size[i0])
            gained += lists * (d * m / max(1.0, ends)) * max(0.0, one)
    return gained > join_cost * looked_up
