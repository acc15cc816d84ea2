"""Matching orders and the id checks that report each subgraph once."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import permutations

from motifprune.plans.pattern import Pattern, automorphisms


@dataclass(frozen=True)
class Schedule:
    """order[p-1] is the pattern vertex matched at position p; checks (a, b) mean id(a) < id(b), by position."""

    pattern: Pattern
    order: tuple[int, ...]
    checks: tuple[tuple[int, int], ...]

    @property
    def n(self) -> int:
        return self.pattern.n

    def linked(self, a: int, b: int) -> bool:
        return self.pattern.adjacent(self.order[a - 1], self.order[b - 1])

    def before(self, h: int, i: int) -> frozenset[int]:
        """Positions 1..h whose vertices neighbour position i."""
        return frozenset(j for j in range(1, h + 1) if self.linked(j, i))


def canonical_checks(p: Pattern, order: tuple[int, ...]) -> tuple[tuple[int, int], ...]:
    """Checks from a chain of stabilisers: a position's vertex precedes all others of its orbit, then it is fixed."""
    group, at, out = automorphisms(p), {v: k + 1 for k, v in enumerate(order)}, []
    for v in order:
        out += [(at[v], at[w]) for w in sorted({s[v] for s in group} - {v}, key=at.get)]
        group = tuple(s for s in group if s[v] == v)
    return tuple(sorted(out))


def connected_orders(p: Pattern) -> Iterator[tuple[int, ...]]:
    """Orders in which each vertex but the first neighbours an earlier one."""
    for order in permutations(range(p.n)):
        if all(p.neighbours(order[k]) & set(order[:k]) for k in range(1, p.n)):
            yield order


def greedy_order(p: Pattern) -> tuple[int, ...]:
    """From a vertex of highest degree, always the one with most matched neighbours, then highest degree."""
    order = [max(range(p.n), key=lambda v: (len(p.neighbours(v)), -v))]
    while len(order) < p.n:
        rest = [v for v in range(p.n) if v not in order]
        order.append(max(rest, key=lambda v: (len(p.neighbours(v) & set(order)), len(p.neighbours(v)), -v)))
    return tuple(order)


def order_cost(p: Pattern, order: tuple[int, ...], stats) -> float:
    """Expected number of partial matches over all depths, each id check halving it."""
    checks = canonical_checks(p, order)
    rows, total = float(stats.n_vertices), float(stats.n_vertices)
    for k in range(1, p.n):
        back = [j for j in range(k) if p.adjacent(order[j], order[k])]
        rows *= stats.n_vertices * stats.p1 * stats.p2 ** (len(back) - 1)
        rows *= 0.5 ** sum(b == k + 1 or a == k + 1 for a, b in checks if max(a, b) == k + 1)
        total += rows
    return total


def choose_schedule(p: Pattern, stats=None, strategy: str = "greedy", order=None) -> Schedule:
    """strategy: "greedy", "cost" (least expected rows; needs stats) or "given"."""
    if strategy == "given":
        order = tuple(order)
        if sorted(order) != list(range(p.n)) or any(not p.neighbours(order[k]) & set(order[:k]) for k in range(1, p.n)):
            raise ValueError("the order is not a connected one")
    elif strategy == "cost":
        order = min(connected_orders(p), key=lambda o: (order_cost(p, o, stats), o))
    elif strategy == "greedy":
        order = greedy_order(p)
    else:
        raise ValueError(f"no strategy {strategy}")
    return Schedule(p, order, canonical_checks(p, order))
