"""Execution plans: which set operation runs at which depth, and which lists are worth pruning ahead.

Notation: position 1..n in matching order; the prefix set of i at depth h holds the vertices that can still
match i once h are matched. A pruned list (h, k, i) is the adjacency list of a candidate of k, cut to the
prefix set of i at depth h, for use when loop k combines the prefix set of i.

Why results do not change: with C within C' and P = C' & N, C & P = C & N and C - P = C - N. Prefix sets only
shrink with depth, and id bounds only accumulate, so the set at depth h contains the one at loop k.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from motifprune.plans.schedule import Schedule

INIT, INTERSECT, SUBTRACT, CARRY = "init", "intersect", "subtract", "carry"


@dataclass(frozen=True)
class PrefixStep:
    depth: int
    target: int
    kind: str
    deferred: tuple[int, ...] = ()  # earlier non-neighbours still to subtract, at INIT
    above: bool = False  # the new vertex bounds the set from below: id(target) > id(new)
    below: bool = False


SetKey = tuple  # what a prefix set is made of; equal keys, equal sets


@dataclass(frozen=True)
class AuxSpec:
    """A pruned list; consumers are the (k, i) that read it, equal lists being one spec."""

    h: int
    select: SetKey
    keep: SetKey
    consumers: tuple[tuple[int, int], ...]
    parent: int | None = None

    @property
    def name(self) -> str:
        return f"aux{self.h}_" + "_".join(f"{k}{i}" for k, i in self.consumers)


@dataclass(frozen=True)
class Options:
    variant: str = "edge"
    bound_prefix: bool = True
    share: bool = True
    merge: bool = True
    reuse_aux: bool = True

    def __post_init__(self) -> None:
        if self.variant not in ("edge", "vertex"):
            raise ValueError("variant is edge or vertex")


@dataclass(frozen=True)
class ExecutionPlan:
    schedule: Schedule
    options: Options = field(default_factory=Options)

    @property
    def n(self) -> int:
        return self.schedule.n

    def key(self, h: int, i: int) -> SetKey | None:
        """What the prefix set of i at depth h is made of; None before a neighbour is matched."""
        s = self.schedule
        near = s.before(h, i)
        if not near:
            return None
        far = frozenset(range(1, h + 1)) - near if self.options.variant == "vertex" else frozenset()
        bounds = frozenset()
        if self.options.bound_prefix:
            bounds = frozenset([(a, ">") for a, b in s.checks if b == i and a <= h] + [(b, "<") for a, b in s.checks if a == i and b <= h])
        return (tuple(sorted(near)), tuple(sorted(far)), tuple(sorted(bounds))) + (() if self.options.share else (i,))

    def positions(self, key: SetKey) -> set[int]:
        """The matched positions that a prefix set depends on."""
        return {*key[0], *key[1], *(a for a, _ in key[2])}

    def step(self, h: int, i: int) -> PrefixStep | None:
        s = self.schedule
        if self.key(h, i) is None:
            return None
        above = self.options.bound_prefix and (h, i) in s.checks
        below = self.options.bound_prefix and (i, h) in s.checks
        if s.linked(h, i):
            if self.key(h - 1, i) is None:
                deferred = tuple(range(1, h)) if self.options.variant == "vertex" else ()
                return PrefixStep(h, i, INIT, deferred, above, below)
            return PrefixStep(h, i, INTERSECT, (), above, below)
        return PrefixStep(h, i, SUBTRACT if self.options.variant == "vertex" else CARRY, (), above, below)

    @cached_property
    def steps(self) -> tuple[PrefixStep, ...]:
        return tuple(x for h in range(1, self.n) for i in range(h + 1, self.n + 1) if (x := self.step(h, i)))

    def alive(self, h: int) -> dict[SetKey, list[int]]:
        """The different prefix sets of later positions at depth h, with those positions."""
        out: dict[SetKey, list[int]] = {}
        for i in range(h + 1, self.n + 1):
            if key := self.key(h, i):
                out.setdefault(key, []).append(i)
        return out

    def reads_list(self, h: int) -> bool:
        """Whether depth h reads the adjacency list of its vertex."""
        return any(x.depth == h and x.kind != CARRY for x in self.steps)

    @cached_property
    def aux(self) -> tuple[AuxSpec, ...]:
        """All pruned lists that can be built, equal ones merged, each with the one it can be built from."""
        found: dict[tuple, list[tuple[int, int]]] = {}
        for k in range(3, self.n):
            for i in range(k + 1, self.n + 1):
                x = self.step(k, i)
                if x is None or x.kind not in (INTERSECT, SUBTRACT):
                    continue
                for h in range(1, k - 1):
                    a, b = self.key(h, k), self.key(h, i)
                    if a and b:
                        found.setdefault((h, a, b) + (() if self.options.merge else (k, i)), []).append((k, i))
        specs = [AuxSpec(key[0], key[1], key[2], tuple(c)) for key, c in sorted(found.items(), key=lambda x: (x[0][0], x[1]))]
        if not self.options.reuse_aux:
            return tuple(specs)
        out = []
        for x in specs:
            parents = [j for j, y in enumerate(specs) if y.h < x.h and set(x.consumers) <= set(y.consumers)]
            out.append(AuxSpec(x.h, x.select, x.keep, x.consumers, max(parents, key=lambda j: specs[j].h, default=None)))
        return tuple(out)

    def version(self, k: int, i: int) -> int | None:
        """The deepest pruned list that loop k can read for i."""
        return max((j for j, x in enumerate(self.aux) if (k, i) in x.consumers), key=lambda j: self.aux[j].h, default=None)

    def versions(self, k: int, i: int) -> list[int]:
        """All pruned lists for loop k and i, deepest first."""
        return sorted((j for j, x in enumerate(self.aux) if (k, i) in x.consumers), key=lambda j: -self.aux[j].h)

    def unbounded_specs(self) -> int:
        """Number of pruned lists before equal ones are merged."""
        return sum(len(x.consumers) for x in self.aux)


def explain(plan: ExecutionPlan) -> str:
    s = plan.schedule
    lines = [f"pattern {s.pattern.name or sorted(map(sorted, s.pattern.edges))}, {plan.options.variant}-induced", f"order {s.order}, checks {' '.join(f'{a}<{b}' for a, b in s.checks)}"]
    for h in range(1, plan.n):
        lines.append(f"loop {h}")
        for x in plan.steps:
            if x.depth == h:
                lines.append(f"  set of {x.target}: {x.kind}" + (f" after subtracting {x.deferred}" if x.deferred else "") + (" >" if x.above else "") + (" <" if x.below else ""))
        for x in plan.aux:
            if x.h == h:
                lines.append(f"  {x.name}" + (f" from {plan.aux[x.parent].name}" if x.parent is not None else ""))
    return "\n".join(lines)
