"""Query graphs and their symmetries (driver only; at most MOST_VERTICES vertices)."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import lru_cache
from itertools import permutations

MOST_VERTICES = 8


@dataclass(frozen=True)
class Pattern:
    """A connected simple graph on vertices 0..n-1, with an optional label for each vertex."""

    n: int
    edges: frozenset[frozenset[int]]
    labels: tuple[int, ...] | None = None
    name: str = ""

    def __post_init__(self) -> None:
        if not 2 <= self.n <= MOST_VERTICES:
            raise ValueError(f"a pattern has 2 to {MOST_VERTICES} vertices, not {self.n}")
        for e in self.edges:
            if len(e) != 2:
                raise ValueError("a pattern has no loops")
            if not e <= set(range(self.n)):
                raise ValueError(f"edge {sorted(e)} names an unknown vertex")
        if self.labels is not None and len(self.labels) != self.n:
            raise ValueError("one label for each vertex is needed")
        reached, front = {0}, [0]
        while front:
            v = front.pop()
            new = self.neighbours(v) - reached
            reached |= new
            front += new
        if len(reached) != self.n:
            raise ValueError("the pattern is not connected")

    @classmethod
    def of(cls, edges, labels=None, name: str = "") -> Pattern:
        edges = [tuple(e) for e in edges]
        n = max((max(e) for e in edges), default=0) + 1
        return cls(n, frozenset(frozenset(e) for e in edges), tuple(labels) if labels is not None else None, name)

    @classmethod
    def parse(cls, text: str, labels=None, name: str = "") -> Pattern:
        """From text such as "1-2, 2-3"; the numbers are renumbered from 0 in ascending order."""
        pairs = [(int(a), int(b)) for a, b in re.findall(r"(\d+)\s*-\s*(\d+)", text)]
        ids = {v: k for k, v in enumerate(sorted({x for p in pairs for x in p}))}
        return cls.of([(ids[a], ids[b]) for a, b in pairs], labels, name)

    @classmethod
    def from_df(cls, df, name: str = "") -> Pattern:
        """From a small DataFrame whose first two columns are an edge's ends."""
        return cls.parse(",".join(f"{r[0]}-{r[1]}" for r in df.limit(MOST_VERTICES**2).collect()), name=name)

    def neighbours(self, v: int) -> set[int]:
        return {w for e in self.edges if v in e for w in e if w != v}

    def adjacent(self, a: int, b: int) -> bool:
        return frozenset((a, b)) in self.edges

    def canonical_form(self) -> str:
        """The same text for isomorphic patterns and no others."""
        return min(",".join(f"{a}-{b}" for a, b in sorted(tuple(sorted((p[a], p[b]))) for a, b in map(tuple, self.edges))) + (f":{[self.labels[p.index(k)] for k in range(self.n)]}" if self.labels else "") for p in permutations(range(self.n)))


@lru_cache(maxsize=256)
def automorphisms(p: Pattern) -> tuple[tuple[int, ...], ...]:
    """All vertex permutations that keep edges and labels."""
    return tuple(s for s in permutations(range(p.n)) if (p.labels is None or all(p.labels[s[v]] == p.labels[v] for v in range(p.n))) and all(frozenset((s[a], s[b])) in p.edges for a, b in map(tuple, p.edges)))


def _complete(n: int, *missing: tuple[int, int]) -> list[tuple[int, int]]:
    return [(a, b) for b in range(n) for a in range(b) if (a, b) not in missing]


#: The workload's eight patterns, from sparse to dense, and small ones for tests.
CATALOGUE: dict[str, Pattern] = {
    k: Pattern.of(e, name=k)
    for k, e in {
        "clique4": _complete(4),
        "house5": [(0, 1), (1, 2), (2, 3), (3, 0), (0, 4), (1, 4)],
        "near_clique5": _complete(5, (3, 4)),
        "clique5": _complete(5),
        "wheel6": [(0, k) for k in range(1, 6)] + [(1, 2), (2, 3), (3, 4), (4, 5), (1, 5)],
        "prism6": [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (0, 3), (1, 4), (2, 5)],
        "octahedron6": _complete(6, (0, 1), (2, 3), (4, 5)),
        "near_clique7": _complete(7, (5, 6)),
        "edge": [(0, 1)],
        "wedge": [(0, 1), (1, 2)],
        "triangle": _complete(3),
        "path4": [(0, 1), (1, 2), (2, 3)],
        "star4": [(0, 1), (0, 2), (0, 3)],
        "cycle4": [(0, 1), (1, 2), (2, 3), (0, 3)],
        "tailed_triangle": [(0, 1), (1, 2), (0, 2), (2, 3)],
        "diamond": _complete(4, (2, 3)),
        "cycle5": [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)],
        "bowtie": [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (2, 4)],
    }.items()
}
WORKLOAD = ("clique4", "house5", "near_clique5", "clique5", "wheel6", "prism6", "octahedron6", "near_clique7")


@lru_cache(maxsize=8)
def connected_shapes(k: int) -> tuple[Pattern, ...]:
    """Every connected graph of k vertices once, by number of edges and canonical form."""
    pairs = _complete(k)
    found = {}
    for mask in range(1 << len(pairs)):
        edges = [e for b, e in enumerate(pairs) if mask >> b & 1]
        if len(edges) < k - 1 or {v for e in edges for v in e} != set(range(k)):
            continue
        try:
            p = Pattern.of(edges)
        except ValueError:
            continue
        degrees = tuple(sorted(len(p.neighbours(v)) for v in range(k)))
        found.setdefault((len(edges), degrees, p.canonical_form()), p)
    return tuple(found[key] for key in sorted(found))
