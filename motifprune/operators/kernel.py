"""Depth-first matching in generated NumPy loops, one set of roots a task.

For each plan a straight-line Python function of nested loops is assembled from the plan's integers alone,
with a fixed choice of list for each operation. Where adjacency is below a checked bound, roots stream through
mapInArrow and adjacency goes to the workers as a broadcast of compressed lists, packed by the tasks; above it, each root is shipped the
lists that its loops can read, as one group. Nested splitting deals one root's second-loop candidates to several
tasks. Set operations look up in buffers that belong to the worker.
"""

from __future__ import annotations

import math
import os
import time
from collections.abc import Iterator
from functools import lru_cache, reduce
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifprune.operators.frontier import Policy
from motifprune.plans.costmodel import CostModel, GraphStats
from motifprune.plans.execution import CARRY, INIT, SUBTRACT, AuxSpec, ExecutionPlan
from motifprune.sources.compressed import Lists, compress
from motifprune.sources.graphs import Graph

BROADCAST_ARCS = 20_000_000  # 80 MB of neighbours
ROWS_A_BATCH = 50_000
JOINED_LISTS = 256  # of the last loop
READS_HELD = 1 << 20
ROOTS_A_GROUP = 256  # labelled roots that are counted beside one another, from one copy of the lists near them
MEASURES = ("cnt", "adjacency", "aux", "prefix", "lists_considered", "lists_built", "lists_used", "aux_bytes")
COUNTERS = "root long, part int, " + ", ".join(f"{m} long" for m in MEASURES) + ", elapsed_ms double, pid int, task int"


def compressed_rows(graph: Graph, most_arcs: int = BROADCAST_ARCS) -> Lists:
    """Lists of a graph of at most most_arcs arcs."""
    arcs = graph.edges.count() * 2
    if arcs > most_arcs:
        raise ValueError(f"{arcs} arcs exceed the bound of {most_arcs} for a broadcast")
    return compress(graph.adj)


class SortedSets:
    """Operations on sorted arrays; positions and comparisons go to buffers kept by the worker."""

    def __init__(self) -> None:
        self._grow(1024)

    def _grow(self, n: int) -> None:
        self._found, self._same = np.empty(n, dtype=np.int64), np.empty(n, dtype=bool)

    def _in(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if len(a) > len(self._found):
            self._grow(2 * len(a))
        found, same = self._found[: len(a)], self._same[: len(a)]
        np.take(b, np.searchsorted(b, a), out=found, mode="clip")
        return np.equal(found, a, out=same)

    def meet(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Members of a in b; looks the shorter up in the longer."""
        if not len(a) or not len(b):
            return a[:0]
        if len(a) > 8 * len(b):
            a, b = b, a
        return a[self._in(a, b)]

    def minus(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if not len(a) or not len(b):
            return a
        same = self._in(a, b)
        return a[np.logical_not(same, out=same)]

    def last(self, before: np.ndarray, c: np.ndarray, flat: np.ndarray | None, sizes: np.ndarray | None, less: bool, op: str, apart: bool) -> int:
        """Members of the last loop's sets, over all u of c: of before in u's list (or not in it, if less; flat is None: all), beyond u by op, without u if apart.

        flat: the lists of c, joined together; sizes: of each.
        """
        if not len(before) or not len(c):
            return 0
        total = 0
        if flat is None or less:
            bounded = len(before) * len(c) if not op else int(np.searchsorted(before, c, "left").sum())
            total = len(before) * len(c) - int(np.searchsorted(before, c, "right").sum()) if op == ">" else bounded
            total -= int(np.count_nonzero(self._in(c, before))) if apart and not op else 0
        if flat is None or not len(flat):
            return total
        found = self._in(flat, before)
        if op:
            found &= (np.greater if op == ">" else np.less)(flat, np.repeat(c, sizes))
        n = int(np.count_nonzero(found))
        return total - n if less else n

    def sources(self, c: np.ndarray, lists, made: list[tuple[dict, set]], count: dict) -> tuple[np.ndarray, np.ndarray]:
        """(the lists that a loop over c reads, joined together; their sizes): a pruned one where one is made, of the first that has it."""
        if not any(own for own, _ in made):
            flat, sizes = lists.many(c)
            count["adjacency"] += len(flat)
            return flat, sizes
        found = []
        for u in c.tolist():
            for own, read in made:
                if u in own:
                    found.append(own[u])
                    count["aux"] += len(found[-1])
                    if u not in read:
                        read.add(u)
                        count["lists_used"] += 1
                    break
            else:
                found.append(lists(u))
                count["adjacency"] += len(found[-1])
        return _joined(found)

    def make(self, x: np.ndarray, n_reads: np.ndarray | None, keep: np.ndarray, lists, out: dict, count: dict) -> int:
        """Puts x's lists, cut to keep, into out; with n_reads only those that pay. Returns how many members they have."""
        total = 0
        for at in range(0, len(x), JOINED_LISTS):
            few = x[at : at + JOINED_LISTS]
            flat, sizes = lists.many(few)
            found = self._in(flat, keep) if len(keep) else np.zeros(len(flat), dtype=bool)
            upto = np.cumsum(sizes)
            inside = np.concatenate([[0], np.cumsum(found)])
            kept = inside[upto] - inside[upto - sizes]
            made = few.tolist()
            pays = np.ones(len(few), dtype=bool) if n_reads is None else n_reads[at : at + JOINED_LISTS] * (sizes - kept) > len(keep) + sizes
            members, end = flat[found].astype(np.int64), inside[upto]
            for k, a, b in zip(np.flatnonzero(pays).tolist(), (end - kept)[pays].tolist(), end[pays].tolist()):
                out[made[k]] = members[a:b]
            n = int(np.count_nonzero(pays))
            count["prefix"] += n * len(keep)
            count["adjacency"] += int(sizes[pays].sum())
            count["lists_built"] += n
            total += int(kept[pays].sum())
        return total

    def cut(self, c: np.ndarray) -> Iterator[np.ndarray]:
        """c in pieces whose lists are joined at once."""
        return (c[k : k + JOINED_LISTS] for k in range(0, len(c), JOINED_LISTS))

    def chosen(self, x: np.ndarray, keys: tuple[int, ...], ids: np.ndarray | None, share: float) -> np.ndarray:
        """Those of x whose lists the random policy makes: by the hash that frames take of x and keys."""
        values = [x, *keys] if ids is None else [ids[x], *(ids[k] for k in keys)]
        return x[_by_chance(values, share)]


def _by_chance(values: list, share: float) -> np.ndarray:
    return np.mod(spark_hash(*values).view(np.int64), 1000) < int(1000 * share)


def chosen_ids(ids: np.ndarray, first: int, share: float) -> np.ndarray:
    """Those of ids whose lists the random policy makes for the first vertex's id."""
    return ids[_by_chance([ids, first], share)]


def _joined(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate([np.zeros(0, np.int64), *lists]), np.array([len(x) for x in lists], dtype=np.int64)


def spark_hash(*columns) -> np.ndarray:
    """xxhash64 of columns of 64-bit numbers, as Spark takes it; the first column is an array."""
    one, two, three, four, five = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turned = lambda x, k: x << np.uint64(k) | x >> np.uint64(64 - k)
    out = np.full(len(columns[0]), 42, dtype=np.uint64)
    for c in columns:
        each = np.broadcast_to(np.asarray(c, dtype=np.int64), out.shape).astype(np.uint64)  # a number's bits, whatever its sign
        out = (out + five + np.uint64(8)) ^ turned(each * two, 31) * one
        out = turned(out, 27) * one + four
        out = (out ^ out >> np.uint64(33)) * two
        out = (out ^ out >> np.uint64(29)) * three
        out ^= out >> np.uint64(32)
    return out


class Neighbours:
    """Lists of a worker by vertex: those of a broadcast, by number, or those of a group, by id."""

    def __init__(self, rows: Lists) -> None:
        self.begin, self.end, self.flat = rows.begin, rows.end, rows.flat

    def __call__(self, v: int) -> np.ndarray:
        return self.flat[self.begin[v] : self.end[v]].astype(np.int64)

    def many(self, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(the lists of c, joined together; their sizes)."""
        begin = self.begin[c]
        sizes = self.end[c] - begin
        upto = np.cumsum(sizes)
        return self.flat[np.repeat(begin - (upto - sizes), sizes) + np.arange(upto[-1] if len(c) else 0)], sizes

    def degrees(self, c: np.ndarray) -> np.ndarray:
        return self.end[c] - self.begin[c]


class NearNeighbours:
    def __init__(self, lists: dict[int, np.ndarray], other: np.ndarray | None = None) -> None:
        """other: the list of a vertex that has none here."""
        self.lists, self.other = lists, other

    def __call__(self, v: int) -> np.ndarray:
        return self.lists[v] if self.other is None else self.lists.get(v, self.other)

    def many(self, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return _joined([self(v) for v in c.tolist()])

    def degrees(self, c: np.ndarray) -> np.ndarray:
        return np.array([len(self(v)) for v in c.tolist()], dtype=np.int64)


class Reads:
    """How often each vertex's list is read below a branch."""

    def __init__(self) -> None:
        self.pending, self.size, self.x, self.n = [], 0, np.zeros(0, np.int64), np.zeros(0, np.int64)

    def add(self, c: np.ndarray, times: int) -> None:
        self.pending += [c] * times
        self.size += times * len(c)
        if self.size > READS_HELD:
            self._add_up()

    def _add_up(self) -> None:
        x, at = np.unique(np.concatenate([self.x, *self.pending]), return_inverse=True)
        n = np.bincount(at[len(self.x) :], minlength=len(x))
        n[at[: len(self.x)]] += self.n
        self.x, self.n, self.pending, self.size = x, n, [], 0

    def worth(self, lists, keep_size: int) -> tuple[np.ndarray, np.ndarray]:
        """(x, reads) where a list of no members would pay; whoever makes it sees whether it does."""
        if not len(self.x) and len(self.pending) < 2:  # lists read once never pay
            return self.x, self.n
        self._add_up()
        degree = lists.degrees(self.x)
        some = self.n * degree > keep_size + degree
        return self.x[some], self.n[some]


class Labels:
    """Vertices of each label."""

    def __init__(self, ids: np.ndarray, labels: np.ndarray) -> None:
        order = np.argsort(ids, kind="stable")
        self._ids, self._labels = ids[order], labels[order]

    def __call__(self, a: np.ndarray, want: int) -> np.ndarray:
        """Members of a with the label."""
        if not len(a) or not len(self._ids):
            return a[:0]
        at = np.minimum(np.searchsorted(self._ids, a), len(self._ids) - 1)
        return a[(self._ids[at] == a) & (self._labels[at] == want)]


def _label(plan: ExecutionPlan, position: int) -> int | None:
    p = plan.schedule.pattern
    return None if p.labels is None else p.labels[plan.schedule.order[position - 1]]


def _names(plan: ExecutionPlan) -> dict:
    return {key: f"s{h}_{'_'.join(map(str, ts))}" for h in range(1, plan.n) for key, ts in plan.alive(h).items()}


def source_of(plan: ExecutionPlan, policy: Policy, stats: GraphStats | None, emit_rows: bool) -> str:
    """Python source of run(N, L, S, ids, u1, part, parts, count): nested loops over one root; yields batches of rows if emit_rows.

    What only counts takes the last two loops at once, unless the last set begins there. The oracle policy goes through the loops that
    read a list before it decides on it.
    """
    s, n = plan.schedule, plan.n
    use_aux = policy.name != "none"
    model = CostModel(stats, policy.order_discount) if stats else None
    lines: list[str] = []
    put = lambda depth, text: lines.append("    " * depth + text)
    var = lambda h, key: f"s{h}_{'_'.join(map(str, plan.alive(h)[key]))}"
    put(0, "def run(N, L, S, ids, u1, part, parts, count):")
    put(1, "meet, minus = S.meet, S.minus")
    specs = plan.aux if use_aux else ()
    for j in range(len(specs)):
        put(1, f"b{j} = 0")
    if emit_rows:
        put(1, "rows = []")

    def readable(h: int, targets: list[int]) -> list[int]:
        return sorted({j for i in targets for j in plan.versions(h, i)}, key=lambda j: -plan.aux[j].h) if use_aux else []

    def prefix_sets(h: int, d: int, plain: bool = False) -> None:
        """The sets of depth h; plain: from whole lists, without counters."""
        if plan.reads_list(h):
            put(d, f"n{h} = N(u{h})")
        for key, targets in plan.alive(h).items():
            step, own = plan.step(h, targets[0]), var(h, key)
            bounds = [(a, op) for a, op in key[2] if step.kind == INIT or a == h]
            if step.kind == INIT:
                put(d, f"{own} = n{h}")
                for j in step.deferred:
                    put(d, f"far = N(u{j})")
                    if not plain:
                        put(d, f"count['prefix'] += len({own}); count['adjacency'] += len(far)")
                    put(d, f"{own} = minus({own}, far)")
            else:
                before = var(h - 1, plan.key(h - 1, targets[0]))
                if step.kind == CARRY:
                    put(d, f"{own} = {before}")
                else:
                    put(d, f"src, kind = n{h}, 'adjacency'")
                    for c, j in enumerate([] if plain else readable(h, targets)):
                        put(d, f"{'if' if c == 0 else 'elif'} u{h} in a{j}:")
                        put(d + 1, f"src, kind = a{j}[u{h}], 'aux'")
                        put(d + 1, f"if u{h} not in r{j}: r{j}.add(u{h}); count['lists_used'] += 1")
                    if not plain:
                        put(d, f"count['prefix'] += len({before}); count[kind] += len(src)")
                    put(d, f"{own} = {'minus' if step.kind == SUBTRACT else 'meet'}({before}, src)")
            for a, op in bounds:
                put(d, f"{own} = {own}[searchsorted({own}, u{a}, 'right'):]" if op == ">" else f"{own} = {own}[:searchsorted({own}, u{a}, 'left')]")

    def narrowed(c: str, h: int, i: int, d: int) -> None:
        """Takes from c what the first h positions forbid position i beyond its prefix set."""
        for j in range(1, h + 1):
            if not plan.options.bound_prefix and (j, i) in s.checks:
                put(d, f"{c} = {c}[searchsorted({c}, u{j}, 'right'):]")
            elif not plan.options.bound_prefix and (i, j) in s.checks:
                put(d, f"{c} = {c}[:searchsorted({c}, u{j}, 'left')]")
            elif not s.linked(j, i) and (j, i) not in s.checks and (i, j) not in s.checks:
                put(d, f"{c} = {c}[{c} != u{j}]")

    def candidates(h: int, d: int) -> None:
        """c: what position h+1 may match."""
        put(d, f"c = {var(h, plan.key(h, h + 1))}")
        narrowed("c", h, h + 1, d)
        if _label(plan, h + 1) is not None:
            put(d, f"c = L(c, {int(_label(plan, h + 1))})")
        if h == 1:
            put(d, "if parts > 1: c = c[part::parts]")

    def reads(spec: AuxSpec, h: int, d: int) -> None:
        """q: how often the lists of a spec are read below depth h, without pruned lists."""
        put(d, "q = Reads()")
        loops = {k: len({plan.key(k, i) for kk, i in spec.consumers if kk == k}) for k, _ in spec.consumers}
        for k in range(h + 1, max(loops) + 1):
            candidates(k - 1, d)
            if k in loops:
                put(d, f"q.add(c, {loops[k]})")
            if k < max(loops):
                put(d, f"for u{k} in c.tolist():")
                d += 1
                prefix_sets(k, d, plain=True)

    last = plan.step(n - 1, n) if n > 2 and not emit_rows and _label(plan, n) is None and not any(x.h == n - 1 for x in specs) else None
    at_once = last is not None and last.kind != INIT
    for h in range(1, n):
        d = h
        prefix_sets(h, d)
        for j, spec in enumerate(specs):
            if spec.h != h:
                continue
            select, keep = var(h, spec.select), var(h, spec.keep)
            put(d, f"a{j}, r{j}, b{j} = {{}}, set(), 0")
            for deeper, other in enumerate(specs):
                if other.h > h:  # lists of the branch before
                    put(d, f"b{deeper} = 0")
            if policy.name == "online":
                terms = []
                for k in sorted({k for k, _ in spec.consumers}):
                    parts = [str(float(sum(1 for kk, _ in spec.consumers if kk == k)))]
                    for t in range(h + 1, k + 1):
                        key = plan.key(h, t)
                        parts.append(f"len({var(h, key)})" if key else str(float(stats.n_vertices)))
                        parts.append(repr(model.shrink(plan, h, t, t - 1)))
                    terms.append(" * ".join(parts))
                put(d, f"reuse = ({' + '.join(terms)}) / max(1, len({select}))")
            if policy.name == "oracle":
                reads(spec, h, d)
                put(d, f"count['lists_considered'] += len({select})")
                put(d, f"x, n_reads = q.worth(N, len({keep}))")
            elif policy.name == "random":
                keys = "".join(f"u{p}, " for p in sorted(plan.positions(spec.select) | plan.positions(spec.keep)))
                put(d, f"count['lists_considered'] += len({select})")
                put(d, f"x, n_reads = S.chosen({select}, ({keys}), ids, {float(policy.share)!r}), None")
            if policy.name in ("oracle", "random"):
                if spec.parent is None:
                    put(d, f"b{j} += 8 * S.make(x, n_reads, {keep}, N, a{j}, count)")
                    put(d, "x = x[:0]")
                put(d, "for x, n_reads in zip(x.tolist(), repeat(None) if n_reads is None else n_reads.tolist()):")
            else:
                put(d, f"for x in {select}.tolist():")
                put(d + 1, "count['lists_considered'] += 1")
            put(d + 1, "deg = len(N(x))")
            if policy.name == "online":
                put(d + 1, f"if reuse * (deg - len({keep}) * deg / {float(max(1, stats.n_vertices))!r}) - (len({keep}) + deg) <= 0: continue")
            elif policy.name == "degree":
                put(d + 1, f"if deg < {int(policy.degree_at)}: continue")
            elif policy.name == "oracle":
                put(d + 1, f"if n_reads * (deg - len(meet({keep}, N(x)))) - (len({keep}) + deg) <= 0: continue")
            put(d + 1, "src, kind = N(x), 'adjacency'")
            if spec.parent is not None:
                put(d + 1, f"if x in a{spec.parent}:")
                put(d + 2, f"src, kind = a{spec.parent}[x], 'aux'")
                put(d + 2, f"if x not in r{spec.parent}: r{spec.parent}.add(x); count['lists_used'] += 1")
            put(d + 1, f"count['prefix'] += len({keep}); count[kind] += len(src); count['lists_built'] += 1")
            put(d + 1, f"a{j}[x] = meet({keep}, src); b{j} += 8 * len(a{j}[x])")
            put(d, f"count['aux_bytes'] = max(count['aux_bytes'], {' + '.join(f'b{x}' for x in range(len(specs)))})")
        i = h + 1
        candidates(h, d)
        if at_once and i == n - 1:
            before = var(h, plan.key(h, n))
            op = ">" if (i, n) in s.checks else "<" if (n, i) in s.checks else ""
            put(d, f"w = {before}")
            narrowed("w", h, n, d)
            put(d, "for c in S.cut(c):")
            if last.kind == CARRY:
                put(d + 1, "flat = sizes = None")
            else:
                made = ", ".join(f"(a{j}, r{j})" for j in readable(i, [n]))
                put(d + 1, f"flat, sizes = S.sources(c, N, [{made}], count)")
                put(d + 1, f"count['prefix'] += len(c) * len({before})")
            put(d + 1, f"count['cnt'] += S.last(w, c, flat, sizes, {last.kind == SUBTRACT}, {op!r}, {not s.linked(i, n)})")
            break
        if i == n:
            put(d, "count['cnt'] += len(c)")
            if emit_rows:
                put(d, f"rows += [({', '.join(f'u{j}' for j in range(1, n))}, w) for w in c.tolist()]")
                put(d, f"if len(rows) >= {ROWS_A_BATCH}: yield rows; rows = []")
        else:
            put(d, f"for u{i} in c.tolist():")
    if emit_rows:
        put(1, "yield rows")
    return "\n".join(lines)


@lru_cache(maxsize=128)
def compile_plan(plan: ExecutionPlan, policy: Policy, stats: GraphStats | None, emit_rows: bool = False):
    """The compiled function; cached by plan, policy and statistics. Its source holds numbers of the plan only."""
    space = {"searchsorted": np.searchsorted, "len": len, "max": max, "set": set, "zip": zip, "repeat": repeat, "Reads": Reads}
    exec(compile(source_of(plan, policy, stats, emit_rows), "<plan>", "exec"), space)  # noqa: S102
    return space["run"]


def interpreted(plan: ExecutionPlan):
    """The same loops driven by the plan's steps at run time, without generated source (a baseline; no pruned lists)."""
    s, n = plan.schedule, plan.n

    def run(N, L, S, ids, u1, part, parts, count):
        u = [0] * (n + 1)

        def loop(h: int, was: dict) -> None:
            own = N(u[h]) if plan.reads_list(h) else None
            sets = {}
            for key, targets in plan.alive(h).items():
                step = plan.step(h, targets[0])
                if step.kind == INIT:
                    a = own
                    for j in step.deferred:
                        count["prefix"] += len(a)
                        count["adjacency"] += len(N(u[j]))
                        a = S.minus(a, N(u[j]))
                else:
                    a = was[plan.key(h - 1, targets[0])]
                    if step.kind != CARRY:
                        count["prefix"] += len(a)
                        count["adjacency"] += len(own)
                        a = S.minus(a, own) if step.kind == SUBTRACT else S.meet(a, own)
                for at, op in key[2]:
                    if step.kind == INIT or at == h:
                        a = a[np.searchsorted(a, u[at], "right") :] if op == ">" else a[: np.searchsorted(a, u[at], "left")]
                sets[key] = a
            i = h + 1
            c = sets[plan.key(h, i)]
            for j in range(1, h + 1):
                if not plan.options.bound_prefix and (j, i) in s.checks:
                    c = c[np.searchsorted(c, u[j], "right") :]
                elif not plan.options.bound_prefix and (i, j) in s.checks:
                    c = c[: np.searchsorted(c, u[j], "left")]
                elif not s.linked(j, i) and (j, i) not in s.checks and (i, j) not in s.checks:
                    c = c[c != u[j]]
            if _label(plan, i) is not None:
                c = L(c, _label(plan, i))
            if h == 1 and parts > 1:
                c = c[part::parts]
            if i == n:
                count["cnt"] += len(c)
                return
            for w in c.tolist():
                u[i] = w
                loop(i, sets)

        u[1] = u1
        loop(1, {})

    return run


def scratch(plan: ExecutionPlan):
    """Loops without prefix sets: what a position may match is found anew for each partial match, from whole lists (a baseline; no counters of work).

    plan: with sets unbounded. Below one partial match the last sets are found in step, each from its own vertex's list.
    """
    s, n, vertex = plan.schedule, plan.n, plan.options.variant == "vertex"
    near = {i: [j for j in range(1, i) if s.linked(j, i)] for i in range(2, n + 1)}
    far = {i: [j for j in range(1, i) if vertex and not s.linked(j, i)] for i in range(2, n + 1)}
    rules = {i: [(j, ">" if (j, i) in s.checks else "<" if (i, j) in s.checks else "") for j in range(1, i) if j not in near[i] or (j, i) in s.checks or (i, j) in s.checks] for i in range(2, n + 1)}
    in_step = n - 1 in near[n] and _label(plan, n) is None

    def run(N, L, S, ids, u1, part, parts, count):
        u = [0] * (n + 1)

        def found(i: int) -> np.ndarray:
            c = reduce(S.meet, [N(u[j]) for j in near[i]])
            for j in far[i]:
                c = S.minus(c, N(u[j]))
            for j, op in rules[i]:
                if op == ">":
                    c = c[np.searchsorted(c, u[j], "right") :]
                elif op == "<":
                    c = c[: np.searchsorted(c, u[j], "left")]
                else:
                    c = c[c != u[j]]
            return c

        def all_found(c: np.ndarray) -> int:
            """Members of the last sets, over all vertices c of the loop before."""
            flat, sizes = N.many(c)
            of = np.repeat(c, sizes)
            keep = np.ones(len(flat), dtype=bool)
            for j, op in rules[n]:
                own = of if j == n - 1 else u[j]
                keep &= flat > own if op == ">" else flat < own if op == "<" else flat != own
            flat = flat[keep]
            for j in near[n][:-1]:
                flat = flat[S._in(flat, N(u[j]))]
            for j in far[n]:
                flat = flat[~S._in(flat, N(u[j]))]
            return len(flat)

        def loop(i: int) -> None:
            c = found(i)
            if _label(plan, i) is not None:
                c = L(c, _label(plan, i))
            if i == 2 and parts > 1:
                c = c[part::parts]
            if i == n:
                count["cnt"] += len(c)
            elif i == n - 1 and in_step:
                for few in S.cut(c):
                    count["cnt"] += all_found(few)
            else:
                for w in c.tolist():
                    u[i] = w
                    loop(i + 1)

        u[1] = u1
        loop(2)

    return run


def _roots(graph: Graph, plan: ExecutionPlan, nested: bool, split_threshold: int | None) -> DataFrame:
    """(root, part, parts): the vertices that may match the first position, cut by their degree if nested.

    Without a threshold, a root is cut into parts of twice the average degree.
    """
    if not nested and _label(plan, 1) is not None:
        return graph.labels.where(F.col("label") == _label(plan, 1)).select(F.col("v").alias("root"), F.lit(0).alias("part"), F.lit(1).alias("parts"))
    degrees = graph.degrees
    if _label(plan, 1) is not None:
        degrees = degrees.join(graph.labels.where(F.col("label") == _label(plan, 1)).select(F.col("v").alias("u")), "u", "left_semi")
    parts = F.lit(1)
    if nested:
        each = split_threshold or max(4, math.ceil(2 * (graph.degrees.agg(F.avg("deg")).first()[0] or 1)))
        parts = F.greatest(F.lit(1), F.ceil(F.col("deg") / each)).cast("int")
    return degrees.withColumn("parts", parts).select(F.col("u").alias("root"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "parts")


def ego_lists(graph: Graph, plan: ExecutionPlan) -> DataFrame:
    """(root, u, nbrs, labels) of all lists that loops from each root can read: vertices as near as the pattern's positions are."""
    s, far, near = plan.schedule, {1: 0}, [1]
    for j in near:
        for i in range(1, plan.n + 1):
            if i not in far and s.linked(j, i):
                far[i] = far[j] + 1
                near.append(i)
    if s.pattern.labels is not None:
        reached, lists = _labelled_ego(graph, plan)
        return reached.join(lists, "u")
    reached = graph.degrees.select(F.col("u").alias("root"), "u")
    edge = reached
    for _ in range(max(far[h] for h in range(1, plan.n))):
        edge = edge.join(graph.arcs, "u").select("root", F.col("w").alias("u")).distinct()
        reached = reached.unionByName(edge).distinct()
    return reached.join(graph.adj.select("u", "nbrs", F.lit(None).cast("array<int>").alias("labels")), "u")


def _labelled_ego(graph: Graph, plan: ExecutionPlan) -> tuple[DataFrame, DataFrame]:
    """(root, u) and (u, nbrs, labels) of a labelled pattern: vertices that can match a position whose list a loop reads, with the members that can match a later one.

    A vertex of another label is in no match, so neither its list nor its place in lists is shipped.
    """
    s, n = plan.schedule, plan.n
    want = {h: _label(plan, h) for h in range(1, n + 1)}
    far, near = {1: 0}, [1]  # by positions whose lists are read: each is linked to an earlier one
    for j in near:
        for i in range(2, n):
            if i not in far and s.linked(j, i):
                far[i] = far[j] + 1
                near.append(i)
    listed = {(want[h], want[i]) for h in range(1, n) for i in range(h + 1, n + 1)}
    own = graph.labels.where(F.col("label").isin(*set(want.values())))
    named = lambda v, label: own.select(F.col("v").alias(v), F.col("label").cast("int").alias(label))
    edges = graph.edges.join(named("src", "ls"), "src").join(named("dst", "ld"), "dst")
    both = F.array(F.struct(F.col("src").alias("u"), F.col("ls").alias("lu"), F.col("dst").alias("w"), F.col("ld").alias("lw")), F.struct(F.col("dst").alias("u"), F.col("ld").alias("lu"), F.col("src").alias("w"), F.col("ls").alias("lw")))

    def arcs(pairs: set) -> DataFrame:
        kept = F.filter(both, lambda x: reduce(lambda p, q: p | q, [(x["lu"] == a) & (x["lw"] == b) for a, b in sorted(pairs)]))
        return edges.select(F.explode(kept).alias("x")).select("x.*")

    lists = arcs(listed).groupBy("u").agg(F.sort_array(F.collect_list(F.struct("w", F.col("lw").alias("label")))).alias("p")).select("u", F.col("p.w").alias("nbrs"), F.col("p.label").alias("labels"))
    reached = edge = own.where(F.col("label") == want[1]).select(F.col("v").alias("root"), F.col("v").alias("u"))
    for d in range(max(far.values())):
        steps = {(want[j], want[i]) for j in far for i in far if far[j] == d and far[i] == d + 1 and s.linked(j, i)}
        edge = edge.join(arcs(steps).select("u", "w"), "u").select("root", F.col("w").alias("u")).distinct()
        reached = reached.unionByName(edge).distinct() if d else reached.unionByName(edge)  # the first step meets no root
    return reached, lists


class _Worker:
    """Runs roots in one Python worker and collects counters or rows."""

    def __init__(self, plan: ExecutionPlan, policy: Policy, stats: GraphStats | None, emit: bool, engine: str, ids: np.ndarray | None = None) -> None:
        """ids: of the vertices, where lists hold their numbers."""
        self.plan, self.emit, self.sets, self.ids = plan, emit, SortedSets(), ids
        self.run = compile_plan(plan, policy, stats, emit) if engine == "generated" else (scratch if engine == "scratch" else interpreted)(plan)
        context = TaskContext.get()
        self.task = context.partitionId() if context else 0

    def one(self, neighbours, labels, root: int, part: int, parts: int, out: list) -> Iterator[list]:
        """Batches of rows; what was counted is appended to out."""
        count, began = dict.fromkeys(MEASURES, 0), time.perf_counter()
        first = root if self.ids is None else int(np.searchsorted(self.ids, root))
        got = self.run(neighbours, labels, self.sets, self.ids, first, part, parts, count)
        if self.emit:
            yield from got
        out.append((root, part, *count.values(), (time.perf_counter() - began) * 1000, os.getpid(), self.task))

    def rows(self, rows: list) -> pa.RecordBatch:
        n, order = self.plan.n, self.plan.schedule.order
        columns = list(zip(*rows)) or [[]] * n
        if self.ids is not None:
            columns = [self.ids[np.array(c, dtype=np.int64)] for c in columns]
        return pa.RecordBatch.from_arrays([pa.array(columns[order.index(v)], pa.int64()) for v in range(n)], [f"v{v + 1}" for v in range(n)])

    def counters(self, out: list) -> pa.RecordBatch:
        kinds = [pa.int64(), pa.int32(), *[pa.int64()] * len(MEASURES), pa.float64(), pa.int32(), pa.int32()]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*out)) or [[]] * len(kinds), kinds)], [f.split(" ")[0] for f in COUNTERS.split(", ")])


def match_kernel(graph: Graph, plan: ExecutionPlan, policy: Policy | str = "online", nested: bool = False, split_threshold: int | None = None, output: str = "counters", engine: str = "generated", tasks: int | None = None, most_arcs: int = BROADCAST_ARCS) -> DataFrame:
    """One row of COUNTERS for each root (and slice, if nested), or rows v1..vn.

    nested: a root with more than split_threshold neighbours is dealt to several tasks by slices of its second loop.
    A graph of more than most_arcs arcs isn't broadcast: each root gets the lists near it.
    """
    policy = Policy(policy) if isinstance(policy, str) else policy
    if policy.name not in ("none", "eager", "online", "degree", "random", "oracle"):
        raise ValueError(f"the kernel has no policy {policy.name}")
    if output == "rows" and engine != "generated":
        raise ValueError(f"the {engine} engine counts only")
    if plan.schedule.pattern.labels is not None and graph.labels is None:
        raise ValueError("a labelled pattern needs a labelled graph")
    stats = graph.stats if policy.name == "online" and plan.aux else None  # the model decides on pruned lists only
    emit = output == "rows"
    schema = ", ".join(f"v{v + 1} long" for v in range(plan.n)) if emit else COUNTERS
    roots = _roots(graph, plan, nested, split_threshold)
    if graph.edges.count() * 2 > most_arcs:
        return _by_ego(graph, plan, policy, stats, emit, engine, roots, schema)
    spark = graph.spark
    labels = None
    if plan.schedule.pattern.labels is not None:
        got = graph.labels.where(F.col("label").isin(*set(plan.schedule.pattern.labels))).join(graph.degrees.select(F.col("u").alias("v")), "v", "left_semi").toPandas()
        labels = got["v"].to_numpy(dtype=np.int64), got["label"].to_numpy(dtype=np.int64)  # a row for each vertex at most
    if "compressed" not in graph.__dict__:
        graph.__dict__["compressed"] = spark.sparkContext.broadcast(compressed_rows(graph, most_arcs))
    lists, own_labels = graph.__dict__["compressed"], spark.sparkContext.broadcast(labels)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows_of, own = lists.value, own_labels.value
        neighbours = Neighbours(rows_of)
        labelled = Labels(rows_of.numbers(own[0]), own[1]) if own else None
        worker = _Worker(plan, policy, stats, emit, engine, rows_of.ids)
        for batch in batches:
            out: list = []
            for root, part, parts in zip(*(c.to_pylist() for c in batch.columns)):
                for rows in worker.one(neighbours, labelled, root, part, parts, out):
                    yield worker.rows(rows)
            if not emit:
                yield worker.counters(out)

    tasks = tasks or 4 * spark.sparkContext.defaultParallelism
    return roots.repartition(tasks, F.xxhash64("root", "part")).mapInArrow(work, schema)


def _by_ego(graph: Graph, plan: ExecutionPlan, policy: Policy, stats: GraphStats | None, emit: bool, engine: str, roots: DataFrame, schema: str) -> DataFrame:
    if plan.schedule.pattern.labels is not None:
        return _by_labelled_ego(graph, plan, policy, stats, emit, engine, roots, schema)

    def work(group: pa.Table) -> pa.Table:
        lists = dict(zip(group.column("u").to_pylist(), (x.values.to_numpy() for x in group.column("nbrs"))))
        worker, out = _Worker(plan, policy, stats, emit, engine), []
        root, part, parts = (group.column(c)[0].as_py() for c in ("root", "part", "parts"))
        batches = [worker.rows(rows) for rows in worker.one(NearNeighbours(lists), None, root, part, parts, out)]
        return pa.Table.from_batches(batches if emit else [worker.counters(out)])

    return roots.join(ego_lists(graph, plan), "root").groupBy("root", "part").applyInArrow(work, schema)


def _by_labelled_ego(graph: Graph, plan: ExecutionPlan, policy: Policy, stats: GraphStats | None, emit: bool, engine: str, roots: DataFrame, schema: str) -> DataFrame:
    """Labelled lists are short, so some hundred roots (one, if rows are made) share a group and one copy of each list."""
    groups = -(-roots.count() // (1 if emit else ROOTS_A_GROUP)) or 1
    group = F.pmod(F.xxhash64("root"), F.lit(groups)).alias("group")
    reached, lists = _labelled_ego(graph, plan)

    def work(own: pa.Table, near: pa.Table) -> pa.Table:
        lists = dict(zip(near.column("u").to_pylist(), (x.values.to_numpy() for x in near.column("nbrs"))))
        ids, labels = (np.concatenate([np.zeros(0, np.int64), *(x.values.to_numpy() for x in near.column(c))]) for c in ("nbrs", "labels"))
        ids, first = np.unique(ids, return_index=True)
        labelled, none = Labels(ids, labels[first]), ids[:0]
        worker, out = _Worker(plan, policy, stats, emit, engine), []
        neighbours = NearNeighbours(lists, none)  # of a vertex without a list nothing can match
        batches = [worker.rows([])] if emit else []
        for root, part, parts in zip(*(own.column(c).to_pylist() for c in ("root", "part", "parts"))):
            batches += [worker.rows(rows) for rows in worker.one(neighbours, labelled, root, part, parts, out)]
        return pa.Table.from_batches(batches if emit else [worker.counters(out)])

    shipped = reached.select(group, "u").distinct().join(lists, "u")
    return roots.select(group, "*").groupBy("group").cogroup(shipped.groupBy("group")).applyInArrow(work, schema)
