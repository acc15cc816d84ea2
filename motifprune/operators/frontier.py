"""Breadth-first matching on DataFrames: one row for each partial match, prefix sets as array columns.

Depth h holds columns u1..uh and one array column for each different prefix set still needed. Extending
explodes the next position's set, joins the new vertex's adjacency list and combines. Pruned lists are
tables keyed on the matched positions they depend on and the vertex they belong to; a row that finds one
reads it, all other rows read adjacency. Which lists are made is the policy's decision, taken from sizes
and degrees before any list is joined.
"""

from __future__ import annotations

import weakref
from dataclasses import dataclass, field
from functools import cached_property, partial, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifprune.functions import sets
from motifprune.plans.costmodel import CostModel, gain, worth
from motifprune.plans.execution import CARRY, INIT, SUBTRACT, AuxSpec, ExecutionPlan, Options, SetKey
from motifprune.plans.pattern import CATALOGUE, Pattern
from motifprune.plans.schedule import Schedule, choose_schedule
from motifprune.sources.graphs import WHOLE_ARCS, WHOLE_COUNTS, Graph

SHIPPED_IDS = 50_000_000  # list members that one join of arcs and lists may ship: 400 MB; a depth of the frontier ships several times that
DECIDED_IDS = 50_000_000  # the same, for policies that decide on a list by its reads or by chance
POLICIES = ("none", "eager", "online", "oracle", "degree", "random")


@dataclass(frozen=True)
class Policy:
    """name: none, eager (always), online (predicted gain), oracle (true gain), degree (of at least degree_at), random (share).

    lazy_degree: lists of vertices of at least that degree are made only once a loop is about to read them.
    join_cost: what a row's look-up of a pruned list costs here, in comparisons; online drops a plan's lists as a
    whole where the expected gains don't cover it (counters of work are taken without that rule).
    """

    name: str = "online"
    degree_at: int = 16
    share: float = 0.5
    lazy_degree: int | None = None
    order_discount: bool = True
    join_cost: float = 24.0

    def __post_init__(self) -> None:
        if self.name not in POLICIES:
            raise ValueError(f"no policy {self.name}")


@dataclass
class Run:
    """One plan over one graph; its frames are built on demand."""

    graph: Graph
    plan: ExecutionPlan
    policy: Policy = field(default_factory=lambda: Policy("none"))
    roots: DataFrame | None = None
    profile: bool = False
    counters: list[DataFrame] = field(default_factory=list)
    tables: dict[int, DataFrame] = field(default_factory=dict)
    waiting: dict[int, DataFrame] = field(default_factory=dict)  # hubs' lists that nothing has read yet
    held: list[DataFrame] = field(default_factory=list)

    def hold(self, df: DataFrame) -> DataFrame:
        """df persisted until release."""
        self.held.append(df.persist())
        return df

    def release(self) -> None:
        """Frees all that this run has persisted; results still lazy are then computed anew."""
        while self.held:
            self.held.pop().unpersist()

    # ------------------------------------------------------------ names and small columns

    def column(self, key: SetKey) -> str:
        return "c_" + "_".join("".join(map(str, part)) if not part or not isinstance(part[0], tuple) else "".join(f"{a}{'gt' if op == '>' else 'lt'}" for a, op in part) for part in key[:3]) + (f"_{key[3]}" if len(key) > 3 else "")

    def size(self, key: SetKey) -> Column:
        return F.size(self.column(key)).cast("double")

    def _bounded(self, a: Column, key: SetKey, only: int | None = None) -> Column:
        for at, op in key[2]:
            if only is None or at == only:
                a = sets.set_bound(a, above=F.col(f"u{at}")) if op == ">" else sets.set_bound(a, below=F.col(f"u{at}"))
        return a

    def candidates(self, h: int) -> Column:
        """What position h+1 may match, given h matched."""
        s, i = self.plan.schedule, h + 1
        a = F.col(self.column(self.plan.key(h, i)))
        if not self.plan.options.bound_prefix:
            for j in range(1, h + 1):
                if (j, i) in s.checks:
                    a = sets.set_bound(a, above=F.col(f"u{j}"))
                elif (i, j) in s.checks:
                    a = sets.set_bound(a, below=F.col(f"u{j}"))
        distinct = [F.col(f"u{j}") for j in range(1, h + 1) if not s.linked(j, i) and (j, i) not in s.checks and (i, j) not in s.checks]
        return sets.set_exclude(a, *distinct)

    def label_of(self, position: int) -> int | None:
        p = self.plan.schedule.pattern
        return None if p.labels is None else p.labels[self.plan.schedule.order[position - 1]]

    def _labelled(self, df: DataFrame, position: int) -> DataFrame:
        want = self.label_of(position)
        if want is None:
            return df
        if self.graph.labels is None:
            raise ValueError("a labelled pattern needs a labelled graph")
        own = self.graph.labels.where(F.col("label") == want).select(F.col("v").alias(f"u{position}"))
        return df.join(own, f"u{position}", "left_semi")

    # ------------------------------------------------------------ depths

    def start(self) -> DataFrame:
        adj = self.graph.adj if self.roots is None else self.graph.adj.join(self.roots.select(F.col("u")).distinct(), "u", "left_semi")
        first = self._labelled(adj.select(F.col("u").alias("u1"), F.col("nbrs").alias("list"), F.col("deg").alias("list_deg")), 1)
        return self._advance(first, 1)

    def _advance(self, df: DataFrame, h: int) -> DataFrame:
        """Prefix sets of depth h, from those of depth h-1 and the list of the new vertex.

        df has u1..uh, the sets of depth h-1, and list, list_deg and (from depth 3 on) a column for each pruned list.
        """
        plan = self.plan
        alive = plan.alive(h)
        out: dict[str, Column] = {}
        deferred: dict[int, str] = {}
        for key, targets in alive.items():
            step = plan.step(h, targets[0])
            for j in step.deferred:
                if j not in deferred:
                    deferred[j] = f"far{j}"
                    df = df.join(self.graph.adj.select(F.col("u").alias(f"u{j}"), F.col("nbrs").alias(f"far{j}")), f"u{j}")
        costs: list[tuple[Column, Column, Column]] = []  # prefix, list, kind of list
        for key, targets in alive.items():
            step = plan.step(h, targets[0])
            before = plan.key(h - 1, targets[0])
            if step.kind == INIT:
                a = F.col("list")
                for j in step.deferred:
                    if self.profile:
                        costs.append((F.size(a), F.size(f"far{j}"), F.lit("adjacency")))
                    a = sets.set_subtract(a, F.col(f"far{j}"))
                out[self.column(key)] = self._bounded(a, key)
                continue
            was = F.col(self.column(before))
            if step.kind == CARRY:
                out[self.column(key)] = self._bounded(was, key, h)
                continue
            names = [f"aux_{j}" for j in self._versions(h, targets) if f"aux_{j}" in df.columns]
            source = F.coalesce(*map(F.col, names), F.col("list")) if names else F.col("list")
            made = reduce(lambda x, y: x | y, [F.col(c).isNotNull() for c in names]) if names else F.lit(False)
            if self.profile:
                costs.append((F.size(was), F.size(source), F.when(made, "aux").otherwise("adjacency")))
            combine = sets.set_subtract if step.kind == SUBTRACT else sets.set_intersect
            out[self.column(key)] = self._bounded(combine(was, source), key, h)
        if self.profile and costs:
            self._count(df, costs)
        return df.select(*(f"u{j}" for j in range(1, h + 1)), *(c.alias(k) for k, c in out.items()))

    def _versions(self, k: int, targets: list[int]) -> list[int]:
        """Pruned lists that serve loop k for a set shared by targets, deepest first."""
        found = {j for i in targets for j in self.plan.versions(k, i)}
        return sorted(found, key=lambda j: -self.plan.aux[j].h)

    def _count(self, df: DataFrame, costs: list[tuple[Column, Column, Column]]) -> None:
        bucket = F.floor(F.log2(F.greatest("list_deg", F.lit(1)).cast("double"))).cast("int").alias("degree_bucket")
        each = F.array(*(F.struct(p.cast("long").alias("prefix"), q.cast("long").alias("list"), kind.alias("kind")) for p, q, kind in costs))
        rows = df.select(bucket, F.explode(each).alias("x"))
        self.counters.append(rows.groupBy("degree_bucket", F.col("x.kind").alias("metric")).agg(F.sum("x.list").alias("value")))
        self.counters.append(rows.groupBy("degree_bucket", F.lit("prefix").alias("metric")).agg(F.sum("x.prefix").alias("value")))

    def frame(self, depth: int) -> DataFrame:
        """The frontier at a depth from 1 to n-1."""
        df = self.start()
        for h in range(1, depth):
            df = self.extend(self._build(df, h), h)
        return df

    def extend(self, df: DataFrame, h: int) -> DataFrame:
        k = h + 1
        kept = [c for c in df.columns if c.startswith("c_")]
        alive_next = self.plan.alive(k)
        used = {self.column(self.plan.key(h, ts[0])) for ts in alive_next.values() if self.plan.key(h, ts[0])}
        df = df.select(*(f"u{j}" for j in range(1, k)), *(c for c in kept if c in used), F.explode(self.candidates(h)).alias(f"u{k}"))
        df = self._labelled(df, k)
        names = []
        readable = sorted({j for ts in alive_next.values() for j in self._versions(k, ts)})
        if any(j in self.waiting for j in readable):
            df = self.hold(df)
            for j in readable:
                self._reach(df, j, k)
        for j in readable:
            if j not in self.tables:
                continue
            spec = self.plan.aux[j]
            keys = self._keys(spec)
            own = self.tables[j].select(*keys, F.col("x").alias(f"u{k}"), F.col("keep").alias(f"aux_{j}"))
            df = df.join(own, [*keys, f"u{k}"], "left")
            names.append(f"aux_{j}")
        if not self.plan.reads_list(k):
            df = df.withColumn("list", F.array().cast("array<bigint>")).withColumn("list_deg", F.lit(0))
            return self._advance(df, k)
        needs_list = F.lit(True)
        steps = [x for x in self.plan.steps if x.depth == k and x.kind != CARRY]
        if names and all(any(f"aux_{j}" in names for j in self._versions(k, [x.target])) for x in steps):
            # rows that found every list they read do not ship the whole one; null keys would meet in one task, so they keep their vertex
            found = [reduce(lambda a, b: a | b, [F.col(f"aux_{j}").isNotNull() for j in self._versions(k, [x.target]) if f"aux_{j}" in names]) for x in steps]
            needs_list = ~reduce(lambda a, b: a & b, found)
        if self.profile or needs_list is None or not names:
            df = df.join(self.graph.adj.select(F.col("u").alias(f"u{k}"), F.col("nbrs").alias("list"), F.col("deg").alias("list_deg")), f"u{k}")
        else:
            adj = self.graph.adj.select(F.col("u").alias("list_of"), F.col("nbrs").alias("list"), F.col("deg").alias("list_deg"))
            df = df.join(adj, (F.col(f"u{k}") == F.col("list_of")) & needs_list, "left").drop("list_of")
        return self._advance(df, k)

    # ------------------------------------------------------------ pruned lists

    def _keys(self, spec: AuxSpec) -> list[str]:
        return [f"u{p}" for p in sorted(self.plan.positions(spec.select) | self.plan.positions(spec.keep))]

    def _build(self, df: DataFrame, h: int) -> DataFrame:
        """Makes the pruned lists of depth h from its frontier, which is kept for its two uses."""
        if self.policy.name == "none":
            return df
        specs = [(j, x) for j, x in enumerate(self.plan.aux) if x.h == h and (self.profile or j in self.worthwhile)]
        if not specs:
            return df
        df = self.hold(df)
        for j, spec in specs:
            self.tables[j] = self.build_aux(df, j, spec)
        return df

    @cached_property
    def worthwhile(self) -> set[int]:
        """The pruned lists whose expected gains cover their look-ups, by the graph's degrees alone (all, if the policy isn't online)."""
        every = set(range(len(self.plan.aux)))
        if self.policy.name != "online" or not every:
            return every
        model = CostModel(self.graph.stats, self.policy.order_discount)
        return {j for j in every if worth(self.plan, self.plan.aux[j], model, self.graph.degree_classes, self.policy.join_cost)}

    def _reach(self, df: DataFrame, j: int, k: int) -> None:
        """Makes those waiting lists of the plan's j-th pruned list that the rows of loop k read; later loops find them made."""
        if j not in self.waiting:
            return
        spec = self.plan.aux[j]
        keys = self._keys(spec)
        read = df.select(*keys, F.col(f"u{k}").alias("x")).distinct()
        found = self.hold(self._lists(self.waiting[j].join(read, [*keys, "x"], "left_semi"), spec))
        self.tables[j] = self.tables[j].unionByName(found.select(*keys, "x", "keep"))
        self.waiting[j] = self.waiting[j].join(read, [*keys, "x"], "left_anti")

    def considered(self, df: DataFrame, spec: AuxSpec) -> DataFrame:
        """(keys, x, deg, keep_size, estimated reuse, overlap and gain, keep set) of each list that could be made."""
        keys = self._keys(spec)
        model = CostModel(self.graph.stats, self.policy.order_discount) if self.policy.name == "online" else None
        reuse = model.reuse(self.plan, spec, self.size).alias("reuse") if model else F.lit(None).cast("double").alias("reuse")
        # keep_size is taken here: whoever doesn't ask for keep_set then ships none with each x
        rows = df.dropDuplicates(keys).select(*keys, F.col(self.column(spec.keep)).alias("keep_set"), self.size(spec.keep).alias("keep_size"), reuse, F.explode(self.column(spec.select)).alias("x"))
        rows = rows.join(self.graph.degrees.select(F.col("u").alias("x"), "deg"), "x")
        if not model:
            return rows
        deg = F.col("deg").cast("double")
        rows = rows.withColumn("overlap", model.overlap(F.col("keep_size"), deg))
        return rows.withColumn("gain", gain(F.col("reuse"), deg, F.col("overlap"), F.col("keep_size")))

    def true_reuse(self, spec: AuxSpec) -> DataFrame:
        """How often each list is read in a run without pruned lists: (keys, x, reads)."""
        keys = self._keys(spec)
        plain = Run(self.graph, self.plan, Policy("none"), self.roots)
        reads = [plain.frame(k).groupBy(*keys, F.col(f"u{k}").alias("x")).agg(F.count("*").alias("reads")) for k in (self._reading_loops(spec))]
        return reduce(DataFrame.unionByName, reads).groupBy(*keys, "x").agg(F.sum("reads").alias("reads"))

    def _reading_loops(self, spec: AuxSpec) -> list[int]:
        """The loops that read a list, once for each different set they combine it into."""
        out = []
        for k in sorted({k for k, _ in spec.consumers}):
            targets = [i for kk, i in spec.consumers if kk == k]
            out += [k] * len({self.plan.key(k, i) for i in targets})
        return out

    def build_aux(self, df: DataFrame, j: int, spec: AuxSpec) -> DataFrame:
        """(keys, x, keep) of the lists that the policy makes."""
        keys, p = self._keys(spec), self.policy
        rows = self.considered(df, spec)
        if p.name == "online":
            rows = rows.where("gain > 0")
        elif p.name == "degree":
            rows = rows.where(F.col("deg") >= p.degree_at)
        elif p.name == "random":
            rows = rows.where(F.pmod(F.xxhash64("x", *keys), F.lit(1000)) < int(1000 * p.share))
        if p.lazy_degree is not None:
            self.waiting[j] = rows.where(F.col("deg") >= p.lazy_degree)
            rows = rows.where(F.col("deg") < p.lazy_degree)
        lists = self._lists(rows, spec)
        if p.name == "oracle":
            reads = self.true_reuse(spec)
            worth = gain(F.col("reads").cast("double"), F.col("deg").cast("double"), F.size("keep").cast("double"), F.col("keep_size"))
            lists = lists.join(reads, [*keys, "x"]).where(worth > 0)
        if self.profile:
            lists = self.hold(lists)
            bucket = F.floor(F.log2(F.greatest("deg", F.lit(1)).cast("double"))).cast("int").alias("degree_bucket")
            kind = F.when(F.col("shorter").isNull(), "adjacency").otherwise("aux").alias("metric")
            count = lambda metric, value: lists.groupBy(bucket, metric).agg(F.sum(value).cast("long").alias("value"))
            self.counters += [count(kind, F.size("from")), count(F.lit("prefix").alias("metric"), F.col("keep_size")), count(F.lit("lists_built").alias("metric"), F.lit(1)), count(F.lit("aux_bytes").alias("metric"), 8 * F.size("keep"))]
            self.counters.append(self.considered(df, spec).groupBy(bucket, F.lit("lists_considered").alias("metric")).agg(F.count("*").alias("value")))
        return self.hold(lists.select(*keys, "x", "keep"))

    def _lists(self, rows: DataFrame, spec: AuxSpec) -> DataFrame:
        """considered rows with `from`, the list each is cut from, and `keep`, what is left of it."""
        if spec.parent is not None and spec.parent in self.tables:
            own = self._keys(self.plan.aux[spec.parent])
            rows = rows.join(self.tables[spec.parent].select(*own, "x", F.col("keep").alias("shorter")), [*own, "x"], "left")
        else:
            rows = rows.withColumn("shorter", F.lit(None).cast("array<bigint>"))
        source = self.graph.adj.select(F.col("u").alias("list_of"), "nbrs")
        lists = rows.join(source, (F.col("x") == F.col("list_of")) & F.col("shorter").isNull(), "left").drop("list_of")
        lists = lists.withColumn("from", F.coalesce("shorter", "nbrs"))
        return lists.withColumn("keep", sets.set_intersect(F.col("keep_set"), F.col("from")))

    # ------------------------------------------------------------ results

    def last(self) -> DataFrame:
        df = self.start()
        for h in range(1, self.plan.n - 1):
            df = self.extend(self._build(df, h), h)
        return df

    def rows(self, limit: int | None = None) -> DataFrame:
        """Matches v1..vn in the pattern's own numbering."""
        n, order = self.plan.n, self.plan.schedule.order
        df = self.last()
        df = df.select(*(f"u{j}" for j in range(1, n)), F.explode(self.candidates(n - 1)).alias(f"u{n}"))
        df = self._labelled(df, n)
        df = df.select(*(F.col(f"u{order.index(v) + 1}").alias(f"v{v + 1}") for v in range(n)))
        return df.limit(limit) if limit is not None else df

    def count(self) -> DataFrame:
        """One row cnt; the last loop only adds up sizes."""
        if self.label_of(self.plan.n) is not None:
            return self.rows().agg(F.count("*").alias("cnt"))
        return self.last().agg(F.coalesce(F.sum(F.size(self.candidates(self.plan.n - 1))), F.lit(0)).cast("long").alias("cnt"))

    def counts(self) -> DataFrame:
        """Counters of a profiled run: (degree_bucket, metric, value). What they share stays persisted until release."""
        self.profile = True
        self.counters, self.tables, self.waiting = [], {}, {}
        self.last()
        if not self.counters:
            return self.graph.spark.createDataFrame([], "degree_bucket int, metric string, value long")
        return reduce(DataFrame.unionByName, self.counters).groupBy("degree_bucket", "metric").agg(F.sum("value").alias("value"))


def make_plan(pattern: Pattern, variant: str = "edge", schedule: Schedule | None = None, **options) -> ExecutionPlan:
    return ExecutionPlan(schedule or choose_schedule(pattern), Options(variant, **options))


def runner(graph: Graph, pattern: Pattern, variant: str = "edge", policy: str | Policy = "online", roots: DataFrame | None = None, schedule: Schedule | None = None, **options) -> Run:
    policy = Policy(policy) if isinstance(policy, str) else policy
    return Run(graph, make_plan(pattern, variant, schedule, **options), policy, roots)


def _counted_whole(pattern: Pattern) -> str | None:
    """The name under which a crowded graph counts the pattern from its whole lists."""
    return next((name for name in WHOLE_COUNTS if (p := CATALOGUE[name]).n == pattern.n and len(p.edges) == len(pattern.edges) and p.canonical_form() == pattern.canonical_form()), None)


def match(graph: Graph, pattern: Pattern, variant: str = "edge", policy: str | Policy = "online", output: str = "rows", limit: int | None = None, **options) -> DataFrame:
    """Subgraphs of the graph isomorphic to the pattern, each once: rows v1..vn, or one row cnt.

    Under the online policy cliques of 3 or 4 in a crowded graph, and edge-induced 5-cliques less an edge, houses and wheels, are counted
    from broadcast lists: the frontier would ship a list for each triangle. So are vertex-induced houses, and 5-cliques less an edge under
    the random policy, with the lists that it chooses. Counts under the policies beside online
    are the kernel's, with the same plan and pruned lists, where a join of arcs and lists ships over SHIPPED_IDS (or DECIDED_IDS) members.
    """
    if pattern.n == 2:
        own = graph.edges.select(F.col("src").alias("v1"), F.col("dst").alias("v2"))
        if pattern.labels is not None:
            if graph.labels is None:
                raise ValueError("a labelled pattern needs a labelled graph")
            if pattern.labels[0] != pattern.labels[1]:
                own = graph.arcs.select(F.col("u").alias("v1"), F.col("w").alias("v2"))
            for c, want in zip(("v1", "v2"), pattern.labels):
                own = own.join(graph.labels.where(F.col("label") == want).select(F.col("v").alias(c)), c, "left_semi")
            own = own.select("v1", "v2")
        return own.agg(F.count("*").alias("cnt")) if output == "count" else own
    by_rule = policy in ("online", Policy()) and not options
    if output == "count" and by_rule and pattern.labels is None and pattern.n in (3, 4) and len(pattern.edges) == pattern.n * (pattern.n - 1) // 2 and graph.counts_cliques:
        return graph.clique_count(pattern.n)
    if output == "count" and by_rule and variant == "edge" and pattern.labels is None and (name := _counted_whole(pattern)) and graph.crowded_whole:
        return graph.whole_count(name)
    if output == "count" and by_rule and variant == "vertex" and pattern.labels is None and _counted_whole(pattern) == "house5" and graph.crowded_whole:
        return graph.twin_count("house5")
    name = policy if isinstance(policy, str) else policy.name if policy == Policy(policy.name) else None
    if output == "count" and name == "random" and not options and variant == "edge" and pattern.labels is None and _counted_whole(pattern) == "near_clique5" and graph.crowded_whole:
        from motifprune.operators.kernel import chosen_ids

        return graph.twin_count("near_clique5", partial(chosen_ids, share=Policy(name).share))
    most = SHIPPED_IDS if name in ("none", "eager", "degree") else DECIDED_IDS if name in ("random", "oracle") else None
    if output == "count" and most is not None and pattern.labels is None and graph.shipped > most and graph.arcs_number <= WHOLE_ARCS:
        from motifprune.operators.kernel import match_kernel  # which imports this module

        return match_kernel(graph, make_plan(pattern, variant, **options), name).agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))
    run = runner(graph, pattern, variant, policy, **options)
    out = run.count() if output == "count" else run.rows(limit)
    # What the run persists goes once nobody holds the result; frames derived from it stay right and compute anew.
    weakref.finalize(out, run.release).atexit = False
    return out


def match_batches(graph: Graph, pattern: Pattern, path: str, batches: int, variant: str = "edge", policy: str | Policy = "online", **options) -> DataFrame:
    """Rows written to path by batches of roots, so that only one batch's frontier and pruned lists exist at once.

    Batches hold roots of about equal expected work: the squared degree, dealt by a hash.
    """
    spark = graph.spark
    for b in range(batches):
        roots = graph.degrees.where(F.pmod(F.xxhash64("u"), F.lit(batches)) == b)
        run = runner(graph, pattern, variant, policy, roots=roots, **options)
        run.rows().write.mode("overwrite" if b == 0 else "append").parquet(path)
        run.release()
    return spark.read.parquet(path)


def match_without_prefix_sets(graph: Graph, pattern: Pattern, variant: str = "edge") -> DataFrame:
    """Count with every candidate set computed anew from whole lists (a baseline); by the kernel's loops where rows with their lists would ship too many members."""
    plan = make_plan(pattern, variant, bound_prefix=False)
    if pattern.labels is None and graph.shipped > SHIPPED_IDS and graph.arcs_number <= WHOLE_ARCS:
        from motifprune.operators.kernel import match_kernel  # which imports this module

        return match_kernel(graph, plan, "none", engine="scratch").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))
    s, run = plan.schedule, Run(graph, plan)
    lists = lambda j: graph.adj.select(F.col("u").alias(f"u{j}"), F.col("nbrs").alias(f"n{j}"))
    df = run._labelled(lists(1), 1)
    for h in range(1, plan.n):
        i = h + 1
        near = [F.col(f"n{j}") for j in range(1, h + 1) if s.linked(j, i)]
        far = [F.col(f"n{j}") for j in range(1, h + 1) if not s.linked(j, i)] if variant == "vertex" else []
        key = plan.key(h, i)
        df = df.withColumn(run.column(key), sets.candidates_scratch(near, far))
        got = run.candidates(h)
        if i == plan.n and run.label_of(i) is None:
            return df.agg(F.coalesce(F.sum(F.size(got)), F.lit(0)).cast("long").alias("cnt"))
        df = run._labelled(df.select(*(c for j in range(1, i) for c in (f"u{j}", f"n{j}")), F.explode(got).alias(f"u{i}")), i)
        if i < plan.n:
            df = df.join(lists(i), f"u{i}")
    return df.agg(F.count("*").alias("cnt"))
