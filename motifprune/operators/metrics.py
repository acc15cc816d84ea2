"""Measures: comparisons, scan shares, list memory, balance, planning time, estimator quality."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifprune.operators import kernel
from motifprune.operators.counting import count_tail_factor
from motifprune.operators.frontier import Policy, Run, make_plan, match, runner
from motifprune.operators.joins import match_joins
from motifprune.plans.costmodel import CostModel, gain
from motifprune.plans.pattern import Pattern
from motifprune.plans.schedule import choose_schedule
from motifprune.sources.compressed import BLOCK_IDS, TwinCounter, WholeCounter
from motifprune.sources.graphs import Graph

READ = ("adjacency", "aux", "prefix")


def work_counters(graph: Graph, p: Pattern, variant: str = "edge", policy: str | Policy = "online", **options) -> DataFrame:
    """(degree_bucket, metric, value); the comparisons of a run are the sum of adjacency, aux and prefix."""
    return runner(graph, p, variant, policy, **options).counts()


def comparisons(counters: DataFrame) -> DataFrame:
    return counters.where(F.col("metric").isin(*READ)).agg(F.coalesce(F.sum("value"), F.lit(0)).alias("comparisons"))


def comparisons_by_degree(graph: Graph, p: Pattern, variant: str = "edge", policies: tuple[str, ...] = ("none", "eager", "online")) -> DataFrame:
    """(mode, degree_bucket, comparisons, running): by log2 of the original list's degree."""
    parts = [work_counters(graph, p, variant, name).where(F.col("metric").isin(*READ)).groupBy("degree_bucket").agg(F.sum("value").alias("comparisons")).withColumn("mode", F.lit(name)) for name in policies]
    rows = reduce(DataFrame.unionByName, parts)
    return rows.withColumn("running", F.sum("comparisons").over(Window.partitionBy("mode").orderBy("degree_bucket")))


def adjacency_scan_share(graph: Graph, p: Pattern, variant: str = "edge", policy: str = "none", **options) -> DataFrame:
    """One row share: percentage of scanned vertices that adjacency lists give."""
    got = work_counters(graph, p, variant, policy, **options).where(F.col("metric").isin(*READ))
    return got.agg(F.round(100 * F.sum(F.when(F.col("metric") == "adjacency", F.col("value")).otherwise(0)) / F.sum("value"), 6).alias("share"))


def timed(action) -> tuple[object, float]:
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began


def timed_within(spark: SparkSession, action, limit: float | None = None) -> tuple[object | None, float, bool]:
    """(result, seconds, whether the time limit was hit); the action's jobs are cancelled at the limit, and its result is then None."""
    if limit is None:
        return *timed(action), False
    sc, tag, over = spark.sparkContext, f"limited-{uuid.uuid4().hex}", threading.Event()

    def stop() -> None:
        over.set()
        sc.cancelJobsWithTag(tag)

    sc.addJobTag(tag)
    watch = threading.Timer(limit, stop)
    watch.start()
    began = time.perf_counter()
    try:
        out = action()
    except Exception:
        if not over.is_set():
            raise
        out = None
    finally:
        watch.cancel()
        sc.removeJobTag(tag)
    return out, time.perf_counter() - began, out is None and over.is_set()


def timed_match(graph: Graph, p: Pattern, variant: str = "edge", policy: str | Policy = "online", limit: float | None = None, **options) -> dict:
    """Count and seconds of one query; loading the graph and its statistics is not part of the time."""
    graph.adj.count(), graph.stats, graph.degree_classes  # noqa: B018
    row, seconds, over = timed_within(graph.spark, lambda: match(graph, p, variant, policy, "count", **options).first(), limit)
    return {"pattern": p.name, "variant": variant, "cnt": row[0] if row else None, "seconds": seconds, "over_limit": over}


MODES = (("base", "none", False), ("base+nested", "none", True), ("online", "online", False), ("online+nested", "online", True))


def ablation(graph: Graph, patterns: list[Pattern], variant: str = "vertex", reuse: bool = True, limit: float | None = None) -> DataFrame:
    """(pattern, variant, mode, cnt, comparisons, seconds, speedup, imbalance, over_limit) of base, base+nested, online and online+nested loops.

    speedup: over the base loops; imbalance: the busiest worker's time over the mean worker's.
    """
    rows = []
    graph.adj.count(), graph.stats  # noqa: B018
    for p in patterns:
        plan, base = make_plan(p, variant, reuse_aux=reuse), None
        for mode, policy, nested in MODES:
            r, seconds, over = timed_within(graph.spark, lambda: task_balance(graph, plan, policy, nested).first(), limit)
            base = seconds if mode == "base" and not over else base
            rows.append((p.name, variant, mode, r and r["cnt"], r and r["comparisons"], seconds, base / seconds if base and not over else None, r and r["imbalance"], over))
    return graph.spark.createDataFrame(rows, "pattern string, variant string, mode string, cnt long, comparisons long, seconds double, speedup double, imbalance double, over_limit boolean")


ENGINES = ("online+nested", "compiled", "interpreted", "tail_factor", "joins")


def compare_engines(graph: Graph, patterns: list[Pattern], variant: str = "edge", engines: tuple[str, ...] = ENGINES[:3], limit: float | None = None) -> DataFrame:
    """(pattern, variant, engine, cnt, seconds, speedup, over_limit): speedup is the engine's time over that of online+nested loops.

    compiled: generated loops without pruned lists; interpreted: the plan's steps at run time; tail_factor: the last
    non-adjacent vertices are only counted (edge-induced); joins: plain staged joins.
    """
    rows = []
    graph.adj.count(), graph.stats  # noqa: B018
    total = lambda df: df.agg(F.coalesce(F.sum("cnt"), F.lit(0))).first()[0]
    for p in patterns:
        plan, own = make_plan(p, variant), None
        runs = {
            "online+nested": lambda: total(kernel.match_kernel(graph, plan, "online", True)),
            "compiled": lambda: total(kernel.match_kernel(graph, plan, "none")),
            "interpreted": lambda: total(kernel.match_kernel(graph, plan, "none", engine="interpreted")),
            "tail_factor": lambda: total(count_tail_factor(graph, p)),
            "joins": lambda: total(match_joins(graph, p, variant)),
        }
        for engine in engines:
            cnt, seconds, over = timed_within(graph.spark, runs[engine], limit)
            own = seconds if engine == "online+nested" and not over else own
            rows.append((p.name, variant, engine, cnt, seconds, seconds / own if own and not over else None, over))
    return graph.spark.createDataFrame(rows, "pattern string, variant string, engine string, cnt long, seconds double, speedup double, over_limit boolean")


def task_balance(graph: Graph, plan, policy: str = "none", nested: bool = False, engine: str = "generated") -> DataFrame:
    """One row (cnt, comparisons, aux_bytes, busiest_ms, mean_ms, imbalance) of a kernel run: times summed up by worker."""
    got = kernel.match_kernel(graph, plan, policy, nested, engine=engine)
    workers = got.groupBy("pid").agg(
        F.sum("cnt").alias("cnt"),
        F.sum(F.col("adjacency") + F.col("aux") + F.col("prefix")).alias("comparisons"),
        F.max("aux_bytes").alias("aux_bytes"),
        F.sum("elapsed_ms").alias("ms"),
    )
    return workers.agg(
        F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"),
        F.coalesce(F.sum("comparisons"), F.lit(0)).alias("comparisons"),
        F.coalesce(F.max("aux_bytes"), F.lit(0)).alias("aux_bytes"),
        F.max("ms").alias("busiest_ms"),
        F.avg("ms").alias("mean_ms"),
        (F.max("ms") / F.avg("ms")).alias("imbalance"),
    )


def aux_memory(graph: Graph, patterns: list[Pattern], variants: tuple[str, ...] = ("edge", "vertex")) -> DataFrame:
    """(pattern, variant, most_bytes, mean_bytes, graph_bytes): most bytes of pruned lists that a worker holds at once, over its roots."""
    parts = []
    for p in patterns:
        for variant in variants:
            got = kernel.match_kernel(graph, make_plan(p, variant), "online").groupBy("pid").agg(F.max("aux_bytes").alias("aux_bytes"))
            parts.append(got.agg(F.max("aux_bytes").alias("most_bytes"), F.avg("aux_bytes").alias("mean_bytes")).select(F.lit(p.name).alias("pattern"), F.lit(variant).alias("variant"), "*"))
    size = graph.degrees.agg((F.sum("deg") * 8).alias("graph_bytes"))
    return reduce(DataFrame.unionByName, parts).join(F.broadcast(size))


def list_usage(graph: Graph, patterns: list[Pattern], variant: str = "vertex", policy: str = "online") -> DataFrame:
    """(pattern, variant, considered, built, used, unused): how many pruned lists could be, were made, and were read at least once."""
    parts = []
    for p in patterns:
        got = kernel.match_kernel(graph, make_plan(p, variant), policy).agg(*(F.coalesce(F.sum(f"lists_{x}"), F.lit(0)).alias(x) for x in ("considered", "built", "used")))
        parts.append(got.select(F.lit(p.name).alias("pattern"), F.lit(variant).alias("variant"), "*", (F.col("built") - F.col("used")).alias("unused")))
    return reduce(DataFrame.unionByName, parts)


def reuse_ablation(graph: Graph, patterns: list[Pattern], variant: str = "vertex") -> DataFrame:
    """(graph, pattern, reuse, cnt, comparisons, seconds, speedup) with lists built from adjacency only and from one another."""
    rows = []
    graph.adj.count(), graph.stats  # noqa: B018
    for p in patterns:
        off = None
        for on in (False, True):
            r, seconds = timed(lambda: task_balance(graph, make_plan(p, variant, reuse_aux=on), "online").first())
            off = off or seconds
            rows.append((graph.name, p.name, on, r["cnt"], r["comparisons"], seconds, off / seconds))
    return graph.spark.createDataFrame(rows, "graph string, pattern string, reuse boolean, cnt long, comparisons long, seconds double, speedup double")


def compile_time(graph: Graph, patterns: list[Pattern], runs: int = 3) -> DataFrame:
    """(pattern, engine, seconds): mean time to plan and compile."""
    rows = []
    for p in patterns:
        for name in ("generated", "interpreted", "frontier"):
            total = 0.0
            for _ in range(runs):
                began = time.perf_counter()
                plan = make_plan(p, "edge", choose_schedule(p))
                plan.steps, plan.aux  # noqa: B018
                if name == "generated":
                    compile(kernel.source_of(plan, Policy("online"), graph.stats, False), "<plan>", "exec")
                elif name == "frontier":
                    Run(graph, plan).count()
                total += time.perf_counter() - began
            rows.append((p.name, name, total / runs))
    return graph.spark.createDataFrame(rows, "pattern string, engine string, seconds double")


def policy_comparison(graph: Graph, patterns: list[Pattern], policies: tuple[str, ...] = ("none", "eager", "online", "degree", "random", "oracle"), variant: str = "edge", work: bool = True) -> DataFrame:
    """(pattern, policy, cnt, comparisons): the cost model against simple rules and the best decision; without work, counts only."""
    rows = []
    for p in patterns:
        for name in policies:
            scanned = None
            if work:
                run = runner(graph, p, variant, name)
                scanned = comparisons(run.counts()).first()[0]
                run.release()
            rows.append((p.name, name, match(graph, p, variant, name, "count").first()[0], scanned))
    return graph.spark.createDataFrame(rows, "pattern string, policy string, cnt long, comparisons long")


def list_truth(run: Run, j: int) -> DataFrame:
    """(keys, x, deg, keep_size, overlap, reads, gain) of each list of the plan's j-th pruned list, with true reads."""
    spec = run.plan.aux[j]
    keys = run._keys(spec)
    plain = Run(run.graph, run.plan, Policy("eager"), run.roots)
    rows = plain.considered(plain.frame(spec.h), spec)
    lists = rows.join(run.graph.adj.select(F.col("u").alias("x"), "nbrs"), "x").withColumn("overlap", F.size(F.array_intersect("keep_set", "nbrs")).cast("long"))
    reads = run.true_reuse(spec)
    out = lists.drop("reuse").join(reads, [*keys, "x"], "left").withColumn("reads", F.coalesce("reads", F.lit(0)))
    deg, size = F.col("deg").cast("long"), F.col("keep_size").cast("long")
    return out.select(*keys, "x", deg.alias("deg"), size.alias("keep_size"), "overlap", "reads", gain(F.col("reads"), deg, F.col("overlap"), size).alias("gain"))


def _crowded_lists(run: Run, j: int) -> DataFrame | None:
    """(deg, keep_size, overlap, reads) of each list of the plan's j-th pruned list in a crowded graph, or none if the plan has another form.

    Lists of a root's later neighbours that a clique of 4 keeps whole at loop 1 and reads at loop 3: tasks make the matrix of a
    root's later neighbours from broadcast lists; a list is read once for each earlier neighbour in it.
    """
    graph, plan, spec = run.graph, run.plan, run.plan.aux[j]
    later = ((1,), (), ((1, ">"),))
    if run.roots is not None or plan.n != 4 or len(plan.schedule.pattern.edges) != 6 or plan.schedule.pattern.labels is not None or (spec.h, spec.select[:3], spec.keep[:3], spec.consumers) != (1, later, later, ((3, 4),)) or not graph.crowded_whole:
        return None
    if graph.alike is not None:
        return _lists_by_class(graph)
    if "compressed" not in graph.__dict__:
        graph.__dict__["compressed"] = graph.spark.sparkContext.broadcast(kernel.compressed_rows(graph))
    lists, tasks = graph.__dict__["compressed"], 16 * graph.spark.sparkContext.defaultParallelism

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = WholeCounter(lists.value)
        for batch in batches:
            for first in batch.column("id").to_pylist():
                for v in range(first, len(lists.value.ids), tasks):
                    near = counter.near(v)
                    near = near[np.searchsorted(near, v, "right") :]
                    if len(near):
                        linked = counter.matrix(near)[:, : len(near)]
                        columns = counter.degrees[near], np.full(len(near), len(near)), linked.sum(axis=1), np.tril(linked).sum(axis=1)
                        yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], ["deg", "keep_size", "overlap", "reads"])

    return graph.spark.range(0, tasks, 1, tasks).mapInArrow(work, "deg long, keep_size long, overlap long, reads long")


def _lists_by_class(graph: Graph) -> DataFrame:
    """_crowded_lists from classes: lists of all vertices, by counts of each class's later members at the places of a class's closed neighbourhood."""
    classes, tasks = graph.twins, 16 * graph.spark.sparkContext.defaultParallelism

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = classes.value
        counter = TwinCounter(known)
        for batch in batches:
            for first in batch.column("id").to_pylist():
                for v in range(first, len(known.weights), tasks):
                    for columns in counter.later_lists(v):
                        yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["deg", "keep_size", "overlap", "reads"])

    return graph.spark.range(0, tasks, 1, tasks).mapInArrow(work, "deg long, keep_size long, overlap long, reads long")


def guessed_by_class(run: Run, j: int) -> DataFrame | None:
    """(us, xs, deg, keep_size, reuse, overlap, gain), estimates as Run.considered gives them, of the lists of xs for the first vertices us; none if there are no classes.

    Lists of all of a first vertex's neighbours. us and xs may be the same vertices, whose pairs with themselves aren't lists.
    """
    graph, plan, spec = run.graph, run.plan, run.plan.aux[j]
    every = ((1,), (), ())
    if graph.alike is None or run.roots is not None or plan.schedule.pattern.labels is not None or (spec.h, spec.select[:3], spec.keep[:3]) != (1, every, every):
        return None
    classes, tasks = graph.twins, 16 * graph.spark.sparkContext.defaultParallelism

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = classes.value
        counter = WholeCounter(known.lists)
        upto = np.concatenate([[0], np.cumsum(np.repeat(known.degrees, known.weights))])  # arcs of the members before each
        for batch in batches:
            for task in batch.column("id").to_pylist():  # members with about as many arcs as any other task's
                at, stop = np.searchsorted(upto, [int(upto[-1]) * k // tasks for k in (task, task + 1)]).tolist()
                while at < stop:
                    v = int(np.searchsorted(known.first, at, "right")) - 1
                    near = np.append(counter.near(v), v)
                    own = known.members[at : min(stop, int(known.first[v + 1]), at + max(1, BLOCK_IDS // len(near)))]
                    size = known.weights[near]
                    us = pa.ListArray.from_arrays(pa.array(np.arange(len(near) + 1, dtype=np.int32) * len(own)), pa.array(np.tile(own, len(near))))
                    xs = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.array(np.concatenate([known.own(k) for k in near.tolist()])))
                    yield pa.RecordBatch.from_arrays([us, xs, pa.array(known.degrees[near]), pa.array(np.full(len(near), known.degrees[v]))], ["us", "xs", "deg", "keep_size"])
                    at += len(own)

    rows = graph.spark.range(0, tasks, 1, tasks).mapInArrow(work, "us array<long>, xs array<long>, deg long, keep_size long")
    return _guessed(rows, run, spec, "reuse", "overlap", "gain")


def _guessed(rows: DataFrame, run: Run, spec, reuse: str, overlap: str, gained: str) -> DataFrame:
    """rows (deg, keep_size), whose select and keep sets are the same, with the model's estimates."""
    model, size, deg = CostModel(run.graph.stats, run.policy.order_discount), F.col("keep_size").cast("double"), F.col("deg").cast("double")
    return rows.withColumn(reuse, model.reuse(run.plan, spec, lambda key: size)).withColumn(overlap, model.overlap(size, deg)).withColumn(gained, gain(F.col(reuse), deg, F.col(overlap), size))


def audit_cost_model(graph: Graph, p: Pattern, variant: str = "edge", order_discount: bool = True) -> DataFrame:
    """(aux, degree_bucket, lists, reuse_ratio, overlap_ratio, false_builds, missed_builds): estimates against the truth."""
    run = runner(graph, p, variant, Policy("online", order_discount=order_discount))
    parts = []
    for j, spec in enumerate(run.plan.aux):
        keys, whole = run._keys(spec), _crowded_lists(run, j)
        if whole is not None:
            both = whole.withColumn("gain", gain(F.col("reads"), F.col("deg"), F.col("overlap"), F.col("keep_size")))
            parts.append(_audited(_guessed(both, run, spec, "reuse_guess", "overlap_guess", "gain_guess"), spec.name))
            continue
        guess = run.considered(Run(graph, run.plan).frame(spec.h), spec).select(*keys, "x", F.col("reuse").alias("reuse_guess"), F.col("overlap").alias("overlap_guess"), F.col("gain").alias("gain_guess"))
        both = list_truth(run, j).join(guess, [*keys, "x"])
        parts.append(_audited(both, spec.name))
    return reduce(DataFrame.unionByName, parts)


def _audited(both: DataFrame, name: str) -> DataFrame:
    bucket = F.floor(F.log2(F.greatest("deg", F.lit(1)).cast("double"))).cast("int").alias("degree_bucket")
    return both.groupBy(F.lit(name).alias("aux"), bucket).agg(
        F.count("*").alias("lists"),
        F.try_divide(F.sum("reuse_guess"), F.sum("reads")).alias("reuse_ratio"),
        F.try_divide(F.sum("overlap_guess"), F.sum("overlap")).alias("overlap_ratio"),
        F.sum(((F.col("gain_guess") > 0) & (F.col("gain") <= 0)).cast("long")).alias("false_builds"),
        F.sum(((F.col("gain_guess") <= 0) & (F.col("gain") > 0)).cast("long")).alias("missed_builds"),
    )


def cost_model_of(graph: Graph, order_discount: bool = True) -> CostModel:
    return CostModel(graph.stats, order_discount)
