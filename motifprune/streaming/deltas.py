"""Matching over a growing graph: matches that new edges complete, and their running count.

A match is new if it uses at least one new edge. With the pattern's edges in a fixed order, the first new one
is pinned: edges before it are old, edges after it any. So each new match is found once (edge-induced,
edges only added).
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from motifprune.plans.pattern import Pattern
from motifprune.plans.schedule import choose_schedule
from motifprune.sources.graphs import checkpoint_folder, cut_lineage, symmetrise

EDGE_SCHEMA = "src long, dst long, ts timestamp"


def delta_matches(old: DataFrame, new: DataFrame, p: Pattern) -> DataFrame:
    """Matches v1..vn that use at least one edge of new (src, dst), none of which is in old."""
    if p.labels is not None:
        raise ValueError("matches of labelled patterns are not followed over streams")
    s = choose_schedule(p)
    edges = sorted(tuple(sorted(e)) for e in p.edges)
    arcs = {"old": symmetrise(old), "new": symmetrise(new)}
    arcs["all"] = arcs["old"].unionByName(arcs["new"])
    parts = []
    for j, pinned in enumerate(edges):
        kind = {e: "old" if k < j else "new" if k == j else "all" for k, e in enumerate(edges)}
        df, bound, left = arcs["new"].select(F.col("u").alias(f"v{pinned[0] + 1}"), F.col("w").alias(f"v{pinned[1] + 1}")), set(pinned), [e for e in edges if e != pinned]
        while left:
            e = max(left, key=lambda e: len(bound & set(e)))  # closing edges first, then connected ones
            left.remove(e)
            names = [f"v{v + 1}" for v in e]
            df = df.join(arcs[kind[e]].select(F.col("u").alias(names[0]), F.col("w").alias(names[1])), [c for v, c in zip(e, names) if v in bound])
            bound |= set(e)
        at = {k + 1: f"v{v + 1}" for k, v in enumerate(s.order)}
        for a, b in s.checks:
            df = df.where(F.col(at[a]) < F.col(at[b]))
        for a in range(p.n):
            for b in range(a):
                if not p.adjacent(a, b):
                    df = df.where(F.col(f"v{a + 1}") != F.col(f"v{b + 1}"))
        parts.append(df.select(*(f"v{k + 1}" for k in range(p.n))))
    return reduce(DataFrame.unionByName, parts)


def edge_stream(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    """Edges (src, dst, ts) as files arrive under path; late repeats of an edge are dropped within the watermark."""
    got = spark.readStream.schema(EDGE_SCHEMA).option("maxFilesPerTrigger", files_a_batch).parquet(path)
    return got.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["src", "dst"])


def running_matches(spark: SparkSession, path: str, p: Pattern, checkpoint: str | None = None) -> list[tuple[int, int]]:
    """[(batch, new matches)] of the edges under path, one micro-batch a file."""
    state = {"old": spark.createDataFrame([], "src long, dst long")}
    found: list[tuple[int, int]] = []

    def step(batch: DataFrame, number: int) -> None:
        batch = batch.persist()  # a stateful batch must run once only, and a checkpoint runs its plan twice
        new = cut_lineage(batch.select("src", "dst").distinct().join(state["old"], ["src", "dst"], "left_anti"))
        found.append((number, delta_matches(state["old"], new, p).count()))
        state["old"] = cut_lineage(state["old"].unionByName(new))
        batch.unpersist()

    query = edge_stream(spark, path).writeStream.foreachBatch(step).trigger(availableNow=True)
    query = query.option("checkpointLocation", checkpoint or f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}").start()
    query.awaitTermination()
    return found


def windowed_activity(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(window_start, event_type, n_events, n_users) by tumbling or sliding windows; works on streams and tables."""
    spans = F.window("ts", width, slide) if slide else F.window("ts", width)
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if rows.isStreaming:
        rows = rows.withWatermark("ts", "2 hours")
    return rows.groupBy(spans.alias("w"), "event_type").agg(F.count("*").alias("n_events"), F.approx_count_distinct("user_id").alias("n_users")).select(F.col("w.start").alias("window_start"), "event_type", "n_events", "n_users")


def session_activity(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, session_start, n_events): each user's events with no longer pause than the gap; works on streams and tables."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if rows.isStreaming:
        rows = rows.withWatermark("ts", "2 hours")
    got = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_events"))
    return got.select("user_id", F.col("w.start").alias("session_start"), "n_events")


COUNT_STATE = "degree long"


def running_degrees(edges: DataFrame) -> DataFrame:
    """(u, degree) each time that a vertex's degree in the stream of edges (src, dst) grows: counts kept as state by vertex."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + sum(len(rows) for rows in batches)
        state.update((total,))
        yield pd.DataFrame({"u": [key[0]], "degree": [total]})

    ends = edges.select(F.explode(F.array("src", "dst")).alias("u"))
    return ends.groupBy("u").applyInPandasWithState(update, "u long, degree long", COUNT_STATE, "update", GroupStateTimeout.NoTimeout)


def running_degree_table(spark: SparkSession, path: str, checkpoint: str | None = None) -> DataFrame:
    """(u, degree) after all edge files under path, arrived one a batch."""
    seen: list[DataFrame] = []

    def step(batch: DataFrame, number: int) -> None:
        seen.append(cut_lineage(batch.withColumn("batch", F.lit(number))))

    query = running_degrees(edge_stream(spark, path)).writeStream.outputMode("update").foreachBatch(step).trigger(availableNow=True)
    query.option("checkpointLocation", checkpoint or f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}").start().awaitTermination()
    rows = reduce(DataFrame.unionByName, seen)
    return rows.groupBy("u").agg(F.max_by("degree", "batch").alias("degree"))
