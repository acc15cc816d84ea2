"""Relational operators around matching: seeds, rankings, reports, sessions and as-of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifprune.operators.frontier import Run, make_plan, match
from motifprune.plans.pattern import Pattern
from motifprune.sources.graphs import Graph


def seeded_match(graph: Graph, p: Pattern, seeds: DataFrame, variant: str = "edge") -> DataFrame:
    """Matches whose first matched vertex is among seeds (u); other roots are never extended."""
    return match(graph, p, variant, "none", roots=seeds)


def root_counts(graph: Graph, p: Pattern, variant: str = "edge") -> DataFrame:
    """(root, cnt): matches by the vertex at the first position, from set sizes."""
    run = Run(graph, make_plan(p, variant))
    return run.last().groupBy(F.col("u1").alias("root")).agg(F.sum(F.size(run.candidates(p.n - 1))).cast("long").alias("cnt")).where("cnt > 0")


def topk_roots(graph: Graph, p: Pattern, k: int = 10) -> DataFrame:
    return root_counts(graph, p).orderBy(F.desc("cnt"), "root").limit(k)


def rank_in_degree_class(graph: Graph, p: Pattern, most: int = 3) -> DataFrame:
    """(degree_bucket, root, cnt, place): the roots with most matches of each degree class."""
    rows = root_counts(graph, p).join(graph.degrees.withColumnRenamed("u", "root"), "root")
    rows = rows.withColumn("degree_bucket", F.floor(F.log2(F.col("deg").cast("double"))).cast("int"))
    place = F.row_number().over(Window.partitionBy("degree_bucket").orderBy(F.desc("cnt"), "root"))
    return rows.withColumn("place", place).where(F.col("place") <= most).select("degree_bucket", "root", "cnt", "place")


def edge_report(graph: Graph, kind: str = "rollup") -> DataFrame:
    """(low, high, edges): edges by the degree classes of their ends, with totals (-1); kind: rollup or cube."""
    bucket = lambda c: F.floor(F.log2(F.col(c).cast("double"))).cast("int")
    d = graph.degrees
    rows = graph.edges.join(d.select(F.col("u").alias("src"), F.col("deg").alias("d1")), "src").join(d.select(F.col("u").alias("dst"), F.col("deg").alias("d2")), "dst")
    rows = rows.select(F.least(bucket("d1"), bucket("d2")).alias("low"), F.greatest(bucket("d1"), bucket("d2")).alias("high"))
    grouped = rows.rollup("low", "high") if kind == "rollup" else rows.cube("low", "high")
    return grouped.agg(F.count("*").alias("edges")).select(F.coalesce("low", F.lit(-1)).alias("low"), F.coalesce("high", F.lit(-1)).alias("high"), "edges")


def degree_deciles(graph: Graph, parts: int = 10) -> DataFrame:
    """(decile, vertices, least, most) of degrees: places of a range sort, so no task sees all vertices."""
    _, places = graph.relabel("degree")
    n = graph.degrees.count()
    each, more = n // parts, n % parts  # the first ones take one more
    place = F.col("new_id")
    cut = more * (each + 1)
    decile = F.when(place < cut, F.floor(place / (each + 1))).otherwise(more + F.floor((place - cut) / max(1, each))) + 1
    rows = places.select(F.col("v").alias("u"), decile.cast("int").alias("decile")).join(graph.degrees, "u")
    return rows.groupBy("decile").agg(F.count("*").alias("vertices"), F.min("deg").cast("long").alias("least"), F.max("deg").cast("long").alias("most"))


def sessions(events: DataFrame, gap_seconds: int = 1800) -> DataFrame:
    """(user_id, session_no, n_events): a user's events with no pause longer than the gap."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    new = F.when(micros - F.lag(micros).over(w) <= gap_seconds * 1_000_000, 0).otherwise(1)
    rows = events.withColumn("fresh", new).withColumn("session_no", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return rows.groupBy("user_id", "session_no").agg(F.count("*").alias("n_events"))


def last_before(events: DataFrame, of: str, before: str) -> DataFrame:
    """(event_id, earlier_id): for each event of type `before` its user's last event of type `of` before it, -1 if none.

    An as-of join as one sort: both kinds in one stream, the last seen carried on.
    """
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    both = events.where(F.col("event_type").isin(of, before))
    seen = F.last(F.when(F.col("event_type") == of, F.col("event_id")), ignorenulls=True).over(w)
    return both.withColumn("earlier_id", seen).where(F.col("event_type") == before).select("event_id", F.coalesce("earlier_id", F.lit(-1)).alias("earlier_id"))
