"""SQL surface: views of a graph, functions, and a table function for small graphs."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from motifprune.operators.frontier import Run
from motifprune.operators.joins import brute_force
from motifprune.plans.execution import ExecutionPlan, explain
from motifprune.plans.pattern import CATALOGUE, Pattern
from motifprune.sources.graphs import Graph


def register(spark: SparkSession, graph: Graph) -> None:
    """Views graph_edges, graph_adj and graph_stats, function pattern_canonical_form, table function match_pattern."""
    graph.edges.createOrReplaceTempView("graph_edges")
    graph.adj.createOrReplaceTempView("graph_adj")
    graph.stats_frame().createOrReplaceTempView("graph_stats")
    spark.udf.register("pattern_canonical_form", pattern_canonical_form)
    spark.udtf.register("match_pattern", F.udtf(MatchPattern))


@F.pandas_udf(StringType())
def pattern_canonical_form(texts: pd.Series) -> pd.Series:
    return texts.map(lambda t: Pattern.parse(t).canonical_form())


class MatchPattern:
    """match_pattern(TABLE(edges), 'clique4' or '1-2,2-3', 'edge' or 'vertex'): one task, for small graphs only."""

    @staticmethod
    def analyze(edges: AnalyzeArgument, pattern: AnalyzeArgument, variant: AnalyzeArgument) -> AnalyzeResult:
        n = _pattern(pattern.value).n
        return AnalyzeResult(StructType([StructField(f"v{k + 1}", LongType()) for k in range(n)]), withSinglePartition=True)

    def __init__(self) -> None:
        self._edges: set[tuple[int, int]] = set()
        self._of: tuple[str, str] | None = None

    def eval(self, row, pattern: str, variant: str):  # noqa: ANN001
        self._edges.add((row[0], row[1]))
        self._of = (pattern, variant)

    def terminate(self):
        if self._of:
            yield from brute_force(self._edges, _pattern(self._of[0]), self._of[1])


def list_maps(run: Run, j: int) -> DataFrame:
    """(keys, lists): each partial match's pruned lists of the plan's j-th kind as one map from vertex to list."""
    keys = run._keys(run.plan.aux[j])
    return run.tables[j].groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("x", "keep"))).alias("lists"))


def write_matches(rows: DataFrame, path: str, parts: int = 16, by: str = "v1") -> None:
    """Matches in `parts` folders by a hash of one column, so that a reader of some vertices reads some folders (see read_matches)."""
    dealt = rows.withColumn("part", F.pmod(F.xxhash64(by), F.lit(parts)).cast("int"))
    dealt.repartition("part", by).write.mode("overwrite").partitionBy("part").parquet(path)


def read_matches(spark: SparkSession, path: str, vertices: list[int] | None = None, parts: int = 16, by: str = "v1") -> DataFrame:
    """What write_matches has written; with vertices, only the folders that can hold them are read."""
    rows = spark.read.parquet(path)
    if vertices is not None:
        held = spark.createDataFrame([(v,) for v in vertices], f"{by} long").select(F.pmod(F.xxhash64(by), F.lit(parts)).cast("int").alias("p")).distinct()
        rows = rows.where(F.col("part").isin(*(r["p"] for r in held.collect())) & F.col(by).isin(*vertices))
    return rows.drop("part")


def _pattern(text: str) -> Pattern:
    return CATALOGUE.get(text) or Pattern.parse(text)


def plan_json(plan: ExecutionPlan) -> str:
    s = plan.schedule
    return json.dumps(
        {
            "order": s.order,
            "checks": s.checks,
            "variant": plan.options.variant,
            "steps": [{"depth": x.depth, "target": x.target, "kind": x.kind, "deferred": x.deferred} for x in plan.steps],
            "aux": [{"h": x.h, "name": x.name, "consumers": x.consumers, "parent": x.parent} for x in plan.aux],
            "text": explain(plan),
        }
    )


def schedule_frame(spark: SparkSession, plan: ExecutionPlan) -> DataFrame:
    """A schedule as one row: (matching_order array<int>, checks array<struct<a, b>>)."""
    s = plan.schedule
    return spark.createDataFrame([(list(s.order), [(a, b) for a, b in s.checks])], "matching_order array<int>, checks array<struct<a: int, b: int>>")
