"""Data graphs: edge tables, sorted adjacency, statistics, and graphs derived from the given tables.

Edges are (src, dst) with src < dst, distinct and without loops. Adjacency is (u, deg, nbrs) with nbrs
ascending. A derived graph is one SQL rule in two dialects, so an oracle can build the same graph.
"""

from __future__ import annotations

import re
import tempfile
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.plans.costmodel import GraphStats
from motifprune.sources.classes import Alike, ClassCounter, Classes, alike, same_rows, twin_classes
from motifprune.sources.compressed import CliqueCounter, Lists, TwinCounter, Twins, WholeCounter, later_lists, twins

# ---------------------------------------------------------------- building blocks


def from_edges(pairs: DataFrame, src: str = "a", dst: str = "b") -> DataFrame:
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    return pairs.where(a != b).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).distinct()


def symmetrise(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("w")), F.struct(F.col("dst").alias("u"), F.col("src").alias("w")))).alias("e")).select("e.*")


def adjacency(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy("u").agg(F.count("*").cast("int").alias("deg"), F.sort_array(F.collect_list("w")).alias("nbrs"))


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """A public text format: two vertex ids a line, comment lines skipped."""
    lines = spark.read.text(path).where(~F.trim("value").startswith(comment) & (F.trim("value") != ""))
    part = F.split(F.trim("value"), sep)
    return from_edges(lines.select(part[0].cast("long").alias("a"), part[1].cast("long").alias("b")))


def triangle_count(edges: DataFrame, degrees: DataFrame | None = None) -> DataFrame:
    """One row n_triangles: edges run from lower to higher degree, so no vertex starts many two-paths."""
    degree = symmetrise(edges).groupBy("u").agg(F.count("*").alias("d")) if degrees is None else degrees.select("u", F.col("deg").alias("d"))
    low = degree.select(F.col("u").alias("src"), F.col("d").alias("ds"))
    high = degree.select(F.col("u").alias("dst"), F.col("d").alias("dd"))
    up = edges.join(low, "src").join(high, "dst")
    forward = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    arcs = up.select(F.when(forward, F.col("src")).otherwise(F.col("dst")).alias("x"), F.when(forward, F.col("dst")).otherwise(F.col("src")).alias("y"))
    two = arcs.join(arcs.select("x", F.col("y").alias("z")), "x").where("y < z")
    return two.join(edges.select(F.col("src").alias("y"), F.col("dst").alias("z")), ["y", "z"], "left_semi").agg(F.count("*").alias("n_triangles"))


# ---------------------------------------------------------------- rules

_PARTS = "SELECT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_partkey < y.l_partkey"
_COMMERCE = """
SELECT 1000000 + c_custkey AS a, 4000000 + c_nationkey AS b FROM customer
UNION ALL SELECT 2000000 + s_suppkey, 4000000 + s_nationkey FROM supplier
UNION ALL SELECT 3000000 + l_partkey, 2000000 + l_suppkey FROM lineitem WHERE l_quantity >= 45
UNION ALL SELECT 1000000 + o_custkey, 3000000 + l_partkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= 45
UNION ALL SELECT 1000000 + o_custkey, 2000000 + l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= 45"""


def _holders(items: str, most: int) -> str:
    """Pairs of holders of an item that 2 to `most` holders have; items: SQL of (holder, item), distinct."""
    return f"""
WITH held AS ({items}), meeting AS (SELECT item FROM held GROUP BY item HAVING count(*) BETWEEN 2 AND {most}),
kept AS (SELECT holder, item FROM held WHERE item IN (SELECT item FROM meeting))
SELECT x.holder AS a, y.holder AS b FROM kept x JOIN kept y ON x.item = y.item WHERE x.holder < y.holder"""


HOLDERS_A_BLOCK = 64


def _all_holders(items: str, dialect: str) -> str:
    """Pairs of holders of an item, however many hold it; items: SQL of (holder, item), distinct.

    For Spark the holders of an item are dealt into blocks, and each pair of blocks meets under a key of its own,
    so no key has more than about HOLDERS_A_BLOCK squared pairs. Each pair of holders meets once an item.
    """
    if dialect == "duckdb":
        return f"""
WITH held AS ({items}) SELECT x.holder AS a, y.holder AS b FROM held x JOIN held y ON x.item = y.item WHERE x.holder < y.holder"""
    return f"""
WITH held AS ({items}), meeting AS (SELECT item AS met, CAST(ceil(count(*) / {HOLDERS_A_BLOCK}) AS INT) AS n FROM held GROUP BY item HAVING count(*) > 1),
dealt AS (SELECT holder, item, n, CAST(pmod(xxhash64(holder), n) AS INT) AS own FROM held JOIN meeting ON item = met),
spread AS (SELECT holder, item, own, explode(sequence(0, n - 1)) AS other FROM dealt)
SELECT x.holder AS a, y.holder AS b FROM spread x JOIN spread y ON x.item = y.item AND x.own = y.other AND x.other = y.own WHERE x.holder < y.holder"""


def _items(name: str, dialect: str) -> str:
    """SQL of (holder, item), distinct: lines of documents, or hrefs of pages."""
    if name.startswith("lines"):
        cut = "unnest(string_split(text, chr(10)))" if dialect == "duckdb" else r"explode(split(text, '\n'))"
        return f"SELECT DISTINCT holder, item FROM (SELECT doc_id AS holder, {cut} AS item FROM documents) WHERE length(item) >= 20"
    cut = "unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1))" if dialect == "duckdb" else "explode(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1))"
    return f"SELECT DISTINCT page_id AS holder, {cut} AS item FROM pages"


def groups_sql(name: str) -> str:
    """Spark SQL of (holders), a row for each item that several hold: the pairs of lines_all and colink_all are all pairs of a row's holders."""
    return f"SELECT collect_list(CAST(holder AS BIGINT)) AS holders FROM ({_items(name, 'spark')}) WHERE holder IS NOT NULL AND item IS NOT NULL GROUP BY item HAVING count(*) > 1"


def graph_rule(name: str, dialect: str = "spark", window: int = 300, cap: int = 20, cosine: float = 0.3, filters: str = "") -> str:
    """SQL of the pairs (a, b) of a derived graph; dialect is spark or duckdb."""
    duck = dialect == "duckdb"
    if name == "basket":
        return _PARTS
    if name == "basket_r":
        return f"{_PARTS} AND x.l_returnflag = 'R' AND y.l_returnflag = 'R'"
    if name == "basket_r25":
        return f"{_PARTS} AND x.l_returnflag = 'R' AND y.l_returnflag = 'R' AND x.l_quantity >= 25 AND y.l_quantity >= 25"
    if name == "commerce":
        return _COMMERCE
    if name in ("coact", "coact_json"):
        where = f"WHERE {filters}" if filters else ""
        stamp = "ts" if duck else "CAST(ts AS TIMESTAMP)"
        src = f"(SELECT user_id, event_type, {stamp} AS ts FROM events {where})"
        if name == "coact_json":
            k = "CAST(json_extract_string(props, '$.k') AS BIGINT)" if duck else "CAST(get_json_object(props, '$.k') AS BIGINT)"
            src = f"(SELECT user_id, event_type, {stamp} AS ts FROM events WHERE {k} % 2 = 0)"
        if duck:
            return f"SELECT x.user_id AS a, y.user_id AS b FROM {src} x JOIN {src} y ON x.event_type = y.event_type WHERE x.user_id <> y.user_id AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL {window} SECOND"
        span = window * 1_000_000
        return f"""
SELECT x.user_id AS a, y.user_id AS b
FROM (SELECT user_id, event_type, ts, explode(array(unix_micros(ts) DIV {span}, unix_micros(ts) DIV {span} + 1)) AS slot FROM {src}) x
JOIN (SELECT user_id, event_type, ts, unix_micros(ts) DIV {span} AS slot FROM {src}) y
ON x.event_type = y.event_type AND x.slot = y.slot
WHERE x.user_id <> y.user_id AND y.ts >= x.ts AND unix_micros(y.ts) <= unix_micros(x.ts) + {span}"""
    if name in ("lines", "lines_all", "colink", "colink_all"):
        items = _items(name, dialect)
        return _all_holders(items, dialect) if name.endswith("_all") else _holders(items, 60 if name == "lines" else cap)
    if name == "embed" and duck:
        return f"SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id WHERE list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) >= {cosine}"
    raise ValueError(f"no graph rule {name}")


TABLES = {
    "basket": ["lineitem"], "basket_r": ["lineitem"], "basket_r25": ["lineitem"], "commerce": ["customer", "supplier", "lineitem", "orders"],
    "coact": ["events"], "coact_json": ["events"], "lines": ["documents"], "lines_all": ["documents"], "colink": ["pages"], "colink_all": ["pages"], "embed": ["embeddings"],
}
GRAPHS = ("basket", "basket_r", "basket_r25", "coact", "coact600", "commerce", "lines", "lines_all", "colink", "colink_all", "embed")


def rule_options(name: str) -> tuple[str, dict]:
    """A graph's rule and options from its short name: coact600 is coact with a window of 600 s."""
    if name.startswith("coact") and name[5:].isdigit():
        return "coact", {"window": int(name[5:])}
    return name, {}


def edges_sql(name: str, dialect: str = "duckdb", **options) -> str:
    rule, own = rule_options(name)
    return f"SELECT DISTINCT CAST(least(a, b) AS BIGINT) AS src, CAST(greatest(a, b) AS BIGINT) AS dst FROM ({graph_rule(rule, dialect, **(own | options))}) AS pairs WHERE a <> b"


def similar_vectors(vectors: DataFrame, least: float, block: int = 1000) -> DataFrame:
    """Pairs (a, b) of vectors with cosine at least `least`, exactly: all pairs are compared, by products of bounded blocks.

    Each vector is sent to every block, so rows and work grow with the square of the vectors; that is what all exact pairs cost.
    """
    n = vectors.count()
    blocks = -(-n // block) or 1
    dealt = vectors.select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("own"))
    meet = F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda j: F.struct(F.least("own", j.cast("long")).alias("i"), F.greatest("own", j.cast("long")).alias("j"))))

    def product(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(rows["embedding"].map(np.asarray)).astype(np.float64)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        ids, own = rows["vec_id"].to_numpy(), rows["own"].to_numpy()
        a, b = np.nonzero(x @ x.T >= least)
        new = (ids[a] < ids[b]) & ((own[a] != own[b]) | (key[0] == key[1]))
        return pd.DataFrame({"a": ids[a[new]], "b": ids[b[new]]})

    return dealt.withColumn("meet", meet).groupBy("meet.i", "meet.j").applyInPandas(product, "a long, b long")


# ---------------------------------------------------------------- the graph

CROWDED_IDS, CROWDED_MEAN = 10_000_000, 64  # list members that arcs would ship, in all and for each arc
LATER_EDGES = 40_000_000  # 160 MB of later neighbours
WHOLE_ARCS = 20_000_000  # 80 MB of neighbours
WHOLE_COUNTS = ("near_clique5", "house5", "wheel6")
TWIN_COUNTS = ("near_clique5", "house5")
CROWDED_GROUPS = 1_000_000  # squared holders of items, in all, above which cliques are counted by classes of vertices
HELD_MEMBERS = 5_000_000  # holders of items that the driver deals into classes: 20 MB of broadcast lists each way


@dataclass
class Graph:
    """Edges with lazily built adjacency; labels: (v, label) or none.

    groups: (holders), rows whose pairs are all the edges, or none. copies: (members), rows of vertices that have the same closed neighbourhood
    or no edge at all, and what gives the graph of some vertices' edges, or none.
    """

    edges: DataFrame
    labels: DataFrame | None = None
    name: str = ""
    triangle_unit: str = "ordered"
    groups: DataFrame | None = None
    copies: tuple[DataFrame, Callable[[DataFrame], DataFrame]] | None = None

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @classmethod
    def from_testdata(cls, spark: SparkSession, sf_dir: str, name: str, **options) -> Graph:
        rule, own = rule_options(name)
        options = own | options
        tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES[rule]}
        labels = None
        if rule == "embed":
            pairs = similar_vectors(tables["embeddings"], options.get("cosine", 0.3))
            labels = tables["embeddings"].select(F.col("vec_id").alias("v"), F.col("label").cast("int").alias("label"))
        else:
            pairs = spark.sql(_named(graph_rule(rule, "spark", **options), tables), **tables)
        edges = from_edges(pairs)
        if rule == "commerce":
            labels = symmetrise(edges).select(F.col("u").alias("v"), F.floor(F.col("u") / 1_000_000).cast("int").alias("label")).distinct()
        groups = spark.sql(_named(groups_sql(rule), tables), **tables).persist() if rule.endswith("_all") else None
        copies = _same_events(spark, tables["events"], options) if rule == "coact" and not options.get("filters") else None
        return cls(edges, labels, name, groups=groups, copies=copies).cached()

    @classmethod
    def of(cls, spark: SparkSession, pairs: list[tuple[int, int]], labels: dict[int, int] | None = None) -> Graph:
        df = spark.createDataFrame(pairs, "a long, b long")
        return cls(from_edges(df), spark.createDataFrame(list(labels.items()), "v long, label int") if labels else None)

    def cached(self) -> Graph:
        self.edges = self.edges.persist()
        return self

    @cached_property
    def arcs(self) -> DataFrame:
        return symmetrise(self.edges)

    @cached_property
    def adj(self) -> DataFrame:
        """Persisted: every depth of a match joins it."""
        return adjacency(self.arcs).persist()

    @cached_property
    def degrees(self) -> DataFrame:
        return self.adj.select("u", "deg")

    def stats_frame(self) -> DataFrame:
        if self.classes is not None:
            return self.spark.createDataFrame([self.classes.shape()], "n_vertices long, n_edges long, d_max long").join(F.broadcast(self.clique_count(3).withColumnRenamed("cnt", "n_triangles")))
        shape = self.degrees.agg(F.count("*").alias("n_vertices"), F.expr("cast(coalesce(sum(deg), 0) / 2 as bigint)").alias("n_edges"), F.coalesce(F.max("deg"), F.lit(0)).cast("long").alias("d_max"))
        triangles = self.clique_count(3).withColumnRenamed("cnt", "n_triangles") if self.counts_cliques else triangle_count(self.edges, self.degrees)
        return shape.join(F.broadcast(triangles))  # one row each

    @cached_property
    def stats(self) -> GraphStats:
        r = self.stats_frame().first()
        return GraphStats(r["n_vertices"], r["n_edges"], r["n_triangles"], r["d_max"], self.triangle_unit)

    @cached_property
    def degree_classes(self) -> list[tuple[float, float]]:
        """(mean degree, vertices) of each quarter octave of degrees: some hundred rows at most."""
        if self.alike is not None:
            return self.alike.degree_classes()
        quarter = F.floor(4 * F.log2(F.col("deg").cast("double")))
        return [(r["d"], float(r["n"])) for r in self.degrees.groupBy(quarter.alias("q")).agg(F.avg("deg").alias("d"), F.count("*").alias("n")).orderBy("q").collect()]

    @property
    def crowded(self) -> bool:
        """Whether a join of arcs and lists ships far more than the arcs, of a graph whose edges can be broadcast."""
        return self.shipped > max(CROWDED_IDS, CROWDED_MEAN * self.arcs_number) and self.arcs_number <= 2 * LATER_EDGES

    @property
    def arcs_number(self) -> float:
        return sum(d * n for d, n in self.degree_classes)

    @property
    def shipped(self) -> float:
        """List members that a join of arcs and lists ships, about."""
        return sum(d * d * n for d, n in self.degree_classes)

    @cached_property
    def classes(self) -> Classes | None:
        """Vertices with the same closed neighbourhood as one, where groups would make many pairs; nothing is made of a pair of vertices."""
        if self.alike is not None:
            return self.alike.classes()
        if self.groups is None:
            return None
        n, squares = self.groups.agg(F.sum(F.size("holders").cast("long")), F.sum(F.size("holders").cast("long") * F.size("holders"))).first()
        if not n or squares <= CROWDED_GROUPS or n > HELD_MEMBERS:
            return None
        return twin_classes(self.groups, 2 * LATER_EDGES)

    @cached_property
    def alike(self) -> Alike | None:
        """The classes of copies, if they halve the vertices at least and the arcs of their first vertices can be broadcast; no other pair is made."""
        if self.copies is None:
            return None
        members, edges_of = self.copies
        members = members.persist()
        reps, out = None, None
        n, held = members.agg(F.count("*"), F.coalesce(F.sum(F.size("members").cast("long")), F.lit(0))).first()
        if n and 2 * n <= held <= HELD_MEMBERS:
            reps = Graph(edges_of(members.select(F.col("members")[0].alias("v")))).cached()
            if reps.arcs_number <= WHOLE_ARCS:
                out = alike(members, later_lists(reps.adj, whole=True))
            reps.release()
        members.unpersist()
        return out

    @cached_property
    def _classes_sent(self) -> Broadcast[Classes]:
        return self.spark.sparkContext.broadcast(self.classes)

    @property
    def counts_cliques(self) -> bool:
        """Whether cliques of 3 or 4 are better counted by clique_count than from a frontier."""
        return self.classes is not None or self.crowded

    def wedges(self) -> DataFrame:
        """One row pairs: pairs of neighbours, over all vertices."""
        if self.classes is not None:
            return self.spark.createDataFrame([(self.classes.wedges(),)], "pairs long")
        return self.degrees.agg(F.coalesce(F.sum(F.expr("cast(deg as bigint) * (deg - 1) div 2")), F.lit(0)).alias("pairs"))

    @cached_property
    def later(self) -> Broadcast[Lists]:
        """Lists of later vertices, at most LATER_EDGES members in all."""
        return self.spark.sparkContext.broadcast(later_lists(self.adj))

    def clique_count(self, k: int) -> DataFrame:
        """One row cnt of cliques of 3 or 4 vertices: tasks count by first vertex, over broadcast lists; no frontier is shipped."""
        if k not in (3, 4):
            raise ValueError("cliques of 3 or 4")
        by_class = self.classes is not None
        lists = self._classes_sent if by_class else self.later
        tasks = 16 * self.spark.sparkContext.defaultParallelism

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            counter = ClassCounter(lists.value) if by_class else CliqueCounter(lists.value)
            count = counter.triangles if k == 3 else counter.cliques4
            for batch in batches:
                for first in batch.column("id").to_pylist():  # a task has every tasks-th vertex, so long lists are dealt evenly
                    yield pa.RecordBatch.from_arrays([pa.array([sum(count(v) for v in range(first, len(counter.lists.ids), tasks))], pa.int64())], ["cnt"])

        return self.spark.range(0, tasks, 1, tasks).mapInArrow(work, "cnt long").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))

    @property
    def crowded_whole(self) -> bool:
        """Whether the graph is crowded and all its arcs, or those of its classes, can be broadcast."""
        return self.alike is not None or self.crowded and self.arcs_number <= WHOLE_ARCS

    @cached_property
    def whole(self) -> Broadcast[Lists]:
        """All neighbours, numbered by degree, at most WHOLE_ARCS in all."""
        return self.spark.sparkContext.broadcast(later_lists(self.adj, whole=True))

    def whole_count(self, name: str) -> DataFrame:
        """One row cnt of near_clique5, house5 or wheel6 (edge-induced) in a crowded graph: tasks count by a vertex, over broadcast whole lists."""
        if name not in WHOLE_COUNTS:
            raise ValueError(f"no count of {name}")
        if self.alike is not None:
            return self._by_class(lambda c: {"near_clique5": c.near_cliques5, "wheel6": c.wheels6, "house5": c.houses5}[name])
        lists = self.whole
        tasks = 16 * self.spark.sparkContext.defaultParallelism

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            counter = WholeCounter(lists.value)
            count = {"near_clique5": counter.near_cliques5, "wheel6": counter.wheels6, "house5": counter.houses5}[name]
            for batch in batches:
                for first in batch.column("id").to_pylist():
                    yield pa.RecordBatch.from_arrays([pa.array([sum(count(v) for v in range(first, len(lists.value.ids), tasks))], pa.int64())], ["cnt"])

        return self.spark.range(0, tasks, 1, tasks).mapInArrow(work, "cnt long").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))

    @cached_property
    def twins(self) -> Broadcast[Twins]:
        """Whole lists of classes of vertices, of at most WHOLE_ARCS arcs."""
        return self.spark.sparkContext.broadcast(self.alike or twins(later_lists(self.adj, whole=True)))

    def twin_count(self, name: str, chosen: Callable[[np.ndarray, int], np.ndarray] | None = None) -> DataFrame:
        """One row cnt of vertex-induced house5 or edge-induced near_clique5 in a crowded graph: tasks count by a class of vertices with the same closed neighbourhood.

        chosen(ids, first id): whose lists near_clique5 cuts to those of the first vertex before it reads them.
        """
        if name not in TWIN_COUNTS:
            raise ValueError(f"no count of {name}")
        return self._by_class(lambda c: c.induced_houses5 if name == "house5" else lambda v: c.near_cliques5(v, chosen))

    def _by_class(self, counted: Callable[[TwinCounter], Callable[[int], int]]) -> DataFrame:
        """One row cnt: the sum over all classes. A sum that 64 bits can't hold is a decimal."""
        classes = self.twins
        tasks = 16 * self.spark.sparkContext.defaultParallelism

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            counter = TwinCounter(classes.value)
            count = counted(counter)
            for batch in batches:
                for first in batch.column("id").to_pylist():
                    yield pa.RecordBatch.from_arrays([pa.array([str(sum(count(v) for v in range(first, len(counter.weights), tasks)))])], ["part"])

        parts = self.spark.range(0, tasks, 1, tasks).mapInArrow(work, "part string")
        if self.alike is None:  # vertices whose arcs can be broadcast
            return parts.agg(F.coalesce(F.sum(F.col("part").cast("long")), F.lit(0)).alias("cnt"))
        total = sum(int(r["part"]) for r in parts.collect())  # a row a task
        return self.spark.range(1).select(F.lit(str(total)).cast("long" if total < 1 << 63 else "decimal(38,0)").alias("cnt"))

    def release(self) -> None:
        """Frees the persisted edges and lists; both are computed anew if needed."""
        self.edges.unpersist()
        self.__dict__.pop("alike", None)
        if self.groups is not None:
            self.groups.unpersist()
        for name in ("adj", "compressed", "later", "whole", "twins", "_classes_sent"):
            if name in self.__dict__:
                self.__dict__.pop(name).unpersist()
        self.__dict__.pop("degrees", None)

    def summary(self) -> DataFrame:
        """One row; of a graph without edges, all but n_vertices is null."""
        return self.degrees.agg(F.count("*").alias("n_vertices"), F.expr("cast(sum(deg) / 2 as bigint)").alias("n_edges"), F.max("deg").cast("long").alias("d_max"), F.round(F.avg("deg"), 9).alias("d_avg"))

    def relabel(self, by: str = "degree") -> tuple[Graph, DataFrame]:
        """The graph with dense ids 0..n-1 in ascending order of degree or id, and the map (v, new_id).

        Positions come from a range sort and the ranges' counts, so no task sees all vertices.
        """
        order = ["deg", "u"] if by == "degree" else ["u"]
        ranged = self.degrees.repartitionByRange(*order).sortWithinPartitions(*order)
        placed = ranged.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id() - (F.col("part").cast("long") * (1 << 33))).persist()
        sizes = {r["part"]: r["count"] for r in placed.groupBy("part").count().collect()}  # a row for each range
        before, total = {}, 0
        for part in sorted(sizes):
            before[part], total = total, total + sizes[part]
        offset = F.create_map(*[F.lit(x) for kv in before.items() for x in kv])[F.col("part")] if before else F.lit(0)
        ids = placed.select(F.col("u").alias("v"), (F.col("at") + offset).cast("long").alias("new_id")).persist()
        moved = self.edges.join(ids.select(F.col("v").alias("src"), F.col("new_id").alias("a")), "src").join(ids.select(F.col("v").alias("dst"), F.col("new_id").alias("b")), "dst")
        labels = self.labels.join(ids, "v").select(F.col("new_id").alias("v"), "label") if self.labels is not None else None
        return Graph(from_edges(moved), labels, self.name).cached(), ids

    def subgraph(self, vertices: DataFrame) -> Graph:
        """Edges between the given vertices (v)."""
        inside = self.edges.join(vertices.select(F.col("v").alias("src")).distinct(), "src", "left_semi").join(vertices.select(F.col("v").alias("dst")).distinct(), "dst", "left_semi")
        return Graph(inside.select("src", "dst"), self.labels, self.name)

    def sample_edges(self, share: float, seed: int = 0) -> Graph:
        """Each edge with the given probability, by a hash: the same edges on every run and in every engine that has md5."""
        digest = F.md5(F.concat_ws("-", F.lit(str(seed)), "src", "dst").cast("binary"))
        place = F.conv(F.substring(digest, 1, 8), 16, 10).cast("long")
        return Graph(self.edges.where(place < int(share * (1 << 32))), self.labels, self.name)

    def k_core(self, k: int) -> Graph:
        """What is left after vertices of degree under k have gone, again and again."""
        edges = self.edges.persist()
        while True:
            n = edges.count()
            low = symmetrise(edges).groupBy("u").agg(F.count("*").alias("d")).where(F.col("d") < k)
            edges = edges.join(low.select(F.col("u").alias("src")), "src", "left_anti").join(low.select(F.col("u").alias("dst")), "dst", "left_anti").select("src", "dst")
            edges = cut_lineage(edges)
            if edges.count() == n:
                return Graph(edges, self.labels, self.name)

    def save(self, path: str, parts: int = 8) -> None:
        """Adjacency by ranges of u, sorted, for joins that read only what they need."""
        self.adj.repartitionByRange(parts, "u").sortWithinPartitions("u").write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Graph:
        adj = spark.read.parquet(path)
        out = cls(adj.select(F.col("u").alias("src"), F.explode("nbrs").alias("dst")).where("src < dst"))
        out.__dict__["adj"] = adj
        return out


def _same_events(spark: SparkSession, events: DataFrame, options: dict) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """Copies of a coact graph: users with the same events (rows without user, type or time link nobody)."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    rows = events.select("user_id", "event_type", at.alias("at")).dropna()

    def edges_of(vertices: DataFrame) -> DataFrame:
        own = {"events": events.join(F.broadcast(vertices.select(F.col("v").alias("user_id"))), "user_id", "left_semi")}
        return from_edges(spark.sql(_named(graph_rule("coact", "spark", **options), own), **own))

    return same_rows(rows, "user_id", "event_type", "at"), edges_of


def _named(sql: str, tables: dict[str, DataFrame]) -> str:
    """The SQL with its tables as parameters of spark.sql, so that no view is registered."""
    for t in tables:
        sql = re.sub(rf"\b(FROM|JOIN) {t}\b", rf"\1 {{{t}}}", sql)
    return sql


def checkpoint_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; one of our own only where none is set, as in tests."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(sc.getConf().get("spark.checkpoint.dir") or tempfile.mkdtemp(prefix="motifprune_"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """df from checkpointed files in the session's checkpoint folder."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint()
