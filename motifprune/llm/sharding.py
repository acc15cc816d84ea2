"""Sharding by balanced label propagation, in DataFrame operations alone.

Documents with equal texts are linked. Every document starts in the shard that its id hashes to; in each
round the linked documents of a group propose to move to the shard where most of their neighbours are,
and a shard accepts proposals up to its quota, so that fewer links are cut and no shard outgrows its
share. Unlinked documents then fill what room is left, and the law `rows` holds exactly: shard sizes
differ by one row at most. Members of a group larger than a shard stay spread over several.

A round's state has one row for each group and starting shard, never pairs of documents. Ranks are
counted in two steps, within hashed buckets and over the buckets' sums, so no task sees a whole shard.

Only tables of one row a shard are broadcast by hint; the buckets' sums, whose number grows with the rows, are
joined as the optimizer sees fit.

Defined results: a null text has 8 bytes and the crc of the empty text, and equals the empty text; texts of any
length count whole; ties go to the shard of the lowest number and then by id and text; rows repeated with one id
count each; an empty table gives no rows; fewer rows than shards leave shards empty; columns beside doc_id and
text are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifprune.llm import common

SHARDS, ROUNDS, BUCKET_ROWS, LEAST_BUCKETS = 24, 4, 50_000, 64


def _ranked(df: DataFrame, by: list[str], order: list[Column], spread: Column, buckets: int) -> DataFrame:
    """df with rank_no from 0 within `by`, counted within buckets and then over the buckets' sums."""
    df = df.withColumn("rank_bucket", F.pmod(spread, F.lit(buckets)))
    sums = df.groupBy(*by, "rank_bucket").agg(F.count("*").alias("rank_n"))
    before = Window.partitionBy(*by).orderBy("rank_bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(*by, "rank_bucket", F.coalesce(F.sum("rank_n").over(before), F.lit(0)).alias("rank_before"))
    own = F.row_number().over(Window.partitionBy(*by, "rank_bucket").orderBy(*order)) - 1
    return df.withColumn("rank_own", own).join(sums, [*by, "rank_bucket"]).withColumn("rank_no", F.col("rank_before") + F.col("rank_own")).drop("rank_bucket", "rank_own", "rank_before")


def propagate(state: DataFrame, quotas: list[int], rounds: int, buckets: int) -> DataFrame:
    """state (linked, home, w, shard) after label propagation under the quotas."""
    spark = state.sparkSession
    room_of = spark.createDataFrame(list(enumerate(quotas)), "shard int, quota long")
    for _ in range(rounds):
        here = state.groupBy("linked", "shard").agg(F.sum("w").alias("w"))
        best = here.groupBy("linked").agg(F.max(F.struct("w", -F.col("shard")))["col2"].alias("target")).select("linked", (-F.col("target")).alias("target"))
        load = state.groupBy("shard").agg(F.sum("w").alias("load"))
        free = F.broadcast(room_of).join(load, "shard", "left").select(F.col("shard").alias("target"), (F.col("quota") - F.coalesce("load", F.lit(0))).alias("room"))
        wished = state.join(best, "linked").withColumn("part", F.pmod(F.xxhash64("linked"), F.lit(buckets)))
        wished = wished.withColumn("ask", F.when(F.col("shard") != F.col("target"), F.col("w")).otherwise(0))
        asked = wished.groupBy("target", "part").agg(F.sum("ask").alias("asked"))
        whole = Window.partitionBy("target")
        share = asked.join(F.broadcast(free), "target").select("target", "part", F.floor(F.greatest("room", F.lit(0)) * F.col("asked") / F.greatest(F.sum("asked").over(whole), F.lit(1))).alias("share"))
        line = Window.partitionBy("target", "part").orderBy(F.desc("ask"), "linked", "home").rowsBetween(Window.unboundedPreceding, 0)
        moved = wished.withColumn("upto", F.sum("ask").over(line)).join(share, ["target", "part"])
        moved = moved.withColumn("moves", (F.col("ask") > 0) & (F.col("upto") <= F.col("share")))
        moved = common.written(moved.select("linked", "home", "w", F.when(F.col("moves"), F.col("target")).otherwise(F.col("shard")).alias("shard"), "moves"), "shard-state")
        state = moved.drop("moves")
        if moved.where("moves").isEmpty():
            break
    return state


def shard_rows(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) of every row."""
    text = F.col("text")
    rows = common.texts_of(docs).select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("linked"))
    rows = common.written(rows.withColumn("home", F.pmod(F.xxhash64("doc_id"), F.lit(shards)).cast("int")), "shard-rows")
    n = rows.count()
    quotas = [n // shards + (s < n % shards) for s in range(shards)]
    buckets = max(LEAST_BUCKETS, math.ceil(n / BUCKET_ROWS))

    state = rows.groupBy("linked", "home").agg(F.count("*").alias("w"))
    groups = state.groupBy("linked").agg(F.sum("w").alias("members")).where("members > 1").select("linked")
    state = common.written(state.join(groups, "linked").withColumn("shard", F.col("home")), "shard-state")
    state = propagate(state, quotas, rounds, buckets)

    placed = rows.join(state.select("linked", "home", "shard", "w"), ["linked", "home"], "left")
    spread = F.xxhash64("linked", "home", F.pmod(F.xxhash64("doc_id"), F.ceil(F.col("w") / BUCKET_ROWS).cast("long")))  # a large group takes several buckets
    linked = _ranked(placed.where("shard IS NOT NULL"), ["shard"], [F.col("linked"), F.col("doc_id")], spread, buckets)
    quota = F.element_at(F.array(*map(F.lit, quotas)), F.col("shard") + 1)
    linked = common.written(linked.withColumn("stays", F.col("rank_no") < quota), "shard-linked")
    kept = {r["shard"]: r["count"] for r in linked.where("stays").groupBy("shard").count().collect()}  # a row for each shard at most

    names = ["doc_id", "size", "text_crc32", "linked"]
    pool = placed.where("shard IS NULL").select(*names).unionByName(linked.where("NOT stays").select(*names))
    pool = _ranked(pool.withColumn("all", F.lit(0)), ["all"], [F.col("doc_id"), F.col("linked")], F.xxhash64("doc_id", "linked"), buckets)
    shard, slot, before = F.lit(shards - 1), F.lit(None).cast("long"), 0
    for s in range(shards):
        room = quotas[s] - kept.get(s, 0)
        within = (F.col("rank_no") >= before) & (F.col("rank_no") < before + room)
        shard, slot = F.when(within, s).otherwise(shard), F.when(within, F.col("rank_no") - before + kept.get(s, 0)).otherwise(slot)
        before += room
    filled = pool.select("doc_id", "size", "text_crc32", shard.cast("int").alias("shard"), slot.cast("long").alias("slot"))
    stayed = linked.where("stays").select("doc_id", "size", "text_crc32", "shard", F.col("rank_no").cast("long").alias("slot"))
    return stayed.unionByName(filled)


def op9_label_propagation_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shard_rows(common.read_table(spark, sf_dir, "documents"))
    return out.withColumns({"law": F.lit("rows"), "grown_shard": F.lit(None).cast("int")})
