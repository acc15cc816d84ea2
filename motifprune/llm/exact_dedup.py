"""Exact duplicates through an extendible-hash index on shared files.

A 64-bit hash of the text is its key; the key's leading bits name a directory slot. Every slot starts
at the same shallow depth and an overfull bucket is split by one more bit, doubling the directory where
its depth is used up, until each bucket is within its room or the directory has its largest size.
Owner tasks take whole buckets in key order, chain the texts of a key, compare their bytes and write
the bucket's postings to shared files. Copies are folded within each read batch before they move, so a
text that fills a third of all rows reaches its owner a few times, and its rows look their group up in
a small table of large groups.

Defined results: a null text counts as empty, and empty texts equal each other; of equal texts the row
with the largest doc_id stays (of rows repeated with that same id, one row). An empty table gives no
rows. Columns beside doc_id and text are not read, and none is normalised.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.llm import common

BUCKET_ROWS, START_BITS, MOST_BITS = 50_000, 4, 16
LARGE_GROUPS = 2000
POSTINGS = "key long, text_sha256 string, keep_id long, group_size long"


def directory(keys: DataFrame, bucket_rows: int = BUCKET_ROWS, most_bits: int = MOST_BITS) -> dict[int, tuple[int, int]]:
    """slot -> (bucket, local depth) at the directory's final depth, of at most 2**most_bits slots.

    keys: (key, n). Counts are kept for 2**most_bits prefixes at most, whatever the table's size.
    """
    total = keys.agg(F.sum("n")).first()[0] or 0
    bits = min(most_bits, max(START_BITS, math.ceil(math.log2(max(1, total / bucket_rows))) + 3))
    filled = {r["slot"]: r["n"] for r in keys.groupBy(F.shiftrightunsigned("key", 64 - bits).alias("slot")).agg(F.sum("n").alias("n")).collect()}
    slots: dict[int, tuple[int, int]] = {}
    waiting = [(prefix, START_BITS) for prefix in range(1 << START_BITS)]
    while waiting:
        prefix, depth = waiting.pop()
        low, high = prefix << (bits - depth), (prefix + 1) << (bits - depth)
        if depth < bits and sum(filled.get(s, 0) for s in range(low, high)) > bucket_rows:
            waiting += [(2 * prefix, depth + 1), (2 * prefix + 1, depth + 1)]
        else:
            slots.update(dict.fromkeys(range(low, high), (low, depth)))
    return slots


def _folded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each different text of some thousand rows: largest id and number of rows."""
    for batch in common.sliced(batches, 2048):
        seen: dict[str, list] = {}
        for doc_id, key, text in zip(*(c.to_pylist() for c in batch.columns)):
            got = seen.setdefault(text, [key, doc_id, 0])
            got[2] += 1
            if got[1] is None or doc_id is not None and doc_id > got[1]:
                got[1] = doc_id
        rows = [(v[0], t, v[1], v[2]) for t, v in seen.items()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [[]] * 4, (pa.int64(), pa.string(), pa.int64(), pa.int64()))], ["key", "text", "last_id", "n"])


def _owned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Postings of a partition sorted by key; a key's chain holds each different text once."""
    key, chain = None, {}

    def posted(key, chain):
        return [(key, hashlib.sha256(t).hexdigest(), last, n) for t, (last, n) in chain.items()]

    for batch in batches:
        rows = []
        for k, text, last, n in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist()):
            if k != key:
                rows += posted(key, chain)
                key, chain = k, {}
            was = chain.get(text)  # equal bytes only
            chain[text] = (last, n) if was is None else (max((x for x in (was[0], last) if x is not None), default=None), was[1] + n)
        yield _postings(rows)
    yield _postings(posted(key, chain))


def _postings(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [[]] * 4, (pa.int64(), pa.string(), pa.int64(), pa.int64()))], ["key", "text_sha256", "keep_id", "group_size"])


def build_index(docs: DataFrame, bucket_rows: int = BUCKET_ROWS, most_bits: int = MOST_BITS) -> DataFrame:
    """The postings (key, text_sha256, keep_id, group_size), read from the index files."""
    spark = docs.sparkSession
    rows = common.texts_of(docs).select("doc_id", F.xxhash64("text").alias("key"), "text")
    slots = directory(rows.groupBy("key").agg(F.count("*").alias("n")).groupBy("key").agg(F.least(F.sum("n"), F.lit(bucket_rows)).alias("n")), bucket_rows, most_bits)
    bits = max(START_BITS, (len(slots) - 1).bit_length())
    table = spark.createDataFrame([(s, b, d) for s, (b, d) in slots.items()], "slot long, bucket long, depth int")
    folded = rows.mapInArrow(_folded, "key long, text string, last_id long, n long").withColumn("slot", F.shiftrightunsigned("key", 64 - bits))
    owned = folded.join(F.broadcast(table), "slot").repartition("bucket").sortWithinPartitions("bucket", "key").select("key", "text", "last_id", "n")
    return common.written(owned.mapInArrow(_owned, POSTINGS), "hash-index")


def duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) of every row."""
    rows = common.texts_of(docs).select("doc_id", F.xxhash64("text").alias("key"), F.sha2("text", 256).alias("text_sha256"))
    index = build_index(docs)
    grouped = index.where("group_size > 1")
    total = index.agg(F.sum("group_size")).first()[0] or 0
    large = grouped.where(F.col("group_size") > max(200, total // LARGE_GROUPS))  # at most LARGE_GROUPS of them
    names = ["key", "text_sha256"]
    tagged = rows.join(F.broadcast(large), names, "left")
    rest = grouped.where(F.col("group_size") <= max(200, total // LARGE_GROUPS))
    rest = rest.select(*names, F.col("keep_id").alias("keep_rest"), F.col("group_size").alias("size_rest"))
    # Rows of large groups join on no key that the rest has, spread by their id.
    spread = tagged.withColumn("join_key", F.when(F.col("keep_id").isNull(), F.col("key")).otherwise(F.xxhash64("doc_id"))).withColumn("join_sha", F.when(F.col("keep_id").isNull(), F.col("text_sha256")).otherwise(F.lit("-")))
    joined = spread.join(rest.withColumnsRenamed({"key": "join_key", "text_sha256": "join_sha"}), ["join_key", "join_sha"], "left")
    keep = F.coalesce("keep_id", "keep_rest", "doc_id")
    return joined.select("doc_id", keep.alias("keep_id"), F.coalesce("group_size", "size_rest", F.lit(1)).cast("long").alias("group_size"), F.coalesce(F.col("doc_id") == keep, F.lit(True)).alias("kept"), "text_sha256")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicates(common.read_table(spark, sf_dir, "documents"))


ORACLE = """
SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
       doc_id = max(doc_id) OVER g AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW g AS (PARTITION BY coalesce(text, ''))
"""
