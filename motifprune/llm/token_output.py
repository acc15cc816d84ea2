"""Token ids as Parquet list columns, for selective reads.

Rows are range-partitioned by doc_id and sorted, so each file holds a contiguous id range and its row
groups and page indexes let a reader skip to some documents or read the metadata columns alone. Format
version 2 pages store ids by dictionary and fall back to delta packing, counters by delta packing.

Defined results: a null text counts as empty and yields the end id alone; texts of any length are one row;
null ids come first; rows repeated with one id keep any order among themselves; an empty table yields no
rows; columns beside doc_id and text are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifprune.llm import common

FILE, END_ID = "word_bpe_49k.json", 1
SCHEMA = "doc_id long, n_tokens long, part int, start_in_part long, tokens array<int>"
LAYOUT = {
    "parquet.writer.version": "v2",
    "parquet.enable.dictionary": "true",
    "parquet.block.size": str(64 << 20),
    "parquet.page.size": str(256 << 10),
    "parquet.page.row.count.limit": "4096",
    "compression": "zstd",
}


def write_tokens(docs: DataFrame, path: str, file: str = FILE, space_kept: bool = False, end_id: int = END_ID) -> None:
    """Encodes every text and writes the format to `path`, in ascending doc_id order."""
    end = np.asarray([end_id], dtype="<u4").tobytes()

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, before = common.encoder(file, space_kept).ids_bytes, 0
        for batch in common.sliced(batches, 2048):
            ids = [encode(text) + end for text in batch.column(1).to_pylist()]
            sizes = np.fromiter((len(x) // 4 for x in ids), dtype=np.int64, count=len(ids))
            ends = np.cumsum(sizes)
            tokens = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(np.frombuffer(b"".join(ids), dtype="<i4")))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes), batch.column(2), pa.array(before + ends - sizes), tokens], ["doc_id", "n_tokens", "part", "start_in_part", "tokens"])
            before += int(sizes.sum())

    rows = common.texts_of(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id").withColumn("part", F.spark_partition_id())
    rows.mapInArrow(encoded, SCHEMA).write.mode("overwrite").options(**LAYOUT).parquet(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """The files' rows, with `start`: the number of ids of all documents before each."""
    rows = spark.read.schema(SCHEMA).parquet(path)
    parts = rows.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    before = parts.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).alias("before"))
    # one row a range of write_tokens: as many as the shuffle had partitions
    return rows.join(F.broadcast(before), "part").withColumn("start", F.coalesce("before", F.lit(0)) + F.col("start_in_part")).drop("before", "part", "start_in_part")


def read_documents(spark: SparkSession, path: str, low: int, high: int) -> DataFrame:
    """(doc_id, n_tokens, tokens) of ids from low to high; files, row groups and pages of other ids are skipped."""
    return spark.read.schema(SCHEMA).parquet(path).where(F.col("doc_id").between(low, high)).select("doc_id", "n_tokens", "tokens")


def read_sizes(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, n_tokens) of every row; the token column is not read."""
    return spark.read.schema(SCHEMA).parquet(path).select("doc_id", "n_tokens")


def digests(rows: DataFrame) -> DataFrame:
    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens = batch.column(2)
            edges, values = tokens.offsets.to_numpy(), tokens.values.to_numpy().astype("<u4", copy=False)
            crc = [zlib.crc32(values[a:b]) for a, b in zip(edges, edges[1:])]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.diff(edges).astype(np.int64)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return rows.select("doc_id", "start", "tokens").mapInArrow(summed, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op5_token_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = common.shared_path(spark, "tokens")
    write_tokens(common.read_table(spark, sf_dir, "documents"), path)
    return digests(read_tokens(spark, path))
