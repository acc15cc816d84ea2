"""Best-fit packing by sums of squares.

Documents become token pieces of at most `capacity` ids. A piece goes where the squared numbers of
open sequences for each residual gap sum to least: into a sequence whose gap is crowded, preferably
one that it closes, and into the tightest of equally good ones. Packing works on bounded groups of
pieces dealt by a hash, so no task grows with the corpus; pieces of sequences that a group leaves
ill-filled are packed again in fewer groups.

Of the two published ways to open a sequence (only if none can take the piece, or whenever the sum prefers it)
each group keeps the one that takes fewer.

Defined results: a null text counts as empty and still yields one piece (its end id); rows repeated
with the same id are packed each; an empty table yields no rows; columns beside doc_id and text are
not read; texts of any length are cut into pieces. Sequence numbers are unique but carry no order.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifprune.llm import common

CAPACITY, END_ID, FILE = 2048, 0, "byte_bpe_50k.json"
PIECES_PER_GROUP, FULL_ENOUGH = 8192, 0.997


def sum_of_squares(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece, by whichever of the two rules for opening takes fewer sequences."""
    late, free = (_placed(lengths, capacity, opening) for opening in (False, True))
    return late if late[0].max(initial=-1) <= free[0].max(initial=-1) else free


def _placed(lengths: np.ndarray, capacity: int, opening: bool) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece; longest pieces are placed first, ties in the order given.

    A piece goes to an open sequence whose gap leaves the least sum of squares; a new one is opened only if none
    can take it or, if `opening` is among the choices, where that leaves a smaller sum.
    """
    open_by_gap: list[list[int]] = [[] for _ in range(capacity + 1)]
    count = np.zeros(capacity + 1, dtype=np.int64)
    sequence = np.empty(len(lengths), dtype=np.int64)
    offset = np.empty(len(lengths), dtype=np.int64)
    made = 0
    for at in np.argsort(-lengths, kind="stable"):
        size = int(lengths[at])
        gaps = np.flatnonzero(count[size:]) + size
        best = capacity
        if len(gaps):
            after = gaps - size
            change = np.where(after > 0, 2 * count[after] + 2, 1) - 2 * count[gaps]
            least = change.argmin()
            if not opening or size == capacity or change[least] <= 2 * count[capacity - size] + 1:
                best = int(gaps[least])
        if best < capacity:
            own = open_by_gap[best].pop()
            count[best] -= 1
        else:
            own, made = made, made + 1
        sequence[at], offset[at] = own, capacity - best
        if best > size:
            open_by_gap[best - size].append(own)
            count[best - size] += 1
    return sequence, offset


def token_pieces(docs: DataFrame, file: str = FILE, space_kept: bool = True, end_id: int = END_ID, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Pieces of each document: only one longer than `capacity` is cut, its first piece being the short one."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    end = np.asarray([end_id], dtype="<u4").tobytes()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = common.encoder(file, space_kept).ids_bytes
        for batch in common.sliced(batches):
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = encode(text) + end
                n = len(ids) // 4
                edges = [0, *range(n - (n - 1) // capacity * capacity, n + 1, capacity)]
                for k, (a, b) in enumerate(zip(edges, edges[1:])):
                    own = ids[4 * a : 4 * b]
                    rows.append((doc_id, k, a, b - a, zlib.crc32(own)) + ((np.frombuffer(own, dtype="<u4").astype(np.int32),) if with_ids else ()))
            columns = list(zip(*rows)) or [[]] * (5 + with_ids)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names[: len(columns)])

    return common.texts_of(docs).mapInArrow(cut, schema)


def pack(pieces: DataFrame, capacity: int = CAPACITY, order: tuple[str, ...] = ("doc_id", "piece")) -> DataFrame:
    """pieces, which have a `length` from 1 to capacity, with their sequence_id and offset."""
    spark = pieces.sparkSession
    pieces = common.written(pieces, "pieces") if pieces.isStreaming is False else pieces
    schema = T.StructType([*pieces.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType()), T.StructField("fill", T.LongType())])

    def dealt(df: DataFrame, round_no: int) -> tuple[DataFrame, int]:
        groups = max(1, math.ceil(df.count() / PIECES_PER_GROUP))
        return df.withColumn("pack_group", F.pmod(F.xxhash64(*order, F.lit(round_no)), F.lit(groups)).cast("long")), groups

    def packer(base: int):
        def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
            rows = rows.sort_values(list(order), kind="stable", ignore_index=True).drop(columns="pack_group")
            sequence, offset = sum_of_squares(rows["length"].to_numpy(), capacity)
            fill = np.bincount(sequence, weights=rows["length"])
            return rows.assign(sequence_id=(base + int(key[0]) << 28) + sequence, offset=offset, fill=fill[sequence].astype(np.int64))

        return one

    first, groups = dealt(pieces, 0)
    first = common.written(first.groupBy("pack_group").applyInPandas(packer(0), schema), "packed")
    if groups == 1:
        return first.drop("fill")
    enough = math.floor(capacity * FULL_ENOUGH)
    again, _ = dealt(first.where(F.col("fill") < enough).select(*pieces.columns), 1)
    second = again.groupBy("pack_group").applyInPandas(packer(groups), schema)
    return first.where(F.col("fill") >= enough).unionByName(second).drop("fill")


def sequences(packed: DataFrame) -> DataFrame:
    """(sequence_id, ids) of packed pieces that carry their ids; at most `capacity` ids a row."""
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(F.flatten(F.transform(parts, lambda p: p["ids"])).alias("ids"))


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(token_pieces(common.read_table(spark, sf_dir, "documents")))
