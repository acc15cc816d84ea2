"""Language identification with a string kernel.

Two texts are as alike as the n-grams they both hold: the blended-spectrum presence kernel counts the
shared n-grams of 1 to 4 characters (hashed to a fixed number of cells), normalised by both texts'
counts. Kernel ridge regression, one language against the rest, is fitted on Nyström landmarks. Since
the kernel is linear in presence cells, landmarks and coefficients fold into one matrix of cells by
languages, and a batch of whole texts is scored by one product with it.

The model is fitted on a sample of at most TRAIN_ROWS labelled rows, dealt evenly to the languages by a
hash of the id (the LANGUAGES most frequent ones are learnt; of the rest no row is in the sample); every text is scored
whole, however long.

Defined results: a text that is null or has no letter is `und` with score 0, and so is any text if there
is nothing to learn from; rows whose lang is null teach nothing; ties go to the language first in
alphabetical order; repeated rows are scored alike; columns beside doc_id, text and lang are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifprune.llm import common

CELL_BITS, ORDERS = 15, (1, 2, 3, 4)
TRAIN_ROWS, LANDMARKS, LANGUAGES, RIDGE, SHARPNESS, FIT_ROWS = 2400, 160, 200, 1e-4, 4.0, 128
UNKNOWN = "und"
_LETTER = re.compile(r"[^\W\d_]")
_FACTORS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], dtype=np.uint32)


def presence(text: str, bits: int = CELL_BITS) -> np.ndarray:
    """The cells (booleans) of the n-grams that the lower-cased text holds."""
    cells = np.zeros(1 << bits, dtype=bool)
    points = np.frombuffer(text.lower().encode("utf-32-le", "replace"), dtype="<u4")
    mixed = np.zeros(len(points), dtype=np.uint32)
    for k in ORDERS:
        if len(points) < k:
            break
        mixed = (mixed[: len(points) - k + 1] ^ points[k - 1 :]) * _FACTORS[k - 1]
        mixed ^= mixed >> np.uint32(15)
        cells[(mixed * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - bits)] = True
    return cells


@dataclass(frozen=True)
class KernelModel:
    languages: tuple[str, ...]
    weights: np.ndarray  # cells x languages

    def margins(self, cells: np.ndarray) -> np.ndarray:
        """Texts x languages, of presence cells given as texts x cells."""
        norms = np.sqrt(np.maximum(1, cells.sum(axis=1, dtype=np.float32)))
        return (cells.astype(np.float32) @ self.weights) / norms[:, None]


def _unit(packed: list[bytes]) -> np.ndarray:
    """Rows of unit length of packed presence cells."""
    rows = np.unpackbits(np.frombuffer(b"".join(packed), dtype=np.uint8).reshape(len(packed), -1), axis=1).astype(np.float32)
    return rows / np.sqrt(np.maximum(1, rows.sum(axis=1, keepdims=True)))


def fit_kernel(packed: list[bytes], langs: list[str], landmarks: int = LANDMARKS, ridge: float = RIDGE) -> KernelModel:
    """packed: packed presence cells of each text; the first texts of each language in turn serve as landmarks.

    Cells are unpacked FIT_ROWS texts at a time, so the driver holds landmarks and kernel values only.
    """
    names = tuple(sorted(set(langs)))
    label = np.array([names.index(x) for x in langs])
    chosen = np.concatenate([np.flatnonzero(label == k)[: max(1, landmarks // len(names))] for k in range(len(names))])
    marks = _unit([packed[k] for k in chosen])
    across = np.concatenate([_unit(packed[a : a + FIT_ROWS]) @ marks.T for a in range(0, len(packed), FIT_ROWS)]).astype(np.float64)
    among = (marks @ marks.T).astype(np.float64)
    target = np.where(label[:, None] == np.arange(len(names)), 1.0, -1.0)
    balance = (1 / np.bincount(label, minlength=len(names)))[label][:, None]  # each language weighs the same
    left = across.T @ (across * balance) + ridge * (among + 1e-6 * np.eye(len(chosen)))
    alpha = np.linalg.lstsq(left, across.T @ (target * balance), rcond=None)[0].astype(np.float32)
    return KernelModel(names, marks.T @ alpha)


def train(docs: DataFrame, rows: int = TRAIN_ROWS) -> KernelModel | None:
    """Fits on labelled rows of docs (doc_id, text, lang); None if there are none."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = labelled.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(LANGUAGES).collect()
    if not counts:
        return None
    each = max(1, rows // len(counts))
    spread = F.pmod(F.xxhash64("doc_id", F.lit(10)), F.lit(1 << 30))
    share = F.lit(0)
    for r in counts:
        share = F.when(F.col("lang") == r["lang"], min(1 << 30, (each << 30) // r["count"] + 1)).otherwise(share)

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.sliced(batches):
            cells = [np.packbits(presence(t)).tobytes() for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(cells, pa.binary())], ["order", "lang", "cells"])

    picked = labelled.where(spread < share).select(spread.alias("order"), "lang", "text")
    got = sorted((r["order"], r["lang"], bytes(r["cells"])) for r in picked.mapInArrow(packed, "order long, lang string, cells binary").collect())[:rows]
    if not got:
        return None
    return fit_kernel([c for _, _, c in got], [x for _, x, _ in got])


def predict(docs: DataFrame, model: KernelModel | None, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns `keep` of every row, with lang_pred and score."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in common.sliced(batches):
            texts = batch.columns[at_text].to_pylist()
            langs, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
            known = [k for k, t in enumerate(texts) if m and t and _LETTER.search(t)]
            for a in range(0, len(known), 128):
                at = known[a : a + 128]
                margins = m.margins(np.stack([presence(texts[k]) for k in at]))
                odds = np.exp(SHARPNESS * (margins - margins.max(axis=1, keepdims=True)))
                for k, best, share in zip(at, margins.argmax(axis=1), odds.max(axis=1) / odds.sum(axis=1)):
                    langs[k], scores[k] = m.languages[best], share
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(langs, pa.string()), pa.array(scores)], [*keep, "lang_pred", "score"])

    rows = docs.select(*keep) if "text" in keep else docs.select(*keep, F.col("text").alias("text_scored"))
    at_text = keep.index("text") if "text" in keep else len(keep)
    return rows.mapInArrow(scored, T.StructType([*rows.schema.fields[: len(keep)], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read_table(spark, sf_dir, "documents")
    held_out = common.remainder_of(F.col("doc_id"), 4) == 2
    model = train(docs.where(~held_out).select("doc_id", "text", "lang"))
    return predict(docs, model).withColumn("held_out", held_out)
