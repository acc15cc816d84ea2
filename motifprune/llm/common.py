"""Helpers shared by the operators: table access, shared storage, cached tokenizing."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
from array import array
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DOCUMENT_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts_of(docs: DataFrame) -> DataFrame:
    """(doc_id, text) of a documents table; a null text reads as empty, other columns are left out."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset."""
    sc = spark.sparkContext
    got = sc._jsc.sc().getCheckpointDir()
    if got.isDefined():
        return got.get()
    named = sc.getConf().get("spark.checkpoint.dir")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="motifprune_"))
    return sc._jsc.sc().getCheckpointDir().get()


def shared_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, deleted when the application ends."""
    path = f"{shared_folder(spark)}/tables/{tag}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    return path


def written(df: DataFrame, tag: str) -> DataFrame:
    """df as a written table in the shared folder: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = shared_path(spark, tag)
    schema = df.schema
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(schema).parquet(path)


def sliced(batches, rows: int = 512):
    """The batches in slices of some rows, so that a worker holds few texts as Python objects; gives memory back after each batch."""
    for batch in batches:
        for lo in range(0, max(1, batch.num_rows), rows):
            yield batch.slice(lo, rows)
        give_back()


def give_back() -> None:
    """Returns memory that this worker has freed to the system, which else keeps what its largest batch took."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def removed(spark: SparkSession, path: str) -> None:
    """Deletes a written table that nothing reads any more."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def swept(spark: SparkSession) -> None:
    """Lets the driver collect its garbage now, which frees the shuffle files of finished steps that nothing holds."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def remainder_of(doc_id, modulus: int):
    """crc32 of the id's decimal text modulo `modulus`: how labelled rows are held out."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(modulus))


_LETTERS, _SIGNS = "A-Za-zÀ-ÖØ-öø-ÿ", ".,;:!?&%$#*|"
#: A piece that these parts cover is cut into its words by them just as the word-level vocabulary's own pattern does.
_PLAIN_PART = re.compile(rf"[{_LETTERS}]+|[{_SIGNS}]+")
#: White space to Python alone, or to the vocabulary's pattern alone.
_ODD_SPACE = re.compile("[\x1c-\x1f\u200b\ufeff]")
_LONGEST = 64
CACHE_BYTES, ENTRY_BYTES = 128 << 20, 160  # a worker's room for ids met, and what an entry takes beside its letters and ids


def _byte_letters() -> dict[int, str]:
    """The letter by which byte-level vocabularies write each byte: printable ones as they are, the rest from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)}


def tokenizer(file: str):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path(file))
    tok.encode_special_tokens = True
    return tok


class ByteEncoder:
    """Ids of a byte-level vocabulary of the tokenizers library, by tiktoken's faster merging of the same ranks.

    Ids of such a vocabulary ascend with the merges, so they serve as ranks. Texts with lone surrogates
    go through the tokenizers library itself.
    """

    def __init__(self, file: str) -> None:
        import json

        import public_tokenizers
        import tiktoken

        with open(public_tokenizers.path(file), encoding="utf-8") as f:
            own = json.load(f)
        byte_of = {c: b for b, c in _byte_letters().items()}
        special = {t["id"] for t in own.get("added_tokens", [])}
        ranks = {bytes(byte_of[c] for c in word): k for word, k in own["model"]["vocab"].items() if k not in special}
        self._encode = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_to_numpy

    def ids_bytes(self, text: str) -> bytes:
        """The text's ids as little-endian unsigned 32-bit bytes."""
        return self._encode(text, disallowed_special=()).astype("<u4", copy=False).tobytes()


class _Pieces(dict):
    """piece -> ids as little-endian 32-bit bytes; filled on demand, bounded by `room` bytes."""

    def __init__(self, encode, room: int) -> None:
        super().__init__()
        self.encode, self.room = encode, room

    def __missing__(self, piece: str) -> bytes:
        out = self.encode(piece)
        if self.room > 0 and len(piece) < _LONGEST:
            self.room -= len(piece) + len(out) + ENTRY_BYTES
            self[piece] = out
        return out


class WordEncoder:
    """Ids of a word-level vocabulary that drops white space, keeping the ids of pieces met.

    No word of such a vocabulary reaches across white space, so a text's ids are those of its pieces in turn.
    Pieces of plain Latin letters and signs go to the vocabulary's model word by word, all others through the
    whole tokenizer.
    """

    def __init__(self, file: str, room: int = CACHE_BYTES) -> None:
        self._tok = tokenizer(file)
        self._model = self._tok.model
        self._model._resize_cache(0)
        self._letters = _byte_letters()
        self._words = _Pieces(self._word, room // 2)
        self._pieces = _Pieces(self._piece, room // 2)

    def _word(self, word: str) -> bytes:
        return array("I", [t.id for t in self._model.tokenize(word.encode().decode("latin-1").translate(self._letters))]).tobytes()

    def _piece(self, piece: str) -> bytes:
        if len(piece) < _LONGEST:
            stem = piece.rstrip(_SIGNS)
            if stem.isalpha() and stem.isascii():
                return self._words[stem.lower()] + (self._words[piece[len(stem) :]] if len(stem) < len(piece) else b"")
            parts = _PLAIN_PART.findall(piece)
            if sum(map(len, parts)) == len(piece):
                return b"".join([self._words[p.lower()] for p in parts])
        return array("I", self._tok.encode(piece, add_special_tokens=False).ids).tobytes()

    def ids_bytes(self, text: str) -> bytes:
        """The text's ids as little-endian unsigned 32-bit bytes."""
        if _ODD_SPACE.search(text):
            return array("I", self._tok.encode(text, add_special_tokens=False).ids).tobytes()
        return b"".join(map(self._pieces.__getitem__, text.split()))


def CachedEncoder(file: str, *, space_kept: bool) -> ByteEncoder | WordEncoder:  # noqa: N802
    """The encoder of a byte-level vocabulary, which keeps white space, or of a word-level one."""
    return ByteEncoder(file) if space_kept else WordEncoder(file)


@lru_cache(maxsize=1)
def encoder(file: str, space_kept: bool) -> ByteEncoder | WordEncoder:
    """One encoder for each Python worker, which Spark reuses between tasks."""
    return CachedEncoder(file, space_kept=space_kept)
