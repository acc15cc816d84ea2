"""Benchmark decontamination by latent semantic retrieval.

Texts are cut into words once and written as numbers of the benchmark's words. Corpus passages are TF-IDF vectors
over the benchmark's terms, with document frequencies counted over the whole corpus; words of more than COMMON_SHARE of
the documents are no terms but for each item's rarest. The passages' Gram matrix is sketched in one distributed pass
(each partition multiplies its passages with a random test matrix and back), together with the benchmark's own
passages, and a Nyström eigendecomposition of the sketch gives the singular directions. Directions of items that the
leading ones capture badly are appended, so no item is lost to truncation. Overlapping windows of every whole text are
folded into that space, as sums of the folded strides that they are made of; a window whose cosine with an item reaches
MIN_COSINE is a candidate. So is, whatever its cosine, each place where SEED words of an item stand in a row, so no
verbatim copy is lost to terms that are common in the corpus; such a row's cosine is null if no window found it. A
candidate counts as a leak if the longest common subsequence of words covers SAME of the item within a span not
much longer than the item, or PARAPHRASE of it and the item's answer (its last sentence) stands there
word for word.

All items share one space as long as they have at most BLOCK_WORDS words and BLOCK_ITEMS items; a larger benchmark is
handled in blocks of that size, so what the driver holds and broadcasts is bounded.

Defined results: null and empty texts match nothing; items without words are skipped; items shorter
than 5 words must occur word for word; repeated documents each give their rows; an item that repeats in a
document gives one row, the best; texts of any length are searched whole; empty tables give no rows; columns beside
the ids and texts are not read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.llm import common

RANK, EXTRA, PASSAGE, BLOCK_ITEMS, BLOCK_WORDS = 96, 8, 64, 1024, 200_000
COMMON_SHARE, LEAST_COMMON, OWN_TERMS = 0.1, 5, 8
STRIDE, SHORT_ITEM, WINDOWS = 16, 24, ((3, 1), (6, 2))  # (strides, steps) for items up to SHORT_ITEM words, and for others
MIN_COSINE, SAME, PARAPHRASE, CAPTURED, SEED = 0.3, 0.8, 0.6, 0.5, 4
HITS = "doc_id long, item_id long, at_word long, cosine double, covered double, answer_found boolean"
_WORD = re.compile(r"\w+")
_SENTENCE = re.compile(r"(?<=[.!?])\s+|\n")


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def covered(item: list[int], region: list[int]) -> int:
    """Length of the longest common subsequence, by bit-parallel rows."""
    where: dict[int, int] = {}
    for k, w in enumerate(item):
        where[w] = where.get(w, 0) | 1 << k
    return len(item) - _unmet(where, len(item), region)


def _unmet(where: dict[int, int], n: int, region: list[int]) -> int:
    full = (1 << n) - 1
    row = full
    for w in region:
        m = where.get(w)
        if m:
            u = row & m
            row = ((row + u) | (row - u)) & full
    return row.bit_count()


def within(part: list, whole: list) -> bool:
    """Whether part stands in whole word for word."""
    n = len(part)
    return n > 0 and any(whole[k : k + n] == part for k, w in enumerate(whole[: len(whole) - n + 1]) if w == part[0])


@dataclass(frozen=True)
class Item:
    item_id: int
    words: tuple[str, ...]
    answer: tuple[str, ...]


def items_of(rows: list) -> list[Item]:
    out = []
    for item_id, text in rows:
        words = words_of(text or "")
        if words:
            last = [w for s in _SENTENCE.split(text.strip()) if (w := words_of(s))][-1]
            out.append(Item(item_id, tuple(words), tuple(last)))
    return out


@dataclass(frozen=True)
class Target:
    """An item's words as numbers."""

    words: list[int]
    answer: list[int]
    where: dict[int, int]  # bits of the places of each word


def target_of(item: Item, every: dict[str, int]) -> Target:
    words = [every[w] for w in item.words]
    where: dict[int, int] = {}
    for k, w in enumerate(words):
        where[w] = where.get(w, 0) | 1 << k
    return Target(words, [every[w] for w in item.answer], where)


def best_cover(item: Target, words: list[int], lo: int) -> tuple[float, int, bool]:
    """(share of the item covered, where, whether its answer is there) over spans of `words`, which stand at lo."""
    n = len(item.words)
    if n < 5:
        ok = within(item.words, words)
        return (1.0 if ok else 0.0), lo, ok
    met = 0
    for w in set(words):
        met |= item.where.get(w, 0)
    if met.bit_count() < PARAPHRASE * n:  # no subsequence can be longer than that
        return 0.0, lo, False
    span, step = n + n // 2 + 1, max(1, n // 4)
    most, where = 0, 0
    for a in range(0, max(1, len(words) - n // 2), step):
        got = n - _unmet(item.where, n, words[a : a + span])
        if got > most:
            most, where = got, a
    return most / n, lo + where, within(item.answer, words[where : where + span])


@dataclass(frozen=True)
class Latent:
    """Terms, their weighted directions, and the items folded into these."""

    every: dict[str, int]  # numbers of all items' words
    term_of: np.ndarray  # of each word's number: its term, or -1
    axes: np.ndarray  # terms x directions, times the terms' weights
    items: list[Item]
    targets: list[Target]
    folded: np.ndarray  # items x directions, unit rows
    padded: np.ndarray  # items x words of the longest item
    sizes: np.ndarray  # words of each item
    seeds: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=dict)  # by length: keys ascending, words, items, places


def _padded(targets: list[Target]) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.array([len(t.words) for t in targets])
    out = np.zeros((len(targets), sizes.max()), dtype=np.int32)
    for row, t in zip(out, targets):
        row[: len(t.words)] = t.words
    return out, sizes


_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def _runs(ids: np.ndarray, n: int) -> np.ndarray:
    """A key of each run of n numbers."""
    key = np.zeros(max(0, len(ids) - n + 1), dtype=np.uint64)
    for j in range(n):
        key = (key ^ (ids[j : len(ids) - n + 1 + j].astype(np.int64).view(np.uint64) + np.uint64(1))) * _MULTIPLIER
        key ^= key >> np.uint64(29)
    return key


def seeds_of(targets: list[Target]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    found: dict[int, list[tuple]] = {}
    for k, t in enumerate(targets):
        n = min(SEED, len(t.words))
        words = np.array(t.words, dtype=np.int32)
        found.setdefault(n, []).extend(zip(_runs(words, n).tolist(), [k] * len(words), range(len(words))))
    out = {}
    for n, rows in found.items():
        key, item, place = (np.array(c, dtype=d) for c, d in zip(zip(*sorted(rows)), (np.uint64, np.int64, np.int64)))
        different, first = np.unique(key, return_index=True)
        out[n] = (different, np.append(first, len(key)), item, place)
    return out


def _sums(rows: np.ndarray, n: int, term: np.ndarray, w: np.ndarray | None, axes: np.ndarray) -> np.ndarray:
    """n x directions: the sum of axes[term] (times w) over each row's entries; rows ascend.

    The first entries of all rows are set at once, then the second ones are added, and so on.
    """
    out = np.zeros((n, axes.shape[1]), dtype=np.float32)
    starts = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
    sizes = np.diff(np.append(starts, len(rows)))
    order = np.argsort(-sizes, kind="stable")
    starts, sizes = starts[order], sizes[order]
    for j in range(sizes[0]):
        at = starts[: np.searchsorted(-sizes, -j, "left")] + j
        part = axes[term[at]]
        if w is not None:
            part *= w[at, None]
        out[rows[at]] += part
    return out


def numbered(texts: DataFrame, every: dict[str, int]) -> DataFrame:
    """(doc_id, words): each text's words as numbers, -1 for words of no item."""
    shared = texts.sparkSession.sparkContext.broadcast(every)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = shared.value.get
        for part in common.sliced(batches, 128):
            words = [words_of(t) for t in part.column(1).to_pylist()]
            ends = np.cumsum([0, *map(len, words)], dtype=np.int32)
            ids = np.fromiter((number(w, -1) for t in words for w in t), dtype=np.int32, count=ends[-1])
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(ids))], ["doc_id", "words"])

    return texts.mapInArrow(cut, "doc_id long, words array<int>")


def _flat(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """(all numbers, where each list starts, and the end)."""
    edges = column.offsets.to_numpy()
    return column.values.to_numpy(zero_copy_only=False)[edges[0] : edges[-1]], edges - edges[0]


def document_frequencies(words: DataFrame, n_words: int) -> tuple[np.ndarray, int]:
    """In how many documents each word occurs, and the number of documents."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, np.zeros(n_words, dtype=np.int64)
        for batch in batches:
            ids, edges = _flat(batch.column(0))
            n += batch.num_rows
            at = np.flatnonzero(ids >= 0)
            doc = np.searchsorted(edges, at, "right")
            total += np.bincount(np.unique(doc * n_words + ids[at]) % n_words, minlength=n_words)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(total[some], n))], ["term", "n"])

    got = words.select("words").mapInArrow(counted, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    by = {r["term"]: r["n"] for r in got}
    return np.array([by.get(k, 0) for k in range(n_words)]), by.get(-1, 0)


def gram_sketch(words: DataFrame, term_of: np.ndarray, idf: np.ndarray, test: np.ndarray) -> np.ndarray:
    """AᵀA times the test matrix, A being the unit TF-IDF rows of all passages."""
    shared = words.sparkSession.sparkContext.broadcast((term_of, idf, test))
    block = 256

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, weights, omega = shared.value
        total = np.zeros_like(omega)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                ids, edges = _flat(batch.column(0).slice(lo, 256))
                at, term, doc = _terms(ids, edges, known)
                if not len(at):
                    continue
                first = np.concatenate([[0], np.cumsum(np.diff(edges) // PASSAGE + 1)])
                row, term, w = _vectors(term, first[doc] + (at - edges[doc]) // PASSAGE, weights)
                y = _sums(row, int(row[-1]) + 1, term, w, omega)
                order = np.argsort(term, kind="stable")
                total += _sums(term[order], len(total), row[order], w[order], y)
        parts = [(k, total[a : a + block].tobytes()) for k, a in enumerate(range(0, len(total), block)) if total[a : a + block].any()]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in parts], pa.int64()), pa.array([b for _, b in parts], pa.binary())], ["block", "part"])

    def added(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        total = sum(np.frombuffer(b, dtype=np.float32).astype(np.float64) for b in rows["part"])
        return pd.DataFrame({"block": [key[0]], "part": [total.astype(np.float32).tobytes()]})

    parts = words.select("words").mapInArrow(sketched, "block long, part binary").withColumn("some", F.spark_partition_id() % 64)
    some = parts.groupBy("block", "some").applyInPandas(added, "block long, part binary")  # in two steps, so that none adds up all
    out = np.zeros_like(test)
    for r in some.groupBy("block").applyInPandas(added, "block long, part binary").collect():
        part = np.frombuffer(bytes(r["part"]), dtype=np.float32).reshape(-1, test.shape[1])
        out[r["block"] * block : r["block"] * block + len(part)] = part
    return out


def _terms(ids: np.ndarray, edges: np.ndarray, term_of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place, term, text number) of each occurrence of a term."""
    term = np.append(term_of, -1)[ids]  # a word of no item is numbered -1
    at = np.flatnonzero(term >= 0)
    return at, term[at], np.searchsorted(edges, at, "right") - 1


def _vectors(term: np.ndarray, rows: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """TF-IDF entries (row, term, weight) of unit rows, from term occurrences in ascending rows."""
    pair, tf = np.unique(rows * len(idf) + term, return_counts=True)
    row, term = pair // len(idf), pair % len(idf)
    w = idf[term] * tf
    norm = np.sqrt(np.bincount(row, w * w, int(row[-1]) + 1))
    return row, term, (w / norm[row]).astype(np.float32)


def word_numbers(items: list[Item]) -> dict[str, int]:
    return {w: k for k, w in enumerate(sorted({w for i in items for w in i.words}))}


def fit_latent(docs: DataFrame, items: list[Item], rank: int = RANK, words: DataFrame | None = None) -> Latent:
    """The space of items over docs (doc_id, text); words: docs as numbered() gives them, where that is written already."""
    every = word_numbers(items)
    words = numbered(docs.select("doc_id", "text"), every) if words is None else words
    df, n = document_frequencies(words, len(every))
    chosen = df <= max(LEAST_COMMON, COMMON_SHARE * n)
    names = list(every)
    targets = [target_of(i, every) for i in items]
    for t in targets:  # an item of common words keeps its rarest
        chosen[sorted(set(t.words), key=lambda k: (df[k], names[k]))[:OWN_TERMS]] = True
    term_of = np.where(chosen, np.cumsum(chosen) - 1, -1).astype(np.int64)
    idf = np.log((2 + n) / (1 + df[chosen]))

    flat, edges = np.concatenate([np.array(t.words) for t in targets]), np.cumsum([0, *(len(t.words) for t in targets)])
    _, term, row = _terms(flat, edges, term_of)
    row, term, w = _vectors(term, row, idf)
    b = np.zeros((len(items), len(idf)), dtype=np.float32)
    b[row, term] = w

    size = min(len(idf), rank + EXTRA)
    test = np.linalg.qr(np.random.default_rng(2).standard_normal((len(idf), size)))[0].astype(np.float32)
    corpus = gram_sketch(words, term_of, idf, test).astype(np.float64)
    mine = b.T.astype(np.float64) @ (b @ test)
    sketch = corpus + mine * max(1.0, np.linalg.norm(corpus) / max(1e-12, np.linalg.norm(mine)))
    shift = 1e-9 * np.linalg.norm(sketch) + 1e-12
    shifted = sketch + shift * test
    core = test.T @ shifted
    strengths, turns = np.linalg.eigh((core + core.T) / 2)
    sound = strengths > 1e-8 * max(1e-300, strengths.max())
    axes, _, _ = np.linalg.svd(shifted @ (turns[:, sound] / np.sqrt(strengths[sound])), full_matrices=False)
    axes = axes[:, :rank]
    rest = b - (b @ axes) @ axes.T  # what the leading directions miss of each item
    bad = rest[(rest**2).sum(axis=1) > 1 - CAPTURED].T
    if bad.shape[1]:
        more, strength, _ = np.linalg.svd(bad, full_matrices=False)
        axes = np.hstack([axes, more[:, strength > 1e-3]])
    folded = b @ axes
    folded /= np.maximum(1e-9, np.linalg.norm(folded, axis=1))[:, None]
    return Latent(every, term_of, (axes * idf[:, None]).astype(np.float32), items, targets, folded.astype(np.float32), *_padded(targets), seeds_of(targets))


def leaks_of(words: list[str], m: Latent) -> list[tuple[int, int, float | None, float, bool]]:
    """(item number, word, cosine, covered share, answer found) of each item that the text holds."""
    ids = np.array([m.every.get(w, -1) for w in words], dtype=np.int32)
    return [hit for _, *hit in search(ids, np.array([0, len(ids)]), m)]


def search(ids: np.ndarray, edges: np.ndarray, m: Latent) -> list[tuple]:
    """(text number, item number, word, cosine, covered share, answer found) of each item that a text holds; text k is ids[edges[k] : edges[k + 1]]."""
    best: dict[tuple[int, int], tuple] = {}
    _by_windows(ids, edges, m, best)
    _by_seeds(ids, edges, m, best)
    return [(*k, *v) for k, v in sorted(best.items())]


def _tried(ids: np.ndarray, edges: np.ndarray, m: Latent, best: dict, doc: int, k: int, lo: int, hi: int, cosine: float | None) -> None:
    """Keeps the best cover of item k within words lo to hi of a text, if it is a leak and better than what is known."""
    start, end = int(edges[doc]), int(edges[doc + 1])
    lo, hi = max(0, lo), min(end - start, hi)
    share, where, answered = best_cover(m.targets[k], ids[start + lo : start + hi].tolist(), lo)
    if (share >= SAME or share >= PARAPHRASE and answered) and ((doc, k) not in best or share > best[doc, k][2]):
        best[doc, k] = (where, cosine if cosine is not None or (doc, k) not in best else best[doc, k][1], share, answered)


def _by_seeds(ids: np.ndarray, edges: np.ndarray, m: Latent, best: dict) -> None:
    """Adds to best what stands around each run of SEED words of an item (of all its words, if they are fewer)."""
    tried = set()
    for n, (keys, firsts, items, places) in m.seeds.items():
        runs = _runs(ids, n)
        at = np.minimum(np.searchsorted(keys, runs), len(keys) - 1)
        for p in np.flatnonzero(keys[at] == runs).tolist():
            doc = int(np.searchsorted(edges, p, "right")) - 1
            for row in range(firsts[at[p]], firsts[at[p] + 1]):
                k = int(items[row])
                start = p - int(edges[doc]) - int(places[row])
                if (doc, k, start) in tried or (doc, k) in best and best[doc, k][2] == 1:
                    continue
                tried.add((doc, k, start))
                size = len(m.targets[k].words)
                _tried(ids, edges, m, best, doc, k, start - size // 2, start + 2 * size + 1, None)


def _by_windows(ids: np.ndarray, edges: np.ndarray, m: Latent, best: dict) -> None:
    at, term, doc = _terms(ids, edges, m.term_of)
    if not len(at):
        return
    longest = max(strides for strides, _ in WINDOWS)
    sizes = np.diff(edges)
    first = np.concatenate([[0], np.cumsum((sizes + STRIDE - 1) // STRIDE + longest)])  # of each text's strides; empty ones part the texts
    strides = _sums(first[doc] + (at - edges[doc]) // STRIDE, int(first[-1]), term, None, m.axes)
    present = _present(ids, edges, first, len(m.every))
    long_item = np.array([len(t.words) > SHORT_ITEM for t in m.targets])
    for kind, (width, step) in enumerate(WINDOWS):
        chosen = np.flatnonzero(long_item == bool(kind))
        if not len(chosen):
            continue
        # Every step-th stride of a text starts a window, up to the first window that reaches its end.
        count = np.maximum(0, -(-(sizes - width * STRIDE) // (step * STRIDE))) + 1
        text = np.repeat(np.arange(len(sizes)), count)
        place = (np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)) * step
        own = first[text] + place
        window = sum(strides[j : len(strides) - width + 1 + j] for j in range(width))[own]
        cosine = (window @ m.folded[chosen].T) / np.maximum(1e-9, np.sqrt(np.einsum("ij,ij->i", window, window)))[:, None]
        r, c = np.nonzero(cosine >= MIN_COSINE)
        enough = _may_cover(present, own[r], chosen[c], width, m)
        for r, c in zip(r[enough].tolist(), c[enough].tolist()):
            k, start = int(chosen[c]), int(place[r]) * STRIDE
            size = len(m.targets[k].words)
            _tried(ids, edges, m, best, int(text[r]), k, start - size // 2, start + width * STRIDE + size // 2, float(cosine[r, c]))


def _present(ids: np.ndarray, edges: np.ndarray, first: np.ndarray, n_words: int) -> np.ndarray:
    """Bits of the words that each stride holds: strides x bytes."""
    size = -(-n_words // 8)
    at = np.flatnonzero(ids >= 0)
    doc = np.searchsorted(edges, at, "right") - 1
    cell = (first[doc] + (at - edges[doc]) // STRIDE) * size + (ids[at] >> 3)
    bits = np.zeros(first[-1] * size, dtype=np.uint8)
    np.bitwise_or.at(bits, cell, np.left_shift(1, ids[at] & 7).astype(np.uint8))
    return bits.reshape(-1, size)


def _may_cover(present: np.ndarray, own: np.ndarray, item: np.ndarray, width: int, m: Latent) -> np.ndarray:
    """Whether the words around the windows that start at strides `own` hold PARAPHRASE of their item's words in any order."""
    out = np.zeros(len(own), dtype=bool)
    beside = -(-m.sizes // 2 // STRIDE) + 1
    for more in np.unique(beside[item]):
        some = np.flatnonzero(beside[item] == more)
        windows, at = np.unique(own[some], return_inverse=True)
        near = np.zeros((len(windows), present.shape[1]), dtype=np.uint8)
        for j in range(-more, width + more):
            near |= present[np.clip(windows + j, 0, len(present) - 1)]
        for lo in range(0, len(some), 20_000):
            part, rows = some[lo : lo + 20_000], at[lo : lo + 20_000, None]
            words = m.padded[item[part]]
            met = near[rows, words >> 3] >> (words & 7) & 1
            met &= np.arange(words.shape[1]) < m.sizes[item[part], None]
            out[part] = met.sum(axis=1) >= np.where(m.sizes[item[part]] < 5, 1, PARAPHRASE) * m.sizes[item[part]] - 1e-9
    return out


def item_blocks(rows: list[tuple[int, str]]) -> list[list[Item]]:
    """The items in blocks of at most BLOCK_ITEMS items and BLOCK_WORDS words (an item above that is a block of its own)."""
    out, held = [], BLOCK_WORDS + 1
    for item in items_of(sorted(rows)):
        held += len(item.words)
        if held > BLOCK_WORDS or len(out[-1]) == BLOCK_ITEMS:
            out.append([])
            held = len(item.words)
        out[-1].append(item)
    return out


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """HITS rows: a document and an item that it holds."""
    spark = docs.sparkSession
    texts = common.texts_of(docs)
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text IS NOT NULL")
    out = spark.createDataFrame([], HITS)
    passes = math.ceil(items.agg(F.coalesce(F.sum(F.greatest(F.lit(1), F.length("text") / 8)), F.lit(0))).first()[0] / BLOCK_WORDS) or 1
    for k in range(passes):  # the driver holds a part of a large benchmark at a time
        own = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(passes)) == k) if passes > 1 else items
        for block in item_blocks([(r["item_id"], r["text"]) for r in own.collect()]):
            words = common.written(numbered(texts, word_numbers(block)), "words")
            out = out.union(_hits(words, fit_latent(texts, block, words=words)))
    return out


def _hits(words: DataFrame, model: Latent) -> DataFrame:
    shared = words.sparkSession.sparkContext.broadcast(model)

    def searched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for part in common.sliced(batches, 256):
            names = part.column(0).to_pylist()
            rows = [(names[doc], m.items[k].item_id, *rest) for doc, k, *rest in search(*_flat(part.column(1)), m)]
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [[]] * 6, kinds)], [f.split(" ")[0] for f in HITS.split(", ")])

    return words.select("doc_id", "words").mapInArrow(searched, HITS)


def op2_latent_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(common.read_table(spark, sf_dir, "documents"), common.read_table(spark, sf_dir, "benchmark"))
