"""Near-duplicate detection by SetSketch registers.

A document's set of five-word shingles is summarised in registers: each shingle draws exponentially
spaced ascending points, each point falls into another register, and a register keeps the truncated
logarithm of its least point. Registers of unions are the maxima of registers, and two sets agree in a
register about as often as they share elements, so bands of registers find candidates: with 42 bands of
6 (51 of 5 below 85 percent) a pair at the threshold shares none with probability below 3e-9. Within a bucket, a
joint maximum likelihood estimate of the similarity from the sets' sizes and the registers' order (above, below,
equal) removes pairs far below the threshold, and what remains is confirmed on the full sets.

Equal sets are one vertex. Buckets are cut into blocks of bounded size. A spanning forest of each block's
plausible pairs, first of some bands and then of what these leave apart, is confirmed first, so that a large group of copies is joined by few tests. Members of a large bucket
outside its main component then meet all of its blocks, two blocks at a time. What plausible pairs connect is
a group; groups that are not one component yet are tested whole: cut into blocks of bounded size, each pair of
blocks compares its full sets in one task and tells only links that join components. So no link between different
texts is lost, no group's pairs are emitted, and no task holds more than two blocks.

Defined results: null and empty texts have the empty set and stand alone; texts under five words have
one shingle; rows with equal ids are separate rows of one component if their sets link; an empty table
yields no rows; columns beside doc_id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.llm import common
from motifprune.llm.components import components

WORDS, PERCENT = 5, 85
REGISTERS, BASE, RATE, TOP = 256, 1.001, 20.0, 65534
BLOCK, DEVIATIONS, FILTER_BITS, FILTER_PART = 1024, 7.0, 27, 15
TEST_ROWS, TEST_HASHES = 256, 100_000  # of a block whose full sets are compared
FIRST_BANDS = 8
KEPT_WORDS = 150_000  # about 30 MB in each worker
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every bit of the result depends on every bit of x."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        if len(self) < KEPT_WORDS and len(word) < 64:
            self[word] = h
        return h


_HASHES = _WordHashes()


def shingles(text: str, width: int = WORDS) -> np.ndarray:
    """Sorted 64-bit hashes of the text's different shingles of `width` words (ASCII letters lower-cased)."""
    words = text.encode("utf-8", "replace").lower().split()
    h = np.fromiter(map(_HASHES.__getitem__, words), dtype=np.uint64, count=len(words))
    if not len(h):
        return h
    n = max(1, len(h) - width + 1)
    total = np.full(n, min(len(h), width), dtype=np.uint64)
    for k in range(min(width, len(h))):
        total += mix(h[k : k + n] * _ODD[k % 5] + np.uint64(k))
    return np.unique(mix(total))


def registers(sets: list[np.ndarray], m: int = REGISTERS) -> np.ndarray:
    """The registers (sets x m) of each set of hashes; zeros for an empty set."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    least = np.full(len(sets) * m, np.inf)
    h = np.concatenate([*sets, np.empty(0, dtype=np.uint64)])
    first, step = (h >> np.uint64(40)).astype(np.int64), ((h >> np.uint64(20)).astype(np.int64) | 1)
    x = np.zeros(len(h))
    for j in range(m):
        if not len(h):
            break
        u = (mix(h + np.uint64((j + 1) * 0x9E3779B97F4A7C15 % (1 << 64))) >> np.uint64(11)).astype(np.float64) * 2.0**-53
        x = x - np.log1p(-u) / (RATE * (m - j))
        cell = owner * m + ((first + j * step) & (m - 1))
        np.minimum.at(least, cell, x)
        live = x < least.reshape(-1, m).max(axis=1)[owner]
        h, owner, first, step, x = h[live], owner[live], first[live], step[live], x[live]
    with np.errstate(divide="ignore"):
        k = np.floor(1 - np.log(least) / np.log(BASE))
    return np.clip(np.where(np.isinf(least), 0, k), 0, TOP + 1).astype(np.uint16).reshape(-1, m)


def likely_similarity(a: np.ndarray, b: np.ndarray, n_a: np.ndarray | None = None, n_b: np.ndarray | None = None, steps: int = 30) -> np.ndarray:
    """Maximum likelihood similarity of register rows a and b, from how many are above, below and equal.

    n_a and n_b are the sets' sizes; without them the mean registers, which grow as a size's logarithm, give the ratio.
    """
    above, below = (a > b).sum(axis=-1).astype(float), (a < b).sum(axis=-1).astype(float)
    equal = a.shape[-1] - above - below
    if n_a is None or n_b is None:
        u = 1 / (1 + np.exp(-np.log(BASE) * (a.mean(axis=-1, dtype=np.float64) - b.mean(axis=-1, dtype=np.float64))))
    else:
        u = np.asarray(n_a / (n_a + n_b), dtype=np.float64)
    v = 1 - u
    chance = lambda x: -np.log1p(-np.clip(x, 1e-12, 1) * (BASE - 1) / BASE) / np.log(BASE)

    def value(j):
        p, q = chance(u - v * j), chance(v - u * j)
        return above * np.log(p) + below * np.log(q) + equal * np.log(np.maximum(1e-12, 1 - p - q))

    low, high = np.zeros_like(u), np.minimum(u / v, v / u)
    for _ in range(steps):  # the likelihood has one peak
        third = (high - low) / 3
        right = value(low + third) < value(high - third)
        low, high = np.where(right, low + third, low), np.where(right, high, high - third)
    return (low + high) / 2


def banding(percent: int) -> tuple[int, int]:
    """(bands, registers a band): shorter bands for lower thresholds."""
    band = 6 if percent >= 85 else 5
    return REGISTERS // band, band


def plausible(percent: int) -> float:
    """The least estimate that a linked pair can show."""
    j = percent / 100
    return j - DEVIATIONS * float(np.sqrt(j * (1 - j) / REGISTERS))


def _sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.sliced(batches):
        sets = [shingles(t) for t in part.column(1).to_pylist()]
        names = [xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63) if len(s) else None for s in sets]
        rows = registers(sets)
        yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array([len(s) for s in sets], pa.int64()), pa.array(names, pa.int64()), pa.array([r.tobytes() for r in rows], pa.binary())], ["doc_id", "text_hash", "n_shingles", "v", "registers"])


def _banded(bands: int, band: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = batch.column(0).to_numpy()
            rows = np.frombuffer(b"".join(batch.column(1).to_pylist()), dtype=np.uint16).reshape(-1, REGISTERS)
            parts = rows[:, : bands * band].reshape(-1, bands, band).astype(np.uint64)
            keys = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * _ODD[1], parts.shape[:2])
            for j in range(band):
                keys = mix(keys + (parts[:, :, j] + np.uint64(1)) * _ODD[j % 5])
            keys = keys.view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel()), pa.array(np.tile(np.arange(bands, dtype=np.int32), len(v))), pa.array(np.repeat(v, bands))], ["bucket", "band", "v"])

    return run


def _block_pairs(starts: np.ndarray, ends: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within blocks, some hundred thousand at a time."""
    held, size = [], 0
    sizes = ends - starts
    for s in np.unique(sizes[sizes > 1]):
        at = starts[sizes == s]
        i, k = np.triu_indices(int(s), 1)
        many = max(1, 200_000 // len(i))
        for lo in range(0, len(at), many):
            own = at[lo : lo + many, None]
            held.append(((own + i).ravel(), (own + k).ravel()))
            size += len(held[-1][0])
            if size >= 200_000:
                yield np.concatenate([x for x, _ in held]), np.concatenate([y for _, y in held])
                held, size = [], 0
    if held:
        yield np.concatenate([x for x, _ in held]), np.concatenate([y for _, y in held])


def _forest_of_blocks(least: float, bands: int, band_size: int):
    """A forest of plausible pairs within blocks of rows sorted by (bucket, block); rows: bucket, block, v, comp, half, registers, band, n_shingles.

    Only pairs of different components and, in blocks that hold two halves, of different halves count. A pair that
    several bands share is the first one's; where blocks part it there, the round over large buckets meets it.
    Of the rest, those pairs stay that join what the task's earlier pairs have not joined.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, root = None, {}

        def top(c: int) -> int:
            while (up := root.setdefault(c, c)) != c:
                root[c] = c = root[up] if up in root else up
            return c

        for batch in _and_none(batches):
            if batch is not None:
                held = batch if held is None or not held.num_rows else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0] if batch.num_rows else held
            if held is None or not held.num_rows:
                continue
            bucket, block = held.column(0).to_numpy(), held.column(1).to_numpy()
            starts = np.flatnonzero(np.concatenate([[True], (bucket[1:] != bucket[:-1]) | (block[1:] != block[:-1])]))
            ends = np.concatenate([starts[1:], [len(bucket)]])
            half = held.column(4).to_numpy()
            halves = np.repeat(np.maximum.reduceat(half, starts) > 0, ends - starts)
            rest = len(bucket)
            if batch is not None:  # the last block may go on in the next batch
                starts, ends, rest = starts[:-1], ends[:-1], int(starts[-1])
            v, comp = held.column(2).to_numpy(), held.column(3).to_numpy()
            rows = np.frombuffer(b"".join(held.column(5).to_pylist()), dtype=np.uint16).reshape(-1, REGISTERS)
            band, n = held.column(6).to_numpy(), held.column(7).to_numpy().astype(float)
            for i, k in _block_pairs(starts, ends):
                ok = (comp[i] != comp[k]) & (v[i] != v[k]) & ((half[i] != half[k]) | ~halves[i])
                i, k = i[ok], k[ok]
                good = []
                for c in range(0, len(i), 20_000):
                    equal = rows[i[c : c + 20_000]] == rows[k[c : c + 20_000]]
                    first = equal[:, : bands * band_size].reshape(-1, bands, band_size).all(axis=2).argmax(axis=1)
                    good.append((equal.mean(axis=1) >= least - 0.1) & (first == band[i[c : c + 20_000]]))
                good = np.concatenate([np.empty(0, dtype=bool), *good])
                i, k = i[good], k[good]
                est = np.concatenate([np.empty(0), *(likely_similarity(rows[x], rows[y], n[x], n[y]) for x, y in ((i[c : c + 20_000], k[c : c + 20_000]) for c in range(0, len(i), 20_000)))])
                i, k, est = i[est >= least], k[est >= least], est[est >= least]
                low, high = np.minimum(v[i], v[k]), np.maximum(v[i], v[k])
                kept = []
                for at in np.lexsort((high, low, -np.round(est, 1))):
                    x, y = top(int(comp[i[at]])), top(int(comp[k[at]]))
                    if x != y:
                        root[max(x, y)] = min(x, y)
                        kept.append(at)
                low, high = low[kept], high[kept]
                yield pa.RecordBatch.from_arrays([pa.array(low, pa.int64()), pa.array(high, pa.int64())], ["a", "b"])
            held = held.slice(rest)

    return run


def _and_none(batches):
    yield from batches
    yield None


def _confirmed(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                good.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good, pa.bool_()))
        common.give_back()

    return run


def _links_of_blocks(percent: int):
    """Links among two blocks' full sets (rows: v, comp, half, hashes), as many as join different components."""

    def run(rows: pa.Table) -> pa.Table:
        v, comp, half = (rows.column(k).to_numpy() for k in ("v", "comp", "half"))
        sets = [np.frombuffer(x.as_buffer(), dtype=np.uint64) for x in rows.column("hashes")]
        n = np.array([len(x) for x in sets])
        names, at = np.unique(np.concatenate(sets), return_inverse=True)
        ends = np.cumsum(n)
        starts = ends - n
        met = np.zeros(len(names), dtype=np.int64)
        first, second = np.flatnonzero(half == 0), np.flatnonzero(half > 0)
        label = np.unique(comp, return_inverse=True)[1]
        a, b = [], []
        for k, x in enumerate(first):
            others = second if len(second) else first[k + 1 :]
            others = others[(label[others] != label[x]) & (100 * np.minimum(n[others], n[x]) >= percent * np.maximum(n[others], n[x]))]
            if not len(others):
                continue
            own = at[starts[x] : ends[x]]
            met[own] = 1
            both = np.add.reduceat(met[at], starts)[others]
            met[own] = 0
            for y in others[100 * both >= percent * (n[others] + n[x] - both)]:
                if label[x] != label[y]:
                    label[label == label[y]] = label[x]
                    a.append(min(v[x], v[y]))
                    b.append(max(v[x], v[y]))
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _hashed(wanted):
    """Full sets (v, hashes) of the texts whose slot is among the wanted; rows: slot, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = wanted.value
        for batch in common.sliced(batches):
            slot = batch.column(0).to_numpy()
            texts = batch.column(1).filter(pa.array((bits[slot >> 3] >> (slot & 7) & 1).astype(bool)))
            sets = [shingles(t) for t in texts.to_pylist()]
            names = [xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63) if len(s) else None for s in sets]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["v", "hashes"])

    return run


def _slots_set(ids: DataFrame) -> np.ndarray:
    """A bitmap of fixed size with the slots of ids set; what it lets through beyond them is joined away."""

    def part(rows: pa.Table) -> pa.Table:
        bits = np.zeros(1 << FILTER_PART - 3, dtype=np.uint8)
        slots = rows.column("slot").to_numpy() & (1 << FILTER_PART) - 1
        np.bitwise_or.at(bits, slots >> 3, np.left_shift(1, slots & 7).astype(np.uint8))
        return pa.table([pa.array([rows.column("part")[0].as_py()], pa.int32()), pa.array([bits.tobytes()], pa.binary())], ["part", "bits"])

    slots = ids.select(_slot()).distinct().withColumn("part", F.shiftright("slot", FILTER_PART))
    bits = np.zeros(1 << FILTER_BITS - FILTER_PART, dtype=f"V{1 << FILTER_PART - 3}")
    for r in slots.groupBy("part").applyInArrow(part, "part int, bits binary").collect():  # at most all of the bitmap
        bits[r["part"]] = bytes(r["bits"])
    return bits.view(np.uint8)


def _slot():
    return F.pmod(F.xxhash64("doc_id"), F.lit(1 << FILTER_BITS)).cast("int").alias("slot")


def _full_sets(texts: DataFrame, vertices: DataFrame, wanted: DataFrame) -> DataFrame:
    """(v, hashes) of the wanted vertices, from one text each."""
    ids = wanted.join(vertices.select("v", "low"), "v").select(F.col("low").alias("doc_id"))
    chosen = texts.sparkSession.sparkContext.broadcast(_slots_set(ids))
    found = texts.select(_slot(), "text").mapInArrow(_hashed(chosen), "v long, hashes binary")
    return common.written(found.join(wanted, "v", "left_semi").dropDuplicates(["v"]), "shingles")


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("v")).union(pairs.select(F.col("b").alias("v"))).distinct()


def _met_in_twos(rows: DataFrame, by: str, most_rows: int, most_hashes: int) -> DataFrame:
    """rows (by, v, comp, n_shingles) with `block` and `half`: all pairs of a group that are not both of its main component meet.

    The main component's rows and all others are dealt into blocks of bounded size; each block of others meets
    itself, each other one, and each block of the main component. Groups of one component yield no rows.
    """
    sizes = rows.groupBy(by, "comp").agg(F.count("*").alias("rows"), F.sum("n_shingles").alias("hashes"))
    dealt = lambda c, h: F.greatest(F.lit(1), F.ceil(F.greatest(c / most_rows, h / most_hashes))).cast("long")
    whole = sizes.groupBy(by).agg(F.max(F.struct("rows", "hashes", "comp")).alias("main"), F.sum("rows").alias("rows"), F.sum("hashes").alias("hashes"), F.count("*").alias("comps")).where("comps > 1")
    whole = whole.select(by, F.col("main.comp").alias("main"), dealt(F.col("rows") - F.col("main.rows"), F.col("hashes") - F.col("main.hashes")).alias("outer"), dealt(F.col("main.rows"), F.col("main.hashes")).alias("inner"))
    spread, inside = F.xxhash64("v", F.lit(8)), F.col("comp") == F.col("main")
    got = rows.join(whole, by).withColumn("own", F.when(inside, F.col("outer") + F.pmod(spread, "inner")).otherwise(F.pmod(spread, "outer")))
    got = got.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.when(inside, F.col("outer")).otherwise(F.col("outer") + F.col("inner")) - 1)))
    block = F.least("own", "other") * (F.col("outer") + F.col("inner")) + F.greatest("own", "other")
    return got.withColumns({"block": block, "half": (F.col("own") > F.col("other")).cast("int")}).drop("main", "outer", "inner", "own", "other")


def near_duplicates(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept, text_hash) of every row."""
    texts = common.texts_of(docs)
    spark = docs.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))  # by count, as small rows carry much work
    sketches = common.written(texts.withColumn("text_hash", F.xxhash64("text")).mapInArrow(_sketched, "doc_id long, text_hash long, n_shingles long, v long, registers binary"), "sketches")
    sets = sketches.where("v IS NOT NULL")
    vertices = common.written(sets.groupBy("v").agg(F.min("doc_id").alias("low"), F.any_value("n_shingles").alias("n_shingles"), F.any_value("registers").alias("registers")), "vertices")

    bands, band = banding(percent)
    found = vertices.select("v", "registers").mapInArrow(_banded(bands, band), "bucket long, band int, v long")
    shared = found.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    salt = F.when(F.col("n") <= BLOCK, 0).otherwise(F.pmod(F.xxhash64("v", F.lit(8)), F.ceil(F.col("n") / (BLOCK // 2)).cast("long"))).cast("long")
    members = common.written(found.join(shared, "bucket").select("bucket", "band", "v", "n", salt.alias("block")), "members")

    def plausible_forest(blocks: DataFrame) -> DataFrame:
        """blocks: bucket, block, band, v, comp, half."""
        rows = blocks.join(vertices.select("v", "registers", "n_shingles"), "v")
        rows = rows.select("bucket", "block", "v", "comp", "half", "registers", "band", "n_shingles").repartition(tasks, "bucket", "block").sortWithinPartitions("bucket", "block", "v")
        return common.written(rows.mapInArrow(_forest_of_blocks(plausible(percent), bands, band), "a long, b long").distinct(), "pairs")

    def labelled(rows: DataFrame, links: DataFrame | None) -> DataFrame:
        """rows with `comp`, the component of v by the links so far."""
        if links is None:
            return rows.withColumn("comp", F.col("v"))
        return rows.join(links, "v", "left").withColumn("comp", F.coalesce("comp", "v"))

    # The first bands join most of what is plausible; of the others, blocks that hold one group only are left out.
    pairs = plausible_forest(members.where(F.col("band") < FIRST_BANDS).withColumns({"comp": F.col("v"), "half": F.lit(0)}))
    later = labelled(members.where(F.col("band") >= FIRST_BANDS), None if pairs.isEmpty() else components(pairs))
    mixed = later.groupBy("bucket", "block").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 <> c1").select("bucket", "block")
    pairs = common.written(pairs.union(plausible_forest(later.join(mixed, ["bucket", "block"]).withColumn("half", F.lit(0)))), "pairs")
    links, labels = None, None
    if not pairs.isEmpty():
        hashes = _full_sets(texts, vertices, _ends(pairs))
        a, b = (hashes.select(F.col("v").alias(k), F.col("hashes").alias(f"h{k}")) for k in "ab")
        links = common.written(pairs.join(a, "a").join(b, "b").select("a", "b", "ha", "hb").mapInArrow(_confirmed(percent), "a long, b long"), "links")
        labels = None if links.isEmpty() else components(links)

        large = labelled(members.where(F.col("n") > BLOCK).drop("block", "n"), labels)
        more = pairs.limit(0)
        if not large.isEmpty():  # pairs that the blocks of a large bucket part
            sized = large.withColumn("n_shingles", F.lit(1))
            more = plausible_forest(_met_in_twos(sized, "bucket", BLOCK // 2, BLOCK // 2).drop("n_shingles"))
        if not more.isEmpty():
            pairs = pairs.union(more)
            hashes = _full_sets(texts, vertices, _ends(pairs))

        groups = components(pairs).withColumnRenamed("comp", "grp")
        rest = _met_in_twos(labelled(groups, labels).join(vertices.select("v", "n_shingles"), "v"), "grp", TEST_ROWS, TEST_HASHES)
        rest = rest.join(hashes, "v").select("grp", "block", "v", "comp", "half", "hashes")
        late = common.written(rest.groupBy("grp", "block").applyInArrow(_links_of_blocks(percent), "a long, b long"), "links")
        if not late.isEmpty():
            links = links.union(late)
            labels = components(links)

    named = vertices.select("v", "low")
    if labels is not None:
        grouped = labels.join(named, "v")
        lowest = grouped.groupBy("comp").agg(F.min("low").alias("component_id"))
        named = named.join(labels, "v", "left").join(lowest, "comp", "left").select("v", F.coalesce("component_id", "low").alias("component_id"))
    else:
        named = named.withColumnRenamed("low", "component_id")
    rows = sketches.drop("registers").join(named, "v", "left").withColumn("component_id", F.coalesce("component_id", "doc_id"))
    return rows.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"), "text_hash")


def op8_setsketch_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(common.read_table(spark, sf_dir, "documents"))
