import hashlib
from collections import Counter

import corpus_pipeline
from motifprune.llm import decontamination, near_dedup, packing, queries
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def test_pipeline_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").collect()
    bench = [f" {' '.join(decontamination.words_of(r['text']))} " for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    left = {r["doc_id"]: r["text"] for r in docs if r["text"] and any(c.isalpha() for c in r["text"])}
    last = {}
    for k in sorted(left):
        last[hashlib.sha256(left[k].encode()).digest()] = k
    left = {k: left[k] for k in last.values()}
    sets = {k: set(near_dedup.shingles(t).tolist()) for k, t in left.items()}
    root = {k: k for k in left}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(left)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if sets[a] and 100 * len(sets[a] & sets[b]) >= corpus_pipeline.PERCENT * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                root[max(x, y)] = min(x, y)
    left = {k: t for k, t in left.items() if top(k) == k}
    left = {k: t for k, t in left.items() if not any(b in f" {' '.join(decontamination.words_of(t))} " for b in bench)}
    got = corpus_pipeline.run(spark, SF)
    assert {r["doc_id"] for r in got.select("doc_id").distinct().collect()} == set(left)
    assert max(Counter({r["sequence_id"]: r["n"] for r in got.groupBy("sequence_id").agg(F.sum("length").alias("n")).collect()}).values()) <= packing.CAPACITY


def test_stages_bear_awkward_rows(spark):
    rows = [(None, "no id but words", "en", None, None), (1, None, "en", "s", 0), (2, "", None, None, 0), (3, "some words here", "en", "s", 3), (3, "some words here", "en", "s", 3), (4, "other words there", None, None, 1), (5, "12 34", "en", None, 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.columns == list(corpus_pipeline.COLUMNS), name
        for empty in (docs.limit(0),):
            assert stage(spark, empty, SF).count() == 0
        if name == "language_id":
            assert all(r["lang"] for r in docs.collect())
    assert sorted((r["doc_id"] or 0, r["text"]) for r in docs.collect()) == [(0, "no id but words"), (3, "some words here"), (4, "other words there")]


def test_last_stage_bears_awkward_rows(spark):
    rows = [(None, "no id", "en", None, None), (1, None, "en", "s", 0), (2, "", None, None, 0), (3, "long " * 9000, "en", "s", 3), (3, "long " * 9000, "en", "s", 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
    assert Counter(r["doc_id"] for r in got if r["piece"] == 0) == Counter(r[0] for r in rows)
    assert sum(r["length"] for r in got if r["doc_id"] == 3) == 2 * (9000 + 2)
    assert corpus_pipeline.STAGES[-1][1](spark, docs.limit(0), SF).count() == 0


def test_registered_queries():
    assert {k.split("_")[0] for k in queries.QUERIES} == {f"op{n}" for n in range(1, 11)}
    assert [name for name, _ in corpus_pipeline.STAGES] == ["language_id", "exact_dedup", "near_dedup", "decontamination", "packing"]
