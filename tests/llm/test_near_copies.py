"""The near-copy stage against brute-force Jaccard similarity of five-word shingles."""

import random

import numpy as np

import corpus_pipeline
from ctxpress.llm import simhash


def shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute_kept(rows):
    rows = sorted(rows)
    sets = [shingles(t) for _, t in rows]
    parent = np.arange(len(rows))
    for i, a in enumerate(sets):
        for j in range(i):
            both = len(a & sets[j])
            if both * 5 >= (len(a) + len(sets[j]) - both) * 4:
                simhash.unite(parent, np.array([i]), np.array([j]))
    return {rows[p][0] for p in parent}


def stage(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return sorted(r["doc_id"] for r in corpus_pipeline.drop_near_duplicates(spark, docs, "").collect())


def test_stage_drops_every_copy_of_given_documents(spark, sf):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert set(stage(spark, rows)) == brute_kept(rows)


def test_stage_on_edited_copies_and_chains(spark):
    rng = random.Random(5)
    rows = []
    for g in range(30):
        base = [f"w{rng.randrange(4000)}" for _ in range(rng.randint(30, 300))]
        for _ in range(8):
            w = list(base)
            for _ in range(rng.randint(0, max(1, len(w) // 25))):
                w[rng.randrange(len(w))] = f"z{rng.randrange(4000)}"
            rows.append((len(rows), " ".join(w)))
            base = w if g % 2 else base  # every other group is a chain, each a copy of the last
    rng.shuffle(rows)
    want = brute_kept(rows)
    assert 30 < len(want) < 200
    assert set(stage(spark, rows)) == want


def test_stage_on_odd_rows(spark):
    rows = [(5, None), (4, ""), (9, "one two"), (7, "ONE  two"), (8, "one three"), (2, "a b c"), (2, "d e f"), (None, "one two")]
    assert stage(spark, rows[:-1]) == [2, 2, 4, 7, 8]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert corpus_pipeline.drop_near_duplicates(spark, docs, "").where("doc_id is null").count() == 1
    assert corpus_pipeline.drop_near_duplicates(spark, docs.limit(0), "").count() == 0


def test_large_buckets_are_compared_in_tiles(spark):
    rng = random.Random(6)
    base = [f"w{rng.randrange(4000)}" for _ in range(120)]
    rows = []
    for _ in range(150):
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = f"z{rng.randrange(4000)}"
        rows.append((len(rows), " ".join(w)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_kept(rows)
    assert 1 < len(want) < 140
    for tile in (20, 8192):
        assert {r["component_id"] for r in simhash.near_copy_components(docs, tile).collect()} == want
