"""The pipeline's stages one after another, each against the operator's definition on what the one before kept."""

import corpus_pipeline
from test_dedup import brute_cut
from test_near_copies import brute_kept


def test_stages_on_odd_rows(spark, sf):
    """Null, empty and repeated rows, null columns, no rows, and columns that operators use names of."""
    long = " ".join(f"the word{i % 97} of{i}" for i in range(3000))
    given = [(r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"], 1, "x") for r in spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 40").collect()]
    rows = given + [given[0], given[0], (None, given[3][1], None, None, None, None, None), (900, None, None, "s", None, 2, "y"), (901, "", None, None, 0, 2, "y"), (902, "12 34", "en", "s", 5, 3, "z"), (903, long, None, "s", len(long), 3, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, node int, gone string")
    for some in (docs, docs.limit(0)):
        out = some
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, out, sf).checkpoint()
            if name != "mix":
                assert out.columns == docs.columns
            if name == "language":
                assert not {900, 901, 902} & {r["doc_id"] for r in out.collect()}
        assert (out.count() > 10) == (some is docs)


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept, columns = [], docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in docs.collect()}
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        after = {r["doc_id"]: r for r in docs.collect()}
        assert set(after) <= set(before)
        if name != "mix":
            assert docs.columns == columns
        if name == "language":
            assert len(after) >= 0.99 * len(before)
        if name == "near_duplicates":
            assert set(after) == brute_kept([(i, r["text"]) for i, r in before.items()])
        if name == "repeats":
            want = brute_cut([(i, r["text"]) for i, r in before.items()])
            for i, r in after.items():
                assert len(r["text"].encode()) <= want[i][0] - want[i][1] and (want[i][1] or r["text"] == before[i]["text"])
        if name == "decontaminate":
            bench = [r["text"] for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            assert not any(b in r["text"] for b in bench for r in after.values())
            assert len(before) - len(after) <= 5 + sum(any(b in r["text"] for b in bench) for r in before.values())
        kept.append(len(after))
    assert sorted(corpus_pipeline.run(spark, sf).select("doc_id", "taken").collect()) == sorted(docs.select("doc_id", "taken").collect())
