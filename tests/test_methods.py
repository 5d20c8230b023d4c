"""Worked examples, invariants and awkward inputs of the compression methods."""

import math
import random

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from ctxpress.functions.scalar import combine_scores, cosine, dequantize, quantize
from ctxpress.functions.tokens import lexical, tokenize, untokenize, words
from ctxpress.operators import abbrev, baselines, exemplars, fidelity, measures, prune, quant, relational, selfinfo
from ctxpress.plans.compressor import CompressorConfig, ContextCompressor
from ctxpress.sources.metadata import MetadataStore, RestoringSource, read_restored, write_compressed
from ctxpress.sources.tables import html_text, load, load_attachment, prompts

ODD_TEXTS = [None, "", " ", "a", "the the the the", "x  y\tz\r\nw", "né́e naïve", "1,234.5 & co.", "…—!", "no break", "AA1 AB1 the the", "the the", "the, the"]


def test_information_of_a_tiny_corpus(spark):
    t = selfinfo.unigram_information(selfinfo.unigram_counts(spark.createDataFrame([("a a b c",)], "text string")))
    got = {r["tok"]: (r["p"], r["s_stat"]) for r in t.collect()}
    assert got == {"a": (0.5, 1.0), "b": (0.25, 2.0), "c": (0.25, 2.0)}
    assert sum(p for p, _ in got.values()) == 1


@pytest.mark.parametrize("s,d,want", [(5, 5.5, 5.25), (5, 4.5, 4.75), (5, 6, 6), (5, 4, 4), (0, 3, 3), (None, 3, 3), (3, None, 3), (None, None, None)])
def test_merge_rule(spark, s, d, want):
    t = spark.createDataFrame([(None if s is None else float(s), None if d is None else float(d))], "s double, d double")
    assert t.select(combine_scores(F.col("s"), F.col("d"))).first()[0] == want


def test_merged_counts_equal_a_recount(spark, sf):
    a, b = (load(spark, sf, t, "text") for t in ("documents", "conversations"))
    whole = {r["tok"]: r["n"] for r in selfinfo.unigram_counts(a.union(b)).collect()}
    assert {r["tok"]: r["n"] for r in selfinfo.merge_counts(selfinfo.unigram_counts(a), selfinfo.unigram_counts(b)).collect()} == whole


def test_scores_do_not_depend_on_partitions(spark, sf):
    def run(parts, shuffles):
        spark.conf.set("spark.sql.shuffle.partitions", shuffles)
        try:
            t = selfinfo.score_tokens(prompts(spark, sf).repartition(parts), load(spark, sf, "documents", "text").repartition(parts))
            return sorted(map(tuple, prune.reassemble(prune.prune_tokens(t, prune.Budget.ratio(0.5))).collect()))
        finally:
            spark.conf.set("spark.sql.shuffle.partitions", 8)

    assert run(1, 4) == run(7, 50)


def test_external_scorer_is_called_in_batches(spark):
    p = spark.createDataFrame([(1, "a b a"), (2, "c")], "prompt_id long, text string")
    got = selfinfo.ExternalModel(lambda asked: [0.5 ** (len(w) + 1) for w, _ in asked], batch=2).score(selfinfo.prompt_tokens(p))
    assert sorted((r["prompt_id"], r["pos"], r["s_dyn"]) for r in got.collect()) == [(1, 0, 1.0), (1, 1, 2.0), (1, 2, 3.0), (2, 0, 1.0)]


def scored(spark, rows):
    return spark.createDataFrame(rows, "prompt_id long, pos int, tok string, s_stat double, score double")


def test_window_and_row_pruning_agree(spark):
    rng = random.Random(1)
    rows = [(p, i, f"w{i}", 1.0, rng.choice([None, 1.0, 2.0, 2.0, 3.5])) for p in range(20) for i in range(rng.randint(1, 15))]
    t = scored(spark, rows)
    for share in (0.2, 0.5, 1.0):
        a = {r["prompt_id"]: r["text"] for r in prune.reassemble(prune.prune_tokens(t, prune.Budget.ratio(share))).collect()}
        packed = t.groupBy("prompt_id").agg(F.collect_list(F.struct("pos", "tok", "score")).alias("ts"))
        b = {r["prompt_id"]: r["text"] for r in packed.select("prompt_id", prune.prune_in_row(F.col("ts"), share).alias("text")).collect()}
        assert a == b
        sizes = t.groupBy("prompt_id").count().collect()
        assert all(len(a[r["prompt_id"]].split()) == math.ceil(share * r["count"] - 1e-9) for r in sizes)


def test_phrases_fit_the_budget_and_protected_ones_stay(spark):
    rows = [(1, i, t, s, s) for i, (t, s) in enumerate([("the", 2.0), ("profit", 9.0), ("of", 2.0), ("2024", 9.5), ("was", 3.0), ("small", 10.0)])]
    t = prune.group_by_attachment(scored(spark, rows), 8.0)
    assert [r["phrase"] for r in t.orderBy("pos").collect()] == [0, 0, 1, 1, 2, 2]
    kept = prune.prune_phrases(t, prune.Budget.tokens(2)).where("kept").count()
    assert kept == 2
    safe = prune.prune_phrases(t, prune.Budget.tokens(2), protect=prune.NUMBER).where("kept").orderBy("pos")
    assert [r["tok"] for r in safe.collect()] == ["of", "2024"]


def test_heads_make_subtrees(spark):
    p = spark.createDataFrame([(1, ["the", "net", "profit", "rose", "fast"], [2, 2, 3, -1, 3])], "prompt_id long, tokens array<string>, heads array<int>")
    assert [r["phrase"] for r in prune.group_by_heads(p, 1).orderBy("pos").collect()] == [2, 2, 2, 3, 4]
    assert [r["phrase"] for r in prune.group_by_heads(p, 0).orderBy("pos").collect()] == [3] * 5


def test_redaction_and_edges(spark):
    t = spark.createDataFrame([("mail a.b@c.org or 123-45-6789, password=abc",)], "text string")
    assert t.select(prune.redact(F.col("text"))).first()[0].split() == ["mail", "or", ","]
    parts = spark.createDataFrame([(1, i, float(s)) for i, s in enumerate([5, 1, 4, 2, 3])], "prompt_id long, part int, score double")
    got = [r["score"] for r in prune.order_for_edges(parts).orderBy("place").collect()]
    assert got[0] == 5 and got[-1] == 4 and min(got) == got[2]


def test_tokens_with_gaps_are_lossless(spark):
    t = spark.createDataFrame([(x,) for x in ODD_TEXTS], "text string")
    assert all(r[0] == r[1] for r in t.where("text is not null").select("text", untokenize(tokenize(F.col("text")))).collect())


MAPPING = {"the the": "AA1", "x y": "AB1", "x y z": "AC1", "A B": "A1"}


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="xyz the\t\n.,é1AB\x1b", max_size=60))
def test_codec_is_lossless_on_any_text(text):
    for policy in ("leftmost_longest", "frequency_first", "max_saving"):
        c = abbrev.Codec(MAPPING, policy)
        assert c.decoder()(c.encoder()(text)) == text


def test_codec_policies_and_traps():
    c = abbrev.Codec(MAPPING).encoder()
    assert c("x y z x y") == "AC1 AB1" and c("x y x y") == "AB1 AB1" and c("the the the the") == "AA1 AA1" and c("the the the") == "AA1 the"
    assert c("x  y") == "x  y" and c("xx y") == "xx y" and c("the, the") == "the, the" and c(None) is None
    back = abbrev.Codec({"a b": "AB1", "c d": "AB12"})
    assert back.decoder()(back.encoder()("a b, c d AB123")) == "a b, c d AB123"
    best = abbrev.Codec({"a b": "P1", "b c d": "P2"}, "max_saving").encoder()
    assert best("a b c d") == "a P2" and abbrev.Codec({"a b": "P1", "b c d": "P2"}).encoder()("a b c d") == "P1 c d"


def test_dictionary_avoids_words_of_the_corpus(spark):
    d = spark.createDataFrame([(1, "AA1 AC1 p q p q r s r s r s")], "doc_id long, text string")
    dic = abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), 3), d)
    rows = sorted((r["rank"], r["placeholder"], r["gram"]) for r in dic.collect())
    assert [r[1] for r in rows] == ["AB1", "AD1", "AE1"] and rows[0][2] == "r s"


def test_round_trip_on_all_tables_and_odd_texts(spark, sf):
    d = load(spark, sf, "documents", "doc_id", "text")
    m = abbrev.as_mapping(abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), 100), d))
    odd = spark.createDataFrame([(x,) for x in ODD_TEXTS], "text string")
    for t in (d, prompts(spark, sf), load(spark, sf, "pages").withColumnRenamed("html", "text"), odd):
        r = abbrev.restore(abbrev.abbreviate(t, m), m)
        assert r.where(~F.col("text").eqNullSafe(F.col("restored"))).count() == 0


@pytest.mark.parametrize("n,k", [(2, 20), (3, 20), (4, 7)])
def test_top_k_ways_agree(spark, sf, n, k):
    d = load(spark, sf, "documents", "text")
    want = sorted(map(tuple, abbrev.select_top(abbrev.ngram_frequencies(d, n), k).collect()))
    assert sorted(map(tuple, abbrev.top_by_levels(d, n, k).collect())) == want
    assert sorted(map(tuple, abbrev.top_by_sketch(d, n, k).collect())) == want


def test_overlapping_and_replaceable_counts(spark):
    t = spark.createDataFrame([("z z z z z",), ("x y x y x y",), ("z",), ("",)], "text string").select(words(F.col("text")).alias("w"))
    got = [tuple(r) for r in t.select(abbrev.greedy_count(F.col("w"), ["z", "z"]), F.size(abbrev.ngrams(F.col("w"), 2)), abbrev.greedy_count(F.col("w"), ["x", "y"])).collect()]
    assert got == [(2, 4, 0), (0, 5, 3), (0, 0, 0), (0, 0, 0)]


def test_very_long_runs_of_words(spark):
    d = spark.createDataFrame([(1, "go on " * 60_000)], "doc_id long, text string")
    assert {r["gram"]: r["freq"] for r in abbrev.codec_frequencies(d, 2).collect()} == {"go on": 60_000, "on go": 59_999}


def test_quantizer_worked_example_and_odd_values(spark):
    t = spark.createDataFrame([(v,) for v in (0.0, 1.0, 2.0, 10.0, None, float("nan"), float("inf"), -5.0, 99.0)], "x double")
    got = [r[0] for r in t.select(quantize(F.col("x"), 0.0, 10.0, 2)).collect()]
    assert got == [0, 0, 1, 3, None, None, None, 0, 3]
    flat = quant.uniform_fit(spark.createDataFrame([(4.0,), (4.0,)], "x double"), ["x"], 8)
    assert flat[0].step == 0 and flat[0].bound() == 0


@pytest.mark.parametrize("bits", [1, 2, 4, 8, 12, 16, 24])
def test_bounds_hold(spark, sf, bits):
    for table, col in (("lineitem", "l_extendedprice"), ("customer", "c_acctbal"), ("events", "value"), ("part", "p_retailprice")):
        t = load(spark, sf, table, col)
        g = quant.uniform_fit(t, [col], bits)
        e = t.select(F.abs(F.col(col) - dequantize(quantize(F.col(col), g[0].lo, g[0].hi, bits), g[0].lo, g[0].hi, bits)).alias("e"), quantize(F.col(col), g[0].lo, g[0].hi, bits).alias("q"))
        r = e.agg(F.max("e"), F.min("q"), F.max("q")).first()
        assert r[0] <= g[0].bound() * (1 + 1e-9) + 1e-9 <= g[0].bound("paper") + 1e-6 and (r[1], r[2]) == (0, 2**bits - 1)
        assert quant.bits_for_tolerance(g[0].lo, g[0].hi, g[0].bound()) == bits
        assert quant.bits_for_tolerance(g[0].lo, g[0].hi, g[0].bound("paper"), "paper") == bits


def test_code_predicates_are_supersets(spark, sf):
    t = load(spark, sf, "lineitem", "l_extendedprice")
    g = quant.uniform_fit(t, ["l_extendedprice"], 6)[0]
    t = quant.uniform_encode(t, [g]).cache()
    for op in (">", ">=", "<", "<="):
        for v in (0.0, g.lo, 5000.0, 50000.5, g.hi, 1e9):
            assert t.where(f"l_extendedprice {op} {v}").where(~quant.code_predicate(g, op, v)).count() == 0
    t.unpersist()


def test_sum_of_codes_is_the_sum_of_decoded_values(spark, sf):
    t = load(spark, sf, "lineitem", "l_returnflag", "l_extendedprice")
    g = quant.uniform_fit(t, ["l_extendedprice"], 8)
    coded = quant.uniform_encode(t, g)
    a = {r["l_returnflag"]: r["total"] for r in quant.code_sum(coded, g[0], "l_returnflag").collect()}
    b = {r[0]: r[1] for r in quant.uniform_decode(coded, g).groupBy("l_returnflag").agg(F.sum("l_extendedprice_hat")).collect()}
    assert all(a[k] == pytest.approx(b[k], rel=1e-9) for k in a)


def test_kmeans_is_exact_for_few_values_and_never_below_the_optimum(spark, sf):
    t = load(spark, sf, "lineitem", "l_discount", "l_quantity")
    v = quant.weighted_values(t, "l_discount")
    cents = sorted(r["x"] for r in v.collect())
    assert v.agg(quant.kmeans_mse(v, cents)).first()[0] == 0
    q = quant.weighted_values(t, "l_quantity")
    rows = q.collect()
    for k in (2, 5):
        best, centers = quant.kmeans_1d_exact(np.array([r["x"] for r in rows]), np.array([r["n"] for r in rows]), k)
        assert q.agg(quant.kmeans_mse(q, quant.kmeans_fit(t, "l_quantity", k))).first()[0] >= best - 1e-9
        assert q.agg(quant.kmeans_mse(q, centers)).first()[0] == pytest.approx(best)


def test_exact_partition_matches_enumeration():
    from itertools import combinations

    x, n = np.array([1.0, 2, 4, 7, 11, 12]), np.array([3, 1, 2, 1, 1, 4])
    sse = lambda a, b: (n[a:b] * (x[a:b] - np.average(x[a:b], weights=n[a:b])) ** 2).sum()
    for k in (1, 2, 3, 6):
        want = min(sum(sse(a, b) for a, b in zip((0, *c), (*c, 6))) for c in combinations(range(1, 6), k - 1)) / n.sum()
        assert quant.kmeans_1d_exact(x, n, k)[0] == pytest.approx(want, abs=1e-12)


def vectors(spark, sf):
    return load(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")


def test_prototypes_are_nearest_and_one_each(spark, sf):
    c = exemplars.cluster(vectors(spark, sf).select("id", "vec"), 6)
    protos = {r["cluster"]: r for r in exemplars.prototypes(c).collect()}
    rows = c.collect()
    assert set(protos) == {r["cluster"] for r in rows} and sum(p["size"] for p in protos.values()) == len(rows)
    for k, p in protos.items():
        own = {r["id"]: np.array(r["vec"], float) for r in rows if r["cluster"] == k}
        mean = np.mean(list(own.values()), 0)
        assert min((round(float(((v - mean) ** 2).sum()), 6), i) for i, v in own.items())[1] == p["id"]
    assert len(exemplars.few_shot(exemplars.prototypes(c)).collect()) == 3


def test_sweep_prefers_the_real_number_of_clusters(spark):
    rng = np.random.default_rng(0)
    rows = [(i, (rng.normal(size=4) * 0.05 + np.eye(4)[i % 4] * 3).tolist()) for i in range(120)]
    f = spark.createDataFrame(rows, "id long, vec array<double>")
    table, best = exemplars.silhouette_sweep(f, ks=(2, 3, 4, 5, 6))
    assert best == 4 and table.count() == 5
    assert len(exemplars.farthest_first(f, 3)) == 3


def test_standardized_columns(spark):
    t = spark.createDataFrame([(1.0, 5.0), (3.0, 5.0)], "a double, b double")
    got = [tuple(r) for r in exemplars.standardize(t, ["a", "b"]).select("a_z", "b_z").collect()]
    assert got == [(pytest.approx(-(0.5**0.5)), 0.0), (pytest.approx(0.5**0.5), 0.0)]


def test_cosine_edges(spark):
    t = spark.createDataFrame([([1.0, 0.0], [1.0, 0.0]), ([1.0, 0.0], [0.0, 1.0]), ([1.0, 0.0], [-1.0, 0.0]), ([0.0, 0.0], [1.0, 0.0])], "a array<double>, b array<double>")
    assert [r[0] for r in t.select(cosine(F.col("a"), F.col("b"))).collect()] == [1.0, 0.0, -1.0, None]
    w = spark.createDataFrame([("a b", "a b"), ("a", "b"), ("", "b")], "a string, b string")
    assert [r[0] for r in w.select(fidelity.word_cosine(F.col("a"), F.col("b"))).collect()] == [pytest.approx(1.0), 0.0, None]


def test_fidelity_falls_with_the_budget(spark, sf):
    d = load(spark, sf, "documents", "text").where("n_chars is null or true")
    means = [d.agg(F.avg(fidelity.word_cosine(F.col("text"), baselines.truncate(F.col("text"), s)))).first()[0] for s in (1.0, 0.6, 0.2)]
    assert means[0] == pytest.approx(1.0) and means[0] > means[1] > means[2]


def test_ratio_and_reduction_agree(spark, sf):
    t = measures.with_tokens(load(spark, sf, "documents", "text").withColumn("short", baselines.truncate(F.col("text"), 0.4)))
    r = measures.compression_report(t).first()
    assert r["ratio"] * (1 - r["reduction"]) == pytest.approx(1, abs=1e-4)


def test_pareto_and_accuracy(spark):
    s = spark.createDataFrame([("a", 1.0, 0.9), ("b", 1.2, 0.8), ("c", 1.1, 0.7)], "setting string, ratio double, cosine double")
    assert {r["setting"]: r["efficient"] for r in measures.pareto(s, "setting", "ratio", "cosine").collect()} == {"a": True, "b": True, "c": False}
    t = spark.createDataFrame([("A", "x", True), ("A", "x", False), ("C", "x", True), ("C", "x", True)], "method string, arm string, correct boolean")
    assert {r["method"]: r["delta"] for r in measures.accuracy_report(t).collect()} == {"A": 0.0, "C": 50.0}


def test_pipeline_stages_and_restoration(spark, sf):
    docs = load(spark, sf, "documents", "doc_id", "text")
    r = ContextCompressor(docs.select("text")).run(prompts(spark, sf), docs, load(spark, sf, "lineitem"))
    m = {x["part"]: x for x in r.metrics().collect()}
    assert set(m) == {"prompts", "documents", "table"} and all(x["ratio"] >= 1 for x in m.values())
    assert r.restored_documents().where("text <> restored").count() == 0
    off = ContextCompressor(docs.select("text"), CompressorConfig(stages=frozenset())).run(prompts(spark, sf), docs)
    assert all(x["ratio"] == 1 for x in off.metrics().collect())


def test_lzw_against_a_plain_coder(spark):
    texts = ["", "a", "aaaaaaa", "tobeornottobe", "né" * 20]

    def codes(b):
        known, w, n = {bytes([i]) for i in range(256)}, b"", 0
        for i in range(len(b)):
            if w + b[i : i + 1] not in known:
                known.add(w + b[i : i + 1])
                n, w = n + 1, b""
            w += b[i : i + 1]
        return n + bool(b)

    t = spark.createDataFrame([(x,) for x in texts], "text string")
    assert [r[0] for r in t.select(baselines.lzw_codes("text")).collect()] == [codes(x.encode()) for x in texts]


def test_sources_and_sinks(spark, sf, tmp_path):
    d = load(spark, sf, "documents", "doc_id", "source", "text")
    dic = abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), 20), d)
    short = abbrev.abbreviate(d, abbrev.as_mapping(dic)).drop("text")
    write_compressed(short, str(tmp_path / "z"), dic, by="source")
    want = sorted((r["doc_id"], r["text"]) for r in d.collect())
    assert sorted((r["doc_id"], r["text"]) for r in read_restored(spark, str(tmp_path / "z")).collect()) == want
    spark.dataSource.register(RestoringSource)
    assert sorted(map(tuple, spark.read.format("ctxpress").option("path", str(tmp_path / "z")).load().collect())) == want
    store = MetadataStore(spark, str(tmp_path / "m"))
    store.put("dictionary", 1, dic.limit(1))
    store.put("dictionary", 2, dic)
    assert store.get("dictionary").count() == 20 and store.get("dictionary", 1).count() == 1
    (tmp_path / "a.csv").write_text("k,v\n1,2.5\n")
    assert load_attachment(spark, str(tmp_path / "a.csv"), "csv", "k int, v double").first()["v"] == 2.5
    t = spark.createDataFrame([("<p>a&amp;b<script>x</script> c</p>",)], "html string")
    assert t.select(html_text(F.col("html"))).first()[0] == "a&b c"


def test_plans_keep_text_out_of_shuffles_and_broadcast_small_sides(spark, sf):
    plan = selfinfo.unigram_counts(load(spark, sf, "documents"))._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<text:string>" in plan and "CartesianProduct" not in plan
    exchange = next(x for x in plan.splitlines() if "Exchange hashpartitioning" in x)
    assert "text" not in exchange
    top = abbrev.select_top(abbrev.ngram_frequencies(load(spark, sf, "documents"), 2), 5)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in top


def test_lexical_tokens_of_odd_texts(spark):
    t = spark.createDataFrame([(x,) for x in ODD_TEXTS], "text string")
    got = [r[0] for r in t.select(lexical(F.col("text"))).collect()]
    assert got[0] is None and got[1] == [] and got[7] == ["1", ",", "234", ".", "5", "&", "co", "."]


def test_dictionary_of_thousands_loses_no_entry(spark):
    top = spark.createDataFrame([(f"g{i} h{i}", 10_000 - i) for i in range(3000)], "gram string, freq long")
    docs = spark.createDataFrame([(1, "AA1 AB1 ZZ4 some words")], "doc_id long, text string")
    dic = abbrev.build_dictionary(top, docs).collect()
    assert len(dic) == len({r["placeholder"] for r in dic}) == 3000 and not {"AA1", "AB1", "ZZ4"} & {r["placeholder"] for r in dic}


def test_sketched_top_k_is_exact_on_ties(spark):
    docs = spark.createDataFrame([(" . ".join(f"w{i:04d} x" for i in range(1000)),) for _ in range(60)], "text string").select("text")
    grams = abbrev.select_top(abbrev.ngram_frequencies(docs, 2), 10).collect()
    assert abbrev.top_by_sketch(docs, 2, 10).collect() == grams


def test_no_array_is_shuffled_for_scores(spark, sf):
    import re

    docs = load(spark, sf, "documents", "text")
    for name in ("scorer_a", "scorer_b", "scorer_c", "scorer_d"):
        t = selfinfo.score_tokens(prompts(spark, sf), docs, selfinfo.get_scorer(name, docs))
        plan = t._jdf.queryExecution().optimizedPlan().toString()
        joined = [x for x in plan.split("\n") if "Join" in x or "Window" in x]
        assert joined and not any(re.search(r"\bw#\d+", x) for x in plan.split("\n") if "Project" in x and "Generate" not in x and "posexplode" not in x and "regexp_extract_all" not in x)


def test_answers_match_brute_force(spark, sf):
    from ctxpress.plans import workloads

    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    extra = spark.createDataFrame([(900, "..."), (901, "no such words anywhere"), (902, None)], "item_id long, text string")
    items = items.unionAll(extra)
    got = sorted(map(tuple, workloads.answers(docs, items).collect()))
    texts = docs.collect()
    assert got == sorted((i["item_id"], d["doc_id"]) for i in items.where("item_id not in (900, 902)").collect() for d in texts if i["text"] in (d["text"] or "")) and got


def test_abbreviation_effects_agree_with_the_codec(spark):
    docs = spark.createDataFrame([(1, "the cat the cat sat on the cat mat"), (2, "rare word here"), (3, None), (4, "")], "doc_id long, text string")
    got = {(r["doc_id"], r["scope"], r["t"]): (r["words_before"], r["words_after"], r["lost"]) for r in abbrev.abbreviation_effects(docs, {2: ["rare word", "the cat"]}, (1, 2)).collect()}
    assert got[1, "corpus", 1] == (9, 9, []) and got[1, "corpus", 2] == (9, 6, ["cat", "the"])
    assert got[2, "corpus", 1] == (3, 2, ["rare", "word"]) and got[2, "document", 2] == (3, 3, [])
    assert got[1, "document", 1] == (9, 6, ["cat", "the"]) and got[3, "corpus", 2] == got[4, "document", 1] == (0, 0, [])


def test_optimal_bins_of_groups(spark):
    from ctxpress.operators import quant as q

    t = spark.createDataFrame([("a", 1.0), ("a", 1.1), ("a", 9.0), ("b", 5.0), ("b", None), ("c", None)], "k string, x double")
    got = {r["k"]: (r["centroids"], round(r["mse"], 6)) for r in q.optimal_bins(t, "k", "x", 2).collect()}
    assert got == {"a": ([1.05, 9.0], round(2 * 0.0025 / 3, 6)), "b": ([5.0], 0.0)}


@given(st.lists(st.sampled_from([" ", "  ", "the", "a", "big", "cat", "AA1", "AB1", abbrev.ESCAPE, ".", "the big", "\n", "_", "é", "$1"]), max_size=30).map("".join))
@settings(max_examples=30, deadline=None, suppress_health_check=list(HealthCheck))
def test_built_in_codec_is_lossless_and_equals_the_other_where_no_words_clash(spark, text):
    m, freq = {"the big": "AA1", "big cat": "AB1"}, {"the big": 9, "big cat": 5}
    t = spark.createDataFrame([(text,), (None,), (text + " the big cat",)], "text string")
    got = t.select("text", abbrev.abbreviate_native(F.col("text"), m, freq).alias("short")).select("*", abbrev.restore_native(F.col("short"), m).alias("back"))
    other = abbrev.Codec(m, "frequency_first", freq).encoder()
    for r in abbrev.restore(got, m).collect():
        assert r["back"] == r["text"] == r["restored"]
        assert r["text"] is None or any(x in r["text"] for x in (abbrev.ESCAPE, "AA1", "AB1")) or r["short"] == other(r["text"])


def test_exact_quantiles_equal_percentile(spark):
    rng = np.random.default_rng(5)
    shares = [0.0, 0.01, 0.25, 1 / 3, 0.5, 0.99, 1.0]
    for x in (rng.lognormal(0, 8, 5000), rng.integers(0, 9, 3000).astype(float), [7.0], [1.0, 2.0], [-1.7e308, 1.7e308, 0.0, 1e-300], np.r_[rng.normal(size=400), 1e300]):
        t = spark.createDataFrame([(float(v),) for v in x] + [(None,), (float("nan"),), (float("inf"),)], "x double")
        want = t.agg(F.percentile(quant.finite(F.col("x")), F.array(*[F.lit(s) for s in shares]))).first()[0]
        for buckets in (64, 1 << 16):
            assert quant.exact_quantiles(t, "x", shares, buckets) == pytest.approx(want, rel=1e-12)
    assert quant.exact_quantiles(t.limit(0), "x", shares) == []


def test_count_min_never_counts_too_few_and_adds_up(spark):
    t = spark.range(4000).select(F.concat(F.lit("w"), F.floor(F.sqrt("id")).cast("string")).alias("w"))
    types = t.groupBy("w").agg(F.count("*").alias("freq"))
    narrow = {r["w"]: (r["freq"], r["estimate"]) for r in relational.count_min_estimates(types, "w", relational.count_min(t, F.col("w"), 16), 16).collect()}
    assert len(narrow) == types.count() and all(f <= e <= f + 4000 for f, e in narrow.values()) and any(e > f for f, e in narrow.values())
    halves = [relational.count_min(h, F.col("w")) for h in t.randomSplit([0.5, 0.5], 3)]
    added = halves[0].unionByName(halves[1]).groupBy("row", "cell").agg(F.sum("n").alias("n"))
    assert sorted(map(tuple, added.collect())) == sorted(map(tuple, relational.count_min(t, F.col("w")).collect()))
