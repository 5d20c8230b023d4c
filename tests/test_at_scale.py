"""Inputs as they come with larger tables: long texts, close scores, fractions of seconds; each query against its SQL."""

import duckdb
import pytest
from test_oracle import ORACLE, QUERIES, rows_of

from ctxpress.operators import prune


def agree(spark, folder, name, **tables):
    """Writes the tables, runs the query and its SQL on them, and compares the rows."""
    con = duckdb.connect()
    for t, rows in tables.items():
        rows.coalesce(1).write.parquet(f"{folder}/{t}.parquet")
        con.execute(f"create view {t} as select * from '{folder}/{t}.parquet/*.parquet'")
    df = QUERIES[name](spark, str(folder))
    got, rel = rows_of(df.columns, df.collect()), con.execute(ORACLE[name])
    assert got == rows_of([d[0] for d in rel.description], rel.fetchall())
    return got


def test_a_cut_is_rounded_as_in_sql(spark):
    scores = [9.4713725, 11.0000035, 14.2613865, 8.0305905, 0.0000005]
    want = duckdb.connect().execute("select list_transform(?::DOUBLE[], lambda v: v >= round(v, 6))", [scores]).fetchone()[0]
    t = spark.createDataFrame([(i, 0, "w", s) for i, s in enumerate(scores)], "prompt_id long, pos int, tok string, score double")
    kept = prune.prune_tokens(t, prune.Budget.percentile(0.4))
    assert [r["kept"] for r in kept.orderBy("prompt_id").collect()] == want


def test_seconds_of_a_range_are_the_nearest(spark, tmp_path):
    rows = [(1, 7, "2024-01-01 00:00:00.400", "a", 1.5), (2, 7, "2024-01-01 01:00:00.600", "b", 2.25), (3, 7, "2024-01-01 02:00:00.500", "c", 4.0), (4, 7, "2024-01-01 02:00:01.500", "d", 8.0)]
    t = spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string, value double").selectExpr("event_id", "user_id", "cast(ts as timestamp_ntz) ts", "event_type", "value")
    agree(spark, tmp_path, "window_frames", events=t)


def test_thousands_of_sentences_in_a_text(spark, tmp_path):
    text = ". ".join(f"word{i % 17} and word{i % 5}" for i in range(3000))
    got = agree(spark, tmp_path, "baseline_extractive", documents=spark.createDataFrame([(1, "s", text), (2, "s", "one. two two")], "doc_id long, source string, text string"))
    assert max(r[2] for r in got) == 3000


def test_texts_of_the_same_words_tie_whatever_the_order(spark, tmp_path):
    import random

    mix, sizes = random.Random(3), list(range(1, 151))
    words = [f"w{n}x{'a' * (n % 7)}" for n in sizes]
    docs, items = [], []
    for group in range(800):
        own = mix.sample(words, 40)
        items.append((group, " ".join(own)))
        for copy in range(4):
            mix.shuffle(own)
            docs.append((group + 800 * copy, "s", " ".join(own)))
    docs += [(10_000 + n, "s", " ".join(words[:n])) for n in sizes]
    tables = {"documents": spark.createDataFrame(docs, "doc_id long, source string, text string").repartition(7), "benchmark": spark.createDataFrame(items, "item_id long, text string")}
    for t, rows in tables.items():
        rows.write.parquet(f"{tmp_path}/{t}.parquet")
    assert [r["found"] for r in QUERIES["passage_finding"](spark, str(tmp_path)).orderBy("item_id").collect()] == list(range(800))


def test_exact_silhouette_makes_no_row_of_a_pair(spark, tmp_path):
    from ctxpress.operators import exemplars

    rows = [(i, [float(i % 5), 1000.0 + i % 3, 0.25 * (i // 40)], i % 4 if i < 199 else 9) for i in range(200)]
    t = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    assert len(agree(spark, tmp_path, "silhouette_exact_given_labels", embeddings=t.where("label < 9"))) == 199
    one = exemplars.silhouette_exact(t.selectExpr("vec_id id", "embedding vec", "label cluster"))
    assert [(r["id"], r["a"], r["s"]) for r in one.where("cluster = 9").collect()] == [(199, None, 0.0)]
    assert "Join" not in one._jdf.queryExecution().executedPlan().toString()


def test_settings_of_the_ablation_scan_no_text_again(monkeypatch):
    from types import SimpleNamespace

    import pandas as pd

    from ctxpress.operators import abbrev

    monkeypatch.setattr(abbrev.Codec, "_scan", None)  # words of a text are found once, not once for each of 40 settings
    docs = SimpleNamespace(select=lambda *_: SimpleNamespace(mapInPandas=lambda f, _: f))
    texts = pd.DataFrame({"doc_id": [1, 2, 3], "text": ["a b a b. A b", "\x1ba b a b", None]})
    out = pd.concat(abbrev.abbreviation_effects(docs, {2: ["a b"]}, (1,))(iter([texts]))).astype({"doc_id": int})
    assert [(r.doc_id, r.scope, r.words_after, r.lost) for r in out.itertuples()] == [
        (1, "corpus", 4, []), (1, "document", 4, []), (2, "corpus", 3, []), (2, "document", 3, []), (3, "corpus", 0, []), (3, "document", 0, []),
    ]


def test_few_prompts_count_only_their_contexts(spark):
    from ctxpress.operators import selfinfo

    docs = spark.createDataFrame([("a b c a b d",), ("c a b",), ("x y z",)], "text string")
    asked = selfinfo.prompt_tokens(spark.createDataFrame([(1, "a b c")], "prompt_id long, text string"), whole=False)
    model = selfinfo.NgramModel(docs, 2, asked=asked)
    assert {r["ctx"] for r in model.tables[0][1].collect()} == {"", "a", "b"}
    few, every = ({r["pos"]: r["s_dyn"] for r in m.score(asked).collect()} for m in (model, selfinfo.NgramModel(docs, 2)))
    assert few == every


def test_all_scorers_share_one_pass_and_ngrams_nobody_asks_for_stay_at_home(spark, tmp_path):
    from ctxpress.operators import selfinfo

    asked = spark.createDataFrame([(f"c{i}", "t") for i in range(50)], "ctx string, tok string")
    rows = spark.createDataFrame([(f"c{i}", t) for i in range(3000) for t in ("t", "u")], "ctx string, tok string")
    left = selfinfo.only_asked(rows, asked, "ctx", "tok").collect()
    assert {tuple(r) for r in left} >= {(f"c{i}", "t") for i in range(50)} and len(left) < 60
    texts = ["the cat sat on the mat the cat", "a dog and a cat and a dog", "one", "the dog sat"]
    docs = spark.createDataFrame([(i, "s", t) for i, t in enumerate(texts * 3)], "doc_id long, source string, text string")
    turns = spark.createDataFrame([(i, 0, "user", t) for i, t in enumerate([*texts, "the the cat saw unseen words", "", None])], "conv_id long, turn int, role string, text string")
    assert len(agree(spark, tmp_path, "scorer_sensitivity", documents=docs, conversations=turns)) == 4
    plan = QUERIES["scorer_sensitivity"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(prompt_id") == 1


def odd_texts(n=60):
    """Texts with words that few have, some of which their text repeats, and passages of them as items, cut anywhere."""
    import random

    mix = random.Random(7)
    rare = [f"{mix.choice(['Éa', 'zu', 'Mo', '中文', 'q_', 'ñ'])}{i}x" for i in range(90)]
    docs, items = [], []
    for i in range(n):
        words = []
        for _ in range(30):
            own = mix.sample(rare[i % 80 : i % 80 + 10], 2)
            words += own * mix.choice([1, 1, 3]) + [mix.choice(["the", "The", "of", "a"]) for _ in range(mix.randrange(4))]
        docs.append((i, "s", "".join(w + mix.choice([" ", " ", " ", " ", " ", "  ", ". ", ",", "\n"]) for w in words)))
        at = mix.randrange(100)
        items.append((i, docs[-1][2][at : at + mix.randrange(30, 120)]))
    docs += [(n, "s", None), (n + 1, "s", ""), (n + 2, "s", " . "), (n + 3, "s", "a a a a a a a a b b b b b " * 5)]
    return docs, [*items, (n, None), (n + 1, "Zzz nowhere in any of them"), (n + 2, "ike")]


def test_the_ablation_finds_what_its_sql_finds_and_reads_texts_in_one_scan(spark, tmp_path):
    docs, items = odd_texts()
    docs = spark.createDataFrame(docs, "doc_id long, source string, text string")
    got = agree(spark, tmp_path, "ablation_regions", documents=docs, benchmark=spark.createDataFrame(items, "item_id long, text string"))
    assert len(got) == 40 and len({r[4] for r in got}) > 2
    plan = QUERIES["ablation_regions"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
    assert "regexp_extract_all" not in plan and "Generate" not in plan  # neither words nor lost words become rows


def test_items_are_found_whose_first_and_last_words_go_on(spark):
    from ctxpress.plans import workloads

    docs, items = odd_texts()
    got = workloads.answers(spark.createDataFrame([(d, t) for d, _, t in docs], "doc_id long, text string").repartition(3), spark.createDataFrame(items, "item_id long, text string"))
    assert sorted(map(tuple, got.collect())) == sorted((i, d) for i, x in items for d, _, t in docs if x and t and x in t)


def test_frequent_ngrams_count_only_what_can_be_frequent(spark):
    from ctxpress.operators import abbrev

    docs = spark.createDataFrame([(t,) for _, _, t in odd_texts(300)[0]], "text string").repartition(5)
    some = abbrev.frequent_codec_ngrams(docs, (2, 3, 5), 4)
    got = {tuple(r) for r in some.collect()}
    for n in (2, 3, 5):
        every = {(n, r["gram"], r["freq"]) for r in abbrev.codec_frequencies(docs, n).collect()}
        least = sorted((f for _, _, f in every), reverse=True)[3]
        here = {r for r in got if r[0] == n}
        assert {r for r in every if r[2] >= least} <= here <= every and len(here) < len(every) / 5
    assert {tuple(r) for r in abbrev.frequent_codec_ngrams(docs.limit(0).unionAll(spark.createDataFrame([("a b c. c",)], "text string")), (2, 3), 2).collect()} == {(2, "a b", 1), (2, "b c", 1), (3, "a b c", 1)}


def test_a_scan_takes_no_overlapping_places():
    import random

    import numpy as np

    from ctxpress.functions import wordarrays

    mix = random.Random(1)
    for n in (2, 3, 5):
        places = sorted(mix.sample(range(400), 150))
        want, end = [], 0
        for p in places:
            if p >= end:
                want.append(p)
                end = p + n
        assert wordarrays.spaced(np.array(places), n).tolist() == want


def test_words_of_many_texts_are_those_of_each():
    import pyarrow as pa
    import regex

    from ctxpress.functions import wordarrays
    from ctxpress.functions.tokens import WORD

    texts = ["ab", "cd", " e", "", None, "f g  h\tİΣ aΣ", "x", "中文 é́e.ñ", "\x1bab cd", "a\x1b", "ab", "𝒜b", "“q” ", "_1"]
    for lo in (0, 3, 8):
        w = wordarrays.Words(pa.array(texts).slice(lo), "\x1b")
        found = [(d, x) for d, t in enumerate(texts[lo:]) for x in regex.finditer(WORD, t or "")]
        assert w.names.take(pa.array(w.word)).to_pylist() == [x[0] for _, x in found] and w.doc.tolist() == [d for d, _ in found]
        assert w.names.to_pylist() == sorted({x[0] for _, x in found}) and w.lower().to_pylist() == [x.lower() for x in w.names.to_pylist()]
        assert w.tight.tolist() == [bool(regex.match(rf" {WORD}", x.string, pos=x.end())) for _, x in found]
        assert w.marked.tolist() == [x.string[: x.start()].endswith("\x1b") for _, x in found]
    assert len(wordarrays.Words(pa.array([None, ""]))) == len(wordarrays.Words(pa.array([], pa.string()))) == 0
