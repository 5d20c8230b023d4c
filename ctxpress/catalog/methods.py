"""Task accuracy of methods A to F by scorer and kind of examples, and of every setting of the ablation."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.catalog.abbreviation import codec_sql
from ctxpress.catalog.information import BI, P1, PROMPTS, W
from ctxpress.catalog.numbers import CENTERS, MIXED, vectors
from ctxpress.operators import abbrev, exemplars, fidelity, measures, prune, selfinfo
from ctxpress.plans import workloads
from ctxpress.sources.tables import load

SCORERS = ("scorer_a", "scorer_b", "scorer_c", "scorer_d")

# The same in SQL, piece by piece.
QUESTIONS = f"pr AS (SELECT item_id AS prompt_id, list_transform(regexp_extract_all(text, '{W}')[1:8], lambda x: lower(x)) AS w FROM benchmark), pt AS (SELECT prompt_id, w, unnest(range(len(w))) AS pos, unnest(w) AS tok FROM pr)"
#: Information of every question's words by the four scorers.
EVERY_SCORER = f"""{P1.replace(PROMPTS, QUESTIONS)}, {BI}, ta AS (SELECT list_concat(['', ''], w) AS x, w FROM da),
  tr AS (SELECT ctx, tok, count(*) AS n FROM (SELECT unnest(list_transform(range(len(w)), lambda i: x[i + 1] || ' ' || x[i + 2])) AS ctx, unnest(w) AS tok FROM ta) GROUP BY ALL),
  tc AS (SELECT ctx, sum(n)::BIGINT AS m FROM tr GROUP BY ctx),
  q AS (SELECT *, CASE WHEN pos >= 1 THEN w[pos] ELSE '' END AS c1, CASE WHEN pos >= 2 THEN w[pos - 1] ELSE '' END || ' ' || CASE WHEN pos >= 1 THEN w[pos] ELSE '' END AS c2,
    count(*) OVER (PARTITION BY prompt_id, tok ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM p1),
  g AS (SELECT q.*, coalesce(tr.n::DOUBLE / tc.m, 0.0) AS p3, coalesce(bi.n::DOUBLE / bc.m, 0.0) AS p2
    FROM q LEFT JOIN tr ON tr.ctx = c2 AND tr.tok = q.tok LEFT JOIN tc ON tc.ctx = c2 LEFT JOIN bi ON bi.ctx = c1 AND bi.tok = q.tok LEFT JOIN bc ON bc.ctx = c1),
  d AS (SELECT prompt_id, pos, tok, round(-log2(p1), 6) AS s, unnest(['scorer_a', 'scorer_b', 'scorer_c', 'scorer_d']) AS scorer,
    unnest([p1, 0.3::DOUBLE * p1 + 0.7::DOUBLE * p2, 0.2::DOUBLE * p1 + 0.5::DOUBLE * p3 + 0.3::DOUBLE * p2, CASE WHEN pos = 0 THEN p1 ELSE 0.5::DOUBLE * seen::DOUBLE / pos + 0.5::DOUBLE * p1 END]) AS p FROM g),
  sd AS (SELECT *, round(-log2(p), 6) AS y FROM d),
  scored AS (SELECT scorer, prompt_id, pos, tok, round(CASE WHEN s <> 0 AND abs(y - s) / s <= 0.1 THEN 0.5 * s + 0.5 * y ELSE y END, 7) AS score FROM sd)"""


def kept_sql(share: str) -> str:
    return f"SELECT *, row_number() OVER (PARTITION BY scorer, prompt_id ORDER BY score DESC, pos) <= ceil({share} * count(*) OVER (PARTITION BY scorer, prompt_id)) AS kept FROM scored"


READER = f"""dt AS (SELECT DISTINCT doc_id, tok FROM dw),
  idf AS (SELECT tok, round(ln((d + 1) / (count(*) + 1)::DOUBLE) * 1000000)::BIGINT AS idf FROM dt, (SELECT count(*) AS d FROM documents) GROUP BY tok, d HAVING count(*) <= 0.1 * d),
  gold AS (SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)), asked AS (SELECT DISTINCT item_id FROM gold)"""


def abbreviated_sql(name: str, grams: str, n: int) -> str:
    """CTE ``name`` (keys, words): each text's words after a scan that replaces the n-grams of list column ``dic`` of ``grams`` (doc_id, keys, dic, text)."""
    done, waiting = "split_part(a, chr(1), 1)", "split_part(a, chr(1), 2)"  # a is what is done, a mark, and up to n - 1 words that wait
    now = f"(CASE WHEN {waiting} = '' THEN x ELSE {waiting} || ' ' || x END)"
    first = f"split_part({now}, ' ', 1)"
    step = f"""(CASE WHEN len(string_split({now}, ' ')) < {n} THEN {done} || chr(1) || {now} WHEN list_contains(dic, {now}) THEN {done} || ' ' || chr(2) || list_position(dic, {now}) || chr(1)
      ELSE {done} || ' ' || {first} || chr(1) || substr({now}, length({first}) + 2) END)"""
    runs = f"(SELECT * EXCLUDE (text), unnest(regexp_extract_all(text, '{W}(?: {W})*')) AS r FROM {grams})"
    scan = f"list_reduce(list_concat([chr(1)], string_split(r, ' ')), lambda a, x: {step})"
    return f"{name} AS (SELECT * EXCLUDE (dic, r), list_filter(string_split(replace({scan}, chr(1), ' '), ' '), lambda z: z <> '') AS words FROM {runs})"


def shots_of(spark, sf, clusters=None) -> dict:
    """Three examples of each kind among the items: vector i stands for the item i modulo the number of items."""
    items, v = load(spark, sf, "benchmark", "item_id"), vectors(spark, sf)
    n = max(1, items.count())
    grouped = clusters if clusters is not None else v.withColumnRenamed("label", "cluster")
    best = exemplars.few_shot(exemplars.prototypes(grouped))
    return {k: t.select((F.col("id") % n).alias("item_id")).distinct() for k, t in (("representative", best), ("random", exemplars.random_shots(v, "id")))}


def corpus_dictionary(docs, n: int, k: int) -> dict[str, str]:
    top = abbrev.select_top(abbrev.codec_frequencies(docs, n), k)
    top = docs.sparkSession.createDataFrame(top.collect(), top.schema)  # k rows, counted once
    return abbrev.as_mapping(abbrev.build_dictionary(top, docs))


def results(spark, sf, clusters=None):
    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    return workloads.method_results(docs, items, shots_of(spark, sf, clusters), corpus_dictionary(docs, 2, 150))


BASE = "method = 'A'"
SHOTS = f"""shot AS (SELECT DISTINCT kind, id % (SELECT count(*) FROM benchmark) AS item_id FROM (SELECT 'representative' AS kind, id FROM (SELECT id FROM proto ORDER BY size DESC, id LIMIT 3) UNION ALL SELECT 'random', vec_id FROM (SELECT vec_id FROM embeddings ORDER BY {MIXED}, vec_id LIMIT 3))),
  ex AS (SELECT DISTINCT kind, tok FROM (SELECT kind, unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM shot JOIN benchmark USING (item_id)))"""
RESULTS = f"""{EVERY_SCORER}, {READER}, {CENTERS}, {SHOTS},
  dic AS (SELECT list(gram) AS dic FROM (SELECT gram FROM {codec_sql(2)} ORDER BY freq DESC, gram LIMIT 150)), src AS (SELECT doc_id, text, dic FROM documents, dic),
  {abbreviated_sql('ab', 'src', 2)},
  seen AS (SELECT 'plain' AS source, doc_id, tok FROM dt UNION ALL SELECT DISTINCT 'short', doc_id, lower(unnest(words)) FROM ab),
  kp AS ({kept_sql('0.6')}),
  terms AS (SELECT scorer, item_id, tok, idf FROM (SELECT DISTINCT 'none' AS scorer, prompt_id AS item_id, tok FROM pt UNION SELECT scorer, prompt_id, tok FROM kp WHERE kept) JOIN idf USING (tok)),
  qs AS (SELECT source, scorer, item_id, doc_id, sum(idf)::BIGINT AS q FROM seen JOIN terms USING (tok) GROUP BY ALL),
  es AS (SELECT source, kind, doc_id, sum(idf)::BIGINT AS e FROM seen JOIN ex USING (tok) JOIN idf USING (tok) GROUP BY ALL),
  m AS (SELECT unnest(['A', 'B', 'C', 'D', 'E', 'F']) AS method, unnest(['plain', 'plain', 'plain', 'plain', 'short', 'plain']) AS source, unnest([false, true, false, true, true, true]) AS shots),
  arms AS (SELECT method, source, kind, scorer FROM m, (SELECT unnest(['none', 'representative', 'random']) AS kind), (SELECT unnest(['none', 'scorer_a', 'scorer_b', 'scorer_c', 'scorer_d']) AS scorer) WHERE shots = (kind <> 'none') AND (method IN ('A', 'B')) = (scorer = 'none')),
  found AS (SELECT method, kind, scorer, item_id, arg_min(doc_id, (-(4 * q + coalesce(e, 0)), doc_id)) AS found FROM arms JOIN qs USING (source, scorer) LEFT JOIN es USING (source, kind, doc_id) GROUP BY ALL),
  res AS (SELECT scorer, method, kind AS exemplar_kind, item_id, found, EXISTS (SELECT 1 FROM gold g WHERE g.item_id = x.item_id AND g.doc_id = x.found) AS correct FROM (SELECT a.*, k.item_id, f.found FROM arms a CROSS JOIN asked k LEFT JOIN found f ON f.method = a.method AND f.kind = a.kind AND f.scorer = a.scorer AND f.item_id = k.item_id) x),
  acc AS (SELECT scorer, method, exemplar_kind, count(*) AS questions, round(100 * sum(correct::INT) / count(*), 4) AS accuracy FROM res GROUP BY ALL),
  tab AS (SELECT *, round(accuracy - (SELECT max(accuracy) FROM acc WHERE method = 'A'), 4) AS delta FROM acc)"""


@query(f"WITH {RESULTS} SELECT scorer, method, exemplar_kind, item_id, found, correct FROM res")
def method_answers(spark, sf):
    """What the reader answers to every question under methods A to F, by scorer and kind of examples."""
    return results(spark, sf)


@query(f"WITH {RESULTS} SELECT * FROM tab")
def method_accuracy(spark, sf):
    """Accuracy of methods A to F by scorer and kind of examples, in points, and against the original prompt."""
    return workloads.accuracy_table(results(spark, sf), "scorer", "method", "exemplar_kind", base=BASE)


@query(f"WITH {RESULTS} SELECT method, exemplar_kind, {', '.join(f'''max(delta) FILTER (WHERE scorer = '{s}') AS {s}''' for s in SCORERS)} FROM tab WHERE method NOT IN ('A', 'B') GROUP BY ALL")
def method_heatmap(spark, sf):
    """Accuracy deltas, methods and kinds of examples down, scorers across."""
    t = workloads.accuracy_table(results(spark, sf), "scorer", "method", "exemplar_kind", base=BASE).where("method not in ('A', 'B')")
    return t.groupBy("method", "exemplar_kind").pivot("scorer", list(SCORERS)).agg(F.max("delta"))


@query()
def method_accuracy_swept(spark, sf):
    """The same with examples from the whole chain: sweep over the number of clusters, best one, clusters, prototypes."""
    f = vectors(spark, sf).select("id", "vec")
    _, best = exemplars.silhouette_sweep(f, sample_fraction=exemplars.sample_share(f))
    return workloads.accuracy_table(results(spark, sf, exemplars.cluster(f, best)), "scorer", "method", "exemplar_kind", base=BASE)


SHARES = (0.4, 0.6, 0.8)
BUDGETS = " UNION ALL ".join(f"SELECT '{s}' AS share, * FROM ({kept_sql(str(s))})" for s in SHARES)
PRUNED = f"""{EVERY_SCORER}, {READER}, kp AS ({BUDGETS}),
  terms AS (SELECT DISTINCT scorer || ' ' || share AS setting, prompt_id AS item_id, tok FROM kp WHERE kept),
  qs AS (SELECT setting, item_id, doc_id, sum(idf)::BIGINT AS q FROM dt JOIN terms USING (tok) JOIN idf USING (tok) GROUP BY ALL),
  found AS (SELECT setting, item_id, arg_min(doc_id, (-q, doc_id)) AS found FROM qs GROUP BY ALL),
  acc AS (SELECT setting, round(avg((EXISTS (SELECT 1 FROM gold g WHERE g.item_id = x.item_id AND g.doc_id = x.found))::INT), 6) AS accuracy FROM (SELECT s.setting, k.item_id, f.found FROM (SELECT DISTINCT setting FROM terms) s CROSS JOIN asked k LEFT JOIN found f ON f.setting = s.setting AND f.item_id = k.item_id) x GROUP BY setting),
  cnt AS (SELECT scorer || ' ' || share AS setting, prompt_id, tok, count(*) AS a, count(*) FILTER (WHERE kept) AS b FROM kp GROUP BY ALL),
  cos AS (SELECT setting, round(avg(c), 6) AS cosine FROM (SELECT setting, prompt_id, sum(a * b) / (sqrt(sum(a * a)) * sqrt(sum(b * b))) AS c FROM cnt GROUP BY ALL) GROUP BY setting),
  st AS (SELECT setting, cosine, accuracy FROM acc JOIN cos USING (setting))"""


def pruned_settings(spark, sf):
    """(setting, cosine, accuracy): questions pruned by every scorer to every share, how close they stay, and what the reader finds."""
    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    questions, idf, gold = workloads.opening(items), workloads.word_weights(docs), workloads.answers(docs, items)
    asked, kept = questions.select(F.col("item_id").alias("prompt_id"), "text"), None
    for name in SCORERS:
        scored = selfinfo.score_tokens(asked, docs.select("text"), selfinfo.get_scorer(name, docs.select("text"))).persist()
        for share in SHARES:
            t = prune.prune_tokens(scored, prune.Budget.ratio(share)).select(F.lit(f"{name} {share}").alias("setting"), F.col("prompt_id").alias("item_id"), "tok", "kept")
            kept = t if kept is None else kept.unionAll(t)
    kept = kept.persist()
    terms = kept.where("kept").select("setting", "item_id", "tok").distinct().join(idf, "tok")
    hits = docs.select("doc_id", F.explode(F.array_distinct(workloads.words(F.col("text"), True))).alias("tok")).join(F.broadcast(terms), "tok")
    found = workloads.best_documents(hits.groupBy("setting", "item_id", "doc_id").agg(F.sum("idf").alias("score")), "setting")
    acc = workloads.judged(found, kept.select("setting").distinct(), gold, "setting").groupBy("setting").agg(F.round(F.avg(F.col("correct").cast("int")), 6).alias("accuracy"))
    counts = kept.groupBy("setting", "item_id", "tok").agg(F.count("*").alias("a"), F.count_if("kept").alias("b"))
    cos = counts.groupBy("setting", "item_id").agg((F.sum(F.col("a") * F.col("b")) / (F.sqrt(F.sum(F.col("a") * F.col("a"))) * F.sqrt(F.sum(F.col("b") * F.col("b"))))).alias("c"))
    return acc.join(cos.groupBy("setting").agg(F.round(F.avg("c"), 6).alias("cosine")), "setting").select("setting", "cosine", "accuracy")


@query(f"WITH {PRUNED} SELECT * FROM st")
def pruned_question_settings(spark, sf):
    return pruned_settings(spark, sf)


@query(f"WITH {PRUNED} SELECT a.setting AS better_task, b.setting AS closer_text FROM st a JOIN st b ON a.cosine < b.cosine AND a.accuracy > b.accuracy")
def metric_disagreement(spark, sf):
    """Pairs of settings that cosine and passage accuracy order differently."""
    return measures.metric_disagreement(pruned_settings(spark, sf).persist(), "setting", "cosine", "accuracy")


GRAMS, TOPS = (2, 3, 4, 5), (1, 2, 3, 4, 5)


def ranked_grams(docs) -> dict[int, list[str]]:
    top = abbrev.select_top(abbrev.frequent_codec_ngrams(docs, GRAMS, max(TOPS)), max(TOPS), "n").collect()
    return {g: [r["gram"] for r in sorted(top, key=lambda r: (-r["freq"], r["gram"])) if r["n"] == g] for g in GRAMS}


def _settings_sql() -> str:
    """CTEs up to eff (doc_id, scope, g, t, words): words of every text under every setting of the ablation, with repeats."""
    parts = []
    for g in GRAMS:
        corpus = f"SELECT gram, row_number() OVER (ORDER BY freq DESC, gram) AS k FROM {codec_sql(g)}"
        own = f"SELECT doc_id, gram, row_number() OVER (PARTITION BY doc_id ORDER BY freq DESC, gram) AS k FROM {codec_sql(g, 'doc_id')} WHERE freq > 1"
        parts.append(f"""c{g} AS (SELECT t, list(gram) FILTER (WHERE k <= t) AS dic FROM ({corpus} QUALIFY k <= 5), (SELECT unnest([1, 2, 3, 4, 5]) AS t) GROUP BY t),
  o{g} AS (SELECT doc_id, t, list(gram) FILTER (WHERE k <= t) AS dic FROM ({own} QUALIFY k <= 5), (SELECT unnest([1, 2, 3, 4, 5]) AS t) GROUP BY ALL),
  s{g} AS (SELECT doc_id, 'corpus' AS scope, t, dic, text FROM documents, c{g} UNION ALL SELECT d.doc_id, 'document', t.t, coalesce(dic, []), text FROM documents d CROSS JOIN (SELECT unnest([1, 2, 3, 4, 5]) AS t) t LEFT JOIN o{g} o ON o.doc_id = d.doc_id AND o.t = t.t),
  {abbreviated_sql(f'a{g}', f's{g}', g)}""")
    eff = " UNION ALL ".join(f"SELECT doc_id, scope, {g} AS g, t, flatten(list(words)) AS words FROM a{g} GROUP BY ALL" for g in GRAMS)
    return ",\n  ".join(parts) + f",\n  eff AS ({eff})"


ABLATION = f"""dw AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM documents), {READER}, {_settings_sql()},
  total AS (SELECT count(*) AS n FROM dw), ratio AS (SELECT scope, g, t, round(any_value(n) / sum(len(words))::DOUBLE, 6) AS ratio FROM eff, total GROUP BY scope, g, t),
  terms AS (SELECT DISTINCT item_id, tok, idf FROM (SELECT item_id, unnest(list_transform(regexp_extract_all(text, '{W}')[1:8], lambda x: lower(x))) AS tok FROM benchmark) JOIN idf USING (tok)),
  seen AS (SELECT 'original' AS scope, 0 AS g, 0 AS t, doc_id, tok FROM dt UNION ALL SELECT DISTINCT scope, g, t, doc_id, lower(unnest(words)) FROM eff),
  qs AS (SELECT scope, g, t, item_id, doc_id, sum(idf)::BIGINT AS q FROM seen JOIN terms USING (tok) GROUP BY ALL),
  found AS (SELECT scope, g, t, item_id, arg_min(doc_id, (-q, doc_id)) AS found FROM qs GROUP BY ALL),
  res AS (SELECT s.*, k.item_id, EXISTS (SELECT 1 FROM found f JOIN gold y ON y.item_id = f.item_id AND y.doc_id = f.found WHERE f.scope = s.scope AND f.g = s.g AND f.t = s.t AND f.item_id = k.item_id) AS correct FROM (SELECT DISTINCT scope, g, t FROM qs) s CROSS JOIN asked k),
  acc AS (SELECT scope, g, t, count(*) AS questions, round(100 * sum(correct::INT) / count(*), 4) AS accuracy FROM res GROUP BY scope, g, t),
  tab AS (SELECT scope, g, t, questions, accuracy, round(accuracy - (SELECT max(accuracy) FROM acc WHERE scope = 'original'), 4) AS delta FROM acc)"""


@query(f"WITH {ABLATION} SELECT scope, g::INTEGER AS g, t::INTEGER AS t, questions, accuracy, delta, CASE WHEN delta >= 4 THEN 'best' WHEN delta > 0 THEN 'next' WHEN delta = 0 THEN 'even' ELSE 'failure' END AS region, ratio FROM tab JOIN ratio USING (scope, g, t)")
def ablation_regions(spark, sf):
    """Passage finding over all documents, abbreviated by every n-gram length and dictionary size, for one dictionary and for one of each text."""
    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    return workloads.ablation_accuracy(docs, items, ranked_grams(docs), TOPS)


@query(f"""WITH dw AS (SELECT doc_id, unnest(regexp_extract_all(text, '{W}')) AS tok FROM documents), {_settings_sql()}
SELECT scope, g::INTEGER AS g, t::INTEGER AS t, ((SELECT count(*) FROM dw) - sum(len(words)))::BIGINT AS saved_words, (SELECT count(*) FROM dw) AS words, round((SELECT count(*) FROM dw) / sum(len(words))::DOUBLE, 6) AS ratio FROM eff GROUP BY scope, g, t""")
def ablation_grid(spark, sf):
    """Words saved by dictionaries of 1 to 5 n-grams of 2 to 5 words, one for the corpus or one for each text; texts are read once."""
    docs = load(spark, sf, "documents", "doc_id", "text")
    t = abbrev.abbreviation_effects(docs, ranked_grams(docs), TOPS).groupBy("scope", "g", "t").agg(F.sum("words_before").alias("words"), F.sum("words_after").alias("after"))
    return t.select("scope", "g", "t", (F.col("words") - F.col("after")).alias("saved_words"), "words", F.round(F.col("words") / F.col("after"), 6).alias("ratio"))


@query()
def pareto_settings(spark, sf):
    """Settings of the whole ablation that no other beats in both ratio and mean cosine."""
    docs = load(spark, sf, "documents", "doc_id", "text")
    t = abbrev.abbreviation_effects(docs, ranked_grams(docs), TOPS).groupBy(F.concat("scope", F.lit(" G"), "g", F.lit("T"), "t").alias("setting"))
    t = t.agg(F.round(F.sum("words_before") / F.sum("words_after"), 6).alias("ratio"), F.round(F.avg("cosine"), 6).alias("cosine"))
    return measures.pareto(t.persist(), "setting", "ratio", "cosine")
