"""The pipeline, methods A to F, the ablation, and the workloads with their measures."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.catalog.abbreviation import codec_sql
from ctxpress.catalog.information import DOC_WORDS, SCORED, W
from ctxpress.catalog.numbers import RANGES, hat_sql
from ctxpress.functions.tokens import token_count
from ctxpress.operators import abbrev, exemplars, fidelity, measures, prune, selfinfo
from ctxpress.plans import workloads
from ctxpress.plans.compressor import CompressorConfig, ContextCompressor, assemble, render_table
from ctxpress.sources.tables import load, prompts


def compressor(spark, sf, **changes) -> ContextCompressor:
    return ContextCompressor(load(spark, sf, "documents", "text"), CompressorConfig(**changes))


def parts(spark, sf):
    return prompts(spark, sf), load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "lineitem", "l_quantity", "l_extendedprice", "l_discount", "l_tax")


@query()
def pipeline_run(spark, sf):
    """Tokens before and after for prompts, documents and a table at the best reported setting."""
    return compressor(spark, sf).run(*parts(spark, sf)).metrics().select("part", "texts", "tokens_before", "tokens_after", "ratio", "reduction")


@query(f"""WITH {SCORED}, g AS (SELECT *, coalesce(sum((s_stat >= 8.0)::INT) OVER (PARTITION BY prompt_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS phrase FROM cs),
  ph AS (SELECT prompt_id, phrase, round(avg(score), 10) AS ps, count(*) AS n, min(pos) AS first, bool_or(regexp_matches(tok, '^\\p{{N}}+$')) AS safe FROM g GROUP BY ALL),
  pk AS (SELECT *, safe OR row_number() OVER o = 1 OR sum(n) OVER (PARTITION BY prompt_id ORDER BY safe DESC, ps DESC, first ROWS UNBOUNDED PRECEDING) <= ceil(0.5 * sum(n) OVER (PARTITION BY prompt_id)) AS kept FROM ph WINDOW o AS (PARTITION BY prompt_id ORDER BY safe DESC, ps DESC, first))
SELECT prompt_id, pos::INTEGER AS pos, tok, s_stat, s_dyn, delta, rule, score, phrase::BIGINT AS phrase, ps AS phrase_score, kept FROM g JOIN pk USING (prompt_id, phrase)""")
def pipeline_decisions(spark, sf):
    """Every decision on every token: scores, rule, phrase, and whether it stays."""
    c = compressor(spark, sf)
    return c.decide(c.score(prompts(spark, sf))).select("prompt_id", "pos", "tok", "s_stat", "s_dyn", "delta", "rule", "score", "phrase", "phrase_score", "kept")


@query()
def pipeline_similarity(spark, sf):
    return compressor(spark, sf).run(prompts(spark, sf)).similarity()


@query()
def stage_ablation(spark, sf):
    """Total tokens with each stage alone, and with all."""
    out = None
    for name, stages in (("prune", {"prune"}), ("abbreviate", {"abbreviate"}), ("quantize", {"quantize"}), ("all", {"prune", "abbreviate", "quantize"})):
        r = compressor(spark, sf, stages=frozenset(stages)).run(*parts(spark, sf))
        m = r.metrics().agg(F.sum("tokens_before").alias("tokens_before"), F.sum("tokens_after").alias("tokens_after")).select(F.lit(name).alias("stages"), "tokens_before", "tokens_after")
        out = m if out is None else out.unionAll(m)
    return out


HEAD_GRIDS = ("l_quantity", "l_extendedprice", "l_discount")


def attachments(spark, sf):
    """(prompt_id, data, data_short) for every prompt: a document and the lines of an order, as they are, and abbreviated and coded.

    A prompt has the document and the order whose number is that of its conversation, modulo their number.
    """
    c = compressor(spark, sf)
    docs, lines = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", *HEAD_GRIDS)
    short, dictionary = c.compress_documents(docs)
    coded, grids = c.compress_table(lines, list(HEAD_GRIDS))
    row = lambda cols: F.struct("l_linenumber", F.concat_ws(",", *[F.col(x).cast("string") for x in cols]).alias("line"))
    every = lambda name: F.array_join(F.transform(F.array_sort(F.col(name)), lambda x: x["line"]), "\n")
    table = coded.groupBy("l_orderkey").agg(F.collect_list(row(HEAD_GRIDS)).alias("a"), F.collect_list(row([f"{x}_q" for x in HEAD_GRIDS])).alias("b")).select("l_orderkey", every("a").alias("rows"), every("b").alias("codes"))
    p = prompts(spark, sf)
    n_docs, n_orders = docs.count(), load(spark, sf, "orders").count()
    p = p.select("prompt_id", F.pmod("conv_id", F.lit(n_docs)).alias("doc_id"), (F.pmod("conv_id", F.lit(n_orders)) + 1).alias("l_orderkey"))
    p = p.join(short.select("doc_id", "text", "short"), "doc_id", "left").join(table, "l_orderkey", "left")
    data = p.select("prompt_id", F.concat_ws("\n", "text", "rows").alias("data"), F.concat_ws("\n", "short", "codes").alias("data_short"))
    header = abbrev.dictionary_header(dictionary).first()["header"] + "; " + "; ".join(f"{g.column} {g.lo} {g.hi} {g.bits}" for g in grids)
    return data, header


def arms(spark, sf):
    """Compressed prompts with their attachments, example lines by kind, and the header."""
    r = compressor(spark, sf).run(prompts(spark, sf))
    v = load(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")
    best = exemplars.few_shot(exemplars.prototypes(v.withColumnRenamed("label", "cluster"))).select("id")
    shots = {}
    for kind, ids in (("representative", best), ("random", exemplars.random_shots(v, "id").select("id"))):
        shots[kind] = " ".join(f"example {x['id']} label {x['label']}" for x in v.join(F.broadcast(ids), "id").orderBy("id").collect())
    data, header = attachments(spark, sf)
    return r.prompts.join(data, "prompt_id", "left"), shots, ("data", "data_short"), header


@query()
def assemble_methods_a_to_f(spark, sf):
    """Tokens of every prompt with its attachments under methods A to F."""
    t = assemble(*arms(spark, sf))
    return t.groupBy("method", "exemplar_kind").agg(F.count("*").alias("prompts"), F.sum("tokens_word").alias("tokens_word"), F.max("header_tokens").alias("header_tokens"))


@query(f"""WITH {DOC_WORDS}, uni AS (SELECT tok, count(*) AS n FROM dw GROUP BY tok), tot AS (SELECT sum(n)::BIGINT AS total FROM uni),
  a AS (SELECT doc_id, unnest(range(len(w))) AS pos, unnest(w) AS tok FROM (SELECT doc_id, regexp_extract_all(lower(text), '{W}') AS w FROM documents)),
  c AS (SELECT *, coalesce(lag(tok) OVER (PARTITION BY doc_id ORDER BY pos), '') AS ctx FROM a), bi AS (SELECT ctx, tok, count(*) AS n FROM c GROUP BY ALL), bc AS (SELECT ctx, sum(n)::BIGINT AS m FROM bi GROUP BY ctx),
  s AS (SELECT doc_id, pos, c.tok, round(-log2(uni.n::DOUBLE / total), 6) AS s, round(-log2(0.3::DOUBLE * (uni.n::DOUBLE / total) + 0.7::DOUBLE * (bi.n::DOUBLE / bc.m)), 6) AS y
    FROM c JOIN uni ON uni.tok = c.tok JOIN bi ON bi.ctx = c.ctx AND bi.tok = c.tok JOIN bc ON bc.ctx = c.ctx, tot),
  g AS (SELECT *, round(CASE WHEN s <> 0 AND abs(y - s) / s <= 0.1 THEN 0.5 * s + 0.5 * y ELSE y END, 7) AS score FROM s),
  k AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, pos) <= ceil(0.5 * count(*) OVER (PARTITION BY doc_id)) AS kept FROM g)
SELECT doc_id, count(*) AS total, count(*) FILTER (WHERE kept) AS kept, md5(string_agg(tok, ' ' ORDER BY pos) FILTER (WHERE kept)) AS short_md5 FROM k GROUP BY doc_id""")
def documents_as_prompts(spark, sf):
    """Whole documents as prompts, whatever their length, pruned to half of their words."""
    d = load(spark, sf, "documents", "doc_id", "text")
    scored = selfinfo.score_tokens(d.select(F.col("doc_id").alias("prompt_id"), "text"), d.select("text"))
    t = prune.reassemble(prune.prune_tokens(scored, prune.Budget.ratio(0.5)))
    return t.select(F.col("prompt_id").alias("doc_id"), "total", "kept", F.md5("text").alias("short_md5"))


@query("SELECT l_orderkey, l_linenumber, concat_ws(',', l_orderkey::VARCHAR, l_linenumber::VARCHAR, l_returnflag, l_linestatus) AS text FROM lineitem")
def render_table_csv(spark, sf):
    return render_table(load(spark, sf, "lineitem"), ["l_orderkey", "l_linenumber", "l_returnflag", "l_linestatus"]).select("l_orderkey", "l_linenumber", "text")


def passage_arms(spark, sf):
    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    m = abbrev.as_mapping(abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(docs, 2), 3), docs))
    short, ishort = abbrev.abbreviate(docs, m), abbrev.abbreviate(items, m)
    return docs, items, {"A": (docs, "text", items, "text"), "C": (short, "short", ishort, "short")}


@query(f"""WITH n AS (SELECT count(*) AS d FROM documents), dt AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '{W}'))) AS tok FROM documents),
  idf AS (SELECT tok, round(ln((d + 1) / (count(*) + 1)::DOUBLE), 6) AS idf FROM dt, n GROUP BY tok, d),
  bt AS (SELECT item_id, unnest(list_distinct(regexp_extract_all(lower(text), '{W}'))) AS tok FROM benchmark),
  s AS (SELECT item_id, doc_id, round(sum(idf), 4) AS score FROM bt JOIN idf USING (tok) JOIN dt USING (tok) GROUP BY ALL),
  b AS (SELECT item_id, arg_min(doc_id, (-score, doc_id)) AS found FROM s GROUP BY item_id),
  g AS (SELECT item_id, list(doc_id) AS gold FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY item_id)
SELECT 'A' AS arm, item_id, gold IS NOT NULL AS answerable, found, coalesce(list_contains(gold, found), false) AS correct FROM benchmark LEFT JOIN b USING (item_id) LEFT JOIN g USING (item_id)""")
def passage_finding(spark, sf):
    """Questions are benchmark passages; the reader names the document that shares most information."""
    docs, items = load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark")
    return workloads.passage_finding(docs, items, {"A": (docs, "text", items, "text")})


@query()
def passage_finding_abbreviated(spark, sf):
    """The same reader on abbreviated documents and questions, with accuracy against the originals."""
    docs, items, a = passage_arms(spark, sf)
    t = workloads.passage_finding(docs, items, a).where("answerable")
    return measures.accuracy_report(t.select(F.col("arm").alias("method"), F.lit("none").alias("arm"), "correct"))


def _questions_sql(bits: int) -> str:
    f = {"sum": "sum({})", "avg": "avg({})", "spread": "max({0}) - min({0})"}
    out = []
    for qid, by, how, col in workloads.QUESTIONS:
        e, d = f[how].format(col), f[how].format(hat_sql(col, bits))
        g = by or "'all'"
        out.append(f"SELECT '{qid}' AS qid, {g} AS grp, round({e}, 4) AS exact, round({d}, 4) AS decoded, round(coalesce(abs(({d} - ({e})) / nullif({e}, 0)), 0.0), 6) AS rel_error, coalesce(abs(({d} - ({e})) / nullif({e}, 0)), 0.0) <= 0.01 AS correct FROM lineitem, mm GROUP BY {g}")
    return f"WITH {RANGES} " + " UNION ALL ".join(out)


@query(_questions_sql(8))
def numeric_questions(spark, sf):
    return workloads.numeric_questions(load(spark, sf, "lineitem"))


@query()
def numeric_accuracy_by_bits(spark, sf):
    """Accuracy of the numeric questions, and points lost against stored values, by code width."""
    out = None
    for bits in (2, 4, 8, 12):
        t = workloads.numeric_questions(load(spark, sf, "lineitem"), bits, tau=0.001).select(F.lit(f"b{bits:02d}").alias("method"), F.lit("none").alias("arm"), "correct")
        out = t if out is None else out.unionAll(t)
    exact = workloads.numeric_questions(load(spark, sf, "lineitem"), 24, tau=0.001).select(F.lit("A").alias("method"), F.lit("none").alias("arm"), F.lit(True).alias("correct"))
    return measures.accuracy_report(out.unionAll(exact))


@query()
def scorer_sensitivity(spark, sf):
    """Mean score, share of tokens within the band, and similarity after pruning, for the four scorers."""
    t = selfinfo.scores_by_all(prompts(spark, sf), load(spark, sf, "documents", "text"))

    def arm(name):
        own = F.transform("tokens", lambda x: F.struct(x["pos"].alias("pos"), x["tok"].alias("tok"), x[name]["score"].alias("score")))
        total = F.aggregate("tokens", F.lit(0.0), lambda a, x: a + x[name]["score"])
        return F.struct(F.lit(name).alias("scorer"), total.alias("total"), F.size(F.filter("tokens", lambda x: x[name]["mean"])).alias("means"), prune.prune_in_row(own, 0.7).alias("short"))

    arms = [arm(name) for name in ("scorer_a", "scorer_b", "scorer_c", "scorer_d")]
    t = t.select(F.size("tokens").alias("n"), F.array_join(F.transform("tokens", lambda x: x["tok"]), " ").alias("text"), F.explode(F.array(*arms)).alias("e"))
    t = t.select("e.scorer", "n", "e.total", "e.means", fidelity.word_cosine(F.col("text"), F.col("e.short")).alias("cosine"))
    return t.groupBy("scorer").agg(
        F.sum("n").alias("tokens"), F.round(F.sum("total") / F.sum("n"), 4).alias("mean_score"), F.round(F.sum("means") / F.sum("n"), 4).alias("band_share"),
        F.round(F.avg("cosine"), 6).alias("mean_cosine"), F.round(F.percentile("cosine", F.lit(0.05)), 6).alias("p5_cosine"),
    )


@query()
def classification_reader(spark, sf):
    """Quality labels predicted on original and on half-truncated text by a model fitted on originals."""
    from ctxpress.operators.baselines import truncate

    d = load(spark, sf, "documents", "doc_id", "text").join(load(spark, sf, "labels", "doc_id", "quality"), "doc_id")
    part = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0  # held-out fold
    train, test = d.where(~part), d.where(part)
    a = workloads.classify_reader(train, test, "quality").select(F.lit("A").alias("arm"), "rows", "accuracy")
    return a.unionAll(workloads.classify_reader(train, test.withColumn("text", truncate(F.col("text"), 0.5)), "quality").select(F.lit("truncated").alias("arm"), "rows", "accuracy"))


def rated(spark, sf):
    """90 pairs in an order mixed by hash, original against its first half, graded by made-up raters."""
    from ctxpress.operators.baselines import truncate

    d = load(spark, sf, "documents", "doc_id", "text").orderBy((F.col("doc_id") * 48271 + 11) % 2147483647, "doc_id").limit(90)
    d = d.select(F.col("doc_id").alias("pair_id"), "text", truncate(F.col("text"), 0.5).alias("short"))
    return d, fidelity.simulated_ratings(d, fidelity.lexical_recall(F.col("text"), F.col("short")))


RATINGS = f"""d AS (SELECT doc_id AS pair_id, list_distinct(regexp_extract_all(lower(text), '{W}')) AS a, regexp_extract_all(text, '{W}') AS w FROM documents ORDER BY (doc_id * 48271 + 11) % 2147483647, doc_id LIMIT 90),
  rc AS (SELECT pair_id, CASE WHEN len(a) = 0 THEN 1.0 ELSE len(list_distinct(list_transform(w[1:ceil(len(w) * 0.5)::INT], lambda x: lower(x)))) / len(a)::DOUBLE END AS recall FROM d),
  ra AS (SELECT pair_id, r AS rater, greatest(1, least(5, round(1 + 4 * recall + b)))::INTEGER AS score FROM rc, (SELECT unnest([1, 2, 3]) AS r, unnest([-0.4, 0.0, 0.4])::DOUBLE AS b))"""


TRAINED = f"""d AS (SELECT doc_id AS pair_id, row_number() OVER (ORDER BY (doc_id * 48271 + 11) % 2147483647, doc_id) AS place, list_distinct(regexp_extract_all(lower(text), '{W}')) AS a, regexp_extract_all(text, '{W}') AS w FROM documents QUALIFY place > 90 AND place <= 150),
  rc AS (SELECT pair_id, place, CASE WHEN len(a) = 0 THEN 1.0 ELSE len(list_distinct(list_transform(w[1:ceil(len(w) * 0.5)::INT], lambda x: lower(x)))) / len(a)::DOUBLE END AS recall FROM d),
  ra AS (SELECT place, r AS rater, greatest(1, least(5, round(1 + 4 * recall + b)))::INTEGER AS score, round(1 + 4 * recall, 4) AS key FROM rc, (SELECT unnest([1, 2, 3]) AS r, unnest([-0.4, 0.0, 0.4])::DOUBLE AS b))"""


@query(f"""WITH {TRAINED}, s AS (SELECT rater, avg(score - key) AS bias FROM ra WHERE place <= 120 GROUP BY rater)
SELECT rater, count(*) AS rated, round(any_value(bias), 4) AS bias, round(avg(abs(score - key)), 4) AS gap_before, round(avg(abs(score - bias - key)), 4) AS gap_after FROM ra JOIN s USING (rater) WHERE place > 120 GROUP BY rater""")
def rater_training(spark, sf):
    """Made-up raters are shown 30 graded pairs, which tell their bias, and rate 30 others before the 90: gaps to the key before and after."""
    from ctxpress.operators.baselines import truncate

    d = load(spark, sf, "documents", "doc_id", "text").orderBy((F.col("doc_id") * 48271 + 11) % 2147483647, "doc_id").limit(150)
    d = d.withColumn("place", F.row_number().over(Window.orderBy((F.col("doc_id") * 48271 + 11) % 2147483647, "doc_id"))).where("place > 90")
    d = d.select(F.col("doc_id").alias("pair_id"), "place", "text", truncate(F.col("text"), 0.5).alias("short"))
    recall = fidelity.lexical_recall(F.col("text"), F.col("short"))
    t = fidelity.simulated_ratings(d, recall).join(d.select("pair_id", "place", F.round(1 + 4 * recall, 4).alias("key")), "pair_id")
    bias = t.where("place <= 120").groupBy("rater").agg(F.avg(F.col("score") - F.col("key")).alias("bias"))
    t = t.where("place > 120").join(F.broadcast(bias), "rater")
    gap = lambda c: F.round(F.avg(F.abs(c - F.col("key"))), 4)
    return t.groupBy("rater").agg(F.count("*").alias("rated"), F.round(F.first("bias"), 4).alias("bias"), gap(F.col("score")).alias("gap_before"), gap(F.col("score") - F.col("bias")).alias("gap_after"))


@query("SELECT unnest(['score', 'prune', 'reassemble']) AS stage, true AS timed, count(*) AS prompts FROM conversations")
def stage_timer(spark, sf):
    """The stages of prompt compression, each run on its own and timed; seconds differ, so only whether there are any is told."""
    timer, p = measures.StageTimer(), prompts(spark, sf)
    scored = selfinfo.score_tokens(p, load(spark, sf, "documents", "text")).persist()
    timer.run("score", scored)
    kept = prune.prune_tokens(scored, prune.Budget.ratio(0.5))
    timer.run("prune", kept)
    timer.run("reassemble", prune.reassemble(kept))
    scored.unpersist()
    return spark.createDataFrame([(k, v > 0, p.count()) for k, v in timer.seconds.items()], "stage string, timed boolean, prompts long")


@query(f"WITH {RATINGS} SELECT x.rater AS rater_a, y.rater AS rater_b, count(*) AS shared, round(count(*) FILTER (WHERE x.score = y.score) / count(*)::DOUBLE, 4) AS exact, round(avg(abs(x.score - y.score)), 4) AS mean_gap FROM ra x JOIN ra y ON x.pair_id = y.pair_id AND x.rater < y.rater GROUP BY ALL")
def rater_alignment(spark, sf):
    return fidelity.rater_alignment(rated(spark, sf)[1])


@query()
def rating_report(spark, sf):
    d, r = rated(spark, sf)
    cos = d.select("pair_id", fidelity.word_cosine(F.col("text"), F.col("short")).alias("cosine"))
    return fidelity.rating_report(cos.join(r.groupBy("pair_id").agg(F.avg("score").alias("rating")), "pair_id"))


@query()
def fidelity_report(spark, sf):
    """Mean and 5th percentile of similarity after pruning prompts to 70 percent, by role."""
    p = prompts(spark, sf)
    short = prune.reassemble(prune.prune_tokens(selfinfo.score_tokens(p, load(spark, sf, "documents", "text")), prune.Budget.ratio(0.7))).select("prompt_id", F.col("text").alias("short"))
    return fidelity.fidelity_report(p.join(short, "prompt_id").select("role", fidelity.word_cosine(F.col("text"), F.col("short")).alias("cosine")), "role")


@query()
def fidelity_gate(spark, sf):
    """Share of prompts that stay safe by hashed-word cosines, at three budgets."""
    p = prompts(spark, sf)
    s, out = selfinfo.score_tokens(p, load(spark, sf, "documents", "text")), None
    for share in (0.9, 0.7, 0.5):
        short = prune.reassemble(prune.prune_tokens(s, prune.Budget.ratio(share))).select("prompt_id", F.col("text").alias("short"))
        t = fidelity.fidelity_gate(fidelity.pair_similarity(p.join(short, "prompt_id")).select("cosine")).select(F.lit(share).alias("share"), "pairs", "safe", "safe_share")
        out = t if out is None else out.unionAll(t)
    return out


@query(f"""WITH e AS (SELECT a.vec_id, b.vec_id AS other, list_cosine_similarity(list_transform(a.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1)
SELECT count(*) AS pairs, round(avg(c), 6) AS mean_cosine, round(quantile_cont(c, 0.05), 6) AS p5_cosine, count(*) FILTER (WHERE c >= 0.92) AS safe FROM e""")
def cosine_of_neighbours(spark, sf):
    """The cosine measure itself, on given vectors with neighbouring ids."""
    from ctxpress.functions.scalar import cosine

    e = load(spark, sf, "embeddings", "vec_id", "embedding")
    t = e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other")), "vec_id").select(cosine(F.col("embedding"), F.col("other")).alias("c"))
    return t.agg(F.count("*").alias("pairs"), F.round(F.avg("c"), 6).alias("mean_cosine"), F.round(F.percentile("c", F.lit(0.05)), 6).alias("p5_cosine"), F.count_if(F.col("c") >= 0.92).alias("safe"))


@query(f"""WITH t AS (SELECT sum(len(regexp_extract_all(text, '{W}')))::BIGINT AS a, sum(least(3000, len(regexp_extract_all(text, '{W}'))))::BIGINT AS b FROM documents)
SELECT price_class, round(a * price / 1000, 4) AS cost_before, round(b * price / 1000, 4) AS cost_after, round(round(a * price / 1000, 4) - round(b * price / 1000, 4), 4) AS saved FROM t, (SELECT unnest(['large', 'small']) AS price_class, unnest([0.01, 0.0005])::DOUBLE AS price)""")
def cost_report(spark, sf):
    """Costs when texts are cut at 3000 words, at two made-up prices."""
    n = token_count(F.col("text"))
    t = load(spark, sf, "documents", "text").select(n.alias("t0"), F.least(n, F.lit(3000)).alias("t1"))
    return measures.cost_report(t, {"large": "0.01", "small": "0.0005"})


@query(f"""WITH {DOC_WORDS}, uni AS (SELECT tok, count(*) AS n FROM dw GROUP BY tok), tot AS (SELECT sum(n)::BIGINT AS total FROM uni),
  sn AS (SELECT doc_id, i, s FROM (SELECT doc_id, unnest(range(len(x))) AS i, unnest(x) AS s FROM (SELECT doc_id, regexp_split_to_array(lower(text), '[.!?\\n]') AS x FROM documents))),
  w AS (SELECT doc_id, i, unnest(regexp_extract_all(s, '{W}')) AS tok FROM sn),
  sc AS (SELECT doc_id, i, round(avg(round(-log2(n::DOUBLE / total), 6)), 10) AS score, count(*) AS words FROM w JOIN uni USING (tok), tot GROUP BY ALL),
  r AS (SELECT *, sum(words) OVER (PARTITION BY doc_id ORDER BY score DESC, i ROWS UNBOUNDED PRECEDING) <= ceil(0.5 * sum(words) OVER (PARTITION BY doc_id)) OR row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, i) = 1 AS kept FROM sc)
SELECT doc_id, count(*) AS sentences, count(*) FILTER (WHERE kept) AS kept, coalesce(sum(words) FILTER (WHERE kept), 0)::BIGINT AS words_kept FROM r GROUP BY doc_id""")
def baseline_extractive(spark, sf):
    """Whole sentences of the highest mean information within half of the words."""
    d = load(spark, sf, "documents", "doc_id", "text")
    uni = selfinfo.unigram_information(selfinfo.unigram_counts(d))
    s = d.select(F.col("doc_id").alias("prompt_id"), F.posexplode(F.split(F.lower("text"), r"[.!?\n]", -1)).alias("i", "s"))
    from ctxpress.functions.tokens import words

    w = s.select("prompt_id", "i", F.posexplode(words(F.col("s"))).alias("pos", "tok")).join(uni, "tok")
    t = w.select("prompt_id", F.col("i").cast("long").alias("phrase"), (F.col("i").cast("long") * 1_000_000_000 + F.col("pos")).alias("pos"), "tok", F.round("s_stat", 6).alias("score"))
    k = prune.prune_phrases(t, prune.Budget.ratio(0.5))
    return k.groupBy(F.col("prompt_id").alias("doc_id")).agg(F.countDistinct("phrase").alias("sentences"), F.countDistinct(F.when(F.col("kept"), F.col("phrase"))).alias("kept"), F.count_if("kept").alias("words_kept"))


@query(f"SELECT source, count(*) AS grams, max(freq) AS top FROM {codec_sql(2, 'source')} GROUP BY source")
def codec_grams_by_source(spark, sf):
    """Replaceable bigrams of each source: the codec's frequencies, not the study's."""
    t = abbrev.codec_frequencies(load(spark, sf, "documents", "source", "text"), 2, "source")
    return t.groupBy("source").agg(F.count("*").alias("grams"), F.max("freq").alias("top"))


JUDGED = f"""j AS (SELECT conv_id, turn, list_distinct(regexp_extract_all(lower(text), '{W}')) AS a, regexp_extract_all(text, '{W}') AS w FROM conversations),
  g AS (SELECT *, round(1 + 4 * CASE WHEN len(a) = 0 THEN 1.0 ELSE len(list_distinct(list_transform(w[1:ceil(len(w) * 0.7)::INT], lambda x: lower(x)))) / len(a)::DOUBLE END, 4) AS grade FROM j)"""


@query(f"WITH {JUDGED} SELECT count(*) AS pairs, round(avg(grade), 4) AS mean_grade, count(*) FILTER (WHERE grade < 3) AS low FROM g")
def judge_report(spark, sf):
    """Grades of truncated prompts by the offline judge: recall of the original's words."""
    from ctxpress.operators.baselines import truncate

    c = load(spark, sf, "conversations", "text").withColumn("short", truncate(F.col("text"), 0.7))
    g = c.select(measures.Judge().grade(F.col("text"), F.col("short")).alias("grade"))
    return g.agg(F.count("*").alias("pairs"), F.round(F.avg("grade"), 4).alias("mean_grade"), F.count_if(F.col("grade") < 3).alias("low"))


@query()
def scorer_agreement(spark, sf):
    """Correlation of static and dynamic information for the four scorers on all prompt words."""
    p, docs, out = prompts(spark, sf), load(spark, sf, "documents", "text"), None
    for name in ("scorer_a", "scorer_b", "scorer_c", "scorer_d"):
        s = selfinfo.score_tokens(p, docs, selfinfo.get_scorer(name, docs))
        t = s.agg(F.count("*").alias("tokens"), F.round(F.corr("s_stat", "s_dyn"), 4).alias("correlation")).select(F.lit(name).alias("scorer"), "tokens", "correlation")
        out = t if out is None else out.unionAll(t)
    return out


@query("SELECT conv_id, count(*) AS turns, string_agg(role || ': ' || text, chr(10) ORDER BY turn) AS text FROM conversations GROUP BY conv_id")
def conversation_prompts(spark, sf):
    """Whole conversations as prompts, turns in order."""
    c = load(spark, sf, "conversations")
    turns = F.array_sort(F.collect_list(F.struct("turn", F.concat("role", F.lit(": "), "text").alias("line"))))
    return c.groupBy("conv_id").agg(F.count("*").alias("turns"), turns.alias("t")).select("conv_id", "turns", F.array_join(F.transform("t", lambda x: x["line"]), "\n").alias("text"))
