"""Self-information, merged scores and pruning."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.operators import prune, selfinfo
from ctxpress.operators.prune import Budget
from ctxpress.sources.tables import load, prompts

W = r"[\p{L}\p{M}\p{N}_]+"
DOC_WORDS = f"dw AS (SELECT doc_id, source, unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM documents)"
UNI = f"{DOC_WORDS}, uni AS (SELECT tok, count(*) AS n FROM dw GROUP BY tok), tot AS (SELECT sum(n)::BIGINT AS total, count(*) AS types FROM uni)"
PROMPTS = f"pr AS (SELECT conv_id * 1000 + turn AS prompt_id, regexp_extract_all(lower(text), '{W}') AS w FROM conversations), pt AS (SELECT prompt_id, w, unnest(range(len(w))) AS pos, unnest(w) AS tok FROM pr)"
#: Prompt words with the unigram probability.
P1 = f"{UNI}, {PROMPTS}, p1 AS (SELECT prompt_id, pos, tok, w, coalesce(n::DOUBLE / total, 1.0::DOUBLE / (total + types + 1)) AS p1 FROM pt LEFT JOIN uni USING (tok), tot)"
ARR = f"da AS (SELECT regexp_extract_all(lower(text), '{W}') AS w FROM documents)"
BI = f"{ARR}, bi AS (SELECT ctx, tok, count(*) AS n FROM (SELECT unnest(list_concat([''], w[1:len(w)-1])) AS ctx, unnest(w) AS tok FROM da WHERE len(w) > 0) GROUP BY ALL), bc AS (SELECT ctx, sum(n)::BIGINT AS m FROM bi GROUP BY ctx)"
BISCORE = f"""{P1}, {BI}, sc AS (
  SELECT prompt_id, pos, p1.tok, round(-log2(p1), 6) AS s_stat,
    round(-log2(0.3::DOUBLE * p1 + 0.7::DOUBLE * coalesce(bi.n::DOUBLE / bc.m, 0.0)), 6) AS s_dyn
  FROM (SELECT *, CASE WHEN pos = 0 THEN '' ELSE w[pos] END AS ctx FROM p1) p1
  LEFT JOIN bi ON bi.ctx = p1.ctx AND bi.tok = p1.tok LEFT JOIN bc ON bc.ctx = p1.ctx)"""
SCORED = f"""{BISCORE}, cs AS (
  SELECT *, round(CASE WHEN s_stat = 0 THEN NULL ELSE abs(s_dyn - s_stat) / s_stat END, 6) AS delta,
    CASE WHEN s_stat = 0 THEN 'dynamic_only' WHEN abs(s_dyn - s_stat) / s_stat <= 0.1 THEN 'mean' ELSE 'dynamic' END AS rule,
    round(CASE WHEN s_stat <> 0 AND abs(s_dyn - s_stat) / s_stat <= 0.1 THEN 0.5 * s_stat + 0.5 * s_dyn ELSE s_dyn END, 7) AS score FROM sc)"""


def scored(spark, sf):
    return selfinfo.score_tokens(prompts(spark, sf), load(spark, sf, "documents", "text"))


@query(f"WITH {UNI} SELECT tok, n, n::DOUBLE / total AS p, round(-log2(n::DOUBLE / total), 6) AS s_stat FROM uni, tot")
def unigram_information(spark, sf):
    t = selfinfo.unigram_information(selfinfo.unigram_counts(load(spark, sf, "documents", "text")))
    return t.withColumn("s_stat", F.round("s_stat", 6))


@query(f"""WITH {DOC_WORDS}, c AS (SELECT tok, source, count(*) AS n FROM dw GROUP BY ROLLUP (tok, source)),
  t AS (SELECT source, sum(n)::BIGINT AS total FROM c WHERE tok IS NOT NULL GROUP BY source)
SELECT tok, c.source, n, round(-log2(n::DOUBLE / total), 6) AS s_stat FROM c JOIN t ON c.source IS NOT DISTINCT FROM t.source WHERE tok IS NOT NULL""")
def unigram_by_source_rollup(spark, sf):
    return selfinfo.unigram_information_by(load(spark, sf, "documents", "source", "text")).withColumn("s_stat", F.round("s_stat", 6))


@query(f"SELECT tok, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM (SELECT text FROM documents UNION ALL SELECT text FROM conversations)) GROUP BY tok")
def unigram_merge_incremental(spark, sf):
    old, new = (selfinfo.unigram_counts(load(spark, sf, t, "text")) for t in ("documents", "conversations"))
    return selfinfo.merge_counts(old, new)


@query(f"WITH {UNI} SELECT tok, n, round((n + 1.0) / (total + 1.0 * (types + 1)), 12) AS p, round(-log2((n + 1.0) / (total + 1.0 * (types + 1))), 6) AS s_stat FROM uni, tot")
def unigram_smoothed(spark, sf):
    t = selfinfo.unigram_information(selfinfo.unigram_counts(load(spark, sf, "documents", "text")), smoothing="add_alpha")
    return t.select("tok", "n", F.round("p", 12).alias("p"), F.round("s_stat", 6).alias("s_stat"))


@query(f"WITH {BISCORE} SELECT prompt_id, pos::INTEGER AS pos, tok, s_dyn FROM sc")
def bigram_conditional_information(spark, sf):
    return scored(spark, sf).select("prompt_id", "pos", "tok", "s_dyn")


@query(f"""WITH {P1}, {BI}, ta AS (SELECT list_concat(['', ''], w) AS x, w FROM da),
  tr AS (SELECT ctx, tok, count(*) AS n FROM (SELECT unnest(list_transform(range(len(w)), lambda i: x[i + 1] || ' ' || x[i + 2])) AS ctx, unnest(w) AS tok FROM ta) GROUP BY ALL),
  tc AS (SELECT ctx, sum(n)::BIGINT AS m FROM tr GROUP BY ctx),
  q AS (SELECT *, CASE WHEN pos >= 1 THEN w[pos] ELSE '' END AS c1, CASE WHEN pos >= 2 THEN w[pos - 1] ELSE '' END || ' ' || CASE WHEN pos >= 1 THEN w[pos] ELSE '' END AS c2 FROM p1)
SELECT prompt_id, pos::INTEGER AS pos, q.tok,
  round(-log2(0.2::DOUBLE * p1 + 0.5::DOUBLE * coalesce(tr.n::DOUBLE / tc.m, 0.0) + 0.3::DOUBLE * coalesce(bi.n::DOUBLE / bc.m, 0.0)), 6) AS s_dyn
FROM q LEFT JOIN tr ON tr.ctx = c2 AND tr.tok = q.tok LEFT JOIN tc ON tc.ctx = c2 LEFT JOIN bi ON bi.ctx = c1 AND bi.tok = q.tok LEFT JOIN bc ON bc.ctx = c1""")
def trigram_backoff_information(spark, sf):
    docs = load(spark, sf, "documents", "text")
    t = selfinfo.NgramModel(docs, 3).score(selfinfo.prompt_tokens(prompts(spark, sf), whole=False))
    return t.select("prompt_id", "pos", "tok", F.round("s_dyn", 6).alias("s_dyn"))


@query(f"""WITH {P1} SELECT prompt_id, pos::INTEGER AS pos, tok,
  round(-log2(CASE WHEN pos = 0 THEN p1 ELSE 0.5::DOUBLE * (count(*) OVER (PARTITION BY prompt_id, tok ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))::DOUBLE / pos + 0.5::DOUBLE * p1 END), 6) AS s_dyn FROM p1""")
def cache_information(spark, sf):
    t = selfinfo.CacheModel(selfinfo.unigram_counts(load(spark, sf, "documents", "text"))).score(selfinfo.prompt_tokens(prompts(spark, sf), whole=False))
    return t.select("prompt_id", "pos", "tok", F.round("s_dyn", 6).alias("s_dyn"))


@query(f"WITH {SCORED} SELECT prompt_id, pos::INTEGER AS pos, tok, s_stat, s_dyn, delta, rule, score FROM cs")
def combined_score(spark, sf):
    return scored(spark, sf)


@query(f"""WITH {SCORED} SELECT band, count(*) AS tokens, count(*) FILTER (WHERE delta <= band) AS averaged,
  round(avg(CASE WHEN s_stat <> 0 AND abs(s_dyn - s_stat) / s_stat <= band THEN 0.5 * s_stat + 0.5 * s_dyn ELSE s_dyn END), 4) AS mean_score
FROM cs, (SELECT unnest([0.05, 0.1, 0.15])::DOUBLE AS band) GROUP BY band""")
def band_sensitivity(spark, sf):
    return selfinfo.band_sensitivity(scored(spark, sf))


@query(f"""WITH {SCORED} SELECT 'static' AS mode, count(*) AS tokens, round(avg(s_stat), 4) AS mean_score FROM cs UNION ALL
SELECT 'dynamic', count(*), round(avg(s_dyn), 4) FROM cs UNION ALL SELECT 'combined', count(*), round(avg(score), 4) FROM cs""")
def score_mode_compare(spark, sf):
    rows = F.array(*[F.struct(F.lit(m).alias("mode"), F.col(c).alias("s")) for m, c in (("static", "s_stat"), ("dynamic", "s_dyn"), ("combined", "score"))])
    return scored(spark, sf).select(F.explode(rows).alias("r")).groupBy("r.mode").agg(F.count("*").alias("tokens"), F.round(F.avg("r.s"), 4).alias("mean_score"))


KEPT = "SELECT prompt_id, count(*) AS total, count(*) FILTER (WHERE kept) AS kept, coalesce(string_agg(tok, ' ' ORDER BY pos) FILTER (WHERE kept), '') AS text FROM k GROUP BY prompt_id"
RANK = "row_number() OVER (PARTITION BY prompt_id ORDER BY {order})"
SIZE = "count(*) OVER (PARTITION BY prompt_id)"


def pruned(spark, sf, budget, **how):
    return prune.reassemble(prune.prune_tokens(scored(spark, sf), budget, **how))


@query(f"WITH {SCORED}, k AS (SELECT *, {RANK.format(order='score DESC, pos')} <= ceil(0.5 * {SIZE}) AS kept FROM cs) {KEPT}")
def prune_tokens_ratio(spark, sf):
    return pruned(spark, sf, Budget.ratio(0.5))


@query(f"WITH {SCORED}, k AS (SELECT *, score >= 10.0 AS kept FROM cs) {KEPT}")
def prune_tokens_cut(spark, sf):
    return pruned(spark, sf, Budget.cut(10.0))


@query(f"WITH {SCORED}, k AS (SELECT *, {RANK.format(order='score DESC, pos')} <= 12 AS kept FROM cs) {KEPT}")
def prune_tokens_budget(spark, sf):
    return pruned(spark, sf, Budget.tokens(12))


@query(f"WITH {SCORED}, c AS (SELECT prompt_id, round(quantile_cont(score, 0.4), 6) AS cut FROM cs GROUP BY prompt_id), k AS (SELECT cs.*, score >= cut AS kept FROM cs JOIN c USING (prompt_id)) {KEPT}")
def prune_tokens_percentile(spark, sf):
    return pruned(spark, sf, Budget.percentile(0.4))


@query(f"WITH {SCORED}, k AS (SELECT *, regexp_matches(tok, '^\\p{{N}}+$') OR {RANK.format(order='''regexp_matches(tok, '^\\p{N}+$') DESC, score DESC, pos''')} <= ceil(0.3 * {SIZE}) AS kept FROM cs) {KEPT}")
def prune_protected(spark, sf):
    return pruned(spark, sf, Budget.ratio(0.3), protect=prune.NUMBER)


@query(f"WITH {SCORED}, k AS (SELECT *, {RANK.format(order='score DESC, pos')} <= ceil(CASE WHEN {SIZE} > 240 THEN 0.3 WHEN {SIZE} > 60 THEN 0.5 ELSE 0.7 END * {SIZE}) AS kept FROM cs) {KEPT}")
def prune_adaptive(spark, sf):
    return pruned(spark, sf, Budget.adaptive(60))


PHRASES = """ph AS (SELECT prompt_id, phrase, round(avg(score), 10) AS ps, count(*) AS n, min(pos) AS first FROM g GROUP BY ALL),
  pk AS (SELECT *, row_number() OVER o = 1 OR sum(n) OVER (PARTITION BY prompt_id ORDER BY ps DESC, first ROWS UNBOUNDED PRECEDING) <= ceil(0.5 * sum(n) OVER (PARTITION BY prompt_id)) AS kept
         FROM ph WINDOW o AS (PARTITION BY prompt_id ORDER BY ps DESC, first)),
  k AS (SELECT g.*, kept FROM g JOIN pk USING (prompt_id, phrase))"""


@query(f"""WITH {SCORED}, g AS (SELECT *, coalesce(sum((s_stat >= 8.0)::INT) OVER (PARTITION BY prompt_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS phrase FROM cs), {PHRASES} {KEPT}""")
def prune_phrases_attachment(spark, sf):
    return prune.reassemble(prune.prune_phrases(prune.group_by_attachment(scored(spark, sf)), Budget.ratio(0.5)))


@query(f"""WITH {SCORED}, ba AS (SELECT a, b, count(*) AS n FROM (SELECT unnest(w[1:len(w)-1]) AS a, unnest(w[2:]) AS b FROM da WHERE len(w) > 1) GROUP BY ALL HAVING count(*) >= 5),
  ap AS (SELECT sum(greatest(len(w) - 1, 0))::BIGINT AS ap FROM da),
  pmi AS (SELECT a, b FROM ba JOIN uni x ON x.tok = a JOIN uni y ON y.tok = b, tot, ap WHERE round(log2((ba.n::DOUBLE / ap) / ((x.n::DOUBLE / total) * (y.n::DOUBLE / total))), 6) >= 4.0),
  l AS (SELECT *, lag(tok) OVER (PARTITION BY prompt_id ORDER BY pos) AS prev FROM cs),
  g AS (SELECT l.*, sum((pmi.a IS NULL)::INT) OVER (PARTITION BY prompt_id ORDER BY pos) - 1 AS phrase FROM l LEFT JOIN pmi ON pmi.a = prev AND pmi.b = tok), {PHRASES} {KEPT}""")
def prune_phrases_pmi(spark, sf):
    docs = load(spark, sf, "documents", "text")
    return prune.reassemble(prune.prune_phrases(prune.group_by_pmi(scored(spark, sf), prune.bigram_association(docs)), Budget.ratio(0.5)))


LEX = r"[\p{L}\p{M}\p{N}_]+|[^\s\p{L}\p{M}\p{N}_]"


@query(f"""WITH {DOC_WORDS}, uni AS (SELECT tok, count(*) AS n FROM dw GROUP BY tok), tot AS (SELECT sum(n)::BIGINT AS total, count(*) AS types FROM uni),
  pr AS (SELECT conv_id * 1000 + turn AS prompt_id, regexp_extract_all(text, '{LEX}') AS w FROM conversations),
  cs AS (SELECT prompt_id, pos, pt.tok, round(-log2(coalesce(n::DOUBLE / total, 1.0::DOUBLE / (total + types + 1))), 6) AS score FROM (SELECT prompt_id, unnest(range(len(w))) AS pos, unnest(w) AS tok FROM pr) pt LEFT JOIN uni ON uni.tok = lower(pt.tok), tot),
  g AS (SELECT *, coalesce(sum(regexp_matches(tok, '^[.,;:!?]$')::INT) OVER (PARTITION BY prompt_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS phrase FROM cs), {PHRASES} {KEPT}""")
def prune_phrases_clause(spark, sf):
    """Clauses of lexical tokens by static information alone."""
    from ctxpress.functions.tokens import lexical

    t = prompts(spark, sf).select("prompt_id", F.posexplode(lexical(F.col("text"))).alias("pos", "surface")).withColumn("tok", F.lower("surface"))
    uni = selfinfo.UnigramModel(selfinfo.unigram_counts(load(spark, sf, "documents", "text")))
    t = uni.attach(t).select("prompt_id", "pos", F.col("surface").alias("tok"), F.round(-F.log2("p1"), 6).alias("score"))
    return prune.reassemble(prune.prune_phrases(prune.group_clauses(t), Budget.ratio(0.5)))


@query(f"""WITH {SCORED}, g AS (SELECT *, pos // 5 AS phrase FROM cs), ph AS (SELECT prompt_id, phrase, round(avg(score), 10) AS p0, count(*) AS n, min(pos) AS first FROM g GROUP BY ALL),
  pb AS (SELECT *, round(p0 * (1 + 0.2 * abs(percent_rank() OVER (PARTITION BY prompt_id ORDER BY first) * 2 - 1)), 10) AS ps FROM ph),
  pk AS (SELECT *, row_number() OVER o = 1 OR sum(n) OVER (PARTITION BY prompt_id ORDER BY ps DESC, first ROWS UNBOUNDED PRECEDING) <= ceil(0.5 * sum(n) OVER (PARTITION BY prompt_id)) AS kept FROM pb WINDOW o AS (PARTITION BY prompt_id ORDER BY ps DESC, first)),
  k AS (SELECT g.*, kept FROM g JOIN pk USING (prompt_id, phrase)) {KEPT}""")
def prune_position_bias(spark, sf):
    t = scored(spark, sf).withColumn("phrase", F.floor(F.col("pos") / 5))
    return prune.reassemble(prune.prune_phrases(t, Budget.ratio(0.5), position_bias=0.2))


PATTERNS = {k: v.replace("'", "''") for k, v in prune.SENSITIVE.items()}


@query("SELECT doc_id, " + ", ".join(f"len(regexp_extract_all(text, '{p}'))::BIGINT AS {k}" for k, p in PATTERNS.items()) + " FROM documents")
def prune_privacy(spark, sf):
    """Sensitive spans of each kind that go before scoring."""
    return load(spark, sf, "documents", "doc_id", "text").select("doc_id", F.explode(F.array(prune.sensitive_counts(F.col("text")))).alias("s")).select("doc_id", "s.*")


@query(f"""WITH {SCORED}, b AS (SELECT *, row_number() OVER (PARTITION BY prompt_id ORDER BY (((prompt_id * 1000003 + pos) % 2147483647 * 48271 + 7) % 2147483647), pos) <= ceil(0.5 * {SIZE}) AS rnd,
   {RANK.format(order='s_stat DESC, pos')} <= ceil(0.5 * {SIZE}) AS stat, {RANK.format(order='s_dyn DESC, pos')} <= ceil(0.5 * {SIZE}) AS dyn, {RANK.format(order='score DESC, pos')} <= ceil(0.5 * {SIZE}) AS comb, pos < ceil(0.5 * {SIZE}) AS trunc FROM cs)
SELECT 'combined' AS filter, count(*) FILTER (WHERE comb) AS kept, round(avg(score) FILTER (WHERE comb), 4) AS kept_information FROM b UNION ALL SELECT 'self_information', count(*) FILTER (WHERE stat), round(avg(score) FILTER (WHERE stat), 4) FROM b
UNION ALL SELECT 'perplexity', count(*) FILTER (WHERE dyn), round(avg(score) FILTER (WHERE dyn), 4) FROM b UNION ALL SELECT 'random_drop', count(*) FILTER (WHERE rnd), round(avg(score) FILTER (WHERE rnd), 4) FROM b UNION ALL SELECT 'truncation', count(*) FILTER (WHERE trunc), round(avg(score) FILTER (WHERE trunc), 4) FROM b""")
def baseline_filters(spark, sf):
    """Static-only and dynamic-only filters, random drop and truncation beside the merged score, at one budget."""
    from ctxpress.operators.baselines import random_drop

    t, out = scored(spark, sf), None
    arms = {"combined": "score", "self_information": "s_stat", "perplexity": "s_dyn", "random_drop": None, "truncation": "_early"}
    for name, col in arms.items():
        k = random_drop(t, 0.5) if col is None else prune.prune_tokens(t.withColumn("_early", -F.col("pos")), Budget.ratio(0.5), score_col=col)
        k = k.where("kept").agg(F.count("*").alias("kept"), F.round(F.avg("score"), 4).alias("kept_information")).select(F.lit(name).alias("filter"), "kept", "kept_information")
        out = k if out is None else out.unionAll(k)
    return out


@query(f"""WITH {SCORED}, t AS (SELECT prompt_id, pos, {RANK.format(order='score DESC, pos')} <= ceil(0.5 * {SIZE}) AS tk FROM cs),
  g AS (SELECT *, coalesce(sum((s_stat >= 8.0)::INT) OVER (PARTITION BY prompt_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS phrase FROM cs), {PHRASES}
SELECT prompt_id, count(*) FILTER (WHERE tk) AS kept_by_token, count(*) FILTER (WHERE kept) AS kept_by_phrase, count(*) FILTER (WHERE tk AND kept) AS kept_by_both FROM k JOIN t USING (prompt_id, pos) GROUP BY prompt_id""")
def compare_granularity(spark, sf):
    """Single tokens against phrases at one budget."""
    s = scored(spark, sf)
    a = prune.prune_tokens(s, Budget.ratio(0.5)).select("prompt_id", "pos", F.col("kept").alias("tk"))
    b = prune.prune_phrases(prune.group_by_attachment(s), Budget.ratio(0.5)).select("prompt_id", "pos", "kept")
    return a.join(b, ["prompt_id", "pos"]).groupBy("prompt_id").agg(F.count_if("tk").alias("kept_by_token"), F.count_if("kept").alias("kept_by_phrase"), F.count_if(F.col("tk") & F.col("kept")).alias("kept_by_both"))


@query(f"""WITH {SCORED}, r AS (SELECT *, row_number() OVER (PARTITION BY prompt_id ORDER BY score DESC, pos) AS r FROM cs)
SELECT prompt_id, pos::INTEGER AS pos, tok, row_number() OVER (PARTITION BY prompt_id ORDER BY (CASE WHEN r % 2 = 1 THEN r ELSE -r END) < 0, CASE WHEN r % 2 = 1 THEN r ELSE -r END)::INTEGER AS place FROM r""")
def order_for_edges(spark, sf):
    t = scored(spark, sf).select("prompt_id", F.col("pos").alias("part"), "tok", "score")
    return prune.order_for_edges(t).select("prompt_id", F.col("part").alias("pos"), "tok", "place")


@query(f"SELECT doc_id, len(regexp_extract_all(text, '{W}'))::BIGINT AS tokens, len(regexp_extract_all(text, '{W}')) > 3000 AS is_long FROM documents")
def long_prompts(spark, sf):
    return prune.flag_long_prompts(load(spark, sf, "documents", "doc_id", "text"), 3000).drop("text")


@query(f"""WITH {PROMPTS} SELECT count(*) AS tokens_scored, ceil(count(*) / 256.0)::BIGINT AS batches FROM pt""")
def scorer_cost(spark, sf):
    """Tokens that an outside scorer would be asked for, and the batches they make."""
    return selfinfo.prompt_tokens(prompts(spark, sf), whole=False).agg(F.count("*").alias("tokens_scored"), F.ceil(F.count("*") / F.lit(256.0)).alias("batches"))
