"""SQL for queries whose own modules have none: the codec, pruning by four scorers, and similarity, built from shared pieces."""

from __future__ import annotations

from ctxpress.catalog import ORACLE
from ctxpress.catalog.abbreviation import CATALOGUE, codec_sql, dictionary_sql
from ctxpress.catalog.experiments import RATINGS, SCORED
from ctxpress.catalog.information import P1, PROMPTS, W
from ctxpress.catalog.methods import EVERY_SCORER, QUESTIONS, SCORERS, _settings_sql, abbreviated_sql, kept_sql
from ctxpress.catalog.numbers import RANGES, code_sql, hat_sql
from ctxpress.plans import workloads


def n_words(c: str) -> str:
    return f"len(regexp_extract_all({c}, '{W}'))"


def encode_sql(source: str, n: int = 2) -> str:
    """Select (all of ``source``, short): texts of ``source`` (text, grams, names) with every n-gram of grams replaced by its name."""
    done, waiting = "split_part(a, chr(1), 1)", "split_part(a, chr(1), 2)"
    now = f"(CASE WHEN {waiting} = '' THEN x ELSE {waiting} || ' ' || x END)"
    step = f"""CASE WHEN len(string_split({now}, ' ')) < {n} THEN {done} || chr(1) || {now} WHEN list_contains(grams, {now}) THEN {done} || ' ' || names[list_position(grams, {now})] || chr(1)
      ELSE {done} || ' ' || split_part({now}, ' ', 1) || chr(1) || substr({now}, length(split_part({now}, ' ', 1)) + 2) END"""
    run = f"trim(replace(list_reduce(list_concat([chr(1)], string_split(p, ' ')), lambda a, x: {step}), chr(1), ' '))"
    pieces = f"regexp_extract_all(text, '{W}(?: {W})*|[^\\p{{L}}\\p{{M}}\\p{{N}}_]+')"
    return f"SELECT * EXCLUDE (grams, names), array_to_string(list_transform({pieces}, lambda p: CASE WHEN regexp_matches(p, '^{W}') THEN {run} ELSE p END), '') AS short FROM {source}"


def coded(k: int, table: str = "documents", text: str = "text", n: int = 2) -> str:
    """Select of a table with short, by the corpus dictionary of the ``k`` most frequent n-grams."""
    names = f"(SELECT list(gram ORDER BY rank) AS grams, list(placeholder ORDER BY rank) AS names FROM ({dictionary_sql(n, k)}))"
    return encode_sql(f"(SELECT * FROM (SELECT *{'' if text == 'text' else f', {text} AS text'} FROM {table}), {names})", n)


def cosines_sql(pairs: str, keys: str) -> str:
    """Select (keys, cosine) of rows (keys, a, b) of word lists; null where one has no word."""
    return f"""SELECT {keys}, sum(x * y) / (sqrt(sum(x * x)) * sqrt(sum(y * y))) AS cosine FROM (
      SELECT {keys}, w, count(*) FILTER (WHERE side = 1) AS x, count(*) FILTER (WHERE side = 2) AS y FROM (SELECT {keys}, 1 AS side, unnest(a) AS w FROM {pairs} UNION ALL SELECT {keys}, 2, unnest(b) FROM {pairs}) GROUP BY ALL) GROUP BY ALL HAVING sum(x) > 0 AND sum(y) > 0"""


def low(c: str) -> str:
    return f"regexp_extract_all(lower({c}), '{W}')"


FIDELITY = "count(cosine) AS pairs, round(avg(cosine), 6) AS mean_cosine, round(quantile_cont(cosine, 0.05), 6) AS p5_cosine"
RATIO = "count(*) AS texts, sum(t0)::BIGINT AS tokens_before, sum(t1)::BIGINT AS tokens_after, round(sum(t0) / nullif(sum(t1), 0)::DOUBLE, 6) AS ratio"

ORACLE["abbreviate_corpus"] = f"WITH e AS ({coded(150)}) SELECT doc_id, length(text) AS chars_before, length(short) AS chars_after, {n_words('text')} AS words_before, {n_words('short')} AS words_after, md5(short) AS short_md5 FROM e"
ORACLE["abbreviation_fidelity"] = f"""WITH e AS ({coded(3)}), p AS (SELECT doc_id, source, {low('text')} AS a, {low('short')} AS b FROM e), c AS ({cosines_sql('p', 'doc_id, source')})
SELECT source, {FIDELITY}, count(*) FILTER (WHERE cosine >= 0.92) AS safe, round(count(*) FILTER (WHERE cosine >= 0.92) / count(cosine)::DOUBLE, 6) AS safe_share FROM c GROUP BY source"""
ORACLE["compression_report_cube"] = f"""WITH e AS ({coded(150)}), t AS (SELECT source, lang, {n_words('text')} AS t0, {n_words('short')} AS t1 FROM e)
SELECT source, lang, {RATIO}, round(1 - sum(t1) / nullif(sum(t0), 0)::DOUBLE, 6) AS reduction, round(avg(t0 / nullif(t1, 0)::DOUBLE), 6) AS mean_ratio FROM t GROUP BY CUBE (source, lang)"""
ORACLE["net_ratio"] = " UNION ALL ".join(
    f"SELECT {k}::INTEGER AS entries, tokens_before, tokens_after, ratio, {3 * k}::BIGINT AS header_tokens, round(tokens_before / (tokens_after + {3 * k})::DOUBLE, 6) AS net_ratio FROM (SELECT {RATIO} FROM (SELECT {n_words('text')} AS t0, {n_words('short')} AS t1 FROM ({coded(k)})))"
    for k in (3, 20, 150)
)
NAMES150 = f"(SELECT list(placeholder) AS all_names FROM ({dictionary_sql(2, 150)}))"
ORACLE["placeholder_density"] = f"""WITH e AS ({coded(150)}), c AS (SELECT doc_id, regexp_extract_all(short, '{W}') AS s, all_names FROM e, {NAMES150}),
  n AS (SELECT doc_id, len(list_filter(s, lambda x: list_contains(all_names, x))) AS placeholders, len(s) AS t FROM c)
SELECT doc_id, placeholders, round(coalesce(100 * placeholders / nullif(t, 0)::DOUBLE, 0.0), 4) AS density FROM n"""
ORACLE["overlap_report"] = f"""WITH e AS ({coded(150)}), d AS (SELECT gram, placeholder FROM ({dictionary_sql(2, 150)})),
  w AS (SELECT regexp_extract_all(text, '{W}') AS w FROM e), g AS (SELECT unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS gram FROM w),
  s AS (SELECT unnest(regexp_extract_all(short, '{W}')) AS placeholder FROM e), p AS (SELECT count(*) AS places FROM g SEMI JOIN d USING (gram)), r AS (SELECT count(*) AS replaced FROM s SEMI JOIN d USING (placeholder))
SELECT places, replaced, places - replaced AS suppressed FROM p, r"""
ORACLE["abbreviate_per_document"] = f"""WITH o AS (SELECT doc_id, list(gram) AS dic FROM (SELECT doc_id, gram, row_number() OVER (PARTITION BY doc_id ORDER BY freq DESC, gram) AS k FROM {codec_sql(2, 'doc_id')} WHERE freq > 1 QUALIFY k <= 3) GROUP BY doc_id),
  s AS (SELECT doc_id, dic, text FROM documents JOIN o USING (doc_id)), {abbreviated_sql('x', 's', 2)}, l AS (SELECT doc_id, sum(len(words))::BIGINT AS n FROM x GROUP BY doc_id)
SELECT doc_id, coalesce(len(dic), 0)::INTEGER AS entries, {n_words('text')} AS words_before, coalesce(n, {n_words('text')}) AS words_after FROM documents LEFT JOIN o USING (doc_id) LEFT JOIN l USING (doc_id)"""
COST = "(coalesce(list_sum(list_transform(regexp_extract_all(gram, '[\\p{L}\\p{M}]+'), lambda r: ceil(len(r) / 4.0))), 0) + coalesce(list_sum(list_transform(regexp_extract_all(gram, '\\p{N}+'), lambda r: ceil(len(r) / 3.0))), 0) + len(regexp_extract_all(gram, '[^\\s\\p{L}\\p{M}\\p{N}]')))::BIGINT"
ORACLE["abbreviation_net_saving"] = f"SELECT gram, freq, (freq * (c - 2) - (c + 2))::BIGINT AS saved_tokens FROM (SELECT gram, freq, {COST} AS c FROM {codec_sql(3)}) WHERE freq * (c - 2) - (c + 2) > 0 ORDER BY saved_tokens DESC, gram LIMIT 150"
_part = codec_sql(2).replace("FROM documents", f"FROM {CATALOGUE}")
ORACLE["catalogue_ratio"] = " UNION ALL ".join(
    f"""SELECT {k}::INTEGER AS entries, b::BIGINT AS tokens_before, n::BIGINT AS tokens_after, round(b / n::DOUBLE, 6) AS ratio FROM (SELECT sum({n_words('text')}) AS b FROM {CATALOGUE}),
  (WITH s AS (SELECT text, dic FROM {CATALOGUE}, (SELECT list(gram) AS dic FROM (SELECT gram FROM {_part} ORDER BY freq DESC, gram LIMIT {k}))), {abbreviated_sql('x', 's', 2)} SELECT sum(len(words)) AS n FROM x)"""
    for k in (3, 5, 100)
)

# The pipeline and its stages.
DECIDED = ORACLE["pipeline_decisions"]
DOCS3 = f"(SELECT {n_words('text')} AS t0, {n_words('short')} AS t1 FROM ({coded(3)}))"
PROMPT_PART = f"(SELECT coalesce(t0, 0) AS t0, coalesce(t1, 0) AS t1 FROM (SELECT conv_id * 1000 + turn AS prompt_id, {n_words('text')} AS t0 FROM conversations) LEFT JOIN (SELECT prompt_id, count(*) FILTER (WHERE kept) AS t1 FROM ({DECIDED}) GROUP BY prompt_id) USING (prompt_id))"
_cols = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
TABLE_PART = "(SELECT " + " + ".join(f"len(printf('%.2f', {c}))" for c in _cols) + " AS t0, " + " + ".join(f"len(({code_sql(c, 8)})::VARCHAR)" for c in _cols) + f" AS t1 FROM lineitem, (WITH {RANGES} SELECT * FROM mm))"
REDUCED = f"{RATIO}, round(1 - sum(t1) / nullif(sum(t0), 0)::DOUBLE, 6) AS reduction"
ORACLE["pipeline_run"] = f"SELECT 'prompts' AS part, {REDUCED} FROM {PROMPT_PART} UNION ALL SELECT 'documents', {REDUCED} FROM {DOCS3} UNION ALL SELECT 'table', {REDUCED} FROM {TABLE_PART}"
ORACLE["stage_ablation"] = f"""WITH p AS (SELECT sum(t0)::BIGINT AS p0, sum(t1)::BIGINT AS p1 FROM {PROMPT_PART}), d AS (SELECT sum(t0)::BIGINT AS d0, sum(t1)::BIGINT AS d1 FROM {DOCS3}), q AS (SELECT sum(t0)::BIGINT AS q0, sum(t1)::BIGINT AS q1 FROM {TABLE_PART})
SELECT unnest(['prune', 'abbreviate', 'quantize', 'all']) AS stages, unnest([p0 + d0, p0 + d0, p0 + d0 + q0, p0 + d0 + q0]) AS tokens_before, unnest([p1 + d0, p0 + d1, p0 + d0 + q1, p1 + d1 + q1]) AS tokens_after FROM p, d, q"""
ORACLE["pipeline_similarity"] = f"""WITH k AS ({DECIDED}), x AS (SELECT prompt_id, list(tok) AS a, list(tok) FILTER (WHERE kept) AS b FROM k GROUP BY prompt_id), c AS ({cosines_sql('x', 'prompt_id')})
SELECT {FIDELITY}, count(*) FILTER (WHERE cosine >= 0.92) AS safe, round(count(*) FILTER (WHERE cosine >= 0.92) / count(cosine)::DOUBLE, 6) AS safe_share FROM c"""

ORACLE["assemble_methods_a_to_f"] = f"""WITH dec AS (SELECT prompt_id, count(*) FILTER (WHERE kept) AS c FROM ({DECIDED}) GROUP BY prompt_id), ed AS ({coded(3)}),
  d AS (SELECT doc_id, {n_words('text')} AS t0, {n_words('short')} AS t1 FROM ed),
  l AS (SELECT l_orderkey, sum(len(regexp_extract_all(l_quantity::VARCHAR || ',' || l_extendedprice::VARCHAR || ',' || l_discount::VARCHAR, '{W}')))::BIGINT AS r0, 3 * count(*) AS r1 FROM lineitem GROUP BY l_orderkey),
  p AS (SELECT conv_id * 1000 + turn AS prompt_id, conv_id % (SELECT count(*) FROM documents) AS doc_id, conv_id % (SELECT count(*) FROM orders) + 1 AS l_orderkey, {n_words('text')} AS a FROM conversations),
  x AS (SELECT a, coalesce(c, 0) AS c, coalesce(t0, 0) + coalesce(r0, 0) AS d0, coalesce(t1, 0) + coalesce(r1, 0) AS d1 FROM p LEFT JOIN dec USING (prompt_id) LEFT JOIN d USING (doc_id) LEFT JOIN l USING (l_orderkey)),
  h AS (SELECT 9 + sum({n_words('number::VARCHAR')}) AS h FROM (SELECT unnest([min(l_quantity), max(l_quantity), min(l_extendedprice), max(l_extendedprice), min(l_discount), max(l_discount)]) AS number FROM lineitem)),
  m AS (SELECT unnest(['A', 'B', 'B', 'C', 'D', 'D', 'E', 'E', 'F', 'F']) AS method, unnest(['none', 'random', 'representative', 'none', 'random', 'representative', 'random', 'representative', 'random', 'representative']) AS exemplar_kind)
SELECT method, exemplar_kind, count(*) AS prompts,
  sum(CASE WHEN method IN ('A', 'B') THEN a ELSE c END + CASE WHEN method IN ('E', 'F') THEN d1 ELSE d0 END + CASE WHEN exemplar_kind = 'none' THEN 0 ELSE 12 END + CASE WHEN method = 'F' THEN h + 6 ELSE 0 END)::BIGINT AS tokens_word,
  max(CASE WHEN method = 'F' THEN h + 6 ELSE 0 END)::BIGINT AS header_tokens FROM x, h, m GROUP BY ALL"""

# Pruned prompts: by the default scorer, and by all four.
ORACLE["fidelity_report"] = f"""WITH {SCORED}, k AS (SELECT *, row_number() OVER (PARTITION BY prompt_id ORDER BY score DESC, pos) <= ceil(0.7 * count(*) OVER (PARTITION BY prompt_id)) AS kept FROM cs),
  x AS (SELECT role, prompt_id, list(tok) AS a, list(tok) FILTER (WHERE kept) AS b FROM k JOIN (SELECT conv_id * 1000 + turn AS prompt_id, role FROM conversations) USING (prompt_id) GROUP BY ALL), c AS ({cosines_sql('x', 'role, prompt_id')})
SELECT role, {FIDELITY} FROM c GROUP BY role"""
ON_PROMPTS = EVERY_SCORER.replace(QUESTIONS, PROMPTS)
assert P1 in ON_PROMPTS
ORACLE["scorer_agreement"] = f"WITH {ON_PROMPTS} SELECT scorer, count(*) AS tokens, round(corr(s, y), 4) AS correlation FROM sd GROUP BY scorer"
ORACLE["scorer_sensitivity"] = f"""WITH {ON_PROMPTS}, k AS ({kept_sql('0.7')}), x AS (SELECT scorer, prompt_id, list(tok) AS a, list(tok) FILTER (WHERE kept) AS b FROM k GROUP BY ALL), c AS ({cosines_sql('x', 'scorer, prompt_id')}),
  f AS (SELECT scorer, round(avg(cosine), 6) AS mean_cosine, round(quantile_cont(cosine, 0.05), 6) AS p5_cosine FROM c GROUP BY scorer),
  b AS (SELECT scorer, count(*) AS tokens, round(avg((s <> 0 AND abs(y - s) / s <= 0.1)::INT), 4) AS band_share FROM sd GROUP BY scorer), m AS (SELECT scorer, round(avg(score), 4) AS mean_score FROM scored GROUP BY scorer)
SELECT scorer, tokens, mean_score, band_share, mean_cosine, p5_cosine FROM b JOIN m USING (scorer) JOIN f USING (scorer)"""
assert len(SCORERS) == 4

# Ratings, numeric questions, passages, examples.
ORACLE["rating_report"] = f"""WITH {RATINGS}, x AS (SELECT pair_id, list_transform(w, lambda v: lower(v)) AS a, list_transform(w[1:ceil(len(w) * 0.5)::INT], lambda v: lower(v)) AS b FROM d), c AS ({cosines_sql('x', 'pair_id')}),
  j AS (SELECT pair_id, cosine, avg(score) AS rating FROM d LEFT JOIN c USING (pair_id) JOIN ra USING (pair_id) GROUP BY ALL),
  r AS (SELECT *, rank() OVER (ORDER BY cosine NULLS FIRST) + (count(*) OVER (PARTITION BY cosine) - 1) / 2.0 AS rc, rank() OVER (ORDER BY rating) + (count(*) OVER (PARTITION BY rating) - 1) / 2.0 AS rr FROM j)
SELECT count(*) AS pairs, round(avg(rating), 4) AS mean_rating, round(corr(cosine, rating), 4) AS pearson, round(corr(rc, rr), 4) AS spearman, round(count(*) FILTER (WHERE cosine >= 0.92 AND rating < 3.0) / count(*)::DOUBLE, 4) AS high_cosine_low_rating FROM r"""


def _correct(bits: int) -> str:
    f = {"sum": "sum({})", "avg": "avg({})", "spread": "max({0}) - min({0})"}
    out = []
    for _, by, how, col in workloads.QUESTIONS:
        e, d = f[how].format(col), f[how].format(hat_sql(col, bits))
        out.append(f"SELECT 'b{bits:02d}' AS method, coalesce(abs(({d} - ({e})) / nullif({e}, 0)), 0.0) <= 0.001 AS correct FROM lineitem, mm GROUP BY {by or '1 = 1'}")
    return " UNION ALL ".join(out)


ORACLE["numeric_accuracy_by_bits"] = f"""WITH {RANGES}, r AS ({' UNION ALL '.join(_correct(b) for b in (2, 4, 8, 12))}), a AS (SELECT method, count(*) AS questions, round(100 * avg(correct::INT), 4) AS accuracy FROM r GROUP BY method)
SELECT method, 'none' AS arm, questions, accuracy, round(accuracy - 100, 4) AS delta FROM a UNION ALL SELECT 'A', 'none', questions, 100.0, 0.0 FROM a WHERE method = 'b02'"""
_idf = f"n AS (SELECT count(*) AS d FROM documents), dt AS (SELECT doc_id, unnest(list_distinct({low('text')})) AS tok FROM documents), idf AS (SELECT tok, round(ln((d + 1) / (count(*) + 1)::DOUBLE), 6) AS idf FROM dt, n GROUP BY tok, d)"
ORACLE["passage_finding_abbreviated"] = f"""WITH {_idf}, ed AS ({coded(3)}), ei AS ({coded(3, 'benchmark')}),
  dw AS (SELECT 'A' AS method, doc_id, tok FROM dt UNION ALL SELECT 'C', doc_id, unnest(list_distinct({low('short')})) FROM ed),
  iw AS (SELECT 'A' AS method, item_id, unnest(list_distinct({low('text')})) AS tok FROM benchmark UNION ALL SELECT 'C', item_id, unnest(list_distinct({low('short')})) FROM ei),
  s AS (SELECT method, item_id, doc_id, round(sum(idf), 4) AS score FROM iw JOIN idf USING (tok) JOIN dw USING (method, tok) GROUP BY ALL),
  f AS (SELECT method, item_id, arg_min(doc_id, (-score, doc_id)) AS found FROM s GROUP BY ALL), g AS (SELECT item_id, list(doc_id) AS gold FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY item_id),
  r AS (SELECT m.method, count(*) AS questions, round(100 * avg(coalesce(list_contains(gold, found), false)::INT), 4) AS accuracy FROM g CROSS JOIN (SELECT unnest(['A', 'C']) AS method) m LEFT JOIN f ON f.item_id = g.item_id AND f.method = m.method GROUP BY m.method)
SELECT method, 'none' AS arm, questions, accuracy, round(accuracy - (SELECT accuracy FROM r WHERE method = 'A'), 4) AS delta FROM r"""
_dist = "list_sum(list_transform(range(1, len(x.v) + 1), lambda i: ({0}.v[i] - x.v[i]) * ({0}.v[i] - x.v[i])))"
ORACLE["farthest_first_shots"] = f"""WITH x AS (SELECT vec_id AS id, list_transform(embedding, lambda z: z::DOUBLE) AS v FROM embeddings), a AS (SELECT * FROM x ORDER BY id LIMIT 1),
  d1 AS (SELECT x.id, x.v, {_dist.format('a')} AS d FROM x, a), b AS (SELECT id, v FROM d1 ORDER BY d DESC, id LIMIT 1), d2 AS (SELECT x.id, least(x.d, {_dist.format('b')}) AS d FROM d1 x, b), c AS (SELECT id FROM d2 ORDER BY d DESC, id LIMIT 1)
SELECT unnest([0, 1, 2])::INTEGER AS place, unnest([a.id, b.id, c.id]) AS vec_id FROM a, b, c"""
ORACLE["pareto_settings"] = f"""WITH dw AS (SELECT doc_id, unnest({low('text')}) AS tok FROM documents), {_settings_sql()}, total AS (SELECT count(*) AS n FROM dw),
  ratio AS (SELECT scope, g, t, round(any_value(n) / sum(len(words))::DOUBLE, 6) AS ratio FROM eff, total GROUP BY scope, g, t),
  x AS (SELECT doc_id, scope, g, t, {low('text')} AS a, list_transform(words, lambda v: lower(v)) AS b FROM eff JOIN documents USING (doc_id)),
  c AS ({cosines_sql('x', 'doc_id, scope, g, t')}), st AS (SELECT scope || ' G' || g || 'T' || t AS setting, ratio, cosine FROM ratio JOIN (SELECT scope, g, t, round(avg(cosine), 6) AS cosine FROM c GROUP BY scope, g, t) USING (scope, g, t))
SELECT setting, ratio, cosine, NOT EXISTS (SELECT 1 FROM st b WHERE b.ratio >= st.ratio AND b.cosine >= st.cosine AND (b.ratio > st.ratio OR b.cosine > st.cosine)) AS efficient FROM st"""
