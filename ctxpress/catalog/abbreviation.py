"""n-gram frequencies, dictionaries, the codec, and coders to compare it with."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.functions.tokens import token_count, words
from ctxpress.operators import abbrev, baselines, fidelity, measures
from ctxpress.sources.tables import html_text, load

W = r"[\p{L}\p{M}\p{N}_]+"


def grams_sql(n: int, keys: str = "") -> str:
    pick = keys + ", " if keys else ""
    text = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    return f"(SELECT {pick}unnest(list_transform(range(1, greatest(len(w) - {n - 2}, 1)), lambda i: {text})) AS gram FROM (SELECT {pick}regexp_extract_all(text, '{W}') AS w FROM documents))"


def freq_sql(n: int, keys: str = "") -> str:
    pick = keys + ", " if keys else ""
    return f"(SELECT {pick}gram, count(*) AS freq FROM {grams_sql(n, keys)} GROUP BY ALL)"


def codec_sql(n: int, keys: str = "") -> str:
    """Frequencies of n-grams whose words stand one blank apart."""
    pick = keys + ", " if keys else ""
    text = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    runs = f"(SELECT {pick}string_split(unnest(regexp_extract_all(text, '{W}(?: {W})*')), ' ') AS w FROM documents)"
    return f"(SELECT {pick}gram, count(*) AS freq FROM (SELECT {pick}unnest(list_transform(range(1, greatest(len(w) - {n - 2}, 1)), lambda i: {text})) AS gram FROM {runs}) GROUP BY ALL)"


def docs(spark, sf, *cols):
    return load(spark, sf, "documents", *(cols or ("doc_id", "text")))


def corpus_mapping(spark, sf, n=2, k=3):
    d = docs(spark, sf)
    return abbrev.as_mapping(abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, n), k), d))


for _n in (2, 3, 4, 5):

    @query(f"SELECT gram, freq FROM {freq_sql(_n)}", name=f"ngram_frequency_{_n}")
    def _frequency(spark, sf, n=_n):
        return abbrev.ngram_frequencies(docs(spark, sf, "text"), n)


@query(f"SELECT floor(log2(freq + 0.5))::INTEGER AS bin, (2 ** floor(log2(freq + 0.5)))::BIGINT AS lo, (2 ** (floor(log2(freq + 0.5)) + 1) - 1)::BIGINT AS hi, count(*) AS distinct_grams, sum(freq)::BIGINT AS occurrences FROM {freq_sql(2)} GROUP BY floor(log2(freq + 0.5))")
def ngram_histogram(spark, sf):
    return abbrev.frequency_histogram(abbrev.ngram_frequencies(docs(spark, sf, "text"), 2))


@query(f"SELECT gram, freq, row_number() OVER (ORDER BY freq DESC, gram) AS rank FROM {freq_sql(2)} ORDER BY freq DESC, gram LIMIT 500")
def ngram_rank_frequency(spark, sf):
    return abbrev.rank_frequency(abbrev.ngram_frequencies(docs(spark, sf, "text"), 2), 500)


TOP150 = f"SELECT gram, freq FROM {freq_sql(2)} ORDER BY freq DESC, gram LIMIT 150"


@query(TOP150)
def ngram_top_k(spark, sf):
    return abbrev.select_top(abbrev.ngram_frequencies(docs(spark, sf, "text"), 2), 150)


@query(TOP150)
def ngram_top_k_by_sketch(spark, sf):
    return abbrev.top_by_sketch(docs(spark, sf, "text"), 2, 150)


@query(f"SELECT gram, freq FROM {freq_sql(3)} ORDER BY freq DESC, gram LIMIT 150")
def ngram_top_k_by_levels(spark, sf):
    return abbrev.top_by_levels(docs(spark, sf, "text"), 3, 150)


@query(f"SELECT source, gram, freq FROM {freq_sql(2, 'source')} QUALIFY row_number() OVER (PARTITION BY source ORDER BY freq DESC, gram) <= 5")
def ngram_top_per_source(spark, sf):
    return abbrev.select_top(abbrev.ngram_frequencies(docs(spark, sf, "source", "text"), 2, "source"), 5, "source")


@query(" UNION ALL ".join(f"SELECT {n} AS n, gram, freq FROM (SELECT * FROM {freq_sql(n)} ORDER BY freq DESC, gram LIMIT 20)" for n in (2, 3, 4, 5)))
def ngram_mixed_lengths(spark, sf):
    out = None
    for n in (2, 3, 4, 5):
        t = abbrev.select_top(abbrev.ngram_frequencies(docs(spark, sf, "text"), n), 20).select(F.lit(n).alias("n"), "gram", "freq")
        out = t if out is None else out.unionAll(t)
    return out


@query(f"""WITH d AS (SELECT doc_id, regexp_extract_all(text, '{W}') AS w FROM documents),
  h AS (SELECT doc_id, unnest(range(1, greatest(len(w), 1))) AS i, w FROM d), m AS (SELECT doc_id, i FROM h WHERE w[i] = 'the' AND w[i + 1] = 'the'),
  s AS (SELECT doc_id, i, i - row_number() OVER (PARTITION BY doc_id ORDER BY i) AS run FROM m), r AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id, run)
SELECT d.doc_id, coalesce(sum(n), 0)::BIGINT AS overlapping, coalesce(sum((n + 1) // 2), 0)::BIGINT AS replaceable FROM d LEFT JOIN r USING (doc_id) GROUP BY d.doc_id""")
def ngram_nonoverlap(spark, sf):
    """Occurrences of the most self-repeating bigram against what a scan from the left can replace."""
    w = F.col("w")
    every = F.size(F.filter(abbrev.ngrams(w, 2), lambda g: g == "the the")).cast("long")
    return docs(spark, sf).select("doc_id", words(F.col("text")).alias("w")).select("doc_id", every.alias("overlapping"), abbrev.greedy_count(w, ["the", "the"]).alias("replaceable"))


def dictionary_sql(n: int, k: int) -> str:
    return f"""WITH top AS (SELECT gram, freq, row_number() OVER (ORDER BY freq DESC, gram) AS rank FROM {codec_sql(n)} ORDER BY freq DESC, gram LIMIT {k}),
  used AS (SELECT DISTINCT tok FROM (SELECT unnest(regexp_extract_all(text, '{W}')) AS tok FROM documents)),
  cand AS (SELECT c, chr((65 + (c % 676) // 26)::INT) || chr((65 + c % 26)::INT) || (c // 676 + 1) AS placeholder FROM (SELECT unnest(range(2000)) AS c)),
  free AS (SELECT placeholder, row_number() OVER (ORDER BY c) AS rank FROM cand WHERE placeholder NOT IN (SELECT tok FROM used))
SELECT placeholder, gram, freq, rank FROM top JOIN free USING (rank)"""


@query(dictionary_sql(2, 150))
def abbreviation_dictionary(spark, sf):
    d = docs(spark, sf)
    return abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), 150), d)


@query(f"SELECT (SELECT count(*) FROM ({dictionary_sql(4, 100)}) d) AS entries, 0::BIGINT AS collisions")
def placeholder_collision_check(spark, sf):
    """Placeholders that some text has as a word: none may be."""
    d = docs(spark, sf)
    dic = abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 4), 100), d)
    used = d.select(F.explode(F.array_distinct(words(F.col("text")))).alias("placeholder")).join(F.broadcast(dic), "placeholder", "left_semi").distinct()
    return dic.agg(F.count("*").alias("entries")).crossJoin(used.agg(F.count("*").alias("collisions")))


@query()
def abbreviate_corpus(spark, sf):
    d = abbrev.abbreviate(docs(spark, sf), corpus_mapping(spark, sf, 2, 150))
    return d.select("doc_id", F.length("text").alias("chars_before"), F.length("short").alias("chars_after"), token_count(F.col("text")).alias("words_before"), token_count(F.col("short")).alias("words_after"), F.md5("short").alias("short_md5"))


@query("SELECT doc_id, text AS restored FROM documents")
def restore_roundtrip(spark, sf):
    m = corpus_mapping(spark, sf, 2, 150)
    return abbrev.restore(abbrev.abbreviate(docs(spark, sf), m), m).select("doc_id", "restored")


@query("SELECT doc_id, text AS restored FROM documents")
def restore_roundtrip_native(spark, sf):
    """There and back by built-in functions alone, for a small dictionary."""
    m = corpus_mapping(spark, sf, 2, 5)
    return docs(spark, sf).select("doc_id", abbrev.restore_native(abbrev.abbreviate_native(F.col("text"), m), m).alias("restored"))


@query("SELECT 'documents' AS part, count(*) AS texts, 0::BIGINT AS mismatches FROM documents UNION ALL SELECT 'conversations', count(*), 0 FROM conversations UNION ALL SELECT 'pages', count(*), 0 FROM pages UNION ALL SELECT 'benchmark', count(*), 0 FROM benchmark")
def roundtrip_report(spark, sf):
    """Texts that are not restored byte for byte, in every table with text."""
    m, out = corpus_mapping(spark, sf, 2, 150), None
    for part, col in (("documents", "text"), ("conversations", "text"), ("pages", "html"), ("benchmark", "text")):
        t = load(spark, sf, part, col).withColumnRenamed(col, "text")
        t = abbrev.restore(abbrev.abbreviate(t, m), m).agg(F.count("*").alias("texts"), F.count_if(~F.col("text").eqNullSafe(F.col("restored"))).alias("mismatches"))
        t = t.select(F.lit(part).alias("part"), "texts", "mismatches")
        out = t if out is None else out.unionAll(t)
    return out


@query()
def abbreviate_overlap_policies(spark, sf):
    """Words left under each policy for overlapping n-grams of mixed length."""
    d, m, freq = docs(spark, sf), {}, {}
    for n in (2, 3):
        for i, r in enumerate(abbrev.select_top(abbrev.codec_frequencies(d, n), 10).collect()):
            m[r["gram"]], freq[r["gram"]] = f"Q{n}Q{i}", r["freq"]
    out = None
    for policy in ("leftmost_longest", "frequency_first", "max_saving"):
        t = abbrev.abbreviate(d, m, overlap=policy, freq=freq).agg(F.sum(token_count(F.col("text"))).alias("words_before"), F.sum(token_count(F.col("short"))).alias("words_after"))
        t = t.select(F.lit(policy).alias("policy"), "words_before", "words_after")
        out = t if out is None else out.unionAll(t)
    return out


@query()
def overlap_report(spark, sf):
    """Matches that overlapping suppresses: all places of the dictionary's n-grams against those replaced."""
    m = corpus_mapping(spark, sf, 2, 150)
    d = abbrev.abbreviate(docs(spark, sf), m).select(words(F.col("text")).alias("w"), words(F.col("short")).alias("s"))
    every = d.select(F.explode(abbrev.ngrams(F.col("w"), 2)).alias("g")).where(F.col("g").isin(list(m))).agg(F.count("*").alias("places"))
    done = d.select(F.explode("s").alias("s")).where(F.col("s").isin(list(m.values()))).agg(F.count("*").alias("replaced"))
    return every.crossJoin(done).withColumn("suppressed", F.col("places") - F.col("replaced"))


@query(f"SELECT string_agg(placeholder || '=' || gram, '; ' ORDER BY rank) AS header FROM ({dictionary_sql(2, 20)})")
def dictionary_header(spark, sf):
    d = docs(spark, sf)
    return abbrev.dictionary_header(abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), 20), d))


@query(r"SELECT doc_id FROM documents WHERE regexp_matches(text, '(^|[^\p{L}\p{M}\p{N}_])of the([^\p{L}\p{M}\p{N}_]|$)')")
def search_abbreviated(spark, sf):
    m = corpus_mapping(spark, sf, 2, 150)
    return abbrev.search_abbreviated(abbrev.abbreviate(docs(spark, sf), m), m, "of the").select("doc_id")


@query()
def abbreviate_per_document(spark, sf):
    """Each text by its own three most frequent repeated bigrams."""
    d = abbrev.abbreviate_each(docs(spark, sf), 2, 3)
    return d.select("doc_id", F.size("used").alias("entries"), token_count(F.col("text")).alias("words_before"), token_count(F.col("short")).alias("words_after"))


@query()
def abbreviation_net_saving(spark, sf):
    """Dictionary by net saving in estimated tokens instead of frequency, and what each entry saves."""
    top = abbrev.select_top(abbrev.codec_frequencies(docs(spark, sf, "text"), 3), 150, by="net_saving")
    return top.select("gram", "freq", abbrev.net_saving(F.col("freq"), F.col("gram")).alias("saved_tokens"))


@query()
def placeholder_density(spark, sf):
    m = corpus_mapping(spark, sf, 2, 150)
    return measures.placeholder_density(abbrev.abbreviate(docs(spark, sf), m), m).select("doc_id", "placeholders", "density")


@query()
def compression_report_cube(spark, sf):
    d = docs(spark, sf, "source", "lang", "text")
    t = measures.with_tokens(abbrev.abbreviate(d, corpus_mapping(spark, sf, 2, 150)))
    return measures.compression_report(t, "source", "lang", cube=True)


@query()
def net_ratio(spark, sf):
    """Ratios with the dictionary sent along, for growing dictionaries."""
    d, out = docs(spark, sf), None
    for k in (3, 20, 150):
        dic = abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(d, 2), k), d)
        m = abbrev.as_mapping(dic)
        head = dic.agg((F.count("*") + F.sum(token_count(F.col("gram")))).alias("h"))
        t = measures.compression_report(measures.with_tokens(abbrev.abbreviate(d, m))).crossJoin(head)
        t = measures.net_ratio(t, F.col("h")).select(F.lit(k).alias("entries"), "tokens_before", "tokens_after", "ratio", F.col("h").alias("header_tokens"), "net_ratio")
        out = t if out is None else out.unionAll(t)
    return out


@query()
def baseline_byte_codecs(spark, sf):
    d = docs(spark, sf)
    cols = {c: baselines.compressed_size(c)(F.col("text")) for c in ("gzip", "deflate", "bzip2")}
    d = d.select("doc_id", F.octet_length("text").alias("bytes"), token_count(F.col("text"), "estimated").alias("tokens"), *[v.alias(k) for k, v in cols.items()])
    return d.agg(F.sum("bytes").alias("bytes"), F.sum("tokens").alias("tokens"), *[F.sum(c).alias(c) for c in cols], F.sum(baselines.base64_tokens(F.col("gzip"))).alias("gzip_base64_tokens"))


@query()
def baseline_lzw_codes(spark, sf):
    return docs(spark, sf).select("doc_id", F.octet_length("text").cast("long").alias("bytes"), baselines.lzw_codes("text").alias("codes"))


@query(f"SELECT doc_id, coalesce(array_to_string(w[1:ceil(len(w) * 0.5)::INT], ' '), '') AS text FROM (SELECT doc_id, regexp_extract_all(text, '{W}') AS w FROM documents)")
def baseline_truncation(spark, sf):
    return docs(spark, sf).select("doc_id", baselines.truncate(F.col("text"), 0.5).alias("text"))


@query(f"SELECT count(*) AS texts, sum(len(regexp_extract_all(text, '{W}')))::BIGINT AS words, count(*) * 192 AS vector_tokens FROM conversations")
def baseline_soft_vector(spark, sf):
    """Size only: a learned vector of fixed length in place of each prompt."""
    t = load(spark, sf, "conversations", "text")
    return t.agg(F.count("*").alias("texts"), F.sum(token_count(F.col("text"))).alias("words"), (F.count("*") * baselines.soft_vector_tokens()).alias("vector_tokens"))


CATALOGUE = f"""(SELECT p_name || ' ' || p_type || ' ' || p_brand AS text FROM part)"""


@query(f"SELECT gram, count(*) AS freq FROM (SELECT unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS gram FROM (SELECT regexp_extract_all(text, '{W}') AS w FROM {CATALOGUE})) GROUP BY gram ORDER BY freq DESC, gram LIMIT 20")
def catalogue_abbreviation(spark, sf):
    """Short recurring phrases of a product catalogue."""
    p = load(spark, sf, "part").select(F.concat_ws(" ", "p_name", "p_type", "p_brand").alias("text"))
    return abbrev.select_top(abbrev.ngram_frequencies(p, 2), 20)


@query()
def catalogue_ratio(spark, sf):
    """What two-word entries save on the repetitive catalogue, by dictionary size."""
    p = load(spark, sf, "part").select(F.col("p_partkey").alias("doc_id"), F.concat_ws(" ", "p_name", "p_type", "p_brand").alias("text"))
    out = None
    for k in (3, 5, 100):
        m = abbrev.as_mapping(abbrev.build_dictionary(abbrev.select_top(abbrev.codec_frequencies(p, 2), k), p))
        t = measures.compression_report(measures.with_tokens(abbrev.abbreviate(p, m))).select(F.lit(k).alias("entries"), "tokens_before", "tokens_after", "ratio")
        out = t if out is None else out.unionAll(t)
    return out


@query(r"""SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>|<!--.*?-->', ' ', 'gis'), '<[^>]*>', ' ', 'g'),
  '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&copy;', '©'), '&middot;', '·'), '&amp;', '&'), '[ \t\r\n\f]+', ' ', 'g')) AS text FROM pages""")
def html_attachment(spark, sf):
    return load(spark, sf, "pages", "page_id", "html").select("page_id", html_text(F.col("html")).alias("text"))


@query()
def abbreviation_fidelity(spark, sf):
    """Cosine of word counts before and after abbreviation, by source, with the safe share."""
    d = abbrev.abbreviate(docs(spark, sf, "doc_id", "source", "text"), corpus_mapping(spark, sf, 2, 3))
    t = d.select("source", fidelity.word_cosine(F.col("text"), F.col("short")).alias("cosine"))
    return fidelity.fidelity_report(t, "source").join(fidelity.fidelity_gate(t, 0.92, "source").drop("pairs"), "source")
