"""Relational operators around the methods: joins, grouping, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.catalog.information import W
from ctxpress.functions.scalar import register_macros
from ctxpress.functions.tokens import estimated_tokens, lexical, token_count
from ctxpress.operators import relational
from ctxpress.sources.tables import load


@query("SELECT d.doc_id, n_chars FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def join_semi(spark, sf):
    return load(spark, sf, "documents", "doc_id", "n_chars").join(load(spark, sf, "labels", "doc_id"), "doc_id", "left_semi")


@query("SELECT d.doc_id, n_chars FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def join_anti(spark, sf):
    return load(spark, sf, "documents", "doc_id", "n_chars").join(load(spark, sf, "labels", "doc_id"), "doc_id", "left_anti")


@query(f"""WITH a AS (SELECT tok, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM documents) GROUP BY tok), b AS (SELECT tok, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM conversations) GROUP BY tok)
SELECT coalesce(a.tok, b.tok) AS tok, a.n AS in_documents, b.n AS in_conversations FROM a FULL JOIN b ON a.tok = b.tok""")
def join_full_outer(spark, sf):
    from ctxpress.operators.selfinfo import unigram_counts

    a, b = (unigram_counts(load(spark, sf, t, "text")).withColumnRenamed("n", c) for t, c in (("documents", "in_documents"), ("conversations", "in_conversations")))
    return a.join(b, "tok", "full")


@query("""SELECT n_name, o_orderpriority, count(*) AS lines, sum((l_extendedprice * (1 - l_discount))::DECIMAL(18,4))::DOUBLE AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL""")
def join_star(spark, sf):
    t = load(spark, sf, "lineitem", "l_orderkey", "l_extendedprice", "l_discount").join(load(spark, sf, "orders", "o_orderkey", "o_custkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    t = t.join(load(spark, sf, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(load(spark, sf, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
    return t.groupBy("n_name", "o_orderpriority").agg(F.count("*").alias("lines"), F.sum((F.col("l_extendedprice") * (1 - F.col("l_discount"))).cast("decimal(18,4)")).cast("double").alias("revenue"))


@query("""WITH v AS (SELECT user_id, ts, event_id AS version FROM events WHERE event_type = 'signup')
SELECT e.event_id, (SELECT max((v.ts, v.version)) FROM v WHERE v.user_id = e.user_id AND v.ts <= e.ts)[2] AS version FROM events e WHERE event_type <> 'signup'""")
def join_asof(spark, sf):
    """The dictionary version in force at each event: the user's last sign-up before it."""
    e = load(spark, sf, "events", "event_id", "user_id", "ts", "event_type")
    v = e.where("event_type = 'signup'").groupBy("user_id", "ts").agg(F.max("event_id").alias("version"))
    return relational.as_of(e.where("event_type <> 'signup'").select("event_id", "user_id", "ts"), v, "user_id", "ts", "version").select("event_id", "version")


@query("""SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY WHERE a.event_type = 'signup' AND b.event_type = 'purchase'""")
def join_interval(spark, sf):
    from ctxpress.streaming.streams import followed_by

    e = load(spark, sf, "events", "event_id", "user_id", "ts", "event_type")
    return followed_by(e.where("event_type = 'signup'"), e.where("event_type = 'purchase'"), "1 DAY", "1 day").select("a_id", "b_id")


BANDS = "(SELECT unnest(['low', 'mid', 'high']) AS band, unnest([0.0, 10000.0, 50000.0])::DOUBLE AS lo, unnest([10000.0, 50000.0, 200000.0])::DOUBLE AS hi)"


@query(f"SELECT band, count(*) AS lines, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN {BANDS} ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY band")
def join_range(spark, sf):
    b = spark.createDataFrame([("low", 0.0, 10000.0), ("mid", 10000.0, 50000.0), ("high", 50000.0, 200000.0)], "band string, lo double, hi double")
    t = relational.range_join(load(spark, sf, "lineitem", "l_extendedprice"), "l_extendedprice", F.broadcast(b), "lo", "hi", 10000.0)
    return t.groupBy("band").agg(F.count("*").alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def join_containment(spark, sf):
    from ctxpress.plans.workloads import answers

    return answers(load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark"))


@query("SELECT source, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def join_lateral_top(spark, sf):
    """The three longest documents of each source by a lateral join."""
    load(spark, sf, "documents", "source", "doc_id", "n_chars").createOrReplaceTempView("_lateral_docs")
    return spark.sql("SELECT s.source, d.doc_id, d.n_chars FROM (SELECT DISTINCT source FROM _lateral_docs) s, LATERAL (SELECT doc_id, n_chars FROM _lateral_docs x WHERE x.source = s.source ORDER BY n_chars DESC, doc_id LIMIT 3) d")


COST = f"sum(len(regexp_extract_all(text, '{W}')))::BIGINT AS tokens"


@query(f"SELECT source, lang, {COST} FROM documents GROUP BY CUBE (source, lang)")
def group_cube(spark, sf):
    return load(spark, sf, "documents", "source", "lang", "text").cube("source", "lang").agg(F.sum(token_count(F.col("text"))).alias("tokens"))


@query(f"SELECT source, lang, {COST} FROM documents GROUP BY ROLLUP (source, lang)")
def group_rollup(spark, sf):
    return load(spark, sf, "documents", "source", "lang", "text").rollup("source", "lang").agg(F.sum(token_count(F.col("text"))).alias("tokens"))


@query(f"SELECT source, lang, {COST} FROM documents GROUP BY GROUPING SETS ((source), (lang), ())")
def group_sets(spark, sf):
    return load(spark, sf, "documents", "source", "lang", "text").groupingSets([["source"], ["lang"], []], "source", "lang").agg(F.sum(token_count(F.col("text"))).alias("tokens"))


@query("SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'fr') AS fr, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'es') AS es FROM documents GROUP BY source")
def pivot_languages(spark, sf):
    return load(spark, sf, "documents", "source", "lang").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).count().fillna(0)


@query('SELECT "column", count(*) AS n, round(avg(value), 6) AS mean, round(min(value), 4) AS lo, round(max(value), 4) AS hi FROM (UNPIVOT (SELECT l_quantity, l_extendedprice, l_discount, l_tax FROM lineitem) ON COLUMNS(*) INTO NAME "column" VALUE value) GROUP BY "column"')
def unpivot_columns(spark, sf):
    t = load(spark, sf, "lineitem", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    return t.unpivot([], t.columns, "column", "value").groupBy("column").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.min("value"), 4).alias("lo"), F.round(F.max("value"), 4).alias("hi"))


def vocabulary(table: str) -> str:
    return f"SELECT unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM {table}"



@query(f"SELECT 'both' AS part, count(*) AS types FROM ({vocabulary('documents')} INTERSECT {vocabulary('conversations')}) UNION ALL SELECT 'only_conversations', count(*) FROM ({vocabulary('conversations')} EXCEPT {vocabulary('documents')}) UNION ALL SELECT 'any', count(*) FROM ({vocabulary('documents')} UNION {vocabulary('conversations')})")
def set_vocabularies(spark, sf):
    from ctxpress.functions.tokens import words

    a, b = (load(spark, sf, t, "text").select(F.explode(words(F.col("text"), True)).alias("tok")) for t in ("documents", "conversations"))
    one = lambda df, part: df.agg(F.count("*").alias("types")).select(F.lit(part).alias("part"), "types")
    return one(a.intersect(b), "both").unionAll(one(b.subtract(a), "only_conversations")).unionAll(one(a.union(b).distinct(), "any"))


@query("SELECT lang, count(*) AS texts FROM (SELECT lang, source FROM documents EXCEPT ALL SELECT DISTINCT lang, source FROM documents) GROUP BY lang")
def set_except_all(spark, sf):
    d = load(spark, sf, "documents", "lang", "source")
    return d.exceptAll(d.distinct()).groupBy("lang").agg(F.count("*").alias("texts"))


@query("""SELECT doc_id, source, row_number() OVER w AS place, rank() OVER v AS chars_rank, dense_rank() OVER v AS chars_dense, round(percent_rank() OVER v, 6) AS share, ntile(4) OVER w AS quarter, round(cume_dist() OVER v, 6) AS cume
FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars DESC, doc_id), v AS (PARTITION BY source ORDER BY n_chars DESC)""")
def window_ranks(spark, sf):
    d = load(spark, sf, "documents", "doc_id", "source", "n_chars")
    w, v = (Window.partitionBy("source").orderBy(*c) for c in ((F.desc("n_chars"), "doc_id"), (F.desc("n_chars"),)))
    big = lambda c: c.cast("long")
    return d.select("doc_id", "source", big(F.row_number().over(w)).alias("place"), big(F.rank().over(v)).alias("chars_rank"), big(F.dense_rank().over(v)).alias("chars_dense"), F.round(F.percent_rank().over(v), 6).alias("share"), big(F.ntile(4).over(w)).alias("quarter"), F.round(F.cume_dist().over(v), 6).alias("cume"))


@query("""SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) AS last_hour,
  lag(event_type) OVER o AS before, lead(event_type) OVER o AS after, first_value(event_id) OVER o AS first_event, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_event
FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def window_frames(spark, sf):
    e = load(spark, sf, "events", "event_id", "user_id", "ts", "event_type", "value").withColumn("s", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long"))  # nearest second, the even one of two
    o = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(
        "event_id", F.round(F.sum("value").over(o.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)), 4).alias("last_hour"),
        F.lag("event_type").over(o).alias("before"), F.lead("event_type").over(o).alias("after"), F.first("event_id").over(o).alias("first_event"), F.nth_value("event_id", 2).over(o.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second_event"),
    )


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20 OFFSET 10")
def top_k_offset(spark, sf):
    return load(spark, sf, "documents", "doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").offset(10).limit(20)


@query("SELECT event_type, count(*) AS records, sum((props->>'$.k')::INTEGER)::BIGINT AS k_sum, max(len(props))::INTEGER AS longest FROM events GROUP BY event_type")
def json_props(spark, sf):
    e = load(spark, sf, "events", "event_type", "props").withColumn("j", F.from_json("props", "k int"))
    return e.groupBy("event_type").agg(F.count("*").alias("records"), F.sum("j.k").alias("k_sum"), F.max(F.length("props")).alias("longest"))


@query(f"SELECT doc_id, len(regexp_extract_all(text, '[\\p{{L}}\\p{{M}}\\p{{N}}_]+|[^\\s\\p{{L}}\\p{{M}}\\p{{N}}_]'))::BIGINT AS lexical, (list_sum(list_transform(regexp_extract_all(text, '[\\p{{L}}\\p{{M}}]+'), lambda r: ceil(len(r) / 4.0))) + coalesce(list_sum(list_transform(regexp_extract_all(text, '\\p{{N}}+'), lambda r: ceil(len(r) / 3.0))), 0) + len(regexp_extract_all(text, '[^\\s\\p{{L}}\\p{{M}}\\p{{N}}]')))::BIGINT AS estimated FROM documents")
def token_costs(spark, sf):
    return load(spark, sf, "documents", "doc_id", "text").select("doc_id", token_count(F.col("text"), "lexical").alias("lexical"), estimated_tokens(F.col("text")).alias("estimated"))


@query("SELECT doc_id, text AS restored FROM documents")
def tokenize_roundtrip(spark, sf):
    """Tokens with their gaps put together again are the text."""
    from ctxpress.functions.tokens import tokenize, untokenize

    t = load(spark, sf, "documents", "doc_id", "text").select("doc_id", tokenize(F.col("text")).alias("t"))
    return t.select("doc_id", untokenize(F.col("t")).alias("restored"))


@query(f"SELECT count(DISTINCT tok) AS types, count(*) AS tokens FROM (SELECT unnest(regexp_extract_all(text, '[\\p{{L}}\\p{{M}}\\p{{N}}_]+|[^\\s\\p{{L}}\\p{{M}}\\p{{N}}_]')) AS tok FROM documents)")
def vocabulary_size(spark, sf):
    return load(spark, sf, "documents", "text").select(F.explode(lexical(F.col("text"))).alias("tok")).agg(F.countDistinct("tok").alias("types"), F.count("*").alias("tokens"))


@query()
def vocabulary_sketch(spark, sf):
    """Types by a sketch of fixed size, with its relative error against the exact count."""
    t = load(spark, sf, "documents", "text").select(F.explode(lexical(F.col("text"))).alias("tok"))
    t = t.agg(F.approx_count_distinct("tok", 0.02).alias("sketched"), F.hll_sketch_estimate(F.hll_sketch_agg("tok")).alias("hll"), F.countDistinct("tok").alias("exact"))
    return t.withColumn("relative_error", F.round(F.abs(F.col("sketched") / F.col("exact") - 1), 4))


@query("SELECT l_orderkey, l_linenumber, CASE WHEN 105000.0 = 900.0 THEN 0 ELSE round((l_extendedprice - 900) / 104100.0::DOUBLE * 255)::INTEGER END AS q FROM lineitem")
def sql_macros(spark, sf):
    """The quantizer through SQL, inlined by the analyzer."""
    register_macros(spark)
    load(spark, sf, "lineitem").createOrReplaceTempView("_macro_lines")
    return spark.sql("SELECT l_orderkey, l_linenumber, quantize(l_extendedprice, 900D, 105000D, 8) AS q FROM _macro_lines")


@query(f"SELECT doc_id, count(*) AS bigrams FROM (SELECT doc_id, unnest(range(1, len(w))) FROM (SELECT doc_id, regexp_extract_all(text, '{W}') AS w FROM documents)) GROUP BY doc_id")
def sql_table_function(spark, sf):
    from ctxpress.functions.udtfs import register_udtfs

    register_udtfs(spark)
    load(spark, sf, "documents", "doc_id", "text").createOrReplaceTempView("_udtf_docs")
    return spark.sql("SELECT doc_id, count(*) AS bigrams FROM _udtf_docs, LATERAL ngram_table(text, 2) GROUP BY doc_id")


def cells_sql(source: str) -> str:
    return " UNION ALL ".join(f"SELECT tok, {i} AS row, ('0x' || substr(md5(tok), {8 * i + 1}, 8))::BIGINT % 4096 AS cell FROM {source}" for i in range(4))


@query(f"""WITH t AS (SELECT unnest(regexp_extract_all(lower(text), '{W}')) AS tok FROM documents), types AS (SELECT tok, count(*) AS freq FROM t GROUP BY tok), c AS ({cells_sql('types')}),
  sketch AS (SELECT row, cell, sum(freq) AS n FROM c JOIN types USING (tok) GROUP BY row, cell)
SELECT tok, any_value(freq) AS freq, min(n)::BIGINT AS estimate FROM types JOIN c USING (tok) JOIN sketch USING (row, cell) GROUP BY tok""")
def count_min_words(spark, sf):
    """Counts of words by a sketch of fixed size beside the exact ones."""
    from ctxpress.functions.tokens import words

    t = load(spark, sf, "documents", "text").select(F.explode(words(F.col("text"), True)).alias("tok"))
    types = t.groupBy("tok").agg(F.count("*").alias("freq"))
    return relational.count_min_estimates(types, "tok", relational.count_min(t, F.col("tok")))


@query()
def quantiles_by_kll(spark, sf):
    """Quantiles of prices by a KLL sketch, with the rank that each really has."""
    p = load(spark, sf, "lineitem", "l_extendedprice").select(F.col("l_extendedprice").cast("double").alias("x"))
    values = F.array(*[F.struct(F.lit(q).alias("share"), F.kll_sketch_get_quantile_double("s", F.lit(q)).alias("value")) for q in (0.01, 0.25, 0.5, 0.75, 0.99)])
    one = p.agg(F.kll_sketch_agg_double("x").alias("s")).select(F.explode(values).alias("v")).select("v.*")
    t = p.join(F.broadcast(one), F.col("x") <= F.col("value")).groupBy("share", "value").agg(F.count("*").alias("at_most"))
    return t.crossJoin(F.broadcast(p.agg(F.count("*").alias("n")))).select("share", "value", F.round(F.col("at_most") / F.col("n"), 6).alias("rank"))


@query("""WITH n AS (SELECT source, lang, count(*) AS n FROM documents WHERE lang IS NOT NULL GROUP BY ALL), m AS (SELECT source, lang, row_number() OVER (PARTITION BY source ORDER BY n DESC, lang) AS place FROM n)
SELECT d.source, any_value(m.lang) AS most_common, (SELECT string_agg(DISTINCT lang, ',' ORDER BY lang) FROM documents e WHERE e.source IS NOT DISTINCT FROM d.source) AS langs FROM documents d LEFT JOIN m ON m.source IS NOT DISTINCT FROM d.source AND place = 1 GROUP BY d.source""")
def list_and_mode(spark, sf):
    """Languages of a source as a list, and the most frequent of them, the least on a tie."""
    d = load(spark, sf, "documents", "source", "lang").groupBy("source", "lang").agg(F.count("*").alias("n"))
    most = F.min_by("lang", F.when(F.col("lang").isNotNull(), F.struct((-F.col("n")).alias("n"), F.col("lang").alias("lang"))))
    return d.groupBy("source").agg(most.alias("most_common"), F.expr("listagg(lang, ',') WITHIN GROUP (ORDER BY lang)").alias("langs"))
