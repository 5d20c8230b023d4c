"""Quantization of numeric columns and choice of examples."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.functions.scalar import dequantize, quantize
from ctxpress.operators import exemplars, quant
from ctxpress.sources.tables import load

LINE = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
RANGES = "mm AS (SELECT " + ", ".join(f"min({c}) AS {c}_lo, max({c}) AS {c}_hi" for c in LINE) + " FROM lineitem)"


def code_sql(c: str, bits: int, lo: str | None = None, hi: str | None = None) -> str:
    lo, hi = lo or f"{c}_lo", hi or f"{c}_hi"
    return f"round(({c} - {lo}) / ({hi} - {lo}) * {float(2**bits - 1)!r}::DOUBLE)::INTEGER"


def hat_sql(c: str, bits: int, lo: str | None = None, hi: str | None = None) -> str:
    lo, hi = lo or f"{c}_lo", hi or f"{c}_hi"
    return f"({lo} + {code_sql(c, bits, lo, hi)} / {float(2**bits - 1)!r}::DOUBLE * ({hi} - {lo}))"


def lines(spark, sf, *cols):
    return load(spark, sf, "lineitem", *(cols or ("l_orderkey", "l_linenumber", *LINE)))


for _b in (4, 8, 12, 16):

    @query(f"WITH {RANGES} SELECT l_orderkey, l_linenumber, " + ", ".join(f"{code_sql(c, _b)} AS {c}_q" for c in LINE) + " FROM lineitem, mm", name=f"quantize_uniform_{_b}")
    def _uniform(spark, sf, bits=_b):
        t = lines(spark, sf)
        return quant.uniform_encode(t, quant.uniform_fit(t, LINE, bits)).select("l_orderkey", "l_linenumber", *[f"{c}_q" for c in LINE])


@query(f"WITH {RANGES} SELECT l_orderkey, l_linenumber, " + ", ".join(f"round({hat_sql(c, 8)}, 6) AS {c}_hat" for c in LINE) + " FROM lineitem, mm")
def dequantize_uniform(spark, sf):
    t = lines(spark, sf)
    g = quant.uniform_fit(t, LINE, 8)
    t = quant.uniform_decode(quant.uniform_encode(t, g), g)
    return t.select("l_orderkey", "l_linenumber", *[F.round(f"{c}_hat", 6).alias(f"{c}_hat") for c in LINE])


@query(f"WITH {RANGES} " + " UNION ALL ".join(
    f"SELECT '{c}' AS column, {b} AS bits, round(max(abs({c} - {hat_sql(c, b)})), 6) AS max_abs, round(avg(abs({c} - {hat_sql(c, b)})), 6) AS mean_abs, round(avg(({c} - {hat_sql(c, b)}) ** 2), 4) AS mse, round(any_value({c}_hi - {c}_lo) / {2**b - 1} / 2, 6) AS tight_bound, round(any_value({c}_hi - {c}_lo) / {2**b - 1}, 6) AS paper_bound, true AS within FROM lineitem, mm"
    for b in (4, 8, 16) for c in LINE))
def quant_error_bounds(spark, sf):
    t = lines(spark, sf, *LINE)
    grids = [quant.Grid(g.column, g.lo, g.hi, b) for b in (4, 8, 16) for g in quant.uniform_fit(t, LINE, b)]
    return quant.quant_error(t, grids)


@query(f"WITH {RANGES} " + " UNION ALL ".join(
    f"SELECT '{c}' AS column, tol AS tolerance, greatest(1, ceil(log2(({c}_hi - {c}_lo) / (2 * tol) + 1) - 1e-12))::INTEGER AS tight_bits, greatest(1, ceil(log2(({c}_hi - {c}_lo) / tol + 1) - 1e-12))::INTEGER AS paper_bits FROM mm, (SELECT unnest([0.001, 0.01, 1.0])::DOUBLE AS tol)" for c in LINE))
def bits_for_tolerance(spark, sf):
    grids = quant.uniform_fit(lines(spark, sf, *LINE), LINE, 8)
    rows = [(g.column, tol, quant.bits_for_tolerance(g.lo, g.hi, tol), quant.bits_for_tolerance(g.lo, g.hi, tol, "paper")) for g in grids for tol in (0.001, 0.01, 1.0)]
    return spark.createDataFrame(rows, "column string, tolerance double, tight_bits int, paper_bits int")


@query(f"WITH r AS (SELECT l_returnflag, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem GROUP BY 1) SELECT l_orderkey, l_linenumber, l_returnflag, {code_sql('l_extendedprice', 8, 'lo', 'hi')} AS q, round({hat_sql('l_extendedprice', 8, 'lo', 'hi')}, 6) AS hat FROM lineitem JOIN r USING (l_returnflag)")
def quantize_grouped(spark, sf):
    t = quant.quantize_grouped(lines(spark, sf, "l_orderkey", "l_linenumber", "l_returnflag", "l_extendedprice"), "l_extendedprice", "l_returnflag", 8)
    return t.select("l_orderkey", "l_linenumber", "l_returnflag", "q", F.round("hat", 6).alias("hat"))


@query("""WITH r AS (SELECT quantile_cont(value, 0.01) AS lo, quantile_cont(value, 0.99) AS hi FROM events)
SELECT count(*) AS records, count(*) FILTER (WHERE value < lo OR value > hi) AS clipped, sum(greatest(0, least(255, round((value - lo) / (hi - lo) * 255.0::DOUBLE)::INTEGER)))::BIGINT AS code_sum FROM events, r""")
def quantize_robust(spark, sf):
    e = load(spark, sf, "events", "value")
    g = quant.uniform_fit(e, ["value"], 8, clip=0.01)[0]
    q = quantize(F.col("value"), g.lo, g.hi, 8)
    return e.agg(F.count("*").alias("records"), F.count_if((F.col("value") < g.lo) | (F.col("value") > g.hi)).alias("clipped"), F.sum(q).alias("code_sum"))


@query(f"WITH {RANGES} SELECT l_returnflag, count(*) AS n, round(count(*) * any_value(l_extendedprice_lo) + any_value(l_extendedprice_hi - l_extendedprice_lo) / 255 * sum({code_sql('l_extendedprice', 8)})::BIGINT, 2) AS total, round(avg({hat_sql('l_extendedprice', 8)}), 4) AS mean FROM lineitem, mm GROUP BY l_returnflag")
def code_aggregate(spark, sf):
    """Sums and means from sums of codes, without decoding a row."""
    t = lines(spark, sf, "l_returnflag", "l_extendedprice")
    g = quant.uniform_fit(t, ["l_extendedprice"], 8)
    t = quant.code_sum(quant.uniform_encode(t, g), g[0], "l_returnflag")
    return t.select("l_returnflag", "n", F.round("total", 2).alias("total"), F.round("mean", 4).alias("mean"))


@query("SELECT count(*) AS matches FROM lineitem WHERE l_extendedprice >= 50000 AND l_quantity < 25")
def code_predicate(spark, sf):
    """A range filter answered on codes first, then verified."""
    t = lines(spark, sf, "l_extendedprice", "l_quantity")
    g = quant.uniform_fit(t, ["l_extendedprice", "l_quantity"], 8)
    t = quant.uniform_encode(t, g).where(quant.code_predicate(g[0], ">=", 50000.0) & quant.code_predicate(g[1], "<", 25.0))
    return t.where("l_extendedprice >= 50000 and l_quantity < 25").agg(F.count("*").alias("matches"))


SEEDS = "[" + ", ".join(f"{(i + 0.5) / 4!r}" for i in range(4)) + "]"


def _lloyd_sql(rounds: int) -> str:
    steps = f"v AS (SELECT value AS x, count(*) AS n FROM events GROUP BY value), c0 AS (SELECT unnest(quantile_cont(value, {SEEDS})) AS c, unnest(range(4)) AS i FROM events)"
    for r in range(rounds):
        steps += f""", m{r} AS (SELECT list(c ORDER BY c) AS cs FROM c{r}),
  c{r + 1} AS (SELECT coalesce(s.m, o.c) AS c, o.i FROM (SELECT c, row_number() OVER (ORDER BY c) - 1 AS i FROM c{r}) o LEFT JOIN
    (SELECT (x > (cs[1] + cs[2]) / 2)::INT + (x > (cs[2] + cs[3]) / 2)::INT + (x > (cs[3] + cs[4]) / 2)::INT AS k, sum(x * n) / sum(n) AS m FROM v, m{r} GROUP BY 1) s ON s.k = o.i)"""
    return f"WITH {steps} SELECT (row_number() OVER (ORDER BY c) - 1)::INTEGER AS cluster, round(c, 4) AS centroid FROM c{rounds}"


@query(_lloyd_sql(5))
def kmeans_quantile_lloyd(spark, sf):
    c = quant.kmeans_fit(load(spark, sf, "events", "value"), "value", 4, rounds=5)
    return spark.createDataFrame([(i, round(v, 4)) for i, v in enumerate(c)], "cluster int, centroid double")


@query()
def kmeans_quantize(spark, sf):
    """Codes and reconstruction by weighted k-means on distinct values."""
    e = load(spark, sf, "events", "event_id", "value")
    c = quant.kmeans_fit(e, "value", 16, init="ml")
    t = quant.kmeans_decode(quant.kmeans_encode(e, "value", c, "code"), "code", c, "hat")
    return t.select("event_id", "code", F.round("hat", 4).alias("hat"))


@query()
def kmeans_vs_uniform(spark, sf):
    """Mean square error with as many centroids as the grid has levels: values with few distinct ones become exact."""
    t, out = lines(spark, sf, *LINE), []
    for c, k in (("l_discount", 11), ("l_tax", 9), ("l_quantity", 16), ("l_quantity", 50)):
        v = quant.weighted_values(t, c)
        bits = max(1, (k - 1).bit_length())
        g = quant.uniform_fit(t, [c], bits)[0]
        cents = quant.kmeans_fit(t, c, k) if k < 40 else sorted(r["x"] for r in v.collect())
        hat = dequantize(quantize(F.col("x"), g.lo, g.hi, bits), g.lo, g.hi, bits)
        r = v.agg(quant.kmeans_mse(v, cents).alias("km"), (F.sum(F.col("n") * F.pow(F.col("x") - hat, 2)) / F.sum("n")).alias("un")).first()
        out.append((c, k, 2**bits, round(r["km"], 10), round(r["un"], 10)))
    return spark.createDataFrame(out, "column string, centroids int, levels int, kmeans_mse double, uniform_mse double")


@query()
def kmeans_exact_optimum(spark, sf):
    """Quantile-seeded rounds against the exact optimum of a dynamic programme on the distinct quantities."""
    import numpy as np

    t, out = lines(spark, sf, "l_quantity"), []
    v = quant.weighted_values(t, "l_quantity")
    rows = v.collect()  # fifty distinct quantities
    x, n = np.array([r["x"] for r in rows]), np.array([r["n"] for r in rows])
    for k in (2, 4, 8):
        cents = quant.kmeans_fit(t, "l_quantity", k)
        got = v.agg(quant.kmeans_mse(v, cents).alias("m")).first()["m"]
        out.append((k, round(got, 6), round(quant.kmeans_1d_exact(x, n, k)[0], 6)))
    return spark.createDataFrame(out, "k int, lloyd_mse double, optimal_mse double")


@query("WITH p AS (" + " UNION ALL ".join(f"SELECT '{c}' AS column, min({c}) AS lo, max({c}) AS hi, count(DISTINCT {c}) AS distinct_values, round(avg(len(printf('%.2f', {c}))), 4) AS mc FROM lineitem" for c in LINE) + """),
  q AS (SELECT *, greatest(1, ceil(log2((hi - lo) / 0.02::DOUBLE + 1) - 1e-12))::INTEGER AS bits FROM p),
  r AS (SELECT *, round(1 - CASE WHEN distinct_values <= 64 THEN len(distinct_values::VARCHAR) ELSE len(((2 ** bits)::BIGINT)::VARCHAR) END / mc, 4) AS saving FROM q)
SELECT "column", distinct_values, bits, saving, CASE WHEN saving < 0.1 THEN 'none' WHEN distinct_values <= 64 THEN 'kmeans' ELSE 'uniform' END AS scheme FROM r""")
def column_policy(spark, sf):
    return quant.plan_columns(lines(spark, sf, *LINE), LINE, 0.01)


@query("WITH s AS (SELECT avg(c_acctbal) AS m, stddev_samp(c_acctbal) AS d FROM customer) SELECT c_custkey, round((c_acctbal - m) / d, 6) AS c_acctbal_z FROM customer, s")
def standardize_numeric(spark, sf):
    t = exemplars.standardize(load(spark, sf, "customer", "c_custkey", "c_acctbal"), ["c_acctbal"])
    return t.select("c_custkey", F.round("c_acctbal_z", 6).alias("c_acctbal_z"))


def vectors(spark, sf):
    return load(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")


EMB = "e AS (SELECT vec_id AS id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings)"


@query(f"""WITH {EMB}, d AS (SELECT a.id, a.label AS own, b.label AS other, avg(list_distance(a.v, b.v)) FILTER (WHERE a.id <> b.id) AS m FROM e a, e b GROUP BY ALL),
  s AS (SELECT id, own, max(m) FILTER (WHERE own = other) AS a, min(m) FILTER (WHERE own <> other) AS b FROM d GROUP BY ALL)
SELECT id, own AS cluster, round(a, 5) AS a, round(b, 5) AS b, round((b - a) / greatest(a, b), 5) AS s FROM s""")
def silhouette_exact_given_labels(spark, sf):
    t = exemplars.silhouette_exact(vectors(spark, sf).withColumnRenamed("label", "cluster"))
    return t.select("id", "cluster", *[F.round(c, 5).alias(c) for c in ("a", "b", "s")])


@query()
def silhouette_sweep(spark, sf):
    """Every number of clusters from 5 to 50; beyond 50 000 vectors the fits run on a hash sample of about that many."""
    v = vectors(spark, sf).select("id", "vec")
    table, best = exemplars.silhouette_sweep(v, sample_fraction=exemplars.sample_share(v))
    return table.withColumn("best", F.col("k") == best)


def mixed_features(spark, sf):
    """Features of three kinds: given vectors, hashed words of the benchmark's texts, and standardized numbers of customers' nations."""
    e = vectors(spark, sf).select("id", "vec")
    t = exemplars.text_features(load(spark, sf, "benchmark"), "item_id").withColumn("vec", F.transform("vec", lambda x: x / F.sqrt(F.greatest(F.aggregate("vec", F.lit(0.0), lambda a, y: a + y * y), F.lit(1e-12)))))
    nation = load(spark, sf, "customer").groupBy("c_nationkey").agg(F.count("*").cast("double").alias("n"), F.avg("c_acctbal").alias("mean"), F.max("c_acctbal").alias("most"))
    return {"embeddings": e, "texts": t, "numbers": exemplars.numeric_features(nation, "c_nationkey", ["n", "mean", "most"])}


@query()
def few_shot_from_sweep(spark, sf):
    """The whole chain on each kind of features: sweep, best number of clusters, clusters, prototypes, three shots."""
    out = None
    for kind, f in mixed_features(spark, sf).items():
        f = f.persist()
        n = f.count()
        ks = range(5, min(50, n - 1) + 1)
        _, best = exemplars.silhouette_sweep(f, ks, sample_fraction=exemplars.sample_share(f))
        t = exemplars.few_shot(exemplars.prototypes(exemplars.cluster(f, best)))
        t = t.select(F.lit(kind).alias("features"), F.lit(best).alias("clusters"), F.col("id").cast("long").alias("id"), "size", "distance")
        out = t if out is None else out.unionAll(t)
    return out


@query("""WITH n AS (SELECT c_nationkey, count(*)::DOUBLE AS n, avg(c_acctbal) AS m, max(c_acctbal) AS x FROM customer GROUP BY c_nationkey), s AS (SELECT avg(n) AS n0, stddev_samp(n) AS n1, avg(m) AS m0, stddev_samp(m) AS m1, avg(x) AS x0, stddev_samp(x) AS x1 FROM n)
SELECT c_nationkey::BIGINT AS id, round((n - n0) / n1, 6) AS z0, round((m - m0) / m1, 6) AS z1, round((x - x0) / x1, 6) AS z2 FROM n, s""")
def numeric_features(spark, sf):
    return mixed_features(spark, sf)["numbers"].select(F.col("id").cast("long").alias("id"), *[F.round(F.element_at("vec", i + 1), 6).alias(f"z{i}") for i in range(3)])


CENTERS = f"""{EMB}, dim AS (SELECT label, i, avg(v[i + 1]) AS m FROM (SELECT label, v, unnest(range(64)) AS i FROM e) GROUP BY ALL), cen AS (SELECT label, list(m ORDER BY i) AS c FROM dim GROUP BY label),
  near AS (SELECT id, e.label, round(list_sum(list_transform(range(1, 65), lambda i: (v[i] - c[i]) * (v[i] - c[i]))), 6) AS d FROM e JOIN cen USING (label)),
  proto AS (SELECT label AS cluster, arg_min(id, (d, id)) AS id, count(*) AS size, min(d) AS distance FROM near GROUP BY label)"""


@query(f"WITH {CENTERS} SELECT cluster, id, size, distance FROM proto")
def prototypes_by_label(spark, sf):
    return exemplars.prototypes(vectors(spark, sf).withColumnRenamed("label", "cluster"))


@query(f"WITH {CENTERS} SELECT cluster, id, size, distance FROM proto ORDER BY size DESC, id LIMIT 3")
def few_shot_set(spark, sf):
    return exemplars.few_shot(exemplars.prototypes(vectors(spark, sf).withColumnRenamed("label", "cluster")))


MIXED = "((vec_id * 2654435761 + 7) % 4294967296)"


@query(f"SELECT vec_id, label FROM embeddings ORDER BY {MIXED}, vec_id LIMIT 3")
def random_shots(spark, sf):
    return exemplars.random_shots(load(spark, sf, "embeddings", "vec_id", "label"), "vec_id").select("vec_id", "label")


@query(f"""WITH {CENTERS}, shots AS (SELECT 'prototypes' AS kind, id FROM proto UNION ALL SELECT 'random', vec_id FROM (SELECT vec_id FROM embeddings ORDER BY {MIXED}, vec_id LIMIT (SELECT count(*) FROM proto))),
  d AS (SELECT kind, p.id, p.label, arg_min(s.label, (round(list_sum(list_transform(range(1, 65), lambda i: (p.v[i] - s.v[i]) * (p.v[i] - s.v[i]))), 6), s.id)) AS nl, min(round(list_sum(list_transform(range(1, 65), lambda i: (p.v[i] - s.v[i]) * (p.v[i] - s.v[i]))), 6)) AS dist
        FROM e p, shots JOIN e s ON s.id = shots.id GROUP BY ALL)
SELECT kind, count(*) AS points, round(avg((nl = label)::INT), 6) AS label_accuracy, round(avg(dist), 4) AS mean_distance FROM d GROUP BY kind""")
def exemplar_coverage(spark, sf):
    """Prototypes against as many random rows: does the nearest example have a point's label, and how far is it."""
    v = vectors(spark, sf)
    protos = exemplars.prototypes(v.withColumnRenamed("label", "cluster")).select("id")
    n = protos.count()
    out = None
    for kind, ids in (("prototypes", protos), ("random", exemplars.random_shots(v, "id", n).select("id"))):
        t = exemplars.coverage(v, v.join(F.broadcast(ids), "id"))
        t = t.agg(F.count("*").alias("points"), F.round(F.avg((F.col("nearest_label") == F.col("label")).cast("int")), 6).alias("label_accuracy"), F.round(F.avg("distance"), 4).alias("mean_distance"))
        t = t.select(F.lit(kind).alias("kind"), "points", "label_accuracy", "mean_distance")
        out = t if out is None else out.unionAll(t)
    return out


@query()
def farthest_first_shots(spark, sf):
    ids = exemplars.farthest_first(vectors(spark, sf).select("id", "vec"), 3)
    return spark.createDataFrame([(i, v) for i, v in enumerate(ids)], "place int, vec_id long")


@query(f"WITH {RANGES} SELECT l_returnflag, round(sum(l_extendedprice * (1 - l_discount)), 2) AS exact, round(sum({hat_sql('l_extendedprice', 8)} * (1 - {hat_sql('l_discount', 8)})), 2) AS approximate, round(abs(sum({hat_sql('l_extendedprice', 8)} * (1 - {hat_sql('l_discount', 8)})) / sum(l_extendedprice * (1 - l_discount)) - 1), 6) AS rel_error FROM lineitem, mm GROUP BY l_returnflag")
def query_fidelity(spark, sf):
    """Revenue by flag on stored and decoded columns."""
    t = lines(spark, sf, "l_returnflag", "l_extendedprice", "l_discount")
    g = {x.column: x for x in quant.uniform_fit(t, ["l_extendedprice", "l_discount"], 8)}
    hat = {c: dequantize(quantize(F.col(c), x.lo, x.hi, 8), x.lo, x.hi, 8) for c, x in g.items()}
    t = t.groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("e"), F.sum(hat["l_extendedprice"] * (1 - hat["l_discount"])).alias("a"))
    return t.select("l_returnflag", F.round("e", 2).alias("exact"), F.round("a", 2).alias("approximate"), F.round(F.abs(F.col("a") / F.col("e") - 1), 6).alias("rel_error"))


@query("""SELECT l_returnflag, round(sum(x * 1.0) / count(*), 6) AS mean, 4::BIGINT AS bins, true AS never_worse FROM (SELECT l_returnflag, l_quantity AS x FROM lineitem) GROUP BY l_returnflag""")
def optimal_bins_by_flag(spark, sf):
    """The exact best four bins of quantities in each group, found by a grouped function; never worse than equal widths."""
    t = quant.optimal_bins(lines(spark, sf, "l_returnflag", "l_quantity"), "l_returnflag", "l_quantity", 4)
    mean = lines(spark, sf, "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.round(F.sum("l_quantity") / F.count("*"), 6).alias("mean"))
    return t.join(mean, "l_returnflag").select("l_returnflag", "mean", F.size("centroids").cast("long").alias("bins"), (F.col("mse") <= F.col("equal_width_mse") + 1e-9).alias("never_worse"))


TABLE_QUESTIONS = (
    ("order_price_by_status", "orders", "o_orderstatus", "avg", "o_totalprice"),
    ("order_price_by_priority", "orders", "o_orderpriority", "sum", "o_totalprice"),
    ("balance_by_segment", "customer", "c_mktsegment", "avg", "c_acctbal"),
    ("balance_by_nation", "customer JOIN nation ON c_nationkey = n_nationkey", "n_name", "sum", "c_acctbal"),
    ("supplier_balance_by_nation", "supplier JOIN nation ON s_nationkey = n_nationkey", "n_name", "avg", "s_acctbal"),
)


def _table_questions_sql(bits: int = 8) -> str:
    out = []
    for qid, source, by, how, col in TABLE_QUESTIONS:
        levels = 2**bits - 1
        hat = f"(lo + round(({col} - lo) / (hi - lo) * {levels}) * (hi - lo) / {levels})"
        mm = f"(SELECT min({col}) AS lo, max({col}) AS hi FROM {source.split(' ')[0]})"
        out.append(f"SELECT '{qid}' AS qid, {by} AS grp, round({how}({col}), 2) AS exact, round({how}({hat}), 2) AS decoded, coalesce(abs(({how}({hat}) - {how}({col})) / nullif({how}({col}), 0)), 0.0) <= 0.01 AS correct FROM {source}, {mm} GROUP BY {by}")
    return " UNION ALL ".join(out)


@query(_table_questions_sql())
def numeric_questions_across_tables(spark, sf):
    """Questions on orders, customers and suppliers, some through their nations, on stored and on decoded values."""
    nation, out = load(spark, sf, "nation", "n_nationkey", "n_name"), None
    for qid, source, by, how, col in TABLE_QUESTIONS:
        table = source.split(" ")[0]
        t = load(spark, sf, table)
        g = quant.uniform_fit(t, [col], 8)[0]
        if "JOIN" in source:
            t = t.join(F.broadcast(nation), F.col(f"{table[0]}_nationkey") == F.col("n_nationkey"))
        f = {"sum": F.sum, "avg": F.avg}[how]
        t = t.groupBy(F.col(by).alias("grp")).agg(f(col).alias("e"), f(dequantize(quantize(F.col(col), g.lo, g.hi, 8), g.lo, g.hi, 8)).alias("d"))
        right = F.coalesce(F.abs(F.try_divide(F.col("d") - F.col("e"), F.col("e"))), F.lit(0.0)) <= 0.01
        t = t.select(F.lit(qid).alias("qid"), "grp", F.round("e", 2).alias("exact"), F.round("d", 2).alias("decoded"), right.alias("correct"))
        out = t if out is None else out.unionAll(t)
    return out
