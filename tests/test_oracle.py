"""Every query with SQL against DuckDB, on the smallest tables."""

import datetime
import decimal
import math

import duckdb
import pytest

from ctxpress.catalog import load_all

QUERIES, ORACLE = load_all()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 9) + 0.0
    if isinstance(v, decimal.Decimal):
        return float(v)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in rows), key=lambda r: tuple((x is None, str(x)) for x in r))


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_matches_sql(spark, con, sf, name):
    df = QUERIES[name](spark, sf)
    got = rows_of(df.columns, df.collect())
    rel = con.execute(ORACLE[name])
    names = [d[0] for d in rel.description]
    assert sorted(names) == sorted(df.columns)
    assert got == rows_of(names, rel.fetchall())


#: What must hold of the rows of queries that SQL cannot express.
HOLDS = {
    "abbreviate_overlap_policies": lambda r: len({x["words_before"] for x in r}) == 1 and (w := {x["policy"]: x["words_after"] for x in r})["max_saving"] <= min(w.values()) and max(w.values()) < r[0]["words_before"],
    "baseline_byte_codecs": lambda r: r[0]["gzip"] < r[0]["bytes"] and r[0]["bzip2"] < r[0]["bytes"] and r[0]["deflate"] <= r[0]["gzip"] and r[0]["gzip"] <= 3 * r[0]["gzip_base64_tokens"] <= r[0]["gzip"] + 3 * 200,  # at most one more for each text
    "baseline_lzw_codes": lambda r: all(0 < x["codes"] <= x["bytes"] or not x["bytes"] for x in r) and sum(x["codes"] for x in r) < 0.7 * sum(x["bytes"] for x in r),
    "classification_reader": lambda r: {x["arm"] for x in r} == {"A", "truncated"} and all(0.4 <= x["accuracy"] <= 1 for x in r),
    "fidelity_gate": lambda r: [x["share"] for x in sorted(r, key=lambda x: -x["safe_share"])] == [0.9, 0.7, 0.5] and all(x["safe"] <= x["pairs"] for x in r),
    "few_shot_from_sweep": lambda r: len(r) == 9 and {x["features"] for x in r} == {"embeddings", "texts", "numbers"} and all(5 <= x["clusters"] <= 50 for x in r),
    "kmeans_exact_optimum": lambda r: all(x["optimal_mse"] <= x["lloyd_mse"] + 1e-9 for x in r) and len(r) == 3,
    "kmeans_quantize": lambda r: {x["code"] for x in r if x["code"] is not None} <= set(range(16)) and all(len({y["hat"] for y in r if y["code"] == c}) <= 1 for c in range(16)),
    "kmeans_vs_uniform": lambda r: all(x["kmeans_mse"] <= x["uniform_mse"] + 1e-9 for x in r if x["centroids"] >= 9 and x["column"] != "l_quantity") and [x["kmeans_mse"] for x in r if x["centroids"] == 50] == [0.0],
    "method_accuracy_swept": lambda r: len(r) == 31 and [x["delta"] for x in r if x["method"] == "A"] == [0.0] and all(0 <= x["accuracy"] <= 100 for x in r),
    "quantiles_by_kll": lambda r: len(r) == 5 and all(abs(x["rank"] - x["share"]) < 0.02 for x in r),
    "silhouette_sweep": lambda r: sorted(x["k"] for x in r) == list(range(5, 51)) and [x["silhouette"] for x in r if x["best"]] == [max(x["silhouette"] for x in r)],
    "vocabulary_sketch": lambda r: r[0]["relative_error"] < 0.06 and abs(r[0]["hll"] / r[0]["exact"] - 1) < 0.06,
}


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLE)))
def test_holds(spark, sf, name):
    assert HOLDS[name](QUERIES[name](spark, sf).collect())
