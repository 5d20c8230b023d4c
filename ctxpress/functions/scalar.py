"""Closed-form expressions of the methods: information, merged score, codes, similarity."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def self_information(p: Column) -> Column:
    return F.when(p > 0, -F.log2(p))


def relative_gap(s_stat: Column, s_dyn: Column) -> Column:
    return F.try_divide(F.abs(s_dyn - s_stat), s_stat)


def merge_rule(s_stat: Column, s_dyn: Column, band: float = 0.10) -> Column:
    return (
        F.when(s_dyn.isNull(), F.when(s_stat.isNotNull(), "static_only"))
        .when(s_stat.isNull() | (s_stat == 0), "dynamic_only")
        .when(relative_gap(s_stat, s_dyn) <= band, "mean")
        .otherwise("dynamic")
    )


def combine_scores(s_stat: Column, s_dyn: Column, band: float = 0.10, weight: float = 0.5) -> Column:
    """The weighted mean where both agree within ``band``, else the dynamic score; what is missing leaves the other."""
    rule = merge_rule(s_stat, s_dyn, band)
    return F.when(rule == "static_only", s_stat).when(rule == "mean", F.lit(weight) * s_stat + F.lit(1 - weight) * s_dyn).otherwise(s_dyn)


def round_binary(x: Column, digits: int) -> Column:
    """Rounds the binary product with the power of ten, half away from zero; F.round decides by the shortest decimal form instead."""
    y = F.abs(x) * F.lit(10.0**digits)
    whole = F.floor(y).cast("double")
    return F.signum(x) * (whole + (y - whole >= 0.5).cast("double")) / F.lit(10.0**digits)


def quantize(x: Column, lo, hi, bits: int) -> Column:
    """Code 0..2**bits-1; a constant column is 0, values outside are clamped, null and non-finite values have none."""
    lo, hi = (v if isinstance(v, Column) else F.lit(float(v)) for v in (lo, hi))
    top = F.lit(float(2**bits - 1))
    x = x.cast("double")
    q = F.when(hi == lo, F.lit(0)).otherwise(F.round(F.try_divide(x - lo, hi - lo) * top).cast("int"))
    fit = x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    return F.when(fit, F.greatest(F.lit(0), F.least(q, F.lit(2**bits - 1))))


def dequantize(q: Column, lo, hi, bits: int) -> Column:
    lo, hi = (v if isinstance(v, Column) else F.lit(float(v)) for v in (lo, hi))
    return lo + q / F.lit(float(2**bits - 1)) * (hi - lo)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def cosine(a: Column, b: Column) -> Column:
    """Null when either vector is zero."""
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, v: s + v)


#: SQL bodies of the same expressions; the analyzer inlines them.
MACROS = {
    "self_info(n BIGINT, total BIGINT) RETURNS DOUBLE": "CASE WHEN n > 0 THEN -log2(n / total) END",
    "combine_score(s DOUBLE, d DOUBLE) RETURNS DOUBLE": "CASE WHEN d IS NULL THEN s WHEN s IS NULL OR s = 0 THEN d WHEN abs(d - s) / s <= 0.1 THEN (s + d) / 2 ELSE d END",
    "quantize(x DOUBLE, lo DOUBLE, hi DOUBLE, b INT) RETURNS INT": "CASE WHEN hi = lo THEN 0 ELSE CAST(round((x - lo) / (hi - lo) * (power(2, b) - 1)) AS INT) END",
    "dequantize(q INT, lo DOUBLE, hi DOUBLE, b INT) RETURNS DOUBLE": "lo + q / (power(2, b) - 1) * (hi - lo)",
    "cosine_of(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v) / (sqrt(aggregate(a, 0D, (s, v) -> s + v * v)) * sqrt(aggregate(b, 0D, (s, v) -> s + v * v)))",
}


def register_macros(spark: SparkSession) -> None:
    for head, body in MACROS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
