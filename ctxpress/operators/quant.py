"""Numeric columns as small integer codes: uniform grids with an error bound, and one-dimensional k-means."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from ctxpress.functions.scalar import dequantize, quantize


@dataclass(frozen=True)
class Grid:
    """What reconstruction needs of a column."""

    column: str
    lo: float
    hi: float
    bits: int

    @property
    def step(self) -> float:
        return (self.hi - self.lo) / (2**self.bits - 1)

    def bound(self, kind: str = "tight") -> float:
        """Greatest error: a step as published, half a step as rounding guarantees."""
        return self.step if kind == "paper" else self.step / 2


def numeric_columns(df: DataFrame) -> list[str]:
    return [f.name for f in df.schema if isinstance(f.dataType, NumericType)]


def finite(c: Column) -> Column:
    c = c.cast("double")
    return F.when(~F.isnan(c) & (F.abs(c) < F.lit(float("inf"))), c)


def exact_quantiles(df: DataFrame, col: str, shares: Sequence[float], buckets: int = 1 << 16) -> list[float]:
    """What ``percentile`` gives, linear between ranks, without all distinct values in one task; [] without a finite value.

    Each scan counts the values in equal parts of the interval that holds a rank and goes on with the part it falls into, from
    its least to its greatest value, until that is one value. A scan returns at most about ``buckets`` counts whatever the
    rows; values need about three scans, spreads of hundreds of decimal places one for every few of them.
    """
    t = df.select(finite(F.col(col)).alias("x")).where("x is not null")
    n, lo, hi = t.agg(F.count("x"), F.min("x"), F.max("x")).first()
    if not n:
        return []
    at = [share * (n - 1) for share in shares]
    open_ = {(lo, hi): (0, sorted({f(p) for p in at for f in (math.floor, math.ceil)}))}  # interval: rows below it, ranks in it
    value: dict[int, float] = {}
    while True:
        for one in [s for s in open_ if s[0] == s[1]]:
            value |= dict.fromkeys(open_.pop(one)[1], one[0])
        if not open_:
            break
        spans, parts = sorted(open_), max(16, buckets // len(open_))
        table = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(a).alias("a"), F.lit(b).alias("b")) for i, (a, b) in enumerate(spans)])
        s = t.select("x", F.get(F.filter(table, lambda v: (v["a"] <= F.col("x")) & (F.col("x") <= v["b"])), F.lit(0)).alias("s")).where("s is not null")
        share = (F.col("x") / 2 - F.col("s.a") / 2) / (F.col("s.b") / 2 - F.col("s.a") / 2)  # halves: a difference of extremes is no double
        part = F.least(F.floor(share * parts), F.lit(parts - 1))
        got = s.groupBy(F.col("s.i").alias("i"), part.alias("part")).agg(F.count("*").alias("n"), F.min("x").alias("a"), F.max("x").alias("b")).collect()
        new = {}
        for i, span in enumerate(spans):
            below, ranks = open_[span]
            for r in sorted((r for r in got if r["i"] == i), key=lambda r: r["part"]):
                mine = [k for k in ranks if below <= k < below + r["n"]]
                if mine:
                    new[r["a"], r["b"]] = (below, mine)
                below += r["n"]
        open_ = new
    out = []
    for p in at:
        a, b = math.floor(p), math.ceil(p)
        out.append(float(value[a] if value[a] == value[b] else (b - p) * value[a] + (p - a) * value[b]))
    return out


def uniform_fit(df: DataFrame, cols: Sequence[str], bits: int, clip: float | None = None) -> list[Grid]:
    """Ranges of all columns in one scan; ``clip`` takes exact percentiles at both ends in place of the extremes."""
    if clip:
        return [Grid(c, *(exact_quantiles(df, c, (clip, 1 - clip)) or (0.0, 0.0)), bits) for c in cols]
    aggs = [f(finite(F.col(c))) for c in cols for f in (F.min, F.max)]
    row = df.agg(*[a.alias(f"a{i}") for i, a in enumerate(aggs)]).first()
    return [Grid(c, float(row[2 * i] or 0.0), float(row[2 * i + 1] or 0.0), bits) for i, c in enumerate(cols)]


def uniform_encode(df: DataFrame, grids: Sequence[Grid], suffix: str = "_q") -> DataFrame:
    return df.select("*", *[quantize(F.col(g.column), g.lo, g.hi, g.bits).alias(g.column + suffix) for g in grids])


def uniform_decode(df: DataFrame, grids: Sequence[Grid], suffix: str = "_q", out: str = "_hat") -> DataFrame:
    return df.select("*", *[dequantize(F.col(g.column + suffix), g.lo, g.hi, g.bits).alias(g.column + out) for g in grids])


def bits_for_tolerance(lo: float, hi: float, tolerance: float, bound: str = "tight") -> int:
    """Smallest code width whose bound is within the tolerance."""
    span = (hi - lo) / (tolerance if bound == "paper" else 2 * tolerance)
    return max(1, math.ceil(math.log2(span + 1) - 1e-12)) if span > 0 else 1


def quantize_grouped(df: DataFrame, col: str, by: str, bits: int) -> DataFrame:
    """A grid for each group; the ranges are one row per group, joined back."""
    ranges = df.groupBy(by).agg(F.min(finite(F.col(col))).alias("lo"), F.max(finite(F.col(col))).alias("hi"))
    t = df.join(ranges, by)
    t = t.withColumn("q", quantize(F.col(col), F.col("lo"), F.col("hi"), bits))
    return t.withColumn("hat", dequantize(F.col("q"), F.col("lo"), F.col("hi"), bits))


def quant_error(df: DataFrame, grids: Sequence[Grid]) -> DataFrame:
    """(column, bits, max_abs, mean_abs, mse, tight_bound, paper_bound, within) of all grids in one pass."""
    aggs, rows = [], []
    for i, g in enumerate(grids):
        x = finite(F.col(g.column))
        e = F.abs(x - dequantize(quantize(x, g.lo, g.hi, g.bits), g.lo, g.hi, g.bits))
        aggs += [F.max(e).alias(f"m{i}"), F.avg(e).alias(f"a{i}"), F.avg(e * e).alias(f"s{i}")]
        within = F.col(f"m{i}") <= F.lit(g.bound() * (1 + 1e-9) + 1e-9)
        rows.append(F.struct(
            F.lit(g.column).alias("column"), F.lit(g.bits).alias("bits"), F.round(f"m{i}", 6).alias("max_abs"), F.round(f"a{i}", 6).alias("mean_abs"), F.round(f"s{i}", 4).alias("mse"),
            F.round(F.lit(g.bound()), 6).alias("tight_bound"), F.round(F.lit(g.bound("paper")), 6).alias("paper_bound"), within.alias("within"),
        ))
    return df.agg(*aggs).select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def code_predicate(g: Grid, op: str, value: float, suffix: str = "_q") -> Column:
    """A superset predicate on codes for ``column op value``; verify on decoded or stored values where it matters."""
    q, top = F.col(g.column + suffix), 2**g.bits - 1
    at = (value - g.lo) / (g.hi - g.lo) * top if g.hi > g.lo else 0.0
    if op in (">", ">="):
        return q >= max(0, math.floor(at + 0.5 - 1e-9)) if at <= top else F.lit(False) if at > top + 0.5 else q >= top
    if op in ("<", "<="):
        return q <= min(top, math.floor(at + 0.5 + 1e-9)) if at >= 0 else F.lit(False) if at < -0.5 else q <= 0
    if op == "=":
        return q == int(min(top, max(0, math.floor(at + 0.5))))
    raise ValueError(op)


def code_sum(df: DataFrame, g: Grid, *by: str, suffix: str = "_q") -> DataFrame:
    """Sums and means of decoded values from sums of codes; one multiplication for each group."""
    t = df.groupBy(*by).agg(F.count(g.column + suffix).alias("n"), F.sum(F.col(g.column + suffix).cast("long")).alias("q"))
    total = F.col("n") * F.lit(g.lo) + F.lit(g.step) * F.col("q")
    return t.select(*by, "n", total.alias("total"), (total / F.col("n")).alias("mean"))


# one-dimensional k-means


def weighted_values(df: DataFrame, col: str) -> DataFrame:
    """Distinct values with their counts: each round of k-means then costs the distinct values only."""
    x = finite(F.col(col))
    return df.select(x.alias("x")).where("x is not null").groupBy("x").agg(F.count("*").alias("n"))


def quantile_seeds(df: DataFrame, col: str, k: int) -> list[float]:
    return sorted(set(exact_quantiles(df, col, [(i + 0.5) / k for i in range(k)])))


def nearest(x: Column, centroids: Sequence[float]) -> Column:
    """Index of the nearest of sorted centroids, the lower on a tie, by the midpoints below x."""
    mids = [(a + b) / 2 for a, b in zip(centroids, centroids[1:])]
    if not mids:
        return F.when(x.isNotNull(), F.lit(0))
    if len(mids) <= 64:
        return F.when(x.isNotNull(), sum(((x > m).cast("int") for m in mids[1:]), (x > mids[0]).cast("int")))
    return F.when(x.isNotNull(), F.size(F.filter(F.array(*[F.lit(m) for m in mids]), lambda m: m < x)))


def lloyd(values: DataFrame, seeds: Sequence[float], rounds: int = 10) -> list[float]:
    """Fixed rounds of assignment and weighted means over (x, n); an empty cluster keeps its centroid."""
    c = sorted(seeds)
    for _ in range(rounds):
        means = {r["k"]: r["m"] for r in values.groupBy(nearest(F.col("x"), c).alias("k")).agg((F.sum(F.col("x") * F.col("n")) / F.sum("n")).alias("m")).collect()}
        new = sorted(means.get(i, v) for i, v in enumerate(c))
        if new == c:
            break
        c = new
    return c


def kmeans_fit(df: DataFrame, col: str, k: int, init: str = "quantile", rounds: int = 10, seed: int = 1) -> list[float]:
    values = weighted_values(df, col)
    if init == "quantile":
        return lloyd(values, quantile_seeds(df, col, k), rounds)
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    v = VectorAssembler(inputCols=["x"], outputCol="features").transform(values.withColumn("w", F.col("n").cast("double")))
    return sorted(float(m[0]) for m in KMeans(k=k, seed=seed, weightCol="w", maxIter=rounds).fit(v).clusterCenters())


def kmeans_encode(df: DataFrame, col: str, centroids: Sequence[float], out: str) -> DataFrame:
    return df.withColumn(out, nearest(finite(F.col(col)), centroids))


def kmeans_decode(df: DataFrame, code: str, centroids: Sequence[float], out: str) -> DataFrame:
    return df.withColumn(out, F.element_at(F.array(*[F.lit(float(c)) for c in centroids]), F.col(code) + 1))


def kmeans_mse(values: DataFrame, centroids: Sequence[float]) -> Column:
    hat = F.element_at(F.array(*[F.lit(float(c)) for c in centroids]), nearest(F.col("x"), centroids) + 1)
    return F.sum(F.col("n") * F.pow(F.col("x") - hat, 2)) / F.sum("n")


def optimal_bins(df: DataFrame, by: str, col: str, k: int) -> DataFrame:
    """(by, centroids, mse, equal_width_mse): the exact best ``k`` bins of each group; a group comes together as its distinct values with counts."""
    import pandas as pd

    def best(f: pd.DataFrame) -> pd.DataFrame:
        x, n = f["x"].to_numpy(float), f["n"].to_numpy(float)
        mse, cents = kmeans_1d_exact(x, n, k)
        wide = x.min() + (np.minimum(k - 1, np.floor((x - x.min()) / max(np.ptp(x), 1e-300) * k)) + 0.5) * np.ptp(x) / k
        return pd.DataFrame([(f[by].iloc[0], cents, mse, float((n * (x - wide) ** 2).sum() / n.sum()))], columns=[by, "centroids", "mse", "equal_width_mse"])

    values = df.select(by, finite(F.col(col)).alias("x")).where("x is not null").groupBy(by, "x").agg(F.count("*").alias("n"))
    return values.groupBy(by).applyInPandas(best, f"{by} {df.schema[by].dataType.simpleString()}, centroids array<double>, mse double, equal_width_mse double")


def kmeans_1d_exact(x: np.ndarray, n: np.ndarray, k: int) -> tuple[float, list[float]]:
    """Least mean square error by dynamic programming over sorted distinct values; for some thousand values."""
    order = np.argsort(x)
    x, n = x[order].astype(float), n[order].astype(float)
    m = len(x)
    k = min(k, m)
    w, s, t = (np.r_[0, np.cumsum(v)] for v in (n, n * x, n * x * x))

    def cost(i, j):  # of one cluster for values i..j-1, for arrays of i
        ww = w[j] - w[i]
        return (t[j] - t[i]) - (s[j] - s[i]) ** 2 / ww

    best = np.r_[np.inf, [cost(0, j) for j in range(1, m + 1)]]
    back = [np.zeros(m + 1, int)]
    for c in range(2, k + 1):
        new, arg = np.full(m + 1, np.inf), np.zeros(m + 1, int)
        for j in range(c, m + 1):
            i = np.arange(c - 1, j)
            v = best[i] + cost(i, j)
            a = int(v.argmin())
            new[j], arg[j] = v[a], i[a]
        best = new
        back.append(arg)
    cuts, j = [m], m
    for arg in reversed(back[1:]):
        j = int(arg[j])
        cuts.append(j)
    cuts = [0, *reversed(cuts)] if cuts[-1] != 0 else list(reversed(cuts))
    return max(0.0, float(best[m] / w[-1])), [float((s[b] - s[a]) / (w[b] - w[a])) for a, b in zip(cuts, cuts[1:])]


def column_profile(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    """(column, lo, hi, distinct_values, mean_chars) of all columns in one scan."""
    rows = [F.struct(F.lit(c).alias("column"), finite(F.col(c)).alias("x")) for c in cols]
    t = df.select(F.explode(F.array(*rows)).alias("r")).groupBy("r.column")
    return t.agg(F.min("r.x").alias("lo"), F.max("r.x").alias("hi"), F.countDistinct("r.x").alias("distinct_values"), F.round(F.avg(F.length(F.format_string("%.2f", F.col("r.x")))), 4).alias("mean_chars"))


def plan_columns(df: DataFrame, cols: Sequence[str], tolerance: float, min_saving: float = 0.1, max_k: int = 64) -> DataFrame:
    """The scheme for each column: k-means if so few values that it is exact, a grid within the tolerance, or none if codes save too little."""
    p = column_profile(df, cols)
    bits = F.greatest(F.lit(1), F.ceil(F.log2((F.col("hi") - F.col("lo")) / F.lit(2 * tolerance) + 1) - F.lit(1e-12))).cast("int")
    p = p.withColumn("bits", bits)
    digits = F.length(F.pow(F.lit(2), "bits").cast("long").cast("string"))
    exact = F.col("distinct_values") <= max_k
    cost = F.when(exact, F.length(F.col("distinct_values").cast("string"))).otherwise(digits)
    saving = F.round(1 - cost / F.col("mean_chars"), 4)
    scheme = F.when(saving < min_saving, "none").when(exact, "kmeans").otherwise("uniform")
    return p.select("column", "distinct_values", "bits", saving.alias("saving"), scheme.alias("scheme"))
