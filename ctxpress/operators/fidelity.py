"""How close compressed text stays to its original: encoders, cosines, gates and ratings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions.scalar import cosine
from ctxpress.functions.tokens import WORD, words


class HashedWords:
    """Counts of words hashed into ``dim`` places, damped by 1 + log2; deterministic, no model is needed."""

    def __init__(self, dim: int = 256):
        self.dim = dim

    def encode(self, text: Column) -> Column:
        dim = self.dim

        @F.pandas_udf("array<double>")
        def run(s):
            import zlib

            import numpy as np
            import regex

            find = regex.compile(WORD).findall

            def one(t):
                n = np.bincount([zlib.crc32(w.encode()) % dim for w in find((t or "").lower())], minlength=dim).astype(float)
                return np.where(n > 0, 1 + np.log2(np.maximum(n, 1)), 0.0)

            return s.map(one)

        return run(text)


class CharGrams:
    """Hashed character n-grams, through Arrow: nearer to spelling than to words."""

    def __init__(self, dim: int = 256, n: int = 3):
        self.dim, self.n = dim, n

    def encode(self, text: Column) -> Column:
        dim, n = self.dim, self.n

        @F.pandas_udf("array<double>")
        def run(s):
            import zlib

            import numpy as np

            def one(t):
                v = np.zeros(dim)
                t = (t or "").lower().encode()
                for i in range(len(t) - n + 1):
                    v[zlib.crc32(t[i : i + n]) % dim] += 1
                return v

            return s.map(one)

        return run(text)


class ExternalEncoder:
    """A sentence encoder outside Spark: ``fn`` maps a list of texts to vectors."""

    def __init__(self, fn):
        self.fn = fn

    def encode(self, text: Column) -> Column:
        fn = self.fn

        @F.pandas_udf("array<double>")
        def run(s):
            import pandas as pd

            return pd.Series([list(map(float, v)) for v in fn(s.fillna("").tolist())])

        return run(text)


def word_cosine(a: Column, b: Column) -> Column:
    """Cosine of the word counts of two texts by exact words; null if one has none. Linear in the texts, through Arrow."""

    @F.pandas_udf("double")
    def run(x, y):
        from collections import Counter

        import pandas as pd
        import regex

        find = regex.compile(WORD).findall

        def one(s, t):
            c, d = Counter(find((s or "").lower())), Counter(find((t or "").lower()))
            norm = (sum(v * v for v in c.values()) * sum(v * v for v in d.values())) ** 0.5
            return sum(v * d[w] for w, v in c.items() if w in d) / norm if norm else None

        return pd.Series([one(s, t) for s, t in zip(x, y)], dtype="float64")

    return run(a, b)


def pair_similarity(pairs: DataFrame, a: str = "text", b: str = "short", encoder=None) -> DataFrame:
    """Adds cosine of both texts under the encoder."""
    e = encoder or HashedWords()
    t = pairs.withColumn("_a", e.encode(F.col(a))).withColumn("_b", e.encode(F.col(b)))
    return t.withColumn("cosine", cosine(F.col("_a"), F.col("_b"))).drop("_a", "_b")


def fidelity_report(pairs: DataFrame, *by: str) -> DataFrame:
    """Mean and 5th percentile of the cosines."""
    return pairs.groupBy(*by).agg(F.count("cosine").alias("pairs"), F.round(F.avg("cosine"), 6).alias("mean_cosine"), F.round(F.percentile("cosine", F.lit(0.05)), 6).alias("p5_cosine"))


def fidelity_gate(pairs: DataFrame, least: float = 0.92, *by: str) -> DataFrame:
    """Share of pairs that count as safe."""
    return pairs.groupBy(*by).agg(F.count("cosine").alias("pairs"), F.count_if(F.col("cosine") >= least).alias("safe"), F.round(F.count_if(F.col("cosine") >= least) / F.count("cosine"), 6).alias("safe_share"))


def ranks(df: DataFrame, col: str, out: str) -> DataFrame:
    """Mean ranks, ties shared; a frame over one column of a small table of ratings."""
    w = Window.orderBy(col)
    same = Window.partitionBy(col)
    return df.withColumn("_r", F.row_number().over(w)).withColumn(out, F.avg("_r").over(same)).drop("_r")


def rating_report(pairs: DataFrame, hi: float = 0.92, lo: float = 3.0) -> DataFrame:
    """Mean rating, its correlation with the cosine by value and by rank, and the share of close vectors with low ratings."""
    t = ranks(ranks(pairs, "cosine", "rc"), "rating", "rr")
    return t.agg(
        F.count("*").alias("pairs"), F.round(F.avg("rating"), 4).alias("mean_rating"), F.round(F.corr("cosine", "rating"), 4).alias("pearson"), F.round(F.corr("rc", "rr"), 4).alias("spearman"),
        F.round(F.count_if((F.col("cosine") >= hi) & (F.col("rating") < lo)) / F.count("*"), 4).alias("high_cosine_low_rating"),
    )


def rater_alignment(ratings: DataFrame) -> DataFrame:
    """(rater_a, rater_b, shared, exact, mean_gap) over the pairs that both rated."""
    a, b = ratings.alias("a"), ratings.alias("b")
    t = a.join(b, (F.col("a.pair_id") == F.col("b.pair_id")) & (F.col("a.rater") < F.col("b.rater")))
    gap = F.abs(F.col("a.score") - F.col("b.score"))
    return t.groupBy(F.col("a.rater").alias("rater_a"), F.col("b.rater").alias("rater_b")).agg(F.count("*").alias("shared"), F.round(F.count_if(gap == 0) / F.count("*"), 4).alias("exact"), F.round(F.avg(gap), 4).alias("mean_gap"))


def simulated_ratings(pairs: DataFrame, recall: Column, biases: tuple[float, ...] = (-0.4, 0.0, 0.4)) -> DataFrame:
    """(pair_id, rater, score): three made-up raters who grade lexical recall, one strictly, one mildly. No human was asked."""
    rows = [F.struct(F.lit(i + 1).alias("rater"), F.greatest(F.lit(1), F.least(F.lit(5), F.round(1 + 4 * recall + b))).cast("int").alias("score")) for i, b in enumerate(biases)]
    return pairs.select("pair_id", F.explode(F.array(*rows)).alias("r")).select("pair_id", "r.rater", "r.score")


def lexical_recall(original: Column, compressed: Column) -> Column:
    """Share of the original's distinct words that the compressed text still has."""
    a = F.array_distinct(words(original, True))
    return F.coalesce(F.try_divide(F.size(F.array_intersect(a, words(compressed, True))), F.size(a)), F.lit(1.0))
