"""Token, cost, accuracy and agreement measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions.tokens import token_count


def with_tokens(df: DataFrame, original: str = "text", compressed: str = "short", model: str = "word") -> DataFrame:
    return df.withColumn("t0", token_count(F.col(original), model)).withColumn("t1", token_count(F.col(compressed), model))


def ratio_columns() -> list[Column]:
    """Counts, the ratio of sums, the reduction, and the mean of single ratios."""
    ratio = F.try_divide(F.sum("t0"), F.sum("t1"))
    return [
        F.count("*").alias("texts"), F.sum("t0").alias("tokens_before"), F.sum("t1").alias("tokens_after"), F.round(ratio, 6).alias("ratio"),
        F.round(1 - F.try_divide(F.sum("t1"), F.sum("t0")), 6).alias("reduction"), F.round(F.avg(F.try_divide(F.col("t0"), F.col("t1"))), 6).alias("mean_ratio"),
    ]


def compression_report(df: DataFrame, *by: str, cube: bool = False) -> DataFrame:
    """Over (t0, t1); ``cube`` gives all sub-totals, null for all."""
    return (df.cube(*by) if cube else df.groupBy(*by)).agg(*ratio_columns())


def cost_report(df: DataFrame, prices: dict[str, str]) -> DataFrame:
    """(price_class, cost_before, cost_after, saved): the caller gives prices per 1000 tokens as decimal text."""
    rows = df.sparkSession.createDataFrame(list(prices.items()), "price_class string, price string")
    t = df.agg(F.sum("t0").alias("a"), F.sum("t1").alias("b")).crossJoin(F.broadcast(rows.withColumn("price", F.col("price").cast("decimal(18,6)"))))
    cost = lambda c: F.round(F.col(c) * F.col("price").cast("double") / 1000, 4)
    return t.select("price_class", cost("a").alias("cost_before"), cost("b").alias("cost_after"), F.round(cost("a") - cost("b"), 4).alias("saved"))


def net_ratio(report: DataFrame, header_tokens: Column) -> DataFrame:
    """The ratio when the dictionary is sent along."""
    return report.withColumn("net_ratio", F.round(F.try_divide(F.col("tokens_before"), F.col("tokens_after") + header_tokens), 6))


def placeholder_density(df: DataFrame, mapping: dict[str, str], short: str = "short") -> DataFrame:
    """Adds placeholders per 100 tokens."""
    from ctxpress.functions.tokens import words

    n = F.size(F.filter(words(F.col(short)), lambda w: w.isin(list(mapping.values()))))
    return df.withColumn("placeholders", n.cast("long")).withColumn("density", F.round(F.coalesce(F.try_divide(100 * n, token_count(F.col(short))), F.lit(0.0)), 4))


def accuracy_report(results: DataFrame, base: str = "A") -> DataFrame:
    """(method, arm, questions, accuracy, delta) in points against method ``base``; results has method, arm, correct."""
    t = results.groupBy("method", "arm").agg(F.count("*").alias("questions"), F.round(100 * F.avg(F.col("correct").cast("double")), 4).alias("accuracy"))
    ref = t.where(F.col("method") == base).agg(F.max("accuracy").alias("base"))
    return t.crossJoin(F.broadcast(ref)).select("method", "arm", "questions", "accuracy", F.round(F.col("accuracy") - F.col("base"), 4).alias("delta"))


def pareto(settings: DataFrame, key: str, gain: str, quality: str) -> DataFrame:
    """Adds efficient: no other setting is at least as good in both measures and better in one. Settings are few rows."""
    a, b = settings.alias("a"), settings.alias("b")
    better = (F.col(f"b.{gain}") >= F.col(f"a.{gain}")) & (F.col(f"b.{quality}") >= F.col(f"a.{quality}")) & ((F.col(f"b.{gain}") > F.col(f"a.{gain}")) | (F.col(f"b.{quality}") > F.col(f"a.{quality}")))
    beaten = a.join(F.broadcast(b), better, "left_semi").select(key)
    return settings.join(F.broadcast(beaten.withColumn("_beaten", F.lit(True))), key, "left").withColumn("efficient", F.col("_beaten").isNull()).drop("_beaten")


def metric_disagreement(settings: DataFrame, key: str, cosine: str, accuracy: str) -> DataFrame:
    """Pairs of settings that the cosine and the task order differently."""
    a, b = settings.alias("a"), settings.alias("b")
    cond = (F.col(f"a.{cosine}") < F.col(f"b.{cosine}")) & (F.col(f"a.{accuracy}") > F.col(f"b.{accuracy}"))
    return a.join(F.broadcast(b), cond).select(F.col(f"a.{key}").alias("better_task"), F.col(f"b.{key}").alias("closer_text"))


def running_total(df: DataFrame, by: str, order: str, value: str) -> DataFrame:
    return df.withColumn("running", F.sum(value).over(Window.partitionBy(by).orderBy(order)))


class StageTimer:
    """Wall time of stages around explicit actions; for experiments, as plans are lazy."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str):
        start = time.perf_counter()
        try:
            yield self
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - start

    def run(self, name: str, df: DataFrame) -> DataFrame:
        with self.stage(name):
            df.write.format("noop").mode("overwrite").save()
        return df


class Judge:
    """Grades pairs of texts from 1 to 5: by any function over two lists of texts, or by recall of the original's words."""

    def __init__(self, fn: Callable[[list[str], list[str]], list[float]] | None = None):
        self.fn = fn

    def grade(self, original: Column, compressed: Column) -> Column:
        from ctxpress.operators.fidelity import lexical_recall

        if self.fn is None:
            return F.round(1 + 4 * lexical_recall(original, compressed), 4)
        fn = self.fn

        @F.pandas_udf("double")
        def run(a, b):
            import pandas as pd

            return pd.Series(fn(a.fillna("").tolist(), b.fillna("").tolist()), dtype="float64")

        return run(original, compressed)

