"""Mixing sources to target weights along a training run, in DataFrame operations only.

Every source has a weight schedule over training time 0..1. Its integral, scaled to the source's target, is the number of
words that the run has asked of the source by then. Documents of a source are laid end to end in a fixed shuffled order
(again and again, up to ``max_epochs`` times); the word offset at which a document starts is turned into the time at which
the schedule asks for it, and documents are range-sorted by that time.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.llm.common import NON_SPACE, cut_lineage

#: Weight at equally spaced times for each class of source, by place in the cycle: falling, level, rising.
SCHEDULES = ((1.5, 1.0, 0.5), (1.0, 1.0, 1.0), (0.5, 1.0, 1.5))


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(NON_SPACE)), F.lit(0)).cast("long")


def integral(knots: Sequence[float]) -> list[float]:
    """Share of the whole demand that is asked for up to each knot (trapezoids)."""
    area = [(a + b) / 2 for a, b in zip(knots, knots[1:])]
    total, run, out = sum(area), 0.0, [0.0]
    for a in area:
        run += a
        out.append(run / total)
    return out


def time_of(share: Column, knots: Sequence[float]) -> Column:
    """The time at which the integrated schedule reaches ``share``: in its segment, the root of a quadratic."""
    cum, n = integral(knots), len(knots) - 1
    total, out = sum((a + b) / 2 for a, b in zip(knots, knots[1:])), None
    for i in range(n - 1, -1, -1):
        rest = (share - F.lit(cum[i])) * F.lit(total)
        slope = knots[i + 1] - knots[i]
        within = F.coalesce(F.try_divide(F.lit(2.0) * rest, F.lit(float(knots[i])) + F.sqrt(F.lit(float(knots[i] * knots[i])) + F.lit(2.0 * slope) * rest)), F.lit(0.0))
        t = (F.lit(float(i)) + within) / F.lit(float(n))
        out = t if out is None else F.when(share < F.lit(cum[i + 1]), t).otherwise(out)
    return out


def source_targets(sizes: DataFrame, weights: Sequence[int], total_share: float, cap: float) -> DataFrame:
    """(src, source_size, cls, target): targets by weight; what exceeds ``cap`` x size is reshared by weight.

    The level at which sources fill is found from the sources in order of cap per weight: those below it are full.
    The table has one row per source.
    """
    n = len(weights)
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), F.col("cls") + 1)
    s = sizes.withColumn("cls", ((F.row_number().over(by_name) - 1) % n).cast("int")).withColumn("weight", weight)
    s = s.withColumn("ratio", F.col("source_size") * F.lit(float(cap)) / F.col("weight"))
    fill = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    s = s.withColumn("full", F.coalesce(F.sum("source_size").over(fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    s = s.withColumn("open", F.sum("weight").over(fill.rowsBetween(0, Window.unboundedFollowing)))
    everything = Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    s = s.withColumn("all", F.sum("source_size").over(everything))
    s = s.withColumn("level", (F.lit(float(total_share)) * F.col("all") - F.lit(float(cap)) * F.col("full")) / F.col("open"))
    s = s.withColumn("level", F.max(F.when(F.col("level") <= F.col("ratio"), F.col("level"))).over(everything))
    target = F.least(F.coalesce(F.col("level"), F.col("ratio")) * F.col("weight"), F.lit(float(cap)) * F.col("source_size"))
    return s.select("src", "source_size", "cls", target.alias("target"))


def mix_to_targets(
    docs: DataFrame,
    weights: Sequence[int] = (3, 1, 2),
    total_share: float = 1.5,
    max_epochs: int = 2,
    schedules: Sequence[Sequence[float]] = SCHEDULES,
    prefix: int = 3,
    sort: bool = True,
) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken, position, in order of position.

    ``docs`` has doc_id, source and text; other columns are ignored. ``size`` is the number of words (null text: 0).
    ``taken`` counts the words that the mix takes of the document, repeats included; in a source they add up to its target,
    rounded to a word. ``position`` is the time of the first taking in billionths of the run, null when nothing is taken.
    A null source is a source of its own, the last. Equal doc_ids are laid in order of size. Empty tables give no rows.
    Running offsets come in two levels, sums of ``16**prefix`` ranges of the shuffled order for each source and then rows
    of one range, so that no task holds a whole source.
    """
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    base = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), key.alias("key"))
    base = base.withColumn("src", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n"))).withColumn("part", F.substring("key", 1, prefix))
    base = cut_lineage(base)  # texts are read once, and leave only their sizes
    parts = base.groupBy("src", "part").agg(F.first("source").alias("source"), F.sum("size").alias("words"))
    targets = source_targets(parts.groupBy("src").agg(F.first("source").alias("source"), F.sum("words").alias("source_size")), weights, total_share, max_epochs)
    before = Window.partitionBy("src").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = parts.select("src", "part", F.coalesce(F.sum("words").over(before), F.lit(0)).alias("start")).join(targets, "src")
    inside = Window.partitionBy("src", "part").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    laid = base.join(starts, ["src", "part"]).withColumn("off", F.col("start") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    laid = laid.withColumn("goal", F.round("target").cast("long"))
    taken = F.lit(0).cast("long")
    for e in range(max_epochs):
        at = F.col("off") + F.col("source_size") * F.lit(e)
        taken = taken + F.greatest(F.lit(0), F.least("goal", at + F.col("size")) - F.least("goal", at))
    laid = laid.withColumn("taken", taken)
    share, t = F.try_divide(F.col("off").cast("double"), F.col("goal").cast("double")), None
    for c, knots in enumerate(schedules):
        here = time_of(share, knots)
        t = here if t is None else F.when(F.col("cls") == c, here).otherwise(t)
    position = F.when(F.col("taken") > 0, F.floor(t * F.lit(1e9)).cast("long"))
    out = laid.select("doc_id", "source", "size", "source_size", "target", "taken", position.alias("position"))
    return out.orderBy(F.col("position").asc_nulls_last(), F.md5(F.col("doc_id").cast("string").cast("binary"))) if sort else out


def op8_mix_sources(spark, sf_dir: str) -> DataFrame:
    """All rows of ``documents`` with the words that the mix takes; null texts have size 0, a null source is the last one, ties of position go by doc_id, no rows give none."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix_to_targets(docs).drop("source")


def mixing_sql(docs: str = "documents") -> str:
    """The same mix for DuckDB, for the default weights and schedules."""
    pieces = []
    for c, knots in enumerate(SCHEDULES):
        cum, total, n = integral(knots), sum((a + b) / 2 for a, b in zip(knots, knots[1:])), len(knots) - 1
        arms = ""
        for i in range(n):
            rest = f"((share - {cum[i]!r}::DOUBLE) * {total!r}::DOUBLE)"
            a, b = float(knots[i]), float(knots[i + 1])
            arm = f"({float(i)!r}::DOUBLE + 2.0::DOUBLE * {rest} / ({a!r}::DOUBLE + sqrt({a * a!r}::DOUBLE + {2.0 * (b - a)!r}::DOUBLE * {rest}))) / {float(n)!r}::DOUBLE"
            arms += f" WHEN share < {cum[i + 1]!r}::DOUBLE THEN {arm}" if i < n - 1 else f" ELSE {arm}"
        pieces.append(f"WHEN cls = {c} THEN CASE{arms} END" if n > 1 else f"WHEN cls = {c} THEN {arms.removeprefix(' ELSE ')}")
    return f"""
WITH sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::BIGINT AS size,
         md5(coalesce(doc_id::VARCHAR, '')) AS k FROM {docs}),
totals AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS cls FROM totals),
weighed AS (SELECT *, CASE cls WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS w FROM ranked),
levels AS (
  SELECT a.source, a.source_size * 2.0::DOUBLE / a.w AS ratio,
    (1.5::DOUBLE * (SELECT sum(source_size)::BIGINT FROM weighed)
      - 2.0::DOUBLE * coalesce(sum(b.source_size) FILTER (WHERE b.source_size * 2.0::DOUBLE / b.w < a.source_size * 2.0::DOUBLE / a.w), 0)::BIGINT)
      / sum(b.w) FILTER (WHERE b.source_size * 2.0::DOUBLE / b.w >= a.source_size * 2.0::DOUBLE / a.w)::BIGINT AS level
  FROM weighed a, weighed b GROUP BY a.source, a.source_size, a.w),
chosen AS (SELECT max(level) AS level FROM levels WHERE level <= ratio),
targets AS (SELECT source, source_size, cls, least(level * w, 2.0::DOUBLE * source_size) AS target FROM weighed, chosen),
laid AS (
  SELECT doc_id, size, source_size, target, cls, round(target)::BIGINT AS goal,
    coalesce(sum(size) OVER (PARTITION BY s.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
cut AS (
  SELECT *, least(goal, off + size) - least(goal, off) + least(goal, off + source_size + size) - least(goal, off + source_size) AS taken,
    CASE WHEN goal > 0 THEN off::DOUBLE / goal END AS share FROM laid)
SELECT doc_id, size, source_size, target, taken::BIGINT AS taken,
  CASE WHEN taken > 0 THEN floor((CASE {' '.join(pieces)} END) * 1e9::DOUBLE)::BIGINT END AS position
FROM cut"""
