"""Scans of the given tables and of attachments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load_attachment(spark: SparkSession, path: str, fmt: str, schema: str | None = None) -> DataFrame:
    """Text files as one row each, CSV and JSON lines by a given schema, Parquet as it is."""
    if fmt == "text":
        return spark.read.text(path, wholetext=True).select(F.col("_metadata.file_path").alias("path"), F.col("value").alias("text"))
    reader = spark.read.schema(schema) if schema else spark.read
    return {"csv": lambda: reader.option("header", True).csv(path), "json": lambda: reader.json(path), "parquet": lambda: reader.parquet(path)}[fmt]()


def html_text(html: Column) -> Column:
    """Text of simple HTML: scripts, styles, comments and tags dropped, basic entities decoded, blanks squeezed."""
    t = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>|<!--.*?-->", " ")
    t = F.regexp_replace(t, r"<[^>]*>", " ")
    for name, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&")):
        t = F.replace(t, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(t, r"[ \t\r\n\f]+", " "))


def hash_sample(df: DataFrame, key: str, fraction: float) -> DataFrame:
    """The same rows at every run and partitioning; no shuffle."""
    return df.where(F.pmod(F.xxhash64(key), F.lit(1_000_000)) < int(fraction * 1_000_000))


def prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversation turns as prompts (prompt_id, conv_id, turn, role, text)."""
    c = load(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    return c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("prompt_id"), "conv_id", "turn", "role", "text")
