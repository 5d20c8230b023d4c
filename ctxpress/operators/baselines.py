"""Baselines: truncation, random drop, extraction, dictionary and byte coders, and a fixed-size vector."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ctxpress.functions.tokens import words


def truncate(text: Column, share: float) -> Column:
    """The first ``share`` of the words."""
    w = words(text)
    return F.array_join(F.slice(w, F.lit(1), F.ceil(F.lit(share) * F.size(w)).cast("int")), " ")


def random_drop(tokens: DataFrame, share: float, seed: int = 7) -> DataFrame:
    """Adds kept: as many tokens as the ratio budget keeps, in an order mixed by place and seed."""
    own = Window.partitionBy("prompt_id")
    mixed = ((F.col("prompt_id") * 1000003 + F.col("pos")) % F.lit(2147483647) * F.lit(48271) + F.lit(seed)) % F.lit(2147483647)
    rank = F.row_number().over(own.orderBy(mixed, "pos"))
    return tokens.withColumn("kept", rank <= F.ceil(F.lit(share) * F.count("*").over(own)))


def extractive(prompts: DataFrame, scores: DataFrame, share: float) -> DataFrame:
    """Whole sentences of the highest mean information within the share of tokens: a stand-in for rewriting by a model."""
    from ctxpress.operators.prune import Budget, prune_phrases

    return prune_phrases(scores, Budget.ratio(share))


@F.pandas_udf(LongType())
def lzw_codes(s: pd.Series) -> pd.Series:
    """Codes that a dictionary coder of the classic growing-table kind emits for the UTF-8 bytes."""

    def one(t):
        if not t:
            return 0
        table, w, n = {bytes([i]): i for i in range(256)}, b"", 0
        for b in t.encode():
            x = w + bytes([b])
            if x in table:
                w = x
            else:
                n += 1
                table[x] = len(table)
                w = bytes([b])
        return n + 1

    return s.map(one)


def compressed_size(codec: str):
    """Bytes of the text under gzip, zip's deflate or bzip2."""

    @F.pandas_udf("long")
    def run(s: pd.Series) -> pd.Series:
        import bz2
        import gzip
        import zlib

        f = {"gzip": lambda b: gzip.compress(b, mtime=0), "deflate": zlib.compress, "bzip2": bz2.compress}[codec]
        return s.map(lambda t: len(f((t or "").encode())))

    return run


def base64_tokens(n_bytes: Column) -> Column:
    """Estimated tokens when the bytes are put into a prompt as base64: four marks for three bytes, four marks a token."""
    return F.ceil(F.ceil(n_bytes / 3) * 4 / 4).cast("long")


def soft_vector_tokens(dim: int = 64, digits: int = 6) -> int:
    """Tokens of a fixed-size vector written out as text. Learned soft prompts need training; only their size is modelled."""
    return dim * (1 + -(-digits // 3))
