"""Table functions for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register_udtfs(spark: SparkSession) -> None:
    @udtf(returnType="gram string, pos int")
    class NgramTable:
        def eval(self, text: str, n: int):
            import regex

            w = regex.findall(r"[\p{L}\p{M}\p{N}_]+", text or "")
            for i in range(len(w) - n + 1):
                yield " ".join(w[i : i + n]), i

    @udtf(returnType="pos int, tok string, gap string")
    class TokenTable:
        def eval(self, text: str):
            import regex

            at = 0
            for i, m in enumerate(regex.finditer(r"[\p{L}\p{M}\p{N}_]+|[^\s\p{L}\p{M}\p{N}_]", text or "")):
                yield i, m[0], text[at : m.start()]
                at = m.end()

    spark.udtf.register("ngram_table", NgramTable)
    spark.udtf.register("token_table", TokenTable)
