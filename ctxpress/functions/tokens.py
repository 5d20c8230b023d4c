"""Tokens and token costs as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{M}\p{N}_]+"
LEXICAL = WORD + r"|[^\s\p{L}\p{M}\p{N}_]"


def words(text: Column, casefold: bool = False) -> Column:
    return F.regexp_extract_all(F.lower(text) if casefold else text, F.lit(WORD), F.lit(0))


def lexical(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(LEXICAL), F.lit(0))


def gaps(text: Column) -> Column:
    """What stands before, between and after the lexical tokens; one more than there are tokens."""
    return F.split(text, LEXICAL, -1)


def tokenize(text: Column) -> Column:
    """array<struct<pos, tok, gap>>; gap stands before the token, and a last element without token holds the tail."""
    placed = F.transform(gaps(text), lambda g, i: F.struct(i.alias("pos"), g.alias("gap")))
    return F.zip_with(placed, lexical(text), lambda p, t: F.struct(p["pos"].alias("pos"), t.alias("tok"), p["gap"].alias("gap")))


def untokenize(tokens: Column) -> Column:
    return F.array_join(F.transform(tokens, lambda t: F.concat(t["gap"], F.coalesce(t["tok"], F.lit("")))), "")


def estimated_tokens(text: Column) -> Column:
    """Subword-like cost: a letter run costs a quarter of its length, a digit run a third, other marks one each, rounded up."""
    letters = F.regexp_extract_all(text, F.lit(r"[\p{L}\p{M}]+"), F.lit(0))
    digits = F.regexp_extract_all(text, F.lit(r"\p{N}+"), F.lit(0))
    marks = F.regexp_count(text, F.lit(r"[^\s\p{L}\p{M}\p{N}]"))
    cost = lambda runs, n: F.aggregate(runs, F.lit(0), lambda a, r: a + F.ceil(F.length(r) / F.lit(float(n))).cast("int"))
    return (cost(letters, 4) + cost(digits, 3) + marks).cast("long")


def token_count(text: Column, model: str = "word") -> Column:
    if model == "word":
        return F.regexp_count(text, F.lit(WORD)).cast("long")
    if model == "lexical":
        return F.regexp_count(text, F.lit(LEXICAL)).cast("long")
    if model == "estimated":
        return estimated_tokens(text)
    raise ValueError(model)


def ngrams(tokens: Column, n: int) -> Column:
    """All n-grams of a token array, blank-joined, in order; empty for shorter arrays.

    Shifted slices are zipped, so the array is read n times in all. Give a column, not a long expression: a lambda that
    holds an expression over the row would compute it anew for every element.
    """
    many = F.greatest(F.size(tokens) - F.lit(n - 1), F.lit(0))
    out = F.slice(tokens, F.lit(1), many)
    for k in range(1, n):
        out = F.zip_with(out, F.slice(tokens, F.lit(k + 1), many), lambda a, b: F.concat(a, F.lit(" "), b))
    return out
