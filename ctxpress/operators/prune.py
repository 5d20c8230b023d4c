"""Dropping the least informative tokens or phrases of prompts within a budget."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions.scalar import round_binary

BREAKS = r"[.,;:!?]"
NUMBER = r"^\p{N}+$"
#: Patterns of personal data and secrets.
SENSITIVE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}",
    "social_number": r"\b\d{3}-\d{2}-\d{4}\b",
    "card": r"\b(?:\d{4}[ -]?){3}\d{4}\b",
    "address": r"\b\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}\b",
    "key": r"\b(?:AKIA|ghp_|sk-)[A-Za-z0-9]{12,}\b",
    "password": r"(?i)\bpassword\s*[=:]\s*\S+",
}


@dataclass(frozen=True)
class Budget:
    """What may stay of a prompt: a share of its tokens, a number, scores from a cut, or scores from an own percentile."""

    kind: str
    value: float

    @classmethod
    def ratio(cls, share: float) -> Budget:
        return cls("ratio", share)

    @classmethod
    def tokens(cls, n: int) -> Budget:
        return cls("tokens", n)

    @classmethod
    def cut(cls, score: float) -> Budget:
        return cls("cut", score)

    @classmethod
    def percentile(cls, q: float) -> Budget:
        return cls("percentile", q)

    @classmethod
    def adaptive(cls, long: int = 60) -> Budget:
        return cls("adaptive", long)

    def allowance(self, size: Column) -> Column:
        """Tokens that may stay, for the kinds that count tokens; longer prompts keep less under the adaptive kind."""
        if self.kind == "ratio":
            return F.ceil(F.lit(self.value) * size)
        if self.kind == "tokens":
            return F.lit(int(self.value)).cast("long")
        share = F.when(size > 4 * self.value, 0.3).when(size > self.value, 0.5).otherwise(0.7)
        return F.ceil(share * size)


def prune_tokens(tokens: DataFrame, budget: Budget, protect: str | None = None, score_col: str = "score") -> DataFrame:
    """Adds kept to (prompt_id, pos, tok, score). Highest scores first, earlier first among equals; no score counts as highest.

    One shuffle on prompt_id serves the count, the order and the running budget.
    """
    own = Window.partitionBy("prompt_id")
    safe = F.col("tok").rlike(protect) if protect else F.lit(False)
    t = tokens.withColumn("_safe", safe)
    if budget.kind == "cut":
        kept = F.col(score_col).isNull() | (F.col(score_col) >= budget.value)
        return t.withColumn("kept", F.col("_safe") | kept).drop("_safe")
    if budget.kind == "percentile":
        t = t.withColumn("_cut", round_binary(F.percentile(score_col, F.lit(budget.value)).over(own), 6))
        return t.withColumn("kept", F.col("_safe") | F.col(score_col).isNull() | (F.col(score_col) >= F.col("_cut"))).drop("_safe", "_cut")
    order = own.orderBy(F.col("_safe").desc(), F.col(score_col).desc_nulls_first(), F.col("pos"))
    t = t.withColumn("_rank", F.row_number().over(order)).withColumn("_size", F.count("*").over(own))
    return t.withColumn("kept", F.col("_safe") | (F.col("_rank") <= budget.allowance(F.col("_size")))).drop("_rank", "_size", "_safe")


def reassemble(tokens: DataFrame) -> DataFrame:
    """(prompt_id, total, kept, text): what stays, in order."""
    left = F.array_sort(F.collect_list(F.when(F.col("kept"), F.struct("pos", "tok"))))
    out = tokens.groupBy("prompt_id").agg(F.count("*").alias("total"), F.count_if("kept").alias("kept"), left.alias("left"))
    return out.select("prompt_id", "total", "kept", F.array_join(F.transform("left", lambda x: x["tok"]), " ").alias("text"))


def prune_in_row(tokens: Column, share: float) -> Column:
    """The ratio budget on array<struct<pos, tok, score>> without a shuffle: what stays, in order."""
    ranked = F.array_sort(tokens, lambda a, b: F.when(a["score"].isNull() & b["score"].isNotNull(), -1).when(b["score"].isNull() & a["score"].isNotNull(), 1).when(a["score"] > b["score"], -1).when(a["score"] < b["score"], 1).when(a["pos"] < b["pos"], -1).otherwise(1))
    kept = F.slice(ranked, F.lit(1), F.ceil(F.lit(share) * F.size(tokens)).cast("int"))
    return F.array_join(F.transform(F.array_sort(F.transform(kept, lambda x: F.struct(x["pos"], x["tok"]))), lambda x: x["tok"]), " ")


# phrases: each grouper adds a phrase number to (prompt_id, pos, tok, …)


def group_clauses(tokens: DataFrame) -> DataFrame:
    """A phrase ends with a mark of punctuation, which belongs to it."""
    before = Window.partitionBy("prompt_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return tokens.withColumn("phrase", F.coalesce(F.sum(F.col("tok").rlike(f"^{BREAKS}$").cast("int")).over(before), F.lit(0)).cast("long"))


def group_by_attachment(tokens: DataFrame, theta: float = 8.0) -> DataFrame:
    """Frequent words join the next word of content: a phrase ends with each word whose static score is at least ``theta``."""
    before = Window.partitionBy("prompt_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    content = (F.col("s_stat").isNull() | (F.col("s_stat") >= theta)).cast("int")
    return tokens.withColumn("phrase", F.coalesce(F.sum(content).over(before), F.lit(0)).cast("long"))


def bigram_association(docs: DataFrame, least: int = 5) -> DataFrame:
    """(a, b, pmi) of the word pairs that occur ``least`` times; word pairs never cross a text."""
    from ctxpress.functions.tokens import words
    from ctxpress.operators.selfinfo import unigram_counts

    uni = unigram_counts(docs)
    total = uni.agg(F.sum("n").alias("total"))
    w = docs.select(words(F.col("text"), True).alias("w"))
    pairs = w.select(F.explode(F.zip_with(F.slice("w", F.lit(1), F.greatest(F.size("w") - 1, F.lit(0))), F.slice("w", 2, 1_000_000_000), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("e"))
    pairs = pairs.groupBy("e.a", "e.b").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    all_pairs = w.agg(F.sum(F.greatest(F.size("w") - 1, F.lit(0))).alias("all_pairs"))
    p = pairs.join(uni.select(F.col("tok").alias("a"), F.col("n").alias("na")), "a").join(uni.select(F.col("tok").alias("b"), F.col("n").alias("nb")), "b")
    p = p.crossJoin(F.broadcast(total)).crossJoin(F.broadcast(all_pairs))
    pmi = F.log2((F.col("n") / F.col("all_pairs")) / ((F.col("na") / F.col("total")) * (F.col("nb") / F.col("total"))))
    return p.select("a", "b", F.round(pmi, 6).alias("pmi"))


def group_by_pmi(tokens: DataFrame, association: DataFrame, tau: float = 4.0) -> DataFrame:
    """Neighbours stay together where their association is at least ``tau``."""
    order = Window.partitionBy("prompt_id").orderBy("pos")
    t = tokens.withColumn("_prev", F.lag("tok").over(order))
    strong = association.where(F.col("pmi") >= tau).select(F.col("a").alias("_prev"), F.col("b").alias("tok"), F.lit(1).alias("_tied"))
    t = t.join(strong, ["_prev", "tok"], "left")
    breaks = F.sum(F.when(F.col("_tied").isNull(), 1).otherwise(0)).over(order)
    return t.withColumn("phrase", (breaks - 1).cast("long")).drop("_prev", "_tied")


def group_by_heads(prompts: DataFrame, max_depth: int = 1) -> DataFrame:
    """(prompt_id, pos, tok, phrase) from tokens array<string> and heads array<int> (-1: root) of any parser.

    A token's phrase is the ancestor ``max_depth`` below the root of its tree, or the root itself.
    """
    climb = F.sequence(F.lit(1), F.size("heads"))

    def anchor(i: Column) -> Column:
        path = F.aggregate(climb, F.array(i), lambda a, _: F.when(F.element_at(F.col("heads"), F.element_at(a, -1) + 1) >= 0, F.concat(a, F.array(F.element_at(F.col("heads"), F.element_at(a, -1) + 1)))).otherwise(a))
        return F.element_at(F.reverse(path), F.least(F.lit(max_depth + 1), F.size(path)))

    rows = F.transform("tokens", lambda t, i: F.struct(i.alias("pos"), t.alias("tok"), anchor(i).alias("phrase")))
    return prompts.select("prompt_id", F.explode(rows).alias("r")).select("prompt_id", "r.pos", "r.tok", F.col("r.phrase").cast("long").alias("phrase"))


def prune_phrases(tokens: DataFrame, budget: Budget, agg: str = "mean", protect: str | None = None, position_bias: float = 0.0) -> DataFrame:
    """Adds phrase_score and kept to (prompt_id, pos, tok, score, phrase).

    Phrases are taken in order of score, earlier first among equals, as long as the running number of tokens, the phrase
    included, fits the budget; one phrase always stays, and so do protected ones, which count first. ``position_bias``
    raises the scores of phrases near both ends of the prompt, where models look most.
    """
    score = {"mean": F.avg("score"), "sum": F.sum("score"), "max": F.max("score")}[agg]
    safe = F.max(F.col("tok").rlike(protect)) if protect else F.lit(False)
    ph = tokens.groupBy("prompt_id", "phrase").agg(F.round(score, 10).alias("phrase_score"), F.count("*").alias("_n"), F.min("pos").alias("_first"), safe.alias("_safe"))
    own = Window.partitionBy("prompt_id")
    if position_bias:
        place = F.abs(F.percent_rank().over(own.orderBy("_first")) * 2 - 1)
        ph = ph.withColumn("phrase_score", F.round(F.col("phrase_score") * (1 + F.lit(position_bias) * place), 10))
    order = own.orderBy(F.col("_safe").desc(), F.col("phrase_score").desc_nulls_first(), F.col("_first"))
    ph = ph.withColumn("_used", F.sum("_n").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("_size", F.sum("_n").over(own)).withColumn("_rank", F.row_number().over(order))
    kept = F.col("_safe") | (F.col("_rank") == 1) | (F.col("_used") <= budget.allowance(F.col("_size")))
    ph = ph.select("prompt_id", "phrase", "phrase_score", kept.alias("kept"))
    return tokens.join(ph, ["prompt_id", "phrase"])


def sensitive_counts(text: Column) -> Column:
    """Struct of how often each kind of sensitive data occurs."""
    return F.struct(*[F.regexp_count(text, F.lit(p)).cast("long").alias(k) for k, p in SENSITIVE.items()])


def redact(text: Column) -> Column:
    """Sensitive spans go before anything is scored."""
    for p in SENSITIVE.values():
        text = F.regexp_replace(text, p, " ")
    return text


def flag_long_prompts(df: DataFrame, limit: int = 3000) -> DataFrame:
    from ctxpress.functions.tokens import token_count

    return df.withColumn("tokens", token_count(F.col("text"))).withColumn("is_long", F.col("tokens") > limit)


def order_for_edges(parts: DataFrame) -> DataFrame:
    """Adds place to (prompt_id, part, score): the best parts at the ends, the weakest in the middle."""
    rank = F.row_number().over(Window.partitionBy("prompt_id").orderBy(F.desc("score"), "part"))
    return parts.withColumn("place", F.when(rank % 2 == 1, rank).otherwise(-rank)).withColumn("place", F.row_number().over(Window.partitionBy("prompt_id").orderBy(F.col("place") < 0, "place")))
