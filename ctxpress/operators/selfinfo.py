"""Self-information of tokens: corpus unigrams, context models, and their merged score."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions.scalar import combine_scores, merge_rule, relative_gap
from ctxpress.functions.tokens import words


def explode_words(df: DataFrame, *keys: str, casefold: bool = True, text_col: str = "text") -> DataFrame:
    """(keys, pos, tok): a row per word; only keys and words leave the scan, the text never meets a shuffle."""
    return df.select(*keys, F.posexplode(words(F.col(text_col), casefold)).alias("pos", "tok"))


def unigram_counts(df: DataFrame, *keys: str, casefold: bool = True) -> DataFrame:
    return df.select(*keys, F.explode(words(F.col("text"), casefold)).alias("tok")).groupBy(*keys, "tok").agg(F.count("*").alias("n"))


def merge_counts(old: DataFrame, new: DataFrame) -> DataFrame:
    """Counts add up, so an offline table takes in new text without a recount."""
    return old.unionByName(new).groupBy("tok").agg(F.sum("n").alias("n"))


def unigram_information(counts: DataFrame, smoothing: str = "none", alpha: float = 1.0, min_count: int = 1) -> DataFrame:
    """(tok, n, p, s_stat) from counts; the totals are one row, broadcast."""
    totals = counts.agg(F.sum("n").alias("_total"), F.count("*").alias("_types"))
    t = counts.crossJoin(F.broadcast(totals)).where(F.col("n") >= min_count)
    p = (F.col("n") + F.lit(alpha)) / (F.col("_total") + F.lit(alpha) * (F.col("_types") + 1)) if smoothing == "add_alpha" else F.col("n") / F.col("_total")
    return t.select("tok", "n", p.alias("p"), (-F.log2(p)).alias("s_stat"))


def unigram_information_by(df: DataFrame, source_col: str = "source") -> DataFrame:
    """Per source and pooled (null source) in one aggregation."""
    c = df.select(source_col, F.explode(words(F.col("text"), True)).alias("tok")).groupBy("tok", source_col).agg(F.count("*").alias("n"))
    c = c.rollup("tok", source_col).agg(F.sum("n").alias("n"), F.grouping_id().alias("g")).where("g < 3")
    totals = c.groupBy("g", source_col).agg(F.sum("n").alias("total"))
    c = c.join(F.broadcast(totals.withColumnRenamed("g", "g2").withColumnRenamed(source_col, "s2")), (F.col("g") == F.col("g2")) & F.col(source_col).eqNullSafe(F.col("s2")))
    return c.select("tok", source_col, "n", (-F.log2(F.col("n") / F.col("total"))).alias("s_stat"))


class UnigramModel:
    """P(t) with a floor for unseen words."""

    name = "unigram"
    whole_prompt = False  # whether a model asks for the word array of the prompt in each row

    def __init__(self, counts: DataFrame):
        self.counts = counts
        self.totals = counts.agg(F.sum("n").alias("total"), F.count("*").alias("types"))

    def attach(self, tokens: DataFrame) -> DataFrame:
        """Adds p1 to (…, tok)."""
        t = tokens.join(self.counts.withColumnRenamed("n", "n1"), "tok", "left").crossJoin(F.broadcast(self.totals))
        return t.withColumn("p1", F.coalesce(F.col("n1") / F.col("total"), F.lit(1.0) / (F.col("total") + F.col("types") + 1))).drop("n1", "total", "types")

    def score(self, tokens: DataFrame) -> DataFrame:
        return self.attach(tokens).withColumn("s_dyn", -F.log2("p1"))


class NgramModel(UnigramModel):
    """Interpolated model of order 2 or 3; contexts never cross a text, the start of a text is an empty word."""

    def __init__(self, docs: DataFrame, order: int = 2, weights: tuple[float, ...] | None = None, counts: DataFrame | None = None, asked: DataFrame | None = None):
        """``asked`` (ctx1, ctx2), if given, are the contexts of all tokens to score, few enough to broadcast: others are not counted."""
        super().__init__(unigram_counts(docs) if counts is None else counts)
        self.order, self.weights, self.name = order, weights or ((0.7, 0.3) if order == 2 else (0.5, 0.3, 0.2)), f"{order}-gram"
        w = docs.select(words(F.col("text"), True).alias("w"))
        self.tables = []
        for k in range(order, 1, -1):
            pairs = w.select(F.explode(with_context(F.col("w"), k - 1)).alias("e")).select("e.ctx", "e.tok")
            if asked is not None:
                pairs = pairs.join(F.broadcast(asked.select(F.col(f"ctx{k - 1}").alias("ctx")).distinct()), "ctx", "left_semi")
            pairs = pairs.groupBy("ctx", "tok").agg(F.count("*").alias("n"))
            pairs = pairs if asked is None else pairs.persist()
            self.tables.append((k, pairs, pairs.groupBy("ctx").agg(F.sum("n").alias("m"))))

    def score(self, tokens: DataFrame) -> DataFrame:
        """Adds s_dyn to (keys, pos, tok, ctx1, ctx2) rows, the contexts being the one and two words before."""
        t, p = self.attach(tokens), F.lit(self.weights[-1]) * F.col("p1")
        for (k, pairs, ctxs), weight in zip(self.tables, self.weights):
            ctx = f"ctx{k - 1}"
            t = t.join(pairs.select(F.col("ctx").alias(ctx), "tok", F.col("n").alias(f"n{k}")), [ctx, "tok"], "left").join(ctxs.select(F.col("ctx").alias(ctx), F.col("m").alias(f"m{k}")), ctx, "left")
            p = p + F.lit(weight) * F.coalesce(F.col(f"n{k}") / F.col(f"m{k}"), F.lit(0.0))
        return t.withColumn("s_dyn", -F.log2(p)).drop(*[f"{c}{k}" for k, _, _ in self.tables for c in "nm"])


class CacheModel(UnigramModel):
    """Half the share of the word among those before it in the prompt, half its corpus share."""

    name = "cache"

    def __init__(self, counts: DataFrame, mix: float = 0.5):
        super().__init__(counts)
        self.mix = mix

    def score(self, tokens: DataFrame) -> DataFrame:
        before = F.row_number().over(Window.partitionBy("prompt_id", "tok").orderBy("pos")) - 1
        p = F.when(F.col("pos") == 0, F.col("p1")).otherwise(F.lit(self.mix) * F.try_divide(before, F.col("pos")) + F.lit(1 - self.mix) * F.col("p1"))
        return self.attach(tokens).withColumn("s_dyn", -F.log2(p))


class ExternalModel:
    """A model outside Spark: ``fn`` takes a list of (words before, word) and returns probabilities; called by batch."""

    name = "external"
    whole_prompt = True

    def __init__(self, fn: Callable[[list[tuple[list[str], str]]], list[float]], batch: int = 256):
        self.fn, self.batch = fn, batch

    def score(self, tokens: DataFrame) -> DataFrame:
        import math

        fn, size = self.fn, self.batch

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                ps: list[float] = []
                asked = [(list(w[:p]), t) for w, p, t in zip(f["w"], f["pos"], f["tok"])]
                for i in range(0, len(asked), size):
                    ps += fn(asked[i : i + size])
                yield f.assign(s_dyn=[-math.log2(p) if p > 0 else None for p in ps])

        kinds = ", ".join(f"`{n}` {t}" for n, t in tokens.dtypes)
        return tokens.mapInPandas(run, f"{kinds}, s_dyn double")


def only_asked(rows: DataFrame, asked: DataFrame, *key: str, bits: int = 26) -> DataFrame:
    """``rows`` without most of those whose key ``asked`` does not have, before any shuffle: a map of hashes of fixed size is broadcast; none that is asked for goes."""
    place = F.pmod(F.xxhash64(*key), F.lit(1 << bits))
    words_of = asked.select(place.alias("_at")).groupBy(F.shiftright("_at", 6).alias("_word")).agg(F.expr("bit_or(shiftleft(1L, cast(_at & 63 as int)))").alias("_mask"))
    t = rows.withColumn("_at", place).withColumn("_word", F.shiftright("_at", 6)).join(F.broadcast(words_of), "_word")
    return t.where(F.expr("bit_get(_mask, cast(_at & 63 as int)) = 1")).select(*rows.columns)


def scores_by_all(prompts: DataFrame, docs: DataFrame, band: float = 0.10) -> DataFrame:
    """(prompt_id, tokens): an array of (pos, tok, and for each scorer score and whether the rule is the mean) for each prompt.

    Of the n-grams of ``docs`` only those that some prompt may ask for are shuffled, once for all scorers.
    """
    t = prompt_tokens(prompts, whole=False)
    model, w = UnigramModel(unigram_counts(docs)), docs.select(words(F.col("text"), True).alias("w"))
    x = model.attach(t)
    for k in (3, 2):
        ctx, asked = f"ctx{k - 1}", t.select(F.col(f"ctx{k - 1}").alias("ctx"), "tok")
        pairs = w.select(F.explode(with_context(F.col("w"), k - 1)).alias("e")).select("e.ctx", "e.tok")
        n = only_asked(pairs, asked, "ctx", "tok").groupBy("ctx", "tok").agg(F.count("*").alias(f"n{k}"))
        m = only_asked(pairs.select("ctx"), asked, "ctx").groupBy("ctx").agg(F.count("*").alias(f"m{k}"))
        x = x.join(n.withColumnRenamed("ctx", ctx), [ctx, "tok"], "left").join(m.withColumnRenamed("ctx", ctx), ctx, "left")
        x = x.withColumn(f"p{k}", F.coalesce(F.col(f"n{k}") / F.col(f"m{k}"), F.lit(0.0))).drop(ctx, f"n{k}", f"m{k}")
    x = x.repartition("prompt_id")
    before = F.row_number().over(Window.partitionBy("prompt_id", "tok").orderBy("pos")) - 1
    x = x.withColumn("seen", before)
    p1, p2, p3 = F.col("p1"), F.col("p2"), F.col("p3")
    dyn = {"scorer_a": p1, "scorer_b": F.lit(0.3) * p1 + F.lit(0.7) * p2, "scorer_c": F.lit(0.2) * p1 + F.lit(0.5) * p3 + F.lit(0.3) * p2, "scorer_d": F.when(F.col("pos") == 0, p1).otherwise(F.lit(0.5) * F.try_divide("seen", "pos") + F.lit(0.5) * p1)}
    x = x.select("prompt_id", "pos", "tok", F.round(-F.log2("p1"), 6).alias("_s"), *[F.round(-F.log2(p), 6).alias(f"_{k}") for k, p in dyn.items()])
    each = [F.struct(F.round(combine_scores(F.col("_s"), F.col(f"_{k}"), band), 7).alias("score"), (merge_rule(F.col("_s"), F.col(f"_{k}"), band) == "mean").alias("mean")).alias(k) for k in dyn]
    return x.groupBy("prompt_id").agg(F.array_sort(F.collect_list(F.struct("pos", "tok", *each))).alias("tokens"))


def with_context(w, size: int):
    """array<struct<ctx, tok>> of a word array."""
    return F.transform(w, lambda t, i: F.struct(context_of(w, i, size).alias("ctx"), t.alias("tok")))


def context_of(w, pos, size: int):
    """The ``size`` words before place ``pos`` of array ``w``, blank-joined, empty words at the start."""
    parts = [F.when(pos >= k, F.try_element_at(w, (pos - k + 1).cast("int"))).otherwise(F.lit("")) for k in range(size, 0, -1)]
    return parts[0] if size == 1 else F.concat_ws(" ", *parts)


def get_scorer(name: str, docs: DataFrame):
    """Four models of growing context stand for four language models: unigram, bigram, trigram, cache."""
    return {"scorer_a": lambda: UnigramModel(unigram_counts(docs)), "scorer_b": lambda: NgramModel(docs, 2), "scorer_c": lambda: NgramModel(docs, 3), "scorer_d": lambda: CacheModel(unigram_counts(docs))}[name]()


def prompt_tokens(prompts: DataFrame, whole: bool = True) -> DataFrame:
    """(prompt_id, pos, tok, ctx1, ctx2): the words of each prompt with the one and two words before; rows stay of one size.

    Rows carry the prompt's word array w too, for models that run before any shuffle, unless ``whole`` is false.
    """
    w = prompts.select("prompt_id", words(F.col("text"), True).alias("w"))
    each = F.transform("w", lambda t, i: F.struct(t.alias("tok"), context_of(F.col("w"), i, 1).alias("ctx1"), context_of(F.col("w"), i, 2).alias("ctx2")))
    return w.select("prompt_id", *(["w"] if whole else []), F.posexplode(each).alias("pos", "e")).select("prompt_id", *(["w"] if whole else []), "pos", "e.*")


def score_tokens(prompts: DataFrame, docs: DataFrame, scorer=None, band: float = 0.10, mode: str = "combined") -> DataFrame:
    """(prompt_id, pos, tok, s_stat, s_dyn, delta, rule, score) for every word of every prompt; information to six digits."""
    scorer = scorer or NgramModel(docs, 2)
    t = scorer.score(prompt_tokens(prompts, scorer.whole_prompt)).drop("w", "ctx1", "ctx2")
    t = t.withColumn("s_stat", -F.log2("p1")) if "p1" in t.columns else UnigramModel(unigram_counts(docs)).attach(t).withColumn("s_stat", -F.log2("p1"))
    s, d = F.round("s_stat", 6), F.round("s_dyn", 6)
    t = t.select("prompt_id", "pos", "tok", s.alias("s_stat"), d.alias("s_dyn"))
    s, d = F.col("s_stat"), F.col("s_dyn")
    score = {"combined": combine_scores(s, d, band), "static": s, "dynamic": d}[mode]
    return t.select("*", F.round(relative_gap(s, d), 6).alias("delta"), merge_rule(s, d, band).alias("rule"), F.round(score, 7).alias("score"))


def scores_of_few(prompts: DataFrame, docs: DataFrame, scorers: Sequence[str]) -> dict[str, DataFrame]:
    """Scored tokens of some thousand prompts by each scorer: words are counted once, and of the n-grams only what the prompts ask for."""
    asked, counts = prompt_tokens(prompts, whole=False).persist(), unigram_counts(docs).persist()
    makers = {"scorer_a": lambda: UnigramModel(counts), "scorer_b": lambda: two, "scorer_c": lambda: three, "scorer_d": lambda: CacheModel(counts)}
    three = NgramModel(docs, 3, counts=counts, asked=asked)
    two = NgramModel(docs, 2, counts=counts, asked=asked)
    two.tables = three.tables[1:]
    return {s: score_tokens(prompts, docs, makers[s]()) for s in scorers}


def band_sensitivity(tokens: DataFrame, bands: tuple[float, ...] = (0.05, 0.10, 0.15)) -> DataFrame:
    """Per band: how many tokens are averaged and the mean score; one pass over scored tokens."""
    arms = [F.struct(F.lit(b).alias("band"), (F.col("delta") <= b).alias("averaged"), combine_scores(F.col("s_stat"), F.col("s_dyn"), b).alias("score")) for b in bands]
    t = tokens.select(F.explode(F.array(*arms)).alias("a"))
    return t.groupBy("a.band").agg(F.count("*").alias("tokens"), F.count_if("a.averaged").alias("averaged"), F.round(F.avg("a.score"), 4).alias("mean_score"))
