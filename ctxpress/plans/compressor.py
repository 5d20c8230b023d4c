"""The whole pipeline over prompts and attachments, in eight stages, each a lazy plan."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.functions.tokens import token_count
from ctxpress.operators import abbrev, fidelity, measures, prune, quant, selfinfo


@dataclass(frozen=True)
class CompressorConfig:
    scorer: str = "scorer_b"
    budget: prune.Budget = field(default_factory=lambda: prune.Budget.ratio(0.5))
    band: float = 0.10
    grouper: str = "attachment"
    protect: str | None = prune.NUMBER
    gram: int = 2
    top: int = 3
    bits: int = 8
    safe_cosine: float = 0.92
    redact: bool = False
    stages: frozenset = frozenset({"prune", "abbreviate", "quantize"})


@dataclass
class Result:
    """Frames of one run; nothing is computed before one of them is asked for, but for the small dictionary and grids."""

    prompts: DataFrame
    decisions: DataFrame | None
    documents: DataFrame | None
    table: DataFrame | None
    dictionary: DataFrame | None
    grids: list
    config: CompressorConfig

    def prompt_metrics(self) -> DataFrame:
        t = measures.with_tokens(self.prompts, "text", "short")
        return measures.compression_report(t).withColumn("part", F.lit("prompts"))

    def document_metrics(self) -> DataFrame:
        return measures.compression_report(measures.with_tokens(self.documents, "text", "short")).withColumn("part", F.lit("documents"))

    def table_metrics(self) -> DataFrame:
        cols = [g.column for g in self.grids]
        before = sum((F.length(F.format_string("%.2f", F.col(c).cast("double"))) for c in cols[1:]), F.length(F.format_string("%.2f", F.col(cols[0]).cast("double"))))
        after = sum((F.length(F.col(f"{c}_q").cast("string")) for c in cols[1:]), F.length(F.col(f"{cols[0]}_q").cast("string")))
        t = self.table.select(before.cast("long").alias("t0"), after.cast("long").alias("t1"))
        return measures.compression_report(t).withColumn("part", F.lit("table"))

    def metrics(self) -> DataFrame:
        parts = [self.prompt_metrics()]
        parts += [self.document_metrics()] if self.documents is not None else []
        parts += [self.table_metrics()] if self.table is not None else []
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def similarity(self) -> DataFrame:
        t = self.prompts.select("prompt_id", fidelity.word_cosine(F.col("text"), F.col("short")).alias("cosine"))
        return fidelity.fidelity_report(t).crossJoin(fidelity.fidelity_gate(t, self.config.safe_cosine).select("safe", "safe_share"))

    def restored_documents(self) -> DataFrame:
        return abbrev.restore(self.documents, abbrev.as_mapping(self.dictionary))


class ContextCompressor:
    """Prompts are pruned and attachments are coded beside each other; each half can be used alone."""

    def __init__(self, corpus: DataFrame, config: CompressorConfig | None = None):
        self.corpus, self.config = corpus, config or CompressorConfig()

    def score(self, prompts: DataFrame) -> DataFrame:
        scorer = selfinfo.get_scorer(self.config.scorer, self.corpus)
        return selfinfo.score_tokens(prompts, self.corpus, scorer, self.config.band)

    def decide(self, scored: DataFrame) -> DataFrame:
        """One row per token: scores, rule, phrase, and whether it stays."""
        c = self.config
        if c.grouper == "token":
            return prune.prune_tokens(scored.withColumn("phrase", F.col("pos").cast("long")).withColumn("phrase_score", F.col("score")), c.budget, c.protect)
        grouped = {
            "attachment": prune.group_by_attachment,
            "clause": prune.group_clauses,
            "pmi": lambda t: prune.group_by_pmi(t, prune.bigram_association(self.corpus)),
        }[c.grouper](scored)
        return prune.prune_phrases(grouped, c.budget, protect=c.protect)

    def compress_prompts(self, prompts: DataFrame) -> tuple[DataFrame, DataFrame | None]:
        if "prune" not in self.config.stages:
            return prompts.withColumn("short", F.col("text")), None
        if self.config.redact:
            prompts = prompts.withColumn("text", prune.redact(F.col("text")))
        decisions = self.decide(self.score(prompts))
        left = prune.reassemble(decisions).select("prompt_id", F.col("text").alias("short"))
        return prompts.join(left, "prompt_id", "left").withColumn("short", F.coalesce("short", F.lit(""))), decisions

    def compress_documents(self, documents: DataFrame) -> tuple[DataFrame, DataFrame | None]:
        if "abbreviate" not in self.config.stages:
            return documents.withColumn("short", F.col("text")), None
        top = abbrev.select_top(abbrev.codec_frequencies(documents, self.config.gram), self.config.top)
        dictionary = abbrev.build_dictionary(top, documents)
        return abbrev.abbreviate(documents, abbrev.as_mapping(dictionary)), dictionary

    def compress_table(self, table: DataFrame, cols: list[str] | None = None) -> tuple[DataFrame, list]:
        cols = cols or [c for c, t in table.dtypes if t in ("double", "float") or t.startswith("decimal")]
        if "quantize" not in self.config.stages or not cols:
            return table, []
        grids = quant.uniform_fit(table, cols, self.config.bits)
        return quant.uniform_encode(table, grids), grids

    def run(self, prompts: DataFrame, documents: DataFrame | None = None, table: DataFrame | None = None) -> Result:
        short, decisions = self.compress_prompts(prompts)
        docs, dictionary = self.compress_documents(documents) if documents is not None else (None, None)
        coded, grids = self.compress_table(table) if table is not None else (None, [])
        return Result(short, decisions, docs, coded if grids else None, dictionary, grids, self.config)


def render_table(df: DataFrame, cols: list[str], fmt: str = "csv") -> DataFrame:
    """Adds text: one row of a table as a line for a prompt."""
    if fmt == "csv":
        line = F.concat_ws(",", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in cols])
    elif fmt == "markdown":
        line = F.concat(F.lit("| "), F.concat_ws(" | ", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in cols]), F.lit(" |"))
    else:
        line = F.to_json(F.struct(*cols))
    return df.withColumn("text", line)


METHODS = {"A": ("text", False, False, False), "B": ("text", True, False, False), "C": ("short", False, False, False), "D": ("short", True, False, False), "E": ("short", True, True, False), "F": ("short", True, True, True)}


def assemble(prompts: DataFrame, shots: dict[str, str], context: tuple, header: str, c_with_shots: bool = False) -> DataFrame:
    """(prompt_id, method, exemplar_kind, prompt, tokens_word, tokens_est, header_tokens) for methods A to F.

    A asks with the original prompt and context; B adds examples; C to F use the compressed prompt, D adds examples, E the
    compressed context too, F the dictionary header. ``shots`` has the example text by kind, ``context`` the names of the
    columns with the original and the compressed attachment, where each prompt has its own, or else two texts for all.
    """
    own = context[0] in prompts.columns and context[1] in prompts.columns
    arms = []
    for method, (col, with_shots, data, head) in METHODS.items():
        for kind in sorted(shots) if with_shots or (c_with_shots and method == "C") else ["none"]:
            parts = [F.lit(header) if head else None, F.lit(shots[kind]) if kind != "none" else None, F.col(context[data]) if own else F.lit(context[data]), F.col(col)]
            prompt = F.concat_ws("\n", *[p for p in parts if p is not None])
            arms.append(F.struct(F.lit(method).alias("method"), F.lit(kind).alias("exemplar_kind"), prompt.alias("prompt"), F.lit(header if head else "").alias("head")))
    t = prompts.select("prompt_id", F.explode(F.array(*arms)).alias("a")).select("prompt_id", "a.*")
    return t.select("prompt_id", "method", "exemplar_kind", "prompt", token_count(F.col("prompt")).alias("tokens_word"), token_count(F.col("prompt"), "estimated").alias("tokens_est"), token_count(F.col("head")).alias("header_tokens"))
