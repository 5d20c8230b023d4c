"""Experiment workloads on the given tables, with deterministic readers where language models would answer."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxpress.functions import wordarrays
from ctxpress.functions.scalar import dequantize, quantize
from ctxpress.functions.tokens import WORD, token_count, words
from ctxpress.operators import abbrev, fidelity, prune, quant, selfinfo


def inverse_document_frequency(docs: DataFrame) -> DataFrame:
    n = docs.agg(F.count("*").alias("d"))
    t = docs.select(F.explode(F.array_distinct(words(F.col("text"), True))).alias("tok")).groupBy("tok").agg(F.count("*").alias("df"))
    return t.crossJoin(F.broadcast(n)).select("tok", F.round(F.log((F.col("d") + 1) / (F.col("df") + 1)), 6).alias("idf"))


def answers(docs: DataFrame, items: DataFrame, most: int = 100_000) -> DataFrame:
    """(item_id, doc_id): documents that hold an item verbatim; an item without words is in none.

    Each item is looked for only in documents that have the one of its words that is rarest among the documents read together, so
    no document meets every item. Words at either end of an item may go on in a document and are not asked for. Items are a
    test set, and it is checked that they are few.
    """
    rows = items.select("item_id", "text").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("too many items to broadcast")
    texts, inner, anywhere = [(r["item_id"], r["text"]) for r in rows], [], []
    for i, (_, text) in enumerate(texts):
        spans = [x.span() for x in regex.finditer(WORD, text or "")]
        own = {text[lo:hi] for lo, hi in spans if lo > 0 and hi < len(text)}
        inner += [(x, i) for x in own]
        anywhere += [i] if spans and not own else []
    inner = sorted(inner, key=lambda x: x[1])
    vocabulary = sorted({x for x, _ in inner})
    at = {x: j for j, x in enumerate(vocabulary)}
    word, of = np.array([at[x] for x, _ in inner], dtype=np.int64), np.array([i for _, i in inner], dtype=np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = pa.array(vocabulary, pa.large_string())
        for b in batches:
            for part in wordarrays.parts_of(b, "text"):
                w = wordarrays.Words(part.column("text"))
                doc, known = distinct_pairs(w.doc, pc.fill_null(pc.index_in(w.names, value_set=values), -1).to_numpy(zero_copy_only=False)[w.word], len(vocabulary))
                by = np.argsort(known, kind="stable")
                doc, starts = doc[by], np.searchsorted(known[by], np.arange(len(vocabulary) + 1))
                many = np.diff(starts)[word] if len(word) else word
                rarest = np.lexsort((word, many, of))
                rarest = rarest[np.flatnonzero(np.diff(of[rarest], prepend=-1))] if len(of) else rarest
                body, pairs = part.column("text"), []
                for i, x in zip(of[rarest].tolist(), word[rarest].tolist()):
                    pairs += [(texts[i][0], d) for d in doc[starts[x] : starts[x + 1]].tolist() if texts[i][1] in body[d].as_py()]
                for i in anywhere:
                    pairs += [(texts[i][0], d) for d in np.flatnonzero(pc.fill_null(pc.match_substring(body, texts[i][1]), False).to_numpy(zero_copy_only=False)).tolist()]
                ids = part.column("doc_id").take(pa.array([d for _, d in pairs], pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in pairs], pa.int64()), ids.cast(pa.int64())], ["item_id", "doc_id"])

    return docs.select("doc_id", "text").mapInArrow(run, "item_id long, doc_id long").distinct()


def distinct_pairs(doc: np.ndarray, known: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs of a document and one of ``n`` numbers; negative ones are left out."""
    pairs = np.unique(doc[known >= 0] * n + known[known >= 0])
    return pairs // max(n, 1), pairs % max(n, 1)


#: The reader leaves out words in more than this share of the documents.
COMMON = 0.1


def word_weights(docs: DataFrame, common: float = COMMON, of: DataFrame | None = None) -> DataFrame:
    """(tok, idf): inverse document frequency in millionths, of words that are not too common; only of the few lower-case words ``of`` (tok), if given."""
    if of is None:
        n = docs.agg(F.count("*").alias("d"))
        t = docs.select(F.explode(F.array_distinct(words(F.col("text"), True))).alias("tok")).groupBy("tok").agg(F.count("*").alias("df"))
        t = t.crossJoin(F.broadcast(n))
    else:
        t = few_document_frequencies(docs, sorted(r["tok"] for r in of.select("tok").distinct().collect()))
    return t.where(F.col("df") <= common * F.col("d")).select("tok", F.round(F.log((F.col("d") + 1) / (F.col("df") + 1)) * 1_000_000).cast("long").alias("idf"))


def few_document_frequencies(docs: DataFrame, asked: list[str]) -> DataFrame:
    """(tok, df, d): in how many of all ``d`` documents each of some lower-case words is, of those that are in any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values, df, d = pa.array(asked, pa.large_string()), np.zeros(len(asked), np.int64), 0
        for b in batches:
            for part in wordarrays.parts_of(b, "text"):
                w = wordarrays.Words(part.column("text"))
                known = pc.fill_null(pc.index_in(w.lower(), value_set=values), -1).to_numpy(zero_copy_only=False)
                df += np.bincount(distinct_pairs(w.doc, known[w.word], len(asked))[1], minlength=len(asked))
                d += w.docs
        there = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array([None, *(asked[i] for i in there)], pa.string()), pa.array([d, *df[there].tolist()], pa.int64())], ["tok", "n"])

    rows = docs.select("text").mapInArrow(run, "tok string, n long").groupBy("tok").agg(F.sum("n").alias("n")).collect()
    d = sum(r["n"] for r in rows if r["tok"] is None)
    return docs.sparkSession.createDataFrame([(r["tok"], r["n"], d) for r in rows if r["tok"] is not None], "tok string, df long, d long")


def opening(items: DataFrame, n: int = 8) -> DataFrame:
    """Items as questions: their first ``n`` words."""
    return items.select("item_id", F.array_join(F.slice(words(F.col("text")), 1, n), " ").alias("text"))


def best_readings(docs: DataFrame, asked: dict[str, DataFrame], shots: DataFrame | None = None, weight: int = 1, step: int = 1, each: int = 500) -> DataFrame:
    """(text, arm, shots, item_id, found): the document whose distinct words share most with each question, the smaller doc_id on a tie.

    ``asked`` has (arm, item_id, tok, idf) for each column of ``docs`` (doc_id and arrays of distinct words); idf are whole numbers, so
    sums are exact in any order, and are rounded to multiples of ``step``. ``shots`` (exemplar_kind, tok, idf) add to ``weight`` times
    the score of documents that share something. Questions are few and go to every task, which keeps one best document for each;
    neither words nor scores are shuffled. doc_id is unique.
    """
    extra: dict[str, dict[str, int]] = {"none": {}}
    for r in shots.collect() if shots is not None else ():
        extra.setdefault(r["exemplar_kind"], {})[r["tok"]] = r["idf"]
    tables = {}
    for text, terms in asked.items():
        rows = sorted((r["tok"], r["arm"], r["item_id"], r["idf"]) for r in terms.collect())
        vocabulary = sorted({r[0] for r in rows} | {t for e in extra.values() for t in e})
        at, cols = {t: i for i, t in enumerate(vocabulary)}, sorted({r[1:3] for r in rows})
        place = {c: i for i, c in enumerate(cols)}
        starts = np.searchsorted(np.array([at[r[0]] for r in rows], dtype=np.int64), np.arange(len(vocabulary) + 1))
        more = {k: np.array([e.get(t, 0) for t in vocabulary], dtype=np.float64) for k, e in extra.items()}
        tables[text] = vocabulary, cols, starts, np.array([place[r[1:3]] for r in rows], dtype=np.int64), np.array([r[3] for r in rows], dtype=np.float64), more

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = {(t, k): (np.full(len(v[1]), -1.0), np.zeros(len(v[1]), dtype=np.int64)) for t, v in tables.items() for k in extra}
        values = {t: pa.array(v[0], pa.string()) for t, v in tables.items()}
        for b in batches:
            ids = b.column("doc_id").to_numpy(zero_copy_only=False)
            order = np.argsort(ids, kind="stable")
            rank = np.empty(len(ids), dtype=np.int64)
            rank[order] = np.arange(len(ids))
            for text, (_, cols, starts, col, idf, more) in tables.items():
                n, words_of = len(cols), b.column(text)
                known = pc.fill_null(pc.index_in(words_of.flatten(), value_set=values[text]), -1).to_numpy(zero_copy_only=False)
                row = rank[np.repeat(np.arange(len(ids)), pc.fill_null(pc.list_value_length(words_of), 0).to_numpy(zero_copy_only=False))]
                row, known = row[known >= 0], known[known >= 0].astype(np.int64)
                by = np.argsort(row, kind="stable")
                row, known = row[by], known[by]
                cuts = np.searchsorted(row, np.arange(0, len(ids) + each, each))
                for c, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
                    if lo == hi or not n:
                        continue
                    first, doc, tok = c * each, row[lo:hi] - c * each, known[lo:hi]
                    size = min(each, len(ids) - first)
                    many = starts[tok + 1] - starts[tok]
                    at = np.repeat(starts[tok] - np.cumsum(many) + many, many) + np.arange(many.sum())
                    cell = np.repeat(doc, many) * n + col[at]
                    q = np.bincount(cell, idf[at], size * n).reshape(size, n)
                    none = (np.bincount(cell, minlength=size * n) == 0).reshape(size, n)
                    q = np.floor((q + step // 2) / step) if step > 1 else q
                    for kind, e in more.items():
                        score = weight * q + np.bincount(doc, e[tok], size)[:, None]
                        score[none] = -1
                        top = score.argmax(0)  # rows are in order of doc_id
                        value, name = score[top, np.arange(n)], ids[order[first + top]]
                        most, found = best[text, kind]
                        new = (value > most) | ((value == most) & (value >= 0) & (name < found))
                        most[new], found[new] = value[new], name[new]
        out = [(t, *tables[t][1][i][:1], k, tables[t][1][i][1], int(found[i]), int(most[i])) for (t, k), (most, found) in best.items() for i in np.flatnonzero(most >= 0)]
        yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out) if out else [[]] * 6, (pa.string(),) * 3 + (pa.int64(),) * 3)], ["text", "arm", "shots", "item_id", "doc_id", "score"])

    t = docs.where("doc_id is not null").mapInArrow(run, "text string, arm string, shots string, item_id long, doc_id long, score long")
    return t.groupBy("text", "arm", "shots", "item_id").agg(F.min_by("doc_id", F.struct(-F.col("score"), F.col("doc_id"))).alias("found"))


def distinct_words(text: str | Column) -> Column:
    return F.array_distinct(words(F.col(text) if isinstance(text, str) else text, True))


def best_documents(hits: DataFrame, *arms: str) -> DataFrame:
    """(arms, item_id, found) of (arms, item_id, doc_id, score): the highest score, the smaller doc_id on a tie."""
    return hits.groupBy(*arms, "item_id").agg(F.min_by("doc_id", F.struct(-F.col("score"), F.col("doc_id"))).alias("found"))


def judged(found: DataFrame, arms: DataFrame, gold: DataFrame, *keys: str) -> DataFrame:
    """(keys, item_id, found, correct) for every arm and every question that has an answer."""
    asked = F.broadcast(arms).crossJoin(gold.select("item_id").distinct())
    t = asked.join(found, [*keys, "item_id"], "left")
    right = gold.withColumnRenamed("doc_id", "found").withColumn("_right", F.lit(True))
    return t.join(right, ["item_id", "found"], "left").select(*keys, "item_id", "found", F.coalesce("_right", F.lit(False)).alias("correct"))


def method_results(docs: DataFrame, items: DataFrame, shots: dict[str, DataFrame], mapping: dict[str, str], share: float = 0.6, scorers: tuple[str, ...] = ("scorer_a", "scorer_b", "scorer_c", "scorer_d")) -> DataFrame:
    """(scorer, method, exemplar_kind, item_id, found, correct): methods A to F on passage finding, over all documents.

    A question is the opening of an item. The reader names the document that shares most information with it among those that
    share anything; words of the examples count a quarter, for all questions alike, so examples can distract. A asks as it
    is, B adds examples, C prunes the question, D does both, E reads abbreviated documents with neither dictionary nor
    original, F has the dictionary and reads what it restores. ``shots`` are items by kind.
    """
    questions, idf, gold = opening(items), word_weights(docs), answers(docs, items)
    terms = questions.select(F.lit("none").alias("arm"), "item_id", F.explode(F.array_distinct(words(F.col("text"), True))).alias("tok"))
    asked = questions.select(F.col("item_id").alias("prompt_id"), "text")
    for name, scored in selfinfo.scores_of_few(asked, docs.select("text"), scorers).items():
        kept = prune.prune_tokens(scored, prune.Budget.ratio(share)).where("kept")
        terms = terms.unionAll(kept.select(F.lit(name).alias("arm"), F.col("prompt_id").alias("item_id"), "tok").distinct())
    examples = None
    for kind, ids in shots.items():
        t = items.join(F.broadcast(ids), "item_id", "left_semi").select(F.explode(words(F.col("text"), True)).alias("tok")).distinct().select(F.lit(kind).alias("exemplar_kind"), "tok")
        examples = t if examples is None else examples.unionAll(t)
    few = F.broadcast(terms.select("tok").union(examples.select("tok")).distinct())  # words of some hundred questions
    idf = idf.join(few, "tok", "left_semi").persist()
    terms, examples = terms.join(F.broadcast(idf), "tok").persist(), examples.join(F.broadcast(idf), "tok")
    pruned = terms.where("arm <> 'none'")
    seen = abbrev.abbreviate_and_restore(docs.select("doc_id", "text"), mapping).select("doc_id", *[distinct_words(c).alias(c) for c in ("text", "short", "restored")])
    found = best_readings(seen, {"text": terms, "short": pruned, "restored": pruned}, examples, weight=4)
    # with and without examples: A and B ask as it is, C and D pruned; E and F always have examples
    plain = F.when(F.col("arm") == "none", F.when(F.col("shots") == "none", "A").otherwise("B")).otherwise(F.when(F.col("shots") == "none", "C").otherwise("D"))
    method = F.when(F.col("text") == "text", plain).when(F.col("text") == "short", "E").otherwise("F")
    out = found.where("text = 'text' or shots <> 'none'").select(F.col("arm").alias("scorer"), method.alias("method"), F.col("shots").alias("exemplar_kind"), "item_id", "found")
    plan = {"A": False, "B": True, "C": False, "D": True, "E": True, "F": True}
    arms = [(s, m, k) for m, w in plan.items() for s in (("none",) if m in "AB" else scorers) for k in (sorted(shots) if w else ("none",))]
    return judged(out, docs.sparkSession.createDataFrame(arms, "scorer string, method string, exemplar_kind string"), gold, "scorer", "method", "exemplar_kind")


def accuracy_table(results: DataFrame, *arms: str, base: str) -> DataFrame:
    """(arms, questions, accuracy, delta) in points, against the arm for which ``base`` holds."""
    t = results.groupBy(*arms).agg(F.count("*").alias("questions"), F.round(100 * F.sum(F.col("correct").cast("int")) / F.count("*"), 4).alias("accuracy"))
    return t.crossJoin(F.broadcast(t.where(base).agg(F.max("accuracy").alias("_base")))).select(*arms, "questions", "accuracy", F.round(F.col("accuracy") - F.col("_base"), 4).alias("delta"))


def ablation_readings(docs: DataFrame, terms: DataFrame, settings: abbrev.Settings, cells: int = 1 << 22) -> DataFrame:
    """(scope, g, t, words_before, words_after) by part and (scope, g, t, item_id, doc_id, score): the best document of a part, for every setting.

    ``terms`` (item_id, tok, idf) are few, with idf of whole numbers above 0; the setting ("original", 0, 0) reads texts as they are.
    Texts are read once for all settings. A score is that of the original less the words that a setting takes from the text, so
    a setting can only find something new where the original scores more than what is found. doc_id is unique.
    """
    rows = sorted((r["tok"], r["item_id"], r["idf"]) for r in terms.collect())
    vocabulary, items = sorted({r[0] for r in rows}), sorted({r[1] for r in rows})
    at, place = {x: i for i, x in enumerate(vocabulary)}, {x: i for i, x in enumerate(items)}
    starts = np.searchsorted(np.array([at[r[0]] for r in rows], dtype=np.int64), np.arange(len(vocabulary) + 1))
    col, idf = np.array([place[r[1]] for r in rows], dtype=np.int64), np.array([r[2] for r in rows], dtype=np.int64)
    names = [("original", 0, 0), *settings.names]
    n, v = len(items), len(vocabulary)

    def spread(doc: np.ndarray, term: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document, question, idf) for each question that has the term."""
        many = starts[term + 1] - starts[term]
        x = np.repeat(starts[term] - np.cumsum(many) + many, many) + np.arange(many.sum())
        return np.repeat(doc, many), col[x], idf[x]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = pa.array(vocabulary, pa.large_string())
        best, found = {s: np.zeros(n, np.int64) for s in names}, {s: np.zeros(n, np.int64) for s in names}
        before, after = 0, dict.fromkeys(names, 0)

        def better(s, which: np.ndarray, top: np.ndarray, name: np.ndarray) -> np.ndarray:
            return (top > best[s][which]) | ((top == best[s][which]) & (top > 0) & (name < found[s][which]))

        for b in batches:
            for part in wordarrays.parts_of(b, "text", most=max(1, cells // max(n, 1))):
                w = wordarrays.Words(part.column("text"), abbrev.ESCAPE)
                ids = part.column("doc_id")
                unnamed = ids.is_null().to_numpy(zero_copy_only=False)
                ids = pc.fill_null(ids, 0).to_numpy(zero_copy_only=False)
                order = np.argsort(ids, kind="stable")  # of equal scores the first is the smaller doc_id
                row = np.empty(len(ids), dtype=np.int64)
                row[order] = np.arange(len(ids))
                ids, unnamed, row = ids[order], unnamed[order], row[w.doc]
                term = pc.fill_null(pc.index_in(w.lower(), value_set=values), -1).to_numpy(zero_copy_only=False)[w.word]
                pairs, counts = np.unique(row[term >= 0] * v + term[term >= 0], return_counts=True)
                doc, question, weight = spread(pairs // max(v, 1), pairs % max(v, 1))
                q = np.zeros((len(ids), n), dtype=np.int64)
                np.add.at(q.reshape(-1), doc * n + question, weight)
                q[unnamed] = 0
                every = np.arange(n)
                top = q.argmax(0)
                score = q[top, every]
                new = better(names[0], every, score, ids[top])
                best[names[0]][new], found[names[0]][new] = score[new], ids[top][new]
                before += len(w)
                for s, places in settings.replaced(w):
                    g = s[1]
                    after[s] -= len(places) * (g - 1)
                    which = np.flatnonzero(better(s, every, score, ids[top]))
                    if not len(which):
                        continue
                    gone = (places[:, None] + np.arange(g)).ravel()
                    gone = gone[term[gone] >= 0]
                    gone, less = np.unique(row[gone] * v + term[gone], return_counts=True)
                    gone = gone[less == counts[np.searchsorted(pairs, gone)]]  # a word is lost when all its places are replaced
                    sub = q[:, which]
                    doc, question, weight = spread(gone // max(v, 1), gone % max(v, 1))
                    to = np.full(n, -1, dtype=np.int64)
                    to[which] = np.arange(len(which))
                    hit = (to[question] >= 0) & ~unnamed[doc]
                    np.subtract.at(sub, (doc[hit], to[question[hit]]), weight[hit])
                    first = sub.argmax(0)
                    value, name = sub[first, np.arange(len(which))], ids[first]
                    new = better(s, which, value, name)
                    best[s][which[new]], found[s][which[new]] = value[new], name[new]
        out = [(*s, before, before + after[s], None, None, None) for s in names]
        out += [(*s, None, None, items[i], int(found[s][i]), int(best[s][i])) for s in names for i in np.flatnonzero(best[s] > 0)]
        kinds = (pa.string(), pa.int32(), pa.int32(), *(pa.int64(),) * 5)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], ["scope", "g", "t", "words_before", "words_after", "item_id", "doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "scope string, g int, t int, words_before long, words_after long, item_id long, doc_id long, score long")


def ablation_accuracy(docs: DataFrame, items: DataFrame, ranked: dict[int, list[str]], tops: tuple[int, ...]) -> DataFrame:
    """(scope, g, t, questions, accuracy, delta, region, ratio): the reader on documents abbreviated by every setting under which it finds anything.

    Each step is a scan of the texts; neither words nor scores are shuffled, only counts and best documents of each part.
    """
    asked = opening(items).select("item_id", F.explode(F.array_distinct(words(F.col("text"), True))).alias("tok")).persist()
    idf, gold = word_weights(docs, of=asked), answers(docs, items).persist()
    terms = asked.join(F.broadcast(idf), "tok").distinct()
    read = ablation_readings(docs, terms, abbrev.Settings(ranked, tops)).persist()
    ratio = read.where("item_id is null").groupBy("scope", "g", "t").agg(F.round(F.try_divide(F.sum("words_before"), F.sum("words_after")), 6).alias("ratio"))
    found = best_documents(read.where("item_id is not null"), "scope", "g", "t")
    t = accuracy_table(judged(found, found.select("scope", "g", "t").distinct(), gold, "scope", "g", "t"), "scope", "g", "t", base="scope = 'original'")
    return t.where("scope <> 'original'").join(F.broadcast(ratio), ["scope", "g", "t"]).select("scope", "g", "t", "questions", "accuracy", "delta", region(F.col("delta")).alias("region"), "ratio")


def passage_finding(docs: DataFrame, items: DataFrame, arms: dict[str, tuple[DataFrame, str, DataFrame, str]]) -> DataFrame:
    """(arm, item_id, answerable, found, correct): the reader names the best document in each arm."""
    idf, gold = inverse_document_frequency(docs), answers(docs, items)
    gold = gold.groupBy("item_id").agg(F.collect_set("doc_id").alias("gold"))
    out = None
    idf = idf.select("tok", F.round(F.col("idf") * 1_000_000).cast("long").alias("idf")).persist()  # whole millionths, so that equal texts have equal sums
    for arm, (d, text_col, i, item_col) in arms.items():
        terms = i.select(F.lit(arm).alias("arm"), "item_id", F.explode(distinct_words(item_col)).alias("tok")).join(idf, "tok")
        best = best_readings(d.select("doc_id", distinct_words(text_col).alias("text")), {"text": terms}, step=100).select("item_id", "found")
        t = items.select("item_id").join(best, "item_id", "left").join(gold, "item_id", "left")
        t = t.select(F.lit(arm).alias("arm"), "item_id", F.col("gold").isNotNull().alias("answerable"), "found", F.coalesce(F.array_contains("gold", F.col("found")), F.lit(False)).alias("correct"))
        out = t if out is None else out.unionAll(t)
    return out


#: (name, grouping column or null, aggregate, value column) of the numeric questions on order lines.
QUESTIONS = (
    ("revenue_by_flag", "l_returnflag", "sum", "l_extendedprice"),
    ("quantity_by_status", "l_linestatus", "avg", "l_quantity"),
    ("discount_by_flag", "l_returnflag", "avg", "l_discount"),
    ("tax_by_status", "l_linestatus", "avg", "l_tax"),
    ("price_spread_by_flag", "l_returnflag", "spread", "l_extendedprice"),
    ("total_quantity", None, "sum", "l_quantity"),
)


def numeric_questions(lines: DataFrame, bits: int = 8, tau: float = 0.01) -> DataFrame:
    """(qid, grp, exact, decoded, rel_error, correct): questions answered on stored and on decoded values in one scan each."""
    cols = sorted({q[3] for q in QUESTIONS})
    grids = {g.column: g for g in quant.uniform_fit(lines, cols, bits)}
    out = None
    for qid, by, how, col in QUESTIONS:
        g = grids[col]
        hat = dequantize(quantize(F.col(col), g.lo, g.hi, bits), g.lo, g.hi, bits)
        f = {"sum": F.sum, "avg": F.avg, "spread": lambda c: F.max(c) - F.min(c)}[how]
        t = lines.groupBy((F.col(by) if by else F.lit("all")).alias("grp")).agg(f(F.col(col)).alias("exact"), f(hat).alias("decoded"))
        rel = F.coalesce(F.abs(F.try_divide(F.col("decoded") - F.col("exact"), F.col("exact"))), F.lit(0.0))
        t = t.select(F.lit(qid).alias("qid"), "grp", F.round("exact", 4).alias("exact"), F.round("decoded", 4).alias("decoded"), F.round(rel, 6).alias("rel_error"), (rel <= tau).alias("correct"))
        out = t if out is None else out.unionAll(t)
    return out


def ablation_grid(docs: DataFrame, grams: tuple[int, ...] = (2, 3, 4, 5), tops: tuple[int, ...] = (1, 2, 3, 4, 5)) -> DataFrame:
    """(g, t, saved_words, words, ratio) by what a left-to-right scan replaces of the t best g-grams of the corpus.

    N-grams are ranked once for each length; every t is served from that ranking. Savings are counted in the row.
    """
    out = None
    for g in grams:
        top = abbrev.select_top(abbrev.codec_frequencies(docs, g), max(tops)).collect()
        ranked = [r["gram"] for r in sorted(top, key=lambda r: (-r["freq"], r["gram"]))]
        for t in tops:
            short = abbrev.abbreviate(docs.select("text"), {x: f"QQ{i + 1}" for i, x in enumerate(ranked[:t])})
            row = short.agg(F.sum(token_count(F.col("text"))).alias("words"), F.sum(token_count(F.col("short"))).alias("left"))
            row = row.select(F.lit(g).alias("g"), F.lit(t).alias("t"), (F.col("words") - F.col("left")).alias("saved_words"), "words", F.round(F.col("words") / F.col("left"), 6).alias("ratio"))
            out = row if out is None else out.unionAll(row)
    return out


def region(delta: Column) -> Column:
    """Label of a setting in the map of the ablation by its accuracy delta in points."""
    return F.when(delta >= 4, "best").when(delta > 0, "next").when(delta == 0, "even").otherwise("failure")


def similarity_of_arms(docs: DataFrame, arms: dict[str, Column]) -> DataFrame:
    """(arm, pairs, mean_cosine, p5_cosine) by cosine of word counts."""
    rows = F.array(*[F.struct(F.lit(a).alias("arm"), fidelity.word_cosine(F.col("text"), c).alias("cosine")) for a, c in arms.items()])
    t = docs.select(F.explode(rows).alias("r")).select("r.*")
    return fidelity.fidelity_report(t, "arm")


def classify_reader(train: DataFrame, test: DataFrame, label: str, dim: int = 1 << 12):
    """Accuracy of a logistic regression on hashed words, fitted on originals; test may be compressed."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import IDF, HashingTF

    tf = HashingTF(numFeatures=dim, inputCol="w", outputCol="tf")
    prep = lambda d: tf.transform(d.withColumn("w", words(F.col("text"), True)))
    idf = IDF(inputCol="tf", outputCol="features").fit(prep(train))
    model = LogisticRegression(labelCol=label, maxIter=20, regParam=0.01).fit(idf.transform(prep(train)))
    return model.transform(idf.transform(prep(test))).agg(F.count("*").alias("rows"), F.round(F.avg((F.col("prediction") == F.col(label)).cast("double")), 6).alias("accuracy"))
