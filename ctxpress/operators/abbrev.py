"""Lossless abbreviation: frequent n-grams get short placeholders, and every text can be restored exactly."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions import wordarrays
from ctxpress.functions.tokens import WORD, ngrams, words


#: Stands before a word of the text that is also a placeholder; n-grams right after one are left alone.
ESCAPE = "\x1b"


def extract_ngrams(docs: DataFrame, n: int, *keys: str, boundary: str = "none") -> DataFrame:
    """(keys, gram): every n-gram of words, case kept. ``sentence`` keeps n-grams from crossing . ! ? or a line end."""
    if boundary == "sentence":
        docs = docs.select(*keys, F.explode(F.split("text", r"[.!?\n]")).alias("text"))
    w = docs.select(*keys, words(F.col("text")).alias("_w"))
    return w.select(*keys, F.explode(ngrams(F.col("_w"), n)).alias("gram"))


def ngram_frequencies(docs: DataFrame, n: int, *keys: str, boundary: str = "none") -> DataFrame:
    return extract_ngrams(docs, n, *keys, boundary=boundary).groupBy(*keys, "gram").agg(F.count("*").alias("freq"))


def codec_frequencies(docs: DataFrame, n: int, *keys: str) -> DataFrame:
    """(keys, gram, freq) of the n-grams that the codec can replace: words with single blanks between them."""
    # cut at whatever is neither part of a word nor a single blank; a repeated group would recurse on very long runs
    runs = F.split("text", r"[^\p{L}\p{M}\p{N}_ ]| {2,}", -1)
    w = docs.select(*keys, F.explode(runs).alias("_r")).select(*keys, F.split(F.trim("_r"), " ").alias("_w"))
    return w.select(*keys, F.explode(ngrams(F.col("_w"), n)).alias("gram")).groupBy(*keys, "gram").agg(F.count("*").alias("freq"))


#: Buckets of n-gram counts, and how many of them a row carries.
BUCKET_BITS = 16
BUCKETS, BUCKETS_A_ROW = 1 << BUCKET_BITS, 1 << 12


def _buckets(w: wordarrays.Words, most: int) -> dict[int, np.ndarray]:
    """For each n up to ``most``, the bucket of the n words from every place on, the same in every task."""
    named = pd.util.hash_array(w.names.to_numpy(zero_copy_only=False), categorize=False) if len(w) else np.zeros(0, np.uint64)
    words_of, out = named[w.word], {}
    h = words_of
    for n in range(2, most + 1):
        h = (h[:-1] ^ (h[:-1] >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) + words_of[n - 1 :]
        out[n] = ((h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
    return out


def frequent_codec_ngrams(docs: DataFrame, sizes: tuple[int, ...], k: int, heavy: int = 256, listed: int = 1000) -> DataFrame:
    """(n, gram, freq) of ``codec_frequencies`` for all ``sizes``, at least for whatever can be among the ``k`` most frequent of its size.

    A first scan adds up counts by bucket of a hash, which are upper bounds, and counts what is in each part's fullest buckets, which
    are lower bounds. The k-th lower bound is one for the k-th frequency, so a second scan counts, and shuffles, only n-grams
    whose bucket and those of the shorter n-grams in them reach it. Counts are exact, and ties are kept.
    """
    texts, longest = docs.select("text"), max(sizes)

    def bounds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, least = {n: np.zeros(BUCKETS, np.int64) for n in range(2, longest + 1)}, {n: Counter() for n in sizes}
        for b in batches:
            for part in wordarrays.parts_of(b, "text"):
                w = wordarrays.Words(part.column("text"))
                bucket = _buckets(w, longest)
                for n, t in table.items():
                    places = w.places(n)
                    full = bucket[n][places]
                    here = np.bincount(full, minlength=BUCKETS)
                    t += here
                    if n not in least or not len(places):
                        continue
                    fullest = np.zeros(BUCKETS, dtype=bool)
                    fullest[np.argpartition(here, -heavy)[-heavy:]] = True
                    places = places[fullest[full]]
                    ids, first = w.same(places, n)
                    freq = np.bincount(ids)
                    best = np.argsort(-freq, kind="stable")[:listed]
                    least[n].update(dict(zip(w.grams(places[first[best]], n), freq[best].tolist())))
                    if len(least[n]) > 20 * listed:
                        least[n] = Counter(dict(least[n].most_common(10 * listed)))
        rows = [(n, i, t[i : i + BUCKETS_A_ROW].tobytes(), None, None) for n, t in table.items() for i in range(0, BUCKETS, BUCKETS_A_ROW) if t[i : i + BUCKETS_A_ROW].any()]
        rows += [(n, None, None, x, f) for n, c in least.items() for x, f in c.most_common(listed)]
        yield _batch(rows, n=pa.int32(), start=pa.int32(), counts=pa.binary(), gram=pa.string(), freq=pa.int64())

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            for n, start, counts in zip(*[b.column(c).to_pylist() for c in ("n", "start", "counts")]):
                total[n, start] = total.get((n, start), 0) + np.frombuffer(counts, np.int64)
        yield _batch([(*x, t.tobytes()) for x, t in total.items()], n=pa.int32(), start=pa.int32(), counts=pa.binary())

    found = texts.mapInArrow(bounds, "n int, start int, counts binary, gram string, freq long").persist()
    upper = {n: np.zeros(BUCKETS, np.int64) for n in range(2, longest + 1)}
    for r in found.where("counts is not null").select("n", "start", "counts").repartition("n", "start").mapInArrow(add, "n int, start int, counts binary").collect():
        upper[r["n"]][r["start"] : r["start"] + BUCKETS_A_ROW] = np.frombuffer(r["counts"], np.int64)
    low = select_top(found.where("gram is not null").groupBy("n", "gram").agg(F.sum("freq").alias("freq")), k, "n").groupBy("n").agg(F.count("*").alias("got"), F.min("freq").alias("least"))
    reach = {r["n"]: r["least"] for r in low.collect() if r["got"] >= k}
    found.unpersist()
    can = {n: {m: upper[m] >= reach.get(n, 1) for m in range(2, n + 1)} for n in sizes}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds, seen = {"n": pa.int32(), "gram": pa.string(), "freq": pa.int64()}, Counter()
        for b in batches:
            for part in wordarrays.parts_of(b, "text"):
                w = wordarrays.Words(part.column("text"))
                bucket = _buckets(w, longest)
                for n, flags in can.items():
                    places = w.places(n)
                    for m in range(n, 1, -1):
                        for j in range(n - m + 1):
                            places = places[flags[m][bucket[m][places + j]]]
                    if len(places):
                        ids, first = w.same(places, n)
                        seen.update(dict(zip([(n, x) for x in w.grams(places[first], n)], np.bincount(ids).tolist())))
                if len(seen) > 200_000:
                    yield _batch([(*x, f) for x, f in seen.items()], **kinds)
                    seen.clear()
        yield _batch([(*x, f) for x, f in seen.items()], **kinds)

    return texts.mapInArrow(count, "n int, gram string, freq long").groupBy("n", "gram").agg(F.sum("freq").alias("freq"))


def _batch(rows: list[tuple], **kinds: pa.DataType) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * len(kinds), kinds.values())], list(kinds))


def frequency_histogram(freqs: DataFrame) -> DataFrame:
    """Distinct n-grams and occurrences by power of two of the frequency."""
    b = F.floor(F.log2(F.col("freq") + F.lit(0.5))).cast("int")
    h = freqs.groupBy(b.alias("bin")).agg(F.count("*").alias("distinct_grams"), F.sum("freq").alias("occurrences"))
    return h.select("bin", F.pow(F.lit(2), "bin").cast("long").alias("lo"), (F.pow(F.lit(2), F.col("bin") + 1) - 1).cast("long").alias("hi"), "distinct_grams", "occurrences")


def rank_frequency(freqs: DataFrame, k: int) -> DataFrame:
    """The curve of the ``k`` most frequent, ranked after a top-k that sorts no more than k rows for each partition."""
    top = select_top(freqs, k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("freq"), "gram")).cast("long"))


def net_saving(freq: Column, gram: Column, placeholder_cost: int = 2) -> Column:
    from ctxpress.functions.tokens import estimated_tokens

    cost = estimated_tokens(gram)
    return freq * (cost - placeholder_cost) - (cost + placeholder_cost)


def select_top(freqs: DataFrame, k: int, *scope: str, by: str = "frequency") -> DataFrame:
    """The ``k`` best n-grams, of each scope if one is given; ties go to the smaller n-gram."""
    key = F.col("freq") if by == "frequency" else net_saving(F.col("freq"), F.col("gram"))
    f = freqs.withColumn("_key", key)
    f = f.where(F.col("_key") > 0) if by != "frequency" else f
    if not scope:
        return f.orderBy(F.desc("_key"), "gram").limit(k).drop("_key")
    rank = F.row_number().over(Window.partitionBy(*scope).orderBy(F.desc("_key"), "gram"))
    return f.withColumn("_rank", rank).where(F.col("_rank") <= k).drop("_rank", "_key")


def top_by_levels(docs: DataFrame, n: int, k: int) -> DataFrame:
    """Top-k n-grams counting only those that can be frequent: both (n-1)-grams must be as frequent as a k-th candidate.

    The first pass gives a lower bound for the k-th frequency from the most frequent prefixes; the count after the two
    semi joins is exact, so the result equals the plain one while far fewer n-grams are shuffled.
    """
    if n < 2:
        return select_top(ngram_frequencies(docs, n), k)
    shorter = ngram_frequencies(docs, n - 1)
    seeds = select_top(shorter, 4 * k).select(F.col("gram").alias("_p"))
    rows = extract_ngrams(docs, n).withColumn("_p", F.regexp_replace("gram", r" [^ ]+$", "")).withColumn("_s", F.regexp_replace("gram", r"^[^ ]+ ", ""))
    guess = rows.join(F.broadcast(seeds), "_p", "left_semi").groupBy("gram").agg(F.count("*").alias("freq"))
    bound = select_top(guess, k).agg(F.min("freq").alias("least"), F.count("*").alias("got"))
    bound = bound.select(F.when(F.col("got") >= k, F.col("least")).otherwise(1).alias("least"))
    can = shorter.crossJoin(F.broadcast(bound)).where("freq >= least").select("gram")
    rows = rows.join(can.select(F.col("gram").alias("_p")), "_p", "left_semi").join(can.select(F.col("gram").alias("_s")), "_s", "left_semi")
    return select_top(rows.groupBy("gram").agg(F.count("*").alias("freq")), k)


def top_by_sketch(docs: DataFrame, n: int, k: int, tracked: int = 20_000) -> DataFrame:
    """Top-k n-grams by a heavy-hitter sketch and an exact recount of all that it lists; no shuffle of all n-grams.

    What the sketch of ``tracked`` items does not list occurs at most 8 * occurrences / tracked times: twice its error, as it
    lists only what is frequent for certain. If the k-th recounted frequency is above that, no other n-gram can even tie with
    it; otherwise the plain count decides.
    """
    grams = extract_ngrams(docs, n)
    found = grams.agg(F.expr(f"approx_top_k(gram, {tracked}, {tracked})").alias("t"), F.count("*").alias("n")).first()
    names = [(r["item"],) for r in found["t"]]
    if len(names) >= k:
        spark = docs.sparkSession
        exact = grams.join(F.broadcast(spark.createDataFrame(names, "gram string")), "gram", "left_semi").groupBy("gram").agg(F.count("*").alias("freq"))
        top = select_top(exact, k)
        if top.agg(F.min("freq")).first()[0] > 8 * found["n"] / tracked:
            return top
    return select_top(ngram_frequencies(docs, n), k)


def placeholder(c: Column) -> Column:
    """AA1, AB1, …, ZZ1, AA2, …"""
    letter = lambda v: F.chr(F.lit(65) + v)
    return F.concat(letter(F.floor((c % 676) / 26)), letter(c % 26), (F.floor(c / 676) + 1).cast("string"))


def build_dictionary(top: DataFrame, docs: DataFrame) -> DataFrame:
    """(placeholder, gram, freq, rank): the r-th n-gram gets the r-th placeholder that no text has as a word.

    There are as many candidates as n-grams and used placeholders together, so no n-gram is left without one.
    """
    spark = top.sparkSession
    used = docs.select(F.explode(F.array_distinct(words(F.col("text")))).alias("placeholder")).where(F.col("placeholder").rlike("^[A-Z]{2}[0-9]+$")).distinct()
    candidates = spark.range(top.count() + used.count()).select("id", placeholder(F.col("id")).alias("placeholder"))
    free = candidates.join(used, "placeholder", "left_anti")
    free = free.withColumn("rank", F.row_number().over(Window.orderBy("id")).cast("long")).drop("id")
    ranked = top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("freq"), "gram")).cast("long"))
    return ranked.join(free, "rank").select("placeholder", "gram", "freq", "rank")


def as_mapping(dictionary: DataFrame, most: int = 100_000) -> dict[str, str]:
    """n-gram to placeholder on the driver; a dictionary is small by definition, and this is checked."""
    rows = dictionary.select("gram", "placeholder").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("dictionary too large to broadcast")
    return {r["gram"]: r["placeholder"] for r in rows}


class Codec:
    """Replaces whole words only, between single blanks; the longest n-gram at the leftmost place wins by default."""

    def __init__(self, mapping: dict[str, str], overlap: str = "leftmost_longest", freq: dict[str, int] | None = None):
        self.mapping, self.overlap, self.freq = mapping, overlap, freq or {}

    _words = regex.compile(WORD)

    def _pattern(self, parts: list[str]):
        return regex.compile(r"(?<![\p{L}\p{M}\p{N}_])(?:" + "|".join(map(regex.escape, parts)) + r")(?![\p{L}\p{M}\p{N}_])")

    def encoder(self):
        m = self.mapping
        if not m:
            return lambda t: t
        names = set(m.values())
        clash = lambda t: t is not None and (ESCAPE in t or any(w in names for w in self._words.findall(t)))
        if self.overlap == "leftmost_longest":
            return self._scan
        if self.overlap == "frequency_first":  # one n-gram after the other over the whole text, the most frequent first
            ps = [(self._pattern([g]), m[g]) for g in sorted(m, key=lambda g: (-self.freq.get(g, 0), g))]

            def f(t):
                if clash(t):
                    return self._scan(t)
                for p, r in ps if t is not None else ():
                    t = p.sub(r, t)
                return t

            return f
        return lambda t: self._scan(t) if clash(t) else self._best_cover(t)

    def _scan(self, t: str | None) -> str | None:
        """One pass over the words: at each, the longest n-gram whose surface is in the dictionary."""
        if t is None:
            return None
        m, sizes, names = self.mapping, sorted({g.count(" ") for g in self.mapping}, reverse=True), set(self.mapping.values())
        spans = [x.span() for x in self._words.finditer(t)]
        out, last, i, n = [], 0, 0, len(spans)
        while i < n:
            start = spans[i][0]
            if t[start : spans[i][1]] in names:  # a word of the text that looks like a placeholder
                out += (t[last:start], ESCAPE)
                last = start
            for k in sizes if t[start - 1 : start] != ESCAPE else ():
                if i + k < n and (short := m.get(t[start : spans[i + k][1]])) is not None:
                    out += (t[last:start], short)
                    last = spans[i + k][1]
                    i += k
                    break
            i += 1
        out.append(t[last:])
        return "".join(out)

    def _best_cover(self, t: str | None) -> str | None:
        """The cover that saves most words: a dynamic programme over the places where n-grams match."""
        if t is None:
            return None
        found = [[] for _ in range(len(t) + 1)]
        for g in self.mapping:
            for x in self._pattern([g]).finditer(t, overlapped=True):
                found[x.start()].append((x.end(), g.count(" "), g))
        best, pick = [0] * (len(t) + 1), [None] * (len(t) + 1)
        for i in range(len(t) - 1, -1, -1):
            best[i] = best[i + 1]
            for end, saved, g in found[i]:
                if saved + best[end] > best[i]:
                    best[i], pick[i] = saved + best[end], (end, g)
        out, i = [], 0
        while i < len(t):
            if pick[i]:
                out.append(self.mapping[pick[i][1]])
                i = pick[i][0]
            else:
                out.append(t[i])
                i += 1
        return "".join(out)

    def decoder(self):
        back = {v: k for k, v in self.mapping.items()}
        p = regex.compile(f"({ESCAPE}?)({WORD})")

        def one(x):
            if x[2] not in back:
                return x[0]
            return x[2] if x[1] else back[x[2]]

        return lambda t: None if t is None else p.sub(one, t)


def _apply(docs: DataFrame, make, text_col: str, out_col: str) -> DataFrame:
    @F.pandas_udf("string")
    def run(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        f = make()
        for s in parts:
            yield s.map(f, na_action="ignore")

    return docs.withColumn(out_col, run(F.col(text_col)))


def abbreviate(docs: DataFrame, mapping: dict[str, str], text_col: str = "text", out_col: str = "short", overlap: str = "leftmost_longest", freq: dict[str, int] | None = None) -> DataFrame:
    """Adds the abbreviated text; one compiled pattern for each task, no shuffle."""
    return _apply(docs, Codec(mapping, overlap, freq).encoder, text_col, out_col)


def restore(docs: DataFrame, mapping: dict[str, str], text_col: str = "short", out_col: str = "restored") -> DataFrame:
    return _apply(docs, Codec(mapping).decoder, text_col, out_col)


def abbreviate_and_restore(docs: DataFrame, mapping: dict[str, str]) -> DataFrame:
    """Adds short and, from it, restored; both in one pass over the texts."""

    def f(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec = Codec(mapping)
        there, back = codec.encoder(), codec.decoder()
        for p in parts:
            short = p["text"].map(there, na_action="ignore")
            yield p.assign(short=short, restored=short.map(back, na_action="ignore"))

    kinds = ", ".join(f"`{c}` {t}" for c, t in docs.dtypes)
    return docs.mapInPandas(f, f"{kinds}, short string, restored string")


def _one_of(parts: list[str], before: str = "") -> str:
    """A pattern for whole words that are one of ``parts``, the longest first, none after a character of ``before``."""
    edge = r"\p{L}\p{M}\p{N}_"
    return rf"(?<![{edge}{before}])(?:" + "|".join(rf"\Q{p}\E" for p in sorted(parts, key=lambda p: (-len(p), p))) + rf")(?![{edge}])"


def abbreviate_native(text: Column, mapping: dict[str, str], freq: dict[str, int] | None = None) -> Column:
    """The text with one n-gram after the other replaced, the most frequent first, by built-in functions only.

    For dictionaries of some dozen entries: each is a pass over the text. ``restore`` and ``restore_native`` both undo it.
    """
    if not mapping:
        return text
    out = F.regexp_replace(text, f"({_one_of(list(mapping.values()))})", f"{ESCAPE}$1")
    for g in sorted(mapping, key=lambda g: (-(freq or {}).get(g, 0), g)):
        out = F.regexp_replace(out, _one_of([g], ESCAPE), mapping[g])
    return out


def restore_native(short: Column, mapping: dict[str, str]) -> Column:
    """The original of an abbreviated text by built-in functions only, one pass for each entry."""
    out = short
    for g, name in mapping.items():
        out = F.regexp_replace(out, _one_of([name], ESCAPE), g)
    return F.regexp_replace(out, f"{ESCAPE}({_one_of(list(mapping.values()))})", "$1") if mapping else out


def abbreviate_each(docs: DataFrame, n: int, k: int) -> DataFrame:
    """Adds short and used: every text by its own ``k`` most frequent repeated n-grams, all within the row."""

    def f(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        word = regex.compile(r"[A-Z]{2}[0-9]+")
        for p in parts:
            shorts, used = [], []
            for t in p["text"]:
                top = own_dictionary(t or "", n, k)
                taken, names, i = set(word.findall(t or "")), [], 0
                while len(names) < len(top):
                    name = f"{chr(65 + i % 676 // 26)}{chr(65 + i % 26)}{i // 676 + 1}"
                    if name not in taken:
                        names.append(name)
                    i += 1
                shorts.append(Codec(dict(zip(top, names))).encoder()(t))
                used.append([{"placeholder": a, "gram": g} for g, a in zip(top, names)])
            yield p.assign(short=shorts, used=used)

    kinds = ", ".join(f"`{c}` {t}" for c, t in docs.dtypes)
    return docs.mapInPandas(f, f"{kinds}, short string, used array<struct<placeholder:string,gram:string>>")


def greedy_count(tokens: Column, gram: list[str]) -> Column:
    """Occurrences of ``gram`` that a left-to-right scan can replace, none overlapping, as an in-row fold."""
    n = len(gram)
    at = F.filter(F.transform(ngrams(tokens, n), lambda g, i: F.when(g == " ".join(gram), i)), lambda i: i.isNotNull())
    start = F.struct(F.lit(0).alias("n"), F.lit(-1).alias("free"))
    return F.aggregate(at, start, lambda a, i: F.when(i > a["free"], F.struct((a["n"] + 1).alias("n"), (i + (n - 1)).alias("free"))).otherwise(a))["n"].cast("long")


def dictionary_header(dictionary: DataFrame) -> DataFrame:
    """One row: the dictionary as a line of context for a prompt, in order of rank."""
    pairs = F.array_sort(F.collect_list(F.struct("rank", F.concat_ws("=", "placeholder", "gram").alias("entry"))))
    return dictionary.agg(F.array_join(F.transform(pairs, lambda x: x["entry"]), "; ").alias("header"))


def search_abbreviated(docs: DataFrame, mapping: dict[str, str], phrase: str, short_col: str = "short") -> DataFrame:
    """Documents whose original has ``phrase`` as whole words, found on the abbreviated text.

    The scan keeps what has a word of the phrase or any placeholder whose n-gram has one; only that is restored to verify.
    """
    parts = set(regex.findall(WORD, phrase))
    hits = [a for g, a in mapping.items() if parts & set(g.split(" "))]
    could = F.lit(False)
    for p in [max(parts, key=len), *hits] if parts else []:
        could = could | F.contains(F.col(short_col), F.lit(p))
    found = restore(docs.where(could), mapping, short_col, "_restored")
    edge = r"[\p{L}\p{M}\p{N}_]"
    return found.where(F.col("_restored").rlike(rf"(?<!{edge})\Q{phrase}\E(?!{edge})")).drop("_restored")


def own_dictionary(text: str, n: int, k: int) -> list[str]:
    """The ``k`` most frequent n-grams that a text repeats, by what the codec could replace."""
    from collections import Counter

    c: Counter = Counter()
    for r in regex.findall(rf"{WORD}(?: {WORD})*", text):
        w = r.split(" ")
        c.update(" ".join(w[i : i + n]) for i in range(len(w) - n + 1))
    return [g for g, x in sorted(c.items(), key=lambda e: (-e[1], e[0]))[:k] if x > 1]


def abbreviation_effects(docs: DataFrame, ranked: dict[int, list[str]], tops: tuple[int, ...], scopes: tuple[str, ...] = ("corpus", "document")) -> DataFrame:
    """(doc_id, scope, g, t, words_before, words_after, cosine, lost): what each setting does to each text, in one pass over the texts.

    ``ranked`` has the corpus's n-grams of each length, best first; in scope ``document`` a text has a dictionary of its own.
    ``cosine`` is that of lower-case word counts, null without words; ``lost`` are the distinct lower-case words that occur in the text but no longer in its abbreviation.
    """

    def f(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from collections import Counter

        word = regex.compile(WORD)
        shared = {g: {tuple(x.split(" ")): i for i, x in enumerate(grams)} for g, grams in ranked.items()}
        most, names_of = max(tops), ["doc_id", "scope", "g", "t", "words_before", "words_after", "cosine", "lost"]
        for p in parts:
            rows = []
            for doc, text in zip(p["doc_id"], p["text"]):
                text = text or ""
                runs, fixed, last = [], [], -1  # words with single blanks between them; whether an escape stands before a run
                for x in word.finditer(text):
                    if runs and x.start() == last + 1 and text[last] == " ":
                        runs[-1].append(x[0])
                    else:
                        runs.append([x[0]])
                        fixed.append(text[x.start() - 1 : x.start()] == ESCAPE)
                    last = x.end()
                low = Counter(w.lower() for r in runs for w in r)
                many, size = sum(map(len, runs)), sum(v * v for v in low.values())
                for g in ranked:
                    places = {"corpus": shared[g]}
                    if "document" in scopes:
                        c = Counter()
                        for r in runs:
                            c.update(zip(*[r[i:] for i in range(g)]))
                        own = sorted((-n, " ".join(x), x) for x, n in c.items() if n > 1)[:most]
                        places["document"] = {x: i for i, (_, _, x) in enumerate(own)}
                    found = {}
                    for scope in scopes:
                        rank = places[scope]
                        found[scope] = [(k, i, rank[x]) for k, r in enumerate(runs) for i, x in enumerate(zip(*[r[j:] for j in range(g)])) if x in rank and not (i == 0 and fixed[k])]
                    for t in tops:
                        for scope in scopes:
                            gone, names, end = Counter(), Counter(), (-1, 0)  # a scan from the left, no two overlapping
                            for k, i, rank in found[scope]:
                                if rank < t and not (k == end[0] and i < end[1]):
                                    end = (k, i + g)
                                    gone.update(w.lower() for w in runs[k][i : i + g])
                                    names[f"zq{rank}qz"] += 1
                            moved = Counter(names)
                            moved.subtract(gone)
                            after = many + sum(moved.values())
                            square = size + sum((low[w] + v) ** 2 - low[w] ** 2 for w, v in moved.items())
                            norm = (size * square) ** 0.5
                            cosine = (size + sum(low[w] * v for w, v in moved.items())) / norm if norm else None
                            rows.append((doc, scope, g, t, many, after, cosine, sorted(w for w, v in moved.items() if low[w] and low[w] + v == 0)))
                if len(rows) >= 20_000:
                    yield pd.DataFrame(rows, columns=names_of)
                    rows = []
            yield pd.DataFrame(rows, columns=names_of)

    return docs.select("doc_id", "text").mapInPandas(f, "doc_id long, scope string, g int, t int, words_before long, words_after long, cosine double, lost array<string>")


class Settings:
    """What every setting of the ablation replaces in many texts at once, as ``abbreviation_effects`` finds it text by text."""

    def __init__(self, ranked: dict[int, list[str]], tops: tuple[int, ...], scopes: tuple[str, ...] = ("corpus", "document")):
        self.ranked, self.tops, self.scopes = {g: [x.split(" ") for x in grams] for g, grams in ranked.items()}, tops, scopes
        self.words = sorted({x for grams in self.ranked.values() for words in grams for x in words})
        self.names = [(s, g, t) for g in ranked for s in scopes for t in tops if s != "corpus" or ranked[g]]

    def replaced(self, w: wordarrays.Words) -> Iterator[tuple[tuple[str, int, int], np.ndarray]]:
        """(setting, places): where the n-grams begin that it replaces. Words have been read with the escape as their mark."""
        own = {n: x for n, *x in w.repeated(max(self.ranked))} if "document" in self.scopes else {}
        place = pc.fill_null(pc.index_in(w.names, value_set=pa.array(self.words, w.names.type)), -1).to_numpy(zero_copy_only=False)
        ids = {self.words[place[i]]: i for i in np.flatnonzero(place >= 0)}
        for g, grams in self.ranked.items():
            for scope in self.scopes:
                places, rank = self._shared(w, g, [[ids.get(x, -1) for x in words] for words in grams]) if scope == "corpus" else self._own(w, g, *own[g])
                clear = ~w.marked[places]  # an n-gram right after an escape stays
                places, rank = places[clear], rank[clear]
                for t in self.tops if scope != "corpus" or grams else ():
                    yield (scope, g, t), wordarrays.spaced(places[rank < t], g)

    @staticmethod
    def _shared(w: wordarrays.Words, g: int, grams: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
        places, rank = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for r, ids in enumerate(grams):  # -1 is no word of these texts
            p = np.flatnonzero(w.word == ids[0])
            p = p[p + g <= len(w)]
            for j in range(1, g):
                p = p[w.tight[p + j - 1] & (w.word[p + j] == ids[j])]
            places.append(p)
            rank.append(np.full(len(p), r))
        places, rank = np.concatenate(places), np.concatenate(rank)
        order = np.argsort(places)
        return places[order], rank[order]

    def _own(self, w: wordarrays.Words, g: int, places: np.ndarray, ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each text's own: its most frequent first, the smaller n-gram on a tie."""
        if not len(first):
            return places, ids
        at, freq = places[first], np.bincount(ids)
        order = np.lexsort((*(w.word[at + j] for j in reversed(range(g))), -freq, w.doc[at]))
        doc = w.doc[at][order]
        rank = np.empty(len(order), dtype=np.int64)
        rank[order] = np.arange(len(order)) - np.searchsorted(doc, doc)
        some = rank[ids] < max(self.tops)
        return places[some], rank[ids][some]
