"""Language of texts and of the stretches inside them.

The script of a word's letters narrows the languages that it can be in to those that were seen in that script. Each remaining
language scores the word by its character n-grams, and the best sequence of languages over all words of a text, with a
penalty for every switch, labels the stretches. A text is in the language that most of its letters are in, or in that of its
opening quarter if enough letters are; how many are enough is learned with the rest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.llm.common import Local, text_parts
from ctxpress.llm.toxicity import blocks

GRAMS, BUCKETS, SWITCH, BLOCK, PART = (2, 3, 4), 1 << 15, 8.0, 3 << 19, 1 << 17
UNKNOWN = "und"
# First and last code point of the main blocks of each script.
SCRIPTS = {
    "latin": [(0x41, 0x24F), (0x1E00, 0x1EFF), (0x2C60, 0x2C7F), (0xA720, 0xA7FF), (0xFF21, 0xFF5A)],
    "greek": [(0x370, 0x3FF), (0x1F00, 0x1FFF)],
    "cyrillic": [(0x400, 0x52F), (0x1C80, 0x1C8F), (0x2DE0, 0x2DFF), (0xA640, 0xA69F)],
    "armenian": [(0x530, 0x58F)],
    "hebrew": [(0x590, 0x5FF)],
    "arabic": [(0x600, 0x6FF), (0x750, 0x77F), (0x8A0, 0x8FF), (0xFB50, 0xFDFF), (0xFE70, 0xFEFF)],
    "devanagari": [(0x900, 0x97F)],
    "bengali": [(0x980, 0x9FF)],
    "tamil": [(0xB80, 0xBFF)],
    "thai": [(0xE00, 0xE7F)],
    "georgian": [(0x10A0, 0x10FF)],
    "ethiopic": [(0x1200, 0x137F)],
    "hangul": [(0x1100, 0x11FF), (0x3130, 0x318F), (0xAC00, 0xD7AF)],
    "kana": [(0x3040, 0x30FF), (0x31F0, 0x31FF)],
    "han": [(0x3400, 0x4DBF), (0x4E00, 0x9FFF), (0xF900, 0xFAFF), (0x20000, 0x3134F)],
}
OTHER = len(SCRIPTS) + 1

_table = Local()


def script_table() -> np.ndarray:
    """For each code point 0 if it is no letter, else the number of its script."""
    if "table" not in _table:
        letter = np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)
        t = np.where(letter, OTHER, 0).astype(np.uint8)
        for i, ranges in enumerate(SCRIPTS.values(), 1):
            for lo, hi in ranges:
                t[lo : hi + 1][letter[lo : hi + 1]] = i
        _table["table"] = t
    return _table["table"]


def code_points(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Lower-case texts as code points with one space around each word, and the number of words of each text."""
    words = [(t or "").lower().split() for t in texts]
    joined = " " + " ".join(" ".join(w) for w in words if w) + " "
    return np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32), np.array([len(w) for w in words], np.int64)


def word_parts(c: np.ndarray, total: int) -> Iterator[tuple[int, int, np.ndarray]]:
    """(first word, word after the last, code points with the spaces on both sides) of stretches of about PART code points."""
    at = np.flatnonzero(c == 32)[: total + 1]
    first = np.flatnonzero(np.r_[True, at[1:-1] // PART != at[:-2] // PART]) if total else []
    for lo, hi in zip(first, [*first[1:], total]):
        yield int(lo), int(hi), c[at[lo] : at[hi] + 1]


def grams(c: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(place of the length, bucket, word) of all n-grams inside single words, in order."""
    spaces = np.cumsum(c == 32, dtype=np.int32)
    h = c.copy()
    for n in range(2, max(GRAMS) + 1):
        if len(c) < n:
            return
        h = h[:-1] * np.uint32(0x01000193) + c[n - 1 :]
        if n in GRAMS:
            ok = spaces[n - 2 : len(c) - 1] == spaces[: len(c) - n + 1]
            if n == 2:
                ok = ok & ~((c[:-1] == 32) & (c[1:] == 32))
            ok = np.flatnonzero(ok)
            x = h[ok] * np.uint32(0x9E3779B1)
            yield GRAMS.index(n), (x ^ (x >> np.uint32(16))) & np.uint32(BUCKETS - 1), spaces[ok] - 1


def word_scripts(c: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    """Script and number of letters of each word; script 0: no letter."""
    s = script_table()[np.minimum(c, 0x10FFFF)]
    word = np.cumsum(c == 32) - 1
    at = np.flatnonzero(s)
    letters = np.bincount(word[at], minlength=total)[:total]
    script = np.zeros(total, np.uint8)
    script[word[at][::-1]] = s[at][::-1]  # that of the first letter
    return script, letters


class LanguageModel:
    def __init__(self, names: list[str], tables: np.ndarray, allowed: np.ndarray, prior: np.ndarray, opening: float = 0.5):
        self.names, self.tables, self.allowed, self.prior, self.opening = names, tables, allowed, prior, opening

    def emissions(self, c: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each word the score in each language, whether any language is a candidate, and its letters."""
        e = np.zeros((total, len(self.names)), np.float32)
        script, letters = np.zeros(total, np.uint8), np.zeros(total, np.int64)
        for lo, hi, part in word_parts(c, total):
            for k, bucket, word in grams(part):
                if len(word):
                    at = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
                    e[lo + word[at]] += np.add.reduceat(self.tables[k][bucket], at, axis=0)
            script[lo:hi], letters[lo:hi] = word_scripts(part, hi - lo)
        can = self.allowed[script]
        known = can.any(1) & (script > 0)
        e = np.where(can | ~known[:, None], e, e.min(1, keepdims=True) - np.float32(1e4))
        e[~known] = 0
        return e, known, letters

    def label(self, texts: list[str | None], switch: float = SWITCH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Language of each word by the best path (-1: none is a candidate), words of each text, letters of each word."""
        c, counts = code_points(texts)
        total = int(counts.sum())
        e, known, letters = self.emissions(c, total)
        start = np.cumsum(counts) - counts
        order = np.argsort(-counts, kind="stable")
        start, counts_, n = start[order], counts[order], len(self.names)
        active = np.searchsorted(-counts_, -np.arange(int(counts.max()) if len(counts) else 0), "left")
        v = np.zeros((len(texts), n), np.float32)
        back = np.empty((total, n), np.int8)
        own = np.arange(n, dtype=np.int8)
        for t, a in enumerate(active):
            x, at = v[:a], start[:a] + t
            best = x.argmax(1)
            jump = x[np.arange(a), best] - np.float32(switch)
            stay = x >= jump[:, None]
            back[at] = np.where(stay, own, best[:, None].astype(np.int8))
            v[:a] = np.where(stay, x, jump[:, None]) + e[at]
        path = np.empty(total, np.int8)
        now = v.argmax(1).astype(np.int8)
        for t in range(len(active) - 1, -1, -1):
            at = start[: active[t]] + t
            path[at] = now[: active[t]]
            now[: active[t]] = back[at, now[: active[t]]]
        return np.where(known, path, -1), counts, letters

    def shares(self, path: np.ndarray, counts: np.ndarray, letters: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Letters of each text in each language, all its letters, and the language that its first half opens in."""
        doc, n = np.repeat(np.arange(len(counts)), counts), len(self.names)
        share = np.zeros((len(counts), n))
        ok = path >= 0
        np.add.at(share, (doc[ok], path[ok]), letters[ok])
        start = np.cumsum(counts) - counts
        early = ok & (np.arange(len(path)) - start[doc] <= counts[doc] // 4)
        front = np.zeros((len(counts), n))
        np.add.at(front, (doc[early], path[early]), letters[early])
        return share, np.bincount(doc, letters, len(counts)), front.argmax(1)

    def decide(self, share: np.ndarray, every: np.ndarray, front: np.ndarray, opening: float) -> np.ndarray:
        row = np.arange(len(share))
        most = share.argmax(1)
        best = np.where(share[row, front] >= opening * np.maximum(every, 1), front, most)
        return np.where(share.any(1), best, self.prior.argmax())

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, list[list[dict]]]:
        """Language, share of letters in it, and stretches (lang, first word, words) of each text."""
        path, counts, letters = self.label(texts)
        doc = np.repeat(np.arange(len(texts)), counts)
        share, every, front = self.shares(path, counts, letters)
        best = self.decide(share, every, front, self.opening)
        score = share[np.arange(len(texts)), best] / np.maximum(every, 1)
        names = [self.names[b] if m else UNKNOWN for b, m in zip(best, every > 0)]
        turn = np.flatnonzero(np.r_[True, (path[1:] != path[:-1]) | (doc[1:] != doc[:-1])]) if len(path) else np.zeros(0, int)
        size, first = np.diff(np.r_[turn, len(path)]), np.cumsum(counts) - counts
        spans: list[list[dict]] = [[] for _ in texts]
        for i, m in zip(turn.tolist(), size.tolist()):
            spans[doc[i]].append({"lang": self.names[path[i]] if path[i] >= 0 else UNKNOWN, "first_word": i - int(first[doc[i]]), "words": m})
        return names, np.where(every > 0, score, 0.0), spans


def train(texts: list[str], langs: list[str], smoothing: float = 0.5, weight: float = 0.35) -> LanguageModel:
    """Hashed n-gram frequencies of each language, as scores relative to their mean over languages."""
    names = sorted(set(langs)) or [UNKNOWN]
    tables = np.zeros((len(GRAMS), BUCKETS, len(names)), np.float64)
    seen = np.zeros((OTHER + 1, len(names)))
    for j, name in enumerate(names):
        mine = [t for t, g in zip(texts, langs) if g == name]
        for lo, hi in blocks(mine, BLOCK):
            c, counts = code_points(mine[lo:hi])
            for k, bucket, _ in grams(c):
                tables[k, :, j] += np.bincount(bucket, minlength=BUCKETS)
            seen[:, j] += np.bincount(script_table()[np.minimum(c, 0x10FFFF)], minlength=OTHER + 1)
    tables = np.log((tables + smoothing) / (tables + smoothing).sum(1, keepdims=True))
    tables = (tables - tables.mean(2, keepdims=True)) * weight
    seen[0] = 0
    allowed = seen > 0.01 * np.maximum(seen.sum(0), 1)
    prior = np.array([langs.count(n) for n in names], float)
    model = LanguageModel(names, tables.astype(np.float32), allowed, prior)
    right = {o: 0 for o in (0.5, 0.45, 0.4, 0.35, 0.3, 0.25)}
    for lo, hi in blocks(texts, BLOCK):
        found = model.shares(*model.label(texts[lo:hi]))
        for o in right:
            right[o] += sum(names[b] == g for b, g in zip(model.decide(*found, o), langs[lo:hi]))
    model.opening = max(right, key=lambda o: (right[o], o))
    return model


def labelled_sample(docs: DataFrame, most: int = 4000) -> tuple[list[str], list[str]]:
    """At most about ``most`` texts, as many of each language, picked by hash of doc_id outside the held-out rows."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) != 0))
    counts = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    each, share = max(20, most // max(1, len(counts))), F.lit(0)
    for k, n in counts.items():
        share = F.when(F.col("lang") == k, F.lit(int(1_000_000 * min(1.0, each / n)))).otherwise(share)
    got = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1_000_000)) < share).select("doc_id", "text", "lang").collect()
    got = sorted((r["doc_id"], r["text"], r["lang"]) for r in got)
    return [t for _, t, _ in got], [g for _, _, g in got]


SPANS = "array<struct<lang:string,first_word:int,words:int>>"


def identify_language(docs: DataFrame, model: LanguageModel, spans: bool = False) -> DataFrame:
    """(doc_id, lang_pred, score) for every row, and spans if asked for; null and letterless texts are ``und`` with score 0."""

    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("lang", pa.string()), ("first_word", pa.int32()), ("words", pa.int32())]))
        for b in batches:
            for lo, texts in text_parts(b.column(1), BLOCK):
                names, score, found = model.predict(texts)
                cols = [b.column(0).slice(lo, len(texts)), pa.array(names, pa.string()), pa.array(score)]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(found, kind)] if spans else cols, names=["doc_id", "lang_pred", "score", "spans"][: 3 + spans])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(f, f"doc_id {kind}, lang_pred string, score double" + f", spans {SPANS}" * spans)


def keep_identified(docs: DataFrame, model: LanguageModel, least: float = 0.2) -> DataFrame:
    """``docs`` without the rows whose text is ``und`` or has less than ``least`` of its letters in its language."""
    at = docs.columns.index("text")

    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, texts in text_parts(b.column(at), BLOCK):
                names, score, _ = model.predict(texts)
                keep = [n != UNKNOWN and s >= least for n, s in zip(names, score)]
                yield b.slice(lo, len(texts)).filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(f, docs.schema)


def op3_language_id(spark, sf_dir: str) -> DataFrame:
    """A language for every row of ``documents``; ``und`` where a text is null or has no letter, ties go to the language first in code point order, no rows give none."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0, F.lit(False))
    return identify_language(docs, train(*labelled_sample(docs))).select("doc_id", held.alias("held_out"), "lang_pred", "score")
