"""Benchmark passages in training documents, found by spaced seeds and verified word by word.

A seed looks at some words of a short span and ignores the others, so a substituted word does not hide a hit. The masks are
chosen so that every window of ``window`` words with no more than ``misses`` substitutions holds a clean seed of one of them.
Hits of the same document, item and diagonal are laid over each other once; they count where some window of the item agrees
with the document in at least ``share`` of its words. Items shorter than a window have to agree in full.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.llm.suffix_dedup import BASES, powers, scramble
from ctxpress.llm.common import Local, text_parts

WINDOW, SHARE, WEIGHT = 12, 0.8, 5
BLOCK = 1 << 20
FILTER = 1 << 22

_alnum = Local()


def alnum_table() -> np.ndarray:
    if "table" not in _alnum:
        _alnum["table"] = np.fromiter((chr(c).isalnum() for c in range(0x110000)), bool, 0x110000)
    return _alnum["table"]


def seed_masks(window: int, misses: int, weight: int) -> list[tuple[int, ...]]:
    """Few masks such that any ``misses`` bad places in a window leave a place where one of them is clean (greedy cover)."""
    masks = [(0, *m) for m in combinations(range(1, window - 1), weight - 1)]
    open_ = list(combinations(range(window), misses))
    covers = {m: frozenset(b for b in open_ if any(not any(i - s in m for i in b) for s in range(window - m[-1]))) for m in masks}
    todo, out = set(open_), []
    while todo:
        best = max(masks, key=lambda m: (len(covers[m] & todo), -m[-1], m))
        if not covers[best] & todo:
            raise ValueError("no seeds of this weight can cover the window")
        out.append(best)
        todo -= covers[best]
    return out


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all lower-case alphanumeric words, text after text, and the first word of each text (and the end)."""
    low = [(t or "").lower() for t in texts]
    c = np.frombuffer("\n".join(["", *low, ""]).encode("utf-32-le", "surrogatepass"), np.uint32)
    inside = alnum_table()[np.minimum(c, 0x10FFFF)]
    turn = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    lo, hi = turn[::2], turn[1::2]
    _, up, down = powers(0, len(c) + 1)
    q = np.zeros(len(c) + 1, np.uint64)
    np.cumsum(scramble(c.astype(np.uint64) * np.uint64(BASES[1])) * up[: len(c)], out=q[1:])
    h = scramble((q[hi] - q[lo]) * down[lo])
    edge = np.r_[1, 1 + np.cumsum([len(t) + 1 for t in low])] if low else np.array([1])
    return h, np.searchsorted(lo, edge)


def seeds(h: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    n = len(h) - mask[-1]
    if n <= 0:
        return h[:0]
    out = np.full(n, np.uint64(len(mask)), np.uint64)
    for k, i in enumerate(mask):
        out = scramble(out + h[i : i + n] * np.uint64(BASES[k % 2]))
    return out


class SeedIndex:
    """Seeds of the items, by mask: sorted hashes with the item and place of each, and a bit table that most words miss."""

    def __init__(self, ids: list, texts: list[str | None], window: int = WINDOW, share: float = SHARE, weight: int = WEIGHT):
        self.ids, self.window, self.share = np.array(ids, np.int64), window, share
        self.h, self.first = word_hashes(texts)
        size = np.diff(self.first)
        masks = {m: size >= window for m in seed_masks(window, window - int(np.ceil(share * window)), weight)}
        for n in np.unique(size[(size > 0) & (size < window)]):
            masks[tuple(range(n))] = size == n
        self.masks = []
        for mask, who in masks.items():
            hs, item, at = [], [], []
            for k in np.flatnonzero(who):
                s = seeds(self.h[self.first[k] : self.first[k + 1]], mask)
                hs.append(s)
                item.append(np.full(len(s), k))
                at.append(np.arange(len(s)))
            if hs:
                hs, item, at = np.concatenate(hs), np.concatenate(item), np.concatenate(at)
                order = np.argsort(hs, kind="stable")
                self.masks.append((mask, hs[order], item[order], at[order]))

    def _table(self, k: int) -> np.ndarray:
        cache = self.__dict__.setdefault("_bits", {})
        if k not in cache:
            cache[k] = np.zeros(FILTER, bool)
            cache[k][self.masks[k][1] & np.uint64(FILTER - 1)] = True
        return cache[k]

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_bits"}

    def find(self, texts: list[str | None]) -> list[tuple[int, int, int, int, float]]:
        """(text, item, words that agree, first word of the overlap in the text, best window share) of what counts."""
        h, first = word_hashes(texts)
        size = np.diff(self.first)
        got = []
        for k, (mask, hs, item, at) in enumerate(self.masks):
            s = seeds(h, mask)
            pos = np.flatnonzero(self._table(k)[s & np.uint64(FILTER - 1)])
            lo, hi = np.searchsorted(hs, s[pos]), np.searchsorted(hs, s[pos], "right")
            n = hi - lo
            e = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(n.sum())
            p = np.repeat(pos, n)
            doc = np.searchsorted(first, p, "right") - 1
            ok = p + mask[-1] < first[doc + 1]
            got.append(np.stack([doc[ok], item[e][ok], (p - at[e])[ok]], 1))
        if not got:
            return []
        best: dict = {}
        for doc, item, diagonal in np.unique(np.concatenate(got), axis=0).tolist():
            a, b = max(0, first[doc] - diagonal), min(size[item], first[doc + 1] - diagonal)
            w = min(self.window, int(size[item]))
            if b - a < w:
                continue
            same = self.h[self.first[item] + a : self.first[item] + b] == h[diagonal + a : diagonal + b]
            run = np.r_[0, np.cumsum(same)]
            top = (run[w:] - run[:-w]).max() / w
            if top >= (self.share if w == self.window else 1.0):
                found = (doc, item, int(run[-1]), int(diagonal + a - first[doc]), float(top))
                best[doc, item] = max(best.get((doc, item), found), found, key=lambda x: (x[2], x[4], -x[3]))
        return sorted(best.values())


def find_leaks(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: float = SHARE, most_bytes: int = 32 << 20) -> DataFrame:
    """(doc_id, item_id, words, at_word, similarity): one row for each document and benchmark item that it holds.

    ``benchmark`` has item_id and text, ``docs`` has doc_id and text. Null and empty texts hold nothing and are held by
    nothing. The items go to all executors; a benchmark of more than ``most_bytes`` is split, and the documents are read
    once for each part.
    """
    out = None
    for index in indexes(benchmark, window, share, most_bytes):
        found = _scan(docs, index)
        out = found if out is None else out.unionAll(found)
    return out


def indexes(benchmark: DataFrame, window: int = WINDOW, share: float = SHARE, most_bytes: int = 32 << 20) -> Iterator[SeedIndex]:
    """The index of the whole benchmark, or one for each part of at most about ``most_bytes``."""
    total = benchmark.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = int(-(-total // most_bytes)) or 1
    fit = benchmark.where("item_id is not null and text is not null").select("item_id", "text")
    for k in range(parts):
        items = sorted((r["item_id"], r["text"]) for r in fit.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k).collect())
        yield SeedIndex([i for i, _ in items], [t for _, t in items], window, share)


def _scan(docs: DataFrame, index: SeedIndex) -> DataFrame:
    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: list = []
            for lo, texts in text_parts(b.column(1), BLOCK):
                rows += [(lo + d, int(index.ids[i]), n, at, s) for d, i, n, at, s in index.find(texts)]
            cols = list(zip(*rows)) or [[]] * 5
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.float64())
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(cols[0], pa.int64())), *[pa.array(c, k) for c, k in zip(cols[1:], kinds)]], names=["doc_id", "item_id", "words", "at_word", "similarity"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(f, f"doc_id {kind}, item_id long, words int, at_word int, similarity double")


def drop_leaks(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: float = SHARE) -> DataFrame:
    """``docs`` without the rows whose text holds a benchmark item."""
    at = docs.columns.index("text")

    def without(index: SeedIndex):
        def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                keep = np.ones(b.num_rows, bool)
                for lo, texts in text_parts(b.column(at), BLOCK):
                    keep[[lo + d for d, *_ in index.find(texts)]] = False
                yield b.filter(pa.array(keep))

        return f

    for index in indexes(benchmark, window, share):
        docs = docs.mapInArrow(without(index), docs.schema)
    return docs


def op9_decontaminate(spark, sf_dir: str) -> DataFrame:
    """A row for each document and benchmark passage that meet; null and empty texts meet nothing, repeated rows are each reported, no rows give none."""
    return find_leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
