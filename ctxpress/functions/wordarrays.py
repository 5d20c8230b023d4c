"""Words of many texts at once, as numbers: one look at every character instead of a pattern for every text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

from ctxpress.functions.tokens import WORD


def _ranges() -> np.ndarray:
    """First code points of stretches that are parts of words, and of stretches that are not, in turn."""
    every = "".join(map(chr, range(0xD800))) + " " * 0x800 + "".join(map(chr, range(0xE000, 0x110000)))  # without surrogates
    return np.array([x.span() for x in regex.finditer(WORD, every)], dtype=np.int32).ravel()


#: Found once, as tasks get this module's values with each function; every task makes its table of code points from them.
_RANGES, _TABLE = _ranges(), []


def _in_words() -> np.ndarray:
    """For every code point, whether it is part of a word."""
    if not _TABLE:
        turns = np.zeros(0x110000, dtype=np.int8)
        turns[_RANGES[::2]], turns[_RANGES[1::2]] = 1, -1
        _TABLE.append(np.cumsum(turns, dtype=np.int8).astype(bool))
    return _TABLE[0]


def ids_of(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A number from 0 for every key, the same for equal keys, and the first place of each number."""
    ids = pa.array(keys).dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int64)
    first = np.empty(ids.max() + 1 if len(ids) else 0, dtype=np.int64)
    first[ids[::-1]] = np.arange(len(ids))[::-1]
    return ids, first


def parts_of(batch: pa.RecordBatch, column: str, size: int = 1 << 21, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in stretches of rows with about ``size`` bytes of texts and ``most`` rows, so that arrays over characters stay small."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    lo = 0
    while lo < len(ends):
        hi = int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + size, "right"))
        hi = min(max(hi, lo + 1), lo + most, len(ends))
        yield batch.slice(lo, hi - lo)
        lo = hi


class Words:
    """The words of all texts in a row, case kept; no text is null after this, only empty.

    ``names`` has the distinct words in binary order; for each word of the texts, ``word`` is its place there, ``doc`` its text,
    ``tight`` whether the next one follows in the same text after a single blank, and ``marked`` whether it stands right after ``mark``, an ASCII character.
    """

    def __init__(self, texts: pa.Array, mark: str | None = None):
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        _, places, body = texts.buffers()
        cuts = np.frombuffer(places, np.int64)[texts.offset : texts.offset + len(texts) + 1]
        data = np.frombuffer(body, np.uint8)[cuts[0] : cuts[-1]] if body is not None and cuts[-1] > cuts[0] else np.zeros(0, np.uint8)
        cuts = cuts - cuts[0]
        table = _in_words()
        inside = np.frombuffer(data.tobytes().translate(table[:128].tobytes() + bytes(128)), bool)
        high = data >= 128
        if high.any():  # all bytes of a character are as the character is
            inside, more = inside.copy(), data[high]
            sizes = np.diff(np.flatnonzero((more & 0xC0) != 0x80), append=len(more))
            inside[high] = np.repeat(table[np.frombuffer(more.tobytes().decode().encode("utf-32-le"), np.uint32)], sizes)
        turns = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        if len(inside) and inside[0]:
            turns = np.concatenate([[0], turns])
        if len(inside) and inside[-1]:
            turns = np.concatenate([turns, [len(inside)]])
        heads = cuts[1:-1][(cuts[1:-1] > 0) & (cuts[1:-1] < len(data))]
        split = np.unique(heads[inside[heads - 1] & inside[heads]])  # a text that begins right after the last word of another
        start, end = (np.sort(np.concatenate([x, split]), kind="stable") if len(split) else x for x in (turns[::2], turns[1::2]))
        ends = np.concatenate([[0], np.cumsum(end - start)])
        words = pa.LargeStringArray.from_buffers(len(start), pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(data[inside])).dictionary_encode()
        order = pc.sort_indices(words.dictionary).to_numpy().astype(np.int64)
        rank = np.empty(len(order), dtype=np.int64)
        rank[order] = np.arange(len(order))
        self.names, self.word = words.dictionary.take(pa.array(order)), rank[words.indices.to_numpy(zero_copy_only=False)]
        self.docs, self.doc = len(texts), np.searchsorted(cuts, start, "right") - 1
        self.tight = np.zeros(len(start), dtype=bool)
        if len(start):
            self.tight[:-1] = (start[1:] - end[:-1] == 1) & (data[end[:-1].clip(max=len(data) - 1)] == 32) & (self.doc[1:] == self.doc[:-1])
        self.marked = (data[start - 1] == ord(mark)) & (start > cuts[self.doc]) if mark and len(start) else np.zeros(len(start), dtype=bool)

    def __len__(self) -> int:
        return len(self.word)

    def lower(self) -> pa.Array:
        """``names`` in lower case, in the same order."""
        low, odd = pc.utf8_lower(self.names), pc.match_substring_regex(self.names, "[\u0130\u03a3]")  # these depend on more than the character
        return pc.replace_with_mask(low, odd, pa.array([x.lower() for x in self.names.filter(odd).to_pylist()], low.type)) if pc.any(odd).as_py() else low

    def grams(self, places: np.ndarray, n: int) -> list[str]:
        """The n-grams that begin at ``places``, blank-joined."""
        return [" ".join(x) for x in zip(*[self.names.take(pa.array(self.word[places + j])).to_pylist() for j in range(n)])]

    def places(self, n: int) -> np.ndarray:
        """Where n-grams with single blanks between their words begin."""
        ok = np.ones(max(len(self) - n + 1, 0), dtype=bool)
        for j in range(n - 1):
            ok &= self.tight[j : j + len(ok)]
        return np.flatnonzero(ok)

    def same(self, places: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """``ids_of`` of the n-grams that begin at ``places``."""
        ids, first = self.word[places], np.zeros(0, np.int64)
        for j in range(1, n):
            ids, first = ids_of(ids * len(self.names) + self.word[places + j])
        return ids, first

    def repeated(self, most: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """(n, places, ids, first) for n from 2 to ``most``: the n-grams that their own text repeats.

        What a text repeats begins and ends with shorter n-grams that it repeats, so only those are looked at.
        """
        v = len(self.names)
        ids, _ = ids_of(self.doc * v + self.word)
        twice = np.bincount(ids, minlength=1)[ids] > 1 if len(ids) else np.zeros(0, dtype=bool)
        places, of = np.flatnonzero(twice), np.where(twice, ids, -1)
        for n in range(2, most + 1):
            places = places[places + 1 < len(self)]
            places = places[(of[places + 1] >= 0) & self.tight[places]]
            ids, _ = ids_of(of[places] * v + self.word[places + n - 1])
            many = np.bincount(ids, minlength=1)[ids] > 1 if len(ids) else np.zeros(0, dtype=bool)
            places = places[many]
            ids, first = ids_of(ids[many])
            yield n, places, ids, first
            of = np.full(len(self), -1, dtype=np.int64)
            of[places] = ids


def spaced(places: np.ndarray, n: int) -> np.ndarray:
    """Those of the ascending places that a scan from the left takes when each covers ``n`` words and none may overlap."""
    close = np.flatnonzero(np.diff(places) < n) + 1
    if not len(close):
        return places
    drop, end, last = [], 0, -1
    for j, here, before in zip(close.tolist(), places[close].tolist(), places[close - 1].tolist()):
        if j - 1 != last:  # the one before is clear of all before it
            end = before + n
        if here < end:
            drop.append(j)
        else:
            end = here + n
        last = j
    return np.delete(places, drop)
