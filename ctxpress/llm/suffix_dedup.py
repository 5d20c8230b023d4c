"""Exact removal of repeated byte strings by merging Burrows-Wheeler transforms of shards.

A byte goes if some 50-byte string over it also starts in a document with a smaller doc_id. Equal strings have to meet, and a
transform of the whole corpus does not fit anywhere, so the suffixes are dealt out first. Each 50-byte window is named by
its minimiser, the 20-byte gram in it whose hash is least; equal windows have equal minimisers. Neighbouring windows with the
same minimiser make one run of at most 80 bytes.

1. Chunks of documents report the hashes of their minimisers; a hash that one document alone has is done with.
2. Chunks send each distinct run of a shared minimiser once, with the least and greatest doc_id that has it here.
3. A bucket of minimisers holds all runs that could share a window. Byte-identical runs are one run with the least doc_id.
   Runs that share a minimiser but differ form a text collection: each shard of it gets its own sorted rotations and
   transform, and the shards' transforms are interleaved, one symbol deeper each time, by a stable distribution on the
   preceding symbol. After 50 rounds the interleave's blocks are the common prefixes of 50 bytes, the repeated intervals;
   no rotation of the whole is ever sorted again. Each window gets the least doc_id of its block.
4. Chunks look their runs up in what comes back and cut.

All passes work on packed arrays: a row is what one chunk and one bucket have to say to each other. A passage in a third of
all documents is one run for each chunk, whatever the number of its copies.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StringType, StructType

from ctxpress.llm.common import Local, give_back, partitions_for, text_bytes

WINDOW, GRAM = 50, 20
SPAN = WINDOW - GRAM + 1
PIECE, LONGEST, MERGED = 1 << 17, 1 << 22, 1 << 16
LOW = np.uint64((1 << 24) - 1)
LAST = np.iinfo(np.int64).max
#: Odd multipliers of the rolling hashes.
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)

_powers = Local()


def scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def powers(which: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Random values of the 256 bytes, powers of the base and powers of its inverse modulo 2**64."""
    got = _powers.get(which)
    if got is None or len(got[1]) < n:
        size = max(n, PIECE * 2)
        table = scramble(np.arange(1, 257, dtype=np.uint64) * np.uint64(BASES[which]))
        up, down = np.full(size, BASES[which], np.uint64), np.full(size, pow(BASES[which], -1, 1 << 64), np.uint64)
        up[0] = down[0] = 1
        got = _powers[which] = (table, np.multiply.accumulate(up), np.multiply.accumulate(down))
    return got


def prefix_hash(data: np.ndarray, which: int) -> np.ndarray:
    table, up, _ = powers(which, len(data) + 1)
    q = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(table[data] * up[: len(data)], out=q[1:])
    return q


def pieces(offsets: np.ndarray):
    """Byte ranges of whole documents, about PIECE long; a longer document alone, in parts that share all but a window."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + PIECE, "right")) - 1)
        lo, hi = int(offsets[i]), int(offsets[j])
        while hi - lo > LONGEST + WINDOW:
            yield lo, lo + LONGEST + WINDOW - 1
            lo += LONGEST
        yield lo, hi
        i = j


def runs(data: np.ndarray, offsets: np.ndarray, keys: bool):
    """For each piece: the runs' first and last window, minimiser hash and document, and a hash of their bytes."""
    for lo, hi in pieces(offsets):
        n = hi - lo
        if n < WINDOW:
            continue
        part = data[lo:hi]
        q = prefix_hash(part, 0)
        down = powers(0, n + 1)[2]
        gram = (q[GRAM:] - q[:-GRAM]) * down[: n - GRAM + 1]
        v = gram & ~LOW
        v |= np.arange(len(gram), dtype=np.uint64)
        for step in (1, 2, 4, 8):
            v = np.minimum(v[:-step], v[step:])
        v = np.minimum(v[: n - WINDOW + 1], v[SPAN - 16 :])
        at = (v & LOW).astype(np.int64)
        valid = np.ones(n - WINDOW + 2, bool)
        valid[-1] = False
        ends = offsets[np.searchsorted(offsets, lo, "right") : np.searchsorted(offsets, hi)] - lo
        bad = (ends[:, None] - np.arange(1, WINDOW)).ravel()
        valid[bad[(bad >= 0) & (bad < len(valid))]] = False
        same = np.zeros(len(at) + 1, bool)
        same[1:-1] = (at[1:] == at[:-1]) & valid[:-2] & valid[1:-1]
        first = np.flatnonzero(valid[:-1] & ~same[:-1])
        last = np.flatnonzero(valid[:-1] & ~same[1:])
        if not len(first):
            continue
        out = {"first": first + lo, "last": last + lo, "gram": scramble(gram[at[first]] ^ np.uint64(BASES[1])), "doc": np.searchsorted(offsets, first + lo, "right") - 1}
        if keys:
            out["body"] = (q[last + WINDOW] - q[first]) * down[first]
        yield out


def all_runs(data, offsets, keys: bool, names=("first", "last", "gram", "doc")) -> dict:
    names = (*names, "body") if keys else names
    got = [{k: r[k] for k in names} for r in runs(data, offsets, keys)]
    empty = {k: np.zeros(0, np.uint64 if k in ("gram", "body") else np.int64) for k in names}
    return {k: np.concatenate([r[k] for r in got]) if got else empty[k] for k in names}


def bytes_of(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Text column to its bytes and offsets; null is empty."""
    arr = column.combine_chunks()
    if isinstance(arr, pa.ChunkedArray):
        arr = pa.concat_arrays(arr.chunks) if arr.num_chunks else pa.array([], column.type)
    arr = arr.cast(pa.large_binary()) if pa.types.is_string(arr.type) or pa.types.is_large_string(arr.type) else arr.cast(pa.large_binary())
    arr = arr.fill_null(b"")
    off = np.frombuffer(arr.buffers()[1], np.int64)[arr.offset : arr.offset + len(arr) + 1] if len(arr) else np.zeros(1, np.int64)
    data = np.frombuffer(arr.buffers()[2], np.uint8) if arr.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def ids_of(column: pa.ChunkedArray) -> np.ndarray:
    """doc_ids; a null one comes after all others."""
    return column.cast(pa.int64()).fill_null(LAST).to_numpy()


def cut_by(gram: np.ndarray, buckets: int) -> np.ndarray:
    """Where the sorted ``gram`` goes from one of ``buckets`` to the next."""
    return np.searchsorted(gram >> np.uint64(40), np.arange(1, buckets, dtype=np.uint64) * np.uint64(1 << 24) // np.uint64(buckets))


def packed(x: np.ndarray, n: np.ndarray) -> pa.Array:
    """A binary column whose rows are the next ``n`` values of ``x`` each; no row is handled on its own."""
    x = np.ascontiguousarray(x)
    offsets = np.r_[0, np.cumsum(n)].astype(np.int32) * np.int32(x.itemsize)
    return pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(offsets), pa.py_buffer(x.view(np.uint8))])


def unpacked(column: pa.ChunkedArray, kind) -> tuple[np.ndarray, np.ndarray]:
    """The values of all rows, one after another, and how many each row has."""
    data, offsets = bytes_of(column)
    return np.frombuffer(data.tobytes(), kind), np.diff(offsets) // np.dtype(kind).itemsize


def plane_places(n: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Where the first byte of each number goes, and how far apart its bytes are, if each row has its first bytes first."""
    return np.arange(int(n.sum())) + np.repeat((np.cumsum(n) - n) * (width - 1), n), np.repeat(n, n)


def planes(x: np.ndarray, n: np.ndarray, width: int) -> np.ndarray:
    """The leading ``width`` bytes of the numbers of rows of ``n``, in each row all first bytes first: sorted numbers compress well so."""
    raw, out = x.astype(">u8").view(np.uint8).reshape(-1, 8), np.empty(len(x) * width, np.uint8)
    at, step = plane_places(n, width)
    for k in range(width):
        out[at + k * step] = raw[:, k]
    return out


def unplanes(data: np.ndarray, n: np.ndarray, width: int) -> np.ndarray:
    out = np.zeros((int(n.sum()), 8), np.uint8)
    at, step = plane_places(n, width)
    for k in range(width):
        out[:, k] = data[at + k * step]
    return out.view(">u8").ravel().astype(np.uint64)


def bit_places(n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the bits of rows of ``n`` are if each row begins with a byte of its own, and the bytes of each row."""
    size = (n + 7) // 8
    return np.arange(int(n.sum())) + np.repeat((np.cumsum(size) - size) * 8 - (np.cumsum(n) - n), n), size


def squeeze(b: bytes) -> bytes:
    return len(b).to_bytes(8, "little") + pa.compress(b, "zstd", asbytes=True)


def unsqueeze(b: bytes) -> np.ndarray:
    return np.frombuffer(pa.decompress(b[8:], int.from_bytes(b[:8], "little"), "zstd", asbytes=True), np.uint8)


def report(width: int, buckets: int):
    """Chunk to a row for each bucket: the minimisers in it, and which of them several of its documents have."""

    def f(key: tuple, table: pa.Table) -> pa.Table:
        data, offsets = bytes_of(table.column("_txt"))
        r, ids = all_runs(data, offsets, False, ("gram", "doc")), ids_of(table.column("_id"))
        gram = r["gram"] >> np.uint64(64 - 8 * width) << np.uint64(64 - 8 * width)
        doc = ids[r["doc"]] if len(ids) else r["doc"]
        order = np.argsort(gram, kind="stable")
        gram, doc = gram[order], doc[order]
        at = np.flatnonzero(np.r_[True, gram[1:] != gram[:-1]]) if len(gram) else np.zeros(0, np.int64)
        several = np.minimum.reduceat(doc, at) != np.maximum.reduceat(doc, at) if len(at) else np.zeros(0, bool)
        gram = gram[at]
        n = np.diff(np.r_[0, cut_by(gram, buckets), len(gram)])
        bucket = np.flatnonzero(n)
        n = n[bucket]
        place, size = bit_places(n)
        bits = np.zeros(int(size.sum()) * 8, bool)
        bits[place] = several
        return pa.table({"bucket": pa.array(bucket, pa.int32()), "chunk": pa.array([key[0].as_py()] * len(n), pa.int64()), "gram": packed(planes(gram, n, width), n * width), "several": packed(np.packbits(bits), size)})

    return f


def agree(width: int):
    """Bucket to a row for each chunk: those of its minimisers that other documents have too."""

    def f(table: pa.Table) -> pa.Table:
        chunk = table.column("chunk").to_numpy()
        data, n = unpacked(table.column("gram"), np.uint8)
        n //= width
        several = np.unpackbits(unpacked(table.column("several"), np.uint8)[0])[bit_places(n)[0]]
        gram, row = unplanes(data, n, width), np.repeat(np.arange(len(n)), n)
        order = np.argsort(gram, kind="stable")
        s = gram[order]
        at = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
        count = np.diff(np.r_[at, len(s)])
        shared = np.repeat((count > 1) | (np.maximum.reduceat(several[order], at) > 0), count)
        order = np.sort(order[shared])
        n = np.bincount(row[order], minlength=len(n))
        keep = n > 0
        return pa.table({"chunk": pa.array(chunk[keep], pa.int64()), "gram": packed(planes(gram[order], n[keep], width), n[keep] * width)})

    return f


def send(width: int, buckets: int):
    """Chunk and its shared minimisers to a row for each bucket: the distinct runs there."""

    def f(key: tuple, table: pa.Table, shared: pa.Table) -> pa.Table:
        bucket, gram, body, runs_of, more = np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), []
        if table.num_rows and shared.num_rows:
            known, n = unpacked(shared.column("gram"), np.uint8)
            known = np.sort(unplanes(known, n // width, width))
            data, offsets = bytes_of(table.column("_txt"))
            r, ids = all_runs(data, offsets, True), ids_of(table.column("_id"))
            short = r["gram"] >> np.uint64(64 - 8 * width) << np.uint64(64 - 8 * width)
            at = np.minimum(np.searchsorted(known, short), len(known) - 1)
            hit = np.flatnonzero(known[at] == short)
            order = hit[np.lexsort((r["body"][hit], r["gram"][hit]))]
            r = {k: v[order] for k, v in r.items()}
            doc = ids[r["doc"]]
            new = np.flatnonzero(np.r_[True, (r["body"][1:] != r["body"][:-1]) | (r["gram"][1:] != r["gram"][:-1])]) if len(doc) else np.zeros(0, np.int64)
            give_back()
            if len(new):
                least, most = np.minimum.reduceat(doc, new), np.maximum.reduceat(doc, new)
                r = {k: v[new] for k, v in r.items()}
                size = r["last"] - r["first"] + WINDOW
                runs_of = np.diff(np.r_[0, cut_by(r["gram"], buckets), len(new)])
                bucket = np.flatnonzero(runs_of)
                runs_of, gram, body = runs_of[bucket], r["gram"], r["body"]
                ids = [planes(x.view(np.uint64), runs_of, 8) for x in (least, most)]
                stop = np.cumsum(runs_of)
                for x, y in zip((stop - runs_of).tolist(), stop.tolist()):
                    n = size[x:y]
                    where = np.repeat(r["first"][x:y] - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
                    more.append(squeeze(b"".join((n.astype(np.uint8).tobytes(), ids[0][8 * x : 8 * y].tobytes(), ids[1][8 * x : 8 * y].tobytes(), data[where].tobytes()))))
        return pa.table({"bucket": pa.array(bucket, pa.int32()), "chunk": pa.array([key[0].as_py()] * len(bucket), pa.int64()), "gram": packed(gram, runs_of), "body": packed(body, runs_of), "more": pa.array(more, pa.binary())})

    return f


def shard_rotations(text: np.ndarray, following: np.ndarray, shard: np.ndarray) -> np.ndarray:
    """Rotations of cyclic words, each shard's sorted on its own, shard after shard."""
    word, hop = text.astype(np.uint64), following
    for bits in (8, 16, 32):
        word = (word << np.uint64(bits)) | word[hop]
        hop = hop[hop]
    order = np.lexsort((word, shard)).astype(np.int32)
    new = np.r_[False, (word[order][1:] != word[order][:-1]) | (shard[order][1:] != shard[order][:-1])]
    for _ in range(6):
        rank = np.empty(len(text), np.uint64)
        rank[order] = np.cumsum(new).astype(np.uint64)
        if new.sum() == len(text) - 1:
            break
        pair = (rank << np.uint64(32)) | rank[hop]
        order = np.argsort(pair, kind="stable").astype(np.int32)
        p = pair[order]
        new = np.r_[False, p[1:] != p[:-1]]
        hop = hop[hop]
    return order


def merge_transforms(transform: np.ndarray, shard: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Interleaves the transforms of shards, laid one after another, until ``depth`` symbols are sorted.

    Returns which place of the shards' order stands where in the merged one, and for each merged place its block: the
    rotations whose first ``depth`` symbols are equal. Round by round the sequence of shards is spread out by the two
    symbols before each rotation, stably, so a rotation's place follows from that of its successor's successor.
    """
    z, block = shard.copy(), np.zeros(len(shard), np.int32)
    symbol = np.empty_like(transform)
    for _ in range(depth // 2):
        symbol[np.argsort(z, kind="stable")] = transform
        order = np.argsort(symbol, kind="stable")
        c, b = symbol[order], block[order]
        block = np.zeros(len(z), np.int32)
        np.cumsum((c[1:] != c[:-1]) | (b[1:] != b[:-1]), out=block[1:])
        z = z[order]
    place = np.empty(len(z), np.int64)
    place[np.argsort(z, kind="stable")] = np.arange(len(z))
    return place, block


def window_least(body: np.ndarray, size: np.ndarray, least: np.ndarray, shard_bytes: int = 1 << 14) -> tuple[np.ndarray, np.ndarray]:
    """For all windows of all runs, run after run: the least doc_id over the runs that contain it; and each run's start."""
    n = size + 1  # each word ends in 0xFF, which UTF-8 does not use
    stop = np.cumsum(n)
    start, total = stop - n, int(stop[-1])
    text = np.full(total, 255, np.uint8)
    inside = np.ones(total, bool)
    inside[stop - 1] = False
    text[inside] = body
    following = np.arange(1, total + 1, dtype=np.int32)
    following[stop - 1] = start
    before = np.arange(-1, total - 1, dtype=np.int32)
    before[start] = stop - 1
    shard_bytes = max(shard_bytes, total // 200)
    shard = np.repeat((start // shard_bytes).astype(np.uint8), n)
    rotations = shard_rotations(text, following, shard)
    pair = (text[before[before]].astype(np.uint16) << np.uint16(8)) | text[before]
    del following
    place, block = merge_transforms(pair[rotations], shard, WINDOW)
    offset = np.arange(total) - np.repeat(start, n)
    is_window = offset <= np.repeat(size - WINDOW, n)
    value = np.where(is_window, np.repeat(least, n), LAST)
    merged = rotations[place]
    at = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
    low = np.empty(total, np.int64)
    low[merged] = np.minimum.reduceat(value[merged], at)[block]
    windows = size - WINDOW + 1
    return low[is_window], np.cumsum(windows) - windows


def whole_minimisers(gram: np.ndarray, size: np.ndarray) -> list[slice]:
    """Stretches of runs, sorted by minimiser, of about MERGED bytes; runs of one minimiser stay together, others share no window."""
    if not len(gram):
        return []
    head = np.flatnonzero(np.r_[True, gram[1:] != gram[:-1]])
    part = (np.cumsum(size) - size)[head] // MERGED
    head = head[np.r_[True, part[1:] != part[:-1]]]
    return [slice(x, y) for x, y in zip(head.tolist(), [*head[1:].tolist(), len(gram)])]


def decide(table: pa.Table) -> pa.Table:
    """Bucket to a row for each chunk: stretches of windows of its runs that a smaller doc_id has, with that doc_id."""
    (gram, each), (body, _) = (unpacked(table.column(k), np.uint64) for k in ("gram", "body"))
    more = [unsqueeze(b.as_py()) for b in table.column("more")]
    row, size = np.repeat(np.arange(len(each)), each), np.concatenate([m[:n] for m, n in zip(more, each)]).astype(np.int64)
    low_id, high_id = (unplanes(np.concatenate([m[n * k : n * (k + 8)] for m, n in zip(more, each)]), each, 8).view(np.int64) for k in (1, 9))
    text = np.concatenate([m[n * 17 :] for m, n in zip(more, each)])
    del more
    begin = np.cumsum(size) - size
    order = np.lexsort((body, gram))
    g, k = gram[order], body[order]
    new = np.r_[True, (g[1:] != g[:-1]) | (k[1:] != k[:-1])]
    at = np.flatnonzero(new)
    kind = np.empty(len(order), np.int64)
    kind[order] = np.cumsum(new) - 1
    least, one = np.minimum.reduceat(low_id[order], at), order[at]
    # A run that stands alone under its minimiser is one repeated interval; the others are merged.
    head = np.r_[True, g[at][1:] != g[at][:-1]]
    rivals = np.repeat(np.diff(np.r_[np.flatnonzero(head), len(at)]) > 1, np.diff(np.r_[np.flatnonzero(head), len(at)]))
    windows = size[one] - WINDOW + 1
    mixed = np.flatnonzero(rivals)
    stretch_kind, stretch_from, stretch_n, stretch_low = [np.flatnonzero(~rivals)], [np.zeros(int((~rivals).sum()), np.int64)], [windows[~rivals]], [least[~rivals]]
    for part in whole_minimisers(g[at][mixed], size[one[mixed]]):
        kinds = mixed[part]
        n = size[one[kinds]]
        where = np.repeat(begin[one[kinds]] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        low, first = window_least(text[where], n, least[kinds])
        owner = np.repeat(np.arange(len(kinds)), windows[kinds])
        turn = np.flatnonzero(np.r_[True, (low[1:] != low[:-1]) | (owner[1:] != owner[:-1])])
        stretch_kind.append(kinds[owner[turn]])
        stretch_from.append(turn - first[owner[turn]])
        stretch_n.append(np.diff(np.r_[turn, len(low)]))
        stretch_low.append(low[turn])
    sk, sf, sn, sl = (np.concatenate(x) for x in (stretch_kind, stretch_from, stretch_n, stretch_low))
    by = np.argsort(sk, kind="stable")
    sk, sf, sn, sl = sk[by], sf[by], sn[by], sl[by]
    lo, hi = np.searchsorted(sk, np.arange(len(at))), np.searchsorted(sk, np.arange(len(at)), "right")
    count = (hi - lo)[kind]
    run = np.repeat(np.arange(len(kind)), count)
    s = np.repeat(lo[kind] - (np.cumsum(count) - count), count) + np.arange(count.sum())
    keep = sl[s] < high_id[run]
    run, s = run[keep], s[keep]
    n = np.bincount(row[run], minlength=len(each))
    some = n > 0
    n = n[some]
    return pa.table({
        "chunk": pa.array(table.column("chunk").to_numpy()[some], pa.int64()), "gram": packed(gram[run], n), "body": packed(body[run], n),
        "from": packed(sf[s].astype(np.uint8), n), "n": packed(sn[s].astype(np.uint8), n), "low": packed(planes(sl[s].view(np.uint64), n, 8), n * 8),
    })


def removed_bytes(data: np.ndarray, offsets: np.ndarray, ids: np.ndarray, found: pa.Table) -> np.ndarray:
    """For each byte whether it goes."""
    edge = np.zeros(len(data) + 1, np.int32)
    if found.num_rows and len(data):
        col = {k: unpacked(found.column(k), t)[0] for k, t in (("gram", np.uint64), ("body", np.uint64), ("from", np.uint8), ("n", np.uint8))}
        low, n = unpacked(found.column("low"), np.uint8)
        col["low"] = unplanes(low, n // 8, 8).view(np.int64)
        order = np.lexsort((col["gram"], col["body"]))
        col = {k: v[order] for k, v in col.items()}
        new = np.flatnonzero(np.r_[True, (col["body"][1:] != col["body"][:-1]) | (col["gram"][1:] != col["gram"][:-1])])
        u1, u2, many = col["body"][new], col["gram"][new], np.diff(np.r_[new, len(order)])
        for r in runs(data, offsets, True):
            at = np.minimum(np.searchsorted(u1, r["body"]), len(u1) - 1)
            while True:  # equal first hashes with another second one: look further
                on = (u1[at] == r["body"]) & (u2[at] != r["gram"]) & (at + 1 < len(u1)) & (u1[np.minimum(at + 1, len(u1) - 1)] == r["body"])
                if not on.any():
                    break
                at = at + on
            hit = np.flatnonzero((u1[at] == r["body"]) & (u2[at] == r["gram"]))
            count = many[at[hit]]
            run = np.repeat(hit, count)
            s = np.repeat(new[at[hit]] - (np.cumsum(count) - count), count) + np.arange(count.sum())
            earlier = col["low"][s] < ids[r["doc"][run]]
            run, s = run[earlier], s[earlier]
            lo = r["first"][run] + col["from"][s]
            np.add.at(edge, lo, 1)
            np.add.at(edge, lo + (col["n"][s].astype(np.int64) - 1 + WINDOW), -1)
    return np.cumsum(edge[:-1], dtype=np.int32) > 0


def between(marks: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """How many marks lie between each two offsets."""
    at = np.searchsorted(np.flatnonzero(marks), offsets)
    return np.diff(at)


def cut_text(key: tuple, table: pa.Table, found: pa.Table) -> pa.Table:
    """As ``cut``, with what remains as text; a character that lost some of its bytes is left out."""
    out = cut(key, table, found)
    texts = pa.array([k.as_py().decode("utf-8", "ignore") for k in out.column("kept")], pa.string())
    return out.set_column(out.column_names.index("kept"), "kept", texts)


def cut(key: tuple, table: pa.Table, found: pa.Table) -> pa.Table:
    """Chunk and what was found in it to its documents with the remaining text and the measures of the cut."""
    data, offsets = bytes_of(table.column("_txt"))
    gone = removed_bytes(data, offsets, ids_of(table.column("_id")), found)
    n, size = table.num_rows, np.diff(offsets)
    removed = between(gone, offsets)
    opening = gone & ~np.r_[False, gone[:-1]] if len(gone) else gone
    heads = offsets[:-1][size > 0]
    opening[heads] = gone[heads]
    spans = between(opening, offsets)
    left = data[~gone]
    bounds = np.r_[0, np.cumsum(size - removed)]
    kept = [left[bounds[i] : bounds[i + 1]].tobytes() for i in range(n)]
    del data, gone, opening, left
    give_back()
    return pa.table({
        **{c: table.column(c) for c in table.column_names if c not in ("chunk", "_txt")}, "kept": pa.array(kept, pa.binary()), "n_bytes": pa.array(size), "n_removed": pa.array(removed.astype(np.int64)),
        "n_spans": pa.array(spans.astype(np.int64)), "kept_sha256": pa.array([hashlib.sha256(k).hexdigest() for k in kept]),
    })


def remove_repeats(docs: DataFrame, chunk_bytes: int = 8 << 20, carry: bool = True, as_text: bool = False) -> DataFrame:
    """One row per document: the columns of ``docs`` but text, and kept (bytes, or text if asked for), n_bytes, n_removed, n_spans, kept_sha256.

    Null text is empty and never matches. A null doc_id comes after all others. Rows of an equal doc_id are one document to
    each other: they never remove each other's bytes. Columns besides doc_id and text travel along untouched, whatever
    their names (``carry=False`` leaves them out). The number of chunks and buckets grows with the text, so each stays of
    one size.
    """
    total = text_bytes(docs)
    chunks, buckets = partitions_for(total, chunk_bytes), partitions_for(total, chunk_bytes // 3)
    width = int(min(8, max(5, -(-(max(total, 1).bit_length() + 10) // 8))))
    rest = [c for c in docs.columns if c not in ("doc_id", "text")] if carry else []
    keyed = docs.select(
        F.pmod(F.when(F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(F.xxhash64("doc_id")), F.lit(chunks)).alias("chunk"), F.col("doc_id").alias("_id"), F.col("text").alias("_txt"), *[F.col(f"`{c}`").alias(f"_r{i}") for i, c in enumerate(rest)]
    ).repartition(chunks, "chunk")
    said = keyed.groupBy("chunk").applyInArrow(report(width, buckets), "bucket int, chunk long, gram binary, several binary")
    shared = said.groupBy("bucket").applyInArrow(agree(width), "chunk long, gram binary")
    sent = keyed.groupBy("chunk").cogroup(shared.groupBy("chunk")).applyInArrow(send(width, buckets), "bucket int, chunk long, gram binary, body binary, more binary")
    found = sent.groupBy("bucket").applyInArrow(decide, "chunk long, gram binary, body binary, `from` binary, n binary, low binary")
    schema = StructType([f for f in keyed.schema if f.name not in ("chunk", "_txt")])
    for name, kind in (("kept", StringType() if as_text else BinaryType()), ("n_bytes", LongType()), ("n_removed", LongType()), ("n_spans", LongType()), ("kept_sha256", StringType())):
        schema = schema.add(name, kind)
    out = keyed.groupBy("chunk").cogroup(found.groupBy("chunk")).applyInArrow(cut_text if as_text else cut, schema)
    return out.select(F.col("_id").alias("doc_id"), *[F.col(f"_r{i}").alias(c) for i, c in enumerate(rest)], "kept", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def without_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with the repeated bytes cut from text and n_chars to match; a text of which nothing but blanks is left goes."""
    left = remove_repeats(docs, as_text=True)
    left = left.where((F.col("n_removed") == 0) | (F.trim("kept") != ""))
    made = {"text": F.col("kept"), "n_chars": F.when(F.col("n_removed") > 0, F.length("kept").cast("long")).otherwise(F.col("n_chars")) if "n_chars" in docs.columns else None}
    return left.select(*[made[c].alias(c) if c in made else F.col(f"`{c}`") for c in docs.columns])


def op6_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """All rows of ``documents`` with what is left of their bytes; null texts are empty, rows with an equal doc_id do not cut each other, no rows give none."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return remove_repeats(docs.select("doc_id", "text"), carry=False).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
