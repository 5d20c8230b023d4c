"""Near duplicates by SimHash fingerprints and a hierarchical index in Gray order.

Fingerprints at most ``max_bits`` apart agree on some ``blocks - max_bits`` of ``blocks`` bit blocks, so each goes once to the
bucket of every such choice. A bucket is searched through a tree over its fingerprints in order of Gray rank, where
neighbours share long bit patterns: a node holds the pattern that all below it share and the mask of those bits. A query
walks down level by level; the bits that differ from a node's pattern are a lower bound for all of its group, which is left
out beyond the threshold, or when the group is already in the query's component.

For a similarity of 0.8 of five-word shingles the threshold is so wide that no bit blocks need agree. There a bucket is what
agrees in any of ``BANDS`` groups of ``ROWS`` minima of the shingles under fixed permutations (a pair at 0.8 meets nowhere
once in about 10^10), the index finds in each bucket what is within ``WIDE_BITS``, and the shingle sets themselves decide.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.llm.common import cut_lineage, free_name, give_back, partitions_for
from ctxpress.llm.graph import connected_components

MAX_BITS, SHINGLE, FAN = 4, 4, 8
#: Of near copies: words of a shingle, and the least Jaccard similarity as a fraction.
WORDS, LEAST, OF = 5, 4, 5
#: At a similarity of 0.8 fingerprints differ in 10 bits of 64 on average, in more than this once in 10^5 or less.
WIDE_BITS = 26
BANDS, ROWS = 32, 3
_RNG = np.random.default_rng(11)
TIMES = _RNG.integers(0, 2**63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
PLUS = _RNG.integers(0, 2**63, BANDS * ROWS, np.uint64)


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """64 bits: bit i is set if it is set in over half of the shingles' XXH64 (seed 42)."""
    import xxhash

    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return 0
    digest, n = xxhash.xxh64_intdigest, len(words) - shingle + 1
    if n <= 1:
        return digest(b" ".join(words), 42)
    joined = b" ".join(words)
    lens = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lens + 1) - 1
    starts = (ends - lens)[:n].tolist()
    stops = ends[shingle - 1 :].tolist()
    sums = np.zeros(64, np.int64)
    for lo in range(0, n, 65536):
        h = np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts[lo : lo + 65536], stops[lo : lo + 65536])), np.uint64)
        sums += np.unpackbits(h.astype(">u8").view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(sums * 2 > n).tobytes(), "big")


def fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches (doc_id, text) to (doc_id, fp)."""
    for b in batches:
        fps = np.fromiter((fingerprint(t.as_py()) for t in b.column(1)), np.uint64, b.num_rows)
        give_back()
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])


def gray_rank(x: np.ndarray) -> np.ndarray:
    r = x.copy()
    for s in (1, 2, 4, 8, 16, 32):
        r ^= r >> np.uint64(s)
    return r


def unite(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the components of a[i] and b[i]; parent points to the smallest index of each afterwards."""
    while len(a):
        ra, rb = parent[a], parent[b]
        open_ = ra != rb
        a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
        if not len(a):
            return
        np.minimum.at(parent, np.maximum(ra, rb), np.minimum(ra, rb))
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent[:] = up


class GrayIndex:
    """Tree over fingerprints sorted by (bucket, Gray rank); no node spans two buckets."""

    def __init__(self, bucket: np.ndarray, fps: np.ndarray, fan: int = FAN):
        self.fps, n = fps, len(fps)
        self.levels = []
        ids, lo, hi = bucket, np.arange(n), np.arange(n) + 1
        low, high = fps, fps
        while True:
            first = np.r_[True, ids[1:] != ids[:-1]]
            place = np.arange(len(ids)) - np.maximum.accumulate(np.where(first, np.arange(len(ids)), 0))
            if self.levels and first.all():
                break
            at = np.flatnonzero(first | (place % fan == 0))
            low, high = np.bitwise_and.reduceat(low, at), np.bitwise_or.reduceat(high, at)
            stop = np.r_[at[1:], len(ids)]
            level = {"first": at, "stop": stop, "pattern": low, "mask": ~(low ^ high), "lo": lo[at], "hi": hi[stop - 1]}
            self.levels.append(level)
            ids, lo, hi = ids[at], level["lo"], level["hi"]
        self.root = np.searchsorted(ids, bucket)  # ids is sorted and has one node for each bucket

    def component_links(self, max_bits: int = MAX_BITS, room: int = 2_000_000) -> np.ndarray:
        """For each fingerprint the least index that chains of links reach inside its bucket."""
        parent = np.arange(len(self.fps))
        near = np.flatnonzero((self.root[1:] == self.root[:-1]) & (np.bitwise_count(self.fps[1:] ^ self.fps[:-1]) <= max_bits))
        unite(parent, near + 1, near)
        for q, hit in self.hits(max_bits, parent, room):
            unite(parent, q, hit)
        return parent

    def hits(self, max_bits: int, label: np.ndarray, room: int = 2_000_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (i, j), i before j, of a bucket within ``max_bits``; groups of one label are left out for queries of that label."""
        n, fps = len(self.fps), self.fps
        top = self.levels[-1]
        width = (top["hi"] - top["lo"])[self.root]
        cost, start = np.cumsum(width), 0
        while start < n:
            stop = max(start + 1, int(np.searchsorted(cost, (cost[start - 1] if start else 0) + room)))
            q = np.arange(start, stop)
            node = self.root[start:stop]
            for k in range(len(self.levels) - 1, -1, -1):
                level = self.levels[k]
                same = self._uniform(label, level)
                keep = (level["hi"][node] > q + 1) & (np.bitwise_count((fps[q] ^ level["pattern"][node]) & level["mask"][node]) <= max_bits) & (same[node] != label[q])
                q, node = q[keep], node[keep]
                count = level["stop"][node] - level["first"][node]
                q = np.repeat(q, count)
                node = np.repeat(level["first"][node] - np.r_[0, np.cumsum(count)[:-1]], count) + np.arange(len(q)) if len(q) else node[:0]
            hit = (node > q) & (np.bitwise_count(fps[q] ^ fps[node]) <= max_bits)
            yield q[hit], node[hit]
            start = stop

    @staticmethod
    def _uniform(parent: np.ndarray, level: dict) -> np.ndarray:
        """The component that all of a node's group are in, or -1."""
        least, most = np.minimum.reduceat(parent, level["lo"]), np.maximum.reduceat(parent, level["lo"])
        return np.where(least == most, least, -1)


def _block_links(max_bits: int):
    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        bucket, fps, rep = (t.column(i).to_numpy() for i in range(3))
        bucket, fps = bucket.view(np.int64), fps.view(np.uint64)
        order = np.lexsort((gray_rank(fps), bucket))
        bucket, fps, rep = bucket[order], fps[order], rep[order]
        parent = GrayIndex(bucket, fps).component_links(max_bits)
        moved = np.flatnonzero(parent != np.arange(len(parent)))
        yield pa.RecordBatch.from_arrays([pa.array(rep[moved]), pa.array(rep[parent[moved]])], names=["u", "v"])

    return link


def block_plan(distinct: int, max_bits: int, load: int = 4096) -> tuple[list[tuple[int, int]], list[tuple[int, ...]]]:
    """Bit blocks (shift, width) and the choices of blocks that must agree; more blocks as fingerprints get more."""
    for m in range(max_bits + 1, max_bits + 5):
        edges = [round(64 * i / m) for i in range(m + 1)]
        blocks = [(a, b - a) for a, b in zip(edges, edges[1:])]
        choices = list(combinations(range(m), m - max_bits))
        if distinct <= load << min(sum(blocks[i][1] for i in c) for c in choices):
            break
    return blocks, choices


def simhash_components(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of ``docs`` (doc_id, text).

    Null and empty texts have fingerprint zero and link like any other. Rows of equal doc_id are each returned. Equal
    fingerprints are searched once, by their smallest doc_id; component_id is the smallest doc_id reachable.
    """
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, fp long"
    marked = cut_lineage(docs.select("doc_id", "text").mapInArrow(fingerprint_batches, schema))
    groups = cut_lineage(marked.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    n = groups.count()
    blocks, choices = block_plan(n, max_bits)
    keys = []
    for i, choice in enumerate(choices):
        key = F.lit(i).cast("long")
        for b in choice:
            shift, width = blocks[b]
            key = F.shiftleft(key, width) + F.shiftrightunsigned("fp", shift).bitwiseAND(F.lit((1 << width) - 1))
        keys.append(key)
    dealt = groups.where("rep is not null").select(F.explode(F.array(*keys)).alias("bucket"), "fp", "rep")
    dealt = dealt.repartition(partitions_for(n * len(choices), 400_000), "bucket")
    edges = dealt.mapInArrow(_block_links(max_bits), "u long, v long")
    roots = connected_components(edges)
    named = groups.join(roots, groups["rep"] == roots["node"], "left").select("fp", F.coalesce("root", "rep").alias("component_id"))
    out = marked.join(named, "fp")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    """All rows of ``documents`` at 4 bits of four-word shingles; null and empty texts, ties and empty tables as in ``simhash_components``."""
    return simhash_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None, shingle: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``shingle`` words; a shorter text is one shingle, a blank one has none."""
    import xxhash

    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    k = min(shingle, len(words))
    s = np.zeros(len(words) - k + 1, np.uint64)
    for i in range(k):
        s = mixed(s * np.uint64(3) + h[i : i + len(s)])
    return np.unique(s)


def set_fingerprint(s: np.ndarray) -> int:
    """64 bits: bit i is set if it is set in over half of the distinct shingles' hashes."""
    sums = np.zeros(64, np.int64)
    for lo in range(0, len(s), 16384):
        sums += np.unpackbits(s[lo : lo + 16384].astype(">u8").view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(sums * 2 > len(s)).tobytes(), "big")


def bands_of(s: np.ndarray) -> np.ndarray:
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for lo in range(0, len(s), 4096):
        np.minimum(least, (TIMES[:, None] * s[lo : lo + 4096] + PLUS[:, None]).min(1), out=least)
    out = np.arange(BANDS, dtype=np.uint64)
    for column in least.reshape(BANDS, ROWS).T:
        out = mixed(out * np.uint64(3) + column)
    return out


def _marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches (doc_id, text) to (doc_id, node, n, fp, bands); a blank text has no bands."""
    import xxhash

    for b in batches:
        sets = [shingle_set(t.as_py()) for t in b.column(1)]
        nodes, fps = (np.fromiter(v, np.uint64, len(sets)).view(np.int64) for v in ((xxhash.xxh64_intdigest(s.tobytes()) for s in sets), map(set_fingerprint, sets)))
        bands = [bands_of(s).tobytes() if len(s) else b"" for s in sets]
        give_back()
        columns = [b.column(0), pa.array(nodes), pa.array([len(s) for s in sets], pa.int64()), pa.array(fps), pa.array(bands, pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "node", "n", "fp", "bands"])


def _banded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches (node, n, fp, bands) to (band, node, n, fp)."""
    for b in batches:
        rows = b.column(1).to_numpy() > 0
        band = np.frombuffer(b"".join(v.as_py() for v in b.column(3)), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(band), *(pa.array(np.repeat(b.column(i).to_numpy()[rows], BANDS)) for i in range(3))], names=["band", "node", "n", "fp"])


def _met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(band, node, n, fp) of buckets with two nodes or more, with the first node of the bucket."""
    got = [b for b in batches if b.num_rows]
    if not got:
        return
    t = pa.Table.from_batches(got)
    columns = [t.column(i).to_numpy() for i in range(t.num_columns)]
    order = np.lexsort((columns[1], columns[0]))
    band, *rest = (c[order] for c in columns)
    at = np.flatnonzero(np.r_[True, band[1:] != band[:-1]])
    size = np.diff(np.r_[at, len(band)])
    keep, head = np.repeat(size > 1, size), np.repeat(at, size)
    yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (band, *rest, *(c[head] for c in rest))], names=["band", "node", "n", "fp", "head", "head_n", "head_fp"])


class _Bucket:
    """Shingle sets of a bucket, with the places of each shingle."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets])
        code = np.unique(np.concatenate(sets), return_inverse=True)[1]
        self.codes, self.starts = code, np.r_[0, np.cumsum(self.sizes)]
        order = np.argsort(code, kind="stable")
        self.holders = np.repeat(np.arange(len(sets)), self.sizes)[order]
        self.edges = np.searchsorted(code[order], np.arange(code.max() + 2))

    def similar_to(self, i: int, others: np.ndarray) -> np.ndarray:
        """Those of ``others`` that are similar to i, by whole sets."""
        mine = self.codes[self.starts[i] : self.starts[i + 1]]
        lo, n = self.edges[mine], self.edges[mine + 1] - self.edges[mine]
        at = np.repeat(lo - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
        both = np.bincount(self.holders[at], minlength=len(self.sizes))[others]
        return others[both * OF >= (self.sizes[i] + self.sizes[others] - both) * LEAST]


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links (u, v) that join labels inside a bucket (bucket, side, node, n, fp, label, shingles); of two sides, only those across."""
    got = [b for b in batches if b.num_rows]
    if not got:
        return
    t = pa.Table.from_batches(got)
    bucket, side, node, n, fp, label = (t.column(i).to_numpy() for i in range(6))
    order = np.lexsort((gray_rank(fp.view(np.uint64)), bucket))
    bucket, side, node, n, fp, label = bucket[order], side[order], node[order], n[order], fp[order].view(np.uint64), label[order]
    shingles = t.column(6).combine_chunks()
    at = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
    us, vs = [], []
    for lo, hi in zip(at.tolist(), [*at[1:].tolist(), len(bucket)]):
        parent = np.unique(label[lo:hi], return_inverse=True)[1]
        parent = np.unique(parent, return_index=True)[1][parent]  # the first of each label
        if not parent.any():
            continue
        own, sides, sizes = None, side[lo:hi], n[lo:hi]
        for q, hit in GrayIndex(bucket[lo:hi], fp[lo:hi]).hits(WIDE_BITS, parent):
            ok = (np.minimum(sizes[q], sizes[hit]) * OF >= np.maximum(sizes[q], sizes[hit]) * LEAST) & ((sides[q] != sides[hit]) | (sides[q] < 0))
            q, hit = q[ok], hit[ok]
            start = np.flatnonzero(np.r_[True, q[1:] != q[:-1]]) if len(q) else q
            for s, e in zip(start.tolist(), [*start[1:].tolist(), len(q)]):
                i, others = int(q[s]), hit[s:e]
                others = others[parent[others] != parent[i]]
                if len(others):
                    own = own or _Bucket([np.frombuffer(shingles[int(k)].as_py(), np.uint64) for k in order[lo:hi]])
                    near = own.similar_to(i, others)
                    near = near[np.unique(parent[near], return_index=True)[1]]  # one link for each label is enough
                    unite(parent, np.full(len(near), i), near)
                    us.append(np.full(len(near), node[lo + i]))
                    vs.append(node[lo + near])
        give_back()
    if us:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], names=["u", "v"])


def _tiled(labelled: DataFrame, tile: int) -> DataFrame:
    """(bucket, side, node, n, fp, label) of buckets with several labels; one of over ``tile`` nodes is cut to parts that meet two by two."""
    several = labelled.groupBy("band").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("size")).where("lo <> hi")
    parts = F.ceil(F.col("size") / tile).cast("int")
    rows = labelled.join(several.select("band", parts.alias("parts")), "band").withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    bucket = F.when(F.col("parts") == 1, F.col("band")).otherwise(F.xxhash64("band", F.least("own", "other"), F.greatest("own", "other")))
    return rows.select(bucket.alias("bucket"), F.when(F.col("own") == F.col("other"), -1).otherwise(F.col("own")).alias("side"), "node", "n", "fp", "label")


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * OF >= (len(a) + len(b) - both) * LEAST


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches (node, text) to (node, shingles) where the text is the node's: rows of one doc_id may differ in text."""
    import xxhash

    for b in batches:
        sets = [shingle_set(t.as_py()).tobytes() for t in b.column(1)]
        own = np.fromiter(map(xxhash.xxh64_intdigest, sets), np.uint64, len(sets)).view(np.int64) == b.column(0).to_numpy()
        give_back()
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.binary())], names=["node", "shingles"]).filter(pa.array(own))


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches (u, v, set of u, set of v) to the pairs (u, v) that are similar."""
    for b in batches:
        a, c = b.column(2), b.column(3)
        keep = [similar(np.frombuffer(a[i].as_py(), np.uint64), np.frombuffer(c[i].as_py(), np.uint64)) for i in range(b.num_rows)]
        give_back()
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["u", "v"]).filter(pa.array(keep, pa.bool_()))


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    left = sets.select(F.col("node").alias("u"), F.col("shingles").alias("a"))
    right = sets.select(F.col("node").alias("v"), F.col("shingles").alias("b"))
    return cut_lineage(pairs.distinct().join(left, "u").join(right, "v").select("u", "v", "a", "b").mapInArrow(_compared, "u long, v long"))


def near_copy_components(docs: DataFrame, tile: int = 8192) -> DataFrame:
    """(doc_id, component_id) for every row of ``docs`` (doc_id, text); component_id is the smallest doc_id that chains of similar texts reach.

    Texts of equal shingle sets are one node; blank and null texts are one too. What meets is first compared with one
    member of its bucket, which settles large groups of copies without all of their pairs. Where a bucket still has several
    components, its sets come together once, at most two times ``tile`` of them, and the index finds what to compare.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    marked = cut_lineage(docs.select("doc_id", "text").mapInArrow(_marked, f"doc_id {kind}, node long, n long, fp long, bands binary"))
    first = cut_lineage(marked.where("doc_id is not null").groupBy("node", "n", "fp", "bands").agg(F.min("doc_id").alias("rep")))
    dealt = first.select("node", "n", "fp", "bands").mapInArrow(_banded, "band long, node long, n long, fp long")
    dealt = dealt.repartition(partitions_for(first.count() * BANDS, 1_000_000), "band")
    met = cut_lineage(dealt.mapInArrow(_met, "band long, node long, n long, fp long, head long, head_n long, head_fp long"))
    some = cut_lineage(met.select(F.col("node").alias("at")).distinct().join(first.select("node", "rep"), F.col("at") == F.col("node")).select("at", "rep"))
    few = some.count() <= 2_000_000  # tens of MB; beyond, both sides are shuffled
    wanted = F.broadcast(some) if few else some
    own = marked.select("doc_id", "node").join(wanted, (F.col("node") == F.col("at")) & (F.col("doc_id") == F.col("rep"))).select(F.col("doc_id").alias("rep"), "node").distinct()
    texts = docs.select("doc_id", "text").join(F.broadcast(own) if few else own, F.col("doc_id") == F.col("rep")).select("node", "text")
    sets = cut_lineage(texts.mapInArrow(_sets, "node long, shingles binary").dropDuplicates(["node"]))
    near = (F.least("n", "head_n") * OF >= F.greatest("n", "head_n") * LEAST) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("head_fp"))) <= WIDE_BITS) & (F.col("node") != F.col("head"))
    links = _verified(met.where(near).select(F.col("head").alias("u"), F.col("node").alias("v")), sets)
    roots = connected_components(links).withColumnRenamed("node", "at")
    labelled = cut_lineage(met.join(roots, met["node"] == roots["at"], "left").select("band", "node", "n", "fp", F.coalesce("root", "node").alias("label")))
    tiled = cut_lineage(_tiled(labelled, tile))
    tiled = tiled.join(sets, "node").select("bucket", "side", "node", "n", "fp", "label", "shingles").repartition(partitions_for(tiled.count(), 20_000), "bucket")
    more = cut_lineage(tiled.mapInArrow(_across, "u long, v long"))
    roots = connected_components(links.union(more)).withColumnRenamed("node", "at")
    named = cut_lineage(first.join(roots, first["node"] == roots["at"], "left").select("node", "rep", F.coalesce("root", "node").alias("root")))
    least = named.groupBy("root").agg(F.min("rep").alias("component_id"))
    return marked.select("doc_id", "node").join(named.join(least, "root").select("node", "component_id"), "node", "left").select("doc_id", "component_id")


def _without(docs: DataFrame, components: DataFrame) -> DataFrame:
    gone = free_name(docs, "gone")
    dropped = cut_lineage(components.where("doc_id <> component_id").select(F.col("doc_id").alias(gone)).distinct())
    if dropped.count() <= 500_000:  # a few MB; beyond, both sides are shuffled
        dropped = F.broadcast(dropped)
    return docs.join(dropped, docs["doc_id"] == dropped[gone], "left_anti")


def drop_near_duplicates(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """``docs`` without the documents whose component of linked fingerprints has a smaller doc_id; of rows with an equal doc_id all stay."""
    return _without(docs, simhash_components(docs, max_bits))


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """``docs`` without the documents whose component of near copies has a smaller doc_id; of rows with an equal doc_id all stay."""
    return _without(docs, near_copy_components(docs))
