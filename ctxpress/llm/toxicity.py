"""Toxicity from bags of subword embeddings under a linear softmax, trained jointly.

A word is the mean of the embeddings of its hashed character n-grams, its boundaries included, so that misspelt and unseen
words share vectors with those they resemble. A short window of words is the mean of its words and is classified by a
linear softmax; both are learned together by gradient descent. A document is as toxic as its worst window, since a few
words among thousands decide its label: after a first pass in which every window carries its document's label, only the worst
window of a toxic document does. A held-back part of the training sample calibrates the document score.

At scoring, the classifier is folded into the embeddings: one number for each n-gram bucket.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxpress.llm.common import text_parts

BUCKETS, DIM, GRAMS, WORDS, STRIDE = 1 << 16, 8, (3, 4, 5, 6), 8, 4
BLOCK = 1 << 20


def spaced_bytes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Lower-case texts as bytes with one space around each word, and the number of words in each text."""
    words = [(t or "").lower().split() for t in texts]
    joined = " " + " ".join(" ".join(w) for w in words if w) + " "
    return np.frombuffer(joined.encode("utf-8", "replace"), np.uint8), np.array([len(w) for w in words], np.int64)


def gram_buckets(b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each length: the buckets of the n-grams inside single words, and the word of each."""
    spaces = np.cumsum(b == 32, dtype=np.int32)
    h = b.astype(np.uint32)
    for n in range(2, max(GRAMS) + 1):
        if len(b) < n:
            return
        h = h[:-1] * np.uint32(0x01000193) + b[n - 1 :]
        if n in GRAMS:
            ok = np.flatnonzero(spaces[n - 2 : len(b) - 1] == spaces[: len(b) - n + 1]) if n > 2 else np.arange(len(h))
            x = h[ok] * np.uint32(0x9E3779B1) + np.uint32(n)
            yield (x ^ (x >> np.uint32(15))) & np.uint32(BUCKETS - 1), spaces[ok + 1] - 1


def windows(counts: np.ndarray, size: int = WORDS, stride: int = STRIDE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word ranges [lo, hi) of the windows of texts laid end to end, and the text of each; a short text is one window."""
    many = np.where(counts > 0, np.maximum(0, -(-(counts - size) // stride)) + 1, 0)
    doc = np.repeat(np.arange(len(counts)), many)
    start = np.cumsum(counts) - counts
    k = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
    lo = start[doc] + np.minimum(k * stride, np.maximum(counts[doc] - size, 0))
    return lo, np.minimum(lo + size, (start + counts)[doc]), doc


def worst_window(texts: list[str | None], table: np.ndarray) -> np.ndarray:
    """For each text the greatest mean over a window of its words' means; minus infinity without words."""
    b, counts = spaced_bytes(texts)
    total = int(counts.sum())
    out = np.full(len(texts), -np.inf)
    if not total:
        return out
    sums, n = np.zeros(total), np.zeros(total)
    for bucket, word in gram_buckets(b):
        sums += np.bincount(word, table[bucket], total)
        n += np.bincount(word, minlength=total)
    run = np.r_[0, np.cumsum(sums / np.maximum(n, 1))]
    lo, hi, doc = windows(counts)
    np.maximum.at(out, doc, (run[hi] - run[lo]) / (hi - lo))
    return out


class ToxicityModel:
    """Embeddings folded with the classifier into one weight for each bucket, a bias and the calibration."""

    def __init__(self, table: np.ndarray, bias: float, slope: float, offset: float, empty: float = 0.0):
        self.table, self.bias, self.slope, self.offset, self.empty = table.astype(np.float32), bias, slope, offset, empty

    def score(self, texts: list[str | None]) -> np.ndarray:
        m = worst_window(texts, self.table)
        some = np.isfinite(m)
        score = 1.0 / (1.0 + np.exp(-np.clip(self.slope * (np.where(some, m, 0.0) + self.bias) + self.offset, -50, 50)))
        return np.where(some, score, self.empty)


def _bags(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """N-gram buckets and weights of the training windows, laid end to end with their starts; the text of each window."""
    b, counts = spaced_bytes(texts)
    got = list(gram_buckets(b))
    bucket, word = np.concatenate([x for x, _ in got]), np.concatenate([w for _, w in got])
    order = np.argsort(word, kind="stable")
    bucket, word = bucket[order].astype(np.int32), word[order]
    per_word = np.bincount(word, minlength=int(counts.sum()))
    first = np.r_[0, np.cumsum(per_word)]
    lo, hi, doc = windows(counts, stride=WORDS)
    size = first[hi] - first[lo]
    keep = size > 0
    lo, hi, doc, size = lo[keep], hi[keep], doc[keep], size[keep]
    at = np.repeat(first[lo] - (np.cumsum(size) - size), size) + np.arange(size.sum())
    weight = (1.0 / (per_word[word[at]] * np.repeat(hi - lo, size))).astype(np.float32)
    return bucket[at], weight, np.cumsum(size) - size, doc


def train(texts: list[str], labels: np.ndarray, prior: float | None = None, rounds: int = 5, steps: int = 600, batch: int = 1024, block: int = 1 << 18, rate: float = 0.5, seed: int = 7) -> ToxicityModel:
    """Fits embeddings and softmax on windows by adaptive gradient steps; deterministic for the same sample.

    There are ``rounds`` passes over the windows or more, if a small sample needs them for ``steps`` steps. ``prior`` is the
    share of toxic documents outside the sample; scores are calibrated to it.
    """
    rng = np.random.default_rng(seed)
    if not len(texts) or labels.min() == labels.max():
        flat = 0.0 if not len(texts) else (8.0 if labels[0] else -8.0)
        return ToxicityModel(np.zeros(BUCKETS), 0.0, 0.0, flat)
    held = np.arange(len(texts)) % 4 == 3
    e = rng.normal(0, 1.0 / DIM, (BUCKETS, DIM)).astype(np.float32)
    w, bias = np.zeros((DIM, 2), np.float32), np.zeros(2, np.float32)
    w[0] = (-1.0, 1.0)
    ge, gw, gb = np.full(BUCKETS, 1e-6, np.float32), np.full(w.shape, 1e-6, np.float32), np.full(2, 1e-6, np.float32)

    def folded() -> np.ndarray:
        return e @ (w[:, 1] - w[:, 0])

    words, done = sum(len(t.split()) for t in texts), 0
    for k in range(int(np.clip(-(-steps * batch * WORDS // max(1, words)), rounds, 40))):
        seen = np.ones(2)
        order = rng.permutation(np.flatnonzero(~held))
        for x0, x1 in blocks([texts[i] for i in order], block):
            some = order[x0:x1]
            bucket, weight, start, doc = _bags([texts[i] for i in some])
            if not len(start):
                continue
            y_all, stop = labels[some][doc], np.r_[start[1:], len(bucket)]
            use = np.ones(len(start), bool)
            if k and done >= steps // 3:  # of a toxic text the worst window, of clean ones the worst and some others
                value = np.add.reduceat(folded()[bucket] * weight, start)
                top = np.full(len(some), -np.inf)
                np.maximum.at(top, doc, value)
                use = (value >= top[doc]) | ((y_all == 0) & (rng.random(len(doc)) < 0.5))
            pick = rng.permutation(np.flatnonzero(use))
            seen += np.bincount(y_all[pick], minlength=2)
            balance = (0.5 * seen.sum() / seen).astype(np.float32)
            for i in range(0, len(pick), batch):
                done += 1
                sel = pick[i : i + batch]
                size = stop[sel] - start[sel]
                at = np.repeat(start[sel] - (np.cumsum(size) - size), size) + np.arange(size.sum())
                g, a, head = bucket[at], weight[at], np.cumsum(size) - size
                x = np.add.reduceat(e[g] * a[:, None], head)
                z = x @ w + bias
                p = np.exp(z - z.max(1, keepdims=True))
                p /= p.sum(1, keepdims=True)
                y = y_all[sel]
                p[np.arange(len(sel)), y] -= 1
                p *= balance[y][:, None]
                dx = p @ w.T
                rows = np.repeat(np.arange(len(sel)), size)
                de = np.stack([np.bincount(g, dx[rows, j] * a, BUCKETS) for j in range(DIM)], 1).astype(np.float32)
                dw, db = x.T @ p / len(sel), p.mean(0)
                ge += (de * de).mean(1)
                gw += dw * dw
                gb += db * db
                e -= rate * de / np.sqrt(ge)[:, None]
                w -= 0.1 * dw / np.sqrt(gw)
                bias -= 0.1 * db / np.sqrt(gb)
    model = ToxicityModel(folded(), float(bias[1] - bias[0]), 1.0, 0.0, empty=float(prior or 0.0))
    back = [texts[i] for i in np.flatnonzero(held)]
    m = np.concatenate([worst_window(back[i:j], model.table) for i, j in blocks(back, block)]) + model.bias
    y = labels[held].astype(float)
    model.slope, model.offset = calibrate(m[np.isfinite(m)], y[np.isfinite(m)])
    if prior is not None and 0 < prior < 1 and 0 < y.mean() < 1:
        model.offset += float(np.log(prior / (1 - prior)) - np.log(y.mean() / (1 - y.mean())))
    return model


def calibrate(m: np.ndarray, y: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """Logistic regression on one measure, slightly damped, by Newton's steps."""
    if len(m) < 2 or y.min() == y.max():
        return 1.0, 0.0
    mean, scale = m.mean(), m.std() + 1e-9
    x = np.stack([(m - mean) / scale, np.ones(len(m))], 1)
    c = np.zeros(2)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ c, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag([0.05, 1e-3])
        step = np.linalg.solve(h, x.T @ (p - y) + np.array([0.05 * c[0], 1e-3 * c[1]]))
        c -= np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return float(c[0] / scale), float(c[1] - c[0] * mean / scale)


def labelled_sample(docs: DataFrame, labels: DataFrame, most_each: int = 2000) -> tuple[list[str], np.ndarray, float | None]:
    """Texts, labels, and the share of label 1 among all rows that may be learned from. At most about ``most_each`` texts of each label, picked by hash of doc_id outside the held-out rows, in order of doc_id."""
    rows = labels.where(F.col("toxic").isNotNull() & (F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) != 2))
    rows = rows.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {r["toxic"]: r["count"] for r in rows.groupBy("toxic").count().collect()}
    share = F.lit(0)
    for k, n in counts.items():
        share = F.when(F.col("toxic") == k, F.lit(int(1_000_000 * min(1.0, most_each / n)))).otherwise(share)
    ids = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1_000_000)) < share)
    spark = docs.sparkSession
    chosen = ids.collect()  # at most about twice most_each rows
    ids = spark.createDataFrame([(r["doc_id"], int(r["toxic"])) for r in chosen], "doc_id long, toxic int")
    got = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(ids), "doc_id").collect()
    got = sorted({(r["doc_id"], r["text"], r["toxic"]) for r in got})
    prior = counts.get(1, 0) / sum(counts.values()) if counts else None
    return [t for _, t, _ in got], np.array([y for _, _, y in got], np.int64), prior


def blocks(texts: list, most: int = BLOCK):
    """Index ranges of texts that make up about ``most`` characters."""
    lo, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t or "") > most:
            yield lo, i
            lo, size = i, 0
        size += len(t or "")
    if lo < len(texts):
        yield lo, len(texts)


def score_toxicity(docs: DataFrame, model: ToxicityModel, threshold: float = 0.3) -> DataFrame:
    """(doc_id, score, predicted) for every row; a null or wordless text has the share of toxic
    documents as its score."""

    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = np.concatenate([model.score(texts) for _, texts in text_parts(b.column(1), BLOCK)] or [np.zeros(0)])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(f, f"doc_id {kind}, score double, predicted int")


def op1_toxicity(spark, sf_dir: str) -> DataFrame:
    """A score for every row of ``documents``, learnt from the others' labels; a null or empty text has the score of no evidence, repeated rows score alike."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    model = train(*labelled_sample(docs, labels))
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2, F.lit(False))
    return score_toxicity(docs, model).select("doc_id", held.alias("held_out"), "score", "predicted")
