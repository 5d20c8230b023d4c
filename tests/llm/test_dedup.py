"""Near-duplicate and repeat operators against brute force, and on awkward tables."""

import hashlib
import random

import numpy as np
import pyarrow.compute  # noqa: F401
import pytest

from ctxpress.llm import embedding_dedup, graph, simhash, suffix_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _id string, chunk int"


def rows(*texts):
    return [(i, t, "en", "s", None if t is None else len(t), "x", 1) for i, t in enumerate(texts)]


def words(rng, n):
    return " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 7))) for _ in range(n))


def test_components_of_chains_stars_and_nothing(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + k) for k in range(1, 300)] + [(7, 7), (None, 3), (500, 501), (501, 500)]
    found = {r["node"]: r["root"] for r in graph.connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert found == {i: 0 for i in range(41)} | {100 + k: 100 for k in range(300)} | {500: 500, 501: 500}
    assert graph.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_fingerprint_is_the_majority_of_shingle_hashes(spark):
    text = "The quick  Brown\tfox jumps over the lazy dog the quick brown fox jumps"
    w = text.lower().split()
    hs = [r[0] & (2**64 - 1) for r in spark.createDataFrame([(" ".join(w[i : i + 4]),) for i in range(len(w) - 3)], "s string").selectExpr("xxhash64(s)").collect()]
    want = sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))
    assert simhash.fingerprint(text) == want
    one = spark.sql("select xxhash64('a b')").first()[0] & (2**64 - 1)
    assert simhash.fingerprint("A  b ") == one
    assert simhash.fingerprint(None) == simhash.fingerprint(" \n") == 0


@pytest.mark.parametrize("max_bits", [3, 4])
def test_gray_index_finds_every_component(max_bits):
    rng = np.random.default_rng(max_bits)
    base = rng.integers(0, 2**63, 60, dtype=np.uint64)
    fps = [b ^ np.uint64(sum(1 << int(i) for i in rng.choice(64, rng.integers(0, 7), replace=False))) for b in base for _ in range(20)]
    fps = np.unique(np.array(fps, np.uint64))
    bucket = np.sort(rng.integers(0, 3, len(fps)))
    order = np.lexsort((simhash.gray_rank(fps), bucket))
    fps, bucket = fps[order], bucket[order]
    got = simhash.GrayIndex(bucket, fps).component_links(max_bits, room=500)
    want = np.arange(len(fps))
    for i in range(len(fps)):
        j = np.flatnonzero((np.bitwise_count(fps ^ fps[i]) <= max_bits) & (bucket == bucket[i]))
        simhash.unite(want, j, np.full(len(j), i))
    assert np.array_equal(got, want)


def test_simhash_components_match_brute_force(spark):
    rng = random.Random(1)
    texts = [None, "", "one", "one", "  "]
    for _ in range(25):
        w = words(rng, 200).split()
        texts.append(" ".join(w))
        for _ in range(rng.randint(0, 3)):
            v = list(w)
            v[rng.randrange(200)] = "changed"
            texts.append(" ".join(v))
    docs = spark.createDataFrame(rows(*texts), SCHEMA)
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.simhash_components(docs).collect()}
    fps = np.array([simhash.fingerprint(t) for t in texts], np.uint64)
    parent = np.arange(len(texts))
    for i in range(len(texts)):
        j = np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 4)
        simhash.unite(parent, j, np.full(len(j), i))
    assert got == {i: (f"{int(f):016x}", int(parent[i])) for i, f in enumerate(fps)}
    kept = simhash.drop_near_duplicates(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted({int(p) for p in parent})


def test_more_blocks_for_more_fingerprints():
    blocks, choices = simhash.block_plan(10**6, 4)
    assert len(choices) == 5 and sum(w for _, w in blocks) == 64
    assert len(simhash.block_plan(10**9, 4)[1]) > 5


def brute_cut(texts):
    data = {i: (t or "").encode() for i, t in texts}
    first = {}
    for i in sorted(data):
        for j in range(len(data[i]) - 49):
            first.setdefault(data[i][j : j + 50], i)
    out = {}
    for i, b in data.items():
        gone = [False] * len(b)
        for j in range(len(b) - 49):
            if first[b[j : j + 50]] < i:
                gone[j : j + 50] = [True] * 50
        kept = bytes(c for c, g in zip(b, gone) if not g)
        spans = sum(g and not (x and gone[x - 1]) for x, g in enumerate(gone))
        out[i] = (len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


def test_repeats_match_brute_force(spark):
    rng = random.Random(2)
    shared = [words(rng, 25) for _ in range(6)]
    texts = [None, "", "short", "x" * 300, "x" * 51, "é" * 120, "aé" * 60]
    for _ in range(60):
        parts = [words(rng, rng.randint(1, 40)) for _ in range(3)]
        for s in rng.sample(shared, rng.randint(0, 3)):
            lo = rng.randrange(0, 20)
            parts.insert(rng.randrange(len(parts) + 1), s[lo : lo + rng.randint(40, 120)])
        texts.append(rng.choice(["", " ", "\n"]).join(parts))
    texts += [texts[20], texts[21] + "tail", "é" * 30 + texts[22]]
    got = suffix_dedup.remove_repeats(spark.createDataFrame(rows(*texts), SCHEMA), chunk_bytes=2000)
    assert set(SCHEMA.replace(",", "").split()[::2]) - {"text"} <= set(got.columns)
    found = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got.collect()}
    assert found == brute_cut(list(enumerate(texts)))


def test_long_documents_are_cut_in_parts(monkeypatch):
    monkeypatch.setattr(suffix_dedup, "LONGEST", 500)
    monkeypatch.setattr(suffix_dedup, "PIECE", 300)
    rng = random.Random(3)
    texts = [words(rng, 400), words(rng, 30), words(rng, 600)]
    data = np.frombuffer("".join(texts).encode(), np.uint8)
    off = np.r_[0, np.cumsum([len(t) for t in texts])]
    parts = suffix_dedup.all_runs(data, off, True)
    monkeypatch.undo()
    whole = suffix_dedup.all_runs(data, off, True)
    windows = lambda r: sorted((w, int(d)) for a, b, d in zip(r["first"], r["last"], r["doc"]) for w in range(a, b + 1))
    assert windows(parts) == windows(whole) == [(int(off[i]) + j, i) for i, t in enumerate(texts) for j in range(len(t) - 49)]


def test_merged_transforms_sort_the_collection():
    rng = random.Random(4)
    segs = sorted({"".join(rng.choice("ab") for _ in range(rng.randint(50, 80))) for _ in range(200)})
    least = np.array([rng.randrange(50) for _ in segs])
    low, first = suffix_dedup.window_least(np.frombuffer("".join(segs).encode(), np.uint8), np.array([len(s) for s in segs]), least, shard_bytes=900)
    want: dict = {}
    for s, d in zip(segs, least):
        for j in range(len(s) - 49):
            want[s[j : j + 50]] = min(want.get(s[j : j + 50], 99), d)
    assert low.tolist() == [want[s[j : j + 50]] for s in segs for j in range(len(s) - 49)]


def test_chunks_and_buckets_pack_each_other_one_blob_and_merge_in_parts(monkeypatch):
    import pyarrow as pa

    rng = random.Random(6)
    shared = [words(rng, 60) for _ in range(40)]
    texts = [" ".join((words(rng, 4), s[: rng.randint(100, len(s))], words(rng, 4))) for s in shared * 6]
    docs = pa.table({"_id": pa.array(range(len(texts)), pa.int64()), "_txt": texts})
    packs, merges = [], []
    pack, merge = suffix_dedup.pa.compress, suffix_dedup.window_least
    monkeypatch.setattr(suffix_dedup.pa, "compress", lambda *a, **k: packs.append(1) or pack(*a, **k))
    monkeypatch.setattr(suffix_dedup, "window_least", lambda body, *a, **k: merges.append(len(body)) or merge(body, *a, **k))
    monkeypatch.setattr(suffix_dedup, "MERGED", 4000, raising=False)
    key = lambda i: (pa.scalar(i),)
    halves = [docs.slice(0, 120), docs.slice(120)]
    by = lambda t, name: {i: t.filter(pa.compute.equal(t[name], i)) for i in t[name].unique().to_pylist()}
    said = pa.concat_tables(suffix_dedup.report(5, 3)(key(i), t) for i, t in enumerate(halves))
    known = by(pa.concat_tables(suffix_dedup.agree(5)(t) for t in by(said, "bucket").values()), "chunk")
    sent = pa.concat_tables(suffix_dedup.send(5, 3)(key(i), t, known[i]) for i, t in enumerate(halves))
    assert len(packs) == sent.num_rows == 6  # one blob for each chunk and bucket, before it was four
    found = by(pa.concat_tables(suffix_dedup.decide(t) for t in by(sent, "bucket").values()), "chunk")
    assert len(packs) == 6 and len(merges) > 6 and max(merges) < 6000  # a bucket is merged in parts of whole minimisers
    got = [r for i, t in enumerate(halves) for r in suffix_dedup.cut(key(i), t, found[i]).to_pylist()]
    assert {r["_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == brute_cut(list(enumerate(texts)))


def test_repeated_rows_null_ids_and_empty_tables(spark):
    t = words(random.Random(5), 40)
    docs = spark.createDataFrame([(3, t), (3, t), (None, t), (1, None)], "doc_id long, text string")
    got = sorted((r["doc_id"] or -1, r["n_removed"]) for r in suffix_dedup.remove_repeats(docs).collect())
    assert got == [(-1, len(t)), (1, 0), (3, 0), (3, 0)]
    none = spark.createDataFrame([], "doc_id long, text string")
    assert suffix_dedup.remove_repeats(none).count() == simhash.simhash_components(none).count() == 0
    assert sorted((r[0] or -1, r[2] or -1) for r in simhash.simhash_components(docs).collect()) == [(-1, 3), (1, 1), (3, 3), (3, 3)]


def test_cosine_links_match_brute_force(spark):
    rng = np.random.default_rng(6)
    data = []
    for label in (0, 1, 2):
        for _ in range(60):
            c = rng.normal(size=16)
            data += [((c + rng.normal(size=16) * s).tolist(), label) for s in rng.choice([0.0, 0.05, 0.12, 0.2], 4)]
    data += [(None, 1), ([0.0] * 16, 1), ([float("nan")] + [1.0] * 15, 1), ([None] + [1.0] * 15, 1), (data[0][0], None), (data[0][0][:8], 0), ([2 * v for v in data[0][0]], 0)]
    vec = spark.createDataFrame([(i, v, g, "x") for i, (v, g) in enumerate(data)], "vec_id long, embedding array<double>, label int, kind string")
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embedding_dedup.cosine_components(vec, per_cell=25).collect()}
    n, parent = [0] * len(data), np.arange(len(data))
    fit = [v is not None and g is not None and None not in v and np.isfinite(v).all() and np.any(v) for v, g in data]
    for i, (v, g) in enumerate(data):
        for j in range(i):
            u, h = data[j]
            if fit[i] and fit[j] and g == h and len(u) == len(v) and np.dot(u, v) / np.linalg.norm(u) / np.linalg.norm(v) >= 0.98:
                n[i] += 1
                n[j] += 1
                simhash.unite(parent, np.array([i]), np.array([j]))
    assert got == {i: (n[i], int(parent[i]), int(parent[i]) == i) for i in range(len(data))}
    assert sum(n) > 100


def test_cover_tree_covers_with_halving_radii():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 8))
    x /= np.linalg.norm(x, axis=1)[:, None]
    t = embedding_dedup.CoverTree(x)
    assert sorted(t.order) == list(range(300))
    for a in range(len(t.center)):
        d = embedding_dedup.distance(x[t.order[t.first[a] : t.stop[a]]] @ x[t.center[a]])
        assert d.max() <= t.radius[a] + 1e-9 or t.stop[a] - t.first[a] == 1
        if t.kids[a] is not None:
            assert all(t.radius[k] <= t.radius[a] / 2 + 1e-9 for k in t.kids[a])


def test_empty_embeddings(spark):
    assert embedding_dedup.cosine_components(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


@pytest.mark.parametrize("n,dim,noise,centres", [(400, 16, 0.1, 50), (900, 8, 0.05, 5), (700, 64, 0.02, 1), (900, 4, 0.3, 10), (800, 64, 1.0, 1)])
def test_trees_and_planes_lose_no_link(n, dim, noise, centres):
    rng = np.random.default_rng(n)
    x = rng.normal(size=(centres, dim))[rng.integers(0, centres, n)] + noise * rng.normal(size=(n, dim))
    x /= np.linalg.norm(x, axis=1)[:, None]
    weight, home = rng.integers(1, 4, n), rng.random(n) < 0.7
    hit = (x @ x.T >= 0.98) & ~np.eye(n, dtype=bool)
    met = hit & (home[:, None] | home[None, :])
    for leaf in (1, 16, 128):
        links, parent = embedding_dedup.links_within(x, weight, home, 0.98, leaf)
        assert (links == np.where(home, (met * weight).sum(1), (met * np.where(home, weight, 0)).sum(1))).all()
        want = np.arange(n)
        simhash.unite(want, *np.nonzero(np.triu(met)))
        assert (parent == want).all()
    row, cell, at_home = embedding_dedup.Planes(x[::8], 16, 0.2).deal(x)
    assert sorted(row[at_home]) == list(range(n))
    total = np.zeros(n, int)
    for c in set(cell.tolist()):
        m = np.flatnonzero(cell == c)
        np.add.at(total, row[m], embedding_dedup.links_within(x[row[m]], weight[row[m]], at_home[m], 0.98)[0])
    assert (total == (hit * weight).sum(1)).all()


def test_rows_dealt_for_each_vector_stay_few(spark):
    rng = np.random.default_rng(9)
    for n in (500, 2000):
        x = np.repeat(rng.normal(size=(n // 5, 12)), 5, axis=0) + 0.02 * rng.normal(size=(n, 12))
        unique = spark.createDataFrame([("0:12", v.tolist(), i, 1) for i, v in enumerate(x)], "kind string, vec array<double>, rep long, n long")
        dealt = embedding_dedup.dealt_vectors(unique, 0.98, 256, 10_000)
        assert dealt.where("home").count() == n and dealt.count() < 2.5 * n
