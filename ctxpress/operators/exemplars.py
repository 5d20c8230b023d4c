"""Few-shot examples: features, number of clusters by silhouette, prototypes, and a small set of shots."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.functions.scalar import squared_distance
from ctxpress.sources.tables import hash_sample


def standardize(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    """Zero mean and unit variance; a constant column becomes zeros. One aggregate, one row broadcast."""
    stats = df.agg(*[f(F.col(c).cast("double")).alias(f"{p}{i}") for i, c in enumerate(cols) for p, f in (("m", F.avg), ("s", F.stddev_samp))])
    t = df.crossJoin(F.broadcast(stats))
    return t.select(*df.columns, *[F.coalesce(F.try_divide(F.col(c) - F.col(f"m{i}"), F.col(f"s{i}")), F.lit(0.0)).alias(f"{c}_z") for i, c in enumerate(cols)])


def numeric_features(df: DataFrame, key: str, cols: Sequence[str]) -> DataFrame:
    z = standardize(df, cols)
    return z.select(F.col(key).alias("id"), F.array(*[F.col(f"{c}_z") for c in cols]).alias("vec"))


def text_features(df: DataFrame, key: str, dim: int = 64, text_col: str = "text") -> DataFrame:
    """Hashed word counts, log-damped and of unit length; a stand-in for a sentence encoder."""
    from ctxpress.operators.fidelity import HashedWords

    return df.select(F.col(key).alias("id"), HashedWords(dim).encode(F.col(text_col)).alias("vec"))


def as_vectors(features: DataFrame) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return features.select("id", "vec", array_to_vector("vec").alias("features"))


def laid_out(features: DataFrame, each: int = 5000) -> DataFrame:
    """The same rows in the same order in parts of about ``each``, as the initial centres depend on the layout."""
    return features.repartitionByRange(max(1, features.count() // each), "id").sortWithinPartitions("id")


def silhouette_sweep(features: DataFrame, ks: Sequence[int] = range(5, 51), seed: int = 1, max_iter: int = 20, sample_fraction: float | None = None) -> tuple[DataFrame, int]:
    """(k, silhouette) for every k, and the best k, the smallest on a tie. Fits may run on a hash sample of the rows.

    Rows are ordered by id first, as the initial centres depend on how rows are laid out.
    """
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.evaluation import ClusteringEvaluator

    data = hash_sample(features, "id", sample_fraction) if sample_fraction else features
    data = as_vectors(laid_out(data)).persist()
    def fit(k: int) -> tuple[int, float]:
        model = KMeans(k=k, seed=seed, maxIter=max_iter).fit(data)
        found = model.transform(data)
        one = found.select("prediction").distinct().limit(2).count() < 2
        return int(k), -1.0 if one else float(ClusteringEvaluator().evaluate(found))

    try:
        with ThreadPoolExecutor(8) as pool:  # fits are many short jobs; several at a time share the cluster
            rows = list(pool.map(fit, ks))
    finally:
        data.unpersist()
    best = max(rows, key=lambda r: (r[1], -r[0]))[0]
    return features.sparkSession.createDataFrame(rows, "k int, silhouette double"), best


def sample_share(features: DataFrame, most: int = 50_000) -> float | None:
    """Share of the rows that a sweep may fit on: all of up to ``most``, about that many of more."""
    n = features.count()
    return None if n <= most else most / n


def cluster(features: DataFrame, k: int, seed: int = 1, max_iter: int = 20) -> DataFrame:
    """(id, vec, cluster) of all rows by k-means."""
    from pyspark.ml.clustering import KMeans

    data = as_vectors(laid_out(features))
    return KMeans(k=k, seed=seed, maxIter=max_iter, predictionCol="cluster").fit(data).transform(data).select("id", "vec", "cluster")


def centroids(assigned: DataFrame) -> DataFrame:
    """(cluster, center): means of members, dimension by dimension."""
    dims = assigned.select("cluster", F.posexplode("vec").alias("d", "v")).groupBy("cluster", "d").agg(F.avg(F.col("v").cast("double")).alias("v"))
    return dims.groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "v"))), lambda x: x["v"]).alias("center"))


def prototypes(assigned: DataFrame) -> DataFrame:
    """(cluster, id, size, distance): the member nearest to the centre of each cluster, the smaller id on a tie."""
    t = assigned.join(F.broadcast(centroids(assigned)), "cluster")
    t = t.withColumn("distance", F.round(squared_distance(F.col("vec"), F.col("center")), 6))
    return t.groupBy("cluster").agg(F.min_by("id", F.struct("distance", "id")).alias("id"), F.count("*").alias("size"), F.min("distance").alias("distance"))


def few_shot(protos: DataFrame, n: int = 3, rule: str = "largest") -> DataFrame:
    if rule == "all":
        return protos
    order = (F.desc("size"), F.asc("id")) if rule == "largest" else (F.asc("distance"), F.asc("id"))
    return protos.orderBy(*order).limit(n)


def random_shots(df: DataFrame, key: str, n: int = 3, seed: int = 7) -> DataFrame:
    """``n`` rows in an order mixed by ``seed``: the baseline for prototypes."""
    mixed = (F.col(key) * F.lit(2654435761) + F.lit(seed)) % F.lit(4294967296)
    return df.withColumn("mixed", mixed).orderBy("mixed", key).limit(n)


def silhouette_exact(assigned: DataFrame) -> DataFrame:
    """(id, cluster, a, b, s) from all pairs of points: brute force, the check of the sweep's measure.

    All vectors go to every task as one matrix in order of cluster, some ten megabytes for 20 000 of 64 numbers; points are compared with
    it by blocks, and no pair becomes a row. Distances come from inner products; where those cancel, from differences.
    """
    rows = assigned.where("cluster is not null").select("cluster", F.col("vec").cast("array<double>").alias("vec")).toArrow()
    names, label = np.unique(rows["cluster"].to_numpy(), return_inverse=True)
    order = np.argsort(label, kind="stable")
    every = rows["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(label), -1)[order] if len(label) else np.zeros((0, 0))
    sizes = np.bincount(label, minlength=len(names))
    starts = np.cumsum(sizes) - sizes
    shared = assigned.sparkSession.sparkContext.broadcast((every, names, sizes, starts))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        y, names, sizes, starts = shared.value
        at, norms = {c: i for i, c in enumerate(names.tolist())}, (y * y).sum(1)
        for f in frames:
            a, b = np.full(len(f), np.nan), np.full(len(f), np.nan)
            vecs, owns = f["vec"].to_numpy(), [at.get(c) for c in f["cluster"].astype(object)]
            for lo in range(0, len(f), 64):
                x = np.array(vecs[lo : lo + 64].tolist(), dtype=np.float64)
                scale = (x * x).sum(1)[:, None] + norms
                d = scale - 2 * (x @ y.T)
                i, j = np.nonzero(d < 1e-6 * scale)
                for k in range(0, len(i), 65536):
                    u, v = i[k : k + 65536], j[k : k + 65536]
                    d[u, v] = ((x[u] - y[v]) ** 2).sum(1)
                total = np.add.reduceat(np.sqrt(d), starts, axis=1)
                for r, own in enumerate(owns[lo : lo + 64]):
                    if own is not None:
                        a[lo + r] = total[r, own] / (sizes[own] - 1) if sizes[own] > 1 else np.nan
                        b[lo + r] = min((v for c, v in enumerate((total[r] / sizes).tolist()) if c != own), default=np.nan)
            yield pd.DataFrame({"id": f["id"], "own": f["cluster"], "a": [None if np.isnan(v) else v for v in a], "b": [None if np.isnan(v) else v for v in b]})

    kinds = dict(assigned.dtypes)
    t = assigned.select("id", "cluster", F.col("vec").cast("array<double>").alias("vec")).repartition("id").mapInPandas(run, f"id {kinds['id']}, own {kinds['cluster']}, a double, b double")
    s = F.when(F.col("a").isNull() | F.col("b").isNull(), F.lit(0.0)).otherwise(F.coalesce(F.try_divide(F.col("b") - F.col("a"), F.greatest("a", "b")), F.lit(0.0)))
    return t.select("id", F.col("own").alias("cluster"), "a", "b", s.alias("s"))


def coverage(points: DataFrame, shots: DataFrame) -> DataFrame:
    """(id, label, nearest, nearest_label, distance) of every point to its nearest shot; shots are a handful, broadcast."""
    t = points.crossJoin(F.broadcast(shots.select(F.col("id").alias("sid"), F.col("vec").alias("svec"), F.col("label").alias("slabel"))))
    t = t.withColumn("d", F.round(squared_distance(F.col("vec"), F.col("svec")), 6))
    return t.groupBy("id", "label").agg(F.min_by("sid", F.struct("d", "sid")).alias("nearest"), F.min_by("slabel", F.struct("d", "sid")).alias("nearest_label"), F.min("d").alias("distance"))


def farthest_first(features: DataFrame, n: int = 3) -> list:
    """Ids of ``n`` points, each as far as can be from those before it; the first is the smallest id. A scan for each."""
    first = features.orderBy("id").limit(1).first()
    if first is None:
        return []
    out, f = [first["id"]], features.withColumn("near", squared_distance(F.col("vec"), F.array(*[F.lit(float(v)) for v in first["vec"]])))
    for _ in range(n - 1):
        top = f.orderBy(F.desc("near"), "id").limit(1).first()
        if top is None or top["near"] <= 0:
            break
        out.append(top["id"])
        f = f.withColumn("near", F.least("near", squared_distance(F.col("vec"), F.array(*[F.lit(float(v)) for v in top["vec"]]))))
    return out


def rank_within(df: DataFrame, by: str, *order) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(*order)))
