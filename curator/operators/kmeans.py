"""Deterministic Lloyd iterations and their reports.

Centroids travel to the tasks as literals (k times d doubles) and come back as k times d averages; nothing else reaches the driver.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from curator.functions.expr import norm, squared_distance

Centroids = list[list[float]]


def initial(vectors: DataFrame, k: int, init: str = "first") -> Centroids:
    """Starting centroids: ``first`` k by id, first by ``hash`` of the id, or ``farthest`` from those chosen so far."""
    if init == "first":
        rows = vectors.orderBy("sample_id").limit(k).collect()
    elif init == "hash":
        rows = vectors.orderBy(F.md5(F.col("sample_id").cast("string")), "sample_id").limit(k).collect()
    elif init == "farthest":
        rows = vectors.orderBy("sample_id").limit(1).collect()
        while rows and len(rows) < k:
            near = F.array_min(nearest(F.col("v"), [r.v for r in rows]))
            rows += vectors.select("sample_id", "v", near.alias("d")).orderBy(F.desc("d"), "sample_id").limit(1).collect()
    else:
        raise ValueError(f"unknown init {init!r}")
    return [list(r.v) for r in rows]


def nearest(v: Column, centroids: Centroids) -> Column:
    """Array of the squared distances to every centroid."""
    literal = F.array(*(F.array(*(F.lit(float(x)) for x in c)) for c in centroids))
    return F.transform(literal, lambda c: squared_distance(v, c))


def assign(vectors: DataFrame, centroids: Centroids) -> DataFrame:
    """``sample_id, cluster_id, dist, v``: the nearest centroid, of equals the first."""
    if not centroids:
        return vectors.select("sample_id", F.lit(0).alias("cluster_id"), F.lit(0.0).alias("dist"), "v")
    if _regular(vectors, centroids):
        kinds = dict(vectors.dtypes)
        return vectors.select("sample_id", "v").mapInArrow(_assign_batches(centroids), f"sample_id {kinds['sample_id']}, cluster_id int, dist double, v array<double>")
    # The generator makes Spark evaluate the distances once.
    near = vectors.select("sample_id", "v", F.explode(F.array(nearest(F.col("v"), centroids))).alias("ds"))
    return near.select("sample_id", (F.array_position("ds", F.array_min("ds")) - 1).cast("int").alias("cluster_id"), F.sqrt(F.array_min("ds")).alias("dist"), "v")


def _regular(vectors: DataFrame, centroids: Centroids) -> bool:
    """Whether distances can be computed by batches; a centroid of another size, or with a null, has none."""
    return dict(vectors.dtypes)["v"] == "array<double>" and len({len(c) for c in centroids}) == 1 and len(centroids[0]) > 0 and not any(x is None for c in centroids for x in c)


def _distances(v, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of an Arrow array of vectors: which have a distance, these as rows, their nearest centroids, and the squared distances to them."""
    dim = centroids.shape[1]
    good = np.nan_to_num(v.value_lengths().to_numpy(zero_copy_only=False), nan=-1) == dim
    if v.flatten().null_count:
        good &= np.array([x is not None and None not in x for x in v.to_pylist()], bool)
    rows = v.filter(good).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
    across, total = np.ascontiguousarray(rows.T), np.zeros((len(centroids), len(rows)))
    # In the order of the dimensions, so that equal distances are equal to the last bit.
    for j in range(dim):
        gap = across[j] - centroids[:, j, None]
        total += gap * gap
    odd = np.isnan(total)
    nearest_ = np.where(odd, np.inf, total).argmin(axis=0)
    for i in np.flatnonzero(odd.any(axis=0)):
        nearest_[i] = min(range(len(centroids)), key=lambda c, i=i: (odd[c, i], total[c, i]))
    return good, rows, nearest_, total[nearest_, np.arange(len(rows))]


def _assign_batches(centroids: Centroids):
    def run(batches):
        import pyarrow as pa

        table = np.array(centroids, float)
        for batch in batches:
            v = batch.column("v")
            good, _, near, d = _distances(v, table)
            cluster, dist = np.zeros(len(v), np.int32), np.zeros(len(v))
            cluster[good], dist[good] = near, np.sqrt(d)
            yield pa.RecordBatch.from_arrays([batch.column("sample_id"), pa.array(cluster, mask=~good), pa.array(dist, mask=~good), v], names=["sample_id", "cluster_id", "dist", "v"])

    return run


def _sum_batches(centroids: Centroids):
    """``cluster_id, n, s``: the number and the sum of a batch's vectors in every cluster; those without a distance have no cluster."""

    def run(batches):
        import pyarrow as pa

        table = np.array(centroids, float)
        for batch in batches:
            _, rows, near, _ = _distances(batch.column("v"), table)
            used = np.unique(near)
            sums = [rows[near == c].sum(axis=0).tolist() for c in used]
            yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(np.bincount(near, minlength=len(table))[used].astype(np.int64)), pa.array(sums, pa.list_(pa.float64()))], names=["cluster_id", "n", "s"])

    return run


def _batch_means(vectors: DataFrame, centroids: Centroids) -> dict[int, list[float]]:
    """``_means`` of what ``assign`` makes, added up in batches; one row per cluster comes to the driver."""
    parts = vectors.select("v").mapInArrow(_sum_batches(centroids), "cluster_id int, n long, s array<double>")
    rows = parts.groupBy("cluster_id").agg(F.sum("n").alias("n"), F.array(*(F.sum(F.get("s", F.lit(i))) for i in range(len(centroids[0])))).alias("m")).collect()
    return {r.cluster_id: [x / r.n for x in r.m] for r in rows}


def _means(assigned: DataFrame, update: str, dim: int) -> dict[int, list[float]]:
    """The mean vector of every cluster that has a member; one row per cluster comes to the driver."""
    if update == "summarizer":
        from pyspark.ml.functions import array_to_vector
        from pyspark.ml.stat import Summarizer

        rows = assigned.groupBy("cluster_id").agg(Summarizer.mean(array_to_vector("v")).alias("m")).collect()
        return {r.cluster_id: r.m.toArray().tolist() for r in rows}
    rows = assigned.groupBy("cluster_id").agg(F.array(*(F.avg(F.get("v", F.lit(i))) for i in range(dim))).alias("m")).collect()
    return {r.cluster_id: list(r.m) for r in rows}


def fit(vectors: DataFrame, k: int = 10, iters: int = 10, init: str = "first", tol: float = 0.0, metric: str = "euclidean", fit_pct: int = 100, update: str = "average") -> Centroids:
    """Centroids after at most ``iters`` rounds, fewer once none moves by more than ``tol``; an empty cluster keeps its centroid.

    ``update``: an ``average`` per dimension, or the library's vector ``summarizer``, for vectors of many dimensions.
    """
    if fit_pct < 100:
        vectors = vectors.filter(F.pmod(F.xxhash64("sample_id"), F.lit(100)) < fit_pct)
    if metric == "cosine":
        vectors = vectors.withColumn("v", F.when(norm(F.col("v")) > 0, F.transform("v", lambda x: x / norm(F.col("v")))).otherwise(F.col("v")))
    vectors = vectors.persist()
    try:
        centroids = initial(vectors, k, init)
        # Vectors of another size than the centroids' have a mean in each dimension that they have.
        whole = not centroids or vectors.filter((F.size("v") != len(centroids[0])) | F.exists("v", lambda x: x.isNull()) | F.col("v").isNull()).isEmpty()
        for _ in range(iters):
            if update == "average" and centroids and whole and _regular(vectors, centroids):
                means = _batch_means(vectors, centroids)
            else:
                means = _means(assign(vectors, centroids), update, max(map(len, centroids), default=0))
            after = [[x if m is None else m for x, m in zip(c, means.get(i, c), strict=False)] for i, c in enumerate(centroids)]
            if metric == "cosine":
                after = [[x / size for x in c] if (size := sum(x * x for x in c) ** 0.5) else c for c in after]
            shift = max((abs(a - b) for c, d in zip(centroids, after, strict=True) for a, b in zip(c, d, strict=True)), default=0.0)
            centroids = after
            if shift <= tol:
                break
    finally:
        vectors.unpersist()
    return centroids


def library_fit(vectors: DataFrame, k: int = 10, iters: int = 10, seed: int = 42) -> Centroids:
    """The K-Means of Spark's library, with its parallel seeding."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    model = KMeans(k=k, maxIter=iters, seed=seed, featuresCol="f").fit(vectors.select(array_to_vector("v").alias("f")))
    return [c.tolist() for c in model.clusterCenters()]


def report(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("dist") * F.col("dist")).alias("sse"), F.avg("dist").alias("mean_dist"))
