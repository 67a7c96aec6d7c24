"""The methods that the engine is compared with."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.operators.cluster import dense_labels, edge_filter, kmeans_cluster, knn_components, merge_by_continuity, merge_clusters, scaled_planes, scored_edges
from tangentia.operators.graph import batch_labels, seed_order
from tangentia.operators.mapper import Model
from tangentia.operators.metrics import clustering_report, matched_accuracy, table_of
from tangentia.operators.neighbors import knn
from tangentia.operators.spectral import spectral_embed
from tangentia.operators.stitch import apply_stitch, fit_stitch, identity_stitch, skeleton, support_set
from tangentia.plans.engine import EmbedParams, embed_clusters, fit, transform
from tangentia.session import broadcast_if_small, materialise


def baseline_ge(points: DataFrame, k: int, d: int) -> DataFrame:
    """Everything as one manifold."""
    return spectral_embed(points, k, d, "geodesic")


def baseline_ge_recompute(batch: DataFrame, stream: DataFrame, sizes: list[int], k: int, d: int) -> DataFrame:
    """(size, seconds): the whole embedding made anew for each prefix of the stream."""
    rows = []
    for n in sizes:
        t0 = time.perf_counter()
        part = batch.select("id", "x").unionByName(stream.orderBy("id").limit(n).select("id", "x"))
        baseline_ge(materialise(part, "prefix"), k, d).count()
        rows.append((n, time.perf_counter() - t0))
    return batch.sparkSession.createDataFrame(rows, "size int, seconds double")


def baseline_sep(points: DataFrame, k: int, d: int, k_near: int = 16, l_far: int = 4, lam: float = 0.01, normalize_local: bool = True) -> DataFrame:
    """(id, cluster, y): clusters by connectivity, each embedded, placed on a support skeleton; one component is simply embedded.

    normalize_local brings each cluster's coordinates to one spread first, which makes placements rigid but for that scale.
    """
    labels = materialise(knn_components(points, k), "components")
    emb = embed_clusters(points, labels, k, d)
    if labels.select("cluster").distinct().count() == 1:
        return apply_stitch(emb, identity_stitch(emb)).select("id", "cluster", F.col("z").alias("y"))
    if normalize_local:
        size = emb.groupBy("cluster").agg(F.sqrt(F.avg(F.aggregate("y", F.lit(0.0), lambda s, v: s + v * v))).alias("s"))
        emb = emb.join(broadcast_if_small(size), "cluster").select("id", "cluster", F.transform("y", lambda v: v / F.greatest(F.col("s"), F.lit(1e-12))).alias("y"))
    emb = materialise(emb, "embedding")
    support = materialise(support_set(points, labels, k_near, l_far), "support")
    maps = fit_stitch(emb, skeleton(points, labels, support, d), lam)
    return apply_stitch(emb, maps).select("id", "cluster", F.col("z").alias("y"))


def baseline_sgm(batch: DataFrame, stream: DataFrame, params: EmbedParams = EmbedParams()) -> tuple[Model, DataFrame]:
    """One manifold learnt on the batch, the stream mapped on it."""
    one = batch.select("id", F.lit(0).alias("cluster"))
    model = fit(batch, params, labels=one)
    return model, transform(stream, model)


def baseline_pca(points: DataFrame, d: int) -> DataFrame:
    """(id, y) by the linear projection of most variance (centred)."""
    from pyspark.ml.feature import PCA, StandardScaler
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = points.select("id", array_to_vector("x").alias("x"))
    v = StandardScaler(withMean=True, withStd=False, inputCol="x", outputCol="c").fit(v).transform(v)
    return PCA(k=d, inputCol="c", outputCol="y").fit(v).transform(v).select("id", vector_to_array("y").alias("y"))


def accuracy_table(points: DataFrame, modes: tuple[str, ...] = ("l1", "l2", "det", "vol", "projection"), eps: tuple[float, ...] = (0.8, 0.9, 0.95), n_tangents: tuple[int, ...] = (2, 3), n_neighbors: int = 8, min_size: int = 50, cap: int = 2) -> DataFrame:
    """(method, n_tangent, eps, balanced, plain, purity, clusters, found, found_clusters, capped) of every setting, and of the clusterers without planes.

    balanced to clusters: of the clusters as they are grown. found: balanced accuracy after merging by continuity, of as many clusters
    as are then found; capped: when those are merged on by votes until ``cap`` are left. Reported as it comes: the setting
    that is best by the true labels is not chosen here. Neighbours and planes are made once.
    """
    spark, rows = points.sparkSession, []
    points = materialise(points, "scene")
    edges = materialise(knn(points, n_neighbors), "knn")
    planes, dim = scaled_planes(points, edges, max(n_tangents), least=n_neighbors)
    accuracy = lambda labels: matched_accuracy(table_of(labels, points))
    for n_tangent in n_tangents:
        for mode in modes:
            scored = materialise(scored_edges(edges, planes.withColumn("basis", F.slice("basis", 1, n_tangent)), mode, n_tangent), "scored")
            for e in eps:
                labels = materialise(dense_labels(batch_labels(edge_filter(scored, e), seed_order(points))), "labels")
                r = clustering_report(labels, points)
                merged = merge_by_continuity(points, labels, planes, dim, e)
                merged = materialise(merge_clusters(merged, edges, None, min_size), "merged")
                t = table_of(merged, points)
                rows.append((mode, n_tangent, e, r["balanced"], r["plain"], r["purity"], int(r["clusters"]), matched_accuracy(t), len(t), accuracy(merge_clusters(merged, edges, None, 1, cap))))
    for name, labels in (("connectivity", knn_components(points, n_neighbors)), ("kmeans", kmeans_cluster(points, cap))):
        r = clustering_report(labels, points)
        rows.append((name, 0, 0.0, r["balanced"], r["plain"], r["purity"], int(r["clusters"]), r["balanced"], int(r["clusters"]), r["balanced"]))
    plain = [tuple(x.item() if hasattr(x, "item") else x for x in r) for r in rows]
    return spark.createDataFrame(plain, "method string, n_tangent int, eps double, balanced double, plain double, purity double, clusters int, found double, found_clusters int, capped double")
