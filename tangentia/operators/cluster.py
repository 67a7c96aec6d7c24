"""Tangent manifold clustering and the clusterers it is compared with."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tangentia.functions.similarity import score_arrays, tangent_similarity
from tangentia.operators.graph import batch_labels, seed_order
from tangentia.operators.neighbors import collect_points, knn, symmetrize
from tangentia.operators.tangent import CELLS, choose_scale, multiscale_svd, scale_ladder, squared_distances, tangent_planes
from tangentia.session import broadcast_if_small, materialise, ship_package, table_frame

CORE = 15  # points from which a cluster takes part in merging by continuity
REACH = 64  # points of other clusters that a point looks at for it
PAIRS = "a int, b int, dist double, id_i long, id_j long, score double"


def scored_edges(edges: DataFrame, planes: DataFrame, mode: str = "l1", n_tangent: int = 2) -> DataFrame:
    """Neighbour arcs with the likeness of the planes at their ends: nk scores, not n squared."""
    a = planes.select(F.col("id").alias("src"), F.col("basis").alias("ba"))
    b = planes.select(F.col("id").alias("dst"), F.col("basis").alias("bb"))
    return edges.join(a, "src").join(b, "dst").withColumn("score", tangent_similarity("ba", "bb", mode, n_tangent)).drop("ba", "bb")


def edge_filter(edges: DataFrame, eps: float) -> DataFrame:
    """Arcs whose ends lie on one surface: a score of eps or more."""
    return edges.where(F.col("score") >= eps)


def gap_threshold(edges: DataFrame, low: float = 0.5, bins: int = 50) -> float:
    """A threshold without labels: the emptiest place of the scores' histogram above ``low`` (its lowest, if several)."""
    counts = dict(edges.where(F.col("score") >= low).groupBy(F.least(F.floor((F.col("score") - low) / (1 - low) * bins), F.lit(bins - 1)).alias("b")).count().collect())
    smooth = [sum(counts.get(b + s, 0) for s in (-1, 0, 1)) for b in range(bins)]
    return low + (1 - low) * int(np.argmin(smooth)) / bins


def dense_labels(labels: DataFrame) -> DataFrame:
    """(id, cluster): labels renumbered from 0 in their order."""
    names = labels.select("label").distinct().withColumn("cluster", (F.row_number().over(Window.orderBy("label")) - 1).cast("int"))
    return labels.join(broadcast_if_small(names), "label").select("id", "cluster")


def scaled_planes(points: DataFrame, edges: DataFrame, n_tangent: int = 2, svd_neighbors: int | None = None, svd_radius: float | None = None, least: int = 8) -> tuple[DataFrame, int]:
    """(planes, dimension): tangent planes at the scale that multiscale singular values tell, or at the one that is given.

    Radii from the median reach of the neighbour table upwards are judged; planes have ``n_tangent`` directions, or
    as many as the dimension found if that is more.
    """
    dim = n_tangent
    if svd_neighbors is None and svd_radius is None:
        spectrum = materialise(multiscale_svd(points, scale_ladder(edges)), "spectrum")
        svd_radius, dim = choose_scale(spectrum, least)
    planes = tangent_planes(points, svd_neighbors, svd_radius, max(n_tangent, dim), least)
    return materialise(planes, "planes"), dim


def tangent_cluster(
    points: DataFrame, eps: float | None = 0.9, n_neighbors: int = 8, n_tangent: int = 2, mode: str = "l1", graph: str = "directed",
    seed: int = 0, order: str = "hash", svd_neighbors: int | None = None, svd_radius: float | None = None, edges: DataFrame | None = None, planes: DataFrame | None = None,
) -> DataFrame:
    """(id, cluster): points reached from a seed over arcs between like planes; the number of clusters is found, not given.

    Planes are those of the scale chosen by multiscale singular values, unless a ball is given. graph: directed as the
    neighbours are, with seeds in hash order (as a random order, but repeatable) or id order; or union or mutual, for which
    the order does not matter. eps None takes the histogram's gap. A point with no arc, or without a proper vector, is its
    own cluster. ``edges`` and ``planes`` that are there already are used as they are.
    """
    edges = materialise(knn(points, n_neighbors), "knn") if edges is None else edges
    if planes is None:
        planes, _ = scaled_planes(points, edges, n_tangent, svd_neighbors, svd_radius, n_neighbors)
    scored = scored_edges(edges, planes.withColumn("basis", F.slice("basis", 1, n_tangent)), mode, n_tangent)
    if eps is None:
        scored = materialise(scored, "scored")
    arcs = edge_filter(scored, gap_threshold(scored) if eps is None else eps)
    ranks = seed_order(points, order, seed)
    return dense_labels(batch_labels(arcs if graph == "directed" else symmetrize(arcs, graph), ranks, graph == "directed"))


def tangent_manifolds(
    points: DataFrame, eps: float | None = 0.9, n_neighbors: int = 8, n_tangent: int = 2, mode: str = "l1", graph: str = "directed", seed: int = 0,
    svd_neighbors: int | None = None, svd_radius: float | None = None, min_size: int = 50, max_clusters: int | None = None, affinity: str = "continuity", edges: DataFrame | None = None,
) -> DataFrame:
    """(id, cluster): tangent clusters at the chosen scale, merged: what the engine learns from.

    affinity continuity merges clusters that go on into each other, by the threshold ``eps`` itself, before what is still below
    ``min_size`` or above ``max_clusters`` joins by votes; votes, gap and tangent do the latter alone.
    """
    edges = materialise(knn(points, n_neighbors), "knn") if edges is None else edges
    planes, dim = scaled_planes(points, edges, n_tangent, svd_neighbors, svd_radius, n_neighbors)
    labels = materialise(tangent_cluster(points, eps, n_neighbors, n_tangent, mode, graph, seed, edges=edges, planes=planes), "labels")
    if affinity == "continuity":
        labels = materialise(merge_by_continuity(points, labels, planes, dim, 0.9 if eps is None else eps), "merged")
        return merge_clusters(labels, edges, None, min_size, max_clusters, "votes")
    return merge_clusters(labels, edges, planes if affinity == "tangent" else None, min_size, max_clusters, affinity)


def _batch_arrays(points: DataFrame, labels: DataFrame, planes: DataFrame, dim: int):
    """(ids, x, cluster, basis) of a bounded batch; bases that are too short are filled with zeros."""
    ids, x = collect_points(points)
    cluster = np.full(len(ids), -1, np.int64)
    at = labels.toArrow()
    own = np.searchsorted(ids, np.asarray(at["id"], np.int64)).clip(0, max(len(ids) - 1, 0))
    here = ids[own] == np.asarray(at["id"], np.int64) if len(ids) else np.zeros(0, bool)
    cluster[own[here]] = np.asarray(at["cluster"], np.int64)[here]
    basis = np.zeros((len(ids), dim, x.shape[1]))
    for i, rows in planes.select("id", F.slice("basis", 1, dim)).toLocalIterator():
        k = int(np.searchsorted(ids, i))
        basis[k, : len(rows)] = rows
    return ids, x, cluster, basis


def in_plane(basis: np.ndarray, step: np.ndarray) -> np.ndarray:
    """Share of each step's length that lies along its plane; 1 for a step of no length."""
    length = np.sqrt((step**2).sum(1))
    along = np.sqrt((np.einsum("nkd,nd->nk", basis, step) ** 2).sum(1))
    return np.where(length > 0, along / np.where(length > 0, length, 1), 1.0)


def continuity_pairs(points: DataFrame, labels: DataFrame, planes: DataFrame, dim: int, core: int = CORE, near: int = 16) -> DataFrame:
    """(a, b, dist, id_i, id_j, score): the ``near`` nearest pairs of each two clusters of ``core`` points or more.

    score: how well one plane goes on into the other, the least of their likeness (whatever the choice of directions within
    them) and of the shares of the step between the points that lie along each. Each task keeps ``near`` pairs of
    each two clusters; a point looks at its REACH nearest points of other clusters. The batch is bounded and broadcast.
    """
    spark = points.sparkSession
    ship_package(spark)
    ids, x, cluster, basis = _batch_arrays(points, labels, planes, dim)
    names, counts = np.unique(cluster[cluster >= 0], return_counts=True)
    keep = np.isin(cluster, names[counts >= core])
    shared = spark.sparkContext.broadcast((ids[keep], x[keep], cluster[keep], basis[keep]))

    def search(frames):
        ids, x, cluster, basis = shared.value
        step, kept = max(1, CELLS // max(len(x), 1)), None
        for f in frames:
            own = np.searchsorted(ids, f["id"].to_numpy()).clip(0, max(len(ids) - 1, 0)) if len(ids) else np.zeros(0, int)
            own = own[ids[own] == f["id"].to_numpy()] if len(ids) else own
            for at in range(0, len(own), step):
                i = own[at : at + step]
                d = squared_distances(x[i], x)
                d[cluster[i][:, None] == cluster] = np.inf
                wide = min(REACH, len(x))
                j = np.argpartition(d, wide - 1, axis=1)[:, :wide]
                part = pd.DataFrame({"i": np.repeat(i, wide), "j": j.ravel(), "d": np.take_along_axis(d, j, 1).ravel()})
                part = part[np.isfinite(part["d"])]
                part["a"], part["b"] = np.minimum(cluster[part["i"]], cluster[part["j"]]), np.maximum(cluster[part["i"]], cluster[part["j"]])
                swap = cluster[part["i"]] > cluster[part["j"]]
                part.loc[swap, ["i", "j"]] = part.loc[swap, ["j", "i"]].to_numpy()
                kept = part if kept is None else pd.concat([kept, part])
                kept = kept.drop_duplicates(["i", "j"]).sort_values(["d", "i", "j"]).groupby(["a", "b"], sort=False).head(near)
        if kept is not None and len(kept):
            i, j = kept["i"].to_numpy(), kept["j"].to_numpy()
            move = x[j] - x[i]
            score = np.minimum(score_arrays(basis[i], basis[j], "projection").clip(0, 1), np.minimum(in_plane(basis[i], move), in_plane(basis[j], move)))
            yield pd.DataFrame({"a": kept["a"].to_numpy(), "b": kept["b"].to_numpy(), "dist": np.sqrt(kept["d"].to_numpy()), "id_i": ids[i], "id_j": ids[j], "score": score})

    found = points.select("id").where("id IS NOT NULL").mapInPandas(search, PAIRS).distinct()
    nearest_first = Window.partitionBy("a", "b").orderBy("dist", "id_i", "id_j")
    return found.withColumn("rk", F.row_number().over(nearest_first)).where(F.col("rk") <= near).drop("rk")


def continuity_groups(pairs: list[tuple[int, int, float, float]], near: int, eps: float) -> dict[int, int]:
    """Cluster to group: of (a, b, dist, score), the two clusters with the best mean score over their ``near`` nearest pairs merge, as long as it reaches ``eps``."""
    lists: dict[int, dict[int, list]] = {}
    for a, b, dist, score in pairs:
        lists.setdefault(a, {}).setdefault(b, []).append((dist, score))
        lists.setdefault(b, {}).setdefault(a, []).append((dist, score))
    into = {c: c for c in lists}
    mean = lambda v: sum(s for _, s in v) / len(v)
    heap = [(-mean(v), a, b) for a, row in lists.items() for b, v in row.items() if a < b]
    heapq.heapify(heap)
    while heap and -heap[0][0] >= eps:
        value, a, b = heapq.heappop(heap)
        if a not in lists or b not in lists or b not in lists[a] or -mean(lists[a][b]) != value:
            continue  # merged or changed since
        for c, v in lists.pop(b).items():
            lists[c].pop(b, None)
            if c != a:
                both = sorted(lists[a].get(c, []) + v)[:near]
                lists[a][c] = lists[c][a] = both
                heapq.heappush(heap, (-mean(both), min(a, c), max(a, c)))
        lists[a].pop(b, None)
        into = {k: a if g == b else g for k, g in into.items()}
    return into


def merge_by_continuity(points: DataFrame, labels: DataFrame, planes: DataFrame, dim: int, eps: float = 0.9, core: int = CORE, near: int = 16) -> DataFrame:
    """(id, cluster): clusters of at least ``core`` points merge as long as one goes on into another with a score of ``eps`` or more.

    The points of smaller clusters go where they lie nearest to the planes of the merged clusters' nearest points. The
    threshold is the clusterer's own: the same condition, between clusters. Without any cluster of ``core`` points, labels stay.
    """
    spark = points.sparkSession
    pairs = [(r["a"], r["b"], r["dist"], r["score"]) for r in continuity_pairs(points, labels, planes, dim, core, near).orderBy("a", "b", "dist", "id_i", "id_j").collect()]
    into = continuity_groups(pairs, near, eps)
    ids, x, cluster, basis = _batch_arrays(points, labels, planes, dim)
    names, counts = np.unique(cluster[cluster >= 0], return_counts=True)
    cores = names[counts >= core]
    if not len(cores):
        return labels
    group = {int(c): into.get(int(c), int(c)) for c in cores}
    keep = np.isin(cluster, cores)
    placed = np.array([group[int(c)] for c in cluster[keep]])
    shared = spark.sparkContext.broadcast((ids[keep], x[keep], placed, basis[keep]))

    def place(frames):
        ids, x, placed, basis = shared.value
        step = max(1, CELLS // max(len(x), 1))
        for f in frames:
            own = f["id"].to_numpy()
            at = np.searchsorted(ids, own).clip(0, len(ids) - 1)
            out = np.where(ids[at] == own, placed[at], -1)
            loose = np.array([k for k in np.flatnonzero(out < 0) if f["x"].iloc[k] is not None and len(f["x"].iloc[k]) == x.shape[1]], int)
            for low in range(0, len(loose), step):
                rows = loose[low : low + step]
                q = np.stack(f["x"].iloc[rows].to_numpy())
                best, d = np.full(len(rows), np.inf), squared_distances(q, x)
                for g in np.unique(placed):
                    mine = np.flatnonzero(placed == g)
                    k = min(8, len(mine))
                    near_by = mine[np.argpartition(d[:, mine], k - 1, axis=1)[:, :k]]
                    move = q[:, None] - x[near_by]
                    off = (move**2).sum(2) - (np.einsum("nmkd,nmd->nmk", basis[near_by], move) ** 2).sum(2)
                    far = np.sqrt(np.maximum(off, 0)).mean(1) + 0.1 * np.sqrt(d[:, mine].min(1))
                    closer = far < best
                    best[closer], out[rows[closer]] = far[closer], g
            yield pd.DataFrame({"id": own, "label": out.astype(np.int64)})

    found = points.select("id", "x").where("id IS NOT NULL").mapInPandas(place, "id long, label long").dropDuplicates(["id"])
    # a row without a proper vector keeps its own cluster
    odd = labels.select("id", (F.col("cluster") + F.lit(1 << 40)).alias("odd"))
    return dense_labels(found.join(odd, "id").select("id", F.when(F.col("label") < 0, F.col("odd")).otherwise(F.col("label")).alias("label")))


def n_clusters(labels: DataFrame) -> int:
    return labels.select(F.count_distinct("cluster")).first()[0]


def cluster_links(labels: DataFrame, edges: DataFrame, planes: DataFrame | None = None) -> DataFrame:
    """(a, b, votes, gap, score) for each pair of clusters with arcs between them: how many, how short, and how like in tangent."""
    e = edges if planes is None else scored_edges(edges, planes)
    e = e.join(labels.select(F.col("id").alias("src"), F.col("cluster").alias("a")), "src").join(labels.select(F.col("id").alias("dst"), F.col("cluster").alias("b")), "dst").where("a <> b")
    score = F.avg("score") if planes is not None else F.lit(None).cast("double")
    return e.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.count(F.lit(1)).alias("votes"), F.min("dist").alias("gap"), score.alias("score"))


def merge_clusters(labels: DataFrame, edges: DataFrame, planes: DataFrame | None = None, min_size: int = 50, max_clusters: int | None = None, affinity: str = "votes") -> DataFrame:
    """(id, cluster): the smallest cluster joins its nearest one as long as it is below ``min_size`` or there are more than ``max_clusters``.

    Nearest: most arcs between (votes), the shortest (gap), or the likest tangents (tangent). Only a row for each pair of
    clusters reaches the driver. A cluster with no arc to others stays.
    """
    spark = labels.sparkSession
    sizes = {r["cluster"]: r["count"] for r in labels.groupBy("cluster").count().collect()}
    links: dict[int, dict[int, list]] = {c: {} for c in sizes}
    for a, b, votes, gap, score in cluster_links(labels, edges, planes if affinity == "tangent" else None).collect():
        links[a][b] = links[b][a] = [votes, gap, score or 0.0]
    rank = {"votes": lambda v, to: (v[0], -v[1]), "gap": lambda v, to: (-v[1], v[0]), "tangent": lambda v, to: (v[2], v[0])}[affinity]
    into = {c: c for c in sizes}
    stuck: set[int] = set()
    while True:
        small = sorted((n, c) for c, n in sizes.items() if c not in stuck)
        if not small or not (small[0][0] < min_size or (max_clusters and len(sizes) > max_clusters)):
            break
        c = small[0][1]
        if not links[c]:
            stuck.add(c)
            continue
        to = max(links[c], key=lambda t: (*rank(links[c][t], t), -t))
        for other, v in links.pop(c).items():
            links[other].pop(c, None)
            if other != to:
                w = links[to].get(other)
                links[to][other] = links[other][to] = v if w is None else [v[0] + w[0], min(v[1], w[1]), (v[2] * v[0] + w[2] * w[0]) / (v[0] + w[0])]
        sizes[to] += sizes.pop(c)
        into = {k: to if v == c else v for k, v in into.items()}
    names = {c: k for k, c in enumerate(sorted(sizes))}
    table = spark.createDataFrame([(int(k), names[v]) for k, v in into.items()], "cluster int, merged int")
    return labels.join(broadcast_if_small(table), "cluster").select("id", F.col("merged").alias("cluster"))


def knn_components(points: DataFrame, k: int) -> DataFrame:
    """(id, cluster) by connectivity alone, without planes: what intersecting surfaces defeat."""
    return tangent_free(points, knn(points, k))


def tangent_free(points: DataFrame, edges: DataFrame) -> DataFrame:
    return dense_labels(batch_labels(edges, seed_order(points, "id"), directed=False))


def kmeans_cluster(points: DataFrame, p: int, seed: int = 0) -> DataFrame:
    """(id, cluster) by k-means on the raw vectors."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = points.select("id", array_to_vector("x").alias("features"))
    return KMeans(k=p, seed=seed).fit(v).transform(v).select("id", F.col("prediction").cast("int").alias("cluster"))
