"""The two-phase engine: learn on a bounded batch, map the rest."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tangentia.functions.numeric import DENSE_ROWS, centred_gram, classical_scaling, nearest, procrustes, shortest_paths, top_eigen
from tangentia.operators import cluster as C
from tangentia.operators.geodesic import MAX_ARCS, SOURCES_PER_TASK, path_chunks
from tangentia.operators.mapper import Manifold, Model, map_by_sources, map_points
from tangentia.operators.neighbors import collect_points, knn, proper
from tangentia.operators.spectral import LOCAL_ROWS, dim_from_spectrum, eig_top, gram_rows, leading_of_paths
from tangentia.operators.stitch import apply_stitch, centers, fit_stitch, identity_stitch, skeleton, support_set
from tangentia.session import materialise, ship_package, table_frame

HELD_CELLS = 16_000_000  # path lengths that a model holds, and that each worker then does
CHUNK_CELLS = 120_000_000  # path lengths of several clusters that are cached at a time


@dataclass(frozen=True)
class EmbedParams:
    """eps, mode, n_tangent: clustering, at the scale of svd_* or (None) that of multiscale singular values; affinity, min_size, max_clusters: merging;
    n_neighbors: graphs; k_near, l_far: support pairs; lam: ridge; d: dimension (None: from the spectrum)."""

    eps: float | None = 0.9
    n_neighbors: int = 8
    n_tangent: int = 2
    mode: str = "l1"
    svd_neighbors: int | None = None
    svd_radius: float | None = None
    graph: str = "directed"
    d: int | None = 2
    d_global: int = 3
    k_near: int = 16
    l_far: int = 4
    lam: float = 0.01
    ridge_intercept: bool = True
    support_metric: str = "euclidean"
    min_size: int = 50
    max_clusters: int | None = None
    affinity: str = "continuity"
    landmarks: int | None = None  # path lengths are stored from so many points of each cluster; None: from all
    seed: int = 0


def embed_clusters(points: DataFrame, labels: DataFrame, k: int, d: int | None) -> DataFrame:
    """(id, cluster, y): every cluster's own geodesic embedding: one task for each cluster of at most DENSE_ROWS points, larger ones by distributed path rows.

    A cluster's neighbour graph is made within it; parts are bridged by their nearest pairs. d None: from the spectrum. Path
    rows of at most CHUNK_CELLS lengths, or of one cluster, are held at a time.
    """
    spark = points.sparkSession
    ship_package(spark)

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("id")
        ids, x = f["id"].to_numpy(), np.stack(f["x"].to_numpy())
        g = local_geodesics(ids, x, k)
        y = classical_scaling(g, d or _dimension(g))
        return pd.DataFrame({"id": ids, "cluster": f["cluster"].to_numpy(), "y": list(y)})

    own = materialise(points.select("id", "x").join(labels.select("id", F.col("cluster").cast("int").alias("cluster")), "id"), "labelled")
    counts = {r["cluster"]: r["count"] for r in own.groupBy("cluster").count().collect()}
    large = sorted(c for c, n in counts.items() if n > DENSE_ROWS)
    parts = [own.where(~F.col("cluster").isin(large)).groupBy("cluster").applyInPandas(solve, "id long, cluster int, y array<double>")] if len(large) < len(counts) or not large else []
    if large:
        many = own.where(F.col("cluster").isin(large))
        arcs = materialise(cluster_arcs(many.select("id", "x"), many.select("id", "cluster"), k), "arcs")
    while large:
        some = [large.pop(0)]
        while large and sum(counts[c] ** 2 for c in some) + counts[large[0]] ** 2 <= CHUNK_CELLS:
            some.append(large.pop(0))
        table = own.where(F.col("cluster").isin(some)).select("id", "cluster").toPandas().sort_values("id")
        ids_of = {c: table["id"].to_numpy()[table["cluster"].to_numpy() == c] for c in some}
        chunks = path_chunks(spark, cluster_graphs(arcs, ids_of)).persist()
        frames = []
        for c, (value, vector) in leading_of_paths(chunks, {c: len(i) for c, i in ids_of.items()}, d or 10).items():
            keep = d or max(1, dim_from_spectrum(value))
            y = vector[:, :keep] * np.sqrt(value[:keep])
            frames.append(pd.DataFrame({"id": ids_of[c], "cluster": np.int32(c), "y": list(np.pad(y, ((0, 0), (0, keep - y.shape[1]))))}))
        chunks.unpersist(True)
        parts.append(table_frame(spark, pd.concat(frames), "id long, cluster int, y array<double>"))
    return reduce(DataFrame.unionByName, parts)


def cluster_graphs(arcs: DataFrame, ids_of: dict[int, np.ndarray]) -> dict[int, tuple]:
    """Cluster to (n, from, to, length), by places in its ids: as many arcs as the clusters have neighbours, counted first."""
    e = arcs.where(F.col("cluster").isin(list(ids_of))).limit(MAX_ARCS + 1).toPandas()
    if len(e) > MAX_ARCS:
        raise ValueError(f"more than {MAX_ARCS} arcs in one batch's graphs")
    by_cluster, out = dict(list(e.groupby("cluster"))), {}
    for c, ids in ids_of.items():
        mine = by_cluster.get(c, e.iloc[:0])
        out[int(c)] = (len(ids), *(np.searchsorted(ids, mine[k].to_numpy()) for k in ("src", "dst")), mine["dist"].to_numpy(float))
    return out


def _dimension(g: np.ndarray) -> int:
    return max(1, dim_from_spectrum(np.linalg.eigvalsh(centred_gram(g))[::-1][:10]))


def local_arcs(ids: np.ndarray, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union neighbour graph of one cluster by place, with its parts bridged."""
    n = len(ids)
    if n < 2:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(0)
    found = [nearest(x[at : at + 1024], x, ids, min(k, n - 1), ids[at : at + 1024]) for at in range(0, n, 1024)]
    places, dists = (np.concatenate([f[i] for f in found]) for i in (0, 1))
    a, b, w = np.repeat(np.arange(n), places.shape[1]), places.ravel(), dists.ravel()
    a, b, w = np.r_[a, b], np.r_[b, a], np.r_[w, w]
    while True:
        part = np.arange(n)
        while True:
            low = part.copy()
            np.minimum.at(low, b, part[a])
            low = low[low]
            if (low == part).all():
                break
            part = low
        names = np.unique(part)
        if len(names) == 1:
            return a, b, w
        mine, rest = np.flatnonzero(part == names[0]), np.flatnonzero(part != names[0])
        places, dists = nearest(x[mine], x[rest], ids[rest], 1)
        i = int(dists[:, 0].argmin())
        j, u = rest[places[i, 0]], mine[i]
        a, b, w = np.r_[a, u, j], np.r_[b, j, u], np.r_[w, dists[i, 0], dists[i, 0]]


def local_geodesics(ids: np.ndarray, x: np.ndarray, k: int, sources: np.ndarray | None = None) -> np.ndarray:
    """Path lengths from ``sources`` (places; all by default) within one cluster."""
    a, b, w = local_arcs(ids, x, k)
    return shortest_paths(len(ids), a, b, w, np.arange(len(ids)) if sources is None else sources)


def fit(batch: DataFrame, params: EmbedParams = EmbedParams(), labels: DataFrame | None = None) -> Model:
    """Cluster, embed each cluster, stitch. ``labels`` (id, cluster) skips the clustering (forced or true clusters).

    The batch is bounded (checked) and is the only thing that is ever held whole; neighbours, planes, path lengths and
    factorisations are worked out in tasks, all clusters at once. Of rows that repeat an id, one is learnt from; rows without
    an id, without a label where labels are given, or without a proper vector (see ``collect_points``) are left out; an empty batch
    gives a model of no manifolds, a single point one of one point. More than HELD_CELLS path lengths are not held by the model, but
    stay in its table ``paths``: see ``map_by_sources``.
    """
    spark = batch.sparkSession
    points = materialise(proper(batch).dropDuplicates(["id"]), "batch")
    if labels is None:
        edges = materialise(knn(points, params.n_neighbors), "knn")
        labels = C.tangent_manifolds(
            points, params.eps, params.n_neighbors, params.n_tangent, params.mode, params.graph, params.seed, params.svd_neighbors, params.svd_radius,
            params.min_size, params.max_clusters, params.affinity, edges,
        )
    labels = materialise(labels.where("cluster IS NOT NULL").select("id", F.col("cluster").cast("int").alias("cluster")).dropDuplicates(["id"]), "labels")
    points = materialise(points.join(labels.select("id"), "id", "left_semi"), "learnt")
    parts, paths = _learn(points, labels, params)
    if not parts:
        return Model([], asdict(params))
    emb = table_frame(spark, pd.concat([pd.DataFrame({"id": p.ids, "cluster": np.int32(p.cluster), "y": list(p.y)}) for p in parts]), "id long, cluster int, y array<double>")
    emb = materialise(emb, "embedding")
    if len(parts) == 1:
        stitch = identity_stitch(emb)
    else:
        support = materialise(support_set(points, labels, params.k_near, params.l_far), "support")
        edges = knn(points, params.n_neighbors) if params.support_metric == "geodesic" else None
        skel = skeleton(points, labels, support, params.d_global, params.support_metric, edges)
        stitch = fit_stitch(emb, skel, params.lam, params.ridge_intercept)
    stitch = materialise(stitch, "stitch")
    mu = {r["cluster"]: np.array(r["mu"]) for r in centers(apply_stitch(emb, stitch)).collect()}
    maps = {r["cluster"]: (np.array(r["R"], float), np.array(r["t"], float)) for r in stitch.collect()}
    manifolds = [Manifold(p.cluster, p.ids, p.x, p.y, p.g, p.value, p.vector, *maps[p.cluster], mu[p.cluster], p.y.mean(0), p.spread or 1.0) for p in parts]
    return Model(manifolds, asdict(params), paths)


@dataclass
class Learnt:
    """One cluster after the exact phase, in its own coordinates."""

    cluster: int
    ids: np.ndarray
    x: np.ndarray
    y: np.ndarray
    g: np.ndarray | None
    value: np.ndarray
    vector: np.ndarray
    spread: float


def cluster_arcs(points: DataFrame, labels: DataFrame, k: int) -> DataFrame:
    """(cluster, src, dst, dist): the neighbour graph within each cluster, its parts bridged; a task for each cluster."""
    ship_package(points.sparkSession)

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("id")
        ids = f["id"].to_numpy()
        a, b, w = local_arcs(ids, np.stack(f["x"].to_numpy()), k)
        return pd.DataFrame({"cluster": np.int32(f["cluster"].iloc[0]), "src": ids[a], "dst": ids[b], "dist": w})

    return points.select("id", "x").join(labels, "id").groupBy("cluster").applyInPandas(solve, "cluster int, src long, dst long, dist double")


def cluster_geodesics(points: DataFrame, labels: DataFrame, arcs: DataFrame, landmarks: int | None = None, seed: int = 0) -> DataFrame:
    """(cluster, src, g): path lengths within its cluster from each source to the cluster's points, in the order of their ids.

    Sources, all points or ``landmarks`` of each cluster, are dealt to tasks whatever their cluster; graphs, as many arcs as
    the batch has neighbours, are broadcast.
    """
    spark = points.sparkSession
    ship_package(spark)
    own = labels.join(points.select("id"), "id", "left_semi").toPandas().sort_values("id")
    ids_of = {int(c): f["id"].to_numpy() for c, f in own.groupby("cluster")}
    graphs, sources = cluster_graphs(arcs, ids_of), []
    for c, ids in ids_of.items():
        chosen = ids if landmarks is None else np.sort(np.random.default_rng(seed).permutation(ids)[:landmarks])
        sources.append(pd.DataFrame({"cluster": np.int32(c), "src": chosen, "place": np.searchsorted(ids, chosen)}))
    if not sources:
        return spark.createDataFrame([], "cluster int, src long, g array<double>")
    shared = spark.sparkContext.broadcast(graphs)
    table = pd.concat(sources)
    rows = table_frame(spark, table, "cluster int, src long, place long").repartition(max(1, -(-len(table) // SOURCES_PER_TASK)))

    def run(frames):
        for f in frames:
            for c, part in f.groupby("cluster"):
                for at in range(0, len(part), 64):
                    some = part.iloc[at : at + 64]
                    yield pd.DataFrame({"cluster": np.int32(c), "src": some["src"].to_numpy(), "g": list(shortest_paths(*shared.value[int(c)], some["place"].to_numpy()))})

    return rows.mapInPandas(run, "cluster int, src long, g array<double>")


def factors(geo: DataFrame, ids_of: dict[int, np.ndarray], d: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Cluster to (values, vectors) of the d leading pairs of its sources' own distances.

    Clusters of up to LOCAL_ROWS sources are dense problems, a task for each; larger ones go by block power steps over distributed rows.
    """

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("src")
        at = np.searchsorted(ids_of[int(f["cluster"].iloc[0])], f["src"].to_numpy())
        value, vector = top_eigen(centred_gram(np.stack(f["g"].to_numpy())[:, at]), d)
        return pd.DataFrame({"cluster": [f["cluster"].iloc[0]], "value": [value], "vector": [vector.ravel()]})

    counts = {r["cluster"]: r["count"] for r in geo.groupBy("cluster").count().collect()}
    large = [c for c, n in counts.items() if n > LOCAL_ROWS]
    small = geo.where(~F.col("cluster").isin(large)) if large else geo
    out = {}
    for r in small.groupBy("cluster").applyInPandas(solve, "cluster int, value array<double>, vector array<double>").collect():
        value = np.array(r["value"])
        out[r["cluster"]] = value, np.array(r["vector"]).reshape(-1, len(value)) if len(value) else np.zeros((counts[r["cluster"]], 0))
    for c in large:
        rows = geo.where(F.col("cluster") == c)
        sources = sorted(r[0] for r in rows.select("src").collect())
        places = np.searchsorted(ids_of[c], sources)
        whole = len(places) == len(ids_of[c])
        own = rows if whole else rows.select("src", F.transform(F.array(*[F.lit(int(k)) for k in places]), lambda k: F.get("g", k)).alias("g"))
        out[c] = eig_top(gram_rows(own.select("src", "g")), d, "subspace")[1:]
    return out


def _learn(points: DataFrame, labels: DataFrame, params: EmbedParams) -> tuple[list[Learnt], DataFrame | None]:
    """Every cluster's coordinates, path lengths and factorisation, ascending by cluster; more than HELD_CELLS path lengths stay in the table that comes second."""
    spark = points.sparkSession
    arcs = materialise(cluster_arcs(points, labels, params.n_neighbors), "arcs")
    ids, x = collect_points(points)
    if not len(ids):
        return [], None
    table = labels.join(points.select("id"), "id", "left_semi").toPandas().sort_values("id")
    cluster = table["cluster"].to_numpy()
    ids_of = {int(c): ids[cluster == c] for c in np.unique(cluster)}
    stored, paths = {}, None
    if params.landmarks is None:
        sizes = {c: len(own) for c, own in ids_of.items()}
        chunks = path_chunks(spark, cluster_graphs(arcs, ids_of)).persist()
        found = leading_of_paths(chunks, sizes, params.d or 10)
        if sum(n * n for n in sizes.values()) > HELD_CELLS:
            paths = chunks
        else:
            stored = {c: (np.arange(n), np.empty((n, n))) for c, n in sizes.items()}
            for r in chunks.collect():
                stored[r["key"]][1][np.frombuffer(r["place"], np.int64)] = np.frombuffer(r["g"]).reshape(-1, sizes[r["key"]])
            chunks.unpersist()
    else:
        geo = materialise(cluster_geodesics(points, labels, arcs, params.landmarks, params.seed), "paths")
        found = factors(geo, ids_of, params.d or 10)
        rows: dict[int, list] = {}
        for c, src, g in geo.toLocalIterator():
            rows.setdefault(c, []).append((src, np.array(g)))
        for c, own in rows.items():
            own.sort(key=lambda r: r[0])
            stored[c] = np.searchsorted(ids_of[c], [r[0] for r in own]), np.stack([r[1] for r in own])
    out = []
    for c, own in ids_of.items():
        at, g = stored.get(c, (np.arange(len(own)), None))
        value, vector = found[c]
        if params.d is None:
            keep = max(1, dim_from_spectrum(value))
            value, vector = value[:keep], vector[:, :keep]
        if not len(value):
            value, vector = np.ones(params.d or 1), np.zeros((len(at), params.d or 1))
        if len(at) == len(own):
            y = vector * np.sqrt(value)
        else:  # all points are placed by triangulation against the landmarks
            y = 0.5 * ((g[:, at] ** 2).mean(1)[:, None] - g**2).T @ (vector / np.sqrt(value))
            y = y - y.mean(0)
        xs = x[cluster == c]
        near = np.concatenate([nearest(xs[k : k + 1024], xs, own, 1, own[k : k + 1024])[1] for k in range(0, len(own), 1024)]) if len(own) > 1 else None
        out.append(Learnt(c, own, xs, y, g, value, vector, float(np.quantile(near, 0.95)) if near is not None else 1.0))
    return out, paths


def transform(stream: DataFrame, model: Model, select: str = "center", select_space: str = "global", mapper: str = "geodesic", keep: tuple[str, ...] = ()) -> DataFrame:
    """The stream phase, batch or streaming: see map_points. A row that can't be mapped comes out with nulls."""
    if model.paths is not None:
        if mapper != "geodesic" or (select != "anchor" and len(model.manifolds) > 1):
            raise ValueError("path lengths that stay in their table map by the anchor rule and along geodesics only")
        return map_by_sources(stream, model, model.params["n_neighbors"], keep)
    return map_points(stream, model, model.params["n_neighbors"], select, select_space, mapper, keep)


def batch_embedding(spark: SparkSession, model: Model) -> DataFrame:
    """(id, manifold, y_local, y_global) of the batch itself."""
    frames = [pd.DataFrame({"id": f.ids, "manifold": np.int32(f.cluster), "y_local": list(f.y), "y_global": list(f.y @ f.R.T + f.t)}) for f in model.manifolds]
    return table_frame(spark, pd.concat(frames), "id long, manifold int, y_local array<double>, y_global array<double>")


def save_model(spark: SparkSession, model: Model, path: str) -> None:
    """Parquet tables, of a model that holds its path lengths: points (with path lengths from the stored sources), factor, maps with the parameters as JSON."""
    if model.paths is not None:
        raise ValueError("this model's path lengths stay in their table")
    points, factor, maps = [], [], []
    for f in model.manifolds:
        points.append(pd.DataFrame({"cluster": np.int32(f.cluster), "id": f.ids, "x": list(f.x), "y": list(f.y), "g": list(f.g.T)}))
        factor.append(pd.DataFrame({"cluster": np.int32(f.cluster), "place": np.arange(len(f.vector)), "vector": list(f.vector)}))
        maps.append((f.cluster, f.R.tolist(), f.t.tolist(), f.mu.tolist(), f.mu_local.tolist(), f.value.tolist(), float(f.spread), json.dumps(model.params)))
    table_frame(spark, pd.concat(points), "cluster int, id long, x array<double>, y array<double>, g array<double>").write.mode("overwrite").parquet(f"{path}/points")
    table_frame(spark, pd.concat(factor), "cluster int, place long, vector array<double>").write.mode("overwrite").parquet(f"{path}/factor")
    spark.createDataFrame(maps, "cluster int, R array<array<double>>, t array<double>, mu array<double>, mu_local array<double>, value array<double>, spread double, params string").write.mode("overwrite").parquet(f"{path}/maps")


def load_model(spark: SparkSession, path: str) -> Model:
    stack = lambda s: np.stack(s.to_numpy())
    points, factor = (spark.read.parquet(f"{path}/{t}").toPandas() for t in ("points", "factor"))
    manifolds, params = [], {}
    for r in spark.read.parquet(f"{path}/maps").orderBy("cluster").collect():
        p, v = points[points["cluster"] == r["cluster"]].sort_values("id"), factor[factor["cluster"] == r["cluster"]].sort_values("place")
        params = json.loads(r["params"])
        manifolds.append(Manifold(r["cluster"], p["id"].to_numpy(), stack(p["x"]), stack(p["y"]), stack(p["g"]).T, np.array(r["value"]), stack(v["vector"]), np.array(r["R"], float), np.array(r["t"]), np.array(r["mu"]), np.array(r["mu_local"]), r["spread"]))
    return Model(manifolds, params)


def choose_batch_size(points: DataFrame, sizes: list[int], tolerance: float = 0.01, params: EmbedParams = EmbedParams()) -> tuple[int, list[tuple[int, float]]]:
    """(size, [(size, error)]): the batch grows until the embedding of the smallest batch's points stops moving (Procrustes error between successive fits).

    Clustering is done once, on the largest batch that is tried, so that errors tell of the embedding alone.
    """
    spark = points.sparkSession
    errors, last = [], None
    for n in sizes:
        batch = points.orderBy("id").limit(n)
        one = spark.createDataFrame([(int(i), 0) for i in collect_points(batch)[0][: sizes[0]]], "id long, cluster int")
        model = fit(batch, replace(params, d=params.d), labels=batch.select("id", F.lit(0).alias("cluster")))
        f = model.manifolds[0]
        y = f.y[np.isin(f.ids, [r[0] for r in one.select("id").collect()])]
        if last is not None:
            errors.append((n, procrustes(last, y)))
            if errors[-1][1] <= tolerance:
                return n, errors
        last = y
    return sizes[-1], errors
