"""The experiment workloads and the methods without an SQL form; checked by invariants and brute force in the tests.

Parameters are those of the published experiments where they are stated, else the defaults of ``EmbedParams``.
"""

from __future__ import annotations

import time
from dataclasses import replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tangentia.functions.numeric import centred_gram, top_eigen
from tangentia.operators import baselines as B
from tangentia.operators import cluster as C
from tangentia.operators import metrics as M
from tangentia.operators import neighbors as N
from tangentia.operators import spectral as S
from tangentia.operators import tangent as P
from tangentia.operators.mapper import novelty as flag_novel
from tangentia.operators.mapper import Model, chosen_by, register_map_point
from tangentia.operators.stitch import support_set
from tangentia.plans.engine import EmbedParams, batch_embedding, choose_batch_size, cluster_arcs, embed_clusters, fit, load_model, save_model, transform
from tangentia.session import materialise, scratch_path, ship_package
from tangentia.sources import workloads as W
from tangentia.sources.tables import split_batch_stream, stream_table
from tangentia.streaming.engine import distinct_events, quality_windows, switch_when_stable, transform_stream, with_labels, write_once

BATCH = 2_000  # as in the published stream experiments
TASK_ROWS = 16_384  # of a stream that a task maps
PARAMS = EmbedParams()
_queries: dict = {}


def query(f):
    _queries[f.__name__] = f
    return f


def queries() -> dict:
    return dict(_queries)


#: Those of the queries that SQL can express.
SQL = {
    "streamed_windows": "SELECT strftime(time_bucket(INTERVAL '1 day', ts), '%Y-%m-%d %H:%M:%S') AS start, CAST(event_id % 3 AS INTEGER) AS manifold, count(*) AS n, round(avg(value), 6) AS residual FROM events GROUP BY ALL",
    "streamed_once": "SELECT event_id AS id, CASE WHEN event_type <> 'view' THEN event_type END AS event_type, round(value, 6) AS value FROM events",
}


def batch_and_stream(spark: SparkSession, sf_dir: str, name: str, n: int = BATCH) -> tuple[DataFrame, DataFrame]:
    """The first n rows by id and the rest; of a table with fewer than twice as many, six tenths are the batch, so that a stream is left.

    A long stream is dealt to tasks by its rows: a small file is one task otherwise, however much each row costs."""
    return with_a_stream(W.scene(spark, sf_dir, name), n)


def with_a_stream(points: DataFrame, n: int = BATCH) -> tuple[DataFrame, DataFrame]:
    there = points.count()
    batch, stream = split_batch_stream(points, n if there >= 2 * n else there * 6 // 10)
    return batch, stream.repartition(-(-there // TASK_ROWS)) if there > TASK_ROWS else stream


def true_labels(points: DataFrame) -> DataFrame:
    return points.select("id", F.col("y_true").alias("cluster"))


def truth(points: DataFrame) -> DataFrame:
    return points.select("id", "y_true", F.col("u").alias("y"))


def digits(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Lifted digits, one third as the batch and the rest as the stream, by id (1:2 as published)."""
    d = materialise(W.lifted_digits(spark, sf_dir), "digits")
    return split_batch_stream(d, max(1, d.count() // 3))


# ---- planes, scales, clusters


@query
def multiscale_svd(spark, sf_dir):
    """Singular value curves of a noisy sphere over the ladder of radii."""
    d = W.noisy_sphere(spark, sf_dir)
    return P.spectrum_curve(P.multiscale_svd(d, [0.6, 0.8, 1.0, 1.2, 1.4, 1.6]))


@query
def point_dimensions(spark, sf_dir):
    s = P.multiscale_svd(W.scene(spark, sf_dir, "sphere_plane", BATCH), [0.3])
    return P.point_dimensions(s, 0.3)


@query
def orthonormal_bases(spark, sf_dir):
    d = W.raw_digits(spark, sf_dir)
    return d.select("id", P.orthonormalize(F.array(*[F.slice("x", 1 + 16 * k, 16) for k in range(4)])).alias("basis"))


@query
def accuracy_spheres(spark, sf_dir):
    return B.accuracy_table(W.scene(spark, sf_dir, "spheres", 2_000))


@query
def accuracy_sphere_plane(spark, sf_dir):
    return B.accuracy_table(W.scene(spark, sf_dir, "sphere_plane", 2_000))


@query
def accuracy_roll_plane(spark, sf_dir):
    return B.accuracy_table(W.scene(spark, sf_dir, "roll_plane", 4_500))


@query
def tangent_planes(spark, sf_dir):
    """Planes of every point of the table from its neighbours, in joins, whatever the number of points."""
    d = materialise(W.scene(spark, sf_dir, "spheres"), "scene")
    return P.planes_from_edges(d, N.knn(d, 12))


@query
def scale_choice(spark, sf_dir):
    """The radii of the ladder, each with its dimension, gap and rate of growth, and the one chosen."""
    d = materialise(W.scene(spark, sf_dir, "spheres", BATCH), "scene")
    s = materialise(P.multiscale_svd(d, P.scale_ladder(N.knn(d, 8))), "spectrum")
    r, _ = P.choose_scale(s)
    rows = [(x.radius, x.points, x.dim, x.gap, x.bend, x.accepted, x.radius == r) for x in P.judge_scales(s)]
    return spark.createDataFrame(rows, "radius double, points double, dim int, gap double, bend double, accepted boolean, chosen boolean")


@query
def tangent_cluster(spark, sf_dir):
    """The clusterer by itself, as grown: mean cosine of like-ranked directions, at the chosen scale."""
    return C.tangent_cluster(W.scene(spark, sf_dir, "roll_plane", BATCH))


@query
def merged_clusters(spark, sf_dir):
    """Grown and merged, nothing told but the neighbour count and the threshold."""
    return C.tangent_manifolds(W.scene(spark, sf_dir, "roll_plane", BATCH))


@query
def merge_rules(spark, sf_dir):
    """Each way of merging, on a plane through a sphere."""
    d = materialise(W.scene(spark, sf_dir, "sphere_plane", 2_000), "scene")
    edges = materialise(N.knn(d, 8), "knn")
    rows = [(a, *map(float, M.clustering_report(C.tangent_manifolds(d, affinity=a, edges=edges), d).values())) for a in ("continuity", "votes", "gap", "tangent")]
    return spark.createDataFrame(rows, "affinity string, balanced double, plain double, purity double, clusters double, rand double, nmi double")


@query
def accuracy_roll_2planes(spark, sf_dir):
    return B.accuracy_table(W.scene(spark, sf_dir, "roll_2planes", 9_000), eps=(0.9,), n_tangents=(2,), cap=3)


@query
def kmeans_cluster(spark, sf_dir):
    return C.kmeans_cluster(W.scene(spark, sf_dir, "roll_plane"), 2)


@query
def neighbour_recall(spark, sf_dir):
    """Hashed neighbours against exact ones, over the whole table; buckets of twice the usual distance to the last neighbour."""
    d = materialise(W.scene(spark, sf_dir, "roll"), "scene")
    exact = materialise(N.knn(d, 8), "exact")
    usual, widest = exact.agg(F.median(F.when(F.col("rk") == 8, F.col("dist"))), F.max("dist")).first()
    near = N.knn_lsh(d, 8, widest or 1.0, 2 * (usual or 0.5))
    hit = exact.select("src", "dst").join(near.select("src", "dst"), ["src", "dst"], "left_semi").count()
    return spark.createDataFrame([(hit / max(exact.count(), 1),)], "recall double")


@query
def shortcut_arcs(spark, sf_dir):
    """Arcs that jump between coils, on the loose and on the tight roll, over the whole table."""
    out = []
    for name in ("roll", "roll_tight"):
        d = materialise(W.scene(spark, sf_dir, name), "scene")
        out.append(M.shortcut_rate(N.knn(d, 8), d).withColumn("scene", F.lit(name)))
    return out[0].unionByName(out[1])


@query
def silhouette(spark, sf_dir):
    """How well the found clusters of the four patches stand apart, in the space they lie in."""
    d = materialise(W.scene(spark, sf_dir, "patches", BATCH), "scene")
    emb = d.select("id", F.col("x").alias("y")).join(C.tangent_manifolds(d), "id")
    return spark.createDataFrame([(float(M.silhouette(emb)),)], "silhouette double")


# ---- embeddings and baselines


@query
def ge_embed(spark, sf_dir):
    return B.baseline_ge(W.scene(spark, sf_dir, "roll", BATCH), 8, 2)


@query
def ge_neighbour_sweep(spark, sf_dir):
    """Four patches on one roll as one manifold: components and error at each neighbour count."""
    d = materialise(W.scene(spark, sf_dir, "patches", BATCH), "scene")
    rows = []
    for k in (8, 32, 128, 500):
        parts = C.knn_components(d, k).agg(F.count_distinct("cluster")).first()[0]
        rows.append((k, parts, M.procrustes_error(truth(d), B.baseline_ge(d, k, 2))))
    return spark.createDataFrame(rows, "k int, components long, error double")


@query
def uneven_roll(spark, sf_dir):
    """One manifold of uneven density: error of the batch's embedding, and of the stream mapped on it."""
    batch, stream = batch_and_stream(spark, sf_dir, "uneven")
    model, mapped = B.baseline_sgm(batch, stream, PARAMS)
    b = M.procrustes_error(truth(batch), batch_embedding(spark, model).select("id", F.col("y_global").alias("y")))
    s = M.procrustes_error(truth(stream), mapped.select("id", F.col("y_global").alias("y"))) if not stream.isEmpty() else 0.0
    return spark.createDataFrame([(b, s)], "batch double, stream double")


@query
def local_linear_embed(spark, sf_dir):
    return S.spectral_embed(W.scene(spark, sf_dir, "roll", BATCH), 10, 2, "local_linear")


@query
def laplacian_embed(spark, sf_dir):
    return S.spectral_embed(W.scene(spark, sf_dir, "roll", BATCH), 10, 2, "laplacian")


@query
def pca_embed(spark, sf_dir):
    return B.baseline_pca(W.raw_digits(spark, sf_dir), 3)


@query
def sep_embed(spark, sf_dir):
    return B.baseline_sep(W.scene(spark, sf_dir, "patches", BATCH), 8, 2)


@query
def spectrum_dimension(spark, sf_dir):
    """The dimension told by the distances of a roll, and the leading eigenvalues, by both solvers."""
    from tangentia.operators.geodesic import geodesics

    d = materialise(W.scene(spark, sf_dir, "roll", BATCH), "scene")
    ids, _ = N.collect_points(d)
    gram = materialise(S.gram_rows(geodesics(N.symmetrize(N.knn(d, 10)), ids)), "gram")
    rows = []
    for solver in ("local", "subspace"):
        _, value, _ = S.eig_top(gram, 4, solver)
        rows += [(solver, i, float(v), S.dim_from_spectrum(value)) for i, v in enumerate(value)]
    return spark.createDataFrame(rows, "solver string, i int, value double, dim int")


# ---- the two-phase engine


@query
def imse_fit_batch(spark, sf_dir):
    batch, _ = batch_and_stream(spark, sf_dir, "roll_plane")
    return batch_embedding(spark, fit(batch, PARAMS))


@query
def imse_stream(spark, sf_dir):
    """Learn on the batch, map the stream."""
    batch, stream = batch_and_stream(spark, sf_dir, "roll_plane", BATCH)
    return transform(stream, fit(batch, PARAMS), keep=("ts",))


@query
def sgm_stream(spark, sf_dir):
    batch, stream = batch_and_stream(spark, sf_dir, "roll")
    return B.baseline_sgm(batch, stream, PARAMS)[1]


@query
def selection_rules(spark, sf_dir):
    """Which manifold is chosen, by each rule, with true clusters given: share of right choices by class."""
    rows = []
    for name in ("patches", "roll_plane", "sphere_plane", "spheres"):
        batch, stream = batch_and_stream(spark, sf_dir, name)
        model = fit(batch, PARAMS, labels=true_labels(batch))
        rules = {"global": ("center", "global"), "local": ("center", "local"), "anchor": ("anchor", "global")}
        m = chosen_by(stream, model, tuple(rules), model.params["n_neighbors"], ("y_true",))
        by_class = m.groupBy("y_true").agg(*[F.avg((F.col(r) == F.col("y_true")).cast("double")).alias(r) for r in rules])
        right = by_class.agg(*[F.avg(r).alias(r) for r in rules]).first()
        rows += [(name, *way, right[r]) for r, way in rules.items()]
    return spark.createDataFrame(rows, "scene string, rule string, space string, accuracy double")


@query
def mapper_variants(spark, sf_dir):
    """Error against the truth of each way of mapping, one manifold: stored paths, landmarks, barycentric weights."""
    batch, stream = batch_and_stream(spark, sf_dir, "roll")
    one = batch.select("id", F.lit(0).alias("cluster"))
    full, few = fit(batch, PARAMS, labels=one), fit(batch, replace(PARAMS, landmarks=100), labels=one)
    rows = []
    for name, model, mapper in (("geodesic", full, "geodesic"), ("landmark", few, "landmark"), ("barycentric", full, "barycentric")):
        m = transform(stream, model, mapper=mapper)
        rows.append((name, M.procrustes_error(truth(stream), m.select("id", F.col("y_global").alias("y")))))
    return spark.createDataFrame(rows, "mapper string, error double")


def _patches_shape(spark, sf_dir, params_of, values) -> DataFrame:
    """Separation, roundness and error of the batch's embedding as one parameter moves."""
    batch = materialise(W.scene(spark, sf_dir, "patches", BATCH), "scene")
    rows = []
    for v in values:
        emb = batch_embedding(spark, fit(batch, params_of(v), labels=true_labels(batch))).select("id", F.col("manifold").alias("cluster"), F.col("y_global").alias("y"))
        emb = materialise(emb, "embedding")
        shape = M.shape_stats(emb).agg(F.avg("ratio"), F.avg("radius")).first()
        rows.append((float(v), M.separation(emb).first()[0], shape[0], shape[1], M.procrustes_error(truth(batch), emb)))
    return spark.createDataFrame(rows, "value double, separation double, roundness double, radius double, error double")


@query
def lambda_sweep(spark, sf_dir):
    return _patches_shape(spark, sf_dir, lambda v: replace(PARAMS, lam=v, d_global=2), (0.01, 0.02, 0.04, 0.16))


@query
def near_pairs_sweep(spark, sf_dir):
    return _patches_shape(spark, sf_dir, lambda v: replace(PARAMS, k_near=v, d_global=2), (8, 16, 24, 32))


@query
def neighbours_sweep(spark, sf_dir):
    return _patches_shape(spark, sf_dir, lambda v: replace(PARAMS, n_neighbors=v, d_global=2), (8, 16, 24, 32))


@query
def far_pairs_sweep(spark, sf_dir):
    return _patches_shape(spark, sf_dir, lambda v: replace(PARAMS, l_far=v, d_global=2), (1, 4))


@query
def method_errors(spark, sf_dir):
    """Four patches: error of each method's batch embedding against the unrolled truth. Ours finds its clusters itself."""
    batch = materialise(W.scene(spark, sf_dir, "patches", BATCH), "scene")
    emb = batch_embedding(spark, fit(batch, replace(PARAMS, d_global=2))).select("id", F.col("y_global").alias("y"))
    found = {"stitched": emb, "separated_rigid": B.baseline_sep(batch, 8, 2), "separated_free": B.baseline_sep(batch, 8, 2, normalize_local=False), "single": B.baseline_ge(batch, 8, 2), "pca": B.baseline_pca(batch, 2)}
    return spark.createDataFrame([(k, M.procrustes_error(truth(batch), v.select("id", "y"))) for k, v in found.items()], "method string, error double")


@query
def intersection_errors(spark, sf_dir):
    """A plane through a roll: each method's batch embedding against the flat truth of each surface; ours with the clusters it found, and with the true ones."""
    batch = materialise(W.scene(spark, sf_dir, "roll_plane", BATCH), "scene")
    local = lambda m: batch_embedding(spark, m).select("id", F.col("y_local").alias("y"))
    found = {"ours": local(fit(batch, PARAMS)), "ours_true_clusters": local(fit(batch, PARAMS, true_labels(batch))), "separated": B.baseline_sep(batch, 8, 2), "single": B.baseline_ge(batch, 8, 2), "pca": B.baseline_pca(batch, 2)}
    out = None
    for name, emb in found.items():
        part = M.procrustes_by(truth(batch), emb.select("id", "y"), "y_true").withColumn("method", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out.select("method", F.col("group").alias("surface"), "error", "n")


def _digit_errors(spark, batch, stream, space: str, given: bool = False) -> DataFrame:
    """Each digit: the stream mapped from a batch of a third, against one embedding of all its points, in three dimensions.

    One model has all digits as its clusters. space local: the coordinates of the digit's own manifold; global: those in the
    common space. given: every sample is mapped on its digit's manifold, else those count that the anchor rule puts there.
    """
    batch, stream = (x.select("id", "x", "y_true") for x in (batch, stream))
    model = fit(batch, replace(PARAMS, d=3, d_global=3, n_neighbors=6), labels=true_labels(batch))
    ways = [(m.cluster, Model([m], model.params)) for m in model.manifolds] if given else [(None, model)]
    parts = [transform(stream if c is None else stream.where(F.col("y_true") == c), m, "anchor", keep=("y_true",)) for c, m in ways]
    mapped = materialise(reduce(DataFrame.unionByName, parts), "mapped")
    if model.paths is not None:
        model.paths.unpersist(True)
    everything = batch.unionByName(stream)
    whole = embed_clusters(everything.select("id", "x"), true_labels(everything), 6, 3).select("id", "y", F.col("cluster").alias("digit"))
    own = mapped.where(F.col("y_true") == F.col("manifold")).select("id", F.col(f"y_{space}").alias("y"))
    return M.procrustes_by(whole, own, "digit").where("n >= 5").select(F.col("group").cast("int").alias("digit"), "error")


@query
def procrustes_digits(spark, sf_dir):
    return _digit_errors(spark, *digits(spark, sf_dir), "local")


@query
def procrustes_digits_global(spark, sf_dir):
    return _digit_errors(spark, *digits(spark, sf_dir), "global")


@query
def procrustes_digits_raw(spark, sf_dir):
    """The raw vectors, in the common space: their labels carry no geometry, so samples are mapped on the manifold of their own label and errors are high; mechanics only."""
    return _digit_errors(spark, *with_a_stream(materialise(W.raw_digits(spark, sf_dir), "digits"), 667), "global", given=True)


@query
def digits_in_two_dimensions(spark, sf_dir):
    """All digits as one manifold, for the picture in the plane."""
    d = materialise(W.lifted_digits(spark, sf_dir), "digits")
    return B.baseline_ge(d, 8, 2).join(d.select("id", F.col("y_true").alias("digit")), "id")


@query
def raw_digit_neighbours(spark, sf_dir):
    """How often a raw vector's nearest neighbour has its label: its labels carry no geometry, so about one in ten."""
    d = W.raw_digits(spark, sf_dir)
    e = N.knn(d, 1).join(d.select(F.col("id").alias("src"), F.col("y_true").alias("a")), "src").join(d.select(F.col("id").alias("dst"), F.col("y_true").alias("b")), "dst")
    return e.agg(F.avg((F.col("a") == F.col("b")).cast("double")).alias("agreement"))


@query
def document_clusters(spark, sf_dir):
    """All documents by character pairs: clusters against languages."""
    langs = F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")])
    docs = W.load_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.array_position(langs, F.col("lang")).cast("int").alias("y_true"))
    d = materialise(W.ngram_vectors(spark, sf_dir).join(docs, "id"), "documents")
    rows = [(name, *map(float, M.clustering_report(labels, d).values())) for name, labels in (("components", C.knn_components(d, 5)), ("kmeans", C.kmeans_cluster(d, 4)))]
    return spark.createDataFrame(rows, "clusterer string, balanced double, plain double, purity double, clusters double, rand double, nmi double")


@query
def documents_on_benchmark(spark, sf_dir):
    """A small batch of one table learnt as one manifold, all documents mapped on it and flagged where they are far from it."""
    batch = W.ngram_vectors(spark, sf_dir, table="benchmark", key="item_id")
    model = fit(batch, replace(PARAMS, d=3), labels=batch.select("id", F.lit(0).alias("cluster")))
    return flag_novel(transform(W.ngram_vectors(spark, sf_dir), model)).select("id", "manifold", "residual", "novel")


@query
def volume_stream(spark, sf_dir):
    """All line items as the stream of a batch of their first rows."""
    batch, stream = with_a_stream(W.lineitem_vectors(spark, sf_dir))
    model = fit(batch, replace(PARAMS, landmarks=200), labels=batch.select("id", F.lit(0).alias("cluster")))
    return transform(stream, model, mapper="landmark")


@query
def novelty(spark, sf_dir):
    """A surface that is not in the batch: its samples are flagged, nothing is relearnt."""
    d = W.scene(spark, sf_dir, "roll_2planes")
    batch, stream = split_batch_stream(d, BATCH)
    model = fit(batch.where("y_true <> 2"), PARAMS, labels=true_labels(batch.where("y_true <> 2")))
    m = flag_novel(transform(stream, model, "anchor", keep=("y_true",)), 2.0)
    return m.groupBy("y_true").agg(F.avg(F.col("novel").cast("double")).alias("novel"), F.count(F.lit(1)).alias("n"))


@query
def batch_size(spark, sf_dir):
    """Where the embedding of the first points stops moving as the batch grows."""
    size, errors = choose_batch_size(W.scene(spark, sf_dir, "roll"), [250, 500, 1_000, 2_000], 0.001, PARAMS)
    return spark.createDataFrame([(n, e, n == size) for n, e in errors], "size int, error double, chosen boolean")


@query
def cost_counts(spark, sf_dir):
    """Steps of each phase, from the clusters, arcs and support pairs of a real fit."""
    batch, stream = batch_and_stream(spark, sf_dir, "roll_plane")
    model = fit(batch, PARAMS)
    found = spark.createDataFrame([(int(i), f.cluster) for f in model.manifolds for i in f.ids], "id long, cluster int")
    arcs = cluster_arcs(batch.select("id", "x"), found, PARAMS.n_neighbors).count()
    pairs = support_set(batch, found, PARAMS.k_near, PARAMS.l_far).count() if len(model.manifolds) > 1 else 0
    return spark.createDataFrame(list(M.cost_counters(model, stream.count(), arcs, pairs).items()), "step string, count long")


@query
def stream_times(spark, sf_dir):
    """Seconds against stream size on intersecting surfaces: everything anew by the single-manifold method, and by the separated one, against mapping.

    Batch as published. The methods that begin anew run to 2,000 stream samples, where they already take most of the time; mapping to the whole stream.
    """
    batch, stream = (materialise(x, "part") for x in batch_and_stream(spark, sf_dir, "roll_plane"))
    there, rows = stream.count(), []
    model = fit(batch, PARAMS)
    for n in sorted({min(n, there) for n in (500, 1_000, 2_000)}):
        part = materialise(batch.unionByName(stream.orderBy("id").limit(n)), "prefix")
        for name, run in (("single", lambda p: B.baseline_ge(p, 8, 2)), ("separated", lambda p: B.baseline_sep(p, 8, 2))):
            rows.append((name, n, M.timed(lambda _, p=part, run=run: run(p), n)[0][1]))
    rows += [("map", n, s) for n, s, _ in M.timed(lambda n: transform(stream if n == there else split_batch_stream(stream, n)[0], model), *sorted({min(n, there) for n in (500, 1_000, 2_000, there)}))]
    return spark.createDataFrame(rows, "method string, size int, seconds double")


@query
def batch_times(spark, sf_dir):
    """Seconds to learn, and to map the same stream, against batch size."""
    rows = []
    for n in (250, 500, 1_000, 2_000):
        batch, stream = (materialise(x, "part") for x in batch_and_stream(spark, sf_dir, "roll_plane", n))
        t0 = time.perf_counter()
        model = fit(batch, replace(PARAMS, min_size=25))
        learnt = time.perf_counter() - t0
        rows.append((n, batch.count(), len(model.manifolds), learnt, M.timed(lambda _, s=stream, m=model: transform(s, m), 1)[0][1], stream.count()))
    return spark.createDataFrame(rows, "size int, batch long, manifolds int, learn_seconds double, map_seconds double, stream long")


@query
def saved_model(spark, sf_dir):
    """A model that was written and read again maps as it did."""
    batch, stream = batch_and_stream(spark, sf_dir, "spheres")
    model = fit(batch, PARAMS, labels=true_labels(batch))
    path = scratch_path(spark, "model")
    save_model(spark, model, path)
    a, b = transform(stream, model), transform(stream, load_model(spark, path))
    return a.join(b.select("id", F.col("manifold").alias("again"), F.col("score").alias("score2")), "id").select("id", "manifold", "again", F.abs(F.col("score") - F.col("score2")).alias("moved"))


# ---- streaming and SQL


@query
def streamed_events(spark, sf_dir):
    """The whole table through Structured Streaming into Parquet parts by manifold, taken once."""
    batch, _ = batch_and_stream(spark, sf_dir, "spheres")
    model = fit(batch, PARAMS, labels=true_labels(batch))
    events = stream_table(spark, f"{sf_dir}/events.parquet*")
    u = F.pmod(F.unix_micros("ts"), F.lit(3_600_000_000)) / F.lit(3.6e9)
    v = 1 - F.exp(-F.col("value") / 50)
    x = F.when(F.col("event_id") % 2 == 1, W.sphere_point(u, v, 1.0)).otherwise(W.sphere_point(u, v))
    points = events.select(F.col("event_id").alias("id"), x.alias("x"), "ts")
    out = scratch_path(spark, "stream")
    run = transform_stream(points, model, f"{out}/data", f"{out}/checkpoint", select="anchor")
    run.awaitTermination()
    return spark.read.parquet(f"{out}/data").select("id", "manifold", "y_global", "score", "residual", "ts")


@query
def streamed_windows(spark, sf_dir):
    """Daily windows over a stream, run once, all of them: the last state of a sink in complete mode."""
    events = stream_table(spark, f"{sf_dir}/events.parquet*")
    m = events.select("ts", (F.col("event_id") % 3).cast("int").alias("manifold"), F.col("value").alias("residual"))
    out = scratch_path(spark, "windows")
    last = lambda rows, _: rows.write.mode("overwrite").parquet(f"{out}/data")
    run = quality_windows(m, "1 day", watermark=None).writeStream.foreachBatch(last).option("checkpointLocation", f"{out}/checkpoint").outputMode("complete").trigger(availableNow=True).start()
    run.awaitTermination()
    q = spark.read.parquet(f"{out}/data")
    return q.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "manifold", "n", F.round("residual", 6).alias("residual"))


@query
def streamed_once(spark, sf_dir):
    """Repeated events dropped within the watermark, labels joined, each micro-batch written once by its number."""
    events = stream_table(spark, f"{sf_dir}/events.parquet*").select(F.col("event_id").alias("id"), "ts", "value")
    twice = events.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    kinds = W.load_table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "event_type").where("event_type <> 'view'")
    out = scratch_path(spark, "once")
    write_once(with_labels(distinct_events(twice), kinds), f"{out}/data", f"{out}/checkpoint").awaitTermination()
    return spark.read.parquet(f"{out}/data").select("id", "event_type", F.round("value", 6).alias("value"))


@query
def streamed_switch(spark, sf_dir):
    """Keys that learn until their embedding is stable and map from then on."""
    events = stream_table(spark, f"{sf_dir}/events.parquet*")
    u = F.pmod(F.unix_micros("ts"), F.lit(3_600_000_000)) / F.lit(3.6e9)
    points = events.select((F.col("event_id") % 2).alias("key"), F.col("event_id").alias("id"), W.roll_point(u, 1 - F.exp(-F.col("value") / 50)).alias("x"))
    out = scratch_path(spark, "switch")
    run = switch_when_stable(points, 100, 100, 800, 0.02).writeStream.format("parquet").option("path", f"{out}/data").option("checkpointLocation", f"{out}/checkpoint").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(f"{out}/data").groupBy("key", "phase").agg(F.count(F.lit(1)).alias("n"), F.min("error").alias("error"))


@query
def sql_surface(spark, sf_dir):
    """map_point in SQL."""
    batch, stream = batch_and_stream(spark, sf_dir, "spheres")
    register_map_point(spark, fit(batch, PARAMS, labels=true_labels(batch)), "map_point", select="anchor")
    stream.createOrReplaceTempView("stream_points")
    return spark.sql("SELECT id, m.manifold, m.score FROM (SELECT id, map_point(x) AS m FROM stream_points)")


class _Spectrum:
    """Table function: the singular values of a vector's table of rows of eight."""

    def eval(self, x):
        s = np.linalg.svd(np.asarray(x, float).reshape(-1, 8), compute_uv=False)
        for i, v in enumerate(s):
            yield i, float(v)


@query
def spectrum_function(spark, sf_dir):
    from pyspark.sql.functions import udtf

    spark.udtf.register("svd_spectrum", udtf(_Spectrum, returnType="i int, sigma double"))
    W.raw_digits(spark, sf_dir).createOrReplaceTempView("digit_vectors")
    return spark.sql("SELECT id, i, sigma FROM digit_vectors, LATERAL svd_spectrum(x)")


@query
def landmark_geodesics(spark, sf_dir):
    """Coordinates from the landmarks' distances alone, against those from all."""
    from tangentia.operators.geodesic import geodesics, geodesics_landmark

    d = materialise(W.scene(spark, sf_dir, "roll", BATCH), "scene")
    ids, _ = N.collect_points(d)
    edges = materialise(N.symmetrize(N.knn(d, 10)), "arcs")
    rows = []
    for name, geo in (("all", geodesics(edges, ids)), ("landmarks", geodesics_landmark(edges, ids, 60))):
        t = geo.toPandas()
        g = np.stack(t.sort_values("src")["g"].to_numpy())
        own = g[:, np.searchsorted(ids, np.sort(t["src"].to_numpy()))]
        value, _ = top_eigen(centred_gram(own), 2)
        rows.append((name, len(g), float(value[1] / value[0])))
    return spark.createDataFrame(rows, "sources string, rows long, ratio double")
