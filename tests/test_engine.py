import numpy as np
import pytest
from pyspark.sql import functions as F

from tangentia.operators import graph as G
from tangentia.operators import metrics as M
from tangentia.operators import neighbors as N
from tangentia.operators.baselines import baseline_sep
from tangentia.plans.engine import EmbedParams, batch_embedding, fit, load_model, save_model, transform
from tangentia.plans.experiments import true_labels, truth
from tangentia.sources import workloads as W
from tangentia.sources.tables import split_bad_rows, split_batch_stream

PARAMS = EmbedParams()


@pytest.fixture(scope="module")
def roll(spark, sf_dir):
    return split_batch_stream(W.scene(spark, sf_dir, "roll"), 500)


@pytest.fixture(scope="module")
def roll_model(roll):
    return fit(roll[0], PARAMS, labels=roll[0].select("id", F.lit(0).alias("cluster")))


def test_three_forms_of_labels_agree(spark):
    for seed in range(3):
        r = np.random.default_rng(seed)
        pairs = [(int(i), int(j)) for i, j in zip(np.arange(40), r.integers(0, 40, 40)) if i != j]
        edges = spark.createDataFrame(pairs, "src long, dst long")
        points = spark.range(40).withColumnRenamed("id", "id")
        ranks = G.seed_order(points, "hash", seed)
        order = [x["id"] for x in ranks.orderBy("rank").collect()]
        arcs = {}
        for i, j in pairs:
            arcs.setdefault(i, []).append(j)
        grown = G.grow_clusters(arcs, order)
        assert dict(G.batch_labels(edges, ranks).collect()) == grown
        if seed == 0:
            assert dict(G.directed_min_label(edges, ranks).collect()) == grown


def test_neighbour_forms_agree(spark, sf_dir):
    d = W.raw_digits(spark, sf_dir)
    rows = lambda e: sorted((r["src"], r["dst"], r["rk"]) for r in e.collect())
    exact = rows(N.knn_exact(d, 5))
    assert exact == rows(N.knn(d, 5)) == rows(N.knn_blocked(d, 5, 3))
    assert all(s != t for s, t, _ in exact) and len(exact) == 5 * d.count()


def test_hashed_neighbours_are_near_all_true_and_never_wrong(spark, sf_dir):
    d = W.scene(spark, sf_dir, "roll")
    exact = {(r.src, r.dst): r.dist for r in N.knn(d, 8).collect()}
    hashed = {(r.src, r.dst): r.dist for r in N.knn_lsh(d, 8, max(exact.values()), 0.3).collect()}
    assert len(exact.keys() & hashed.keys()) >= 0.95 * len(exact)
    assert all(abs(hashed[p] - exact[p]) < 1e-6 for p in exact.keys() & hashed.keys())
    odd = spark.createDataFrame([(1, [0.0, 0.0]), (2, None), (3, [0.0, 0.0]), (3, [0.0, 0.0]), (4, [9.0, 9.0])], "id long, x array<double>")
    assert sorted((r.src, r.dst) for r in N.knn_lsh(odd, 3, 1.0, 0.5).collect()) == [(1, 3), (3, 1)]
    assert N.knn_lsh(odd.limit(0), 3, 1.0, 0.5).count() == 0


def test_fewer_points_than_neighbours(spark):
    d = spark.createDataFrame([(1, [0.0, 0.0]), (2, [0.0, 0.0]), (3, [1.0, 0.0])], "id long, x array<double>")
    assert N.knn(d, 8).count() == 6
    assert N.knn(d.limit(0), 8).count() == 0


def test_roll_is_unrolled_and_stream_follows(spark, roll, roll_model):
    batch, stream = roll
    b = batch_embedding(spark, roll_model).select("id", F.col("y_global").alias("y"))
    assert M.procrustes_error(truth(batch), b) < 0.02
    m = transform(stream, roll_model).select("id", F.col("y_global").alias("y"))
    assert M.procrustes_error(truth(stream), m) < 0.02
    assert m.count() == stream.count()


def test_batch_points_come_back(roll, roll_model):
    f = roll_model.manifolds[0]
    found = roll_model.map_batch(f.x[:50])
    exact = 0.5 * ((f.g**2).mean(1) - f.g[:50] ** 2) @ (f.vector / np.sqrt(f.value))
    assert np.allclose(np.stack(found["y_local"]), exact, atol=1e-6)


def test_mapping_does_not_depend_on_partitions(roll, roll_model):
    m = lambda d: {r["id"]: tuple(np.round(r["y_global"], 9)) for r in transform(d, roll_model).collect()}
    assert m(roll[1]) == m(roll[1].repartition(7))


def test_mapping_is_map_only(roll, roll_model):
    plan = transform(roll[1], roll_model)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInPandas" in plan


def test_separated_patches_are_found_and_chosen(spark, sf_dir):
    batch, stream = split_batch_stream(W.scene(spark, sf_dir, "patches"), 600)
    model = fit(batch, PARAMS, labels=true_labels(batch))
    m = transform(stream, model, "anchor", keep=("y_true",))
    assert m.where("manifold = y_true").count() > 0.97 * m.count()


def test_saved_model_maps_alike(spark, roll, roll_model, tmp_path):
    save_model(spark, roll_model, str(tmp_path / "m"))
    a = {r["id"]: r["score"] for r in transform(roll[1], roll_model).collect()}
    b = {r["id"]: r["score"] for r in transform(roll[1], load_model(spark, str(tmp_path / "m"))).collect()}
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


def test_one_component_is_simply_embedded(spark, sf_dir):
    d = W.scene(spark, sf_dir, "roll", 300)
    e = baseline_sep(d, 8, 2)
    assert e.select("cluster").distinct().count() == 1
    assert M.procrustes_error(truth(d), e.select("id", "y")) < 0.05


def test_bad_rows_are_set_aside(spark):
    d = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [float("nan"), 0.0])], "id long, x array<double>")
    good, bad = split_bad_rows(d, 2)
    assert [r["id"] for r in good.collect()] == [1]
    assert {r["id"]: r["reason"] for r in bad.collect()} == {2: "null", 3: "length", 4: "not finite"}


def test_stream_equals_batch(spark, sf_dir, tmp_path):
    from tangentia.plans.experiments import streamed_events

    rows = streamed_events(spark, sf_dir)
    assert rows.count() == spark.read.parquet(f"{sf_dir}/events.parquet").count()
    assert rows.select("id").distinct().count() == rows.count()


def test_intersecting_surfaces_are_found_without_labels(spark, sf_dir):
    """A plane through a roll: two manifolds, nothing told of their number, mapped and stitched into one space."""
    batch, stream = split_batch_stream(W.scene(spark, sf_dir.replace("0.001", "0.01"), "roll_plane"), 2_000)
    model = fit(batch)
    assert len(model.manifolds) == 2
    found = spark.createDataFrame([(int(i), f.cluster) for f in model.manifolds for i in f.ids], "id long, cluster int")
    assert M.clustering_accuracy(found, batch) > 0.838
    assert {f.R.shape[0] for f in model.manifolds} == {3}
    m = transform(stream.limit(500), model, "anchor", keep=("y_true",)).toPandas()
    assert set(m["manifold"]) == {f.cluster for f in model.manifolds}
    assert all(len(z) == 3 for z in m["y_global"])


def test_flagship_has_rows_on_the_smallest_tables(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).select("manifold").distinct().count() > 1


ODD = [(1, [0.0, 0.0]), (2, None), (3, [1.0, 0.0]), (4, [float("nan"), 1.0]), (5, [0.0, 1.0]), (6, [1.0, 1.0, 1.0]), (7, [1.0, 1.0]), (8, [None, 1.0])]


def test_odd_rows_have_defined_results(spark):
    d = spark.createDataFrame(ODD, "id long, x array<double>")
    pairs = lambda e: sorted((r["src"], r["dst"]) for r in e.collect())
    assert pairs(N.knn(d, 2)) == pairs(N.knn_blocked(d, 2, 2)) == [(1, 3), (1, 5), (3, 1), (3, 7), (5, 1), (5, 7), (7, 3), (7, 5)]
    model = fit(d, EmbedParams(min_size=1))
    rows = {r["id"]: r for r in transform(d, model).collect()}
    assert len(rows) == len(ODD)
    for i in (2, 4, 6, 8):
        assert rows[i]["manifold"] is None and rows[i]["y_global"] is None and rows[i]["score"] is None
    assert all(rows[i]["manifold"] == 0 for i in (1, 3, 5, 7))
    none = fit(d.limit(0))
    assert not none.manifolds and {r["manifold"] for r in transform(d, none).collect()} == {None}
    assert len(fit(d.limit(1)).manifolds[0].ids) == 1


def test_planes_equal_covariances_and_both_forms_agree(spark, sf_dir):
    from tangentia.operators.tangent import planes_from_edges, tangent_planes

    d = W.scene(spark, sf_dir, "spheres", 120)
    x = {r["id"]: np.array(r["x"]) for r in d.collect()}
    edges = N.knn(d, 9)
    near = {}
    for r in edges.collect():
        near.setdefault(r["src"], []).append(r["dst"])
    joined = {r["id"]: r for r in planes_from_edges(d, edges).collect()}
    for r in tangent_planes(d, 9).collect():
        i = r["id"]
        c = np.stack([x[j] for j in [i, *near[i]]])
        value, vector = np.linalg.eigh(np.cov(c.T, bias=True))
        assert np.allclose(np.array(r["sv"]) ** 2, value[::-1], atol=1e-9)
        own, want = np.stack(r["basis"]), vector[:, ::-1].T[:2]
        assert np.allclose(own.T @ own, want.T @ want, atol=1e-6)
        assert np.allclose(own, np.stack(joined[i]["basis"]), atol=1e-9)


def test_both_solvers_agree(spark, sf_dir):
    from tangentia.operators import spectral as S
    from tangentia.operators.geodesic import geodesics

    d = W.scene(spark, sf_dir, "roll", 150)
    ids, _ = N.collect_points(d)
    gram = S.gram_rows(geodesics(N.symmetrize(N.knn(d, 8)), ids))
    (_, v1, u1), (_, v2, u2) = S.eig_top(gram, 3, "local"), S.eig_top(gram, 3, "subspace")
    assert np.allclose(v1, v2, rtol=1e-6) and np.allclose(np.abs(u1[:, :2]), np.abs(u2[:, :2]), atol=1e-3)


def test_ridge_fit_solves_its_normal_equations(spark):
    from tangentia.operators.stitch import fit_stitch

    r = np.random.default_rng(3)
    y, z = r.standard_normal((30, 2)), r.standard_normal((30, 3))
    emb = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(y)], "id long, cluster int, y array<double>")
    skel = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(z)], "id long, cluster int, z array<double>")
    a = np.column_stack([y, np.ones(30)])
    for lam in (0.01, 5.0):
        row = fit_stitch(emb, skel, lam).first()
        want = np.linalg.solve(a.T @ a + lam * np.eye(3), a.T @ z).T
        assert np.allclose(np.column_stack([row["R"], row["t"]]), want, atol=1e-9)


def test_merging_goes_by_the_threshold():
    from tangentia.operators.cluster import continuity_groups

    pairs = [(0, 1, 0.1, 0.99), (0, 1, 0.2, 0.97), (1, 2, 0.1, 0.92), (2, 3, 0.1, 0.7), (0, 3, 0.3, 0.4)]
    assert continuity_groups(pairs, 2, 0.9) == {0: 0, 1: 0, 2: 0, 3: 3}
    assert continuity_groups(pairs, 2, 0.95) == {0: 0, 1: 0, 2: 2, 3: 3}
    assert continuity_groups(pairs, 2, 0.6) == {0: 0, 1: 0, 2: 0, 3: 3}  # 3's two nearest pairs to the rest: 0.7 and 0.4
