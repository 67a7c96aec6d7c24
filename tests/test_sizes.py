"""What larger tables and odd inputs of the second round showed."""

import math

import numpy as np
from pyspark.sql import functions as F

from tangentia import session
from tangentia.functions import numeric as X
from tangentia.functions.vectors import vec_round
from tangentia.operators import metrics as M
from tangentia.operators import neighbors as N
from tangentia.operators import spectral as S
from tangentia.operators import stitch as K
from tangentia.operators import tangent as P
from tangentia.operators.mapper import chosen_by
from tangentia.plans import catalogue
from tangentia.plans import engine as E
from tangentia.sources import workloads as W


def test_rounding_keeps_the_sign_of_zero_as_sql_does(spark, sf_dir):
    d = spark.createDataFrame([([-1e-9, 1e-9, -0.0, 0.0, -1.5e-6, None, float("nan")],)], "x array<double>")
    r = d.select(vec_round("x").alias("x")).first()
    assert [math.copysign(1, v) for v in r["x"][:4]] == [-1, 1, -1, 1]
    assert r["x"][4] == -2e-6 and r["x"][5] is None and math.isnan(r["x"][6])
    scalars = spark.createDataFrame([(-1e-9,), (1e-9,)], "v double").select(*catalogue.r6("v")).collect()
    assert [math.copysign(1, x["v"]) for x in scalars] == [-1, 1]


def brute(ids, x, k):
    out = []
    for i, q in zip(ids, x):
        d = np.sqrt(((x - q) ** 2).sum(1))
        d[ids == i] = np.inf
        out += [(int(i), int(ids[j]), r) for r, j in enumerate(np.lexsort((ids, np.round(d, 12)))[:k], 1)]
    return sorted(out)


def test_nearest_holds_few_distances_and_takes_the_first_of_many_copies():
    r = np.random.default_rng(0)
    x = r.standard_normal((900, 5))
    x = np.concatenate([x, x[:300], np.repeat(x[:1], 40, 0)])
    ids = r.permutation(len(x))
    held, X.CELLS, X.COLUMNS = (X.CELLS, X.COLUMNS), 2_000, 100
    try:
        places, _ = X.nearest(x, x, ids, 6, ids)
    finally:
        X.CELLS, X.COLUMNS = held
    assert sorted((int(i), int(ids[p]), r) for i, row in zip(ids, places) for r, p in enumerate(row, 1)) == brute(ids, x, 6)


def test_blocks_give_each_point_few_visits_and_exact_neighbours(spark):
    r = np.random.default_rng(1)
    x = r.random((1_500, 2)).round(2)
    x[:60] = x[0]
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    got = sorted((e.src, e.dst, e.rk) for e in N.knn_blocked(points, 5, 9).collect())
    assert got == brute(np.arange(1_500), x, 5)
    p, lower, upper = N.dealt(points, 9)
    sizes = [v["count"] for v in p.groupBy("block").count().collect()]
    assert sum(sizes) == 1_500 and len(sizes) == len(lower) == 9
    near = sorted((e.src, e.dst) for e in N.radius_neighbors(points, 0.03).collect())
    d = np.sqrt(((x[:, None] - x) ** 2).sum(2))
    assert near == [(int(i), int(j)) for i, j in zip(*np.nonzero(d <= 0.03)) if i != j]


def test_many_points_are_not_paired_one_by_one(spark, monkeypatch):
    points = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(60)], "id long, x array<double>")
    pairs = lambda e: sorted((r.src, r.dst, r.rk) for r in e.collect())
    small = pairs(N.knn_exact(points, 3))
    monkeypatch.setattr(N, "EXPRESSION_ROWS", 50)
    e = N.knn_exact(points, 3)
    assert "NestedLoop" not in e._jdf.queryExecution().toString() and pairs(e) == small


def test_support_pairs_of_several_pieces_equal_brute_force(spark, monkeypatch):
    r = np.random.default_rng(2)
    x, c = r.random((300, 3)).round(1), r.integers(0, 3, 300)
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    labels = spark.createDataFrame([(i, int(v)) for i, v in enumerate(c)], "id long, cluster int")
    for module in (N, K):
        monkeypatch.setattr(module, "BLOCK_ROWS", 64)
    monkeypatch.setattr(N, "WIDE_ROWS", 100)
    monkeypatch.setattr(N, "BROADCAST_ROWS", 200)
    got = {}
    for p in K.support_set(points, labels, 5, 3).collect():
        got.setdefault((p.ci, p.cj, p.kind), set()).add((p.id_i, p.id_j))
    for a in range(3):
        for b in range(a + 1, 3):
            pairs = [(round(float(np.sqrt(((x[i] - x[j]) ** 2).sum())), 9), int(i), int(j)) for i in np.flatnonzero(c == a) for j in np.flatnonzero(c == b)]
            assert got[a, b, "near"] == {(i, j) for _, i, j in sorted(pairs)[:5]}
            assert got[a, b, "far"] == {(i, j) for _, i, j in sorted((-d, i, j) for d, i, j in pairs)[:3]}
    far = [(p.src, p.dst) for p in N.farthest_pairs(points, 7).collect()]
    every = sorted((-round(float(np.sqrt(((x[i] - x[j]) ** 2).sum())), 6), i, j) for i in range(300) for j in range(i + 1, 300))
    assert far == [(i, j) for _, i, j in every[:7]]


def test_all_pairs_are_made_without_joins(spark, sf_dir):
    for name in ("double_center", "farthest_pairs", "map_relational", "support_near", "support_far"):
        plan = catalogue.queries()[name](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
        assert "Join" not in plan, name


def test_more_points_than_one_task_solves_are_embedded_alike(spark, sf_dir, monkeypatch):
    d = W.scene(spark, sf_dir, "roll", 300)
    a = S.spectral_embed(d, 8, 2)
    monkeypatch.setattr(S, "LOCAL_ROWS", 200)
    b = S.spectral_embed(d, 8, 2)
    assert M.procrustes_error(a, b) < 1e-8


def test_values_from_moments_equal_those_of_the_points():
    r = np.random.default_rng(3)
    x = r.standard_normal((400, 10)) * np.linspace(1, 0.05, 10)
    d = X.squared_distances(x[:20], x)
    for radius, rows, s, counts in P.ball_spectra(x[:20], d, x, [0.8, 1.5, 2.5]):
        for i, values, n in zip(rows, s, counts):
            ball = x[d[i] <= radius * radius]
            assert n == len(ball) and np.allclose(values, P.planes_of(ball[None], 1)[1][0], atol=1e-9)


def test_a_bucket_of_many_copies_makes_no_pairs_of_all(spark):
    points = spark.range(3_000).selectExpr("id", "array(0.5D, 0.5D) AS x")
    e = N.knn_lsh(points, 4, 1.0, 0.5, tables=2)
    assert "SortMergeJoin" not in e._jdf.queryExecution().toString()
    rows = e.where("src IN (0, 2, 2999)").collect()
    assert sorted((r.src, r.dst, r.rk) for r in rows) == [(0, d, d) for d in (1, 2, 3, 4)] + [(2, 0, 1), (2, 1, 2), (2, 3, 3), (2, 4, 4)] + [(2999, d, d + 1) for d in range(4)]


def test_paths_of_a_group_equal_those_of_single_sources():
    r = np.random.default_rng(4)
    n = 150
    src, dst = r.integers(0, n - 5, 700), r.integers(0, n - 5, 700)  # the last points have no arcs
    w = r.random(700)
    want = np.full((n, n), np.inf)
    np.minimum.at(want, (src, dst), w)
    np.fill_diagonal(want, 0)
    for k in range(n):
        want = np.minimum(want, want[:, k : k + 1] + want[k])
    order = X.graph_order(n, np.r_[src, dst], np.r_[dst, src], np.r_[w, w])
    assert sorted(order) == list(range(n))
    got = X.shortest_paths(n, src, dst, w, order)
    assert np.allclose(got, want[order], atol=1e-12) and (np.isinf(got) == np.isinf(want[order])).all()


def test_block_steps_equal_the_dense_problem(monkeypatch):
    r = np.random.default_rng(5)
    x = r.standard_normal((300, 6)) * (5, 3, 2, 1, 0.5, 0.1)
    gram = X.centred_gram(np.sqrt(X.squared_distances(x, x)) ** 0.9)
    value, vector = X.top_eigen(gram, 3)
    monkeypatch.setattr(X, "DENSE_ROWS", 40)
    again, other = X.top_eigen(gram, 3)
    assert np.allclose(value, again, rtol=1e-12) and np.allclose(vector, other, atol=1e-6)


def test_a_model_that_leaves_its_paths_in_a_table_maps_alike(spark, sf_dir, monkeypatch):
    d = W.scene(spark, sf_dir, "patches", 500)
    batch, stream = d.where("id % 2 = 0"), d.where("id % 2 = 1").select("id", "x", "y_true").unionByName(spark.createDataFrame([(10_000, None, 7), (10_001, [1.0], 7)], "id long, x array<double>, y_true int"))
    held = E.fit(batch, E.EmbedParams(), batch.select("id", F.col("y_true").alias("cluster")))
    monkeypatch.setattr(E, "HELD_CELLS", 0)
    monkeypatch.setattr("tangentia.operators.mapper.PIECE_ROWS", 100)
    left = E.fit(batch, E.EmbedParams(), batch.select("id", F.col("y_true").alias("cluster")))
    assert all(f.g is None for f in left.manifolds) and held.paths is None
    a, b = ({r["id"]: r for r in E.transform(stream, m, "anchor", keep=("y_true",)).collect()} for m in (held, left))
    assert a.keys() == b.keys() and len(a) == 252
    for i, r in a.items():
        s = b[i]
        assert (r["manifold"], r["y_true"]) == (s["manifold"], s["y_true"])
        if r["manifold"] is not None:
            assert np.allclose(r["y_global"], s["y_global"], atol=1e-9) and np.allclose(r["y_local"], s["y_local"], atol=1e-9) and abs(r["score"] - s["score"]) < 1e-12
    assert b[10_000]["manifold"] is None and b[10_001]["y_local"] is None


def test_clusters_too_large_for_a_task_are_embedded_alike(spark, sf_dir, monkeypatch):
    d = W.scene(spark, sf_dir, "patches", 500)
    labels = d.select("id", F.least("y_true", F.lit(2)).alias("cluster"))
    a = E.embed_clusters(d, labels, 8, 2)
    monkeypatch.setattr(E, "DENSE_ROWS", 150)  # one of three clusters is larger
    b = E.embed_clusters(d, labels, 8, 2)
    monkeypatch.setattr(E, "DENSE_ROWS", 100)
    monkeypatch.setattr(E, "CHUNK_CELLS", 20_000)  # two go at a time, the third alone
    c = E.embed_clusters(d, labels, 8, 2)
    one = {r["id"]: r["y"] for r in a.collect()}
    for other in (b, c):
        rows = {r["id"]: r["y"] for r in other.collect()}
        assert rows.keys() == one.keys() and max(abs(u - v) for i, y in rows.items() for u, v in zip(y, one[i])) < 1e-6


def test_rules_in_one_pass_choose_as_each_by_itself(spark, sf_dir):
    d = W.scene(spark, sf_dir, "spheres", 600)
    batch, stream = d.where("id < 300"), d.where("id >= 300").select("id", "x").unionByName(spark.createDataFrame([(9_999, None)], "id long, x array<double>"))
    model = E.fit(batch, E.EmbedParams(), batch.select("id", F.col("y_true").alias("cluster")))
    got = {r["id"]: (r["global"], r["local"], r["anchor"]) for r in chosen_by(stream, model).collect()}
    ways = [E.transform(stream, model, select, space) for select, space in (("center", "global"), ("center", "local"), ("anchor", "global"))]
    each = [{r["id"]: r["manifold"] for r in w.collect()} for w in ways]
    assert len(got) == len(each[0]) and all(got[i] == tuple(e[i] for e in each) for i in got) and got[9_999] == (None, None, None)


def test_a_stream_in_one_small_file_is_dealt_to_tasks(spark, sf_dir, monkeypatch):
    from tangentia.plans import experiments as Q

    batch, stream = Q.batch_and_stream(spark, sf_dir, "roll_plane")
    n = batch.count() + stream.count()
    monkeypatch.setattr(Q, "TASK_ROWS", 100)
    again, dealt = Q.batch_and_stream(spark, sf_dir, "roll_plane")
    assert dealt.rdd.getNumPartitions() == -(-n // 100)
    assert sorted(r[0] for r in again.select("id").union(dealt.select("id")).collect()) == sorted(r[0] for r in batch.select("id").union(stream.select("id")).collect())


def test_blocks_in_many_dimensions_go_to_the_points_and_no_visit_is_shuffled(spark, monkeypatch):
    r = np.random.default_rng(6)
    x = (r.random((1_200, 7)) ** 3).round(2)
    x[:90] = x[0]
    x[90] = 1e6
    ids = r.permutation(5_000)[:1_200]
    points = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x)] + [(9_000, None), (9_001, [1.0])], "id long, x array<double>")
    e = N.knn_blocked(points, 6, 5)
    assert "FlatMapCoGroups" not in e._jdf.queryExecution().toString()
    got = sorted((v.src, v.dst, v.rk) for v in e.collect())
    assert got == brute(ids, x, 6)
    monkeypatch.setattr(N, "HELD_CELLS", 1_000)
    assert sorted((v.src, v.dst, v.rk) for v in N.knn_blocked(points, 6, 5).collect()) == got


def test_a_large_undirected_graph_is_contracted(spark, monkeypatch):
    from tangentia.operators import graph as G

    n = 300  # a long path, a triangle, and points without arcs
    arcs = spark.createDataFrame([(i, i + 1) for i in range(n - 1)] + [(400, 401), (401, 402), (402, 400)], "src long, dst long")
    points = spark.createDataFrame([(i,) for i in [*range(n), 400, 401, 402, 500]], "id long")
    ranks = G.seed_order(points)
    one = {r["id"]: r["label"] for r in G.batch_labels(arcs, ranks, directed=False).collect()}
    monkeypatch.setattr(G, "BATCH_ARCS", 10)
    monkeypatch.setattr(G, "directed_min_label", None)  # a step for each arc of the longest path
    assert {r["id"]: r["label"] for r in G.batch_labels(arcs, ranks, directed=False).collect()} == one and len(set(one.values())) == 3


def test_pairs_made_one_by_one_are_dealt_to_tasks(spark, monkeypatch):
    points = spark.createDataFrame([(i, [float(i % 7), float(i)]) for i in range(60)], "id long, x array<double>").coalesce(1)
    monkeypatch.setattr(N, "EXPRESSION_PAIRS", 400)
    plan = N.knn_exact(points, 3)._jdf.queryExecution().toString()
    assert "NestedLoop" in plan and "hashpartitioning(id" in plan and ", 9), REPARTITION_BY_NUM" in plan
    x = np.array([[float(i % 7), float(i)] for i in range(60)])
    assert sorted((r.src, r.dst, r.rk) for r in N.knn_exact(points, 3).collect()) == brute(np.arange(60), x, 3)


def test_parts_of_a_block_give_its_nearest_rows_and_few_of_them_are_visited(monkeypatch):
    r = np.random.default_rng(7)
    x = r.random((3_000, 3)).round(2)
    x[:200], x[200] = x[0], 50.0
    ids = r.permutation(9_000)[:3_000]
    visited = []
    searched = N.searched
    monkeypatch.setattr(N, "searched", lambda held, lower, upper, q, own, block, k, reach=None: (visited.append(len(held.first)), searched(held, lower, upper, q, own, block, k, reach))[1])
    row, dst, dist = N.nearest_by_parts(x, ids, x, ids, 6)
    places, dists = X.nearest(x, x, ids, 6, ids)
    assert min(visited) > 8 and (row == np.repeat(np.arange(3_000), 6)).all() and (dst == ids[places].ravel()).all() and np.allclose(dist, dists.ravel(), atol=1e-12)
    reach = np.full(3_000, 0.02)
    row, dst, dist = N.nearest_by_parts(x, ids, x, ids, 6, reach)
    near = dists <= 0.02 * (1 + 1e-9) + 1e-12
    assert (dst == ids[places][near]).all() and (np.bincount(row, minlength=3_000) == near.sum(1)).all()
    far = np.array([[0.0, 0.0], [1e160, 0.0], [0.0, 3.0], [1.0, 0.0]])  # squares overflow
    row, dst, _ = N.nearest_by_parts(far, np.arange(4), far, np.arange(4), 1)
    assert dst[row != 1].tolist() == [3, 0, 0]
    same = np.ones((5, 2))
    assert N.nearest_by_parts(same, np.arange(5), same, np.arange(5), 2)[1].tolist() == [1, 2, 0, 2, 0, 1, 0, 1, 0, 1]


def test_few_bytes_that_make_many_pairs_do_not_share_a_task(spark, monkeypatch):
    points = spark.createDataFrame([(i, [i % 40 / 40, i // 40 / 40]) for i in range(1_600)], "id long, x array<double>")
    monkeypatch.setattr(N, "BLOCK_ROWS", 200)
    e = N.radius_neighbors(points, 0.026)
    assert e.rdd.getNumPartitions() >= 2
    assert e.count() == 4 * 40 * 39


def test_a_written_table_frees_the_driver_where_its_heap_is_large(spark, monkeypatch):
    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    full = lambda: sum(b.getCollectionCount() for b in beans if "Old" in b.getName())
    trimmed = []
    trim = session.trim_native
    monkeypatch.setattr(session, "trim_native", lambda s: trimmed.append(trim(s)))
    for share, collections in ((2.0, 0), (0.0, 1)):
        monkeypatch.setattr(session, "HEAP_SHARE", share)
        before = full()
        assert session.materialise(spark.range(3), "freed").count() == 3
        assert full() - before == collections
    assert trimmed == [True, True]


def test_an_embedding_of_more_points_than_are_collected_is_the_same(spark, monkeypatch):
    r = np.random.default_rng(3)
    x = np.column_stack([r.random((1_100, 2)), np.zeros(1_100)])
    x[700:] += [3.0, 0.5, 0.0]
    x[1_000:] += [0.0, 4.0, 0.0]
    d = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())] + [(5_000, [1.0]), (5_001, None)], "id long, x array<double>")
    own = np.array([r["y"] for r in S.spectral_embed(d, 8, 2).orderBy("id").collect()])
    monkeypatch.setattr(N, "BROADCAST_ROWS", 400)
    monkeypatch.setattr(N, "WIDE_ROWS", 300)
    monkeypatch.setattr(N.collect_points, "__defaults__", (400,))
    monkeypatch.setattr(S, "HELD_LENGTHS", 1_000_000, raising=False)
    many = np.array([r["y"] for r in S.spectral_embed(d, 8, 2).orderBy("id").collect()])
    assert own.shape == many.shape == (1_100, 2) and np.abs(own - many).max() < 1e-6 * np.abs(own).max()


def test_more_points_than_a_task_holds_have_the_same_spectra(spark, sf_dir, monkeypatch):
    r = np.random.default_rng(21)
    cases = [(W.noisy_sphere(spark, sf_dir).select("id", "x"), [0.6, 1.0, 1.4]), (spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(r.random((400, 2)).round(2))], "id long, x array<double>"), [0.01, 0.3, 0.05])]
    table = lambda d, s: {(x["id"], x["r"], x["i"]): (x["n"], x["sigma"]) for x in P.multiscale_svd(d, s).collect()}
    whole = [table(d, s) for d, s in cases]
    monkeypatch.setattr(N.collect_points, "__defaults__", (300,))
    for name, value in {"BROADCAST_ROWS": 300, "WALK_ROWS": 64, "WALK_COLUMNS": 50, "PIECE_CELLS": 10_000, "MOMENT_CELLS": 200_000}.items():
        monkeypatch.setattr(P, name, value, raising=False)
    for (d, s), a in zip(cases, whole):
        b = table(d, s)
        assert a.keys() == b.keys() and all(a[k][0] == b[k][0] and abs(a[k][1] - b[k][1]) < 1e-7 for k in a)


def test_rounding_without_decimals_is_that_with_decimals(spark):
    r = np.random.default_rng(22)
    ties = np.concatenate([(r.integers(-(10**9), 10**9, 3_000) + 0.5) / 1e6 + e for e in (0.0, 1e-16, -1e-16, 1e-9)])
    values = np.concatenate([ties, r.standard_normal(20_000), r.standard_normal(2_000) * 1e7, r.standard_normal(2_000) * 1e-6, [1e300, -1e300, np.inf, -np.inf, np.nan, 99_999.9999995]])
    d = spark.createDataFrame([(float(v),) for v in values], "v double")
    for a, b in d.select(catalogue.r6("v")[0], F.round("v", 6).alias("b")).collect():
        assert a == b or (math.isnan(a) and math.isnan(b))


def test_paths_of_samples_through_a_large_batch_are_not_shuffled(spark, sf_dir, monkeypatch):
    from tangentia.operators import mapper

    rows = lambda: {(x["id"], x["anchor"]): x["g"] for x in catalogue.queries()["map_relational"](spark, sf_dir).collect()}
    d = W.raw_digits(spark, sf_dir).toPandas()
    x, y = np.stack(d["x"].to_numpy()), d["y_true"].to_numpy()
    a, b, i, j = x[y >= 5], x[y < 5], d["id"].to_numpy()[y >= 5], d["id"].to_numpy()[y < 5]
    across, within = np.sqrt(X.squared_distances(a, b)), np.sqrt(X.squared_distances(b, b))
    near = np.argsort(np.round(across, 12), axis=1, kind="stable")[:, :4]
    g = np.min([np.take_along_axis(across, near[:, [k]], 1) + within[near[:, k]] for k in range(4)], 0)
    expected = {(int(i[p]), int(j[q])): g[p, q] for p in range(len(i)) for q in range(len(j))}
    monkeypatch.setattr(N.collect_points, "__defaults__", (150,))
    for module, name, value in ((N, "BROADCAST_ROWS", 150), (N, "WIDE_ROWS", 100), (N, "CHUNK_CELLS", 2_000), (mapper, "NEAR_ROWS", 400)):
        monkeypatch.setattr(module, name, value, raising=False)
    got = rows()
    assert got.keys() == expected.keys() and all(abs(got[k] - expected[k]) < 1e-6 for k in got)
    assert "Exchange" not in catalogue.queries()["map_relational"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()


def test_distances_by_products_lose_no_digits_where_points_are_near():
    r = np.random.default_rng(23)
    x = np.concatenate([r.standard_normal((60, 7)), 1e4 + r.standard_normal((60, 7)) * 1e-4, np.full((2, 7), 1e4)])
    assert np.allclose(X.distances(x[::3], x), np.sqrt(X.squared_distances(x[::3], x)), rtol=1e-12, atol=0)
    assert np.array_equal(X.distances(x * 1e160, x[:3] * 1e160), np.sqrt(X.squared_distances(x * 1e160, x[:3] * 1e160)))
    assert X.distances(np.zeros((0, 7)), x).shape == (0, len(x)) and X.distances(x, np.zeros((0, 7))).shape == (len(x), 0)


def test_rounds_that_work_out_all_lengths_anew_are_few(spark, sf_dir, monkeypatch):
    d = W.scene(spark, sf_dir, "roll", 1_000).unionByName(W.scene(spark, sf_dir, "spheres", 400).selectExpr("id + 5000 id", "transform(x, v -> v + 5) x", "y_true", "u", "ts"))
    count, steps = [], X.krylov

    def counted(*a, **b):
        inner = steps(*a, **b)
        block = next(inner)
        while True:
            count.append(block.shape[1])
            try:
                block = inner.send((yield block))
            except StopIteration as e:
                return e.value

    monkeypatch.setattr(S, "krylov", counted)
    own = np.array([r["y"] for r in S.spectral_embed(d, 8, 2).orderBy("id").collect()])
    kept = len(count)
    monkeypatch.setattr(S, "HELD_LENGTHS", 1_000_000)
    many = np.array([r["y"] for r in S.spectral_embed(d, 8, 2).orderBy("id").collect()])
    assert own.shape == many.shape == (1_400, 2) and np.abs(own - many).max() < 1e-6 * np.abs(own).max()
    assert len(count) - kept < kept


def test_path_lengths_are_those_of_a_dense_table_with_parallel_arcs_and_none():
    r = np.random.default_rng(24)
    src, dst, dist = r.integers(0, 200, 900), r.integers(0, 200, 900), r.random(900).round(2)
    g = np.full((210, 210), np.inf)
    np.minimum.at(g, (src, dst), dist)
    np.fill_diagonal(g, 0.0)
    for k in range(210):
        g = np.minimum(g, g[:, k : k + 1] + g[k])
    for arcs in (8_192, 7):
        held, X.ARCS = X.ARCS, arcs
        try:
            assert np.allclose(X.shortest_paths(210, src, dst, dist, np.arange(210)), g)
        finally:
            X.ARCS = held
    assert np.isinf(X.shortest_paths(3, src[:0], dst[:0], dist[:0], np.arange(3))).sum() == 6
