"""Spectral factorisation: centring, leading eigenpairs (local or distributed), and the three-step workflow."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.functions.numeric import CELLS, DENSE_ROWS, classical_scaling, distances, krylov, shortest_paths, signed, top_eigen
from tangentia.operators.geodesic import arcs_of, geodesics, path_chunks, path_groups
from tangentia.operators.neighbors import bridge_components, collect_points, knn, point_ids, proper, symmetrize
from tangentia.session import free_driver, materialise, ship_package, table_frame

LOCAL_ROWS = 4_000  # a dense problem of so many rows goes to one task
PAIR_ROWS = 512  # points whose pairs with all others a task makes
PAIR_POINTS = 500_000
PAIR_CELLS = 8_000_000  # pairs that a task makes of more points
HELD_LENGTHS = 200_000_000  # path lengths of one table that are kept from round to round; more are worked out anew in each
LANDMARKS, START = 256, 46  # columns that such rounds start from, and directions of these beyond those that are asked for


def double_center(geo: DataFrame) -> DataFrame:
    """(src, dst, b) of long distances (src, dst, dist): -1/2 of the squares less row and column means plus the grand mean."""
    s = geo.select("src", "dst", (F.col("dist") * F.col("dist")).alias("s"))
    row = s.groupBy("src").agg(F.avg("s").alias("mr"))
    column = s.groupBy("dst").agg(F.avg("s").alias("mc"))
    grand = s.agg(F.avg("s").alias("mg"))
    return s.join(row, "src").join(column, "dst").join(F.broadcast(grand)).select("src", "dst", (-0.5 * (F.col("s") - F.col("mr") - F.col("mc") + F.col("mg"))).alias("b"))


def double_center_points(points: DataFrame) -> DataFrame:
    """(src, dst, b) of all pairs of points: the centring of their distances, each task working out its own rows against the broadcast points, twice: for the sums, then for the rows."""
    spark = points.sparkSession
    ship_package(spark)
    p = materialise(proper(points), "points")
    n = p.count()
    queries = p.repartition(max(1, -(-n // PAIR_ROWS) if n <= PAIR_CELLS // PAIR_ROWS else -(-n * n // PAIR_CELLS)))
    shared = spark.sparkContext.broadcast(collect_points(p, PAIR_POINTS))

    def squares(f):
        x = shared.value[1]
        step = max(1, CELLS // 4 // max(1, len(x)))
        for at in range(0, len(f), step):
            part = f.iloc[at : at + step]
            d = distances(np.stack(part["x"].to_numpy()), x)
            yield part["id"].to_numpy(), np.square(d, out=d)

    def sums(frames):
        yield pd.concat([pd.DataFrame({"id": ids, "m": s.mean(1)}) for f in frames for ids, s in squares(f)] or [pd.DataFrame({"id": [], "m": []})])

    means = queries.mapInPandas(sums, "id long, m double").toPandas().sort_values("id")["m"].to_numpy()  # rows' and columns' alike
    mean = spark.sparkContext.broadcast((means, float(means.mean()) if len(means) else 0.0))

    def rows(batches):
        ids, (column, grand) = shared.value[0], mean.value
        every = pa.array(ids, pa.int64())
        for batch in batches:
            for own, s in squares(batch.to_pandas()):
                s = -0.5 * (s - column[np.searchsorted(ids, own)][:, None] - column + grand)
                for i, b in zip(own, s, strict=True):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), i)), every, pa.array(b)], ["src", "dst", "b"])

    return queries.mapInArrow(rows, "src long, dst long, b double")


def gram_rows(geo: DataFrame) -> DataFrame:
    """(src, g) of dense rows to (src, b): the same centring. Each task gives one vector of column sums; their mean is broadcast."""
    spark = geo.sparkSession
    ship_package(spark)
    geo = materialise(geo, "path-rows")

    def sums(frames):
        total, n = 0.0, 0
        for f in frames:
            for g in f["g"]:
                total, n = total + np.square(g), n + 1
        if n:
            yield pd.DataFrame({"s": [total], "n": [n]})

    parts = geo.mapInPandas(sums, "s array<double>, n long").collect()
    column = sum(np.array(r["s"]) for r in parts) / max(sum(r["n"] for r in parts), 1)
    shared = spark.sparkContext.broadcast(column)

    def centre(frames):
        c = shared.value
        for f in frames:
            rows = [-0.5 * (np.square(g) - np.square(g).mean() - c + c.mean()) for g in f["g"]]
            yield pd.DataFrame({"src": f["src"], "b": rows})

    return geo.mapInPandas(centre, "src long, b array<double>")


def eig_top(gram: DataFrame, d: int, solver: str = "local", rounds: int = 200, tolerance: float = 1e-8, seed: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, values, vectors) of (src, b) rows, ascending by src.

    local: one dense problem of at most LOCAL_ROWS rows. subspace: block Krylov steps; each task multiplies its rows by
    the newest block, which is broadcast; the driver holds at most KRYLOV directions and their images (never n x n).
    """
    spark = gram.sparkSession
    ids = np.array(sorted(r[0] for r in gram.select("src").collect()), np.int64)
    n = len(ids)
    if solver == "local":
        if n > LOCAL_ROWS:
            raise ValueError(f"{n} rows are too many for one task; use solver='subspace'")
        table = gram.orderBy("src").toArrow()
        m = np.asarray(table["b"].combine_chunks().flatten(), float).reshape(n, n) if n else np.zeros((0, 0))
        return ids, *top_eigen(m, d)
    ship_package(spark)
    gram = gram.cache()

    def product(block):
        shared = spark.sparkContext.broadcast(block)

        def multiply(frames):
            for f in frames:
                yield pd.DataFrame({"src": f["src"], "z": list(np.stack(f["b"].to_numpy()) @ shared.value)})

        rows = gram.mapInPandas(multiply, "src long, z array<double>").toArrow()
        shared.unpersist()
        return np.asarray(rows["z"].combine_chunks().flatten(), float).reshape(n, -1)[np.argsort(np.asarray(rows["src"]))]

    found = lockstep({0: n}, d, lambda blocks: {0: product(blocks[0])}, rounds, tolerance, seed)[0]
    gram.unpersist()
    return ids, *found


def lockstep(sizes: dict[int, int], d: int, product, rounds: int = 200, tolerance: float = 1e-8, seed: int = 0, starts: dict[int, np.ndarray] | None = None) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Key to (values, vectors) of several symmetric tables at once: ``product`` takes a block for each table that is not done and gives their products."""
    steps, blocks, out = {k: krylov(n, d, rounds, tolerance, seed, (starts or {}).get(k)) for k, n in sizes.items()}, {}, {}

    def step(k, z=None):
        try:
            blocks[k] = steps[k].send(z)
        except StopIteration as e:
            blocks.pop(k, None)
            out[k] = e.value

    for k in sizes:
        step(k)
    while blocks:
        for k, z in product(dict(blocks)).items():
            step(k, z)
    return out


def landmark_starts(spark, graphs, sizes: dict[int, int], d: int, seed: int = 0) -> dict[int, np.ndarray]:
    """Key to a first block for the steps over centred squares of path lengths: the leading directions of LANDMARKS of their columns.

    Rounds that work out all lengths anew are dear, and a start near the wanted directions saves about half of them; it does not
    change what the steps end with. ``graphs``: a broadcast of what ``path_chunks`` takes.
    """
    draw = np.random.default_rng(seed)
    rows = [(k, int(place)) for k, n in sizes.items() for place in draw.choice(n, min(n, LANDMARKS), replace=False)]

    def squares(batches):
        for batch in batches:
            for key, place in zip(batch.column("key").to_pylist(), batch.column("place").to_pylist(), strict=True):
                g = shortest_paths(*graphs.value[key], np.array([place]))  # one by one: these lie far apart
                yield pa.RecordBatch.from_pydict({"key": pa.array([key], pa.int32()), "s": pa.array([np.square(g).astype(np.float32).tobytes()], pa.binary())})

    table = table_frame(spark, pd.DataFrame(rows, columns=["key", "place"]).astype({"key": "int32"}), "key int, place long").repartition(max(1, -(-len(rows) // 8)))
    found = table.mapInArrow(squares, "key int, s binary").toArrow()
    out = {}
    for k, n in sizes.items():
        c = np.stack([np.frombuffer(s.as_buffer(), np.float32) for key, s in zip(found["key"], found["s"], strict=True) if key.as_py() == k])
        c -= c.mean(1, keepdims=True)
        c -= c.mean(0)
        small = np.linalg.eigh((c @ c.T).astype(float))[1][:, ::-1]
        out[k] = (c.T @ small[:, : min(len(c), d + START)].astype(np.float32)).astype(float)
    del found, c
    free_driver(spark)
    return out


def leading_of_paths(chunks: DataFrame, sizes: dict[int, int], d: int, graphs=None) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Key to (values, vectors) of the centred squares of symmetric path lengths, from ``path_chunks``.

    Centring both sides of the squares is centring the block before the product and the product after it, so rows are kept as
    they are; each round is one pass over them, and the driver holds KRYLOV directions and their images. With ``graphs``, a
    broadcast of what ``path_chunks`` takes, ``chunks`` has the groups of sources alone and each round works out their lengths.
    """
    spark = chunks.sparkSession

    def product(blocks):
        shared = spark.sparkContext.broadcast({k: b - b.mean(0) for k, b in blocks.items()})

        def multiply(batches):
            for batch in batches:
                for key, place, *g in zip(*(batch.column(c) for c in batch.schema.names), strict=True):
                    block = shared.value.get(key.as_py())
                    if block is not None:
                        lengths = np.frombuffer(g[0].as_buffer()).reshape(-1, len(block)) if g else shortest_paths(*graphs.value[key.as_py()], np.frombuffer(place.as_py(), np.int64))
                        z = np.square(lengths) @ block
                        yield pa.RecordBatch.from_pydict({"key": pa.array([key.as_py()], pa.int32()), "place": pa.array([place.as_py()], pa.binary()), "z": pa.array([z.tobytes()], pa.binary())})

        out = {k: np.empty(b.shape) for k, b in blocks.items()}
        for r in chunks.mapInArrow(multiply, "key int, place binary, z binary").collect():
            out[r["key"]][np.frombuffer(r["place"], np.int64)] = np.frombuffer(r["z"]).reshape(-1, out[r["key"]].shape[1])
        shared.unpersist()
        if graphs is not None:  # rounds are long and blocks wide
            free_driver(spark)
        return {k: -0.5 * (z - z.mean(0)) for k, z in out.items()}

    return lockstep(sizes, d, product, starts=None if graphs is None else landmark_starts(spark, graphs, sizes, d))


def classical_mds(dist: DataFrame, d: int) -> DataFrame:
    """(id, y) of a complete table of distances (src, dst, dist) of bounded size."""
    ship_package(dist.sparkSession)

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        m = f.pivot_table(index="src", columns="dst", values="dist", fill_value=0.0)
        return pd.DataFrame({"id": m.index.to_numpy(), "y": list(classical_scaling(m.to_numpy(), d))})

    return dist.withColumn("all", F.lit(0)).groupBy("all").applyInPandas(solve, "id long, y array<double>")


def dim_from_spectrum(values: np.ndarray, rule: str = "gap", share: float = 0.95) -> int:
    """The dimension that the leading eigenvalues tell: the largest ratio between neighbours (values below a millionth of the first count as that), or the share of their sum.

    A ratio, since on a long and narrow surface the first value exceeds the second by more than the second exceeds noise.
    """
    v = np.maximum(np.asarray(values, float), 0)
    if len(v) < 2 or v.sum() == 0:
        return len(v)
    if rule == "share":
        return int(np.searchsorted(np.cumsum(v) / v.sum(), share) + 1)
    v = np.maximum(v, 1e-6 * v[0])
    return int((v[:-1] / v[1:]).argmax() + 1)


def spectral_embed(points: DataFrame, k: int, d: int, feature: str = "geodesic", graph: str = "union", solver: str | None = None) -> DataFrame:
    """(id, y): neighbour graph, feature matrix, factorisation; solver None: a dense problem up to DENSE_ROWS points, beyond that block steps over distributed rows.

    geodesic: shortest paths, leading pairs (the classic single-manifold method). local_linear: weights that rebuild a point from
    its neighbours, bottom vectors. laplacian: heat weights, bottom vectors of the normalised graph Laplacian.
    """
    spark = points.sparkSession
    if feature == "geodesic":
        points = materialise(points.select("id", "x"), "points")
        edges = bridge_components(symmetrize(knn(points, k), graph), points)
        ids = point_ids(points)
        if solver or len(ids) <= min(LOCAL_ROWS, DENSE_ROWS) or graph == "directed":
            ids, value, vector = eig_top(gram_rows(geodesics(edges, ids)), d, solver or ("local" if len(ids) <= LOCAL_ROWS else "subspace"))
        else:
            graphs, sizes = {0: (len(ids), *arcs_of(edges, ids))}, {0: len(ids)}
            if len(ids) ** 2 <= HELD_LENGTHS:
                chunks = path_chunks(spark, graphs).persist()
                value, vector = leading_of_paths(chunks, sizes, d)[0]
                chunks.unpersist()
            else:
                value, vector = leading_of_paths(path_groups(spark, graphs), sizes, d, spark.sparkContext.broadcast(graphs))[0]
        y = vector * np.sqrt(value)
    else:
        ids, x = collect_points(points, LOCAL_ROWS)
        table = symmetrize(knn(points, k), "directed" if feature == "local_linear" else "union").toArrow()
        src, dst = (np.searchsorted(ids, np.asarray(table[c], np.int64)) for c in ("src", "dst"))
        dist, n = np.asarray(table["dist"], float), len(ids)
        w = np.zeros((n, n))
        if feature == "local_linear":
            for i in range(n):
                own = dst[src == i]
                c = (x[own] - x[i]) @ (x[own] - x[i]).T
                c += np.eye(len(own)) * 1e-3 * max(np.trace(c), 1e-12)
                v = np.linalg.solve(c, np.ones(len(own)))
                w[i, own] = v / v.sum()
            m = (np.eye(n) - w).T @ (np.eye(n) - w)
            scale = np.ones(n)
        elif feature == "laplacian":
            w[src, dst] = np.exp(-(dist**2) / max(np.median(dist) ** 2, 1e-300))
            degree = w.sum(1)
            scale = 1 / np.sqrt(np.maximum(degree, 1e-300))
            m = np.eye(n) - scale[:, None] * w * scale
        else:
            raise ValueError(f"unknown feature {feature!r}")
        vector = np.linalg.eigh((m + m.T) / 2)[1][:, 1 : d + 1]
        y = signed(vector * scale[:, None] * np.sqrt(n))
    y = np.pad(y, ((0, 0), (0, max(0, d - y.shape[1]))))
    return table_frame(spark, pd.DataFrame({"id": ids, "y": list(y)}), "id long, y array<double>")
