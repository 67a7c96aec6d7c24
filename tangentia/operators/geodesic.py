"""Geodesic distances: shortest paths over a neighbour graph."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tangentia.functions.numeric import GROUP, graph_order, shortest_arcs, shortest_paths
from tangentia.operators.graph import signature
from tangentia.session import materialise, ship_package, table_frame

SOURCES_PER_TASK = 128
MAX_ARCS = 5_000_000


def arcs_of(edges: DataFrame, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(from, to, length) by place in ``ids``, as ``shortest_arcs`` has them; the graph of one batch, so its size is bounded and checked."""
    table = edges.select("src", "dst", F.col("dist").cast("double").alias("dist")).limit(MAX_ARCS + 1).toArrow()
    if len(table) > MAX_ARCS:
        raise ValueError(f"more than {MAX_ARCS} arcs in one batch's graph")
    src, dst = (np.searchsorted(ids, np.asarray(table[c], np.int64)) for c in ("src", "dst"))
    return shortest_arcs(src, dst, np.asarray(table["dist"], float))


def geodesics(edges: DataFrame, ids: np.ndarray, sources: np.ndarray | None = None) -> DataFrame:
    """(src, g): for each source the lengths to all ``ids``, in their (ascending) order. Arcs are broadcast, sources dealt to tasks."""
    spark = edges.sparkSession
    ship_package(spark)
    sources = ids if sources is None else sources
    shared = spark.sparkContext.broadcast((len(ids), *arcs_of(edges, ids)))
    tasks = max(1, -(-len(sources) // SOURCES_PER_TASK))
    rows = table_frame(spark, pd.DataFrame({"src": sources.astype("int64"), "place": np.searchsorted(ids, sources).astype("int64")}), "src long, place long").repartition(tasks)

    def run(frames):
        n, a, b, w = shared.value
        for f in frames:
            for at in range(0, len(f), 64):
                part = f.iloc[at : at + 64]
                yield pd.DataFrame({"src": part["src"].to_numpy(), "g": list(shortest_paths(n, a, b, w, part["place"].to_numpy()))})

    return rows.mapInPandas(run, "src long, g array<double>")


def path_groups(spark: SparkSession, graphs: dict[int, tuple]) -> DataFrame:
    """(key, place): groups of sources that lie near each other, as ``path_chunks`` has them, two to a task."""
    ship_package(spark)
    rows = []
    for key, graph in graphs.items():
        order = graph_order(*graph).astype(np.int64)
        rows += [(key, order[at : at + GROUP].tobytes()) for at in range(0, len(order), GROUP)]
    return table_frame(spark, pd.DataFrame(rows, columns=["key", "place"]).astype({"key": "int32"}), "key int, place binary").repartition(max(1, -(-len(rows) // 2)))


def path_chunks(spark: SparkSession, graphs: dict[int, tuple]) -> DataFrame:
    """(key, place, g): the path lengths between all points of each graph (n, from, to, length), by places.

    A row has a group of sources that lie near each other, and their lengths to all points, as plain bytes (place: int64, g:
    float64, sources by points). Graphs are broadcast, groups dealt to tasks, two to a task. To be persisted by whoever reads it again.
    """
    shared = spark.sparkContext.broadcast(graphs)

    def run(batches):
        for batch in batches:
            for key, place in zip(batch.column("key"), batch.column("place"), strict=True):
                g = shortest_paths(*shared.value[key.as_py()], np.frombuffer(place.as_py(), np.int64))
                yield pa.RecordBatch.from_pydict({"key": pa.array([key.as_py()], pa.int32()), "place": pa.array([place.as_py()], pa.binary()), "g": pa.array([g.tobytes()], pa.binary())})

    return path_groups(spark, graphs).mapInArrow(run, "key int, place binary, g binary")


def geodesics_landmark(edges: DataFrame, ids: np.ndarray, n_landmarks: int, seed: int = 0) -> DataFrame:
    """Rows of ``n_landmarks`` sources only (ours): what a large batch stores in place of all rows."""
    chosen = np.sort(np.random.default_rng(seed).permutation(ids)[:n_landmarks])
    return geodesics(edges, ids, chosen)


def geodesics_minplus(edges: DataFrame, hops: int | None = None) -> DataFrame:
    """(src, dst, dist): the relational form. Each round joins paths to arcs and keeps the shortest, until nothing changes or ``hops`` arcs."""
    e = materialise(edges.select("src", "dst", "dist"), "arcs")
    nodes = e.select(F.col("src").alias("id")).union(e.select("dst")).distinct()
    d = nodes.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0.0).alias("dist"))
    seen, k = None, 0
    while hops is None or k < hops:
        longer = d.join(e.select(F.col("src").alias("dst"), F.col("dst").alias("to"), F.col("dist").alias("w")), "dst").select("src", F.col("to").alias("dst"), (F.col("dist") + F.col("w")).alias("dist"))
        d = materialise(d.unionByName(longer).groupBy("src", "dst").agg(F.min("dist").alias("dist")), "paths")
        k += 1
        now = signature(d, "src", "dst", "dist")
        if now == seen:
            break
        seen = now
    return d
