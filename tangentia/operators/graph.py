"""Graph operators over edge tables: components, the directed least-ancestor label, symmetrised neighbour graphs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tangentia.session import materialise, ship_package


STEPS_A_ROUND = 3
BATCH_ARCS = 2_000_000  # a batch's graph of so many arcs goes to one task


def signature(df: DataFrame, *cols: str) -> tuple:
    """(rows, hash sum): equal for equal tables, in any order."""
    return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*cols).cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 64) -> DataFrame:
    """(id, component): for each endpoint of an undirected edge, the least id that it reaches.

    Alternating star contraction: each round ties all larger neighbours of a node, then the node and its smaller ones,
    to the least of them. The number of rounds grows with the logarithm of the longest path. Minima are
    taken before rows are joined back, so a hub is one row for each map task; each round is a written table.
    """
    both = lambda e: e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    e = edges.where(F.col(src) != F.col(dst)).select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).distinct()
    e = materialise(e, "edges")
    for _ in range(0 if e.isEmpty() else max_rounds):
        wide = both(e)
        least = wide.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("n"), F.least("u", "m").alias("m"))
        large = wide.where("v > u").join(least, F.col("u") == F.col("n")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        e = materialise(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "edges")
        # stars already, if no parent is a child and no child has two parents
        parents, children = e.select(F.col("v").alias("u")).distinct(), e.groupBy("u").agg(F.count(F.lit(1)).alias("n"))
        if children.join(parents.withColumn("parent", F.lit(1)), "u", "left").where("n > 1 OR parent = 1").isEmpty():
            break
    roots = e.select(F.col("v").alias("id")).distinct().select("id", F.col("id").alias("component"))
    return e.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)


def seed_order(points: DataFrame, order: str = "hash", seed: int = 0) -> DataFrame:
    """(id, rank): the order in which points are tried as seeds, by id or by a hash. Ranks are dense over the batch."""
    key = [F.col("id")] if order == "id" else [F.xxhash64(F.lit(seed), F.col("id")), F.col("id")]
    return points.select("id").withColumn("rank", F.row_number().over(Window.orderBy(*key)).cast("long"))


def directed_min_label(edges: DataFrame, ranks: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """(id, label): the least rank among a point's ancestors over the arcs src -> dst, itself included.

    This is what growing clusters one after another from the seeds in rank order gives: the lowest ancestor of a point is
    reached from no lower seed, so it becomes a seed, and no point on its way to the point is taken before. Only
    rows whose label fell in the last step send it on; after a few steps the table is written.
    """
    label = materialise(ranks.select("id", F.col("rank").alias("label"), F.lit(True).alias("fresh")), "labels")
    arcs = materialise(edges.select("src", "dst").where("src <> dst").distinct(), "arcs")
    for _ in range(max_rounds):
        for _ in range(STEPS_A_ROUND):
            sent = label.where("fresh").join(arcs, F.col("id") == F.col("src")).groupBy(F.col("dst").alias("id")).agg(F.min("label").alias("offer"))
            label = label.join(sent, "id", "left").select("id", F.least("label", "offer").alias("label"), F.coalesce(F.col("offer") < F.col("label"), F.lit(False)).alias("fresh"))
        label = materialise(label, "labels")
        if label.where("fresh").isEmpty():
            return label.select("id", "label")
    raise RuntimeError(f"labels still move after {max_rounds} rounds")


def component_min_label(arcs: DataFrame, ranks: DataFrame) -> DataFrame:
    """(id, label): the least rank in each point's component; points without arcs are components of their own."""
    own = materialise(ranks.join(connected_components(arcs), "id", "left").select("id", "rank", F.coalesce("component", "id").alias("component")), "components")
    least = own.groupBy("component").agg(F.min("rank").alias("label"))
    return own.join(least, "component").select("id", "label")


def batch_labels(edges: DataFrame, ranks: DataFrame, directed: bool = True) -> DataFrame:
    """(id, label): directed_min_label of a bounded batch, or its undirected form, in one task; a larger graph goes the distributed way, undirected by contraction, whose rounds grow with the logarithm of its paths."""
    arcs = edges.select("src", "dst").where("src <> dst")
    arcs = arcs if directed else arcs.unionByName(arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    arcs = materialise(arcs.distinct(), "arcs")
    if arcs.limit(BATCH_ARCS + 1).count() > BATCH_ARCS:
        return directed_min_label(arcs, ranks) if directed else component_min_label(arcs, ranks)
    ship_package(edges.sparkSession)
    spread = ranks.select(F.col("id").alias("src"), F.lit(None).cast("long").alias("dst"), "rank").unionByName(arcs.withColumn("rank", F.lit(None).cast("long")))

    def settle(f: pd.DataFrame) -> pd.DataFrame:
        own = f[f["dst"].isna()].sort_values("src")
        ids, label = own["src"].to_numpy(), own["rank"].to_numpy().astype(np.int64)
        e = f[f["dst"].notna()]
        a, b = np.searchsorted(ids, e["src"].to_numpy()), np.searchsorted(ids, e["dst"].to_numpy().astype(np.int64))
        fresh = np.ones(len(ids), bool)
        while len(a) and fresh.any():
            live = fresh[a]
            new = label.copy()
            np.minimum.at(new, b[live], label[a[live]])
            fresh, label = new < label, new
        return pd.DataFrame({"id": ids, "label": label})

    return spread.withColumn("all", F.lit(0)).groupBy("all").applyInPandas(settle, "id long, label long")


def grow_clusters(arcs: dict[int, list[int]], order: list[int]) -> dict[int, int]:
    """The sequential form: breadth-first growth from each seed not yet taken; label = the seed's place. The test oracle."""
    label: dict[int, int] = {}
    for place, seed in enumerate(order, 1):
        if seed in label:
            continue
        label[seed], frontier = place, [seed]
        while frontier:
            frontier = [j for i in frontier for j in arcs.get(i, ()) if j not in label and label.setdefault(j, place) == place]
    return label
