"""Accuracy and cost measures."""

from __future__ import annotations

import itertools
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.functions.vectors import vec_dist, vec_dist2
from tangentia.session import broadcast_if_small, ship_package

EXACT_MATCHING = 8  # classes up to which all one-to-one matchings are tried


def contingency(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(cluster, y_true, n)."""
    return pred.select("id", "cluster").join(truth.select("id", "y_true"), "id").groupBy("cluster", "y_true").agg(F.count(F.lit(1)).alias("n"))


def table_of(pred: DataFrame, truth: DataFrame) -> np.ndarray:
    """Clusters by classes; a row for each cluster reaches the driver."""
    c = contingency(pred, truth).toPandas()
    return c.pivot_table(index="cluster", columns="y_true", values="n", fill_value=0).to_numpy().astype(float) if len(c) else np.zeros((0, 0))


def matched_accuracy(table: np.ndarray, balanced: bool = True) -> float:
    """Share of points in the class that their cluster is matched with, one to one; balanced: the mean of that over classes."""
    if not table.size:
        return 0.0
    classes = table.shape[1]
    w = table / (table.sum(0) * classes if balanced else table.sum())
    if classes <= EXACT_MATCHING:
        rows = sorted({int(r) for j in range(classes) for r in np.argsort(-w[:, j])[:classes]})
        rows += [-1] * max(0, classes - len(rows))
        pad = np.vstack([w, np.zeros(classes)])
        if len(rows) <= EXACT_MATCHING:
            return float(max(sum(pad[r, j] for j, r in enumerate(p)) for p in itertools.permutations(rows, classes)))
        best = {frozenset(): 0.0}
        for j in range(classes):
            step: dict = {}
            for used, v in best.items():
                for r in [*rows, None]:
                    if r is None or r not in used:
                        key = used if r is None else used | {r}
                        step[key] = max(step.get(key, -1.0), v + (0.0 if r is None else pad[r, j]))
            best = step
        return float(max(best.values()))
    total, left = 0.0, w.copy()
    for _ in range(classes):
        r, j = np.unravel_index(left.argmax(), left.shape)
        total += left[r, j]
        left[r, :] = left[:, j] = -1.0
    return float(total)


def clustering_accuracy(pred: DataFrame, truth: DataFrame, balanced: bool = True) -> float:
    return matched_accuracy(table_of(pred, truth), balanced)


def clustering_report(pred: DataFrame, truth: DataFrame) -> dict[str, float]:
    """Balanced and plain accuracy, purity, clusters found, adjusted Rand index, normalised mutual information."""
    t = table_of(pred, truth)
    n = t.sum()
    pairs = lambda x: (x * (x - 1) / 2).sum()
    a, b, both = pairs(t.sum(1)), pairs(t.sum(0)), pairs(t)
    expected = a * b / max(n * (n - 1) / 2, 1)
    rand = (both - expected) / ((a + b) / 2 - expected) if (a + b) / 2 != expected else 1.0
    p = t / n
    with np.errstate(divide="ignore", invalid="ignore"):
        info = np.nansum(p * np.log(p / (p.sum(1, keepdims=True) * p.sum(0))))
    h = lambda q: -(q[q > 0] * np.log(q[q > 0])).sum()
    scale = np.sqrt(h(p.sum(1)) * h(p.sum(0)))
    return {"balanced": matched_accuracy(t), "plain": matched_accuracy(t, False), "purity": t.max(1).sum() / n, "clusters": float(len(t)), "rand": float(rand), "nmi": float(info / scale) if scale else 0.0}


def purity(pred: DataFrame, truth: DataFrame) -> DataFrame:
    c = contingency(pred, truth).groupBy("cluster").agg(F.max("n").alias("most"), F.sum("n").alias("all"))
    return c.agg((F.sum("most") / F.sum("all")).alias("purity"))


def pair_up(a: DataFrame, b: DataFrame, by: str | None = None) -> DataFrame:
    left = a.select("id", F.col("y").alias("a"), *([by] if by else []))
    return left.join(b.select("id", F.col("y").alias("b")), "id")


def procrustes_by(a: DataFrame, b: DataFrame, by: str | None = None) -> DataFrame:
    """(group, error, n): what no shift, turn, mirror and scale of b explains of a, for each group. Moments are sums over all rows; only d x d tables are solved."""
    ship_package(a.sparkSession)
    j = pair_up(a, b, by).withColumn("g", F.col(by).cast("string") if by else F.lit("all"))
    la = j.select("g", "id", F.posexplode("a").alias("i", "p"), "b").select("g", "id", "i", "p", F.posexplode("b").alias("k", "q"))
    m = la.groupBy("g", "i", "k").agg(F.covar_pop("p", "q").alias("c"), F.var_pop("p").alias("vp"), F.var_pop("q").alias("vq"), F.count(F.lit(1)).alias("n"))

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        c = f.pivot_table(index="i", columns="k", values="c").to_numpy()
        va, vb = f.groupby("i")["vp"].first().sum(), f.groupby("k")["vq"].first().sum()
        s = np.linalg.svd(c, compute_uv=False).sum()
        return pd.DataFrame({"group": [f["g"].iloc[0]], "error": [max(0.0, 1 - s * s / (va * vb)) if va > 0 and vb > 0 else 1.0], "n": [int(f["n"].iloc[0])]})

    return m.groupBy("g").applyInPandas(solve, "group string, error double, n long")


def procrustes_error(a: DataFrame, b: DataFrame) -> float:
    return procrustes_by(a, b).first()["error"]


def procrustes_2d(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row of (error) for planar embeddings, in closed form: with M the normalised cross moments, 1 - (|M|^2 + 2 |det M|)."""
    j = pair_up(a, b)
    cov = lambda p, q: F.covar_pop(p, q)
    a0, a1, b0, b1 = F.col("a")[0], F.col("a")[1], F.col("b")[0], F.col("b")[1]
    s = j.agg(cov(a0, b0).alias("m00"), cov(a0, b1).alias("m01"), cov(a1, b0).alias("m10"), cov(a1, b1).alias("m11"), (F.var_pop(a0) + F.var_pop(a1)).alias("va"), (F.var_pop(b0) + F.var_pop(b1)).alias("vb"))
    square = sum(F.col(c) * F.col(c) for c in ("m00", "m01", "m10", "m11"))
    det = F.abs(F.col("m00") * F.col("m11") - F.col("m01") * F.col("m10"))
    return s.select((1 - (square + 2 * det) / (F.col("va") * F.col("vb"))).alias("error"))


def sampled_pairs(a: DataFrame, b: DataFrame, step: int = 7) -> DataFrame:
    """(da, db): distances of pairs of rows in both embeddings. Each id meets those ids that follow it by 1, step, step^2 places of id: a sample linear in the rows."""
    j = pair_up(a, b)
    other = j.select(F.col("id").alias("id2"), F.col("a").alias("a2"), F.col("b").alias("b2"))
    hops = F.explode(F.array(*[F.lit(s) for s in (1, step, step * step)]))
    return j.withColumn("hop", hops).withColumn("id2", F.col("id") + F.col("hop")).join(other, "id2").select(vec_dist("a", "a2").alias("da"), vec_dist("b", "b2").alias("db"))


def residual_variance(a: DataFrame, b: DataFrame) -> DataFrame:
    """1 - r^2 between distances in the two embeddings, over sampled pairs."""
    c = F.corr("da", "db")
    return sampled_pairs(a, b).agg((1 - c * c).alias("residual_variance"))


def distance_stress(a: DataFrame, b: DataFrame) -> DataFrame:
    return sampled_pairs(a, b).agg(F.sqrt(F.sum((F.col("da") - F.col("db")) * (F.col("da") - F.col("db"))) / F.sum(F.col("da") * F.col("da"))).alias("stress"))


def mean_vector(df: DataFrame, by: str, y: str = "y") -> DataFrame:
    m = df.select(by, F.posexplode(y).alias("k", "v")).groupBy(by, "k").agg(F.avg("v").alias("m"))
    return m.groupBy(by).agg(F.transform(F.sort_array(F.collect_list(F.struct("k", "m"))), lambda s: s["m"]).alias("mu"))


def tightness(emb: DataFrame, by: str = "cluster") -> DataFrame:
    """(by, tightness, n): mean squared distance to the group's mean."""
    return emb.join(broadcast_if_small(mean_vector(emb, by)), by).groupBy(by).agg(F.avg(vec_dist2("y", "mu")).alias("tightness"), F.count(F.lit(1)).alias("n"))


def silhouette(emb: DataFrame, by: str = "cluster") -> float:
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.functions import array_to_vector

    v = emb.select(array_to_vector("y").alias("features"), F.col(by).cast("double").alias("prediction"))
    return ClusteringEvaluator().evaluate(v)


def shortcut_rate(edges: DataFrame, truth: DataFrame, factor: float = 4.0) -> DataFrame:
    """Share of neighbour arcs that join two surfaces, or places of one surface ``factor`` times further apart than the arc is long."""
    a = truth.select(F.col("id").alias("src"), F.col("y_true").alias("ya"), F.col("u").alias("ua"))
    b = truth.select(F.col("id").alias("dst"), F.col("y_true").alias("yb"), F.col("u").alias("ub"))
    j = edges.join(a, "src").join(b, "dst")
    across, far = F.col("ya") != F.col("yb"), vec_dist("ua", "ub") > factor * F.col("dist")
    return j.agg(F.avg((across | far).cast("double")).alias("shortcut_rate"), F.count(F.lit(1)).alias("arcs"))


def shape_stats(emb: DataFrame, by: str = "cluster") -> DataFrame:
    """(by, n, spread_0, spread_1, ratio, radius) of each group: standard deviations along the first two axes, their ratio, mean distance to the mean."""
    j = emb.join(broadcast_if_small(mean_vector(emb, by)), by)
    s = j.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.stddev_pop(F.col("y")[0]).alias("spread_0"), F.stddev_pop(F.col("y")[1]).alias("spread_1"), F.avg(vec_dist("y", "mu")).alias("radius"))
    return s.withColumn("ratio", F.least("spread_0", "spread_1") / F.greatest("spread_0", "spread_1"))


def separation(emb: DataFrame, by: str = "cluster") -> DataFrame:
    """(separation): least distance between group means over the mean radius; the table of groups is small."""
    s = shape_stats(emb, by).agg(F.avg("radius").alias("r"))
    m = mean_vector(emb, by)
    gap = m.join(m.select(F.col(by).alias("other"), F.col("mu").alias("nu")), F.col(by) < F.col("other")).agg(F.min(vec_dist("mu", "nu")).alias("gap"))
    return gap.join(s).select((F.col("gap") / F.col("r")).alias("separation"))


def cost_counters(model, n_stream: int, arcs: int, support_pairs: int) -> dict[str, int]:
    """How many elementary steps each phase of a fitted model takes, from the clusters it found, its stored sources and its arcs."""
    sizes, sources = [len(f.ids) for f in model.manifolds], [len(f.g) for f in model.manifolds]
    n, dim = sum(sizes), model.manifolds[0].x.shape[1] if model.manifolds else 0
    return {
        "batch_distances": n * n,
        "arcs": arcs,
        "path_arcs": sum(m * arcs * k // max(n, 1) for m, k in zip(sources, sizes, strict=True)),
        "factor_steps": sum(m**3 for m in sources),
        "cross_distances": sum(a * b for i, a in enumerate(sizes) for b in sizes[i + 1 :]),
        "support_pairs": support_pairs,
        "stream_distances": n_stream * n,
        "stream_steps": n_stream * sum(a * dim + m * model.params["n_neighbors"] for a, m in zip(sizes, sources, strict=True)),
    }


def timed(run, *rows: int) -> list[tuple[int, float, float]]:
    """(rows, seconds, rows a second) of run(n) written to no sink, for each n."""
    out = []
    for n in rows:
        t0 = time.perf_counter()
        run(n).write.format("noop").mode("overwrite").save()
        s = time.perf_counter() - t0
        out.append((n, s, n / s))
    return out

