"""Bounded samples of labelled texts, and the held-out rule shared by the classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RESOLUTION = 1 << 20


def remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; null for a null id."""
    return F.crc32(doc_id.cast("string")) % modulus


def sample_labels(labels: DataFrame, label: str, at_most: int) -> DataFrame:
    """(doc_id, y) of about ``at_most`` labelled ids, half of them for each label where there are enough, chosen by hash.

    An id with several labels has the one that most of its rows give (1 if even); null ids and labels are left out.
    Adds ``weight``: how many labelled ids of its label one sampled id stands for.
    """
    y = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).groupBy("doc_id").agg((F.avg(F.col(label).cast("double")) >= 0.5).cast("int").alias("y"))
    counts = {r["y"]: r["count"] for r in y.groupBy("y").count().collect()}
    if not counts:
        return y.withColumn("weight", F.lit(1.0))
    least = min(counts.values()) if len(counts) == 2 else 0
    room = {k: min(n, at_most // 2) if n == least or len(counts) == 1 else at_most - min(least, at_most // 2) for k, n in counts.items()}
    share = {k: min(1.0, room[k] / n) for k, n in counts.items()}
    at = F.pmod(F.xxhash64("doc_id"), F.lit(RESOLUTION))
    chosen = F.when(F.col("y") == 1, at < share.get(1, 0) * RESOLUTION).otherwise(at < share.get(0, 0) * RESOLUTION)
    weight = F.when(F.col("y") == 1, F.lit(1 / share.get(1, 1.0))).otherwise(F.lit(1 / share.get(0, 1.0)))
    return y.where(chosen).withColumn("weight", weight).limit(2 * at_most)


def labelled_texts(docs: DataFrame, sample: DataFrame, longest: int) -> DataFrame:
    """(y, weight, text) of the sampled ids whose text has at most ``longest`` bytes; one row for a repeated doc_id.

    The sample has a documented bound, so it is broadcast whatever the size of ``docs``.
    """
    ids = sample.withColumnRenamed("doc_id", "label_id")
    rows = docs.select("doc_id", "text").join(F.broadcast(ids), F.col("doc_id") == F.col("label_id"))
    return rows.where(F.coalesce(F.octet_length("text"), F.lit(0)) <= longest).dropDuplicates(["doc_id"]).select("y", "weight", "text")
