"""The stream phase under Structured Streaming: map-only mapping, quality windows, and the switch from learning to mapping."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.operators.mapper import Model
from tangentia.plans.engine import transform
from tangentia.session import ship_package


def transform_stream(stream: DataFrame, model: Model, path: str, checkpoint: str, keep: tuple[str, ...] = ("ts",), once: bool = True, **options):
    """Start the mapping of a stream into Parquet, parted by manifold. No shuffle and no state; the file sink's log makes restarts exact.

    once: take what is there and end (AvailableNow), else run on.
    """
    out = transform(stream, model, keep=keep, **options)
    writer = out.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).partitionBy("manifold").outputMode("append")
    return (writer.trigger(availableNow=True) if once else writer).start()


def write_once(mapped: DataFrame, path: str, checkpoint: str):
    """foreachBatch sink that is idempotent by batch id: a batch that runs again overwrites its own folder."""

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return mapped.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def quality_windows(mapped: DataFrame, size: str = "1 day", slide: str | None = None, watermark: str | None = "1 hour") -> DataFrame:
    """(start, end, manifold, n, residual): tumbling or sliding windows; later rows than the watermark are dropped and counted by Spark."""
    m = mapped.withWatermark("ts", watermark) if watermark and mapped.isStreaming else mapped
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    g = m.groupBy(w.alias("w"), "manifold").agg(F.count(F.lit(1)).alias("n"), F.avg("residual").alias("residual"))
    return g.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "manifold", "n", "residual")


def session_windows(mapped: DataFrame, gap: str = "30 minutes", watermark: str | None = "1 hour") -> DataFrame:
    m = mapped.withWatermark("ts", watermark) if watermark and mapped.isStreaming else mapped
    g = m.groupBy(F.session_window("ts", gap).alias("w"), "manifold").agg(F.count(F.lit(1)).alias("n"), F.avg("residual").alias("residual"))
    return g.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "manifold", "n", "residual")


def distinct_events(stream: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Repeated ids within the watermark once."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["id"])


def with_labels(mapped: DataFrame, labels: DataFrame) -> DataFrame:
    """Outer join of the stream to a static table by id: rows without a label stay."""
    return mapped.join(labels, "id", "left_outer")


def interval_join(left: DataFrame, right: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Pairs of events of one user at most ``within`` apart, the right one later; both sides bounded by watermarks when streaming."""
    a, b = left.select("user_id", F.col("id").alias("id_a"), F.col("ts").alias("ts_a")), right.select(F.col("user_id").alias("user_b"), F.col("id").alias("id_b"), F.col("ts").alias("ts_b"))
    if left.isStreaming:
        a, b = a.withWatermark("ts_a", "1 hour"), b.withWatermark("ts_b", "1 hour")
    return a.join(b, (F.col("user_id") == F.col("user_b")) & (F.col("ts_b") > F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr(f"INTERVAL {within}"))).drop("user_b")


def switch_when_stable(stream: DataFrame, least: int = 200, step: int = 200, most: int = 4_000, tolerance: float = 0.02, k: int = 8, d: int = 2) -> DataFrame:
    """(key, id, phase, error): the switch from exact learning to mapping, as a stateful operator.

    Each key buffers its samples (at most ``most``). Every ``step`` of them the embedding is made anew, and the error is what
    changed for the first ``least`` samples; once it is below the tolerance, or the buffer full, the key has switched: its later
    samples come out as "map" with no buffering, earlier ones as "learn". The stream needs columns key, id, x.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    ship_package(stream.sparkSession)

    def step_over(key, frames, state: GroupState):
        import json

        import numpy as np

        from tangentia.functions.numeric import classical_scaling, procrustes
        from tangentia.plans.engine import local_geodesics

        held = json.loads(state.get[0]) if state.exists else {"x": [], "y": None, "error": None, "done": False, "tried": 0}
        for f in frames:
            phases, errors = [], []
            for x in f["x"]:
                if not held["done"]:
                    held["x"].append([float(v) for v in x])
                    n = len(held["x"])
                    if n >= least and n - held["tried"] >= step:
                        held["tried"] = n
                        y = classical_scaling(local_geodesics(np.arange(n), np.array(held["x"]), k), d)[:least]
                        if held["y"] is not None:
                            held["error"] = procrustes(np.array(held["y"]), y)
                        held["y"] = y.tolist()
                    held["done"] = n >= most or (held["error"] is not None and held["error"] <= tolerance)
                    if held["done"]:
                        held["x"], held["y"] = [], None
                    phases.append("learn")
                else:
                    phases.append("map")
                errors.append(held["error"])
            yield pd.DataFrame({"key": key[0], "id": f["id"].to_numpy(), "phase": phases, "error": pd.Series(errors, dtype="float64")})
        state.update((json.dumps(held),))

    return stream.groupBy("key").applyInPandasWithState(step_over, "key long, id long, phase string, error double", "held string", "append", GroupStateTimeout.NoTimeout)
