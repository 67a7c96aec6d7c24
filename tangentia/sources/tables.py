"""Batch and streaming readers of the tables, and the splits around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tangentia.functions.vectors import is_valid

#: Streams are never inferred. Timestamps in the files carry no zone; the session's (UTC) is taken.
EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
    ]
)
POINT = T.StructType(
    [
        T.StructField("id", T.LongType(), False), T.StructField("x", T.ArrayType(T.DoubleType()), False), T.StructField("y_true", T.IntegerType()),
        T.StructField("u", T.ArrayType(T.DoubleType())), T.StructField("ts", T.TimestampType()),
    ]
)


def zoned(df: DataFrame) -> DataFrame:
    """Zoneless timestamps as instants: watermarks and unix_micros take no others."""
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema if isinstance(f.dataType, T.TimestampNTZType)})


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return zoned(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def stream_table(spark: SparkSession, path: str, schema: T.StructType = EVENTS, files_per_trigger: int = 1) -> DataFrame:
    """A streaming read of Parquet files with a fixed schema; ``path`` is a folder or a glob."""
    return zoned(spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path))


def split_bad_rows(points: DataFrame, size: int, x: str = "x") -> tuple[DataFrame, DataFrame]:
    """(good, bad): bad rows have a null, short, long or non-finite vector, and say so in ``reason``."""
    reason = F.when(F.col(x).isNull(), "null").when(F.size(x) != size, "length").otherwise("not finite")
    ok = is_valid(x, size)
    return points.where(ok), points.where(~ok).withColumn("reason", reason)


def split_batch_stream(points: DataFrame, n: int | None = None, fraction: float | None = None, order: str = "id") -> tuple[DataFrame, DataFrame]:
    """The first n rows by ``order`` (or a hash share of the ids) as the batch, all others as the stream."""
    if n is not None:
        cut = points.select(order).orderBy(order).limit(n).agg(F.max(order)).first()[0]
        return (points.where(F.lit(False)), points) if cut is None else (points.where(F.col(order) <= cut), points.where(F.col(order) > cut))
    chosen = F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < F.lit(int(fraction * 1_000_000))
    return points.where(chosen), points.where(~chosen)


def standardise(df: DataFrame, columns: list[str]) -> DataFrame:
    """Adds x: the columns less their means over their standard deviations (one aggregate, one row joined to all)."""
    stats = df.agg(*[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns])
    x = F.array(*[(F.col(c) - F.col(f"m_{c}")) / F.when(F.col(f"s_{c}") == 0, 1.0).otherwise(F.col(f"s_{c}")) for c in columns])
    return df.join(F.broadcast(stats)).withColumn("x", x).drop(*[f"{p}_{c}" for p in "ms" for c in columns])


def attach_latest(events: DataFrame, versions: DataFrame, at: str = "ts", value: str = "version") -> DataFrame:
    """As-of join: each event with the last version at or before it. Both are sorted together once; no pairs are made."""
    v = versions.select(F.col(at), F.lit(0).alias("side"), F.struct(value, F.col(at).alias("valid_from")).alias("v"))
    e = events.withColumn("side", F.lit(1)).withColumn("v", F.lit(None).cast(v.schema["v"].dataType))
    day = F.date_trunc("day", at)
    both = e.unionByName(v, allowMissingColumns=True).withColumn("day", day)
    within = Window.partitionBy("day").orderBy(at, "side").rowsBetween(Window.unboundedPreceding, 0)
    # the last version of each day carries over to the days after it: one row a day
    days = both.groupBy("day").agg(F.max_by("v", F.when(F.col("side") == 0, F.col(at))).alias("last"))
    days = days.withColumn("carried", F.last("last", ignorenulls=True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1))).select("day", "carried")
    out = both.withColumn("found", F.last("v", ignorenulls=True).over(within)).where("side = 1").join(F.broadcast(days), "day")
    return out.withColumn("found", F.coalesce("found", "carried")).select(*events.columns, F.col(f"found.{value}").alias(value), F.col("found.valid_from").alias("valid_from"))
