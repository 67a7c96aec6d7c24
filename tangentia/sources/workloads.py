"""The experiments' inputs on the given tables: surfaces over two latent coordinates of ``events``, and vectors of other tables."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tangentia.functions.numeric import rotation
from tangentia.functions.vectors import DOT, vec_norm
from tangentia.sources.tables import load_table, standardise

LENGTH, PHASE, HEIGHT = 6.0, 8.0, 3.0  # of the roll; its turning angle at arc length s is s^2 / PHASE
NODES, WEIGHTS = (a.tolist() for a in ((np.polynomial.legendre.leggauss(12)[0] + 1) / 2, np.polynomial.legendre.leggauss(12)[1] / 2))


def latent_uv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, ts, u, v): the place within the hour, and the value's rank under its exponential law; both uniform on [0, 1]."""
    e = load_table(spark, sf_dir, "events")
    u = F.pmod(F.unix_micros("ts"), F.lit(3_600_000_000)) / F.lit(3.6e9)
    return e.select(F.col("event_id").alias("id"), "ts", u.alias("u"), (1 - F.exp(-F.col("value") / 50)).alias("v"))


def arc(s: Column, f, phase: float = PHASE) -> Column:
    """The integral of f(t^2 / phase) from 0 to s, by fixed nodes."""
    return s * sum(F.lit(w) * f((s * t) * (s * t) / phase) for t, w in zip(NODES, WEIGHTS, strict=True))


def roll_point(u: Column, v: Column, phase: float = PHASE) -> Column:
    """A rolled-up rectangle; distances along it are those of the rectangle LENGTH by HEIGHT."""
    s = u * LENGTH
    return F.array(arc(s, F.cos, phase), v * HEIGHT, arc(s, F.sin, phase))


def sphere_point(u: Column, v: Column, shift: float = 0.0) -> Column:
    z, r, a = 2 * v - 1, F.sqrt(F.greatest(1 - (2 * v - 1) * (2 * v - 1), F.lit(0.0))), 2 * math.pi * u
    return F.array(r * F.cos(a) + shift, r * F.sin(a), z)


def plane_point(u: Column, v: Column, kind: str) -> Column:
    """roll: across the roll, at half its first rise; roll2: upright across it; sphere: through a sphere's middle."""
    if kind == "roll":
        return F.array(u * 6 - 1, v * HEIGHT, F.lit(0.8) + 0 * u)
    if kind == "roll2":
        return F.array(F.lit(1.2) + 0 * u, v * HEIGHT, u * 4 - 1)
    return F.array(3 * u - 1.5, 3 * v - 1.5, 0 * u)


def scene(spark: SparkSession, sf_dir: str, name: str, n: int | None = None) -> DataFrame:
    """(id, x, y_true, u, ts) of one of the scenes, the first n rows by id.

    roll_plane (two of three rows on the roll), roll_2planes, spheres, sphere_plane, patches (four on one roll), roll_tight
    (coils so near that neighbour graphs jump across), roll (all rows), uneven (a roll whose density falls along it).
    """
    d = latent_uv(spark, sf_dir)
    if n:
        d = d.where(F.col("id") < d.agg(F.min("id")).first()[0] + n)
    u, v, i = F.col("u"), F.col("v"), F.col("id")
    if name == "roll_plane":
        label = F.when(i % 3 == 2, 1).otherwise(0)
        x = F.when(label == 1, plane_point(u, v, "roll")).otherwise(roll_point(u, v))
        truth = F.when(label == 1, F.array(u * 6, v * HEIGHT)).otherwise(F.array(u * LENGTH, v * HEIGHT))
    elif name == "roll_2planes":
        label = (i % 3).cast("int")
        x = F.when(label == 1, plane_point(u, v, "roll")).when(label == 2, plane_point(u, v, "roll2")).otherwise(roll_point(u, v))
        truth = F.when(label == 2, F.array(u * 4, v * HEIGHT)).otherwise(F.array(u * 6, v * HEIGHT))
    elif name == "spheres":
        label = (i % 2).cast("int")
        x = F.when(label == 1, sphere_point(u, v, 1.0)).otherwise(sphere_point(u, v))
        truth = F.array(u, v)
    elif name == "sphere_plane":
        label = (i % 2).cast("int")
        x = F.when(label == 1, plane_point(u, v, "sphere")).otherwise(sphere_point(u, v))
        truth = F.array(u, v)
    elif name == "patches":
        label = (i % 4).cast("int")
        r = F.sqrt(-2 * F.log(F.greatest(1 - v, F.lit(1e-12)))) * 0.22
        s = F.array(*[F.lit(c) for c in (1.0, 2.3, 3.7, 5.0)])[label] + r * F.cos(2 * math.pi * u)
        h = F.array(*[F.lit(c) for c in (1.0, 2.2, 0.8, 2.0)])[label] + r * F.sin(2 * math.pi * u)
        x, truth = F.array(arc(s, F.cos), h, arc(s, F.sin)), F.array(s, h)
    elif name in ("roll", "roll_tight", "uneven"):
        label = F.lit(0)
        s = F.pow(u, 1.7) if name == "uneven" else u
        x, truth = roll_point(s, v, 4.0 if name == "roll_tight" else PHASE), F.array(s * LENGTH, v * HEIGHT)
    else:
        raise ValueError(f"unknown scene {name!r}")
    return d.select("id", x.alias("x"), label.cast("int").alias("y_true"), truth.alias("u"), "ts")


def raw_digits(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load_table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"), F.col("label").alias("y_true"))


def lifted_digits(spark: SparkSession, sf_dir: str, noise: float = 0.01) -> DataFrame:
    """Digits with structure: three coordinates of each vector as latents, bent smoothly into a frame of the label's own, plus little noise."""
    d = raw_digits(spark, sf_dir)
    frames = F.array(*[F.array(*[F.array(*[F.lit(float(a)) for a in row]) for row in rotation(100 + k, 6, 64).T]) for k in range(10)])
    z = [F.col("x")[k] * 3 for k in range(3)]
    bent = F.array(*z, 0.3 * F.sin(2 * z[0]), 0.3 * F.cos(2 * z[1]), 0.3 * z[2] * z[0])
    lifted = F.transform(frames[F.col("y_true")], lambda row: DOT(row, bent))
    x = F.transform(F.zip_with(lifted, F.concat(F.slice("x", 4, 61), F.slice("x", 1, 3)), lambda a, b: a + noise * b), lambda v: v)
    return d.select("id", x.alias("x"), "y_true", F.array(*z).alias("u"))


def noisy_sphere(spark: SparkSession, sf_dir: str, sigma: float = 0.05, sphere_dims: int = 6) -> DataFrame:
    """Points of a unit sphere in the first coordinates, with noise in all the others (64 in all)."""
    d = raw_digits(spark, sf_dir)
    head = F.slice("x", 1, sphere_dims)
    norm = vec_norm(head)
    tail = F.transform(F.slice("x", sphere_dims + 1, 64 - sphere_dims), lambda v: v * sigma)
    return d.withColumn("n", norm).where("n > 0").select("id", F.concat(F.transform(head, lambda v: v / F.col("n")), tail).alias("x"))


def ngram_vectors(spark: SparkSession, sf_dir: str, size: int = 32, table: str = "documents", key: str = "doc_id") -> DataFrame:
    """(id, x): shares of hashed pairs of neighbouring characters a-z; the class is the language. Counted after an explode, so long texts are no special case."""
    d = load_table(spark, sf_dir, table)
    text = F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), "[^a-z]", "")
    pairs = F.regexp_extract_all(text, F.lit("(?=([a-z]{2}))"), F.lit(1))  # overlapping; one pass over the text
    grams = d.select(F.col(key).alias("id"), F.explode(pairs).alias("g"))
    code = lambda c: F.ascii(c) - 97
    bucket = (code(F.substring("g", 1, 1)) * 26 + code(F.substring("g", 2, 1))) * 31 % size
    counts = grams.groupBy("id", bucket.alias("b")).count()
    rows = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("b", "count"))).alias("m"), F.sum("count").alias("n"))
    return rows.select("id", F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda b: F.coalesce(F.try_element_at("m", b), F.lit(0)) / F.col("n")).alias("x"))


TAGS = ("p", "a", "li", "div", "span", "h1", "h2", "script", "img", "table")


def html_tag_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load_table(spark, sf_dir, "pages")
    return d.select(F.col("page_id").alias("id"), F.array(*[F.regexp_count(F.coalesce("html", F.lit("")), F.lit(f"<{t}[ >]")).cast("double") for t in TAGS]).alias("x"))


def lineitem_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, x): four standardised measures of every line item; the volume stream."""
    d = load_table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id"), "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    return standardise(d, ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]).select("id", "x")
