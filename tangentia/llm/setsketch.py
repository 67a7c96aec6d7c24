"""Near-duplicate groups from SetSketch registers.

A register holds the truncated, exponentially spaced minimum of its own hash over a document's shingles: a larger value
for a smaller minimum, so sketches of parts merge by the larger value, and two registers are equal with about the
similarity of the sets. Documents that agree on a band of registers are candidates. How many registers are larger, smaller and
equal gives the likelihood of each similarity (set sizes are known), and candidates are dropped only where the
threshold is far less likely than the best value. What stays is confirmed on the full shingle sets.

Documents with the same set are one class and are compared once. Within a bucket of many members not all pairs are
tried: a pivot for each bucket links most of them. Members of buckets that still hold different components are then
joined exactly by a prefix filter: with shingles in the order of how many of these members have them, two sets that are
similar enough share one among the first few of each. A copy's own edits come first in that order, so copies
that are too far from each other never meet, and no link that could join two groups is left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tangentia.llm import textkit
from tangentia.operators.graph import connected_components
from tangentia.session import materialise, ship_package

BANDS, BAND_ROWS = 52, 6  # sets with a similarity of 0.8 share no band once in 7 million pairs, with 0.2 they share one in 300
REGISTERS = BANDS * BAND_ROWS
SPACING = 1.001  # ratio of neighbouring register boundaries
RATE = 20.0
TOP = 2**16 - 2
DROP_LIKELIHOOD = 16.0  # log likelihood that the threshold must lose to the best value
BROADCAST_IDS = 2_000_000

_random = np.random.Generator(np.random.PCG64(20240229))
_FACTOR = _random.integers(0, 2**31, REGISTERS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_SHIFT = _random.integers(0, 2**32, REGISTERS, dtype=np.uint32)


def registers_of(least: np.ndarray) -> np.ndarray:
    """Register values of 32-bit minima: exponential variates of the given rate, in steps of the spacing."""
    uniform = (least.astype(np.float64) + 0.5) * 2.0**-32
    exponential = -np.log1p(-uniform) / RATE
    return np.clip(np.floor(1 - np.log(exponential) / np.log(SPACING)), 0, TOP + 1).astype(np.uint16)


def sketch_sets(sets: list[np.ndarray]) -> np.ndarray:
    """(sets, registers) of non-empty sets."""
    everything = np.concatenate(sets)
    first = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    folded = (everything ^ (everything >> np.uint64(32))).astype(np.uint32)
    least, own = np.empty((REGISTERS, len(sets)), np.uint32), np.empty_like(folded)
    for r in range(REGISTERS):
        np.multiply(folded, _FACTOR[r], out=own)
        own += _SHIFT[r]
        least[r] = np.minimum.reduceat(own, first)
    return registers_of(least.T)


def set_key(sets: list[np.ndarray]) -> list[bytes]:
    """128 bits that name a set."""
    everything = np.concatenate(sets)
    first = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    a = np.add.reduceat(everything, first)
    b = np.add.reduceat(textkit.mix(everything ^ np.uint64(0x5851F42D4C957F2D)), first)
    return [x.tobytes() + y.tobytes() for x, y in zip(a, b, strict=True)]


def _sketch_batches(width: int):
    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, offs = textkit.text_buffer(batch.column(1))
            n = np.zeros(len(offs) - 1, np.int64)
            keys: list = [None] * len(n)
            sketches: list = [None] * len(n)
            for i, _, b, o in textkit.runs(buf, offs):
                sets = textkit.shingle_sets(b, o, width)
                full = [k for k, s in enumerate(sets) if len(s)]
                if full:
                    own = [sets[k] for k in full]
                    for k, key, regs in zip(full, set_key(own), sketch_sets(own), strict=True):
                        n[i + k], keys[i + k], sketches[i + k] = len(sets[k]), key, regs.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), pa.array(keys, pa.binary()), pa.array(sketches, pa.binary())], ["doc_id", "n", "key", "sketch"])
        textkit.tidy()

    return sketch


def log_likelihood(similarity: np.ndarray, n_a: np.ndarray, n_b: np.ndarray, more: np.ndarray, less: np.ndarray) -> np.ndarray:
    """Log likelihood of each similarity, given how many of a's registers are larger and smaller than b's.

    With shares u and v of the two sizes, a's register is larger with probability p(u - v J), smaller with p(v - u J),
    where p(x) = -log_base(1 - x (base - 1) / base).
    """
    u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
    p = lambda x: np.clip(-np.log1p(-np.clip(x, 0, 1) * (SPACING - 1) / SPACING) / np.log(SPACING), 1e-9, 1.0)
    up, down = p(u - v * similarity), p(v - u * similarity)
    return more * np.log(up) + less * np.log(down) + (REGISTERS - more - less) * np.log(np.clip(1 - up - down, 1e-9, 1.0))


def _estimate_batches(percent: int):
    grid = np.linspace(0, 1, 101)

    def estimate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            n_a, n_b = (batch.column(k).to_numpy(zero_copy_only=False).astype(float) for k in (2, 3))
            a, b = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint16).reshape(-1, REGISTERS) for k in (4, 5))
            more, less = (a > b).sum(1).astype(float), (a < b).sum(1).astype(float)
            at = log_likelihood(np.full(len(n_a), percent / 100), n_a, n_b, more, less)
            best, where = np.full(len(n_a), -np.inf), np.zeros(len(n_a))
            for j in grid:
                possible = j <= np.minimum(n_a, n_b) / np.maximum(n_a, n_b)
                ll = np.where(possible, log_likelihood(np.full(len(n_a), j), n_a, n_b, more, less), -np.inf)
                where, best = np.where(ll > best, j, where), np.maximum(best, ll)
            keep = (where >= percent / 100) | (best - at <= DROP_LIKELIHOOD)
            yield pa.RecordBatch.from_arrays([batch.column(k).filter(pa.array(keep)) for k in (0, 1)], ["a", "b"])

    return estimate


def _verify_batches(width: int, percent: int):
    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            step = 256
            for i in range(0, batch.num_rows, step):
                part = batch.slice(i, step)
                sets = []
                for k in (2, 3):
                    buf, offs = textkit.text_buffer(part.column(k))
                    sets.append([s for *_, b, o in textkit.runs(buf, offs) for s in textkit.shingle_sets(b, o, width)])
                for k, (x, y) in enumerate(zip(*sets, strict=True)):
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    keep[i + k] = common > 0 and 100 * common >= percent * (len(x) + len(y) - common)
            yield pa.RecordBatch.from_arrays([batch.column(k).filter(pa.array(keep)) for k in (0, 1)], ["a", "b"])
        textkit.tidy()

    return verify


def _set_batches(width: int):
    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, offs = textkit.text_buffer(batch.column(1))
            for i, j, b, o in textkit.runs(buf, offs):
                own = textkit.shingle_sets(b, o, width)
                flat = np.concatenate(own).view(np.int64)
                offsets = np.concatenate([[0], np.cumsum([len(s) for s in own])]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], ["id", "shingles"])
        textkit.tidy()

    return sets


def _broadcast_if_small(ids: DataFrame) -> DataFrame:
    return F.broadcast(ids) if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else ids


def _ties(named: DataFrame, classes: DataFrame) -> tuple[DataFrame | None, DataFrame | None]:
    """((doc_id) of ids with different texts, links (a, b) between the classes that such an id ties together); None where there is none."""
    several = materialise(named.groupBy("doc_id").agg(F.min("key").alias("k0"), F.max("key").alias("k1")).where("k0 <> k1").select("doc_id"), "repeated-ids")
    if several.isEmpty():
        return None, None
    own = named.join(several, "doc_id", "left_semi").select("doc_id", "key", "n").distinct().join(classes.select("key", "n", "id"), ["key", "n"]).select("doc_id", "id").distinct()
    # the id is itself a member of its classes, so each is tied to it or to the class' least id
    return several, materialise(own.where("id <> doc_id").select(F.col("id").alias("a"), F.col("doc_id").alias("b")).distinct(), "ties")


class _Linker:
    """Tests pairs of classes: estimate on sketches, then confirm on texts."""

    def __init__(self, docs: DataFrame, classes: DataFrame, width: int, percent: int):
        self.docs, self.classes, self.width, self.percent = docs, classes, width, percent

    def links(self, pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) whose full sets are similar enough."""
        side = lambda x: self.classes.select(F.col("id").alias(x), F.col("n").alias(f"n_{x}"), F.col("sketch").alias(f"sketch_{x}"))
        p = pairs.join(side("b"), "b").join(side("a"), "a")
        p = p.where(100 * F.least("n_a", "n_b") >= self.percent * F.greatest("n_a", "n_b"))
        p = p.select("a", "b", "n_a", "n_b", "sketch_a", "sketch_b").mapInArrow(_estimate_batches(self.percent), "a long, b long")
        likely = materialise(p, "likely-pairs")
        ids = likely.select(F.explode(F.array("a", "b")).alias("id")).distinct()
        texts = materialise(self.docs.join(_broadcast_if_small(ids), "id", "left_semi"), "pair-texts")
        side = lambda x: texts.select(F.col("id").alias(x), F.col("text").alias(f"text_{x}"))
        q = likely.join(side("b"), "b").join(side("a"), "a").select("a", "b", "text_a", "text_b")
        return materialise(q.mapInArrow(_verify_batches(self.width, self.percent), "a long, b long").distinct(), "links")


    def prefixes(self, loose: DataFrame, several: DataFrame | None) -> DataFrame:
        """(id, n, c, shingle, place): the first shingles of each set, rarest among ``loose`` first, one of which any similar enough set has among its own first.

        A set of n shares at least percent * n / 100 shingles with such a set, so the first n - that + 1 will do. Shingles
        of one set only can't be shared; they take their places and need no row. An id of ``several`` texts brings
        the shingles of all of them, each in the first place: which set a shingle is of does not matter there.
        """
        ids = _broadcast_if_small(loose.select("id").distinct())
        texts = self.docs.join(ids, "id", "left_semi")
        sets = texts.select("id", "text").mapInArrow(_set_batches(self.width), "id long, shingles array<long>")
        each = materialise(sets.select("id", F.explode("shingles").alias("shingle")).distinct(), "loose-shingles")
        common = each.groupBy("shingle").count().where("count > 1")
        rows = each.join(common, "shingle").join(loose, "id")
        by_set = Window.partitionBy("id")
        rows = rows.withColumn("alone", F.col("n") - F.count(F.lit(1)).over(by_set))
        rows = rows.withColumn("place", F.col("alone") + F.row_number().over(by_set.orderBy("count", "shingle")))
        length = F.col("n") - F.ceil(F.col("n") * self.percent / 100) + 1
        if several is not None:
            rows = rows.join(several.select(F.col("doc_id").alias("id"), F.lit(True).alias("many")), "id", "left")
            rows = rows.withColumn("place", F.when(F.col("many"), F.lit(1)).otherwise(F.col("place")))
        return rows.where(F.col("place") <= length).select("id", "n", "c", "shingle", "place")


def near_duplicates(docs: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row.

    A-Z is lower-cased, words are parted by ASCII white space, a document's set is its distinct shingles of ``width``
    words; with fewer words the whole sequence is its one shingle. Documents with at least ``threshold`` (in whole
    per cent) similarity are linked; component_id is the least doc_id reached, kept marks it.
    Null and empty texts have the empty set and stay alone; rows that repeat a doc_id are one document, whose texts are all
    linked with each other and with what any of them is like; n_shingles is the row's own; a null doc_id stays alone with
    a null component and is kept; an empty table gives no rows; other columns are ignored.
    """
    ship_package(docs.sparkSession)
    percent = round(100 * threshold)
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    sketches = rows.mapInArrow(_sketch_batches(width), "doc_id long, n long, key binary, sketch binary")
    sketches = materialise(sketches, "sketches")
    named = sketches.where("n > 0 AND doc_id IS NOT NULL")
    classes = materialise(named.groupBy("key", "n").agg(F.min("doc_id").alias("id"), F.first("sketch").alias("sketch")), "classes")
    linker = _Linker(rows, classes, width, percent)
    several, ties = _ties(named, classes)

    bands = F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda k: F.xxhash64(k, F.substring(F.col("sketch"), k * (2 * BAND_ROWS) + 1, F.lit(2 * BAND_ROWS))))
    members = classes.select("id", "n", F.explode(bands).alias("bucket"))
    shared = members.groupBy("bucket").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high")
    members = materialise(members.join(shared.select("bucket", "low"), "bucket"), "bucket-members")
    pairs = members.where("id <> low").select(F.col("low").alias("a"), F.col("id").alias("b")).distinct()
    tried = materialise(pairs, "pairs")
    links = linker.links(tried)
    links = links if ties is None else links.unionByName(ties)
    groups = connected_components(links, "a", "b")

    # members of buckets whose members are still in different components
    placed = members.join(groups.withColumnRenamed("component", "c"), "id", "left").withColumn("c", F.coalesce("c", "id"))
    open_ = placed.groupBy("bucket").agg(F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 < c1").select("bucket")
    loose = materialise(placed.join(open_, "bucket").select("id", "n", "c").distinct(), "loose")
    ordered = [F.least("id", "pid").alias("a"), F.greatest("id", "pid").alias("b")]
    fits = (F.col("c") != F.col("pc")) & (100 * F.least("n", "pn") >= F.lit(percent) * F.greatest("n", "pn"))
    other = [F.col("id").alias("pid"), F.col("c").alias("pc"), F.col("n").alias("pn")]
    first = materialise(linker.prefixes(loose, several), "prefixes")
    # all that two sets can share if the shingle is their first in common; with enough of it they may be similar enough
    most = 1 + F.least(F.col("n") - F.col("place"), F.col("pn") - F.col("pplace"))
    enough = most * (100 + percent) >= F.lit(percent) * (F.col("n") + F.col("pn"))
    new = first.join(first.select("shingle", F.col("place").alias("pplace"), *other), "shingle").where((F.col("id") < F.col("pid")) & fits & enough).select(*ordered).distinct()
    new = materialise(new.join(tried, ["a", "b"], "left_anti"), "pairs")
    if not new.isEmpty() and not (found := linker.links(new)).isEmpty():
        groups = connected_components(links.unionByName(found), "a", "b")

    whole = classes.select("key", "n", F.col("id").alias("first")).join(groups.select(F.col("id").alias("first"), "component"), "first", "left")
    whole = whole.select("key", "n", F.coalesce("component", "first").alias("component"))
    by_id = named.join(whole, ["key", "n"]).groupBy("doc_id").agg(F.min("component").alias("component"))
    out = sketches.select("doc_id", "n").join(by_id, "doc_id", "left")
    out = out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one_of_each(docs: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """``docs`` without the documents of a group but one; of rows that repeat a doc_id, one stays (the least by text), as all others of that document are copies by its id."""
    found = near_duplicates(docs, width, threshold)
    dropped = found.where("NOT kept").select("doc_id").distinct()
    repeated = docs.groupBy("doc_id").count().where("count > 1 AND doc_id IS NOT NULL").select("doc_id")
    left = docs.join(dropped, "doc_id", "left_anti")
    if repeated.isEmpty():
        return left.select(docs.columns)
    fresh = "row"
    while fresh in docs.columns:
        fresh += "_"
    first = Window.partitionBy("doc_id").orderBy(F.xxhash64("text"), "text")
    once = left.join(repeated, "doc_id", "left_semi").withColumn(fresh, F.row_number().over(first)).where(F.col(fresh) == 1)
    return left.join(repeated, "doc_id", "left_anti").select(docs.columns).unionByName(once.select(docs.columns))
